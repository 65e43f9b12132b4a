"""Look-ahead cache of aggregates: access trace, scores, policies, and the store used while training."""

from __future__ import annotations

from collections import OrderedDict, defaultdict

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .sequences import count, seq2seq
from .temporal import TemporalGraph, expand

SIZE = 16
#: Positions of a trace in one range of a running sum.
RANGE = 1 << 20


def trace(spark: SparkSession, snapshots: int, length: int = 8, stride: int = 1, gates: int = 4, order: str = "seq_first", batches: int = 1, layers: int = 1) -> DataFrame:
    """Accesses of the graph layers, in order: pos, batch_id, q, part, layer, idx, gate, kind, t, key. Each gate reads the input's aggregate and the hidden state's; inputs of layer 1 are keyed by snapshot, all else by its cell."""
    s = seq2seq(spark, snapshots, length, stride)
    s = s.withColumn("batch_id", F.explode(F.sequence(F.lit(0), F.lit(batches - 1)))).withColumn("layer", F.explode(F.sequence(F.lit(1), F.lit(layers))))
    s = s.withColumn("gate", F.explode(F.sequence(F.lit(1), F.lit(gates)))).withColumn("kind", F.explode(F.array(F.lit("input"), F.lit("hidden"))))
    cell = F.concat_ws(":", "kind", "batch_id", "q", "part", "layer", "idx")
    key = F.when((F.col("kind") == "input") & (F.col("layer") == 1), F.concat_ws(":", F.lit("x"), "batch_id", "t")).otherwise(cell)
    n = count(snapshots, length, stride, stride)
    outer = F.col("batch_id") * n + F.col("q") if order == "seq_first" else F.col("q") * batches + F.col("batch_id")
    # 'enc' before 'dec', a layer after the one below, the input before the hidden state: places follow without a sort
    pos = outer.cast("long") * 2 + F.when(F.col("part") == "dec", 1).otherwise(0)
    pos = ((pos * layers + F.col("layer") - 1) * length + F.col("idx") - 1) * gates + F.col("gate") - 1
    pos = pos * 2 + F.when(F.col("kind") == "hidden", 1).otherwise(0)
    return s.withColumn("key", key).select(pos.cast("long").alias("pos"), "batch_id", "q", "part", "layer", "idx", "gate", "kind", "t", "key")


def future_count(part: str, idx: Column, stride: int, gates: int, gate: Column) -> Column:
    """Remaining reads of a layer-1 input by the published closed form (exact for stride 1)."""
    low, shift = (1, 1) if part == "enc" else (2, 2)
    return F.greatest(F.lit(low), 2 * idx - 2 * stride + shift) * gates - gate


def trace_batches(accesses: DataFrame) -> DataFrame:
    """Accesses by batch, for traces too long for one simulator: batches share no key."""
    return accesses.groupBy("batch_id").agg(F.count(F.lit(1)).alias("accesses"), F.count_distinct("key").alias("entries"))


def future_count_upper(gates: int, gate: Column) -> Column:
    """Of layers above the first, and of hidden aggregates: the gates still to come."""
    return F.lit(gates) - gate


def future_count_exact(part: str, idx: Column, stride: int, gates: int, gate: Column) -> Column:
    """Remaining reads by enumeration of the sequences that still hold the snapshot."""
    turns = F.floor((idx - 1) / stride)
    return ((2 * turns + (1 if part == "enc" else 2)) * gates - gate).cast("int")


def imminence(where: str, length: int, stride: int) -> int:
    return {"local": 0, "enc": length - stride, "dec": length - 1}[where]


def priority(future: Column, size: float, imminent: Column) -> Column:
    return future / F.lit(float(size)) - imminent


def scores(spark: SparkSession, length: int = 8, stride: int = 1, gates: int = 4, policy: str = "formula") -> DataFrame:
    """part, idx, gate, future, imminence, score of every layer-1 input."""
    grid = spark.range(1, length + 1).select(F.col("id").cast("int").alias("idx")).withColumn("gate", F.explode(F.sequence(F.lit(1), F.lit(gates))))
    count = future_count if policy == "formula" else future_count_exact
    one = lambda p: grid.select(F.lit(p).alias("part"), "idx", "gate", count(p, F.col("idx"), stride, gates, F.col("gate")).cast("int").alias("future"), F.lit(imminence(p, length, stride)).alias("imminence"))
    both = one("enc").union(one("dec"))
    return both.withColumn("score", priority(F.col("future"), SIZE, F.col("imminence")))


class Store:
    """In-task cache. Expired entries leave at once; else the lowest score leaves first. Sizes are relative to the mean entry's; `capacity` is their sum."""

    def __init__(self, capacity: float, policy: str = "lookahead"):
        self.capacity, self.policy, self.held = capacity, policy, OrderedDict()
        self.sizes: dict = {}
        self.uses: dict = defaultdict(int)
        self.clock, self.age = 0, {}

    def access(self, key, future: int = 0, imminent: float = 0.0, next_use: float = float("inf"), size: float = 1.0) -> bool:
        hit = key in self.held
        self.uses[key] += 1
        if self.policy in ("lookahead", "optimum") and future <= 0:  # no read to come
            self.held.pop(key, None)
            self.sizes.pop(key, None)
            return hit
        if self.policy == "lookahead":
            score = future / (SIZE * size) - imminent
        elif self.policy == "optimum":
            score = -next_use
        elif self.policy == "lfu":
            score = self.uses[key]
        elif self.policy == "freq_size_age":
            score = self.clock + self.uses[key] / (SIZE * size)
        else:
            score = 0
        if hit:
            self.held.move_to_end(key)
            self.held[key] = score
            return True
        self.held[key] = score
        self.sizes[key] = size
        while sum(self.sizes.values()) > self.capacity:
            victim = next(iter(self.held)) if self.policy == "lru" else min(self.held, key=self.held.get)
            if self.policy == "freq_size_age":
                self.clock = self.held[victim]
            del self.held[victim], self.sizes[victim]
            if self.policy == "lfu":
                self.uses[victim] = 0
        return False


class GlobalStore:
    """Values of input aggregates under a capacity (entries; None: unbounded), for layers, sequences, parts and the next snapshot's deltas.

    Who leaves is the policy's choice; entries without a read to come leave at once, except the newest one of each gate, where
    the next snapshot's deltas start from it. Keys begin with the gate. Sizes are counted in bytes."""

    def __init__(self, capacity: int | None = None, policy: str = "lookahead"):
        self.store = Store(1 << 60 if capacity is None else capacity, policy)
        self.values: dict = {}
        self.newest: dict = {}
        self.hits = self.misses = self.bytes = self.peak_bytes = 0

    def peek(self, key):
        if key in self.values:
            return self.values[key]
        last = self.newest.get(key[0])
        return last[1] if last is not None and last[0] == key else None

    def get(self, key, future: int, imminent: float, make, keep_newest: bool = False):
        held = self.values.get(key)
        value = make() if held is None else held
        self.hits += held is not None
        self.misses += held is None
        self.store.access(key, future, imminent)
        if key in self.store.held:
            self.values[key] = value
        for gone in [k for k in self.values if k not in self.store.held]:
            del self.values[gone]
        if keep_newest:
            self.newest[key[0]] = (key, value)
        self.bytes = sum(v.nbytes for v in self.values.values()) + sum(v.nbytes for k, v in self.newest.values() if k not in self.values)
        self.peak_bytes = max(self.peak_bytes, self.bytes)
        return value


class LocalStore:
    """The aggregates of one cell's operands, read by all its gates; emptied when the next cell opens."""

    def __init__(self):
        self.values: dict = {}
        self.hits = self.misses = self.peak_bytes = 0

    def open(self) -> None:
        self.values.clear()

    def get(self, key, make):
        if key in self.values:
            self.hits += 1
        else:
            self.misses += 1
            self.values[key] = make()
            self.peak_bytes = max(self.peak_bytes, sum(v.value.nbytes for v in self.values.values()))
        return self.values[key]


POLICIES = ("lookahead", "lru", "lfu", "freq_size_age", "optimum")


def replay(rows: list[tuple], policy: str, capacity: float, length: int, stride: int, gates: int) -> dict:
    """Hits of one policy over (key, kind, part, gate[, size]) rows, over all, repeated and input accesses."""
    store, left, seen, places = Store(capacity, policy), defaultdict(int), set(), defaultdict(list)
    for i, r in enumerate(rows):
        left[r[0]] += 1
        places[r[0]].append(i)
    turn: dict = defaultdict(int)
    hits = repeat = hit_repeat = inputs = hit_inputs = 0
    for key, kind, part, gate, *size in rows:
        left[key] -= 1
        turn[key] += 1
        nxt = places[key][turn[key]] if turn[key] < len(places[key]) else float("inf")
        wait = 0 if gate < gates or kind == "hidden" else imminence(part, length, stride)
        hit = store.access(key, left[key], wait, nxt, *size)
        hits += hit
        if key in seen:
            repeat += 1
            hit_repeat += hit
        seen.add(key)
        if kind == "input":
            inputs += 1
            hit_inputs += hit
    return {"accesses": len(rows), "hits_all": hits / max(1, len(rows)), "hits_repeated": hit_repeat / max(1, repeat), "hits_input": hit_inputs / max(1, inputs)}


def with_cells(accesses: DataFrame, rows: DataFrame, lanes: int = 2, hidden: int = 64) -> DataFrame:
    """The trace with the cells of each aggregate: `rows` (targets by t, or by batch and t; 1 where there are none) by lanes, or by the hidden size."""
    keys = [c for c in ("batch_id", "t") if c in rows.columns]
    width = F.when(F.col("kind") == "hidden", hidden).otherwise(lanes)
    return accesses.join(F.broadcast(rows), keys, "left").withColumn("cells", F.coalesce("rows", F.lit(1)) * width).drop("rows")


def relative(sized: DataFrame) -> DataFrame:
    """The cells as sizes relative to the mean entry's."""
    mean = sized.select("key", "cells").distinct().agg(F.avg("cells").alias("mean"))
    return sized.join(F.broadcast(mean)).withColumn("size", F.col("cells") / F.col("mean")).drop("cells", "mean")


def with_sizes(accesses: DataFrame, graph: TemporalGraph, hidden: int = 64) -> DataFrame:
    """The trace with the size of each aggregate of a graph, relative to the mean."""
    rows = expand(graph.edges).groupBy("t").agg(F.count_distinct("dst").alias("rows"))
    return relative(with_cells(accesses, rows, len(graph.lanes), hidden))


def sized_scores(table: DataFrame, rows: DataFrame) -> DataFrame:
    """The scores of every snapshot's aggregates: their size is the snapshot's targets, relative to the mean snapshot's."""
    mean = rows.agg(F.avg("rows").alias("mean"))
    size = F.lit(float(SIZE)) * F.col("rows") / F.col("mean")
    return table.drop("score").join(F.broadcast(rows.select("t", "rows").join(mean))).withColumn("score", F.col("future") / size - F.col("imminence")).drop("mean")


def simulate(accesses: DataFrame, cases: list[tuple[str, float]], length: int = 8, stride: int = 1, gates: int = 4) -> DataFrame:
    """policy, capacity and hit rates: one group per case, sequential inside, parallel across."""
    spark = accesses.sparkSession
    todo = spark.createDataFrame([(p, float(c)) for p, c in cases], "policy string, capacity double")
    columns = ["key", "kind", "part", "gate", *(["size"] if "size" in accesses.columns else [])]
    rows = accesses.select("pos", *columns).join(F.broadcast(todo))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        p, c = pdf["policy"].iloc[0], float(pdf["capacity"].iloc[0])
        ordered = pdf.sort_values("pos")[columns].itertuples(index=False, name=None)
        return pd.DataFrame([{"policy": p, "capacity": c} | replay(list(ordered), p, c, length, stride, gates)])

    return rows.groupBy("policy", "capacity").applyInPandas(run, "policy string, capacity double, accesses long, hits_all double, hits_repeated double, hits_input double")


def memory(accesses: DataFrame) -> DataFrame:
    """Peak number of live aggregates, or of their cells where the trace has them: kept to the end of the run, and dropped after their last read."""
    held = F.max("cells") if "cells" in accesses.columns else F.lit(1)
    life = accesses.groupBy("key").agg(F.min("pos").alias("born"), F.max("pos").alias("last"), held.alias("held"))
    steps = life.select(F.col("born").alias("pos"), F.col("held").alias("d")).union(life.select(F.col("last") + 1, -F.col("held"))).groupBy("pos").agg(F.sum("d").alias("d"))
    # running sums by ranges of positions: each range within a task, then the ranges before it
    steps = steps.withColumn("range", F.floor(F.col("pos") / RANGE))
    whole = steps.groupBy("range").agg(F.sum("d").alias("whole"))
    earlier = whole.select("range", F.coalesce(F.sum("whole").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("earlier"))
    own = F.sum("d").over(Window.partitionBy("range").orderBy("pos"))
    live = steps.withColumn("own", own).join(F.broadcast(earlier), "range").select((F.col("own") + F.col("earlier")).alias("live"))
    kept = life.agg(F.sum("held").cast("long").alias("kept_all"))
    return live.agg(F.max("live").alias("peak_with_expiry")).join(kept).select("kept_all", "peak_with_expiry", (1 - F.col("peak_with_expiry") / F.col("kept_all")).alias("saving"))
