"""Communication, aggregation work and other measures, by counting."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.reuse import Flags, ModelShape, passes
from . import delta, placement
from .sequences import count, seq2seq, windows
from .temporal import TemporalGraph, expand

BYTES = 8


def _visits(seqs: DataFrame) -> DataFrame:
    return seqs.groupBy("t").agg(F.count(F.lit(1)).alias("visits"))


def comm_node_part(graph: TemporalGraph, machines: int, length: int = 8, stride: int = 1, hidden: int = 64, hops: int = 2) -> DataFrame:
    """Features, and hidden states for each further hop, of remote sources, pulled again for every sequence that holds the snapshot."""
    e = expand(graph.edges).select("t", "src", F.pmod("dst", F.lit(machines)).alias("machine")).filter(F.pmod("src", F.lit(machines)) != F.col("machine"))
    remote = e.groupBy("t").agg(F.count_distinct("machine", "src").alias("remote"))
    seqs = _visits(windows(e.sparkSession, graph.snapshots, length, stride))
    width = len(graph.lanes) + hidden * (hops - 1)
    total = remote.join(F.broadcast(seqs), "t").agg(F.coalesce(F.sum(F.col("remote") * F.col("visits")), F.lit(0)).alias("n"))
    return total.select(F.lit(machines).alias("machines"), (F.col("n") * width * BYTES).alias("bytes"))


def comm_seq_part(graph: TemporalGraph, machines: int, length: int = 8, stride: int = 1, hidden: int = 64, layers: int = 2, integrated: bool = False) -> DataFrame:
    """Hidden states moved from the machine of a step to the owner of the node, forward and again for gradients; an integrated cell also hands its state over where the machine changes."""
    spark = graph.nodes.sparkSession
    owners = placement.nodes(graph.nodes, machines).groupBy(F.col("machine").alias("owner")).agg(F.count(F.lit(1)).alias("n"))
    steps = placement.sequence_steps(windows(spark, graph.snapshots, length, stride), length, machines).groupBy("machine").agg(F.count(F.lit(1)).alias("steps"))
    moved = steps.join(owners, F.col("machine") != F.col("owner")).agg(F.coalesce(F.sum(F.col("steps") * F.col("n")), F.lit(0)).alias("moved"))
    changes = windows(spark, graph.snapshots, length, stride).filter(f"idx > 1 and floor((idx - 1) * {machines} / {length}) <> floor((idx - 2) * {machines} / {length})").agg(F.count(F.lit(1)).alias("changes"))
    every = graph.nodes.agg(F.count(F.lit(1)).alias("nodes"))
    extra = F.col("changes") * F.col("nodes") if integrated else F.lit(0)
    return moved.join(changes).join(every).select(F.lit(machines).alias("machines"), ((F.col("moved") + extra) * (hidden * layers * 2 * BYTES)).alias("bytes"))


def comm_block(graph: TemporalGraph, machines: int, length: int = 8, stride: int = 1, overlap: bool = True) -> DataFrame:
    """Nothing moves if copies are kept; else each fetched snapshot's edges (two ids) and features."""
    spark = graph.nodes.sparkSession
    if overlap:
        seqs = placement.sequence_blocks(spark, graph.snapshots, machines, length, stride).select("block", F.explode(F.sequence("first_t", "last_t")).alias("t"))
        lacking = seqs.join(placement.overlapped(spark, graph.snapshots, machines, length, stride), ["block", "t"], "left_anti")
    else:
        lacking = placement.on_demand(spark, graph.snapshots, machines, length, stride)
    sizes = delta.snapshot_sizes(graph).join(graph.nodes.agg(F.count(F.lit(1)).alias("nodes"))).select("t", (F.col("n_edges") * 2 + F.col("nodes") * len(graph.lanes)).alias("cells"))
    return lacking.select("block", "t").distinct().join(sizes, "t").agg(F.coalesce(F.sum(F.col("cells") * BYTES), F.lit(0)).cast("long").alias("bytes")).select(F.lit(machines).alias("machines"), "bytes")


def cut(graph: TemporalGraph, owners: DataFrame, machines: int) -> DataFrame:
    """Per snapshot the share of needed (machine, source) pairs that are remote; nodes without an owner are hashed."""
    own = lambda side: owners.select(F.col("node").alias(side), F.col("machine").alias(f"m_{side}"))
    e = expand(graph.edges).select("t", "src", "dst").join(own("src"), "src", "left").join(own("dst"), "dst", "left")
    e = e.select("t", "src", F.coalesce("m_src", F.pmod("src", F.lit(machines)).cast("int")).alias("ms"), F.coalesce("m_dst", F.pmod("dst", F.lit(machines)).cast("int")).alias("md")).distinct()
    return e.groupBy("t").agg(F.avg((F.col("ms") != F.col("md")).cast("double")).alias("remote_share"))


def work(graph: TemporalGraph, model: ModelShape, flags: Flags, length: int = 8, stride: int = 1) -> DataFrame:
    """Messages that all graph passes of one epoch gather: layer 1's inputs, and everything else."""
    spark = graph.nodes.sparkSession
    seqs = seq2seq(spark, graph.snapshots, length, stride) if model.decoder else windows(spark, graph.snapshots, length, stride)
    p = passes(model, flags.gates)
    sizes = delta.snapshot_sizes(graph)
    moved = delta.ratio(graph).select("t", (F.col("n_minus") + F.col("n_plus")).alias("moved"))
    cost = sizes.join(moved, "t", "left").select("t", "n_edges", F.when(F.lit(flags.incremental), F.least(F.coalesce("moved", F.col("n_edges")), F.col("n_edges"))).otherwise(F.col("n_edges")).alias("first_cost"))
    keys = {(True, True): ["t"], (True, False): ["part", "t"], (False, True): ["q", "t"], (False, False): ["q", "part", "idx", "t"]}
    inputs = seqs.select(*keys[flags.sequences, flags.teacher]).distinct()
    first = inputs.join(cost, "t").agg(F.sum("first_cost").alias("f"))
    all_visits = seqs.join(cost, "t").agg(F.sum("n_edges").alias("v"))
    rest = (model.layers - 1) * p["input"] + model.layers * p["hidden"]
    return first.join(all_visits).select(F.lit(model.name).alias("model"), (F.col("f") * p["input"]).alias("first_inputs"), (F.col("v") * rest).alias("rest"), (F.col("f") * p["input"] + F.col("v") * rest).alias("messages"))


def degree(graph: TemporalGraph) -> DataFrame:
    """Edges, targets and mean in-degree per snapshot."""
    e = expand(graph.edges)
    return e.groupBy("t").agg(F.count(F.lit(1)).alias("n_edges"), F.count_distinct("dst").alias("targets")).withColumn("mean_degree", F.col("n_edges") / F.col("targets"))


@dataclass(frozen=True)
class Profile:
    """What the counts of a graph need: per snapshot its edges, delta edges and remote (machine, source) pairs; nodes per owner."""

    machines: int
    width: int
    edges: list[int]
    moved: list[int | None]
    remote: list[int]
    owners: list[int]

    @property
    def snapshots(self) -> int:
        return len(self.edges)

    def sequences(self, length: int, stride: int = 1, horizon: int = 0) -> int:
        return count(self.snapshots, length, stride, horizon)


def profile(graph: TemporalGraph, machines: int) -> Profile:
    """Counted in the engine; one row per snapshot, and one per machine, come back."""
    r = delta.ratio(graph).select("t", (F.col("n_minus") + F.col("n_plus")).alias("moved"))
    pairs = expand(graph.edges).select("t", "src", F.pmod("dst", F.lit(machines)).alias("machine")).filter(F.pmod("src", F.lit(machines)) != F.col("machine"))
    far = pairs.groupBy("t").agg(F.count_distinct("machine", "src").alias("remote"))
    rows = {x["t"]: x for x in delta.snapshot_sizes(graph).join(r, "t", "left").join(far, "t", "left").fillna(0, ["remote"]).collect()}
    own = {x["machine"]: x["count"] for x in placement.nodes(graph.nodes, machines).groupBy("machine").count().collect()}
    every = range(graph.snapshots)
    return Profile(machines, len(graph.lanes), [rows[t]["n_edges"] for t in every], [rows[t]["moved"] for t in every], [rows[t]["remote"] for t in every], [own.get(m, 0) for m in range(machines)])


def messages(p: Profile, model: ModelShape, flags: Flags, length: int = 8, stride: int = 1) -> tuple[int, int]:
    """Messages of layer 1's inputs, and of all graph passes of one epoch; the same counts as `work`."""
    n = p.sequences(length, stride, stride if model.decoder else 0)
    parts = (0, stride) if model.decoder else (0,)
    cost = [min(m, e) if flags.incremental and m is not None else e for m, e in zip(p.moved, p.edges)]
    seen: set[tuple] = set()
    first = every = 0
    for q in range(n):
        for part in parts:
            for i in range(length):
                t = q * stride + i + part
                every += p.edges[t]
                key = (None if flags.sequences else (q, i if not flags.teacher else None), None if flags.teacher else part, t)
                if key not in seen:
                    seen.add(key)
                    first += cost[t]
    k = passes(model, flags.gates)
    rest = (model.layers - 1) * k["input"] + model.layers * k["hidden"]
    return first * k["input"], first * k["input"] + every * rest


def scheme_bytes(p: Profile, model: ModelShape, scheme: str, length: int = 8, hidden: int = 64, width: int | None = None, layers: int = 2) -> int:
    """Bytes between machines of one epoch; gradients of weights, equal everywhere, aside."""
    n, machines = p.sequences(length), p.machines
    if scheme == "block":  # with copies of the straddling snapshots
        return 0
    if scheme.startswith("node_part"):
        visits = [sum(q <= t < q + length for q in range(max(0, t - length + 1), min(n, t + 1))) for t in range(p.snapshots)]
        return sum(r * v for r, v in zip(p.remote, visits)) * ((p.width if width is None else width) + hidden) * BYTES
    spread = [i * machines // length for i in range(length)]
    moved = n * sum(nodes for m in spread for owner, nodes in enumerate(p.owners) if owner != m)
    turns = n * sum(a != b for a, b in zip(spread, spread[1:])) * sum(p.owners) if model.decoder else 0
    return (moved + turns) * hidden * layers * 2 * BYTES


def epoch_time(run: Callable[[], object], repeats: int = 3) -> float:
    """Median seconds of warm runs."""
    run()
    took = []
    for _ in range(repeats):
        t = time.perf_counter()
        run()
        took.append(time.perf_counter() - t)
    return median(took)


def throughput(samples: int, seconds: float) -> float:
    return samples / seconds


def speedup(base: float, ours: float) -> float:
    return base / ours

