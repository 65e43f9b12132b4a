"""Distributed training of four schemes on the same samples.

A sample is a block's mini-batch over one sequence: the targets of the batch and their (sampled) k-hop in-neighbours, over the
snapshots of the sequence and those that it predicts. A global step takes one chunk of consecutive sequences of every block,
of one batch. All schemes compute the same gradients; what differs is where the parts of a sample live and what moves:

* block: a block's rows lie on one machine, placed once, with copies of the snapshots that straddle blocks. A task takes the whole
  chunk, keeps its stores over the sequences, and only its summed gradient leaves.
* node_part: features lie with their nodes' owners. Each sample pulls the features it needs, for every snapshot and again for
  every sequence; every gate gathers anew.
* node_part_gate: the same, with one aggregate for all gates of a cell.
* seq_part: snapshots of one sequence lie on different machines. Stacked models shuffle the graph layers' output to the nodes'
  owners and the states back; integrated ones hand the state on from machine to machine, forth and back.

Gradients are summed within the task and then by (parameter, position) in the engine; one vector comes to the driver.
Rows that cross machines are counted while they are moved (`moved`: bytes of node vectors, 8 a value).
"""

from __future__ import annotations

import itertools
import json
import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from .nn import models, sweep
from .nn.models import Adam, Sample, Weights
from .nn.tape import Graph
from .operators import batches as mini
from .operators import placement
from .operators.sequences import count
from .operators.temporal import TemporalGraph, coded, expand
from .plans.reuse import ALL, MODELS, Flags
from .storage import shuffles_dropped, stored, temporary

SCHEMES = {"block": ALL, "node_part": Flags(False, False, False, False), "node_part_gate": Flags(False, True, False, False), "seq_part": Flags(False, False, False, False)}
PART = "name string, i int, g double"
#: Edges of one packed row.
PACKED = 1 << 14
#: Vectors of one packed row.
VECTORS = 1 << 8


@dataclass(frozen=True)
class Job:
    """Settings of a run. `capacity`: entries of the global store, None without bound."""

    model: str = "int_conv_gru"
    scheme: str = "block"
    epochs: int = 2
    hidden: int = 8
    length: int = 8
    machines: int = 2
    batches: int = 2
    chunks: int = 2
    fanouts: tuple[int, ...] | None = (25, 10)
    rate: float = 1e-2
    seed: int = 7
    held_out: float = 0.2
    order: str = "seq_first"
    capacity: int | None = None
    policy: str = "lookahead"
    flags: Flags | None = None

    @property
    def reuse(self) -> Flags:
        return self.flags or SCHEMES[self.scheme]

    @property
    def extra(self) -> int:
        """Snapshots beyond a sequence's own that it reads or predicts."""
        return 2 if MODELS[self.model].decoder else 1


@dataclass
class Samples:
    """rows(block, batch_id, t, kind, a, b, n, lanes, src, dst): edges 'e' (many in a row, both ends squeezed into src) and features 'f' (of a; b 1 for targets, n targets in the batch)."""

    rows: DataFrame
    plan: list[tuple[int, int, int]]  # (q, block, chunk); chunk -1: held out
    lanes: tuple[str, ...]
    scale: np.ndarray
    moved: dict[str, int] = field(default_factory=dict)
    placed: DataFrame | None = None  # by block, where jobs share it

    def chunk(self, chunk: int) -> dict[int, list[int]]:
        out: dict[int, list[int]] = {}
        for q, b, c in self.plan:
            if c == chunk:
                out.setdefault(b, []).append(q)
        return out


def schedule(snapshots: int, job: Job) -> list[tuple[int, int, int]]:
    """(q, block, chunk) of every sequence; the last share of the sequences is held out (chunk -1). As long as the snapshots are many, not the data."""
    n = count(snapshots, job.length, 1, job.extra)
    train = max(1, int(n * (1 - job.held_out)))
    out = []
    for q in range(n):
        block = q * job.machines // n
        mine = [x for x in range(train) if x * job.machines // n == block]
        out.append((q, block, (q - mine[0]) * job.chunks // len(mine) if q < train else -1))
    return out


def pack(edges: DataFrame) -> DataFrame:
    """(batch_id, t, src, dst) with some PACKED edges of one batch and snapshot in a row, squeezed into src."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}

        def row(key: tuple) -> pa.RecordBatch:
            ends = sweep.put_edges(*(np.concatenate(x) for x in zip(*held.pop(key))))
            return pa.RecordBatch.from_arrays([pa.array([int(k)], pa.int32()) for k in key] + [pa.array([x], pa.binary()) for x in (ends, None)], ["batch_id", "t", "src", "dst"])

        for rb in batches:
            batch, t, src, dst = (rb.column(k).to_numpy() for k in ("batch_id", "t", "src", "dst"))
            order = np.lexsort((t, batch))
            batch, t, src, dst = batch[order], t[order], src[order], dst[order]
            cuts = np.flatnonzero((batch[1:] != batch[:-1]) | (t[1:] != t[:-1])) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(t)]):
                if hi > lo:
                    mine = held.setdefault(key := (batch[lo], t[lo]), [])
                    mine.append((src[lo:hi], dst[lo:hi]))
                    if sum(len(x) for x, _ in mine) >= PACKED:
                        yield row(key)
        for key in list(held):
            yield row(key)

    return edges.select("batch_id", "t", "src", "dst").mapInArrow(run, "batch_id int, t int, src binary, dst binary")


def bundled(rows: DataFrame, keys: list[str], lanes: tuple[str, ...]) -> DataFrame:
    """The rows with the features of one key and snapshot, as far as they meet in a partition, some PACKED in a row."""
    names, by = rows.columns, [*keys, "t"]
    schema = to_arrow_schema(rows.schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}

        def row(key: tuple, n: int) -> pa.RecordBatch:
            src, dst = sweep.put_features(*(np.concatenate(x) for x in zip(*held.pop((key, n)))))
            values = dict(zip(by, key)) | {"kind": "f", "a": 0, "b": 0, "n": n, "src": src, "dst": dst} | dict.fromkeys(lanes, 0.0)
            return pa.RecordBatch.from_arrays([pa.array([values[x]], schema.field(x).type) for x in names], names)

        for rb in batches:
            cols = {k: rb.column(k).to_numpy() for k in (*by, "a", "b", "n", *lanes)}
            order = np.lexsort([cols["a"], *(cols[k] for k in (*by, "n"))])
            cols = {k: v[order] for k, v in cols.items()}
            cuts = np.flatnonzero(np.any([cols[k][1:] != cols[k][:-1] for k in (*by, "n")], axis=0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, rb.num_rows]):
                if hi > lo:
                    at = tuple(int(cols[k][lo]) for k in by), int(cols["n"][lo])
                    mine = held.setdefault(at, [])
                    mine.append((cols["a"][lo:hi], cols["b"][lo:hi], np.column_stack([cols[k][lo:hi] for k in lanes])))
                    if sum(len(x) for x, _, _ in mine) >= PACKED:
                        yield row(*at)
        for at in list(held):
            yield row(*at)

    return rows.filter("kind = 'f'").mapInArrow(run, rows.schema).unionByName(rows.filter("kind = 'e'"))


def streamed(rows: DataFrame, keys: list[str], run: Callable[[tuple, Sample, int, sweep.Shelf], Iterator[pa.RecordBatch]], lanes: tuple[str, ...], scale: np.ndarray, job: Job, schema: str) -> DataFrame:
    """`run` on the sample of each key. The rows of a key lie together as `in_order` leaves them; they are read as a stream into files of the task, never held at once."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, parts in itertools.groupby(sweep.slices(batches, keys), lambda x: x[0]):
            edges, work = sweep.Shelf(), sweep.Shelf()
            try:
                sample, n = sweep.shelved((rb for _, rb in parts), lanes, scale, edges, job.capacity, job.policy)
                pa.default_memory_pool().release_unused()
                yield from run(key, sample, n, work)
            finally:
                edges.close()
                work.close()

    return rows.mapInArrow(each, schema)


def in_order(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Within its partition each key's features before its edges, which come by snapshot."""
    return rows.sortWithinPartitions(*keys, F.desc("kind"), "t")


def samples(graph: TemporalGraph, job: Job) -> Samples:
    """Computation graphs and features of all batches, placed by block once."""
    spark = graph.edges.sparkSession
    plan = schedule(graph.snapshots, job)
    need = spark.createDataFrame(sorted({(b, t) for q, b, _ in plan for t in range(q, q + job.length + job.extra)}), "block int, t int")
    batch = stored(mini.sampler(graph.nodes, job.batches))
    size = batch.groupBy("batch_id").agg(F.count(F.lit(1)).cast("int").alias("n"))
    hops = stored(mini.khop(graph, batch, 2, job.fanouts).select("batch_id", "t", "src", "dst").distinct())
    spans = batch.select("batch_id", F.explode(F.sequence(F.lit(0), F.lit(graph.snapshots - 1))).alias("t"), "node", F.lit(1).cast("long").alias("b"))
    nodes = hops.select("batch_id", "t", F.col("src").alias("node"), F.lit(0).cast("long").alias("b")).union(spans)
    nodes = nodes.groupBy("batch_id", "t", "node").agg(F.max("b").alias("b")).join(size, "batch_id")
    lanes = [F.coalesce(F.col(x).cast("double"), F.lit(0.0)).alias(x) for x in graph.lanes]
    f = nodes.join(expand(graph.feats), ["t", "node"], "left").select("batch_id", "t", F.lit("f").alias("kind"), F.col("node").alias("a"), "b", "n", *lanes, *[F.lit(None).cast("binary").alias(x) for x in ("src", "dst")])
    none = F.lit(0).cast("long")
    e = pack(hops).select("batch_id", "t", F.lit("e").alias("kind"), none.alias("a"), none.alias("b"), F.lit(0).alias("n"), *[F.lit(0.0).alias(x) for x in graph.lanes], "src", "dst")
    rows = stored(e.unionByName(f).join(F.broadcast(need), "t").select("block", "batch_id", "t", "kind", "a", "b", "n", *graph.lanes, "src", "dst"))
    top = graph.feats.agg(*[F.max(x) for x in graph.lanes]).first()
    return Samples(rows, plan, graph.lanes, np.array([max(1.0, float(x or 0)) for x in top]))


def unpack(pdf: pd.DataFrame, lanes: tuple[str, ...], scale: np.ndarray, job: Job, nodes: np.ndarray | None = None) -> tuple[Sample, np.ndarray, int]:
    """A sample from its rows, its nodes in order, and the number of targets; nodes are numbered within the sample."""
    edge = (pdf["kind"] == "e").to_numpy()
    a, b, t = pdf["a"].to_numpy(), pdf["b"].to_numpy(), pdf["t"].to_numpy()
    if nodes is None:
        nodes = np.unique(a[~edge])  # every end of an edge has features
    values = pdf[list(lanes)].to_numpy()
    ends = [pdf[k].to_numpy() for k in ("src", "dst")]
    graphs, feats, none = {}, {}, np.zeros(0, dtype=np.int64)
    for at in np.unique(t):
        e = np.flatnonzero(edge & (t == at))
        pairs = [sweep.edge_ends(x, y) for x, y in zip(*(x[e] for x in ends))]
        src, dst = (np.searchsorted(nodes, np.concatenate([none, *x])) for x in (zip(*pairs) if pairs else ((), ())))
        order = np.lexsort((src, dst))
        src, dst = src[order], dst[order]
        degree = np.bincount(dst, minlength=len(nodes))
        graphs[int(at)] = Graph(src, dst, np.ones(len(src)), len(nodes), 1 / np.maximum(1, degree))
        f = np.flatnonzero(~edge & (t == at))
        x = np.zeros((len(nodes), len(lanes)))
        x[np.searchsorted(nodes, a[f])] = values[f]
        feats[int(at)] = x
    wanted = np.searchsorted(nodes, np.unique(a[~edge & (b == 1)]))
    n = int(pdf["n"].max()) if len(pdf) else 0
    return Sample(graphs, feats, wanted, scale, job.capacity, job.policy), nodes, n


def _parts(grads: Weights, loss: float, stats: dict[str, float] | None = None) -> pd.DataFrame:
    names, places, values = ["loss"], [np.zeros(1, dtype=np.int32)], [np.array([loss])]
    for k, v in (stats or {}).items():
        names.append(f"stat:{k}")
        places.append(np.zeros(1, dtype=np.int32))
        values.append(np.array([float(v)]))
    for k in sorted(grads):
        names += [k] * grads[k].size
        places.append(np.arange(grads[k].size, dtype=np.int32))
        values.append(grads[k].ravel())
    return pd.DataFrame({"name": names, "i": np.concatenate(places), "g": np.concatenate(values)})


def sync_gradients(parts: DataFrame, like: Weights) -> tuple[Weights, float, dict[str, float]]:
    """Sums (name, i, g) in the engine, partial sums first; one vector, the loss and the counters come back."""
    out, loss, stats = {k: np.zeros(v.size) for k, v in like.items()}, 0.0, {}
    with shuffles_dropped(parts.sparkSession):
        summed = parts.groupBy("name", "i").agg(F.sum("g").alias("g")).collect()
    for r in summed:
        if r["name"] == "loss":
            loss = r["g"]
        elif r["name"].startswith("stat:"):
            stats[r["name"][5:]] = r["g"]
        else:
            out[r["name"]][r["i"]] = r["g"]
    return {k: v.reshape(like[k].shape) for k, v in out.items()}, loss, stats


def _counters(s: Sample) -> Weights:
    return {"stat:passes": np.array([s.passes()], dtype=float), "stat:messages": np.array([s.messages()], dtype=float)}


class Scheme:
    """One way to spread the samples; `step` gives the summed gradients and loss of one chunk of one batch, `test` the held-out error."""

    def __init__(self, s: Samples, job: Job, graph: TemporalGraph):
        self.s, self.job, self.graph, self.spark = s, job, graph, s.rows.sparkSession

    def sequences(self, chunk: int) -> DataFrame:
        """(block, q, t) of a chunk, t over all snapshots that a sequence reads or predicts."""
        span = self.job.length + self.job.extra
        return self.spark.createDataFrame([(b, q, q + i) for b, qs in self.s.chunk(chunk).items() for q in qs for i in range(span)], "block int, q int, t int")

    def parts(self, w: Weights, batch: int, chunk: int, learn: bool) -> DataFrame:
        raise NotImplementedError

    def close(self) -> None:
        """Frees what the scheme holds."""

    def step(self, w: Weights, batch: int, chunk: int, learn: bool = True) -> tuple[Weights, float, dict[str, float]]:
        return sync_gradients(self.parts(w, batch, chunk, learn), w)


def _whole(sample: Sample, qs: list[int], w: Weights, job: Job, n: int, learn: bool, work: sweep.Shelf) -> Iterator[pa.RecordBatch]:
    """Loss and gradients of whole sequences, in order, through one pair of stores."""
    flags, cells = job.reuse, max(1, n * next(iter(sample.feats.values())).shape[1])
    sequences = [list(range(q, q + job.length)) for q in qs]
    sample.expect(job.model, sequences, flags)
    loss, grads = 0.0, {}
    for at, times in enumerate(sequences):
        ends = models.targets(job.model, times)

        def seen(i: int, y: np.ndarray, ends: list[int] = ends) -> np.ndarray:
            nonlocal loss
            d = y - sample.x(ends[i])[sample.targets]
            loss += np.abs(d).sum() / (cells * len(ends))
            return np.sign(d) / (cells * len(ends))

        for k, v in sweep.sweep(job.model, sample, at, times, w, job.hidden, flags, seen, work, learn).items():
            grads[k] = grads.get(k, 0) + v
    g, local = sample.global_store, sample.local_store
    stats = {"passes": sample.passes(), "messages": sample.messages(), "hits": g.hits, "misses": g.misses, "local_hits": local.hits, "peak_bytes": g.peak_bytes + local.peak_bytes}
    yield pa.RecordBatch.from_pandas(_parts(grads, loss, stats), preserve_index=False)


def place(s: Samples, job: Job) -> DataFrame:
    """The blocks' rows, each block's on one machine, kept there until they are unpersisted."""
    rows = bundled(s.rows, ["block", "batch_id"], s.lanes)
    placed = in_order(rows.repartitionById(job.machines, F.col("block")), ["block", "batch_id"]).persist()  # the one shuffle of the job; steps read in place
    placed.count()  # once filled, its partitioning is known to the planner
    return placed


class Block(Scheme):
    def __init__(self, s: Samples, job: Job, graph: TemporalGraph):
        super().__init__(s, job, graph)
        self.placed = s.placed or place(s, job)
        s.moved.update(features=0, states=0)

    def close(self) -> None:
        if not self.s.placed:
            self.placed.unpersist()

    def parts(self, w: Weights, batch: int, chunk: int, learn: bool) -> DataFrame:
        job, lanes, scale, mine = self.job, self.s.lanes, self.s.scale, self.s.chunk(chunk)
        span = job.length + job.extra
        times = {b: (min(qs), max(qs) + span) for b, qs in mine.items()}
        where = [(F.col("block") == b) & F.col("t").between(lo, hi - 1) for b, (lo, hi) in times.items()]
        any_of: Column = where[0]
        for x in where[1:]:
            any_of = any_of | x

        def run(key: tuple, sample: Sample, n: int, work: sweep.Shelf) -> Iterator[pa.RecordBatch]:
            return _whole(sample, mine[int(key[0])], w, job, n, learn, work)

        return streamed(self.placed.filter((F.col("batch_id") == batch) & any_of), ["block"], run, lanes, scale, job, PART)


class NodePart(Scheme):
    """Sample (batch, q) runs on machine (q * batches + batch) mod M; a feature row is pulled from machine node mod M."""

    def __init__(self, s: Samples, job: Job, graph: TemporalGraph):
        super().__init__(s, job, graph)
        features = expand(graph.feats).select("t", F.col("node").alias("a"), *[F.col(x).cast("double").alias(x) for x in graph.lanes])
        self.features = stored(features.withColumn("owner", F.pmod("a", F.lit(job.machines)).cast("int")))
        s.moved.update(features=0, states=0)

    def parts(self, w: Weights, batch: int, chunk: int, learn: bool) -> DataFrame:
        job, lanes, scale = self.job, self.s.lanes, self.s.scale
        here = self.s.rows.filter(F.col("batch_id") == batch).join(F.broadcast(self.sequences(chunk)), ["block", "t"])
        here = here.withColumn("machine", F.pmod(F.col("q") * job.batches + batch, F.lit(job.machines)).cast("int"))
        columns = ["machine", "q", "t", "kind", "a", "b", "n"]
        pulled = here.filter("kind = 'f'").drop(*lanes).join(self.features, ["t", "a"], "left")
        seen = Observation()
        far = F.sum(F.when(F.col("owner") != F.col("machine"), 8 * len(lanes)).otherwise(0))
        pulled = pulled.observe(seen, F.coalesce(far, F.lit(0)).alias("bytes"))
        pulled = pulled.select(*columns, *[F.coalesce(F.col(x), F.lit(0.0)).alias(x) for x in lanes], "src", "dst")
        # written, so that what was pulled is counted once and survives a lost executor
        rows = stored(bundled(pulled, ["machine", "q"], lanes)).unionByName(here.filter("kind = 'e'").select(*columns, *lanes, "src", "dst"))
        self.s.moved["features"] += seen.get["bytes"]

        def run(key: tuple, sample: Sample, n: int, work: sweep.Shelf) -> Iterator[pa.RecordBatch]:
            return _whole(sample, [int(key[1])], w, job, n, learn, work)

        keys = ["machine", "q"]
        return streamed(in_order(rows.repartition(*keys), keys), keys, run, lanes, scale, job, PART)


VECTOR_ROWS = "what string, q int, idx int, owner int, layer int, node binary, v binary"


def vector_rows(what: str, q: int, idx: int, layer: int, nodes: np.ndarray, x: np.ndarray, machines: int = 1) -> pd.DataFrame:
    """The vectors of nodes as bytes, those of one owner (node mod machines) together, up to VECTORS in a row."""
    rows = []
    for owner in range(machines):
        mine = np.flatnonzero(nodes % machines == owner)
        for lo in range(0, len(mine), VECTORS):
            k = mine[lo : lo + VECTORS]
            rows.append((what, q, idx, owner, layer, nodes[k].astype("<i8").tobytes(), x[k].astype("<f8").tobytes()))
    return pd.DataFrame(rows, columns=["what", "q", "idx", "owner", "layer", "node", "v"])


def grad_rows(q: int, grads: Weights, loss: float | None = None) -> pd.DataFrame:
    some = {f"g:{k}": v for k, v in grads.items()} | ({"loss": np.array([loss])} if loss is not None else {})
    return pd.DataFrame([(k, q, 0, 0, 0, b"", v.astype("<f8").tobytes()) for k, v in some.items()], columns=["what", "q", "idx", "owner", "layer", "node", "v"])


def ends(packed: pd.Series) -> np.ndarray:
    return np.frombuffer(b"".join(packed), dtype="<i8")


def values_of(packed: pd.Series, rows: int, width: int) -> np.ndarray:
    return np.frombuffer(b"".join(packed), dtype="<f8").reshape(rows, width)


def vectors(pdf: pd.DataFrame, nodes: np.ndarray, width: int) -> np.ndarray:
    """What the packed rows hold of `nodes`, in their order; zeros where they hold nothing."""
    x = np.zeros((len(nodes), width))
    if len(pdf) and len(nodes):
        ids = ends(pdf["node"])
        at = np.minimum(np.searchsorted(nodes, ids), len(nodes) - 1)
        good = nodes[at] == ids
        x[at[good]] = values_of(pdf["v"], len(ids), width)[good]
    return x


def pack_features(rows: DataFrame, lanes: tuple[str, ...]) -> DataFrame:
    """(block, batch_id, t, kind, n, src, dst, v): of features up to VECTORS in a row, nodes in src, whether they are targets in dst, values in v; edges as they are."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for (block, batch, t), mine in pdf.groupby(["block", "batch_id", "t"]):
                x = mine[list(lanes)].to_numpy()
                a, b, out = mine["a"].to_numpy(), mine["b"].to_numpy(), []
                for lo in range(0, len(a), VECTORS):
                    k = slice(lo, lo + VECTORS)
                    out.append((block, batch, t, "f", int(mine["n"].iloc[0]), a[k].astype("<i8").tobytes(), b[k].astype("<i8").tobytes(), x[k].astype("<f8").tobytes()))
                yield pd.DataFrame(out, columns=["block", "batch_id", "t", "kind", "n", "src", "dst", "v"])

    f = rows.filter("kind = 'f'").select("block", "batch_id", "t", "a", "b", "n", *lanes)
    # of one snapshot together, or its rows would hold few
    f = f.repartition("block", "batch_id", "t").sortWithinPartitions("block", "batch_id", "t")
    f = f.mapInPandas(run, "block int, batch_id int, t int, kind string, n int, src binary, dst binary, v binary")
    return f.unionByName(rows.filter("kind = 'e'").select("block", "batch_id", "t", "kind", "n", "src", "dst", F.lit(None).cast("binary").alias("v")))


def loose(pdf: pd.DataFrame, lanes: tuple[str, ...]) -> pd.DataFrame:
    """Rows as `unpack` takes them, from those of `pack_features`."""
    f = (pdf["kind"] == "f").to_numpy()
    few, edges = pdf[f], pdf[~f]
    a, size = ends(few["src"]), few["src"].map(len).to_numpy(dtype=np.int64) // 8
    x = values_of(few["v"], len(a), len(lanes))
    one = pd.DataFrame({"kind": "f", "t": np.repeat(few["t"].to_numpy(), size), "a": a, "b": ends(few["dst"]), "n": np.repeat(few["n"].to_numpy(), size), **{k: x[:, i] for i, k in enumerate(lanes)}, "src": None, "dst": None})
    rest = edges.assign(a=0, b=0, **{k: 0.0 for k in lanes})[list(one.columns)]
    return pd.concat([one, rest], ignore_index=True) if len(rest) and len(one) else one if len(one) else rest


class SeqPart(Scheme):
    """Snapshot i of a sequence lies on machine floor((i - 1) * M / L), node v's states on machine v mod M."""

    def __init__(self, s: Samples, job: Job, graph: TemporalGraph):
        super().__init__(s, job, graph)
        self.rows = stored(pack_features(s.rows, s.lanes))
        s.moved.update(features=0, states=0)

    def machine(self, idx: Column) -> Column:
        return F.floor((idx - 1) * self.job.machines / self.job.length).cast("int")

    def kept(self, df: DataFrame, apart: Column | None = None) -> DataFrame:
        """The rows written down; those that cross machines (`apart`) are counted on the way."""
        if apart is None:
            return stored(df)
        seen = Observation()
        bytes_ = F.sum(F.when(apart & F.col("what").isin("u", "h", "du", "dh", "state", "dstate"), F.length("v")).otherwise(0))
        out = stored(df.observe(seen, F.coalesce(bytes_, F.lit(0)).alias("bytes")))
        self.s.moved["states"] += int(seen.get["bytes"])
        return out

    def parts(self, w: Weights, batch: int, chunk: int, learn: bool) -> DataFrame:
        seqs = F.broadcast(self.sequences(chunk))
        rows = self.rows.filter(F.col("batch_id") == batch).join(seqs, ["block", "t"]).drop("block", "batch_id")
        return (self._integrated if MODELS[self.job.model].decoder else self._stacked)(w, rows, learn)

    def _gradient_parts(self, tables: list[DataFrame]) -> DataFrame:
        out = None
        for t in tables:
            one = t.filter("what like 'g:%' or what = 'loss'").select("what", "v")
            out = one if out is None else out.unionByName(one)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in frames:
                for what, v in zip(pdf["what"], pdf["v"]):
                    g = np.frombuffer(v, dtype="<f8")
                    yield pd.DataFrame({"name": what.removeprefix("g:"), "i": np.arange(len(g), dtype=np.int32), "g": g})

        return out.mapInPandas(run, PART)

    # stacked models

    def _stacked(self, w: Weights, rows: DataFrame, learn: bool) -> DataFrame:
        job, lanes, scale, name = self.job, self.s.lanes, self.s.scale, self.job.model
        layers, length, machines = MODELS[name].layers, job.length, job.machines
        rows = stored(rows.withColumn("idx", (F.col("t") - F.col("q") + 1).cast("int")))
        own = rows.filter(F.col("idx") <= length)
        # what the last snapshot's successors hold is predicted where the nodes' states lie
        apart = self.machine(F.col("idx")) != F.col("owner")

        def wanted(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in frames:
                for r in pdf.itertuples():
                    hit = np.frombuffer(r.dst, dtype="<i8") == 1
                    nodes = np.frombuffer(r.src, dtype="<i8")[hit]
                    yield vector_rows("y", r.q, r.idx, r.n, nodes, np.frombuffer(r.v, dtype="<f8").reshape(len(hit), -1)[hit] / scale, machines)

        truth = rows.filter((F.col("idx") == length + 1) & (F.col("kind") == "f")).mapInPandas(wanted, VECTOR_ROWS)

        def tables(pdf: pd.DataFrame) -> tuple[Sample, np.ndarray]:
            s, nodes, _ = unpack(loose(pdf, lanes), lanes, scale, job)
            return s, nodes

        def conv(layer: int, back: bool):
            def run(key: tuple, snap: pd.DataFrame, given: pd.DataFrame) -> pd.DataFrame:
                q, idx = int(key[0]), int(key[1])
                if not len(snap):
                    return vector_rows("u", q, idx, layer, np.zeros(0, dtype=np.int64), np.zeros((0, 1)), machines)
                s, mine = tables(snap)
                t = q + idx - 1
                hs = given[given["what"] == "h"]
                nodes = mine if layer == 0 else np.unique(np.r_[mine, ends(hs["node"])])
                if layer:
                    s, _, _ = unpack(loose(snap, lanes), lanes, scale, job, nodes)
                x = s.x(t) if layer == 0 else vectors(hs, nodes, job.hidden)
                if not back:
                    u, _ = models.conv_piece(name, layer, s.graphs[t], x, w)
                    return pd.concat([vector_rows("u", q, idx, layer, nodes, u, machines), grad_rows(q, _counters(s))])
                width = job.hidden + (x.shape[1] if name == "stk_skip_lstm" else 0)
                dx, grads = models.conv_piece(name, layer, s.graphs[t], x, w, vectors(given[given["what"] == "du"], nodes, width))
                parts = [grad_rows(q, grads)]
                if layer:
                    parts.append(vector_rows("dh", q, idx, layer - 1, nodes, dx, machines))
                return pd.concat(parts)

            return run

        def cell(layer: int, back: bool):
            last = layer == layers - 1

            def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
                q = int(key[0])
                us = pdf[pdf["what"] == "u"]
                nodes = np.unique(ends(us["node"]))
                width = job.hidden + ((len(lanes) if layer == 0 else job.hidden) if name == "stk_skip_lstm" else 0)
                x = [vectors(us[us["idx"] == i], nodes, width) for i in range(1, length + 1)]
                if last:
                    t = pdf[pdf["what"] == "y"]
                    at, cells = np.searchsorted(nodes, ends(t["node"])), max(1, int(t["layer"].max()) * len(lanes)) if len(t) else 1
                    values = values_of(t["v"], len(at), len(lanes))
                else:
                    d = pdf[pdf["what"] == "dh"]
                    ups = [vectors(d[d["idx"] == i], nodes, job.hidden) for i in range(1, length + 1)] if back else None
                forward = not back and not last
                made = [np.zeros((len(nodes), job.hidden if forward else width)) for _ in x]
                grads, loss = {}, 0.0
                for lo in range(0, len(nodes), sweep.ROWS):  # nodes don't meet here
                    hi = lo + sweep.ROWS
                    up, y = [u[lo:hi] for u in ups] if back and not last else None, None
                    if last:
                        mine = (at >= lo) & (at < hi)
                        y = values[mine], at[mine] - lo, cells
                    out, some, l = models.cell_piece(layer, [u[lo:hi] for u in x], w, job.hidden, up, y)
                    for whole, o in zip(made, out):
                        whole[lo:hi] = o
                    grads, loss = {k: grads.get(k, 0) + v for k, v in some.items()}, loss + l
                if forward:
                    return pd.concat([vector_rows("h", q, i + 1, layer, nodes, h, machines) for i, h in enumerate(made)])
                parts = [grad_rows(q, grads if learn else {}, loss if last else None)]
                if learn:
                    parts += [vector_rows("du", q, i + 1, layer, nodes, d, machines) for i, d in enumerate(made)]
                return pd.concat(parts)

            return run

        empty = self.spark.createDataFrame([], VECTOR_ROWS)
        at_snapshot = lambda given, layer, back: own.groupBy("q", "idx").cogroup(given.groupBy("q", "idx")).applyInPandas(conv(layer, back), VECTOR_ROWS)
        at_owner = lambda given, layer, back: given.groupBy("q", "owner").applyInPandas(cell(layer, back), VECTOR_ROWS)
        us, hs, grads = [], [], []
        below = empty
        for layer in range(layers):
            made = self.kept(at_snapshot(below, layer, False), apart)
            grads.append(made)
            us.append(made.filter("what = 'u'"))
            if layer < layers - 1:
                below = self.kept(at_owner(us[-1], layer, False), apart)
                hs.append(below)
        up = truth
        for layer in reversed(range(layers)):
            down = self.kept(at_owner(us[layer].unionByName(up), layer, True), apart)
            grads.append(down)
            if not learn:
                break
            given = down.filter("what = 'du'")
            up = self.kept(at_snapshot(given.unionByName(hs[layer - 1]) if layer else given, layer, True), apart)
            grads.append(up)
            up = up.filter("what = 'dh'")
        return self._gradient_parts(grads)

    # integrated models

    def _integrated(self, w: Weights, rows: DataFrame, learn: bool) -> DataFrame:
        job, lanes, scale, name = self.job, self.s.lanes, self.s.scale, self.job.model
        length, hidden, layers = job.length, job.hidden, MODELS[name].layers
        runs: list[list[int]] = []
        for i in range(length):
            m = i * job.machines // length
            if not runs or runs[-1][0] * job.machines // length != m:
                runs.append([])
            runs[-1].append(i)
        stages = [("enc", r) for r in runs] + [("dec", r) for r in runs]
        rows = stored(rows)
        both = 2 if MODELS[name].gates == 4 else 1  # a GRU hands on one vector a layer
        cells = length * len(lanes)

        def piece(part: str, idx: list[int], back: bool):
            def run(key: tuple, snap: pd.DataFrame, given: pd.DataFrame) -> pd.DataFrame:
                q = int(key[0])
                states = given[given["what"] == "state"]
                nodes = np.unique(ends(states["node"]))
                s, _, n = unpack(loose(snap, lanes), lanes, scale, job, nodes)
                times = [q + i + (part == "dec") for i in idx]

                def pairs(rows: pd.DataFrame) -> list[sweep.Pair]:
                    x = [vectors(rows[rows["layer"] == layer], nodes, both * hidden) for layer in range(layers)]
                    return [(v[:, :hidden], v[:, hidden:] if both == 2 else None) for v in x]

                up, work = pairs(given[given["what"] == "dstate"]) if back else None, sweep.Shelf()
                came, grads, loss = sweep.piece(name, s, part, times, w, pairs(states), job.reuse, work, up, max(1, n * cells))
                work.close()
                what = "dstate" if back else "state"
                out = [vector_rows(what, q, 0, layer, nodes, np.hstack([h, c][:both])) for layer, (h, c) in enumerate(came)]
                out.append(grad_rows(q, grads if back else _counters(s), loss if part == "dec" and (back or not learn) else None))
                return pd.concat(out)

            return run

        def snapshots(part: str, idx: list[int]) -> DataFrame:
            lo, hi = idx[0] + (part == "dec"), idx[-1] + (2 if part == "dec" else 0)
            return rows.filter((F.col("t") >= F.col("q") + lo) & (F.col("t") <= F.col("q") + hi))

        def begin(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
            nodes = np.unique(ends(pdf["src"]))
            return pd.concat([vector_rows("state", int(key[0]), 0, layer, nodes, np.zeros((len(nodes), hidden * both))) for layer in range(layers)])

        zero = rows.filter("kind = 'f'").select("q", "src").groupBy("q").applyInPandas(begin, VECTOR_ROWS)
        states, grads = [stored(zero)], []
        home = [i % len(runs) for i in range(len(stages))]
        for i, (part, idx) in enumerate(stages):
            out = snapshots(part, idx).groupBy("q").cogroup(states[-1].groupBy("q")).applyInPandas(piece(part, idx, False), VECTOR_ROWS)
            turn = i + 1 < len(stages) and home[i] != home[i + 1]
            made = self.kept(out, F.lit(turn))
            grads.append(made)
            states.append(made.filter("what = 'state'"))
        if learn:
            up = self.spark.createDataFrame([], VECTOR_ROWS)
            for i in reversed(range(len(stages))):
                part, idx = stages[i]
                out = snapshots(part, idx).groupBy("q").cogroup(states[i].unionByName(up).groupBy("q")).applyInPandas(piece(part, idx, True), VECTOR_ROWS)
                kept = self.kept(out, F.lit(i > 0 and home[i] != home[i - 1]))
                grads.append(kept)
                up = kept.filter("what = 'dstate'")
        return self._gradient_parts(grads)


KINDS = {"block": Block, "node_part": NodePart, "node_part_gate": NodePart, "seq_part": SeqPart}


def drawn_by(job: Job) -> tuple:
    """What the samples of a job depend on; jobs that agree in it can share them."""
    return job.batches, job.chunks, job.fanouts, job.length, job.extra, job.machines, job.held_out


#: Fits that `fit_all` runs side by side where it may.
ABREAST = 16


def fit_all(graph: TemporalGraph, jobs: list[Job], abreast: int = 1) -> Iterator[tuple[Job, Weights, list[dict]]]:
    """`fit` of each job, in the order given; samples are drawn, and placed by block, once for all jobs that agree in what they depend on.

    Up to `abreast` jobs are in work at a time: a step has a task per block only, and jobs don't wait for each other. Their seconds are then no measure."""
    spark = graph.edges.sparkSession
    with temporary(spark):
        graph = coded(graph)
        drawn: dict[tuple, Samples] = {}

        def made(job: Job) -> Samples:
            if drawn_by(job) not in drawn:
                drawn[drawn_by(job)] = samples(graph, job)
            s = drawn[drawn_by(job)]
            if job.scheme == "block" and not s.placed:
                s.placed = place(s, job)
            return Samples(s.rows, s.plan, s.lanes, s.scale, placed=s.placed if job.scheme == "block" else None)

        try:
            if abreast == 1:
                for job in jobs:
                    yield job, *fit(graph, job, drawn=made(job))
            else:
                with ThreadPoolExecutor(abreast) as pool:
                    for job, done in [(job, pool.submit(fit, graph, job, drawn=made(job))) for job in jobs]:
                        yield job, *done.result()
        finally:
            for s in drawn.values():
                if s.placed:
                    s.placed.unpersist()


def fit(graph: TemporalGraph, job: Job = Job(), keep: str | None = None, drawn: Samples | None = None) -> tuple[Weights, list[dict]]:
    """Synchronous training; each global step sums the gradients of one chunk of one batch over all blocks. With `keep`, a checkpoint is written after each epoch and the last one found there is resumed. `drawn`: the job's samples, if they are there already.

    The curve holds for each epoch: train_mae, test_mae, seconds and samples of the training steps, bytes moved so far, and the counters of the graph layers and stores."""
    spark = graph.edges.sparkSession
    with temporary(spark):
        return _fit(spark, graph if drawn else coded(graph), job, keep, drawn)


def _fit(spark: SparkSession, graph: TemporalGraph, job: Job, keep: str | None, drawn: Samples | None = None) -> tuple[Weights, list[dict]]:
    s = drawn or samples(graph, job)
    scheme = KINDS[job.scheme](s, job, graph)
    w = models.init(job.model, len(s.lanes), job.hidden, job.seed)
    opt, curve, first = Adam(w, job.rate), [], 0
    if keep and (found := latest(spark, keep)) is not None:
        first, w, opt, curve = resume(spark, keep, found, job.rate)
    held = sum(c < 0 for _, _, c in s.plan)
    steps = [(b, c) for b in range(job.batches) for c in range(job.chunks)]
    if job.order == "node_first":
        steps.sort(key=lambda x: (x[1], x[0]))
    for epoch in range(first, job.epochs):
        losses, stats, began = 0.0, {}, time.perf_counter()
        for b, c in steps:
            with temporary(spark):
                n = sum(map(len, s.chunk(c).values()))
                grads, loss, counted = scheme.step(w, b, c)
            opt.step(w, {k: g / n for k, g in grads.items()})
            losses += loss / n
            stats = {k: stats.get(k, 0) + v for k, v in counted.items()}
        seconds, moved = time.perf_counter() - began, dict(s.moved)  # the test's own pulls aren't part of an epoch
        with temporary(spark):
            test = sum(scheme.step(w, b, -1, learn=False)[1] for b in range(job.batches)) / (held * job.batches) if held else 0.0
        s.moved.update(moved)
        made = (len(s.plan) - held) * job.batches
        curve.append({"scheme": job.scheme, "model": job.model, "epoch": epoch, "train_mae": losses / len(steps), "test_mae": test, "seconds": seconds, "samples": made, "moved": sum(moved.values()), **stats})
        if keep:
            checkpoint(spark, keep, w, epoch + 1, opt, curve)
    scheme.close()
    return w, curve


def checkpoint(spark: SparkSession, path: str, w: Weights, step: int, opt: Adam | None = None, curve: list[dict] | None = None) -> None:
    """One row per parameter, the optimizer's moments beside it; a step is a folder of its own, so a half-written one is never read."""
    flat = lambda x, k: x[k].ravel().tolist() if opt else None
    rows = [(k, json.dumps(list(v.shape)), v.ravel().tolist(), flat(opt.m, k) if opt else None, flat(opt.v, k) if opt else None, opt.t if opt else 0, json.dumps(curve or []), step) for k, v in w.items()]
    schema = "param string, shape string, value array<double>, m array<double>, v array<double>, turns int, curve string, step int"
    spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{path}/step={step:08d}")


def latest(spark: SparkSession, path: str) -> int | None:
    """The last step whose folder was written to its end."""
    hadoop = spark._jvm.org.apache.hadoop.fs
    base = hadoop.Path(path)
    fs = base.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(base):
        return None
    done = [f.getPath() for f in fs.listStatus(base) if f.getPath().getName().startswith("step=") and fs.exists(hadoop.Path(f.getPath(), "_SUCCESS"))]
    return max((int(p.getName()[5:]) for p in done), default=None)


def resume(spark: SparkSession, path: str, step: int, rate: float = 1e-2) -> tuple[int, Weights, Adam, list[dict]]:
    """Step, weights, optimizer and curve as they were."""
    rows = spark.read.parquet(f"{path}/step={step:08d}").collect()
    shaped = lambda r, c: np.array(r[c]).reshape(json.loads(r["shape"]))
    w = {r["param"]: shaped(r, "value") for r in rows}
    opt = Adam(w, rate)
    for r in rows:
        if r["m"] is not None:
            opt.m[r["param"]], opt.v[r["param"]], opt.t = shaped(r, "m"), shaped(r, "v"), r["turns"]
    return step, w, opt, json.loads(rows[0]["curve"]) if rows else []

