"""Neighbourhood aggregates per snapshot: from scratch, incrementally, and by the cheaper of both."""

from __future__ import annotations

from collections.abc import Callable
from heapq import heappop, heappush

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..storage import stored
from . import delta
from .temporal import TemporalGraph, at, coded, contributions, expand


#: So many rows of two numbers may be broadcast; beyond, they are joined by shuffle.
MAX_BROADCAST = 1_000_000


def by_target(graph: TemporalGraph) -> TemporalGraph:
    """The graph written once for sums at targets: edges of one target lie together, in order, so that partial sums are few before they are shuffled; a hub's are spread over as many partitions as their bytes ask for. Few features travel to the edges."""
    edges = stored(graph.edges.hint("rebalance", "dst").sortWithinPartitions("dst"))
    feats = stored(graph.feats)
    few = feats.count() <= MAX_BROADCAST
    return TemporalGraph(edges, F.broadcast(feats) if few else feats, graph.nodes, graph.snapshots, graph.lanes)


def _sums(lanes: tuple[str, ...], sign: Column | None = None) -> list[Column]:
    s = F.lit(1) if sign is None else sign
    return [F.sum(s).alias("cnt")] + [F.sum(s * F.col("w") * F.col(x)).alias(f"a{i}") for i, x in enumerate(lanes)]


def _mean(df: DataFrame, lanes: tuple[str, ...]) -> DataFrame:
    return df.select("t", "dst", "cnt", *[(F.col(f"a{i}") / F.col("cnt")).alias(f"a{i}") for i in range(len(lanes))])


def scratch(graph: TemporalGraph, fn: str = "sum") -> DataFrame:
    """t, dst, cnt, a0.. of every target with an in-edge: each snapshot gathered anew, partial sums before the shuffle."""
    if fn in ("max", "min"):
        return _extremes(expand(contributions(graph)), graph.lanes, fn, ["t", "dst"])
    out = expand(contributions(graph)).groupBy("t", "dst").agg(*_sums(graph.lanes))
    return _mean(out, graph.lanes) if fn == "mean" else out


def _dense(steps: DataFrame, lanes: tuple[str, ...], until: Column, keys: list[str]) -> DataFrame:
    """Running sums of signed changes per target, then one row for each snapshot they hold."""
    order = Window.partitionBy(*keys).orderBy("t")
    names = ["cnt", *[f"a{i}" for i in range(len(lanes))]]
    running = steps.select(*keys, "t", *[F.sum(c).over(order).alias(c) for c in names], F.coalesce(F.lead("t").over(order), until).alias("next"))
    return running.filter("cnt > 0 and next > t").select(F.explode(F.sequence(F.col("t").cast("int"), (F.col("next") - 1).cast("int"))).alias("t"), "dst", *names)


def incremental(graph: TemporalGraph, fn: str = "sum") -> DataFrame:
    """The same rows as `scratch`, from the first snapshot and the deltas alone: partial sums per (target, t), then running sums per target."""
    if fn in ("max", "min"):
        return extremal(graph, fn).drop("recomputed")
    out = _by_deltas(contributions(graph), graph.lanes, F.lit(graph.snapshots), ["dst"])
    return _mean(out, graph.lanes) if fn == "mean" else out


def _by_deltas(c: DataFrame, lanes: tuple[str, ...], until: Column, keys: list[str]) -> DataFrame:
    """Every contribution is read once and gives its arrival and, before `until`, its departure."""
    ends = F.explode(F.array(F.struct(F.col("valid_from").alias("t"), F.lit(1).alias("sign")), F.struct(F.col("valid_to").alias("t"), F.lit(-1).alias("sign")))).alias("end")
    steps = c.select(*keys, "w", *lanes, ends).filter(F.col("end.t") < until).select(*keys, "end.t", "end.sign", "w", *lanes)
    return _dense(steps.groupBy(*keys, "t").agg(*_sums(lanes, F.col("sign"))), lanes, until, keys)


def adaptive(graph: TemporalGraph, threshold: float = 0.5) -> DataFrame:
    """Sums where each snapshot whose change ratio exceeds the threshold starts anew; the others continue by deltas.

    The coded graph is written once and read for the ratios and for the sums. A contribution is cut at the segments it
    spans: their numbers are looked up at its two ends and lie side by side, so all joins are on equality, with one row per snapshot."""
    graph = coded(graph)
    seg = stored(delta.segments(graph, threshold))
    number = lambda at, name: seg.select(F.col("t").alias(at), F.col("segment").alias(name))
    bounds = seg.select("segment", "seg_from", "seg_to").distinct()
    c = contributions(graph).withColumn("last_t", F.col("valid_to") - 1)
    c = c.join(F.broadcast(number("valid_from", "first_seg")), "valid_from").join(F.broadcast(number("last_t", "last_seg")), "last_t")
    c = c.withColumn("segment", F.explode(F.sequence("first_seg", "last_seg"))).join(F.broadcast(bounds), "segment")
    c = c.withColumns({"valid_from": F.greatest("valid_from", "seg_from"), "valid_to": F.least("valid_to", "seg_to")})
    return _by_deltas(c, graph.lanes, F.col("seg_to"), ["dst", "segment", "seg_to"])


def step(previous: DataFrame, changes: DataFrame, lanes: tuple[str, ...]) -> DataFrame:
    """One snapshot further: the previous sums (dst, cnt, a0..) less the minus set's messages, plus the plus set's."""
    moved = changes.groupBy("dst").agg(*_sums(lanes, F.col("sign")))
    names = ["cnt", *[f"a{i}" for i in range(len(lanes))]]
    both = previous.select("dst", *names).unionByName(moved)
    return both.groupBy("dst").agg(*[F.sum(n).alias(n) for n in names]).filter("cnt > 0")


def _extremes(rows: DataFrame, lanes: tuple[str, ...], fn: str, keys: list[str]) -> DataFrame:
    """m0, e0, ..: the extreme message and the edge that supplies it; ties go to the smallest edge id."""
    out = []
    for i, x in enumerate(lanes):
        v = F.col("w") * F.col(x)
        pick = F.max(F.struct(v.alias("v"), (-F.col("edge_id")).alias("e"))) if fn == "max" else F.min(F.struct(v.alias("v"), F.col("edge_id").alias("e")))
        out += [pick["v"].alias(f"m{i}"), (-pick["e"] if fn == "max" else pick["e"]).alias(f"e{i}")]
    return rows.groupBy(*keys).agg(*out)


#: In-edges (stays) of one target that a single task scans; a target with more is cut by edge.
HUB = 100_000


def extremal(graph: TemporalGraph, fn: str = "max", hub: int = HUB) -> DataFrame:
    """Extremes by deltas. While no contributor of a target leaves, the old extreme is combined with the insertions; else the target alone is gathered anew, from the contributions still held. A target's changes are scanned in order, targets in parallel.

    The contributions of a target with more than `hub` in-edges are dealt by edge into pieces that are scanned apart; the pieces' extremes are then combined per snapshot.
    Columns t, dst, m0, e0, .., recomputed (lanes gathered anew at t, over the pieces).
    """
    lanes, last = graph.lanes, graph.snapshots
    c = contributions(graph).select("dst", "edge_id", "valid_from", "valid_to", *[(F.col("w") * F.col(x)).alias(x) for x in lanes])
    names = [f"{p}{i}" for i in range(len(lanes)) for p in "me"]
    side = -1 if fn == "max" else 1
    sizes = graph.edges.groupBy("dst").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > hub)
    pieces = stored(sizes.select("dst", F.ceil(F.col("n") / hub).cast("int").alias("pieces")))
    few = pieces.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST
    c = c.join(F.broadcast(pieces) if few else pieces, "dst", "left")
    c = c.withColumn("piece", F.pmod(F.xxhash64("edge_id"), F.coalesce("pieces", F.lit(1)))).drop("pieces")

    def scan(pdf: pd.DataFrame) -> pd.DataFrame:
        """Each lane keeps its held contributions in a heap; those that have left are taken off when they come to the top."""
        rows = list(pdf[["edge_id", "valid_from", "valid_to", *lanes]].itertuples(index=False, name=None))
        points = sorted({r[1] for r in rows} | {r[2] for r in rows if r[2] < last})
        rows.sort(key=lambda r: r[1])
        heaps: list[list] = [[] for _ in lanes]
        out, at = [], 0
        for p, t in enumerate(points):
            hit = 0
            for heap in heaps:
                if heap and heap[0][2] <= t:  # the contributor leaves
                    while heap and heap[0][2] <= t:
                        heappop(heap)
                    hit += 1
            while at < len(rows) and rows[at][1] == t:
                r = rows[at]
                for i, heap in enumerate(heaps):
                    heappush(heap, (side * r[3 + i], r[0], r[2]))
                at += 1
            if all(heaps):
                values = [x for heap in heaps for x in (side * heap[0][0], heap[0][1])]
                until = points[p + 1] if p + 1 < len(points) else last
                out.append((t, until, *values, hit))
        done = pd.DataFrame(out, columns=["t", "until", *names, "recomputed"])
        done.insert(2, "dst", pdf["dst"].iloc[0])
        return done

    schema = "t int, until int, dst long, " + ", ".join(f"{n} long" for n in names) + ", recomputed int"
    runs = c.groupBy("dst", "piece").applyInPandas(scan, schema)
    # one row per run leaves the task; snapshots are spread after it, and only a run's first is marked
    each = runs.withColumn("u", F.explode(F.sequence(F.col("t"), F.col("until") - 1)))
    each = each.select(F.col("u").alias("t"), "dst", *names, F.when(F.col("u") == F.col("t"), F.col("recomputed")).otherwise(0).alias("recomputed"))
    best = []
    for i in range(len(lanes)):
        pick = F.min(F.struct((side * F.col(f"m{i}")).alias("v"), F.col(f"e{i}").alias("e")))
        best += [(side * pick["v"]).alias(f"m{i}"), pick["e"].alias(f"e{i}")]
    whole = each.join(F.broadcast(pieces) if few else pieces, "dst", "left_semi").groupBy("t", "dst").agg(*best, F.sum("recomputed").cast("int").alias("recomputed"))
    return each.join(F.broadcast(pieces) if few else pieces, "dst", "left_anti").unionByName(whole)


def recompute_targets(graph: TemporalGraph, fn: str = "max") -> DataFrame:
    """t, dst, lane whose contributor at t-1 is in the minus set of t while the target still has in-edges."""
    was = scratch(graph, fn).withColumn("t", F.col("t") + 1)
    pairs = F.explode(F.array(*[F.struct(F.lit(i).alias("lane"), F.col(f"e{i}").alias("edge_id")) for i in range(len(graph.lanes))])).alias("p")
    minus = delta.build(graph).filter("sign < 0").select("t", "dst", "edge_id")
    still = expand(graph.edges).select("t", "dst").distinct()
    return was.select("t", "dst", pairs).select("t", "dst", "p.lane", "p.edge_id").join(minus, ["t", "dst", "edge_id"], "left_semi").join(still, ["t", "dst"], "left_semi").select("t", "dst", "lane")


def retain_all(graph: TemporalGraph, fn: str = "max", lane: int = 0) -> DataFrame:
    """Extremes with every contribution retained over time, so that a deletion never gathers anew: t, dst, kept (contributions held), best.

    The retained table holds one row per value and stay; what is held in a snapshot is counted by running sums of arrivals and
    departures, and its extreme is read off the retained rows, partial extremes first, so no target's rows meet in one list."""
    c = contributions(graph)
    held = _by_deltas(c.withColumn("_one", F.lit(0).cast("long")), ("_one",), F.lit(graph.snapshots), ["dst"]).select("t", "dst", F.col("cnt").alias("kept"))
    v = F.col("w") * F.col(graph.lanes[lane])
    # contributions of one target with one value and one stay differ in nothing that the extreme needs
    runs = c.select("dst", v.alias("v"), "valid_from", "valid_to").groupBy("dst", "v", "valid_from").agg(F.max("valid_to").alias("valid_to"))
    best = expand(runs).groupBy("t", "dst").agg((F.max("v") if fn == "max" else F.min("v")).alias("best"))
    return held.join(best, ["t", "dst"]).select("t", "dst", "kept", "best")


def weighted(graph: TemporalGraph, score: Column, version: int = 0) -> DataFrame:
    """Attention with fixed weights: softmax of `score` over a target's in-edges. The weight version is part of the result's identity; after each update the sums start anew.

    Partial aggregates only: each target's top score first, then the sums relative to it."""
    c = contributions(graph).withColumn("s", score)
    # the top over all snapshots keeps every exponent at or below zero, and one row per target is enough
    c = c.join(c.groupBy("dst").agg(F.max("s").alias("top")), "dst").withColumn("p", F.exp(F.col("s") - F.col("top")))
    sums = [(F.sum(F.col("p") * F.col(x)) / F.sum("p")).alias(f"a{i}") for i, x in enumerate(graph.lanes)]
    return expand(c).groupBy("t", "dst").agg(*sums).withColumn("version", F.lit(version))


def weighted_step(graph: TemporalGraph, kept: DataFrame, t: int, score: Column, version: int = 0) -> DataFrame:
    """Attention at snapshot t with the weights of version `version`, from `kept` (that of t - 1 and the same version): only targets with a changed in-edge are gathered anew. dst, a0.., version."""
    names = [f"a{i}" for i in range(len(graph.lanes))]
    hit = delta.build(graph).filter(F.col("t") == t).select("dst").distinct()
    now = at(graph, t).select("dst").distinct()
    c = contributions(graph).filter((F.col("valid_from") <= t) & (F.col("valid_to") > t)).join(hit, "dst", "left_semi").withColumn("s", score)
    c = c.join(c.groupBy("dst").agg(F.max("s").alias("top")), "dst").withColumn("p", F.exp(F.col("s") - F.col("top")))
    anew = c.groupBy("dst").agg(*[(F.sum(F.col("p") * F.col(x)) / F.sum("p")).alias(n) for n, x in zip(names, graph.lanes)])
    same = kept.filter(F.col("version") == version).join(hit, "dst", "left_anti").join(now, "dst", "left_semi").select("dst", *names)
    return anew.unionByName(same).withColumn("version", F.lit(version))


def propagate(graph: TemporalGraph, message: Callable[[dict[str, Column]], Column], reduce: Callable[[Column], Column], invertible: bool = False, target: DataFrame | None = None) -> DataFrame:
    """User-defined message over (source lanes, edge weight, lanes of the target: `target.<name>` of a table by node) and reduction; an invertible one runs on deltas."""
    c = contributions(graph)
    names = {x: F.col(x) for x in graph.lanes} | {"w": F.col("w")}
    if target is not None:
        own = {x: f"_target_{x}" for x in target.columns if x != "node"}
        c = c.join(target.withColumnsRenamed({"node": "dst"} | own), "dst")
        names |= {f"target.{x}": F.col(y) for x, y in own.items()}
    c = c.withColumn("message", message(names))
    if invertible:
        return _by_deltas(c.withColumn("w", F.lit(1)), ("message",), F.lit(graph.snapshots), ["dst"]).select("t", "dst", F.col("a0").alias("value"))
    return expand(c).groupBy("t", "dst").agg(reduce(F.col("message")).alias("value"))


def with_isolated(agg: DataFrame, graph: TemporalGraph) -> DataFrame:
    """All nodes of the universe in every snapshot; those without in-edges get zeros."""
    grid = graph.nodes.select(F.col("node").alias("dst"), F.explode(F.sequence(F.lit(0), F.lit(graph.snapshots - 1))).alias("t"))
    return grid.join(agg, ["t", "dst"], "left").fillna(0)


def normalised(graph: TemporalGraph) -> DataFrame:
    """Sums with each message divided by the root of the product of out- and in-degree."""
    rows = expand(contributions(graph))
    out_deg = expand(graph.edges).groupBy("t", "src").agg(F.count(F.lit(1)).alias("do"))
    in_deg = expand(graph.edges).groupBy("t", "dst").agg(F.count(F.lit(1)).alias("di"))
    joined = rows.join(out_deg, ["t", "src"]).join(in_deg, ["t", "dst"])
    norm = F.sqrt(F.col("do") * F.col("di"))
    return joined.groupBy("t", "dst").agg(*[F.sum(F.col("w") * F.col(x) / norm).alias(f"a{i}") for i, x in enumerate(graph.lanes)])


def fused_static(graph: TemporalGraph, topology_at: int) -> DataFrame:
    """All snapshots' lanes over one frozen topology, side by side: the edges are read once."""
    frozen = graph.edges.filter((F.col("valid_from") <= topology_at) & (F.col("valid_to") > topology_at)).select("src", "dst", "w")
    lanes = expand(graph.feats)
    return frozen.join(lanes, frozen.src == lanes.node).groupBy("t", "dst").agg(*_sums(graph.lanes))


def multi_snapshot(graph: TemporalGraph, first: int, count: int) -> DataFrame:
    """`count` neighbouring snapshots gathered in one job."""
    return expand(contributions(graph), first, first + count).groupBy("t", "dst").agg(*_sums(graph.lanes))


def static_features(graph: TemporalGraph) -> DataFrame:
    """Features frozen at the first snapshot: only topology deltas move the cached aggregate."""
    frozen = graph.feats.filter("valid_from = 0").withColumn("valid_to", F.lit(graph.snapshots))
    return incremental(TemporalGraph(graph.edges, frozen, graph.nodes, graph.snapshots, graph.lanes))
