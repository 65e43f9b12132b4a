"""Deltas between snapshots, read off the interval coding."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .temporal import TemporalGraph, contributions, expand


def _ends(rows: DataFrame, snapshots: int, *more: Column) -> DataFrame:
    """Each interval's beginning (sign 1) and end (-1) within the snapshots, in one pass; `more`: a column for each of the two."""
    pair = [F.struct(F.col("valid_from").alias("t"), F.lit(1).alias("sign"), *[m.alias("cause") for m in more[:1]])]
    pair.append(F.struct(F.col("valid_to").alias("t"), F.lit(-1).alias("sign"), *[m.alias("cause") for m in more[1:]]))
    return rows.withColumn("end", F.explode(F.array(*pair))).filter(F.col("end.t") < snapshots)


def topology(graph: TemporalGraph) -> DataFrame:
    """Deleted (-1) and inserted (+1) edges at each t >= 1."""
    return _ends(graph.edges, graph.snapshots).filter("end.t > 0").select("end.t", "end.sign", "src", "dst", "edge_id", "w")


def features(graph: TemporalGraph) -> DataFrame:
    """Edges of nodes whose features change at t: out-edges of t-1 in the minus set, of t in the plus set."""
    return build(graph).filter("cause <> 'edge'").drop("cause", *graph.lanes)


def build(graph: TemporalGraph) -> DataFrame:
    """Both causes together; an edge stands once in each set. Lanes: the features before (minus) or after (plus) the change."""
    cause = lambda edge, feat: F.when(edge & feat, "both").when(edge, "edge").otherwise("feature")
    came = cause(F.col("edge_from") == F.col("valid_from"), F.col("feat_from") == F.col("valid_from"))
    went = cause(F.col("edge_to") == F.col("valid_to"), F.col("feat_to") == F.col("valid_to"))
    both = _ends(contributions(graph), graph.snapshots, came, went).filter("end.t > 0")
    return both.select("end.t", "end.sign", "src", "dst", "edge_id", "w", *graph.lanes, "end.cause")


def by_anti_join(graph: TemporalGraph) -> DataFrame:
    """The topology deltas again, by comparing neighbouring snapshots."""
    now = expand(graph.edges).select("t", "src", "dst")
    last = graph.snapshots - 1
    before = now.filter(F.col("t") < last).withColumn("t", F.col("t") + 1)
    gone = before.join(now, ["t", "src", "dst"], "left_anti").withColumn("sign", F.lit(-1))
    come = now.filter("t > 0").join(before, ["t", "src", "dst"], "left_anti").withColumn("sign", F.lit(1))
    return gone.unionByName(come)


def by_except(graph: TemporalGraph) -> DataFrame:
    now = expand(graph.edges).select("t", "src", "dst")
    before = now.filter(F.col("t") < graph.snapshots - 1).withColumn("t", F.col("t") + 1)
    return before.subtract(now).withColumn("sign", F.lit(-1)).unionByName(now.filter("t > 0").subtract(before).withColumn("sign", F.lit(1)))


def ratio(graph: TemporalGraph) -> DataFrame:
    """t, n_minus, n_plus, n_edges, change_ratio (all deltas over the snapshot's edges) for t >= 1."""
    sums = build(graph).groupBy("t").agg(F.sum((F.col("sign") < 0).cast("long")).alias("n_minus"), F.sum((F.col("sign") > 0).cast("long")).alias("n_plus"))
    sizes = snapshot_sizes(graph).filter("t > 0")
    return sizes.join(sums, "t", "left").fillna(0, ["n_minus", "n_plus"]).select("t", "n_minus", "n_plus", "n_edges", F.try_divide(F.col("n_minus") + F.col("n_plus"), F.col("n_edges")).alias("change_ratio"))


def snapshot_sizes(graph: TemporalGraph) -> DataFrame:
    """Edges per snapshot by a running sum of arrivals and departures; no snapshot is written out."""
    steps = _ends(graph.edges, graph.snapshots).groupBy("end.t").agg(F.sum("end.sign").alias("d"))
    every = graph.edges.sparkSession.range(graph.snapshots).select(F.col("id").cast("int").alias("t"))
    # one row per snapshot: the window over all of them is small
    return every.join(steps, "t", "left").select("t", F.sum(F.coalesce("d", F.lit(0))).over(Window.orderBy("t")).alias("n_edges"))


def segments(graph: TemporalGraph, threshold: float = 0.5) -> DataFrame:
    """t, scratch (its change ratio exceeds the threshold, or it is the first), segment (number of scratch snapshots so far), start of the segment and of the next. One row per snapshot."""
    r = ratio(graph).select("t", F.coalesce(F.col("change_ratio") > threshold, F.lit(True)).alias("scratch"))
    r = r.union(graph.edges.sparkSession.range(1).select(F.lit(0).alias("t"), F.lit(True).alias("scratch")))
    numbered = r.select("t", "scratch", F.sum(F.col("scratch").cast("int")).over(Window.orderBy("t")).alias("segment"))
    whole = Window.partitionBy("segment")
    return numbered.select("t", "scratch", "segment", F.min("t").over(whole).alias("seg_from"), (F.max("t").over(whole) + 1).alias("seg_to"))
