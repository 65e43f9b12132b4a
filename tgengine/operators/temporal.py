"""Interval-coded dynamic graphs: edges and features carry the snapshots [valid_from, valid_to) in which they hold."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.exact import edge_id
from ..storage import stored


@dataclass(frozen=True)
class TemporalGraph:
    """edges(src, dst, edge_id, w, valid_from, valid_to), feats(node, lanes, valid_from, valid_to), nodes(node)."""

    edges: DataFrame
    feats: DataFrame
    nodes: DataFrame
    snapshots: int
    lanes: tuple[str, ...] = ("f0", "f1")


def from_activity(activity: DataFrame, trailing: int, snapshots: int) -> DataFrame:
    """Edges active for `trailing` snapshots from each (src, dst, t); overlapping stays are merged, gaps kept."""
    order = Window.partitionBy("src", "dst").orderBy("t")
    marked = activity.select("src", "dst", "t").distinct().withColumn("before", F.lag("t").over(order))
    fresh = F.when(F.col("before").isNull() | (F.col("t") > F.col("before") + trailing), 1).otherwise(0)
    stays = marked.withColumn("stay", F.sum(fresh).over(order)).groupBy("src", "dst", "stay").agg(F.min("t").alias("valid_from"), (F.max("t") + trailing).alias("valid_to"))
    return stays.select(
        F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), edge_id().alias("edge_id"), F.lit(1).cast("long").alias("w"),
        F.col("valid_from").cast("int").alias("valid_from"), F.least(F.col("valid_to"), F.lit(snapshots)).cast("int").alias("valid_to"),
    )


def from_snapshots(edges_by_t: DataFrame, snapshots: int) -> DataFrame:
    """Edges listed snapshot by snapshot (src, dst, w, t); runs with one weight become intervals, a weight change ends one."""
    order = Window.partitionBy("src", "dst").orderBy("t")
    same = (F.col("t") == F.lag("t").over(order) + 1) & (F.col("w") == F.lag("w").over(order))
    runs = edges_by_t.withColumn("fresh", F.when(same, 0).otherwise(1)).withColumn("run", F.sum("fresh").over(order))
    out = runs.groupBy("src", "dst", "w", "run").agg(F.min("t").cast("int").alias("valid_from"), F.least(F.max("t") + 1, F.lit(snapshots)).cast("int").alias("valid_to"))
    return out.select("src", "dst", edge_id().alias("edge_id"), "w", "valid_from", "valid_to")


def runs_of_values(values: DataFrame, key: str, lanes: tuple[str, ...]) -> DataFrame:
    """(key, valid_from, valid_to, lanes) with neighbouring equal values merged."""
    order = Window.partitionBy(key).orderBy("valid_from")
    row = F.struct(*lanes)
    same = F.coalesce((F.lag("valid_to").over(order) == F.col("valid_from")) & (F.lag(row).over(order) == row), F.lit(False))
    runs = values.withColumn("fresh", F.when(same, 0).otherwise(1)).withColumn("run", F.sum("fresh").over(order))
    return runs.groupBy(key, "run", *lanes).agg(F.min("valid_from").cast("int").alias("valid_from"), F.max("valid_to").cast("int").alias("valid_to")).drop("run")


def at(graph: TemporalGraph, t: int) -> DataFrame:
    """Edges of one snapshot; the predicate reaches the scan."""
    return graph.edges.filter((F.col("valid_from") <= t) & (F.col("valid_to") > t))


def expand(df: DataFrame, first: int = 0, last: int | None = None) -> DataFrame:
    """One row per snapshot in which each row holds."""
    end = F.col("valid_to") if last is None else F.least("valid_to", F.lit(last))
    held = df.filter(end > F.greatest("valid_from", F.lit(first)))
    return held.withColumn("t", F.explode(F.sequence(F.greatest("valid_from", F.lit(first)), end - 1))).drop("valid_from", "valid_to")


def contributions(graph: TemporalGraph) -> DataFrame:
    """Each edge with its source's features while both hold: the join on src keeps only overlapping intervals."""
    e, f = graph.edges.alias("e"), graph.feats.alias("f")
    overlap = (F.col("e.valid_from") < F.col("f.valid_to")) & (F.col("f.valid_from") < F.col("e.valid_to"))
    joined = e.join(f, (F.col("e.src") == F.col("f.node")) & overlap)
    return joined.select(
        "src", "dst", "edge_id", "w", *[F.col(f"f.{x}") for x in graph.lanes],
        F.greatest("e.valid_from", "f.valid_from").alias("valid_from"), F.least("e.valid_to", "f.valid_to").alias("valid_to"),
        F.col("e.valid_from").alias("edge_from"), F.col("e.valid_to").alias("edge_to"), F.col("f.valid_from").alias("feat_from"), F.col("f.valid_to").alias("feat_to"),
    )


def coded(graph: TemporalGraph) -> TemporalGraph:
    """The graph with its intervals written once, for plans that read them more than once."""
    return TemporalGraph(stored(graph.edges), stored(graph.feats), graph.nodes, graph.snapshots, graph.lanes)


def by_snapshot(intervals: DataFrame, *by: str) -> DataFrame:
    """t, `by`, rows: how many intervals hold in each snapshot. Counted by their ends first, so that they aren't spread over their snapshots."""
    ends = intervals.groupBy(*by, "valid_from", "valid_to").agg(F.count(F.lit(1)).alias("n"))
    return expand(ends).groupBy(*by, "t").agg(F.sum("n").alias("rows"))


def as_of(events: DataFrame, feats: DataFrame, lanes: tuple[str, ...], width: int = 8) -> DataFrame:
    """Events (node, t) with the features that hold at t: an equi-join on (node, time bucket) and a residual filter."""
    f = feats.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("valid_from") / width), F.floor((F.col("valid_to") - 1) / width))))
    e = events.withColumn("bucket", F.floor(F.col("t") / width))
    joined = e.join(f, ["node", "bucket"]).filter((F.col("valid_from") <= F.col("t")) & (F.col("t") < F.col("valid_to")))
    return joined.select(*events.columns, *lanes)


def degrees(graph: TemporalGraph) -> DataFrame:
    """In-degree of each target per snapshot."""
    return expand(graph.edges).groupBy("t", "dst").agg(F.count(F.lit(1)).alias("degree"))
