"""Mini-batches, k-hop neighbourhoods and the order in which they are visited."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.exact import arithmetic_hash
from .temporal import TemporalGraph, expand


def sampler(nodes: DataFrame, batches: int, seed: int = 42) -> DataFrame:
    """node -> batch_id by a seeded hash."""
    return nodes.select("node", F.pmod(arithmetic_hash(F.col("node"), 17, 0, seed), F.lit(batches)).cast("int").alias("batch_id"))


def khop(graph: TemporalGraph, batch: DataFrame, hops: int = 2, fanouts: tuple[int, ...] | None = None, seed: int = 42) -> DataFrame:
    """batch_id, t, hop, src, dst. With fanouts, of each target the in-neighbours with the smallest hashes stay; the hash knows nothing of t, so the choice moves only with the neighbourhood."""
    frontier = batch.select("batch_id", F.col("node").alias("dst"))
    out = None
    for hop in range(1, (len(fanouts) if fanouts else hops) + 1):
        # only the frontier's in-edges are spread over their snapshots and ranked
        wanted = graph.edges.join(frontier.select("dst").distinct(), "dst", "left_semi")
        here = expand(wanted).select("t", "src", "dst")
        if fanouts:
            order = Window.partitionBy("t", "dst").orderBy(arithmetic_hash(F.col("src"), F.col("dst"), hop, seed), "src")
            here = here.withColumn("r", F.row_number().over(order)).filter(F.col("r") <= fanouts[hop - 1]).drop("r")
        keys = ["dst"] if hop == 1 else ["t", "dst"]
        reached = here.join(frontier, keys).select("batch_id", "t", F.lit(hop).alias("hop"), "src", "dst")
        out = reached if out is None else out.union(reached)
        frontier = reached.select("batch_id", "t", F.col("src").alias("dst")).distinct()
    return out


def khop_delta(khop_rows: DataFrame, first: int) -> DataFrame:
    """The computation graphs as the first snapshot whole (sign 1) and changes after it."""
    names = ["batch_id", "hop", "src", "dst"]
    run = Window.partitionBy(*names).orderBy("t")
    k = khop_rows.filter(F.col("t") >= first).withColumn("before", F.lag("t").over(run)).withColumn("after", F.lead("t").over(run))
    come = k.filter(F.col("before").isNull() | (F.col("before") < F.col("t") - 1)).select(*names, "t", F.lit(1).alias("sign"))
    last = khop_rows.agg(F.max("t").alias("last"))
    gone = k.join(F.broadcast(last)).filter((F.col("t") < F.col("last")) & (F.col("after").isNull() | (F.col("after") > F.col("t") + 1))).select(*names, (F.col("t") + 1).alias("t"), F.lit(-1).alias("sign"))
    return come.unionByName(gone)


def features(graph: TemporalGraph, sample: DataFrame) -> DataFrame:
    """Only the feature rows that a sample's nodes need: t, node, lanes."""
    need = sample.select("t", F.col("src").alias("node")).distinct()
    return expand(graph.feats).join(need, ["t", "node"], "left_semi")


def order(seqs: DataFrame, batches: int, kind: str = "seq_first") -> DataFrame:
    """pos, q, batch_id. seq_first: all sequences of a batch, then the next batch; node_first: all batches of a sequence."""
    q = seqs.select("q").distinct().withColumn("batch_id", F.explode(F.sequence(F.lit(0), F.lit(batches - 1))))
    n = q.agg(F.max("q").alias("last_q"))
    first = F.col("batch_id") * (F.col("last_q") + 1) + F.col("q") if kind == "seq_first" else F.col("q") * batches + F.col("batch_id")
    return q.join(F.broadcast(n)).select(first.cast("int").alias("pos"), "q", "batch_id")


def with_nodes(ordered: DataFrame, rows: DataFrame, length: int) -> DataFrame:
    """The visits with the nodes of their batch that are active in their sequence; rows(batch_id, t, rows): those active in the `length` snapshots that end at t."""
    nodes = rows.select("batch_id", (F.col("t") - length + 1).alias("q"), F.col("rows").alias("nodes"))
    return ordered.join(F.broadcast(nodes), ["batch_id", "q"], "left").fillna(0, ["nodes"]).select(*ordered.columns, "nodes")


def loader_rows(khop_rows: DataFrame, seqs: DataFrame, mode: str = "delta") -> DataFrame:
    """Edges that a loader ships per sequence: every snapshot whole, or the first whole and changes only."""
    per_t = khop_rows.groupBy("t").agg(F.count(F.lit(1)).alias("whole"))
    if mode == "full":
        return seqs.join(F.broadcast(per_t), "t").groupBy("q").agg(F.sum("whole").alias("rows"))
    moved = khop_delta(khop_rows, 0).groupBy("t").agg(F.count(F.lit(1)).alias("moved"))
    j = seqs.join(F.broadcast(per_t), "t", "left").join(F.broadcast(moved), "t", "left").fillna(0, ["whole", "moved"])
    return j.groupBy("q").agg(F.sum(F.when(F.col("idx") == 1, F.col("whole")).otherwise(F.col("moved"))).alias("rows"))
