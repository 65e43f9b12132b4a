"""Placements of snapshots and nodes on machines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .sequences import count


def blocks(spark: SparkSession, snapshots: int, machines: int) -> DataFrame:
    """Consecutive snapshots per machine: t, block."""
    return spark.range(snapshots).select(F.col("id").cast("int").alias("t"), F.floor(F.col("id") * machines / snapshots).cast("int").alias("block"))


def sequence_blocks(spark: SparkSession, snapshots: int, machines: int, length: int, stride: int = 1, horizon: int = 0, split: str = "by_snapshot") -> DataFrame:
    """q, block, first and last snapshot. by_snapshot: the block of the first snapshot; by_sequence: equal numbers of sequences."""
    n = count(snapshots, length, stride, horizon)
    q = spark.range(n).select(F.col("id").cast("int").alias("q"))
    block = F.floor(F.col("q") * stride * machines / snapshots) if split == "by_snapshot" else F.floor(F.col("q") * machines / n)
    return q.select("q", block.cast("int").alias("block"), (F.col("q") * stride).alias("first_t"), (F.col("q") * stride + length + horizon - 1).alias("last_t"))


def with_rows(placed: DataFrame, rows: DataFrame) -> DataFrame:
    """What is placed by snapshot, with the rows (t, rows) that the snapshot holds."""
    return placed.join(F.broadcast(rows), "t", "left").fillna(0, ["rows"])


def overlapped(spark: SparkSession, snapshots: int, machines: int, length: int, stride: int = 1, horizon: int = 0, split: str = "by_snapshot") -> DataFrame:
    """t, block, is_copy: every sequence lies whole on one machine, at the price of a few copied snapshots."""
    need = sequence_blocks(spark, snapshots, machines, length, stride, horizon, split).select("block", F.explode(F.sequence("first_t", "last_t")).alias("t"))
    own = blocks(spark, snapshots, machines)
    held = need.union(own.select("block", "t")).distinct()
    return held.join(own.withColumnRenamed("block", "owner"), "t").select("t", "block", (F.col("block") != F.col("owner")).alias("is_copy"))


def on_demand(spark: SparkSession, snapshots: int, machines: int, length: int, stride: int = 1, horizon: int = 0) -> DataFrame:
    """(block, t) of the snapshots that a machine has to fetch where copies are not kept, with the number of its sequences that do."""
    need = sequence_blocks(spark, snapshots, machines, length, stride, horizon).select("q", "block", F.explode(F.sequence("first_t", "last_t")).alias("t"))
    own = blocks(spark, snapshots, machines).withColumnRenamed("block", "owner")
    return need.join(own, "t").filter("block <> owner").groupBy("block", "t").agg(F.count(F.lit(1)).alias("fetches"))


def nodes(df: DataFrame, machines: int, col: str = "node") -> DataFrame:
    return df.withColumn("machine", F.pmod(F.col(col), F.lit(machines)).cast("int"))


def sequence_steps(seqs: DataFrame, length: int, machines: int) -> DataFrame:
    """Snapshots of one sequence spread over the machines."""
    return seqs.withColumn("machine", F.floor((F.col("idx") - 1) * machines / length).cast("int"))


def balance(placed: DataFrame, by: str = "block", weight: str | None = None) -> DataFrame:
    """Items per machine, or their summed weights, and the largest over the mean."""
    n = placed.groupBy(by).agg((F.sum(weight) if weight else F.count(F.lit(1))).alias("items"))
    whole = n.agg(F.max("items").alias("largest"), F.avg("items").alias("average"))
    return n.join(F.broadcast(whole)).select(by, "items", (F.col("largest") / F.col("average")).alias("imbalance"))


def first_snapshot_cut(edges: DataFrame, machines: int, rounds: int = 3) -> DataFrame:
    """node, label by label propagation over the given (symmetric) edges: each node takes its neighbours' most frequent label; ties to the smallest."""
    both = edges.select("src", "dst").union(edges.select("dst", "src")).distinct()
    label = both.select(F.col("src").alias("node")).distinct().withColumn("label", F.col("node"))
    for _ in range(rounds):
        votes = both.join(label.withColumnRenamed("node", "src"), "src").groupBy("dst", "label").agg(F.count(F.lit(1)).alias("n"))
        label = votes.groupBy(F.col("dst").alias("node")).agg((-F.max(F.struct("n", (-F.col("label")).alias("l")))["l"]).alias("label"))
    return label.withColumn("machine", F.pmod("label", F.lit(machines)).cast("int"))
