"""Sliding windows of snapshots as training sequences."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def count(snapshots: int, length: int, stride: int = 1, horizon: int = 0) -> int:
    return max(0, (snapshots - length - horizon) // stride + 1)


def windows(spark: SparkSession, snapshots: int, length: int = 8, stride: int = 1, horizon: int = 0) -> DataFrame:
    """q, part ('enc'), idx (from 1), t of every sequence; snapshots after the last whole sequence are unused."""
    q = spark.range(count(snapshots, length, stride, horizon)).select(F.col("id").cast("int").alias("q"))
    rows = q.select("q", F.lit("enc").alias("part"), F.explode(F.sequence(F.lit(1), F.lit(length))).alias("idx"))
    return rows.withColumn("t", F.col("q") * stride + F.col("idx") - 1)


def seq2seq(spark: SparkSession, snapshots: int, length: int = 8, stride: int = 1) -> DataFrame:
    """Encoder windows, and decoder windows shifted by the stride (teacher forcing reads the true snapshots)."""
    enc = windows(spark, snapshots, length, stride, stride)
    return enc.union(enc.select("q", F.lit("dec").alias("part"), "idx", (F.col("t") + stride).alias("t")))


def repeat_share(seqs: DataFrame) -> DataFrame:
    """How many (sequence, place) aggregations repeat a snapshot that was aggregated already."""
    return seqs.agg(F.count(F.lit(1)).alias("visits"), F.count_distinct("t").alias("distinct_t")).withColumn("repeat_share", 1 - F.col("distinct_t") / F.col("visits"))


class SlidingSequences:
    """Table function: SELECT * FROM sliding_sequences(80, 8, 1)."""

    def eval(self, snapshots: int, length: int, stride: int) -> Iterator[tuple[int, int, int]]:
        for q in range(count(snapshots, length, stride)):
            for i in range(length):
                yield q, i + 1, q * stride + i
