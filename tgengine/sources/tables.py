"""Readers and writers of tables and graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, table: str, kind: str = "parquet", **options) -> DataFrame:
    reader = spark.read.options(**options)
    return reader.parquet(f"{sf_dir}/{table}.parquet") if kind == "parquet" else reader.format(kind).load(f"{sf_dir}/{table}")


def load_all(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {t: load(spark, sf_dir, t) for t in TABLES}


def write_graph(edges: DataFrame, path: str, by: tuple[str, ...] = ()) -> None:
    """Sorted by validity within files, so that row groups are skipped on a snapshot's predicate."""
    w = edges.sortWithinPartitions("valid_from", "src").write.mode("overwrite")
    (w.partitionBy(*by) if by else w).parquet(path)


def write_bucketed(edges: DataFrame, table: str, key: str = "dst", buckets: int = 16) -> None:
    edges.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def register_views(spark: SparkSession, graph) -> None:
    """The graph's tables as SQL views, and the sequence generator as a table function."""
    graph.edges.createOrReplaceTempView("temporal_edges")
    graph.feats.createOrReplaceTempView("temporal_feats")
    graph.nodes.createOrReplaceTempView("temporal_nodes")
    from ..operators.sequences import SlidingSequences

    spark.udtf.register("sliding_sequences", udtf(SlidingSequences, returnType="q int, idx int, t int"))
