"""The corpus pipeline: quality rules, language, near duplicates, benchmark passages, token ids.

Each stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept. All but the last return the columns of
documents; the last returns each kept document with its token ids.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from tgengine.llm import decontaminate, language_id, near_dup, quality_rules, sentencepiece_codec
from tgengine.llm.common import read, shared_dir


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep_good(docs, read(spark, sf_dir, "labels"))


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_id.keep_known(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dup.keep_one(docs)


def no_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, read(spark, sf_dir, "benchmark"))


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.encode(docs)


STAGES = [
    ("quality rules", good_quality),
    ("language ID", known_language),
    ("near duplicates", one_of_each),
    ("benchmark decontamination", no_benchmark),
    ("SentencePiece encoding", token_ids),
]
#: Fitted kernels, sketches and the tokenizer aren't SQL; the tests hold the stages against brute force.
ORACLE_SQL = None


def _done(spark: SparkSession, path: str) -> bool:
    """Whether a stage was written to its end."""
    p = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def stages(spark: SparkSession, sf_dir: str, folder: str | None = None) -> list[tuple[str, DataFrame]]:
    """Name and rows of the documents and of each stage but the last, as written. With `folder`, a run that was stopped goes on after the last stage written there."""
    base = folder or f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = read(spark, sf_dir, "documents")
    out = [("documents", docs)]
    for i, (name, stage) in enumerate(STAGES[:-1]):
        path = f"{base}/stage-{i}"
        if not (folder and _done(spark, path)):
            stage(spark, docs, sf_dir).write.mode("overwrite").parquet(path)
        docs = spark.read.schema(docs.schema).parquet(path)
        out.append((name, docs))
    return out


def run(spark: SparkSession, sf_dir: str, folder: str | None = None) -> DataFrame:
    return STAGES[-1][1](spark, stages(spark, sf_dir, folder)[-1][1], sf_dir)


def dropped(spark: SparkSession, sf_dir: str, folder: str | None = None) -> DataFrame:
    """stage, rows_in, rows_out of each stage that drops rows."""
    made = stages(spark, sf_dir, folder)
    counts = [d.count() for _, d in made]
    return spark.createDataFrame([(n, a, b) for (n, _), a, b in zip(made[1:], counts, counts[1:])], "stage string, rows_in long, rows_out long")
