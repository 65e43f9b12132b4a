"""Shared helpers: the cluster's shared folder, stored intermediates, Arrow row mapping."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..storage import shared_dir, stored

__all__ = ["BLANKS", "map_rows", "quoted", "read", "remainder", "shared_dir", "stored", "text_or_empty"]
#: The six characters that separate words.
BLANKS = "\x20\x09\x0a\x0b\x0c\x0d"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def quoted(name: str) -> str:
    """A column's name as a path of one part, whatever characters it holds."""
    return "`" + name.replace("`", "``") + "`"


def text_or_empty(col: str = "text"):
    return F.coalesce(F.col(col), F.lit(""))


def remainder(modulus: int):
    """crc32 of doc_id as text, modulo `modulus`; null ids count as the empty text."""
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % modulus


def map_rows(df: DataFrame, schema: str | T.StructType, rows: Callable[[Iterator[dict]], Iterator[dict]], batch: int = 256) -> DataFrame:
    """mapInArrow over column lists: `rows` gets dicts of lists (one per Arrow batch, at most `batch` rows) and yields dicts of lists."""
    schema = T._parse_datatype_string(schema) if isinstance(schema, str) else schema
    arrow = to_arrow_schema(schema)

    def run(batches):
        def columns():
            for b in batches:
                for at in range(0, b.num_rows, batch):
                    yield b.slice(at, batch).to_pydict()

        for out in rows(columns()):
            yield pa.RecordBatch.from_pydict({f.name: out[f.name] for f in arrow}, schema=arrow)

    return df.mapInArrow(run, schema)
