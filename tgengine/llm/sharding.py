"""Two-pass external shuffle into shards.

Pass one scatters whole rows by seeded hashes: the highest of one hash per shard picks the shard (so one more shard takes
rows only into itself), and a further hash picks one of the shard's memory-sized buckets, whose number follows from the
total size of the rows. Each bucket goes to a task of its own. Pass two shuffles each bucket by Fisher-Yates (the built-in
seeded `shuffle`) and writes it under its shard; a bucket's first slot is the number of rows in the shard's earlier
buckets. Built-in functions only. `plan` writes the shards to the shared folder and reports on the rows read from there.

Null texts count as empty, null ids as the id 'null'. Rows equal in all columns are counted first; where the copies of one
would take more than 1 / `PARTS` of a bucket, they are dealt out by copy number, so that no row, however frequent, fills one
bucket; such copies are interchangeable. Columns of type map are carried but not compared. An empty table gives no rows.
Columns named shard or slot are replaced.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import quoted, read, shared_dir, stored

SHARDS = 16
SEED = 20_011
BUCKET_BYTES = 32 << 20
PARTS = 8
#: Copy numbers made from one row at a time.
SPAN = 1 << 16
SAME = ["_s_key", "_s_size", "_s_crc", "_s_row"]


def _pick(shards: int, seed: int, key: str = "_s_key") -> Column:
    """The shard with the highest hash of (seed, shard, key)."""
    marks = F.array(*[F.struct(F.xxhash64(F.lit(seed), F.lit(i), F.col(key)).alias("h"), F.lit(i).alias("i")) for i in range(shards)])
    return F.array_max(marks)["i"]


def _bytes(f: T.StructField) -> Column:
    c = F.col(quoted(f.name))
    if isinstance(f.dataType, (T.StringType, T.BinaryType)):
        return F.coalesce(F.octet_length(c), F.lit(0)).cast("long")
    if isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType)):
        return F.octet_length(F.to_json(F.struct(c))).cast("long")
    return F.lit(8).cast("long")


def _has_map(t: T.DataType) -> bool:
    return isinstance(t, T.MapType) or isinstance(t, T.ArrayType) and _has_map(t.elementType) or isinstance(t, T.StructType) and any(_has_map(f.dataType) for f in t)


def _compared(docs: DataFrame) -> list[Column]:
    return [F.col(quoted(f.name)) for f in docs.schema if not _has_map(f.dataType)]


def digests() -> dict[str, Column]:
    """Key, size and checksum of a row."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return {"_s_key": F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), "_s_size": (F.octet_length(text) + 1).cast("long"), "_s_crc": F.crc32(text).cast("long")}


def write(docs: DataFrame, path: str, shards: int = SHARDS, seed: int = SEED, bucket_bytes: int = BUCKET_BYTES) -> None:
    """Writes the rows with their slots as Parquet under shard=<i>, each bucket in one file or more, in slot order."""
    docs = docs.drop("shard", "slot")
    whole = F.struct(*[F.col(quoted(c)) for c in docs.columns])
    rows = docs.select(whole.alias("row"), *[c.alias(n) for n, c in digests().items()], F.xxhash64(*_compared(docs)).alias("_s_row"), sum(map(_bytes, docs.schema), F.lit(0)).alias("bytes"))
    same = stored(rows.groupBy(*SAME).agg(F.count(F.lit(1)).alias("copies"), F.max("bytes").alias("bytes")))
    total = same.agg(F.coalesce(F.sum(F.col("bytes") * F.col("copies")), F.lit(0)).alias("b")).first()["b"]
    buckets = max(1, -(-total // (shards * bucket_bytes)))

    def dealt(df: DataFrame) -> DataFrame:
        """With the bucket, counted over all shards."""
        inner = F.pmod(F.xxhash64(F.lit(seed + 1), *SAME, F.col("copy").cast("long")), F.lit(buckets))
        return df.withColumn("bucket", (_pick(shards, seed) * buckets + inner).cast("int"))

    often = (F.col("copies") > 1) & (F.col("copies") * F.col("bytes") * PARTS > bucket_bytes)
    hot = stored(same.filter(often).select(*SAME, "copies"))  # at most PARTS for each bucket
    # copy numbers in two steps, so that no row holds an array as long as a count
    span = F.sequence(F.lit(0).cast("long"), F.when(often, F.floor((F.col("copies") - 1) / SPAN)).otherwise(F.lit(0)).cast("long"))
    spread = same.withColumn("span", F.explode(span))
    ends = F.when(often, F.least(F.col("copies"), (F.col("span") + 1) * SPAN)).otherwise(F.lit(1)).cast("long")
    first = spread.withColumn("copy", F.explode(F.sequence(F.col("span") * SPAN + 1, ends)))
    first = dealt(first.withColumn("n", F.when(often, 1).otherwise(F.col("copies"))))
    first = first.groupBy("bucket").agg(F.sum("n").alias("n")).withColumn("shard", F.floor(F.col("bucket") / buckets).cast("int"))
    before = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    first = stored(first.select("bucket", "shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first_slot")))

    if hot.limit(1).count():
        # copies are numbered within the tasks that read them, and a task's first number follows from the counts of the tasks before
        some = stored(rows.join(F.broadcast(hot.drop("copies")), SAME).withColumn("task", F.spark_partition_id()))
        counts = some.groupBy(*SAME, "task").agg(F.count(F.lit(1)).alias("n"))
        earlier = Window.partitionBy(*SAME).orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
        counts = counts.select(*SAME, "task", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("begin"))
        here = F.row_number().over(Window.partitionBy(*SAME, "task").orderBy(F.lit(1)))
        numbered = some.withColumn("here", here).join(counts, [*SAME, "task"]).withColumn("copy", F.col("begin") + F.col("here"))
        others = rows.join(F.broadcast(hot.drop("copies")), SAME, "left_anti").withColumn("copy", F.lit(1).cast("long"))
        scattered = dealt(others).select("bucket", *SAME, "row").unionByName(dealt(numbered).select("bucket", *SAME, "row"))
    else:
        scattered = dealt(rows.withColumn("copy", F.lit(1).cast("long"))).select("bucket", *SAME, "row")
    # sorted before it is shuffled: the same seed gives the same order, whatever order the rows came in
    own = scattered.repartitionById(shards * buckets, F.col("bucket")).sortWithinPartitions("bucket", *SAME)
    lists = own.groupBy("bucket").agg(F.shuffle(F.collect_list("row"), F.lit(seed)).alias("rows"))
    placed = lists.join(F.broadcast(first), "bucket").select("shard", "first_slot", F.posexplode("rows").alias("pos", "row"))
    out = placed.select("row.*", (F.col("first_slot") + F.col("pos")).cast("long").alias("slot"), "shard")
    out.sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def plan(docs: DataFrame, shards: int = SHARDS, seed: int = SEED, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """Writes the shards to the shared folder; doc_id, size, text_crc32, law, shard, slot, grown_shard of every row written."""
    path = f"{shared_dir(docs.sparkSession)}/shards-{uuid.uuid4().hex}"
    write(docs, path, shards, seed, bucket_bytes)
    schema = T.StructType([f for f in docs.schema if f.name in ("doc_id", "text")]).add("slot", T.LongType()).add("shard", T.IntegerType())
    rows = docs.sparkSession.read.schema(schema).parquet(path).select("*", *[c.alias(n) for n, c in digests().items()])
    grown = F.greatest(F.col("shard"), F.when(_pick(shards + 1, seed) == shards, F.lit(shards)).otherwise(-1))
    return rows.select(
        "doc_id", F.col("_s_size").alias("size"), F.col("_s_crc").alias("text_crc32"), F.lit("key").alias("law"),
        "shard", "slot", grown.cast("int").alias("grown_shard"),
    )


def op8_sharding(spark, sf_dir: str) -> DataFrame:
    return plan(read(spark, sf_dir, "documents"))
