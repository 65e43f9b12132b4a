"""Benchmark decontamination as a prefix-filtered set join.

Items and documents are taken as words. A window is 13 consecutive words of an item, or the whole item where it is
shorter. Words are ordered by rarity: first the number of documents that hold a benchmark word is counted over all
documents. A window must be contained whole, so its necessary prefix is its one rarest word; windows with a word that no
document holds can't occur. The prefix index maps a word to the windows it stands for, with its place in them. For each
prefix word in a document, the place gives where the window would begin (positional bound) and its length whether it fits
(length bound); then the words are compared, exactly.

The index travels to the tasks only while the benchmark has at most `MAX_WINDOWS` pairs of a window and an item. A larger one
is cut into parts of that size; each part is one pass over the documents, and hits are united by row.

Null and empty texts have no words and no hits. Null item ids count as the id ''. Empty benchmarks hit nothing; repeated
items and rows are judged alike; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_rows, quoted, read, stored

WINDOW = 13
MAX_WINDOWS = 400_000
SHARE = 20
#: Lower-cases A-Z and blanks the ASCII characters that aren't letters or digits; other bytes stay.
TABLE = bytes(c + 32 if 0x41 <= c <= 0x5A else c if c >= 0x80 or 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A else 0x20 for c in range(256))


def words(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(TABLE).split()


def windows(text: str | None, size: int = WINDOW) -> list[tuple[bytes, ...]]:
    w = words(text)
    return [tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))] if w else []


def item_windows(items: DataFrame, size: int = WINDOW) -> DataFrame:
    """window (words joined by a blank) and item, distinct."""

    def run(batches):
        for b in batches:
            made = {(b" ".join(w), "" if i is None else str(i)) for i, t in zip(b["item_id"], b["text"]) for w in windows(t, size)}
            yield {"window": [m[0] for m in made], "item": [m[1] for m in made]}

    return map_rows(items.select("item_id", "text"), "window binary, item string", run).distinct()


def word_documents(docs: DataFrame, vocabulary: frozenset[bytes]) -> dict[bytes, int]:
    """In how many documents each word of the vocabulary stands; at most one row a word comes back."""
    sent = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches):
        seen: Counter = Counter()
        for b in batches:
            for t in b["text"]:
                seen.update(sent.value.intersection(words(t)))
        if seen:
            yield {"word": list(seen), "n": list(seen.values())}

    counted = map_rows(docs.select("text"), "word binary, n long", run).groupBy("word").agg(F.sum("n").alias("n"))
    return {bytes(r["word"]): r["n"] for r in counted.collect()}


def prefix_index(held: dict[tuple[bytes, ...], list[str]], documents: dict[bytes, int]) -> dict:
    """rarest word -> [(its place, window length, window, items)]."""
    index: dict[bytes, list] = {}
    for w, items in held.items():
        if all(x in documents for x in w):
            at = min(range(len(w)), key=lambda i: (documents[w[i]], w[i], i))
            index.setdefault(w[at], []).append((at, len(w), list(w), items))
    return index


def hits(doc: list[bytes], index: dict) -> tuple[set[int], set[str]]:
    """Places of the words that lie in an occurring window, and the items of these windows."""
    where: set[int] = set()
    items: set[str] = set()
    n = len(doc)
    for p, word in enumerate(doc):
        if word in index:
            for at, size, window, its in index[word]:
                s = p - at
                if s >= 0 and s + size <= n and doc[s : s + size] == window:
                    where.update(range(s, s + size))
                    items.update(its)
    return where, items


def _verdict(n_words: int, n_hit: int, items) -> dict:
    return {
        "n_words": n_words, "n_hit": n_hit, "n_items": len(items),
        "items_sha256": hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(),
        "contaminated": n_hit > 0 and SHARE * n_hit >= n_words,
    }


REPORT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def _parts(docs: DataFrame, items: DataFrame, size: int, limit: int):
    """Broadcast prefix indexes, each of at most `limit` windows."""
    spark = docs.sparkSession
    held = stored(item_windows(items, size))
    # (window, item) pairs are what travels: a passage that very many items share fills parts of its own
    n = held.count()
    parts = max(1, -(-n // limit))
    if parts > 1:
        parts *= 2  # hashing isn't even
    held = held.withColumn("part", F.pmod(F.xxhash64("window", "item"), F.lit(parts)))
    for p in range(parts):
        mine: dict[tuple[bytes, ...], list[str]] = {}
        for r in held.filter(F.col("part") == p).toLocalIterator():
            mine.setdefault(tuple(bytes(r["window"]).split()), []).append(r["item"])
        known = word_documents(docs, frozenset(x for w in mine for x in w)) if mine else {}
        yield parts, spark.sparkContext.broadcast(prefix_index(mine, known))


def report(docs: DataFrame, items: DataFrame, size: int = WINDOW, limit: int = MAX_WINDOWS) -> DataFrame:
    """One row per document: n_words, n_hit, n_items, items_sha256, contaminated."""
    return _judged(docs.select("doc_id", "text"), ["doc_id"], REPORT, items, size, limit)


def _judged(docs: DataFrame, carry: list[str], schema: str, items: DataFrame, size: int, limit: int) -> DataFrame:
    parts = _parts(docs, items, size, limit)
    many, index = next(parts)
    if many == 1:

        def run(batches):
            for b in batches:
                out = []
                for t in b["text"]:
                    w = words(t)
                    where, its = hits(w, index.value)
                    out.append(_verdict(len(w), len(where), its))
                yield {c: b[c] for c in carry} | {k: [o[k] for o in out] for k in out[0]}

        return map_rows(docs, schema, run)
    rows = stored(docs.withColumn("_d_at", F.monotonically_increasing_id()))
    found = None
    for index in [index, *(i for _, i in parts)]:

        def some(batches, index=index):
            for b in batches:
                got = [(r, *hits(words(t), index.value)) for r, t in zip(b["_d_at"], b["text"])]
                got = [g for g in got if g[1]]
                yield {"_d_at": [g[0] for g in got], "where": [list(g[1]) for g in got], "its": [list(g[2]) for g in got]}

        one = stored(map_rows(rows.select("_d_at", "text"), "_d_at long, where array<int>, its array<string>", some))
        found = one if found is None else found.unionByName(one)
    united = found.groupBy("_d_at").agg(F.array_distinct(F.flatten(F.collect_list("where"))).alias("where"), F.array_distinct(F.flatten(F.collect_list("its"))).alias("its"))

    def last(batches):
        for b in batches:
            out = [_verdict(len(words(t)), len(w or ()), set(i or ())) for t, w, i in zip(b["text"], b["where"], b["its"])]
            yield {c: b[c] for c in carry} | {k: [o[k] for o in out] for k in out[0]}

    return map_rows(rows.join(united, "_d_at", "left"), schema, last)


def clean(docs: DataFrame, items: DataFrame, size: int = WINDOW, limit: int = MAX_WINDOWS) -> DataFrame:
    """The rows that aren't contaminated, with their own columns only."""
    whole = F.struct(*[F.col(quoted(c)) for c in docs.columns])
    rows = docs.select(whole.alias("row"), "text")
    parts = _parts(docs, items, size, limit)
    many, index = next(parts)
    if many == 1:

        def run(batches):
            # the rows themselves pass through as they are; only their texts are read
            for b in batches:
                for at in range(0, b.num_rows, 256):
                    part = b.slice(at, 256)
                    keep = []
                    for t in part.column(1).to_pylist():
                        w = words(t)
                        keep.append(not _verdict(len(w), *hits_of(w, index.value))["contaminated"])
                    yield pa.RecordBatch.from_arrays([part.column(0).filter(pa.array(keep))], names=["row"])

        return rows.mapInArrow(run, T.StructType([rows.schema["row"]])).select("row.*")
    marked = stored(rows.withColumn("_d_row", F.monotonically_increasing_id()))
    judged = _judged(marked.select("_d_row", "text"), ["_d_row"], "_d_row long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean", items, size, limit)
    return marked.join(judged.filter("not contaminated").select("_d_row"), "_d_row", "left_semi").select("row.*")


def hits_of(w: list[bytes], index: dict) -> tuple[int, set[str]]:
    where, its = hits(w, index)
    return len(where), its


def op7_decontaminate(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))
