"""Language identification with string kernels.

The kernel of two texts is the number of character n-grams (n = 1, 2, 3; hashed to `DIMS` buckets) present in both, over
the root of the product of their numbers of n-grams. Landmarks drawn from the training sample give Nyström features, and
one ridge regression per language, each against the rest, is fitted on them. Since the kernel is linear in presence,
scoring a batch is one matrix product of its presence matrix with the landmarks' weights, followed by the norm.

The fit takes at most `PER_LANG` labelled documents of each language, of which at most `LANDMARKS` become landmarks: those
with the smallest hashes of doc_id, at any size of input. Texts without a letter, and null texts, are 'und' with score 0;
null languages and ids teach nothing, and of rows with one id and language the longest text does; with nothing to learn from, every text is 'und'. Ties go to the language first in
order. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import map_rows, quoted, read, remainder

DIMS = 1 << 14
PER_LANG = 300
LANDMARKS = 60
RIDGE = 1e-2
SHARPNESS = 6.0
#: Slices in which a language is ranked first.
SLICES = 64
#: Share of the texts with a language that may lie below twice the evidence a text needs in the pipeline.
TAIL = 0.005
ROWS = 64


def ngrams(text: str) -> np.ndarray:
    """The buckets of the text's n-grams, distinct and in order."""
    c = np.frombuffer(text.lower().encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
    found = np.zeros(DIMS, dtype=bool)
    x = np.zeros_like(c)
    for n in range(3):
        if len(c) <= n:
            break
        x = x[: len(c) - n] * np.uint64(0x100000001B3) + c[n:]
        found[((x ^ np.uint64(n)) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(50)] = True
    return np.flatnonzero(found)


def has_letter(text: str | None) -> bool:
    return text is not None and any(map(str.isalpha, text[:400])) or text is not None and any(map(str.isalpha, text))


def presence(grams: list[np.ndarray]) -> np.ndarray:
    p = np.zeros((len(grams), DIMS), dtype=np.float32)
    for i, g in enumerate(grams):
        p[i, g] = 1
    return p


def fit(grams: list[np.ndarray], langs: list[str], order: list[int]) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Languages, weights [DIMS + 1 x languages], and how many of a language's landmarks hold each bucket, as a share. `order`: rows by preference as landmarks."""
    names = sorted(set(langs))
    taken = {n: 0 for n in names}
    marks = []
    for i in order:
        if taken[langs[i]] < LANDMARKS:
            taken[langs[i]] += 1
            marks.append(i)
    size = np.sqrt(np.maximum(1, np.array([len(g) for g in grams], dtype=np.float64)))
    land = presence([grams[i] for i in marks]) / size[marks, None].astype(np.float32)
    values, vectors = np.linalg.eigh((land @ land.T).astype(np.float64))
    good = values > 1e-6 * values.max()
    root = vectors[:, good] / np.sqrt(values[good])
    near = np.vstack([presence(grams[i : i + 256]) @ land.T for i in range(0, len(grams), 256)]) / size[:, None]
    feats = near @ root
    target = np.where(np.array(langs)[:, None] == np.array(names)[None, :], 1.0, -1.0)
    bias = target.mean(axis=0)
    w = np.linalg.solve(feats.T @ feats + RIDGE * len(grams) / max(1, len(marks)) * np.eye(feats.shape[1]), feats.T @ (target - bias))
    held = np.vstack([presence([grams[i] for i in marks if langs[i] == n]).mean(axis=0) for n in names]).T
    return names, np.vstack([(land.T @ (root @ w)).astype(np.float32), bias[None, :].astype(np.float32)]), held.astype(np.float32)


def sample(docs: DataFrame, per_lang: int) -> DataFrame:
    """doc_id and lang of at most `per_lang` training rows of each language, one row of each id and language.

    Each of `SLICES` slices of a language gives its first `per_lang` before they meet, so that no task ranks a whole language."""
    rows = docs.filter((remainder(4) != 2) & F.col("lang").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", "lang", F.xxhash64("doc_id").alias("h"))
    rows = rows.withColumn("slice", F.pmod(F.col("h"), F.lit(SLICES))).distinct()
    first = Window.partitionBy("lang", "slice").orderBy("h", "doc_id")
    some = rows.withColumn("n", F.row_number().over(first)).filter(F.col("n") <= per_lang).drop("n")
    best = Window.partitionBy("lang").orderBy("h", "doc_id")
    return some.withColumn("n", F.row_number().over(best)).filter(F.col("n") <= per_lang).select("doc_id", "lang", "h")


def learn(docs: DataFrame, per_lang: int = PER_LANG):
    ids = sample(docs.select("doc_id", "lang"), per_lang).withColumnRenamed("lang", "taught")
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "lang").join(F.broadcast(ids), "doc_id").filter("lang = taught")
    # one row of each id and language, however often it stands in the table
    rows = rows.groupBy("doc_id", "lang", "h").agg(F.max(F.struct(F.length("text").alias("n"), "text")).alias("x")).select("x.text", "lang", "h")

    def run(batches):
        for b in batches:
            yield {"lang": b["lang"], "h": b["h"], "grams": [ngrams(t).tolist() for t in b["text"]]}

    got = map_rows(rows, "lang string, h long, grams array<int>", run, ROWS).collect()
    got = sorted((r for r in got if r["grams"]), key=lambda r: (r["h"], r["lang"], len(r["grams"])))
    if not got:
        return [], np.zeros((DIMS + 1, 0), dtype=np.float32), np.zeros((DIMS, 0), dtype=np.float32)
    return fit([np.array(r["grams"]) for r in got], [r["lang"] for r in got], list(range(len(got))))


def classify(texts: list[str | None], names: list[str], weights: np.ndarray, held: np.ndarray) -> list[tuple[str, float, float]]:
    """Language, score, and evidence: the share of the text's n-grams that a landmark of the language holds, over its landmarks."""
    grams = [ngrams(t or "") for t in texts]
    if not names:
        return [("und", 0.0, 0.0)] * len(texts)
    size = np.maximum(1, np.array([len(g) for g in grams], dtype=np.float32))
    x = presence(grams)
    s = x @ weights[:-1] / np.sqrt(size)[:, None] + weights[-1]
    e = np.exp(SHARPNESS * (s - s.max(axis=1, keepdims=True)))
    best, rows = s.argmax(axis=1), np.arange(len(texts))
    p, found = e[rows, best] / e.sum(axis=1), (x @ held)[rows, best] / size
    return [(names[k], float(x), float(f)) if has_letter(t) else ("und", 0.0, 0.0) for t, k, x, f in zip(texts, best, p, found)]


def predict(docs: DataFrame, carry: list[str], schema: str, model) -> DataFrame:
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            out = classify(b["text"], *sent.value)
            yield {c: b[c] for c in carry} | {"lang_pred": [o[0] for o in out], "score": [o[1] for o in out], "evidence": [o[2] for o in out]}

    return map_rows(docs, f"{schema}, lang_pred string, score double, evidence double", run, ROWS)


def report(docs: DataFrame, per_lang: int = PER_LANG) -> DataFrame:
    """doc_id, held_out, lang_pred, score, evidence of every row."""
    rows = docs.select("doc_id", (remainder(4) == 2).alias("held_out"), "text")
    return predict(rows, ["doc_id", "held_out"], "doc_id long, held_out boolean", learn(docs, per_lang))


def limit(docs: DataFrame, model, tail: float = TAIL) -> float:
    """Half the evidence that all but a share `tail` of the rows with a language reach, over all of them; 0 where nothing was learned. It is counted in a thousand steps."""
    if not model[0]:
        return 0.0
    rows = docs.filter((remainder(4) != 2) & F.col("lang").isNotNull()).select("lang", "text")
    scored = predict(rows, ["lang"], "lang string", model).filter("lang = lang_pred")
    counts = {r["step"]: r["count"] for r in scored.groupBy(F.floor(F.col("evidence") * 1000).cast("int").alias("step")).count().collect()}
    total, held = sum(counts.values()), 0
    for step in sorted(counts):
        held += counts[step]
        if held > tail * total:
            return step / 2000
    return 0.0


def keep_known(docs: DataFrame, per_lang: int = PER_LANG) -> DataFrame:
    """The rows whose language is recognised, with their own columns only: those with a letter whose evidence is no lower than `limit`. With nothing to learn from, all rows with a letter stay."""
    model = learn(docs, per_lang)
    least = limit(docs, model)
    whole = F.struct(*[F.col(quoted(c)) for c in docs.columns])
    rows = docs.select(whole.alias("row"), "text")

    def run(batches):
        # the rows themselves pass through as they are; only their texts are read
        for b in batches:
            for at in range(0, b.num_rows, ROWS):
                part = b.slice(at, ROWS)
                texts = part.column(1).to_pylist()
                out = classify(texts, *sent.value) if sent.value[0] else [("any" if has_letter(t) else "und", 1.0, 1.0) for t in texts]
                keep = [name != "und" and found >= least for name, _, found in out]
                yield pa.RecordBatch.from_arrays([part.column(0).filter(pa.array(keep))], names=["row"])

    sent = docs.sparkSession.sparkContext.broadcast(model)
    return rows.mapInArrow(run, T.StructType([rows.schema["row"]])).select("row.*")


def op10_language_id(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "documents"))
