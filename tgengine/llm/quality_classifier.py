"""Quality classifier learned from positives and unlabelled texts.

A logistic model over text statistics is fitted by minimising the non-negative unbiased risk: with class prior `pi`, the
risk is pi * R(positives as 1) + max(0, R(unlabelled as 0) - pi * R(positives as 0)); while the second part is below zero
its gradient is followed backwards, so that it can't be driven negative. Trusted positives are labelled 1; the unlabelled
texts are training rows taken whatever their label. No label 0 is used.

The prior is estimated from the two samples alone: a first model tells positives from unlabelled texts on one half, and on the
other half every score gives a bound of it, the share of unlabelled texts above the score over the share of positives above
it. The bound is tight where only positives lie above, so the least one is taken, with an allowance for chance at few texts.

Statistics: how often each pair of character classes follows one another, immediate word repetition, distinct words,
repeated lines and lengths. At most `SAMPLE` positives and as many unlabelled texts are taken, those with the smallest
hashes of doc_id; of rows with one id the longest text counts (of equally long ones the first in order). Null and empty texts are scored as the empty text; null ids teach nothing; several labels of one id
count by their highest; without positives or unlabelled texts every score is 1/2. Other columns are ignored.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, read, remainder

SAMPLE = 6000
CUTOFF = 0.3
STEPS = 600
RATE = 0.05
DECAY = 1e-4
KINDS = 18
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def _kinds() -> np.ndarray:
    """Class of each code point below 0x250; those above are 17."""
    k = np.full(0x250, 16, dtype=np.uint16)
    for c in range(0x250):
        ch = chr(c)
        if ch.islower():
            k[c] = 0
        elif ch.isupper():
            k[c] = 1
        elif ch.isdigit():
            k[c] = 2
        elif ch == "\n":
            k[c] = 4
        elif ch.isspace():
            k[c] = 3
    for at, chars in enumerate((",.;:", "!?", "#", "*", "$", "%", "&", "|", "<>", "'\"()", "-_/"), start=5):
        for ch in chars:
            k[ord(ch)] = at
    return k


TABLE = _kinds()
N_FEATURES = KINDS * KINDS + 7


def features(text: str | None) -> np.ndarray:
    out = np.zeros(N_FEATURES, dtype=np.float32)
    text = text or ""
    c = np.frombuffer(text.encode("utf-32-le"), dtype=np.uint32)
    kind = np.where(c < 0x250, TABLE[np.minimum(c, 0x24F)], 17).astype(np.int32)
    if len(kind) > 1:
        out[: KINDS * KINDS] = np.sqrt(np.bincount(kind[:-1] * KINDS + kind[1:], minlength=KINDS * KINDS) / (len(kind) - 1))
    w = WORD.findall(text)
    lines = [x for x in text.split("\n") if x]
    n = max(1, len(w))
    pairs = set(zip(w, w[1:]))
    out[KINDS * KINDS :] = (
        1.0, np.log1p(len(w)) / 10, len(set(w)) / n, sum(map(str.__eq__, w, w[1:])) / n, len(pairs) / n,
        1 - len(set(lines)) / max(1, len(lines)), np.log1p(sum(map(len, w)) / n),
    )
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -50, 50)))


def risk(w: np.ndarray, p: np.ndarray, u: np.ndarray, prior: float) -> tuple[float, float]:
    """The two parts: positives as 1, and unlabelled texts as 0 less the positives' share of them."""
    fp, fu = p @ w, u @ w
    return prior * float(np.logaddexp(0, -fp).mean()), float(np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean())


def gradient(w: np.ndarray, p: np.ndarray, u: np.ndarray, prior: float) -> np.ndarray:
    """Of the risk; while its second part is below zero, that part's gradient backwards."""
    sp, su = _sigmoid(p @ w), _sigmoid(u @ w)
    second = u.T @ su / len(u) - prior * (p.T @ sp) / len(p)
    if risk(w, p, u, prior)[1] < 0:
        return -second
    return second - prior * (p.T @ (1 - sp)) / len(p)


def _descend(slope, size: int, steps: int) -> np.ndarray:
    w, m, v = np.zeros(size), np.zeros(size), np.zeros(size)
    for t in range(1, steps + 1):
        g = slope(w) + DECAY * w
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= RATE * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return w


def estimate_prior(p: np.ndarray, u: np.ndarray, steps: int = 200) -> float:
    """Share of positives among the unlabelled texts, from scaled statistics of both."""
    half = lambda x: (x[0::2], x[1::2])
    (p1, p2), (u1, u2) = half(p), half(u)
    if not len(p2) or not len(u2):
        return 0.5
    w = _descend(lambda w: u1.T @ _sigmoid(u1 @ w) / len(u1) - p1.T @ (1 - _sigmoid(p1 @ w)) / len(p1), p.shape[1], steps)
    sp, su = np.sort(p2 @ w), np.sort(u2 @ w)
    above_p = 1 - np.arange(len(sp)) / len(sp)
    above_u = 1 - np.searchsorted(su, sp) / len(su)
    chance = np.sqrt(np.log(4 / 0.1) / 2) * (1 / np.sqrt(len(sp)) + 1 / np.sqrt(len(su)))
    at = np.argmin((above_u + chance) / above_p)
    return float(min(0.99, max(0.01, above_u[at] / above_p[at])))


def fit(pos: np.ndarray, unl: np.ndarray, prior: float | None = None, steps: int = STEPS) -> np.ndarray:
    """Weights, the scale of each statistic folded in. `prior` None: estimated."""
    if not len(pos) or not len(unl):
        return np.zeros(N_FEATURES)
    scale = 1 / np.maximum(1e-3, np.sqrt((unl.astype(np.float64) ** 2).mean(axis=0)))
    p, u = pos * scale, unl * scale
    prior = estimate_prior(p, u) if prior is None else prior
    return _descend(lambda w: gradient(w, p, u, prior), N_FEATURES, steps) * scale


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> np.ndarray:
    taught = labels.filter(F.col("doc_id").isNotNull() & (F.col("quality") == 1) & (remainder(5) != 0)).select("doc_id").distinct()
    h = F.xxhash64(F.lit(7), F.col("doc_id"))
    positives = taught.select("doc_id", F.lit(1).alias("taught")).orderBy(h, "doc_id").limit(sample)
    h = F.xxhash64(F.lit(8), F.col("doc_id"))
    others = docs.filter(F.col("doc_id").isNotNull() & (remainder(5) != 0)).select("doc_id").distinct().select("doc_id", F.lit(0).alias("taught")).orderBy(h, "doc_id").limit(sample)
    chosen = F.broadcast(positives.unionByName(others))
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(chosen, "doc_id")
    # one row of each id, however often it stands in the table
    longest = F.max(F.struct(F.length("text").alias("n"), "text")).alias("x")
    rows = rows.groupBy("doc_id", "taught").agg(longest).select("doc_id", "taught", "x.text")

    def run(batches):
        for b in batches:
            yield {"doc_id": b["doc_id"], "taught": b["taught"], "x": [features(t).tobytes() for t in b["text"]]}

    got = sorted(map_rows(rows, "doc_id long, taught int, x binary", run).collect(), key=lambda r: r["doc_id"] * 2654435761 % 4294967296)
    sides = [[bytes(r["x"]) for r in got if r["taught"] == k] for k in (1, 0)]
    pos, unl = (np.frombuffer(b"".join(s), dtype=np.float32).reshape(-1, N_FEATURES) for s in sides)
    return fit(pos, unl)


def scores(texts: list[str | None], w: np.ndarray) -> list[float]:
    x = np.stack([features(t) for t in texts])
    return (1 / (1 + np.exp(-np.clip(x @ w, -50, 50)))).tolist()


def report(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    w = learn(docs, labels, sample)

    def run(batches):
        for b in batches:
            s = scores(b["text"], w)
            yield {"doc_id": b["doc_id"], "held_out": b["held_out"], "score": s, "predicted": [int(x >= CUTOFF) for x in s]}

    return map_rows(docs.select("doc_id", (remainder(5) == 0).alias("held_out"), "text"), "doc_id long, held_out boolean, score double, predicted int", run)


def op3_quality_classifier(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))
