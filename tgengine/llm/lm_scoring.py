"""Language-model scoring with a log-bilinear model.

A token's context vector is the sum of its two predecessors' vectors, each scaled by a position vector; its score is the
product with the token's output vector plus a bias. The vocabulary is the `VOCABULARY` most frequent tokens and one class
for all others. Each task trains on all its training tokens by noise-contrastive estimation (noise: the unigram model,
shared within a minibatch), from the unigram model as start; the tasks' parameters are averaged by their tokens.

Since scores are sums over the two positions, the normaliser of every context is one matrix product of the exponentials:
log-probabilities of tokens are three lookups and exactly normalised. A token of the class for others costs the class and
its add-one share among all others, by its count in all training texts.

Counts cover every training token. Up to `HEAD` of the most frequent tokens travel to the tasks (a fixed bound; longer tokens are
named by a digest, so their size is bounded too); all others are joined by shuffle. Null and empty texts are one end
token; null ids are hashed as the empty text; without training texts N and V are 0 and every score is that of an unseen
token. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from math import log, log10

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, read, remainder, stored

VOCABULARY = 1024
HEAD = 65_536
DIMS = 24
NOISE = 48
BATCH = 2048
RATE = 0.08
LONGEST = 64
FLUSH = 250_000
END = b""
LOWER = bytes(c + 32 if 0x41 <= c <= 0x5A else c for c in range(256))


def tokens(text: str | None) -> list[bytes]:
    """The words in lower case, then the end."""
    w = (text or "").encode().translate(LOWER).split()
    if w and max(map(len, w)) > LONGEST:
        w = [x if len(x) <= LONGEST else b"\x00" + hashlib.sha256(x).digest() for x in w]
    w.append(END)
    return w


def token_counts(docs: DataFrame) -> DataFrame:
    """token, c over all rows."""

    def run(batches):
        seen: Counter = Counter()
        for b in batches:
            for t in b["text"]:
                seen.update(tokens(t))
            if len(seen) > FLUSH:
                yield {"token": list(seen), "c": list(seen.values())}
                seen = Counter()
        yield {"token": list(seen), "c": list(seen.values())}

    return map_rows(docs.select("text"), "token binary, c long", run).groupBy("token").agg(F.sum("c").alias("c"))


def most_frequent(counts: DataFrame, head: int) -> list[tuple[bytes, int]]:
    """The most frequent tokens, by falling count: all whose count reaches the least bound that at most `head` tokens reach.

    Bounds keep the eleven leading bits of a count, so their histogram is small at any size of input, and no task sends
    more than its share of the `head` tokens.
    """
    low = F.expr("shiftleft(shiftright(c, greatest(length(bin(c)) - 11, 0)), greatest(length(bin(c)) - 11, 0))")
    held, least = 0, None
    for r in sorted(counts.groupBy(low.alias("low")).count().collect(), reverse=True):
        held += r["count"]
        if held > head:
            break
        least = r["low"]
    if least is None:
        return []
    rows = counts.filter(low >= least).collect()
    return sorted(((bytes(r["token"]), r["c"]) for r in rows), key=lambda x: (-x[1], x[0]))


class Model:
    """Parameters as one vector: input vectors (with a start), output vectors, biases, position vectors."""

    def __init__(self, size: int, theta: np.ndarray | None = None, unigram: np.ndarray | None = None):
        self.size, shapes = size, ((size + 1, DIMS), (size, DIMS), (size,), (2, DIMS))
        at = np.cumsum([0] + [int(np.prod(s)) for s in shapes])
        if theta is None:
            r = np.random.default_rng(3)
            theta = np.concatenate([r.normal(0, 0.1, at[1]), r.normal(0, 0.1, at[2] - at[1]), np.log(unigram), np.ones(2 * DIMS)]).astype(np.float32)
        self.theta = theta
        self.inp, self.out, self.bias, self.pos = (theta[a:b].reshape(s) for a, b, s in zip(at, at[1:], shapes))

    def train(self, ids: np.ndarray, one: np.ndarray, two: np.ndarray, unigram: np.ndarray, rng, seen: list[np.ndarray]) -> None:
        """One minibatch; `seen` holds the sums of squared gradients."""
        noise = np.minimum(np.searchsorted(np.cumsum(unigram), rng.random(NOISE)), self.size - 1)
        shift = np.log(NOISE * unigram).astype(np.float32)
        a, b = self.inp[one], self.inp[two]
        q = a * self.pos[0] + b * self.pos[1]
        true, fake = self.out[ids], self.out[noise]
        g = 1 / (1 + np.exp(np.clip((q * true).sum(1) + self.bias[ids] - shift[ids], -30, 30)))
        f = -1 / (1 + np.exp(-np.clip(q @ fake.T + self.bias[noise] - shift[noise], -30, 30)))
        dq = g[:, None] * true + f @ fake
        grads = [np.zeros_like(self.inp), np.zeros_like(self.out), np.zeros_like(self.bias), np.stack([(dq * a).sum(0), (dq * b).sum(0)])]
        _add(grads[0], one, dq * self.pos[0])
        _add(grads[0], two, dq * self.pos[1])
        _add(grads[1], ids, g[:, None] * q)
        np.add.at(grads[1], noise, f.T @ q)
        grads[2] += np.bincount(ids, g, self.size).astype(np.float32) + np.bincount(noise, f.sum(0), self.size).astype(np.float32)
        for p, x, s in zip((self.inp, self.out, self.bias, self.pos), grads, seen):
            x /= len(ids) ** 0.5
            s += x * x
            p += RATE * x / np.sqrt(s)

    def tables(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scores by predecessor (biases in the second), and the logarithm of every context's normaliser."""
        s1 = (self.inp * self.pos[0]) @ self.out.T
        s2 = (self.inp * self.pos[1]) @ self.out.T + self.bias
        m1, m2 = s1.max(1), s2.max(1)
        z = np.log(np.exp(s1 - m1[:, None]) @ np.exp(s2 - m2[:, None]).T + 1e-30) + m1[:, None] + m2[None, :]
        return s1.astype(np.float32), s2.astype(np.float32), z.astype(np.float32)


def _add(to: np.ndarray, rows: np.ndarray, what: np.ndarray) -> None:
    order = np.argsort(rows, kind="stable")
    r = rows[order]
    starts = np.flatnonzero(np.r_[True, r[1:] != r[:-1]])
    to[r[starts]] += np.add.reduceat(what[order], starts, axis=0)


def contexts(ids: np.ndarray, start: int) -> tuple[np.ndarray, np.ndarray]:
    return np.r_[start, ids[:-1]].astype(ids.dtype), np.r_[start, start, ids[:-2]].astype(ids.dtype)[: len(ids)]


def learn(docs: DataFrame, vocabulary: dict[bytes, int], unigram: np.ndarray) -> Model:
    """Trains on every row; the parameters of all tasks are averaged."""
    sent = docs.sparkSession.sparkContext.broadcast((vocabulary, unigram))

    def run(batches):
        known, p = sent.value
        model, rng, other, n, held, kept = Model(len(p), unigram=p), np.random.default_rng(11), len(p) - 1, 0, [], 0
        seen = [np.full_like(x, 1e-4) for x in (model.inp, model.out, model.bias, model.pos)]

        def flush():
            ids, one, two = (np.concatenate(x) for x in zip(*held))
            order = rng.permutation(len(ids))
            for at in range(0, len(ids), BATCH):
                pick = order[at : at + BATCH]
                model.train(ids[pick], one[pick], two[pick], p, rng, seen)
            held.clear()

        for b in batches:
            for t in b["text"]:
                w = tokens(t)
                ids = np.fromiter((known.get(x, other) for x in w), dtype=np.int16, count=len(w))
                held.append((ids, *contexts(ids, len(p))))
                n, kept = n + len(ids), kept + len(ids)
                if kept > 100_000:
                    flush()
                    kept = 0
        if held:
            flush()
        if n:
            yield {"n": [n], "theta": [model.theta.tolist()]}

    each = map_rows(docs.select("text"), "n long, theta array<float>", run)
    mean = each.select("n", F.posexplode("theta").alias("i", "v")).groupBy("i").agg((F.sum(F.col("v").cast("double") * F.col("n")) / F.sum("n")).alias("v"))
    got = mean.toPandas().sort_values("i")
    return Model(len(unigram), got["v"].to_numpy().astype(np.float32)) if len(got) else Model(len(unigram), unigram=unigram)


def report(docs: DataFrame, vocabulary: int = VOCABULARY, head: int = HEAD) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    spark = docs.sparkSession
    rows = docs.select("doc_id", (remainder(7) == 2).alias("held_out"), "text")
    training = rows.filter("not held_out")
    counts = stored(token_counts(training))
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    top = most_frequent(counts, head)
    known = {t: i for i, (t, _) in enumerate(top[:vocabulary])}
    rest, rest_kinds = total - sum(c for _, c in top[:vocabulary]), distinct - len(known)
    unigram = np.array([c for _, c in top[:vocabulary]] + [rest + 1], dtype=np.float64)
    unigram /= unigram.sum()
    model = learn(training, known, unigram)
    sent = spark.sparkContext.broadcast((known, {t: log10(c + 1) for t, c in top}, model.tables()))
    size = len(known)

    def run(batches):
        ids_of, logs, (s1, s2, z) = sent.value
        for b in batches:
            out = {k: [] for k in ("n_tokens", "n_head", "n_other", "logs", "other_logs", "model", "tail")}
            for t in b["text"]:
                w = tokens(t)
                ids = np.fromiter((ids_of.get(x, size) for x in w), dtype=np.int32, count=len(w))
                one, two = contexts(ids, size + 1)
                p = float((s1[one, ids] + s2[two, ids] - z[one, two]).sum(dtype=np.float64)) / log(10)
                got = [logs.get(x) for x in w]
                other = sum(g for g, i in zip(got, ids.tolist()) if g is not None and i == size)
                tail = Counter(x for x, g in zip(w, got) if g is None)
                n_tail = tail.total()
                for k, v in (("n_tokens", len(w)), ("n_head", len(w) - n_tail), ("n_other", int((ids == size).sum())), ("logs", sum(g for g in got if g is not None)), ("other_logs", other), ("model", p), ("tail", [{"token": x, "n": n} for x, n in tail.items()])):
                    out[k].append(v)
            yield {k: b[k] for k in ("row", "doc_id", "held_out")} | out

    schema = "row long, doc_id long, held_out boolean, n_tokens long, n_head long, n_other long, logs double, other_logs double, model double, tail array<struct<token: binary, n: int>>"
    parts = stored(map_rows(rows.withColumn("row", F.monotonically_increasing_id()), schema, run))
    tail = parts.select("row", F.explode("tail").alias("t")).select("row", "t.token", "t.n").join(counts, "token")
    tail = tail.groupBy("row").agg(F.sum("n").alias("tail_known"), F.sum(F.col("n") * F.log10(F.col("c") + 1)).alias("tail_logs"))
    joined = parts.drop("tail").join(tail, "row", "left").fillna(0, ["tail_known", "tail_logs"])
    return joined.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_head") + F.col("tail_known")).cast("long").alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (F.col("logs") + F.col("tail_logs") - F.col("n_tokens") * F.lit(log10(total + distinct + 1))).alias("base_score"),
        (F.col("model") + F.col("other_logs") + F.col("tail_logs") - F.col("n_other") * F.lit(log10(rest + rest_kinds + 1))).alias("score"),
    )


def op4_lm_scoring(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "documents"))
