"""Near duplicates by Order MinHash.

The k-mers of a text are its runs of five words, each labelled with its occurrence number. For each of `SKETCHES` hash
functions the two labelled k-mers with the smallest hashes are taken and kept in text order; the pair is one sketch. Two
texts agree in a sketch the likelier the more k-mers they share in the same order. Since links are judged by the distinct
k-mers, a text written twice or with its parts moved can be a link and yet share few of these sketches: for `SETS` of the hash
functions, the two distinct k-mers with the smallest hashes, in order of the hashes, are a sketch too, by sets alone.

Equal texts are one node. Nodes that agree in a sketch share a bucket and are candidates if they are of similar size and their
one-bit minimum hashes don't rule out a Jaccard similarity of `FLOOR` of their five-word runs. In buckets of up to `SMALL` nodes
all pairs are candidates. The members of a larger bucket are compared, by joins on the bucket and a salt, so that no task holds it
whole, with `PIVOTS` members drawn by hash of the text in each of `ROUNDS` rounds (so the buckets of a group draw much the same
ones, and its links stay few); then every pair with a member outside the bucket's largest component, and not connected yet, is a
candidate too. So no link that joins two classes is left out, while links within a class need not all be found. In larger
buckets, where two texts have up to `FEW` distinct k-mers, the hashes of these tell their similarity before their texts are fetched.

Candidates are verified by alignment: k-mers that each text holds once, in the same order in both, are anchors; the words between
two anchors are aligned within a band of edits. Two texts are linked if the words matched in order are `LEAST` or more of the
longer text, or, for parts moved or repeated, if the Jaccard similarity of the distinct five-word runs is `LEAST` or more. Links
of a Jaccard similarity below `FLOOR` are not looked for. At `FLOOR` two nodes agree in none of the sketches with probability
0.03, at 0.5 with 0.01, at 0.6 with 0.001 (`recall` measures it against all pairs).
Links are closed to classes by union-find within tasks, round by round, as long as the links of a task fall to fewer; what
is left is closed by label propagation with pointer jumping. Each round is a written table.

Words are what stands between ASCII blanks, in lower case.
Texts without a word, and null texts, are classes of their own row (class_id: their doc_id). A class is named by its
smallest doc_id; null ids sort first only where no other exists. Repeated rows share a class; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import remove
from .common import map_rows, quoted, read, stored

K = 5
SKETCHES = 16
SETS = 8
LEAST = 0.8
FLOOR = 0.45
SMALL = 12
BAND = 48
PIVOTS = 8
#: Rounds of pivots before the rest of a large bucket is compared pair by pair.
ROUNDS = 1
#: Members of a large bucket that share a salt where they meet its pivots.
SALTED = 4096
#: Where a bucket's pairs are compared one by one, its members are dealt to blocks of `BLOCK`, and the unsettled ones to strips
#: of `STRIP`; a block and a strip meet in one task, whatever the size of the bucket.
BLOCK, STRIP = 2048, 1 << 14
#: One-bit minimum hashes: `ROWS` hash functions of 32 bins each, four 64-bit values in all. At a similarity of `FLOOR` 70 of
#: the 256 bits differ, 106 with five standard deviations (3 pairs in ten million are lost); texts of fewer than `SHORT`
#: k-mers leave bins empty and aren't filtered.
ROWS = 8
UNLIKE, SHORT = 106, 64
#: Distinct k-mers up to which a node carries the 32-bit hashes of all.
FEW = 256
#: Links that one task closes by union-find.
CLOSED = 250_000
#: Hash values computed at a time.
CELLS = 1 << 20
#: So many keys, of 16 bytes, may be broadcast; beyond, they are joined by shuffle.
MAX_BROADCAST = 2_000_000
_rng = np.random.default_rng(5)
MULTIPLY = _rng.integers(1, 1 << 63, SKETCHES, dtype=np.uint64) | np.uint64(1)
ADD = _rng.integers(0, 1 << 63, SKETCHES, dtype=np.uint64)

_TOP = np.uint64(2**64 - 1)
_NUMBER = np.arange(SKETCHES, dtype=np.uint64)
_EDGES = np.arange(32, dtype=np.uint64) << np.uint64(59)


def words(text: str | None) -> list[bytes]:
    return (text or "").lower().encode("utf-8", "surrogatepass").split()


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


class Hasher:
    """Word -> 64-bit hash, the same on every machine; a bounded table saves repeated work."""

    def __init__(self, size: int = 200_000):
        self.known, self.size = {}, size

    def __call__(self, w: list[bytes]) -> np.ndarray:
        from hashlib import blake2b

        known = self.known
        new = set(w).difference(known)
        if len(known) + len(new) > self.size:
            known.clear()
            new = set(w)
        for x in new:
            known[x] = int.from_bytes(blake2b(x, digest_size=8).digest(), "little")
        return np.fromiter(map(known.__getitem__, w), dtype=np.uint64, count=len(w))


def kmers(h: np.ndarray) -> np.ndarray:
    """Hashes of the k-mers in text order; a shorter text is one k-mer."""
    n = max(1, len(h) - K + 1)
    out = np.zeros(n, dtype=np.uint64)
    for i in range(min(K, len(h))):
        out = _mix(out * np.uint64(0x100000001B3) + h[i : i + n])
    return out


def labelled(x: np.ndarray) -> tuple[int, np.ndarray]:
    """Number of distinct k-mers; each k-mer's hash combined with the number of its earlier occurrences."""
    order = np.argsort(x, kind="stable")
    s = x[order]
    new = np.r_[True, s[1:] != s[:-1]]
    if new.all():
        return len(x), x
    start = np.maximum.accumulate(np.where(new, np.arange(len(s)), 0))
    count = np.empty(len(x), dtype=np.uint64)
    count[order] = (np.arange(len(s)) - start).astype(np.uint64)
    return int(new.sum()), np.where(count == 0, x, _mix(x + count * np.uint64(0xD6E8FEB86659FD93)))


def bits(x: np.ndarray) -> np.ndarray:
    """The one-bit minimum hashes of a text's k-mers; an empty bin takes the next bin's."""
    out = np.zeros(ROWS * 32, dtype=bool)
    for r in range(ROWS):
        v = np.sort(x * MULTIPLY[-1 - r] ^ ADD[r])
        at = np.searchsorted(v, _EDGES)
        low = v[np.where(at < len(v), at, 0)] * np.uint64(0x9E3779B97F4A7C15)
        out[32 * r : 32 * r + 32] = low >> np.uint64(63)
    return np.packbits(out).view(np.int64)


def short_hashes(x: np.ndarray) -> np.ndarray:
    """The distinct 32-bit hashes of the k-mers."""
    return np.unique((x >> np.uint64(32)).astype(np.uint32)).view(np.int32)


def smallest(x: np.ndarray, functions: int) -> np.ndarray:
    """Places of the two k-mers with the smallest hashes, by hash function; of a single k-mer twice its own."""
    place = np.zeros((functions, 2), dtype=np.int64)
    some = max(1, CELLS // len(x))  # hash functions at a time
    for i in range(0, functions if len(x) > 1 else 0, some):
        to = min(functions, i + some)
        v = x * MULTIPLY[i:to, None] + ADD[i:to, None]
        v ^= v >> np.uint64(29)
        v *= np.uint64(0x9E3779B97F4A7C15)
        rows = np.arange(len(v))
        place[i:to, 0] = v.argmin(axis=1)
        v[rows, place[i:to, 0]] = _TOP
        place[i:to, 1] = v.argmin(axis=1)
    return place


def _pair(x: np.ndarray, place: np.ndarray, number: np.ndarray) -> np.ndarray:
    return _mix(x[place[:, 0]] * np.uint64(3) + _mix(x[place[:, 1]]) + number)


def sketch(h: np.ndarray) -> tuple[int, np.ndarray]:
    """Number of distinct k-mers; the sketches, those by sets, then the one-bit hashes, as 64-bit values."""
    each = kmers(h)
    few = bits(each)
    distinct, x = labelled(each)
    place = smallest(x, SKETCHES)
    kinds, first = (x, place[:SETS]) if distinct == len(x) else (u := np.unique(each), smallest(u, SETS))
    sets = _pair(kinds, first, _NUMBER[:SETS] + np.uint64(SKETCHES))
    place.sort(axis=1)
    return distinct, np.r_[_pair(x, place, _NUMBER).view(np.int64), sets.view(np.int64), few]


def align(a: list, b: list, band: int = BAND) -> list[tuple[int, int, int]] | None:
    """Matched runs (start in a, start in b, length) with the fewest insertions and deletions; None beyond `band` of them."""
    n, m = len(a), len(b)
    codes: dict[str, int] = {}
    x = np.array([codes.setdefault(w, len(codes)) for w in a], dtype=np.int64)
    y = np.array([codes.setdefault(w, len(codes)) for w in b], dtype=np.int64)
    unlike: dict[int, np.ndarray] = {}

    def reach(i: int, d: int) -> int:
        """How far the match from (i, i - d) goes on diagonal d."""
        if d not in unlike:
            lo, hi = max(0, d), min(n, m + d)
            unlike[d] = np.append(np.flatnonzero(x[lo:hi] != y[lo - d : hi - d]) + lo, max(lo, hi))
        return int(unlike[d][np.searchsorted(unlike[d], i)]) if i < unlike[d][-1] else max(i, 0)

    far = {1: 0}
    trace = []
    for e in range(band + 1):
        now = {}
        for d in range(-e, e + 1, 2):
            if d < -m or d > n:
                continue
            i = far.get(d + 1, -1) if d == -e or (d != e and far.get(d - 1, -1) < far.get(d + 1, -1)) else far.get(d - 1, -1) + 1
            if i < 0 or i > n or i - d < 0 or i - d > m:
                continue
            now[d] = reach(i, d)
            if now[d] >= n and now[d] - d >= m:
                trace.append(now)
                return _runs(trace, n, m)
        trace.append(now)
        far = {**far, **now}
    return None


def _runs(trace: list[dict[int, int]], n: int, m: int) -> list[tuple[int, int, int]]:
    runs, i, d = [], n, n - m
    for e in range(len(trace) - 1, -1, -1):
        best = (0, d) if e == 0 else max(((trace[e - 1][p] + (p == d - 1), p) for p in (d - 1, d + 1) if p in trace[e - 1] and trace[e - 1][p] + (p == d - 1) <= i), default=(0, d))
        if i > best[0]:
            runs.append((best[0], best[0] - d, i - best[0]))
        if e:
            i, d = trace[e - 1][best[1]], best[1]
    return runs[::-1]


def _between(a: np.ndarray, b: np.ndarray) -> int:
    """Words matched in order between two anchors, within the band."""
    n = min(len(a), len(b))
    if not n:
        return 0
    off = np.flatnonzero(a[:n] != b[:n])
    head = int(off[0]) if len(off) else n
    a, b, n = a[head:], b[head:], n - head
    if not n:
        return head
    off = np.flatnonzero(a[::-1][:n] != b[::-1][:n])
    tail = int(off[0]) if len(off) else n
    a, b = a[: len(a) - tail], b[: len(b) - tail]
    if not len(a) or not len(b) or not np.isin(a, b).any():
        return head + tail
    runs = align(a.tolist(), b.tolist())
    return head + tail + (sum(r for _, _, r in runs) if runs else 0)


def _rising(values: np.ndarray) -> np.ndarray:
    """Places of a longest rising subsequence."""
    if len(values) < 2 or (np.diff(values) > 0).all():
        return np.arange(len(values))
    from bisect import bisect_left

    ends, at, before = [], [], []
    for i, v in enumerate(values.tolist()):
        k = bisect_left(ends, v)
        before.append(at[k - 1] if k else -1)
        if k == len(ends):
            ends.append(v)
            at.append(i)
        else:
            ends[k], at[k] = v, i
    out, i = [], at[-1]
    while i >= 0:
        out.append(i)
        i = before[i]
    return np.array(out[::-1])


def _once_only(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values that occur once, and where."""
    value, at, n = np.unique(x, return_index=True, return_counts=True)
    return value[n == 1], at[n == 1]


class Text:
    """Word hashes of a text, its distinct k-mers, and those that it holds once."""

    def __init__(self, ids: np.ndarray):
        self.ids, self.kmers = ids, kmers(ids)
        self.distinct = np.unique(self.kmers)
        self._single = None

    def single(self) -> tuple[np.ndarray, np.ndarray]:
        if self._single is None:
            self._single = _once_only(self.kmers)
        return self._single


def matched(x: Text, y: Text) -> int:
    """Words matched in order: those of the anchors, and between them within the band."""
    a, b = x.ids, y.ids
    (va, pa), (vb, pb) = x.single(), y.single()
    _, ia, ib = np.intersect1d(va, vb, assume_unique=True, return_indices=True)
    i, j = pa[ia], pb[ib]
    order = np.argsort(i)
    i, j = i[order], j[order]
    keep = _rising(j)
    i, j = i[keep], j[keep]
    if len(a) < K or len(b) < K or not len(i):
        return _between(a, b)
    # neighbouring anchors on one diagonal are one run
    first = np.r_[True, (np.diff(i) != 1) | (np.diff(j) != 1)]
    last = np.r_[first[1:], True]
    total, ea, eb = 0, 0, 0
    for si, sj, ti in zip(i[first].tolist(), j[first].tolist(), (i[last] + K).tolist()):
        over = max(ea - si, eb - sj, 0)  # anchors may overlap the run before on another diagonal
        si, sj = si + over, sj + over
        if si >= ti:
            continue
        total += _between(a[ea:si], b[eb:sj]) + ti - si
        ea, eb = ti, sj + ti - si
    return total + _between(a[ea:], b[eb:])


def similarity(x: Text, y: Text) -> float:
    """Share of the longer text's words that are matched in order, or the Jaccard similarity of the five-word runs, whichever links; 0 if neither does."""
    small, large = sorted((len(x.distinct), len(y.distinct)))
    short, long = sorted((len(x.ids), len(y.ids)))
    if small < LEAST * large and short < LEAST * long:
        return 0.0
    common = len(np.intersect1d(x.distinct, y.distinct, assume_unique=True))
    exact = common / (small + large - common)
    if exact < FLOOR:
        return 0.0
    share = matched(x, y) / long if short >= LEAST * long else 0.0
    return share if share >= LEAST else exact if exact >= LEAST else 0.0


def nodes(docs: DataFrame) -> DataFrame:
    """doc_id, key (of the text), n (distinct k-mers), w (words), sketches, bits, few (hashes, null beyond `FEW`); key is null without words."""

    def run(batches):
        hasher = Hasher()
        for b in batches:
            n, s, key, few, size = [], [], [], [], []
            for t, k in zip(b["text"], b["key"]):
                w = words(t)
                h = hasher(w) if w else None
                d, x = sketch(h) if w else (0, ())
                few.append(short_hashes(kmers(h)) if 0 < d <= FEW else None)
                n.append(d)
                size.append(len(w))
                s.append(list(x))
                key.append(k if w else None)
            yield {"doc_id": b["doc_id"], "key": key, "n": n, "w": size, "sketches": [x[: SKETCHES + SETS] for x in s], "bits": [x[SKETCHES + SETS :] for x in s], "few": few}

    rows = docs.select("doc_id", F.unhex(F.md5("text")).alias("key"), "text")
    return map_rows(rows, "doc_id long, key binary, n int, w int, sketches array<long>, bits array<long>, few array<int>", run)


def _likely(a: str, b: str):
    """Whether two nodes that agree in a sketch can be a link, by their sizes and one-bit hashes."""
    close = lambda c: f"least({a}.{c}, {b}.{c}) >= {LEAST}D * greatest({a}.{c}, {b}.{c})"
    unlike = " + ".join(f"bit_count({a}.bits[{i}] ^ {b}.bits[{i}])" for i in range(ROWS // 2))
    return F.expr(f"({close('n')} or {close('w')}) and ({a}.n < {SHORT} or {b}.n < {SHORT} or {unlike} <= {UNLIKE})")


def _alike(a: str, b: str):
    """Whether the k-mers' hashes, where both nodes carry them, allow a link; one hash may be lost to a collision."""
    enough = f"(1 + {FLOOR}D) * (size(array_intersect({a}.few, {b}.few)) + 1) >= {FLOOR}D * (size({a}.few) + size({b}.few))"
    return F.expr(f"{a}.few is null or {b}.few is null or {enough}")


def _once(a: str, b: str):
    """Whether sketch `i` is the first in which two nodes agree."""
    return F.expr(f"array_position(zip_with({a}.sketches, {b}.sketches, (x, y) -> x = y), true) = i + 1")


def _pairs(a: str, b: str):
    return F.least(F.col(f"{a}.key"), F.col(f"{b}.key")).alias("a"), F.greatest(F.col(f"{a}.key"), F.col(f"{b}.key")).alias("b")


def verified(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """The pairs (a, b) of keys whose texts are similar enough, with their similarity."""
    pairs = stored(pairs.distinct())
    keys = pairs.select(F.col("a").alias("key")).union(pairs.select("b")).distinct()
    few = pairs.count() * 2 <= MAX_BROADCAST
    texts = docs.select(F.unhex(F.md5("text")).alias("key"), "text").join(F.broadcast(keys) if few else keys, "key", "left_semi")
    texts = stored(texts.groupBy("key").agg(F.first("text").alias("text")))
    sides = pairs.join(texts.withColumnsRenamed({"key": "a", "text": "ta"}), "a").join(texts.withColumnsRenamed({"key": "b", "text": "tb"}), "b")

    def run(batches):
        hasher = Hasher()
        for x in batches:
            split = {t: Text(hasher(words(t))) for t in {*x["ta"], *x["tb"]}}
            s = [similarity(split[p], split[q]) for p, q in zip(x["ta"], x["tb"])]
            keep = [i for i, v in enumerate(s) if v >= LEAST]
            yield {"a": [x["a"][i] for i in keep], "b": [x["b"][i] for i in keep], "similarity": [s[i] for i in keep]}

    found = stored(map_rows(sides, "a binary, b binary, similarity double", run, 64))
    _drop(pairs, texts)
    return found


def _drop(*tables: DataFrame) -> None:
    """Removes stored tables that nothing reads any more."""
    for t in tables:
        for path in {f.rsplit("/", 1)[0] for f in t.inputFiles()}:
            remove(t.sparkSession, path)


def _stars(links: DataFrame, parts: int) -> DataFrame:
    """(a, b): b is a key of a task's links, a the smallest key that they connect it to; a itself is left out. Connects what the links connect."""

    def run(batches):
        up: dict[bytes, bytes] = {}

        def root(k: bytes) -> bytes:
            top = k
            while up[top] != top:
                top = up[top]
            while up[k] != top:
                up[k], k = top, up[k]
            return top

        for x in batches:
            for a, b in zip(x["a"], x["b"]):
                up.setdefault(a, a)
                up.setdefault(b, b)
                a, b = root(a), root(b)
                if a != b:
                    up[max(a, b)] = min(a, b)
        keys = [k for k in up if up[k] != k]
        for i in range(0, len(keys), 4096):
            some = keys[i : i + 4096]
            yield {"a": [root(k) for k in some], "b": some}

    rows = links.select("a", "b")
    return stored(map_rows(rows.coalesce(1) if parts == 1 else rows.repartition(parts), "a binary, b binary", run, 4096))


def components(links: DataFrame) -> DataFrame:
    """key, label: the smallest key connected to each key that has a link. `links`: stored."""
    few, n = links, links.count()
    while True:
        parts = max(1, -(-n // CLOSED))
        less = _stars(few, parts)
        if few is not links:
            _drop(few)
        few, before, n = less, n, less.count()
        if parts == 1:  # every key beside its label, but the labels themselves
            label = stored(few.select(F.col("b").alias("key"), F.col("a").alias("label")).union(few.select("a", "a").distinct()))
            _drop(few)
            return label
        if n > 0.8 * before:
            break
    label = _spread(few)
    _drop(few)
    return label


def _spread(links: DataFrame) -> DataFrame:
    """The components by label propagation, for links that no longer fall to fewer within tasks."""
    edges = stored(links.select(F.col("a").alias("key"), F.col("b").alias("other")).union(links.select("b", "a")).distinct())
    label = stored(edges.groupBy("key").agg(F.least(F.min("other"), F.col("key")).alias("label")))
    while True:
        near = edges.join(label.withColumnRenamed("key", "other"), "other").groupBy("key").agg(F.min("label").alias("near"))
        step = label.join(near, "key").select("key", F.least("label", "near").alias("next"), F.col("label").alias("was"))
        jump = label.select(F.col("key").alias("next"), F.col("label").alias("over"))
        new = stored(step.join(jump, "next", "left").select("key", F.least("next", F.coalesce("over", "next")).alias("label"), "was"))
        moved = new.filter("label <> was").limit(1).count()
        _drop(label)
        label = new.drop("was")
        if not moved:
            _drop(edges)
            return label


def links(docs: DataFrame, found: DataFrame) -> DataFrame:
    """Verified links (a, b, similarity) between different texts that connect whatever all links connect; `found`: stored nodes."""
    texts = stored(found.filter("key is not null").groupBy("key").agg(F.first(F.struct("n", "w", "sketches", "bits", "few")).alias("x")).select("key", "x.*"))
    buckets = texts.select("key", F.posexplode("sketches").alias("i", "value")).select("key", "i", F.xxhash64("i", "value").alias("bucket"))
    sizes = buckets.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).filter("size > 1")
    shared = stored(buckets.join(sizes.hint("merge"), "bucket"))
    node = F.struct("key", "n", "w", "sketches", "bits", F.when(F.col("size") > SMALL, F.col("few")).alias("few")).alias("node")
    shared = stored(shared.join(texts.hint("merge"), "key").select("bucket", "i", "size", node))
    small = shared.filter(F.col("size") <= SMALL).groupBy("bucket", "i").agg(F.collect_list("node").alias("all"))
    small = small.select("i", F.explode(F.expr("flatten(transform(all, (x, i) -> transform(slice(all, i + 2, size(all)), y -> struct(x, y))))")).alias("p")).select("i", "p.x", "p.y").filter(_once("x", "y") & _likely("x", "y"))
    done = verified(small.select(*_pairs("x", "y")), docs)
    members = shared.filter(F.col("size") > SMALL)
    if members.limit(1).count() == 0:
        return done
    salts = F.ceil(F.col("size") / SALTED).cast("int")
    members = members.withColumn("salt", F.pmod(F.xxhash64("node.key", F.lit(3)), salts).cast("int"))
    every = F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt")
    # in the last round all pairs of the rest meet, in cells of a block and a strip; two unsettled members meet once
    blocks, strips = (F.ceil(F.col("size") / n).cast("int") for n in (BLOCK, STRIP))
    cell, parts = ("bucket", "block", "strip"), int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    for turn in range(ROUNDS + 1):
        label = components(done)
        named = members.withColumn("key", F.col("node.key")).join(label, "key", "left").select("bucket", "i", "size", "salt", "node", F.coalesce("label", "key").alias("label"))
        named = stored(named)
        # the component with most members in the bucket is settled; all others are compared
        main = named.groupBy("bucket", "size", "label").agg(F.count(F.lit(1)).alias("n")).groupBy("bucket", "size").agg(F.max(F.struct("n", "label")).alias("m")).select("bucket", F.col("m.label").alias("main"), every)
        rest = named.join(main, ["bucket", "salt"]).filter("label <> main").select("bucket", "i", "size", "salt", "main", F.col("node").alias("x"), F.col("label").alias("lx"))
        others = named.select("bucket", "size", F.col("node").alias("y"), F.col("label").alias("ly"))
        if turn < ROUNDS:
            draws = [F.min(F.struct(F.xxhash64("y.key", F.lit(turn * PIVOTS + p)).alias("h"), "y", "ly")).alias(f"p{p}") for p in range(PIVOTS)]
            drawn = others.groupBy("bucket", "size").agg(*draws)
            drawn = drawn.select("bucket", "size", F.explode(F.array(*[F.struct(f"p{p}.y", f"p{p}.ly") for p in range(PIVOTS)])).alias("p")).select("bucket", "p.y", "p.ly", every)
            more = rest.join(drawn, ["bucket", "salt"])
        else:
            rest = rest.withColumn("strip", F.pmod(F.xxhash64("x.key", F.lit(6)), strips).cast("int"))
            rest = rest.withColumn("block", F.explode(F.sequence(F.lit(0), blocks - 1))).drop("size", "salt")
            others = others.withColumn("block", F.pmod(F.xxhash64("y.key", F.lit(4)), blocks).cast("int"))
            others = others.withColumn("strip", F.explode(F.sequence(F.lit(0), strips - 1))).drop("size")
            more = rest.repartition(parts, *cell).join(others.repartition(parts, *cell), list(cell)).filter("ly = main or x.key < y.key")
        more = more.filter("lx <> ly").filter(_likely("x", "y")).filter(_alike("x", "y"))
        if turn == ROUNDS:
            more = more.filter(_once("x", "y"))
        more = verified(more.select(*_pairs("x", "y")), docs)
        before, done = done, stored(done.unionByName(more))
        _drop(before, more, named, label)
    return done


def _classes(found: DataFrame, linked: DataFrame) -> DataFrame:
    """key, copies, first (doc_id), label, n_links, similarity of every text with words."""
    per_text = found.filter("key is not null").groupBy("key").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("copies"))
    ends = linked.select(F.col("a").alias("key"), F.col("b").alias("other"), "similarity").union(linked.select("b", "a", "similarity"))
    own = ends.groupBy("key").agg(F.count_distinct("other").alias("n_links"), F.max("similarity").alias("similarity"))
    return per_text.join(components(linked), "key", "left").join(own, "key", "left").withColumn("label", F.coalesce("label", "key"))


def classes(docs: DataFrame) -> DataFrame:
    """doc_id, class_id, class_size (rows), n_links (verified links of the row's text to other texts), similarity (the highest of these, 1.0 for a text with copies, null for a single one) for every row."""
    found = stored(nodes(docs.select("doc_id", "text")))
    named = stored(_classes(found, links(docs.select("text"), found)))
    groups = named.groupBy("label").agg(F.min("first").alias("class_id"), F.sum("copies").alias("class_size"))
    like = F.when(F.col("copies") > 1, F.lit(1.0)).otherwise(F.col("similarity")).alias("similarity")
    of_text = stored(named.join(groups, "label").select("key", "class_id", "class_size", "n_links", like))
    out = found.select("doc_id", "key").join(of_text, "key", "left")
    return out.select(
        "doc_id", F.when(F.col("key").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("class_size", F.lit(1)).cast("long").alias("class_size"),
        F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), "similarity",
    )


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each class: of its rows with the smallest doc_id, the first in order of all columns that can be compared; wordless rows all stay.

    Rows are joined on text and doc_id together, so that copies with ids of their own lie apart, and rows that agree in both are reduced before they move."""
    rows = docs.select(F.struct(*[F.col(quoted(c)) for c in docs.columns]).alias("row"))
    rows = rows.select("row", F.unhex(F.md5("row.text")).alias("key"), F.col("row.doc_id").alias("first"))
    found = stored(nodes(docs.select("doc_id", "text")))
    named = _classes(found, links(docs.select("text"), found))
    best = named.groupBy("label").agg(F.min(F.struct(F.col("first").isNull().alias("none"), "first", "key")).alias("b")).select("b.key", "b.first")
    best = stored(best)
    same = (rows["key"] == best["key"]) & rows["first"].eqNullSafe(best["first"])
    kept = rows.join(best, same, "left_semi")
    order = F.struct(*[F.col("row." + quoted(f.name)) for f in docs.schema if "map<" not in f.dataType.simpleString()])
    one = kept.groupBy("key", "first").agg(F.min_by("row", order).alias("row")).select("row.*")
    return one.unionByName(docs.filter(wordless("text")))


def wordless(col: str):
    """Whether a text holds no word, as `words` has it: ASCII blanks only, or null."""
    return ~F.coalesce(F.col(col), F.lit("")).rlike(r"[^\x20\x09-\x0D]")


def recall(docs: DataFrame, sample_key: int = 100) -> tuple[int, int]:
    """(links found within a class, links): all rows of every class and rows with ids divisible by `sample_key` as queries, against brute force. For measuring on small tables only."""
    rows = [(r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect()]
    hasher = Hasher()
    texts = {i: Text(hasher(words(t))) for i, t in rows if i is not None and words(t)}
    of = {r["doc_id"]: r["class_id"] for r in classes(docs).collect()}
    got = total = 0
    for q in (i for i in texts if i % sample_key == 0):
        for i, t in texts.items():
            if i != q and similarity(texts[q], t) >= LEAST:
                total += 1
                got += of[q] == of[i]
    return got, total


def op5_near_duplicates(spark, sf_dir: str) -> DataFrame:
    return classes(read(spark, sf_dir, "documents"))
