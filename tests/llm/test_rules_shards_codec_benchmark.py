import hashlib
import math
import re
import zlib
from collections import Counter

import pytest
from cases import EDGES, SCHEMA, edges
from tgengine.llm import decontaminate, quality_rules, sentencepiece_codec, sharding
from tgengine.llm.common import read

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def base(text):
    text = text or ""
    w = WORD.findall(text)
    three = Counter(zip(w, w[1:], w[2:]))
    places = {p for i in range(len(w) - 2) if three[tuple(w[i : i + 3])] > 1 for p in range(i, i + 3)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(places)


def check_counts(rows, docs):
    assert sorted(map(str, [(r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in rows])) == sorted(map(str, [(d, *base(t)) for d, t in docs]))
    for r in rows:
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
        assert not (r.base_failed and r.kept)


def test_base_counts(spark, sf_dir):
    docs = read(spark, sf_dir, "documents")
    check_counts(quality_rules.op2_quality_rules(spark, sf_dir).collect(), [(r.doc_id, r.text) for r in docs.collect()])


def test_rules_bear_edges(spark):
    labels = spark.createDataFrame([(4, 1, 0), (4, 0, 0), (None, 1, 0), (99, 1, 0)], "doc_id long, quality int, toxic int")
    check_counts(quality_rules.report(edges(spark), labels).collect(), [(r[0], r[1]) for r in EDGES])
    none = spark.createDataFrame([], SCHEMA)
    assert quality_rules.report(none, labels.limit(0)).count() == 0
    kept = quality_rules.keep_good(edges(spark, "n_words kept stratum"), labels)
    assert kept.columns == [*SCHEMA.replace(" long", "").replace(" string", "").split(", "), "n_words", "kept", "stratum"]
    assert {r.doc_id for r in kept.collect()} <= {None, 4, 5, 6, 12}


def test_binomial_tail_is_exact(spark):
    for n, k, p in ((50, 0, 0.01), (50, 3, 0.1), (3000, 12, 0.01), (20000, 150, 0.01), (5, 9, 0.3)):
        want = sum(math.exp(math.lgamma(n + 1) - math.lgamma(j + 1) - math.lgamma(n - j + 1) + j * math.log(p) + (n - j) * math.log1p(-p)) for j in range(min(k, n) + 1))
        got = spark.createDataFrame([(k, n)], "k long, n long").select(quality_rules.binomial_below("k", "n", p)).first()[0]
        assert math.isclose(got, min(1, want), rel_tol=1e-6, abs_tol=1e-300)


def test_cutoffs_reject_few_good_texts_and_catch_junk(spark):
    good = [(i, " ".join(f"w{(i * 7 + j * j) % 991}" for j in range(60))) for i in range(3000)]
    junk = [(10_000 + i, " ".join(f"w{(i * 7 + j * j) % 991}###" for j in range(60))) for i in range(50)]
    docs = spark.createDataFrame([(i, t, "en") for i, t in good + junk], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, int(i < 10_000)) for i, _ in good + junk], "doc_id long, quality int")
    rows = quality_rules.report(docs, labels).collect()
    assert sum(not r.kept and not r.base_failed for r in rows if r.doc_id < 10_000) <= 0.05 * 3000
    assert not any(r.kept for r in rows if r.doc_id >= 10_000)


def measures_of(t):
    w = WORD.findall(t or "")
    n, chars = len(w), sum(map(len, w))
    _, _, symbols, same, repeats = base(t)
    lines = [x for x in (t or "").split("\n") if WORD.search(x)]
    over = lambda a, b: None if not b else 100 * a / b
    capitals = sum("A" <= c <= "Z" or "À" <= c <= "Þ" and c != "×" for c in t or "")
    return {"symbols": over(symbols, n), "capitals": over(capitals, chars), "shouts": over((t or "").count("!"), n), "same_lines": over(same, len(lines)), "repeats": over(repeats, n), "long_words": over(chars, 40 * n)}


def level_by_force(rejected_at, n, strata):
    """The tightest level before the first whose exact test fails."""
    below = lambda k: sum(math.comb(n, j) * quality_rules.ALPHA**j * (1 - quality_rules.ALPHA) ** (n - j) for j in range(k + 1))
    for g, k in enumerate(rejected_at):
        if below(k) > quality_rules.DELTA / strata:
            return g - 1
    return len(rejected_at) - 1


@pytest.fixture(scope="module")
def good_texts(spark):
    d = "/root/testdata/sf0.1"
    good = read(spark, d, "labels").groupBy("doc_id").max("quality").filter("`max(quality)` = 1").select("doc_id")
    rows = read(spark, d, "documents").join(good, "doc_id", "left_semi").select("doc_id", "lang", "text").collect()
    out = {}
    for r in rows:
        n, *_, repeats = base(r.text)
        if not (n < 50 or 2 * repeats > n):
            m = measures_of(r.text)
            broken = [any(m[k] is not None and m[k] > c[g] for k, c in quality_rules.LEVELS.items()) for g in range(quality_rules.N_LEVELS)]
            out.setdefault(r.lang or "und", []).append(broken)
    return out


def test_cutoffs_equal_the_test_by_force(spark, good_texts):
    d = "/root/testdata/sf0.1"
    counted = quality_rules.with_counts(read(spark, d, "documents").select("doc_id", "text", quality_rules.stratum().alias("stratum")))
    got = {r.stratum: r for r in quality_rules.certified_cutoffs(counted, read(spark, d, "labels")).collect()}
    assert set(got) == set(good_texts)
    for lang, rows in good_texts.items():
        level = level_by_force([sum(r[g] for r in rows) for g in range(quality_rules.N_LEVELS)], len(rows), len(good_texts))
        assert {k: got[lang][k] for k in quality_rules.LEVELS} == {k: c[level] if level >= 0 else None for k, c in quality_rules.LEVELS.items()}
        assert level >= 0


def test_the_guarantee_holds_when_labels_are_drawn_again(good_texts):
    """Levels are chosen on drawn halves; over all texts more than a share alpha may be lost in a share delta of the draws only."""
    import random

    r = random.Random(4)
    bad = 0
    for _ in range(300):
        broken = False
        for rows in good_texts.values():
            # the share that a level loses grows with the level: good texts of this table lose little, so some are marked at random
            noisy = [[x or (g >= 4 and i % 11 == 0) for g, x in enumerate(row)] for i, row in enumerate(rows)]
            drawn = [r.choice(noisy) for _ in noisy]
            level = level_by_force([sum(x[g] for x in drawn) for g in range(quality_rules.N_LEVELS)], len(drawn), len(good_texts))
            broken |= level >= 0 and sum(x[level] for x in noisy) > quality_rules.ALPHA * len(noisy)
        bad += broken
    assert bad <= 300 * quality_rules.DELTA * 1.5


def test_rules_reject_beyond_the_base_rule(spark):
    """At the size of the correctness check one language has labels enough, and its junk goes."""
    d = "/root/testdata/sf0.01"
    rows = quality_rules.op2_quality_rules(spark, d).collect()
    lang = {r.doc_id: r.lang for r in read(spark, d, "documents").collect()}
    quality = {r.doc_id: r.quality for r in read(spark, d, "labels").collect()}
    gone = [r.doc_id for r in rows if not r.kept and not r.base_failed]
    assert gone and {lang[i] for i in gone} == {"en"}
    labelled = [quality[i] for i in gone if i in quality]
    assert sum(labelled) <= 0.1 * len(labelled)
    assert sum(quality.get(r.doc_id) == 1 and not r.kept and not r.base_failed for r in rows) <= quality_rules.ALPHA * sum(quality.values())


def test_shards(spark, sf_dir):
    docs = read(spark, sf_dir, "documents").unionByName(edges(spark).select("doc_id", "text", "lang", "source", "n_chars"))
    want = Counter((r.doc_id, len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode())) for r in docs.collect())
    for bucket in (32 << 20, 4000):
        rows = sharding.plan(docs, bucket_bytes=bucket).collect()
        assert Counter((r.doc_id, r.size, r.text_crc32) for r in rows) == want
        for s in range(16):
            assert sorted(r.slot for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))
        assert all(r.grown_shard in (r.shard, 16) for r in rows) and any(r.grown_shard == 16 for r in rows)
        assert len({r.shard for r in rows}) == 16
        assert len({(r.doc_id, r.shard) for r in rows}) == len({r.doc_id for r in rows})
    again = sharding.plan(docs.repartition(3), bucket_bytes=4000).collect()
    assert Counter(map(tuple, again)) == Counter(map(tuple, rows))
    assert [r.slot for r in sorted(rows, key=lambda r: str(r.doc_id))] != sorted(r.slot for r in rows)
    assert sharding.plan(docs.limit(0)).count() == 0


def test_shard_files(spark, tmp_path):
    sharding.write(edges(spark, "shard"), str(tmp_path / "out"), shards=4)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert Counter((r.doc_id, r.text) for r in back.collect()) == Counter((r[0], r[1]) for r in EDGES)


def test_shards_hold_whole_rows_in_slot_order(spark, tmp_path):
    import glob

    import pyarrow.parquet as pq

    hot = [(50, "hot " * 200, "en", "s", 1)] * 300 + [(51, f"{i} " * 150, "en", f"s{i}", i) for i in range(200)]
    docs = edges(spark).unionByName(spark.createDataFrame(hot, SCHEMA))
    orders = []
    for parts in (7, 2):
        path = str(tmp_path / f"out{parts}")
        sharding.write(docs.repartition(parts), path, shards=3, bucket_bytes=16_000)
        files = [(int(re.search(r"shard=(\d+)", f)[1]), pq.ParquetFile(f).read().to_pylist()) for f in glob.glob(f"{path}/shard=*/*.parquet")]
        rows = [(shard, *r.values()) for shard, part in files for r in part]
        assert Counter(r[1:-1] for r in rows) == Counter([*EDGES, *hot])
        assert len(files) > 12 and max(sum(r["doc_id"] == 50 for r in part) for _, part in files) < 100  # of 300 copies
        for _, part in files:  # each bucket is written as it was shuffled
            assert [r["slot"] for r in part] == list(range(part[0]["slot"], part[0]["slot"] + len(part)))
        for s in range(3):
            assert sorted(r[-1] for r in rows if r[0] == s) == list(range(sum(r[0] == s for r in rows)))
        orders.append(sorted(map(str, rows)))
    assert orders[0] == orders[1]


def test_the_sharding_query_reports_what_it_wrote(spark, monkeypatch):
    paths, write = [], sharding.write
    monkeypatch.setattr(sharding, "write", lambda docs, path, *a: (paths.append(path), write(docs, path, *a)))
    rows = sharding.plan(edges(spark, "extra")).collect()
    back = spark.read.parquet(*paths)
    assert back.columns == [*edges(spark, "extra").columns, "slot", "shard"]
    assert Counter((r.doc_id, len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode()), r.shard, r.slot) for r in back.collect()) == Counter((r.doc_id, r.size, r.text_crc32, r.shard, r.slot) for r in rows)


@pytest.fixture(scope="module")
def library():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=sentencepiece_codec.default_model())


def test_codec_equals_the_library(spark, sf_dir, library):
    docs = read(spark, sf_dir, "documents").select("doc_id", "text").unionByName(edges(spark).select("doc_id", "text"))
    want = Counter()
    for r in docs.collect():
        ids = library.encode(r.text or "")
        want[r.doc_id, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(library.decode(ids).encode()).hexdigest()] += 1
    clash = docs.withColumn("key", docs.doc_id).withColumn("chunk", docs.text).withColumn("ids", docs.doc_id)
    for head in (200_000, 300, 0):
        assert Counter(map(tuple, sentencepiece_codec.digests(clash, head=head).collect())) == want
    small = sentencepiece_codec.encode(edges(spark))
    assert Counter((r.doc_id, r.text) for r in sentencepiece_codec.decode(small).collect()) == Counter((r.doc_id, r.decoded) for r in small.collect())
    assert sentencepiece_codec.digests(docs.limit(0)).count() == 0


def test_chunks_are_segmented_once_each(spark, library):
    texts = [("a b a",), ("b  c\n\n d",), (" ▁▁a b▁",), ("",), ("   ",), ("a b a",), ("c c",)]
    model = sentencepiece_codec.default_model()
    counted = Counter(x for (t,) in texts for x in sentencepiece_codec.chunks(t))
    df = spark.createDataFrame(texts, "text string")
    assert {r.chunk: r.c for r in sentencepiece_codec.chunk_counts(df).collect()} == counted
    table = sentencepiece_codec.chunk_table(df, model)
    assert set(table) == {c for c, n in counted.items() if n > 1}
    assert set(sentencepiece_codec.chunk_table(df, model, 2)) < set(table)
    for size in (1000, 2):  # a table that is emptied all the time gives the same
        own = sentencepiece_codec.OwnTable(model, table, size)
        for (t,) in texts:
            c = sentencepiece_codec.chunks(t)
            want = library.encode(t)
            assert sentencepiece_codec.put_together(c, table, own.learn([c])) == (",".join(map(str, want)), len(want), library.decode(want))


DOC_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def hit_by_force(text, items):
    low = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
    d = DOC_WORD.findall(low(text))
    where, found = set(), set()
    for i, t in items:
        w = DOC_WORD.findall(low(t))
        size = min(13, len(w))
        ws = {tuple(w[k : k + size]) for k in range(len(w) - size + 1)} if w else set()
        for s in range(len(d) - size + 1):
            if size and tuple(d[s : s + size]) in ws:
                where |= set(range(s, s + size))
                found.add("" if i is None else str(i))
    sha = hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()
    return len(d), len(where), len(found), sha, len(where) > 0 and 20 * len(where) >= len(d)


@pytest.mark.parametrize("limit", [400_000, 30])
def test_benchmark_hits(spark, sf_dir, limit):
    items = read(spark, sf_dir, "benchmark").select("item_id", "text").limit(12)
    more = spark.createDataFrame([(None, None), (77, ""), (78, "And1 WORD2"), (79, "word0 and0 word1 and1"), (79, "word0 and0 word1 and1"), (None, "line one")], items.schema)
    items = items.unionByName(more)
    known = [(r.item_id, r.text) for r in items.collect()]
    docs = read(spark, sf_dir, "documents").unionByName(edges(spark)).select("doc_id", "text")
    planted = spark.createDataFrame([(900 + k, f"x {t} y" + " z" * 40 * k) for k, (_, t) in enumerate(known[:5])], docs.schema)
    docs = docs.filter("length(text) < 4000 or text is null").unionByName(planted)
    want = Counter((r.doc_id, *hit_by_force(r.text, known)) for r in docs.collect())
    assert Counter(map(tuple, decontaminate.report(docs, items, limit=limit).collect())) == want
    assert any(k[-1] for k in want)


def test_clean_keeps_rows_and_columns(spark):
    items = spark.createDataFrame([(1, "word0 and0 word1 and1")], "item_id long, text string")
    out = decontaminate.clean(edges(spark, "n_words contaminated"), items)
    assert out.columns[-2:] == ["n_words", "contaminated"]
    assert {r.doc_id for r in out.collect()} == {1, 2, 3, 7, 8, 9, 10, 11, 13} | {r.doc_id for r in out.collect() if r.doc_id in (None, 4, 5, 6, 12)}
    assert decontaminate.clean(edges(spark), items.limit(0)).count() == len(EDGES)
    assert decontaminate.report(edges(spark).limit(0), items).count() == 0
