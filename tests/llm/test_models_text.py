import re
from collections import Counter
from math import log10

import pytest
from cases import EDGES, SCHEMA, edges
from tgengine.llm import html_extract, language_id, license_scan, lm_scoring, near_dup, quality_classifier
from tgengine.llm.common import read

import corpus_pipeline


def test_extraction_keeps_the_article_only(spark):
    page = """<html><head><title>T</title><script>var x="</p>";</script></head><body><nav><ul><li><a href=x>Home</a></li></ul></nav><!-- ad --><div class="ad">Buy now</div>
    <div class="cookie-notice">We use cookies</div><article><h1>Head &amp; <b>line</b></h1><p>First\n  para&nbsp;graph.<br>Next<p>Short.</article>
    <section id="comments"><p>A reader's long comment that isn't part of it.</p></section><form>Sign up</form><footer>&copy; me</footer>"""
    assert html_extract.main_text(page) == "Head & line\nFirst para graph.\nNext\nShort."
    plain = "<body><ul><li><a>Menu</a><li><a>More</a></ul><p>" + "A long body text. " * 10 + "<p>" + "Another one here. " * 8 + "<div><a>Next</a></div>"
    assert html_extract.main_text(plain).startswith("A long body") and "Menu" not in html_extract.main_text(plain)
    for odd in (None, "", "<", "<p", "&am", "<!-- open", "<script>never closed", "</p></div>", "<p>" * 3000):
        assert html_extract.main_text(odd) in ("", "<", "&am")
    rows = [(1, "u", page), (1, "u", page), (None, None, None), (2, "v", "")]
    out = html_extract.report(spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, text int")).collect()
    assert Counter((r.page_id, r.n_chars) for r in out) == Counter({(1, 41): 2, (None, 0): 1, (2, 0): 1}) and all(r.n_chars == len(r.text) for r in out)


LONG = "A sentence of the article that is long enough to count as text of its own. "
LINKS = "".join(f"<p><a href=x>See also {i}</a></p>" for i in range(3))


def test_extraction_without_marks():
    nav = "".join(f"<div><a href=x>Topic {i}</a></div>" for i in range(12))
    page = f"<body>{nav}<h1>Title</h1><p>{LONG}</p>{LINKS}<p>{LONG}2</p><p>{LONG}3</p>{nav}<p>{LONG}elsewhere</p></body>"
    t = LONG.strip()
    assert html_extract.main_text(page).split("\n") == ["Title", t, "See also 0", "See also 1", "See also 2", f"{LONG}2", f"{LONG}3"]
    teaser = f"<body><article><p>Teaser of another text, not long at all, yet some sixty letters</p></article>{nav}<p>{LONG * 9}</p></body>"
    assert html_extract.main_text(teaser) == (LONG * 9).strip()


def test_extraction_keeps_links_of_the_article():
    page = f"<body><p><a href=x>Home</a></p><article><h1><a href=x>Linked head</a></h1><p>{LONG}</p><p><a href=x>Read on</a></p></article></body>"
    assert html_extract.main_text(page).split("\n") == ["Linked head", LONG.strip(), "Read on"]


@pytest.mark.parametrize("outer", ["form", "div class='content with-sidebar'", "div id=share", "header"])
def test_extraction_reads_what_holds_the_article(outer):
    end, t = f"</{outer.split()[0]}>", LONG.strip()
    assert html_extract.main_text(f"<body><p>Note.</p><{outer}><div class=menu>Menu</div><article><p>{LONG}</p></article>{end}</body>") == t
    assert html_extract.main_text(f"<body><{outer}><nav>Menu</nav><div class=promo><h2>Buy</h2></div><h1>Title</h1><p>{LONG}</p>{end}</body>") == f"Title\n{t}"
    assert html_extract.main_text(f"<body><p>{LONG}</p><{outer}><p>{LONG}other</p>{end}</body>") == t
    assert html_extract.main_text("<form>" * 3000 + LONG) in ("", t)


def test_extraction_keeps_text_whose_class_only_sounds_like_furniture():
    page = f"<body><article><h1>Head</h1><p class='entry-header'>{LONG}</p><p class=share-price>{LONG}2</p><div class='share-buttons'>Tweet</div><div class='related-posts'>More</div></article></body>"
    assert html_extract.main_text(page) == f"Head\n{LONG.strip()}\n{LONG}2"
    two = f"<body><article><h1>Head</h1><p>{LONG * 4}</p></article><article><p>Teaser</p></article><article><p>Other teaser</p></article></body>"
    assert html_extract.main_text(two) == f"Head\n{(LONG * 4).strip()}"


def test_extraction_by_regions_alone(spark):
    """With the marks renamed and all names taken away, regions and the elements that hold them still find the article."""
    import html

    equal = n = 0
    for r in read(spark, "/root/testdata/sf0.01", "pages").collect():
        body = r.html[r.html.index("<article>") + 9 :].partition("</article>")[0]
        blocks = (re.sub(r"\s+", " ", html.unescape(re.sub("<[^>]*>", "", b))).strip() for b in re.split(r"</?(?:p|h1|br)>", body))
        bare = re.sub(r"\s(?:class|id|role)=(\"[^\"]*\"|'[^']*')", "", r.html.replace("<article>", "<div>").replace("</article>", "</div>"))
        equal += html_extract.main_text(bare) == "\n".join(b for b in blocks if b)
        n += 1
    assert equal >= 0.9 * n


def test_extraction_is_linear_in_nesting():
    import time

    t = time.perf_counter()
    html_extract.main_text("<div>" * 60_000 + "</p>" * 20_000 + LONG)
    assert time.perf_counter() - t < 5


def test_extraction_of_all_pages(spark, sf_dir):
    import html

    for r, t in ((r, html_extract.main_text(r.html)) for r in read(spark, sf_dir, "pages").collect()):
        body = r.html[r.html.index("<article>") + 9 :].partition("</article>")[0]
        blocks = (re.sub(r"\s+", " ", html.unescape(re.sub("<[^>]*>", "", b))).strip() for b in re.split(r"</?(?:p|h1|br)>", body))
        assert t == "\n".join(b for b in blocks if b)


def test_language_on_held_out_rows(spark, sf_dir):
    known = {r.doc_id: r.lang for r in read(spark, sf_dir, "documents").collect()}
    out = language_id.op10_language_id(spark, sf_dir).collect()
    held = [r for r in out if r.held_out]
    assert sum(known[r.doc_id] == r.lang_pred for r in held) >= 0.97 * len(held) and all(0 <= r.score <= 1 for r in out)
    rows = language_id.report(edges(spark)).collect()
    assert len(rows) == len(EDGES) and {r.lang_pred for r in rows if r.doc_id in (1, 2, 3)} == {"und"}
    assert {r.lang_pred for r in rows if r.doc_id == 13} == {"und"}
    assert language_id.report(edges(spark).limit(0)).count() == 0
    assert {r.lang_pred for r in language_id.report(edges(spark).selectExpr("doc_id", "text", "cast(null as string) as lang")).collect()} == {"und"}
    kept = language_id.keep_known(edges(spark, "lang_pred score row").selectExpr("*", "1 as `a``b`"))
    assert kept.columns[-3:] == ["score", "row", "a`b"] and kept.count() >= len(EDGES) - 6


def test_quality_on_held_out_rows(spark, sf_dir):
    labels = {r.doc_id: r.quality for r in read(spark, sf_dir, "labels").collect()}
    out = [r for r in quality_classifier.report(read(spark, "/root/testdata/sf0.01", "documents"), read(spark, "/root/testdata/sf0.01", "labels")).collect()]
    labels = {r.doc_id: r.quality for r in read(spark, "/root/testdata/sf0.01", "labels").collect()}
    held = [r for r in out if r.held_out and r.doc_id in labels]
    assert sum(r.predicted == labels[r.doc_id] for r in held) >= 0.93 * len(held)
    none = read(spark, sf_dir, "labels").limit(0)
    rows = quality_classifier.report(edges(spark), none).collect()
    assert len(rows) == len(EDGES) and {r.score for r in rows} == {0.5}
    assert quality_classifier.report(edges(spark).limit(0), none).count() == 0


def test_nonnegative_risk_separates():
    import numpy as np

    r = np.random.default_rng(0)
    n = quality_classifier.N_FEATURES
    pos, neg = r.random((300, n)).astype("float32"), r.random((300, n)).astype("float32")
    pos[:, 3:], neg[:, 3:] = 0, 0
    pos[:, 2], neg[:, 2] = 1, 1
    pos[:, 0] += 1
    w = quality_classifier.fit(pos, np.vstack([r.permutation(pos)[:150], neg[:150]]), 0.5)
    assert (pos @ w > 0).mean() > 0.9 and (neg @ w < 0).mean() > 0.9


def test_risk_and_gradient_by_differences():
    import numpy as np

    r = np.random.default_rng(4)
    p, u = r.normal(size=(40, 6)) + 0.5, r.normal(size=(70, 6))
    for k, prior in enumerate((0.3, 0.3, 0.9)):
        w = r.normal(size=6) * (k + 1)
        by_hand = lambda w: (prior * np.mean([np.log1p(np.exp(-x @ w)) for x in p]), np.mean([np.log1p(np.exp(x @ w)) for x in u]) - prior * np.mean([np.log1p(np.exp(x @ w)) for x in p]))  # noqa: B023, E731
        assert np.allclose(quality_classifier.risk(w, p, u, prior), by_hand(w))
        goal = (lambda w: -by_hand(w)[1]) if by_hand(w)[1] < 0 else (lambda w: sum(by_hand(w)))  # noqa: B023
        slope = [(goal(w + h) - goal(w - h)) / 2e-6 for h in np.eye(6) * 1e-6]
        assert np.allclose(slope, quality_classifier.gradient(w, p, u, prior), atol=1e-6)


@pytest.mark.parametrize("prior", [0.2, 0.5, 0.85])
def test_prior_from_positives_and_unlabelled(prior):
    import numpy as np

    r = np.random.default_rng(6)
    make = lambda n, at: np.c_[r.normal(at, 1, (n, 3)), np.ones(n)]
    n = 4000
    u = np.vstack([make(int(n * prior), 1.6), make(n - int(n * prior), -1.6)])
    assert abs(quality_classifier.estimate_prior(make(3000, 1.6), r.permutation(u)) - prior) < 0.08


def test_kernel_and_ridge_by_force():
    """Scores of all training texts from the Nystroem features equal ridge regression on the kernel matrix itself."""
    import numpy as np

    r = np.random.default_rng(8)
    langs = [f"l{i % 3}" for i in range(24)]
    texts = [" ".join("".join(r.choice(list("abcdefgh")[int(x[1]) * 2 : int(x[1]) * 2 + 4], 5)) for _ in range(12)) for x in langs]
    sets = [set(language_id.ngrams(t).tolist()) for t in texts]
    kernel = np.array([[len(a & b) / np.sqrt(len(a) * len(b)) for b in sets] for a in sets])
    names, weights, held = language_id.fit([language_id.ngrams(t) for t in texts], langs, list(range(24)))
    target = np.where(np.array(langs)[:, None] == np.array(names)[None, :], 1.0, -1.0)
    bias = target.mean(axis=0)
    # all texts are landmarks, so the features span the kernel: alpha = (K + c I)^-1 y
    want = kernel @ np.linalg.solve(kernel + language_id.RIDGE * np.eye(24), target - bias) + bias
    p = language_id.presence([language_id.ngrams(t) for t in texts])
    got = p @ weights[:-1] / np.sqrt([[len(s)] for s in sets]) + weights[-1]
    share = np.array([[np.mean([len(a & b) / len(a) for b, x in zip(sets, langs) if x == n]) for n in names] for a in sets])
    assert np.allclose(p @ held / p.sum(axis=1, keepdims=True), share, atol=1e-5)
    assert np.allclose(got, want, atol=5e-3) and (got.argmax(1) == [names.index(x) for x in langs]).all()


def test_language_limit_rejects_what_no_language_taught(spark):
    d = "/root/testdata/sf0.01"
    docs = read(spark, d, "documents")
    odd = spark.createDataFrame([(10**7 + i, "".join(chr(0x4E00 + (i * 7 + j * 13) % 900) for j in range(200)), None, "s", 1) for i in range(5)], SCHEMA)
    kept = {r.doc_id for r in language_id.keep_known(docs.unionByName(odd.select(docs.columns))).collect()}
    assert kept >= {r.doc_id for r in docs.select("doc_id", "text").collect() if r.text and len(r.text) > 400} and not any(i >= 10**7 for i in kept)
    untaught = docs.selectExpr("doc_id", "text", "cast(null as string) as lang")
    assert language_id.keep_known(untaught).count() == sum(language_id.has_letter(r.text) for r in docs.collect())


def test_language_model(spark, sf_dir):
    docs = read(spark, sf_dir, "documents").unionByName(edges(spark)).select("doc_id", "text")
    rows = docs.collect()
    import zlib

    word = re.compile(r"[^\x20\x09-\x0D]+")
    low = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
    held = lambda d: zlib.crc32(("" if d is None else str(d)).encode()) % 7 == 2
    c = Counter()
    for r in rows:
        if not held(r.doc_id):
            c.update([*word.findall(low(r.text)), ""])
    total, kinds = c.total(), len(c)
    want = Counter()
    for r in rows:
        t = [*word.findall(low(r.text)), ""]
        want[r.doc_id, held(r.doc_id), len(t), sum(x in c for x in t), total, round(sum(log10((c[x] + 1) / (total + kinds + 1)) for x in t), 3)] += 1
    out = lm_scoring.report(docs, vocabulary=64, head=500).collect()
    assert Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 3)) for r in out) == want
    assert sum(r.score for r in out if r.held_out) > sum(r.base_score for r in out if r.held_out) and all(r.score < 0 for r in out)
    assert lm_scoring.report(docs.limit(0)).count() == 0


def test_language_model_is_normalised():
    import numpy as np

    m = lm_scoring.Model(7, unigram=np.full(7, 1 / 7))
    s1, s2, z = m.tables()
    p = np.exp(s1[3][None, :] + s2[5][None, :] - z[3, 5])
    assert abs(p.sum() - 1) < 1e-5


def as_text(w):
    return near_dup.Text(near_dup.Hasher()([x.encode() for x in w]))


def common_in_order(a, b):
    """Longest common subsequence, by the whole table."""
    row = [0] * (len(b) + 1)
    for x in a:
        before, row = row, [0]
        for j, y in enumerate(b):
            row.append(before[j] + 1 if x == y else max(before[j + 1], row[j]))
    return row[-1]


def link_by_force(a, b):
    """Whether two word lists are a link: exact word runs, and the exact longest common subsequence."""
    runs = [set(zip(*(w[i:] for i in range(5)))) if len(w) >= 5 else {tuple(w)} for w in (a, b)]
    jaccard = len(runs[0] & runs[1]) / len(runs[0] | runs[1])
    return jaccard >= 0.8 or jaccard >= near_dup.FLOOR and common_in_order(a, b) >= 0.8 * max(len(a), len(b))


def test_short_hash_filter_keeps_every_link(spark):
    base = [f"u{i}" for i in range(120)]
    texts = [base[:60] + [f"x{k}y{i}" for i in range(k)] + base[60 + k :] for k in range(0, 70, 2)] + [base + base[:9], base * 3]
    rows = []
    for k, w in enumerate(texts):
        x = as_text(w).kmers
        rows.append((k, near_dup.short_hashes(x).tolist() if len(set(x.tolist())) <= near_dup.FEW else None))
    few = spark.createDataFrame([*rows, (len(rows), None)], "k int, few array<int>")
    kept = {tuple(r) for r in few.alias("x").crossJoin(few.alias("y")).filter(near_dup._alike("x", "y")).select("x.k", "y.k").collect()}
    runs = [as_text(w).distinct for w in texts]
    exact = {(i, j): len(set(a) & set(b)) / len(set(a) | set(b)) for i, a in enumerate(runs) for j, b in enumerate(runs)}
    assert {p for p, s in exact.items() if s >= near_dup.FLOOR} <= kept
    assert not any(p in kept for p, s in exact.items() if s < near_dup.FLOOR - 0.03)
    assert {(len(rows), k) for k in range(len(rows) + 1)} <= kept  # without hashes nothing is ruled out


def test_matched_words_against_the_whole_table():
    import random

    r = random.Random(9)
    for n in (3, 30, 200, 400):
        for edits in (0, 1, n // 20, n // 8):
            a = [f"w{r.randrange(n)}" for _ in range(n)] if n % 3 else [f"w{i}" for i in range(n)]
            b = list(a)
            for _ in range(edits):
                at = r.randrange(len(b))
                b[at : at + r.randrange(2)] = [f"v{r.randrange(9)}"] * r.randrange(1, 3)
            got, want = near_dup.matched(as_text(a), as_text(b)), common_in_order(a, b)
            assert want * 0.97 - 1 <= got <= want


def test_near_duplicates_against_all_pairs(spark, sf_dir):
    docs = read(spark, sf_dir, "documents").select("doc_id", "text").collect()
    base = " ".join(f"u{i}" for i in range(200))
    near = [(5000 + k, base.replace(f"u{40 + 9 * k} ", f"changed{k} ")) for k in range(15)]  # one large bucket
    far = [(6000 + k, " ".join(f"u{i}" for i in range(60)) + " " + " ".join(f"v{k}x{i}" for i in range(140))) for k in range(15)]
    edited = [(6500 + k, " ".join(f"e{k}z{i}" if i % (14 + k) or j < 1 else f"new{k}q{i}" for i in range(260))) for k in range(10) for j in range(2)]
    edited = [(i + 100 * (n % 2), t) for n, (i, t) in enumerate(edited)]
    all_docs = [(r.doc_id, r.text) for r in docs] + near + far + edited + [(None, base), (7000, None), (7001, ""), (7002, " "), (7003, "a b"), (7003, "a b"), (7004, "\u00a0"), (7005, "\u3000\u00a0"), (7006, "\x1c"), (7007, "\u00a0")]
    split = [[w.decode() for w in near_dup.words(t)] for _, t in all_docs]
    label = list(range(len(all_docs)))

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    few = [Counter(w) for w in split]
    for i, a in enumerate(split):
        for j in range(i):
            b = split[j]
            if a and b and (a == b or (min(len(a), len(b)) >= 0.5 * max(len(a), len(b)) and (few[i] & few[j]).total() > 0.5 * min(len(a), len(b)) and link_by_force(a, b))):
                label[find(i)] = find(j)
    groups = {}
    for i, (d, _) in enumerate(all_docs):
        groups.setdefault(find(i), []).append(d)
    want = Counter((d, min((x for x in g if x is not None), default=None), len(g)) for g in groups.values() for d in g)
    table = spark.createDataFrame(all_docs, "doc_id long, text string")
    rows = near_dup.classes(table).collect()
    got = Counter((r.doc_id, r.class_id, r.class_size) for r in rows)
    assert got.total() == want.total() and (want - got).total() <= 0.02 * want.total()
    assert all(r.class_size == 2 and r.n_links == 1 and 0.9 < r.similarity < 1 for r in rows if r.doc_id is not None and 6500 <= r.doc_id < 6700)
    assert all(r.n_links == 0 and r.similarity is None for r in rows if r.doc_id in (7000, 7001, 7002, 7006))
    one = near_dup.keep_one(table.withColumn("key", table.doc_id).withColumn("`x", table.doc_id))
    assert one.columns == ["doc_id", "text", "key", "`x"]
    kept = Counter(r.doc_id for r in one.collect())
    assert kept.total() == len({(r.class_id, r.class_size, r.doc_id if r.class_size == 1 else 0) for r in rows})
    assert kept[7004] == kept[7005] == kept[7006] == 1 and not kept[7007]
    assert near_dup.classes(table.limit(0)).count() == 0


def test_near_duplicate_recall(spark):
    got, links = near_dup.recall(read(spark, "/root/testdata/sf0.01", "documents"), 1)
    assert links > 100 and got >= 0.97 * links


def test_repeated_and_reordered_copies_are_near_duplicates(spark):
    import random

    rows, want = [], Counter()
    for k in range(80):
        r = random.Random(k)
        base = [f"t{k}w{r.randrange(10**6)}" for _ in range(300)]
        blocks = [base[i : i + 60] for i in range(0, 300, 60)][::-1]
        group = [base, base * 2, base * 3, [w for b in blocks for w in b]]
        assert all(near_dup.similarity(as_text(group[0]), as_text(x)) >= near_dup.LEAST for x in group)
        rows += [(4 * k + i, " ".join(w)) for i, w in enumerate(group)]
        want.update((4 * k + i, 4 * k, 4) for i in range(4))
    rows += [(900, "a a a a a"), (901, "a " * 40)]
    want.update([(900, 900, 2), (901, 900, 2)])
    table = spark.createDataFrame(rows, "doc_id long, text string")
    assert Counter((r.doc_id, r.class_id, r.class_size) for r in near_dup.classes(table).collect()) == want
    assert sorted(r.doc_id for r in near_dup.keep_one(table).collect()) == [*range(0, 320, 4), 900]


def test_cells_lose_no_pair(spark, monkeypatch):
    """All texts share a passage and so large buckets, in which each class of three must find itself, whatever the cells' size."""
    passage = [f"p{i}" for i in range(120)]
    rows = [(3 * k + j, " ".join(passage + [f"k{k}w{i}" if i % 40 != 7 * j or not j else f"k{k}j{j}w{i}" for i in range(100)])) for k in range(16) for j in range(3)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    want = {(3 * k + j, 3 * k, 3) for k in range(16) for j in range(3)}
    monkeypatch.setattr(near_dup, "SMALL", 1)
    monkeypatch.setattr(near_dup, "PIVOTS", 1)
    for block, strip in ((5, 9), (1 << 16, 1 << 16)):
        monkeypatch.setattr(near_dup, "BLOCK", block)
        monkeypatch.setattr(near_dup, "STRIP", strip)
        assert {(r.doc_id, r.class_id, r.class_size) for r in near_dup.classes(table).collect()} == want


def test_alignment():
    a = [f"w{i}" for i in range(60)]
    b = a[:20] + ["x", "y"] + a[21:50] + a[52:]
    runs = near_dup.align(a, b)
    assert sum(r for _, _, r in runs) == 57 and all(a[i : i + r] == b[j : j + r] for i, j, r in runs)
    assert near_dup.align(a, [f"z{i}" for i in range(60)]) is None
    assert near_dup.align(a, a) == [(0, 0, 60)]


def test_license_spans(spark):
    mit = license_scan.TEMPLATES["MIT"]
    text = "Some words first. " + mit.replace("free of charge", "free of any charge").replace("sublicense, ", "") + " Tail. Released under the MIT License."
    found = license_scan.scan(text, license_scan.Index(license_scan.TEMPLATES))
    assert [f["license"] for f in found] == ["MIT", "MIT-line"]
    w = license_scan.words(text)
    assert w[found[0]["first_word"]] == "permission" and found[0]["first_word"] == 3 and w[found[0]["end_word"]] == "tail" and found[0]["coverage"] > 0.97
    out = {r.doc_id: r for r in license_scan.report(edges(spark, "license spans n_spans")).collect()}
    assert len(out) == len({e[0] for e in EDGES}) and all(r.n_spans == 0 for r in out.values())
    assert license_scan.report(edges(spark).limit(0)).count() == 0


def test_families_and_versions_are_told_apart():
    index = license_scan.Index(license_scan.TEMPLATES)
    for name, text in license_scan.TEMPLATES.items():
        assert [f["license"] for f in license_scan.scan(f"Code by us. {text} End of it.", index)] == [name]
    old = license_scan.TEMPLATES["LGPL-notice"].replace("version 3", "version 2.1")
    assert [(f["license"], f["version"]) for f in license_scan.scan(old, index)] == [("LGPL-notice", "2.1")]
    assert [(f["license"], f["version"]) for f in license_scan.scan("Licensed under the Apache License, Version 2.0.", index)] == [("Apache-line", "2.0")]


def test_license_alignment_by_force():
    import random

    r = random.Random(5)
    index = license_scan.Index(license_scan.TEMPLATES)
    found = asked = 0
    for name in ("MIT", "BSD-2-Clause", "Zlib", "Apache-notice", "GPL-notice", "ISC"):
        t = license_scan.words(license_scan.TEMPLATES[name])
        for _ in range(10):
            w = list(t)
            for _ in range(len(t) // 12):
                at = r.randrange(len(w))
                w[at : at + r.randrange(2)] = [f"zz{r.randrange(99)}"] * r.randrange(2)
            doc = [f"f{r.randrange(500)}" for _ in range(200)] + w + [f"f{r.randrange(500)}" for _ in range(50)]
            best = common_in_order(t, doc)
            if best < license_scan.COVERAGE * len(t):
                continue
            asked += 1
            hit = [f for f in license_scan.scan(" ".join(doc), index) if f["license"] == name]
            found += bool(hit)
            assert not hit or (hit[0]["matched"] == best and 200 <= hit[0]["first_word"] and hit[0]["end_word"] <= 200 + len(w))
    assert asked > 40 and found >= 0.95 * asked


def test_whole_licenses_from_a_table(spark):
    import glob
    import os

    files = [f for f in glob.glob("/usr/share/common-licenses/*") if os.path.isfile(f) and not os.path.islink(f)]
    whole = {os.path.basename(f): open(f, encoding="utf-8", errors="replace").read() for f in files} or license_scan.TEMPLATES
    table = spark.createDataFrame(list(whole.items()), "name string, text string")
    docs = spark.createDataFrame([(i, f"Preface of mine. {t} And an end.") for i, t in enumerate(whole.values())], "doc_id long, text string")
    out = {r.doc_id: r for r in license_scan.report(docs, table).collect()}
    for i, name in enumerate(whole):
        assert name in out[i].licenses.split(",") and out[i].best_coverage > 0.99
    with pytest.raises(ValueError):
        license_scan.read_templates(spark.createDataFrame([("x", "y" * 1000)] * 40_000, "name string, text string"))


@pytest.mark.parametrize("extra", ["", "n_words score row key"])
def test_pipeline_bears_edges(spark, sf_dir, extra):
    docs = edges(spark, extra).selectExpr("*", "doc_id as `a``b`")
    names = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf_dir)
        assert docs.columns == names, name
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf_dir).count() == docs.count() > 0


def test_pipeline_on_documents(spark, sf_dir, tmp_path, monkeypatch):
    docs = read(spark, sf_dir, "documents")
    folder = str(tmp_path / "run")
    rows = corpus_pipeline.run(spark, sf_dir, folder).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    assert len({r.doc_id for r in rows}) == len(rows) and 0 < len(rows) < len(text)
    assert all(r.decoded == text[r.doc_id].replace("▁", " ") for r in rows)
    assert len({text[r.doc_id] for r in rows}) == len(rows)
    # a second run takes what the first has written
    monkeypatch.setattr(corpus_pipeline, "STAGES", [(n, None) for n, _ in corpus_pipeline.STAGES[:-1]] + corpus_pipeline.STAGES[-1:])
    counts = corpus_pipeline.dropped(spark, sf_dir, folder).collect()
    assert [r.stage for r in counts] == [n for n, _ in corpus_pipeline.STAGES[:-1]]
    assert counts[0].rows_in == docs.count() and counts[-1].rows_out == len(rows)
    assert all(a.rows_out == b.rows_in for a, b in zip(counts, counts[1:]))


def test_links_of_a_large_group_are_closed_without_joining_them_all(spark, monkeypatch):
    name = lambda i: i.to_bytes(4, "big")
    clique = [(i, j) for i in range(60) for j in range(i + 1, 60)]
    chain = [(1000 + i, 1001 + i) for i in range(30)]
    pairs = [(2000 + 2 * i, 2001 + 2 * i) for i in range(5)]
    links = near_dup.stored(spark.createDataFrame([(bytearray(name(a)), bytearray(name(b))) for a, b in clique + chain + pairs], "a binary, b binary").repartition(7))
    want = {name(k): name(k // 1000 * 1000 if k < 2000 else k // 2 * 2) for p in clique + chain + pairs for k in p}
    for closed in (near_dup.CLOSED, 300, 10, 1):
        monkeypatch.setattr(near_dup, "CLOSED", closed)
        assert {bytes(r["key"]): bytes(r["label"]) for r in near_dup.components(links).collect()} == want
    assert near_dup._stars(links, 1).count() == 59 + 30 + 5
    assert near_dup.components(links.limit(0)).count() == 0
