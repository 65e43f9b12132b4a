"""Quality rules whose cutoffs are certified on labelled holdouts.

A rule rejects a text whose measure exceeds its cutoff. The cutoffs of all rules are tightened together, level by level, along
the fixed grid `LEVELS`. For every stratum (language) the levels are tested from the loosest on: a level is certified while the
exact binomial test of "the rules together reject at least a share `alpha` of this stratum's good texts" is significant at
level `delta / strata`. Testing in a fixed order needs no further correction along the levels, and since all rules are judged
as one rejection none over the rules; Bonferroni covers the strata. The tightest certified level is used; a stratum with too
few labelled good texts for even a level that rejects none (86 for four strata) gets no cutoffs and keeps the base rule. Hence
with probability 1 - delta no stratum loses more than a share `alpha` of its good texts to the rules.

Everything runs in built-in DataFrame functions. Null or empty texts have no words and fail the base rule; a null language
is the stratum 'und'; labels of unknown documents and repeated labels (any good one counts once) are harmless; repeated
rows are judged alike; extra columns pass through `judge` untouched unless they carry one of the added names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import quoted, read, stored

ALPHA = 0.05
DELTA = 0.05
MIN_WORDS = 50
REPEAT_PERCENT = 50
CAPITALS = "A-ZÀ-ÖØ-Þ"
BLANK = r"\x20\x09-\x0D"
#: Rule -> measure over the base counts; a share or a rate.
MEASURES = {
    "symbols": "n_symbols / n_words",
    "capitals": "n_capitals / word_chars",
    "shouts": "n_shouts / n_words",
    "same_lines": "n_dup_lines / n_lines",
    "repeats": "n_repeat_words / n_words",
    "long_words": "word_chars / (40.0 * n_words)",
}
#: Cutoffs in percent by level, loosest first.
LEVELS = {
    "symbols": (200, 150, 100, 70, 50, 40, 30, 25, 20, 15),
    "capitals": (90, 80, 70, 60, 55, 50, 45, 40, 35, 30),
    "shouts": (100, 80, 60, 50, 40, 30, 25, 20, 15, 10),
    "same_lines": (90, 80, 70, 60, 55, 50, 45, 40, 35, 30),
    "repeats": (50, 48, 46, 44, 42, 40, 38, 35, 32, 30),
    "long_words": (100, 80, 70, 60, 50, 45, 40, 35, 30, 25),
}
N_LEVELS = 10
#: Beyond so many strata the cutoffs are joined by shuffle instead of broadcast.
MAX_BROADCAST_STRATA = 10_000
STEP = "_q_"


def _removed(text: Column, kind: str) -> Column:
    """How many characters of the class `kind` the text has."""
    return F.length(text) - F.length(F.regexp_replace(text, f"[{kind}]+", ""))


def _let(value: Column, body) -> Column:
    """`body` of a value that is computed once: a name of a lambda is never replaced by its expression."""
    return F.transform(F.array(value), body)[0]


def _repeat_words(w: Column) -> Column:
    """Words within windows of three that occur twice or more; windows as (hash, place) are sorted, so equal ones are neighbours."""
    window = lambda i: F.struct(F.xxhash64(w[i], w[i + 1], w[i + 2]).alias("h"), i.alias("i"))

    def covered(s: Column) -> Column:
        twin = lambda x, j: ((j > 0) & (s[j - 1]["h"] == x["h"])) | ((j + 1 < F.size(s)) & (s[j + 1]["h"] == x["h"]))
        places = F.transform(F.filter(s, twin), lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2))
        return F.size(F.array_distinct(F.flatten(places)))

    windows = F.sort_array(F.transform(F.sequence(F.lit(0), F.size(w) - 3), window))
    return F.when(F.size(w) < 4, F.lit(0)).otherwise(_let(windows, covered))


def with_counts(docs: DataFrame) -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and the counts that only rules use."""

    def counts(t: Column) -> Column:
        parts = F.struct(
            F.filter(F.split(t, f"[{BLANK}]+"), lambda x: x != "").alias("w"),
            F.filter(F.split(t, "\n"), lambda x: x.rlike(f"[^{BLANK}]")).alias("l"),
        )
        return _let(parts, lambda p: F.struct(
            F.size(p["w"]).cast("long").alias("n_words"),
            F.length(F.array_join(p["w"], "")).cast("long").alias("word_chars"),
            _removed(t, "#*$%\\&|<>").cast("long").alias("n_symbols"),
            _removed(t, CAPITALS).cast("long").alias("n_capitals"),
            _removed(t, "!").cast("long").alias("n_shouts"),
            F.size(p["l"]).cast("long").alias("n_lines"),
            (F.size(p["l"]) - F.size(F.array_distinct(p["l"]))).cast("long").alias("n_dup_lines"),
            _repeat_words(p["w"]).cast("long").alias("n_repeat_words"),
        ))

    # the row number keeps the optimizer from copying the whole expression into every filter above
    once = F.when(F.monotonically_increasing_id() >= 0, _let(F.coalesce(F.col("text"), F.lit("")), counts))
    names = ("n_words", "word_chars", "n_symbols", "n_capitals", "n_shouts", "n_lines", "n_dup_lines", "n_repeat_words")
    df = docs.withColumn(f"{STEP}counts", once)
    return df.withColumns({c: F.col(f"{STEP}counts.{c}") for c in names}).drop(f"{STEP}counts")


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))


def _measure(rule: str) -> Column:
    return F.expr(f"try_divide({MEASURES[rule].split(' / ')[0]}, {MEASURES[rule].split(' / ')[1]})")


def binomial_below(k: str, n: str, p: float) -> Column:
    """P(Bin(n, p) <= k), by summing the exact terms; their logarithms are accumulated so that none underflows early."""
    step = f"""aggregate(sequence(1L, greatest({k}, 1L)),
        named_struct('t', {n} * ln(1 - {p}D), 's', exp({n} * ln(1 - {p}D))),
        (a, j) -> if(j > {k} or j > {n}, a, named_struct(
            't', a.t + ln(({n} - j + 1D) / j) + ln({p}D / (1 - {p}D)),
            's', a.s + exp(a.t + ln(({n} - j + 1D) / j) + ln({p}D / (1 - {p}D))))),
        a -> least(a.s, 1D))"""
    return F.expr(step)


def _broken(cutoffs: dict[str, Column]) -> Column:
    """Whether any rule's measure exceeds its cutoff; null cutoffs and measures reject nothing."""
    out = F.lit(False)
    for rule, c in cutoffs.items():
        out = out | F.coalesce(_measure(rule) * 100 > c, F.lit(False))
    return out


def certified_cutoffs(counts: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """stratum and, for each rule, the cutoff of the tightest certified level (null: none). `counts`: doc_id, stratum, base counts."""
    good = labels.groupBy("doc_id").agg(F.max("quality").alias(f"{STEP}good")).filter(f"{STEP}good = 1").select("doc_id")
    held = counts.filter(~base_failed()).join(good, "doc_id", "left_semi")
    rejected = [F.sum(_broken({r: F.lit(c[g]) for r, c in LEVELS.items()}).cast("long")).alias(f"k{g}") for g in range(N_LEVELS)]
    tested = held.groupBy("stratum").agg(F.count(F.lit(1)).alias("n"), *rejected)
    strata = tested.agg(F.count(F.lit(1)).alias(f"{STEP}strata"))
    pairs = ", ".join(f"{g}, k{g}" for g in range(N_LEVELS))
    long = tested.join(F.broadcast(strata)).selectExpr("stratum", "n", f"{STEP}strata", f"stack({N_LEVELS}, {pairs}) as (g, k)")
    failed = F.when(binomial_below("k", "n", alpha) > delta / F.col(f"{STEP}strata"), F.col("g"))
    level = long.groupBy("stratum").agg((F.coalesce(F.min(failed), F.lit(N_LEVELS)) - 1).alias("level"))
    return level.select("stratum", *[F.get(F.array(*map(F.lit, c)), F.col("level")).alias(r) for r, c in LEVELS.items()])


def stratum() -> Column:
    return F.coalesce(F.col("lang"), F.lit("und"))


def verdicts(counted: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """Adds base_failed and kept; every row keeps its columns."""
    names = {r: f"{STEP}cut_{r}" for r in MEASURES}
    small = cutoffs.select(F.col("stratum").alias(f"{STEP}stratum"), *[F.col(r).alias(c) for r, c in names.items()])
    side = F.broadcast(small) if small.limit(MAX_BROADCAST_STRATA + 1).count() <= MAX_BROADCAST_STRATA else small
    df = counted.join(side, F.col("stratum") == F.col(f"{STEP}stratum"), "left")
    broken = _broken({r: F.col(c) for r, c in names.items()})
    df = df.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & ~broken)
    return df.drop(f"{STEP}stratum", *names.values())


EXTRA = ("n_capitals", "n_shouts", "n_lines", "stratum")
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def report(docs: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """doc_id, the base counts, base_failed and kept of every row."""
    counted = stored(with_counts(docs.select("doc_id", "text", stratum().alias("stratum"))).drop("text"))
    cutoffs = stored(certified_cutoffs(counted, labels, alpha, delta))
    return verdicts(counted, cutoffs).select("doc_id", *COUNTS, "base_failed", "kept")


def keep_good(docs: DataFrame, labels: DataFrame, alpha: float = ALPHA, delta: float = DELTA) -> DataFrame:
    """The rows that the rules keep, with their own columns only. Counts are made once and stored beside each row."""
    mine = docs.select(F.struct(*[F.col(quoted(c)) for c in docs.columns]).alias(f"{STEP}row"))
    inner = mine.select(f"{STEP}row", F.col(f"{STEP}row.doc_id").alias("doc_id"), F.col(f"{STEP}row.text").alias("text"), F.coalesce(F.col(f"{STEP}row.lang"), F.lit("und")).alias("stratum"))
    counted = stored(with_counts(inner).drop("text"))
    cutoffs = stored(certified_cutoffs(counted.drop(f"{STEP}row"), labels, alpha, delta))
    return verdicts(counted, cutoffs).filter("kept").select(f"{STEP}row.*")


def op2_quality_rules(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))
