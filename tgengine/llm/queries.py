"""The queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from .decontaminate import op7_decontaminate
from .html_extract import op1_html_extraction
from .language_id import op10_language_id
from .license_scan import op9_license_scan
from .lm_scoring import op4_lm_scoring
from .near_dup import op5_near_duplicates
from .quality_classifier import op3_quality_classifier
from .quality_rules import ALPHA, DELTA, LEVELS, MEASURES, N_LEVELS, op2_quality_rules
from .sentencepiece_codec import op6_sentencepiece
from .sharding import op8_sharding

QUERIES = {
    f.__name__: f
    for f in (
        op1_html_extraction, op2_quality_rules, op3_quality_classifier, op4_lm_scoring, op5_near_duplicates,
        op6_sentencepiece, op7_decontaminate, op8_sharding, op9_license_scan, op10_language_id,
    )
}


def pipeline(spark, sf_dir: str):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {**QUERIES, "pipeline": pipeline}


def rules_sql() -> str:
    part = lambda m: f"({m.split(' / ')[0]}) * 1.0 / nullif({m.split(' / ')[1]}, 0)"
    broken_at = lambda cut: " or ".join(f"coalesce({part(m)} * 100 > {cut(r)}, false)" for r, m in MEASURES.items())
    sums = ", ".join(f"count(*) filter ({broken_at(lambda r, g=g: LEVELS[r][g])}) as k{g}" for g in range(N_LEVELS))
    cells = " union all ".join(f"select stratum, n, strata, {g} as g, k{g} as k from tested, (select count(*) as strata from tested)" for g in range(N_LEVELS))
    tail = f"list_sum(list_transform(range(0, least(k, n) + 1), lambda j: exp(lgamma(n + 1) - lgamma(j + 1) - lgamma(n - j + 1) + j * ln({ALPHA}) + (n - j) * ln(1 - {ALPHA}))))"
    cuts = ", ".join(f"{list(c)}[level + 1] as cut_{r}" for r, c in LEVELS.items())
    broken = broken_at(lambda r: f"cut_{r}")
    ws = r"[\x20\x09-\x0D]+"
    return rf"""
with texts as (select doc_id, coalesce(lang, 'und') as stratum, coalesce(text, '') as text, row_number() over () as row from documents),
parts as (select *, list_filter(string_split_regex(text, '{ws}'), lambda x: x <> '') as w,
    list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as l from texts),
windows as (select row, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as three from (select row, w, unnest(range(1, len(w) - 1)) as i from parts)),
twice as (select row, i from (select row, i, count(*) over (partition by row, three) as n from windows) where n > 1),
repeats as (select row, count(distinct i + d) as n from twice, (select unnest([0, 1, 2]) as d) group by row),
counts as (select doc_id, stratum, len(w) as n_words, cast(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) as bigint) as word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) as n_symbols, length(regexp_replace(text, '[^A-ZÀ-ÖØ-Þ]', '', 'g')) as n_capitals,
    length(regexp_replace(text, '[^!]', '', 'g')) as n_shouts, len(l) as n_lines, len(l) - len(list_distinct(l)) as n_dup_lines,
    coalesce(n, 0) as n_repeat_words from parts left join repeats using (row)),
judged as (select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from counts),
good as (select doc_id from labels group by doc_id having max(quality) = 1),
tested as (select stratum, count(*) as n, {sums} from judged where not base_failed and doc_id in (select doc_id from good) group by stratum),
cells as ({cells}),
tails as (select *, {tail} as p from cells),
levels as (select stratum, coalesce(min(g) filter (p > {DELTA} / strata), {N_LEVELS}) - 1 as level from tails group by stratum),
cuts as (select stratum, {cuts} from levels where level >= 0)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and not ({broken}) as kept
from judged left join cuts using (stratum)"""


BENCHMARK_SQL = r"""
with doc as (select row_number() over () as row, doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as w from documents),
item as (select item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as w from benchmark),
windows as (select distinct item_id, size, array_to_string(w[i : i + size - 1], ' ') as k
    from (select item_id, w, least(13, len(w)) as size, unnest(range(1, len(w) - least(13, len(w)) + 2)) as i from item where len(w) > 0)),
sizes as (select distinct size from windows),
spans as (select row, size, i, array_to_string(w[i : i + size - 1], ' ') as k
    from (select row, w, size, unnest(range(1, len(w) - size + 2)) as i from doc, sizes where len(w) >= size)),
hits as (select row, item_id, i, spans.size as size from spans join windows on spans.k = windows.k and spans.size = windows.size),
places as (select row, count(distinct p) as n_hit from (select row, unnest(range(i, i + size)) as p from hits) group by row),
items as (select row, count(*) as n_items, string_agg(item, ',' order by item) as its from (select distinct row, cast(item_id as varchar) as item from hits) group by row)
select doc_id, len(w) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items, sha256(coalesce(its, '')) as items_sha256,
    coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(w) as contaminated
from doc left join places using (row) left join items using (row)"""


def oracle_sql() -> dict[str, str]:
    return {"op2_quality_rules": rules_sql(), "op7_decontaminate": BENCHMARK_SQL}
