"""All queries of the library and the SQL that checks them.

The SQL builds every snapshot from the base tables anew, without interval coding, so an incremental result is always held
against one computed from scratch.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .operators import aggregate, batches, cache, delta, measures, placement, sequences, temporal
from .plans.reuse import ALL, MODELS, NONE, Flags
from .sources import graphs
from .sources.tables import load

T, L, M, K, H = graphs.MONTHS, 8, 4, 4, 64
DAYS = graphs.DAYS

SALES = """sales as (select 2 * l_suppkey as src, 2 * o_custkey + 1 as dst, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 as m,
  cast(round(l_quantity) as bigint) as qty, cast(round(l_extendedprice * 100) as bigint) as revenue from lineitem join orders on l_orderkey = o_orderkey)"""
#: Snapshots of the trade graph: e(t, src, dst, id, w), f(t, node, f0, f1).
TRADE = f"""with {SALES}, months as (select unnest(range(0, {T})) as t),
e as (select distinct t, src, dst, src * 2147483648 + dst as id, 1 as w from (select distinct src, dst, m from sales) join months on m <= t and t < m + 12),
sold as (select src as node, m // 3 as quarter, sum(qty) as qty from sales group by all),
f as (select t, 2 * s_suppkey as node, cast(round(s_acctbal * 100) as bigint) as f0, cast(coalesce(qty, 0) // {graphs.QUANTITY_STEP} as bigint) as f1
  from supplier cross join months left join sold on sold.node = 2 * s_suppkey and quarter = t // 3 - 1),
c as (select e.*, f0, f1 from e join f on e.t = f.t and e.src = f.node),
changed as (select b.t as t, a.node as node from f a join f b on a.node = b.node and b.t = a.t + 1 where a.f0 <> b.f0 or a.f1 <> b.f1),
minus as (select a.t + 1 as t, -1 as sign, a.src, a.dst, a.id, a.f0, a.f1, b.src is null as gone, ch.node is not null as moved from c a left join e b on b.t = a.t + 1 and a.src = b.src and a.dst = b.dst
  left join changed ch on ch.t = a.t + 1 and ch.node = a.src where a.t < {T - 1} and (b.src is null or ch.node is not null)),
plus as (select b.t as t, 1 as sign, b.src, b.dst, b.id, b.f0, b.f1, a.src is null as gone, ch.node is not null as moved from c b left join e a on b.t = a.t + 1 and a.src = b.src and a.dst = b.dst
  left join changed ch on ch.t = b.t and ch.node = b.src where b.t > 0 and (a.src is null or ch.node is not null)),
d as (select *, case when gone and moved then 'both' when gone then 'edge' else 'feature' end as cause from (select * from minus union all select * from plus)),
sizes as (select t, count(e.src) as n_edges from months left join e using (t) group by t),
ratios as (select t, coalesce(sum((sign < 0)::int), 0) as n_minus, coalesce(sum((sign > 0)::int), 0) as n_plus, n_edges from sizes left join d using (t) where t > 0 group by t, n_edges)
"""
SEQS = f"seqs as (select q, idx, q + idx - 1 as t from (select unnest(range(0, {T} - {L} + 1)) as q), (select unnest(range(1, {L} + 1)) as idx))"
PAIRED = f"""enc as (select q, 'enc' as part, idx, q + idx - 1 as t from (select unnest(range(0, {T} - {L})) as q), (select unnest(range(1, {L} + 1)) as idx)),
both_parts as (select * from enc union all select q, 'dec', idx, t + 1 from enc)"""

_q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_sql: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def keep(f):
        n = name or f.__name__
        _q[n] = f
        if sql:
            _sql[n] = sql
        return f

    return keep


def _trade(spark, d):
    return graphs.trade(spark, d)


# graphs
ISLANDS = """select src, dst, min(m)::int as valid_from, least({cap}, max(m) + {w})::int as valid_to from (select *, sum(case when before is null or m > before + {w} then 1 else 0 end) over (partition by src, dst order by m) as stay
  from (select src, dst, m, lag(m) over (partition by src, dst order by m) as before from (select distinct src, dst, m from {act}))) group by src, dst, stay"""
HANDOFF = """act as (select * from (select lag(user_id) over (partition by event_type, date_diff('day', timestamp '2024-01-01', ts) order by ts, event_id) as src, user_id as dst, date_diff('day', timestamp '2024-01-01', ts) as m from events) where src is not null and src <> dst)"""


@query(f"with {SALES} " + ISLANDS.format(cap=T, w=12, act="sales"))
def trade_edges_w12(spark, d):
    return _trade(spark, d).edges.select("src", "dst", "valid_from", "valid_to")


@query(f"with {HANDOFF} " + ISLANDS.format(cap=30, w=7, act="act"))
def handoff_edges_w7(spark, d):
    return graphs.handoff(spark, d).edges.select("src", "dst", "valid_from", "valid_to")


@query(f"with {SALES} select m::int as t, s_nationkey::bigint as src, c_nationkey::bigint as dst, sum(qty)::bigint as qty, sum(revenue)::bigint as revenue from sales join supplier on src = 2 * s_suppkey join customer on dst = 2 * c_custkey + 1 group by 1, 2, 3")
def flow_monthly(spark, d):
    return graphs.flow_monthly(spark, d)


@query(f"with act as (select distinct a.l_partkey as src, b.l_partkey as dst, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 as m from lineitem a join lineitem b using (l_orderkey) join orders on l_orderkey = o_orderkey where a.l_partkey <> b.l_partkey) " + ISLANDS.format(cap=T, w=3, act="act"))
def copurchase_edges(spark, d):
    return graphs.copurchase(spark, d).edges.select("src", "dst", "valid_from", "valid_to")


@query("with p as (select doc_id as src, unnest([lag(doc_id, 1) over o, lag(doc_id, 2) over o, lag(doc_id, 3) over o]) as dst from documents window o as (partition by source order by doc_id)) select src, dst, (src // 50)::int as valid_from from p where dst is not null")
def citation_edges(spark, d):
    return graphs.citation_edges(spark, d)


_HASH = "((({a}) * 7919 + ({b}) * 104729 + ({c}) * 1299709 + 42) % 1000003)"
_h = lambda a, b, c: _HASH.format(a=a, b=b, c=c)
CHURN = f"""with base as (select distinct s_nationkey::bigint as src, c_nationkey::bigint as dst from lineitem join orders on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey join customer on o_custkey = c_custkey where s_nationkey <> c_nationkey),
steps as (select unnest(range(1, 20)) as t), made as (select i, t from steps, (select unnest(range(0, (select count(*) from base))) as i) where i < floor(0.1 / 2 * (select count(*) from base))),
births as (select src, dst, 0 as born from base union select {_h('i', 't', 1)} % 25, {_h('t', 'i', 2)} % 25, t from made where {_h('i', 't', 1)} % 25 <> {_h('t', 'i', 2)} % 25),
fates as (select src, dst, born, coalesce(min(t), 20) as died from births left join steps on t > born and {_h('src', 'dst', 't')} < 0.1 / 2 * 1000003 group by src, dst, born)
select src, dst, min(a)::int as valid_from, max(b)::int as valid_to from (select *, sum(case when a <= before then 0 else 1 end) over (partition by src, dst order by a) as stay
  from (select *, lag(b) over (partition by src, dst order by a) as before from (select src, dst, min(born) as a, died as b from fates group by src, dst, died))) group by src, dst, stay"""


@query(CHURN)
def churn_edges_rho10(spark, d):
    return graphs.churned_flow(spark, d).edges.select("src", "dst", "valid_from", "valid_to")


@query("with base as (select distinct s_nationkey::bigint as src, c_nationkey::bigint as dst from lineitem join orders on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey join customer on o_custkey = c_custkey) select src + 25 * r as src, dst + 25 * r as dst from base, (select unnest(range(0, 4)) as r)")
def replica_flow_x4(spark, d):
    return graphs.replicate(graphs.flow_base(spark, d), 4, 25).select("src", "dst")


# deltas
@query(TRADE + f"select a.t + 1 as t, -1 as sign, a.src, a.dst from e a left join e b on b.t = a.t + 1 and a.src = b.src and a.dst = b.dst where a.t < {T - 1} and b.src is null union all select b.t, 1, b.src, b.dst from e b left join e a on b.t = a.t + 1 and a.src = b.src and a.dst = b.dst where b.t > 0 and a.src is null")
def delta_topology(spark, d):
    return delta.topology(_trade(spark, d)).select("t", "sign", "src", "dst")


for _name, _f in (("delta_via_anti_join", delta.by_anti_join), ("delta_via_except", delta.by_except)):
    query(_sql["delta_topology"], _name)(lambda spark, d, f=_f: f(_trade(spark, d)).select("t", "sign", "src", "dst"))


@query(TRADE + "select t, sign, src, dst from d where cause <> 'edge'")
def delta_features(spark, d):
    return delta.features(_trade(spark, d)).select("t", "sign", "src", "dst")


@query(TRADE + "select t, sign, src, dst, f0, f1, cause from d")
def delta_combined(spark, d):
    return delta.build(_trade(spark, d)).select("t", "sign", "src", "dst", "f0", "f1", "cause")


@query(TRADE + "select t, n_minus::bigint as n_minus, n_plus::bigint as n_plus, n_edges, round((n_minus + n_plus) * 1.0 / n_edges, 6) as change_ratio from ratios")
def change_ratio(spark, d):
    return delta.ratio(_trade(spark, d)).withColumn("change_ratio", F.round("change_ratio", 6))


SEGMENTS = "seg as (select t, coalesce((n_minus + n_plus) * 1.0 / nullif(n_edges, 0) > 0.35, true) as scratch from ratios union all select 0, true)"


@query(TRADE + f", {SEGMENTS} select t, scratch, sum(scratch::int) over (order by t)::bigint as segment from seg")
def fallback_segments(spark, d):
    return delta.segments(_trade(spark, d), 0.35).select("t", "scratch", "segment")


# aggregates
SUM_SQL = TRADE + "select t, dst, count(*) as cnt, sum(w * f0)::bigint as a0, sum(w * f1)::bigint as a1 from c group by t, dst"
MEAN_SQL = TRADE + "select t, dst, count(*) as cnt, round(sum(w * f0) * 1.0 / count(*), 6) as a0, round(sum(w * f1) * 1.0 / count(*), 6) as a1 from c group by t, dst"


def _extreme_sql(way: str) -> str:
    pick = lambda f: f"first(id order by {f} {way}, id)"
    fn = "max" if way == "desc" else "min"
    return TRADE + f"select t, dst, {fn}(f0) as m0, {pick('f0')} as e0, {fn}(f1) as m1, {pick('f1')} as e1 from c group by t, dst"


for _fn, _s in (("sum", SUM_SQL), ("mean", MEAN_SQL), ("max", _extreme_sql("desc")), ("min", _extreme_sql("asc"))):
    for _way, _f in (("scratch", aggregate.scratch), ("incremental", aggregate.incremental)):

        def _run(spark, d, f=_f, fn=_fn):
            out = f(_trade(spark, d), fn)
            return out.withColumns({a: F.round(a, 6) for a in ("a0", "a1")}) if fn == "mean" else out

        query(_s, f"agg_{_way}_{_fn}")(_run)


@query(SUM_SQL)
def agg_adaptive_sum(spark, d):
    return aggregate.adaptive(_trade(spark, d), 0.35)


@query(SUM_SQL)
def agg_propagate_sum(spark, d):
    g = _trade(spark, d)
    a = aggregate.propagate(g, lambda x: x["f0"] * x["w"], F.sum, invertible=True).withColumnRenamed("value", "a0")
    b = aggregate.propagate(g, lambda x: x["f1"] * x["w"], F.sum).withColumnRenamed("value", "a1")
    n = aggregate.propagate(g, lambda x: x["w"], F.count).withColumnRenamed("value", "cnt")
    return a.join(b, ["t", "dst"]).join(n, ["t", "dst"])


@query(TRADE + "select t, dst, count(*) as kept, max(f0) as best from c group by t, dst")
def agg_retain_all_max(spark, d):
    return aggregate.retain_all(_trade(spark, d))


@query(TRADE.replace("minus as (", "minus as materialized (").replace("c as (", "c as materialized (") + """, top as (select t, dst, arg_min(id, (-f0, id)) as e0, arg_min(id, (-f1, id)) as e1 from c group by t, dst),
lanes as materialized (select t + 1 as t, dst, 0 as lane, e0 as id from top union all select t + 1, dst, 1, e1 from top)
select distinct lanes.t, lanes.dst, lane from lanes join (select distinct t, id from minus) m on m.t = lanes.t and m.id = lanes.id join (select distinct t, dst from e) held on held.t = lanes.t and held.dst = lanes.dst""")
def extremal_recompute_targets(spark, d):
    return aggregate.recompute_targets(_trade(spark, d))


@query(TRADE + "select t, dst, round(sum(exp(f1 * 0.1) * f0) / sum(exp(f1 * 0.1)), 4) as a0, round(sum(exp(f1 * 0.1) * f1) / sum(exp(f1 * 0.1)), 6) as a1, 0 as version from c group by t, dst")
def agg_attention_fixed_weights(spark, d):
    return aggregate.weighted(_trade(spark, d), F.col("f1") * 0.1).withColumns({"a0": F.round("a0", 4), "a1": F.round("a1", 6)})


@query(TRADE + "select f.t, e.dst, count(*) as cnt, sum(f0)::bigint as a0, sum(f1)::bigint as a1 from e join f on e.src = f.node where e.t = 24 group by f.t, e.dst")
def agg_fused_static(spark, d):
    return aggregate.fused_static(_trade(spark, d), 24)


@query(TRADE + "select t, dst, count(*) as cnt, sum(f0)::bigint as a0, sum(f1)::bigint as a1 from c where t between 20 and 27 group by t, dst")
def agg_multi_snapshot(spark, d):
    return aggregate.multi_snapshot(_trade(spark, d), 20, 8)


@query(TRADE + "select e.t, e.dst, count(*) as cnt, sum(f0)::bigint as a0, sum(f1)::bigint as a1 from e join f on e.src = f.node and f.t = 0 group by e.t, e.dst")
def agg_static_features(spark, d):
    return aggregate.static_features(_trade(spark, d))


@query(TRADE + """, o as (select t, src, count(*) as n from e group by t, src), i as (select t, dst, count(*) as n from e group by t, dst)
select c.t, c.dst, round(sum(f1 / sqrt(o.n * i.n)), 6) as a1 from c join o on c.t = o.t and c.src = o.src join i on c.t = i.t and c.dst = i.dst group by c.t, c.dst""")
def gcn_norm_layer1(spark, d):
    return aggregate.normalised(_trade(spark, d)).select("t", "dst", F.round("a1", 6).alias("a1"))


@query(TRADE + """, rows as (select unnest(range(0, 80, 5)) as t), ev as (select 2 * s_suppkey as node, t from supplier, rows) select node, ev.t, f0, f1 from ev join f using (node, t)""")
def as_of_features(spark, d):
    g = _trade(spark, d)
    events = g.feats.select("node").distinct().withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(79), F.lit(5))))
    return temporal.as_of(events, g.feats, g.lanes)


@query(TRADE + "select t, count(*) as n_edges, count(distinct dst) as targets, round(count(*) * 1.0 / count(distinct dst), 6) as mean_degree from e group by t")
def degree_stats(spark, d):
    return measures.degree(_trade(spark, d)).withColumn("mean_degree", F.round("mean_degree", 6))


# sequences and batches
@query(f"with {SEQS} select q, 'enc' as part, idx, t from seqs")
def sequences_l8_s1(spark, d):
    return sequences.windows(spark, T, L)


@query(f"with {PAIRED} select * from both_parts")
def sequences_seq2seq(spark, d):
    return sequences.seq2seq(spark, T, L)


@query(f"with {SEQS} select count(*) as visits, count(distinct t) as distinct_t, round(1 - count(distinct t) * 1.0 / count(*), 6) as repeat_share from seqs")
def repeat_share(spark, d):
    return sequences.repeat_share(sequences.windows(spark, T, L)).withColumn("repeat_share", F.round("repeat_share", 6))


BATCH = f"batch as (select node, ({_h('node', 17, 0)} % 8)::int as batch_id from (select 2 * c_custkey + 1 as node from customer union select 2 * s_suppkey from supplier))"


@query(f"with {BATCH} select * from batch")
def minibatches(spark, d):
    return batches.sampler(_trade(spark, d).nodes, 8)


for _kind, _pos in (("seq_first", f"b * {T - L + 1} + q"), ("node_first", "q * 8 + b")):
    query(f"""with active as (select distinct o_custkey as node, {_h('o_custkey', 17, 0)} % 8 as batch, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 as m from orders)
select ({_pos})::int as pos, q::int as q, b::int as batch_id, count(distinct node) as nodes from (select unnest(range(0, {T - L + 1})) as q) cross join (select unnest(range(0, 8)) as b) left join active on batch = b and m between q and q + {L - 1} group by q, b""", f"order_{_kind}")(
        lambda spark, d, k=_kind: batches.with_nodes(batches.order(sequences.windows(spark, T, L), 8, k), graphs.order_targets(spark, d, L, 8), L))

HAND = f"with {HANDOFF}, days as (select unnest(range(0, 30)) as t), e as (select distinct t, src, dst from (select distinct src, dst, m from act) join days on m <= t and t < m + 7), batch as (select node, ({_h('node', 17, 0)} % 4)::int as batch_id from (select distinct user_id as node from events)) "


def _hops(fan: tuple[int, ...] | None) -> str:
    """Two hops k(batch_id, t, hop, src, dst) from batch over e."""
    edge = lambda hop: f"(select t, src, dst from (select *, row_number() over (partition by t, dst order by {_h('src', 'dst', hop)}, src) as r from e) where r <= {fan[hop - 1]})" if fan else "e"
    return f""", h1 as (select batch_id, e1.t, 1 as hop, src, dst from {edge(1)} e1 join batch on node = dst),
h2 as (select distinct batch_id, e2.t, 2 as hop, e2.src, e2.dst from {edge(2)} e2 join (select distinct batch_id, t, src from h1) f on f.t = e2.t and f.src = e2.dst),
k as (select * from h1 union all select * from h2)"""


def _hop_sql(fan: tuple[int, ...] | None, last: str) -> str:
    return f"{HAND.rstrip()}{_hops(fan)} {last}"


def _handoff_khop(spark, d, fan=None):
    g = graphs.handoff(spark, d)
    return batches.khop(g, batches.sampler(g.nodes, 4), 2, fan)


@query(_hop_sql(None, "select batch_id, t, hop, count(*) as n, sum(src * 7 + dst)::bigint as digest from k group by all"))
def khop_full(spark, d):
    return _handoff_khop(spark, d).groupBy("batch_id", "t", "hop").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("src") * 7 + F.col("dst")).alias("digest"))


@query(_hop_sql((25, 10), "select * from k"))
def khop_sampled_25_10(spark, d):
    return _handoff_khop(spark, d, (25, 10))


@query(_hop_sql((5, 3), "select b.batch_id, b.hop, b.src, b.dst, b.t, 1 as sign from k b left join k a on a.batch_id = b.batch_id and a.hop = b.hop and a.src = b.src and a.dst = b.dst and a.t = b.t - 1 where a.t is null union all select a.batch_id, a.hop, a.src, a.dst, a.t + 1, -1 from k a left join k b on a.batch_id = b.batch_id and a.hop = b.hop and a.src = b.src and a.dst = b.dst and a.t = b.t - 1 where b.t is null and a.t < (select max(t) from k)"))
def khop_delta(spark, d):
    return batches.khop_delta(_handoff_khop(spark, d, (5, 3)), 0)


@query(_hop_sql((5, 3), ", n as (select distinct t, src as node from k), daily as (select user_id as node, date_diff('day', timestamp '2024-01-01', ts) as t, count(*) as f0, sum(cast(round(value * 100) as bigint)) as f1 from events group by 1, 2) select n.t, n.node, coalesce(f0, 0) as f0, coalesce(f1, 0)::bigint as f1 from n left join daily using (t, node)"))
def batch_features(spark, d):
    g = graphs.handoff(spark, d)
    return batches.features(g, batches.khop(g, batches.sampler(g.nodes, 4), 2, (5, 3))).select("t", "node", "f0", "f1")


def _edges_by_snapshot(spark, d):
    return temporal.by_snapshot(_trade(spark, d).edges)


# placement and communication
@query(f"select t::int as t, (t * {M} // {T})::int as block from (select unnest(range(0, {T})) as t)")
def placement_blocks(spark, d):
    return placement.blocks(spark, T, M)


OWN = f"own as (select t, t * {M} // {T} as owner from (select unnest(range(0, {T})) as t)), need as (select distinct q * {M} // {T} as block, q + i as t from (select unnest(range(0, {T - L + 1})) as q), (select unnest(range(0, {L})) as i))"


@query(TRADE + f", {OWN} select t::int as t, block::int as block, block <> owner as is_copy, n_edges as rows from (select block, t from need union select owner, t from own) join own using (t) join sizes using (t)")
def place_overlap_copies(spark, d):
    """Where the trade graph's snapshots lie, with the edges that each holds."""
    return placement.with_rows(placement.overlapped(spark, T, M, L), _edges_by_snapshot(spark, d)).select("t", "block", "is_copy", "rows")


for _split, _b in (("by_snapshot", f"q * {M} // {T}"), ("by_sequence", f"q * {M} // {T - L + 1}")):
    query(TRADE + f", n as (select ({_b})::int as block, sum(n_edges)::bigint as items from (select unnest(range(0, {T - L + 1})) as q) join sizes on t between q and q + {L - 1} group by 1) select block, items, round((select max(items) / avg(items) from n), 6) as imbalance from n", f"place_balance_{_split}")(
        lambda spark, d, s=_split: placement.balance(placement.with_rows(placement.sequence_blocks(spark, T, M, L, split=s).withColumn("t", F.explode(F.sequence("first_t", "last_t"))), _edges_by_snapshot(spark, d)), weight="rows").withColumn("imbalance", F.round("imbalance", 6)))

for _m in (2, 4, 8):
    _remote = f", r as (select t, count(distinct (dst % {_m}, src)) as n from e where src % {_m} <> dst % {_m} group by t), {SEQS} select {_m} as machines, (sum(n) * (2 + {H}) * 8)::bigint as bytes from r join seqs using (t)"
    query(TRADE + _remote, f"comm_node_part_m{_m}")(lambda spark, d, m=_m: measures.comm_node_part(_trade(spark, d), m))
_OWNERS = f"with nodes as (select 2 * c_custkey + 1 as node from customer union select 2 * s_suppkey from supplier), {SEQS}, moved as (select count(*) as n from seqs, nodes where (idx - 1) * 4 // {L} <> node % 4), turns as (select count(*) as n from seqs where idx > 1 and (idx - 1) * 4 // {L} <> (idx - 2) * 4 // {L}) select 4 as machines, "
query(_OWNERS + f"(moved.n * {H} * 2 * 2 * 8)::bigint as bytes from moved", "comm_seq_part_stacked")(lambda spark, d: measures.comm_seq_part(_trade(spark, d), 4))
query(_OWNERS + f"((moved.n + turns.n * (select count(*) from nodes)) * {H} * 2 * 2 * 8)::bigint as bytes from moved, turns", "comm_seq_part_integrated")(lambda spark, d: measures.comm_seq_part(_trade(spark, d), 4, integrated=True))
query(TRADE + f", {OWN}, held as (select block, t from need union select owner, t from own), lack as (select block, t from need except select block, t from held) select 4 as machines, coalesce(sum(n_edges * 2 + (select count(*) from customer) * 2 + (select count(*) from supplier) * 2) * 8, 0)::bigint as bytes from lack join sizes using (t)", "comm_block_overlap")(lambda spark, d: measures.comm_block(_trade(spark, d), 4))
query(TRADE + f", {OWN}, lack as (select block, t from need join own using (t) where block <> owner) select 4 as machines, (sum(n_edges * 2 + (select count(*) from customer) * 2 + (select count(*) from supplier) * 2) * 8)::bigint as bytes from lack join sizes using (t)", "comm_block_ondemand")(
    lambda spark, d: measures.comm_block(_trade(spark, d), 4, overlap=False))


@query(TRADE + "select t, round(avg((src % 4 <> dst)::int), 6) as remote_share from (select distinct t, src, dst % 4 as dst from e) group by t")
def cut_over_time(spark, d):
    g = _trade(spark, d)
    none = g.nodes.limit(0).select("node", F.lit(0).alias("machine"))
    return measures.cut(g, none, 4).withColumn("remote_share", F.round("remote_share", 6))


def _spread_sql(rounds: int) -> str:
    """Label propagation over snapshot 0, round by round."""
    out = ", both_ways as (select src, dst from e where t = 0 union select dst, src from e where t = 0), label0 as (select distinct src as node, src as label from both_ways)"
    for i in range(rounds):
        out += f""", votes{i} as (select dst as node, label, count(*) as n from both_ways join label{i} on node = src group by all),
label{i + 1} as (select node, arg_min(label, (-n, label)) as label from votes{i} group by node)"""
    return out + f", owners as (select node, label % 4 as machine from label{rounds})"


@query(TRADE + _spread_sql(3) + ", pairs as (select distinct t, src, coalesce(a.machine, src % 4) as ms, coalesce(b.machine, dst % 4) as md from e left join owners a on a.node = src left join owners b on b.node = dst) select t, round(avg((ms <> md)::int), 6) as remote_share from pairs group by t")
def cut_first_snapshot_kept(spark, d):
    """Owners by label propagation over the first snapshot, kept while the graph moves on."""
    g = _trade(spark, d)
    owners = placement.first_snapshot_cut(temporal.at(g, 0), 4)
    return measures.cut(g, owners, 4).withColumn("remote_share", F.round("remote_share", 6))


# work
_COST = {False: "n_edges", True: "least(coalesce(moved, n_edges), n_edges)"}
WORKS = {"scratch": NONE, "incremental": Flags(True, False, False, False), "gates": Flags(False, True, False, False), "seq": Flags(False, False, True, False), "teacher": Flags(False, False, False, True), "all": ALL}
for _model in MODELS:
    for _name, _flags in WORKS.items():
        _shape = MODELS[_model]
        _k = 1 if _flags.gates or _shape.kind == "stacked" else _shape.gates
        _keys = {(True, True): "t", (True, False): "part, t", (False, True): "q, t", (False, False): "q, part, idx, t"}[_flags.sequences, _flags.teacher]
        _rows = f"{PAIRED}, visits as (select * from both_parts)" if _shape.decoder else f"{SEQS}, visits as (select q, 'enc' as part, idx, t from seqs)"
        _rest = (_shape.layers - 1) * _k + (_shape.layers * _k if _shape.kind == "integrated" else 0)
        query(TRADE + f""", {_rows}, cost as (select sizes.t, sizes.n_edges, {_COST[_flags.incremental]} as first_cost from (select t, n_edges from sizes) sizes left join (select t, n_minus + n_plus as moved from ratios) r using (t)),
first as (select sum(first_cost) as f from (select distinct {_keys} from visits) join cost using (t)), every as (select sum(n_edges) as v from visits join cost using (t))
select '{_model}' as model, (f * {_k})::bigint as first_inputs, (v * {_rest})::bigint as rest, (f * {_k} + v * {_rest})::bigint as messages from first, every""", f"work_{_name}_{_model}")(
            lambda spark, d, m=_shape, fl=_flags: measures.work(_trade(spark, d), m, fl))


# cache
def _targets_sql(batches: int = 1) -> str:
    """targets(batch_id, t, rows): users with an in-edge in each snapshot of the hand-off graph."""
    return f"{HANDOFF}, targets as (select ({_h('dst', 17, 0)} % {batches})::int as batch_id, t, count(distinct dst) as rows from act join (select unnest(range(0, {DAYS})) as t) on m <= t and t < m + 7 group by 1, 2)"


@query(f"""with {_targets_sql()}, {PAIRED.replace(str(T), str(DAYS))}, x as (select b.*, gate, kind from both_parts b, (select unnest(range(1, 5)) as gate), (select unnest(['input', 'hidden']) as kind))
select row_number() over (order by q, part desc, idx, gate, kind desc) - 1 as pos, 0 as batch_id, q, part, 1 as layer, idx, gate, kind, t,
  case when kind = 'input' then 'x:0:' || t else concat_ws(':', kind, 0, q, part, 1, idx) end as key,
  coalesce(rows, 1) * if(kind = 'hidden', {H}, 2) as cells from x left join targets using (t)""")
def cache_trace(spark, d):
    """Accesses over the snapshots of the hand-off graph, with the cells of each aggregate."""
    trace = cache.trace(spark, DAYS)
    return cache.with_cells(trace, graphs.handoff_targets(spark, d), 2, H).select(*trace.columns, "cells")


for _policy in ("formula", "exact"):
    _low = {"formula": ("greatest(1, 2 * idx - 2 * s + 1)", "greatest(2, 2 * idx - 2 * s + 2)"), "exact": ("(2 * ((idx - 1) // s) + 1)", "(2 * ((idx - 1) // s) + 2)")}[_policy]
    query(f"""with {_targets_sql()} select part, idx::int as idx, gate::int as gate, future::int as future, imminence::int as imminence, t::int as t, rows, round(future / (16.0::double * rows / (select avg(rows) from targets)) - imminence, 6) as score from targets, (
select 'enc' as part, idx, gate, {_low[0]} * 4 - gate as future, 8 - s as imminence from (select unnest(range(1, 9)) as idx), (select unnest(range(1, 5)) as gate), (select 2 as s)
union all select 'dec', idx, gate, {_low[1]} * 4 - gate, 7 from (select unnest(range(1, 9)) as idx), (select unnest(range(1, 5)) as gate), (select 2 as s))""", f"cache_scores_{_policy}")(
        lambda spark, d, p=_policy: cache.sized_scores(cache.scores(spark, L, 2, K, p), graphs.handoff_targets(spark, d)).withColumn("score", F.round("score", 6)))


@query()
def cache_hits_by_policy(spark, d):
    """Hits by policy on the aggregates of the trade graph, as large as their snapshot's customers."""
    rows = cache.relative(cache.with_cells(cache.trace(spark, T), graphs.trade_targets(spark, d), 2, 2))
    return cache.simulate(rows, [(p, c) for p in cache.POLICIES for c in (1, 2, 3, 5, 7, 9, 10, 13, 15, 17)])


@query()
def cache_hits_real_sizes(spark, d):
    """Hits by policy where entries are as large as the aggregates of the hand-off graph; capacity as a share of the data of one sequence."""
    rows = cache.with_sizes(cache.trace(spark, 30), graphs.handoff(spark, d), 2)
    return cache.simulate(rows, [(p, 17 * share) for p in cache.POLICIES for share in (0.1, 0.2, 0.4, 0.6, 0.8, 1.0)])


@query(f"""with {_targets_sql()} select layer::int as layer, gate::int as gate, (4 - gate)::int as future, 0::int as imminence, t::int as t, rows, round((4 - gate) / (16.0::double * rows / (select avg(rows) from targets)), 6) as score from targets, (select unnest([1, 2]) as layer), (select unnest(range(1, 5)) as gate)""")
def cache_upper_counts(spark, d):
    """Hidden aggregates, and inputs above the first layer, are read by the gates still to come; they never wait. By snapshot of the hand-off graph, whose targets are their size."""
    grid = spark.range(1, 3).select(F.col("id").cast("int").alias("layer")).withColumn("gate", F.explode(F.sequence(F.lit(1), F.lit(K))))
    counts = grid.select("layer", "gate", cache.future_count_upper(K, F.col("gate")).cast("int").alias("future"), F.lit(cache.imminence("local", L, 1)).alias("imminence"))
    return cache.sized_scores(counts, graphs.handoff_targets(spark, d)).withColumn("score", F.round("score", 6))


@query(TRADE + "select dst, round(sum(exp(f1 * 0.1) * f0) / sum(exp(f1 * 0.1)), 4) as a0, round(sum(exp(f1 * 0.1) * f1) / sum(exp(f1 * 0.1)), 6) as a1, 3 as version from c where t = 31 group by dst")
def agg_attention_step(spark, d):
    """Attention at one snapshot from that before it: targets without a changed in-edge keep theirs while the weights stay."""
    g, score = _trade(spark, d), F.col("f1") * 0.1
    kept = aggregate.weighted(g, score, 3).filter("t = 30").drop("t")
    return aggregate.weighted_step(g, kept, 31, score, 3).withColumns({"a0": F.round("a0", 4), "a1": F.round("a1", 6)})


@query()
def cache_order_compare(spark, d):
    """Hits by visiting order, over batches of the hand-off graph's users, entries as large as their batch's targets."""
    sized = lambda o: cache.relative(cache.with_cells(cache.trace(spark, DAYS, order=o, batches=6), graphs.handoff_targets(spark, d, 6), 2, 2))
    run = lambda o: cache.simulate(sized(o), [("lookahead", c) for c in (1, 3, 9, 17, 34, 68)]).withColumn("visit_order", F.lit(o))
    return run("seq_first").union(run("node_first"))


@query(f"""with {_targets_sql()}, {PAIRED.replace(str(T), str(DAYS))}, x as (select b.*, gate, kind from both_parts b, (select unnest(range(1, 5)) as gate), (select unnest(['input', 'hidden']) as kind)),
tr as (select row_number() over (order by q, part desc, idx, gate, kind desc) - 1 as pos, case when kind = 'input' then 'x:0:' || t else concat_ws(':', kind, 0, q, part, 1, idx) end as key, coalesce(rows, 1) * if(kind = 'hidden', {H}, 2) as cells from x left join targets using (t)),
life as (select key, min(pos) as born, max(pos) as last, max(cells) as cells from tr group by key),
live as (select pos, sum(life.cells)::bigint as n from tr join life on born <= pos and pos <= last group by pos)
select (select sum(cells)::bigint from life) as kept_all, max(n) as peak_with_expiry, round(1 - max(n)::double / (select sum(cells)::bigint from life), 6) as saving from live""")
def memory_model(spark, d):
    """Live cells of the hand-off graph's aggregates."""
    sized = cache.with_cells(cache.trace(spark, DAYS), graphs.handoff_targets(spark, d), 2, H)
    return cache.memory(sized).select("kept_all", F.col("peak_with_expiry"), F.round("saving", 6).alias("saving"))


# surrounding operators
@query("select r_name, n_name, round(sum(c_acctbal), 2) as balance, count(*) as customers from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
def rollup_region(spark, d):
    c = load(spark, d, "customer").join(F.broadcast(load(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(load(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.rollup("r_name", "n_name").agg(F.round(F.sum("c_acctbal"), 2).alias("balance"), F.count(F.lit(1)).alias("customers"))


@query("select event_type, date_diff('day', timestamp '2024-01-01', ts)::int as day, count(*) as n, sum(cast(round(value * 100) as bigint))::bigint as cents from events group by cube (event_type, date_diff('day', timestamp '2024-01-01', ts)::int)")
def cube_event_day(spark, d):
    e = load(spark, d, "events").select("event_type", F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("day"), F.round(F.col("value") * 100).cast("long").alias("c"))
    return e.cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"), F.sum("c").alias("cents"))


KINDS = ("click", "error", "purchase", "signup", "view")


@query("select user_id, count(*) as n_events, max(value) as largest, count(distinct event_type) as kinds, sum(cast(json_extract_string(props, '$.k') as bigint))::bigint as k_sum from events group by user_id")
def user_lanes(spark, d):
    """Feature lanes per user, one read of the JSON column."""
    e = load(spark, d, "events")
    return e.groupBy("user_id").agg(F.count(F.lit(1)).alias("n_events"), F.max("value").alias("largest"), F.count_distinct("event_type").alias("kinds"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k_sum"))


@query("select user_id, " + ", ".join(f"count(*) filter (event_type = '{k}') as n_{k}" for k in KINDS) + " from events group by user_id")
def pivot_types(spark, d):
    """One lane per event type, by pivoting."""
    lanes = load(spark, d, "events").groupBy("user_id").pivot("event_type", list(KINDS)).agg(F.count(F.lit(1))).fillna(0)
    return lanes.withColumnsRenamed({k: f"n_{k}" for k in KINDS})


@query("select event_type, date_diff('day', timestamp '2024-01-01', ts)::int as day, count(*) as n, (grouping(event_type) * 2 + grouping(date_diff('day', timestamp '2024-01-01', ts)::int))::bigint as level from events group by grouping sets ((event_type), (date_diff('day', timestamp '2024-01-01', ts)::int), ())")
def grouping_sets_events(spark, d):
    e = load(spark, d, "events").select("event_type", graphs.day("ts").alias("day"))
    return e.groupingSets([[F.col("event_type")], [F.col("day")], []], "event_type", "day").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


@query("select l_returnflag, count(*) as n, quantile_disc(l_quantity, 0.5) as middle, quantile_disc(l_quantity, 0.9) as high from lineitem group by l_returnflag")
def percentiles_quantity(spark, d):
    """Exact percentiles: of a column with few values, by its counts."""
    x = load(spark, d, "lineitem").groupBy("l_returnflag", "l_quantity").agg(F.count(F.lit(1)).alias("c"))
    order = Window.partitionBy("l_returnflag").orderBy("l_quantity")
    x = x.withColumn("upto", F.sum("c").over(order))
    all_of = x.groupBy("l_returnflag").agg(F.sum("c").alias("n"))
    at = lambda p: F.min(F.when(F.col("upto") >= F.ceil(F.col("n") * p), F.col("l_quantity")))
    return x.join(F.broadcast(all_of), "l_returnflag").groupBy("l_returnflag").agg(F.max("n").alias("n"), at(0.5).alias("middle"), at(0.9).alias("high"))


@query("select count(distinct l_partkey) as exact, true as near from lineitem")
def approximate_distinct(spark, d):
    """The sketch's estimate lies within a tenth of the exact number."""
    x = load(spark, d, "lineitem").agg(F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("sketch"))
    return x.select("exact", (F.abs(F.col("sketch") - F.col("exact")) <= 0.1 * F.col("exact")).alias("near"))


@query(TRADE + "(select src, dst from e where t = 20 intersect select src, dst from e where t = 30)")
def edges_in_both(spark, d):
    g = _trade(spark, d)
    return temporal.at(g, 20).select("src", "dst").intersect(temporal.at(g, 30).select("src", "dst"))


@query("select l_suppkey, l_partkey from lineitem where l_quantity > 25 except all select l_suppkey, l_partkey from lineitem where l_returnflag = 'R'")
def lines_except_all(spark, d):
    x = load(spark, d, "lineitem")
    return x.filter("l_quantity > 25").select("l_suppkey", "l_partkey").exceptAll(x.filter("l_returnflag = 'R'").select("l_suppkey", "l_partkey"))


@query("""with marked as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hours then 0 else 1 end as fresh from events),
runs as (select *, sum(fresh) over (partition by user_id order by ts) as run from marked) select user_id, epoch_us(min(ts)) as began, count(*) as n from runs group by user_id, run""")
def session_activity(spark, d):
    """Runs of a user's events without a pause of six hours."""
    e = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_micros("w.start").alias("began"), "n")


@query("select o_custkey, o_orderkey, r::int as r, dr::int as dr, quarter::int as quarter from (select o_custkey, o_orderkey, rank() over w as r, dense_rank() over w as dr, ntile(4) over (partition by o_custkey order by o_totalprice, o_orderkey) as quarter from orders window w as (partition by o_custkey order by year(o_orderdate)))")
def ranked_orders(spark, d):
    order = Window.partitionBy("o_custkey").orderBy(F.year("o_orderdate"))
    quarter = F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey"))
    return load(spark, d, "orders").select("o_custkey", "o_orderkey", F.rank().over(order).alias("r"), F.dense_rank().over(order).alias("dr"), quarter.alias("quarter"))


@query(TRADE + "select c.t, c.dst, sum(f0 * 2 + c.dst % 10)::bigint as value from c group by c.t, c.dst")
def agg_message_with_target(spark, d):
    """A user message of the source's lanes, the edge and the target's."""
    g = _trade(spark, d)
    tag = g.nodes.select("node", (F.col("node") % 10).alias("tag"))
    return aggregate.propagate(g, lambda x: x["f0"] * 2 + x["target.tag"] * x["w"], F.sum, target=tag)


@query(TRADE + ", k as (select t, src, dst from e), ids as (select 2 * c_custkey + 1 as node from customer union select 2 * s_suppkey from supplier), grid as (select t, node from months, ids where t % 20 = 0), s as (select t, dst, count(*) as cnt, sum(f0)::bigint as a0 from c group by t, dst) select grid.t, node as dst, coalesce(cnt, 0) as cnt, coalesce(a0, 0)::bigint as a0 from grid left join s on s.t = grid.t and s.dst = node")
def agg_with_isolated(spark, d):
    """The whole node universe in every twentieth snapshot; nodes without in-edges count as such."""
    g = _trade(spark, d)
    return aggregate.with_isolated(aggregate.incremental(g), g).filter("t % 20 = 0").select("t", "dst", "cnt", "a0")


@query(TRADE + "select t, dst, degree from (select t, dst, count(*) as degree, row_number() over (partition by t order by count(*) desc, dst) as r from e group by t, dst) where r <= 3")
def topk_degree(spark, d):
    order = Window.partitionBy("t").orderBy(F.desc("degree"), "dst")
    return temporal.degrees(_trade(spark, d)).withColumn("r", F.row_number().over(order)).filter("r <= 3").drop("r")


def _late(name: str, sql: str | None = None):
    """Queries of modules that are loaded on first use."""

    def run(spark, d):
        from . import experiments

        return getattr(experiments, name)(spark, d)

    query(sql, name)(run)


DAILY_SQL = "select date_diff('day', timestamp '2024-01-01', ts)::int as t, event_type, count(*) as n, sum(cast(round(value * 100) as bigint))::bigint as cents from events group by 1, 2"
_late("stream_snapshots", DAILY_SQL)
_late("stream_sliding", "with e as (select date_diff('day', timestamp '2024-01-01', ts)::int as d, event_type, cast(round(value * 100) as bigint) as c from events), w as (select d as t, event_type, c from e union all select d - 1, event_type, c from e) select t::int as t, event_type, count(*) as n, sum(c)::bigint as cents from w group by 1, 2")
_late("stream_sessions", _sql["session_activity"])
_late("stream_static_join", "select date_diff('day', timestamp '2024-01-01', ts)::int as t, c_mktsegment as segment, count(*) as n from events left join customer on user_id = c_custkey group by 1, 2")
_late("stream_running_agg", f"with {HANDOFF}, days as (select unnest(range(0, 30)) as t) select t, dst, count(*) as cnt from (select distinct t, src, dst from (select distinct src, dst, m from act) join days on m <= t and t < m + 7) group by t, dst")
_late("gru_scalar_recurrence", "with recursive x as (select row_number() over (order by t) as i, v from (select date_diff('day', timestamp '2024-01-01', ts) as t, count(*) / 1000.0 as v from events group by 1)), s(i, h) as (select 0::bigint, 0.0::double union all select x.i, (1 - 1 / (1 + exp(-(0.5 * v + 0.3 * h)))) * h + 1 / (1 + exp(-(0.5 * v + 0.3 * h))) * tanh(0.8 * v + 0.6 * h / (1 + exp(-(0.2 * v + 0.4 * h)))) from s join x on x.i = s.i + 1) select i::int as i, round(h, 6) as h from s where i > 0")
_late("agg_one_step", TRADE + "select dst, count(*) as cnt, sum(f0)::bigint as a0, sum(f1)::bigint as a1 from c where t = 24 group by dst")


# counted workloads: the SQL builds edges e(t, src, dst, w), features f(t, node, f0, f1) and nodes of each graph
_DAYS = "months as (select unnest(range(0, 30)) as t)"
_MONTHS = f"months as (select unnest(range(0, {T})) as t)"
_GRAPHS = {
    "trade": (T, TRADE + ", nodes as (select 2 * c_custkey + 1 as node from customer union select 2 * s_suppkey from supplier)"),
    "handoff": (30, f"""with {HANDOFF}, {_DAYS}, e as (select distinct t, src, dst, 1 as w from (select distinct src, dst, m from act) join months on m <= t and t < m + 7),
nodes as (select distinct user_id as node from events), daily as (select user_id as node, date_diff('day', timestamp '2024-01-01', ts) as t, count(*) as f0, sum(cast(round(value * 100) as bigint)) as f1 from events group by 1, 2),
f as (select t, node, coalesce(f0, 0) as f0, coalesce(f1, 0) as f1 from nodes cross join months left join daily using (node, t))"""),
    "flow": (T, f"""with {SALES}, {_MONTHS}, nodes as (select n_nationkey as node from nation), e as (select m as t, s_nationkey as src, c_nationkey as dst, sum(revenue) as w, sum(qty) as qty from sales join supplier on src = 2 * s_suppkey join customer on dst = 2 * c_custkey + 1 group by 1, 2, 3),
f as (select t, src as node, sum(qty) as f0, sum(w) as f1 from e group by 1, 2)"""),
    "copurchase": (T, f"""with act as (select distinct a.l_partkey as src, b.l_partkey as dst, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 as m from lineitem a join lineitem b using (l_orderkey) join orders on l_orderkey = o_orderkey where a.l_partkey <> b.l_partkey),
{_MONTHS}, nodes as (select p_partkey as node from part), e as (select distinct t, src, dst, 1 as w from act join months on m <= t and t < m + 3), f as (select t, p_partkey as node, cast(round(p_retailprice * 100) as bigint) as f0, p_size as f1 from part cross join months)"""),
}


def _counts_sql(name: str, machines: int = 4, length: int = L, head: tuple[int, str] | None = None) -> str:
    """Snapshot profile: prof(t, n_edges, moved, remote); visits by stacked (vs) and integrated (vi) models; far (rows that sequence partitioning moves), turns."""
    n, cte = head or _GRAPHS[name]
    same = "b.src = a.src and b.dst = a.dst and b.w = a.w and b.f0 = a.f0 and b.f1 = a.f1"
    return f"""{cte}, ec as materialized (select e.t, src, dst, w, f0, f1 from e join f on e.t = f.t and e.src = f.node),
mv as (select a.t + 1 as t, count(*) as n from ec a left join ec b on b.t = a.t + 1 and {same} where b.src is null and a.t < {n - 1} group by 1 union all select b.t, count(*) from ec b left join ec a on a.t = b.t - 1 and {same} where a.src is null and b.t > 0 group by 1),
mvs as (select t, sum(n) as moved from mv group by t), ne as (select t, count(*) as n_edges from e group by t),
rem as (select t, count(distinct (dst % {machines}, src)) as remote from e where src % {machines} <> dst % {machines} group by t),
prof as (select months.t, coalesce(n_edges, 0) as n_edges, case when months.t > 0 then coalesce(moved, 0) else coalesce(n_edges, 0) end as moved, coalesce(remote, 0) as remote from months left join ne using (t) left join mvs using (t) left join rem using (t)),
sq as (select q, i, q + i as t from (select unnest(range(0, {n - length + 1})) as q), (select unnest(range(0, {length})) as i)),
pq as (select q, i, q + i as t from (select unnest(range(0, {n - length})) as q), (select unnest(range(0, {length})) as i)),
vs as (select t, count(*) as v from sq group by t), vi as (select t, count(*) as v from (select t from pq union all select t + 1 from pq) group by t),
far as (select count(*) as n from sq, nodes where i * {machines} // {length} <> node % {machines}), turns as (select count(*) as n from sq where i > 0 and i * {machines} // {length} <> (i - 1) * {machines} // {length})"""


_SHAPES = "shapes as (select * from (values " + ", ".join(f"('{m.name}', {m.decoder}, {m.gates})" for m in MODELS.values()) + ") x(model, decoder, k))"
_WAYS = "ways as (select unnest(['node_part', 'node_part_gate', 'seq_part', 'block']) as scheme)"
_PULLED = "(select sum(remote * v) from prof join vs using (t))"
_SENT = "((select n from far) + case when decoder then (select n from turns) * (select count(*) from nodes) else 0 end)"
_VISITED = "case when decoder then (select sum(v * n_edges) from prof join vi using (t)) else (select sum(v * n_edges) from prof join vs using (t)) end"
_ONCE = "case when decoder then (select sum(least(moved, n_edges)) from prof join vi using (t)) else (select sum(least(moved, n_edges)) from prof join vs using (t)) end"


def _overall_sql(head: str, models: str = "true", graph: str = "") -> str:
    reused = "case when decoder then 3 else 1 end"
    return f"""{head}, {_SHAPES}, {_WAYS} select {graph} model, scheme, (case when scheme = 'block' then 0 when scheme = 'seq_part' then {_SENT} * {H} * 32 else {_PULLED} * (2 + {H}) * 8 end)::bigint as bytes,
(case when scheme = 'block' then {_ONCE} + {_VISITED} * {reused} when not decoder then 2 * {_VISITED} when scheme = 'node_part_gate' then 4 * {_VISITED} else 4 * k * {_VISITED} end)::bigint as messages from shapes, ways where {models}"""


for _n in _GRAPHS:
    _late(f"overall_{_n}", _overall_sql(_counts_sql(_n), graph=f"'{_n}' as graph, "))
_CHURNED = CHURN.replace("0.1", "0.05").replace("range(1, 20)", "range(1, 40)").replace("coalesce(min(t), 20)", "coalesce(min(t), 40)")
_CHURNED_GRAPH = (40, _CHURNED[: _CHURNED.index("select src, dst, min(a)")].rstrip() + f""", ivs as (select src, dst, min(born) as a, died as b from fates group by src, dst, died), months as (select unnest(range(0, 40)) as t), nodes as (select n_nationkey::bigint as node from nation),
e as (select t, src, dst, 1 as w from ivs join months on a <= t and t < b), marks as (select node, t from nodes, months where t = 0 or (node * 7919 + t * 104729 + 3 * 1299709 + 43) % 1000003 < 0.05 * 1000003),
latest as (select months.t, node, max(marks.t) as m from months join marks on marks.t <= months.t group by 1, 2), f as (select t, node, {_h('node', 0, 'm')} % 1000 as f0, {_h('node', 1, 'm')} % 1000 as f1 from latest)""")
_late("table_churned", _overall_sql(_counts_sql("", head=_CHURNED_GRAPH), "model in ('stk_conv_lstm', 'int_conv_lstm')"))
_late("size_sweep", _counts_sql("trade") + f""", sizes_of as (select unnest([8, 16, 32, 64, 128]) as features, 64 as hidden union all select 100, unnest([16, 32, 64, 128]))
select features, hidden, scheme, (case scheme when 'block' then 0 when 'seq_part' then (select n from far) * hidden * 32 else {_PULLED} * (features + hidden) * 8 end)::bigint as bytes from sizes_of, (select unnest(['node_part', 'seq_part', 'block']) as scheme)""")
_late("machines_sweep", " union all ".join(f"""select * from ({_counts_sql('trade', m)}, most as (select max(n) as n from (select count(*) as n from (select unnest(range(0, {T - L + 1})) as q) group by q * {m} // {T - L + 1}))
select {m} as machines, scheme, (case scheme when 'block' then 0 when 'seq_part' then (select n from far) * {H} * 32 else coalesce({_PULLED}, 0) * (2 + {H}) * 8 end)::bigint as bytes, case scheme when 'block' then (select n from most)::int else {-(-(T - L + 1) // m)} end as most_samples from (select unnest(['node_part', 'seq_part', 'block']) as scheme))""" for m in (1, 2, 4, 8)))
_late("sequence_length_sweep", " union all ".join(f"""select * from ({_counts_sql('trade', 4, n)}, whole as (select sum(v * n_edges) as w from prof join vi using (t)), once as (select sum(least(moved, n_edges)) as o from prof join vi using (t))
select {n} as length, reuse, (case reuse when 'all' then o else 4 * w end)::bigint as first_inputs, (case reuse when 'all' then o + 3 * w else 16 * w end)::bigint as messages from whole, once, (select unnest(['all', 'none']) as reuse))""" for n in (4, 8, 16, 32)))


def _smooth_sql(w: int) -> str:
    return TRADE.replace("t < m + 12", f"t < m + {w}") + f"select round(avg((n_minus + n_plus) * 1.0 / nullif(n_edges, 0)), 6) as mean_ratio, {w} as window from ratios"


_late("smoothing_by_window", " union all ".join(f"select * from ({_smooth_sql(w)})" for w in (1, 6, 12, 24)))


def _churn_sql(rho: float) -> str:
    made = CHURN.replace("0.1 / 2", f"{rho} / 2")
    head = made[: made.index("select src, dst, min(a)")].rstrip() + f""", ivs as (select src, dst, min(born) as a, died as b from fates group by src, dst, died), months as (select unnest(range(0, 20)) as t), nodes as (select n_nationkey::bigint as node from nation),
e as (select t, src, dst, 1 as w from ivs join months on a <= t and t < b), marks as (select node, t from nodes, months where t = 0 or (node * 7919 + t * 104729 + 3 * 1299709 + 43) % 1000003 < {rho} * 1000003),
latest as (select months.t, node, max(marks.t) as m from months join marks on marks.t <= months.t group by 1, 2), f as (select t, node, {_h('node', 0, 'm')} % 1000 as f0, {_h('node', 1, 'm')} % 1000 as f1 from latest)"""
    return f"select * from ({_counts_sql('', head=(20, head))} select {rho}::double as rho, way, (case way when 'deltas' then (select sum(least(moved, n_edges)) from prof join vi using (t)) else (select sum(n_edges) from prof join vi using (t)) end)::bigint as first_inputs from (select unnest(['deltas', 'scratch']) as way))"


_late("churn_ratio_sweep", " union all ".join(map(_churn_sql, (0.0, 0.01, 0.05, 0.1, 0.25, 0.5, 1.0))))


def _near_sql(name: str) -> str:
    n, cte = _GRAPHS[name]
    batch = f"{cte}, batch as (select node, ({_h('node', 17, 0)} % 8)::int as batch_id from nodes where {_h('node', 17, 0)} % 8 = 0)"
    one = lambda label, fan: f"select '{label}' as fanouts, count(*) as edges from ({batch}{_hops(fan)} select * from k)"
    return " union all ".join(one(*x) for x in (("5 then 3", (5, 3)), ("25 then 10", (25, 10)), ("all", None)))


_late("sampling_handoff", _near_sql("handoff"))
_late("sampling_copurchase", _near_sql("copurchase"))


def _moved_sql(scheme: str) -> str:
    """What one epoch moves between two machines: two batches, 25 then 10 neighbours, hidden size 8."""
    head = HAND.replace("% 4)::int as batch_id", "% 2)::int as batch_id").rstrip()
    base = f"{head}{_hops((25, 10))}, need as materialized (select distinct batch_id, t, src as node from k union select batch_id, t, node from batch, days)"

    def one(model: str, train: int, extra: int) -> str:
        of = f"(select unnest(range(0, {train})) as q)"
        if scheme == "block":
            n = "0"
        elif scheme.startswith("node_part"):
            n = f"(select 16 * count(*) from need, {of} where t between q and q + {7 + extra} and node % 2 <> (q * 2 + batch_id) % 2)"
        elif model.startswith("stk"):
            crossed = "((idx - 1) * 2) // 8 <> node % 2"
            whole = f"(select distinct q, batch_id, node from need, {of} where t between q and q + 7), (select unnest(range(1, 9)) as idx)"
            n = f"(select 64 * count(*) from (select t - q + 1 as idx, node from need, {of} where t between q and q + 7) where {crossed}) + (select 5 * 64 * count(*) from {whole} where {crossed})"
        else:
            n = f"(select 6 * 2 * 64 * count(*) from (select distinct q, batch_id, node from need, {of} where t between q and q + {7 + extra}))"
        return f"select '{scheme}' as scheme, '{model}' as model, ({n})::bigint as bytes"

    return f"{base} {one('stk_conv_lstm', 17, 1)} union all {one('int_conv_gru', 16, 2)}"


for _n in ("block", "node_part", "node_part_gate", "seq_part"):
    _late(f"train_moved_{_n}", _moved_sql(_n))
    _late(f"train_mae_{_n}")
    _late(f"train_mae_{_n}_stacked")
_late("reuse_applicability", "select * from (values " + ", ".join(
    f"('{m.name}', {layer}, '{operand}', {m.decoder}, {layer == 1 and operand == 'input'}, {layer == 1 and operand == 'input' and m.decoder}, {layer == 1 and operand == 'input'})"
    for m in MODELS.values() for layer in (1, 2) for operand in (("input", "hidden") if m.decoder else ("input",))) + ") x(model, layer, operand, gates, sequences, teacher, incremental)")
for _n in (*(f"forward_{m}" for m in MODELS), "train_ablation", "train_cache_capacity", "epoch_times", "aggregation_times", "attention_layer", "forecast_vs_last"):
    _late(_n)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_q)


def oracle_sql() -> dict[str, str]:
    # snapshot, sequence and gate numbers are INT on both sides
    return {n: re.sub(r"unnest\(range\((\d[^()]*)\)\)", r"unnest(range(\1)::int[])", s) for n, s in _sql.items()}
