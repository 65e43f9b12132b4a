"""Dynamic graphs from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.exact import PRIME, arithmetic_hash, cents, edge_id, month
from ..operators.temporal import TemporalGraph, by_snapshot, expand, from_activity, from_snapshots, runs_of_values
from .tables import load

MONTHS = 80
DAYS = 30
QUANTITY_STEP = 400
#: Ids in one slice of the citation order.
CITATION_SLICE = 100_000


def _sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers get even node ids, customers odd ones."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity", "l_extendedprice")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", month("o_orderdate").alias("t"))
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.select((2 * F.col("l_suppkey")).alias("src"), (2 * F.col("o_custkey") + 1).alias("dst"), "t", F.round("l_quantity").cast("long").alias("qty"), cents("l_extendedprice").alias("revenue"))


def trade(spark: SparkSession, sf_dir: str, trailing: int = 12, lane_set: str = "slow") -> TemporalGraph:
    """Supplier -> customer, active for `trailing` months from each order. Lanes: balance and last quarter's quantity level (slow), or each month's quantity and revenue (volatile)."""
    sales = _sales(spark, sf_dir)
    supplier = load(spark, sf_dir, "supplier").select((2 * F.col("s_suppkey")).alias("node"), cents("s_acctbal").alias("f0"))
    if lane_set == "slow":
        grid = supplier.withColumn("quarter", F.explode(F.sequence(F.lit(0), F.lit((MONTHS - 1) // 3))))
        sold = sales.groupBy(F.col("src").alias("node"), (F.floor(F.col("t") / 3) + 1).cast("int").alias("quarter")).agg(F.sum("qty").alias("qty"))
        level = F.floor(F.coalesce("qty", F.lit(0)) / QUANTITY_STEP).cast("long")
        values = grid.join(sold, ["node", "quarter"], "left").select("node", "f0", level.alias("f1"), (3 * F.col("quarter")).alias("valid_from"), F.least(3 * F.col("quarter") + 3, F.lit(MONTHS)).alias("valid_to"))
    else:
        values = sales.groupBy(F.col("src").alias("node"), "t").agg(F.sum("qty").alias("f0"), F.sum("revenue").alias("f1")).select("node", "f0", "f1", F.col("t").alias("valid_from"), (F.col("t") + 1).alias("valid_to"))
    customers = load(spark, sf_dir, "customer").select((2 * F.col("c_custkey") + 1).alias("node"))
    return TemporalGraph(from_activity(sales, trailing, MONTHS), runs_of_values(values, "node", ("f0", "f1")), supplier.select("node").union(customers), MONTHS)


def day(col: str) -> Column:
    return F.datediff(col, F.lit("2024-01-01").cast("date"))


def targets(activity: DataFrame, trailing: int, snapshots: int, batches: int = 1) -> DataFrame:
    """batch_id, t, rows: the nodes `dst` of a batch that were active in the trailing snapshots."""
    active = from_activity(activity.select(F.lit(0).alias("src"), "dst", "t"), trailing, snapshots)
    batch = F.pmod(arithmetic_hash(F.col("dst"), 17), F.lit(batches)).cast("int")
    return by_snapshot(active.withColumn("batch_id", batch), "batch_id")


def handoff_targets(spark: SparkSession, sf_dir: str, batches: int = 1) -> DataFrame:
    """Users with an in-edge in each snapshot of the hand-off graph."""
    return targets(handoff_activity(spark, sf_dir), 7, DAYS, batches)


def trade_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with an in-edge in each snapshot of the trade graph."""
    return targets(_sales(spark, sf_dir), 12, MONTHS)


def order_targets(spark: SparkSession, sf_dir: str, length: int, batches: int) -> DataFrame:
    """Customers of each batch with an order in the `length` months that end at t."""
    orders = load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("dst"), month("o_orderdate").alias("t"))
    return targets(orders, length, MONTHS, batches)


def before_in_order(df: DataFrame, keys: list[str], cut: Column, order: list[str], value: str, back: int = 1) -> DataFrame:
    """Adds `earlier`: up to `back` values before each row, nearest first, within `keys` in `order`.

    Groups may hold any share of the rows: each is cut into slices that follow the order (`cut`, a function of its first
    column). Within a slice a window answers; the rows at a slice's start look into the ends of the slices before it, of which each gives `back` values."""
    rows = df.withColumn("_cut", cut)
    slice_ = Window.partitionBy(*keys, "_cut").orderBy(*order)
    rows = rows.withColumn("_own", F.collect_list(value).over(slice_.rowsBetween(-back, -1)))
    last = rows.withColumn("_place", F.row_number().over(Window.partitionBy(*keys, "_cut").orderBy(*[F.desc(c) for c in order]))).filter(F.col("_place") <= back)
    ends = last.groupBy(*keys, "_cut").agg(F.sort_array(F.collect_list(F.struct((-F.col("_place")).alias("p"), F.col(value).alias("v")))).alias("_end"))
    over = Window.partitionBy(*keys).orderBy("_cut").rowsBetween(-back, -1)
    ends = ends.select(*keys, "_cut", F.flatten(F.collect_list(F.expr("transform(_end, x -> x.v)")).over(over)).alias("_before"))
    joined = rows.join(ends, [*keys, "_cut"], "left")
    whole = F.reverse(F.concat(F.coalesce("_before", F.array().cast(f"array<{df.schema[value].dataType.simpleString()}>")), F.col("_own")))
    return joined.withColumn("earlier", F.slice(whole, 1, back)).drop("_cut", "_own", "_before")


def handoff_pairs(events: DataFrame) -> DataFrame:
    """Previous -> next user of one event type and day (t), cut into quarters of an hour."""
    quarter = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 900_000_000)
    e = before_in_order(events, ["event_type", "t"], quarter, ["ts", "event_id"], "user_id")
    return e.select(F.expr("try_element_at(earlier, 1)").alias("src"), F.col("user_id").alias("dst"), "t").filter("src is not null and src <> dst")


def handoff_activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return handoff_pairs(load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", day("ts").alias("t")))


def handoff(spark: SparkSession, sf_dir: str, trailing: int = 7) -> TemporalGraph:
    """Lanes: events and value (cents) of each user and day."""
    e = load(spark, sf_dir, "events").select("user_id", "value", day("ts").alias("t"))
    daily = e.groupBy(F.col("user_id").alias("node"), "t").agg(F.count(F.lit(1)).alias("f0"), F.sum(cents("value")).alias("f1"))
    users = e.select(F.col("user_id").alias("node")).distinct()
    grid = users.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(DAYS - 1))))
    values = grid.join(daily, ["node", "t"], "left").fillna(0, ["f0", "f1"]).select("node", "f0", "f1", F.col("t").alias("valid_from"), (F.col("t") + 1).alias("valid_to"))
    return TemporalGraph(from_activity(handoff_activity(spark, sf_dir), trailing, DAYS), runs_of_values(values, "node", ("f0", "f1")), users, DAYS)


def flow_monthly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """t, src and dst nation, quantity, revenue in cents."""
    supplier = load(spark, sf_dir, "supplier").select((2 * F.col("s_suppkey")).alias("src"), F.col("s_nationkey").cast("long").alias("from_nation"))
    customer = load(spark, sf_dir, "customer").select((2 * F.col("c_custkey") + 1).alias("dst"), F.col("c_nationkey").cast("long").alias("to_nation"))
    sales = _sales(spark, sf_dir).join(supplier, "src").join(customer, "dst")
    return sales.groupBy("t", F.col("from_nation").alias("src"), F.col("to_nation").alias("dst")).agg(F.sum("qty").alias("qty"), F.sum("revenue").alias("revenue"))


def flow(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    """Nation -> nation, weighted by revenue (cents); a weight change is a deletion and an insertion."""
    monthly = flow_monthly(spark, sf_dir)
    edges = from_snapshots(monthly.select("src", "dst", F.col("revenue").alias("w"), "t"), MONTHS)
    nodes = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("node"))
    values = monthly.groupBy(F.col("src").alias("node"), "t").agg(F.sum("qty").alias("f0"), F.sum("revenue").alias("f1")).select("node", "f0", "f1", F.col("t").alias("valid_from"), (F.col("t") + 1).alias("valid_to"))
    return TemporalGraph(edges, runs_of_values(values, "node", ("f0", "f1")), nodes, MONTHS)


def copurchase(spark: SparkSession, sf_dir: str, trailing: int = 3) -> TemporalGraph:
    """Part -> part of one order (an order has few lines, so the self-join is bounded). Lanes: price (cents) and size."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    orders = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), month("o_orderdate").alias("t"))
    dated = lines.join(orders, "l_orderkey")
    pairs = dated.alias("a").join(dated.alias("b"), "l_orderkey").filter("a.l_partkey <> b.l_partkey").select(F.col("a.l_partkey").alias("src"), F.col("b.l_partkey").alias("dst"), F.col("a.t").alias("t"))
    part = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), cents("p_retailprice").alias("f0"), F.col("p_size").cast("long").alias("f1"), F.lit(0).alias("valid_from"), F.lit(MONTHS).alias("valid_to"))
    return TemporalGraph(from_activity(pairs, trailing, MONTHS), part, part.select("node"), MONTHS)


def citation_edges(spark: SparkSession, sf_dir: str, back: int = 3, per_snapshot: int = 50) -> DataFrame:
    """Document -> each of its `back` predecessors of one source; arrives at doc_id / per_snapshot."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "source")
    docs = before_in_order(docs, ["source"], F.floor(F.col("doc_id") / CITATION_SLICE), ["doc_id"], "doc_id", back)
    return docs.select(F.col("doc_id").alias("src"), F.explode("earlier").alias("dst"), F.floor(F.col("doc_id") / per_snapshot).cast("int").alias("valid_from"))


def churn(base: DataFrame, n_nodes: int, snapshots: int, rho: float | None, seed: int = 42) -> DataFrame:
    """A static base (src, dst) made dynamic: with ratio rho (None: drawn per snapshot) half of it dies, half is born at each step."""
    ratio = F.lit(rho) if rho is not None else arithmetic_hash(0, F.col("t"), 0, seed) / PRIME
    spark = base.sparkSession
    steps = spark.range(1, snapshots).select(F.col("id").alias("t")).withColumn("ratio", ratio)
    size = base.agg(F.count(F.lit(1)).alias("m"))
    new = steps.join(F.broadcast(size)).withColumn("i", F.explode(F.expr("sequence(0L, greatest(cast(floor(ratio / 2 * m) as bigint) - 1, 0L))"))).filter("i < floor(ratio / 2 * m)")
    born = new.select(F.pmod(arithmetic_hash(F.col("i"), F.col("t"), 1, seed), F.lit(n_nodes)).alias("src"), F.pmod(arithmetic_hash(F.col("t"), F.col("i"), 2, seed), F.lit(n_nodes)).alias("dst"), F.col("t").alias("valid_from")).filter("src <> dst")
    births = base.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.lit(0).cast("long").alias("valid_from")).union(born).distinct()
    # one row per snapshot, so the ratios travel as one array; the first death is found within the row
    ratios = steps.agg(F.transform(F.sort_array(F.collect_list(F.struct("t", "ratio"))), lambda x: x["ratio"]).alias("ratios"))
    dies = lambda t: arithmetic_hash(F.col("src"), F.col("dst"), t, seed) < F.get("ratios", (t - 1).cast("int")) / 2 * PRIME
    later = F.when(F.col("valid_from") < snapshots - 1, F.sequence(F.col("valid_from") + 1, F.lit(snapshots - 1).cast("long"))).otherwise(F.array().cast("array<bigint>"))
    end = F.array_min(F.filter(later, dies))
    ended = births.join(F.broadcast(ratios)).withColumn("valid_to", F.coalesce(end, F.lit(snapshots)))
    lives = ended.groupBy("src", "dst", "valid_to").agg(F.min("valid_from").alias("valid_from"))
    # an edge born in the snapshot in which it would die lives on
    order = Window.partitionBy("src", "dst").orderBy("valid_from")
    fresh = F.when(F.col("valid_from") <= F.lag("valid_to").over(order), 0).otherwise(1)
    lives = lives.withColumn("fresh", fresh).withColumn("stay", F.sum("fresh").over(order))
    merged = lives.groupBy("src", "dst", "stay").agg(F.min("valid_from").alias("valid_from"), F.max("valid_to").alias("valid_to"))
    return merged.select("src", "dst", edge_id().alias("edge_id"), F.lit(1).cast("long").alias("w"), F.col("valid_from").cast("int").alias("valid_from"), F.col("valid_to").cast("int").alias("valid_to"))


def churn_feats(nodes: DataFrame, snapshots: int, rho: float, lanes: int = 2, seed: int = 42) -> DataFrame:
    """A node gets new features at t with probability rho, of the same width, by hashing (node, lane, version)."""
    versions = nodes.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(snapshots - 1)))).filter((F.col("t") == 0) | (arithmetic_hash(F.col("node"), F.col("t"), 3, seed + 1) < rho * PRIME))
    order = Window.partitionBy("node").orderBy("t")
    made = [F.pmod(arithmetic_hash(F.col("node"), F.lit(k), F.col("t"), seed), F.lit(1000)).alias(f"f{k}") for k in range(lanes)]
    values = versions.select("node", *made, F.col("t").alias("valid_from"), F.coalesce(F.lead("t").over(order), F.lit(snapshots)).alias("valid_to"))
    return runs_of_values(values, "node", tuple(f"f{k}" for k in range(lanes)))


def replicate(edges: DataFrame, copies: int, n_nodes: int) -> DataFrame:
    """Copies of a graph side by side; copy r adds r * n_nodes to every id."""
    shifted = edges.withColumn("r", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumns({c: F.col(c) + F.col("r") * n_nodes for c in ("src", "dst")})
    return shifted.withColumn("edge_id", edge_id()).drop("r")


def flow_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return expand(flow(spark, sf_dir).edges).select("src", "dst").distinct()


def churned_flow(spark: SparkSession, sf_dir: str, snapshots: int = 20, rho: float | None = 0.1) -> TemporalGraph:
    nodes = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("node"))
    return TemporalGraph(churn(flow_base(spark, sf_dir).filter("src <> dst"), 25, snapshots, rho), churn_feats(nodes, snapshots, rho if rho is not None else 0.5), nodes, snapshots)
