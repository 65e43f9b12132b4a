"""Queries that train, stream or sweep a parameter."""

from __future__ import annotations

import datetime
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import train
from .nn import layers as nn_layers
from .nn import sweep
from .nn.models import init
from .nn.tape import Var
from .operators import aggregate, batches, delta, measures
from .operators.temporal import TemporalGraph, coded, expand
from .plans.reuse import ALL, MODELS, NONE, Flags, applicable
from .sources import graphs
from .sources.tables import load
from .streaming import events as stream

#: One reuse at a time, none and all.
ABLATION = {"none": NONE, "incremental": Flags(True, False, False, False), "gates": Flags(False, True, False, False), "sequences": Flags(False, False, True, False), "teacher": Flags(False, False, False, True), "all": ALL}
GRAPHS: dict[str, Callable[[SparkSession, str], TemporalGraph]] = {"trade": graphs.trade, "handoff": graphs.handoff, "flow": graphs.flow, "copurchase": graphs.copurchase}


# streams


def _third(spark: SparkSession, d: str) -> str:
    cuts = [datetime.datetime(2024, 1, 11), datetime.datetime(2024, 1, 21)]
    return stream.staged(spark, load(spark, d, "events"), cuts)


def stream_snapshots(spark, d: str) -> DataFrame:
    """Daily sums by type from a stream in three parts, closed windows only."""
    done = stream.run_to_table(stream.windows(stream.read_events(spark, _third(spark, d), per_trigger=1)))
    return done.select(F.datediff(F.col("w.start"), F.lit("2024-01-01").cast("date")).alias("t"), "event_type", "n", "cents")


def stream_sliding(spark, d: str) -> DataFrame:
    """Sums over two days, a new window each day."""
    done = stream.run_to_table(stream.windows(stream.read_events(spark, _third(spark, d)), "2 days", "1 day"))
    return done.select(F.datediff(F.col("w.start"), F.lit("2024-01-01").cast("date")).alias("t"), "event_type", "n", "cents")


def stream_sessions(spark, d: str) -> DataFrame:
    done = stream.run_to_table(stream.sessions(stream.read_events(spark, _third(spark, d))))
    return done.filter("user_id is not null").select("user_id", F.unix_micros("w.start").alias("began"), "n")


def stream_static_join(spark, d: str) -> DataFrame:
    """Events of a stream beside their user's market segment, a static table; counts per segment and day."""
    segment = load(spark, d, "customer").select("c_custkey", "c_mktsegment")
    e = stream.read_events(spark, _third(spark, d)).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 day")
    joined = e.join(segment, F.col("user_id") == F.col("c_custkey"), "left").groupBy(F.window("ts", "1 day").alias("w"), "c_mktsegment").agg(F.count("user_id").alias("n"))
    done = stream.run_to_table(joined)
    return done.filter("n > 0").select(F.datediff(F.col("w.start"), F.lit("2024-01-01").cast("date")).alias("t"), F.col("c_mktsegment").alias("segment"), "n")


def stream_running_agg(spark, d: str) -> DataFrame:
    """In-degrees of the trailing hand-off graph, kept while a stream brings the events and moved by each closed day's deltas."""
    return stream.run_incremental(stream.read_events(spark, _third(spark, d)), 7).result().filter(F.col("t") < graphs.DAYS).select(F.col("t").cast("int").alias("t"), "dst", "cnt")


def gru_scalar_recurrence(spark, d: str) -> DataFrame:
    """A cell of width one run over the daily event counts, in order, by a fold over the (few) days."""
    e = load(spark, d, "events").groupBy(graphs.day("ts").alias("t")).agg((F.count(F.lit(1)) / 1000.0).alias("v"))
    days = e.agg(F.sort_array(F.collect_list(F.struct("t", "v"))).alias("days"))
    sig = lambda x: f"1D / (1D + exp(-({x})))"
    nxt = f"(1D - {sig('0.5D * x.v + 0.3D * last')}) * last + {sig('0.5D * x.v + 0.3D * last')} * tanh(0.8D * x.v + 0.6D * last * {sig('0.2D * x.v + 0.4D * last')})"
    fold = f"aggregate(days, array(0D), (s, x) -> concat(s, transform(array(element_at(s, -1)), last -> {nxt})))"
    return days.select(F.posexplode(F.expr(fold)).alias("i", "h")).filter("i > 0").select("i", F.round("h", 6).alias("h"))


# models


def _forward(name: str):
    def run(spark, d: str) -> DataFrame:
        """Mean absolute prediction of every sequence with fixed weights, with all reuse and with none, over all blocks and batches."""
        g = coded(graphs.handoff(spark, d))  # hops, features and scales read it apart
        job = train.Job(model=name, batches=1, held_out=0.0, chunks=1)
        s = train.samples(g, job)
        qs: dict[int, list[int]] = s.chunk(0)
        lanes, scale, length = s.lanes, s.scale, job.length

        def one(key, t, _, work):
            block, label = int(key[0]), key[1]
            w, flags, out = init(name, len(lanes), 8), {"all": ALL, "none": NONE}[label], []
            times = [list(range(q, q + length)) for q in qs[block]]
            t.expect(name, times, flags)
            for at, ts in enumerate(times):
                before, means = t.messages(), []
                sweep.sweep(name, t, at, ts, w, 8, flags, lambda i, y, means=means: means.append(float(np.abs(y).mean())), work)
                out.append((name, label, qs[block][at], float(np.mean(means)), t.messages() - before))
            yield pa.RecordBatch.from_arrays([pa.array(list(x), kind) for x, kind in zip(zip(*out), (pa.string(), pa.string(), pa.int32(), pa.float64(), pa.int64()))], ["model", "reuse", "q", "mean_output", "messages"])

        keys = ["block", "reuse"]
        rows = train.bundled(s.rows, ["block", "batch_id"], lanes).withColumn("reuse", F.explode(F.array(F.lit("all"), F.lit("none"))))
        rows = train.in_order(rows.repartition(*keys), keys)
        out = train.streamed(rows, keys, one, lanes, scale, job, "model string, reuse string, q int, mean_output double, messages long")
        return out.withColumn("mean_output", F.round("mean_output", 9))

    return run


for _m in MODELS:
    globals()[f"forward_{_m}"] = _forward(_m)


def _train(scheme: str, model: str):
    def run(spark, d: str) -> DataFrame:
        """Errors by epoch with the bytes moved between machines and the messages of the graph layers so far."""
        _, curve = train.fit(graphs.handoff(spark, d), train.Job(model=model, scheme=scheme, chunks=1))
        rows = [(c["scheme"], c["model"], c["epoch"], round(c["train_mae"], 8), round(c["test_mae"], 8), c["moved"], int(c.get("messages", 0))) for c in curve]
        return spark.createDataFrame(rows, "scheme string, model string, epoch int, train_mae double, test_mae double, moved_bytes long, messages long")

    return run


for _s in train.SCHEMES:
    globals()[f"train_mae_{_s}"] = _train(_s, "int_conv_gru")
    globals()[f"train_mae_{_s}_stacked"] = _train(_s, "stk_conv_lstm")


def _moved(scheme: str):
    def run(spark, d: str) -> DataFrame:
        """Bytes that one epoch moves, counted while it runs."""
        g, rows = graphs.handoff(spark, d), []
        for model in ("stk_conv_lstm", "int_conv_gru"):
            _, curve = train.fit(g, train.Job(model=model, scheme=scheme, chunks=1, epochs=1))
            rows.append((scheme, model, int(curve[-1]["moved"])))
        return spark.createDataFrame(rows, "scheme string, model string, bytes long")

    return run


for _s in train.SCHEMES:
    globals()[f"train_moved_{_s}"] = _moved(_s)


def train_ablation(spark, d: str) -> DataFrame:
    """Counters of one epoch under each reuse, of all four models, as run: passes and messages fall, the error does not move."""
    g, rows = graphs.handoff(spark, d), []
    cases = [(model, name) for model in MODELS for name in ABLATION]
    jobs = [train.Job(model=model, chunks=1, batches=1, epochs=1, flags=ABLATION[name]) for model, name in cases]
    for (model, name), (_, _, c) in zip(cases, train.fit_all(g, jobs, train.ABREAST)):
        rows.append((model, name, round(c[-1]["test_mae"], 8), *(int(c[-1][k]) for k in ("passes", "messages", "hits", "misses"))))
    return spark.createDataFrame(rows, "model string, reuse string, test_mae double, passes long, messages long, hits long, misses long")


def train_cache_capacity(spark, d: str) -> DataFrame:
    """The global store while training: hits, messages and peak bytes by policy and capacity; the error does not move."""
    g, rows = graphs.handoff(spark, d), []
    cases = (("lookahead", 1), ("lookahead", 4), ("lookahead", 9), ("lru", 4), ("lru", 9), ("lfu", 4), ("lookahead", None))
    for job, _, c in train.fit_all(g, [train.Job(model="int_conv_lstm", chunks=1, batches=1, epochs=1, capacity=capacity, policy=policy) for policy, capacity in cases], train.ABREAST):
        rows.append((job.policy, job.capacity, round(c[-1]["test_mae"], 8), *(int(c[-1][k]) for k in ("hits", "misses", "messages", "peak_bytes"))))
    return spark.createDataFrame(rows, "policy string, capacity int, test_mae double, hits long, misses long, messages long, peak_bytes long")


def epoch_times(spark, d: str) -> DataFrame:
    """Seconds of a warm epoch by scheme and model, samples per second, and the speedup over plain node partitioning (measured, so they vary)."""
    g, rows = graphs.handoff(spark, d), []
    for model in ("stk_conv_lstm", "int_conv_gru"):
        base = None
        schemes = ("node_part", "node_part_gate", "seq_part", "block")
        for scheme, (_, _, c) in zip(schemes, train.fit_all(g, [train.Job(model=model, scheme=s, chunks=1, batches=1, epochs=2) for s in schemes])):
            last = c[-1]
            base = base or last["seconds"]
            rows.append((model, scheme, last["seconds"], measures.throughput(last["samples"], last["seconds"]), measures.speedup(base, last["seconds"]), int(last["moved"]) // 2))
    return spark.createDataFrame(rows, "model string, scheme string, seconds double, samples_per_second double, speedup double, bytes long")


def aggregation_times(spark, d: str) -> DataFrame:
    """Seconds (median of warm runs) of aggregation from scratch and by deltas, where little and where much changes (measured, so they vary)."""
    rows = []
    for trailing in (24, 1):
        g = aggregate.by_target(graphs.trade(spark, d, trailing))  # what is timed is the aggregation, not the graph's making
        for name, f in (("scratch", aggregate.scratch), ("incremental", aggregate.incremental)):
            rows.append((trailing, name, measures.epoch_time(lambda f=f, g=g: f(g).write.format("noop").mode("overwrite").save())))
    return spark.createDataFrame(rows, "window int, way string, seconds double")


def attention_layer(spark, d: str) -> DataFrame:
    """Learned attention over in-edges with fixed weights: every snapshot from scratch, and by deltas; messages and the largest difference."""
    g = graphs.handoff(spark, d)
    job = train.Job(model="stk_conv_lstm", batches=1, held_out=0.0, machines=1, chunks=1, fanouts=(3, 2))
    s = train.samples(g, job)
    lanes, scale = s.lanes, s.scale

    def one(pdf):
        import pandas as pd

        sample, _, _ = train.unpack(pdf, lanes, scale, job)
        layer = nn_layers.GraphAttention(len(lanes), 4)
        out = []
        feats = {t: sample.x(t) for t in sample.feats}
        for t in sorted(sample.graphs):
            before = sample.messages()
            kept = layer.infer(t, sample.graphs, feats, layer.w)
            used = sample.messages() - before
            whole = layer(sample.graphs[t], Var(feats[t]), {k: Var(v) for k, v in layer.w.items()}).value
            out.append((t, used, len(sample.graphs[t].src), float(np.round(np.abs(whole - kept).max(), 9))))
        return pd.DataFrame(out, columns=["t", "messages", "edges", "difference"])

    return s.rows.groupBy("block").applyInPandas(one, "t int, messages long, edges long, difference double")


def reuse_applicability(spark, d: str) -> DataFrame:
    """Which reuse applies to which operand of which layer."""
    rows = [tuple(r.values()) for m in MODELS.values() for r in applicable(m)]
    return spark.createDataFrame(rows, "model string, layer int, operand string, gates boolean, sequences boolean, teacher boolean, incremental boolean")


def forecast_vs_last(spark, d: str) -> DataFrame:
    """Next-snapshot error of a trained model beside that of repeating the last value, over users and over nations."""
    rows = []
    for name in ("handoff", "flow"):
        g = GRAPHS[name](spark, d)
        _, curve = train.fit(g, train.Job(model="stk_skip_lstm", epochs=4, batches=1))
        top = g.feats.agg(F.max("f0"), F.max("f1")).first()
        f = g.nodes.select("node", F.explode(F.sequence(F.lit(0), F.lit(g.snapshots - 1))).alias("t")).join(expand(g.feats), ["node", "t"], "left").fillna(0, list(g.lanes))
        after = f.select("node", (F.col("t") + 1).alias("t"), *[F.col(x).alias(f"was_{x}") for x in g.lanes])
        err = f.join(after, ["node", "t"]).select("t", *[(F.abs(F.col(x) - F.col(f"was_{x}")) / float(m)).alias(x) for x, m in zip(g.lanes, top)])
        last = err.filter(F.col("t") >= int((g.snapshots - 8) * 0.8) + 8).agg(F.avg((F.col("f0") + F.col("f1")) / 2)).first()[0]
        rows += [(name, "model", round(curve[-1]["test_mae"], 6)), (name, "last value", round(float(last), 6))]
    return spark.createDataFrame(rows, "graph string, forecast string, mae double")


# sweeps by count


def smoothing_by_window(spark, d: str) -> DataFrame:
    """Mean change ratio by trailing window: longer windows move less."""
    out = None
    for w in (1, 6, 12, 24):
        one = delta.ratio(graphs.trade(spark, d, trailing=w)).agg(F.round(F.avg("change_ratio"), 6).alias("mean_ratio")).withColumn("window", F.lit(w))
        out = one if out is None else out.union(one)
    return out


def churn_ratio_sweep(spark, d: str) -> DataFrame:
    """Messages of layer 1's inputs by change ratio: rising with it by deltas, flat from scratch."""
    out = None
    for rho in (0.0, 0.01, 0.05, 0.1, 0.25, 0.5, 1.0):
        g = graphs.churned_flow(spark, d, 20, rho)
        both = [measures.work(g, MODELS["int_conv_lstm"], f).select(F.lit(rho).alias("rho"), F.lit(n).alias("way"), "first_inputs") for n, f in (("deltas", Flags(True, True, True, True)), ("scratch", Flags(False, True, True, True)))]
        both = both[0].union(both[1])
        out = both if out is None else out.union(both)
    return out


LENGTHS = (4, 8, 16, 32)


def sequence_length_sweep(spark, d: str) -> DataFrame:
    """Messages per epoch by sequence length: layer 1's inputs stay flat with reuse and grow without."""
    p = measures.profile(graphs.trade(spark, d), 4)
    rows = [(n, name, *measures.messages(p, MODELS["int_conv_lstm"], f, n)) for n in LENGTHS for name, f in (("all", ALL), ("none", NONE))]
    return spark.createDataFrame(rows, "length int, reuse string, first_inputs long, messages long")


#: What each scheme reuses, for counting.
COUNTED = {"node_part": NONE, "node_part_gate": Flags(False, True, False, False), "seq_part": NONE, "block": ALL}


def _overall(names: list[str]):
    def run(spark, d: str) -> DataFrame:
        """Bytes between machines and messages of one epoch: model by graph by scheme, full neighbourhoods, four machines."""
        rows = []
        for g in names:
            p = measures.profile(GRAPHS[g](spark, d), 4)
            for m in MODELS.values():
                rows += [(g, m.name, s, measures.scheme_bytes(p, m, s), measures.messages(p, m, f)[1]) for s, f in COUNTED.items()]
        return spark.createDataFrame(rows, "graph string, model string, scheme string, bytes long, messages long")

    return run


for _g in GRAPHS:
    globals()[f"overall_{_g}"] = _overall([_g])


def table_churned(spark, d: str) -> DataFrame:
    """The motivating table on a graph made dynamic (ratio 0.05): bytes and messages of the schemes, one stacked and one integrated model."""
    p = measures.profile(graphs.churned_flow(spark, d, 40, 0.05), 4)
    rows = [(m, s, measures.scheme_bytes(p, MODELS[m], s), measures.messages(p, MODELS[m], f)[1]) for m in ("stk_conv_lstm", "int_conv_lstm") for s, f in COUNTED.items()]
    return spark.createDataFrame(rows, "model string, scheme string, bytes long, messages long")


FEATURES, HIDDENS, MACHINES = (8, 16, 32, 64, 128), (16, 32, 64, 128), (1, 2, 4, 8)


def size_sweep(spark, d: str) -> DataFrame:
    """Bytes by feature and hidden size: node partitioning grows with both, sequence partitioning with the hidden size alone, blocks move nothing."""
    p = measures.profile(graphs.trade(spark, d), 4)
    m = MODELS["stk_conv_lstm"]
    sizes = [(f, 64) for f in FEATURES] + [(100, h) for h in HIDDENS]
    rows = [(f, h, s, measures.scheme_bytes(p, m, s, width=f, hidden=h)) for f, h in sizes for s in ("node_part", "seq_part", "block")]
    return spark.createDataFrame(rows, "features int, hidden int, scheme string, bytes long")


def machines_sweep(spark, d: str) -> DataFrame:
    """By number of machines: bytes, and the largest number of samples on one machine."""
    g, rows = graphs.trade(spark, d), []
    for n in MACHINES:
        p = measures.profile(g, n)
        most = max(sum(q * n // p.sequences(8) == b for q in range(p.sequences(8))) for b in range(n))
        rows += [(n, s, measures.scheme_bytes(p, MODELS["stk_conv_lstm"], s), most if s == "block" else -(-p.sequences(8) // n)) for s in ("node_part", "seq_part", "block")]
    return spark.createDataFrame(rows, "machines int, scheme string, bytes long, most_samples int")


def _sampling(name: str):
    def run(spark, d: str) -> DataFrame:
        """Edges of the two-hop computation graphs of one batch in eight, sampled and whole, with the mean in-degree: sampling saves little on the sparse graph and much on the dense one."""
        g = GRAPHS[name](spark, d)
        batch = batches.sampler(g.nodes, 8).filter("batch_id = 0")
        out = None
        for label, fan in (("5 then 3", (5, 3)), ("25 then 10", (25, 10)), ("all", None)):
            one = batches.khop(g, batch, 2, fan).agg(F.count(F.lit(1)).alias("edges")).select(F.lit(label).alias("fanouts"), "edges")
            out = one if out is None else out.union(one)
        return out

    return run


sampling_handoff, sampling_copurchase = _sampling("handoff"), _sampling("copurchase")


def agg_one_step(spark, d: str) -> DataFrame:
    """Aggregates of snapshot 24 from those of snapshot 23 and the two delta sets."""
    g = graphs.trade(spark, d)
    before = aggregate.scratch(g).filter("t = 23").drop("t")
    return aggregate.step(before, delta.build(g).filter("t = 24"), g.lanes)

