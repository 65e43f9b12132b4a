import tracemalloc

import numpy as np
import pyarrow as pa
import pytest

from tgengine import catalogue, train
from tgengine.nn import models, sweep
from tgengine.plans import reuse
from tgengine.sources import graphs

LANES, SCALE = ("f0", "f1"), np.array([9.0, 9.0])


def batches(snapshots, nodes, edges, seed=0):
    """Rows of one sample as they come to a task: features, then packed edges by snapshot."""
    r = np.random.default_rng(seed)
    none = pa.nulls(nodes, pa.binary())
    for t in range(snapshots):
        f = [pa.array(["f"] * nodes), pa.array(np.full(nodes, t)), pa.array(3 * np.arange(nodes)), pa.array((np.arange(nodes) % 2 == 0).astype(np.int64)), pa.array(np.full(nodes, (nodes + 1) // 2))]
        yield pa.RecordBatch.from_arrays([*f, *[pa.array(r.integers(0, 9, nodes).astype(float)) for _ in LANES], none, none], ["kind", "t", "a", "b", "n", *LANES, "src", "dst"])
    code = r.choice(nodes * nodes, edges, replace=False)
    for t in range(snapshots):
        code = np.unique(np.r_[code[2:], r.choice(nodes * nodes, 2)])
        for part in np.array_split(r.permutation(code), 3):
            ends = [pa.array([(3 * x).astype("<i8").tobytes()], pa.binary()) for x in (part // nodes, part % nodes)]
            zero = [pa.array([0]), pa.array([0]), pa.array([0]), pa.array([0.0]), pa.array([0.0])]
            yield pa.RecordBatch.from_arrays([pa.array(["e"]), pa.array([t]), *zero, *ends], ["kind", "t", "a", "b", "n", *LANES, "src", "dst"])


@pytest.mark.parametrize("name", list(reuse.MODELS))
@pytest.mark.parametrize("flags", [reuse.ALL, reuse.NONE, reuse.Flags(True, True, False, False)])
def test_a_sweep_in_pieces_is_the_whole_pass(monkeypatch, name, flags):
    monkeypatch.setattr(sweep, "ROWS", 5)
    monkeypatch.setattr(sweep, "EDGES", 7)
    edges, work, (pieces, n) = (s := sweep.Shelf()), sweep.Shelf(), sweep.shelved(batches(9, 13, 40), LANES, SCALE, s, 2, "lookahead")
    g = {t: models.Graph(x.src, x.dst, np.ones(x.edges), x.nodes, x.norm) for t, x in pieces.graphs.items()}
    whole = models.Sample(g, pieces.feats, pieces.targets, SCALE, 2, "lookahead")
    assert n == len(whole.targets) == 7 and all(x.edges for x in g.values())
    r = np.random.default_rng(3)
    w = {k: v + 0.2 * r.normal(size=v.shape) for k, v in models.init(name, 2, 4).items()}
    sequences = [[0, 1, 2, 3], [1, 2, 3, 4], [2, 3, 4, 5]]
    for s in (pieces, whole):
        s.expect(name, sequences, flags)
    for at, times in enumerate(sequences):
        ends = models.targets(name, times)
        ys, p = models.forward(name, whole, times, w, 4, flags, q=at)
        models.backward(models.total([models.error(y, whole, t, 14) for y, t in zip(ys, ends)]))
        got = []

        def seen(i, y, ends=ends, got=got):
            got.append(y)
            return np.sign(y - pieces.x(ends[i])[pieces.targets]) / 14

        grads = sweep.sweep(name, pieces, at, times, w, 4, flags, seen, work, True)
        assert len(got) == len(ys) and all(np.allclose(a, b.value[whole.targets], atol=1e-12) for a, b in zip(got, ys))
        assert set(grads) == {k for k, v in p.items() if v.grad is not None}
        assert all(np.allclose(grads[k], p[k].grad, atol=1e-12) for k in grads)
    count = lambda s: (s.passes(), s.messages(), s.global_store.hits, s.global_store.misses, s.local_store.hits, s.local_store.peak_bytes, s.global_store.peak_bytes)
    assert count(pieces) == count(whole)
    edges.close()


def test_a_task_holds_a_snapshot_and_not_the_sample():
    edges, work = sweep.Shelf(), sweep.Shelf()
    tracemalloc.start()
    s, _ = sweep.shelved(batches(30, 400, 60_000), LANES, SCALE, edges, None, "lookahead")
    s.expect("int_conv_gru", [list(range(20))], reuse.ALL)
    sweep.sweep("int_conv_gru", s, 0, list(range(20)), models.init("int_conv_gru", 2, 8), 8, reuse.ALL, lambda i, y: np.zeros_like(y), work, True)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 30 * 60_000 * 16 / 2  # the ends of the sample's edges alone are twice as large


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("model", list(reuse.MODELS))
def test_forward_streams_its_samples(spark, sf_dir, model):
    p = plan_of(catalogue.queries()[f"forward_{model}"](spark, sf_dir))
    assert "MapInArrow" in p and "FlatMapGroupsIn" not in p


@pytest.mark.parametrize("scheme", ["block", "node_part", "node_part_gate"])
def test_steps_stream_their_samples(spark, sf_dir, scheme):
    g, job = graphs.handoff(spark, sf_dir), train.Job(model="stk_conv_lstm", scheme=scheme, hidden=4, chunks=1, batches=1)
    made = train.KINDS[scheme](train.samples(g, job), job, g)
    p = plan_of(made.parts(models.init("stk_conv_lstm", 2, 4), 0, 0, True))
    assert "MapInArrow" in p and "FlatMapGroupsIn" not in p
    made.close()


def test_blocks_lie_on_machines_of_their_own(spark, sf_dir):
    from pyspark.sql import functions as F

    g, job = graphs.handoff(spark, sf_dir), train.Job(model="stk_conv_lstm", hidden=4, chunks=1, batches=1, machines=2)
    made = train.Block(train.samples(g, job), job, g)
    held = made.placed.select("block", F.spark_partition_id().alias("p")).distinct().collect()
    assert len(held) == len({r.p for r in held}) == 2
    made.close()


def test_graphs_are_made_once_for_all_that_read_them(spark, sf_dir, monkeypatch):
    from tgengine.operators import batches as mini

    seen, khop = [], mini.khop

    def watched(graph, *args, **kwargs):
        seen.append(graph)
        return khop(graph, *args, **kwargs)

    monkeypatch.setattr(mini, "khop", watched)
    catalogue.queries()["forward_stk_skip_lstm"](spark, sf_dir)
    train.fit(graphs.handoff(spark, sf_dir), train.Job(model="stk_conv_lstm", scheme="node_part", hidden=2, chunks=1, batches=1, epochs=0))
    assert len(seen) == 2
    assert all("events" not in f for g in seen for df in (g.edges, g.feats) for f in df.inputFiles())


@pytest.mark.parametrize("name", ["int_conv_gru", "int_conv_lstm"])
@pytest.mark.parametrize("part", ["enc", "dec"])
def test_handed_on_states_are_swept_in_pieces(monkeypatch, name, part):
    monkeypatch.setattr(sweep, "ROWS", 5)
    edges, work = sweep.Shelf(), sweep.Shelf()
    s, n = sweep.shelved(batches(6, 13, 40), LANES, SCALE, edges, None, "lookahead")
    r = np.random.default_rng(3)
    w = {k: v + 0.2 * r.normal(size=v.shape) for k, v in models.init(name, 2, 4).items()}
    pairs = lambda: [tuple(r.normal(size=(13, 4)) for _ in "hc") for _ in range(2)]
    state, up = pairs(), pairs()
    gru = lambda pairs: [(h.copy(), None if "gru" in name else c.copy()) for h, c in pairs]
    for back in (None, up):
        came, grads, loss = models.run_piece(name, s, part, [1, 2, 3], w, state, reuse.NONE, back, 2 * n)
        got, mine, own = sweep.piece(name, s, part, [1, 2, 3], w, gru(state), reuse.NONE, work, back and gru(back), 2 * n)
        assert np.isclose(loss, own) and set(mine) == set(grads)
        assert all(np.allclose(a[0], b[0]) and ("gru" in name or np.allclose(a[1], b[1])) for a, b in zip(came, got))
        assert all(np.allclose(mine[k], grads[k]) for k in grads)
    edges.close()


def test_sequence_partitioning_moves_packed_vectors(spark, sf_dir):
    g, job = graphs.handoff(spark, sf_dir), train.Job(model="stk_conv_lstm", scheme="seq_part", hidden=4, chunks=1, batches=1)
    made = train.SeqPart(train.samples(g, job), job, g)
    loose, packed = made.s.rows.filter("kind = 'f'"), made.rows.filter("kind = 'f'")
    assert packed.count() == packed.select("block", "batch_id", "t").distinct().count() < loose.count() / 5
    one = train.loose(made.rows.filter("block = 0 and t = 3").toPandas(), made.s.lanes)
    key = lambda pdf: sorted(map(tuple, pdf[pdf["kind"] == "f"][["t", "a", "b", "n", *made.s.lanes]].to_numpy().tolist()))
    assert key(one) == key(made.s.rows.filter("block = 0 and t = 3").toPandas())


def test_timed_aggregations_read_a_made_graph(spark, sf_dir, monkeypatch):
    from tgengine.operators import aggregate, measures

    seen = []
    monkeypatch.setattr(aggregate, "scratch", lambda g: seen.append(g) or g.edges)
    monkeypatch.setattr(aggregate, "incremental", lambda g: seen.append(g) or g.edges)
    monkeypatch.setattr(measures, "epoch_time", lambda run: float(bool(run.__defaults__[0](run.__defaults__[1]))))
    assert catalogue.queries()["aggregation_times"](spark, sf_dir).count() == 4
    assert len(seen) == 4 and not any("lineitem" in f or "orders" in f for g in seen for f in g.edges.inputFiles())


def test_rows_of_a_sample_are_squeezed(spark, sf_dir):
    r = np.random.default_rng(5)
    src, dst = r.integers(-3, 90_000, 1 << 14) * 7, r.integers(0, 90_000, 1 << 14) * 7
    row = sweep.put_edges(src, dst)
    assert len(row) < 16 * len(src) / 4
    order = np.lexsort((src, dst))
    assert all(np.array_equal(a, b[order]) for a, b in zip(sweep.edge_ends(row, None), (src, dst)))
    assert all(np.array_equal(a, b) for a, b in zip(sweep.edge_ends(src.tobytes(), dst.tobytes()), (src, dst)))
    assert not any(len(x) for x in sweep.edge_ends(sweep.put_edges(src[:0], dst[:0]), None))
    s = train.samples(graphs.handoff(spark, sf_dir), train.Job(hidden=2, chunks=1))
    few = train.bundled(s.rows, ["block", "batch_id"], s.lanes)
    key = ["block", "batch_id", "t"]
    assert few.filter("kind = 'f'").count() < s.rows.filter("kind = 'f'").count() / 5
    assert few.columns == s.rows.columns and few.filter("kind = 'e' and dst is not null").isEmpty()
    for block, batch in ((0, 0), (1, 1)):
        whole = s.rows.filter(f"block = {block} and batch_id = {batch}").toPandas()
        want, nodes, n = train.unpack(whole, s.lanes, s.scale, train.Job())
        table = train.in_order(few.filter(f"block = {block} and batch_id = {batch}").coalesce(1), key[:2]).toArrow()
        got, m = sweep.shelved(iter(table.to_batches()), s.lanes, s.scale, sweep.Shelf(), None, "lookahead")
        assert n == m and np.array_equal(want.targets, got.targets) and sorted(want.graphs) == sorted(got.graphs)
        for t, g in want.graphs.items():
            assert np.array_equal(want.feats[t], got.feats[t]) and np.array_equal(g.src, got.graphs[t].src) and np.array_equal(g.dst, got.graphs[t].dst)


@pytest.mark.parametrize("scheme", ["node_part", "block"])
def test_steps_shuffle_bundled_features(spark, sf_dir, scheme, monkeypatch):
    seen, in_order = [], train.in_order
    monkeypatch.setattr(train, "in_order", lambda rows, keys: seen.append(rows) or in_order(rows, keys))
    job = train.Job(model="stk_conv_lstm", scheme=scheme, hidden=2, chunks=1, batches=1)
    g = graphs.handoff(spark, sf_dir)
    made = train.KINDS[scheme](train.samples(g, job), job, g)
    made.parts(models.init("stk_conv_lstm", 2, 2), 0, 0, True)
    assert len(seen) == 1 and seen[0].filter("kind = 'f'").filter("src is null").isEmpty()
    made.close()


@pytest.mark.parametrize("name", ["int_conv_gru", "int_conv_lstm", "stk_conv_lstm", "stk_skip_lstm"])
def test_cells_on_arrays_are_those_of_the_tape(name):
    from tgengine.nn import cells, tape

    r, m = np.random.default_rng(11), reuse.MODELS[name]
    w = {k: v + 0.3 * r.normal(size=v.shape) for k, v in models.init(name, 2, 4).items() if k.startswith("enc1.")}
    ax, ah, across, h, c, gh, gc = (3 * r.normal(size=(9, 4)) for _ in range(7))
    stacked, skip, lstm = m.kind == "stacked", name == "stk_skip_lstm", m.gates == 4
    ins = ax, None if stacked else ah, across if skip else None, h, c if lstm else None
    v, p = [None if x is None else tape.Var(x) for x in ins], {k: tape.Var(x) for k, x in w.items()}
    if stacked:
        u = tape.relu(v[0] @ p["enc1.conv"])
        want = models._lstm([tape.beside(u, v[2]) if skip else u] * 4, [v[3]] * 4, v[4], p, "enc1")
    else:
        want = models._lstm([v[0]] * 4, [v[1]] * 4, v[4], p, "enc1") if lstm else (models._gru([v[0]] * 3, [v[1]] * 3, v[3], p, "enc1"), None)
    tape.backward(tape.total([tape.dot(x, g) for x, g in zip(want, (gh, gc)) if x is not None]))
    cell = cells.Cell(name, "enc1", w)
    assert all(x is None or np.allclose(x.value, y) for x, y in zip(want, cell.forward(*ins)))
    for x, y in zip(v, cell.backward(ins, gh, gc if lstm else None)):
        assert x is None or x.grad is None or np.allclose(x.grad, y)
    mine = cell.weights()
    assert set(mine) == set(p) and all(np.allclose(p[k].grad, mine[k]) for k in p)


def test_fits_run_abreast_on_one_placement(spark, sf_dir, monkeypatch):
    from tgengine.storage import CLEANUP

    placed, place, before = [], train.place, spark.conf.get(CLEANUP, None)
    monkeypatch.setattr(train, "place", lambda s, job: placed.append(place(s, job)) or placed[-1])
    jobs = [train.Job(model=m, hidden=2, length=3, chunks=1, batches=1, epochs=1) for m in ("stk_conv_lstm", "stk_skip_lstm")]
    g = graphs.handoff(spark, sf_dir)
    curve = lambda made: [(job.model, [{k: v for k, v in c.items() if k != "seconds"} for c in cs]) for job, _, cs in made]
    assert curve(train.fit_all(g, jobs, 2)) == curve(train.fit_all(g, jobs))
    assert len(placed) == 2 and not any(x.is_cached for x in placed)
    assert spark.conf.get(CLEANUP, None) == before


def test_edges_of_a_target_lie_together(spark, sf_dir):
    from tgengine.operators import aggregate
    from tgengine.operators.temporal import coded

    g = graphs.trade(spark, sf_dir)
    near, plain = aggregate.by_target(g), coded(g)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(near.edges) == rows(plain.edges) and rows(near.feats) == rows(plain.feats)
    for f in (aggregate.scratch, aggregate.incremental):
        assert rows(f(near)) == rows(f(plain))
    by = near.edges.selectExpr("dst", "input_file_name() as f").distinct()
    assert by.count() == by.select("dst").distinct().count()
    assert "SortMergeJoin" not in near.edges.join(near.feats, near.edges.src == near.feats.node)._jdf.queryExecution().toString()
