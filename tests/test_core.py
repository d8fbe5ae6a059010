"""Worked examples and closed forms, and a sample of queries against their SQL."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS
from deltamp.operators import infer, partition, training
from deltamp.operators import window as win
from deltamp.operators import windowed as wd
from deltamp.operators.store import Store, cascade
from deltamp.queries import ORACLES, QUERIES
from deltamp.sources.graphs import DAY
from tests.harness import DATA, differs

SAMPLE = ("g_hop_edges", "g_trade_deletes", "inf_sage2", "agg_mean_incremental", "agg_min_retract", "delta_feature_update", "worked_example", "win_session_counts", "win_adaptive_counts", "win_tumbling_perkey", "part_masters", "place_physical", "explosion_parallelism", "train_grad_2layer", "wl_w11_ablation", "join_asof_feature", "volume_by_policy")


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, name):
    assert not differs(spark, name, QUERIES[name], ORACLES[name])


LONGS = ", ".join(f"x{i} long" for i in range(DIMS))


def _plain(vertices, edges, layers=2):
    """Full inference in plain Python."""
    from deltamp.functions.grid import weights

    h = {v: list(x) for v, x in vertices.items()}
    for layer in range(layers):
        ws, wn, b = weights(layer)
        new = {}
        for v, x in h.items():
            m = [h[s] for s, d in edges if d == v]
            mean = [int(np.floor(sum(c) / len(m) + 0.5)) if m else 0 for c in (zip(*m) if m else [[]] * DIMS)]
            new[v] = [max(0, int(np.floor((b[i] + sum(ws[i][j] * x[j] + wn[i][j] * mean[j] for j in range(DIMS))) / 4.0 + 0.5))) for i in range(DIMS)]
        h = new
    return h


def test_cascade_with_multi_edges_self_loops_and_deletions(spark):
    rng = random.Random(4)
    vertices = {v: [rng.randint(-50, 50) for _ in range(DIMS)] for v in range(6)}
    v = spark.createDataFrame([(k, *x) for k, x in vertices.items()], f"v long, {LONGS}")
    frame = lambda rows: spark.createDataFrame(rows, "eid string, src long, dst long")
    first = [(str(i), rng.randrange(6), rng.randrange(6)) for i in range(14)] + [("m1", 0, 1), ("m2", 0, 1), ("s", 2, 2)]
    gone, more = first[3:8] + [("m2", 0, 1)], [("n1", 5, 0), ("n2", 1, 5), ("x", 3, 4)]
    store = cascade(v, [(frame(first), None), (frame(more), frame([*gone, ("x", 3, 4)]))], 2)
    live = [(s, d) for e, s, d in first + more if (e, s, d) not in gone and e != "x"]
    assert {r[0]: list(r[1:]) for r in store.outputs().collect()} == _plain(vertices, live)
    again = Store(spark, 2, 4, store.root)  # a restart over the same folder
    assert not again.apply(2, frame(first)) and again.outputs().exceptAll(store.outputs()).count() == 0
    again.compact()
    again.apply(3, None, frame([("m1", 0, 1)]))
    assert {r[0]: list(r[1:]) for r in again.outputs().collect()} == _plain(vertices, [e for k, e in enumerate(live) if k != live.index((0, 1))])


def test_a_batch_reads_the_buckets_it_touches(spark):
    vertices = {k: [(37 * k + 11 * i * i) % 101 for i in range(DIMS)] for k in range(60)}
    v = spark.createDataFrame([(k, *x) for k, x in vertices.items()], f"v long, {LONGS}")
    ring = [(k, (k + 1) % 60) for k in range(60)]
    store = Store(spark, 2, 64).load(v, spark.createDataFrame(ring, "src long, dst long"))
    store.apply(1, spark.createDataFrame([(7, 9)], "src long, dst long"))
    for layer in (1, 2):
        old, new = _plain(vertices, ring, layer), _plain(vertices, [*ring, (7, 9)], layer)
        moved = sorted(k for k in old if old[k] != new[k])
        assert moved and set(moved) <= {9, 10} and sorted(r[0] for r in store.changed(layer).collect()) == moved
    from deltamp.plans.shared import names

    assert len(names(spark, f"{store.root}/values2/a={store.last}")) <= 4


def test_windowed_layers_hold_edges_and_outputs_back(spark):
    """By hand: an edge joins when its window closes, two updates in a window leave as one, and the swap takes what was sent before."""
    v = spark.createDataFrame([(k, *[10 * k + i % 5 for i in range(DIMS)]) for k in range(4)], f"v long, {LONGS}")
    e = spark.createDataFrame([(1, 3, 0, 1), (2, 4, 2, 1), (3, 12, 3, 0), (4, 25, 1, 2)], "seq long, us long, src long, dst long")
    ten = lambda r: win.tumbling(r, 10)
    one, two = wd.run(v, e, ten, ten)
    assert sorted((r["dst"], r["at"], r["kind"]) for r in one.messages.collect()) == [(0, 20, "absorb"), (1, 10, "absorb"), (1, 10, "absorb"), (2, 30, "absorb")]
    assert sorted((r["v"], r["at"]) for r in one.emissions.collect() if r["at"] > wd.ALWAYS) == [(0, 30), (1, 20), (2, 40)]
    assert sorted((r["src"], r["dst"], r["at"]) for r in two.messages.where("kind = 'swap'").collect()) == [(0, 1, 30), (2, 1, 40)]
    edges = [tuple(r) for r in e.select("src", "dst").collect()]
    plain = _plain({r[0]: list(r[1:]) for r in v.collect()}, edges)
    assert {r[0]: list(r[1:]) for r in wd.final([one, two]).collect()} == plain


def test_sketch_gaps_are_exact_without_collisions(spark):
    r = spark.createDataFrame([(k % 5, d * DAY + k * 1000, k) for d in range(4) for k in range(5 * (d + 1))], "key long, us long, seq long")
    assert win.adaptive_gaps(r).exceptAll(win.adaptive_gaps(r, sketch=win.CountMin())).count() == 0
    small = {(x["key"], x["day"]): x["freq"] for x in win.adaptive_gaps(r, sketch=win.CountMin(1, 2)).collect()}
    assert all(small[x["key"], x["day"]] >= x["freq"] for x in win.adaptive_gaps(r).collect())


def test_physical_parts_cover_and_are_even():
    for most, par in itertools.product((1, 7, 16, 128), (1, 2, 5, 16, 64)):
        if par <= most:
            sizes = [sum(k * par // most == p for k in range(most)) for p in range(par)]
            assert min(sizes) >= 1 and max(sizes) - min(sizes) <= 1


def test_explosion_factor_and_votes():
    assert [n for _, n, _ in partition.layer_parallelism(2, 3, 3, 64)] == [2, 6, 18]
    assert [training.should_start(n, 4) for n in (2, 3)] == [False, True]
    c = training.Coordinator(4)
    assert not c.vote(1) and not c.vote(1) and not c.vote(2) and c.vote(3)
    assert [c.advance() for _ in range(4)] == ["flushing", "training", "rebuilding", "running"]


def test_sessions_and_tumbling_by_hand(spark):
    rows = lambda ts: spark.createDataFrame([(1, t, i) for i, t in enumerate(ts)], "key long, us long, seq long")
    due = lambda d: sorted({r["due"] for r in d.collect()})
    assert due(win.session(rows([0, 4, 9, 20]), 6)) == [15, 26] == win.reference_sessions([0, 4, 9, 20], 6)
    assert due(win.tumbling_per_key(rows([3, 8, 14]), 10)) == [13, 24]
    days = rows([d * DAY + k for d, n in enumerate((4, 8, 8)) for k in range(n)])
    assert [r["freq"] for r in win.adaptive_gaps(days).orderBy("day").collect()] == [4_000_000, 6_000_000, 7_000_000]


def test_greedy_partitioner_is_sequential_with_one_worker_and_beats_random(spark):
    rng = random.Random(1)
    rows = [(i, int(30 * rng.random() ** 3), 100 + int(60 * rng.random() ** 2)) for i in range(600)]
    e = spark.createDataFrame(rows, "seq long, src long, dst long")
    placed = partition.hdrf(e, 8, chunk=10_000)
    got = [r["lpart"] for r in placed.orderBy("seq").collect()]
    assert got == partition.hdrf_sequential([(a, b) for _, a, b in rows], 8)
    copies = lambda parts: len({(v, p) for (_, a, b), p in zip(rows, parts) for v in (a, b)})
    assert copies(got) < copies([rng.randrange(8) for _ in rows])


def test_linear_gradients_match_finite_differences(spark):
    rng = random.Random(2)
    rows = [(v, v % 3, *[rng.randint(-4, 4) for _ in range(DIMS)]) for v in range(5)]
    edges = [(rng.randrange(5), rng.randrange(5)) for _ in range(9)]
    v = spark.createDataFrame(rows, f"v long, label int, {LONGS}")
    e = spark.createDataFrame(edges, "src long, dst long")

    def loss(table):
        from deltamp.functions.grid import weights

        h = {r[0]: list(r[2:]) for r in table}
        for layer in range(2):
            ws, wn, _ = weights(layer)
            a = {k: [sum(h[s][j] for s, d in edges if d == k) for j in range(DIMS)] for k in h}
            h = {k: [sum(ws[i][j] * x[j] + wn[i][j] * a[k][j] for j in range(DIMS)) for i in range(DIMS)] for k, x in h.items()}
        return sum((h[r[0]][0] - r[1]) ** 2 for r in table)

    f2 = training.forward_linear(training.forward_linear(v, e, 0), e, 1)
    g = training.backward_layer(training.backward_layer(training.output_gradient(f2, v), e, 1), e, 0)
    got = {r["v"]: r["g1"] for r in g.collect()}
    for k in range(5):
        up, down = ([(*r[:3], r[3] + s, *r[4:]) if r[0] == k else r for r in rows] for s in (1, -1))
        assert got.get(k, 0) == (loss(up) - loss(down)) / 2


def test_no_cartesian_product_and_pruned_scans(spark):
    from tests.harness import DATA

    plan = QUERIES["src_parquet_pruned"](spark, f"{DATA}/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(event_type), EqualTo(event_type,click)" in plan and "props" not in plan
    assert "CartesianProduct" not in QUERIES["inf_sage2"](spark, f"{DATA}/sf0.001")._jdf.queryExecution().executedPlan().toString()


def test_lockstep_rounds_reach_every_edge(spark):
    rng = random.Random(8)
    rows = [(k, 0, k + 1) for k in range(260)] + [(1000 + k, 5000 + k, 5001 + k) for k in range(230)]
    rows += [(2000 + k, rng.randrange(40), rng.randrange(40)) for k in range(200)]
    got = {r["seq"]: r["round"] for r in partition.lockstep_rounds(spark.createDataFrame(rows, "seq long, src long, dst long"), chunk=150).collect()}
    left, want, k = sorted(rows), {}, 0
    while left:
        low = {}
        for q, a, b in left:
            low.setdefault(a, q), low.setdefault(b, q)
        want |= {q: k for q, a, b in left if low[a] == low[b] == q}
        left, k = [e for e in left if e[0] not in want], k + 1
    assert got == want and max(want.values()) > 259


def test_attention_deltas_follow_changed_destinations(spark):
    rng = random.Random(6)
    frame = lambda rows: spark.createDataFrame(rows, "eid string, src long, dst long")
    values = lambda rows: spark.createDataFrame([(k, *x, *[0] * (DIMS - 4)) for k, x in rows.items()], f"v long, {LONGS}")
    before = {v: [rng.randint(-2000, 2000) for _ in range(4)] for v in range(6)}
    after = {**before, 0: [5, 900, 1, 1], 1: [before[1][0], -1500, 0, 0], 6: [700, 300, 0, 0]}  # 1 changes as a destination only
    first = [(str(i), rng.randrange(7), rng.randrange(6)) for i in range(20)] + [("s", 1, 1), ("m1", 2, 1), ("m2", 2, 1)]
    gone, more = [*first[2:6], ("m2", 2, 1)], [("n1", 6, 0), ("n2", 3, 6), ("x", 3, 4)]
    state = infer.attention_cascade([(values(before), frame(first), frame([])), (values(after), frame(more), frame([*gone, ("x", 3, 4)]))])
    live = [(a, b) for e, a, b in first + more if (e, a, b) not in gone and e != "x"]
    want = {}
    for a, b in live:
        w = np.exp((0.5 * after[a][0] - 0.25 * after[b][1]) / 1024)
        num, den = want.get(b, (0, 0))
        want[b] = (num + w * after[a][0] / 1024, den + w)
    got = {r["dst"]: (float(r["num"]), float(r["den"])) for r in state.collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], rtol=1e-9) for k in want)


def test_gat_state_by_deltas_equals_full_inference(spark):
    from tests.harness import DATA

    assert QUERIES["delta_gat_state"] is not QUERIES["inf_gat1"]
    got, want = ({r["v"]: r["y"] for r in QUERIES[n](spark, f"{DATA}/sf0.001").collect()} for n in ("delta_gat_state", "inf_gat1"))
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_packed_sums_carry_runs_over_batches(spark):
    from deltamp.operators import packed

    rows = [(k % 3, [k + i for i in range(DIMS)], 1, -1 if k % 5 == 0 else 1) for k in range(40)] + [(9, [4] * DIMS, 1, s) for s in (1, -1)] + [(None, [1] * DIMS, 1, 1), (7, None, 1, 1)]
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, "4")
    try:
        got = {r["v"]: (r["s"], r["n"]) for r in packed.add_up(spark.createDataFrame(rows, f"v long, s {packed.VECTOR}, n long, sign long")).collect()}
    finally:
        spark.conf.set(key, before)
    held = [r for r in rows if r[0] in (0, 1, 2)]
    assert got == {v: ([sum(r[1][i] * r[3] for r in held if r[0] == v) for i in range(DIMS)], sum(r[3] for r in held if r[0] == v)) for v in range(3)}


def test_softmax_divides_in_doubles(spark, tmp_path, monkeypatch):
    """Components whose quotient by 1024 needs more than six places."""
    import tests.harness as harness

    rng = random.Random(3)
    vectors = [(v, [rng.uniform(-0.5, 0.5) for _ in range(DIMS)], v % 3) for v in range(3000)]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>, label int").coalesce(1).write.parquet(f"{tmp_path}/made/e")
    spark.range(3000).selectExpr("id AS event_id", "id AS user_id").coalesce(1).write.parquet(f"{tmp_path}/made/u")
    for folder, name in (("e", "embeddings"), ("u", "events")):
        next((tmp_path / "made" / folder).glob("*.parquet")).rename(tmp_path / "made" / f"{name}.parquet")
    monkeypatch.setattr(harness, "DATA", str(tmp_path))
    assert not differs(spark, "vec_softmax", QUERIES["vec_softmax"], ORACLES["vec_softmax"], "made")


# Queries that once made their data up.
READS = ("explosion_parallelism", "place_physical", "place_coverage", "place_hashed_idle", "place_moves", "sql_function_grid", "train_vote", "udtf_khop", )


@pytest.mark.parametrize("name", READS)
def test_query_reads_a_given_table(spark, name):
    from tests.harness import DATA

    assert QUERIES[name](spark, f"{DATA}/sf0.001").inputFiles()
    assert name not in ORACLES or not differs(spark, name, QUERIES[name], ORACLES[name])


def test_python_source_keeps_the_hop_graph(spark, tmp_path):
    assert not differs(spark, "src_python_ds", QUERIES["src_python_ds"], ORACLES["src_python_ds"])
    edges = spark.createDataFrame([(k, k % 5, k % 7) for k in range(40)], "seq long, src long, dst long").repartition(3)
    store = lambda mode: edges.write.format("graph_edges").mode(mode).save(f"{tmp_path}/e")
    count = lambda: spark.read.format("graph_edges").load(f"{tmp_path}/e").count()
    store("append"), store("append")
    assert count() == 80
    store("overwrite")
    assert count() == 40 and spark.read.format("graph_edges").option("vertices", "10").load().count() == 20


def test_one_worker_joins_small_chunks(spark):
    """Chunks of 10 edges come to the sequential result in a few jobs, not some for each chunk."""
    rng = random.Random(12)
    rows = [(i, rng.randrange(40), 100 + rng.randrange(60)) for i in range(400)]
    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("rounds", "rounds")
    try:
        placed = partition.hdrf(spark.createDataFrame(rows, "seq long, src long, dst long"), 8, chunk=10)
    finally:
        spark.sparkContext._jsc.clearJobGroup()
    assert len(tracker.getJobIdsForGroup("rounds")) < 40
    assert [r["lpart"] for r in placed.orderBy("seq").collect()] == partition.hdrf_sequential([(a, b) for _, a, b in rows], 8)


def test_gather_windows_are_stored_once_and_the_last_layer_not_at_all(spark, monkeypatch):
    v = spark.createDataFrame([(k, *[10 * k + i % 5 for i in range(DIMS)]) for k in range(4)], f"v long, {LONGS}")
    e = spark.createDataFrame([(k, 3 * k, k % 4, (k * k + 1) % 4) for k in range(30)], "seq long, us long, src long, dst long")
    ranks, stored = [], []
    rank, settle = win.global_rank, wd.settle
    monkeypatch.setattr(win, "global_rank", lambda *a, **b: (ranks.append(1), rank(*a, **b))[1])
    monkeypatch.setattr(wd, "settle", lambda df: (stored.append(df.columns), settle(df))[1])
    trace = wd.run(v, e, win.by_count(e, 7), None)
    assert len(ranks) == 1 and len(stored) == 2
    plain = _plain({r[0]: list(r[1:]) for r in v.collect()}, [tuple(r) for r in e.select("src", "dst").collect()])
    assert {r[0]: list(r[1:]) for r in wd.final(trace).collect()} == plain


def test_an_input_is_carried_once_to_a_part_of_destinations(spark):
    """Sums along edges equal those of single messages, for wide integers, deletions and a hub, from a row for an input and part."""
    from deltamp.operators import packed

    rng = np.random.default_rng(5)
    x = rng.integers(-(2**40), 2**40, (30, DIMS))
    x[:10] %= 100
    edges = [(a, b, int(rng.integers(-1, 3))) for a in range(30) for b in range(100, 300)] + [(3, b, 1) for b in range(1000, 3000)]
    want = {}
    for a, b, sign in edges:
        s, n = want.get(b, (np.zeros(DIMS, np.int64), 0))
        want[b] = s + sign * x[a], n + sign
    inputs = spark.createDataFrame([(a, x[a].tolist(), 1) for a in range(30)] + [(None, x[0].tolist(), 1), (99, None, 1)], "src long, s array<bigint>, n long")
    frame = spark.createDataFrame([*edges, (None, 5, 1), (3, None, 1), (77, 5, 1)], "src long, dst long, sign long").repartition(1).sortWithinPartitions("src", F.expr("dst % 4"))
    rows = packed.carried(inputs, frame, F.expr("dst % 4"))
    assert rows.count() <= 30 * 4 + len(edges) // packed.RUN + 20
    got = packed.received(rows, 4).collect()
    assert len(got) == len({r["v"] for r in got})
    assert {r["v"]: (r["s"], r["n"]) for r in got} == {v: (s.tolist(), n) for v, (s, n) in want.items() if n or s.any()}


def test_sums_held_in_parts_add_up(monkeypatch):
    import pyarrow as pa

    from deltamp.operators import packed

    monkeypatch.setattr(packed, "HELD", 50)
    monkeypatch.setattr(packed, "STEP", 16)
    edges = np.array([[v % 70, 1] for v in range(7 * 70)])
    batch = pa.RecordBatch.from_arrays([packed._blobs(np.ones((1, DIMS), np.int16), np.array([0, 2 * DIMS])), pa.array([1]), packed._blobs(edges, np.array([0, edges.nbytes]))], names=["s", "n", "to"])
    total = {}
    for b in packed._received(iter([batch.slice(0, 0), batch])):
        for v, s, n in zip(*(c.to_pylist() for c in b.columns)):
            assert s == [n] * DIMS
            total[v] = total.get(v, 0) + n
    assert total == {v: 7 for v in range(70)}


def test_trade_is_stored_without_names_of_edges(spark, monkeypatch):
    """An edge's name needs a window over lineitem, and the store cancels edges by their ends."""
    class Seen(Exception):
        pass

    def settle(df):
        if "op" in df.columns:
            raise Seen("eid" in df.columns or "Window" in df._jdf.queryExecution().optimizedPlan().toString())
        return df

    monkeypatch.setattr(infer, "settle", settle)
    with pytest.raises(Seen) as seen:
        QUERIES["wl_w9_trade"](spark, "/root/testdata/sf0.001")
    assert seen.value.args == (False,)


def test_ranks_are_made_without_storing_rows(spark, monkeypatch):
    from deltamp import durable

    def refuse(df):
        raise AssertionError("rows stored")

    monkeypatch.setattr(durable, "settle", refuse)
    seqs = sorted({k**3 % 1009 for k in range(900)} | set(range(2000, 2400)) | {-5, 10**12})
    rows = spark.createDataFrame([(s,) for s in reversed(seqs)], "seq long").repartition(3)
    assert {r["seq"]: r["rank"] for r in win.global_rank(rows, "seq").collect()} == {s: k for k, s in enumerate(seqs)}
    assert win.global_rank(rows.where("seq < -5"), "seq").count() == 0


def test_the_last_layer_sums_vectors_by_destination_only(spark):
    """Its windows run without vectors: no sums of 64 for each time of a destination."""
    v = spark.createDataFrame([(k, *[10 * k + i % 5 for i in range(DIMS)]) for k in range(4)], f"v long, {LONGS}")
    e = spark.createDataFrame([(k, k * DAY // 7, k % 4, (k * k + 1) % 4) for k in range(40)], "seq long, us long, src long, dst long")
    sketched = lambda r: win.adaptive(r, sketch=win.CountMin())
    out = wd.final(wd.run(v, e, sketched, sketched))
    key = "spark.sql.debug.maxToStringFields"
    before = spark.conf.get(key)
    spark.conf.set(key, "10000")
    try:
        plan = out._jdf.queryExecution().optimizedPlan().toString()
    finally:
        spark.conf.set(key, before)
    groups = [line.split("Aggregate [")[1].split("]")[0] for line in plan.splitlines() if "Aggregate [" in line and "AS s63#" in line]
    assert groups and not any("," in g for g in groups)
    assert {r[0]: list(r[1:]) for r in out.collect()} == _plain({r[0]: list(r[1:]) for r in v.collect()}, [tuple(r) for r in e.select("src", "dst").collect()])


def test_copurchase_loads_are_told_for_every_policy(spark, monkeypatch):
    """Events handled one by one stand beside the windows, and what a policy stored goes once it is counted."""
    import os

    from deltamp.queries import traces

    stored = []
    keep = wd.settle
    monkeypatch.setattr(wd, "settle", lambda df: (stored.append(keep(df)), stored[-1])[1])
    assert not differs(spark, "wl_w1_copurchase", QUERIES["wl_w1_copurchase"], ORACLES["wl_w1_copurchase"])
    rows = QUERIES["wl_w1_copurchase"](spark, f"{DATA}/sf0.001").collect()
    assert {r["policy"] for r in rows} == set(traces.MAIN) and len(rows) == 4 * len(traces.MAIN)
    assert stored and not any(os.path.exists(df.kept_at.removeprefix("file:")) for df in stored)
