"""Kernels, compressors and training methods against plain linear algebra and enumeration."""

import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from curvature_spark.functions import packed, prng
from curvature_spark.operators import baselines, compressors, costmodel, features, server
from curvature_spark.operators.methods import shift_gap, train_partial, train_shifts
from curvature_spark.operators.partition import pack_blocks, pin, split_equal, split_hashed
from curvature_spark.operators.problems import LogisticProblem, QuadraticProblem, check_oracles, curvature_bounds, lipschitz_ratios
from curvature_spark.operators.rounds import Engine, global_oracles
from curvature_spark.plans import workloads

PROBLEM = LogisticProblem(1e-3)


def symmetric(d, seed=0):
    m = np.random.default_rng(seed).normal(size=(d, d))
    return packed.pack(m + m.T)


def test_packed_layout():
    for d in (1, 2, 5, 9):
        seen = [packed.position(i, j) for j in range(d) for i in range(j + 1)]
        assert seen == list(range(packed.length(d))) and packed.dimension(packed.length(d)) == d
        v = symmetric(d)
        full = packed.unpack(v, d)
        assert (packed.pack(full) == v).all() and (full == full.T).all()
        assert packed.frobenius(v, d) == pytest.approx(np.linalg.norm(full))
        assert (np.diag(full) == v[packed.diagonal(d)]).all()
    assert packed.layout(124) == "packed" and packed.layout(6000) == "tiled"


def test_portable_draw_equals_both_engines(spark):
    import duckdb

    assert prng.draw(7, 3, 12) == 4243181197
    got = spark.range(50).select(prng.draw_column(7, 3, F.col("id")).alias("d")).collect()
    assert [r.d for r in got] == [prng.draw(7, 3, i) for i in range(50)] == prng.draws(50, 7, 3).tolist()
    con = duckdb.connect()
    assert [r[0] for r in con.execute(f"SELECT {prng.draw_sql('7', '3', 'i')} FROM range(50) t(i)").fetchall()] == [r.d for r in got]


@pytest.mark.parametrize("k", [1, 3, 7, 15, 40])
def test_windows_are_unbiased_with_exact_variance(k):
    v = symmetric(5)
    w = len(v)
    c = compressors.make("windowk", k)
    size = c.budget(w)
    sent = []
    for s in range(w):
        idx = (s + np.arange(size)) % w
        out = np.zeros(w)
        out[idx] = v[idx] * w / size
        sent.append(out)
    assert np.mean(sent, axis=0) == pytest.approx(v)
    error = np.mean([packed.frobenius(x - v, 5) ** 2 for x in sent])
    assert error == pytest.approx(c.omega(w) * packed.frobenius(v, 5) ** 2)


def test_random_subsets_are_unbiased_with_exact_variance():
    v = symmetric(3)
    sent = []
    for idx in itertools.combinations(range(6), 2):
        out = np.zeros(6)
        out[list(idx)] = v[list(idx)] * 3
        sent.append(out)
    assert np.mean(sent, axis=0) == pytest.approx(v)
    assert np.mean([packed.frobenius(x - v, 3) ** 2 for x in sent]) == pytest.approx(compressors.make("randk", 2).omega(6) * packed.frobenius(v, 3) ** 2)
    picked = [tuple(compressors.make("randk", 2)(v, 3, (1, r, 0)).idx) for r in range(600)]
    assert len(set(picked)) == 15 and all(len(p) == 2 for p in picked)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 7), st.integers(1, 30), st.integers(0, 10_000))
def test_tight_selection_keeps_the_contraction_with_equality(d, k, seed):
    v = symmetric(d, seed)
    c = compressors.make("tight", k)
    w = len(v)
    order, count, less = c.split(v, d)
    assert count <= c.budget(w) and 0 <= less <= 1
    energy = (packed.multiplicity(d) * v * v)[order]
    share = np.concatenate([[0], np.cumsum(energy) / energy.sum()])
    lost = less * (1 - share[count - 1]) + (1 - less) * (1 - share[count])
    assert lost == pytest.approx(1 - c.delta(w), abs=1e-12)
    assert c(np.zeros(w), d, (0,)).idx.size == 0


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 7), st.integers(1, 30), st.integers(0, 10_000), st.floats(-5, 5).filter(lambda b: abs(b) > 1e-3))
def test_largest_entries_contract_and_are_homogeneous(d, k, seed, factor):
    v = symmetric(d, seed)
    c = compressors.make("topk", k)
    m = c(v, d, (0,))
    assert packed.frobenius(m.dense(len(v)) - v, d) ** 2 <= (1 - c.delta(len(v))) * packed.frobenius(v, d) ** 2 + 1e-9
    assert packed.frobenius(m.dense(len(v)), d) <= packed.frobenius(v, d) + 1e-12
    assert c(factor * v, d, (0,)).idx.tolist() == m.idx.tolist() or min(np.diff(np.sort(np.abs(v))), default=1) < 1e-9
    for impl in ("sort", "heap", "partition"):
        assert np.sort(compressors.largest(compressors.scores(v, d, "frobenius"), c.budget(len(v)), impl)).tolist() == m.idx.tolist()


def test_magnitude_ranking_can_break_the_bound():
    """All-equal entries: diagonals, which count once, are kept before pairs, which count twice."""
    d, k = 4, 4
    v = np.ones(packed.length(d))
    v[packed.diagonal(d)] *= 1 + 1e-6
    lost = {r: packed.frobenius(compressors.make("topk", k, ranking=r)(v, d, (0,)).dense(len(v)) - v, d) ** 2 / packed.frobenius(v, d) ** 2 for r in ("magnitude", "frobenius")}
    assert lost["magnitude"] > 1 - k / len(v) >= lost["frobenius"]


def test_natural_rounding():
    c = compressors.make("natural")
    v = np.array([0.0, 1.0, -2.0, 3.0, -0.3, 1e-310, 0.75])
    sent = np.array([c(v, None, (s,)).val for s in range(4000)])
    assert (sent[:, :3] == v[:3]).all() and set(np.abs(sent[:, 3])) == {2.0, 4.0} and (sent[:, 5] == 0).all()
    assert sent.mean(axis=0) == pytest.approx(v, abs=0.04)
    assert ((sent - v) ** 2).mean(axis=0).sum() <= 0.125 * (v * v).sum()
    assert c(np.ones(5), None, (0,)).payload == 8


def test_step_constants():
    w = 20
    assert compressors.make("topk", 5).alpha(w, "default") == 1 and compressors.make("randk", 5).alpha(w, "default") == 0.25
    assert compressors.make("topk", 5).alpha(w, "contractive") == pytest.approx(1 - np.sqrt(0.75))
    assert compressors.make("natural").alpha(w, "default") == pytest.approx(8 / 9) and compressors.make("windowk", 5).alpha(w, 0.3) == 0.3


def test_bytes_of_the_published_run():
    for kind, kept, want in (("randk", None, 2937.0), ("windowk", None, 2937.0), ("topk", None, 4241.4), ("identity", None, 49568.7), ("tight", 18.46, 358.8)):
        assert costmodel.total_megabytes(kind, 301, 142, 1000, 2408, kept) == pytest.approx(want, abs=0.06)


def test_solvers_and_projection():
    rng = np.random.default_rng(0)
    a = rng.normal(size=(130, 130))
    a, b = a @ a.T / 130 + 3 * np.eye(130), rng.normal(size=130)
    for name in ("cholesky", "gauss", "qr", "gauss_seidel", "cg"):
        assert a @ server.SOLVERS[name](a, b) == pytest.approx(b, abs=1e-8)
    small = np.array([[4.0, 1.0], [1.0, 3.0]])
    assert small @ server.jacobi(small, np.array([1.0, 2.0])) == pytest.approx([1.0, 2.0])
    m = packed.unpack(symmetric(6), 6)
    assert np.linalg.eigvalsh(server.projected(m, 0.5))[0] == pytest.approx(0.5)
    assert server.projected(a, 1e-3) is a
    p = server.cubic_direction(packed.pack(a), 0.0, b, 2.0)
    assert a @ p + np.linalg.norm(p) * p == pytest.approx(-b, abs=1e-6)
    assert len(server.participants(9, 4, 1, 2)) == 4


def test_oracles_by_differences_and_overflow():
    rng = np.random.default_rng(1)
    z, x = rng.normal(size=(40, 6)), rng.normal(size=6)
    g, h = check_oracles(PROBLEM, z, x)
    assert g < 1e-8 and h < 1e-7
    g, h = check_oracles(QuadraticProblem(0.1), rng.normal(size=(40, 7)), x)
    assert g < 1e-7 and h < 1e-7
    f, g, h = PROBLEM.sums(np.array([[800.0], [-800.0]]), np.array([1.0]))
    assert np.isfinite([f, *g, *h]).all() and f == pytest.approx(800)
    at = np.array([0, 3, 7])
    assert PROBLEM.entries(z, x, at) == pytest.approx(PROBLEM.sums(z, x)[2][at])
    low, high, ratio = curvature_bounds(PROBLEM.finish(40, PROBLEM.sums(z, x), x)[2], 6)
    assert 0 < low <= high and ratio == pytest.approx(high / low)
    hx, hy = symmetric(4, 1), symmetric(4, 2)
    s, f, e = lipschitz_ratios(hx, hy, np.zeros(4), np.ones(4))
    assert e <= s <= f


def test_difference_check_holds_on_long_clients():
    """With the values of all rows summed first, rounding alone passed the bound of oracle_fd_check from some 700,000 rows on."""
    rng = np.random.default_rng(2)
    z = np.column_stack([rng.integers(0, 11, 800_000) / 10, rng.integers(0, 9, 800_000) / 8, np.ones(800_000)]) * np.where(rng.random(800_000) < 0.25, 1.0, -1.0)[:, None]
    g, h = check_oracles(PROBLEM, z, np.array([0.3, -0.2, 0.1]))
    assert g < 1e-9 and h < 1e-7


@pytest.fixture(scope="module")
def samples(spark):
    rng = np.random.default_rng(2)
    truth = rng.normal(size=6)
    rows = []
    for i in range(403):
        a = np.append(rng.normal(size=5), 1.0)
        rows.append((str(i), 1.0 if rng.random() < 1 / (1 + np.exp(-a @ truth)) else -1.0, a.tolist()))
    return spark.createDataFrame(rows, "sample_key string, label double, features array<double>").repartition(3)


@pytest.fixture(scope="module")
def clients(samples):
    return pin(split_equal(samples, 8), 6)


@pytest.fixture(scope="module")
def local(clients):
    return {r.client_id: np.frombuffer(r.z, dtype=np.float64).reshape(r.n_rows, -1) for r in clients.blocks.collect()}


@pytest.fixture(scope="module")
def answer(clients):
    return baselines.damped_newton(clients, PROBLEM, tol=1e-13)[0]


def test_equal_split_drops_the_remainder(samples, clients):
    assert sorted(clients.rows.values()) == [50] * 8
    assert split_hashed(samples, 5).groupBy("client_id").count().count() == 5


def test_blocks_hold_every_row_once(samples):
    for rows, salts in ((7, 1), (1000, 3)):
        blocks = pack_blocks(split_hashed(samples, 3), 6, rows, salts).collect()
        z = np.concatenate([np.frombuffer(b.z, dtype=np.float64).reshape(b.n_rows, 6) for b in blocks])
        want = np.array([np.array(r.features) * r.label for r in samples.collect()])
        assert max(b.n_rows for b in blocks) <= rows
        assert np.array(sorted(z.tolist())) == pytest.approx(np.array(sorted(want.tolist())))


def test_global_oracles_equal_the_pooled_ones(clients, local):
    x = np.linspace(-1, 1, 6)
    f, g, h = global_oracles(clients, PROBLEM, x)
    z = np.concatenate(list(local.values()))
    f2, g2, h2 = PROBLEM.finish(len(z), PROBLEM.sums(z, x), x)
    assert f == pytest.approx(f2) and g == pytest.approx(g2) and h == pytest.approx(h2)


@pytest.mark.parametrize("kind", list(compressors.KINDS))
@pytest.mark.parametrize("option", ["project", "shift"])
def test_engine_follows_the_prototype_and_converges(clients, local, answer, kind, option):
    c = compressors.make(kind, 12)
    a = train_shifts(clients, PROBLEM, c, option=option, rounds=4, tol=0.0)
    b, _ = baselines.numpy_reference(local, PROBLEM, c, option=option, rounds=4, tol=0.0)
    assert a.x == pytest.approx(b, abs=1e-9) and shift_gap(a) < 1e-12
    full, log = baselines.numpy_reference(local, PROBLEM, c, option=option, rounds=80, tol=1e-10)
    assert log.rows[-1]["grad_norm"] < 1e-10 and full == pytest.approx(answer, abs=1e-7)


def test_convergence_is_superlinear(clients):
    norms = [r["grad_norm"] for r in train_shifts(clients, PROBLEM, compressors.make("topk", 12), rounds=30, tol=1e-13).log.rows]
    ratios = np.array(norms[1:]) / np.array(norms[:-1])
    assert norms[-1] < 1e-12 and ratios[-2:].min() < 0.1


def test_line_search_lazy_windows_and_cubic(clients, answer):
    c = compressors.make("topk", 12)
    searched = train_shifts(clients, PROBLEM, c, line_search=(0.49, 0.5), rounds=40)
    assert searched.x == pytest.approx(answer, abs=1e-7) and all(r["step_s"] >= 0 for r in searched.log.rows)
    window = compressors.make("windowk", 12)
    a = train_shifts(clients, PROBLEM, window, rounds=6, tol=0.0)
    b = train_shifts(clients, PROBLEM, window, rounds=6, tol=0.0, lazy=True)
    assert a.x == pytest.approx(b.x, abs=1e-10)
    cubic = train_shifts(clients, PROBLEM, c, option="shift", lipschitz=0.5, rounds=60)
    assert cubic.x == pytest.approx(answer, abs=1e-6)


def test_partial_participation(clients, answer):
    c = compressors.make("topk", 12)
    fit = train_partial(clients, PROBLEM, c, 3, rounds=120)
    assert fit.x == pytest.approx(answer, abs=1e-6) and shift_gap(fit) < 1e-11
    assert all(r["bytes"] == 3 * (8 * 6 + 16 + 12 * 12) for r in fit.log.rows)
    everyone = train_partial(clients, PROBLEM, c, 8, rounds=60)
    assert everyone.rounds < fit.rounds


def test_a_replayed_round_gives_the_same_bits(clients):
    c = compressors.make("tight", 12)
    a, b = (train_shifts(clients, PROBLEM, c, option="shift", rounds=7, tol=0.0, commit_every=k) for k in (0, 3))
    assert (a.x == b.x).all()


def test_unequal_clients_pool(samples):
    pooled = pin(split_hashed(samples, 4), 6, weights="pooled", rows_per_block=16, salts=2)
    assert not pooled.together
    fit = train_shifts(pooled, PROBLEM, compressors.make("topk", 12), rounds=40)
    z = np.array([np.array(r.features) * r.label for r in samples.collect()])
    _, g, _ = PROBLEM.finish(len(z), PROBLEM.sums(z, fit.x), fit.x)
    assert np.linalg.norm(g) < 1e-8


def test_first_order_and_splitting_baselines(clients, samples, answer):
    assert baselines.lbfgs(clients, PROBLEM)[0] == pytest.approx(answer, abs=1e-6)
    assert baselines.newton_cg(clients, PROBLEM)[0] == pytest.approx(answer, abs=1e-6)
    assert baselines.admm(clients, PROBLEM, tol=1e-6, rounds=60)[0] == pytest.approx(answer, abs=1e-3)
    for feedback in ("difference", "error"):
        _, log = baselines.compressed_gradient(clients, PROBLEM, 3, 1.0, rounds=25, feedback=feedback)
        assert log.rows[-1]["grad_norm"] < 0.7 * log.rows[0]["grad_norm"]
    x, _ = baselines.mllib_logistic(split_equal(samples, 8), 1e-3)
    assert x == pytest.approx(answer, abs=1e-5)


def test_features_have_fixed_dimensions(spark, small):
    for name in ("tiny", "users", "dense", "onehot", "sparse"):
        d = features.DIMENSIONS[name]
        sizes = features.expanded(features.BUILDERS[name](spark, small), d).select(F.size("features").alias("d"), F.element_at("features", -1).alias("last")).distinct().collect()
        assert [(r.d, r.last) for r in sizes] == [(d, 1.0)]
    ones = features.onehot(spark, small).select(F.size("hot").alias("n")).distinct().collect()
    assert [r.n for r in ones] == [16]


def test_binary_rows_scatter_into_blocks(spark):
    import pyarrow as pa

    z = features.scattered(pa.array([[0, 3], None, [], [None, 2]], pa.list_(pa.int32())), 4)
    assert z.tolist() == [[1, 0, 0, 1], [0] * 4, [0] * 4, [0, 0, 1, 0]]
    rows = spark.createDataFrame([("a", 1.0, 0, [0, 2]), ("b", -1.0, 0, [1, 2]), ("c", 1.0, 1, [2])], "sample_key string, label double, client_id long, hot array<int>")
    blocks = {r.client_id: np.frombuffer(r.z).reshape(r.n_rows, 3).tolist() for r in pack_blocks(rows, 3).collect()}
    assert blocks == {0: [[1, 0, 1], [0, -1, -1]], 1: [[0, 0, 1]]}


def test_equal_split_ranks_by_the_draw(spark):
    rows = spark.range(1000).select(F.col("id").cast("string").alias("sample_key"))
    got = {r.sample_key: r.client_id for r in split_equal(rows, 7).collect()}
    order = sorted((str(i) for i in range(1000)), key=lambda k: (prng.draw(7, k), k))
    assert got == {k: n // 142 for n, k in enumerate(order) if n < 7 * 142}


def test_base_method_diverges_where_the_search_converges(spark):
    """Hessians that change by orders between the start and the minimiser: full projected steps overshoot, as in the
    prototype; with the search along the step both engines go the same way to the minimiser."""
    rng = np.random.default_rng(4)
    ones = rng.random((240, 24)) < 0.3
    rows = [(str(i), 1.0 if a[:12].sum() > a[12:].sum() else -1.0, int(i % 6), [int(j) for j in np.nonzero(a)[0]] + [24]) for i, a in enumerate(ones)]
    samples = spark.createDataFrame(rows, "sample_key string, label double, client_id long, hot array<int>")
    clients = pin(samples, 25)
    local = {r.client_id: np.frombuffer(r.z).reshape(r.n_rows, -1) for r in clients.blocks.collect()}
    c = compressors.make("topk", 12)
    _, log = baselines.numpy_reference(local, PROBLEM, c, rounds=60)
    assert min(r["grad_norm"] for r in log.rows) > 1e-6
    search = (0.49, 0.5)
    a = train_shifts(clients, PROBLEM, c, line_search=search, rounds=8, tol=0.0)
    b, steps = baselines.numpy_reference(local, PROBLEM, c, rounds=8, tol=0.0, line_search=search)
    assert a.x == pytest.approx(b, abs=1e-8) and [r["step_s"] for r in a.log.rows] == [r["step_s"] for r in steps.rows]
    _, log = baselines.numpy_reference(local, PROBLEM, c, rounds=300, line_search=search)
    assert log.rows[-1]["grad_norm"] < 1e-9


def test_plans(spark, small):
    """Only needed columns are read, the star's dimensions are broadcast, and a round shuffles sums, never rows."""
    plan = features.onehot(spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan
    blocks = pin(features.portable_split(features.tiny(spark, small), 5), 3).blocks
    shifts = spark.range(5).select(F.col("id").alias("client_id"), F.lit(0.0).alias("l")).hint("merge")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    joined = blocks.join(shifts, "client_id")._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.adaptive.enabled")
    above = joined.split("InMemoryRelation")[0]
    assert "SortMergeJoin" in above and "Exchange" not in above and "Sort [" not in above
    scan = features.tiny(spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "o_orderdate" not in scan and "l_shipdate" not in scan.split("ReadSchema")[-1]


def test_binary_clients_keep_positions(spark):
    """Blocks of ones are positions in memory, and give what dense blocks give."""
    rng = np.random.default_rng(3)
    rows = [(str(i), i % 4, 1.0 if rng.random() < 0.5 else -1.0, [*map(int, np.nonzero(rng.random(40) < 0.1)[0]), 40]) for i in range(400)]
    rows.append(("n", 1, 1.0, None))
    clients = pin(spark.createDataFrame(rows, "sample_key string, client_id long, label double, hot array<int>"), 41)
    assert clients.blocks.agg(F.max(F.length("z") / F.col("n_rows"))).first()[0] < 41 * 8 / 4
    x = rng.normal(size=41)
    data = {c: np.array([[(p in (r[3] or [])) * r[2] for p in range(41)] for r in rows if r[1] == c]) for c in range(4)}
    want = [PROBLEM.finish(len(z), PROBLEM.sums(z, x), x) for z in data.values()]
    f, g, h = global_oracles(clients, PROBLEM, x)
    assert np.isclose(f, np.mean([w[0] for w in want])) and np.allclose(g, np.mean([w[1] for w in want], axis=0)) and np.allclose(h, np.mean([w[2] for w in want], axis=0))
    found = baselines.client_gradients(clients, PROBLEM, x)
    assert all(np.allclose(found[c], want[c][1]) for c in range(4))


def test_runs_from_one_point_share_their_first_shifts(spark, small):
    clients = workloads.tiny_clients(spark, small)
    a, b = (Engine(clients, PROBLEM, compressors.make(kind, 3), 1.0) for kind in ("topk", "windowk"))
    assert np.array_equal(a.start(np.zeros(3), "hessian")[0], b.start(np.zeros(3), "hessian")[0]) and a.shifts is b.shifts
    b.start(np.ones(3), "hessian")
    assert a.shifts is not b.shifts


def test_repeated_rows_fold_and_give_the_same_gradients(spark, small):
    clients, x = workloads.tiny_clients(spark, small), np.array([0.3, -0.2, 0.1])
    few = baselines.client_gradients(clients, PROBLEM, x)
    assert sum(n.sum() for _, n in clients.folded.values()) == sum(clients.rows.values())
    clients.folded = {}  # as if rows were too many
    jobs = baselines.client_gradients(clients, PROBLEM, x)
    assert few.keys() == jobs.keys() and all(np.allclose(few[c], jobs[c], rtol=0, atol=1e-14) for c in jobs)


@pytest.mark.parametrize("keys", [(7,), (7, 123, 4), (1 << 60, 1 << 60, 1 << 60)])
def test_draws_at_once_are_the_single_draws(keys):
    assert prng.draws(1200, *keys).tolist() == [prng.draw(*keys, i) for i in range(1200)]


def test_pinned_blocks_lie_in_few_partitions_and_stay(spark, samples):
    """A pass over blocks costs a task a partition, so their number follows the cores, whatever the session's shuffles use."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "40")
    try:
        clients = pin(split_equal(samples, 8), 6)
        parts = clients.blocks.rdd.getNumPartitions()
        assert parts == clients.parts <= 4 * spark.sparkContext.defaultParallelism < 40
        engine = Engine(clients, PROBLEM, compressors.make("topk", 12), 1.0)
        engine.start(np.zeros(6), "zero")
        engine.round(np.zeros(6), 0)
        assert engine._kept[-1].rdd.getNumPartitions() == parts
        engine.release()
        assert spark.conf.get("spark.sql.shuffle.partitions") == "40"
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_shorter_steps_are_tried_only_after_the_full_one():
    asked = []

    def values(points):
        asked.append(len(points))
        return (points**2).sum(axis=1)

    x = np.array([1.0, 0.0])
    assert server.backtrack(values, x, -x, 1.0, -2.0, 0.49, 0.5) == 0 and asked == [1]
    assert server.backtrack(values, x, -4 * x, 1.0, -8.0, 0.49, 0.5) == 2 and asked == [1, 1, 30]


def test_lbfgs_asks_for_values_only_where_the_first_step_fails(clients, answer, monkeypatch):
    calls, kept = [], baselines.global_values
    monkeypatch.setattr(baselines, "global_values", lambda *given: calls.append(1) or kept(*given))
    x, log = baselines.lbfgs(clients, PROBLEM)
    assert x == pytest.approx(answer, abs=1e-6) and len(calls) == sum(r["step_s"] != 0 for r in log.rows)
