"""The method's identities, statistics, bounds and solvers against brute force and against one another."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from fsketch.functions.hashing import normal, py_normal, py_uniform, uniform
from fsketch.operators import baselines, bounds, candidates, freq, hadamard, lloyd, measures, qubo, refine, resources, sample, scale, seed, sketch, solve, variational
from fsketch.operators.noise import Noise
from fsketch.plans import views
from fsketch.plans.pipeline import cluster, compressive_baseline
from fsketch.sources.workloads import WORKLOADS, load

RNG = np.random.default_rng(7)


def model(k=2, d=3, m=12, dim=2, rng=None):
    rng = rng or RNG
    w = rng.standard_normal((m, dim))
    sets = [rng.standard_normal((d, dim)) for _ in range(k)]
    z = np.exp(1j * rng.standard_normal((50, dim)) @ w.T).mean(axis=0)
    return z, sets, w, qubo.joint(z, sets, w)


@pytest.fixture(scope="module")
def parts(spark, sf):
    points, scaler = scale.prepare(load(spark, sf, "W8"))
    return points.cache(), scaler


def numpy_points(points, prefix="z"):
    cols = sorted(c for c in points.columns if c[0] == prefix)
    rows = points.orderBy("row_key").collect()
    return np.array([[r[c] for c in cols] for r in rows])


def test_randomness_is_the_same_everywhere(spark):
    row = spark.range(3).select(uniform("t", F.col("id")).alias("u"), normal("t", F.col("id")).alias("n")).collect()
    for i, r in enumerate(row):
        assert r.u == py_uniform("t", i) and abs(r.n - py_normal("t", i)) < 1e-12


def test_scaling(spark):
    rows = [("a", 1.0, 5.0), ("b", 3.0, 5.0), ("c", float("nan"), 5.0), ("d", None, 5.0), ("e", 2.0, 5.0)]
    df = spark.createDataFrame(rows, "row_key string, x0 double, x1 double")
    points, s = scale.prepare(df)
    assert (s.n, s.dropped, points.count()) == (3, 2, 3) and s.std[1] == 0
    z = numpy_points(points)
    assert np.allclose(z.mean(axis=0), 0) and np.allclose(z[:, 0].std(), 1) and not z[:, 1].any()
    assert np.allclose(s.inverse(s.forward([[1.0, 5.0]])), [[1.0, 5.0]])
    with pytest.raises(ValueError):
        scale.fit(df, on_invalid="error")
    assert scale.fit(df.limit(0)).n == 0


def test_sketch_engines_merge_and_subtract(spark, parts):
    points, _ = parts
    w = freq.matrix(10, 2)
    x = numpy_points(points)
    want = np.exp(1j * x @ w.T).mean(axis=0)
    for engine in ("wide", "arrow"):
        assert np.allclose(sketch.vector(sketch.exact(points, w, engine), 10), want, atol=1e-9)
    labelled = lloyd.assign(points, np.array([[0.0, 0.0], [1.0, 1.0]]))
    zg, n = sketch.cluster_vectors(sketch.per_cluster(labelled, w), 2, 10)
    assert np.allclose((n[:, None] * zg).sum(axis=0) / n.sum(), want, atol=1e-9)
    one = sketch.sums(labelled.where("g = 0"), w)
    rest = sketch.means(sketch.subtract(sketch.sums(points, w), one))
    assert np.allclose(sketch.vector(rest, 10), zg[1], atol=1e-9)
    draw = freq.draw(spark, 10, 2).orderBy("j").collect()
    assert np.allclose([r.w for r in draw], w)


def test_samples(parts):
    points, _ = parts
    a = {r.row_key for r in sample.shared(points, 20).collect()}
    assert a == {r.row_key for r in sample.shared(points.repartition(7), 20).collect()} and len(a) == 20
    assert sample.shared(points, 10_000).count() == points.count()
    per = sample.per_frequency(points, 8, 5).collect()
    assert len(per) == 40 and {(r.j, r.pos) for r in per} == {(j, p) for j in range(5) for p in range(8)} and len({r.row_key for r in per}) == 40
    again = sample.per_frequency(points, 60, 5).collect()  # fewer rows than 5 x 60: hashed for every frequency
    assert len(again) == 300 and all(len({r.row_key for r in again if r.j == j}) == 60 for j in range(5))
    groups = sample.per_group(lloyd.assign(points, np.array([[0.0, 0.0], [50.0, 50.0]])), 7).collect()
    assert len(groups) == 7


@given(st.integers(1, 70))
@settings(max_examples=70, deadline=None)
def test_padding_rescales_to_the_sample_mean(b):
    n, slots = hadamard.register(b)
    assert n >= 1 and b <= slots and slots / b <= 2
    theta = np.random.default_rng(b).uniform(-9, 9, b)
    mu = complex(hadamard.statevector(theta), hadamard.statevector(theta, True))
    assert abs(slots / b * mu - (slots - b) / b - np.exp(1j * theta).mean()) < 1e-12


def test_estimator(spark, parts):
    points, _ = parts
    w = freq.matrix(4, 2)
    z = sketch.vector(sketch.exact(points, w), 4)
    full = sketch.vector(hadamard.estimate_sketch(points, 4, points.count(), None, "shared"), 4)
    assert np.allclose(full, z, atol=1e-9)
    assert np.allclose(sketch.vector(hadamard.estimate_sketch(points, 4, sampling="exact"), 4), z)
    e = measures.estimator_error(points, 4, 16, 256, 12)
    assert e["mse"] < 2.5 * e["bound"]
    some, n = hadamard.estimate_clusters(lloyd.assign(points, np.zeros((1, 2))), w, 64, 4096)
    assert n[0] == points.count() and np.abs(some[0] - z).max() < 0.5


def test_subsample_variance_is_the_bound():
    rng = np.random.default_rng(0)
    v = np.exp(1j * rng.uniform(0, 3, 60))
    got = np.mean([abs(rng.choice(v, 12, replace=False).mean() - v.mean()) ** 2 for _ in range(20_000)])
    assert abs(got / bounds.subsample(60, 12, v.mean()) - 1) < 0.05
    assert bounds.subsample(5, 5, 0) == 0 and bounds.shot(48, 100) == (64 / 48) ** 2 / 100
    b1, s1 = bounds.sizes(0.1)
    b2, _ = bounds.sizes(0.05)
    assert b2 == 4 * b1 == 4 * s1


def test_joint_energy_is_the_mismatch():
    z, sets, w, m = model()
    for state in solve.digits(np.arange(9), m.sizes):
        f = sketch.of_centroids(candidates.chosen(sets, state.tolist()), w)
        y = m.bits(state.tolist())
        assert abs(m.fit_energy(y)[0] + (np.abs(z) ** 2).sum() - sketch.mismatch(z, f)) < 1e-9
        linear, quadratic, constant = m.matrix_form(3.0)
        assert abs(constant + linear @ y + y @ quadratic @ y - m.energy(y, 3.0)[0]) < 1e-9


def test_penalty_and_its_counter_example():
    for i in range(60):
        rng = np.random.default_rng(i)
        _, _, _, m = model(2, 2, 6, rng=rng)
        m = qubo.normalise(m)
        y = (np.arange(16)[:, None] >> np.arange(4)) & 1
        e, ok = m.energy(y, qubo.penalty_weight(m)), m.one_hot_violation(y) == 0
        assert e[ok].max() < e[~ok].min() + 1e-9 or e[ok].min() < e[~ok].min()
        assert ok[np.argmin(e)]
    one = qubo.joint(np.zeros(3, complex), [np.zeros((1, 2))], np.ones((3, 2)))
    weak = qubo.penalty_bound_off_diagonal(one)
    assert one.energy([[0]], weak)[0] < one.energy([[1]], weak)[0]
    safe = qubo.penalty_weight(one)
    assert one.energy([[1]], safe)[0] < one.energy([[0]], safe)[0]


def test_ising_form():
    _, _, _, m = model(2, 2)
    fields, couplings, offset, _ = qubo.ising(m, 1.7)
    for i in range(16):
        y = (i >> np.arange(4)) & 1
        s = 1 - 2 * y
        assert abs(offset + fields @ s + s @ couplings @ s - m.energy(y, 1.7)[0]) < 1e-9


def test_solvers_agree_with_brute_force(spark):
    z, sets, w, m = model(3, 3)
    states = solve.digits(np.arange(27), m.sizes)
    e = np.array([m.fit_energy(m.bits(s.tolist()))[0] for s in states])
    got = solve.coupled(spark, m)
    assert got.selection == states[np.argmin(e)].tolist() and abs(got.value - e.min()) < 1e-9
    scaled = qubo.normalise(m)
    assert solve.bits(spark, scaled, qubo.penalty_weight(scaled)).selection == got.selection
    assert solve.coupled(spark, m, budget=26).status == "no_solution" and solve.bits(spark, m, 1.0, most=8).status == "no_solution"
    alone = qubo.decouple(m)
    assert solve.coupled(spark, alone).selection == solve.grouped_exact(qubo.global_costs(m)).selection
    assert solve.anneal(scaled, qubo.penalty_weight(scaled)).selection == got.selection
    tie = solve.grouped_exact([np.array([2.0, 1.0, 1.0])])
    assert tie.selection == [1]


def test_ragged_candidates(spark):
    z, _, w, _ = model()
    rows = [(0, 0, [0.0, 0.0]), (1, 0, [1.0, 0.0]), (1, 1, [0.0, 1.0]), (2, 0, [2.0, 0.0]), (2, 1, [0.0, 2.0]), (2, 2, [1.0, 1.0])]
    sets = candidates.from_frame(spark.createDataFrame(rows, "g int, r int, c array<double>"))
    assert [len(s) for s in sets] == [1, 2, 3]
    m = qubo.joint(z, sets, w)
    assert solve.coupled(spark, m).states == 6
    kept = candidates.around(np.zeros((2, 2)), 4)
    assert not kept[0][0].any() and candidates.to_frame(spark, kept).where("is_incumbent").count() == 2


def test_exhaustive_is_the_wcss_minimum(spark, parts):
    points, _ = parts
    x = numpy_points(points)
    sets = candidates.around(np.array([[-1.0, -1.0], [1.0, 1.0]]), 3, 0.5)
    states = solve.digits(np.arange(9), [3, 3])
    want = [np.min([((x - s[r]) ** 2).sum(axis=1) for s, r in zip(sets, st_, strict=True)], axis=0).sum() for st_ in states]
    got = solve.exhaustive(points, sets)
    assert abs(got.value - min(want)) < 1e-6 and got.selection == states[int(np.argmin(want))].tolist()
    by_sql = {r.state: r.wcss for r in solve.wcss_of_states(points, sets, states).collect()}
    assert np.allclose([by_sql[i] for i in range(9)], want)


@pytest.mark.parametrize("d", [1, 2, 3, 4, 6])
@pytest.mark.parametrize("mixer", variational.MIXERS)
def test_circuit_subspace_equals_full(d, mixer):
    c = np.random.default_rng(d).uniform(0, 2, d)
    for init in ("w", "basis"):
        sub = variational.simulate(c, [0.7, 1.1], [0.4, 0.2], mixer, init)
        whole = variational.full(c, [0.7, 1.1], [0.4, 0.2], mixer, init)
        assert abs(sub.sum() - 1) < 1e-12 and np.allclose(whole[1 << np.arange(d)], sub, atol=1e-9) and abs(whole.sum() - 1) < 1e-9


@pytest.mark.parametrize("d", [1, 2, 3, 4, 6])
def test_circuit_closed_form(d):
    c = np.random.default_rng(d).uniform(0, 2, d)
    g, b = np.array([0.0, 0.3, 1.9]), np.array([0.0, 0.2, 0.9])
    table = variational.p1(c, g, b)
    for i, x in enumerate(g):
        for j, y in enumerate(b):
            assert np.allclose(table[i, j], variational.simulate(c, [x], [y]), atol=1e-9)
    assert np.allclose(table[:, 0], 1 / d) and np.allclose(table[0], 1 / d)  # no mixing, or no costs: the start stays
    if d == 2:
        assert np.allclose(variational.hopping(2), [[0, 4], [4, 0]])


def test_one_layer_from_a_basis_state_is_blind():
    a, b = (variational.simulate(np.array([0.1, 0.9, 0.4]), [g], [0.5], init="basis") for g in (0.2, 2.0))
    assert np.allclose(a, b)


def test_angles_and_decoding():
    c = np.array([3.0, 1.0, 2.5, 2.0])
    a = variational.optimise(c)
    probs = variational.simulate(c - c.min(), a.gammas, a.betas)
    unit = (c - 1) / 2
    assert probs @ unit < unit.mean()
    assert variational.decode(probs, c, "best_sampled") == 1
    assert measures.success_probability(probs, c) > 0.4
    again = variational.optimise(c, init_angles=a)
    assert again.value <= a.value + 1e-9
    deep = variational.optimise(c, p=2)
    assert deep.value <= a.value + 0.05
    pick, _, share = variational.select([c, c[::-1]], how="best_sampled")
    assert pick == [1, 2] and share == 1.0


def test_noise():
    c = np.array([3.0, 1.0, 2.5])
    probs = np.array([0.1, 0.8, 0.1])
    clean, noisy = Noise(0, 0, 0).outcomes(probs), Noise().outcomes(probs)
    assert np.allclose(clean[[1, 2, 4]], probs) and abs(noisy.sum() - 1) < 1e-12
    assert 0.8 < measures.feasible_rate(noisy) < 1
    assert Noise().pick(probs, c, "mode", 10_000, ("t",))[0] == 1 and Noise(postselect=False).pick(probs, c, "best_sampled", 10_000, ("t",))[0] == 1


def test_noise_grows_with_the_gates(spark):
    flat, gates = Noise(), Noise(p2=0.01)
    assert flat.lost(4, 1) == flat.lost(8, 3) == pytest.approx(flat.depolarise) and flat.ancilla(256) == flat.contrast
    assert gates.lost(4, 1) == pytest.approx(1 - 0.98 * 0.99**8)  # a ring of four has four edges of two gates
    assert flat.lost(4) < gates.lost(4) < gates.lost(6) < gates.lost(6, 2)
    probs = np.array([0.1, 0.8, 0.1])
    rates = [measures.feasible_rate(gates.outcomes(probs, p)) for p in (1, 2, 4)]
    assert rates == sorted(rates, reverse=True) and rates[0] < measures.feasible_rate(flat.outcomes(probs))
    rows = spark.createDataFrame([(str(i), 0, 0.1 * i, -0.2 * i) for i in range(16)], "row_key string, g int, z0 double, z1 double")
    w = freq.matrix(5, 2)
    exact, clear, dim = (hadamard.estimate_clusters(rows, w, b, None, p2=p2)[0] for b, p2 in ((None, 0.0), (16, 0.0), (16, 0.01)))
    assert np.allclose(clear, exact) and np.allclose(dim, exact * 0.99**16)
    frame = hadamard.estimate_sketch(rows, 5, 16, None, "shared", p2=0.01)
    assert np.allclose(sketch.vector(frame, 5), exact[0] * 0.99**16)


def test_annealing_in_tasks(spark):
    m = qubo.normalise(model(3, 3, rng=np.random.default_rng(3))[3])
    a, b = (solve.anneal(m, qubo.penalty_weight(m), 60, 5, 9, s) for s in (None, spark))
    assert a == b and a.selection is not None


def test_plan_counts(spark, sf):
    orders = spark.read.parquet(f"{sf}/orders.parquet")
    n = orders.count()
    scan = measures.io(orders.select("o_orderkey"))
    assert scan["rows_scanned"] == scan["rows_out"] == n and scan["bytes_scanned"] > 0 and scan["rows_shuffled"] == scan["bytes_shuffled"] == 0
    moved = measures.io(orders.repartition(4, "o_orderkey"))
    assert moved["rows_shuffled"] == moved["rows_out"] == n and moved["bytes_shuffled"] > 0
    points = scale.prepare(load(spark, sf, "W12"))[0]
    summed = measures.io(sketch.exact(points, freq.matrix(8, 3)))
    assert summed["rows_shuffled"] <= 64 and summed["rows_out"] == 8  # partial sums, not points


def test_views(spark, sf, parts):
    points, _ = parts
    c, w = seed.initial(points, 3), freq.matrix(12, 2)
    sets = candidates.around(c, 4, 0.2)
    names = views.register(points, c, w, sets, "t_")
    assert sorted(names) == sorted(views.VIEWS) and all(spark.catalog.tableExists(n) for n in names.values())
    costs = qubo.grouped_costs(hadamard.estimate_clusters(lloyd.assign(points, c), w, None)[0], sets, w)
    got = {(r.g, r.r): r.cost for r in spark.table("t_costs").collect()}
    assert all(abs(got[g, r] - v) < 1e-9 for g, row in enumerate(costs) for r, v in enumerate(row)) and len(got) == 12
    assert {r.g: r.r for r in spark.table("t_selection").collect()} == dict(enumerate(solve.grouped_exact(costs).selection))


def test_relaxation_bounds(spark):
    for i in range(10):
        _, _, _, m = model(3, 2, rng=np.random.default_rng(i))
        states = solve.digits(np.arange(8), m.sizes)
        y = np.array([m.bits(s.tolist()) for s in states])
        b = bounds.relaxation(m)
        assert np.abs(bounds.cross_energy(m, y)).max() <= b["pointwise"] + 1e-9
        loose = y[np.argmin(qubo.decouple(m).fit_energy(y))]
        gap = m.fit_energy(loose)[0] - m.fit_energy(y).min()
        assert -1e-9 <= gap <= b["gap"] + 1e-9 <= b["row_sum_gap"] + 2e-9
        assert bounds.relaxation(qubo.decouple(m))["gap"] == 0


def test_resources(spark):
    assert resources.peak(4, 256) == 9 and resources.peak(6, 256) == 9 and resources.peak(4, 1) == 4 and resources.joint(10, 6) == 60
    assert [resources.peak(8, b) for b in (128, 256, 512, 1024)] == [8, 9, 10, 11]
    assert resources.noisy_means_qubits(300) == 11 and resources.noisy_means_qubits(2100) == 14
    rows = resources.grid(spark, [3], [1, 4], [1, 256], [2]).collect()
    for r in rows:
        assert r.peak_qubits == resources.peak(r.d, r.b) and r.mixer_gates == resources.gates(r.p, r.d)["mixer"] and r.cost_gates == resources.gates(r.p, r.d)["cost"]


def test_lloyd_and_seeds(spark, parts):
    points, _ = parts
    x = numpy_points(points)
    c0 = seed.initial(points, 3)
    new, value = lloyd.step(points, c0)
    d2 = ((x[:, None] - c0[None]) ** 2).sum(axis=2)
    g = d2.argmin(axis=1)
    assert abs(value - d2.min(axis=1).sum()) < 1e-6 and np.allclose(new, [x[g == i].mean(axis=0) for i in range(3)])
    far = np.vstack([c0[:2], [[99.0, 99.0]]])
    assert np.allclose(lloyd.step(points, far)[0][2], far[2])  # an empty cluster keeps its centroid
    _, history = lloyd.run(points, c0, 8)
    assert all(a >= b - 1e-9 for a, b in zip(history, history[1:], strict=False))
    for init in ("hash", "plusplus", "mllib"):
        assert seed.initial(points, 3, init).shape == (3, 2)
    assert seed.kmeans(points, 3, on="sample", sample_rows=50).shape == (3, 2)
    same = spark.createDataFrame([("a", 1.0), ("b", 1.0)], "row_key string, z0 double")
    assert seed.initial(same, 3).shape == (3, 1)


def test_refinement(parts):
    points, _ = parts
    w = freq.matrix(24, 2)
    c0 = seed.initial(points, 3)
    s = refine.Settings(b=None, shots_phase=None, solver="grouped_exact", accept="guard")
    r = refine.step(points, c0, w, s)
    assert r.after <= r.before + 1e-9
    _, history = refine.run(points, c0, w, s, 4)
    assert len(history) <= 4 and all(h["surrogate_grouped"] <= h["before"] + 1e-9 for h in history)
    circuit = refine.step(points, c0, w, refine.Settings(b=None, shots_phase=None))
    costs = qubo.grouped_costs(circuit.sketches, candidates.around(c0, 4, 0.2), w)
    assert circuit.after <= circuit.before + sum(measures.delta(costs, circuit.selection)) + 1e-9
    blocked, h = refine.run(points, c0, w, refine.Settings(solver="coupled", budget=3), 5)
    assert h[-1]["status"] == "no_solution" and np.allclose(blocked, c0)
    scheduled = refine.Settings(schedule=lambda t: (1 + t, 256), decode="best_sampled")
    assert len(refine.run(points, c0, w, scheduled, 2, transfer_angles=True)[1]) == 2


@pytest.mark.parametrize("settings_", [{"solver": "grouped_exact", "b": None}, {}, {"noise": Noise()}, {"solver": "coupled"}, {"solver": "exhaustive"}, {"solver": "global"}])
def test_pipeline(spark, sf, settings_):
    r = cluster(load(spark, sf, "W8"), 3, seed_iters=4, **settings_)
    assert r.status == "solved" and r.assignments.count() == 200 and r.sse > 0
    assert r.record(spark, "W8").first().k == 3
    if settings_.get("solver") in ("coupled", "exhaustive"):
        assert r.peak_qubits == 12
    else:
        assert r.peak_qubits == (9 if settings_.get("b", 256) else 4)  # without sampling there is no phase test


def test_pipeline_does_not_depend_on_partitions(spark, sf):
    df = load(spark, sf, "W10")
    a, b = (cluster(x, 3, seed_iters=3, solver="grouped_exact") for x in (df.repartition(2), df.repartition(9)))
    assert np.allclose(a.centroids, b.centroids, atol=1e-9)
    key = lambda r: {x.row_key: x.g for x in r.assignments.collect()}
    assert key(a) == key(b)


def test_edge_points(spark):
    few = spark.createDataFrame([(str(i), float(i % 2), 7.0) for i in range(4)], "row_key string, x0 double, x1 double")
    r = cluster(few, 3, seed_iters=2, solver="grouped_exact")  # fewer rows than B, fewer distinct rows than k, a constant column
    assert r.assignments.count() == 4 and r.sse >= 0
    assert cluster(few, 1, d=1, seed_iters=1).status == "solved"


def test_planted_clusters_are_found(spark, sf):
    """Grouped selection stays near k-means on separated shapes and does not lose to the noisy stand-ins by much."""
    df = load(spark, sf, "W4")
    r = cluster(df, 6, seed_init="plusplus", solver="grouped_exact", b=None)
    assert r.sse <= 1.05 * r.seed_sse


def test_baselines(spark, sf, parts):
    points, _ = parts
    _, best = baselines.kmeans(points, 3, 2, 6)
    _, noisy = baselines.noisy_kmeans(points, 3, 0.05, 4)
    _, overlap = baselines.overlap_kmeans(points, 3, 256, 4)
    assert noisy[-1] >= 0.9 * best and overlap[-1] >= 0.9 * best
    c, got = baselines.assign_qubo(points, 3, 3)
    want, _ = lloyd.run(points, seed.initial(points, 3), 3, 1e-6)
    assert got.status == "solved" and np.allclose(c, lloyd.run(points, seed.initial(points, 3), 2, 0.0)[0], atol=1.0) and want.shape == c.shape
    assert baselines.assign_qubo(points, 3, 3, budget=10)[1].status == "no_solution"
    for weights in ("uniform", "free"):
        c, sse = compressive_baseline(load(spark, sf, "W8"), 3, 24, weights, 2)
        assert c.shape == (3, 2) and math.isfinite(sse)
    x = baselines.nonnegative_least_squares(np.eye(3), np.array([1.0, -1.0, 2.0]))
    assert np.allclose(x, [1, 0, 2], atol=1e-6)


def test_measures(spark, parts):
    points, scaler = parts
    c = np.array([[-0.5, 0.0], [0.5, 0.2]])
    labelled = lloyd.assign(points, c)
    x, g = numpy_points(points), None
    d2 = ((x[:, None] - c[None]) ** 2).sum(axis=2)
    g = d2.argmin(axis=1)
    assert abs(measures.wcss(labelled, c, prefix="z") - d2.min(axis=1).sum()) < 1e-6
    means = np.array([x[g == i].mean(axis=0) for i in range(2)])
    assert abs(measures.wcss(labelled, c, "mean", "z") - sum(((x[g == i] - means[i]) ** 2).sum() for i in range(2))) < 1e-6
    assert measures.original_wcss(points, c, scaler) > 0
    lab = spark.createDataFrame([(0, "a"), (0, "a"), (1, "b"), (1, "b")], "g int, label string")
    assert measures.agreement(lab) == {"purity": 1.0, "ari": 1.0, "nmi": pytest.approx(1.0)}
    few = sample.shared(points, 12)
    errors = [measures.kernel_error(few, freq.matrix(m, 2)).agg(F.avg("error")).first()[0] for m in (16, 400)]
    assert errors[1] < errors[0]
    counted, seen = measures.observed(points, "rows")
    counted.write.format("noop").mode("overwrite").save()
    assert seen.get["rows"] == points.count() and measures.sketch_bytes(24) == 384


def test_plans_are_narrow(spark, sf):
    points, _ = scale.prepare(load(spark, sf, "W14"))
    plan = sketch.exact(points, freq.matrix(6, 2))._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in plan and "l_tax" not in plan and "partial_sum" in plan
    plan = lloyd.assign(points, np.zeros((2, 2))).select("row_key", "g")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan


@pytest.mark.parametrize("name", ["W1", "W2", "W3", "W5", "W7", "W9b", "W11", "W13", "W23", "W24", "W24b", "W24c"])
def test_workloads(spark, sf, name):
    df = load(spark, sf, name)
    assert len(df.columns) == WORKLOADS[name][1] + 1
    assert df.count() == df.select("row_key").distinct().count() > 0


def test_samples_move_few_rows(spark):
    """At a sample size beyond Spark's window group limit, only rows below the threshold reach the shuffle; the sample is that of the full order."""
    n, b = 60_000, 1024
    df = spark.range(n).select(F.col("id").cast("string").alias("row_key"), (F.col("id") % 3).cast("int").alias("g"), F.col("id").cast("double").alias("z0"))
    got = sample.per_group(df, b, sizes=sample.sizes_of(df))
    want = df.withColumn("_h", uniform("s", 42, F.col("row_key"))).withColumn("pos", F.row_number().over(Window.partitionBy("g").orderBy("_h", "row_key"))).where(F.col("pos") <= b)
    assert {(r.g, r.row_key, r.pos) for r in got.collect()} == {(r.g, r.row_key, r.pos - 1) for r in want.collect()}
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "Filter" in plan.split("Window", 1)[1]
    below = df.withColumn("_h", uniform("s", 42, F.col("row_key"))).where(F.col("_h") < sample.group_threshold(b, {0: n // 3, 1: n // 3, 2: n // 3}))
    assert 3 * b <= below.count() < 3 * b * 1.5
    few = sample.shared(df, 50, n=n)
    assert "Filter" in few._jdf.queryExecution().optimizedPlan().toString() and few.count() == 50


def test_samples_of_repeated_keys(spark):
    """Keys that repeat spoil the hashes' uniformity: all rows are ordered then, and no row of the sample is missing."""
    df = spark.range(5000).select(F.lit("same").alias("row_key"), (F.col("id") % 2).cast("int").alias("g"), F.col("id").cast("double").alias("z0"))
    assert sample.shared(df, 100).count() == 100
    assert {r["count"] for r in sample.per_group(df, 30).groupBy("g").count().collect()} == {30}
    z, size = hadamard.estimate_clusters(df, freq.matrix(4, 1), 30, None)
    assert size.tolist() == [2500, 2500] and np.isfinite(z).all() and (np.abs(z) > 0).all()


@pytest.mark.parametrize("rows", [400, 9000])
def test_clusters_per_frequency(spark, rows):
    """Every component of a cluster's sketch has a sample of its own, of the given size, close to the exact value on average."""
    df = spark.range(rows).select(F.col("id").cast("string").alias("row_key"), (F.col("id") % 2).cast("int").alias("g"), (F.col("id") % 17 / F.lit(8.0) - 1).alias("z0"))
    w, b = freq.matrix(40, 1), 64
    drawn = sample.per_group_frequency(df, b, len(w))
    counts = drawn.groupBy("g", "j").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("row_key").alias("u"), F.max("pos").alias("last")).collect()
    assert len(counts) == 80 and all((r.n, r.u, r["last"]) == (b, b, b - 1) for r in counts)
    assert drawn.groupBy("g").agg(F.countDistinct("row_key").alias("u")).where(F.col("u") > b).count() == 2
    exact, _ = hadamard.estimate_clusters(df, w, None)
    apart, size = hadamard.estimate_clusters(df, w, b, None, sampling="per_frequency")
    assert size.tolist() == [rows // 2, rows // 2] and np.sqrt(np.mean(np.abs(apart - exact) ** 2)) < 1.5 / np.sqrt(b)
    with pytest.raises(ValueError):
        hadamard.estimate_clusters(df, w, b, sampling="none")
