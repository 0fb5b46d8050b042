"""Solvers under erasures: exact limits, bounds, and the order of the schemes."""

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from erasureml.operators import blocks, codes, compare, encode, factorization, partials, solvers, spectrum, stragglers
from erasureml.plans import workloads
from erasureml.sources import fixtures

AT = "/root/testdata/sf0.001"
N, P, M, LAM = 256, 20, 16, 0.05


def data(seed=0, noise=3.0, n=N, p=P):
    rng = np.random.default_rng(seed)
    x, w = rng.normal(size=(n, p)), rng.normal(size=p)
    return x, x @ w + noise * rng.normal(size=n)


def problem(scheme, x, y, m=M, lam=LAM, seed=1):
    n, p = x.shape
    original = partials.GramPartials.of([(x, y)])
    if scheme == "replication":
        part = np.arange(n) % (m // 2)
        own = [(x[part == i % (m // 2)], y[part == i % (m // 2)]) for i in range(m)]
        return solvers.Problem(partials.GramPartials.of(own), n, m, p, lam, original, np.arange(m) % (m // 2))
    code = codes.FAMILIES[scheme](n, seed)
    e, worker = code.apply(np.c_[x, y]), codes.assign(code, m)
    return solvers.Problem(partials.GramPartials.of([(e[worker == i, :-1], e[worker == i, -1]) for i in range(m)]), n, m, p, lam, original)


def random_sets(k, rounds, m=M, seed=3):
    rng = np.random.default_rng(seed)
    out = np.zeros((rounds, m), bool)
    for t in range(rounds):
        out[t, rng.permutation(m)[:k]] = True
    return out


@pytest.mark.parametrize("scheme", ["uncoded", "paley", "hadamard", "steiner", "haar", "dft", "replication"])
def test_all_replies_give_the_uncoded_iterates(scheme):
    x, y = data()
    full = np.ones((6, M), bool)
    step = solvers.gradient_step(problem("uncoded", x, y))
    want = solvers.gradient_descent(problem("uncoded", x, y), full, step=step).w
    assert np.allclose(solvers.gradient_descent(problem(scheme, x, y), full, step=step).w, want)
    a = solvers.lbfgs(problem("uncoded", x, y), full).w
    assert np.allclose(solvers.lbfgs(problem(scheme, x, y), full).w, a)


def test_lbfgs_reaches_the_exact_solution():
    x, y = data()
    pr = problem("uncoded", x, y)
    best = solvers.ridge_solution(pr.original, N, LAM)
    run = solvers.lbfgs(pr, np.ones((60, M), bool), rho=1.0)
    assert np.allclose(run.w, best, atol=1e-6)


def test_order_of_schemes_at_few_replies():
    """Median over paired trials of the final objective: coded under uncoded, replication between or near."""
    last = {s: [] for s in ("uncoded", "replication", "hadamard", "paley", "steiner")}
    for trial in range(7):
        x, y = data(trial, noise=5.0)
        active = random_sets(10, 40, seed=trial)
        for s in last:
            pr = problem(s, x, y)
            best = pr.objective(solvers.ridge_solution(pr.original, N, LAM))
            last[s].append(solvers.lbfgs(pr, active).trace["objective"].iloc[-1] / best)
    mid = {s: float(np.median(v)) for s, v in last.items()}
    assert max(mid["hadamard"], mid["paley"], mid["steiner"]) < mid["uncoded"]
    assert mid["steiner"] < mid["replication"]


def test_losing_both_copies_hurts_replication_for_good():
    x, y = data(noise=5.0)
    active = stragglers.adversary("kill_replicas", M, 12, 200)
    ratio = {}
    for s in ("replication", "steiner"):
        pr = problem(s, x, y)
        best = pr.objective(solvers.ridge_solution(pr.original, N, LAM))
        ratio[s] = solvers.gradient_descent(pr, active, step=solvers.gradient_step(pr)).trace["objective"].iloc[-1] / best
    assert ratio["steiner"] < ratio["replication"]


def test_erased_solution_is_within_the_factor_of_the_code():
    x, y = data()
    code = codes.FAMILIES["steiner"](N, 1)
    worker, e = codes.assign(code, M), code.apply(np.c_[x, y])
    live = np.isin(worker, np.arange(14))
    eps = spectrum.epsilon(code, M, 14, subsets="sample", count=1)
    eig = np.linalg.eigvalsh(spectrum.left_over(code, worker, tuple(range(14)))) * M / 14
    eps = max(1 - eig[0], eig[-1] - 1)
    w = np.linalg.lstsq(e[live, :-1], e[live, -1], rcond=None)[0]
    best = np.linalg.lstsq(x, y, rcond=None)[0]
    assert ((x @ w - y) ** 2).sum() <= spectrum.approximation_ratio(eps) * ((x @ best - y) ** 2).sum()


def test_proximal_maps_minimise():
    rng = np.random.default_rng(2)
    v, tau = rng.normal(size=6) * 2, 0.3
    forms = [(solvers.prox_l1, lambda z: np.abs(z).sum()), (solvers.prox_l2sq, lambda z: 0.5 * z @ z), (solvers.prox_group(3), lambda z: np.linalg.norm(z.reshape(-1, 3), axis=1).sum()), (solvers.prox_l1sq, lambda z: np.abs(z).sum() ** 2), (solvers.prox_elastic(0.4), lambda z: 0.4 * np.abs(z).sum() + 0.3 * z @ z)]
    for prox, h in forms:
        at = prox(v, tau)
        value = lambda z, h=h: 0.5 * ((z - v) ** 2).sum() + tau * h(z)
        assert all(value(at) <= value(at + 1e-3 * rng.normal(size=6)) + 1e-12 for _ in range(200))
    assert np.linalg.norm(solvers.project_l2ball(1.0)(v, 0)) <= 1 + 1e-12 and (solvers.project_box(-1, 1)(v, 0) <= 1).all() and (solvers.project_nonneg(v, 0) >= 0).all()


def test_lasso_matches_the_long_run():
    x, y = data()
    pr = problem("uncoded", x, y, lam=0.5)
    step = 0.9 / (solvers.largest_eigenvalue(pr.original.G[0]) / N)
    run = solvers.proximal_gradient(pr, np.ones((600, M), bool), solvers.prox_l1, lambda w: np.abs(w).sum(), step=step)
    assert np.allclose(run.w, solvers.lasso_solution(pr.original, N, 0.5), atol=1e-6)


@pytest.mark.parametrize(("scheme", "exact"), [("hadamard", True), ("steiner", True), ("uncoded", False), ("haar", False)])
def test_block_descent_under_fixed_erasures(scheme, exact):
    """The same workers never reply: codes whose rest has full rank still reach the optimum, the others don't."""
    rng = np.random.default_rng(0)
    p = 30
    x = rng.normal(size=(150, p))
    y = np.sign(x @ rng.normal(size=p) + rng.normal(size=150))
    grad = blocks.LocalGradient(x, y, blocks.LOGISTIC, 0.05)
    best = grad(blocks.logistic_solution(x, y, 0.05))[0]
    active = stragglers.adversary("fixed", 16, 11, 4000)
    run = blocks.block_coordinate_descent(grad, codes.FAMILIES[scheme](p, 1), active, step=0.95 / grad.smoothness())
    f = run.trace["objective"].to_numpy()
    assert (np.diff(f) <= 1e-12).all()
    assert (f[-1] - best < 1e-6) == exact


def test_losses_have_the_slope_they_say():
    z, y = np.linspace(-2, 2, 41), np.where(np.arange(41) % 2, 1.0, -1.0)
    for loss in (blocks.LOGISTIC, blocks.SQUARED, blocks.HINGE):
        numeric = (loss.value(z + 1e-6, y) - loss.value(z - 1e-6, y)) / 2e-6
        assert np.allclose(numeric, loss.slope(z, y), atol=1e-4)


def test_async_updates_are_uneven_under_background_load(spark):
    d = stragglers.delays(spark, stragglers.background_power_law(), 40, 8).toPandas().pivot(index="t", columns="worker", values="delay").to_numpy()
    x, y = data(n=120, p=16)
    grad = blocks.LocalGradient(x, np.sign(y), blocks.LOGISTIC, 0.05)
    run, events = blocks.async_block_descent(grad, 16, d, step=0.5 / grad.smoothness(), horizon=6.0)
    share = np.bincount(events["worker"], minlength=8) / len(events)
    assert share.max() > 1.5 / 8 and run.trace["objective"].iloc[-1] < run.trace["objective"].iloc[0]
    pr = problem("uncoded", x, y, m=8)
    assert blocks.async_gradient(pr, d[:, :8], step=0.2, horizon=3.0).trace["objective"].iloc[-1] < pr.objective(np.zeros(16))


def test_bounds_hold_on_a_run():
    x, y = data(noise=1.0)
    pr = problem("steiner", x, y)
    best = pr.objective(solvers.ridge_solution(pr.original, N, LAM))
    eps = spectrum.epsilon(codes.FAMILIES["steiner"](N, 1), M, 15, subsets="all")
    e = np.linalg.eigvalsh(pr.original.G[0]) / N
    run = solvers.gradient_descent(pr, random_sets(15, 80), step=solvers.gradient_step(pr, eps))
    bound = spectrum.bound_gd(80, pr.objective(np.zeros(P)), eps, 0.5, e[0], e[-1], LAM)
    if np.isfinite(bound["first"]):
        assert run.trace["objective"].iloc[-1] <= bound["first"] + bound["factor"] * best
    grow = spectrum.bound_prox(0.05, 10, 0.1, 1.0)
    assert grow["mean_factor"] > 1 and np.isnan(spectrum.bound_prox(0.2, 10, 0.1, 1.0)["mean_factor"])
    cos, low = spectrum.kantorovich(pr.original.G[0], np.random.default_rng(0).normal(size=P))
    assert low <= cos <= 1


def test_encoders_agree(spark):
    df = fixtures.dense_embeddings(spark, AT, 4).where("row_id < 28")
    code = codes.hadamard_etf(3)
    a, b = ({r.enc_row: (r.worker, *r.x, r.y) for r in encode.encode_rows(df, code, 8, mode=m).collect()} for m in ("join", "grouped"))
    assert a.keys() == b.keys() and all(np.allclose(a[k], b[k]) for k in a)
    with pytest.raises(ValueError):
        encode.encode_rows(df, code, 8, mode="other")


def test_scan_gram_and_online_partials_agree(spark):
    df = fixtures.dense_embeddings(spark, AT, 5)
    code = codes.steiner(8)
    enc = encode.encode_rows(df, code, 8).persist()
    w, live = np.linspace(-1, 1, 5), np.arange(8) % 3 != 0
    scan, gram = partials.ScanPartials(enc, 8, 5), partials.GramPartials(enc, 8, 5)
    online = partials.OnlinePartials(encode.support_rows(df, code, 8), code, 8, 5)
    g, f = scan.gradients(w, live)
    for other in (gram, online):
        assert np.allclose(other.gradients(w, live)[0], g) and np.allclose(other.gradients(w, live)[1], f)
    assert np.allclose(scan.curvature(w, live), gram.curvature(w, live))
    again = partials.ScanPartials(enc.repartition(5), 8, 5).gradients(w, live)[0]
    assert np.allclose(again, g)


def test_pruned_layout_reads_active_folders_only(spark, tmp_path):
    enc = encode.encode_rows(fixtures.dense_embeddings(spark, AT, 3), codes.steiner(4), 4)
    encode.write_by_worker(enc, f"{tmp_path}/enc")
    got = encode.read_active(spark, f"{tmp_path}/enc", [1, 2])
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(worker" in plan or "worker#" in plan.split("PartitionFilters")[1][:80]
    assert {r.worker for r in got.select("worker").distinct().collect()} == {1, 2}


def test_ridge_rows_and_columns(spark):
    df = fixtures.dense_embeddings(spark, AT, 4)
    a, b = partials.whole_gram(encode.absorb_ridge(df, 0.3, 4), 4), partials.whole_gram(df, 4)
    assert np.allclose(a.G[0] - b.G[0], 0.3 * np.eye(4)) and np.allclose(a.c, b.c)
    code = codes.hadamard(4, 2, 1)
    cols = encode.encode_columns(df, code, 2).where("row_id = 3").orderBy("worker").collect()
    x = np.array(df.where("row_id = 3").first().x)
    worker = codes.assign(code, 2)
    assert all(np.allclose(r.xblk, (code.matrix() @ x)[worker == r.worker]) for r in cols)


def test_scan_gradient_equals_arrays(spark):
    df = fixtures.dense_embeddings(spark, AT, 6)
    rows = df.orderBy("row_id").collect()
    x, y = np.array([r.x for r in rows]), np.array([r.y for r in rows])
    a, b = blocks.ScanGradient(df, 6, blocks.SQUARED, 0.1), blocks.LocalGradient(x, y, blocks.SQUARED, 0.1)
    w = np.linspace(-1, 1, 6)
    assert np.isclose(a(w)[0], b(w)[0]) and np.allclose(a(w)[1], b(w)[1])


def test_recovery_of_a_planted_support(spark):
    t = workloads.lasso_rows(spark, AT)
    late = t[t["t"] >= 50].groupby(["scheme", "k"])
    f1, clock = late["measure"].mean(), late["clock"].max()
    assert f1[("uncoded", 16)] + 0.02 >= f1[("steiner", 10)] > f1[("uncoded", 10)]
    assert f1[("steiner", 10)] > f1[("uncoded", 16)] - 0.12
    assert clock[("steiner", 10)] < 0.8 * clock[("uncoded", 16)]


def test_adversaries_on_a_table(spark):
    t = workloads.adversary_rows(spark, AT, 40).pivot(index="scheme", columns="adversary", values="ratio")
    assert (t.loc["hadamard"] < 1.6).all() and t.loc["hadamard", "kill_replicas"] < t.loc["replication", "kill_replicas"] + 0.2
    assert isinstance(t, pd.DataFrame)


def test_factorisation_learns_planted_ratings(spark):
    r = fixtures.ratings_planted(spark, AT).persist()
    error = {}
    for scheme in ("exact", "hadamard", "uncoded"):
        _, _, trace = factorization.alternating(r, rank=3, lam=1.0, epochs=2, schemes=scheme, m=8, k=4, threshold=8, rounds=8)
        error[scheme] = trace[-1]["train_rmse"]
    base = float(np.std([x.rating for x in r.select("rating").collect()]))
    assert error["exact"] < base and error["exact"] <= error["hadamard"] + 1e-9
    assert error["hadamard"] < error["uncoded"] + 0.05


def test_a_real_race_cancels_the_rest(spark):
    import time

    def answer(i):
        if i == 3:
            return spark.range(1).rdd.map(lambda x: time.sleep(20)).count()
        return spark.range(100).count()

    began = time.time()
    done = compare.wall_clock_round(spark, answer, 4, 3, pool=4)
    assert set(done) == {0, 1, 2} and time.time() - began < 15


def test_batched_quasi_newton_is_the_single_one():
    rng = np.random.default_rng(4)
    cuts = np.array([0, 40, 100, 190])
    x, y = rng.normal(size=(190, 5)), rng.normal(size=190)
    delays = factorization.reply_delays(10, 8, 3)
    for scheme, k in (("hadamard", 6), ("paley", 5), ("uncoded", 8), ("replication", 5)):
        sums = factorization.Sums.of(x, y, cuts, scheme, 8)
        weights = factorization.round_weights(scheme, 8, k, delays)
        got = sums.solved(2.0, weights, 10)
        again = factorization.Sums.unpacked(sums.packed(), 5).solved(2.0, weights, 10)
        assert np.array_equal(got, again)
        whole = np.stack([np.linalg.solve(x[i:j].T @ x[i:j] + 2 * np.eye(5), x[i:j].T @ y[i:j]) for i, j in zip(cuts[:-1], cuts[1:], strict=True)])
        assert np.allclose(factorization.Sums.of(x, y, cuts, "exact", 8).solved(2.0, None, 0), whole)
        if scheme != "replication":
            assert np.allclose(sums.gram.sum(1), factorization.Sums.of(x, y, cuts, "exact", 8).gram[:, 0])
        for i, (lo, hi) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
            if scheme == "replication":
                continue
            problem = solvers.Problem(partials.GramPartials.of([(np.linalg.cholesky(sums.gram[i, j] + 1e-13 * np.eye(5)).T, np.zeros(5)) for j in range(8)]), 1, 8, 5, 2.0)
            problem.partials.G, problem.partials.c = sums.gram[i], sums.c[i]
            rank = delays.argsort(1).argsort(1) < k
            one = solvers.lbfgs(problem, rank[:10], rank[10:], memory=5).w
            assert np.allclose(one, got[i], atol=1e-6), (scheme, i)


def test_a_hot_id_is_solved_from_several_tasks(spark):
    rng = np.random.default_rng(8)
    rows = [(0, i, float(rng.integers(1, 6)), False) for i in range(600)] + [(u, int(i), float(rng.integers(1, 6)), False) for u in range(1, 30) for i in rng.choice(600, 20, replace=False)]
    r = spark.createDataFrame(rows, "user long, item long, rating double, is_test boolean")
    runs = []
    for spread in (1 << 14, 100):
        users, _, trace = factorization.alternating(r, rank=2, lam=1.0, epochs=1, schemes=["exact"], m=8, k=8, rounds=4, threshold=50, spread=spread)
        runs.append({x.user: [*x.f, x.bias] for x in users.collect()})
    assert all(np.allclose(runs[0][u], runs[1][u]) for u in runs[0])
    coded, _, _ = factorization.alternating(r, rank=2, lam=1.0, epochs=1, schemes=["hadamard"], m=8, k=8, rounds=12, threshold=50, spread=100)
    got = {x.user: [*x.f, x.bias] for x in coded.collect()}
    assert np.allclose(got[0], runs[0][0], atol=1e-4)


def test_encoding_refuses_what_no_sum_can_stand_for(spark):
    code = codes.hadamard(8, 2, 1)
    good = [(i, [float(i), 1.0], 2.0) for i in range(20)]
    schema = "row_id long, x array<double>, y double"

    def energy(rows):
        e = encode.encode_rows(spark.createDataFrame(rows, schema), code, 4)
        return sum(sum(v * v for v in r.x) + r.y * r.y for r in e.collect())

    assert np.isclose(energy(good), sum(i * i + 5 for i in range(20)))
    for bad in ((3, [1.0, 2.0], 0.0), (None, [1.0, 2.0], 0.0), (99, None, 0.0), (99, [1.0], 0.0), (99, [1.0, None], 0.0), (99, [1.0, 2.0], None)):
        with pytest.raises(Exception, match="BadRows"):
            energy([*good, bad])
    big = (1 << 53) + 1
    e = encode.encode_rows(spark.createDataFrame([(big * 8 + i, [1.0, float(i)], 0.0) for i in range(8)], schema), code, 4).collect()
    assert {r.enc_row for r in e} == set(range(big * 16, big * 16 + 16))
    df = spark.createDataFrame([(None, [float(i)], 0.0) for i in range(37)], schema).repartition(5)
    assert sorted(r.row_id for r in encode.numbered(df).collect()) == list(range(37))
    assert encode.encode_rows(spark.createDataFrame([], schema), code, 4).collect() == []


def test_absorbed_ridge_rows_are_never_erased(spark):
    rng = np.random.default_rng(2)
    x, y, w, lam = rng.normal(size=(56, 3)), rng.normal(size=56), rng.normal(size=3), 0.7
    df = spark.createDataFrame([(i, x[i].tolist(), float(y[i])) for i in range(56)], "row_id long, x array<double>, y double")
    both = encode.absorb_ridge(df, lam, 3)
    for mode in ("grouped", "join"):
        enc = encode.encode_rows(both, codes.hadamard_etf(3), 8, mode=mode)
        rows = enc.collect()
        assert np.isclose(sum(sum(v * v for v in r.x) for r in rows), (x * x).sum() + 3 * lam)
        assert sorted(r.enc_row for r in rows if r.worker == encode.ALWAYS) == [-3, -2, -1]
        g, _ = partials.ScanPartials(enc, 8, 3).total(w, np.ones(8, bool))
        assert np.allclose(g, x.T @ (x @ w - y) + lam * w)
        live = np.arange(8) < 6
        g, _ = partials.ScanPartials(enc, 8, 3).total(w, live)
        part = sum(np.array(r.x) * (np.dot(r.x, w) - r.y) for r in rows if 0 <= r.worker < 6) * 8 / 6
        assert np.allclose(g, part + lam * w)


def test_sparse_scan_and_runs_side_by_side(spark):
    rng = np.random.default_rng(21)
    p, n = 12, 60
    x = rng.normal(size=(n, p)) * (rng.random((n, p)) < 0.4)
    y, test = np.where(rng.random(n) < 0.5, 1.0, -1.0), rng.random(n) < 0.2
    rows = [([int(j) for j in np.flatnonzero(x[i])], [float(v) for v in x[i][x[i] != 0]], float(y[i]), bool(test[i])) for i in range(n)]
    df = spark.createDataFrame(rows, "idx array<int>, val array<double>, y double, is_test boolean").repartition(3)
    scan = blocks.SparseScan(df, p, blocks.LOGISTIC, 0.02)
    own = blocks.LocalGradient(x[~test], y[~test], blocks.LOGISTIC, 0.02)
    w = rng.normal(size=(p, 3))
    value, g, wrong = scan(w)
    for j in range(3):
        f, h = own(w[:, j])
        assert np.isclose(value[j], f) and np.allclose(g[:, j], h)
        assert np.isclose(wrong[0, j], (x[~test] @ w[:, j] * y[~test] <= 0).mean()) and np.isclose(wrong[1, j], (x[test] @ w[:, j] * y[test] <= 0).mean())
    assert scan.smoothness() >= own.smoothness() - 1e-12
    active = np.stack([np.arange(4) != t % 4 for t in range(4)])
    runs = blocks.side_by_side(scan, {"a": "hadamard", "b": "steiner"}, dict.fromkeys("ab", active), dict.fromkeys("ab", np.arange(4.0)), 0.3)
    for name, scheme in (("a", "hadamard"), ("b", "steiner")):
        alone = blocks.block_coordinate_descent(own, codes.FAMILIES[scheme](p, 1), active, step=0.3)
        assert np.allclose(runs[runs["name"] == name]["objective"].to_numpy()[1:], alone.trace["objective"])
    d = rng.exponential(size=(5, 4))
    curve, events = blocks.async_side(scan, d, 0.3, 3.0, looks=100)
    alone, same = blocks.async_block_descent(own, p, d, step=0.3, horizon=3.0)
    assert np.allclose(curve["objective"].to_numpy()[1:], alone.trace["objective"]) and events["staleness"].tolist() == same["staleness"].tolist()


def test_slabs_give_the_whole_matrix(monkeypatch):
    for name, make in codes.FAMILIES.items():
        code = make(13, 1)
        s, v, z = code.matrix(), np.random.default_rng(1).normal(size=(13, 2)), np.random.default_rng(2).normal(size=code.N)
        for slab in (64 << 20, 8 * 13 * 3):
            monkeypatch.setattr(codes, "SLAB_BYTES", slab)
            assert np.allclose(code.apply(v), s @ v) and np.allclose(code.apply_t(z), s.T @ z), name


def test_late_commits_take_back_what_was_not_accepted():
    states = blocks.BlockStates([2, 2])
    states.reply({0: np.ones(2), 1: np.ones(2)}, 0.5)
    states.hear(1, np.array([True, False]))
    assert states.v[0].tolist() == [-0.5, -0.5] and states.v[1].tolist() == [0.0, 0.0]
    assert states.committed == [1, -1] and states.pending == [None, None]


def test_blocks_give_the_errors_and_factors_of_one_block(spark, monkeypatch):
    """A block gets every factor row it names once, for all schemes; errors by block are those of the joined predictions."""
    rng = np.random.default_rng(5)
    rows = [(int(u), int(i), float(1 + (3 * u + 5 * i) % 5), bool((u + i) % 5 == 0)) for u in range(40) for i in rng.choice(30, 12, replace=False)]
    r = spark.createDataFrame(rows, "user long, item long, rating double, is_test boolean")
    kw = {"rank": 2, "lam": 1.0, "epochs": 1, "schemes": ["exact", "hadamard"], "m": 8, "k": 4, "rounds": 6, "threshold": 8}
    users, items, one = factorization.alternating(r, **kw)
    monkeypatch.setattr(factorization, "BLOCK", 40)
    many_users, _, many = factorization.alternating(r, **kw)
    train = factorization.counted(r).where("not is_test")
    cuts = factorization.blocks_of(train, "user")
    assert len(cuts) > 3
    sent = factorization._sent(train.withColumn("block", factorization._block("user", cuts)), items, "item")
    assert sent.count() == sent.select("to", "id").distinct().count() and all(r["names"] == ["exact", "hadamard"] for r in sent.collect())
    assert np.allclose([[t["train_rmse"], t["test_rmse"]] for t in one], [[t["train_rmse"], t["test_rmse"]] for t in many])
    a, b = ({(r["scheme"], r["user"]): [*r["f"], r["bias"]] for r in u.collect()} for u in (users, many_users))
    assert a.keys() == b.keys() and all(np.allclose(a[x], b[x]) for x in a)
    joined = {(x["scheme"], x["is_test"]): x["rmse"] for x in factorization.rmse(factorization.predicted(r, users, items, 3.0, ["exact", "hadamard"])).collect()}
    for t in one:
        assert np.allclose([t["train_rmse"], t["test_rmse"]], [joined[t["scheme"], False], joined[t["scheme"], True]])


@pytest.mark.parametrize("scheme", ["uncoded", "replication", "gaussian", "paley", "hadamard"])
@pytest.mark.parametrize(("m", "k"), [(8, 4), (24, 3)])
def test_rows_are_solved_as_their_workers_sums_are(scheme, m, k):
    """With no matrix for each worker, whose number (24) made the time; ids of under, just and over one group."""
    rng = np.random.default_rng(6)
    cuts = np.array([0, 9, 41, 74, 74 + 100])
    x, y = rng.normal(size=(174, 6)), rng.normal(size=174)
    weights = factorization.round_weights(scheme, m, k, factorization.reply_delays(8, m, 2))
    rows, sums = (kind(x, y, cuts, scheme, m) if kind is factorization.Rows else kind.of(x, y, cuts, scheme, m) for kind in (factorization.Rows, factorization.Sums))
    assert np.allclose(rows.solved(3.0, weights, 8), sums.solved(3.0, weights, 8), rtol=1e-9)
    assert np.allclose(rows.solved(3.0, None, 8), factorization.Sums.of(x, y, cuts, "exact", m).solved(3.0, None, 8))
    assert rows.x.size == 8 * factorization.GROUP * 6


def test_schemes_that_take_their_turn_give_the_same(spark, monkeypatch):
    """One scheme at a time, also with ids that are dealt over tasks, whose factors go to every block of theirs."""
    rng = np.random.default_rng(7)
    rows = [(int(u), int(i), float(1 + (3 * u + 5 * i) % 5), bool((u + i) % 5 == 0)) for u in range(20) for i in rng.choice(60, 30, replace=False)]
    r = spark.createDataFrame(rows, "user long, item long, rating double, is_test boolean")
    kw = {"rank": 2, "lam": 1.0, "epochs": 2, "schemes": ["hadamard", "exact", "replication"], "m": 8, "k": 4, "rounds": 6, "threshold": 8, "spread": 20, "save": workloads.saved, "drop": workloads.dropped}
    monkeypatch.setattr(factorization, "BLOCK", 300)
    users, items, together = factorization.alternating(r, **kw)
    monkeypatch.setattr(factorization, "FACTOR_BYTES", 1)
    one_users, _, single = factorization.alternating(r, **kw)
    assert [(t["scheme"], t["epoch"]) for t in single] == [(s, e) for e in (0, 1) for s in kw["schemes"]]
    assert np.allclose([[t["train_rmse"], t["test_rmse"], t["clock"]] for t in single], [[t["train_rmse"], t["test_rmse"], t["clock"]] for t in together])
    a, b = ({(x["scheme"], x["user"]): [*x["f"], x["bias"]] for x in u.collect()} for u in (users, one_users))
    assert len(a) == 3 * 20 and a.keys() == b.keys() and all(np.allclose(a[x], b[x]) for x in a)
    joined = {(x["scheme"], x["is_test"]): x["rmse"] for x in factorization.rmse(factorization.predicted(r, users, items, 3.0, kw["schemes"])).collect()}
    for t in together[3:]:
        assert np.allclose([t["train_rmse"], t["test_rmse"]], [joined[t["scheme"], False], joined[t["scheme"], True]])


@pytest.mark.parametrize("scheme", ["uncoded", "replication", "gaussian", "paley", "hadamard"])
def test_a_factorisation_makes_its_ratings_once(spark, scheme):
    """What gives the ratings (joins of whole tables) must not run again for each side's counts."""
    made = spark.sparkContext.accumulator(0)

    def tally(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    pairs = fixtures.ratings_planted(spark, AT).select("user", "item", "rating", "is_test").localCheckpoint()
    r = pairs.mapInArrow(tally, pairs.schema)
    factorization.alternating(r, rank=2, lam=2.0, epochs=1, schemes=scheme, m=8, k=4, threshold=8, rounds=2, save=workloads.spooled, drop=workloads.dropped)
    assert made.value == pairs.count()


def test_a_singular_system_does_not_end_the_run():
    """Factors can grow until lambda is lost in rounding; then LAPACK refuses one id's system, and with it all of its batch."""
    x = np.full((2, 4), 2.0**40)
    y, cuts = np.array([2.0**40, 1.0]), np.array([0, 1, 2])
    x[1] = [1.0, 2.0, 0.0, 1.0]
    with pytest.raises(np.linalg.LinAlgError):
        np.linalg.solve(x[:1].T @ x[:1] + 0.5 * np.eye(4), x[:1].T @ y[:1])
    for problem in (factorization.Rows(x, y, cuts, "exact", 8), factorization.Sums.of(x, y, cuts, "exact", 8)):
        w = problem.solved(0.5, None, 0)
        assert np.allclose(w[0], 0.25) and np.allclose(w[1], np.linalg.solve(np.outer(x[1], x[1]) + 0.5 * np.eye(4), x[1]))


def test_ids_of_as_many_groups_are_solved_as_among_others():
    """A row of zeros between ids' groups changes nothing, whether all ids have one group, three, or each its own number."""
    rng = np.random.default_rng(9)
    for sizes in ([5, 32, 20], [70, 96, 65], [5, 70, 40]):
        cuts = np.concatenate([[0], np.cumsum(sizes)])
        x, y = rng.normal(size=(cuts[-1], 6)), rng.normal(size=cuts[-1])
        weights = factorization.round_weights("hadamard", 8, 4, factorization.reply_delays(8, 8, 2))
        rows = factorization.Rows(x, y, cuts, "hadamard", 8)
        assert rows.even == (len({-(-n // factorization.GROUP) for n in sizes}) == 1)
        assert np.allclose(rows.solved(3.0, weights, 8), factorization.Sums.of(x, y, cuts, "hadamard", 8).solved(3.0, weights, 8), rtol=1e-9)


def test_only_hot_ids_are_counted_over_all_ratings(spark):
    """The counts of the other ids are made where their ratings are packed, so ratings meet no join for them."""
    rows = [(u, i, 1.0, i % 4 == 0) for u, n in ((1, 60), (2, 8), (3, 5)) for i in range(n)]
    r = spark.createDataFrame(rows, "user long, item long, rating double, is_test boolean")
    cold, none = factorization.with_hot(r, r.where("not is_test"), "user", 53, 100)
    hot, some = factorization.with_hot(r, r.where("not is_test"), "user", 53, 40)
    assert (none, some) == (False, True) and {(x.user, x.n_user) for x in cold.collect()} == {(1, None), (2, None), (3, None)}
    assert {(x.user, x.n_user) for x in hot.collect()} == {(1, 45), (2, None), (3, None)}
    for given in (cold, hot):
        got = factorization._unpacked(pa.Table.from_batches(factorization.packed(given, "user", "item", 100, F.lit(0), F.lit(0)).toArrow().to_batches()))
        assert {*zip(got["own"].tolist(), got["n"].tolist(), strict=True)} == {(1, 45), (2, 6), (3, 3)}


def test_the_block_of_an_id_is_the_number_of_cuts_up_to_it(spark):
    cuts = [3.0, 4.0, 7.5, 20.0, 21.0]
    for some in ([], cuts[:1], cuts):
        got = spark.range(30).select("id", factorization._block("id", some).alias("block")).collect()
        assert all(r["block"] == sum(c <= r["id"] for c in some) for r in got)
    assert "lambda" not in factorization._block("id", cuts)._jc.toString()  # a list searched by every row took most of packing
