"""Algebra of the codes, and what erasures leave of them."""

import numpy as np
import pytest

from erasureml.functions.transforms import fwht, haar
from erasureml.functions.uniform import uniform, uniform_np, uniform_sql
from erasureml.operators import codes, spectrum

TIGHT = [codes.hadamard(20, 2, 3), codes.hadamard(20, 2, 3, True), codes.hadamard_etf(2), codes.hadamard_etf(3), codes.paley(13), codes.paley(29), codes.steiner(4), codes.steiner(8), codes.steiner(16), codes.steiner_triples(3), codes.steiner_triples(4), codes.haar(24, 2, 1), codes.dft(24, 2, 1), codes.replication(12, 3), codes.identity(9), codes.columns_of(codes.paley(29), 9)]


@pytest.mark.parametrize("code", TIGHT, ids=lambda c: f"{c.name}-{c.n}")
def test_tight_and_fast_equals_matrix(code):
    s = code.matrix()
    assert np.allclose(s.T @ s, np.eye(code.n))
    x = np.random.default_rng(0).normal(size=(code.n, 3))
    assert np.allclose(code.apply(x), s @ x) and np.isclose((code.apply(x) ** 2).sum(), (x**2).sum())
    assert np.isclose(code.entry(1, 2), s[1, 2]) and np.allclose(code.apply_t(s @ x), x)
    # erasing rows leaves at least this many eigenvalues at one
    for m, k in ((4, 3), (8, 7)):
        worker = codes.assign(code, m)
        for i in range(m):
            eig = np.linalg.eigvalsh(spectrum.left_over(code, worker, tuple(j for j in range(m) if j != i)[:k]))
            lost = int((worker == i).sum()) if k == m - 1 else 0
            assert (abs(eig - 1) < 1e-9).sum() >= code.n - lost


@pytest.mark.parametrize("code", [codes.hadamard_etf(2), codes.hadamard_etf(3), codes.hadamard_etf(2, "even"), codes.paley(13), codes.paley(29), codes.steiner(4), codes.steiner(8), codes.steiner_triples(3), codes.steiner_triples(4)], ids=lambda c: f"{c.name}-{c.n}")
def test_equiangular_frames_meet_the_bound(code):
    assert spectrum.is_etf(code)
    assert np.allclose(spectrum.frame_bounds(code), code.beta)


def test_bulk_bound_and_gaussian_edges():
    code = codes.steiner(16)
    worker = codes.assign(code, 8)
    eig = np.linalg.eigvalsh(spectrum.left_over(code, worker, tuple(range(6))))
    assert (abs(eig - 1) < 1e-9).sum() >= spectrum.bulk_ones(code, 8, 6) == 56
    g = codes.gaussian(256, 2, 1)
    low, high = spectrum.gaussian_edges(2, 0.75)
    e = np.linalg.eigvalsh(spectrum.left_over(g, codes.assign(g, 16), tuple(range(12)))) / 0.75
    assert low - 0.1 < e[0] and e[-1] < high + 0.3


def test_scatter_beats_whole_blocks_and_haar_fails_the_worst_case():
    code = codes.steiner(16)
    contiguous, scattered = (spectrum.epsilon(code, 8, 7, how=h, subsets="all") for h in ("contiguous", "scatter"))
    assert contiguous > 1 - 1e-9 > scattered
    assert spectrum.epsilon(codes.haar(28, 2, 1), 8, 7, subsets="all") > 1 - 1e-9


def test_support_bounds():
    assert (spectrum.support_overhead(codes.steiner(16), 8)["ratio"] <= 2 + 1e-9).all()
    haar_code = codes.haar(128, 2, 1)
    assert (spectrum.support_overhead(haar_code, 8)["rows"] <= haar_code.beta * 128 * np.log2(128) / 8).all()


def test_assignments_are_even():
    code = codes.steiner(8)
    for how in ("contiguous", "round_robin", "scatter", "half_block"):
        assert np.ptp(np.bincount(codes.assign(code, 8, how), minlength=8)) <= 1
    with pytest.raises(ValueError):
        codes.assign(code, 8, "other")


def test_bank_cuts_columns():
    bank = codes.CodeBank("paley", 20, 200)
    code = bank.get(33, 5)
    assert bank.bucket(33) == 40 and code.n == 33 and np.allclose(code.matrix().T @ code.matrix(), np.eye(33))
    with pytest.raises(ValueError):
        bank.get(201)


def test_transforms_are_orthogonal():
    x = np.random.default_rng(1).normal(size=(32, 2))
    assert np.allclose(fwht(fwht(x)), 32 * x) and np.isclose((haar(x) ** 2).sum(), (x**2).sum())
    with pytest.raises(ValueError):
        fwht(x[:31])


def test_uniforms_agree(spark):
    import duckdb

    rows = spark.range(200).select("id", uniform("id", "id", 9).alias("u")).collect()
    sql = dict(duckdb.sql(f"SELECT range, {uniform_sql('range', 'range', 9)} FROM range(200)").fetchall())
    for r in rows:
        assert r.u == uniform_np(r.id, r.id, 9) == sql[r.id]
    u = uniform_np(np.arange(40000)[:, None] % 200, np.arange(40000)[:, None] // 200, 4)
    assert abs(u.mean() - 0.5) < 0.01 and abs(np.histogram(u, 20)[0] / 2000 - 1).max() < 0.12


def test_coordinates_made_in_tasks(spark):
    code = codes.steiner(4)
    got = np.zeros((code.N, code.n))
    for r in code.to_df(spark, 4).collect():
        got[r.enc_row, r.src_row] = r.coef
    assert np.allclose(got, code.matrix())


def test_both_encodings_agree_in_every_group(spark):
    """Three groups of 28, the last of four rows; encoding by join gave the first group only."""
    from erasureml.operators import encode

    rng, code = np.random.default_rng(0), codes.hadamard_etf(3)
    n = 2 * code.n + 4
    x = rng.normal(size=(n, 3))
    df = spark.createDataFrame([(i, x[i, :2].tolist(), float(x[i, 2])) for i in range(n)], "row_id long, x array<double>, y double")
    got = []
    for mode in ("join", "grouped"):
        rows = sorted(encode.encode_rows(df, code, 8, mode=mode).collect(), key=lambda r: r.enc_row)
        assert [r.enc_row for r in rows] == list(range(3 * code.N))
        got.append(np.array([[r.worker, *r.x, r.y] for r in rows]))
    assert np.allclose(got[0], got[1])
