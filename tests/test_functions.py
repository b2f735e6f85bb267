"""Metrics, numerics, families and filters."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from pivotjoin.functions import families as fam
from pivotjoin.functions import filters, numerics
from pivotjoin.functions.metrics import ANGULAR, EDIT, HAMMING, JACCARD, L1, L2, LINF, check_metric, combine, edit_block, edit_near, lp, metric_of, register_metric, register_sql_functions


@pytest.mark.parametrize("m", [L1, L2, LINF, HAMMING, ANGULAR, lp(3)])
def test_columns_equal_blocks(spark, m):
    g = np.random.default_rng(0)
    x = [[float(v) for v in g.integers(1, 5, 6)] for _ in range(12)]
    df = spark.createDataFrame([(i, v) for i, v in enumerate(x)], "id int, v array<double>")
    rows = df.alias("a").crossJoin(df.alias("b")).select("a.id", F.col("b.id").alias("j"), m.distance(F.col("a.v"), F.col("b.v")).alias("d")).collect()
    block = m.block(x, x)
    assert all(math.isclose(r["d"], block[r["id"], r["j"]], abs_tol=1e-7) for r in rows)
    axes = {r["id"]: r["a"] for r in df.select("id", m.to_axes(F.col("v"), x[:3]).alias("a")).collect()}
    assert all(np.allclose(axes[i], block[i, :3]) for i in axes)
    if m.rowwise:
        assert np.allclose(m.rowwise(np.array(x), np.array(x[::-1])), np.diag(m.block(x, x[::-1])))


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text("abcé", max_size=7), min_size=1, max_size=4), st.lists(st.text("abcé", max_size=7), min_size=1, max_size=4))
def test_edit_block(xs, ys):
    def slow(a, b):
        row = list(range(len(b) + 1))
        for i, c in enumerate(a, 1):
            new = [i]
            for j, e in enumerate(b, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != e)))
            row = new
        return row[-1]

    assert (edit_block(xs, ys) == np.array([[slow(a, b) for b in ys] for a in xs])).all()


def test_strings_and_sets(spark):
    df = spark.createDataFrame([("kitten", "sitting", ["a", "b"], ["b", "c"]), ("", "", [], [])], "x string, y string, s array<string>, t array<string>")
    rows = df.select(EDIT.distance(F.col("x"), F.col("y")).alias("e"), EDIT.at_most(F.col("x"), F.col("y"), 2).alias("near"), JACCARD.distance(F.col("s"), F.col("t")).alias("j")).collect()
    assert [tuple(r) for r in rows] == [(3.0, False, 1 - 1 / 3), (0.0, True, 0.0)]
    assert np.allclose(JACCARD.block([["a", "b"], []], [["b", "c"], []]), [[2 / 3, 1], [1, 0]])


def test_axioms_and_refusals(spark):
    df = spark.createDataFrame([([float(i), float(i * i % 5)],) for i in range(12)], "v array<double>")
    assert check_metric("l1", df, "v") == check_metric("l2", df, "v") == []
    from pivotjoin.functions.metrics import Metric

    squared = Metric("sq", "vector", None, lambda x, y: L2.block(x, y) ** 2)
    assert "triangle" in check_metric(squared, df, "v")
    for name in ("squared_l2", "cosine"):
        with pytest.raises(ValueError):
            metric_of(name)
        with pytest.raises(ValueError):
            register_metric(name, L1.block)
    with pytest.raises(ValueError):
        lp(0.5)
    register_metric("twice_l1", lambda x, y: 2 * L1.block(x, y))
    assert metric_of("twice_l1").block([[0.0]], [[3.0]])[0, 0] == 6
    both = combine([("a", L1, 1.0), ("b", EDIT, 0.5)])
    assert both.block([{"a": [0.0], "b": "xy"}], [{"a": [2.0], "b": "x"}])[0, 0] == 2.5


def test_worked_example():
    """Six published distances of four objects; at 30 two pairs are near."""
    d = {(1, 2): 14, (1, 3): 45, (1, 4): 45, (2, 3): 49, (2, 4): 47, (3, 4): 18}
    m = np.zeros((4, 4))
    for (i, j), v in d.items():
        m[i - 1, j - 1] = m[j - 1, i - 1] = v
    assert (m[:, None, :] <= m[:, :, None] + m[None, :, :]).all()
    assert [p for p, v in d.items() if v <= 30] == [(1, 2), (3, 4)]


def test_sql_functions(spark):
    register_sql_functions(spark)
    r = spark.sql("SELECT l1_distance(array(1D, 2D), array(2D, 4D)) a, ed_distance('ab', 'b') b, jaccard_distance(array('a'), array('a')) c").first()
    assert tuple(r) == (3.0, 1.0, 0.0)


# -- numerics ------------------------------------------------------------------------------------
def test_special_functions():
    assert math.isclose(numerics.digamma(1), -0.5772156649015329, abs_tol=1e-12)
    assert math.isclose(numerics.trigamma(1), math.pi**2 / 6, abs_tol=1e-11)
    for x in (0.1, 1.0, 5.0, 30.0):
        assert math.isclose(numerics.chi2_sf(x, 2), math.exp(-x / 2), rel_tol=1e-12)
        assert math.isclose(numerics.chi2_sf(x, 4), math.exp(-x / 2) * (1 + x / 2), rel_tol=1e-12)
    for dof, value in ((1, 3.841459), (5, 11.070498), (10, 18.307038)):  # published critical values at 5 %
        assert math.isclose(numerics.chi2_isf(0.05, dof), value, abs_tol=1e-5)
    assert math.isclose(numerics.beta_p(2, 3, 0.4), 0.5248, abs_tol=1e-10)
    for y in (-5.0, -1.0, 0.3, 4.0):
        assert math.isclose(numerics.digamma(numerics.inverse_digamma(y)), y, abs_tol=1e-10)


CASES = [
    (fam.EXPONENTIAL, {"rate": 0.7}), (fam.GAMMA, {"shape": 2.3, "rate": 0.7}), (fam.CHI_SQUARE, {"dof": 3.4}), (fam.NORMAL, {"mean": 1.5, "var": 0.6}), (fam.LOG_NORMAL, {"mean": 0.2, "var": 0.3}), (fam.BETA, {"a": 2.0, "b": 3.5}), (fam.POISSON, {"mean": 3.2}),
]


@pytest.mark.parametrize(("family", "params"), CASES, ids=[f.name for f, _ in CASES])
def test_families(family, params):
    """The gradient of A is the mean of T; fits recover parameters; densities, distribution functions and quantiles agree."""
    x = family.draw(params, np.random.default_rng(1), 200_000)
    e = family.eta(params)
    mean_t = np.mean([family.statistic(float(v)) for v in x[:50_000]], axis=0)
    h = 1e-5
    slope = [(family.log_partition(e + d) - family.log_partition(e - d)) / (2 * h) for d in np.eye(len(e)) * h]
    assert np.allclose(slope, mean_t, rtol=0.03, atol=0.02)
    pos, low = x[x > 0], x[x < 1]
    stats = {"x": x.mean(), "xx": (x * x).mean(), "log": np.log(pos).mean(), "loglog": (np.log(pos) ** 2).mean(), "log1m": np.log1p(-low).mean(), "min": x.min(), "max": x.max()}
    got = family.fit(stats)
    assert all(math.isclose(got[k], v, rel_tol=0.03) for k, v in params.items())
    if family is not fam.POISSON:
        for q in (0.05, 0.5, 0.93):
            assert math.isclose(family.cdf(params, family.quantile(params, q)), q, abs_tol=1e-9)
        a, b = family.quantile(params, 0.3), family.quantile(params, 0.7)
        grid = np.linspace(a, b, 4001)
        mass = np.trapezoid([math.exp(family.logpdf(params, v)) for v in grid], grid)
        assert math.isclose(mass, 0.4, abs_tol=1e-5)
    numeric = fam.fit_numeric(mean_t, family, e * 0.8)
    assert np.allclose(numeric, e, rtol=0.08, atol=0.05)


def test_supports():
    assert fam.GAMMA.fit({"min": 0.0, "x": 1.0, "log": 0.0}) is None
    assert fam.EXPONENTIAL.fit({"min": -1.0, "x": 1.0}) is None
    assert fam.NORMAL.fit({"x": 2.0, "xx": 4.0, "min": 2.0}) is None
    assert fam.BETA.fit({"min": 0.1, "max": 1.0, "log": -1.0, "log1m": -1.0}) is None


def test_matrix_laws():
    g = np.random.default_rng(4)
    v = np.array([[1.0, 0.3], [0.3, 0.5]])
    x = fam.Wishart(v, 9.0).draw(g, 20_000)
    got = fam.Wishart.fit(x.mean(0), float(np.linalg.slogdet(x)[1].mean()))
    assert math.isclose(got.dof, 9, rel_tol=0.03) and np.allclose(got.v, v, rtol=0.05)
    e1, e2 = fam.Wishart(v, 9.0).eta()
    h = 1e-5
    assert math.isclose((fam.Wishart.log_partition(e1, e2 + h) - fam.Wishart.log_partition(e1, e2 - h)) / (2 * h), float(np.linalg.slogdet(x)[1].mean()), abs_tol=0.02)
    a = fam.Dirichlet(np.array([1.0, 2.0, 4.0]))
    assert np.allclose(fam.Dirichlet.fit(np.log(a.draw(g, 50_000)).mean(0)).alpha, a.alpha, rtol=0.03)
    m = fam.MultiNormal(np.array([1.0, -1.0]), v)
    y = m.draw(g, 50_000)
    fitted = fam.MultiNormal.fit(y.mean(0), (y.T @ y) / len(y))
    assert np.allclose(fitted.cov, v, atol=0.02) and math.isclose(m.radius2(y).mean(), 2, rel_tol=0.02)
    assert fam.MultiNormal(np.zeros(20), np.eye(20)).w == 230


@pytest.mark.parametrize("how", ["newton", "gradient"])
def test_numeric_fit_ends_at_the_mean(how):
    """Statistics of a group of events (sf0.001) whose likelihood is a narrow ridge: the fitted law expects them."""
    mean, mean_log = 3294.43, 8.099749
    e = fam.fit_numeric([mean_log - math.log(1000), mean / 1000], fam.GAMMA, [0.5, -1.0], how)
    shape, rate = float(e[0] + 1), float(-e[1] / 1000)
    assert abs(shape / rate - mean) < 1e-3 and abs(numerics.digamma(shape) - math.log(rate) - mean_log) < 1e-6
    assert math.isclose(fam.fit_numeric([1e5], fam.EXPONENTIAL, [-2e-5], how)[0], -1e-5, rel_tol=0.01)  # near the end of the domain


# -- filters -------------------------------------------------------------------------------------
def test_filters_lose_nothing(spark):
    g = np.random.default_rng(6)
    strings = [(i, "".join(g.choice(list("ab"), g.integers(0, 9)))) for i in range(60)]
    df = spark.createDataFrame(strings, "id long, obj string")
    d = edit_block([s for _, s in strings], [s for _, s in strings])
    for delta in (0, 1, 2):
        near = {(i, j) for i in range(60) for j in range(i + 1, 60) if d[i, j] <= delta}
        for f in (filters.length_candidates, filters.segment_candidates):
            assert near <= {tuple(r) for r in f(df, delta).collect()}
    sets = [(i, sorted({str(v) for v in g.integers(0, 12, g.integers(1, 9))})) for i in range(60)]
    df = spark.createDataFrame(sets, "id long, obj array<string>")
    d = JACCARD.block([s for _, s in sets], [s for _, s in sets])
    for delta in (0.0, 0.25, 0.6):
        near = {(i, j) for i in range(60) for j in range(i + 1, 60) if d[i, j] <= delta + 1e-12}
        for positions in (False, True):
            assert near <= {tuple(r) for r in filters.prefix_candidates(df, delta, positions).collect()}


def test_edit_near():
    """All pairs within delta with their distances, of strings with and without common beginnings; none twice."""
    rng = np.random.default_rng(4)
    make = lambda n, most: ["".join(rng.choice(list("ab\u00e9\U0001f600"), rng.integers(0, most))) for _ in range(n)]
    xs, ys = make(60, 40) + ["", "ab", "ab"], make(50, 45) + ["", "ab" * 20]
    d = edit_block(xs, ys)
    for delta in (0, 1, 4, 8, 17, 31):
        i, j, found = edit_near(xs, ys, delta)
        assert sorted(zip(i.tolist(), j.tolist(), found.tolist(), strict=True)) == [(a, b, d[a, b]) for a, b in np.argwhere(d <= delta).tolist()]
    assert edit_near(xs, ys, 32) is None and not len(edit_near(xs, [], 4)[0])


def test_counted_segments_of_cells(monkeypatch):
    """Pairs of a cell that hold enough of each other's segments, whatever parts its blocks are met in."""
    import pyarrow as pa

    def held(x: str, y: str, segments: int, delta: int) -> int:
        bounds = [(i * len(x) // segments, (i + 1) * len(x) // segments) for i in range(segments)]
        return sum(any(y[p : p + b - a] == x[a:b] for p in range(max(a - delta, 0), min(a + delta, len(y) - b + a) + 1)) for a, b in bounds)

    monkeypatch.setattr(filters, "MET_STRINGS", 7)
    g = np.random.default_rng(5)
    for n, m, delta, segments, least, letters in ((9, 11, 2, 3, 1, "ab\0"), (9, 9, 2, 9, 7, "ab"), (3, 4, 4, 5, 1, "a\U0001f600"), (16, 17, 1, 6, 5, "abé"), (0, 2, 2, 3, 1, "ab")):
        xs, ys = (["".join(letters[c] for c in g.integers(0, len(letters), k)) for _ in range(40)] for k in (n, m))
        for once in {False, n == m}:
            rows = [(s, False) for s in xs] + ([] if once else [(s, True) for s in ys])
            t = pa.table({"n": [n] * len(rows), "a": [0] * len(rows), "m": [m] * len(rows), "b": [0 if once else 1] * len(rows), "right": [r for _, r in rows], "obj": [s for s, _ in rows]})
            for both, every in ((True, all), (False, any)):
                got = [(i[p], j[q]) for i, j, ok in filters._met(t, delta, segments, least, both) for p, q in np.argwhere(ok)]
                pairs = [(p, q) for p in range(40) for q in (range(40) if once else range(40, 80)) if p != q]
                want = {(p, q) for p, q in pairs if every(held(rows[a][0], rows[b][0], segments, delta) >= least for a, b in ((p, q), (q, p)))}
                assert {tuple(sorted(p)) for p in want} == {tuple(sorted(p)) for p in got} and len(got) == len(set(map(frozenset, got)))


def moved(spark, f) -> int:
    """Rows that are shuffled while f runs."""
    sc = spark.sparkContext._jsc.sc()

    def written() -> int:
        sc.listenerBus().waitUntilEmpty()
        stages = sc.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
        return sum(stages.apply(i).shuffleWriteRecords() for i in range(stages.size()))

    before = written()
    f()
    return written() - before


def test_segment_candidates_are_not_shuffled(spark, monkeypatch):
    """A segment that all strings have makes all pairs candidates; they are given out where they are found."""
    monkeypatch.setattr(filters, "BLOCK_STRINGS", 200)
    strings = [(i, f"https://{i * 7919 % 900 + 100}{'x' * (i % 3)}") for i in range(700)]
    df = spark.createDataFrame(strings, "id long, obj string")
    got = []
    assert moved(spark, lambda: got.extend(tuple(r) for r in filters.segment_candidates(df, 4).collect())) < 20_000
    assert sorted(got) == [(i, j) for i in range(700) for j in range(i + 1, 700)]  # 244,650


def test_segment_candidates_of_odd_rows(spark):
    """Null strings and ids have no candidates, a row is none of its own, and pairs of repeated ids are given once."""
    rows = [(1, "abcdef"), (2, None), (None, "abcdef"), (3, "abcdeg"), (3, "abcdeh"), (4, ""), (5, "a"), (5, "abcdef"), (6, "z" * 9)]
    df = spark.createDataFrame(rows, "id long, obj string")
    assert sorted(tuple(r) for r in filters.segment_candidates(df, 1).collect()) == [(1, 3), (1, 5), (3, 5), (4, 5)]
    named = spark.createDataFrame([("b", "abc"), ("a", "abd")], "name string, text string")
    assert [tuple(r) for r in filters.segment_candidates(named, 1, "name", "text").collect()] == [("a", "b")]
    assert filters.segment_candidates(df.limit(0), 1).count() == 0
