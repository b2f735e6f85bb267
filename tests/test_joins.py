"""Joins, their stages, measures and competitors against the definition."""

import itertools
import math
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from pivotjoin import queries, surrounding, workloads
from pivotjoin.functions.metrics import JACCARD, L1, L2, edit_block, metric_of
from pivotjoin.operators import baselines, fits, sampling, split
from pivotjoin.operators.join import bad_rows, brute_force_join, join_classes, make_plan, mapped, metric_join, metric_self_join, refined, route, validate_objects, verify
from pivotjoin.operators.tables import connected_components
from pivotjoin.plans import measures
from pivotjoin.plans.config import JoinConfig
from pivotjoin.sources import io

SMALL = {"k": 60, "p": 7, "n": 3}


def near(objs, metric, delta):
    d = metric.block([o for _, o in objs], [o for _, o in objs])
    return {(min(a, b), max(a, b)) for (i, (a, _)), (j, (b, _)) in itertools.combinations(enumerate(objs), 2) if d[i, j] <= delta + 1e-9}


def pairs(df):
    rows = [(r["id_x"], r["id_y"]) for r in df.collect()]
    assert len(rows) == len(set(rows)), "a pair was found twice"
    return set(rows)


@pytest.fixture(scope="module")
def points(spark):
    """Integer points: distances hit the threshold exactly, and coordinates have many ties."""
    g = np.random.default_rng(8)
    objs = [(int(i), [float(v) for v in g.integers(0, 6, 3)]) for i in g.permutation(200)]
    return objs, spark.createDataFrame(objs, "id long, obj array<double>").cache()


GRID = [{"sampler": s, "splitter": t} for s in ("random", "distribution_aware", "generative") for t in ("iterative", "learned")] + [
    {"sampler": "stratified"}, {"sampler": "local"}, {"splitter": "widest"}, {"bounds": "cell"}, {"replication": "both"}, {"engine": "sql"}, {"max_region": 15}, {"collapse": True}, {"space": "target"}, {"snap": True}, {"model": "mvn_full"},
    {"model": "mvn_diag", "node_by": "range"}, {"p": 1}, {"p": 150}, {"k": 3}, {"n": 1}, {"seed": 99}, {"oversample": 3, "sampler": "random"},
]


@pytest.mark.parametrize("config", GRID, ids=str)
def test_every_configuration_is_exact(points, config):
    objs, df = points
    assert pairs(metric_self_join(df, "id", "obj", "l1", 2.0, JoinConfig(**{**SMALL, **config}))) == near(objs, L1, 2.0)


@pytest.mark.parametrize("delta", [-1.0, 0.0, 1.0, 100.0])
def test_thresholds(points, delta):
    objs, df = points
    assert pairs(metric_self_join(df, "id", "obj", "l2", delta, JoinConfig(**SMALL))) == (near(objs, L2, delta) if delta >= 0 else set())


def test_edge_tables(spark):
    schema = "id long, obj array<double>"
    cfg = JoinConfig(**SMALL)
    assert metric_self_join(spark.createDataFrame([], schema), "id", "obj", "l1", 1.0, cfg).count() == 0
    assert metric_self_join(spark.createDataFrame([(1, [0.0])], schema), "id", "obj", "l1", 1.0, cfg).count() == 0
    same = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(40)], schema)
    assert metric_self_join(same, "id", "obj", "l1", 0.0, cfg).count() == 40 * 39 // 2
    reps, members = join_classes(same, "id", "obj", "l1", 0.0, cfg)
    assert reps.count() == 0 and members.select("rep").distinct().count() == 1
    bad = spark.createDataFrame([(1, [0.0]), (2, None), (3, [float("nan")]), (None, [0.0]), (4, [0.5]), (5, [None])], schema)
    assert pairs(metric_self_join(bad, "id", "obj", "l1", 1.0, cfg)) == {(1, 4)}
    assert bad_rows(bad, "id", "obj", "l1") == {"unusable": 4, "repeated_ids": 0}
    with pytest.raises(ValueError):
        validate_objects(bad, "id", "obj", metric_of("l1"), "error")


def test_strings_sets_and_numbers(spark):
    g = np.random.default_rng(9)
    strings = [(i, "".join(g.choice(list("abc"), g.integers(0, 7)))) for i in range(120)]
    df = spark.createDataFrame(strings, "id long, obj string")
    d = edit_block([s for _, s in strings], [s for _, s in strings])
    for config in ({}, {"engine": "block"}, {"sampler": "random"}):
        assert pairs(metric_self_join(df, "id", "obj", "edit", 1, JoinConfig(**SMALL, **config))) == {(i, j) for i in range(120) for j in range(i + 1, 120) if d[i, j] <= 1}
    sets = [(i, [str(v) for v in set(g.integers(0, 9, g.integers(0, 7)).tolist())]) for i in range(120)]
    df = spark.createDataFrame(sets, "id long, obj array<string>")
    for delta, config in itertools.product((0.0, 0.4, 1.0), ({}, {"filters": False})):
        assert pairs(metric_self_join(df, "id", "obj", "jaccard", delta, JoinConfig(**SMALL, **config))) == near(sets, JACCARD, delta)
    left, right = df.where("id < 60"), df.where("id >= 60")
    want = {(i, j) for i, j in near(sets, JACCARD, 0.4) if i < 60 <= j}
    assert pairs(metric_join(left, right, ("id", "id"), ("obj", "obj"), "jaccard", 0.4, JoinConfig(**SMALL))) == want
    numbers = spark.createDataFrame([(i, float(i % 13)) for i in range(50)], "id long, obj double")
    assert pairs(metric_self_join(numbers, "id", "obj", "abs1", 1.0, JoinConfig(**SMALL))) == {(i, j) for i in range(50) for j in range(i + 1, 50) if abs(i % 13 - j % 13) <= 1}


@pytest.mark.parametrize("config", [{}, {"engine": "sql"}, {"bounds": "cell"}, {"max_region": 9}], ids=str)
def test_join_of_two_tables(points, config):
    objs, df = points
    a, b = [o for o in objs if o[0] % 3], [o for o in objs if not o[0] % 3]
    d = L1.block([o for _, o in a], [o for _, o in b])
    want = {(a[i][0], b[j][0]) for i, j in zip(*np.nonzero(d <= 2), strict=True)}
    assert pairs(metric_join(df.where("id % 3 <> 0"), df.where("id % 3 = 0"), ("id", "id"), ("obj", "obj"), "l1", 2.0, JoinConfig(**SMALL, **config))) == want


@pytest.mark.parametrize("join", [baselines.multi_round_join, baselines.repartition_join, baselines.nearest_pivot_join, baselines.kd_split_join, baselines.oversampled_join, brute_force_join])
def test_competitors(points, join):
    objs, df = points
    extra = {"max_part": 30} if join is baselines.multi_round_join else {"p": 5, "heavy": 30, "parts": 3} if join is baselines.repartition_join else {}
    assert pairs(join(df, "id", "obj", "l1", 2.0, **extra)) == near(objs, L1, 2.0)


def test_string_and_set_competitors(spark):
    g = np.random.default_rng(10)
    strings = [(i, "".join(g.choice(list("ab"), g.integers(0, 7)))) for i in range(80)]
    d = edit_block([s for _, s in strings], [s for _, s in strings])
    df = spark.createDataFrame(strings, "id long, obj string")
    assert pairs(baselines.segment_signature_join(df, "id", "obj", "edit", 2)) == {(i, j) for i in range(80) for j in range(i + 1, 80) if d[i, j] <= 2}
    sets = [(i, [str(v) for v in set(g.integers(0, 9, g.integers(0, 7)).tolist())]) for i in range(80)]
    df = spark.createDataFrame(sets, "id long, obj array<string>")
    for f in (lambda: baselines.segment_signature_join(df, "id", "obj", "jaccard", 0.4), lambda: baselines.fragment_set_join(df, "id", "obj", 0.4, 3)):
        assert pairs(f()) == near(sets, JACCARD, 0.4)


# -- stages --------------------------------------------------------------------------------------
def test_routing_properties(points):
    objs, df = points
    for replication in ("lower", "both"):
        plan = make_plan(df, L1, 2.0, JoinConfig(**SMALL, replication=replication, bounds="cell"))
        rows = route(df, plan).collect()
        kernel = [(r["id"], r["region"]) for r in rows if r["home"] == r["region"]]
        assert sorted(i for i, _ in kernel) == sorted(i for i, _ in objs)
        assert len({(r["id"], r["region"]) for r in rows}) == len(rows)
        if replication == "lower":
            assert all(r["region"] <= r["home"] for r in rows)
    x = {r["id"]: r["coord"] for r in mapped(df, plan).collect()}
    d = {i: o for i, o in objs}
    for a, b in itertools.combinations(list(d)[:40], 2):
        assert np.abs(np.subtract(x[a], x[b])).max() <= L1.block([d[a]], [d[b]])[0, 0] + 1e-9
    lo, hi = plan.tree.bounds()
    probes = np.random.default_rng(1).uniform(-5, 25, (500, plan.tree.width))
    inside = ((probes[:, None, :] >= lo) & (probes[:, None, :] < hi)).all(axis=2)
    assert (inside.sum(axis=1) == 1).all() and (inside.argmax(axis=1) == plan.tree.home(probes)).all()
    row, region = plan.tree.near(probes, 1.5)
    want = ((probes[:, None, :] + 1.5 >= lo - 1e-6) & (probes[:, None, :] - 1.5 < hi + 1e-6)).all(axis=2)
    assert {(a, b) for a, b in zip(row.tolist(), region.tolist(), strict=True)} == set(zip(*(v.tolist() for v in np.nonzero(want)), strict=True))


def test_second_level_is_exact(points):
    objs, df = points
    plan = make_plan(df, L1, 2.0, JoinConfig(k=60, p=2, n=3))
    deep = refined(df, plan, 40)
    assert deep.tree.regions > plan.tree.regions
    assert pairs(verify(route(df, deep), deep)) == near(objs, L1, 2.0)


def test_published_boxes_lose_pairs(points):
    objs, df = points
    got = pairs(metric_self_join(df, "id", "obj", "l1", 2.0, JoinConfig(**{**SMALL, "k": 12}, sampler="random", bounds="pivot_box")))
    assert got < near(objs, L1, 2.0)


def test_splits():
    g = np.random.default_rng(2)
    x = g.normal(size=(700, 4))
    for p in (1, 2, 7, 16):
        t = split.grow(x, p)
        assert t.regions == p
        counts = np.bincount(t.home(x), minlength=p)
        assert counts.max() - counts.min() <= p  # about even, by shares of 4:3 and so on
    assert split.grow(np.ones((50, 3)), 8).regions == 1
    assert split.grow(np.array([[0.0], [0.0], [0.0], [1.0]]), 4).regions == 2
    labels = (x[:, 2] > np.median(x[:, 2])).astype(int)
    assert split.grow(x, 2, "learned", labels).axis[0] == 2
    assert split.grow(x, 2, "learned", labels, measure="gain").axis[0] == 2


def test_entropy_by_hand():
    y, below = np.array([0, 0, 1, 1]), np.array([True, True, False, False])
    assert math.isclose(split.entropy(y), math.log(2))
    assert math.isclose(split.split_gain(y, below), math.log(2)) and math.isclose(split.gain_ratio(y, below), 1)
    assert split.gain_ratio(y, np.zeros(4, bool)) == 0


def test_linkage():
    x = np.array([[0.0], [0.1], [0.2], [5.0], [5.1], [9.0]])
    for how in ("average", "single", "complete"):
        a = split.linkage_labels(L1.block(x, x), 3, how)
        assert len(set(a)) == 3 and len(set(a[:3])) == 1 and a[3] == a[4] != a[5]
    assert len(set(split.cluster_labels(list(x), L1))) == 3
    tree = split.grow(x, 2)
    assert 0 <= split.compactness(tree, x, a) <= math.log(3)
    assert len(split.choose_axes(list(x), 3, L1, "farthest")) == 3


def test_components(spark):
    e = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (3, 10)], "id_x long, id_y long")
    assert {tuple(r) for r in connected_components(e).collect()} == {(1, 1), (2, 1), (3, 1), (10, 1), (8, 8), (9, 8)}


# -- fits and sampling ------------------------------------------------------------------------------
@pytest.fixture(scope="module")
def strata(spark):
    g = np.random.default_rng(3)
    rows = [(i, [float(g.exponential(2.0)), float(g.normal(3, 1))], 0) for i in range(2000)] + [(i, [float(g.normal(0, 1)), float(g.uniform())], 1) for i in range(2000, 2600)]
    return spark.createDataFrame(rows, "id long, obj array<double>, node int").cache()


def test_fits(strata):
    found = fits.fit_nodes(strata, families=("normal", "exponential", "gamma"))
    assert [f.n for f in found] == [2000, 600]
    assert found[0].dims[0].family in ("exponential", "gamma") and found[0].dims[1].family == "normal"
    assert found[0].confidence > 0.001 > found[1].dims[1].confidence  # a uniform column is no normal one
    assert all(0 <= f.confidence <= 1 for f in found)
    joint = fits.fit_nodes(strata, model="mvn_full")
    assert joint[0].confidence < 1e-3  # an exponential column


def test_confidence_under_a_true_model(spark):
    g = np.random.default_rng(5)
    rows = [(i, [float(g.normal())], i % 40) for i in range(20_000)]
    df = spark.createDataFrame(rows, "id long, obj array<double>, node int")
    lower = [f.confidence for f in fits.fit_nodes(df, families=("normal",))]
    upper = [f.confidence for f in fits.fit_nodes(df, families=("normal",), dof="upper")]
    assert np.mean(lower) < 0.62 and np.mean(upper) > 0.38 and all(a <= b for a, b in zip(lower, upper, strict=True))
    assert fits.confidence(50.0, 5, "as_printed") > 0.99 > fits.confidence(50.0, 5)


def test_global_confidence():
    k = fits.chi2_isf(0.2, 2)
    assert math.isclose(fits.global_confidence([(k, 2), (k, 2)], "pooled"), 0.1688, abs_tol=1e-4)
    g = np.random.default_rng(0)
    for _ in range(20):
        c, d = g.uniform(0.05, 0.95, 3), g.integers(1, 9, 3)
        stats = [(fits.chi2_isf(float(a), int(b)), int(b)) for a, b in zip(c, d, strict=True)]
        assert c.min() - 1e-6 <= fits.global_confidence(stats) <= c.max() + 1e-6


def test_allocation():
    f = [fits.NodeFit(i, n, confidence=c) for i, (n, c) in enumerate([(100, 0.2), (100, 0.9), (5, 0.001)])]
    q = sampling.allocate(f, 60)
    assert sum(q.values()) == 60 and q[0] > q[1] and q[2] <= 5
    assert sampling.shares([1, 1, 1], 2) == [1, 1, 0]
    assert sum(sampling.shares([1.0, 2.0], 50, [10, 10])) == 20


def test_distribution_aware(strata):
    found = fits.fit_nodes(strata)
    got = sampling.distribution_aware_pivots(strata, found, 300).collect()
    quota = sampling.allocate(found, 300)
    assert len(got) == 300 and len({r["id"] for r in got}) == 300
    real = {r["id"]: r["obj"] for r in strata.collect()}
    assert all(real[r["id"]] == r["obj"] for r in got)
    assert {n: sum(r["node"] == n for r in got) for n in quota} == quota


def test_chain_and_mixture_have_one_law(spark):
    f = [fits.NodeFit(i, n, [fits.DimFit("normal", {"mean": float(i), "var": 1.0})], confidence=c) for i, (n, c) in enumerate([(100, 0.2), (300, 0.5), (600, 0.9)])]
    _, nodes, proposals = sampling.gibbs_chain(f, 20_000, 3)
    assert np.allclose(np.bincount(nodes) / len(nodes), [0.1, 0.3, 0.6], atol=0.015)
    assert math.isclose(proposals / 20_000, sum(a / b for a, b in [(100, 0.2), (300, 0.5), (600, 0.9)]) / 1000, rel_tol=0.03)
    draws = sampling.mixture_draws(spark, f, 6000, 3).collect()
    assert np.allclose(np.bincount([r["node"] for r in draws]) / 6000, [0.1, 0.3, 0.6], atol=0.02)
    again = sampling.mixture_draws(spark, f, 6000, 3).repartition(3).collect()
    assert {r["pivot_id"]: r["obj"] for r in draws} == {r["pivot_id"]: r["obj"] for r in again}
    x = np.array([r["obj"] for r in draws])
    assert sampling.sampling_error(x, f) <= sampling.error_bound(6000, 1, 0.001)


def test_bounds():
    for m, eps in ((10, 0.0306), (20, 0.0323), (64, 0.0350), (128, 0.0365)):
        assert math.isclose(sampling.error_bound(3200, m), eps, abs_tol=5e-5)
        assert sampling.sample_size(sampling.error_bound(3200, m), m) in (3200, 3201)
    assert sampling.exceed_prob(3200, 20, 0.03, "product") <= sampling.exceed_prob(3200, 20, 0.03)
    assert sampling.error_bound_local([100, 400], 5) == sampling.error_bound(100, 5)
    assert sampling.sampling_traffic(3200, 15) == {"distribution_aware": 44_800, "generative": 210, "generative_through_driver": 30}


# -- measures --------------------------------------------------------------------------------------
def test_measures(points):
    objs, df = points
    plan = make_plan(df, L1, 2.0, JoinConfig(**SMALL, replication="both", bounds="cell"))
    routed = route(df, plan).cache()
    truth = brute_force_join(df, "id", "obj", "l1", 2.0)
    c = measures.costs(routed).first()
    sizes = measures.region_sizes(routed).collect()
    assert c["inner_cost"] + c["outer_cost"] == sum(r["v"] * r["w"] for r in sizes) and c["all_pairs"] == sum(r["w"] ** 2 for r in sizes)
    assert c["inner_cost"] >= 200 * 200 / len(sizes) and measures.evenness(routed).first()["ratio"] >= 1
    assert measures.uncovered_pairs(routed, truth).count() == 0
    assert measures.colocation_count(routed).count() >= truth.count()
    q = measures.result_quality(metric_self_join(df, "id", "obj", "l1", 2.0, JoinConfig(**SMALL)), truth).first()
    assert (q["recall"], q["precision"], q["repeats"]) == (1.0, 1.0, 0)
    assert measures.partition_stats(routed).first()["regions"] == len(sizes)
    lower = make_plan(df, L1, 2.0, JoinConfig(**SMALL, bounds="cell"))
    assert measures.costs(route(df, lower)).first()["verifications"] <= 200 * 199 / 2
    report = measures.join_report(df, lower)
    assert report["pairs"] == truth.count() and report["copies"] >= 1


def test_motivating_numbers(spark):
    def most(parts):
        rows = [(h, h, i) for h, n in enumerate(parts) for i in range(n)]
        return measures.region_costs(spark.createDataFrame(rows, "region int, home int, id int")).agg(F.max("verifications")).first()[0]

    assert most([88, 6, 93, 13]) == 4278 and most([47, 51, 48, 54]) == 1431


def test_plan_cost(points):
    _, df = points
    plan, seen = measures.plan_cost(df, L1, 1.0, JoinConfig(**SMALL))
    assert plan is not None and len(seen) == 3
    none, _ = measures.plan_cost(df, L1, 1000.0, JoinConfig(**SMALL))
    assert none is None  # everything is near everything: compare unpartitioned


def test_least_cover():
    d = np.array([[1, 1, 0, 0], [1, 1, 0, 0], [0, 0, 1, 1], [0, 0, 1, 1]], bool)
    assert measures.optimal_cover_cost(d, 2) == 8 and measures.optimal_cover_cost(d, 1) == 16


# -- sources, sinks, table functions ---------------------------------------------------------------
def test_sources(spark, points, tmp_path):
    objs, df = points
    plan = make_plan(df, L1, 2.0, JoinConfig(**SMALL))
    routed = route(df, plan)
    io.save_routed(routed, str(tmp_path / "r"))
    back = spark.read.parquet(str(tmp_path / "r"))
    assert pairs(verify(back, plan)) == near(objs, L1, 2.0)
    io.save_model(spark, plan, str(tmp_path / "m"))
    again = io.load_model(spark, str(tmp_path / "m"))
    assert pairs(verify(route(df, again), again)) == near(objs, L1, 2.0)
    io.save_pairs(verify(routed, plan), str(tmp_path / "p"))
    assert spark.read.parquet(str(tmp_path / "p")).count() == len(near(objs, L1, 2.0))
    df.select("id").write.csv(str(tmp_path / "c"))
    assert io.load_format(spark, str(tmp_path / "c"), "csv", "id long").count() == 200
    assert io.tree_rows(spark, plan).count() == len(plan.tree.axis)
    io.register_region_probe(spark, plan)
    x = mapped(df, plan).limit(1).first()
    rows = spark.sql(f"SELECT * FROM region_probe(array({', '.join(f'{v}D' for v in x['coord'])}))").collect()
    assert [r["region"] for r in rows if r["home"]] == [x["home"]]


def test_workload_inputs(spark, sf_dir):
    a = workloads.activity(spark, sf_dir).collect()
    assert all(len(r["obj"]) == 20 for r in a)
    assert sum(sum(r["obj"]) for r in a) == io.load(spark, sf_dir, "events").count()
    x = workloads.line_items(spark, sf_dir)
    assert x.count() == x.select("id").distinct().count()


assert surrounding.TABLES  # its queries are in the catalogue


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_catalogue(spark, sf_dir, name, oracle):
    oracle(name, queries.QUERIES[name], queries.ORACLES[name])


@pytest.fixture(scope="module")
def oracle(spark, sf_dir):
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")

    def plain(v):
        if isinstance(v, list | tuple | np.ndarray):
            return str([plain(x) for x in v])
        if v is None or (isinstance(v, float) and math.isnan(v)):
            return "null"
        return f"{v:.6f}".replace("-0.000000", "0.000000") if isinstance(v, float | np.floating) else str(v)

    def check(name, f, sql):
        got, want = f(spark, sf_dir).toPandas(), con.execute(sql).df()
        c = sorted(want.columns)
        assert sorted(got.columns) == c
        a, b = (sorted(tuple(plain(v) for v in r) for r in d[c].itertuples(index=False)) for d in (got, want))
        assert a == b

    return check




def test_label_measures_count_the_whole_table(spark, tmp_path):
    n = 5000  # rows of the lowest ids, all alike; the rest differ
    rows = spark.range(2 * n).selectExpr("id AS vec_id", f"CASE WHEN id < {n} THEN 'a' ELSE 'b' END AS label", f"array(CASE WHEN id < {n} THEN -1.0f ELSE 1.0f END) AS embedding")
    rows.write.parquet(f"{tmp_path}/embeddings.parquet")
    got = [queries.QUERIES[q](spark, str(tmp_path)).first()[0] for q in ("label_entropy", "split_gain", "gain_ratio")]
    assert got == [round(math.log(2), 6), round(math.log(2), 6), 1.0]


def test_registered_fits_count_all_rows(spark, sf_dir, monkeypatch):
    x = queries._event_values(spark, sf_dir)
    many = x.crossJoin(spark.range(60).select()).withColumn("id", F.monotonically_increasing_id())
    monkeypatch.setattr(queries, "_event_values", lambda spark, sf_dir: many)
    seen, whole = [], fits.cell_counts
    monkeypatch.setattr(fits, "cell_counts", lambda df, cuts, obj: (seen.append(df.count()), whole(df, cuts, obj))[1])
    found = queries._value_fits(spark, sf_dir)
    assert max(f.n for f in found) > 10_000 and seen == [sum(f.n for f in found)]


def test_components_by_rounds_and_in_one_task(spark):
    import random

    g = random.Random(1)
    links = [(g.randrange(300), g.randrange(300)) for _ in range(200)] + [(1000 + i, 1000 + i // 2) for i in range(1, 200)] + [(5000, i) for i in range(5001, 5100)]
    e = spark.createDataFrame(links, "id_x long, id_y long")
    found = {tuple(r) for r in connected_components(e).collect()}
    assert found == {tuple(r) for r in connected_components(e, local_links=0, most_links=len(links)).collect()}
    assert {c for i, c in found if 1000 <= i < 1200} == {1000} and {c for i, c in found if i >= 5000} == {5000}


def test_hot_region_is_dealt_into_blocks(spark):
    """Most strings and numbers in one place: no task gets the region, and every pair is found once."""
    import numpy as np

    from pivotjoin.operators import join as j

    g = np.random.default_rng(3)
    words = ["abcdefgh"[: g.integers(4, 9)] + "xyz"[g.integers(0, 3)] * int(g.integers(0, 3)) for _ in range(150)]
    strings = spark.createDataFrame([(i, w) for i, w in enumerate(words)], "id long, obj string")
    numbers = spark.createDataFrame([(i, float(v)) for i, v in enumerate(g.integers(0, 5, 150))], "id long, obj double")
    for df, metric, delta in ((strings, "edit", 1), (numbers, "abs1", 1.0)):
        config = JoinConfig(max_region=20, p=2, sampler="random")
        objs = j.validate_objects(df, "id", "obj", j.metric_of(metric))
        plan = j.make_plan(objs, j.metric_of(metric), delta, config)
        cells = j._grid(j.route(objs, plan), plan).groupBy("region", "a", "b").count().agg({"count": "max"}).first()[0]
        assert cells <= 80  # two blocks of about 20, more where few hashes meet
        truth = {tuple(r) for r in j.brute_force_join(df, "id", "obj", metric, delta).collect()}
        assert {tuple(r) for r in j.metric_self_join(df, "id", "obj", metric, delta, config).collect()} == truth
        both = j.metric_join(df, df, ("id", "id"), ("obj", "obj"), metric, delta, config).select("id_x", "id_y").collect()
        assert len(both) == len(set(map(tuple, both))) == 2 * len(truth) + 150


def test_plans_say_where_they_depart(spark):
    from pivotjoin.operators import join as j

    few = spark.range(10).selectExpr("id", "array(CAST(id AS DOUBLE)) AS obj")
    objs = j.validate_objects(few, "id", "obj", j.metric_of("l1"))
    assert any("random" in n for n in j.make_plan(objs, j.metric_of("l1"), 1.0, JoinConfig()).notes)
    assert JoinConfig().sized(10**10)[1] == 1024 and JoinConfig().sized(10**10)[0] <= 10_000


def test_running_sum_and_ranked_sets(spark):
    from pivotjoin.functions.filters import ranked_sets
    from pivotjoin.operators.tables import running_sum

    x = spark.range(1000).selectExpr("(id * 7919) % 1009 AS k", "id % 13 AS v")
    rows = sorted(running_sum(x, ["k"], F.col("v"), "s").collect(), key=lambda r: r["k"])
    total = 0
    for r in rows:
        total += r["v"]
        assert r["s"] == total
    sets = spark.createDataFrame([(1, ["a", "b"]), (2, ["b", "c"]), (3, []), (4, ["b"])], "id long, obj array<string>")
    assert {r["id"]: r["obj"] for r in ranked_sets(sets).collect()} == {1: [1, 3], 2: [2, 3], 3: [], 4: [3]}


def test_runs_are_stopped_when_their_time_is_over(spark):
    slow = F.udf(lambda i: __import__("time").sleep(30) or i, "long")
    assert measures.limited(spark, lambda: spark.range(4).select(slow("id")).collect(), 2) is None
    assert measures.limited(spark, lambda: spark.range(4).count(), 60) < 60
    with pytest.raises(ZeroDivisionError):
        measures.limited(spark, lambda: 1 / 0, 60)


@pytest.mark.parametrize("delta", [0.1, 0.4])
def test_counted_prefixes_lose_nothing(spark, delta):
    from pivotjoin.functions import filters

    rng = np.random.default_rng(3)
    base = [rng.choice(400, int(n), replace=False) for n in rng.integers(1, 120, 25)]
    sets = [sorted({int(t) if rng.random() > 0.1 else int(rng.integers(400, 800)) for t in rng.permutation(b)[: max(1, int(len(b) * share))]}) for b in base for share in (1.0, 0.9, 0.75, 0.6)]
    sets += [[], [], [1], [1], *sets[:10]]
    df = spark.createDataFrame([(i, [f"t{t}" for t in s]) for i, s in enumerate(sets)], "id long, obj array<string>")
    want = pairs(brute_force_join(df, "id", "obj", "jaccard", delta))
    for got in (metric_self_join(df, "id", "obj", "jaccard", delta), baselines.segment_signature_join(df, "id", "obj", "jaccard", delta), baselines.fragment_set_join(df, "id", "obj", delta)):
        assert pairs(got) == want
    found, classes = join_classes(df, "id", "obj", "jaccard", delta)
    rep = {r["id"]: r["rep"] for r in classes.collect()}
    assert sorted(rep) == list(range(len(sets))) and all(rep[i] == min(j for j, s in enumerate(sets) if s == sets[i]) for i in rep)
    assert {(rep[x], rep[y]) for x, y, *_ in want} - {(i, i) for i in rep} <= {(r["id_x"], r["id_y"]) for r in found.collect()} | {(r["id_y"], r["id_x"]) for r in found.collect()}
    # one rare token in common is no candidate
    far = spark.createDataFrame([(i, [f"both{i // 2}", *(f"{i}_{j}" for j in range(200))]) for i in range(60)], "id long, obj array<string>")
    assert filters.counted_candidates(filters.ranked_sets(far), 0.25).count() == 0


def test_shuffles_of_a_written_table_are_deleted(spark):
    from pivotjoin.operators import tables

    before = spark.conf.get(tables.CLEANUP, "false")
    assert tables.materialize(spark.range(1000).repartition(3).groupBy((F.col("id") % 7).alias("k")).count()).count() == 7
    assert spark.conf.get(tables.CLEANUP, "false") == before


@pytest.mark.parametrize("name", ["allocate_samples", "chi_square_confidence", "error_bound_strata", "error_bound_table", "gap_factor", "global_confidence_levels", "sample_size_table"])
def test_figures_come_from_a_table(spark, sf_dir, tmp_path, name):
    for t in ("events", "orders"):
        io.load(spark, sf_dir, t).where("user_id % 7 < 3" if t == "events" else "o_custkey % 7 < 3").write.parquet(f"{tmp_path}/{t}.parquet")
    whole, part = (sorted(map(tuple, queries.QUERIES[name](spark, d).collect()), key=str) for d in (sf_dir, str(tmp_path)))
    assert whole != part


def test_colocations_are_counted_without_pairs(spark):
    at = {i: [(0,), (1,), (0, 1), (0, 1, 2), (2,)][i % 5] for i in range(33)}
    routed = spark.createDataFrame([(r, i) for i, rs in at.items() for r in rs], "region int, id long")
    pair = measures.colocation_count(routed).groupBy("n").count().collect()
    assert {(r["regions"], r["pairs"]) for r in measures.colocation_histogram(routed).collect()} == {(r["n"], r["count"]) for r in pair}
    # as many as only counts can tell: 5 * 10**9 pairs
    many = spark.range(100_000).select(F.lit(0).alias("region"), "id")
    assert measures.colocation_histogram(many).first()["pairs"] == 100_000 * 99_999 // 2


def test_coverage_is_measured_without_comparing_all_pairs(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(queries, "brute_force_join", lambda *a: pytest.fail("all pairs compared"))
    assert queries.QUERIES["uncovered_pairs"](spark, sf_dir).first()[0] == 0


def test_grid_moves_few_rows(spark):
    """However small max_region is, a row goes to a bounded number of cells."""
    from pivotjoin.operators.join import MOST_BLOCKS, _parts

    rows = spark.range(6000).select(F.lit(0).alias("region"), "id")
    assert _parts([rows], 10).first()["parts"] == MOST_BLOCKS
    assert _parts([rows], 1000).first()["parts"] == 6


def test_rounds_and_cells_that_do_not_pay(spark, monkeypatch):
    """Objects that are about equally far from each other are compared in blocks; windows and cells that would hold nearly all of them are not written."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 32))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, obj array<double>")
    d = L1.block(x, x)
    delta = float(np.quantile(d[d > 0], 0.01))
    want = {(i, j) for i, j in np.argwhere(d <= delta).tolist() if i < j}
    written = []
    real = baselines.materialize
    monkeypatch.setattr(baselines, "materialize", lambda t, *a: written.append((y := real(t, *a)).count()) or y)
    for join in (baselines.multi_round_join, baselines.repartition_join):
        assert pairs(join(df, "id", "obj", "l1", delta)) == want
    assert max(written) <= 4 * len(x)


def test_equality_inside_the_join(spark):
    """Only rows of one value are compared, in both engines; a null value equals nothing."""
    rows = [(i, [float(i % 10)], float(i % 10), None if i % 7 == 0 else i % 3) for i in range(90)]
    df = spark.createDataFrame(rows, "id long, v array<double>, s double, k int")
    want = {(i, j) for i, j in itertools.combinations(range(90), 2) if i % 10 == j % 10 and i % 3 == j % 3 and i % 7 and j % 7}
    for col, metric in (("v", "l1"), ("s", "abs1")):
        assert pairs(metric_self_join(df, "id", col, metric, 0.5, JoinConfig(max_region=20), by="k")) == want
    with pytest.raises(ValueError):
        metric_self_join(df, "id", "s", "abs1", 0.5, JoinConfig(collapse=True), by="k")


def test_l1_in_whole_steps_misses_nothing():
    g = np.random.default_rng(5)
    m = metric_of("l1")
    for scale, shift in ((1.0, 0.0), (1e-6, 3.0), (1e5, -1e7)):
        x, y = (g.normal(0, scale, (n, 64)) + shift for n in (70, 5000))
        y[:70] = x + g.normal(0, scale / 40, (70, 64))
        d = np.abs(x[:, None] - y[None]).sum(-1)
        for delta in (np.quantile(d, 0.01), d[0, 0], d.max() * 2):
            found = list(m.maybe(x, y, delta))
            got = {(i, j) for a, b in found for i, j in zip(a.tolist(), b.tolist(), strict=True)}
            want = set(zip(*(v.tolist() for v in np.nonzero(d <= delta)), strict=True))
            assert want and want <= got and len(got) == sum(len(a) for a, _ in found)
    assert m.maybe(x, x + 1e9, 1.0) is None and m.maybe(np.ones((2, 3)), np.ones((2, 3)), 1.0) is None


def test_cells_that_coordinates_leave_whole_are_filtered_first(monkeypatch):
    import pivotjoin.operators.join as j

    g = np.random.default_rng(8)
    x = g.uniform(0, 1, (3000, 64))
    x[1500:] = x[:1500] + g.normal(0, 0.002, (1500, 64))
    m, ids, at = metric_of("l1"), np.arange(3000) * 7, np.arange(3000)
    compared = []
    counting = replace(m, rowwise=lambda a, b: compared.append(len(a)) or m.rowwise(a, b))
    none = np.zeros((3000, 0))
    got = [(a, b) for t in j.met(counting, 1.0, ids, x, none, at, at, True) for a, b in zip(t.column(0).to_pylist(), t.column(1).to_pylist(), strict=True)]
    assert sorted(got) == [(7 * i, 7 * (i + 1500)) for i in range(1500)]
    assert sum(compared) < 10_000  # of 4,498,500


def test_repeated_vectors_are_compared_once(spark, monkeypatch):
    import pivotjoin.operators.join as j

    rows = [(i, [float(i % 3), float(i % 5), float(i % 2 * (i < 400))]) for i in range(600)]
    df, planned = spark.createDataFrame(rows, "id long, obj array<double>"), []
    real = j._planned_join
    monkeypatch.setattr(j, "_planned_join", lambda objs, *a: planned.append(objs.count()) or real(objs, *a))
    monkeypatch.setattr(j, "LISTED", 7)
    want = sorted((a, b, float(d)) for a, x in rows for b, y in rows if a < b and (d := sum(p != q for p, q in zip(x, y, strict=True))) <= 1)
    assert sorted(tuple(r) for r in metric_self_join(df, "id", "obj", "hamming", 1.0).collect()) == want
    assert planned == [30]


def test_segment_signatures_are_verified_where_they_meet(spark, monkeypatch):
    """Candidates that share a common segment are verified without being shuffled; whole and broken thresholds, odd rows."""
    from test_functions import moved

    from pivotjoin.functions import filters

    monkeypatch.setattr(filters, "BLOCK_STRINGS", 200)
    g = np.random.default_rng(12)
    strings = [f"https://{'m.' * (i % 2)}{g.integers(10**6):06d}/{'é' * (i % 4)}" for i in range(700)] + ["", "a", "abc", "abd", "ab\0"]
    df = spark.createDataFrame([*enumerate(strings), (None, "abc"), (9999, None)], "id long, obj string")
    d, got = edit_block(strings, strings), []
    assert moved(spark, lambda: got.extend(tuple(r) for r in baselines.segment_signature_join(df, "id", "obj", "edit", 4).collect())) < 20_000
    assert sorted(got) == [(i, j, float(d[i, j])) for i in range(705) for j in range(i + 1, 705) if d[i, j] <= 4]
    assert pairs(baselines.segment_signature_join(df, "id", "obj", "edit", 2.5)) == {(i, j) for i in range(705) for j in range(i + 1, 705) if d[i, j] <= 2}
    assert baselines.segment_signature_join(df, "id", "obj", "edit", -1).count() == 0
