"""Catalogue: one query per method, variant, baseline, measure and workload, with SQL where SQL can say it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as w
from .functions import filters
from .functions.families import FAMILIES, Dirichlet, Wishart, fit_numeric
from .functions.metrics import check_metric, lp, metric_of
from .functions.numerics import digamma
from .operators import baselines, fits, sampling
from .operators.join import JoinPlan, brute_force_join, join_classes, make_plan, mapped, metric_join, metric_self_join, route, validate_objects
from .operators.split import Tree, entropy, gain_ratio, split_gain
from .operators.tables import connected_components, running_sum
from .plans import measures
from .plans.config import JoinConfig
from .sources.io import load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def rounded(pairs: DataFrame) -> DataFrame:
    return pairs.select("id_x", "id_y", F.round("distance", 6).alias("distance"))


def _self(name: str, source, metric, delta: float, sql: str, **config) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return rounded(metric_self_join(source(spark, sf_dir), "id", "obj", metric, delta, JoinConfig(**config)))

    query(name, sql)(run)


def _narrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w.descriptors(spark, sf_dir, 4)


# -- workloads by the full method ------------------------------------------------------------------
_self("w1_activity_l2", w.activity, "l2", 7.0, w.self_join_sql("activity", "l2", 7.0))
_self("w2_embedding_l1", w.descriptors, "l1", 7.0, w.self_join_sql("descriptors", "l1", 7.0))
_self("w2_embedding_l2", w.descriptors, "l2", 1.1, w.self_join_sql("descriptors", "l2", 1.1))
_self("w2_prefix_l1", _narrow, "l1", 0.1, w.self_join_sql("prefix4", "l1", 0.1))
_self("w3_url_edit", w.urls, "edit", 4, w.self_join_sql("urls", "edit", 4))
_self("w3_name_edit", w.names, "edit", 2, w.self_join_sql("names", "edit", 2))
_self("w4_document_jaccard", w.document_sets, "jaccard", 0.25, w.set_join_sql("document_sets", None, 0.25))
_self("w4_conversation_jaccard", w.conversation_sets, "jaccard", 0.5, w.set_join_sql("conversation_sets", None, 0.5))
_self("w5_lineitem_l1", w.line_items, "l1", 1.0, w.self_join_sql("line_items", "l1", 1.0))


@query("w5_balance_abs", "SELECT c_custkey AS id_x, s_suppkey AS id_y, round(abs(c_acctbal - s_acctbal), 6) AS distance FROM customer, supplier WHERE abs(c_acctbal - s_acctbal) <= 2.0 + 2e-9")
def _(spark, sf_dir):
    return rounded(metric_join(w.balances(spark, sf_dir, "customer"), w.balances(spark, sf_dir, "supplier"), ("id", "id"), ("obj", "obj"), "abs1", 2.0))


_RS = w.DISTANCE_SQL["l1"]


@query("w2_embedding_rs", f"WITH v AS (SELECT vec_id AS id, label, CAST(embedding AS DOUBLE[]) AS obj FROM embeddings) SELECT id_x, id_y, round(d, 6) AS distance FROM (SELECT x.id AS id_x, y.id AS id_y, {_RS} AS d FROM v x JOIN v y ON x.label < 5 AND y.label >= 5) WHERE d <= 7.0 + 1e-9")
def _(spark, sf_dir):
    return rounded(metric_join(w.descriptors(spark, sf_dir, where="label < 5"), w.descriptors(spark, sf_dir, where="label >= 5"), ("id", "id"), ("obj", "obj"), "l1", 7.0))


@query("w4_benchmark_documents_rs", w.set_join_sql("benchmark_sets", "document_sets", 0.8))
def _(spark, sf_dir):
    return rounded(metric_join(w.benchmark_sets(spark, sf_dir), w.document_sets(spark, sf_dir), ("id", "id"), ("obj", "obj"), "jaccard", 0.8))


# -- combinations and variants: all give the same pairs --------------------------------------------
_NARROW_SQL = w.self_join_sql("prefix4", "l1", 0.1)
for _sampler in ("random", "distribution_aware", "generative"):
    for _splitter in ("iterative", "learned"):
        _self(f"join_{_sampler.replace('distribution_aware', 'distaware')}_{_splitter}", _narrow, "l1", 0.1, _NARROW_SQL, sampler=_sampler, splitter=_splitter)
_VARIANTS = {
    "stratified": {"sampler": "stratified"}, "local": {"sampler": "local"}, "bounds_cell": {"bounds": "cell"}, "bounds_data_box": {"bounds": "data_box"}, "replication_both": {"replication": "both"}, "engine_block": {"engine": "block"}, "engine_sql": {"engine": "sql"},
    "target_space": {"space": "target"}, "farthest_axes": {"axes": "farthest"}, "equal_width_boxes": {"sampler": "distribution_aware", "boxes": "equal_width"}, "equal_width_cells": {"cells_by": "width"}, "snapped": {"snap": True}, "joint_normal": {"model": "mvn_full"}, "collapse": {"collapse": True}, "region_grid": {"max_region": 40}, "column_nodes": {"node_by": "range"},
}
for _name, _config in _VARIANTS.items():
    _self(f"join_{_name}", _narrow, "l1", 0.1, _NARROW_SQL, **_config)
_self("join_region_grid_edit", w.urls, "edit", 4, w.self_join_sql("urls", "edit", 4), max_region=50)
_self("join_region_segments_edit", w.urls, "edit", 2, w.self_join_sql("urls", "edit", 2), segments=True)
_self("join_refined", _narrow, "l1", 0.1, _NARROW_SQL, p=4, per_region=60)
_self("join_refined_jaccard", w.document_sets, "jaccard", 0.1, w.set_join_sql("document_sets", None, 0.1), p=4, per_region=100)
_self("join_linf", _narrow, "linf", 0.04, w.self_join_sql("prefix4", "linf", 0.04))
_self("join_l3", _narrow, lp(3), 0.05, w.self_join_sql("prefix4", "l3", 0.05))
_self("join_hamming", w.line_items, "hamming", 1.0, w.self_join_sql("line_items", "hamming", 1.0))
_self("join_angular", _narrow, "angular", 0.1, w.self_join_sql("prefix4", "angular", 0.1))

# -- baselines -----------------------------------------------------------------------------------
_BASELINES = {
    "brute_force": brute_force_join, "multi_round": baselines.multi_round_join, "repartition": baselines.repartition_join, "nearest_pivot": baselines.nearest_pivot_join, "kd_split": baselines.kd_split_join,
    "oversampled_3x": lambda *a: baselines.oversampled_join(*a, factor=3), "oversampled_10x": lambda *a: baselines.oversampled_join(*a, factor=10),
}
for _name, _join in _BASELINES.items():
    query(f"baseline_{_name}", _NARROW_SQL)(lambda spark, sf_dir, f=_join: rounded(f(_narrow(spark, sf_dir), "id", "obj", "l1", 0.1)))
query("baseline_segment_signature", w.self_join_sql("urls", "edit", 4))(lambda spark, sf_dir: rounded(baselines.segment_signature_join(w.urls(spark, sf_dir), "id", "obj", "edit", 4)))
query("baseline_prefix_signature", w.set_join_sql("document_sets", None, 0.25))(lambda spark, sf_dir: rounded(baselines.segment_signature_join(w.document_sets(spark, sf_dir), "id", "obj", "jaccard", 0.25)))
query("baseline_fragment_set", w.set_join_sql("document_sets", None, 0.25))(lambda spark, sf_dir: rounded(baselines.fragment_set_join(w.document_sets(spark, sf_dir), "id", "obj", 0.25)))

# the competitors on strings, on sets and on whole vectors
for _name, _join in {"multi_round": baselines.multi_round_join, "kd_split": baselines.kd_split_join}.items():
    query(f"baseline_{_name}_edit", w.self_join_sql("urls", "edit", 4))(lambda spark, sf_dir, f=_join: rounded(f(w.urls(spark, sf_dir), "id", "obj", "edit", 4)))
    query(f"baseline_{_name}_jaccard", w.set_join_sql("document_sets", None, 0.25))(lambda spark, sf_dir, f=_join: rounded(f(w.document_sets(spark, sf_dir), "id", "obj", "jaccard", 0.25)))
for _name in ("multi_round", "repartition", "nearest_pivot", "kd_split"):
    query(f"baseline_{_name}_whole", w.self_join_sql("descriptors", "l1", 7.0))(lambda spark, sf_dir, f=_BASELINES[_name]: rounded(f(w.descriptors(spark, sf_dir), "id", "obj", "l1", 7.0)))
for _sampler, _splitter in (("random", "iterative"), ("distribution_aware", "iterative"), ("generative", "iterative")):
    _self(f"join_{_sampler.replace('distribution_aware', 'distaware')}_{_splitter}_whole", w.descriptors, "l1", 7.0, w.self_join_sql("descriptors", "l1", 7.0), sampler=_sampler, splitter=_splitter)
# the other thresholds of the workloads
for _delta in (6.6, 7.5):
    _self(f"w2_embedding_l1_{_delta}", w.descriptors, "l1", _delta, w.self_join_sql("descriptors", "l1", _delta))
for _delta in (2, 8):
    _self(f"w3_url_edit_{_delta}", w.urls, "edit", _delta, w.self_join_sql("urls", "edit", _delta))
for _delta in (0.1, 0.4):
    _self(f"w4_document_jaccard_{_delta}", w.document_sets, "jaccard", _delta, w.set_join_sql("document_sets", None, _delta))
for _delta in (6.0, 8.0):
    _self(f"w1_activity_l2_{_delta:g}", w.activity, "l2", _delta, w.self_join_sql("activity", "l2", _delta))

# -- filters -------------------------------------------------------------------------------------
_RANKED = f"""WITH d AS MATERIALIZED ({w.SQL["document_sets"]}), e AS (SELECT id, len(obj) AS size, unnest(obj) AS token FROM d), f AS (SELECT token, count(*) AS n FROM e GROUP BY token),
 r AS (SELECT id, size, token, row_number() OVER (PARTITION BY id ORDER BY n, token) - 1 AS pos FROM e JOIN f USING (token)),
 p AS (SELECT * FROM r WHERE pos < size - ceil(0.9 * size - 1e-9) + 1)"""
_MATCHED = "SELECT x.id AS id_x, y.id AS id_y, min(x.pos) AS i, min(y.pos) AS j, any_value(x.size) AS sx, any_value(y.size) AS sy FROM p x JOIN p y ON x.token = y.token AND x.id < y.id AND 0.9 * x.size <= y.size + 1e-9 AND 0.9 * y.size <= x.size + 1e-9 GROUP BY 1, 2"
query("filter_length", f"WITH v AS ({w.SQL['urls']}) SELECT x.id AS id_x, y.id AS id_y FROM v x JOIN v y ON x.id < y.id AND abs(length(x.obj) - length(y.obj)) <= 2")(lambda spark, sf_dir: filters.length_candidates(w.urls(spark, sf_dir), 2))
query("filter_prefix", f"{_RANKED} SELECT id_x, id_y FROM ({_MATCHED})")(lambda spark, sf_dir: filters.prefix_candidates(w.document_sets(spark, sf_dir), 0.1))
query("filter_position", f"{_RANKED} SELECT id_x, id_y FROM ({_MATCHED}) WHERE least(sx - i, sy - j) >= ceil(0.9 / 1.9 * (sx + sy) - 1e-9)")(lambda spark, sf_dir: filters.prefix_candidates(w.document_sets(spark, sf_dir), 0.1, positions=True))
_SEGMENTS = f"""WITH v AS MATERIALIZED ({w.SQL['urls']}), i AS (SELECT CAST(unnest(range(5)) AS INT) AS i),
 x AS (SELECT id, length(obj) AS n, i, substr(obj, i * length(obj) // 5 + 1, (i + 1) * length(obj) // 5 - i * length(obj) // 5) AS seg FROM v, i),
 l AS (SELECT id, obj, length(obj) AS len, unnest(range(greatest(length(obj) - 4, 0), length(obj) + 5)) AS n FROM v),
 b AS (SELECT id, obj, len, n, i, i * n // 5 AS a, (i + 1) * n // 5 - i * n // 5 AS size FROM l, i),
 k AS (SELECT id, obj, n, i, size, unnest(range(greatest(a - 4, 0), greatest(a - 4, 0, least(a + 4, len - size)) + 1)) AS pos FROM b),
 y AS (SELECT DISTINCT id, n, i, substr(obj, pos + 1, size) AS seg FROM k)
 SELECT DISTINCT least(x.id, y.id) AS id_x, greatest(x.id, y.id) AS id_y FROM x JOIN y ON x.n = y.n AND x.i = y.i AND x.seg = y.seg AND x.id <> y.id"""
query("filter_segment", _SEGMENTS)(lambda spark, sf_dir: filters.segment_candidates(w.urls(spark, sf_dir), 4))
query("token_order", f"SELECT token, n, row_number() OVER (ORDER BY n, token) AS rank FROM (SELECT token, count(*) AS n FROM (SELECT unnest(obj) AS token FROM ({w.SQL['document_sets']})) GROUP BY token)")(lambda spark, sf_dir: filters.token_order(w.document_sets(spark, sf_dir)))

# -- distribution fits ---------------------------------------------------------------------------


def _event_values(spark, sf_dir) -> DataFrame:
    e = load(spark, sf_dir, "events")
    kinds = w.event_kinds(e)  # numbered by their order
    node = F.element_at(F.create_map(*[F.lit(v) for i, k in enumerate(kinds) for v in (k, i)]), F.col("event_type"))
    return e.select(F.col("event_id").alias("id"), F.array("value").alias("obj"), node.alias("node"))


_NODES = "(SELECT event_id, value, dense_rank() OVER (ORDER BY event_type) - 1 AS node FROM events)"


@query("fit_exponential", f"SELECT CAST(node AS INT) AS node, count(*) AS n, round(avg(value), 6) AS mean, round(1 / avg(value), 9) AS rate FROM {_NODES} GROUP BY node")
def _(spark, sf_dir):
    m = fits.vector_moments(_event_values(spark, sf_dir))
    return m.select("node", "n", F.round(F.col("x") / F.col("n"), 6).alias("mean"), F.round(F.col("n") / F.col("x"), 9).alias("rate"))


def _by_label(spark, sf_dir, width: int) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.slice(F.col("embedding").cast("array<double>"), 1, width).alias("obj"), F.col("label").alias("node"))


@query("fit_normal", "SELECT label AS node, count(*) AS n, round(avg(CAST(embedding[1] AS DOUBLE)), 6) AS mean, round(avg(pow(CAST(embedding[1] AS DOUBLE), 2)) - pow(avg(CAST(embedding[1] AS DOUBLE)), 2), 6) AS var FROM embeddings GROUP BY label")
def _(spark, sf_dir):
    m = fits.vector_moments(_by_label(spark, sf_dir, 1))
    mean = F.col("x") / F.col("n")
    return m.select("node", "n", F.round(mean, 6).alias("mean"), F.round(F.col("xx") / F.col("n") - mean * mean, 6).alias("var"))


@query("fit_mvn_moments", "SELECT label AS node, CAST(i - 1 AS INT) AS dim, CAST(j - 1 AS INT) AS dim2, round(avg(CAST(embedding[i] AS DOUBLE) * CAST(embedding[j] AS DOUBLE)), 6) AS second FROM embeddings, (SELECT unnest(range(1, 5)) AS i), (SELECT unnest(range(1, 5)) AS j) GROUP BY 1, 2, 3")
def _(spark, sf_dir):
    x = _by_label(spark, sf_dir, 4).select("node", "obj", F.posexplode("obj").alias("dim", "a"))
    x = x.select("node", "dim", "a", F.posexplode("obj").alias("dim2", "b"))
    return x.groupBy("node", "dim", "dim2").agg(F.round(F.avg(F.col("a") * F.col("b")), 6).alias("second"))


@query("fit_gamma_stats", "SELECT CAST(user_id % 4 AS INT) AS node, count(*) AS n, round(avg(total), 6) AS mean, round(avg(ln(total)), 6) AS mean_log FROM (SELECT user_id, sum(value) AS total FROM events GROUP BY user_id) WHERE total > 0 GROUP BY 1")
def _(spark, sf_dir):
    x = load(spark, sf_dir, "events").groupBy("user_id").agg(F.sum("value").alias("t")).where("t > 0")
    m = fits.vector_moments(x.select(F.array("t").alias("obj"), (F.col("user_id") % 4).alias("node")))
    return m.select("node", "n", F.round(F.col("x") / F.col("n"), 6).alias("mean"), F.round(F.col("log") / F.col("nlog"), 6).alias("mean_log"))


def _type_shares(spark, sf_dir) -> DataFrame:
    a = w.activity(spark, sf_dir)
    kinds = 5
    total = [sum((F.element_at("obj", i * w.PERIODS + p + 1) for p in range(w.PERIODS)), F.lit(0.5)) for i in range(kinds)]
    return a.select("id", F.array(*[t / sum(total, F.lit(0.0)) for t in total]).alias("obj"), (F.col("id") % 4).alias("node"))


@query("fit_dirichlet_stats", f"""WITH a AS ({w.SQL["activity"]}), s AS (SELECT id, [list_sum(obj[i * 4 + 1:i * 4 + 4]) + 0.5 for i in range(5)] AS t FROM a)
 SELECT CAST(id % 4 AS INT) AS node, CAST(i - 1 AS INT) AS dim, count(*) AS n, round(avg(ln(t[i] / list_sum(t))), 6) AS mean_log FROM s, (SELECT unnest(range(1, 6)) AS i) GROUP BY 1, 2""")
def _(spark, sf_dir):
    m = fits.vector_moments(_type_shares(spark, sf_dir))
    return m.select("node", "dim", "n", F.round(F.col("log") / F.col("n"), 6).alias("mean_log"))


def _scatter(spark, sf_dir) -> DataFrame:
    """2 x 2 scatter matrices of blocks of ten rows of a label, over two entries."""
    e = load(spark, sf_dir, "embeddings").select("label", F.floor(F.col("vec_id") / 100).alias("block"), F.col("embedding")[0].cast("double").alias("a"), F.col("embedding")[1].cast("double").alias("b"))
    g = e.groupBy("label", "block").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("a") * F.col("a")).alias("aa"), F.sum(F.col("a") * F.col("b")).alias("ab"), F.sum(F.col("b") * F.col("b")).alias("bb"))
    return g.where("n >= 3")


@query("fit_wishart_stats", """WITH s AS (SELECT label, vec_id // 100 AS block, count(*) AS n, sum(CAST(embedding[1] AS DOUBLE) ** 2) AS aa, sum(CAST(embedding[1] AS DOUBLE) * CAST(embedding[2] AS DOUBLE)) AS ab, sum(CAST(embedding[2] AS DOUBLE) ** 2) AS bb
 FROM embeddings GROUP BY 1, 2 HAVING count(*) >= 3) SELECT label AS node, count(*) AS n, round(avg(aa), 6) AS aa, round(avg(ab), 6) AS ab, round(avg(bb), 6) AS bb, round(avg(ln(aa * bb - ab * ab)), 6) AS mean_logdet FROM s GROUP BY label""")
def _(spark, sf_dir):
    x = _scatter(spark, sf_dir)
    det = F.log(F.col("aa") * F.col("bb") - F.col("ab") * F.col("ab"))
    return x.groupBy(F.col("label").alias("node")).agg(F.count(F.lit(1)).alias("n"), *[F.round(F.avg(c), 6).alias(c) for c in ("aa", "ab", "bb")], F.round(F.avg(det), 6).alias("mean_logdet"))


_TOTALS = "(SELECT user_id, sum(value) AS total FROM events GROUP BY user_id) WHERE total > 0"


@query("fit_gamma", f"SELECT CAST(user_id % 4 AS INT) AS node, round(avg(total), 4) AS mean, round(avg(ln(total)), 6) AS mean_log FROM {_TOTALS} GROUP BY 1")
def _(spark, sf_dir):
    """What the fitted laws expect of x and of its logarithm: the most likely parameters reproduce the means of both."""
    x = load(spark, sf_dir, "events").groupBy("user_id").agg(F.sum("value").alias("t")).where("t > 0")
    x = x.select(F.col("user_id").alias("id"), F.array("t").alias("obj"), (F.col("user_id") % 4).cast("int").alias("node"))
    found = [(f.node, f.dims[0].params["shape"], f.dims[0].params["rate"]) for f in fits.fit_nodes(x, families=("gamma",), gof_rows=None)]
    return spark.createDataFrame([(k, round(float(a / b), 4), round(float(digamma(a) - np.log(b)), 6)) for k, a, b in found], "node int, mean double, mean_log double")


@query("fit_dirichlet", f"""WITH a AS ({w.SQL["activity"]}), s AS (SELECT id, [list_sum(obj[i * 4 + 1:i * 4 + 4]) + 0.5 for i in range(5)] AS t FROM a)
 SELECT CAST(id % 4 AS INT) AS node, CAST(i - 1 AS INT) AS dim, round(avg(ln(t[i] / list_sum(t))), 5) AS mean_log FROM s, (SELECT unnest(range(1, 6)) AS i) GROUP BY 1, 2""")
def _(spark, sf_dir):
    """What the fitted laws expect of the logarithm of each share: the most likely parameters reproduce its mean."""
    m = fits.vector_moments(_type_shares(spark, sf_dir)).orderBy("node", "dim").collect()
    by: dict[int, list[float]] = {}
    for r in m:
        by.setdefault(r["node"], []).append(r["log"] / r["n"])
    found = {k: np.array(Dirichlet.fit(v).alpha) for k, v in by.items()}
    return spark.createDataFrame([(k, d, round(float(digamma(a) - digamma(alpha.sum())), 5)) for k, alpha in found.items() for d, a in enumerate(alpha)], "node int, dim int, mean_log double")


@query("fit_wishart", """WITH s AS (SELECT label, vec_id // 100 AS block, count(*) AS n, sum(CAST(embedding[1] AS DOUBLE) ** 2) AS aa, sum(CAST(embedding[1] AS DOUBLE) * CAST(embedding[2] AS DOUBLE)) AS ab, sum(CAST(embedding[2] AS DOUBLE) ** 2) AS bb
 FROM embeddings GROUP BY 1, 2 HAVING count(*) >= 3) SELECT label AS node, round(avg(aa), 4) AS aa, round(avg(ab), 4) AS ab, round(avg(bb), 4) AS bb, round(avg(ln(aa * bb - ab * ab)), 4) AS mean_logdet FROM s GROUP BY label HAVING count(*) >= 2""")
def _(spark, sf_dir):
    """What the fitted laws expect of the matrix and of the logarithm of its determinant."""
    out = []
    for x in QUERIES["fit_wishart_stats"](spark, sf_dir).collect():
        if x["n"] >= 2:
            f = Wishart.fit(np.array([[x["aa"], x["ab"]], [x["ab"], x["bb"]]]), x["mean_logdet"])
            mean = f.dof * np.asarray(f.v)
            log_det = digamma(f.dof / 2) + digamma((f.dof - 1) / 2) + 2 * np.log(2) + np.log(np.linalg.det(f.v))
            out.append((x["node"], *[round(float(v), 4) for v in (mean[0, 0], mean[0, 1], mean[1, 1])], round(float(log_det), 4)))
    return spark.createDataFrame(out, "node int, aa double, ab double, bb double, mean_logdet double")


@query("fit_numeric", f"SELECT CAST(user_id % 4 AS INT) AS node, how, round(avg(total), 1) AS mean, round(avg(ln(total)), 3) AS mean_log FROM {_TOTALS.replace(' WHERE', ', (SELECT unnest([$$newton$$, $$gradient$$]) AS how) WHERE')} GROUP BY 1, 2")
def _(spark, sf_dir):
    """Gamma by Newton and by gradient steps on the mean statistics, without the closed equation; what the fitted laws expect."""
    from .functions.families import GAMMA

    out = []
    for r in QUERIES["fit_gamma_stats"](spark, sf_dir).collect():
        t = [r["mean_log"], r["mean"] / 1000]  # in thousands, so that both steps are of one scale
        t[0] -= np.log(1000)
        for how in ("newton", "gradient"):
            e = fit_numeric(t, GAMMA, [0.5, -1.0], how)
            shape, rate = float(e[0] + 1), float(-e[1] / 1000)
            out.append((r["node"], how, shape / rate, float(digamma(shape) - np.log(rate))))
    # steps end near the mean: digits beyond what they reach must not decide a tie
    rounded_to = lambda c, near, digits: F.round(F.round(c, near), digits).alias(c)
    return spark.createDataFrame(out, "node int, how string, mean double, mean_log double").select("node", "how", rounded_to("mean", 4, 1), rounded_to("mean_log", 6, 3))


_CELLS = 20


@query("gof_exponential", f"""WITH v AS (SELECT node, value, avg(value) OVER (PARTITION BY node) AS mean, count(*) OVER (PARTITION BY node) AS n FROM {_NODES}),
 c AS (SELECT node, n, least({_CELLS - 1}, floor((1 - exp(-value / mean)) * {_CELLS})) AS cell, count(*) AS seen FROM v GROUP BY ALL),
 k AS (SELECT node, any_value(n) AS n, sum(pow(seen - n / {_CELLS}.0, 2) / (n / {_CELLS}.0)) + ({_CELLS} - count(*)) * any_value(n) / {_CELLS}.0 AS k FROM c GROUP BY node)
 SELECT CAST(node AS INT) AS node, n, round(k, 6) AS k_stat FROM k""")
def _(spark, sf_dir):
    """Statistic of the exponential law by event type, with cells of equal probability in closed form."""
    x = _event_values(spark, sf_dir).select("node", F.col("obj")[0].alias("value"))
    sizes = F.broadcast(x.groupBy("node").agg(F.avg("value").alias("mean"), F.count(F.lit(1)).alias("n")))  # one row per node
    cell = F.least(F.lit(_CELLS - 1), F.floor((1 - F.exp(-F.col("value") / F.col("mean"))) * _CELLS))
    c = x.join(sizes, "node").groupBy("node", "n", cell.alias("cell")).agg(F.count(F.lit(1)).alias("seen"))
    want = F.col("n") / _CELLS
    return c.groupBy("node", "n").agg(F.round(F.sum(F.pow(F.col("seen") - want, 2) / want) + (_CELLS - F.count(F.lit(1))) * F.first(want), 6).alias("k_stat"))


_BUCKETS = (2, 3, 6, 20)
#: How evenly the events of each type lie over so many buckets of users: the statistic and its degrees of freedom.
_EVEN = f"""(SELECT event_type, m - 1 AS dof, sum(pow(seen - n / m, 2) / (n / m)) + (m - count(*)) * any_value(n) / any_value(m) AS k_stat
 FROM (SELECT event_type, m, user_id % m AS cell, count(*) AS seen, CAST(sum(count(*)) OVER (PARTITION BY event_type, m) AS DOUBLE) AS n FROM events, (SELECT unnest([{", ".join(map(str, _BUCKETS))}]) AS m) WHERE user_id IS NOT NULL GROUP BY 1, 2, 3) GROUP BY event_type, m)"""
#: The upper tail of the chi-square law by the series of its lower one.
_TAIL = """(SELECT {0}, greatest(0.0, 1 - sum(exp(dof / 2.0 * ln(k_stat / 2) - k_stat / 2 - lgamma(dof / 2.0 + n + 1) + n * ln(k_stat / 2)))) AS c
 FROM {1} AS t, (SELECT unnest(range(4000)) AS n) WHERE k_stat > 0 GROUP BY {0}, k_stat, dof)"""


def _evenness(spark, sf_dir) -> list[tuple[str, int, float]]:
    """(event type, degrees of freedom, statistic) over all events."""
    e = load(spark, sf_dir, "events").where(F.col("user_id").isNotNull())
    x = e.select("event_type", "user_id", F.explode(F.array(*[F.lit(m) for m in _BUCKETS])).alias("m"))
    cells = x.groupBy("event_type", "m", (F.col("user_id") % F.col("m")).alias("cell")).agg(F.count(F.lit(1)).alias("seen"))
    by: dict[tuple[str, int], list[int]] = {}
    for r in cells.orderBy("event_type", "m", "cell").collect():  # a row an event type and bucket
        by.setdefault((r["event_type"], r["m"]), []).append(r["seen"])
    want = lambda seen, m: sum(seen) / m
    found = [(k, m - 1, sum((v - want(seen, m)) ** 2 / want(seen, m) for v in seen) + (m - len(seen)) * want(seen, m)) for (k, m), seen in by.items()]
    return [f for f in found if f[2] > 0]


@query("chi_square_confidence", f"SELECT event_type, CAST(dof AS INT) AS dof, round(c, 6) AS confidence FROM {_TAIL.format('event_type, dof', _EVEN)}")
def _(spark, sf_dir):
    """By event type, how likely its events are as uneven over buckets of users as they are."""
    return spark.createDataFrame([(t, d, round(max(0.0, float(fits.confidence(k, d))), 6)) for t, d, k in _evenness(spark, sf_dir)], "event_type string, dof int, confidence double")


_LEVEL = f"(SELECT mode, CASE WHEN mode = 'pooled' THEN sum(dof) ELSE any_value(dof) END AS dof, CASE WHEN mode = 'pooled' THEN sum(k_stat) ELSE avg(k_stat) END AS k_stat FROM {_EVEN}, (SELECT unnest(['pooled', 'quantile_sum']) AS mode) WHERE dof = {_BUCKETS[1] - 1} AND k_stat > 0 GROUP BY mode)"


@query("global_confidence_levels", f"SELECT mode, round(c, 6) AS confidence FROM {_TAIL.format('mode', _LEVEL)}")
def _(spark, sf_dir):
    """Both readings of the confidence of all event types together; with one number of degrees of freedom the level of the mean statistic is that of the sum."""
    pool = [(k, d) for _, d, k in _evenness(spark, sf_dir) if d == _BUCKETS[1] - 1]
    return spark.createDataFrame([(m, round(max(0.0, float(fits.global_confidence(pool, m))), 6)) for m in ("pooled", "quantile_sum")], "mode string, confidence double")


def _value_fits(spark, sf_dir) -> list:
    return fits.fit_nodes(_event_values(spark, sf_dir), families=("exponential", "normal", "gamma"), gof_rows=None)


@query("gof_confidence")
def _(spark, sf_dir):
    return fits.fits_table(spark, _value_fits(spark, sf_dir)).select("node", "k_stat", "dof", "confidence")


@query("select_family")
def _(spark, sf_dir):
    return fits.fits_table(spark, _value_fits(spark, sf_dir)).select("node", "dim", "family", "confidence")


@query("global_confidence")
def _(spark, sf_dir):
    f = [(x.k_stat, x.dof) for x in _value_fits(spark, sf_dir)]
    return spark.createDataFrame([(m, fits.global_confidence(f, m)) for m in ("quantile_sum", "pooled")], "mode string, confidence double")


# -- sampling ------------------------------------------------------------------------------------
def _users(spark, sf_dir, nodes: int) -> list:
    """Events of each group of users, and their share of values below 50."""
    e = load(spark, sf_dir, "events").where(F.col("user_id").isNotNull()).groupBy((F.col("user_id") % nodes).cast("int").alias("node"))
    return e.agg(F.count(F.lit(1)).alias("n"), F.avg(F.when(F.col("value") < 50, 1.0).otherwise(0.0)).alias("c")).orderBy("node").collect()


def _users_sql(nodes: int) -> str:
    return f"(SELECT CAST(user_id % {nodes} AS INT) AS node, count(*) AS n, avg(CASE WHEN value < 50 THEN 1.0 ELSE 0.0 END) AS c FROM events WHERE user_id IS NOT NULL GROUP BY 1)"


@query("allocate_samples", f"""WITH q AS (SELECT node, 170 * (n / greatest(c, 0.001)) / sum(n / greatest(c, 0.001)) OVER () AS want FROM {_users_sql(3)})
 SELECT node, CAST(floor(want) + CAST(row_number() OVER (ORDER BY round(floor(want) - want, 9), node) <= 170 - sum(floor(want)) OVER () AS INT) AS INT) AS quota FROM q""")
def _(spark, sf_dir):
    """Quotas of 170 pivots over three groups of users by their events; the share of values below 50 stands for the confidence."""
    got = sampling.allocate([fits.NodeFit(r["node"], r["n"], confidence=r["c"]) for r in _users(spark, sf_dir, 3)], 170)
    return spark.createDataFrame(list(got.items()), "node int, quota int")


def _hash_sql(column: str, seed: int) -> str:
    p, a, b = fits.MIX_P, fits.MIX_A, fits.MIX_B
    return f"((((({column} % {p}) * {a} + {(seed * 7919 + 12_345) % p}) % {p}) * {b} + 1) % {p})"


query("sample_random", f"SELECT doc_id AS id FROM documents ORDER BY {_hash_sql('doc_id', 7)}, doc_id LIMIT 50")(lambda spark, sf_dir: sampling.random_pivots(load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id")), 50))


def _lang_nodes(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), (F.col("doc_id") % 5).cast("int").alias("node"), F.col("n_chars"))


@query("sample_local", f"SELECT id, CAST(node AS INT) AS node FROM (SELECT doc_id AS id, doc_id % 5 AS node, row_number() OVER (PARTITION BY doc_id % 5 ORDER BY {_hash_sql('doc_id', 7)}, doc_id) AS r FROM documents) WHERE r <= 10")
def _(spark, sf_dir):
    return sampling.local_stratified_pivots(_lang_nodes(spark, sf_dir), 50).select("id", "node")


_STRATIFIED = f"""WITH d AS (SELECT doc_id AS id, n_chars, {_hash_sql('doc_id', 7)} AS h FROM documents), q AS (SELECT quantile_disc(n_chars, [0.2, 0.4, 0.6, 0.8]) AS cuts FROM d),
 s AS (SELECT d.*, len(list_filter(cuts, lambda c: n_chars > c)) AS stratum FROM d, q), n AS (SELECT stratum, count(*) AS n, 50 * count(*) / CAST(sum(count(*)) OVER () AS DOUBLE) AS want FROM s GROUP BY stratum),
 m AS (SELECT stratum, floor(want) + CAST(row_number() OVER (ORDER BY floor(want) - want, stratum) <= 50 - sum(floor(want)) OVER () AS INT) AS take FROM n)
 SELECT id, n_chars FROM (SELECT s.*, take, row_number() OVER (PARTITION BY stratum ORDER BY h, id) AS r FROM s JOIN m USING (stratum)) WHERE r <= take"""


@query("sample_stratified", _STRATIFIED)
def _(spark, sf_dir):
    return sampling.shuffled_stratified_pivots(_lang_nodes(spark, sf_dir), 50, 5, "n_chars").select("id", "n_chars")


def _label_fits(spark, sf_dir):
    x = _by_label(spark, sf_dir, 4)
    return x, fits.fit_nodes(x, families=("normal",))


@query("sample_distribution_aware")
def _(spark, sf_dir):
    x, f = _label_fits(spark, sf_dir)
    return sampling.distribution_aware_pivots(x, f, 100)


_LAW = 0.125  # the deviation of an entry of a unit vector with 64 entries
_NODE_CONFIDENCE = 0.5
_SLICES = ", ".join(f"({n}, {b}, {float(FAMILIES['normal'].quantile({'mean': 0.0, 'var': _LAW**2}, b / n))!r})" for n in range(2, 12) for b in range(1, n))
_DRAWN = f"""WITH x AS (SELECT vec_id AS id, label AS node, CAST(embedding[1] AS DOUBLE) AS v, {_hash_sql('vec_id', 7)} AS h, CAST({_hash_sql('vec_id', 38)} >= {_NODE_CONFIDENCE} * {fits.MIX_P} AS INT) AS rejected FROM embeddings),
 n AS (SELECT node, count(*) AS n, 100 * count(*) / CAST(sum(count(*)) OVER () AS DOUBLE) AS want FROM x GROUP BY node),
 m AS (SELECT node, CAST(floor(want) + CAST(row_number() OVER (ORDER BY floor(want) - want, node) <= 100 - sum(floor(want)) OVER () AS INT) AS INT) AS quota FROM n),
 b AS (SELECT node, quota, CAST(floor(sqrt(quota)) AS INT) AS boxes FROM m), cuts(boxes, b, cut) AS (VALUES {_SLICES}),
 y AS (SELECT x.*, quota, boxes, (SELECT count(*) FROM cuts c WHERE c.boxes = b.boxes AND c.cut < v) AS box FROM x JOIN b USING (node)),
 r AS (SELECT *, row_number() OVER (PARTITION BY node, box ORDER BY rejected, h, id) AS r FROM y),
 w AS (SELECT *, quota // boxes + CAST(box < quota % boxes AS INT) AS q FROM r)
 SELECT id, node, CAST(box AS INT) AS box FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY CAST(r > q AS INT), rejected, h, id) AS o FROM w) WHERE o <= quota"""


@query("sample_distribution_aware_fixed", _DRAWN)
def _(spark, sf_dir):
    """Real rows by a given law: slices of equal probability, rejection by the confidence, quotas by size."""
    x = _by_label(spark, sf_dir, 1)
    sizes = {r["node"]: r["count"] for r in x.groupBy("node").count().collect()}
    law = fits.DimFit("normal", {"mean": 0.0, "var": _LAW**2}, confidence=_NODE_CONFIDENCE)
    found = [fits.NodeFit(k, n, [law], confidence=_NODE_CONFIDENCE) for k, n in sorted(sizes.items())]
    return sampling.distribution_aware_pivots(x, found, 100).select("id", "node", "box")


@query("sample_generative")
def _(spark, sf_dir):
    return sampling.mixture_draws(spark, _label_fits(spark, sf_dir)[1], 100)


@query("gibbs_chain")
def _(spark, sf_dir):
    points, nodes, proposals = sampling.gibbs_chain(_label_fits(spark, sf_dir)[1], 100)
    return spark.createDataFrame([(int(k), [float(v) for v in p], proposals) for p, k in zip(points, nodes, strict=True)], "node int, obj array<double>, proposals int")


@query("sampling_error_ks", f"""WITH d AS (SELECT doc_id, n_chars FROM documents), s AS (SELECT n_chars FROM d ORDER BY {_hash_sql('doc_id', 7)}, doc_id LIMIT 50),
 v AS (SELECT DISTINCT n_chars AS x FROM d) SELECT round(max(abs((SELECT count(*) FROM s WHERE n_chars <= x) / 50.0 - (SELECT count(*) FROM d WHERE n_chars <= x) / CAST((SELECT count(*) FROM d) AS DOUBLE))), 6) AS error FROM v""")
def _(spark, sf_dir):
    """Greatest gap between the shares of a sample of 50 and of all documents, over text lengths."""
    d = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "n_chars")
    full = fits.ecdf(d, "n_chars")
    part = sampling.random_pivots(d, 50).groupBy(F.col("n_chars").alias("value")).agg(F.count(F.lit(1)).alias("n"))
    both = running_sum(full.join(part, "value", "left"), ["value"], F.coalesce("n", F.lit(0)), "run")
    return both.select(F.abs(F.col("run") / F.lit(50.0) - F.col("share")).alias("gap")).agg(F.round(F.max("gap"), 6).alias("error"))


query("ecdf", "SELECT n_chars AS value, round(max(c), 9) AS share FROM (SELECT n_chars, cume_dist() OVER (ORDER BY n_chars) AS c FROM documents) GROUP BY n_chars")(lambda spark, sf_dir: fits.ecdf(load(spark, sf_dir, "documents"), "n_chars").select("value", F.round("share", 9).alias("share")))


@query("error_bound_table", f"SELECT node, CAST(n AS INT) AS k, m, round(sqrt(ln(2.0 * m / 0.05) / (2.0 * n)), 9) AS eps FROM {_users_sql(5)}, (SELECT CAST(unnest([10, 20, 64, 128]) AS INT) AS m)")
def _(spark, sf_dir):
    """Bounds if each group of users' events is the sample."""
    rows = [(r["node"], r["n"], m, round(sampling.error_bound(r["n"], m), 9)) for r in _users(spark, sf_dir, 5) for m in (10, 20, 64, 128)]
    return spark.createDataFrame(rows, "node int, k int, m int, eps double")


@query("sample_size_table", f"SELECT node, eps, m, CAST(ceil(ln(2.0 * m / 0.05) / (2 * eps * eps)) AS INT) AS k FROM (SELECT node, c / 10 AS eps FROM {_users_sql(5)} WHERE c > 0), (SELECT CAST(unnest([10, 20, 64, 128]) AS INT) AS m)")
def _(spark, sf_dir):
    """Sizes for an error of a tenth of each group's share of values below 50."""
    rows = [(r["node"], r["c"] / 10, m, sampling.sample_size(r["c"] / 10, m)) for r in _users(spark, sf_dir, 5) if r["c"] for m in (10, 20, 64, 128)]
    return spark.createDataFrame(rows, "node int, eps double, m int, k int")


@query("sampling_traffic", "SELECT k, nodes, CAST(k * (nodes - 1) AS BIGINT) AS distribution_aware, CAST(nodes * (nodes - 1) AS BIGINT) AS generative FROM (SELECT CAST(unnest([800, 3200]) AS INT) AS k), (SELECT CAST(unnest([6, 15]) AS INT) AS nodes)")
def _(spark, sf_dir):
    rows = [(k, n, t["distribution_aware"], t["generative"]) for k in (800, 3200) for n in (6, 15) for t in [sampling.sampling_traffic(k, n)]]
    return spark.createDataFrame(rows, "k int, nodes int, distribution_aware long, generative long")


# -- a fixed routing, which SQL can repeat -----------------------------------------------------------
_DELTA = 0.1
_CUTS = (0.35, 0.4, 0.35)


def fixed_plan(spark, sf_dir, replication: str = "both") -> tuple[DataFrame, JoinPlan]:
    """Axes are the two lowest ids; four cells by literal cuts."""
    objs = validate_objects(_narrow(spark, sf_dir), "id", "obj", metric_of("l1"))
    axes = [r["obj"] for r in objs.orderBy("id").limit(2).collect()]
    tree = Tree(np.array([0, 1, 1, -1, -1, -1, -1]), np.array([*_CUTS, 0, 0, 0, 0]), np.array([1, 3, 5, 0, 1, 2, 3]), np.array([2, 4, 6, -1, -1, -1, -1]), 4, 2)
    return objs, JoinPlan(metric_of("l1"), _DELTA, JoinConfig(bounds="cell", replication=replication), 0, 0, 4, 2, axes, tree, np.zeros((0, 2)))


_MAPPED = f"""WITH v AS MATERIALIZED ({w.SQL["prefix4"]}), a AS (SELECT row_number() OVER (ORDER BY id) AS k, obj FROM (SELECT * FROM v ORDER BY id LIMIT 2)),
 m AS MATERIALIZED (SELECT x.id, max(CASE WHEN k = 1 THEN d END) AS c1, max(CASE WHEN k = 2 THEN d END) AS c2 FROM (SELECT x.id, y.k, {w.DISTANCE_SQL["l1"]} AS d FROM v x, a y) x GROUP BY x.id),
 b(region, a1, b1, a2, b2) AS (VALUES (0, -1e300, {_CUTS[0]}, -1e300, {_CUTS[1]}), (1, -1e300, {_CUTS[0]}, {_CUTS[1]}, 1e300), (2, {_CUTS[0]}, 1e300, -1e300, {_CUTS[2]}), (3, {_CUTS[0]}, 1e300, {_CUTS[2]}, 1e300)),
 h AS (SELECT m.*, region AS home FROM m JOIN b ON c1 >= a1 AND c1 < b1 AND c2 >= a2 AND c2 < b2),
 r AS MATERIALIZED (SELECT b.region, h.home, h.id FROM h JOIN b ON c1 + {_DELTA} + 1e-9 >= a1 AND c1 - {_DELTA} - 1e-9 < b1 AND c2 + {_DELTA} + 1e-9 >= a2 AND c2 - {_DELTA} - 1e-9 < b2),
 s AS (SELECT region, count(*) FILTER (home = region) AS v, count(*) AS w FROM r GROUP BY region)"""


@query("map_space_fixed", f"{_MAPPED} SELECT id, round(c1, 6) AS c1, round(c2, 6) AS c2, CAST(home AS INT) AS home FROM h")
def _(spark, sf_dir):
    objs, plan = fixed_plan(spark, sf_dir)
    return mapped(objs, plan).select("id", F.round(F.col("coord")[0], 6).alias("c1"), F.round(F.col("coord")[1], 6).alias("c2"), "home")


def _routed(spark, sf_dir) -> DataFrame:
    return route(*fixed_plan(spark, sf_dir))


query("split_fixed_grid", f"{_MAPPED} SELECT CAST(region AS INT) AS region, CAST(home AS INT) AS home, id FROM r")(lambda spark, sf_dir: _routed(spark, sf_dir).select("region", "home", "id"))
query("kernel_sizes", f"{_MAPPED} SELECT CAST(region AS INT) AS region, v FROM s")(lambda spark, sf_dir: measures.region_sizes(_routed(spark, sf_dir)).select("region", "v"))
query("whole_sizes", f"{_MAPPED} SELECT CAST(region AS INT) AS region, w FROM s")(lambda spark, sf_dir: measures.region_sizes(_routed(spark, sf_dir)).select("region", "w"))
query("cost_all_pairs", f"{_MAPPED} SELECT CAST(sum(w * w) AS BIGINT) AS all_pairs FROM s")(lambda spark, sf_dir: measures.costs(_routed(spark, sf_dir)).select("all_pairs"))
query("cost_inner_outer", f"{_MAPPED} SELECT CAST(sum(v * v) AS BIGINT) AS inner_cost, CAST(sum(v * (w - v)) AS BIGINT) AS outer_cost FROM s")(lambda spark, sf_dir: measures.costs(_routed(spark, sf_dir)).select("inner_cost", "outer_cost"))
query("verification_count", f"{_MAPPED} SELECT CAST(region AS INT) AS region, CAST(v * (v - 1) // 2 + v * (w - v) AS BIGINT) AS verifications FROM s")(lambda spark, sf_dir: measures.region_costs(_routed(spark, sf_dir)).select("region", "verifications"))
_K4 = "v * (v - 1) // 2 + v * (w - v)"
query("partition_stats", f"{_MAPPED} SELECT count(*) AS regions, round(avg({_K4}), 6) AS mean, round(stddev_pop({_K4}), 6) AS stdev, round(stddev_pop({_K4}) / avg({_K4}), 6) AS cv, round(max({_K4}) / avg({_K4}), 6) AS max_over_mean FROM s")(
    lambda spark, sf_dir: measures.partition_stats(_routed(spark, sf_dir)).select("regions", *[F.round(c, 6).alias(c) for c in ("mean", "stdev", "cv", "max_over_mean")])
)
query("replication_factor", f"{_MAPPED} SELECT round(sum(w) / sum(v), 6) AS copies, CAST(sum(w) AS BIGINT) AS rows_moved FROM s")(lambda spark, sf_dir: measures.replication_factor(_routed(spark, sf_dir)).select(F.round("copies", 6).alias("copies"), "rows_moved"))
query("evenness", f"{_MAPPED} SELECT round(sum(v * v) * count(*) / pow(sum(v), 2), 6) AS ratio, round(pow(sum(v), 2) / count(*), 6) AS lower_bound FROM s")(lambda spark, sf_dir: measures.evenness(_routed(spark, sf_dir)).select(F.round("ratio", 6).alias("ratio"), F.round("lower_bound", 6).alias("lower_bound")))
_UNCOVERED = f"""{_MAPPED}, t AS (SELECT x.id AS i, y.id AS j FROM v x JOIN v y ON x.id < y.id AND {w.DISTANCE_SQL["l1"]} <= {_DELTA} + 1e-9),
 c AS (SELECT DISTINCT least(a.id, b.id) AS i, greatest(a.id, b.id) AS j FROM r a JOIN r b ON a.region = b.region AND a.home = a.region AND a.id <> b.id)
 SELECT count(*) AS uncovered FROM t ANTI JOIN c ON t.i = c.i AND t.j = c.j"""
query("uncovered_pairs", _UNCOVERED)(lambda spark, sf_dir: measures.uncovered_pairs(_routed(spark, sf_dir), metric_self_join(_narrow(spark, sf_dir), "id", "obj", "l1", _DELTA)).agg(F.count(F.lit(1)).alias("uncovered")))
query("colocation_count", f"{_MAPPED} SELECT n AS regions, count(*) AS pairs FROM (SELECT x.id AS i, y.id AS j, count(*) AS n FROM r x JOIN r y ON x.region = y.region AND x.id < y.id GROUP BY 1, 2) GROUP BY n")(
    lambda spark, sf_dir: measures.colocation_histogram(_routed(spark, sf_dir))
)


_PURITY = f"""{_MAPPED}, l AS (SELECT h.home AS region, label, count(*) AS n FROM h JOIN embeddings e ON e.vec_id = h.id GROUP BY 1, 2),
 t AS (SELECT region, sum(n) AS n, max(n) AS most, -sum(n * ln(n)) AS s FROM l GROUP BY region)
 SELECT CAST(region AS INT) AS region, CAST(n AS BIGINT) AS n, round(most / CAST(n AS DOUBLE), 6) AS purity, round(ln(n) + s / n, 6) AS entropy FROM t"""


@query("label_purity", _PURITY)
def _(spark, sf_dir):
    """By region, how far its home objects have one label."""
    labels = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "label")
    x = measures.label_purity(_routed(spark, sf_dir), labels)
    return x.select("region", "n", F.round("purity", 6).alias("purity"), F.round("entropy", 6).alias("entropy"))


@query("region_extent", f"{_MAPPED} SELECT CAST(home AS INT) AS region, round(max(c1) - min(c1), 6) AS extent1, round(max(c2) - min(c2), 6) AS extent2 FROM h GROUP BY home")
def _(spark, sf_dir):
    """How wide each region's home objects are along the axes: what its copies are counted around."""
    return measures.region_extent(_routed(spark, sf_dir), 2).select("region", *[F.round(f"extent{d}", 6).alias(f"extent{d}") for d in (1, 2)])


@query("error_bound_strata", f"SELECT CAST(sum(n) AS INT) AS k, m, round(sqrt(ln(2.0 * m / 0.05) / (2.0 * min(n))), 9) AS eps FROM {_users_sql(10)}, (SELECT CAST(unnest([10, 64]) AS INT) AS m) GROUP BY m")
def _(spark, sf_dir):
    """Of stratified samples the stratum with the fewest decides: ten groups of users and their events."""
    sizes = [r["n"] for r in _users(spark, sf_dir, 10)]
    return spark.createDataFrame([(sum(sizes), m, round(sampling.error_bound_local(sizes, m), 9)) for m in (10, 64)], "k int, m int, eps double")


@query("metric_axioms", "SELECT * FROM (VALUES ('abs1', 0), ('edit', 0), ('jaccard', 0), ('l1', 0), ('l2', 0), ('linf', 0)) AS t(metric, broken)")
def _(spark, sf_dir):
    """Axioms that fail on a sample of each kind of objects."""
    inputs = {"l1": w.descriptors, "l2": w.descriptors, "linf": w.descriptors, "edit": w.urls, "jaccard": w.conversation_sets, "abs1": lambda s, d: w.balances(s, d, "customer")}
    return spark.createDataFrame([(m, len(check_metric(m, f(spark, sf_dir), "obj"))) for m, f in inputs.items()], "metric string, broken int")


@query("pivot_box_recall")
def _(spark, sf_dir):
    """Recall of the published boxes around pivots, which lose pairs."""
    x = _narrow(spark, sf_dir)
    return measures.result_quality(metric_self_join(x, "id", "obj", "l1", _DELTA, JoinConfig(bounds="pivot_box", sampler="random")), brute_force_join(x, "id", "obj", "l1", _DELTA))


_CUT_SQL = "(SELECT label, CAST(embedding[1] AS DOUBLE) < 0.0 AS below FROM embeddings)"
_H = "(SELECT -sum(f * ln(f)) FROM (SELECT count(*) / CAST(sum(count(*)) OVER () AS DOUBLE) AS f FROM c {0} GROUP BY label))"
_GAIN = f"{_H.format('')} - (SELECT avg(CASE WHEN below THEN 1.0 ELSE 0 END) FROM c) * {_H.format('WHERE below')} - (SELECT avg(CASE WHEN below THEN 0.0 ELSE 1 END) FROM c) * {_H.format('WHERE NOT below')}"


def _label_counts(spark, sf_dir) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Labels, sides of a fixed cut, and how many rows of the whole table have both: a row for each label and side."""
    x = load(spark, sf_dir, "embeddings").groupBy("label", (F.col("embedding")[0].cast("double") < 0.0).alias("below")).agg(F.count(F.lit(1)).alias("n"))
    rows = x.orderBy("label", "below").collect()
    return np.array([r["label"] for r in rows]), np.array([r["below"] for r in rows], bool), np.array([r["n"] for r in rows], float)


def _measure(of, spark, sf_dir) -> float:
    """A measure of labels and sides from their counts."""
    labels, below, n = _label_counts(spark, sf_dir)
    return round(float(of(labels, below, n)), 6)


query("label_entropy", f"WITH c AS {_CUT_SQL} SELECT round({_H.format('')}, 6) AS cost")(lambda spark, sf_dir: spark.createDataFrame([(_measure(lambda labels, below, n: entropy(labels, n), spark, sf_dir),)], "cost double"))
query("split_gain", f"WITH c AS {_CUT_SQL} SELECT round({_GAIN}, 6) AS gain")(lambda spark, sf_dir: spark.createDataFrame([(_measure(split_gain, spark, sf_dir),)], "gain double"))
query("gain_ratio", f"WITH c AS {_CUT_SQL}, g AS (SELECT {_GAIN} AS gain, (SELECT -sum(f * ln(f)) FROM (SELECT count(*) / CAST(sum(count(*)) OVER () AS DOUBLE) AS f FROM c GROUP BY below)) AS own) SELECT round(gain / own, 6) AS ratio FROM g")(
    lambda spark, sf_dir: spark.createDataFrame([(_measure(gain_ratio, spark, sf_dir),)], "ratio double")
)

_SCALES = [("workers", 6, 7785.0), ("workers", 9, 5513.0), ("workers", 12, 4644.0), ("workers", 15, 4050.0), ("percent", 25, 201.0), ("percent", 50, 400.0), ("percent", 75, 565.0), ("percent", 100, 835.0)]
_values = lambda rows: ", ".join(str(r) for r in rows)


@query("gap_factor", "SELECT method, round(avg(r), 6) AS mean, round(median(r), 6) AS median, round(max(r), 6) AS most FROM (SELECT method, seconds / min(seconds) OVER (PARTITION BY workload) AS r FROM (SELECT o_orderpriority AS workload, o_orderstatus AS method, avg(o_totalprice) AS seconds FROM orders GROUP BY 1, 2)) GROUP BY method")
def _(spark, sf_dir):
    """Mean prices of orders stand for seconds: their priority is the workload, their status the method."""
    o = load(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("workload"), F.col("o_orderstatus").alias("method"))
    x = measures.gap_factor(o.agg(F.avg("o_totalprice").alias("seconds")))
    return x.select("method", *[F.round(c, 6).alias(c) for c in ("mean", "median", "most")])


@query("scaling_ratio", f"SELECT series, CAST(size AS INT) AS size, round(seconds / first(seconds) OVER w, 6) AS time_ratio, round(first(seconds) OVER w / seconds, 6) AS speed_up FROM (VALUES {_values(_SCALES)}) AS t(series, size, seconds) WINDOW w AS (PARTITION BY series ORDER BY size)")
def _(spark, sf_dir):
    x = measures.scaling_ratio(spark.createDataFrame(_SCALES, "series string, size int, seconds double"))
    return x.select("series", "size", F.round("time_ratio", 6).alias("time_ratio"), F.round("speed_up", 6).alias("speed_up"))


@query("verification_by_method")
def _(spark, sf_dir):
    """Verifications and balance of the combinations of samplers and splits on one workload (sf-sized, cell bounds)."""
    objs = validate_objects(_narrow(spark, sf_dir), "id", "obj", metric_of("l1"))
    out = []
    for s, t in (("random", "widest"), ("random", "iterative"), ("distribution_aware", "iterative"), ("generative", "iterative"), ("generative", "learned")):
        plan = make_plan(objs, metric_of("l1"), _DELTA, JoinConfig(sampler=s, splitter=t))
        r = measures.partition_stats(route(objs, plan)).first()
        out.append((s, t, r["regions"], r["mean"], r["stdev"], r["cv"]))
    return spark.createDataFrame(out, "sampler string, splitter string, regions long, mean double, stdev double, cv double")


_CC_SQL = f"""WITH RECURSIVE p AS ({w.set_join_sql("document_sets", None, 0.4)}), e AS (SELECT id_x AS a, id_y AS b FROM p UNION ALL SELECT id_y, id_x FROM p),
 r AS (SELECT DISTINCT a AS id, a AS c FROM e UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.id) SELECT id, min(c) AS component FROM r GROUP BY id"""


@query("use_document_clusters", _CC_SQL)
def _(spark, sf_dir):
    """Groups of near-duplicate documents: components of the join."""
    pairs, classes = join_classes(w.document_sets(spark, sf_dir), "id", "obj", "jaccard", 0.4)
    return connected_components(pairs.select("id_x", "id_y").unionByName(classes.where("id <> rep").select(F.col("rep").alias("id_x"), F.col("id").alias("id_y"))))


@query("use_user_lookalikes", f"WITH p AS ({w.self_join_sql('activity', 'l2', 7.0)}), e AS (SELECT id_x AS id, id_y AS other, distance FROM p UNION ALL SELECT id_y, id_x, distance FROM p) SELECT id, other, distance FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY distance, other) AS r FROM e) WHERE r <= 3")
def _(spark, sf_dir):
    """Up to three nearest users within the threshold."""
    from pyspark.sql.window import Window

    p = rounded(metric_self_join(w.activity(spark, sf_dir), "id", "obj", "l2", 7.0))
    e = p.select(F.col("id_x").alias("id"), F.col("id_y").alias("other"), "distance").unionByName(p.select(F.col("id_y").alias("id"), F.col("id_x").alias("other"), "distance"))
    return e.withColumn("r", F.row_number().over(Window.partitionBy("id").orderBy("distance", "other"))).where("r <= 3").drop("r")
