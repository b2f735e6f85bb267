"""Queries of the operators around a join: scans, joins of other kinds, aggregates, windows, functions, user functions, streams."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import workloads as w
from .operators.join import make_plan, metric_self_join
from .operators.tables import materialize, shared_dir
from .plans.config import JoinConfig
from .queries import QUERIES, query
from .sources import io
from .streaming import streams

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "conversations")


class _Tables:
    """Tables of a folder by name."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return io.load(self.spark, self.sf_dir, name)


def op(name: str, sql: str | None):
    def add(f):
        query(f"op_{name}", sql)(lambda spark, sf_dir: f(_Tables(spark, sf_dir)))
        return f

    return add


def same_text(name: str, sql: str) -> None:
    """A query whose SQL both engines take; {table} is the table's file in Spark."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(sql.format(**{t: f"parquet.`{sf_dir}/{t}.parquet`" for t in TABLES}))

    query(f"op_{name}", sql.format(**{t: t for t in TABLES}))(run)


r6 = lambda c: F.round(c, 6)

# -- scans, filters, joins -------------------------------------------------------------------------
op("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 49 AND l_returnflag = 'R'")(lambda t: t.lineitem.where("l_quantity > 49 AND l_returnflag = 'R'").select("l_orderkey", "l_quantity"))
op("filter_predicates", "SELECT p_partkey FROM part WHERE (p_size BETWEEN 10 AND 20 OR p_brand IN ('Brand#11', 'Brand#12')) AND p_type IS NOT NULL AND p_name LIKE '%a%'")(
    lambda t: t.part.where((F.col("p_size").between(10, 20) | F.col("p_brand").isin("Brand#11", "Brand#12")) & F.col("p_type").isNotNull() & F.col("p_name").like("%a%")).select("p_partkey")
)
op("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")(
    lambda t: t.customer.join(t.orders.where("o_orderpriority = '1-URGENT'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")
)
op("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")(lambda t: t.customer.join(t.orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))
op("join_outer", "SELECT coalesce(c_custkey, -1) AS c_custkey, coalesce(s_suppkey, -1) AS s_suppkey FROM (SELECT * FROM customer WHERE c_custkey < 60) FULL JOIN (SELECT * FROM supplier WHERE s_suppkey > 3) ON c_custkey = s_suppkey")(
    lambda t: t.customer.where("c_custkey < 60").join(t.supplier.where("s_suppkey > 3"), F.col("c_custkey") == F.col("s_suppkey"), "full").select(*[F.coalesce(c, F.lit(-1)).alias(c) for c in ("c_custkey", "s_suppkey")])
)
op("join_broadcast", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")(
    lambda t: t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))  # nations are 25 by definition
)
op("join_cross", "SELECT a.n_name AS a, b.r_name AS b FROM nation a CROSS JOIN region b")(lambda t: t.nation.select(F.col("n_name").alias("a")).crossJoin(t.region.select(F.col("r_name").alias("b"))))
op("join_theta", "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_acctbal < b.s_acctbal AND b.s_acctbal - a.s_acctbal < 20")(
    lambda t: t.supplier.select(F.col("s_suppkey").alias("a"), F.col("s_acctbal").alias("x")).join(t.supplier.select(F.col("s_suppkey").alias("b"), F.col("s_acctbal").alias("y")), F.expr("x < y AND y - x < 20")).select("a", "b")
)


@op("join_range", "WITH b(bin, lo, hi) AS (VALUES (0, -1000.0, 0.0), (1, 0.0, 2500.0), (2, 2500.0, 6000.0), (3, 6000.0, 1e9)) SELECT c_custkey, CAST(bin AS INT) AS bin FROM customer JOIN b ON c_acctbal >= lo AND c_acctbal < hi")
def _(t: _Tables) -> DataFrame:
    """Values and intervals: both sides get the coarse bins they touch, and an equi-join on the bin replaces the nested loop."""
    width = 1000.0
    b = t.spark.createDataFrame([(0, -1000.0, 0.0), (1, 0.0, 2500.0), (2, 2500.0, 6000.0), (3, 6000.0, 1e9)], "bin int, lo double, hi double")
    top = 20
    cells = F.sequence(F.greatest(F.floor(F.col("lo") / width), F.lit(-1)), F.least(F.floor(F.col("hi") / width), F.lit(top)))
    cell = F.greatest(F.least(F.floor(F.col("c_acctbal") / width), F.lit(top)), F.lit(-1)).alias("cell")
    return t.customer.select("c_custkey", "c_acctbal", cell).join(b.withColumn("cell", F.explode(cells)), "cell").where("c_acctbal >= lo AND c_acctbal < hi").select("c_custkey", "bin")


@op("join_asof", "SELECT a.event_id, coalesce(b.event_id, -1) AS before FROM (SELECT * FROM events WHERE event_type = 'purchase') a ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY 1, 2) b ON a.user_id = b.user_id AND a.ts >= b.ts")
def _(t: _Tables) -> DataFrame:
    """The last click at or before each purchase of a user: one union and one running window instead of a join."""
    e = t.events.where("event_type IN ('purchase', 'click')").select("user_id", "ts", "event_id", (F.col("event_type") == "purchase").cast("int").alias("p"))
    run = Window.partitionBy("user_id").orderBy("ts", "p", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.last(F.when(F.col("p") == 0, F.col("event_id")), ignorenulls=True).over(run)
    return e.withColumn("before", last).where("p = 1").select("event_id", F.coalesce("before", F.lit(-1)).alias("before"))


op("join_lateral", "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")(
    lambda t: t.customer.select("c_custkey").lateralJoin(t.orders.where(F.col("o_custkey") == F.col("c_custkey").outer()).select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2)).select("c_custkey", "o_orderkey")
)

# -- aggregates -----------------------------------------------------------------------------------
same_text("aggregate_moments", "SELECT event_type, count(*) AS n, round(avg(value), 6) AS mean, round(var_pop(value), 6) AS var, round(stddev_samp(value), 6) AS sd, round(covar_pop(value, user_id), 4) AS cov FROM {events} GROUP BY event_type")
op("aggregate_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")(lambda t: t.lineitem.rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")))
op("aggregate_cube", "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS q FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda t: t.lineitem.cube("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("q")))
same_text("aggregate_grouping_sets", "SELECT o_orderstatus, o_orderpriority, CAST(grouping(o_orderstatus) AS INT) AS g, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
op("aggregate_pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events WHERE event_type IN ('click', 'purchase') GROUP BY user_id")(
    lambda t: t.events.groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).na.fill(0).where("click + purchase > 0")
)
op("aggregate_distinct", "SELECT count(DISTINCT l_suppkey) AS s, count(DISTINCT l_partkey) AS p FROM lineitem")(lambda t: t.lineitem.agg(F.countDistinct("l_suppkey").alias("s"), F.countDistinct("l_partkey").alias("p")))
same_text("aggregate_filtered", "SELECT l_returnflag, count(*) FILTER (WHERE l_discount > 0.05) AS n, max(l_tax) FILTER (WHERE l_quantity < 5) AS m FROM {lineitem} GROUP BY l_returnflag")
op("aggregate_argmax", "SELECT c_nationkey, arg_max(c_custkey, c_acctbal) AS richest FROM customer GROUP BY c_nationkey")(lambda t: t.customer.groupBy("c_nationkey").agg(F.max_by("c_custkey", "c_acctbal").alias("richest")))
op("aggregate_quantile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type")(
    lambda t: t.events.groupBy("event_type").agg(r6(F.percentile("value", F.lit(0.5))).alias("median"), r6(F.percentile("value", F.lit(0.9))).alias("p90"))
)
op("aggregate_sketches", None)(lambda t: t.lineitem.agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5, 100).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers")))
op("aggregate_user", "SELECT label, round(sum(CAST(embedding[1] AS DOUBLE)), 5) AS s FROM embeddings GROUP BY label")(lambda t: _vector_sums(t))


def _vector_sums(t: _Tables) -> DataFrame:
    """A user aggregate of vectors: sums of each Arrow batch first, then of the batches."""
    from .operators.fits import vector_moments

    m = vector_moments(t.embeddings.select(F.col("label").alias("node"), F.slice(F.col("embedding").cast("array<double>"), 1, 1).alias("obj")))
    return m.select(F.col("node").alias("label"), F.round("x", 5).alias("s"))


# -- windows and sorts --------------------------------------------------------------------------------
same_text(
    "window_ranks",
    "SELECT s_suppkey, CAST(row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS BIGINT) AS rn, CAST(rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal) AS BIGINT) AS dr, "
    "CAST(ntile(3) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS BIGINT) AS nt, round(percent_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal), 6) AS pr, round(cume_dist() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal), 6) AS cd FROM {supplier}",
)
same_text(
    "window_analytic",
    "SELECT o_orderkey, lag(o_totalprice) OVER w AS before, lead(o_totalprice, 2) OVER w AS after2, first_value(o_totalprice) OVER w AS first, nth_value(o_totalprice, 2) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second "
    "FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
)
same_text(
    "window_frames",
    "SELECT c_custkey, round(sum(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_custkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS rows3, round(avg(c_acctbal) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING), 4) AS near FROM {customer}",
)
op("top_k", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20 OFFSET 5")(lambda t: t.lineitem.select("l_orderkey", "l_linenumber", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").offset(5).limit(20))
op("sort_in_partitions", "SELECT o_orderkey FROM orders")(lambda t: t.orders.repartition(4, "o_custkey").sortWithinPartitions("o_custkey", "o_orderkey").select("o_orderkey"))
same_text("set_operations", "SELECT k FROM ((SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier}) UNION (SELECT n_nationkey FROM {nation} EXCEPT SELECT c_nationkey FROM {customer})) u")
op("union_by_name", "SELECT c_custkey AS id, c_acctbal AS v FROM customer UNION ALL SELECT s_suppkey, s_acctbal FROM supplier")(
    lambda t: t.customer.select(F.col("c_custkey").alias("id"), F.col("c_acctbal").alias("v")).unionByName(t.supplier.select(F.col("s_acctbal").alias("v"), F.col("s_suppkey").alias("id")))
)

# -- functions -----------------------------------------------------------------------------------------
same_text("functions_string", "SELECT p_partkey, upper(trim(p_name)) AS u, CAST(length(p_name) AS BIGINT) AS l, substring(p_name, 2, 3) AS s, replace(p_name, ' ', '_') AS r, concat(p_brand, '-', p_type) AS c, md5(p_name) AS m FROM {part}")
same_text("functions_math", "SELECT s_suppkey, round(sqrt(abs(s_acctbal)), 6) AS q, CAST(ceil(s_acctbal) AS BIGINT) AS c, CAST(floor(s_acctbal) AS BIGINT) AS f, round(ln(abs(s_acctbal) + 1), 6) AS l, greatest(s_acctbal, 0) AS g, round(pow(s_suppkey, 1.5), 4) AS p FROM {supplier}")
op("functions_array", "SELECT vec_id, round(list_max(CAST(embedding AS DOUBLE[])), 6) AS mx, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda e: e * e)), 4) AS sq, len(list_filter(embedding, lambda e: e > 0)) AS pos FROM embeddings")(
    lambda t: t.embeddings.withColumn("e", F.col("embedding").cast("array<double>")).select("vec_id", r6(F.array_max("e")).alias("mx"), F.round(F.aggregate("e", F.lit(0.0), lambda a, v: a + v * v), 4).alias("sq"), F.size(F.filter("e", lambda v: v > 0)).cast("long").alias("pos"))
)
op("functions_map", "SELECT user_id, CAST(count(DISTINCT event_type) AS BIGINT) AS kinds, CAST(max(n) AS BIGINT) AS most FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY user_id")(
    lambda t: t.events.groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.array_max(F.map_values("m")).alias("most"))
)
op("functions_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")(lambda t: t.events.select("event_id", F.from_json("props", "k bigint")["k"].alias("k")))
op("functions_time", "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS d FROM orders")(
    lambda t: t.orders.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("d"))
)
same_text("functions_conditional", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'ok' END AS k, coalesce(nullif(c_mktsegment, 'BUILDING'), 'other') AS s FROM {customer}")


# -- user functions -------------------------------------------------------------------------------------
@op("udf_arrow", "SELECT s_suppkey, round(s_acctbal * 1.1, 4) AS v FROM supplier")
def _(t: _Tables) -> DataFrame:
    import pyarrow.compute as pc

    @F.arrow_udf("double")
    def more(v: pa.Array) -> pa.Array:
        return pc.multiply(v, 1.1)

    return t.supplier.select("s_suppkey", F.round(more("s_acctbal"), 4).alias("v"))


@op("udf_pandas_grouped", "SELECT c_nationkey, round(max(c_acctbal) - min(c_acctbal), 4) AS span FROM customer GROUP BY c_nationkey")
def _(t: _Tables) -> DataFrame:
    @F.pandas_udf("double")
    def span(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return t.customer.groupBy("c_nationkey").agg(F.round(span("c_acctbal"), 4).alias("span"))


@op("udf_map_batches", "SELECT page_id, length(url) AS n FROM pages")
def _(t: _Tables) -> DataFrame:
    def run(it):
        for pdf in it:
            yield pd.DataFrame({"page_id": pdf.page_id, "n": pdf.url.str.len()})

    return t.pages.select("page_id", "url").mapInPandas(run, "page_id long, n long")


@op("udtf", None)
def _(t: _Tables) -> DataFrame:
    """The regions near one point, asked in SQL."""
    objs = w.descriptors(t.spark, t.sf_dir, 4)
    plan = make_plan(objs, w_metric("l1"), 0.1, JoinConfig(bounds="cell"))
    io.register_region_probe(t.spark, plan)
    x = plan.metric.block([objs.orderBy("id").first()["obj"]], plan.axes)[0]
    return t.spark.sql(f"SELECT region, home FROM region_probe(array({', '.join(f'{float(v)!r}D' for v in x)}))")


def w_metric(name: str):
    from .functions.metrics import metric_of

    return metric_of(name)


# -- sources and sinks ------------------------------------------------------------------------------------
def _round_trip(fmt: str, schema: str | None = None):
    def run(t: _Tables) -> DataFrame:
        path = f"{io_dir(t.spark)}/{fmt}"
        t.nation.select("n_nationkey", "n_name").write.format(fmt).mode("overwrite").save(path)
        return io.load_format(t.spark, path, fmt, schema)

    return run


def io_dir(spark: SparkSession) -> str:
    from uuid import uuid4

    from .operators.tables import shared_dir

    return f"{shared_dir(spark)}/formats/{uuid4().hex}"


for _fmt in ("csv", "json", "orc", "parquet"):
    op(f"source_{_fmt}", "SELECT n_nationkey, n_name FROM nation")(_round_trip(_fmt, "n_nationkey int, n_name string"))


@op("sink_routed", w.self_join_sql("prefix4", "l1", 0.1))
def _(t: _Tables) -> DataFrame:
    """Routed objects kept by region, read again and verified."""
    from .operators.join import route, verify
    from .queries import rounded

    objs = w.descriptors(t.spark, t.sf_dir, 4)
    plan = make_plan(objs, w_metric("l1"), 0.1, JoinConfig())
    path = io_dir(t.spark)
    io.save_routed(route(objs, plan), path)
    return rounded(verify(t.spark.read.parquet(path), plan))


@op("nearest_neighbours", f"WITH p AS ({w.self_join_sql('prefix4', 'l1', 0.1)}), e AS (SELECT id_x AS id, id_y AS other, distance FROM p UNION ALL SELECT id_y, id_x, distance FROM p) SELECT id, other, distance FROM (SELECT *, row_number() OVER (PARTITION BY id ORDER BY distance, other) AS r FROM e) WHERE r = 1")
def _(t: _Tables) -> DataFrame:
    p = materialize(QUERIES["w2_prefix_l1"](t.spark, t.sf_dir))
    e = p.select(F.col("id_x").alias("id"), F.col("id_y").alias("other"), "distance").unionByName(p.select(F.col("id_y").alias("id"), F.col("id_x").alias("other"), "distance"))
    return e.groupBy("id").agg(F.min(F.struct("distance", "other")).alias("m")).select("id", F.col("m.other").alias("other"), F.col("m.distance").alias("distance"))


@op("join_with_equality", f"WITH v AS ({w.self_join_sql('SELECT c_custkey AS id, c_acctbal AS obj FROM customer', 'abs1', 1.0)}) SELECT id_x, id_y FROM v JOIN customer a ON a.c_custkey = id_x JOIN customer b ON b.c_custkey = id_y WHERE a.c_nationkey = b.c_nationkey")
def _(t: _Tables) -> DataFrame:
    """Close balances in one nation: the metric join, with an equality on the payload of both ends inside its regions."""
    return metric_self_join(t.customer, "c_custkey", "c_acctbal", "abs1", 1.0, by="c_nationkey").select("id_x", "id_y")


# -- streams, run to the end ----------------------------------------------------------------------------
def _drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """The stream's rows, from files in the shared folder: of all batches, or the last state in mode 'complete'. A batch that is run again writes the same file."""
    from uuid import uuid4

    spark, base = df.sparkSession, f"{shared_dir(df.sparkSession)}/streams/{uuid4().hex}"
    spark.createDataFrame([], df.schema).write.parquet(f"{base}/rows/none")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows/{'all' if mode == 'complete' else number}")

    writer = df.writeStream.foreachBatch(keep).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/state")
    writer.start().awaitTermination()  # without a limit: a table that is read before the end is partial
    return spark.read.schema(df.schema).parquet(f"{base}/rows/*")


def _stream(t: _Tables, name: str) -> DataFrame:
    batch = io.load(t.spark, t.sf_dir, name)
    # the folder is watched for the table's file or files
    return t.spark.readStream.schema(batch.schema).option("pathGlobFilter", f"{name}.parquet").parquet(t.sf_dir) if _one_file(t, name) else t.spark.readStream.schema(batch.schema).parquet(f"{t.sf_dir}/{name}.parquet")


def _one_file(t: _Tables, name: str) -> bool:
    jvm = t.spark._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{t.sf_dir}/{name}.parquet")
    return path.getFileSystem(t.spark._jsc.hadoopConfiguration()).getFileStatus(path).isFile()


def stream(name: str, sql: str | None):
    def add(f):
        query(f"stream_{name}", sql)(lambda spark, sf_dir: f(_Tables(spark, sf_dir)))
        return f

    return add


stream("tumbling", "SELECT CAST(epoch(time_bucket(INTERVAL 1 DAY, ts)) AS BIGINT) AS start, user_id, event_type, count(*) AS n FROM events GROUP BY ALL")(
    lambda t: _drained(streams.windowed_counts(_stream(t, "events"), "1 day"), "complete").select(F.unix_timestamp("start").alias("start"), "user_id", "event_type", "n")
)
stream("sliding", "SELECT CAST(epoch(time_bucket(INTERVAL 12 HOUR, ts)) - k * 43200 AS BIGINT) AS start, user_id, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS k) GROUP BY ALL")(
    lambda t: _drained(streams.windowed_counts(_stream(t, "events"), "1 day", "12 hours"), "complete").select(F.unix_timestamp("start").alias("start"), "user_id", "event_type", "n")
)
stream(
    "session",
    """WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
 s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, s""",
)(lambda t: _drained(streams.sessions(_stream(t, "events"), "6 hours"), "complete").select("user_id", F.unix_timestamp("start").alias("start"), "n"))
stream("dedup", "SELECT DISTINCT event_id FROM events")(lambda t: _drained(streams.deduplicated(_stream(t, "events"), ["event_id"], "3650 days")).select("event_id"))


@stream("static_join", f"WITH v AS ({w.SQL['prefix4']}) SELECT id_x, id_y, round(d, 6) AS distance FROM (SELECT x.id AS id_x, y.id AS id_y, {w.DISTANCE_SQL['l1']} AS d FROM v x JOIN v y ON x.id % 2 = 1 AND y.id % 2 = 0) WHERE d <= 0.1 + 1e-9")
def _(t: _Tables) -> DataFrame:
    """Odd ids arrive and are joined with the even ones."""
    corpus = w.descriptors(t.spark, t.sf_dir, 4).where("id % 2 = 0")
    plan = make_plan(corpus, w_metric("l1"), 0.1, JoinConfig(bounds="cell"))
    new = _stream(t, "embeddings").select(F.col("vec_id").alias("id"), F.slice(F.col("embedding").cast("array<double>"), 1, 4).alias("obj")).where("id % 2 = 1")
    return _drained(streams.stream_static_join(new, corpus, plan)).select("id_x", "id_y", F.round("distance", 6).alias("distance"))


@stream("stream_join", f"WITH v AS ({w.SQL['prefix4']}) SELECT id_x, id_y, round(d, 6) AS distance FROM (SELECT x.id AS id_x, y.id AS id_y, {w.DISTANCE_SQL['l1']} AS d FROM v x JOIN v y ON x.id % 2 = y.id % 2 AND abs(x.id - y.id) <= 30 AND x.id < y.id) WHERE d <= 0.2 + 1e-9")
def _(t: _Tables) -> DataFrame:
    """Objects of one kind that came within half an hour, a minute apart by id."""

    def objs() -> DataFrame:
        return _stream(t, "embeddings").select(F.col("vec_id").alias("id"), F.slice(F.col("embedding").cast("array<double>"), 1, 4).alias("obj"), F.timestamp_seconds(F.col("vec_id") * 60 + 86_400).alias("ts"), (F.col("vec_id") % 2).alias("event_type"))

    both = streams.stream_stream_join(objs(), objs(), "l1", 0.2, "30 minutes")
    return _drained(both.where("id_x < id_y")).select("id_x", "id_y", F.round("distance", 6).alias("distance"))
