"""The experiments' inputs on the given tables: (id, obj) each, and the same in SQL for the oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.filters import tokens
from .sources.io import load

PERIODS, PERIOD_DAYS = 4, 8


#: More event types than this are refused rather than dropped: each has columns of its own.
MOST_KINDS = 1000


def event_kinds(events: DataFrame) -> list[str]:
    """The event types in order."""
    kinds = [r[0] for r in events.select("event_type").distinct().orderBy("event_type").limit(MOST_KINDS + 1).collect()]
    if len(kinds) > MOST_KINDS:
        raise ValueError(f"more than {MOST_KINDS} event types")
    return kinds


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user the counts of each event type in each of four periods of eight days, the last one open: integer ratings' stand-in."""
    e = load(spark, sf_dir, "events").where(F.col("user_id").isNotNull())
    kinds = event_kinds(e)
    period = F.least(F.floor(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) / PERIOD_DAYS), F.lit(PERIODS - 1))
    x = e.select("user_id", "event_type", period.alias("p"))
    slots = [F.count_if((F.col("event_type") == k) & (F.col("p") == p)).cast("double").alias(f"s{i}_{p}") for i, k in enumerate(kinds) for p in range(PERIODS)]
    wide = x.groupBy(F.col("user_id").alias("id")).agg(*slots)
    return wide.select("id", F.array(*[f"s{i}_{p}" for i in range(len(kinds)) for p in range(PERIODS)]).alias("obj"))


def descriptors(spark: SparkSession, sf_dir: str, width: int | None = None, where: str | None = None) -> DataFrame:
    """Embeddings as doubles; ``width``: only so many leading entries."""
    e = load(spark, sf_dir, "embeddings")
    e = e.where(where) if where else e
    v = F.col("embedding").cast("array<double>")
    return e.select(F.col("vec_id").alias("id"), (F.slice(v, 1, width) if width else v).alias("obj"))


def urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.col("url").alias("obj"))


def names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct part names, numbered in their order (a few dozen rows)."""
    d = load(spark, sf_dir, "part").select(F.col("p_name").alias("obj")).distinct()
    return d.select(F.row_number().over(Window.orderBy("obj")).cast("long").alias("id"), "obj")


def document_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), tokens(F.col("text")).alias("obj"))


def benchmark_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("id"), tokens(F.col("text")).alias("obj"))


def conversation_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), tokens(F.col("text")).alias("obj"))


def line_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items shipped in one month as (quantity, discount, tax), in whole units; numbered within the order, so no global sort."""
    x = load(spark, sf_dir, "lineitem").where((F.col("l_shipdate") >= "1996-03-01") & (F.col("l_shipdate") < "1996-04-01"))
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    unit = [F.col("l_quantity").cast("double"), F.round(F.col("l_discount") * 100), F.round(F.col("l_tax") * 100)]
    return x.select((F.col("l_orderkey") * 1000 + F.row_number().over(w)).alias("id"), F.array(*unit).alias("obj"))


def balances(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    key, value = ("c_custkey", "c_acctbal") if table == "customer" else ("s_suppkey", "s_acctbal")
    return load(spark, sf_dir, table).select(F.col(key).alias("id"), F.col(value).cast("double").alias("obj"))


TOKENS_SQL = "list_distinct(list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda t: t <> ''))"
#: SQL of each input: (id, obj).
SQL = {
    "activity": """SELECT u.user_id AS id, list(CAST(coalesce(n, 0) AS DOUBLE) ORDER BY t.event_type, p.p) AS obj
        FROM (SELECT DISTINCT user_id FROM events) u CROSS JOIN (SELECT DISTINCT event_type FROM events) t CROSS JOIN (SELECT unnest([0, 1, 2, 3]) AS p) p
        LEFT JOIN (SELECT user_id, event_type, least(3, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) // 8) AS p, count(*) AS n FROM events GROUP BY ALL) c
        ON c.user_id = u.user_id AND c.event_type = t.event_type AND c.p = p.p GROUP BY u.user_id""",
    "descriptors": "SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS obj FROM embeddings",
    "prefix4": "SELECT vec_id AS id, CAST(embedding[1:4] AS DOUBLE[]) AS obj FROM embeddings",
    "urls": "SELECT page_id AS id, url AS obj FROM pages",
    "names": "SELECT row_number() OVER (ORDER BY p_name) AS id, p_name AS obj FROM (SELECT DISTINCT p_name FROM part)",
    "document_sets": f"SELECT doc_id AS id, {TOKENS_SQL} AS obj FROM documents",
    "benchmark_sets": f"SELECT item_id AS id, {TOKENS_SQL} AS obj FROM benchmark",
    "conversation_sets": f"SELECT conv_id * 1000 + turn AS id, {TOKENS_SQL} AS obj FROM conversations",
    "line_items": """SELECT l_orderkey * 1000 + row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS id,
        [CAST(l_quantity AS DOUBLE), round(l_discount * 100), round(l_tax * 100)] AS obj FROM lineitem WHERE l_shipdate >= '1996-03-01' AND l_shipdate < '1996-04-01'""",
}
DISTANCE_SQL = {
    "l1": "list_sum(list_transform(list_zip(x.obj, y.obj), lambda z: abs(z[1] - z[2])))",
    "l2": "list_distance(x.obj, y.obj)",
    "linf": "list_max(list_transform(list_zip(x.obj, y.obj), lambda z: abs(z[1] - z[2])))",
    "l3": "pow(list_sum(list_transform(list_zip(x.obj, y.obj), lambda z: pow(abs(z[1] - z[2]), 3))), 1.0 / 3)",
    "hamming": "list_sum(list_transform(list_zip(x.obj, y.obj), lambda z: CASE WHEN z[1] <> z[2] THEN 1.0 ELSE 0.0 END))",
    "angular": "acos(least(1.0, greatest(-1.0, list_cosine_similarity(x.obj, y.obj))))",
    "edit": "CAST(levenshtein(x.obj, y.obj) AS DOUBLE)",
    "abs1": "abs(x.obj - y.obj)",
}


def self_join_sql(source: str, distance: str, delta: float) -> str:
    d = DISTANCE_SQL[distance]
    return f"WITH v AS MATERIALIZED ({SQL.get(source, source)}) SELECT id_x, id_y, round(d, 6) AS distance FROM (SELECT x.id AS id_x, y.id AS id_y, {d} AS d FROM v x JOIN v y ON x.id < y.id) WHERE d <= {delta} + 1e-9"


def set_join_sql(left: str, right: str | None, delta: float) -> str:
    """Jaccard joins by counting common tokens (delta below 1; no set of the tables is empty)."""
    once = "a.id < b.id" if right is None else "true"
    return f"""WITH a AS MATERIALIZED ({SQL[left]}), b AS MATERIALIZED ({SQL[right or left]}),
      c AS (SELECT a.id AS id_x, b.id AS id_y, count(*) AS n, any_value(a.s) AS s, any_value(b.s) AS t
        FROM (SELECT id, len(obj) AS s, unnest(obj) AS tok FROM a) a JOIN (SELECT id, len(obj) AS s, unnest(obj) AS tok FROM b) b ON a.tok = b.tok AND {once} GROUP BY 1, 2)
      SELECT id_x, id_y, round(1.0 - n / CAST(s + t - n AS DOUBLE), 6) AS distance FROM c WHERE 1.0 - n / CAST(s + t - n AS DOUBLE) <= {delta} + 1e-9"""
