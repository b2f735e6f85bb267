"""Operator 7: drop lines by their frequency within a site."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, small

#: A line that more than this share of a site's pages have, and at least so many, is boilerplate.
RATIO, LEAST_PAGES = 0.02, 5


def line_key(line: Column) -> Column:
    return F.xxhash64(F.trim(line))


def boilerplate(docs: DataFrame, ratio: float = RATIO, least_pages: int = LEAST_PAGES, text_col: str = "text", host_col: str = "source") -> DataFrame:
    """(host, line, pages, total): hashes of the lines that too large a share of their host's pages have.

    Pages are a host's distinct texts, so that copies of one page do not make its own lines
    boilerplate. Counts are summed before they are shuffled, and a key is a line, not a host.
    """
    pages = docs.select(docs[host_col].alias("host"), F.coalesce(docs[text_col], F.lit("")).alias("text")).withColumn("page", F.xxhash64("text"))
    total = pages.groupBy("host", "page").count().groupBy("host").agg(F.count(F.lit(1)).alias("total"))
    lines = pages.select("host", "page", F.explode(F.split("text", "\n")).alias("line")).where(F.trim("line") != "")
    lines = lines.select("host", "page", line_key(F.col("line")).alias("line")).distinct()
    counted = lines.groupBy("host", "line").agg(F.count(F.lit(1)).alias("pages")).where(F.col("pages") >= least_pages)
    both = counted.alias("l").join(small(materialize(total)).alias("t"), F.col("l.host").eqNullSafe(F.col("t.host")))
    return both.where(F.col("pages") > ratio * F.col("total")).select("l.host", "line", "pages", "total")


def cleaned(docs: DataFrame, ratio: float = RATIO, least_pages: int = LEAST_PAGES, text_col: str = "text", host_col: str = "source") -> DataFrame:
    """_row (all columns), text without boilerplate lines, lines, dropped.

    A host has at most (lines of a page / ratio) such lines, so its set is bounded; the sets are
    broadcast after a count, else joined. Blank lines stay; a null text stays null and has no
    lines; null hosts are one host; repeated rows are cleaned alike; a document can end up empty.
    """
    found = boilerplate(docs, ratio, least_pages, text_col, host_col).groupBy("host").agg(F.collect_set("line").alias("_gone"))
    found = small(materialize(found), 20_000)
    x = docs.select(F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("_row"), docs[host_col].alias("_host"), F.split(docs[text_col], "\n").alias("_lines"))
    x = x.alias("x").join(found.alias("f"), F.col("x._host").eqNullSafe(F.col("f.host")), "left")
    kept = F.when(F.col("_gone").isNull(), F.col("_lines")).otherwise(F.filter("_lines", lambda s: (F.trim(s) == "") | ~F.array_contains(F.col("_gone"), line_key(s))))
    x = x.select("_row", "_lines", kept.alias("_kept"))
    size = lambda c: F.when(F.col(c).isNull(), F.lit(0)).otherwise(F.size(c)).cast("long")
    return x.select("_row", F.array_join("_kept", "\n").alias("text"), size("_lines").alias("lines"), (size("_lines") - size("_kept")).alias("dropped"))


def op7(docs: DataFrame) -> DataFrame:
    light = docs.select("doc_id", "source", "text")
    return cleaned(light).select(F.col("_row.doc_id").alias("doc_id"), "lines", "dropped", "text")


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, source, text FROM documents),
p AS (SELECT DISTINCT source, coalesce(text, '') AS text FROM d),
t AS (SELECT source, count(*) AS total FROM p GROUP BY source),
l AS (SELECT DISTINCT source, text, trim(line) AS line FROM (SELECT source, text, unnest(string_split(text, chr(10))) AS line FROM p) WHERE trim(line) <> ''),
b AS (SELECT l.source, line FROM l JOIN t ON l.source IS NOT DISTINCT FROM t.source GROUP BY l.source, line, total HAVING count(*) >= 5 AND count(*) > 0.02 * total),
s AS (SELECT source, list(line) AS gone FROM b GROUP BY source)
SELECT doc_id, CAST(coalesce(len(string_split(text, chr(10))), 0) AS BIGINT) AS lines,
  CAST(coalesce(len(list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '' AND list_contains(coalesce(gone, []), trim(x)))), 0) AS BIGINT) AS dropped,
  array_to_string(list_filter(string_split(text, chr(10)), lambda x: trim(x) = '' OR NOT list_contains(coalesce(gone, []), trim(x))), chr(10)) AS text
FROM d LEFT JOIN s ON d.source IS NOT DISTINCT FROM s.source
"""
