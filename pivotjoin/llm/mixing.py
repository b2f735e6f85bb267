"""Operator 1: mix sources to target weights by capped water-filling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import hash32, materialize, small, word_count

WEIGHTS, SHARE, MAX_EPOCHS, SEED = (3, 1, 2), 1.5, 2.0, 17
#: The 32 bits of a document's place in its source are searched in two steps.
COARSE_BITS = 12


def water_fill(sources: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """(source, source_size) -> (source, source_size, target).

    Sources by code point, null last, take the weights in turn. ``share`` of all sizes is dealt by
    weight; a source stops at ``max_epochs`` times its size and the excess goes to the others by
    weight, again and again. Where that ends is found in one pass: in the order of cap by weight
    the full sources come first, and one water level holds for the rest. There is one row per
    source here, never one per document.
    """
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    upto = Window.orderBy("_fill", "_place").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    weigh = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.col("_place") - 1) % len(weights) + 1).cast("int"))
    x = sources.withColumn("_place", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())))
    x = x.withColumn("_weight", weigh).withColumn("_cap", F.lit(float(max_epochs)) * F.col("source_size"))
    x = x.withColumn("_fill", F.col("_cap") / F.col("_weight"))
    x = x.withColumn("_total", F.lit(float(share)) * F.sum("source_size").over(everything))
    x = x.withColumn("_caps", F.sum("_cap").over(upto) - F.col("_cap"))
    x = x.withColumn("_rest", F.sum("_weight").over(everything) - F.sum("_weight").over(upto) + F.col("_weight"))
    x = x.withColumn("_full", F.col("_fill") * F.col("_rest") <= F.col("_total") - F.col("_caps"))
    x = x.withColumn("_left", F.col("_total") - F.sum(F.when(F.col("_full"), F.col("_cap")).otherwise(0.0)).over(everything))
    x = x.withColumn("_open", F.sum(F.when(F.col("_full"), 0.0).otherwise(F.col("_weight"))).over(everything))
    level = F.when(F.col("_full"), F.col("_cap")).otherwise(F.least(F.col("_cap"), F.col("_left") * F.col("_weight") / F.col("_open")))
    return x.select("source", "source_size", level.alias("target"))


def mixture(docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, max_epochs: float = MAX_EPOCHS, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", size: Column | None = None) -> DataFrame:
    """One row per document: _row (all its columns), size, source_size, target, copies, taken.

    A source's target is so many whole repetitions and a fraction of one. Whole ones take every
    document; the fraction takes documents in the order of a seeded hash until half of the next
    would overshoot. The place where it stops is searched by histograms of the hash (the upper
    bits, then the lower bits inside one bucket), so no source is ever sorted or gathered.

    Null text has size 0; null sources form one source, the last; repeated rows and rows of equal
    hash are taken or left together; an empty table gives no rows; a source of size 0 has target 0
    and takes none. ``size`` replaces the word count of the text. All columns are kept in _row, so their names cannot clash.
    """
    x = docs.select(
        F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("_row"), docs[source_col].alias("source"), (word_count(docs[text_col]) if size is None else size).alias("size"), hash32(seed, docs[id_col]).alias("_h")
    )
    light = materialize(x.select("source", "size", "_h"))  # words are counted once
    low = 32 - COARSE_BITS
    coarse = materialize(light.groupBy("source", F.shiftright("_h", low).alias("_b")).agg(F.sum("size").alias("_s")))
    plan = water_fill(coarse.groupBy("source").agg(F.sum("_s").alias("source_size")), weights, share, max_epochs)
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    plan = plan.withColumn("_whole", F.floor(ratio)).withColumn("_need", (ratio - F.floor(ratio)) * F.col("source_size"))
    plan = small(materialize(plan))

    def crossing(steps: DataFrame, place: str, before) -> DataFrame:
        """The first place, by source, at which the running size passes what is needed."""
        run = F.sum("_s").over(Window.partitionBy("source").orderBy(place).rowsBetween(Window.unboundedPreceding, Window.currentRow))
        found = steps.withColumn("_run", run + before)
        return found.where(F.col("_run") > F.col("_need")).groupBy("source").agg(F.min(F.struct(place, (F.col("_run") - F.col("_s")).alias("_before"), "_s", "_need")).alias("_at"))

    same = lambda a, b: a["source"].eqNullSafe(b["source"])
    joined = lambda a, b, how="inner": a.alias("a").join(b.alias("b"), F.col("a.source").eqNullSafe(F.col("b.source")), how)
    at = joined(coarse, plan).select("a.source", "_b", "_s", "_need")
    bucket = crossing(at, "_b", F.lit(0)).select("source", F.col("_at._b").alias("_bucket"), F.col("_at._before").alias("_pre"))
    bucket = small(materialize(bucket))
    fine = joined(light, bucket).where(F.shiftright("_h", low) == F.col("_bucket")).groupBy(F.col("a.source").alias("source"), "_h").agg(F.sum("size").alias("_s"), F.first("_pre").alias("_pre"))
    fine = joined(fine, plan).select("a.source", "_h", "_s", "_pre", "_need")
    stop = crossing(fine, "_h", F.col("_pre")).select("source", F.when(F.col("_at._before") + F.col("_at._s") / 2 <= F.col("_at._need"), F.col("_at._h")).otherwise(F.col("_at._h") - 1).alias("_stop"))
    plan = joined(plan, stop, "left").select("a.*", F.coalesce("_stop", F.lit(-1)).alias("_stop"))
    plan = small(materialize(plan))
    out = joined(x, plan)
    extra = ((F.col("_need") > 0) & (F.col("_h") <= F.col("_stop"))).cast("int")
    out = out.withColumn("copies", (F.col("_whole") + extra).cast("int"))
    return out.select("_row", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The documents of the mix, as many rows of each as it is repeated."""
    plan = mixture(docs, **options).where("copies > 0")
    return plan.select("_row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("_row.*")


def op1(docs: DataFrame) -> DataFrame:
    light = materialize(docs.select("doc_id", "source", word_count(docs["text"]).alias("_size")))
    return mixture(light, size=light["_size"]).select(F.col("_row.doc_id").alias("doc_id"), "size", "source_size", "target", "taken", "copies")


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         CAST('0x' || substr(md5('17|' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 8) AS BIGINT) AS h
  FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
p AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) AS place FROM s),
w AS (SELECT *, CAST([3.0, 1.0, 2.0][CAST((place - 1) % 3 + 1 AS BIGINT)] AS DOUBLE) AS weight, 2.0::DOUBLE * source_size AS cap, 1.5::DOUBLE * sum(source_size) OVER () AS total FROM p),
c AS (SELECT *, cap / weight AS fill, sum(cap) OVER (ORDER BY cap / weight, place ROWS UNBOUNDED PRECEDING) - cap AS caps,
        sum(weight) OVER () - sum(weight) OVER (ORDER BY cap / weight, place ROWS UNBOUNDED PRECEDING) + weight AS rest FROM w),
f AS (SELECT *, fill * rest <= total - caps AS is_full FROM c),
t AS (SELECT source, source_size, CASE WHEN is_full THEN cap ELSE least(cap,
        (total - sum(CASE WHEN is_full THEN cap ELSE 0 END) OVER ()) * weight / sum(CASE WHEN is_full THEN 0 ELSE weight END) OVER ()) END AS target FROM f),
r AS (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS ratio FROM t),
n AS (SELECT *, floor(ratio) AS whole, (ratio - floor(ratio)) * source_size AS need FROM r),
g AS (SELECT source, h, sum(size) AS s FROM d GROUP BY source, h),
k AS (SELECT g.*, sum(s) OVER (PARTITION BY source ORDER BY h ROWS UNBOUNDED PRECEDING) AS run FROM g),
m AS (SELECT k.source, k.h, n.need > 0 AND (k.run <= n.need OR (k.run - k.s / 2 <= n.need)) AS extra FROM k JOIN n ON k.source IS NOT DISTINCT FROM n.source)
SELECT d.doc_id, d.size, n.source_size, n.target, CAST((n.whole + CAST(m.extra AS INT)) * d.size AS BIGINT) AS taken, CAST(n.whole + CAST(m.extra AS INT) AS INT) AS copies
FROM d JOIN n ON d.source IS NOT DISTINCT FROM n.source JOIN m ON m.source IS NOT DISTINCT FROM d.source AND m.h = d.h
"""
