"""Operator 2: shards along a Hilbert curve through several metadata dimensions (built-in functions only)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import BROADCAST_ROWS, gapless_rank

SHARDS, BITS, SALT_BITS = 40, 4, 6


def hilbert_index(point: tuple[int, ...], bits: int) -> int:
    """Place of a grid point on the Hilbert curve (the published Gray-code transposition)."""
    x, n = list(point), len(point)
    for level in reversed(range(1, bits)):
        mask = (1 << level) - 1
        for i in range(n):
            if x[i] >> level & 1:
                x[0] ^= mask
            else:
                swap = (x[0] ^ x[i]) & mask
                x[0] ^= swap
                x[i] ^= swap
    for i in range(1, n):
        x[i] ^= x[i - 1]
    flip = 0
    for level in reversed(range(1, bits)):
        if x[-1] >> level & 1:
            flip ^= (1 << level) - 1
    return sum(((v ^ flip) >> b & 1) << (b * n + n - 1 - i) for i, v in enumerate(x) for b in range(bits))


def curve(dims: list[Column], bits: int = BITS) -> Column:
    """Curve index of integer coordinates below 2**bits; the table of the small grid is made here by the rule."""
    n = len(dims)
    cells = [tuple(c >> (bits * i) & ((1 << bits) - 1) for i in range(n)) for c in range(1 << bits * n)]
    lookup = F.split(F.lit(",".join(str(hilbert_index(c, bits)) for c in cells)), ",").cast("array<int>")
    cell = sum((d.cast("int") * (1 << bits * i) for i, d in enumerate(dims)), F.lit(0))
    return F.element_at(lookup, cell + 1)


def text_size(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 16


def shards(docs: DataFrame, n_shards: int = SHARDS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", size: Column | None = None) -> DataFrame:
    """One row per document: _row (all its columns), size, shard, slot; law ``rows``.

    Dimensions: the id scaled between its extremes, the binary logarithm of the size, and the
    source's rank in code point order. The order is (curve index, hash of id, size and source, id); its runs of
    equal row count are the shards, so counts are at most one apart and each shard covers few cells
    of the grid. A hot cell is dealt into 2**SALT_BITS parts by the hash, and places are counts of
    what lies before, so nothing is gathered.

    ``size`` replaces the size by the text, so that rows without texts can be dealt out.
    Null text has size 16; null ids and sources have coordinate 0; repeated rows get different
    slots; an empty table gives no rows.
    """
    size = text_size(docs[text_col]) if size is None else size
    x = docs.select(F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("_row"), docs[id_col].alias("_id"), docs[source_col].alias("_source"), size.alias("size"))
    top = (1 << BITS) - 1
    ends = x.agg(F.min("_id").alias("lo"), F.max("_id").alias("hi"), F.count(F.lit(1)).alias("n")).first()
    lo, span, n = (float(ends["lo"]), max(float(ends["hi"] - ends["lo"]), 1.0), ends["n"]) if ends["lo"] is not None else (0.0, 1.0, ends["n"])
    names = docs.select(docs[source_col].alias("_source")).where(F.col("_source").isNotNull()).distinct()
    n_sources = names.limit(BROADCAST_ROWS + 1).count()
    if n_sources <= BROADCAST_ROWS:
        ranks = names.select("_source", F.row_number().over(Window.orderBy("_source")).alias("_rank"))
        x = x.join(F.broadcast(ranks), "_source", "left")
        by_source = F.floor((F.coalesce("_rank", F.lit(1)) - 1) * (top + 1) / F.lit(max(n_sources, 1)))
    else:
        by_source = F.pmod(F.xxhash64("_source"), F.lit(top + 1))
    by_id = F.coalesce(F.floor((F.col("_id") - F.lit(lo)) / F.lit(span) * top), F.lit(0))
    by_size = F.least(F.greatest(F.floor(F.log2(F.col("size"))) - 4, F.lit(0)), F.lit(top))
    salt = F.pmod(F.xxhash64("_id", "size", "_source"), F.lit(1 << SALT_BITS))
    x = x.withColumn("_key", (curve([by_id, by_size, by_source]).cast("long") * (1 << SALT_BITS) + salt).cast("int"))
    ranked = gapless_rank(x, "_key", [F.col("_id").asc_nulls_first(), F.col("size")], "_place")
    shard = F.floor(F.col("_place") * n_shards / F.lit(max(n, 1)))
    first = F.ceil(shard * F.lit(max(n, 1)) / n_shards)
    return ranked.select("_row", "size", shard.cast("int").alias("shard"), (F.col("_place") - first).cast("long").alias("slot"))


def write_shards(docs: DataFrame, path: str, n_shards: int = SHARDS) -> None:
    """Write the documents as one folder of files per shard, in slot order."""
    x = shards(docs, n_shards)
    x.repartition(n_shards, "shard").sortWithinPartitions("shard", "slot").select("_row.*", F.col("shard").alias("_shard")).write.partitionBy("_shard").parquet(path)


def shard_boxes(docs: DataFrame, n_shards: int = SHARDS) -> DataFrame:
    """What a reader prunes by: the extremes of each dimension in each shard."""
    x = shards(docs, n_shards)
    ends = [f(c).alias(f"{f.__name__}_{a}") for c, a in (("_row.doc_id", "doc_id"), ("size", "size"), ("_row.source", "source")) for f in (F.min, F.max)]
    return x.groupBy("shard").agg(F.count(F.lit(1)).alias("rows"), *ends)


def op2(docs: DataFrame) -> DataFrame:
    """Null text has the checksum of the empty text, 0. Texts stay where they are: only their sizes and checksums move."""
    light = docs.select("doc_id", "source", text_size(F.col("text")).alias("_size"), F.coalesce(F.crc32("text"), F.lit(0)).cast("long").alias("_crc"))
    x = shards(light, size=F.col("_size"), text_col="doc_id")
    return x.select(F.col("_row.doc_id").alias("doc_id"), "size", F.col("_row._crc").alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
