"""The training-data pipeline: toxicity, line dedup, near-duplicates, mixing, packing.

Of all stages: a row with a null text is kept like an empty one (it has no term, no line, no word, and one
token, the end), null sources are one source, null ids are no group; equal rows are treated alike; texts of any length count
whole; ties are broken by ids or hashes; an empty table gives an empty table; all columns are kept whatever their names.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pivotjoin.llm import line_dedup, mixing, packing, simhash, toxicity, word_shingles
from pivotjoin.llm.common import remove, shared_dir, table

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the lexicon, learned from the labelled ones, rejects go; null and empty texts stay, and without toxic labels all do."""
    return toxicity.accepted(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that too large a share of a source's documents have go; n_chars follows the text, and a null text stays null."""
    x = line_dedup.cleaned(docs)
    new = {"text": F.col("text"), "n_chars": F.length("text").cast(docs.schema["n_chars"].dataType)}
    return x.select(*[new.get(c, F.col(f"_row.`{c}`")).alias(c) for c in docs.columns])


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays whose sets of five-word shingles have a Jaccard similarity of 0.8 or more: that of the smallest id. Texts without words are one group.

    SimHash fingerprints and their inverted index on byte positions find the pairs, whole sets check them; bands add the similar pairs that differ in too many bits.
    """
    return simhash.drop_near_duplicates(docs, find=word_shingles.near_duplicates)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are brought to their target weights; repeated documents are repeated rows. Documents without words have no weight: they follow their source's repetitions."""
    return mixing.mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences (see packing.packed); a document without words is its end id alone."""
    return packing.packed(docs, packing.vocabulary())


STAGES: list[tuple[str, Stage]] = [("toxicity", drop_toxic), ("line_dedup", drop_lines), ("simhash", drop_copies), ("mixing", mix), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on documents; each one's result is written to the shared folder and read again, and goes when the next one's is written."""
    docs, before = table(spark, sf_dir, "documents"), None
    base = f"{shared_dir(spark)}/pipeline/{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{name}")
        docs = spark.read.parquet(f"{base}/{name}")
        if before:
            remove(spark, before)
        before = f"{base}/{name}"
    return docs


#: Toxicity, fingerprints and token ids are not in SQL's reach.
ORACLE_SQL = None
