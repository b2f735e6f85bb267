"""The registered queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import fingerprints, html_extract, langid, line_dedup, mixing, packing, sharding, simhash, topk, toxicity
from .common import table

Query = Callable[[SparkSession, str], DataFrame]


def _on(name: str, op: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, sf_dir: op(table(spark, sf_dir, name))


QUERIES: dict[str, Query] = {
    "op1_mixing": _on("documents", mixing.op1),
    "op2_hilbert_shards": _on("documents", sharding.op2),
    "op3_simhash": _on("documents", simhash.op3),
    "op4_improbable_features": _on("documents", fingerprints.op4),
    "op5_harmonic_packing": _on("documents", packing.op5),
    "op6_style_tree": _on("pages", html_extract.op6),
    "op7_line_frequency": _on("documents", line_dedup.op7),
    "op8_toxic_lexicon": lambda spark, sf_dir: toxicity.op8(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")),
    "op9_exact_top_k": _on("embeddings", topk.op9),
    "op10_compression_language": _on("documents", langid.op10),
}

ORACLES: dict[str, str] = {"op1_mixing": mixing.ORACLE, "op7_line_frequency": line_dedup.ORACLE, "op9_exact_top_k": topk.ORACLE}
