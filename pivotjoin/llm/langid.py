"""Operator 10: language by compression with a dictionary of each language."""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import materialize, tidy

#: Bounds of what is learned from: documents of each language, characters of each, bytes of a dictionary.
FIT_DOCS, FIT_CHARS, DICTIONARY_BYTES = 400, 2000, 1 << 16
#: More languages than this are refused rather than dropped.
MOST_LANGUAGES = 1000
#: Text is encoded in pieces of so many bytes, so that the dictionary counts in long texts too.
PIECE_BYTES = 1 << 13
LEVEL = 6
#: Share of its size by which the best must beat the second.
MARGIN = 0.02
UNKNOWN = "und"
LETTERS = re.compile(r"[^\W\d_]+")


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 5 == 0


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> dict[str, bytes]:
    """Raw dictionaries by language, from the FIT_DOCS distinct texts of each that have the lowest hashes, of documents that are not held out.

    Copies count once, so a language of few distinct texts is learned from all of them however
    often they are repeated. Null texts and languages teach nothing; ties of hashes go by the text;
    FIT_CHARS of a long text count; an empty table gives no dictionary.
    """
    x = docs.where(docs[lang_col].isNotNull() & docs[text_col].isNotNull() & ~held_out(docs[id_col]))
    x = x.select(docs[lang_col].alias("lang"), docs[text_col].alias("text"), F.xxhash64(docs[text_col]).alias("h"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy("h"))
    lowest = materialize(x.select("lang", "h").distinct().withColumn("r", place).where(F.col("r") <= FIT_DOCS).select("lang", "h"))
    if lowest.select("lang").distinct().count() > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    some = x.join(F.broadcast(lowest), ["lang", "h"])  # at most MOST_LANGUAGES times FIT_DOCS rows of a name and a number
    some = some.groupBy("lang", "h").agg(F.min(F.substring("text", 1, FIT_CHARS)).alias("text"))
    texts: dict[str, list[str]] = {}
    for r in some.orderBy("lang", "h").collect():  # bounded by MOST_LANGUAGES, FIT_DOCS and FIT_CHARS
        texts.setdefault(r["lang"], []).append(r["text"])
    return {lang: _content(t) for lang, t in texts.items()}


def letters(text: str) -> bytes:
    """The words of a text in lower case, without signs and digits, which belong to no language."""
    return " ".join(LETTERS.findall(text.lower())).encode()


def _content(texts: list[str]) -> bytes:
    return letters("\n".join(texts))[:DICTIONARY_BYTES]


class Coder:
    """Compressors of all languages, in the order of their names."""

    def __init__(self, dictionaries: dict[str, bytes], level: int = LEVEL):
        self.names, self.coders = sorted(dictionaries), []
        for name in self.names:
            d = zstandard.ZstdCompressionDict(dictionaries[name], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(level=level)
            self.coders.append(zstandard.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False))

    def sizes(self, data: bytes) -> list[int]:
        pieces = [data[i : i + PIECE_BYTES] for i in range(0, len(data), PIECE_BYTES)]
        return [sum(len(c.compress(p)) for p in pieces) for c in self.coders]

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """Language, score, and whether the margin is wide enough. Ties go to the first name."""
        data = letters(text or "")
        if not data or not self.names:
            return UNKNOWN, 0.0, False
        s = self.sizes(data)
        order = sorted(range(len(s)), key=lambda i: (s[i], i))
        best = order[0]
        if len(s) == 1:
            return self.names[0], 1.0, True
        margin = (s[order[1]] - s[best]) / max(s[order[1]], 1)
        # the share of the best if a percent of size counts as a factor of e
        score = 1 / sum(math.exp(-min(100 * (v - s[best]) / max(s[best], 1), 50.0)) for v in s)
        return self.names[best], score, margin >= MARGIN


def identified(docs: DataFrame, dictionaries: dict[str, bytes], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score, accepted) of whole texts; accepted is false where the margin is narrow or nothing is known.

    Null texts and texts without a letter are ``und`` with score 0; repeated rows get equal answers; an empty table gives no rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = Coder(dictionaries)
        for b in batches:
            found = [coder.predict(t.as_py()) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64()), pa.array([f[2] for f in found], pa.bool_())], ["doc_id", "lang_pred", "score", "accepted"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(tidy(run), "doc_id long, lang_pred string, score double, accepted boolean")


def op10(docs: DataFrame) -> DataFrame:
    return identified(docs, fit(docs)).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "accepted")
