"""Operator 5: pack token sequences by classes of reciprocal capacity."""

from __future__ import annotations

import json
import re
import zlib
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import gapless_rank, materialize, tidy

CAPACITY = 4096
#: The vocabulary file, and the id that ends a document.
VOCABULARY, END_ID = "word_bpe_49k.json", 2
#: A rest of at most so many tokens is not cut again.
SMALLEST_CUT = 128
#: Share of its place that a piece may leave empty instead of being cut.
SLACK = 1 / 64
#: Bytes that the words and ids kept by a task may take, in each of two generations; longer words are not kept.
KEPT_BYTES, LONGEST_KEPT = 32 << 20, 256
#: What a kept word takes beside its own bytes and those of its ids.
ENTRY_BYTES = 120
SALT_BITS = 6

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, class int, salt int"


def cut(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """Lengths of the pieces of a document of n tokens, with the class of each.

    Class k holds lengths between capacity/(k+1) and capacity/k: k of them fill a sequence. Whole
    sequences are cut off first; then, while the rest would leave much of its place empty, a piece
    of exactly capacity/(k+1) is cut off, which leaves less than capacity/k(k+1).
    """
    out = [(capacity, 1)] * (n // capacity)
    rest = n % capacity
    while rest:
        k = capacity // rest
        place = capacity // k
        if rest <= SMALLEST_CUT or place - rest <= SLACK * place:
            out.append((rest, k))
            break
        out.append((capacity // (k + 1), k + 1))
        rest -= capacity // (k + 1)
    return out


#: Signs that may follow a word's letters.
SIGNS = b".,;:!?#$%&*)]}\"-+=/|"
SIGN_BYTES = frozenset(SIGNS)
#: Words of Latin letters with or without such signs: their normal form is their lower case.
SIMPLE = re.compile(rb"(?<![^ ])(?:[A-Za-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+[" + re.escape(SIGNS) + rb"]*(?![^ ])")

TAIL = re.compile(rb"(?<=[A-Za-z\x80-\xbf])[" + re.escape(SIGNS) + rb"]+")
#: Bytes that byte-level vocabularies show as themselves; the others are shown by the letters from 256 on.
_SHOWN = [*range(33, 127), *range(161, 173), *range(174, 256)]
LETTER_BYTES = {chr(b): b for b in _SHOWN} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in _SHOWN)}
#: Ends a part of a word in the texts of ``merger``; no word holds it, since it is white space.
END = b"\n"


def merger(model: dict):
    """An encoder of the same merges over ranks of byte strings, or None where the vocabulary does not number its tokens in the order of its merges."""
    import tiktoken

    vocab, suffix = model["vocab"], model.get("end_of_word_suffix") or ""
    made = [vocab.get("".join(m if isinstance(m, list) else m.split(" "))) for m in model["merges"]]
    first = len(vocab) - len(made)
    if not suffix or made != list(range(first, len(vocab))) or any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges")):
        return None
    ranks: dict[bytes, int] = {}
    for token, i in vocab.items():
        ends = token.endswith(suffix) and token != suffix
        letters = token[: -len(suffix)] if ends else token
        if not all(c in LETTER_BYTES for c in letters):
            return None
        raw = bytes(LETTER_BYTES[c] for c in letters)
        if END in raw:
            continue  # white space, in no word
        if ranks.setdefault(raw + END * ends, i) != i:
            return None
    if any(bytes([b]) not in ranks or bytes([b]) + END not in ranks for b in range(256) if b != END[0]):
        return None
    ranks[END] = len(vocab)  # no result: it joins the byte before it first
    return tiktoken.Encoding("words", pat_str=r"[^\n]+\n", mergeable_ranks=ranks, special_tokens={})


class Words:
    """Ids of texts, word by word: no token of this vocabulary reaches over white space, so a word's ids can be kept.

    Two generations of KEPT_BYTES are kept: when the young one is full it becomes the old one, and
    words that occur again move over. ``forget`` drops both; a task does so at its end.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        self.tokenizer, self.merger = Tokenizer.from_file(path), merger(model)
        self.closing = np.zeros(len(model["vocab"]) + 1, bool)
        self.closing[[i for t, i in model["vocab"].items() if t.endswith("</w>")]] = True
        self.forget()

    def forget(self) -> None:
        self.young, self.old, self.size = {}, {}, 0

    def learned(self, words: set[bytes]) -> dict[bytes, bytes]:
        """Ids of words."""
        simple = SIMPLE.findall(b" ".join(words)) if self.merger else []
        found = self.encode_each(list(words.difference(simple)))
        for at in range(0, len(simple), 4096):
            found |= self.encode_joined(simple[at : at + 4096])
        return found

    def encode_each(self, words: list[bytes]) -> dict[bytes, bytes]:
        found = {}
        for at in range(0, len(words), 4096):
            part = words[at : at + 4096]
            made = self.tokenizer.encode_batch_fast([w.decode() for w in part], add_special_tokens=False)
            found.update((w, array("I", e.ids).tobytes()) for w, e in zip(part, made, strict=True))
        return found

    def encode_joined(self, words: list[bytes]) -> dict[bytes, bytes]:
        """Words of SIMPLE as one text, through the same merges without the slower patterns.

        Their letters are one part and the signs behind them another, and each part ends with the
        one token that closes it. Where the closing tokens are not as many as the parts, the whole
        tokenizer is asked.
        """
        parts = TAIL.sub(END + rb"\g<0>", END.join(words) + END).decode().lower()
        ids = self.merger.encode_to_numpy(parts, disallowed_special=()).astype("<u4")
        closings = np.flatnonzero(self.closing[ids]) + 1
        ends = np.cumsum([1 if w[-1] not in SIGN_BYTES else 2 for w in words])
        if len(closings) != ends[-1] or closings[-1] != len(ids):
            return self.encode_each(words)
        data, ends = ids.tobytes(), (closings[ends - 1] * 4).tolist()
        return dict(zip(words, [data[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)], strict=True))

    def ids(self, texts: list[bytes]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        split = [t.split() for t in texts]
        new = set().union(*split) - self.young.keys()
        again = new & self.old.keys()
        found = dict(zip(again, map(self.old.__getitem__, again), strict=True))
        found |= self.learned(new - again)
        self.young |= found
        out = [b"".join(map(self.young.__getitem__, words)) for words in split]
        for w, i in found.items():
            if len(w) > LONGEST_KEPT:
                del self.young[w]
            else:
                self.size += ENTRY_BYTES + len(w) + len(i)
        if self.size > KEPT_BYTES:
            self.young, self.old, self.size = {}, self.young, 0
        return out


_WORDS: dict[str, Words] = {}


def words_of(path: str) -> Words:
    """The worker's own tokenizer, kept from task to task; its words are not. (A task's function travels by value, with copies of the globals it names; this one is found by name.)"""
    if path not in _WORDS:
        _WORDS[path] = Words(path)
    return _WORDS[path]


#: Characters of texts that are looked up together.
TOGETHER = 1 << 21


def together(texts: Iterable[bytes]) -> Iterator[list[bytes]]:
    part, size = [], 0
    for t in texts:
        part.append(t)
        size += len(t)
        if size > TOGETHER:
            yield part
            part, size = [], 0
    if part:
        yield part


def tokenized_pieces(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        words, end, seen = words_of(path), np.array([END_ID], "<u4").tobytes(), 0
        try:
            for b in batches:
                rows = []
                texts = (t.as_py() or b"" for t in b.column(1).cast(pa.binary()))
                found = (ids for part in together(texts) for ids in words.ids(part))
                for doc, ids in zip(b.column(0).to_pylist(), found, strict=True):
                    ids, start, seen = ids + end, 0, seen + 1
                    for length, k in cut(len(ids) // 4):
                        rows.append((doc, start, length, zlib.crc32(ids[4 * start : 4 * (start + length)]), len(ids) // 4, k, (zlib.crc32(b"%d" % (doc or 0)) + start + seen * (doc is None)) % (1 << SALT_BITS)))
                        start += length
                if rows:
                    kinds = [pa.int64()] * 5 + [pa.int32()] * 2
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "class", "salt"])
        finally:
            words.forget()

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(tidy(run), PIECES)


def packed(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Each class fills its sequences with its fixed number of pieces, apart from the other classes
    and in many parts at once: a piece's place in its class is a count of what lies before. What
    is left of each class, fewer pieces than one sequence holds and so never more than some
    hundred thousand tokens in all, is packed first-fit by falling length in one task of that bounded size.

    Null and empty texts have the end id alone; null ids and repeated rows are packed as they are;
    an empty table gives no rows; texts of any length are cut.
    """
    pieces = materialize(tokenized_pieces(docs, path, id_col, text_col))
    keyed = pieces.withColumn("_key", F.col("class") * (1 << SALT_BITS) + F.col("salt"))
    ranked = gapless_rank(keyed, "_key", [F.col("doc_id").asc_nulls_first(), F.col("start"), F.col("ids_crc32")], "_rank")
    classes = pieces.groupBy("class").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.orderBy("class").rowsBetween(Window.unboundedPreceding, -1)  # at most CAPACITY rows
    full = F.floor(F.col("_n") / F.col("class"))
    classes = classes.select("class", full.alias("_full"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"), F.coalesce(F.sum(full).over(before), F.lit(0)).alias("_first"), F.sum(full).over(Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("_all"))
    classes = F.broadcast(materialize(classes))
    x = ranked.join(classes, "class").withColumn("_place", F.col("_rank") - F.col("_before"))
    x = x.withColumn("_bin", F.floor(F.col("_place") / F.col("class")))
    whole = x.where("_bin < _full").withColumn("sequence_id", F.col("_first") + F.col("_bin"))
    ahead = Window.partitionBy("sequence_id").orderBy("_place").rowsBetween(Window.unboundedPreceding, -1)
    columns = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    whole = whole.withColumn("offset", F.coalesce(F.sum("length").over(ahead), F.lit(0)).cast("long")).select(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [r for b in batches for r in zip(*[c.to_pylist() for c in b.columns], strict=True)]
        rows.sort(key=lambda r: (-r[2], r[0] is not None, r[0] or 0, r[1], r[3]))
        room: list[int] = []
        out, least = [], 0
        for r in rows:
            while least < len(room) and room[least] == 0:
                least += 1
            at = next((i for i in range(least, len(room)) if room[i] >= r[2]), len(room))
            if at == len(room):
                room.append(CAPACITY)
            out.append((*r[:5], r[5] + at, CAPACITY - room[at]))
            room[at] -= r[2]
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], columns)

    left = x.where("_bin >= _full").select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "_all").repartition(1)
    left = left.mapInArrow(run, ", ".join(f"`{c}` long" for c in columns))
    return whole.unionByName(left)


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def op5(docs: DataFrame) -> DataFrame:
    return packed(docs, vocabulary())
