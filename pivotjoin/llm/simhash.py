"""Operator 3: near-duplicates by SimHash with an inverted index on byte positions."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, small, tidy
from .graph import components

SHINGLE, SEED, DISTANCE = 3, 42, 3
#: Byte positions of a fingerprint; each differing bit spoils one of them at most.
POSITIONS = 8
LEAST_SHARED = POSITIONS - DISTANCE
#: Postings are kept by triples of positional bytes inside a half: five shared bytes put three into one half.
TRIPLES = [t for half in ((0, 1, 2, 3), (4, 5, 6, 7)) for t in combinations(half, 3)]
#: A posting list is compared in blocks of so many fingerprints.
BLOCK = 4096
#: Shingles that are counted at once, so that long texts need no more memory than short ones.
CHUNK = 1 << 16


def fingerprint(text: bytes | None) -> int:
    """The unsigned 64-bit SimHash of a text in UTF-8; 0 where it has no word."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    k = min(SHINGLE, len(words))
    starts, ends = starts[: len(words) - k + 1].tolist(), ends[k - 1 :].tolist()
    digest, ones = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    for at in range(0, len(starts), CHUNK):
        part = [digest(joined[a:b], SEED) for a, b in zip(starts[at : at + CHUNK], ends[at : at + CHUNK], strict=True)]
        ones += np.unpackbits(np.array(part, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(starts), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): fp holds the 64 bits as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).cast(pa.binary())
            found = np.fromiter((fingerprint(t.as_py()) for t in texts), np.uint64, len(texts)).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found)], ["doc_id", "fp"])

    light = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    return light.mapInArrow(tidy(run), "doc_id long, fp long")


def links(fps: np.ndarray, other: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Index pairs that join each cluster of one block (or of two, side by side) to a forest.

    For each row the shared bytes by position are tallied against the rest; pairs with the
    guaranteed number of matches are verified by their differing bits.
    """
    x = fps if other is None else np.concatenate([fps, other])
    parent = list(range(len(x)))

    def find(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    found = []
    for i in range(len(x) - 1 if other is None else len(fps)):
        rest = slice(i + 1, None) if other is None else slice(len(fps), None)
        diff = x[rest] ^ x[i]
        shared = (diff.view(np.uint8).reshape(-1, POSITIONS) == 0).sum(axis=1)
        near = np.flatnonzero(shared >= LEAST_SHARED)
        near = near[np.bitwise_count(diff[near]) <= DISTANCE]
        for j in (near + rest.start).tolist():
            if (a := find(i)) != (b := find(j)):
                parent[max(a, b)] = min(a, b)
                found.append((i, j))
    return found


def sorted_groups(batches: Iterator[pa.RecordBatch], n_keys: int) -> Iterator[np.ndarray]:
    """Rows of equal leading columns, from batches sorted by them, as 2-d arrays of long."""
    held = np.empty((0, 0), np.int64)
    for b in batches:
        rows = np.column_stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in b.columns])
        rows = np.concatenate([held, rows]) if held.size else rows
        if not len(rows):
            continue
        cuts = np.flatnonzero((rows[1:, :n_keys] != rows[:-1, :n_keys]).any(axis=1)) + 1
        parts = np.split(rows, cuts)
        yield from parts[:-1]
        held = parts[-1]
    if held.size:
        yield held


def near_links(distinct: DataFrame, block: int = BLOCK, rows: int | None = None) -> DataFrame:
    """(fp) distinct -> (u, v): links that connect what lies within DISTANCE bits, directly or through others.

    Postings: each fingerprint under eight triples of positional bytes. A pair that shares the
    guaranteed five bytes meets in one of them. A posting list is compared in one task as long as
    it has ``block`` rows; a longer one is dealt into blocks, and each pair of blocks goes to a task
    of its own. A task returns a forest, never all pairs of its list. ``rows``: a bound of the rows of ``distinct``, if known.
    """

    def byte(p: int) -> Column:
        return F.shiftrightunsigned("fp", 8 * p).bitwiseAND(F.lit(255))

    keys = [sum((byte(p) * F.lit(1 << 8 * j) for j, p in enumerate(t)), F.lit(i << 24)).cast("long") for i, t in enumerate(TRIPLES)]
    posted = distinct.select("fp", F.explode(F.array(*keys)).alias("key"))
    # written, so that a hot list is split in the join, as it is in the count
    lists = materialize(posted.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), rows and len(TRIPLES) * rows)
    posted = posted.join(lists, "key")
    parts = F.ceil(F.col("n") / block).cast("int")
    own = F.pmod(F.xxhash64("fp"), parts).cast("int")
    posted = posted.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), parts - 1)))
    posted = posted.select("key", F.least("own", "other").alias("a"), F.greatest("own", "other").alias("b"), "own", "fp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in sorted_groups(batches, 3):
            fps = np.ascontiguousarray(g[:, 4]).view(np.uint64)
            left = g[:, 3] == g[0, 1]
            both = g[0, 1] == g[0, 2]
            x = fps if both else np.concatenate([fps[left], fps[~left]])
            found = links(fps) if both else links(fps[left], fps[~left])
            if found:
                i, j = np.array(found).T
                yield pa.RecordBatch.from_arrays([pa.array(x[i].view(np.int64)), pa.array(x[j].view(np.int64))], ["u", "v"])

    dealt = posted.repartition("key", "a", "b").sortWithinPartitions("key", "a", "b")
    return dealt.mapInArrow(tidy(run), "u long, v long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """(doc_id, fp, component_id): every document with the smallest id it is linked to, directly or through others.

    Equal fingerprints are one node, so copies make no pairs. Texts without words (null, empty,
    white space) have fingerprint zero and are linked like any other; a null id stands in no other
    document's component (the smallest id counts known ids only) and its row is returned too;
    repeated rows share a component; texts of any length count whole; an empty table gives no rows.
    """
    prints = materialize(fingerprints(docs, id_col, text_col))
    n = prints.count()
    reps = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), n)
    # a list's forest has fewer links than rows
    roots = components(near_links(reps.select("fp"), block, n), len(TRIPLES) * n)
    nodes = roots.join(reps, F.col("node") == F.col("fp")).select("fp", "root", "least")
    tops = nodes.groupBy("root").agg(F.min("least").alias("component_id"))
    nodes = materialize(nodes.join(tops, "root").select("fp", "component_id"), n)
    classes = materialize(reps.join(nodes, "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id")), n)
    discard(reps, nodes)
    return prints.join(classes, "fp").select("doc_id", "fp", "component_id")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", find: Callable[..., DataFrame] = near_duplicates) -> DataFrame:
    """One document of each group that ``find`` makes stays, that with the smallest id; rows without an id stay."""
    found = materialize(find(docs, id_col, text_col))
    gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias("_gone")).distinct()
    kept = docs.join(small(gone), docs[id_col] == F.col("_gone"), "left_anti")
    again = materialize(found.where("doc_id = component_id").groupBy(F.col("doc_id").alias("_again")).count().where("count > 1").select("_again"))
    if not again.limit(1).count():
        return kept
    twice = kept.join(small(again), kept[id_col] == F.col("_again"), "left_semi").dropDuplicates([id_col])
    return kept.join(small(again), kept[id_col] == F.col("_again"), "left_anti").unionByName(twice)


def op3(docs: DataFrame) -> DataFrame:
    x = near_duplicates(docs)
    return x.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
