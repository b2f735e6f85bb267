"""Operator 4: similarity digests of statistically improbable features in chained Bloom filters."""

from __future__ import annotations

import hashlib
from base64 import b64decode, b64encode
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import tidy

#: Bytes of a feature, and feature places among which the rarest gets a point.
WINDOW = 64
#: Points that select a feature; a longer text without such a feature gives its best one.
LEAST_POINTS = 16
#: Steps of the entropy scale between 0 and the most that a window can have.
STEPS = 1000
#: In texts of fewer bytes each window that is the rarest among so few neighbours is selected.
SHORT, SHORT_NEIGHBOURS = 256, 8
#: Of texts below so many bytes every window of TINY_WINDOW bytes is a feature.
TINY, TINY_WINDOW = 128, 16
#: Entropies that carry nothing: runs of few bytes, and noise.
LOW, HIGH = 100, 990
FILTER_BITS, FILTER_FEATURES, HASHES = 2048, 160, 5
#: Bytes that are worked on at once.
BATCH = 1 << 18
#: Bytes of texts in a range of documents that one task sorts.
RANGE_BYTES = 1 << 28
#: Fixed-point scale, so that sums of entropy terms are exact in any order.
SCALE = 1 << 32

_C = np.arange(WINDOW + 2, dtype=np.float64)
_TERM = np.round(np.where(_C > 0, _C * np.log2(np.maximum(_C, 1)), 0) * SCALE).astype(np.int64)
#: What the k-th equal byte of a window adds to the sum of c log c.
_ADDED = np.concatenate(([0], np.diff(_TERM)))
_TOP = int(_TERM[WINDOW])


def window_entropy(x: np.ndarray) -> np.ndarray:
    """Entropy, on the scale 0..STEPS, of each window of x (bytes).

    Only the count of the byte that leaves and of the byte that enters change a window's sum, and
    both come from comparing x with itself at 63 shifts.
    """
    n = len(x) - WINDOW + 1
    if n <= 0:
        return np.empty(0, np.int64)
    ahead, behind = np.zeros(len(x), np.uint8), np.zeros(len(x), np.uint8)
    for k in range(1, WINDOW):
        same = (x[k:] == x[:-k]).view(np.uint8)
        ahead[: len(x) - k] += same
        behind[k:] += same
    first = int(_TERM[np.bincount(x[:WINDOW], minlength=256)].sum())
    change = _ADDED[behind[WINDOW:].astype(np.intp) + 1] - _ADDED[ahead[: n - 1].astype(np.intp) + 1]
    total = first + np.concatenate(([0], np.cumsum(change)))
    return (_TOP - total) * STEPS // _TOP


def batches_of(texts: list[bytes]) -> Iterator[tuple[list[int], np.ndarray, np.ndarray]]:
    """Texts together up to BATCH bytes (a longer one alone): their places, the bytes, their bounds."""
    at, size = [], 0
    for i, t in enumerate(texts):
        if at and size + len(t) > BATCH:
            yield at, *_joined(texts, at)
            at, size = [], 0
        at.append(i)
        size += len(t)
    if at:
        yield at, *_joined(texts, at)


def _joined(texts: list[bytes], at: list[int]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(texts[i] for i in at), np.uint8), np.concatenate(([0], np.cumsum([len(texts[i]) for i in at])))


def entropy_counts(texts: list[bytes]) -> np.ndarray:
    """How many windows of the texts have each entropy."""
    counts = np.zeros(STEPS + 1, np.int64)
    for _, x, ends in batches_of(texts):
        h = window_entropy(x)
        inside = np.zeros(len(x) + 1, np.int64)
        for a, b in zip(ends[:-1], ends[1:], strict=True):
            if b - a >= WINDOW:
                inside[a] += 1
                inside[b - WINDOW + 1] -= 1
        counts += np.bincount(h[np.cumsum(inside)[: len(h)] > 0], minlength=STEPS + 1)
    return counts


def ranks(counts: np.ndarray) -> np.ndarray:
    """Rank of each entropy by rarity, 1 the rarest; entropies that carry nothing rank behind all."""
    order = np.lexsort((np.arange(STEPS + 1), counts))
    out = np.empty(STEPS + 1, np.int64)
    out[order] = np.arange(1, STEPS + 2)
    out[:LOW] = out[HIGH:] = STEPS + 2
    return out


def _features(x: np.ndarray, ends: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the selected windows of all texts of a batch, and the text of each, in order."""
    h = window_entropy(x)
    n = len(h)
    key = (rank[h] << 32) + np.arange(n)
    best = key.copy()
    step = 1
    while step < WINDOW:  # the least of 64 neighbours, by doubling
        best[: n - step] = np.minimum(best[: n - step], best[step:])
        step *= 2
    starts, owners = [], []
    for t, (a, b) in enumerate(zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)):
        last = b - WINDOW + 1  # one past the last window of the text
        if b - a < TINY:
            continue
        if b - a < SHORT:
            near = np.lib.stride_tricks.sliding_window_view(key[a:last], min(SHORT_NEIGHBOURS, last - a))
            chosen = np.unique(near.min(axis=1) & 0xFFFFFFFF)
            starts.append(chosen)
            owners.append(np.full(len(chosen), t))
            continue
        rows = last - a - WINDOW + 1
        won = best[a : a + rows] if rows > 0 else key[a:last].min(keepdims=True)
        local = np.bincount((won & 0xFFFFFFFF) - a, minlength=last - a)
        local[rank[h[a:last]] > STEPS + 1] = 0
        chosen = np.flatnonzero(local >= LEAST_POINTS)
        if not len(chosen):
            chosen = np.array([local.argmax()])
        starts.append(chosen + a)
        owners.append(np.full(len(chosen), t))
    empty = np.empty(0, np.int64)
    return (np.concatenate(starts), np.concatenate(owners)) if starts else (empty, empty)


def _mix(v: np.ndarray) -> np.ndarray:
    v ^= v >> np.uint64(33)
    v *= np.uint64(0xFF51AFD7ED558CCD)
    v ^= v >> np.uint64(33)
    v *= np.uint64(0xC4CEB9FE1A85EC53)
    return v ^ v >> np.uint64(33)


def _bits(windows: np.ndarray) -> np.ndarray:
    """HASHES bit places of each feature (rows of 64 bytes)."""
    words = np.ascontiguousarray(windows).view("<u8")
    h = np.zeros(len(words), np.uint64)
    for i in range(words.shape[1]):
        h = _mix((h ^ words[:, i]) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(i + 1))
    return np.stack([(h >> np.uint64(11 * i)).astype(np.int64) & (FILTER_BITS - 1) for i in range(HASHES)], axis=1)


Digest = np.ndarray  # filters x FILTER_BITS / 8 bytes


def digests(texts: list[bytes], rank: np.ndarray) -> list[Digest]:
    """The filters of each text; an empty one has none. Tiny texts are cut into all their small windows, filled up with zero bytes."""
    out: list[Digest] = [np.zeros((0, FILTER_BITS // 8), np.uint8)] * len(texts)
    for at, x, ends in batches_of(texts):
        starts, owners = _features(x, ends, rank)
        rows = x[starts[:, None] + np.arange(WINDOW)] if len(starts) else np.empty((0, WINDOW), np.uint8)
        tiny = [(i, x[k : min(k + TINY_WINDOW, b)]) for i, (a, b) in enumerate(zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)) if 0 < b - a < TINY for k in range(a, max(b - TINY_WINDOW, a) + 1)]
        if tiny:
            rows = np.concatenate([rows, [np.pad(w, (0, WINDOW - len(w))) for _, w in tiny]])
            owners = np.concatenate([owners, [i for i, _ in tiny]]).astype(np.int64)
        if not len(rows):
            continue
        order = np.argsort(owners, kind="stable")
        rows, owners = rows[order], owners[order]
        counts = np.bincount(owners, minlength=len(at))
        place = np.arange(len(owners)) - (np.cumsum(counts) - counts)[owners]
        chain = -(-counts // FILTER_FEATURES)
        base = np.cumsum(chain) - chain
        filters = np.zeros((int(chain.sum()), FILTER_BITS), bool)
        filters[(base[owners] + place // FILTER_FEATURES)[:, None], _bits(rows)] = True
        packed = np.packbits(filters, axis=1)
        for i, t in enumerate(at):
            out[t] = packed[base[i] : base[i] + chain[i]]
    return out


def likeness(a: Digest, b: Digest) -> float:
    """0 to 1: for each filter of the shorter chain the best match in the other, averaged.

    A match is the overlap of set bits above what two unrelated filters of these sizes share,
    over the most they could share above it. Two empty digests are alike; an empty one and another are not.
    """
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    if len(a) > len(b) or (len(a) == len(b) and a.tobytes() > b.tobytes()):
        a, b = b, a
    wa, wb = a.view("<u8"), b.view("<u8")
    ea, eb = np.bitwise_count(wa).sum(1, dtype=np.int64), np.bitwise_count(wb).sum(1, dtype=np.int64)
    total = 0.0
    for i in range(len(a)):
        both = np.bitwise_count(wb & wa[i]).sum(1, dtype=np.int64)
        most = np.minimum(eb, ea[i])
        # chance: the expected overlap and three deviations of it
        chance = ea[i] * eb / FILTER_BITS
        floor = np.minimum(chance + 3 * np.sqrt(chance * (1 - np.maximum(ea[i], eb) / FILTER_BITS)), most - 1)
        total += float(np.clip((both - floor) / (most - floor), 0, 1).max())
    return total / len(a)


def encode(d: Digest) -> str:
    return b64encode(d.tobytes()).decode()


def decode(s: str) -> Digest:
    return np.frombuffer(b64decode(s), np.uint8).reshape(-1, FILTER_BITS // 8)


def fit_ranks(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """Rarity ranks from the windows of all texts; what comes to the driver is STEPS + 1 counts a task, summed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(STEPS + 1, np.int64)
        for b in batches:
            counts += entropy_counts([t.as_py() or b"" for t in b.column(0).cast(pa.binary())])
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(counts)), pa.array(counts[counts > 0])], ["step", "n"])

    found = docs.select(docs[text_col].alias("text")).mapInArrow(tidy(run), "step long, n long").groupBy("step").agg(F.sum("n").alias("n")).collect()
    counts = np.zeros(STEPS + 1, np.int64)
    for r in found:
        counts[r["step"]] = r["n"]
    return ranks(counts)


def fingerprints(docs: DataFrame, rank: np.ndarray, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fingerprint) of whole texts; equal texts have equal fingerprints; null counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = digests([t.as_py() or b"" for t in b.column(1).cast(pa.binary())], rank)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([encode(d) for d in found])], ["doc_id", "fingerprint"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(tidy(run), "doc_id long, fingerprint string")


EDITED = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _edited(rows: list[tuple[int, str]], after: tuple[int, str], rank: np.ndarray) -> pa.RecordBatch:
    """rows: documents in order; after: the one that follows the last."""
    texts = [t for _, t in rows]
    nexts = [*texts[1:], after[1]]
    edited = []
    for t, u in zip(texts, nexts, strict=True):
        k = len(t) // 4
        edited.append(t[: len(t) - k] + u[:k])
    own = digests([t.encode() for t in [*texts, after[1]]], rank)
    new = digests([t.encode() for t in edited], rank)
    return pa.RecordBatch.from_arrays(
        [
            pa.array([i for i, _ in rows], pa.int64()), pa.array([len(t) for t in texts], pa.int64()), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in edited]),
            pa.array([encode(d) for d in own[:-1]]), pa.array([encode(d) for d in new]), pa.array([likeness(a, b) for a, b in zip(own[:-1], new, strict=True)]), pa.array([likeness(a, b) for a, b in zip(own[:-1], own[1:], strict=True)]),
        ],
        [c.split()[0] for c in EDITED.split(", ")],
    )


def edited_pairs(docs: DataFrame, rank: np.ndarray, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each document, its edited text and their likeness (schema EDITED).

    Documents move once, into ranges of the id; the first one of a range goes to the range before
    too, so each range knows what follows its last document. The bounds of the ranges are ids of
    the table; there are as many as shuffle partitions, and more where these would hold above RANGE_BYTES in the mean. Null ids come first; rows of equal id follow one another in the order of their
    texts; the only row of a table is its own successor; an empty table gives no rows.
    """
    spark = docs.sparkSession
    light = docs.select(docs[id_col].cast("long").alias("id"), F.coalesce(docs[text_col], F.lit("")).alias("text"))
    size = light.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // RANGE_BYTES))
    least = -(1 << 63)
    ids = light.select(F.coalesce("id", F.lit(least)).alias("key"))
    got = ids.agg(F.min("key").alias("first"), F.percentile_approx("key", [i / parts for i in range(1, parts)] or [0.5], 10 * parts).alias("cuts")).first()
    if got["first"] is None:
        return spark.createDataFrame([], EDITED)
    cuts = np.array(sorted(set(got["cuts"]) | {got["first"]}), np.int64)

    @F.arrow_udf("array<int>")
    def ranges(key: pa.Array) -> pa.Array:
        k = key.to_numpy(zero_copy_only=False)
        own = np.searchsorted(cuts, k, side="right") - 1
        head = cuts[own] == k
        return pa.array([[a, (a - 1) % len(cuts)] if h else [a] for a, h in zip(own.tolist(), head.tolist(), strict=True)], pa.list_(pa.int32()))

    dealt = light.withColumn("key", F.coalesce("id", F.lit(least))).withColumn("ranges", ranges("key"))
    dealt = dealt.select("id", "key", "text", F.posexplode("ranges").alias("ahead", "range"))
    dealt = dealt.repartitionById(len(cuts), F.col("range")).sortWithinPartitions("range", "ahead", "key", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, str]] = []
        first, size, follower = None, 0, None
        for b in batches:
            for i, text, ahead in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                if ahead:
                    follower = follower or (i, text)
                    continue
                if held and size > BATCH:
                    yield _edited(held, (i, text), rank)
                    held, size = [], 0
                held.append((i, text))
                size += len(text)
        if held:
            yield _edited(held, follower, rank)

    return dealt.select("id", "text", "ahead").mapInArrow(tidy(run), EDITED)


def op4(docs: DataFrame) -> DataFrame:
    return edited_pairs(docs, fit_ranks(docs))
