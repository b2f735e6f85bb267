"""Filters for strings and sets: conditions that every pair within the threshold meets."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.tables import discard, materialize, running_sum
from .metrics import code_points

#: Subtracted before rounding up, so that sums just above a whole number do not count as the next.
TINY = 1e-9
#: Two sets have to share more tokens of their prefixes than this share of their mean size, as far as the threshold demands so many.
COUNTED_SHARE = 0.02
#: Ids of repeated sets that are broadcast; more are joined.
BROADCAST_IDS = 200_000
#: Strings of one length are dealt into blocks of a 32nd of all rows, within these bounds, and of so many code points at most.
BLOCK_STRINGS, MOST_STRINGS, BLOCK_POINTS = 1 << 14, 1 << 16, 1 << 24
#: Strings of a block that meet others at once; fewer if they have more code points than that in all.
MET_STRINGS, MET_POINTS = 4096, 1 << 23
#: Strings whose candidates are verified at once.
CHECKED_STRINGS = 256
#: Candidates that a task gives out at once.
GIVEN_PAIRS = 1 << 20
#: Segments for each edit and one more when candidates are verified: the more, the fewer of them.
SEGMENTS = 3


def tokens(text: Column) -> Column:
    """Distinct lower-case tokens of letters a-z and digits."""
    return F.array_distinct(F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda t: t != ""))


def token_order(sets: DataFrame, set_col: str = "obj") -> DataFrame:
    """(token, n, rank): how many sets have each token, and its place from the rarest, from 1; equally rare ones by the token."""
    counts = sets.select(F.explode(set_col).alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("n"))
    return running_sum(counts, ["n", "token"], F.lit(1), "rank").select("token", "n", F.col("rank").cast("long").alias("rank"))


def ranked_sets(sets: DataFrame, keys: tuple[str, ...] = ("id",), set_col: str = "obj") -> DataFrame:
    """The same sets with the ranks of their tokens, from the rarest: equal tokens are equal numbers. Sets without tokens stay empty.

    Tokens are shuffled to their ranks, and ranks to their sets; no list of all tokens is gathered.
    """
    return _ranked(materialize(sets.select(*keys, F.col(set_col).alias("obj"))), keys)


def _ranked(sets: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """``ranked_sets`` of a written table."""
    each = sets.select(*keys, F.explode("obj").alias("token"))
    ranks = materialize(token_order(sets, "obj").select("token", "rank"))
    found = each.join(ranks, "token").groupBy(*keys).agg(F.array_sort(F.collect_list("rank")).alias("obj"))
    return found.unionByName(sets.where(F.size("obj") == 0).select(*keys, F.array().cast("array<long>").alias("obj")))


def ranked_classes(sets: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """(ranked, copies): ``ranked_sets`` of one set of each class of equal ones, that of the smallest id; and (rep, id) of all sets
    of the classes that have others, None if none has. Classes are told apart by a digest of 256 bits, so sets are not moved.
    """
    sets = materialize(sets.select("id", "obj"))
    keyed = sets.select("id", F.unhex(F.sha2(F.to_json(F.array_sort("obj")), 256)).alias("key"))
    keyed = materialize(keyed)
    reps = materialize(keyed.groupBy("key").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("n")).where("n > 1").select("key", "rep"))
    copies = materialize(keyed.join(reps, "key").select("rep", "id"))
    n = copies.count()
    kept = sets
    if n:
        gone = copies.where("id <> rep").select("id")
        kept = sets.join(F.broadcast(gone) if n <= BROADCAST_IDS else gone, "id", "left_anti")
    ranked = materialize(_ranked(kept, ("id",)))
    discard(sets, keyed, reps)
    return ranked, copies if n else None


def with_copies(pairs: DataFrame, copies: DataFrame | None) -> DataFrame:
    """(id_x, id_y, distance) of representatives -> those of all sets: every copy links where its representative does, and to its own copies."""
    if copies is None:
        return pairs
    x, y = (copies.select(F.col("rep").alias(f"id_{s}"), F.col("id").alias(f"copy_{s}")) for s in "xy")
    across = pairs.join(x, "id_x", "left").join(y, "id_y", "left")
    a, b = F.coalesce("copy_x", "id_x"), F.coalesce("copy_y", "id_y")
    across = across.select(F.least(a, b).alias("id_x"), F.greatest(a, b).alias("id_y"), "distance")
    x, y = copies.alias("x"), copies.alias("y")
    inside = x.join(y, (F.col("x.rep") == F.col("y.rep")) & (F.col("x.id") < F.col("y.id")))
    return across.unionByName(inside.select(F.col("x.id").alias("id_x"), F.col("y.id").alias("id_y"), F.lit(0.0).alias("distance")))


def needed_overlap(size_x: Column, size_y: Column, delta: float) -> Column:
    """Common tokens that sets of these sizes need for a distance of at most delta."""
    s = 1.0 - delta
    return F.ceil(F.lit(s / (1.0 + s)) * (size_x + size_y) - F.lit(TINY))


def prefix_length(size: Column, delta: float) -> Column:
    return size - F.ceil(F.lit(1.0 - delta) * size - F.lit(TINY)) + 1


def size_close(x: Column, y: Column, delta: float) -> Column:
    s = 1.0 - delta
    return (F.lit(s) * x <= y + F.lit(TINY)) & (F.lit(s) * y <= x + F.lit(TINY))


def length_candidates(strings: DataFrame, delta: int, id_col: str = "id", obj: str = "obj") -> DataFrame:
    """(id_x, id_y) whose lengths differ by at most delta, by an equi-join on the length."""
    x = strings.select(F.col(id_col).alias("id"), F.length(obj).alias("len"))
    near = x.select("id", F.explode(F.sequence(F.col("len") - delta, F.col("len") + delta)).alias("len"))
    both = x.alias("x").join(near.alias("y"), F.col("x.len") == F.col("y.len")).where("x.id < y.id")
    return both.select(F.col("x.id").alias("id_x"), F.col("y.id").alias("id_y"))


def enough_left(x: str, y: str, delta: float) -> Column:
    """Whether what follows a common token at the places x.pos and y.pos (from 0) of two sets in one order, with it, can suffice. It does for the first common one of every pair within delta."""
    left = F.least(F.col(f"{x}.size") - F.col(f"{x}.pos"), F.col(f"{y}.size") - F.col(f"{y}.pos"))
    return left >= needed_overlap(F.col(f"{x}.size"), F.col(f"{y}.size"), delta)


def counted_least(size_x: Column, size_y: Column, delta: float) -> Column:
    """How many common tokens of both prefixes are asked of sets of these sizes: no more than any pair within delta has.

    Of a pair with so many tokens in common as it needs, the k-th common one has at most size - needed + k - 1 before it in either set; the
    prefixes hold these places up to k = needed - (size less its prefix).
    """
    rest = lambda n: F.ceil(F.lit(1.0 - delta) * n - F.lit(TINY))
    sure = needed_overlap(size_x, size_y, delta) - F.greatest(rest(size_x), rest(size_y)) + 1
    return F.greatest(F.lit(1), F.least(sure, F.ceil(F.lit(COUNTED_SHARE / 2) * (size_x + size_y)) + 2))


def counted_pairs(x: DataFrame, y: DataFrame, on: Column, delta: float) -> DataFrame:
    """(i, j) of postings aliased x and y (id, size, pos, token) that meet under ``on`` as often as ``counted_least`` asks, at places early enough.

    Only numbers move; nearly all pairs that are left are within delta.
    """
    sx, sy = F.col("x.size"), F.col("y.size")
    least = counted_least(sx, sy, delta)
    left = F.least(sx - F.col("x.pos"), sy - F.col("y.pos")) + least - 1
    both = x.join(y, on & size_close(sx, sy, delta) & (left >= needed_overlap(sx, sy, delta)))
    met = both.select(F.col("x.id").alias("i"), F.col("y.id").alias("j"), least.cast("int").alias("least"))
    return met.groupBy("i", "j", "least").agg(F.count(F.lit(1)).alias("n")).where("n >= least").select("i", "j")


def prefix(size: Column, delta: float, obj: str = "obj") -> Column:
    """The first tokens of a set in the common order; two sets within delta share one of them."""
    return F.slice(obj, F.lit(1), F.greatest(prefix_length(size, delta), F.lit(0)).cast("int"))


def prefix_postings(sets: DataFrame, delta: float) -> DataFrame:
    """(id, token, pos, size) of the tokens in each set's prefix."""
    return ranked_sets(sets).select("id", F.size("obj").alias("size"), F.posexplode(prefix(F.size("obj"), delta)).alias("pos", "token"))


def counted_candidates(ranked: DataFrame, delta: float) -> DataFrame:
    """(id_x, id_y) of ranked sets that share as many tokens of both prefixes as every pair within delta does (see ``counted_least``)."""
    p = materialize(ranked.select("id", F.size("obj").alias("size"), F.posexplode(prefix(F.size("obj"), delta)).alias("pos", "token")))
    found = counted_pairs(p.alias("x"), p.alias("y"), (F.col("x.token") == F.col("y.token")) & (F.col("x.id") < F.col("y.id")), delta)
    found = materialize(found.select(F.col("i").alias("id_x"), F.col("j").alias("id_y")))
    discard(p)
    return found


def prefix_candidates(sets: DataFrame, delta: float, positions: bool = False) -> DataFrame:
    """(id_x, id_y) that share a token of both prefixes and have sizes close enough.

    With ``positions`` the tokens still to come must suffice: the first shared token of the
    prefixes, at places i and j, leaves at most 1 + min(rest of x, rest of y) in common.
    """
    p = materialize(prefix_postings(sets, delta))
    on = (F.col("x.token") == F.col("y.token")) & (F.col("x.id") < F.col("y.id")) & size_close(F.col("x.size"), F.col("y.size"), delta)
    both = p.alias("x").join(p.alias("y"), on & enough_left("x", "y", delta) if positions else on)
    return both.select(F.col("x.id").alias("id_x"), F.col("y.id").alias("id_y")).distinct()


def segment_index(strings: DataFrame, delta: int, keep: tuple[str, ...] = ("id",), obj: str = "obj") -> DataFrame:
    """(keep, n, i, seg): the delta + 1 segments of each string of length n; segment i starts at floor(i n / (delta + 1))."""
    x = strings.select(*keep, F.col(obj).alias("s"), F.length(obj).alias("n"))
    seg = lambda i: F.struct(i.alias("i"), F.substring(F.col("s"), _bound(i, F.col("n"), delta) + 1, _bound(i + 1, F.col("n"), delta) - _bound(i, F.col("n"), delta)).alias("seg"))
    return x.select(*keep, "n", F.explode(F.transform(F.sequence(F.lit(0), F.lit(delta)), seg)).alias("p")).select(*keep, "n", "p.i", "p.seg")


def segment_probes(strings: DataFrame, delta: int, keep: tuple[str, ...] = ("id",), obj: str = "obj") -> DataFrame:
    """(keep, n, i, seg): what each string holds where a segment i of a string of length n could be, moved by at most delta."""
    x = strings.select(*keep, F.col(obj).alias("s"), F.length(obj).alias("len"))
    x = x.select(*keep, "s", "len", F.explode(F.sequence(F.greatest(F.col("len") - delta, F.lit(0)), F.col("len") + delta)).alias("n")).select(*keep, "s", "len", "n", F.explode(F.sequence(F.lit(0), F.lit(delta))).alias("i"))
    start = _bound(F.col("i"), F.col("n"), delta)
    size = _bound(F.col("i") + 1, F.col("n"), delta) - start
    places = F.sequence(F.greatest(start - delta, F.lit(0)), F.greatest(start - delta, F.lit(0), F.least(start + delta, F.col("len") - size)))
    return x.select(*keep, "n", "i", F.explode(F.array_distinct(F.transform(places, lambda k: F.substring(F.col("s"), k + 1, size)))).alias("seg"))


def _bound(i: Column, n: Column, delta: int) -> Column:
    return F.floor(i * n / (delta + 1)).cast("int")


def _length_cells(strings: DataFrame, delta: int) -> DataFrame:
    """(n, a, m, b, right, id, obj): each block a of strings of length n meets each block b of length m in n to n + delta; right: the row is of b.

    Strings move once for each block they meet, pairs never. A block with itself is there once.
    """
    x = materialize(strings.where(F.col("id").isNotNull() & F.col("obj").isNotNull()).select("id", "obj", F.length("obj").alias("n")))
    counts = materialize(x.groupBy("n").agg(F.count(F.lit(1)).alias("c")))  # a row a length
    total = counts.agg(F.sum("c")).first()[0] or 0
    block = min(max(total // 32, BLOCK_STRINGS), MOST_STRINGS)
    parts = counts.select("n", F.greatest(F.ceil(F.col("c") / block), F.ceil(F.col("c") * F.col("n") / BLOCK_POINTS)).cast("int").alias("parts"))
    near = parts.select("n", "parts", F.explode(F.sequence(F.col("n") - delta, F.col("n") + delta)).alias("m")).join(parts.select(F.col("n").alias("m"), F.col("parts").alias("others")), "m")
    near = near.groupBy("n", "parts").agg(F.collect_list(F.struct("m", "others")).alias("near"))
    x = x.join(near, "n").select("id", "obj", "n", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int").alias("a"), F.explode("near").alias("o"))
    x = x.select("id", "obj", "n", "a", F.col("o.m").alias("m"), F.explode(F.sequence(F.lit(0), F.col("o.others") - 1)).alias("b"))
    first = (F.col("n") < F.col("m")) | ((F.col("n") == F.col("m")) & (F.col("a") <= F.col("b")))
    key = [F.when(first, F.col(c)).otherwise(F.col(d)).alias(c) for c, d in (("n", "m"), ("a", "b"), ("m", "n"), ("b", "a"))]
    return x.select(*key, (~first).alias("right"), "id", "obj")


def _windows(codes: np.ndarray, start: int, size: int) -> pa.Array:
    part = np.ascontiguousarray(codes[:, start : start + size])
    return pa.FixedSizeBinaryArray.from_buffers(pa.binary(size * part.itemsize), len(part), [None, pa.py_buffer(part)])


def _segments_held(x: np.ndarray, y: np.ndarray, segments: int, least: int, delta: int) -> np.ndarray:
    """Of each row of x, as packed bits, the rows of y that hold at least so many of its segments, each moved by at most delta. Rows are code points, those of x of one length and those of y of another."""
    n, width = x.shape[1], -(-len(y) // 8)
    counts = [np.zeros((len(x), width), np.uint8) for _ in range(segments.bit_length())]  # the bits of each pair's count
    for i in range(segments):
        start, end = i * n // segments, (i + 1) * n // segments
        size = end - start
        if size:
            own = _windows(x, start, size).dictionary_encode()
            held = np.zeros((len(own.dictionary), width), np.uint8)
            for place in range(max(start - delta, 0), min(start + delta, y.shape[1] - size) + 1):
                found = pc.index_in(_windows(y, place, size), value_set=own.dictionary).fill_null(-1).to_numpy()
                at = np.flatnonzero(found >= 0)
                for bit in range(8):  # rows of y with the same bit are in bytes of their own
                    some = at[at & 7 == bit]
                    held[found[some], some >> 3] |= np.uint8(128 >> bit)
            carry = held[own.indices.to_numpy()]
        else:  # every string holds an empty segment
            carry = np.full((len(x), width), 255, np.uint8)
        for count in counts:
            left = count & carry
            count ^= carry
            carry = left
    enough = np.full((len(x), width), 255, np.uint8)
    for bit, count in enumerate(counts):
        enough = count & enough if least >> bit & 1 else count | enough
    return enough


def _met(t: pa.Table, delta: int, segments: int, least: int, both: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, rows, pairs) of a cell, some of its rows at a time: which pairs of them hold enough of each other's segments; ``both``: each of them has to, not one."""
    n, a, m, b = (t.column(c)[0].as_py() for c in ("n", "a", "m", "b"))
    right, obj = t.column("right").to_numpy(), t.column("obj")
    once = (n, a) == (m, b)

    def some(rows: np.ndarray, length: int) -> list[tuple[np.ndarray, np.ndarray]]:
        strings = obj.take(pa.array(rows)).to_pylist()
        order = sorted(range(len(rows)), key=strings.__getitem__)
        most = max(1, min(MET_STRINGS, MET_POINTS // max(1, length)))
        parts = [order[s : s + most] for s in range(0, len(order), most)]
        return [(rows[p], code_points([strings[i] for i in p])[0]) for p in parts]

    xs = some(np.flatnonzero(~right), n)
    ys = xs if once else some(np.flatnonzero(right), m)
    for p, (i, x) in enumerate(xs):
        for j, y in ys[p if once else 0 :]:
            kind = np.uint8 if max(x.max(initial=0), y.max(initial=0)) < 256 else np.uint32
            x_, y_ = x.astype(kind), y.astype(kind)
            ok = np.unpackbits(_segments_held(x_, y_, segments, least, delta), axis=1, count=len(j)).view(bool)
            back = np.unpackbits(_segments_held(y_, x_, segments, least, delta), axis=1, count=len(i)).view(bool).T
            ok = ok & back if both else ok | back
            yield i, j, np.triu(ok, 1) if i is j else ok


def _in_cells(strings: DataFrame, delta: int, run: Callable[[pa.Table], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """What ``run`` finds in each cell. A task holds one cell of bounded size and gives its pairs out in parts."""
    keys = ("n", "a", "m", "b")
    n = int(strings.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(pa.Table.from_batches(list(batches)).combine_chunks())

    return _length_cells(strings, delta).repartition(n, *keys).groupBy(*keys).applyInArrow(cell, schema)


def segment_candidates(strings: DataFrame, delta: int, id_col: str = "id", obj: str = "obj") -> DataFrame:
    """(id_x, id_y): one of delta + 1 segments of one string is found in the other, moved by at most delta.

    Strings shorter than delta + 1 have an empty segment, which every string near in length holds. Blocks of strings
    meet in cells, and each string gets the list of its candidates there, so no pair is shuffled.
    """
    x = strings.select(F.col(id_col).alias("id"), F.col(obj).alias("obj"))
    kind = x.schema["id"].dataType.simpleString()
    repeated = not x.where(F.col("id").isNotNull()).groupBy("id").count().where("count > 1").isEmpty()

    def run(t: pa.Table) -> Iterator[pa.RecordBatch]:
        ids = t.column("id").chunk(0)
        for i, j, ok in _met(t, delta, delta + 1, 1, both=False):
            others, rows = ids.take(pa.array(j)), max(1, GIVEN_PAIRS // len(j))
            for s in range(0, len(i), rows):
                part = ok[s : s + rows]
                ends = np.concatenate(([0], np.cumsum(np.count_nonzero(part, axis=1))))
                lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), others.take(pa.array(np.nonzero(part)[1])))
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(i[s : s + rows])), lists], ["x", "ys"])

    both = _in_cells(x, delta, run, f"x {kind}, ys array<{kind}>").select("x", F.explode("ys").alias("y")).where("x <> y")
    both = both.select(F.least("x", "y").alias("id_x"), F.greatest("x", "y").alias("id_y"))
    return both.distinct() if repeated else both


def segment_near(strings: DataFrame, delta: float, whole: int, near: Callable) -> DataFrame:
    """(id_x, id_y, distance): pairs of strings within delta, at most ``whole`` edits, that hold enough of each other's segments.

    An edit spoils one segment at most, so that of SEGMENTS (whole + 1) all but ``whole`` are held, either way. Candidates are
    verified by ``near`` where they are found: they outnumber the pairs by far and are never written.
    """
    segments = SEGMENTS * (whole + 1)

    def run(t: pa.Table) -> Iterator[pa.RecordBatch]:
        ids, obj = t.column("id").to_numpy(), t.column("obj")
        for i, j, ok in _met(t, whole, segments, segments - whole, both=True):
            xs, ys = (np.array(obj.take(pa.array(k)).to_pylist(), object) for k in (i, j))
            for s in range(0, len(i), CHECKED_STRINGS):
                part = ok[s : s + CHECKED_STRINGS]
                rows, cols = s + np.flatnonzero(part.any(axis=1)), np.flatnonzero(part.any(axis=0))
                if not len(rows):
                    continue
                p, q, d = near(xs[rows].tolist(), ys[cols].tolist(), delta)
                p, q = rows[p], cols[q]
                keep = ok[p, q] & (ids[i[p]] != ids[j[q]])
                x, y = ids[i[p[keep]]], ids[j[q[keep]]]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(d[keep])], ["id_x", "id_y", "distance"])

    return _in_cells(strings, whole, run, "id_x long, id_y long, distance double")


def verified(candidates: DataFrame, objs: DataFrame, metric, delta: float) -> DataFrame:
    """Candidates within delta, with their distances."""
    x, y = objs.alias("x"), objs.alias("y")
    both = candidates.join(x, F.col("id_x") == F.col("x.id")).join(y, F.col("id_y") == F.col("y.id"))
    both = both.where(metric.at_most(F.col("x.obj"), F.col("y.obj"), delta))
    return both.select("id_x", "id_y", metric.distance(F.col("x.obj"), F.col("y.obj")).cast("double").alias("distance"))


def sparse_to_dense(entries: Column, vocabulary: list[str]) -> Column:
    """Map of token weights as a vector over a fixed vocabulary."""
    return F.array(*[F.coalesce(F.element_at(entries, F.lit(t)), F.lit(0.0)).cast("double") for t in vocabulary])


def segment_bounds(n: int, delta: int) -> list[tuple[int, int]]:
    return [(math.floor(i * n / (delta + 1)), math.floor((i + 1) * n / (delta + 1))) for i in range(delta + 1)]
