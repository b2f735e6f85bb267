"""Metric distances: as Spark columns, as numpy blocks, and from a column to a few fixed objects."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Relative and absolute padding of thresholds against rounding of sums in another order.
PAD = 1e-9
#: Pairs that a filter of many small tiles gathers before it gives them out.
HELD_PAIRS = 1 << 14


@dataclass(frozen=True)
class Metric:
    """One distance. ``column`` compares two columns, ``block`` two lists of objects as a matrix.

    ``kind``: vector, string, set or scalar; it decides how objects reach numpy. ``filters`` are
    cheap conditions (x, y, delta) -> Column that every pair within delta meets.
    """

    name: str
    kind: str
    column: Callable[[Column, Column], Column] | None
    block: Callable[[Sequence, Sequence], np.ndarray]
    within: Callable[[Column, Column, float], Column] | None = None
    filters: tuple[Callable[[Column, Column, float], Column], ...] = field(default=())
    #: Distances of matching rows of two matrices, where that is cheaper than a block.
    rowwise: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None
    #: (x, y, delta) -> (i, j, distance) of the pairs within delta, where they are found without a whole matrix; None if delta is too large for that.
    near: Callable[[Sequence, Sequence, float], tuple[np.ndarray, np.ndarray, np.ndarray] | None] | None = None
    #: (x, y, delta) -> (i, j) of matrices, some at a time: every pair within delta and few others, cheaper than distances; None if that cannot be had.
    maybe: Callable[[np.ndarray, np.ndarray, float], Iterator[tuple[np.ndarray, np.ndarray]] | None] | None = None

    def at_most(self, x: Column, y: Column, delta: float) -> Column:
        """Whether the distance is at most delta."""
        if self.within is not None:
            return self.within(x, y, delta)
        return self.distance(x, y) <= F.lit(padded(delta))

    def distance(self, x: Column, y: Column) -> Column:
        if self.column is not None:
            return self.column(x, y)
        block = self.block

        @F.arrow_udf("double")
        def pairwise(a: pa.Array, b: pa.Array) -> pa.Array:
            return pa.array([float(block([p], [q])[0, 0]) for p, q in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.float64())

        return pairwise(x, y)

    def to_axes(self, obj: Column, axes: Sequence) -> Column:
        """Array of the distances to a few fixed objects. Strings, sets of strings and numbers stay in the JVM."""
        if not len(axes):
            return F.array().cast("array<double>")
        if self.name == "jaccard" and all(isinstance(t, int) for a in axes for t in a):
            return _jaccard_to(axes)(obj)
        if self.kind != "vector" and self.column is not None:
            return F.array(*[self.column(obj, literal(a)).cast("double") for a in axes])
        block, fixed = self.block, list(axes)

        @F.arrow_udf("array<double>")
        def mapped(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
            for part in parts:
                yield rows_to_arrow(block(objects(part), fixed))

        return mapped(obj)


def padded(delta: float) -> float:
    return delta + PAD * max(1.0, abs(delta))


def literal(value) -> Column:
    return F.array(*[F.lit(v) for v in value]) if isinstance(value, list | tuple | np.ndarray) else F.lit(value)


def objects(part: pa.Array) -> np.ndarray | list:
    """An Arrow column as objects for ``block``: a matrix where all rows are vectors of one length."""
    if pa.types.is_list(part.type) and not pa.types.is_string(part.type.value_type):
        flat = part.flatten().to_numpy(zero_copy_only=False)
        if len(part) and len(flat) % len(part) == 0 and len(set(part.value_lengths().to_pylist())) == 1:
            return flat.astype(np.float64).reshape(len(part), -1)
    return part.to_pylist()


def rows_to_arrow(m: np.ndarray) -> pa.Array:
    n, k = m.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(0, n * k + 1, k, dtype=np.int32) if k else np.zeros(n + 1, np.int32)), pa.array(np.ascontiguousarray(m, np.float64).ravel()))


def as_matrix(x) -> np.ndarray:
    """Vectors as rows; no vectors are a matrix without rows."""
    return np.asarray(x, np.float64).reshape(len(x), -1) if len(x) else np.zeros((0, 0))


_vectors = as_matrix


def _by_rows(step: Callable[[np.ndarray, np.ndarray], np.ndarray], cells: int = 1 << 22):
    """Distances of two sets of vectors, as many rows at a time as fit a fixed number of cells."""

    def block(x, y) -> np.ndarray:
        a, b = _vectors(x), _vectors(y)
        if not (len(a) and len(b)):
            return np.zeros((len(a), len(b)))
        rows = max(1, cells // max(1, b.size))
        return np.concatenate([step(a[i : i + rows, None, :], b[None, :, :]) for i in range(0, len(a), rows)])

    return block


def _folded(each: Callable[[Column, Column], Column], finish: Callable[[Column], Column] = lambda c: c):
    return lambda x, y: finish(F.aggregate(F.zip_with(x, y, lambda a, b: each(a.cast("double"), b.cast("double"))), F.lit(0.0), lambda s, v: s + v))


def _vector_metric(name: str, column, step) -> Metric:
    return Metric(name, "vector", column, _by_rows(step), rowwise=step)


def _maybe_l1(x: np.ndarray, y: np.ndarray, delta: float, tile: tuple[int, int] = (32, 4096)) -> Iterator[tuple[np.ndarray, np.ndarray]] | None:
    """Pairs whose entries, as whole numbers of 16 bits, differ by no more than delta allows: each is rounded down, which adds less than one step.

    Steps are so wide that no sum leaves 16 bits; None for vectors too long for that or too far apart for the threshold to count in steps.
    """
    width = x.shape[1]
    levels = 32767 // max(1, width)
    if not (len(x) and len(y) and width) or y.shape[1] != width:
        return None
    low = np.minimum(x.min(axis=0), y.min(axis=0))
    step = float((np.maximum(x.max(axis=0), y.max(axis=0)) - low).max()) / max(1, levels - 1)
    if not (np.isfinite(step) and 0 < step and padded(delta) >= width * step):
        return None
    most = padded(delta) / step + width + 1  # the one more is for rounding of the quotients
    a, b = np.floor((x - low) / step).astype(np.int16), np.ascontiguousarray(np.floor((y - low) / step).astype(np.int16).T)

    def found() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        held, n = [], 0
        for r in range(0, len(a), tile[0]):
            rows = a[r : r + tile[0]]
            for c in range(0, b.shape[1], tile[1]):
                part = b[:, c : c + tile[1]]
                total = np.zeros((len(rows), part.shape[1]), np.int16)
                gap = np.empty_like(total)
                for d in range(width):
                    np.subtract(rows[:, d, None], part[d], out=gap)
                    np.abs(gap, out=gap)
                    total += gap
                i, j = np.nonzero(total <= min(most, 32767))
                held.append((i + r, j + c))
                n += len(i)
                if n >= HELD_PAIRS:
                    yield tuple(np.concatenate(v) for v in zip(*held, strict=True))
                    held, n = [], 0
        if n:
            yield tuple(np.concatenate(v) for v in zip(*held, strict=True))

    return found()


L1 = replace(_vector_metric("l1", _folded(lambda a, b: F.abs(a - b)), lambda a, b: np.abs(a - b).sum(-1)), maybe=_maybe_l1)
L2 = _vector_metric("l2", _folded(lambda a, b: (a - b) * (a - b), F.sqrt), lambda a, b: np.sqrt(((a - b) ** 2).sum(-1)))
LINF = _vector_metric("linf", lambda x, y: F.array_max(F.zip_with(x, y, lambda a, b: F.abs(a.cast("double") - b.cast("double")))), lambda a, b: np.abs(a - b).max(-1))


def lp(p: float) -> Metric:
    """The norm of order p >= 1; below 1 the triangle inequality fails."""
    if p < 1:
        raise ValueError("p must be at least 1")
    if math.isinf(p):
        return LINF
    return _vector_metric(f"l{p:g}", _folded(lambda a, b: F.pow(F.abs(a - b), F.lit(float(p))), lambda c: F.pow(c, F.lit(1.0 / p))), lambda a, b: (np.abs(a - b) ** p).sum(-1) ** (1.0 / p))


def _angular_block(x, y) -> np.ndarray:
    a, b = _vectors(x), _vectors(y)
    na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    return np.arccos(np.clip((a @ b.T) / np.maximum(na[:, None] * nb[None, :], 1e-300), -1.0, 1.0))


def _angular(x: Column, y: Column) -> Column:
    dot = _folded(lambda a, b: a * b)
    return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), dot(x, y) / F.sqrt(dot(x, x) * dot(y, y)))))


#: Angle between directions; vectors of one direction are one object.
ANGULAR = Metric("angular", "vector", _angular, _angular_block)
HAMMING = _vector_metric("hamming", _folded(lambda a, b: (a != b).cast("double")), lambda a, b: (a != b).sum(-1).astype(np.float64))
ABS1 = Metric("abs1", "scalar", lambda x, y: F.abs(x - y), lambda x, y: np.abs(np.asarray(x, np.float64)[:, None] - np.asarray(y, np.float64)[None, :]))


def edit_block(xs: Sequence[str], ys: Sequence[str]) -> np.ndarray:
    """Edit distances of all pairs; each step of the recurrence runs over all ys at once."""
    out = np.zeros((len(xs), len(ys)))
    if not len(ys):
        return out
    longest = max(map(len, ys))
    codes = np.full((len(ys), longest), -1, np.int64)
    for i, y in enumerate(ys):
        codes[i, : len(y)] = [ord(c) for c in y]
    lengths = np.array([len(y) for y in ys])
    for r, x in enumerate(xs):
        row = np.tile(np.arange(longest + 1, dtype=np.int64)[:, None], len(ys))
        for i, c in enumerate(x, 1):
            new = np.empty_like(row)
            new[0] = i
            swap = row[:-1] + (codes.T != ord(c))
            keep = row[1:] + 1
            np.minimum(swap, keep, out=keep)
            for j in range(longest):
                np.minimum(keep[j], new[j] + 1, out=new[j + 1])
            row = new
        out[r] = row[lengths, np.arange(len(ys))]
    return out


def _edit_within(x: Column, y: Column, delta: float) -> Column:
    whole = int(math.floor(padded(delta)))
    return F.levenshtein(x, y, whole) >= 0 if whole >= 0 else F.lit(False)


#: Strings of a trie, and strings that walk it at once: what a step works on fits a core's cache.
TRIE_ROWS, WALKERS = 512, 256
#: Code points of a trie; fewer strings if they are long.
TRIE_CELLS = 1 << 21


def code_points(strings: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of strings as rows, and lengths."""
    size = np.array([len(s) for s in strings], np.int64)
    out = np.zeros((len(strings), int(size.max(initial=0))), np.uint32)
    flat = np.frombuffer("".join(strings).encode("utf-32-le", "surrogatepass"), np.uint32)
    out[np.arange(out.shape[1])[None, :] < size[:, None]] = flat
    return out, size


def _walk(xs: tuple[np.ndarray, np.ndarray], ys: tuple[np.ndarray, np.ndarray], delta: int, kind: type) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, distance) within delta of sorted xs and some ys, as codes and lengths.

    The table of the recurrence is kept along its diagonal as bits that tell where it rises and falls. Prefixes that
    several xs have in common are walked once, for all ys at once, and left as soon as no y can be near.
    """
    (x, nx), (y, ny) = xs, ys
    width = kind(0).itemsize * 8
    one, high, core = kind(1), kind(width - 1), kind(delta)
    letters = np.unique(x[np.arange(x.shape[1])[None, :] < nx[:, None]])
    letter = np.searchsorted(letters, x)
    same = (x[1:] == x[:-1]) & (np.arange(x.shape[1])[None, :] < np.minimum(nx[1:], nx[:-1])[:, None])
    fresh = np.concatenate(([0], np.cumprod(same, axis=1).sum(axis=1))) if len(x) > 1 else np.zeros(1, np.int64)  # places shared with the one before
    q = len(ny)

    def matches(at: int) -> np.ndarray:
        if at >= y.shape[1]:
            return np.zeros((len(letters), q), kind)
        return ((y[:, at][None, :] == letters[:, None]) & (at < ny)[None, :]).astype(kind)

    table = np.zeros((len(letters), q), kind)
    for b in range(delta, width):
        table |= matches(b - delta) << kind(b)
    rise = np.full((1, q), np.iinfo(kind).max << delta & np.iinfo(kind).max, kind)
    fall = np.full((1, q), (1 << delta) - 1, kind)
    diagonal = np.zeros((1, q), np.uint32 if x.shape[1] > 60_000 else np.uint16)
    node = np.zeros(len(x), np.int64)  # of each string, its prefix's place among the live ones; -1: none
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def ended(rows: np.ndarray, length: int) -> None:
        rows = rows[node[rows] >= 0]
        cols = np.flatnonzero(np.abs(ny - length) <= delta)
        if not (len(rows) and len(cols)):
            return
        ahead = ny[cols] - length
        mask = np.array([((1 << abs(a)) - 1) << (delta - max(0, -a)) for a in ahead.tolist()], kind)
        at = np.ix_(node[rows], cols)
        step = np.bitwise_count(rise[at] & mask).astype(np.int64) - np.bitwise_count(fall[at] & mask)
        d = diagonal[at].astype(np.int64) + np.where(ahead > 0, step, -step)
        i, j = np.nonzero(d <= delta)
        out.append((rows[i], cols[j], d[i, j].astype(np.float64)))

    ended(np.flatnonzero(nx == 0), 0)
    for level in range(x.shape[1]):
        left = np.flatnonzero((nx > level) & (node >= 0))
        if not len(left):
            break
        # fresh is about the string just before, which is left too where a place of this level is shared
        new = fresh[left] <= level
        new[0] = True
        new[1:] |= np.diff(left) > 1
        first, number = left[new], np.cumsum(new) - 1
        up, match = node[first], table[letter[first, level]]
        vp, vn = rise[up], fall[up]
        d0 = (((match & vp) + vp) ^ vp) | match | vn
        hp = vn | ~(d0 | vp)
        hn = d0 & vp
        diagonal = diagonal[up] + ((~d0 >> core) & one)
        below = d0 >> one
        rise, fall = hn | ~(below | hp), below & hp
        live = diagonal.min(axis=1) <= 2 * delta
        if not live.all():
            rise, fall, diagonal = rise[live], fall[live], diagonal[live]
        place = np.where(live, np.cumsum(live) - 1, -1)
        node[:] = np.where(nx > level, -1, node)
        node[left] = place[number]
        ended(left[nx[left] == level + 1], level + 1)
        table = (table >> one) | (matches(level + 1 - delta + width - 1) << high)
    if not out:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def edit_near(xs: Sequence[str], ys: Sequence[str], delta: float) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """(i, j, distance) of all pairs within delta, without the distances of others; None beyond 31 edits."""
    whole = int(math.floor(padded(delta)))
    if whole > 31:
        return None
    kind = np.uint16 if whole < 8 else np.uint32 if whole < 16 else np.uint64
    a, b = (np.array(sorted(range(len(s)), key=s.__getitem__), np.int64) for s in (xs, ys))

    def parts(order: np.ndarray, strings: Sequence[str], most: int):
        at = 0
        while at < len(order):
            part, longest = [], 0
            for i in order[at : at + most].tolist():
                longest = max(longest, len(strings[i]))
                if part and longest * (len(part) + 1) > TRIE_CELLS:
                    break
                part.append(i)
            at += len(part)
            yield np.array(part), code_points([strings[i] for i in part])

    walkers, out = list(parts(b, ys, WALKERS)), []
    for rows, x in parts(a, xs, TRIE_ROWS):
        for cols, y in walkers:
            i, j, d = _walk(x, y, whole, kind)
            if len(i):
                out.append((rows[i], cols[j], d))
    if whole < 0 or not out:
        return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


EDIT = Metric("edit", "string", lambda x, y: F.levenshtein(x, y).cast("double"), edit_block, _edit_within, (lambda x, y, d: F.abs(F.length(x) - F.length(y)) <= F.lit(padded(d)),), near=edit_near)


def jaccard_block(xs: Sequence[Sequence], ys: Sequence[Sequence]) -> np.ndarray:
    """Common tokens are counted for all xs at once, one y after the other."""
    sizes = np.array([len(x) for x in xs], np.int64)
    number = {t: i for i, t in enumerate({t for y in ys for t in y})}
    flat = np.array([number.get(t, -1) for x in xs for t in x], np.int64)
    ends = np.cumsum(sizes)
    out = np.zeros((len(xs), len(ys)))
    mark = np.zeros(len(number) + 1, bool)  # the last place is that of tokens that no y has
    for j, y in enumerate(ys):
        at = [number[t] for t in y]
        mark[at] = True
        upto = np.concatenate(([0], np.cumsum(mark[flat])))
        mark[at] = False
        both = upto[ends] - upto[ends - sizes]
        either = sizes + len(y) - both
        out[:, j] = np.where(either > 0, 1.0 - both / np.maximum(either, 1), 0.0)
    return out


def _jaccard(x: Column, y: Column) -> Column:
    both = F.size(F.array_intersect(x, y))
    either = F.size(x) + F.size(y) - both
    return F.when(either == 0, F.lit(0.0)).otherwise(1.0 - both / either)


def _jaccard_to(axes: Sequence[Sequence[int]]):
    """UDF: distances of sets of whole numbers to a few fixed ones."""
    fixed = [np.unique(np.array(a, np.int64)) for a in axes]

    @F.arrow_udf("array<double>")
    def mapped(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for part in parts:
            flat, size = part.flatten().to_numpy(zero_copy_only=False), part.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            ends = np.cumsum(size)
            out = np.zeros((len(size), len(fixed)))
            for j, a in enumerate(fixed):
                at = np.searchsorted(a, flat)
                hit = (a[np.minimum(at, len(a) - 1)] == flat) & (at < len(a)) if len(a) else np.zeros(len(flat), bool)
                upto = np.concatenate(([0], np.cumsum(hit)))
                both = upto[ends] - upto[ends - size]
                either = size + len(a) - both
                out[:, j] = np.where(either > 0, 1.0 - both / np.maximum(either, 1), 0.0)
            yield rows_to_arrow(out)

    return mapped


def _jaccard_sizes(x: Column, y: Column, delta: float) -> Column:
    s = max(0.0, 1.0 - delta)
    return (F.size(x) * F.lit(s) <= F.size(y) + F.lit(1e-6)) & (F.size(y) * F.lit(s) <= F.size(x) + F.lit(1e-6))


#: On arrays of distinct tokens; two empty sets are at distance 0.
JACCARD = Metric("jaccard", "set", _jaccard, jaccard_block, None, (_jaccard_sizes,))


def combine(parts: Sequence[tuple[str, Metric, float]], name: str = "combined") -> Metric:
    """Weighted sum of metrics on the fields of a struct: again a metric."""

    def column(x: Column, y: Column) -> Column:
        return sum((F.lit(float(w)) * m.distance(x[f], y[f]) for f, m, w in parts), F.lit(0.0))

    def block(xs, ys) -> np.ndarray:
        return sum(w * m.block([x[f] for x in xs], [y[f] for y in ys]) for f, m, w in parts)

    return Metric(name, "struct", column, block)


METRICS: dict[str, Metric] = {m.name: m for m in (L1, L2, LINF, ANGULAR, HAMMING, ABS1, EDIT, JACCARD)}
#: Dissimilarities that break the triangle inequality.
NOT_METRIC = {"squared_l2", "sql2", "sqeuclidean", "cosine", "kl", "dot"}


def register_metric(name: str, block: Callable, column: Callable | None = None, kind: str = "vector", filters: tuple = ()) -> Metric:
    """Add a user's metric; names of known non-metrics are refused."""
    if name in NOT_METRIC:
        raise ValueError(f"{name} is no metric: the triangle inequality fails")
    METRICS[name] = Metric(name, kind, column, block, None, filters)
    return METRICS[name]


def metric_of(m: str | Metric) -> Metric:
    if isinstance(m, Metric):
        return m
    if m in NOT_METRIC:
        raise ValueError(f"{m} is no metric: the triangle inequality fails")
    if m not in METRICS and m[:1] == "l" and m[1:].replace(".", "", 1).isdigit():
        return lp(float(m[1:]))
    return METRICS[m]


def check_metric(m: str | Metric, df: DataFrame, obj: str, sample: int = 40) -> list[str]:
    """Axioms that fail on a small sample, which comes to the driver: negative, identity, symmetry, triangle."""
    m = m if isinstance(m, Metric) else METRICS.get(m) or metric_of(m)
    rows = [r[0] for r in df.select(obj).where(F.col(obj).isNotNull()).orderBy(F.xxhash64(obj)).limit(sample).collect()]
    d = m.block(rows, rows)
    near = 1e-9 * max(1.0, float(np.abs(d).max(initial=0)))
    same = np.array([[a == b for b in rows] for a in rows]) if rows else np.zeros((0, 0), bool)
    found = []
    if (d < -near).any():
        found.append("negative")
    if (d[same] > max(near, 1e-6)).any() or (d[~same] <= 0).any():
        found.append("identity")
    if (np.abs(d - d.T) > near).any():
        found.append("symmetry")
    if len(rows) and (d[:, None, :] > d[:, :, None] + d[None, :, :] + near).any():
        found.append("triangle")
    return found


def register_sql_functions(spark) -> None:
    """l1_distance, l2_distance, linf_distance, jaccard_distance and ed_distance for SQL: Arrow batches, whole matrices at a time where rows are vectors of one length."""
    import pandas as pd

    def rowwise(m: Metric):
        def pairwise(a, b):
            x, y = (pa.array(v) for v in (a, b))
            p, q = objects(x), objects(y)
            if isinstance(p, np.ndarray) and isinstance(q, np.ndarray):
                return pd.Series(m.rowwise(p, q))
            return pd.Series([float(m.block([i], [j])[0, 0]) for i, j in zip(p, q, strict=True)])

        return pairwise

    for name, m in (("l1_distance", L1), ("l2_distance", L2), ("linf_distance", LINF)):
        spark.udf.register(name, F.pandas_udf(rowwise(m), "double"))
    spark.udf.register("jaccard_distance", F.pandas_udf(lambda a, b: pd.Series([float(jaccard_block([p], [q])[0, 0]) for p, q in zip(a, b, strict=True)]), "double"))
    spark.udf.register("ed_distance", F.pandas_udf(lambda a, b: pd.Series([float(edit_block([p], [q])[0, 0]) for p, q in zip(a, b, strict=True)]), "double"))
