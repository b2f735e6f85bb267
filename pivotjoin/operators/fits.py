"""Strata ("nodes"), the fit of a law to each, and the test of each fit."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.families import FAMILIES, Family, MultiNormal, Params
from ..functions.metrics import as_matrix, objects
from ..functions.numerics import bisect, chi2_isf, chi2_sf
from .tables import running_sum

#: Fixed values of the portable hash: a multiplicative generator, repeatable in any SQL engine.
MIX_A, MIX_B, MIX_P = 48_271, 69_621, 2_147_483_647


def portable_hash(id_: Column, seed: int = 0) -> Column:
    """A number below MIX_P from an integer id, by integer arithmetic alone."""
    x = F.pmod(id_.cast("long"), F.lit(MIX_P))
    x = F.pmod(x * F.lit(MIX_A) + F.lit((seed * 7919 + 12_345) % MIX_P), F.lit(MIX_P))
    return F.pmod(x * F.lit(MIX_B) + F.lit(1), F.lit(MIX_P))


def with_nodes(df: DataFrame, id_col: str, by: str = "hash", nodes: int = 4, seed: int = 0) -> DataFrame:
    """Adds node: a hash of the id, a range of it, the partition, or the number of a column's value.

    Values of a column are numbered by a hash, so that no list of them is needed.
    """
    if by == "hash":
        node = F.pmod(portable_hash(F.col(id_col), seed), F.lit(nodes)).cast("int")
    elif by == "range":
        ends = df.agg(F.min(id_col).alias("a"), F.max(id_col).alias("b")).first()
        width = max(1, (ends["b"] - ends["a"] + 1 if ends["a"] is not None else 1) / nodes)
        node = F.least(F.floor((F.col(id_col) - F.lit(ends["a"] or 0)) / F.lit(width)), F.lit(nodes - 1)).cast("int")
    elif by == "partition":
        node = F.spark_partition_id()
    else:
        node = F.pmod(F.xxhash64(by), F.lit(1 << 30)).cast("int")
    return df.withColumn("node", node)


@dataclass
class DimFit:
    family: str
    params: Params
    k_stat: float = 0.0
    cells: int = 0
    dof: int = 0
    confidence: float = 1.0

    @property
    def law(self) -> Family:
        return FAMILIES[self.family]


@dataclass
class NodeFit:
    """The law of one node: one fit per dimension, or one joint normal."""

    node: int
    n: int
    dims: list[DimFit] = field(default_factory=list)
    joint: MultiNormal | None = None
    k_stat: float = 0.0
    dof: int = 0
    confidence: float = 1.0

    @property
    def width(self) -> int:
        return len(self.dims) or len(self.joint.mean)

    def marginal(self, d: int) -> tuple[Family, Params]:
        return (self.dims[d].law, self.dims[d].params) if self.dims else self.joint.marginal(d)

    def draw(self, g: np.random.Generator, n: int) -> np.ndarray:
        if self.joint is not None:
            return self.joint.draw(g, n)
        return np.column_stack([f.law.draw(f.params, g, n) for f in self.dims])


MOMENTS = "node int, dim int, n long, x double, xx double, log double, loglog double, log1m double, nlog long, low double, high double"


def vector_moments(df: DataFrame, obj: str = "obj", node: str = "node") -> DataFrame:
    """Sums of all statistics by node and dimension: per task first, then over tasks. Rows do not move."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[np.ndarray]] = {}
        for b in batches:
            x, nodes = as_matrix(objects(b.column(1))), b.column(0).to_numpy(zero_copy_only=False)
            for k in np.unique(nodes):
                v = x[nodes == k]
                with np.errstate(divide="ignore", invalid="ignore"):
                    lg, l1 = np.where(v > 0, np.log(np.where(v > 0, v, 1)), 0), np.where(v < 1, np.log1p(-np.where(v < 1, v, 0)), 0)
                now = [np.full(v.shape[1], len(v)), v.sum(0), (v * v).sum(0), lg.sum(0), (lg * lg).sum(0), l1.sum(0), (v > 0).sum(0), v.min(0), v.max(0)]
                if k in held:
                    old = held[k]
                    held[k] = [*(p + q for p, q in zip(old[:7], now[:7], strict=True)), np.minimum(old[7], now[7]), np.maximum(old[8], now[8])]
                else:
                    held[k] = now
        for k, s in held.items():
            m = len(s[0])
            names = [c.split()[0] for c in MOMENTS.split(", ")]
            cols = [pa.array([int(k)] * m, pa.int32()), pa.array(range(m), pa.int32()), pa.array(s[0], pa.int64()), *[pa.array(c, pa.float64()) for c in s[1:6]], pa.array(s[6], pa.int64()), pa.array(s[7], pa.float64()), pa.array(s[8], pa.float64())]
            yield pa.RecordBatch.from_arrays(cols, names)

    parts = df.select(F.col(node).cast("int").alias("node"), F.col(obj).alias("obj")).mapInArrow(run, MOMENTS)
    sums = [F.sum(c).alias(c) for c in ("n", "x", "xx", "log", "loglog", "log1m", "nlog")]
    return parts.groupBy("node", "dim").agg(*sums, F.min("low").alias("low"), F.max("high").alias("high"))


def fit_dimension(row, families: Sequence[str]) -> list[DimFit]:
    """All candidate fits of one node and dimension from its sums."""
    n = row["n"]
    stats = {c: row[c] / n for c in ("x", "xx", "log1m")} | {"log": row["log"] / max(1, row["nlog"]), "loglog": row["loglog"] / max(1, row["nlog"]), "min": row["low"], "max": row["high"]}
    found = [DimFit(f, p) for f in families if (p := FAMILIES[f].fit(stats)) is not None]
    if not found:  # one value only: a normal law as narrow as rounding
        found = [DimFit("normal", {"mean": stats["x"], "var": max(1e-18, 1e-18 * stats["xx"])}, confidence=0.0)]
    return found


def cell_number(n: int, w: int) -> int:
    """Cells of equal probability: about 2 n^0.4, but more than parameters, and five rows in each."""
    return max(w + 2, min(int(2 * n**0.4), n // 5))


def make_cells(fit: DimFit, cells: int, by: str = "probability") -> np.ndarray:
    """Cuts between cells of equal probability, or of equal width over all but two thousandths of the law."""
    if by == "width":
        ends = [fit.law.quantile(fit.params, q) for q in (0.001, 0.999)]
        return np.linspace(*ends, cells + 1)[1:-1]
    return np.array([fit.law.quantile(fit.params, j / cells) for j in range(1, cells)])


def chi_square_stat(observed: np.ndarray, probability: np.ndarray) -> tuple[float, int]:
    """Statistic and number of cells; neighbours are merged until each expects five rows."""
    n = observed.sum()
    seen, want = [0.0], [0.0]
    for o, q in zip(observed.tolist(), probability.tolist(), strict=True):
        seen[-1] += o
        want[-1] += n * q
        if want[-1] >= 5:
            seen.append(0.0)
            want.append(0.0)
    if len(want) > 1 and want[-1] < 5:
        last = seen.pop(), want.pop()
        seen[-1] += last[0]
        want[-1] += last[1]
    o, e = np.array(seen), np.array(want)
    ok = e > 0
    return float(((o[ok] - e[ok]) ** 2 / e[ok]).sum()), int(ok.sum())


def confidence(k_stat: float, dof: int, mode: str = "prose") -> float:
    """Probability that the statistic is at least k_stat if the law holds. 'as_printed' is its complement, for contrast."""
    if dof <= 0:
        return 0.0
    p = chi2_sf(k_stat, dof)
    return 1 - p if mode == "as_printed" else p


CELL_COUNTS = "node int, dim int, candidate int, cell int, n long"


def cell_counts(df: DataFrame, cuts: dict[tuple[int, int, int], np.ndarray], obj: str = "obj", node: str = "node") -> DataFrame:
    """Rows by node, dimension, candidate law and cell."""
    by_node: dict[int, list] = {}
    for (k, d, c), at in cuts.items():
        by_node.setdefault(k, []).append((d, c, at))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int, int], np.ndarray] = {}
        for b in batches:
            nodes = b.column(0).to_numpy(zero_copy_only=False)
            x = as_matrix(objects(b.column(1)))
            for k in np.unique(nodes):
                v = x[nodes == k]
                for d, c, at in by_node.get(int(k), ()):
                    now = np.bincount(np.searchsorted(at, v[:, d], side="left"), minlength=len(at) + 1)
                    held[int(k), d, c] = held.get((int(k), d, c), 0) + now
        rows = [(k, d, c, j, int(n)) for (k, d, c), v in held.items() for j, n in enumerate(v) if n]
        if rows:
            kinds = [pa.int32()] * 4 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["node", "dim", "candidate", "cell", "n"])

    parts = df.select(F.col(node).cast("int").alias("node"), F.col(obj).alias("obj")).mapInArrow(run, CELL_COUNTS)
    return parts.groupBy("node", "dim", "candidate", "cell").agg(F.sum("n").alias("n"))


def test_rows(df: DataFrame, id_col: str, sizes: dict[int, int], gof_rows: int | None, seed: int) -> DataFrame:
    """About gof_rows rows of each node, by hash: with all rows of a large node every law is rejected. None: all rows."""
    if gof_rows is None or all(n <= gof_rows for n in sizes.values()):
        return df
    share = F.create_map(*[F.lit(v) for k, n in sizes.items() for v in (k, min(1.0, gof_rows / n))])
    return df.where(portable_hash(F.col(id_col), seed + 101) < F.element_at(share, F.col("node")) * F.lit(MIX_P))


def fit_nodes(df: DataFrame, id_col: str = "id", obj: str = "obj", families: Sequence[str] = ("normal", "exponential", "gamma"), model: str = "marginal", cells: int | None = None, gof_rows: int | None = 10_000, seed: int = 7, dof: str = "printed", cells_by: str = "probability") -> list[NodeFit]:
    """Fit and test the law of each node (column ``node``). Two passes; what comes to the driver is sums per node and dimension.

    model 'marginal': per dimension the family of the highest confidence, statistics and degrees
    of freedom summed. 'mvn_full', 'mvn_diag': one normal law, tested on shells of equal probability.
    ``cells_by``: see ``make_cells``. ``dof``: 'printed' subtracts the parameters, 'upper' does not.
    """
    moments = vector_moments(df, obj).collect()
    sizes = {r["node"]: r["n"] for r in moments if r["dim"] == 0}
    some = test_rows(df, id_col, sizes, gof_rows, seed)
    if model != "marginal":
        return _fit_joint(df, some, obj, sizes, model == "mvn_full", cells, dof)
    candidates = {(r["node"], r["dim"]): fit_dimension(r, families) for r in moments}
    cuts = {}
    for (k, d), fits in candidates.items():
        for c, f in enumerate(fits):
            cuts[k, d, c] = make_cells(f, cells or cell_number(min(sizes[k], gof_rows or sizes[k]), f.law.w), cells_by)
    seen: dict[tuple[int, int, int], np.ndarray] = {key: np.zeros(len(at) + 1) for key, at in cuts.items()}
    for r in cell_counts(some, cuts, obj).collect():
        seen[r["node"], r["dim"], r["candidate"]][r["cell"]] = r["n"]
    out = []
    for k in sorted(sizes):
        node = NodeFit(k, sizes[k])
        for d in range(max(d for kk, d in candidates if kk == k) + 1):
            for c, f in enumerate(candidates[k, d]):
                at = cuts[k, d, c]
                edges = np.array([0.0, *(f.law.cdf(f.params, v) for v in at), 1.0])
                f.k_stat, f.cells = chi_square_stat(seen[k, d, c], np.diff(edges))
                f.dof = f.cells - 1 - (f.law.w if dof == "printed" else 0)
                f.confidence = confidence(f.k_stat, f.dof)
            best = max(candidates[k, d], key=lambda f: (f.confidence, -f.k_stat / max(1, f.dof)))
            node.dims.append(best)
            node.k_stat += best.k_stat
            node.dof += max(0, best.dof)
        node.confidence = confidence(node.k_stat, node.dof)
        out.append(node)
    return out


def _fit_joint(df: DataFrame, some: DataFrame, obj: str, sizes: dict[int, int], full: bool, cells: int | None, dof: str) -> list[NodeFit]:
    def products(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for b in batches:
            nodes = b.column(0).to_numpy(zero_copy_only=False)
            x = as_matrix(objects(b.column(1)))
            for k in np.unique(nodes):
                v = x[nodes == k]
                held[int(k)] = held.get(int(k), 0) + np.concatenate([[len(v)], v.sum(0), (v.T @ v).ravel()])
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), pa.array([v.tolist() for v in held.values()], pa.list_(pa.float64()))], ["node", "s"])

    parts = df.select(F.col("node").cast("int").alias("node"), F.col(obj).alias("obj")).mapInArrow(products, "node int, s array<double>")
    total = parts.select("node", F.posexplode("s").alias("i", "v")).groupBy("node", "i").agg(F.sum("v").alias("v")).collect()
    sums: dict[int, dict[int, float]] = {}
    for r in total:
        sums.setdefault(r["node"], {})[r["i"]] = r["v"]
    fits = {}
    for k, s in sums.items():
        v = np.array([s[i] for i in range(len(s))])
        m = int(round((-1 + math.sqrt(1 + 4 * (len(v) - 1))) / 2))
        fits[k] = MultiNormal.fit(v[1 : m + 1] / v[0], v[m + 1 :].reshape(m, m) / v[0], full)
    shells = {}
    for k, f in fits.items():
        t = cells or max(8, min(int(2 * sizes[k] ** 0.4), sizes[k] // 5))
        shells[k] = np.array([chi2_isf(1 - j / t, len(f.mean)) for j in range(1, t)])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            nodes = b.column(0).to_numpy(zero_copy_only=False)
            x = as_matrix(objects(b.column(1)))
            cell = np.zeros(len(nodes), np.int32)
            for k in np.unique(nodes):
                cell[nodes == k] = np.searchsorted(shells[int(k)], fits[int(k)].radius2(x[nodes == k]))
            yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int32()), pa.array(cell)], ["node", "cell"])

    counts = some.select(F.col("node").cast("int").alias("node"), F.col(obj).alias("obj")).mapInArrow(count, "node int, cell int").groupBy("node", "cell").count().collect()
    out = []
    for k in sorted(sizes):
        t = len(shells[k]) + 1
        seen = np.zeros(t)
        for r in counts:
            if r["node"] == k:
                seen[r["cell"]] = r["count"]
        stat, used = chi_square_stat(seen, np.full(t, 1 / t))
        # the shells are fixed by the fit; a full covariance has more parameters than there can be shells, so one degree goes for the scale
        free = used - 2 if dof == "printed" else used - 1
        out.append(NodeFit(k, sizes[k], joint=fits[k], k_stat=stat, dof=free, confidence=confidence(stat, free)))
    return out


def global_confidence(fits: Sequence[tuple[float, int]], mode: str = "quantile_sum") -> float:
    """Confidence of all nodes together from their (statistic, degrees of freedom).

    'quantile_sum': the level at which the critical values add up to the sum of the statistics; it
    lies between the least and the greatest of the nodes. 'pooled': one test with all degrees of freedom.
    """
    total, used = sum(k for k, _ in fits), [d for _, d in fits if d > 0]
    if not used:
        return 0.0
    if mode == "pooled":
        return chi2_sf(total, sum(used))
    return bisect(lambda c: total - sum(chi2_isf(min(max(c, 1e-12), 1 - 1e-12), d) for d in used), 1e-12, 1 - 1e-12, 80)


def fits_table(spark, fits: Sequence[NodeFit]) -> DataFrame:
    """The fits as rows: one per node and dimension (dim -1: a joint law)."""
    rows = []
    for f in fits:
        if f.joint is not None:
            rows.append((f.node, -1, "mvn", [float(v) for v in f.joint.mean], {}, f.n, 0, f.dof, f.k_stat, f.confidence))
        rows += [(f.node, d, x.family, [float(v) for v in x.law.eta(x.params)], {a: float(b) for a, b in x.params.items()}, f.n, x.cells, x.dof, x.k_stat, x.confidence) for d, x in enumerate(f.dims)]
    return spark.createDataFrame(rows, "node int, dim int, family string, eta array<double>, params map<string,double>, n_rows long, cells int, dof int, k_stat double, confidence double")


def ecdf(df: DataFrame, value: str) -> DataFrame:
    """(value, share): share of rows at or below each distinct value, from counts of values."""
    counts = df.groupBy(F.col(value).alias("value")).agg(F.count(F.lit(1)).alias("n"))
    total = df.count()
    return running_sum(counts, ["value"], F.col("n"), "upto").select("value", (F.col("upto") / F.lit(float(max(total, 1)))).alias("share"))
