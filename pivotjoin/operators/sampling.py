"""Pivots: random, stratified, by fitted distributions, or drawn from them."""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .fits import MIX_P, NodeFit, portable_hash


def random_pivots(df: DataFrame, k: int, id_col: str = "id", seed: int = 7) -> DataFrame:
    """k rows in the order of a hash of the id: a uniform sample of exactly that size, the same on every run."""
    h = portable_hash(F.col(id_col), seed)
    return df.withColumn("_h", h).orderBy("_h", id_col).limit(k).drop("_h")


def shares(weights: Sequence[float], k: int, caps: Sequence[int] | None = None) -> list[int]:
    """k dealt in proportion to the weights by largest remainders, equal ones (to nine digits) from the first; what exceeds a cap goes to the others."""
    out, open_ = [0] * len(weights), [i for i, w in enumerate(weights) if w > 0]
    left = min(k, sum(caps)) if caps is not None else k
    while left and open_:
        total = sum(weights[i] for i in open_)
        exact = {i: left * weights[i] / total for i in open_}
        now = {i: int(exact[i]) for i in open_}
        for i in sorted(open_, key=lambda i: (round(now[i] - exact[i], 9), i))[: left - sum(now.values())]:
            now[i] += 1
        for i in open_:
            out[i] += now[i]
        left = 0
        if caps is not None:
            for i in open_:
                left += max(0, out[i] - caps[i])
                out[i] = min(out[i], caps[i])
            open_ = [i for i in open_ if out[i] < caps[i]]
    return out


def allocate(fits: Sequence[NodeFit], k: int, c_min: float = 1e-3) -> dict[int, int]:
    """Samples of each node: in proportion to its size over its confidence, never more than it has."""
    got = shares([f.n / max(f.confidence, c_min) for f in fits], k, [f.n for f in fits])
    return dict(zip([f.node for f in fits], got, strict=True))


def shuffled_stratified_pivots(df: DataFrame, k: int, strata: int, by: str, id_col: str = "id", seed: int = 7) -> DataFrame:
    """The direct way: the whole table is dealt into ranges of a value, and each range is sampled in proportion."""
    cuts = df.agg(F.percentile_approx(by, [i / strata for i in range(1, strata)] or [0.5])).first()[0] or []
    stratum = sum((F.when(F.col(by) > F.lit(c), 1).otherwise(0) for c in cuts), F.lit(0))
    x = df.withColumn("_stratum", stratum).withColumn("_h", portable_hash(F.col(id_col), seed))
    sizes = {r["_stratum"]: r["count"] for r in x.groupBy("_stratum").count().collect()}
    return _first_of_each(x, sizes, shares([sizes[s] for s in sorted(sizes)], k, [sizes[s] for s in sorted(sizes)]), "_stratum", id_col)


def local_stratified_pivots(df: DataFrame, k: int, id_col: str = "id", seed: int = 7) -> DataFrame:
    """The same number from each node, whatever its size or fit."""
    x = df.withColumn("_h", portable_hash(F.col(id_col), seed))
    sizes = {r["node"]: r["count"] for r in df.groupBy("node").count().collect()}
    return _first_of_each(x, sizes, shares([1.0] * len(sizes), k, [sizes[s] for s in sorted(sizes)]), "node", id_col)


def _first_of_each(x: DataFrame, sizes: dict, quota: Sequence[int], key: str, id_col: str) -> DataFrame:
    if not sizes:
        return x.drop("_h", "_stratum").limit(0)
    take = F.create_map(*[F.lit(v) for s, q in zip(sorted(sizes), quota, strict=True) for v in (s, q)])
    rank = F.row_number().over(Window.partitionBy(key).orderBy("_h", id_col))
    return x.withColumn("_rank", rank).where(F.col("_rank") <= F.element_at(take, F.col(key))).drop("_rank", "_h", "_stratum")


def node_boxes(fit: NodeFit, quota: int, how: str = "equal_probability") -> tuple[int, np.ndarray, np.ndarray]:
    """Axis, cuts and probabilities of the boxes of a node: as many slices along the widest axis as the square root of its quota."""
    laws = [fit.marginal(d) for d in range(fit.width)]
    axis = int(np.argmax([law.variance(p) for law, p in laws]))
    law, p = laws[axis]
    n = max(1, math.isqrt(quota))
    if how == "equal_width" and n > 1:
        lo, hi = law.quantile(p, 0.001), law.quantile(p, 0.999)
        cuts = np.linspace(lo, hi, n + 1)[1:-1]
    else:
        cuts = np.array([law.quantile(p, j / n) for j in range(1, n)])
    edges = np.array([0.0, *(law.cdf(p, c) for c in cuts), 1.0])
    return axis, cuts, np.diff(edges)


def box_quota(probabilities: np.ndarray, quota: int) -> list[int]:
    return shares(probabilities.tolist(), quota)


def distribution_aware_pivots(df: DataFrame, fits: Sequence[NodeFit], k: int, id_col: str = "id", obj: str = "obj", seed: int = 7, c_min: float = 1e-3, how: str = "equal_probability", accept: bool = True) -> DataFrame:
    """k real rows (with columns node, box): every node's quota is dealt over slices of its fitted law.

    A row is rejected with the probability that the fit is wrong; rejected rows are used only when
    a slice runs out of others. What a slice cannot give, the node's other slices give. A task
    passes on no more than a quota of its best rows, so the exchange carries quotas, not the table.
    """
    quota = allocate(fits, k, c_min)
    boxes = {f.node: node_boxes(f, quota[f.node], how) for f in fits if quota[f.node]}
    want = {n: box_quota(b[2], quota[n]) for n, b in boxes.items()}
    keep = {f.node: f.confidence if accept else 1.0 for f in fits}
    types = dict(df.dtypes)

    def tag(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list] = {}
        for b in batches:
            rows = zip(b.column("node").to_pylist(), b.column("_h").to_pylist(), b.column("_g").to_pylist(), b.column(id_col).to_pylist(), b.column(obj).to_pylist(), strict=True)
            for node, h, g, i, o in rows:
                if node not in boxes or o is None:
                    continue
                axis, cuts, _ = boxes[node]
                box = int(np.searchsorted(cuts, o[axis], side="left"))
                held.setdefault((node, box), []).append((g >= keep[node] * MIX_P, h, i, o))
            for (node, _), v in held.items():
                if len(v) > 4 * quota[node] + 64:
                    v.sort(key=lambda r: r[:3])
                    del v[quota[node] :]
        rows = [(n, x, int(r), h, i, o) for (n, x), v in held.items() for r, h, i, o in sorted(v, key=lambda r: r[:3])[: quota[n]]]
        if rows:
            yield pa.RecordBatch.from_pylist([dict(zip(("node", "box", "rejected", "h", "id", "obj"), r, strict=True)) for r in rows], schema=pa.schema([("node", pa.int32()), ("box", pa.int32()), ("rejected", pa.int32()), ("h", pa.int64()), ("id", pa.int64()), ("obj", pa.list_(pa.float64()))]))

    x = df.select(F.col(id_col).cast("long").alias(id_col), F.col(obj).cast("array<double>").alias(obj), F.col("node").cast("int").alias("node"), portable_hash(F.col(id_col), seed).alias("_h"), portable_hash(F.col(id_col), seed + 31).alias("_g"))
    tagged = x.mapInArrow(tag, "node int, box int, rejected int, h long, id long, obj array<double>")
    by_box = F.row_number().over(Window.partitionBy("node", "box").orderBy("rejected", "h", "id"))
    ranked = tagged.withColumn("r", by_box)
    spark = df.sparkSession
    quotas = spark.createDataFrame([(n, b, q) for n, qs in want.items() for b, q in enumerate(qs)] or [(-1, 0, 0)], "node int, box int, q int")
    ranked = ranked.join(F.broadcast(quotas), ["node", "box"], "left")  # as many rows as there are slices
    # within the node: first what fills the slices, then the rest in the same order
    order = F.row_number().over(Window.partitionBy("node").orderBy((F.col("r") > F.coalesce("q", F.lit(0))).cast("int"), "rejected", "h", "id"))
    totals = F.create_map(*[F.lit(v) for n, q in quota.items() for v in (n, q)])
    assert types[obj].startswith("array")
    return ranked.withColumn("_o", order).where(F.col("_o") <= F.element_at(totals, F.col("node"))).select("id", "obj", "node", "box")


def node_given_selector(fits: Sequence[NodeFit], selector: int, c_min: float = 1e-3) -> np.ndarray:
    """Probabilities of the nodes for the next proposal: sizes, divided by the confidences after an acceptance."""
    w = np.array([f.n * max(f.confidence, c_min) ** -selector for f in fits], float)
    return w / w.sum()


def gibbs_chain(fits: Sequence[NodeFit], k: int, seed: int = 7, burn_in: int = 0, c_min: float = 1e-3) -> tuple[np.ndarray, np.ndarray, int]:
    """Pivots, their nodes and the number of proposals of the sequential chain; a reference for ``mixture_draws``.

    The state holds node and selector; a rejected proposal leaves it as it was.
    """
    g = np.random.default_rng(seed)
    after = {s: node_given_selector(fits, s, c_min) for s in (0, 1)}
    node = int(g.choice(len(fits), p=after[0]))
    points, nodes, selector, proposals = [fits[node].draw(g, 1)[0]], [node], 1, 1
    while len(points) < k + burn_in:
        e = int(g.choice(len(fits), p=after[selector]))
        x = fits[e].draw(g, 1)[0]
        proposals += 1
        if g.random() < max(fits[e].confidence, c_min):
            points.append(x)
            nodes.append(e)
            selector = 1
    return np.array(points[burn_in : burn_in + k]), np.array([fits[i].node for i in nodes[burn_in : burn_in + k]]), proposals


def mixture_draws(spark, fits: Sequence[NodeFit], k: int, seed: int = 7, weights: str = "size", c_min: float = 1e-3) -> DataFrame:
    """(pivot_id, obj, node): independent draws of the law that the chain's accepted states have.

    An accepted state proposes by size over confidence and is kept with its confidence, so kept
    nodes come by size alone. Each draw has a generator of its own, so any number of tasks gives
    the same pivots, and only the nodes' parameters travel. weights='inverse_confidence' favours
    badly fitted nodes, as the quotas of real rows do.
    """
    share = node_given_selector(fits, 0 if weights == "size" else 1, c_min)
    fits = list(fits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            points, nodes = [], []
            for i in b.column(0).to_pylist():
                g = np.random.default_rng((seed, i))
                f = fits[int(g.choice(len(fits), p=share))]
                nodes.append(f.node)
                points.append(f.draw(g, 1)[0].tolist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(points, pa.list_(pa.float64())), pa.array(nodes, pa.int32())], ["pivot_id", "obj", "node"])

    tasks = max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), k // 1000))
    return spark.range(0, k, 1, tasks).mapInArrow(run, "pivot_id long, obj array<double>, node int")


def generative_pivots(spark, fits: Sequence[NodeFit], k: int, seed: int = 7, engine: str = "mixture") -> np.ndarray:
    """k drawn pivots on the driver."""
    if engine == "chain":
        return gibbs_chain(fits, k, seed)[0]
    rows = mixture_draws(spark, fits, k, seed).orderBy("pivot_id").collect()
    return np.array([r["obj"] for r in rows], float)


# -- error bounds --------------------------------------------------------------------------------


def exceed_prob(k: int, m: int, eps: float, form: str = "union") -> float:
    """Bound of the probability that the sampling error reaches eps. 'union' needs no independence of dimensions."""
    one = 2 * math.exp(-2 * k * eps * eps)
    return min(1.0, m * one) if form == "union" else 1 - max(0.0, 1 - one) ** m


def sample_size(eps: float, m: int, alpha: float = 0.05) -> int:
    return math.ceil(math.log(2 * m / alpha) / (2 * eps * eps))


def error_bound(k: int, m: int, alpha: float = 0.05) -> float:
    return math.sqrt(math.log(2 * m / alpha) / (2 * k))


def error_bound_local(quotas: Sequence[int], m: int, alpha: float = 0.05) -> float:
    """Of stratified samples: the bound of the node with the fewest."""
    return max(error_bound(q, m, alpha) for q in quotas if q)


def sampling_traffic(k: int, nodes: int) -> dict[str, int]:
    """Records sent: samples to all other nodes, or parameters to all other nodes; and parameters to one driver and back."""
    return {"distribution_aware": k * (nodes - 1), "generative": nodes * (nodes - 1), "generative_through_driver": 2 * nodes}


def sampling_error(samples: np.ndarray, fits: Sequence[NodeFit] | None = None, data: np.ndarray | None = None) -> float:
    """Greatest gap, over dimensions and values, between the samples' shares and the mixture's or the data's."""
    worst = 0.0
    for d in range(samples.shape[1]):
        x = np.sort(samples[:, d])
        if data is not None:
            ref = np.sort(data[:, d])
            at = np.concatenate([x, ref])
            gap = np.abs(np.searchsorted(x, at, side="right") / len(x) - np.searchsorted(ref, at, side="right") / len(ref)).max()
        else:
            f = np.array([mixture_cdf(fits, d, v) for v in x])
            i = np.arange(1, len(x) + 1)
            gap = max((i / len(x) - f).max(), (f - (i - 1) / len(x)).max())
        worst = max(worst, float(gap))
    return worst


def mixture_cdf(fits: Sequence[NodeFit], d: int, x: float) -> float:
    """Marginal distribution function of all nodes together."""
    total = sum(f.n for f in fits)
    return sum(f.n * law.cdf(p, x) for f in fits for law, p in [f.marginal(d)]) / total
