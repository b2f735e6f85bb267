"""The join: plan it from pivots, route objects to regions, verify inside regions."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.filters import counted_pairs, prefix, ranked_classes, ranked_sets, segment_index, segment_probes, with_copies
from ..functions.metrics import Metric, as_matrix, metric_of, objects, padded
from ..plans.config import MOST_REGIONS, SAMPLERS, SPLITTERS, JoinConfig
from . import sampling
from .fits import NodeFit, fit_nodes, with_nodes
from .split import Tree, choose_axes, cluster_labels, grow
from .tables import materialize

PAIRS = "id_x long, id_y long, distance double"
#: Real objects that come to the driver for axes and, where pivots are drawn, for snapping.
AXIS_POOL = 2000
#: Blocks that a region is dealt into at most, as long as they have no more than BLOCK_ROWS rows.
MOST_BLOCKS, BLOCK_ROWS = 32, 20_000
#: Strings that are compared with a cell's others before their pairs are given out.
NEAR_ROWS = 2048
#: Vectors are compared once for all equal ones where there are so many rows for each different one.
REPEATED = 8
#: Members of a class that are kept in one list.
LISTED = 1000
#: Pairs that tell whether coordinates rule out most of a cell, and the share that has to be left for ``Metric.maybe`` to come first.
TRIED_PAIRS, LEFT_SHARE = 4096, 0.25


@dataclass
class JoinPlan:
    """What the driver decided: small, and sent to every task."""

    metric: Metric
    delta: float
    config: JoinConfig
    rows: int
    k: int
    p: int
    n: int
    axes: list
    tree: Tree
    coords: np.ndarray
    labels: np.ndarray | None = None
    fits: list[NodeFit] = field(default_factory=list)
    boxes: tuple[np.ndarray, np.ndarray] | None = None
    seconds: dict[str, float] = field(default_factory=dict)
    #: Where the plan departs from what was asked for.
    notes: list[str] = field(default_factory=list)


def validate_objects(df: DataFrame, id_col: str, obj_col: str, metric: Metric, on_bad: str = "drop", keep: tuple[Column, ...] = ()) -> DataFrame:
    """(id, obj, and what to keep) of usable rows: id and object not null, vectors without null or non-finite elements.

    on_bad='error' raises if there are others. Ids have to be unique; ``bad_rows`` counts both kinds.
    """
    out = df.select(F.col(id_col).cast("long").alias("id"), F.col(obj_col).alias("obj"), *keep)
    good = F.col("id").isNotNull() & F.col("obj").isNotNull()
    if metric.kind == "vector":
        out = out.withColumn("obj", F.col("obj").cast("array<double>"))
        good = good & F.forall("obj", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    if on_bad == "error" and out.where(~good | good.isNull()).limit(1).count():
        raise ValueError("null or non-finite objects")
    return out.where(good)


def bad_rows(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric) -> dict[str, int]:
    good = validate_objects(df, id_col, obj_col, metric_of(metric))
    n = good.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("id").alias("ids")).first()
    return {"unusable": df.count() - n["n"], "repeated_ids": n["n"] - n["ids"]}


def make_plan(objs: DataFrame, metric: Metric, delta: float, config: JoinConfig) -> JoinPlan:
    """Sample pivots, map them, label them, split. ``objs``: (id, obj)."""
    if config.sampler not in SAMPLERS or config.splitter not in SPLITTERS:
        raise ValueError("unknown sampler or splitter")
    began, seconds, notes = time.time(), {}, []
    spark = objs.sparkSession
    rows = objs.count()
    k, p, n = config.sized(rows)
    draws = config.sampler in ("generative", "distribution_aware")
    space = config.space or ("origin" if metric.kind == "vector" else "target")
    if draws and rows < 8 * max(1, config.nodes):
        config, draws = replace(config, sampler="random"), False  # too few to fit laws to
        notes.append(f"{rows} objects are too few to fit {config.nodes} laws to: random pivots")
    pool_size = max(AXIS_POOL if draws else k * config.oversample, n)
    pool = [r["obj"] for r in sampling.random_pivots(objs, min(pool_size, rows), seed=config.seed).select("obj").collect()]
    axes = choose_axes(pool, n, metric, config.axes, config.seed)
    pivots, coords, fits = pool[: k * config.oversample], None, []
    if draws:
        data = objs
        if space == "target":
            data = materialize(objs.select("id", metric.to_axes(F.col("obj"), axes).alias("obj")))  # read by the sums, the cells and the draws
        elif metric.kind == "scalar":
            data = objs.select("id", F.array(F.col("obj").cast("double")).alias("obj"))
        data = with_nodes(data, "id", config.node_by, config.nodes, config.seed)
        model = config.model if space == "origin" else "mvn_full"
        fits = fit_nodes(data, "id", "obj", config.families, model, config.cells, config.gof_rows, config.seed, cells_by=config.cells_by)
        if config.sampler == "generative":
            made = sampling.generative_pivots(spark, fits, k, config.seed)
        else:
            made = np.array([r["obj"] for r in sampling.distribution_aware_pivots(data, fits, k, "id", "obj", config.seed, config.c_min, config.boxes).orderBy("id").collect()], float)
        if space == "target":
            pivots, coords = None, made
            if config.snap:
                real = metric.block(pool, axes)
                near = np.array([np.abs(real - c).max(axis=1).argmin() for c in made])
                pivots, coords = [pool[i] for i in near], real[near]
        else:
            pivots = made if metric.kind == "vector" else made[:, 0]
            if config.snap:
                pivots = [pool[i] for i in metric.block(list(pivots), pool).argmin(axis=1)]
    elif config.sampler in ("stratified", "local"):
        data = with_nodes(objs, "id", config.node_by, config.nodes, config.seed)
        got = sampling.local_stratified_pivots(data, k, seed=config.seed) if config.sampler == "local" else sampling.shuffled_stratified_pivots(data, k, config.nodes, "node", seed=config.seed)
        pivots = [r["obj"] for r in got.orderBy("id").collect()]
    seconds["sampling"] = time.time() - began
    began = time.time()
    if coords is None:
        coords = metric.block(list(pivots), axes) if len(axes) else np.zeros((len(pivots), 0))
    labels = None
    if config.splitter == "learned" and len(coords):
        origin = pivots is not None and (config.label_space or ("origin" if metric.kind in ("vector", "scalar") else "target")) == "origin"
        labels = cluster_labels(list(pivots) if origin else list(coords), metric if origin else None, config.n_labels, seed=config.seed)
    tree = grow(coords, p, config.splitter, labels, config.seed)
    while config.max_copies and tree.regions > 1 and expected_copies(tree, coords, delta, config.replication) > config.max_copies:
        # coordinates do not tell these objects apart at this threshold: fewer regions, down to one that is dealt into blocks
        p = max(1, tree.regions // 2)
        tree = grow(coords, p, config.splitter, labels, config.seed)
    if tree.regions < p or p < config.sized(rows)[1]:
        notes.append(f"{tree.regions} of {config.sized(rows)[1]} regions: pivots do not differ more, or more than {config.max_copies} copies were expected")
    seconds["split"] = time.time() - began
    plan = JoinPlan(metric, delta, config, rows, k, p, n, axes, tree, as_matrix(coords), labels, fits, None, seconds, notes)
    if config.bounds == "pivot_box":
        plan.boxes = _boxes_of(plan.coords, tree.home(plan.coords), tree.regions)
    return plan


def expected_copies(tree: Tree, coords: np.ndarray, delta: float, replication: str) -> float:
    """Rows per object after routing, as the pivots tell."""
    x = as_matrix(coords)
    if not len(x):
        return 1.0
    row, region = tree.near(x, delta)
    home = tree.home(x)[row]
    return 1.0 + float((region < home).sum() if replication == "lower" else (region != home).sum()) / len(x)


def _boxes_of(x: np.ndarray, home: np.ndarray, regions: int) -> tuple[np.ndarray, np.ndarray]:
    lo, hi = np.full((regions, x.shape[1]), np.inf), np.full((regions, x.shape[1]), -np.inf)
    np.minimum.at(lo, home, x)
    np.maximum.at(hi, home, x)
    return lo, hi


def mapped(objs: DataFrame, plan: JoinPlan) -> DataFrame:
    """Adds coord (distances to the axes) and home (the object's one region). Rows do not move."""
    tree, lossy = plan.tree, plan.config.bounds == "pivot_box"
    boxes = plan.boxes

    @F.arrow_udf("int")
    def home(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for part in parts:
            x = as_matrix(objects(part))
            h = tree.home(x)
            if lossy:
                inside = ((x >= boxes[0][h]) & (x <= boxes[1][h])).all(axis=1)
                h = np.where(inside, h, -1)
            yield pa.array(h, pa.int32())

    return objs.withColumn("coord", plan.metric.to_axes(F.col("obj"), plan.axes)).withColumn("home", home("coord"))


def data_boxes(with_home: DataFrame, plan: JoinPlan) -> tuple[np.ndarray, np.ndarray]:
    """Boxes around the objects of each region: one row per region comes to the driver."""
    n = plan.tree.width
    ends = [f(F.col("coord")[d]).alias(f"{s}{d}") for d in range(n) for s, f in (("a", F.min), ("b", F.max))]
    lo, hi = np.full((plan.tree.regions, n), np.inf), np.full((plan.tree.regions, n), -np.inf)
    for r in with_home.groupBy("home").agg(F.count(F.lit(1)).alias("_n"), *ends).collect():
        lo[r["home"]], hi[r["home"]] = [r[f"a{d}"] for d in range(n)], [r[f"b{d}"] for d in range(n)]
    return lo, hi


def region_lists(plan: JoinPlan, which: str):
    """UDF (coord, home) -> regions an object goes to. which: 'lower' and 'both' as in the configuration (home first), 'whole' (all near ones)."""
    tree, delta, boxes = plan.tree, plan.delta, plan.boxes
    pad, lossy = padded(plan.delta), plan.config.bounds == "pivot_box"

    @F.arrow_udf("array<int>")
    def regions(coord: pa.Array, home: pa.Array) -> pa.Array:
        x = as_matrix(objects(coord))
        h = home.to_numpy(zero_copy_only=False)
        row, region = tree.near(x, delta)
        if lossy:  # published boxes: every region is asked
            row, region = (a.ravel() for a in np.meshgrid(np.arange(len(x)), np.arange(tree.regions), indexing="ij"))
        keep = np.ones(len(row), bool) if which == "whole" else region != h[row]
        if which == "lower":
            keep &= region < h[row]
        if boxes is not None:
            keep &= ((x[row] >= boxes[0][region] - pad) & (x[row] <= boxes[1][region] + pad)).all(axis=1)
        row, region = row[keep], region[keep]
        if which != "whole":
            own = np.flatnonzero(h >= 0)
            row, region = np.concatenate([own, row]), np.concatenate([h[own], region])
        order = np.argsort(row, kind="stable")
        ends = np.concatenate(([0], np.cumsum(np.bincount(row, minlength=len(x)))))
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(region[order], pa.int32()))

    return regions("coord", "home")


def route(objs: DataFrame, plan: JoinPlan, which: str | None = None) -> DataFrame:
    """(region, home, id, obj, coord): an object once for its home and once for each copy.

    With copies to lower regions only, a pair of different homes meets in the lower of them and
    nowhere else, so no result is found twice.
    """
    x = mapped(objs, plan)
    if plan.config.bounds == "data_box" and plan.boxes is None:
        began = time.time()
        plan.boxes = data_boxes(x, plan)
        plan.seconds["boxes"] = time.time() - began
    kept = [c for c in ("by",) if c in x.columns]
    return x.select(F.explode(region_lists(plan, which or plan.config.replication)).alias("region"), "home", "id", "obj", "coord", *kept)


def _parts(sized: list[DataFrame], max_region: int) -> DataFrame:
    """(region, parts) of regions of more than max_region rows in one of the tables: how many blocks each is dealt into. A row a region.

    A row goes to as many cells as there are blocks: there are at most MOST_BLOCKS, as long as these have no more than BLOCK_ROWS.
    """
    counts = [d.groupBy("region").agg(F.count(F.lit(1)).alias("n")) for d in sized]
    n = counts[0]
    for c in counts[1:]:
        n = n.unionByName(c)
    n = n.groupBy("region").agg(F.max("n").alias("n")).where(F.col("n") > max_region)
    parts = F.least(F.ceil(F.col("n") / max_region), F.greatest(F.lit(MOST_BLOCKS), F.ceil(F.col("n") / BLOCK_ROWS)))
    return F.broadcast(materialize(n.select("region", parts.cast("int").alias("parts")), MOST_REGIONS))


def _dealt(rows: DataFrame, parts: DataFrame) -> DataFrame:
    """Adds own, the block of a row's region that it is dealt to, and parts, the number of blocks."""
    x = rows.join(parts, "region", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    return x.withColumn("own", F.pmod(F.xxhash64("id", F.lit(11)), F.col("parts")).cast("int"))


def _grid(routed: DataFrame, plan: JoinPlan) -> DataFrame:
    """Adds the cell (a, b) of a region's grid and own: regions of more than max_region rows are dealt into blocks, and each pair of blocks is a cell."""
    x = _dealt(routed, _parts([routed], plan.config.max_region)).withColumn("_o", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    return x.withColumn("a", F.least("own", "_o")).withColumn("b", F.greatest("own", "_o")).drop("_o", "parts")


def _block_pairs(metric: Metric, delta: float, xs, ys, cx: np.ndarray, cy: np.ndarray, allowed) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, distance) of pairs within delta, some at a time. Coordinates rule out most pairs before a distance is computed.

    ``allowed``: rows and columns, as indices that are spread over each other, -> which pairs count.
    """
    pad = padded(delta)
    if metric.near is not None:
        order = sorted(range(len(xs)), key=xs.__getitem__)
        for s in range(0, len(order), NEAR_ROWS):
            part = np.array(order[s : s + NEAR_ROWS])
            found = metric.near([xs[i] for i in part], ys, delta)
            if found is None:
                break
            i, j, d = found
            keep = allowed(part[i], j)
            yield part[i][keep], j[keep], d[keep]
        else:
            return
    found = metric.maybe(xs, ys, delta) if metric.maybe is not None and isinstance(xs, np.ndarray) and isinstance(ys, np.ndarray) and _share_left(cx, cy, pad) > LEFT_SHARE else None
    if found is not None:
        for i, j in found:
            keep = allowed(i, j)
            i, j = i[keep], j[keep]
            for q in range(0, len(i), 1 << 14):
                a, b = i[q : q + (1 << 14)], j[q : q + (1 << 14)]
                dist = metric.rowwise(xs[a], ys[b])
                near = dist <= pad
                yield a[near], b[near], dist[near]
        return
    rows = max(1, (1 << 22) // max(1, len(ys)))
    every = np.arange(len(ys))[None, :]
    for s in range(0, len(xs), rows):
        e = min(s + rows, len(xs))
        ok = allowed(np.arange(s, e)[:, None], every)
        for d in range(cx.shape[1]):
            ok &= np.abs(cx[s:e, d, None] - cy[None, :, d]) <= pad
        if metric.rowwise is not None and isinstance(xs, np.ndarray) and isinstance(ys, np.ndarray):
            i, j = np.nonzero(ok)
            for q in range(0, len(i), 1 << 16):
                a, b = i[q : q + (1 << 16)] + s, j[q : q + (1 << 16)]
                dist = metric.rowwise(xs[a], ys[b])
                near = dist <= pad
                yield a[near], b[near], dist[near]
        elif ok.any():
            dist = metric.block(xs[s:e], ys)
            i, j = np.nonzero(ok & (dist <= pad))
            yield i + s, j, dist[i, j]


def _share_left(cx: np.ndarray, cy: np.ndarray, pad: float) -> float:
    """Share of pairs that coordinates leave, by some of them spread over both sides."""
    if not (len(cx) and len(cy)):
        return 0.0
    g = np.random.default_rng(7)
    i, j = g.integers(0, len(cx), TRIED_PAIRS), g.integers(0, len(cy), TRIED_PAIRS)
    return float((np.abs(cx[i] - cy[j]) <= pad).all(axis=1).mean())


def _take(x, at: np.ndarray):
    return x[at] if isinstance(x, np.ndarray) else [x[i] for i in at]


def _batch(x: np.ndarray, y: np.ndarray, d: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64()), pa.array(d, pa.float64())], ["id_x", "id_y", "distance"])


def in_cells(cells: DataFrame, keys: tuple[str, ...], run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> DataFrame:
    """Pairs that ``run`` finds in each cell. Cells are few bytes and much work, so they are not put together by their bytes."""
    n = int(cells.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cells.repartition(n, *keys).groupBy(*keys).applyInArrow(run, PAIRS)


def met(metric: Metric, delta: float, ids: np.ndarray, xs, coord: np.ndarray, left: np.ndarray, right: np.ndarray, once: bool, also=None) -> Iterator[pa.RecordBatch]:
    """Pairs within delta of the rows left and right, by their places; ``once``: both are the same rows, and each pair of them counts once. ``also``: (places, places) -> which pairs count."""
    if not (len(left) and len(right)):
        return
    sides = [(left, right)]
    halved = once and (metric.near is not None or metric.maybe is not None)
    if halved:  # parts, sorted where that serves, each with itself and those behind it
        if metric.near is not None:
            left = left[sorted(range(len(left)), key=lambda i: xs[left[i]])]
        sides = [(left[s : s + NEAR_ROWS], left[s:]) for s in range(0, len(left), NEAR_ROWS)]
    for mine, rest in sides:

        def allowed(p: np.ndarray, q: np.ndarray, mine=mine, rest=rest) -> np.ndarray:
            x, y = ids[mine[p]], ids[rest[q]]
            ok = (p < q) & (x != y) if halved else x < y if once else np.ones(np.broadcast_shapes(p.shape, q.shape), bool)
            return ok if also is None else ok & also(mine[p], rest[q])

        for i, j, d in _block_pairs(metric, delta, _take(xs, mine), _take(xs, rest), coord[mine], coord[rest], allowed):
            x, y = ids[mine[i]], ids[rest[j]]
            yield _batch(np.minimum(x, y), np.maximum(x, y), d)


def whole_cells(rows: DataFrame, metric: Metric, delta: float, also: Callable[[pa.Table], Callable], max_region: int = BLOCK_ROWS) -> DataFrame:
    """Pairs within delta of rows (region, id, obj) of one region. Large regions are dealt into blocks. ``also``: a cell's table -> which pairs of places count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches)).combine_chunks()
        a, b = (t.column(c)[0].as_py() for c in ("a", "b"))
        ids, own = (t.column(c).to_numpy() for c in ("id", "own"))
        left, right = np.flatnonzero(own == a), np.flatnonzero(own == b)
        yield from met(metric, delta, ids, objects(t.column("obj").chunk(0)), np.zeros((len(ids), 0)), left, right, a == b, also(t))

    return in_cells(_grid(rows, _Blocks(JoinConfig(max_region=max_region))), ("region", "a", "b"), run)


@dataclass
class _Blocks:
    """What dealing into blocks reads of a plan."""

    config: JoinConfig


def verify_blocks(routed: DataFrame, plan: JoinPlan) -> DataFrame:
    """Pairs within delta, cell by cell, in numpy; a task holds one cell of bounded size and gives its pairs out in parts."""
    metric, delta = plan.metric, plan.delta

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches)).combine_chunks()
        region, a, b = (t.column(c)[0].as_py() for c in ("region", "a", "b"))
        ids, home, own = (t.column(c).to_numpy() for c in ("id", "home", "own"))
        xs = objects(t.column("obj").chunk(0))
        coord = as_matrix(objects(t.column("coord").chunk(0)))
        kernel = home == region
        later = home > region
        if a == b:  # two rows at home meet once, and each a copy from a later region
            steps = [(kernel, kernel, True), (kernel, later, False)]
        else:
            steps = [(kernel & (own == a), (kernel | later) & (own == b), False), (kernel & (own == b), later & (own == a), False)]
        for left, right, once in steps:
            yield from met(metric, delta, ids, xs, coord, np.flatnonzero(left), np.flatnonzero(right), once)

    return in_cells(_grid(routed, plan), ("region", "a", "b", *(c for c in ("by",) if c in routed.columns)), run)


def coord_prune(x: Column, y: Column, delta: float) -> Column:
    """Coordinates of a pair within delta differ by at most delta on every axis."""
    return F.forall(F.zip_with(x, y, lambda a, b: F.abs(a - b) <= F.lit(padded(delta))), lambda v: v)


def verify_sql(routed: DataFrame, plan: JoinPlan) -> DataFrame:
    """Pairs within delta by an equi-join in the JVM: on the cell of a region's grid, or on what the filters of sets and strings share inside a region."""
    if uses_prefixes(plan):
        # of a copy only the prefix is read
        size, home = F.size("obj"), F.col("home") == F.col("region")
        routed = materialize(routed.select("region", "home", "id", size.alias("size"), F.when(home, F.col("obj")).otherwise(prefix(size, plan.delta)).alias("obj")))
        return _prefix_pairs(routed.where(home), routed, plan)
    routed = materialize(routed)  # both sides read it: mapping is not done twice
    if plan.config.segments and plan.metric.kind == "string" and plan.delta >= 0:
        return _segment_pairs(routed.where(F.col("home") == F.col("region")), routed, plan)
    dealt = _grid(routed, plan)
    x, y = dealt.where(F.col("home") == F.col("region")).alias("x"), dealt.alias("y")
    cell = (F.col("x.region") == F.col("y.region")) & (F.col("x.a") == F.col("y.a")) & (F.col("x.b") == F.col("y.b"))
    if "by" in dealt.columns:
        cell = cell & (F.col("x.by") == F.col("y.by"))
    # off the diagonal of the grid only rows of different blocks meet
    both = x.join(y, cell & ((F.col("x.a") == F.col("x.b")) | (F.col("x.own") != F.col("y.own"))) & _once())
    return _checked(both, plan, F.col("x.obj"), F.col("y.obj"))


def _once() -> Column:
    """Of two home objects each pair once; a copy meets home objects of an earlier region than its own."""
    return F.when(F.col("y.home") == F.col("y.region"), F.col("x.id") < F.col("y.id")).otherwise(F.col("y.home") > F.col("y.region"))


def uses_prefixes(plan: JoinPlan) -> bool:
    return plan.metric.name == "jaccard" and plan.config.filters and 0 <= plan.delta < 1


def _prefix_pairs(x: DataFrame, y: DataFrame, plan: JoinPlan, ordered: bool = True) -> DataFrame:
    """Sets of token ranks, x and y (region, home, id, size, obj): inside a region only those are compared that share enough tokens of both prefixes.

    Postings carry ids, sizes and places; the sets themselves join the few candidates afterwards.
    """
    delta = plan.delta

    def posted(side: DataFrame, name: str) -> DataFrame:
        # a set without tokens has one mark of its own: two such sets are at distance 0
        tokens = F.when(F.col("size") == 0, F.array(F.lit(-1).cast("long"))).otherwise(prefix(F.col("size"), delta))
        return side.select("region", "home", "id", "size", F.posexplode(tokens).alias("pos", "token")).alias(name)

    on = (F.col("x.region") == F.col("y.region")) & (F.col("x.token") == F.col("y.token"))
    if ordered:
        on = on & _once()
    found = materialize(counted_pairs(posted(x, "x"), posted(y, "y"), on, delta))
    a = x.select(F.col("id").alias("i"), F.col("obj").alias("p"))
    b = (x if ordered else y.dropDuplicates(["id"])).select(F.col("id").alias("j"), F.col("obj").alias("q"))
    both = found.join(a, "i").join(b, "j")
    shared = F.size(F.array_intersect("p", "q"))
    both = both.select("i", "j", shared.alias("n"), (F.size("p") + F.size("q")).alias("s"))
    both = both.select("i", "j", F.when(F.col("s") == 0, F.lit(0.0)).otherwise(1.0 - F.col("n") / (F.col("s") - F.col("n"))).alias("distance")).where(F.col("distance") <= F.lit(padded(delta)))
    ends = (F.least("i", "j"), F.greatest("i", "j")) if ordered else (F.col("i"), F.col("j"))
    return both.select(ends[0].alias("id_x"), ends[1].alias("id_y"), "distance")


def _segment_pairs(home: DataFrame, routed: DataFrame, plan: JoinPlan) -> DataFrame:
    """Strings: inside a region only those are compared of which one holds a segment of the other near its place."""
    keep, delta = ("region", "home", "id"), int(padded(plan.delta))
    x, y = segment_index(home, delta, keep).alias("x"), segment_probes(routed, delta, keep).alias("y")
    on = F.lit(True)
    for c in ("region", "n", "i", "seg"):
        on = on & (F.col(f"x.{c}") == F.col(f"y.{c}"))
    # the segments of one string are asked of the other: of two home objects in either order
    other = F.when(F.col("y.home") == F.col("y.region"), F.col("x.id") != F.col("y.id")).otherwise(F.col("y.home") > F.col("y.region"))
    found = x.join(y, on & other).select(F.least("x.id", "y.id").alias("i"), F.greatest("x.id", "y.id").alias("j")).distinct()
    objs = home.select("id", "obj", "coord")
    both = found.join(objs.alias("x"), F.col("i") == F.col("x.id")).join(objs.alias("y"), F.col("j") == F.col("y.id"))
    return _checked(both, plan, F.col("x.obj"), F.col("y.obj"))


def _checked(both: DataFrame, plan: JoinPlan, px: Column, py: Column, ordered: bool = True) -> DataFrame:
    m, delta = plan.metric, plan.delta
    if plan.config.filters:
        for f in m.filters:
            both = both.where(f(px, py, delta))
        if plan.axes:
            both = both.where(coord_prune(F.col("x.coord"), F.col("y.coord"), delta))
    both = both.where(m.at_most(px, py, delta))
    ids = F.col("x.id"), F.col("y.id")
    low, high = (F.least(*ids), F.greatest(*ids)) if ordered else ids
    return both.select(low.alias("id_x"), high.alias("id_y"), m.distance(px, py).cast("double").alias("distance"))


def engine_of(plan: JoinPlan) -> str:
    m = plan.metric
    whole = m.near is not None and not plan.config.segments and m.near([], [], plan.delta) is not None
    return plan.config.engine or ("block" if m.kind == "vector" or m.column is None or whole else "sql")


def verify(routed: DataFrame, plan: JoinPlan) -> DataFrame:
    found = verify_blocks(routed, plan) if engine_of(plan) == "block" else verify_sql(routed, plan)
    return found.distinct() if plan.config.bounds == "pivot_box" else found


def metric_self_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, config: JoinConfig | None = None, by: str | None = None) -> DataFrame:
    """(id_x, id_y, distance): every unordered pair of rows within delta, once, id_x < id_y.

    Null objects and vectors with null or non-finite elements match nothing; ids have to be unique.
    ``by``: only rows with equal values in this column are compared; null equals nothing.
    """
    m, config = metric_of(metric), config or JoinConfig()
    if by is not None:
        if config.collapse or config.segments or m.kind == "set":
            raise ValueError("an equality goes with cells only, not with collapse, segments or sets")
        df = df.where(F.col(by).isNotNull())
    objs = validate_objects(df, id_col, obj_col, m, keep=() if by is None else (F.col(by).alias("by"),))
    if delta < 0:
        return objs.sparkSession.createDataFrame([], PAIRS)
    if config.collapse or (by is None and _repeated(objs, m)):
        return _collapsed(objs, m, delta, config)
    if m.name == "jaccard" and config.filters and delta < 1:
        objs, copies = ranked_classes(objs)
        return with_copies(_planned_join(objs, m, delta, config), copies)
    return _planned_join(objs, m, delta, config)


def _planned_join(objs: DataFrame, m: Metric, delta: float, config: JoinConfig) -> DataFrame:
    plan = make_plan(objs, m, delta, config)
    if config.per_region and plan.rows > config.per_region:
        plan = refined(objs, plan, config.per_region)
    return verify(route(objs, plan), plan)


def _repeated(objs: DataFrame, m: Metric) -> bool:
    """Whether vectors have many copies: one pass over hashes."""
    if m.kind != "vector":
        return False
    n = objs.agg(F.count(F.lit(1)).alias("rows"), F.approx_count_distinct(F.xxhash64("obj")).alias("classes")).first()
    return n["rows"] >= REPEATED * max(1, n["classes"])


def _collapsed(objs: DataFrame, m: Metric, delta: float, config: JoinConfig) -> DataFrame:
    """Compare one row of each group of equal objects, then pair the groups' members.

    Members move as lists of about LISTED ids at most; the pairs of two lists are made where the lists meet, and these are dealt over all tasks.
    """
    objs = materialize(objs)
    reps = materialize(objs.groupBy("obj").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("n")))
    pairs = materialize(_planned_join(reps.select(F.col("rep").alias("id"), "obj"), m, delta, replace(config, collapse=False)))
    part = F.pmod(F.xxhash64("id", F.lit(13)), F.ceil(F.col("n") / LISTED))
    lists = materialize(objs.join(reps, "obj").select("id", "rep", "n", part.alias("part")).groupBy("rep", "n", "part").agg(F.collect_list("id").alias("ids")))
    x, y = (lists.select(F.col("rep").alias(f"id_{s}"), F.col("n").alias(f"n_{s}"), F.col("part").alias(f"part_{s}"), F.col("ids").alias(s)) for s in "xy")
    across = pairs.join(x, "id_x").join(y, "id_y").select("x", "y", "distance", F.lit(True).alias("both"), "id_x", "part_x", "id_y", "part_y")
    own = x.where("n_x > 1").join(y, (F.col("id_x") == F.col("id_y")) & (F.col("part_x") <= F.col("part_y")))
    own = own.select("x", "y", F.lit(0.0).alias("distance"), (F.col("part_x") < F.col("part_y")).alias("both"), "id_x", "part_x", "id_y", "part_y")
    met = across.unionByName(own).repartition(int(objs.sparkSession.conf.get("spark.sql.shuffle.partitions")), "id_x", "part_x", "id_y", "part_y")
    each = met.select("distance", "both", "y", F.explode("x").alias("x")).select("distance", "both", "x", F.explode("y").alias("y")).where(F.col("both") | (F.col("x") < F.col("y")))
    return each.select(F.least("x", "y").alias("id_x"), F.greatest("x", "y").alias("id_y"), "distance")


def join_classes(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, config: JoinConfig | None = None) -> tuple[DataFrame, DataFrame]:
    """(pairs of representatives, (id, rep)): for data of many equal objects, whose pairs are not written out."""
    m = metric_of(metric)
    objs = validate_objects(df, id_col, obj_col, m)
    if m.name == "jaccard" and (config or JoinConfig()).filters and 0 <= delta < 1:
        ids = objs.select("id")
        ranked, copies = ranked_classes(objs)
        pairs = _planned_join(ranked, m, delta, replace(config or JoinConfig(), collapse=False))
        if copies is None:
            return pairs, ids.select("id", F.col("id").alias("rep"))
        return pairs, ids.join(copies, "id", "left").select("id", F.coalesce("rep", "id").alias("rep"))
    reps = objs.groupBy("obj").agg(F.min("id").alias("rep"))
    pairs = metric_self_join(reps.select(F.col("rep").alias("id"), "obj"), "id", "obj", m, delta, config)
    return pairs, objs.join(reps, "obj").select("id", "rep")


def metric_join(left: DataFrame, right: DataFrame, id_cols: tuple[str, str], obj_cols: tuple[str, str], metric: str | Metric, delta: float, config: JoinConfig | None = None) -> DataFrame:
    """(id_x, id_y, distance): pairs of a left and a right row within delta, once each.

    A left object has one home; a right one goes to every region that reaches within delta of it.
    """
    m, config = metric_of(metric), config or JoinConfig()
    a, b = (validate_objects(d, i, o, m) for d, i, o in zip((left, right), id_cols, obj_cols, strict=True))
    if delta < 0:
        return a.sparkSession.createDataFrame([], PAIRS)
    if m.name == "jaccard" and config.filters and delta < 1:
        # one order of tokens for both sides
        both = a.select(F.lit(0).alias("side"), "id", "obj").unionByName(b.select(F.lit(1).alias("side"), "id", "obj"))
        both = materialize(ranked_sets(both, ("side", "id")))
        a, b = (both.where(F.col("side") == s).select("id", "obj") for s in (0, 1))
    plan = make_plan(a, m, delta, config)
    if config.per_region and plan.rows > config.per_region:
        plan = refined(a, plan, config.per_region)
    x = mapped(a, plan)
    if config.bounds == "data_box":
        plan.boxes = data_boxes(x, plan)
    kernel = x.select(F.col("home").alias("region"), "home", "id", "obj", "coord")
    whole = mapped(b, plan).select(F.explode(region_lists(plan, "whole")).alias("region"), "home", "id", "obj", "coord")
    if engine_of(plan) == "sql" and uses_prefixes(plan):
        kernel, whole = (materialize(d.select("region", "home", "id", F.size("obj").alias("size"), "obj")) for d in (kernel, whole))
        return _prefix_pairs(kernel, whole, plan, ordered=False)
    kernel, whole = materialize(kernel), materialize(whole)
    parts, every = _parts([kernel, whole], config.max_region), F.explode(F.sequence(F.lit(0), F.col("parts") - 1))
    kernel, whole = (_dealt(d, parts).withColumn(b, every).withColumnRenamed("own", a).drop("parts") for d, a, b in ((kernel, "a", "b"), (whole, "b", "a")))
    if engine_of(plan) == "sql":
        cell = (F.col("x.region") == F.col("y.region")) & (F.col("x.a") == F.col("y.a")) & (F.col("x.b") == F.col("y.b"))
        return _checked(kernel.alias("x").join(whole.alias("y"), cell), plan, F.col("x.obj"), F.col("y.obj"), ordered=False)

    def run(p: pa.Table, q: pa.Table) -> pa.Table:
        out = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)]
        if p.num_rows and q.num_rows:
            p, q = p.combine_chunks(), q.combine_chunks()
            ids = [t.column("id").to_numpy() for t in (p, q)]
            os = [objects(t.column("obj").chunk(0)) for t in (p, q)]
            cs = [as_matrix(objects(t.column("coord").chunk(0))) for t in (p, q)]
            found = list(_block_pairs(m, delta, *os, *cs, lambda i, j: np.ones(np.broadcast_shapes(i.shape, j.shape), bool)))
            if found:
                i, j, dist = (np.concatenate(c) for c in zip(*found, strict=True))
                out = [ids[0][i], ids[1][j], dist]
        return pa.table({"id_x": pa.array(out[0], pa.int64()), "id_y": pa.array(out[1], pa.int64()), "distance": pa.array(out[2], pa.float64())})

    keys = ("region", "a", "b")
    return kernel.groupBy(*keys).cogroup(whole.groupBy(*keys)).applyInArrow(run, PAIRS)


def brute_force_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float) -> DataFrame:
    """All pairs compared: the definition, for tests and as the baseline without any method."""
    m = metric_of(metric)
    x = validate_objects(df, id_col, obj_col, m)
    both = x.alias("x").join(x.alias("y"), F.col("x.id") < F.col("y.id"))
    both = both.where(m.at_most(F.col("x.obj"), F.col("y.obj"), delta))
    return both.select(F.col("x.id").alias("id_x"), F.col("y.id").alias("id_y"), m.distance(F.col("x.obj"), F.col("y.obj")).cast("double").alias("distance"))


def refined(objs: DataFrame, plan: JoinPlan, per_region: int, pivots_per_region: int = 400) -> JoinPlan:
    """A second level: every region of more than ``per_region`` objects is split again by a bounded sample of its own.

    The cells of the cells still tile the space, so the result stays exact. Both the regions (at most
    pivots_per_region / 8 for each of the first split) and the sample are bounded whatever the rows; a region that
    stays larger is dealt into blocks.
    """
    x = materialize(mapped(objs, plan).select("id", "home", "coord"))
    counts = {r["home"]: r["count"] for r in x.groupBy("home").count().collect()}
    big = {h: c for h, c in counts.items() if c > per_region}
    if not big:
        return plan
    shares = F.broadcast(x.sparkSession.createDataFrame([(int(h), min(1.0, pivots_per_region / c)) for h, c in big.items()], "home int, share double"))  # a row a region
    place = F.pmod(F.xxhash64("id", F.lit(plan.config.seed)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    sample: dict[int, list] = {}
    for r in x.join(shares, "home").where(place < F.col("share")).orderBy("home", "id").select("home", "coord").collect():  # about pivots_per_region each
        sample.setdefault(r["home"], []).append(r["coord"])
    t = plan.tree
    axis, cut, left, right = (list(v) for v in (t.axis, t.cut, t.left, t.right))
    leaf_of = {int(t.left[i]): i for i in range(len(t.axis)) if t.axis[i] < 0}
    regions = t.regions
    for region, count in big.items():
        pts = np.array(sample.get(region, []), float).reshape(-1, t.width)
        sub = grow(pts, min(math.ceil(count / per_region), max(1, pivots_per_region // 8)), "iterative", None, plan.config.seed + region)
        if sub.regions < 2:
            continue
        base = len(axis)
        place = lambda i: leaf_of[region] if i == 0 else base + i - 1  # noqa: B023, E731
        names = [region, *range(regions, regions + sub.regions - 1)]
        regions += sub.regions - 1
        for i in range(len(sub.axis)):
            inner = sub.axis[i] >= 0
            row = (int(sub.axis[i]), float(sub.cut[i]), place(int(sub.left[i])) if inner else names[int(sub.left[i])], place(int(sub.right[i])) if inner else -1)
            if i == 0:
                at = leaf_of[region]
                axis[at], cut[at], left[at], right[at] = row
            else:
                for v, r in zip((axis, cut, left, right), row, strict=True):
                    v.append(r)
    tree = Tree(np.array(axis), np.array(cut), np.array(left), np.array(right), regions, t.width)
    return replace(plan, tree=tree, boxes=None)
