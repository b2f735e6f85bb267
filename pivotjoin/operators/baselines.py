"""The competing joins, each in our own rendition; all are exact."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import filters
from ..functions.metrics import Metric, as_matrix, metric_of, objects, padded, rows_to_arrow
from ..plans.config import JoinConfig
from .join import AXIS_POOL, PAIRS, JoinPlan, metric_self_join, validate_objects, verify, whole_cells
from .sampling import random_pivots
from .split import Tree
from .tables import materialize


def _pivots(objs: DataFrame, p: int, seed: int) -> list:
    rows = [r["obj"] for r in random_pivots(objs, p, seed=seed).select("obj").collect()]
    return list({tuple(o) if isinstance(o, list) else o: o for o in rows}.values())


def kd_split_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, config: JoinConfig | None = None) -> DataFrame:
    """Random pivots, cut along the widest axis."""
    return metric_self_join(df, id_col, obj_col, metric, delta, replace(config or JoinConfig(), sampler="random", splitter="widest"))


def oversampled_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, factor: int = 3, config: JoinConfig | None = None) -> DataFrame:
    """Random pivots, ``factor`` times as many, cut along random axes."""
    return metric_self_join(df, id_col, obj_col, metric, delta, replace(config or JoinConfig(), sampler="random", splitter="iterative", oversample=factor))


def _nearest(distances: str):
    """Place of the least of an array of distances."""

    @F.arrow_udf("int")
    def least(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for part in parts:
            yield pa.array(as_matrix(objects(part)).argmin(axis=1), pa.int32())

    return least(distances)


def _cells(objs: DataFrame, pivots: list, m: Metric, delta: float) -> DataFrame:
    """(region, home, id, obj, coord): home is the nearest pivot; a copy goes to each earlier one not 2 delta farther."""
    x = objs.withColumn("coord", m.to_axes(F.col("obj"), pivots)).withColumn("home", _nearest("coord"))
    reach = F.element_at("coord", F.col("home") + 1) + F.lit(2 * padded(delta))
    earlier = F.filter(F.sequence(F.lit(0), F.col("home")), lambda j: (j == F.col("home")) | (F.element_at(F.col("coord"), j + 1) <= reach))
    return x.select(F.explode(earlier).alias("region"), "home", "id", "obj", "coord")


def _stub(m: Metric, delta: float, config: JoinConfig, pivots: list) -> JoinPlan:
    none = np.array([-1])
    return JoinPlan(m, delta, config, 0, 0, 0, len(pivots), pivots, Tree(none, np.zeros(1), np.zeros(1, int), none, 1, len(pivots)), np.zeros((0, len(pivots))))


def nearest_pivot_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, p: int = 16, seed: int = 7) -> DataFrame:
    """Cells of the nearest pivot, with copies by the triangle inequality."""
    m = metric_of(metric)
    objs = validate_objects(df, id_col, obj_col, m)
    pivots = _pivots(objs, p, seed)
    if not pivots:
        return objs.sparkSession.createDataFrame([], PAIRS)
    return verify(_cells(objs, pivots, m, delta), _stub(m, delta, JoinConfig(seed=seed), pivots))


def _own_distances(m: Metric, of: dict[int, list]):
    """UDF (region, obj) -> distances to the region's own pivots, filled up to one length with infinity."""
    block, width = m.block, max(map(len, of.values()))

    @F.arrow_udf("array<double>")
    def far(region: pa.Array, obj: pa.Array) -> pa.Array:
        at = region.to_numpy(zero_copy_only=False)
        out = np.full((len(at), width), np.inf)
        for r in np.unique(at).tolist():
            rows = np.flatnonzero(at == r)
            out[rows, : len(of[r])] = block(objects(obj.take(pa.array(rows))), of[r])
        return rows_to_arrow(out)

    return far


def _fewer(m: Metric, delta: float, pivots: list, sample: list, most: float) -> list:
    """So many of the pivots that their cells expect at most ``most`` rows an object, as the sample tells; with one there are no copies."""
    while len(pivots) > 1 and sample:
        d = m.block(sample, pivots)
        home = d.argmin(axis=1)
        near = d <= d[np.arange(len(d)), home][:, None] + 2 * padded(delta)
        if (near & (np.arange(len(pivots))[None, :] <= home[:, None])).sum() <= most * len(sample):
            break
        pivots = pivots[: len(pivots) // 2]
    return pivots


def repartition_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, p: int | None = None, heavy: int = 100, parts: int = 64, seed: int = 7, max_copies: float = 4.0) -> DataFrame:
    """Cells of the nearest pivot; heavy ones are dealt again by pivots of their own, all of them in one pass.

    Each object of a heavy cell has a home in the second level too, and copies by the same rule, so
    a pair meets once in each level. ``p``: first cells, None by the number of objects; a cell gets a pivot of its own
    for every ``heavy`` objects, ``parts`` at most. In both levels there are fewer pivots where more than ``max_copies`` rows
    an object are expected, down to one cell, whose objects are compared in blocks.
    """
    m = metric_of(metric)
    objs = validate_objects(df, id_col, obj_col, m)
    pivots = _pivots(objs, p or JoinConfig(k=1, n=1).sized(objs.count())[1], seed)
    if not pivots:
        return objs.sparkSession.createDataFrame([], PAIRS)
    pivots = _fewer(m, delta, pivots, [r["obj"] for r in random_pivots(objs, AXIS_POOL, seed=seed + 2).select("obj").collect()], max_copies)
    plan = _stub(m, delta, JoinConfig(seed=seed), pivots)
    first = materialize(_cells(objs, pivots, m, delta))
    sizes = first.groupBy("region").count().where(F.col("count") > heavy).select("region", F.least(F.lit(parts), F.ceil(F.col("count") / heavy)).cast("int").alias("own"))
    sizes = F.broadcast(materialize(sizes, len(pivots)))  # a row a pivot
    rank = F.row_number().over(Window.partitionBy("region").orderBy(F.xxhash64("id", F.lit(seed + 1))))
    of: dict[int, list] = {}
    others: dict[int, list] = {}
    for r in first.where("home = region").join(sizes, "region").withColumn("r", rank).where("r <= 2 * own").select("region", "obj", (F.col("r") <= F.col("own")).alias("pivot")).collect():  # at most 2 * parts for each pivot
        mine = of.setdefault(r["region"], [])
        if not r["pivot"]:
            others.setdefault(r["region"], []).append(r["obj"])
        elif r["obj"] not in mine:
            mine.append(r["obj"])
    of = {r: f for r, mine in of.items() if len(f := _fewer(m, delta, mine, others.get(r, []), max_copies)) > 1}
    if not of:
        return verify(first, plan)
    light = verify(first.where(~F.col("region").isin(list(of))), plan)
    deep = first.where(F.col("region").isin(list(of))).select("region", "id", "obj", "home").withColumn("far", _own_distances(m, of)("region", "obj")).withColumn("sub_home", _nearest("far"))
    reach = F.element_at("far", F.col("sub_home") + 1) + F.lit(2 * padded(delta))
    deep = deep.withColumn("sub", F.explode(F.filter(F.sequence(F.lit(0), F.col("sub_home")), lambda j: (j == F.col("sub_home")) | (F.element_at(F.col("far"), j + 1) <= reach))))
    deep = deep.select(F.col("region").alias("cell"), "sub", F.struct("region", "sub").alias("region"), "id", "obj", "home", "sub_home")

    def ours(t: pa.Table):
        # in each level: both at home here, or one at home and the other a copy from a later cell
        here = [(t.column(c).to_numpy(), t.column(k)[0].as_py()) for c, k in (("home", "cell"), ("sub_home", "sub"))]
        return lambda i, j: np.logical_and.reduce([np.minimum(c[i], c[j]) == k for c, k in here])

    return light.unionByName(whole_cells(deep, m, delta, ours))


def _spread(m: Metric, delta: float, of: dict[str, list]):
    """UDF (part, obj) -> the parts of the next round: that of the nearest pivot, and the windows of borders within delta."""
    block, pad = m.block, padded(delta)

    @F.arrow_udf("array<struct<part:string,tag:int>>")
    def spread(part: pa.Array, obj: pa.Array) -> pa.Array:
        names, out = part.to_pylist(), [None] * len(part)
        for name in set(names):
            rows = [i for i, n in enumerate(names) if n == name]
            at = of[name]
            d = block(objects(obj.take(pa.array(rows))), at)
            for i, row in zip(rows, d, strict=True):
                h = int(row.argmin())
                out[i] = [{"part": f"{name}.{h}", "tag": -1}]
                out[i] += [{"part": f"{name}.w{min(h, j)}_{max(h, j)}", "tag": h} for j in range(len(at)) if j != h and (row[j] - row[h]) / 2 <= pad]
        return pa.array(out, pa.list_(pa.struct([("part", pa.string()), ("tag", pa.int32())])))

    return spread


def multi_round_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float, max_part: int = 100, pivots: int = 4, max_rounds: int = 20, seed: int = 7) -> DataFrame:
    """Parts by the nearest pivot and windows along their borders; what is still too large is split in another round.

    A window holds the objects of two parts that are within delta of their border; only pairs of
    different sides count there. ``tags`` keeps the sides of all windows an object is in, so a pair is
    found in one part alone. Every round is a job of its own on a written table; a part is compared as it is
    where what it would be split into had more than half of its pairs (objects that no pivot tells apart, or windows that hold nearly all).
    """
    m = metric_of(metric)
    objs = validate_objects(df, id_col, obj_col, m)
    copies, ranked = None, m.name == "jaccard" and 0 <= delta < 1
    if ranked:
        objs, copies = filters.ranked_classes(objs)
    elif m.name == "jaccard":
        objs = materialize(filters.ranked_sets(objs))
    state = objs.select(F.lit("0").alias("part"), F.array().cast("array<int>").alias("tags"), "id", "obj")
    done: list[DataFrame] = []
    for step in range(max_rounds):
        state = materialize(state)
        sizes = {r["part"]: r["count"] for r in state.groupBy("part").count().where(F.col("count") > max_part).collect()} if step < max_rounds - 1 else {}  # at most N / max_part rows
        left = state.where(F.col("part").isin(list(sizes)))
        of: dict[str, list] = {}
        for r in left.withColumn("r", F.row_number().over(_window(seed + step))).where(F.col("r") <= pivots).select("part", "obj").collect() if sizes else []:
            mine = of.setdefault(r["part"], [])
            if r["obj"] not in mine:
                mine.append(r["obj"])
        spread = F.explode(_spread(m, delta, of)("part", "obj"))
        pairs: dict[str, int] = {}
        for r in left.select("part", spread.alias("to")).groupBy("part", F.col("to.part").alias("to")).count().collect() if of else []:  # at most 10 rows a part
            pairs[r["part"]] = pairs.get(r["part"], 0) + r["count"] ** 2
        big = [p for p, n in sizes.items() if 2 * pairs[p] <= n * n]
        done.append(state.where(~F.col("part").isin(big)) if big else state)
        if not big:
            break
        x = left.where(F.col("part").isin(big)).withColumn("to", spread)
        tags = F.when(F.col("to.tag") < 0, F.col("tags")).otherwise(F.concat("tags", F.array(F.col("to.tag"))))
        state = x.select(F.col("to.part").alias("part"), tags.alias("tags"), "id", "obj")
    rows = done[0]
    for d in done[1:]:
        rows = rows.unionByName(d)
    if ranked:
        posted = materialize(rows.select("part", "tags", "id", F.size("obj").alias("size"), F.posexplode(filters.prefix(F.size("obj"), delta)).alias("pos", "token")))
        on = (F.col("x.part") == F.col("y.part")) & (F.col("x.token") == F.col("y.token")) & (F.col("x.id") < F.col("y.id"))
        on = on & F.forall(F.zip_with("x.tags", "y.tags", lambda a, b: a != b), lambda v: v)
        found = materialize(filters.counted_pairs(posted.alias("x"), posted.alias("y"), on, delta).select(F.col("i").alias("id_x"), F.col("j").alias("id_y")))
        return filters.with_copies(filters.verified(found, objs, m, delta), copies)

    def apart(t: pa.Table):
        tags = np.array(t.column("tags").to_pylist(), np.int32).reshape(t.num_rows, -1)  # a part's rows have as many
        return lambda i, j: np.logical_and.reduce([np.ones(np.broadcast_shapes(i.shape, j.shape), bool), *(c[i] != c[j] for c in tags.T)])

    return whole_cells(rows.withColumnRenamed("part", "region"), m, delta, apart)


def _window(seed: int):
    return Window.partitionBy("part").orderBy(F.xxhash64("id", F.lit(seed)))


def segment_signature_join(df: DataFrame, id_col: str, obj_col: str, metric: str | Metric, delta: float) -> DataFrame:
    """Signatures over the whole table: segments of strings, rare prefixes of sets; then verification, of strings where their candidates are found."""
    m = metric_of(metric)
    objs = validate_objects(df, id_col, obj_col, m)
    if m.kind == "string":
        if delta < 0:
            return objs.sparkSession.createDataFrame([], PAIRS)
        if m.near is not None and m.near([], [], delta) is not None:
            return filters.segment_near(objs, delta, int(padded(delta)), m.near)
        return filters.verified(filters.segment_candidates(objs, int(delta)), objs, m, delta)
    if not 0 <= delta < 1:
        return filters.verified(_with_empty(filters.prefix_candidates(objs, delta, positions=True), objs), objs, m, delta)
    ranked, copies = filters.ranked_classes(objs)  # empty sets are one class
    return filters.with_copies(filters.verified(filters.counted_candidates(ranked, delta), ranked, m, delta), copies)


def _empty_pairs(objs: DataFrame, block: int = 1000) -> DataFrame:
    """(id_x, id_y) of all empty sets: they share no token but are at distance 0. They are dealt into blocks, and each pair of blocks is a key."""
    empty = objs.where(F.size("obj") == 0).select("id")
    blocks = max(1, -(-empty.count() // block))
    x = empty.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")).withColumn("_o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    x = x.select("id", "own", F.least("own", "_o").alias("a"), F.greatest("own", "_o").alias("b"))
    x, y = x.alias("x"), x.alias("y")
    both = x.join(y, (F.col("x.a") == F.col("y.a")) & (F.col("x.b") == F.col("y.b")) & (F.col("x.id") < F.col("y.id")) & ((F.col("x.a") == F.col("x.b")) | (F.col("x.own") != F.col("y.own"))))
    return both.select(F.col("x.id").alias("id_x"), F.col("y.id").alias("id_y"))


def _with_empty(candidates: DataFrame, objs: DataFrame) -> DataFrame:
    return candidates.unionByName(_empty_pairs(objs))


def set_fragments(sets: DataFrame, fragments: int) -> DataFrame:
    """(id, size, fragment, head, tail, items): sets of token ranks cut at common ranks into parts of about equal load; head and tail tokens lie before and after a part."""
    load = sets.select(F.explode("obj").alias("t")).agg(F.percentile_approx("t", [i / fragments for i in range(1, fragments)] or [1.0], 1000 * fragments).alias("cuts")).first()["cuts"] or []
    cuts = sorted(set(load[: fragments - 1]))
    bounds = list(zip([0, *cuts], [*cuts, (1 << 62)], strict=True))
    between = lambda a, b: F.filter("obj", lambda t: (t > F.lit(a)) & (t <= F.lit(b)))
    parts = F.array(*[F.struct(F.lit(i).alias("fragment"), between(a, b).alias("items")) for i, (a, b) in enumerate(bounds)])
    x = sets.select("id", F.size("obj").alias("size"), "obj", F.explode(parts).alias("p")).where(F.size("p.items") > 0)
    head = F.array_position("obj", F.element_at("p.items", 1)).cast("int") - 1
    return x.select("id", "size", "p.fragment", head.alias("head"), (F.col("size") - head - F.size("p.items")).alias("tail"), "p.items")


def fragment_set_join(df: DataFrame, id_col: str, obj_col: str, delta: float, fragments: int = 8) -> DataFrame:
    """Sets are cut into fragments of the tokens' order; overlaps are counted in each fragment and added up.

    Equal sets are one. The fragments together propose the pairs that share enough tokens of both sets' prefixes
    (``filters.counted_least``). Then each fragment counts what a pair has in common there: a pair goes as soon as a count is
    below what the tokens before and after the fragment leave to be reached.
    """
    if delta >= 1:
        raise ValueError("below 1 only: sets without a common token are not compared")
    objs = validate_objects(df, id_col, obj_col, metric_of("jaccard"))
    if delta < 0:
        return objs.sparkSession.createDataFrame([], PAIRS)
    ranked, copies = filters.ranked_classes(objs)
    parts = materialize(set_fragments(ranked, fragments))
    posted = parts.select("fragment", "id", "size", "head", F.posexplode("items").alias("at", "token")).withColumn("pos", F.col("head") + F.col("at"))
    posted = materialize(posted.where(F.col("pos") < filters.prefix_length(F.col("size"), delta)).select("fragment", "token", "id", "size", "pos"))
    x, y = posted.alias("x"), posted.alias("y")
    on = (F.col("x.fragment") == F.col("y.fragment")) & (F.col("x.token") == F.col("y.token")) & (F.col("x.id") < F.col("y.id"))
    pairs = filters.counted_pairs(x, y, on, delta)
    pairs = materialize(pairs.select(F.col("i").alias("id_x"), F.col("j").alias("id_y")))
    x, y = parts.alias("x"), parts.alias("y")
    both = pairs.join(x, F.col("id_x") == F.col("x.id")).join(y, (F.col("id_y") == F.col("y.id")) & (F.col("x.fragment") == F.col("y.fragment")))
    common = F.size(F.array_intersect("x.items", "y.items"))
    least = filters.needed_overlap(F.col("x.size"), F.col("y.size"), delta) - F.least("x.head", "y.head") - F.least("x.tail", "y.tail")
    counted = both.select("id_x", "id_y", common.alias("n"), least.alias("least"), (F.col("x.size") + F.col("y.size")).alias("sizes"))
    total = counted.groupBy("id_x", "id_y", "sizes").agg(F.sum("n").alias("n"), F.bool_and(F.col("n") >= F.col("least")).alias("possible")).where("possible")
    found = total.select("id_x", "id_y", (1.0 - F.col("n") / (F.col("sizes") - F.col("n"))).alias("distance")).where(F.col("distance") <= F.lit(padded(delta)))
    return filters.with_copies(found, copies)
