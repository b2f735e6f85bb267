"""Costs, balance and quality of a routed join."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from contextlib import contextmanager
from itertools import product

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators.join import JoinPlan, mapped, route, verify
from ..operators.tables import materialize


def region_sizes(routed: DataFrame) -> DataFrame:
    """(region, v, w): objects at home in each region, and all that are sent there."""
    return routed.groupBy("region").agg(F.count_if(F.col("home") == F.col("region")).alias("v"), F.count(F.lit(1)).alias("w"))


def region_costs(routed: DataFrame) -> DataFrame:
    """By region: all ordered pairs, pairs of home objects, pairs of home objects and copies, and unordered verifications."""
    v, w = F.col("v"), F.col("w")
    return region_sizes(routed).select("region", "v", "w", (w * w).alias("all_pairs"), (v * v).alias("inner_cost"), (v * (w - v)).alias("outer_cost"), (F.expr("v * (v - 1) div 2") + v * (w - v)).alias("verifications"))


def costs(routed: DataFrame) -> DataFrame:
    """Sums over regions of ``region_costs``."""
    return region_costs(routed).agg(*[F.sum(c).cast("long").alias(c) for c in ("all_pairs", "inner_cost", "outer_cost", "verifications")])


def partition_stats(routed: DataFrame) -> DataFrame:
    """Mean, deviation, relative deviation and greatest over mean of the verifications of a region."""
    x = region_costs(routed).agg(F.avg("verifications").alias("mean"), F.stddev_pop("verifications").alias("stdev"), F.max("verifications").alias("most"), F.count(F.lit(1)).alias("regions"))
    return x.select("regions", "mean", "stdev", F.try_divide("stdev", "mean").alias("cv"), F.try_divide("most", "mean").alias("max_over_mean"))


def evenness(routed: DataFrame) -> DataFrame:
    """Inner cost over its least value, N * N / p."""
    return region_sizes(routed).agg((F.sum(F.col("v") * F.col("v")) * F.count(F.lit(1)) / F.pow(F.sum("v"), 2)).alias("ratio"), (F.pow(F.sum("v"), 2) / F.count(F.lit(1))).alias("lower_bound"))


def replication_factor(routed: DataFrame) -> DataFrame:
    return region_sizes(routed).agg((F.sum("w") / F.sum("v")).alias("copies"), F.sum("w").cast("long").alias("rows_moved"))


def colocation_count(routed: DataFrame) -> DataFrame:
    """(id_x, id_y, n): in how many regions each pair meets; for small inputs, as it is quadratic."""
    x = routed.select("region", "id")
    both = x.alias("x").join(x.alias("y"), "region").where("x.id < y.id")
    return both.groupBy(F.col("x.id").alias("id_x"), F.col("y.id").alias("id_y")).agg(F.count(F.lit(1)).alias("n"))


def colocation_histogram(routed: DataFrame) -> DataFrame:
    """(regions, pairs): how many pairs meet in how many regions, by counts of objects that go to the same set of regions; no pair is made."""
    sets = routed.groupBy("id").agg(F.sort_array(F.collect_set("region")).alias("at")).groupBy("at").agg(F.count(F.lit(1)).alias("c"))
    sets = materialize(sets)  # a row a set of regions
    keyed = sets.withColumn("region", F.explode("at"))
    x, y = keyed.alias("x"), keyed.alias("y")
    met = x.join(y, (F.col("x.region") == F.col("y.region")) & (F.col("x.at") <= F.col("y.at"))).groupBy(F.col("x.at").alias("a"), F.col("y.at").alias("b"))
    met = met.agg(F.count(F.lit(1)).alias("regions"), F.first("x.c").alias("c"), F.first("y.c").alias("d"))
    pairs = F.when(F.col("a") == F.col("b"), F.expr("c * (c - 1) div 2")).otherwise(F.col("c") * F.col("d"))
    return met.groupBy("regions").agg(F.sum(pairs).alias("pairs")).where("pairs > 0")


def uncovered_pairs(routed: DataFrame, truth: DataFrame) -> DataFrame:
    """True pairs that meet in no region as a home object and any other; empty for exact bounds."""
    kernel = routed.where("home = region").select("region", "id")
    whole = routed.select("region", "id")
    t = materialize(truth.select("id_x", "id_y"))  # read three times
    meet = t.join(kernel.withColumnRenamed("id", "id_x"), "id_x").join(whole.withColumnRenamed("id", "id_y"), ["region", "id_y"]).select("id_x", "id_y")
    back = t.join(kernel.withColumnRenamed("id", "id_y"), "id_y").join(whole.withColumnRenamed("id", "id_x"), ["region", "id_x"]).select("id_x", "id_y")
    return t.join(meet.unionByName(back).distinct(), ["id_x", "id_y"], "left_anti")


def label_purity(routed: DataFrame, labels: DataFrame) -> DataFrame:
    """(region, n, purity, entropy) of home objects: the share of the most frequent label, and the labels' entropy. ``labels``: (id, label)."""
    x = routed.where("home = region").select("region", "id").join(labels, "id").groupBy("region", "label").agg(F.count(F.lit(1)).alias("c"))
    x = x.groupBy("region").agg(F.sum("c").alias("n"), F.max("c").alias("most"), F.sum(F.col("c") * F.log("c")).alias("s"))
    return x.select("region", "n", (F.col("most") / F.col("n")).alias("purity"), (F.log("n") - F.col("s") / F.col("n")).alias("entropy"))


def region_extent(routed: DataFrame, width: int) -> DataFrame:
    """(region, extent1, ...): how far apart a region's home objects are along each axis."""
    x = routed.where("home = region")
    return x.groupBy("region").agg(*[(F.max(F.col("coord")[d]) - F.min(F.col("coord")[d])).alias(f"extent{d + 1}") for d in range(width)])


def result_quality(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Recall and precision of a result, and how often it repeats a pair."""
    f, t = found.select("id_x", "id_y").withColumn("f", F.lit(1)), truth.select("id_x", "id_y").distinct().withColumn("t", F.lit(1))
    d = f.groupBy("id_x", "id_y").agg(F.count(F.lit(1)).alias("f"))
    both = d.join(t, ["id_x", "id_y"], "full_outer")
    hits = F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull())
    return both.agg(F.coalesce(F.try_divide(hits, F.count("t")), F.lit(1.0)).alias("recall"), F.coalesce(F.try_divide(hits, F.count("f")), F.lit(1.0)).alias("precision"), F.coalesce(F.sum(F.col("f") - 1), F.lit(0)).cast("long").alias("repeats"))


def gap_factor(times: DataFrame) -> DataFrame:
    """(workload, method, seconds) -> per method the mean, median and greatest ratio to the best of each workload."""
    best = F.min("seconds").over(Window.partitionBy("workload"))
    x = times.withColumn("ratio", F.col("seconds") / best)
    return x.groupBy("method").agg(F.avg("ratio").alias("mean"), F.percentile("ratio", F.lit(0.5)).alias("median"), F.max("ratio").alias("most"))


def scaling_ratio(times: DataFrame) -> DataFrame:
    """(series, size, seconds) -> ratios to the smallest size of each series: of time, and of time per unit."""
    w = Window.partitionBy("series").orderBy("size")
    first, base = F.first("seconds").over(w), F.first("size").over(w)
    return times.select("series", "size", "seconds", (F.col("size") / base).alias("size_ratio"), (F.col("seconds") / first).alias("time_ratio"), (first / F.col("seconds")).alias("speed_up"))


def estimate(plan: JoinPlan) -> dict[str, float]:
    """Expected costs before anything is routed: pivots stand for N / k objects each."""
    x, t = plan.coords, plan.tree
    if not len(x):
        return {"inner": 0.0, "outer": 0.0, "verifications": 0.0, "copies": 1.0, "brute_force": 0.0, "mean_region": 0.0}
    scale = plan.rows / len(x)
    home = t.home(x)
    v = np.bincount(home, minlength=t.regions) * scale
    row, region = t.near(x, plan.delta)
    keep = region < home[row] if plan.config.replication == "lower" else region != home[row]
    c = np.bincount(region[keep], minlength=t.regions) * scale
    return {"inner": float((v * v).sum()), "outer": float((v * c).sum()), "verifications": float((v * (v - 1) / 2 + v * c).clip(0).sum()), "copies": float(1 + c.sum() / max(1, plan.rows)), "brute_force": plan.rows * (plan.rows - 1) / 2, "mean_region": float((v + c).mean())}


def plan_cost(objs: DataFrame, metric, delta: float, config, splitters=("iterative", "learned", "widest"), ps=(None,), limit: float = 0.9) -> tuple[JoinPlan | None, list[dict]]:
    """The cheapest of several plans by estimated verifications; None (compare in blocks, unpartitioned) where no plan saves a tenth."""
    from dataclasses import replace

    from ..operators.join import make_plan

    best, seen = None, []
    for s, p in product(splitters, ps):
        plan = make_plan(objs, metric, delta, replace(config, splitter=s, p=p or config.p))
        cost = estimate(plan)
        seen.append({"splitter": s, "p": plan.p, **cost})
        if best is None or cost["verifications"] < best[1]["verifications"]:
            best = (plan, cost)
    return (best[0] if best and best[1]["verifications"] <= limit * best[1]["brute_force"] else None), seen


@contextmanager
def phase(seconds: dict[str, float], name: str):
    began = time.time()
    yield
    seconds[name] = time.time() - began


def join_report(objs: DataFrame, plan: JoinPlan) -> dict[str, float]:
    """Measured costs and times of the phases of a planned join."""
    seconds = dict(plan.seconds)
    with phase(seconds, "map"):
        mapped(objs, plan).agg(F.count(F.lit(1)), F.max("home")).collect()
    routed = route(objs, plan)
    with phase(seconds, "route"):
        row = costs(routed).first()
        stats = partition_stats(routed).first()
        copies = replication_factor(routed).first()
    with phase(seconds, "verify"):
        pairs = verify(routed, plan).count()
    return {"rows": plan.rows, "regions": plan.tree.regions, "pairs": pairs, **row.asDict(), **stats.asDict(), **copies.asDict(), **{f"seconds_{k}": v for k, v in seconds.items()}}


def optimal_cover_cost(near: np.ndarray, p: int) -> int:
    """Least sum of squared region sizes over all ways to cover every near pair with p regions; exponential, for a handful of objects."""
    n = len(near)
    need = {(i, j) for i in range(n) for j in range(i, n) if near[i, j]}
    subsets = [(s, [i for i in range(n) if s >> i & 1]) for s in range(1 << n)]
    cover = {s: {(i, j) for a, i in enumerate(m) for j in m[a:]} for s, m in subsets}
    best = math.inf

    def go(left: set, used: int, cost: int, start: int) -> None:
        nonlocal best
        if cost >= best:
            return
        if not left:
            best = cost
            return
        if used == p:
            return
        i, j = min(left)
        for s, m in subsets:
            if s >> i & 1 and s >> j & 1:
                go(left - cover[s], used + 1, cost + len(m) ** 2, s)

    go(need, 0, 0, 0)
    return int(best)


def limited(spark, f: Callable[[], object], seconds: float) -> float | None:
    """Seconds of a run, or None if it was stopped after its time was over."""
    from threading import Timer
    from uuid import uuid4

    tag, over = f"limited_{uuid4().hex}", []
    spark.addTag(tag)
    timer = Timer(seconds, lambda: (over.append(True), spark.interruptTag(tag)))
    timer.start()
    began = time.time()
    try:
        f()
    except Exception:
        if not over:
            raise
    finally:
        timer.cancel()
        spark.removeTag(tag)
    return None if over else time.time() - began


def repeated(f: Callable[[], object], times: int = 3) -> float:
    """Mean seconds of a number of runs."""
    began = time.time()
    for _ in range(times):
        f()
    return (time.time() - began) / times
