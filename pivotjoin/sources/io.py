"""Sources and sinks: tables in any format, routed data kept for later joins, models, and views."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.metrics import metric_of
from ..operators.join import JoinPlan
from ..operators.split import Tree
from ..plans.config import JoinConfig


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_format(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, text, orc or parquet; a schema spares the pass that would infer it."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def save_routed(routed: DataFrame, path: str, mode: str = "overwrite") -> None:
    """One folder per region, so that a later join on a region reads only it."""
    routed.repartition("region").write.mode(mode).partitionBy("region").parquet(path)


def save_bucketed(routed: DataFrame, name: str, buckets: int = 16, mode: str = "overwrite") -> None:
    """A table bucketed by region: joins on the region need no exchange."""
    routed.write.mode(mode).bucketBy(buckets, "region").sortBy("region").saveAsTable(name)


def save_pairs(pairs: DataFrame, path: str, mode: str = "append") -> None:
    pairs.write.mode(mode).parquet(path)


def save_model(spark: SparkSession, plan: JoinPlan, path: str) -> None:
    """Axes, split and boxes of a plan as one small JSON row."""
    t = plan.tree
    model = {
        "metric": plan.metric.name, "delta": plan.delta, "rows": plan.rows, "k": plan.k, "p": plan.p, "n": plan.n, "bounds": plan.config.bounds, "replication": plan.config.replication,
        "axes": [a.tolist() if isinstance(a, np.ndarray) else a for a in plan.axes], "axis": t.axis.tolist(), "cut": t.cut.tolist(), "left": t.left.tolist(), "right": t.right.tolist(), "regions": t.regions, "width": t.width,
        "boxes": [b.tolist() for b in plan.boxes] if plan.boxes is not None else None,
    }
    spark.createDataFrame([(json.dumps(model),)], "model string").write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> JoinPlan:
    m = json.loads(spark.read.parquet(path).first()["model"])
    tree = Tree(np.array(m["axis"]), np.array(m["cut"], float), np.array(m["left"]), np.array(m["right"]), m["regions"], m["width"])
    boxes = tuple(np.array(b, float) for b in m["boxes"]) if m["boxes"] else None
    return JoinPlan(metric_of(m["metric"]), m["delta"], JoinConfig(bounds=m["bounds"], replication=m["replication"]), m["rows"], m["k"], m["p"], m["n"], m["axes"], tree, np.zeros((0, m["width"])), boxes=boxes)


def register_views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    for n in names:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def tree_rows(spark: SparkSession, plan: JoinPlan) -> DataFrame:
    return spark.createDataFrame(plan.tree.rows(), "node int, axis int, cut double, `left` int, `right` int")


def register_region_probe(spark: SparkSession, plan: JoinPlan, name: str = "region_probe") -> None:
    """SQL table function: the regions within delta of one point, given by its distances to the axes."""
    tree, delta = plan.tree, plan.delta

    class Probe:
        def eval(self, coord: list):  # noqa: ANN201
            x = np.array([coord], float)
            home = int(tree.home(x)[0])
            for r in sorted(tree.near(x, delta)[1].tolist()):
                yield r, r == home

    spark.udtf.register(name, F.udtf(Probe, returnType="region int, home boolean"))
