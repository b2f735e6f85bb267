"""Tables written into the folder that driver and executors share."""

from __future__ import annotations

import math
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Rows of a few numbers that are worth a file of their own.
FILE_ROWS = 100_000
#: Links that one task finishes (16 bytes each); more are contracted by rounds over all tasks.
LOCAL_LINKS = 500_000
#: Setting under which Spark deletes what a finished write has shuffled.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder. Only on one machine (tests) a temporary one is set where it names none; on a cluster that is an error."""
    sc = spark.sparkContext
    found = sc._jsc.sc().getCheckpointDir()
    if found.isDefined():
        return found.get()
    named = sc.getConf().get("spark.checkpoint.dir", None)
    if named is None and not (sc.master == "local" or sc.master.startswith("local[")):
        raise ValueError("spark.checkpoint.dir has to name a folder that driver and executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="shared_"))
    return sc._jsc.sc().getCheckpointDir().get()


def materialize(df: DataFrame, most_rows: int | None = None) -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: the lineage ends there, and lost executors lose nothing.

    The new scan has no partitioning, so a join on it gets an exchange of its own, which adaptive execution can split.
    What was shuffled for it is deleted when it is written.
    ``most_rows``: df, the result of a shuffle, has at most so many rows of a few numbers, and gets no more files than these need.
    """
    if most_rows is not None:
        df = df.coalesce(max(1, math.ceil(most_rows / FILE_ROWS)))
    path = f"{shared_dir(df.sparkSession)}/tables/{uuid.uuid4().hex}"
    conf = df.sparkSession.conf
    before = conf.get(CLEANUP, "false")
    conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        conf.set(CLEANUP, before)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._written = path
    return out


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder in the shared folder."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def discard(*tables: DataFrame) -> None:
    """Delete written tables that nothing reads any more."""
    for t in tables:
        remove(t.sparkSession, t._written)


def running_sum(df: DataFrame, order: list[str], amount: Column, out: str) -> DataFrame:
    """Adds ``out``: the sum of ``amount`` over all rows up to this one in the order, whose keys are distinct.

    Rows are dealt into ranges, and what lies before a range is a sum of few numbers, so no task sees the whole table.
    """
    x = materialize(df.repartitionByRange(*order).withColumn("_range", F.spark_partition_id()))
    sums = x.groupBy("_range").agg(F.sum(amount).alias("_sum"))
    ahead = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    sums = sums.select("_range", F.coalesce(F.sum("_sum").over(ahead), F.lit(0)).alias("_before"))
    upto = Window.partitionBy("_range").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return x.withColumn("_upto", F.sum(amount).over(upto)).join(F.broadcast(sums), "_range").withColumn(out, F.col("_before") + F.col("_upto")).drop("_range", "_upto", "_before")


def _finished(links: DataFrame) -> DataFrame:
    """Components of few links, in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs = [np.column_stack([c.to_numpy() for c in b.columns]) for b in batches if b.num_rows]
        if not pairs:
            return
        ids, at = np.unique(np.concatenate(pairs), return_inverse=True)
        parent = list(range(len(ids)))

        def find(i: int) -> int:
            while parent[i] != i:
                parent[i] = parent[parent[i]]
                i = parent[i]
            return i

        for a, b in at.reshape(-1, 2).tolist():
            a, b = find(a), find(b)
            parent[max(a, b)] = min(a, b)
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[[find(i) for i in range(len(ids))]])], ["id", "component"])

    return links.coalesce(1).mapInArrow(run, "id long, component long")


def connected_components(edges: DataFrame, local_links: int = LOCAL_LINKS, most_links: int | None = None) -> DataFrame:
    """(id_x, id_y) -> (id, component): the smallest id reachable; ids without edges are absent.

    Every round points all neighbours of a node at its smallest one, from above and from below in
    turn, until stars are left; both sides of each join are written tables, so hubs can be split.
    At most ``local_links`` links are left to one task instead, with the same result. ``most_links``: a bound of their number, if known.
    """
    e = materialize(edges.select(F.greatest("id_x", "id_y").cast("long").alias("u"), F.least("id_x", "id_y").cast("long").alias("v")).where("u <> v").distinct(), most_links)
    before = None
    while True:
        now = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v") % F.lit(1 << 40))).first()
        if now[0] <= local_links:
            out = materialize(_finished(e))
            discard(e)
            return out
        if now == before:
            break
        before = now
        low = materialize(e.groupBy("u").agg(F.min("v").alias("m")))
        up = e.alias("e").join(low.alias("l"), F.col("e.v") == F.col("l.u"), "left")
        up = materialize(up.select("e.u", F.coalesce("l.m", "e.v").alias("v")).distinct())
        discard(e, low)
        low = materialize(up.groupBy("u").agg(F.min("v").alias("m")))
        down = up.alias("e").join(low.alias("l"), F.col("e.u") == F.col("l.u")).where("e.v <> l.m")
        down = down.select(F.col("e.v").alias("u"), F.col("l.m").alias("v")).unionByName(low.withColumnRenamed("m", "v"))
        e = materialize(down.distinct())
        discard(up, low)
    roots = e.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    return e.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots)
