"""Streams run to the end and compared with the same rows in one batch."""

import pytest
from pyspark.sql import functions as F

from pivotjoin import workloads
from pivotjoin.functions.metrics import L1
from pivotjoin.operators import fits
from pivotjoin.operators.join import make_plan, metric_join
from pivotjoin.plans.config import JoinConfig
from pivotjoin.streaming import streams


@pytest.fixture(scope="module")
def folder(spark, sf_dir, tmp_path_factory):
    base = tmp_path_factory.mktemp("stream")
    spark.read.parquet(f"{sf_dir}/events.parquet").repartition(2).write.parquet(str(base / "events"))
    workloads.descriptors(spark, sf_dir, 4).withColumn("ts", F.timestamp_seconds(F.col("id") * 60 + 86_400)).withColumn("event_type", (F.col("id") % 2).cast("string")).repartition(1).write.parquet(str(base / "objs"))
    return base


def stream(spark, path):
    return spark.readStream.schema(spark.read.parquet(str(path)).schema).parquet(str(path))


def finished(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(180)
    return df.sparkSession.table(name)


def test_windows(spark, folder):
    for slide, name in ((None, "w1"), ("12 hours", "w2")):
        got = finished(streams.windowed_counts(stream(spark, folder / "events"), "1 day", slide), name, "complete")
        want = streams.windowed_counts(spark.read.parquet(str(folder / "events")), "1 day", slide)
        assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}


def test_sessions(spark, folder):
    got = finished(streams.sessions(stream(spark, folder / "events"), "6 hours"), "s1", "complete")
    want = streams.sessions(spark.read.parquet(str(folder / "events")), "6 hours")
    key = lambda d: {(r["start"], r["end"], r["user_id"], r["n"]) for r in d.collect()}
    assert key(got) == key(want)


def test_deduplicated(spark, folder):
    x = stream(spark, folder / "events")
    got = finished(streams.deduplicated(x, ["event_id"], "60 days"), "d1")
    assert got.count() == spark.read.parquet(str(folder / "events")).select("event_id").distinct().count()


def test_new_objects_against_a_corpus(spark, folder):
    corpus = spark.read.parquet(str(folder / "objs")).where("id % 2 = 0").select("id", "obj")
    plan = make_plan(corpus, L1, 0.1, JoinConfig(bounds="cell"))
    got = finished(streams.stream_static_join(stream(spark, folder / "objs").where("id % 2 = 1").select("id", "obj"), corpus, plan), "j1")
    new = spark.read.parquet(str(folder / "objs")).where("id % 2 = 1")
    want = metric_join(corpus, new, ("id", "id"), ("obj", "obj"), "l1", 0.1)
    assert {(r["id_x"], r["id_y"]) for r in got.collect()} == {(r["id_y"], r["id_x"]) for r in want.collect()}


def within(spark, folder, minutes, delta=0.15):
    x = spark.read.parquet(str(folder / "objs"))
    a, b = x.alias("a"), x.alias("b")
    near = (F.col("a.id") < F.col("b.id")) & (F.col("a.event_type") == F.col("b.event_type")) & ((F.col("b.id") - F.col("a.id")) <= minutes)
    return {(r[0], r[1]) for r in a.join(b, near).where(L1.at_most(F.col("a.obj"), F.col("b.obj"), delta)).select("a.id", "b.id").collect()}


def test_two_streams(spark, folder):
    x = stream(spark, folder / "objs")
    got = finished(streams.stream_stream_join(x, stream(spark, folder / "objs"), "l1", 0.15, "30 minutes"), "j2")
    assert {(r["id_x"], r["id_y"]) for r in got.collect() if r["id_x"] < r["id_y"]} == within(spark, folder, 30)


def test_stateful_pairs(spark, folder):
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got = finished(streams.stateful_pairs(stream(spark, folder / "objs"), "event_type", "l1", 0.15, 30 * 60_000), "p1")
        assert {(r["id_x"], r["id_y"]) for r in got.collect()} == within(spark, folder, 30)
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)


def test_drift(spark, folder):
    e = spark.read.parquet(str(folder / "events"))
    data = e.select(F.col("event_id").alias("id"), F.array("value").alias("obj"), F.lit(0).alias("node"))
    fit = fits.fit_nodes(data, families=("exponential",))[0]
    calm, alarms = [], []
    streams.drift_monitor(fit, 0, 1e-6, calm)(e, 0)
    streams.drift_monitor(fit, 0, 1e-6, alarms)(e.withColumn("value", F.col("value") * 3), 1)
    assert not calm and alarms and alarms[0][0] == 1


def test_drained_waits_for_the_end(spark, sf_dir, monkeypatch):
    from pyspark.sql.streaming import StreamingQuery

    from pivotjoin import surrounding
    from pivotjoin.operators.tables import shared_dir

    limits, whole = [], StreamingQuery.awaitTermination
    monkeypatch.setattr(StreamingQuery, "awaitTermination", lambda q, timeout=None: (limits.append(timeout), whole(q, timeout))[1])
    t = surrounding._Tables(spark, sf_dir)
    found = surrounding._drained(surrounding._stream(t, "events").select("event_id"))
    assert found.count() == t.events.count() and limits == [None]
    jvm = spark._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/streams")
    assert path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path)


def test_stream_join_by_slices(spark):
    """Rows meet those of their slice of time, on all sides of its borders; pairs farther apart in time do not count."""
    at = [0, 1, 1799, 1800, 1801, 3600, 3601, 5400, 9000]
    rows = spark.createDataFrame([(i, [0.0], t) for i, t in enumerate(at)], "id long, obj array<double>, t long").select("id", "obj", F.timestamp_seconds("t").alias("ts"), F.lit("a").alias("event_type"))
    got = streams.stream_stream_join(rows, rows, "l1", 0.5, "30 minutes")
    assert sorted((r["id_x"], r["id_y"]) for r in got.collect()) == [(i, j) for i in range(len(at)) for j in range(len(at)) if abs(at[i] - at[j]) <= 1800]
    assert "slice_x" in got._jdf.queryExecution().optimizedPlan().toString()
