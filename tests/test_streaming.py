"""Streams give what the batch gives."""

from pathlore.operators import temporal
from pathlore.plans.ontology import shop
from pathlore.sources.graph import table
from pathlore.streaming import events as stream

DATA = "/root/testdata/sf0.001"


def test_windows_on_a_stream(spark, tmp_path):
    batch = table(spark, DATA, "events")
    batch = batch.withColumn("ts", batch.ts.cast("timestamp"))
    batch.orderBy("ts").repartitionByRange(4, "ts").write.parquet(str(tmp_path / "in"))
    live = stream.read_event_stream(spark, str(tmp_path / "in"), batch.schema).withWatermark("ts", "40 days")
    for name, work in (("tumbling", stream.tumbling), ("sliding", stream.sliding)):
        q = work(live, shop()).writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        q.awaitTermination(120)
        got = sorted((r[0], r[1], r.n) for r in spark.table(name).collect())
        assert got == sorted((r[0], r[1], r.n) for r in work(batch, shop()).collect())


def test_stream_against_static_nodes(spark, tmp_path):
    batch = table(spark, DATA, "events")
    batch.repartition(3).write.parquet(str(tmp_path / "in"))
    wealthy = table(spark, DATA, "customer").where("c_acctbal >= 5000").select("c_custkey")
    live = stream.read_event_stream(spark, str(tmp_path / "in"), batch.schema)
    q = stream.error_customers(live, wealthy).writeStream.format("memory").queryName("errors").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.table("errors").count() == stream.error_customers(batch, wealthy).count() > 0


def test_asof_and_intervals_with_ties_and_nulls(spark):
    left = spark.createDataFrame([(1, 10, "a"), (1, 5, "b"), (2, 1, "c"), (None, 3, "d")], "k int, t int, x string")
    right = spark.createDataFrame([(1, 5, 50), (1, 5, 51), (1, 11, 99), (2, 2, 7)], "k int, at int, v int")
    got = {r.x: r.v for r in temporal.asof_join(left, right, "k", "t", "at", "v").collect()}
    assert got == {"a": 51, "b": 51, "c": None, "d": None}


def test_two_streams_within_an_interval(spark, tmp_path):
    batch = table(spark, DATA, "events")
    batch = batch.withColumn("ts", batch.ts.cast("timestamp"))
    batch.orderBy("ts").repartitionByRange(4, "ts").write.parquet(str(tmp_path / "in"))
    live = stream.read_event_stream(spark, str(tmp_path / "in"), batch.schema)
    q = stream.followed_by(live, "view", "purchase", "12 hours", "40 days").writeStream.format("memory").queryName("followed").option("checkpointLocation", str(tmp_path / "f")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = sorted(map(tuple, stream.followed_by(batch, "view", "purchase", "12 hours").collect()))
    assert sorted(map(tuple, spark.table("followed").collect())) == want and want


def test_late_and_repeated_events(spark, tmp_path):
    """What comes later than the watermark allows is left out; what comes twice counts once."""
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    rows = {
        "1": [(1, "2024-01-01 10:00:00", "view"), (1, "2024-01-01 10:00:00", "view"), (2, "2024-01-01 10:10:00", "purchase")],
        "2": [(3, "2024-01-01 20:00:00", "view"), (6, "2024-01-01 20:05:00", "purchase"), (1, "2024-01-01 10:00:00", "view")],
        "3": [(4, "2024-01-01 10:20:00", "purchase"), (5, "2024-01-01 20:30:00", "purchase")],
    }
    folder = tmp_path / "in"
    folder.mkdir()
    for name, some in rows.items():
        spark.createDataFrame([(i, t, 7, k, 0.0, "{}") for i, t, k in some], "event_id long, ts string, user_id long, event_type string, value double, props string").selectExpr("event_id", "CAST(ts AS timestamp) AS ts", "user_id", "event_type", "value", "props").coalesce(1).write.parquet(str(folder / name))
        live = spark.readStream.schema(schema).option("recursiveFileLookup", "true").parquet(str(folder))
        for kind, work in (("followed", lambda e: stream.followed_by(e, "view", "purchase", "1 hour", "1 hour")), ("once", lambda e: stream.without_repeats(e, "1 hour").select("event_id"))):
            out = str(tmp_path / f"out-{kind}")
            q = work(live).writeStream.format("parquet").option("path", out).option("checkpointLocation", str(tmp_path / f"c-{kind}")).trigger(availableNow=True).start()
            q.awaitTermination(120)
    pairs = {(r.event_id, r.next_id) for r in spark.read.parquet(str(tmp_path / "out-followed")).collect()}
    assert pairs == {(1, 2), (3, 5), (3, 6)}  # 4 came ten hours late
    ids = sorted(r.event_id for r in spark.read.parquet(str(tmp_path / "out-once")).collect())
    assert ids == [1, 2, 3, 5, 6]
