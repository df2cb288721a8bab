from pyspark.sql import functions as F

from provgraph.operators import trace
from provgraph.sources import carriers
from provgraph.sources.audit_log import AuditLogSource
from provgraph.streaming import live

SF = "/root/testdata/sf0.001"


def test_audit_log_source(spark, tmp_path):
    (tmp_path / "a.log").write_text("2024-01-01T00:00:00|d:1:2024-01-01|read|f:1|5\nbroken\n2024-01-01T00:00:01|d:1:2024-01-01|written|f:2|\n")
    (tmp_path / "b.log").write_text("2024-01-01T00:00:02|d:2:2024-01-01|failed|f:3|1\n")
    spark.dataSource.register(AuditLogSource)
    a = spark.read.format("audit_log").load(str(tmp_path))
    assert a.count() == 4 and [r["object"] for r in a.filter("op = 'malformed'").collect()] == ["broken"]
    g = trace.from_accesses(a)
    assert {r["label"]: r["n"] for r in g.edges.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()} == {"used": 1, "wasGeneratedBy": 1, "wasInformedBy": 2}
    s = spark.readStream.format("audit_log").load(str(tmp_path))
    state, seen = str(tmp_path / "state"), str(tmp_path / "rows")
    live.sink_runs(s.select("op"), seen, state).awaitTermination()
    (tmp_path / "aa.log").write_text("2024-01-01T00:00:03|d:2:2024-01-01|read|f:4|1\n")  # late, and earlier by name than one seen
    live.sink_runs(s.select("op"), seen, state).awaitTermination()
    got = spark.read.parquet(seen)
    assert got.count() == 5 and got.filter("op = 'malformed'").count() == 1


def _parts(spark, tmp_path, k=4):
    ev = carriers.table(spark, SF, "events").orderBy("ts").toPandas()
    step = -(-len(ev) // k)
    for i in range(k):
        part = spark.createDataFrame(ev.iloc[i * step : (i + 1) * step]).withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        part.coalesce(1).write.mode("append").parquet(str(tmp_path))
    return live.audit_source(spark, str(tmp_path))


def test_streams_equal_batch(spark, tmp_path):
    s = _parts(spark, tmp_path / "events")
    ev = carriers.table(spark, SF, "events")
    got = live.drain(live.access_counts(s), "complete")
    want = ev.groupBy(F.date_trunc("day", F.col("ts").cast("timestamp")).alias("begun"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    q = live.sink_runs(s.select("event_id"), str(tmp_path / "out"), str(tmp_path / "ck"))
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "out")).count() == ev.count()


def test_live_versions(spark, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    s = live.audit_source(spark, f"file://{_one(spark, tmp_path)}")
    got = live.drain(live.live_versions(s))
    writes = got.filter("op = 'written'").groupBy("object").agg(F.max("version").alias("m"), F.count(F.lit(1)).alias("n"))
    assert writes.filter("m <> n").isEmpty() and not writes.isEmpty()


def _one(spark, tmp_path):
    carriers.table(spark, SF, "events").coalesce(1).write.parquet(str(tmp_path / "one"))
    return tmp_path / "one"
