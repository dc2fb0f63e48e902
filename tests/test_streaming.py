from datetime import datetime, timedelta

from pyspark.sql import functions as F

from carepath.operators import sequences
from carepath.sources import events as EV
from carepath.streaming import state, windows

SF = "/root/testdata/sf0.001"


def split_events(spark, folder, parts=4):
    """Events in files by time, and one event far ahead that moves the watermark past all others."""
    e = spark.read.parquet(f"{SF}/events.parquet")
    last = e.orderBy(F.desc("ts")).limit(1).select(F.lit(-1).cast("long").alias("event_id"), (F.col("ts") + F.expr("INTERVAL 90 DAYS")).alias("ts"), F.lit(-1).cast("long").alias("user_id"), "event_type", "value", "props")
    rows = e.unionByName(last).orderBy("ts").toPandas()
    step = -(-len(rows) // parts)
    for i in range(parts):
        spark.createDataFrame(rows.iloc[i * step : (i + 1) * step], e.schema).coalesce(1).write.mode("append").parquet(folder)
    return e


def test_sessions_of_the_stream_equal_the_batch(spark, tmp_path):
    e = split_events(spark, str(tmp_path / "in"))
    rows = windows.sessions(windows.dedup(windows.with_lateness(windows.read_events(spark, str(tmp_path / "in"), 1), "30 days")))
    windows.start(rows, str(tmp_path / "cp"), to_table="got_sessions").awaitTermination()
    got = {(r.subject_id, r.visit_id, r.n_events) for r in spark.table("got_sessions").collect()}
    want = {(r.subject_id, r.visit_id, r.n_events) for r in EV.sessions(e).collect()}
    assert got == want


def test_counts_and_enrichment(spark, tmp_path):
    e = split_events(spark, str(tmp_path / "in"))
    stream = windows.read_events(spark, str(tmp_path / "in"), 2)
    windows.start(windows.tumbling(stream), str(tmp_path / "cp"), mode="complete", to_table="got_counts").awaitTermination()
    got = {(r.start, r.event_type): r.n for r in spark.table("got_counts").filter(F.col("start") < "2100-01-01").collect()}
    want = {(r.start, r.event_type): r.n for r in windows.tumbling(e.withColumn("ts", F.col("ts").cast("timestamp"))).collect()}
    assert all(got[k] == n for k, n in want.items())
    customers, nations = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("customer", "nation"))
    sink = windows.score_sink(str(tmp_path / "out"), lambda d: windows.enrich(d, customers, nations))
    for _ in range(2):  # the second run finds nothing new in its checkpoint
        windows.start(stream, str(tmp_path / "cp2"), each=sink).awaitTermination()
    assert spark.read.parquet(str(tmp_path / "out")).count() == e.count()


def visit_files(spark, folder):
    day = datetime(2020, 1, 1)
    rows = [(s, s * 100 + i, day + timedelta(days=17 * i * s), day + timedelta(days=17 * i * s + 2)) for s in (1, 2, 3) for i in range(6)]
    rows.append((9, 999, day + timedelta(days=900), day + timedelta(days=901)))
    rows.sort(key=lambda r: r[2])
    schema = "subject_id long, visit_id long, admit_ts timestamp, discharge_ts timestamp"
    for i in range(0, len(rows), 5):
        spark.createDataFrame(rows[i : i + 5], schema).coalesce(1).write.mode("append").parquet(folder)
    return spark.createDataFrame(rows, schema), spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)


def test_state_of_trajectories_equals_windows(spark, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    batch, stream = visit_files(spark, str(tmp_path / "in"))
    windows.start(state.trajectories(stream, 3), str(tmp_path / "cp"), to_table="got_windows").awaitTermination()
    got = {(r.target_visit, r.visit_ids) for r in spark.table("got_windows").collect()}
    want = {(r.target_visit, ",".join(map(str, r.visit_ids))) for r in sequences.sliding(batch, 3, partial="none").collect()}
    assert got == want and got


def test_interval_join_finds_returns(spark, tmp_path):
    batch, stream = visit_files(spark, str(tmp_path / "in"))
    rows = windows.returns(stream.select("subject_id", "visit_id", "discharge_ts"), stream.select("subject_id", "visit_id", "admit_ts"))
    windows.start(rows, str(tmp_path / "cp"), to_table="got_returns").awaitTermination()
    got = {(r.visit_id, r.next_id) for r in spark.table("got_returns").collect()}
    assert got == {(100 + i, 101 + i) for i in range(5)}


def test_labels_mature(spark, tmp_path):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    batch, stream = visit_files(spark, str(tmp_path / "in"))
    windows.start(state.matured_labels(stream.withWatermark("admit_ts", "1 hour")), str(tmp_path / "cp"), to_table="got_labels").awaitTermination()
    got = {r.visit_id: r.y_return for r in spark.table("got_labels").filter("subject_id < 9").collect()}
    from carepath.operators import temporal

    want = {r.visit_id: r.y_return for r in temporal.return_label(batch.withColumn("urgency", F.lit(""))).filter("subject_id < 9").collect()}
    assert got == want
