import pytest
from pyspark.sql import functions as F

from clusterfuse.sources import tables
from clusterfuse.streaming import summaries

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("events") / "in")
    tables.read_table(spark, SMALL, "events").orderBy("event_id").repartitionByRange(3, "event_id").write.parquet(out)
    return out


def drain(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def test_tumbling_stream_equals_batch(spark, folder):
    got = drain(summaries.window_summaries(summaries.read_events(spark, folder), watermark="40 days"), "tumbling", "update")
    batch = {(r.event_type, r.start): r.n for r in summaries.window_summaries(tables.events(spark, SMALL)).collect()}
    last = {}
    for r in got.collect():
        last[(r.event_type, r.start)] = max(r.n, last.get((r.event_type, r.start), 0))
    assert last == batch


def test_running_state_equals_batch(spark, folder):
    got = drain(summaries.running_clusters(summaries.read_events(spark, folder)), "running", "append")
    last = {}
    for r in got.collect():
        if r.n >= last.get(r.event_type, (0,))[0]:
            last[r.event_type] = (r.n, r["mean"], r["var"])
    for r in tables.events(spark, SMALL).filter("value is not null").groupBy("event_type").agg(*summaries.moments()).collect():
        n, mean, var = last[r.event_type]
        assert n == r.n and mean == pytest.approx(r["mean"]) and var == pytest.approx(r["var"])


def test_duplicates_are_dropped(spark, folder, tmp_path):
    twice = str(tmp_path / "twice")
    e = tables.read_table(spark, SMALL, "events")
    e.union(e).repartition(1).write.parquet(twice)
    got = drain(summaries.deduplicated(summaries.read_events(spark, twice), "40 days"), "dedup", "append")
    assert got.count() == e.count()


def test_late_rows_beyond_the_watermark_are_dropped(spark, tmp_path):
    src = str(tmp_path / "late")
    row = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    for day in ("2024-01-10", "2024-01-20", "2024-01-01"):
        spark.createDataFrame([(1, None, 1, "x", 1.0, "{}")], row).withColumn("ts", F.lit(f"{day} 01:00:00").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(src)
        import time

        time.sleep(1.1)
    got = drain(summaries.window_summaries(summaries.read_events(spark, src), watermark="1 day"), "late", "append")
    assert [str(r.start)[:10] for r in got.collect()] == ["2024-01-10"]


def test_snapshots_are_fused(spark, folder, tmp_path):
    out = str(tmp_path / "snap")
    s = summaries.window_summaries(summaries.read_events(spark, folder, 3), watermark="40 days")
    k = summaries.as_clusters(s, F.ascii("event_type") * 100000 + F.datediff("start", F.lit("2024-01-01").cast("date")))
    q = k.filter("n > 2").writeStream.outputMode("update").foreachBatch(summaries.fuse_snapshots(out)).option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination()
    fused = spark.read.parquet(f"{out}/fused/batch=0")
    kept = spark.read.parquet(f"{out}/clusters/batch=0")
    assert fused.agg(F.sum("n")).first()[0] == kept.agg(F.sum("n")).first()[0] and fused.count() < kept.count()


def test_state_of_a_silent_key_is_flushed(spark, tmp_path):
    src = str(tmp_path / "ttl")
    import time

    row = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    for day, key, value in (("2024-01-01", "a", 1.0), ("2024-01-01", "a", 3.0), ("2024-01-20", "b", 5.0), ("2024-01-25", "b", 6.0), ("2024-01-26", "b", 7.0)):
        spark.createDataFrame([(1, None, 1, key, value, "{}")], row).withColumn("ts", F.lit(f"{day} 01:00:00").cast("timestamp_ntz")).coalesce(1).write.mode("append").parquet(src)
        time.sleep(1.1)
    got = [(r.event_type, r.n, r["mean"], r.final) for r in drain(summaries.running_clusters(summaries.read_events(spark, src), ttl="2 days"), "ttl", "append").collect()]
    assert ("a", 2, 2.0, False) in got and ("a", 2, 2.0, True) in got and ("b", 3, 6.0, False) in got


def test_stream_is_joined_to_static_clusters(spark, folder):
    from clusterfuse.operators import summarize as S

    e = tables.read_table(spark, SMALL, "events", ["event_id", "event_type", "value"])
    k = S.summarize_columns(e, F.ascii("event_type"), ["value"])
    got = drain(summaries.assigned_events(summaries.read_events(spark, folder).select("event_id", "value"), k), "assigned", "append")
    want = summaries.assigned_events(e.select("event_id", "value"), k)
    assert sorted((r.event_id, r.assigned or 0) for r in got.collect()) == sorted((r.event_id, r.assigned or 0) for r in want.collect())


def test_asof_takes_the_latest_snapshot_across_stretches(spark):
    ev, snaps = [(1, "a", 1, 5), (2, "a", 3, 0), (3, "a", 3, 12), (4, "a", 9, 1), (5, "b", 9, 1), (6, "a", 1, 1)], [("a", 1, 4, 10), ("a", 3, 12, 20), ("b", 9, 2, 30)]
    events = spark.createDataFrame([(i, k, f"2024-01-{d:02d} {h:02d}:00:00") for i, k, d, h in ev], "id int, k string, t string").select("id", "k", F.to_timestamp("t").alias("ts"))
    held = spark.createDataFrame([(k, f"2024-01-{d:02d} {h:02d}:00:00", n) for k, d, h, n in snaps], "k string, t string, n int").select("k", F.to_timestamp("t").alias("valid_from"), "n")
    for width in ("hour", "day", "month"):
        got = summaries.asof(events, held, "k", take=("n",), width=width).collect()
        assert {r.id: r.snap_n for r in got} == {1: 10, 2: 10, 3: 20, 4: 20, 5: None, 6: None} and set(got[0].asDict()) == {"id", "k", "ts", "snap_n"}
