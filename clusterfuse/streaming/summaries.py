"""Clusters from streams: windowed summaries with watermarks, running clusters in state, joins with snapshots.

Fusion is additive, so late rows inside the watermark simply join their window. State holds (n, mean, M2) for each key and
does not grow with rows; fusing across keys is done on snapshots in foreachBatch.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.stats import assign
from ..operators.summarize import CLUSTER, usable

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_a_batch: int = 1) -> DataFrame:
    """Stream of Parquet files with events; ts becomes a timestamp, which watermarks need."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_a_batch).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def moments(value: str = "value") -> list[Column]:
    return [F.count(F.lit(1)).alias("n"), F.avg(value).alias("mean"), F.coalesce(F.var_samp(value), F.lit(0.0)).alias("var")]


def window_summaries(ev: DataFrame, size: str = "1 day", slide: str | None = None, watermark: str | None = None, key: str = "event_type", value: str = "value") -> DataFrame:
    """n, mean, var of ``value`` by key in tumbling or sliding windows of ts; works on batches and streams."""
    x = ev.filter(usable([value]))
    x = x.withWatermark("ts", watermark) if watermark else x
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return x.groupBy(key, w.alias("w")).agg(*moments(value)).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "mean", "var")


def session_summaries(ev: DataFrame, gap: str = "6 hours", watermark: str | None = None, key: str = "user_id", value: str = "value") -> DataFrame:
    x = ev.filter(usable([value]))
    x = x.withWatermark("ts", watermark) if watermark else x
    return x.groupBy(key, F.session_window("ts", gap).alias("w")).agg(*moments(value)).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "mean", "var")


def deduplicated(ev: DataFrame, watermark: str = "1 day") -> DataFrame:
    """A stream without events of an id seen within the watermark."""
    return ev.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def running_clusters(ev: DataFrame, key: str = "event_type", value: str = "value", ttl: str | None = None, watermark: str = "1 day") -> DataFrame:
    """Running n, mean, var of each key of a stream, kept in state and emitted for each batch that brings rows.

    With ``ttl`` a key that brings no row for that long in event time (behind ``watermark``) is flushed: its last values come
    once more with final = true and its state is dropped, so that state does not grow with keys of the past."""
    seconds = None if ttl is None else int(ev.sparkSession.sql(f"SELECT CAST(interval {ttl} AS INTERVAL SECOND) AS s").first()[0].total_seconds())

    def update(k, frames, state):
        import pandas as pd

        if state.hasTimedOut:
            n, mean, m2 = state.get
            state.remove()
            yield pd.DataFrame({key: [k[0]], "n": [n], "mean": [mean], "var": [m2 / (n - 1) if n > 1 else 0.0], "final": [True]})
            return
        n, mean, m2 = state.get if state.exists else (0, 0.0, 0.0)
        last = None
        for f in frames:
            x = f[value].dropna()
            last = f["ts"].max() if last is None else max(last, f["ts"].max())
            if len(x):
                c, m = len(x), float(x.mean())
                s = float(((x - m) ** 2).sum())
                d = m - mean
                m2 += s + d * d * n * c / (n + c)
                mean += d * c / (n + c)
                n += c
        state.update((int(n), float(mean), float(m2)))
        if seconds is not None and last is not None:
            at = int(last.timestamp() * 1000) + 1000 * seconds
            state.setTimeoutTimestamp(max(at, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({key: [k[0]], "n": [int(n)], "mean": [mean], "var": [m2 / (n - 1) if n > 1 else 0.0], "final": [False]})

    kind = dict(ev.dtypes)[key]
    x = ev.filter(usable([value]))
    x = x.withWatermark("ts", watermark) if ttl else x
    return x.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, n bigint, mean double, var double, final boolean", "n bigint, mean double, m2 double", "append", "EventTimeTimeout" if ttl else "NoTimeout")


def assigned_events(ev: DataFrame, clusters: DataFrame, features: tuple[str, ...] = ("value",)) -> DataFrame:
    """Events of a batch or a stream joined to the current clusters: ``assigned`` is the one of the highest density.

    The clusters are static; a restarted query, or the next foreachBatch, takes newer ones."""
    return assign(ev.withColumns({f: F.col(f).cast("double") for f in features}), list(features), clusters, len(features))


def as_clusters(summaries: DataFrame, cluster_id: Column, model_id: str = "stream") -> DataFrame:
    """D = 1 clusters from n, mean, var."""
    return summaries.select(F.lit(model_id).alias("model_id"), cluster_id.cast("long").alias("cluster_id"), F.lit(1).alias("dim"), "n", F.array("mean").alias("mean"), F.array("var").alias("cov"))


def fuse_snapshots(path: str, every: int = 1, threshold: float = 1.5):
    """A foreachBatch function that writes each snapshot of clusters and, every so many batches, their fusion, under ``path``."""

    def batch(df: DataFrame, k: int) -> None:
        from ..operators.fuse import fuse_overlapping

        df.select("model_id", "cluster_id", "dim", "n", "mean", "cov").write.mode("overwrite").parquet(f"{path}/clusters/batch={k}")
        if k % every == 0 and not df.isEmpty():
            fuse_overlapping(df.sparkSession.read.schema(CLUSTER).parquet(f"{path}/clusters/batch={k}"), threshold=threshold, dim=1).write.mode("overwrite").parquet(f"{path}/fused/batch={k}")

    return batch


def asof(events: DataFrame, snapshots: DataFrame, by: str, at: str = "ts", valid: str = "valid_from", take: tuple[str, ...] = ("n", "mean", "var"), width: str = "day") -> DataFrame:
    """Each event with the latest snapshot of its key at or before it, as columns snap_*; null if there is none.

    Events and snapshots of one key and one stretch of time (``width``, a unit of date_trunc) are merged in time order in a
    window of their own; the snapshot that a stretch begins with is carried into it. So a window holds the events of one
    stretch, and only the snapshots and the distinct stretches of a key, which are few, meet in one task."""
    kinds = dict(snapshots.dtypes)
    stretch = lambda c: F.date_trunc(width, c)
    held = snapshots.select(F.col(by), F.col(valid).alias("_at"), F.struct(*[F.col(c) for c in take]).alias("_snap"))
    starts = events.select(by, stretch(at).alias("_at")).distinct().withColumn("_snap", F.lit(None).cast(f"struct<{','.join(f'{c}:{kinds[c]}' for c in take)}>"))
    before = Window.partitionBy(by).orderBy("_at", F.col("_snap").isNull().cast("int")).rowsBetween(Window.unboundedPreceding, 0)
    carried = held.unionByName(starts).withColumn("_last", F.last("_snap", ignorenulls=True).over(before)).filter("_snap is null and _last is not null").select(by, "_at", F.col("_last").alias("_snap"))
    right = held.unionByName(carried).select(*[F.col(by) if c == by else F.lit(None).cast(t).alias(c) for c, t in events.dtypes], F.lit(0).alias("_kind"), "_at", "_snap")
    left = events.select(*events.columns, F.lit(1).alias("_kind"), F.col(at).alias("_at"), F.lit(None).cast(dict(held.dtypes)["_snap"]).alias("_snap"))
    seen = Window.partitionBy(by, "_stretch").orderBy("_at", "_kind").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right).withColumn("_stretch", stretch("_at")).withColumn("_snap", F.last("_snap", ignorenulls=True).over(seen))
    return both.filter("_kind = 1").select(*events.columns, *[F.col("_snap")[c].alias(f"snap_{c}") for c in take])


def within_validity(events: DataFrame, models: DataFrame, by: str) -> DataFrame:
    """Events with the model of their key that is valid at ts (valid_from <= ts < valid_to): an equi-join on key and day, then the range."""
    days = models.withColumn("day", F.explode(F.sequence(F.to_date("valid_from"), F.to_date(F.col("valid_to") - F.expr("interval 1 microsecond")))))
    return events.withColumn("day", F.to_date("ts")).join(days, [by, "day"]).filter((F.col("ts") >= F.col("valid_from")) & (F.col("ts") < F.col("valid_to"))).drop("day")
