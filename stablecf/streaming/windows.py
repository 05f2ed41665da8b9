"""Streaming features: windowed aggregates with JVM state, and an evolving leaf set by micro-batch."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState

from stablecf.functions.features import stable_agg, stable_decay
from stablecf.operators.mixture import Mixture, assign
from stablecf.operators.summarize import project, summarize
from stablecf.operators.tree import FeatureTree, TreeConfig
from stablecf.sources.session import ship


def window_features(events: DataFrame, axes: list[Column], ts: str, size: str, slide: str | None = None, keys: tuple[str, ...] = (), late: str | None = None) -> DataFrame:
    """Features per time window (tumbling, or sliding with ``slide``); batch and streaming alike.  NTZ times are cast, as watermarks need."""
    e = events.withColumn("_ts", F.col(ts).cast("timestamp"))
    if late:
        e = e.withWatermark("_ts", late)
    w = F.window("_ts", size, slide) if slide else F.window("_ts", size)
    e = e.withColumn("win", w)
    return stable_agg(e, axes, ["win", *keys])


def session_features(events: DataFrame, axes: list[Column], ts: str, gap: str, keys: tuple[str, ...] = (), late: str | None = None) -> DataFrame:
    """Features per session: events of a key less than ``gap`` apart."""
    e = events.withColumn("_ts", F.col(ts).cast("timestamp"))
    if late:
        e = e.withWatermark("_ts", late)
    return stable_agg(e.withColumn("win", F.session_window("_ts", gap)), axes, ["win", *keys])


def late_rows(query: StreamingQuery) -> int:
    """Rows that the watermark dropped so far; rows that are late but allowed merge, as features add up."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


def score_stream(stream: DataFrame, axes: list[Column], model: Mixture, keep: list[str]) -> DataFrame:
    """Rows of a stream with their most likely component: the model is a few rows that go with the task."""
    rows = stream.select(*keep, F.lit(1.0).alias("w"), F.array(*[a.cast("double") for a in axes]).alias("m"))
    return assign(rows.where(F.forall("m", lambda v: v.isNotNull() & ~F.isnan(v))), model)


def unique_events(stream: DataFrame, key: list[str], ts: str, late: str) -> DataFrame:
    """Each key once within the watermark, so that the state is bounded."""
    e = stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late)
    return e.dropDuplicatesWithinWatermark(key) if stream.isStreaming else e.dropDuplicates(key)


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, minutes: int, late: str) -> DataFrame:
    """(key, left_ts, right_ts): events of ``right`` at most ``minutes`` after one of ``left``; watermarks let both states be dropped."""
    x = left.select(key, F.col(ts).cast("timestamp").alias("left_ts")).withWatermark("left_ts", late)
    y = right.select(F.col(key).alias("_key"), F.col(ts).cast("timestamp").alias("right_ts")).withWatermark("right_ts", late)
    on = (F.col(key) == F.col("_key")) & (F.col("right_ts") >= F.col("left_ts")) & (F.col("right_ts") <= F.col("left_ts") + F.expr(f"interval {minutes} minutes"))
    return x.join(y, on).drop("_key")


def keyed_summary(stream: DataFrame, key: str, axes: list[Column], cfg: TreeConfig, ttl_ms: int = 0) -> DataFrame:
    """(key, w, m, q): leaf entries per key of everything seen, at most ``cfg.leaf_cap`` each; the entries are the state, dropped ``ttl_ms`` after the key's last rows (0: never)."""
    d = len(axes)
    ship(stream.sparkSession)
    rows = stream.select(F.col(key).cast("string").alias("key"), F.array(*[a.cast("double") for a in axes]).alias("m"))

    def step(k, batches, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        tree = FeatureTree(cfg, d)
        if state.exists:
            threshold, w, m, q = state.get
            tree.threshold = threshold
            tree.insert_batch(np.array(w), np.array(m).reshape(-1, d), np.array(q).reshape(-1, d))
        for b in batches:
            x = np.stack(b["m"].to_numpy())
            x = x[np.isfinite(x).all(axis=1)]
            if len(x):
                tree.insert_batch(np.ones(len(x)), x, np.zeros_like(x))
        w, m, q = tree.leaves()
        state.update((tree.threshold, w.tolist(), m.ravel().tolist(), q.ravel().tolist()))
        if ttl_ms:
            state.setTimeoutDuration(ttl_ms)
        yield pd.DataFrame({"key": k[0], "w": w, "m": list(m), "q": list(q)})

    return rows.groupBy("key").applyInPandasWithState(step, "key string, w double, m array<double>, q array<double>", "threshold double, w array<double>, m array<double>, q array<double>", "update", "ProcessingTimeTimeout" if ttl_ms else "NoTimeout")


def evolving_summary(stream: DataFrame, axes: list[Column], cfg: TreeConfig, path: str, checkpoint: str, decay: float = 1.0, least: float = 0.0, keep: int = 2) -> StreamingQuery:
    """Leaf set of everything seen, one version a batch; a replayed batch overwrites its own version from the one before.

    ``decay`` scales what was seen before each batch, entries below ``least`` are dropped, and the last ``keep`` versions stay.
    """

    def fold(batch: DataFrame, n: int) -> None:
        spark, new = batch.sparkSession, project(batch, axes)
        if n:
            old = spark.read.parquet(f"{path}/v={n - 1}").select(stable_decay(F.struct("w", "m", "q"), decay).alias("f")).select("f.*")
            new = new.unionByName(old.where(F.col("w") >= least))
        summarize(new, cfg, compact=False).write.mode("overwrite").parquet(f"{path}/v={n}")
        if n >= keep:
            gone = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/v={n - keep}")
            gone.getFileSystem(spark._jsc.hadoopConfiguration()).delete(gone, True)

    return stream.writeStream.foreachBatch(fold).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
