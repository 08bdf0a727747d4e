"""Streams of observations: hourly sums, sessions, replays, late rows, joins, and scoring as slots come in."""

from __future__ import annotations

import sys
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream that ends once all files are read; time as an instant, which watermarks ask for."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(rows: DataFrame, width: str = "1 hour", late: str = "2 hours") -> DataFrame:
    out = rows.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("y"), F.count("*").alias("n"))
    return out.select(F.col("event_type").alias("source"), F.col("window.start").cast("timestamp_ntz").alias("start"), "y", "n")


def sliding(rows: DataFrame, width: str = "6 hours", step: str = "1 hour", late: str = "2 hours") -> DataFrame:
    out = rows.withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n"))
    return out.select(F.col("event_type").alias("source"), F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


def sessions(rows: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    out = rows.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


def deduplicated(rows: DataFrame, late: str = "2 hours") -> DataFrame:
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def joined(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pairs of rows of a user whose second follows the first within a bound; both sides forget what cannot match."""
    a = left.withWatermark("ts", late).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta"))
    b = right.withWatermark("ts", late).select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb"))
    return a.join(b, F.expr(f"u = v and tb > ta and tb <= ta + interval {within}")).select("a", "b", F.col("u").alias("user_id"))


class OnlineScore(StatefulProcessor):
    """Keeps the last context + horizon slots of a series and emits a window's squared error once its future is complete."""

    def __init__(self, context: int, horizon: int, season: int):
        self.context, self.horizon, self.season = context, horizon, season

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("tail", "first long, ys array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:
        new = pd.concat(list(rows)).sort_values("t")
        t, y = new["t"].to_numpy(np.int64), pd.to_numeric(new["y"]).to_numpy(float)
        first, tail = self.state.get() if self.state.exists() else (int(t[0]), [])
        held, span = len(tail), self.context + self.horizon
        ys = np.full(max(int(t[-1]) - first + 1, held), np.nan)
        ys[:held] = [np.nan if v is None else v for v in tail]
        ys[t - first] = y
        done = max(len(ys) - span + 1, 0)
        out = {c: [] for c in ("origin", "m", "rfl")}
        if done:
            # Squared errors of the slots once, then sums over every window's future.
            e = (ys[self.context :] - ys[self.context - self.season : len(ys) - self.season]) ** 2
            m = np.lib.stride_tricks.sliding_window_view((~np.isnan(e)).astype(np.int64), self.horizon).sum(1)
            total = np.lib.stride_tricks.sliding_window_view(np.nan_to_num(e), self.horizon).sum(1)
            out = {"origin": first + np.arange(done), "m": m, "rfl": np.where(m > 0, total / np.maximum(m, 1), np.nan)}
        self.state.update((first + done, [None if np.isnan(v) else float(v) for v in ys[done:]]))
        rows = pd.DataFrame({"source": key[0], "series_id": key[1], **out})
        yield rows

    def close(self) -> None:
        pass


def online_scores(rows: DataFrame, context: int, horizon: int, season: int) -> DataFrame:
    """Scores of ``rows(source, series_id, t, y)``, whose slots come in order; horizon at most one season."""
    if horizon > season or context < season:
        raise ValueError("the season must cover the horizon and fit the context")
    # The process that plans the state has no added files, so the processor travels by value.
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    return rows.groupBy("source", "series_id").transformWithStateInPandas(
        OnlineScore(context, horizon, season), outputStructType="source string, series_id string, origin long, m long, rfl double", outputMode="Append", timeMode="None"
    )


def keep_within(scores: DataFrame, cuts: DataFrame) -> DataFrame:
    """Scores inside their source's frozen bounds ``cuts(source, lo, hi)``; one row a source, so it is broadcast."""
    return scores.join(F.broadcast(cuts), "source").where(F.col("rfl").between(F.col("lo"), F.col("hi")))


def run_in_turns(parts: list[DataFrame], plan, mode: str = "update") -> DataFrame:
    """Feed ``parts`` one after another to the stream ``plan(rows)`` under one checkpoint; its rows with the turn that gave them.

    Each turn starts from the state and the watermark of the one before, so what a watermark turns away in a later
    part is what it would turn away in a stream that never stopped.
    """
    from ..sources.tables import shared_dir

    spark, root = parts[0].sparkSession, f"{shared_dir(parts[0].sparkSession)}/lossband-streams/{uuid.uuid4().hex[:12]}"
    for turn, part in enumerate(parts):
        part.write.parquet(f"{root}/in/turn={turn}")
        rows = plan(spark.readStream.schema(part.schema).option("recursiveFileLookup", "true").parquet(f"{root}/in"))

        def write(df: DataFrame, epoch: int, turn: int = turn) -> None:
            df.write.mode("overwrite").parquet(f"{root}/out/turn={turn}/epoch={epoch}")

        rows.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).foreachBatch(write).start().awaitTermination()
    return spark.read.option("basePath", f"{root}/out").schema(f"{_ddl(rows)}, turn int, epoch long").parquet(f"{root}/out/turn=*/epoch=*")


def _ddl(rows: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema)


def run_once(rows: DataFrame, mode: str = "append", batch=None, columns: list[str] | None = None) -> DataFrame:
    """Run a bounded stream to its end and return its rows as a written table; ``batch(df, id)`` sees every batch besides."""
    from ..sources.tables import shared_dir

    spark, root = rows.sparkSession, f"{shared_dir(rows.sparkSession)}/lossband-streams/{uuid.uuid4().hex[:12]}"

    def write(df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(f"{root}/out/epoch={epoch}")
        if batch:
            batch(df, epoch)

    query = rows.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    return spark.read.schema(rows.schema).parquet(f"{root}/out/epoch=*")


class CutoffRefresh:
    """Merges each batch's sketch of scores by source and republishes approximate cuts of the middle share."""

    def __init__(self, low: float, high: float, path: str):
        self.low, self.high, self.path, self.epoch = low, high, path, 0

    def __call__(self, df: DataFrame, epoch: int) -> None:
        spark = df.sparkSession
        new = df.where("rfl is not null").groupBy("source").agg(F.kll_sketch_agg_double("rfl").alias("sketch"))
        if self.epoch:
            old = spark.read.parquet(f"{self.path}/{self.epoch}")
            both = old.join(new.withColumnRenamed("sketch", "fresh"), "source", "full")
            new = both.select("source", F.when(F.col("fresh").isNull(), F.col("sketch")).when(F.col("sketch").isNull(), F.col("fresh")).otherwise(F.kll_sketch_merge_double("sketch", "fresh")).alias("sketch"))
        self.epoch += 1
        new.write.mode("overwrite").parquet(f"{self.path}/{self.epoch}")

    def cuts(self, spark: SparkSession) -> DataFrame:
        rows = spark.read.parquet(f"{self.path}/{self.epoch}")
        return rows.select("source", F.kll_sketch_get_quantile_double("sketch", F.lit(self.low)).alias("lo"), F.kll_sketch_get_quantile_double("sketch", F.lit(self.high)).alias("hi"))
