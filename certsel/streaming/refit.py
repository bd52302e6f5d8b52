"""Selection over a stream: every micro-batch is a universe of its own, whose cut is estimated anew.

Guarantees hold per batch; for a joint one the failure probability is split over the batches that are expected.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from certsel.operators import runner
from certsel.sources.staging import fresh_path
from certsel.spec import SelectionSpec


def windowed_counts(events: DataFrame, width: str = "1 day", late: str = "2 hours") -> DataFrame:
    """Tumbling counts by type with a watermark; a repeated event_id within it counts once."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return e.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def sliding_counts(events: DataFrame, width: str = "2 days", slide: str = "1 day", late: str = "2 hours") -> DataFrame:
    """Counts by type in overlapping windows."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def running_matches(events: DataFrame) -> DataFrame:
    """(event_type, n, most) after each batch: a state of two numbers a type, kept by a Python operator."""

    def fold(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, most = state.get if state.exists else (0, float("-inf"))
        for p in parts:
            n, most = n + len(p), max(most, float(p["value"].max()))
        state.update((n, most))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "most": [most]})

    out = "event_type string, n long, most double"
    return events.select("event_type", "value").groupBy("event_type").applyInPandasWithState(fold, out, "n long, most double", "update", "NoTimeout")


def refit_batch(base: DataFrame, oracle, spec: SelectionSpec, batch: int) -> DataFrame:
    """The answer of one micro-batch with its batch number; the seed moves with the batch."""
    s = spec.but(seed=spec.seed + 1000 * batch)
    if base.limit(spec.budget + 1).count() <= spec.budget:
        s = s.but(method="exhaustive")
    return runner.run(base, oracle, s).rows.withColumn("batch", F.lit(batch))


def refit_stream(stream: DataFrame, prepare, oracle, spec: SelectionSpec, out_dir: str, checkpoint_dir: str, per_batch_delta: int = 1):
    """Start a query that writes each micro-batch's answer under out_dir; a rerun batch overwrites its own folder only."""
    own = spec.but(delta=spec.delta / per_batch_delta)

    def each(df: DataFrame, batch: int) -> None:
        base = prepare(df).persist()
        try:
            refit_batch(base, oracle, own, batch).write.mode("overwrite").parquet(f"{out_dir}/batch={batch}")
        finally:
            base.unpersist()

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint_dir).trigger(availableNow=True).start()


def apply_current(stream: DataFrame, cuts: DataFrame) -> DataFrame:
    """Stream rows above the newest cut: cuts holds (fitted_at, tau_u), of which the latest counts."""
    newest = cuts.withColumn("k", F.row_number().over(Window.orderBy(F.desc("fitted_at")))).where("k = 1").select("tau_u")
    return stream.crossJoin(F.broadcast(newest)).where("score_u >= tau_u").drop("tau_u")  # one row


def replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream of one batch: rows (event_id, score_u) of its answer."""
    from certsel.sources.workloads import ALL
    from certsel.functions.synth import quantised

    w = ALL["rare"]
    run_dir = fresh_path(spark, "refit")  # of this call alone: an older checkpoint would make it do nothing
    stream = _events(spark, sf_dir)
    prepare = lambda df: df.select(F.col("event_id").alias("key"), quantised(F.col("value") / F.lit(300)).alias("score_u"), "event_type", "value")
    q = refit_stream(stream, prepare, w.oracle, SelectionSpec(budget=w.budget), f"{run_dir}/out", f"{run_dir}/checkpoint")
    q.awaitTermination()
    return spark.read.parquet(f"{run_dir}/out").select(F.col("key").alias("event_id"), "score_u", "batch")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{sf_dir}/events.parquet"
    return spark.readStream.schema(spark.read.parquet(path).schema).parquet(path + "*")


def replay_counts(spark: SparkSession, sf_dir: str, count, by: str = "event_type") -> DataFrame:
    """The events table as a file stream through sliding_counts or session_counts: (start day, by, n) of all windows."""
    run_dir = fresh_path(spark, "counts")
    each = lambda df, batch: df.write.mode("overwrite").parquet(f"{run_dir}/out")  # noqa: E731  complete: the last batch holds all windows
    counts = count(_events(spark, sf_dir))
    counts.writeStream.outputMode("complete").foreachBatch(each).option("checkpointLocation", f"{run_dir}/c").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{run_dir}/out").select(F.date_format("start", "yyyy-MM-dd").alias("start"), by, "n")


def replay_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last state of running_matches over the events table."""
    run_dir = fresh_path(spark, "running")
    each = lambda df, batch: df.withColumn("batch", F.lit(batch)).write.mode("append").parquet(f"{run_dir}/out")
    running_matches(_events(spark, sf_dir)).writeStream.outputMode("update").foreachBatch(each).option("checkpointLocation", f"{run_dir}/c").trigger(availableNow=True).start().awaitTermination()
    last = spark.read.parquet(f"{run_dir}/out").groupBy("event_type").agg(F.max(F.struct("batch", "n", "most")).alias("s"))
    return last.select("event_type", "s.n", "s.most")
