"""Worker reports as streams: windows, duplicates, enrichment, aggregation into the plan and asynchronous promotion."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stagewise.store import PlanStore, Scratch

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def source(spark: SparkSession, path: str, schema: str | None = None) -> DataFrame:
    """Files of reports as they arrive; event times are timestamps, as watermarks need them."""
    schema = schema or spark.read.parquet(path).schema
    return spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def collected(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs what is there now to its end and gives the result table, which is written as Parquet, a folder per micro-batch.

    A micro-batch that runs again after a failure writes its folder anew.  In complete mode the last folder holds the result.
    """
    return followed_progress(stream, mode)[0]


def followed_progress(stream: DataFrame, mode: str = "complete") -> tuple[DataFrame, int]:
    """(the result table, reports that came after the watermark and were dropped)."""
    spark, scratch, batches = stream.sparkSession, Scratch(stream.sparkSession, "stream"), []

    def write(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{scratch.root}/out/{batch}")
        if batch not in batches:
            batches.append(batch)

    q = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{scratch.root}/progress").trigger(availableNow=True).start()
    try:
        q.awaitTermination()
        late = sum(int(s.numRowsDroppedByWatermark) for p in q.recentProgress for s in p.stateOperators)
    finally:
        q.stop()
    if not batches:
        return spark.createDataFrame([], stream.schema), late
    taken = batches[-1:] if mode == "complete" else batches
    return spark.read.schema(stream.schema).parquet(*[f"{scratch.root}/out/{b}" for b in taken]), late


def tumbling(stream: DataFrame, size: str, late: str) -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"), F.max("value").alias("best"))
    return w.select(F.col("window.start").alias("window_start"), "event_type", "n", "best")


def sliding(stream: DataFrame, size: str, slide: str, late: str) -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", size, slide)).agg(F.count("*").alias("n"), F.max("value").alias("best"))
    return w.select(F.col("window.start").alias("window_start"), "n", "best")


def sessions(stream: DataFrame, gap: str, late: str) -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("session_start"), "n")


def deduplicated(stream: DataFrame, keys: list[str], late: str) -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def enriched(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    return stream.join(static, on)


def followed(first: DataFrame, later: DataFrame, within: str, late: str) -> DataFrame:
    """Each report with those of the other stream by the same user after it and at most ``within`` later; old state leaves with the watermark."""
    a = first.withWatermark("ts", late).select("event_id", "user_id", "ts")
    b = later.withWatermark("ts", late).select(F.col("event_id").alias("later_id"), F.col("user_id").alias("later_user"), F.col("ts").alias("later_ts"))
    return a.join(b, F.expr(f"user_id = later_user and later_ts > ts and later_ts <= ts + interval {within}"))


def latest(batch: DataFrame) -> DataFrame:
    """Reports(path, step, ord, value) as metrics of (path, step): the last report of each, so that repeats change nothing."""
    return batch.groupBy("path", "step").agg(F.max_by("value", "ord").alias("value"))


def aggregate(stream: DataFrame, plan: PlanStore, wake) -> int:
    """Folds a stream of reports(path, step, ord, value) into the plan's metrics until its present end; the number of micro-batches.

    Each micro-batch is reduced where it lies, then by key, and appended as a part named by its number, so one that runs twice
    changes nothing.  ``wake`` is called after a micro-batch that brought metrics that the plan had not, with their number.
    """
    scratch, done = Scratch(stream.sparkSession, "reports"), []

    def fold(batch: DataFrame, number: int) -> None:
        known = plan.read("metrics").select("path", "step")
        new = scratch.save(latest(batch).join(known, ["path", "step"], "left_anti"), f"new-{number}")
        n = new.count()
        if n:
            plan.append("metrics", new, f"reports-{number}")
            wake(n)
        done.append(number)

    q = stream.writeStream.foreachBatch(fold).option("checkpointLocation", f"{scratch.root}/progress").trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return len(done)


def async_promotions(stream: DataFrame, eta: int, steps: list[int], counted: bool = False) -> DataFrame:
    """Stateful asynchronous halving per study over reports(study, ord, trial, step, value): (study, trial, rung, nth).

    State holds, per rung, the results that were not promoted as a heap and the promoted ones in order; a report costs the logarithm of their number.
    Only reports at a rung's step reach a study's task.  With ``counted`` the k-th report of a trial is that of its step k, and the
    numbers of reports are state too.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    from stagewise.operators.tuners import AsyncHalving

    def on_batch(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        told = json.loads(state.get[0]) if state.exists else {"counts": []}
        tuner, counts = AsyncHalving.load(told) if state.exists else AsyncHalving(eta, steps), dict(told["counts"])
        new, made = pd.concat(list(parts)).sort_values("ord"), []
        before = tuner.made
        for t, s, v in zip(new["trial"].tolist(), new["step"].tolist(), new["value"].tolist()):
            if counted:
                s = counts[t] = counts.get(t, 0) + 1
            made += tuner.report(int(t), int(s), float(v))
        state.update((json.dumps(tuner.dump() | {"counts": list(counts.items())}),))
        yield pd.DataFrame([(key[0], t, r, before + k) for k, (t, r) in enumerate(made)], columns=["study", "trial", "rung", "nth"])

    return (stream if counted else stream.where(F.col("step").isin(steps))).groupBy("study").applyInPandasWithState(
        on_batch, "study string, trial long, rung long, nth long", "tuner string", "append", GroupStateTimeout.NoTimeout
    )
