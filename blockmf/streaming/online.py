"""Structured Streaming over events(event_id, ts, user_id, event_type, value): views, windows, online training."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.functions.vectors import dot
from blockmf.operators.factors import side
from blockmf.operators.params import MFParams
from blockmf.session import exists, scratch_path

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A file stream of events; ts becomes a timestamp of the session's zone. path: a folder or a pattern of Parquet files."""
    rows = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def as_ratings(events: DataFrame) -> DataFrame:
    """u = user, v = hour of the day, r = value / 20."""
    return events.select("event_id", "ts", F.col("user_id").alias("u"), F.hour("ts").cast("long").alias("v"), (F.col("value") / 20).alias("r"))


def drain(stream: DataFrame, name: str, mode: str = "append", folder: str | None = None) -> DataFrame:
    """Run a stream over what is there into a table in the shared folder, and read it. With a folder of the caller's, a later call goes on from
    the state and the offsets that the former one left there; without one, each call starts anew."""
    spark = stream.sparkSession
    folder = folder or scratch_path(spark, name)
    out, state = f"{folder}/out", f"{folder}/state"
    if mode == "complete":
        def keep(batch: DataFrame, batch_id: int) -> None:
            batch.write.mode("overwrite").parquet(out)

        stream.writeStream.outputMode("complete").foreachBatch(keep).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    else:
        stream.writeStream.outputMode(mode).format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def split_late(events: DataFrame, late: str, folder: str) -> tuple[DataFrame, DataFrame]:
    """(rows on time, late rows) of a stream, run over what is there: a row is late if it is more than `late` behind the newest row of the batches before its own,
    which is what a watermark of that delay drops. Each batch writes its rows and its newest time under its number, so a batch that is run again replaces its own."""
    spark = events.sparkSession

    def keep(batch: DataFrame, batch_id: int) -> None:
        newest = None
        if batch_id:
            newest = spark.read.parquet(f"{folder}/newest").where(F.col("batch") < batch_id).agg(F.max("ts")).first()[0]
        border = F.lit(newest).cast("timestamp") - F.expr(f"INTERVAL {late}")
        rows = batch.withColumn("late", F.coalesce(F.col("ts") < border, F.lit(False))).persist()
        top = rows.agg(F.max("ts").alias("ts"))
        for name, part in (("on_time", rows.where("not late").drop("late")), ("late", rows.where("late").drop("late")), ("newest", top)):
            part.write.mode("overwrite").parquet(f"{folder}/{name}/batch={batch_id}")
        rows.unpersist()

    events.writeStream.foreachBatch(keep).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return tuple(spark.read.schema(events.schema).parquet(f"{folder}/{name}/batch=*") for name in ("on_time", "late"))


def tumbling(events: DataFrame, every: str = "1 day", late: str = "10 minutes") -> DataFrame:
    """Count and mean per window and type; rows later than `late` behind the newest are dropped."""
    w = events.withWatermark("ts", late).groupBy(F.window("ts", every).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean"))
    return w.select(F.col("w.start").alias("start"), "event_type", "n", "mean")


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day", late: str = "10 minutes") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size, step).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("w.start").alias("start"), "n", "total")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "10 minutes") -> DataFrame:
    """Runs of a user's events without a pause of `gap`."""
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def online_error(ratings: DataFrame, factors: DataFrame, every: str = "1 day", late: str = "10 minutes") -> DataFrame:
    """Windowed error of a fixed model on arriving ratings: a stream-static join with the factors."""
    rows = ratings.withWatermark("ts", late).join(side(factors, "p", "u", "p"), "u").join(side(factors, "q", "v", "q"), "v")
    e = F.col("r") - dot(F.col("p"), F.col("q"))
    return rows.groupBy(F.window("ts", every).alias("w")).agg(F.sqrt(F.avg(e * e)).alias("rmse"), F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "rmse", "n")


def follow_ups(events: DataFrame, within: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Stream-stream interval join: a purchase of a user with the user's clicks up to `within` before it."""
    a = events.where("event_type = 'purchase'").select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", late)
    b = events.where("event_type = 'click'").select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", late)
    return a.join(b, F.expr(f"a_user = b_user AND b_ts <= a_ts AND b_ts >= a_ts - INTERVAL {within}")).select("a_id", "b_id")


def online_sgd(ratings: DataFrame, factors: DataFrame, params: MFParams, name: str = "online", folder: str | None = None) -> list[DataFrame]:
    """Serial steps on each micro-batch in order of event_id, over versions of the factors: one table per batch, under the batch's number.

    With a folder of the caller's, a later call (or a restart after a failure) goes on from the last version: a batch that is run again starts from the version before
    it and replaces its own. A batch's users are independent only through their items, so the batch is one block here; large deployments use train() on it."""
    from blockmf.operators.executor import STATE, run_rounds, write_state
    from blockmf.plans.scheduler import Visit
    from blockmf.sources.blocks import lay_out

    spark = ratings.sparkSession
    folder = folder or scratch_path(spark, name)
    visit = Visit(0, 0, "narrow", (0,), 0, 1, "static", 0.0, 1.0)
    version = lambda n: spark.read.schema(STATE).parquet(f"{folder}/versions/{n}").select("side", "id", "stripe", "vec")
    if not exists(spark, f"{folder}/versions/0/_SUCCESS"):
        write_state(factors.withColumn("stripe", F.lit(0)).select("side", "id", "stripe", "vec"), path=f"{folder}/versions/0")

    def step(batch: DataFrame, batch_id: int) -> None:
        pinned = lay_out(batch.select("u", "v", "r", F.lit(0).alias("row_key"), F.lit(0).alias("bj"), F.col("event_id").alias("o")))
        after, kept = run_rounds(pinned, version(batch_id), [visit], [0], params)
        write_state(after, path=f"{folder}/versions/{batch_id + 1}")
        kept[0].unpersist()
        pinned.remove(spark)

    ratings.writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    found, n = [], 0
    while exists(spark, f"{folder}/versions/{n}/_SUCCESS"):
        found.append(version(n).select("side", "id", "vec"))
        n += 1
    return found


def per_user_state(ratings: DataFrame, columns: dict[int, list[float]], params: MFParams, ttl: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Each user's vector as keyed state, stepped at each of the user's ratings with the column vectors fixed: u, n, vec after each batch.
    columns: a model's column vectors, of bounded number (a stated set of items). ttl: a user without ratings for so long (by the watermark) is
    forgotten; a last row with n = 0 says so."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    k = params.k
    q = {int(i): np.array(v) for i, v in columns.items()}
    life = int(pd.Timedelta(ttl).total_seconds() * 1000) if ttl else 0

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"u": [key[0]], "n": [0], "vec": [None]})
            return
        n, vec = state.get if state.exists else (0, [0.1] * k)
        p = np.array(vec)
        rows = pd.concat(list(frames)).sort_values("event_id")
        for v, r in zip(rows["v"], rows["r"], strict=True):
            if int(v) in q:
                y = q[int(v)]
                p = p + params.gamma * params.grad_scale * ((r - float(p @ y)) * y - params.lam_p * p)
                n += 1
        state.update((n, p.tolist()))
        if life:
            newest = int(pd.Timestamp(rows["ts"].max()).timestamp() * 1000)
            state.setTimeoutTimestamp(max(newest + life, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"u": [key[0]], "n": [n], "vec": [p.tolist()]})

    rows = ratings.withWatermark("ts", late) if ttl else ratings
    timeout = GroupStateTimeout.EventTimeTimeout if ttl else GroupStateTimeout.NoTimeout
    return rows.groupBy("u").applyInPandasWithState(step, "u long, n long, vec array<double>", "n long, vec array<double>", "update", timeout)


def into_batches(stream: DataFrame, work: Callable[[DataFrame, int], None], name: str) -> None:
    stream.writeStream.outputMode("update").foreachBatch(work).option("checkpointLocation", scratch_path(stream.sparkSession, name)).trigger(availableNow=True).start().awaitTermination()
