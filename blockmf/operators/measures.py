"""Measures: accuracy, time, work shares, skew, idle time, ranking quality. Tables in, small tables out."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockmf.functions.vectors import dot
from blockmf.operators.factors import side, with_vectors


def rmse(ratings: DataFrame, factors: DataFrame, cold: str = "drop") -> DataFrame:
    """One row: rmse, n, n_cold. Cells whose row or column has no vector are dropped and counted, or get the mean of the rest."""
    rows = ratings.join(side(factors, "p", "u", "p"), "u", "left").join(side(factors, "q", "v", "q"), "v", "left")
    known = F.col("p").isNotNull() & F.col("q").isNotNull()
    rows = rows.select("r", known.alias("known"), F.when(known, dot(F.col("p"), F.col("q"))).alias("hat"))
    if cold == "mean":
        mean = rows.agg(F.avg("hat").alias("m"))
        rows = rows.crossJoin(F.broadcast(mean)).withColumn("hat", F.coalesce("hat", "m"))  # one row
    return rows.agg(F.sqrt(F.avg((F.col("r") - F.col("hat")) ** 2)).alias("rmse"), F.count("hat").alias("n"), F.count_if(~F.col("known")).alias("n_cold"))


def mae(ratings: DataFrame, factors: DataFrame) -> DataFrame:
    return with_vectors(ratings, factors).agg(F.avg(F.abs(F.col("r") - dot(F.col("p"), F.col("q")))).alias("mae"))


def time_to_target(trace: DataFrame, target: float) -> DataFrame:
    """algo, seconds, epochs until the test error is at most the target; null if never."""
    ok = F.col("rmse_test") <= target
    return trace.groupBy("algo").agg(F.min(F.when(ok, F.col("wall_s"))).alias("seconds"), F.min(F.when(ok, F.col("epoch"))).alias("epochs"))


def speedup(times: DataFrame, base: str) -> DataFrame:
    """times(algo, seconds) -> algo, speedup over the base algorithm."""
    b = times.where(F.col("algo") == base).select(F.col("seconds").alias("base_s"))
    return times.crossJoin(F.broadcast(b)).select("algo", (F.col("base_s") / F.col("seconds")).alias("speedup"))  # one row


def work_share(schedule: DataFrame) -> DataFrame:
    """kind, share of the ratings processed, in percent."""
    per = schedule.dropDuplicates(["visit"]).groupBy("kind").agg(F.sum("nnz").alias("nnz"))
    return per.select("kind", (100.0 * F.col("nnz") / F.sum("nnz").over(Window.partitionBy())).alias("share"))  # one row per kind


def update_skew(schedule: DataFrame) -> DataFrame:
    """One row over blocks: least, most, mean, coefficient of variation and Gini index of the update counts of blocks that occur."""
    counts = schedule.groupBy("row", "col").agg(F.count(F.lit(1)).alias("n"))
    rank = counts.select("n", F.row_number().over(Window.orderBy("n", "row", "col")).alias("i"))  # metadata: one row per block
    g = rank.agg(F.min("n").alias("least"), F.max("n").alias("most"), F.avg("n").alias("mean"), (F.stddev_pop("n") / F.avg("n")).alias("cv"), F.sum(F.col("i") * F.col("n")).alias("s"), F.sum("n").alias("t"), F.count(F.lit(1)).alias("m"))
    return g.select("least", "most", "mean", "cv", (2 * F.col("s") / (F.col("m") * F.col("t")) - (F.col("m") + 1) / F.col("m")).alias("gini"))


def lane_usage(schedule: DataFrame) -> DataFrame:
    """lane_id, kind, busy, makespan, idle share."""
    visits = schedule.dropDuplicates(["visit"])
    lanes = visits.groupBy("lane_id", "kind").agg(F.sum(F.col("t_end") - F.col("t_start")).alias("busy"))
    end = visits.agg(F.max("t_end").alias("makespan"))
    return lanes.crossJoin(F.broadcast(end)).select("lane_id", "kind", "busy", "makespan", (1 - F.col("busy") / F.col("makespan")).alias("idle"))  # one row


def overhead(schedule: DataFrame) -> DataFrame:
    """One row: share of the lanes' time that is not work, and imbalance (most busy over mean busy)."""
    return lane_usage(schedule).agg((1 - F.sum("busy") / F.sum("makespan")).alias("overhead"), (F.max("busy") / F.avg("busy")).alias("imbalance"))


def moved_bytes(schedule: DataFrame, k: int, stripe_rows: DataFrame) -> DataFrame:
    """kind, ratings_bytes, p_bytes, q_bytes over a schedule. stripe_rows(axis, idx, n): ids per stripe. Row vectors stay where a lane works on the same
    row stripe as before; column vectors and ratings move at each visit."""
    s = schedule.withColumn("prev", F.lag("row").over(Window.partitionBy("lane_id").orderBy("visit", "row")))
    p = stripe_rows.where("axis = 'row'").select(F.col("idx").alias("row"), F.col("n").alias("np"))
    q = stripe_rows.where("axis = 'col'").select(F.col("idx").alias("col"), F.col("n").alias("nq"))
    j = s.join(F.broadcast(p), "row", "left").join(F.broadcast(q), "col", "left")
    first = F.row_number().over(Window.partitionBy("visit").orderBy("row")) == 1
    j = j.withColumn("first", first)
    return j.groupBy("kind").agg(
        F.sum(F.when(F.col("first"), F.col("nnz") * 24).otherwise(0)).alias("ratings_bytes"),
        F.sum(F.when(F.col("prev").eqNullSafe(F.col("row")), 0).otherwise(F.col("np") * 8 * k)).alias("p_bytes"),
        F.sum(F.when(F.col("first"), F.col("nq") * 8 * k).otherwise(0)).alias("q_bytes"),
    )


def loss_curve(trace: DataFrame) -> DataFrame:
    """trace with the change of the test error since the epoch before and a mean over three epochs."""
    w = Window.partitionBy("algo").orderBy("epoch")
    return trace.select("algo", "epoch", "rmse_test", (F.col("rmse_test") - F.lag("rmse_test").over(w)).alias("change"), F.avg("rmse_test").over(w.rowsBetween(-1, 1)).alias("smooth"))


def ranking_quality(ranked: DataFrame, relevant: DataFrame, k: int) -> DataFrame:
    """One row: precision, recall, ndcg at k over users with relevant items. ranked(u, v, rank from 1), relevant(u, v)."""
    hits = ranked.where(F.col("rank") <= k).join(relevant.withColumn("hit", F.lit(1)), ["u", "v"], "left")
    per = hits.groupBy("u").agg(F.sum(F.coalesce("hit", F.lit(0))).alias("hits"), F.sum(F.coalesce("hit", F.lit(0)) / F.log2(F.col("rank") + 1.0)).alias("dcg"))
    want = relevant.groupBy("u").agg(F.count(F.lit(1)).alias("m"))
    ideal = F.aggregate(F.sequence(F.lit(1), F.least(F.col("m"), F.lit(k)).cast("int")), F.lit(0.0), lambda s, i: s + 1 / F.log2(i + 1.0))
    joined = want.join(per, "u", "left")
    return joined.agg(
        F.avg(F.coalesce("hits", F.lit(0)) / float(k)).alias("precision_at_k"),
        F.avg(F.coalesce("hits", F.lit(0)) / F.col("m")).alias("recall_at_k"),
        F.avg(F.coalesce("dcg", F.lit(0.0)) / ideal).alias("ndcg_at_k"),
    )
