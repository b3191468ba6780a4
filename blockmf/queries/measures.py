"""Measures over literal traces and over the published result tables (values that must equal the reported ones)."""

from __future__ import annotations

from pyspark.sql import functions as F

from blockmf.operators import measures as m

QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


#: Seconds of 20 passes as reported, for the line model, the piecewise model, and the piecewise model with stealing.
PUBLISHED = [("DS1", 0.92, 0.89, 0.84), ("DS2", 15.87, 13.02, 11.42), ("DS3", 13.07, 12.08, 10.58), ("DS4", 40.88, 35.41, 30.96)]
#: Training ratings of the four datasets.
TRAINING = {"DS1": 9_301_274, "DS2": 99_072_112, "DS3": 104_215_016, "DS4": 252_800_275}
_TRACE = [("narrow_only", e, 2.0 * e, 25.2 - 0.6 * e) for e in range(1, 13)] + [("wide_only", e, 1.5 * e, 25.0 - 0.5 * e) for e in range(1, 13)] + [("hybrid_full", e, 1.0 * e, 23.0 - 0.5 * e) for e in range(1, 13)]
_TRACE_SQL = "(VALUES " + ", ".join(f"('{a}', {e}, CAST({s} AS DOUBLE), CAST({round(r, 6)} AS DOUBLE))" for a, e, s, r in _TRACE) + ") t(algo, epoch, wall_s, rmse_test)"


def _trace(spark):
    return spark.createDataFrame([(a, e, s, round(r, 6)) for a, e, s, r in _TRACE], "algo string, epoch int, wall_s double, rmse_test double")


@query(f"SELECT algo, min(CASE WHEN rmse_test <= 20 THEN wall_s END) AS seconds, min(CASE WHEN rmse_test <= 20 THEN epoch END) AS epochs FROM {_TRACE_SQL} GROUP BY algo")
def measure_time_to_target(spark, sf_dir):
    return m.time_to_target(_trace(spark), 20.0)


@query(f"WITH x AS (SELECT algo, min(CASE WHEN rmse_test <= 20 THEN wall_s END) AS seconds FROM {_TRACE_SQL} GROUP BY algo) SELECT algo, round((SELECT seconds FROM x WHERE algo = 'narrow_only') / seconds, 6) AS speedup FROM x")
def measure_speedup(spark, sf_dir):
    times = m.time_to_target(_trace(spark), 20.0).select("algo", "seconds")
    return m.speedup(times, "narrow_only").select("algo", F.round("speedup", 6).alias("speedup"))


@query(f"SELECT algo, epoch, round(rmse_test - lag(rmse_test) OVER w, 6) AS change, round(avg(rmse_test) OVER (PARTITION BY algo ORDER BY epoch ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 6) AS smooth FROM {_TRACE_SQL} WINDOW w AS (PARTITION BY algo ORDER BY epoch)")
def measure_loss_curve(spark, sf_dir):
    return m.loss_curve(_trace(spark)).select("algo", "epoch", F.round("change", 6).alias("change"), F.round("smooth", 6).alias("smooth"))


_PUB = "(VALUES " + ", ".join(f"('{d}', {a}, {b}, {c}, {TRAINING[d]})" for d, a, b, c in PUBLISHED) + ") t(ds, line_s, model_s, full_s, training)"


@query(f"SELECT ds, round(line_s / model_s, 2) AS gain_model, round(model_s / full_s, 2) AS gain_steal, round(line_s / full_s, 2) AS gain_both, round(20.0 * training / full_s / 1e6, 0) AS million_per_s FROM (SELECT ds, CAST(line_s AS DOUBLE) AS line_s, CAST(model_s AS DOUBLE) AS model_s, CAST(full_s AS DOUBLE) AS full_s, training FROM {_PUB}) x")
def measure_published_gains(spark, sf_dir):
    t = spark.createDataFrame([(d, a, b, c, TRAINING[d]) for d, a, b, c in PUBLISHED], "ds string, line_s double, model_s double, full_s double, training long")
    return t.select("ds", F.round(F.col("line_s") / F.col("model_s"), 2).alias("gain_model"), F.round(F.col("model_s") / F.col("full_s"), 2).alias("gain_steal"), F.round(F.col("line_s") / F.col("full_s"), 2).alias("gain_both"), F.round(20.0 * F.col("training") / F.col("full_s") / 1e6, 0).alias("million_per_s"))


_VISITS = [(i, i % 3, "wide" if i % 3 == 2 else "narrow", i % 4, (i * 2 + i // 3) % 5, 1, 100 * (1 + i % 7), "static", float(i), i + 1.0 + (i % 3) * 0.5, i // 3) for i in range(30)]
_VISITS_SQL = "(VALUES " + ", ".join(f"({v[0]}, {v[1]}, '{v[2]}', {v[3]}, {v[4]}, {v[6]}, CAST({v[8]} AS DOUBLE), CAST({v[9]} AS DOUBLE))" for v in _VISITS) + ') t(visit, lane_id, kind, "row", col, nnz, t_start, t_end)'
DDL = "visit long, lane_id int, kind string, row int, col int, n_rows int, nnz long, phase string, t_start double, t_end double, round int"


def _visits(spark):
    return spark.createDataFrame(_VISITS, DDL)


@query(f"SELECT kind, round(100.0 * sum(nnz) / (SELECT sum(nnz) FROM {_VISITS_SQL}), 6) AS share FROM {_VISITS_SQL} GROUP BY kind")
def measure_share(spark, sf_dir):
    return m.work_share(_visits(spark)).select("kind", F.round("share", 6).alias("share"))


@query(f"""WITH c AS (SELECT "row", col, count(*) AS n FROM {_VISITS_SQL} GROUP BY "row", col), i AS (SELECT n, row_number() OVER (ORDER BY n, "row", col) AS i FROM c)
SELECT min(n) AS least, max(n) AS most, round(avg(n), 6) AS mean, round(stddev_pop(n) / avg(n), 6) AS cv, round(2.0 * sum(i * n) / (count(*) * sum(n)) - (count(*) + 1.0) / count(*), 6) AS gini FROM i""")
def measure_update_skew(spark, sf_dir):
    s = m.update_skew(_visits(spark))
    return s.select("least", "most", *[F.round(c, 6).alias(c) for c in ("mean", "cv", "gini")])


@query(f"WITH l AS (SELECT lane_id, kind, sum(t_end - t_start) AS busy FROM {_VISITS_SQL} GROUP BY lane_id, kind), e AS (SELECT max(t_end) AS makespan FROM {_VISITS_SQL}) SELECT lane_id, kind, round(busy, 6) AS busy, makespan, round(1 - busy / makespan, 6) AS idle FROM l, e")
def measure_lane_usage(spark, sf_dir):
    return m.lane_usage(_visits(spark)).select("lane_id", "kind", F.round("busy", 6).alias("busy"), "makespan", F.round("idle", 6).alias("idle"))


@query(f"WITH l AS (SELECT lane_id, sum(t_end - t_start) AS busy FROM {_VISITS_SQL} GROUP BY lane_id), e AS (SELECT max(t_end) AS makespan FROM {_VISITS_SQL}) SELECT round(1 - sum(busy) / sum(makespan), 6) AS overhead, round(max(busy) / avg(busy), 6) AS imbalance FROM l, e")
def measure_overhead(spark, sf_dir):
    return m.overhead(_visits(spark)).select(F.round("overhead", 6).alias("overhead"), F.round("imbalance", 6).alias("imbalance"))


@query(f"""WITH s AS (SELECT *, lag("row") OVER (PARTITION BY lane_id ORDER BY visit) AS prev FROM {_VISITS_SQL})
SELECT kind, sum(nnz * 24) AS ratings_bytes, sum(CASE WHEN prev IS NOT DISTINCT FROM "row" THEN 0 ELSE 50 * 64 END) AS p_bytes, sum(CAST(20 * 64 AS BIGINT)) AS q_bytes FROM s GROUP BY kind""")
def measure_moved_bytes(spark, sf_dir):
    stripes = spark.createDataFrame([("row", i, 50) for i in range(4)] + [("col", i, 20) for i in range(5)], "axis string, idx int, n long")
    return m.moved_bytes(_visits(spark), 8, stripes)


@query("SELECT round(0.23 * 1.33 + 2.32 * 2.00, 4) AS product, round(5.0 - (0.23 * 1.33 + 2.32 * 2.00), 4) AS residual")
def measure_worked_cell(spark, sf_dir):
    from blockmf.functions.vectors import dot

    d = spark.createDataFrame([([0.23, 2.32], [1.33, 2.00], 5.0)], "p array<double>, q array<double>, r double").withColumn("d", dot(F.col("p"), F.col("q")))
    return d.select(F.round("d", 4).alias("product"), F.round(F.col("r") - F.col("d"), 4).alias("residual"))
