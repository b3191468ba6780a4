"""Streams over the events table, run over what is there (availableNow) into a table, and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from blockmf.operators.factors import flat, init_expr, init_factors
from blockmf.operators.params import MFParams
from blockmf.sources.tables import rating_view
from blockmf.streaming import online as s

QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


def _events(spark, sf_dir):
    return s.event_stream(spark, f"{sf_dir}/events.parquet*")


@query("SELECT event_id, user_id AS u, CAST(hour(ts) AS BIGINT) AS v, round(value / 20, 6) AS r FROM events")
def stream_ratings(spark, sf_dir):
    return s.drain(s.as_ratings(_events(spark, sf_dir)), "ratings").select("event_id", "u", "v", F.round("r", 6).alias("r"))


@query("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n, round(avg(value), 8) AS mean FROM events WHERE ts < (SELECT date_trunc('day', max(ts) - INTERVAL 10 MINUTE) FROM events) GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    """Windows that the watermark has closed."""
    w = s.drain(s.tumbling(_events(spark, sf_dir)), "tumbling")
    return w.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", F.round("mean", 8).alias("mean"))


@query("""WITH d AS (SELECT date_trunc('day', ts) AS d, value FROM events), w AS (SELECT d AS start, value FROM d UNION ALL SELECT d - INTERVAL 1 DAY, value FROM d)
SELECT start, count(*) AS n, round(sum(value), 3) AS total FROM w GROUP BY start""")
def stream_sliding(spark, sf_dir):
    w = s.drain(s.sliding(_events(spark, sf_dir)), "sliding", "complete")
    return w.select(F.col("start").cast("timestamp_ntz").alias("start"), "n", F.round("total", 3).alias("total"))


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events),
k AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM k GROUP BY user_id, k""")
def stream_sessions(spark, sf_dir):
    w = s.drain(s.sessions(_events(spark, sf_dir)), "sessions", "complete")
    return w.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("SELECT event_id, user_id FROM events")
def stream_dedup(spark, sf_dir):
    """Every event twice in the stream, once in the result."""
    twice = _events(spark, sf_dir).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1))))
    return s.drain(s.deduplicated(twice), "dedup").select("event_id", "user_id")


@query("SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL 30 MINUTE WHERE a.event_type = 'purchase' AND b.event_type = 'click'")
def stream_follow_ups(spark, sf_dir):
    return s.drain(s.follow_ups(_events(spark, sf_dir)), "follow")


def _error_sql() -> str:
    """The watermark closes the windows that end before the newest event less its delay."""
    element = lambda side: f"list_transform(range(4), lambda j: {init_expr(side, 4, 1, 1.0)})"
    return f"""WITH x AS (SELECT date_trunc('day', ts) AS start, value / 20 AS r, user_id, CAST(hour(ts) AS BIGINT) AS h FROM events),
u AS (SELECT id, {element('p')} AS p FROM (SELECT DISTINCT user_id AS id FROM x) a), v AS (SELECT id, {element('q')} AS q FROM (SELECT DISTINCT h AS id FROM x) b)
SELECT start, round(sqrt(avg(power(r - list_inner_product(p, q), 2))), 5) AS rmse, count(*) AS n FROM x JOIN u ON u.id = user_id JOIN v ON v.id = h
WHERE start < (SELECT date_trunc('day', max(ts) - INTERVAL 10 MINUTE) FROM events) GROUP BY start"""


@query(_error_sql())
def stream_online_error(spark, sf_dir):
    r = rating_view(spark, sf_dir, "user_hour")
    f = init_factors(r, 4)
    w = s.drain(s.online_error(s.as_ratings(_events(spark, sf_dir)), f), "error")
    return w.select(F.col("start").cast("timestamp_ntz").alias("start"), F.round("rmse", 5).alias("rmse"), "n")


P1 = MFParams(k=4, epochs=1)


@query()
def stream_online_sgd(spark, sf_dir):
    """Steps by event over all events and users, in four micro-batches: the error of each version on all events. Tested against a serial loop."""
    from blockmf.operators.measures import rmse
    from blockmf.session import scratch_path

    ratings = rating_view(spark, sf_dir, "user_hour")
    f = init_factors(ratings, P1.k, P1.seed, P1.scale)
    path = scratch_path(spark, "event-files")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    events.repartitionByRange(4, "event_id").write.parquet(path)
    versions = s.online_sgd(s.as_ratings(s.event_stream(spark, path)), f, P1)
    out = None
    for n, v in enumerate(versions):
        e = rmse(ratings, v).select(F.lit(n).alias("version"), F.round("rmse", 5).alias("rmse"), "n")
        out = e if out is None else out.unionByName(e)
    return out


@query()
def stream_online_sgd_all(spark, sf_dir):
    """Serial steps by event over all events and users: the last version of the factors."""
    f = init_factors(rating_view(spark, sf_dir, "user_hour"), P1.k, P1.seed, P1.scale)
    return flat(s.online_sgd(s.as_ratings(_events(spark, sf_dir)), f, P1)[-1])


_Q = {h: [0.1 * (1 + (h + j) % 3) for j in range(4)] for h in range(24)}
_STATE_SQL = f"""WITH RECURSIVE q(h, y) AS (VALUES {", ".join(f"({h}, {y})" for h, y in _Q.items())}),
e AS (SELECT user_id AS u, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS n, value / 20 AS r, CAST(y AS DOUBLE[]) AS y FROM events JOIN q ON q.h = hour(ts)),
s(u, n, vec) AS (SELECT DISTINCT u, CAST(0 AS BIGINT), CAST([0.1, 0.1, 0.1, 0.1] AS DOUBLE[]) FROM e
  UNION ALL SELECT s.u, e.n, list_transform(range(1, 5), lambda j: vec[j] + {P1.gamma} * ((e.r - list_inner_product(vec, e.y)) * e.y[j] - {P1.lam_p} * vec[j])) FROM s JOIN e ON e.u = s.u AND e.n = s.n + 1),
m AS (SELECT u, max(n) AS n FROM s GROUP BY u)
SELECT u, n, CAST(i AS INT) AS pos, round(vec[i + 1], 6) AS value FROM s JOIN m USING (u, n), range(4) t(i)"""


@query(_STATE_SQL)
def stream_user_state(spark, sf_dir):
    """Vectors as keyed state, after all events: the last row of each user."""
    from blockmf.session import scratch_path

    out = scratch_path(spark, "user-state")
    s.into_batches(s.per_user_state(s.as_ratings(_events(spark, sf_dir)), _Q, P1), lambda batch, i: batch.write.mode("append").parquet(out), "state")
    last = spark.read.parquet(out).groupBy("u").agg(F.max(F.struct("n", "vec")).alias("x"))
    return last.select("u", "x.n", F.posexplode("x.vec").alias("pos", "value")).withColumn("value", F.round("value", 6))


@query("SELECT event_id, coalesce(ts < (SELECT max(b.ts) FROM events b WHERE b.event_id % 3 < a.event_id % 3) - INTERVAL 6 HOUR, false) AS late FROM events a")
def stream_late_rows(spark, sf_dir):
    """Events that arrive in three files dealt by number: which of them come too late for a watermark of six hours; none is lost."""
    from blockmf.session import scratch_path

    path, folder = scratch_path(spark, "late-files"), scratch_path(spark, "late")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    for part in range(3):
        events.where(F.col("event_id") % 3 == part).coalesce(1).write.mode("append").parquet(path)
    on_time, late = s.split_late(s.event_stream(spark, path), "6 hours", folder)
    return on_time.select("event_id", F.lit(False).alias("late")).unionByName(late.select("event_id", F.lit(True).alias("late")))
