"""Experiment workloads, re-expressed on the given tables: on the virtual clock (any number of lanes) or as measured probes."""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import functions as F

from blockmf.operators import measures
from blockmf.operators.params import MFParams
from blockmf.operators.train import DS3_RATINGS, plan, published_lanes, share, trace_frame, train
from blockmf.plans import costmodel as cm
from blockmf.plans.grid import id_counts, placed
from blockmf.plans.scheduler import makespan, schedule_frame
from blockmf.session import at_once, cut
from blockmf.sources.tables import hash_split, rating_view

QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


#: Views and the published data sets that they stand for: same shape or same share of cells; a rating stands for as many as the sizes say.
STANDS_FOR = {"supp_part": "DS1", "cust_supp": "DS2", "cust_part": "DS3", "planted": "DS4"}
WIDTHS, LANES = (32, 64, 128, 256, 512), (4, 8, 12, 16)


def _sizes(most: int, least: int = 1 << 9) -> list[int]:
    return [s for s in (least << i for i in range(20)) if s <= most]


@query()
def w1_speed_by_size(spark, sf_dir):
    """Measured ratings per second of the kernels that runs use, on growing prefixes of the shuffled flagship view up to all of it (at most 2^18), k = 32."""
    ratings = rating_view(spark, sf_dir, "cust_part")
    sample = cut(cm.probe_sample(ratings, 1 << 18), "w1")
    sizes = _sizes(sample.count())
    got = cm.probe_lane(sample, "narrow", MFParams(k=32, gamma=0.001), sizes, 3).withColumn("width", F.lit(1))
    for width in (32, 128, 512):
        got = got.unionByName(cm.probe_lane(sample, "wide", MFParams(k=32, gamma=0.001, batch_width=width), sizes, 3).withColumn("width", F.lit(width)))
    return got.groupBy("kind", "width", "size").agg(F.round(F.col("size") / F.avg("seconds"), 0).alias("rate"))


@query()
def w2_transfer_by_size(spark, sf_dir):
    """Measured ratings per second: blocks of the flagship view into a worker, and the factors they touch back (k = 32); clocks inside the workers."""
    sample = cut(cm.probe_sample(rating_view(spark, sf_dir, "cust_part"), 1 << 18), "w2")
    sizes = _sizes(sample.count(), 1 << 11)[::2]
    got = cm.probe_transfer(sample, "to", MFParams(k=32), sizes, 2).unionByName(cm.probe_transfer(sample, "from", MFParams(k=32), sizes, 2))
    return cm.throughput(got).select("stage", "size", F.round("speed", 0).alias("rate"))


@query()
def w3_kernel_by_size(spark, sf_dir):
    """Measured kernel seconds of both lane kinds by block size, k = 32."""
    sample = cut(cm.probe_sample(rating_view(spark, sf_dir, "cust_part"), 1 << 18), "w3")
    sizes = _sizes(sample.count())
    got = cm.probe_lane(sample, "narrow", MFParams(k=32, gamma=0.001), sizes, 2).unionByName(cm.probe_lane(sample, "wide", MFParams(k=32, gamma=0.001), sizes, 2))
    return cm.average(got).select("kind", "size", F.round("seconds", 6).alias("seconds"))


@query()
def cost_probe_to_share(spark, sf_dir):
    """The offline phase on this machine and what the online phase makes of it: probe, fit, cost function, share of the wide lanes on the flagship view."""
    ratings = rating_view(spark, sf_dir, "cust_part")
    fit = cm.estimate_costs(ratings, MFParams(k=32, gamma=0.001), repeats=2)
    alpha = share("hybrid_full", cm.cost_of(fit), ratings.count(), 3, 1)
    return fit.select("kind", "stage", "form").withColumn("share_is_a_share", F.lit(0 <= alpha <= 1))


_THREE = ("narrow_only", "wide_only", "hybrid_full")


@lru_cache(maxsize=32)
def _plans(spark, sf_dir, view, settings, algos, epochs=1):
    """(algo, setting, seconds of a pass of the data set that the view stands for, share of wide lanes in percent): on the clock of the published machine."""
    from blockmf.queries.measures import TRAINING

    r = cut(rating_view(spark, sf_dir, view), "view")
    counts = id_counts(placed(r, 0))
    scale = TRAINING[STANDS_FOR[view]] / counts.total
    rows, known = [], {}
    for setting, n, width in settings:
        for algo in algos:
            key = (algo, n if algo != "wide_only" else 0, width if algo != "narrow_only" else 0)
            if key not in known:
                p = plan(r, algo, n, 1, published_lanes(width, scale), epochs, counts=counts)
                known[key] = (p.makespan / epochs, None if p.alpha is None else p.alpha * 100)
            rows.append((view, algo, setting, *known[key]))
    return rows


_PASS = "view string, algo string, setting int, pass_s double, wide_share double"


@lru_cache(maxsize=8)
def _real_runs(spark, sf_dir) -> tuple:
    """Test error per pass of real runs on the planted view (3 narrow lanes, 1 wide lane), and seconds of a pass of the published machine with these lanes."""
    from blockmf.queries.measures import TRAINING

    a, b = hash_split(rating_view(spark, sf_dir, "planted"), 98)
    a, b = a.persist(), b.persist()
    cost, params = published_lanes(128, TRAINING["DS4"] / a.count()), MFParams(k=8, epochs=4, gamma=0.02, lam_p=0.01, lam_q=0.01)
    # side by side: a run has at most as many tasks as lanes, and its clock is virtual
    runs = at_once(spark, [lambda x=algo: train(a, params, x, 3, 1, cost, b, start="sqrt_mean", measure="test") for algo in (*_THREE, "hybrid_uniform")])
    a.unpersist(), b.unpersist()
    return tuple(t for run in runs for t in run.trace)


def _passes_to_target(spark, sf_dir) -> dict[str, int]:
    """Passes until the test error that all algorithms reach in the real runs."""
    traces = _real_runs(spark, sf_dir)
    target = max(min(t["rmse_test"] for t in traces if t["algo"] == a) for a in {t["algo"] for t in traces})
    return {a: min(t["epoch"] for t in traces if t["algo"] == a and t["rmse_test"] <= target + 1e-9) for a in {t["algo"] for t in traces}}


def _to_target(spark, sf_dir, settings):
    views = ("cust_part", "planted")
    reached, *planned = at_once(spark, [lambda: _passes_to_target(spark, sf_dir), *(lambda v=view: _plans(spark, sf_dir, v, settings, _THREE) for view in views)])
    rows = [x for found in planned for x in found]
    passes = spark.createDataFrame(list(reached.items()), "algo string, passes int")
    got = spark.createDataFrame(rows, _PASS).join(passes, "algo")
    return got.select("view", "algo", "setting", F.round("pass_s", 4).alias("pass_s"), "passes", F.round(F.col("pass_s") * F.col("passes"), 4).alias("target_s"))


@query()
def w4_vary_width(spark, sf_dir):
    """16 narrow lanes, width of the wide lane from 32 to 512: seconds of a pass and to the target error, two views."""
    return _to_target(spark, sf_dir, tuple((w, 16, w) for w in WIDTHS))


@query()
def w5_vary_lanes(spark, sf_dir):
    """Width 128, 4 to 16 narrow lanes: seconds of a pass and to the target error, two views."""
    return _to_target(spark, sf_dir, tuple((n, n, 128) for n in LANES))


@query()
def w4_gains(spark, sf_dir):
    """Where the hybrid wins and where it loses, in pass time: gain over either kind alone (below 1: it loses) for all widths, 16 narrow lanes."""
    rows = _plans(spark, sf_dir, "cust_part", tuple((w, 16, w) for w in WIDTHS), _THREE)
    p = spark.createDataFrame(rows, _PASS).groupBy("setting").pivot("algo", list(_THREE)).agg(F.first("pass_s"))
    return p.select("setting", F.round(F.col("narrow_only") / F.col("hybrid_full"), 3).alias("over_narrow"), F.round(F.col("wide_only") / F.col("hybrid_full"), 3).alias("over_wide"))


@query()
def w6_error_by_time(spark, sf_dir):
    """Test error by seconds of the published machine, real runs of all three algorithms and the uniform mix."""
    return trace_frame(spark, list(_real_runs(spark, sf_dir))).select("algo", "epoch", F.round("virtual_s", 4).alias("virtual_s"), F.round("rmse_test", 4).alias("rmse_test"))


@query()
def w7_grid_skew(spark, sf_dir):
    """Spread of update counts of the uniform mix and of the two-region division, under the same rule (least updated block first, equal ties by hash, no barrier
    and no equal counts forced), each stopped at the same virtual time: that of four passes of the uniform mix."""
    from blockmf.plans.scheduler import Policy, lanes_of, simulate

    r = rating_view(spark, sf_dir, "cust_part").persist()
    cost, out, until = published_lanes(512, DS3_RATINGS / r.count()), None, None
    for algo, name in (("hybrid_uniform", "greedy"), ("hybrid_full", "static")):
        p = plan(r, algo, 4, 1, cost, 1, steal="none")
        v = simulate(p.nnz, lanes_of(4, 1), cost, Policy(name, count="visits", steal="none"), 4 if until is None else 12, p.groups)
        until = until or makespan(v)
        s = measures.update_skew(schedule_frame(spark, [x for x in v if x.t_end <= until])).withColumn("algo", F.lit(algo))
        out = s if out is None else out.unionByName(s)
    r.unpersist()
    return out.select("algo", "least", "most", F.round("cv", 4).alias("cv"), F.round("gini", 4).alias("gini"))


def _twenty(spark, sf_dir, algos):
    """20 passes, each scheduled with its own seed, on all four views."""
    rows = [x for view in STANDS_FOR for x in _plans(spark, sf_dir, view, ((20, 16, 128),), algos, 20)]
    data = spark.createDataFrame(list(STANDS_FOR.items()), "view string, stands_for string")
    return spark.createDataFrame(rows, _PASS).join(data, "view")


@query()
def w8_cost_models(spark, sf_dir):
    """Shares and seconds of 20 passes of the line model and the piecewise model, without stealing, on a saturating device; four views."""
    got = _twenty(spark, sf_dir, ("hybrid_linear", "hybrid_model"))
    return got.select("stands_for", "algo", F.round("wide_share", 2).alias("wide_share"), F.round(F.col("pass_s") * 20, 3).alias("seconds_20"))


@query()
def w9_stealing(spark, sf_dir):
    """Seconds of 20 passes without and with stealing; four views."""
    return _twenty(spark, sf_dir, ("hybrid_model", "hybrid_full")).select("stands_for", "algo", F.round(F.col("pass_s") * 20, 3).alias("seconds_20"))


@query("SELECT CAST(18 AS INT) AS n_rows, CAST(17 AS INT) AS n_cols, CAST(826144 AS BIGINT) AS per_block, true AS below_million")
def w14_default_blocks(spark, sf_dir):
    from blockmf.plans.grid import min_grid
    from blockmf.queries.measures import TRAINING

    r, c = min_grid(16, 1)
    per = TRAINING["DS4"] // (r * c)
    return spark.createDataFrame([(r, c, per, per < 1_000_000)], "n_rows int, n_cols int, per_block long, below_million boolean")


_ALPHAS = " UNION ALL ".join(f"SELECT {n} AS n, {w} AS w, {x} AS nnz" for n, w in ((4, 1), (8, 1), (16, 1), (8, 2)) for x in (10**5, 10**7))


@query(f"SELECT CAST(n AS INT) AS n, CAST(w AS INT) AS w, CAST(nnz AS BIGINT) AS nnz, a AS algo, round((1e-6 / n) / (1e-7 / w + 1e-6 / n), 6) AS alpha FROM ({_ALPHAS}) x, (VALUES ('hybrid_linear'), ('hybrid_model')) t(a)")
def w8_shares_on_lines(spark, sf_dir):
    """On devices that are straight lines both cost models give the closed-form share."""
    cost = lambda kind, s: s * 1e-6 if kind == "narrow" else s * 1e-7
    rows = [(n, w, x, a, round(share(a, cost, x, n, w), 6)) for n, w in ((4, 1), (8, 1), (16, 1), (8, 2)) for x in (10**5, 10**7) for a in ("hybrid_linear", "hybrid_model")]
    return spark.createDataFrame(rows, "n int, w int, nnz long, algo string, alpha double")
