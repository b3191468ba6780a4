"""Kernels, losses, training, measures, recommendation, model files, streams."""

import math
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockmf.functions.ids import dense_codes, prefix_sum
from blockmf.operators import baselines, losses, measures
from blockmf.operators.factors import init_factors, init_vector
from blockmf.operators.kernels import narrow_kernel, ordered_kernel, run_block, wide_kernel
from blockmf.operators.params import AnyOf, FixedEpochs, MFParams, RelChange, TargetRMSE
from blockmf.operators.serial import order_expr, sgd_serial
from blockmf.operators.train import train
from blockmf.plans.scheduler import speeds
from blockmf.session import at_once, scratch_path
from blockmf.sources import model_io
from blockmf.sources.tables import check_ratings, hash_split, rating_view

P = MFParams(k=4, epochs=2)


@pytest.fixture(scope="module")
def hours(spark):
    return rating_view(spark, "/root/testdata/sf0.001", "user_hour").persist()


@pytest.mark.parametrize("k", [1, 4, 16])
@pytest.mark.parametrize("q_sees", ["old_p", "new_p"])
def test_kernels_agree_bit_for_bit(k, q_sees):
    rng = np.random.default_rng(k)
    rows, cols, vals = rng.integers(0, 30, 2000), rng.integers(0, 40, 2000), rng.random(2000)
    p, q = rng.random((30, k)), rng.random((40, k))
    out = []
    for f, params in ((narrow_kernel, MFParams(k=k, q_sees=q_sees)), (ordered_kernel, MFParams(k=k, q_sees=q_sees)), (wide_kernel, MFParams(k=k, q_sees=q_sees, batch_width=1)), (wide_kernel, MFParams(k=k, q_sees=q_sees, batch_width=64, collide="split"))):
        a, b = p.copy(), q.copy()
        f(rows, cols, vals, a, b, params)
        out.append((a, b))
    for a, b in out[1:]:
        assert (a == out[0][0]).all() and (b == out[0][1]).all()


def test_collision_rules_differ_only_on_shared_vectors():
    rows, cols, vals = np.array([0, 0, 1]), np.array([0, 1, 2]), np.array([1.0, 2.0, 3.0])
    got = {}
    for c in ("sum", "mean", "last"):
        p, q = np.full((2, 2), 0.5), np.full((3, 2), 0.5)
        wide_kernel(rows, cols, vals, p, q, MFParams(k=2, batch_width=8, collide=c))
        got[c] = (p, q)
    assert (got["sum"][1] == got["mean"][1]).all() and (got["sum"][0][1] == got["last"][0][1]).all()
    assert got["mean"][0][0] == pytest.approx((got["sum"][0][0] + 0.5) / 2)
    assert (got["last"][0][0] != got["sum"][0][0]).all()


def test_worked_cell(spark):
    f = spark.createDataFrame([("p", 1, [0.23, 2.32]), ("q", 1, [1.33, 2.0])], "side string, id long, vec array<double>")
    r = spark.createDataFrame([(1, 1, 5.0)], "u long, v long, r double")
    assert losses.score(r, f).first().r_hat == pytest.approx(4.9459)


def test_gradient_is_the_slope_of_the_loss(spark, hours):
    some = hours.where("u < 6")
    f = init_factors(some, 3)
    params = MFParams(k=3, grad_scale=2.0)
    g = {(r.side, r.id): r.grad for r in losses.sum_gradients(some, f, params).collect()}
    at = lambda fac: losses.loss(some, fac, params.lam_p, params.lam_q).first().loss
    eps = 1e-5
    for side, i, j in (("p", 2, 0), ("q", 5, 2)):
        def moved(d):
            vec = F.transform("vec", lambda x, k: x + F.when((F.col("side") == side) & (F.col("id") == i) & (k == j), d).otherwise(0.0))  # noqa: B023
            return f.withColumn("vec", vec)

        assert (at(moved(eps)) - at(moved(-eps))) / (2 * eps) == pytest.approx(g[(side, i)][j], rel=1e-4)
    assert at(losses.gd_full(some, f, MFParams(k=3, gamma=0.001, epochs=1))) < at(f)


def serial_of(plan, ratings_rows, params):
    """Visits one after the other in order of time, on one machine."""
    blocks = defaultdict(list)
    for x in ratings_rows:
        blocks[(x.row_key, x.bj)].append(x)
    pi, qi = np.array(sorted({x.u for x in ratings_rows})), np.array(sorted({x.v for x in ratings_rows}))
    p, q = init_vector("p", pi, params.k, params.seed, params.scale), init_vector("q", qi, params.k, params.seed, params.scale)
    for visits in plan.passes:
        for v in sorted(visits, key=lambda v: (v.t_start, v.visit)):
            rows = sorted((x for r in v.rows for x in blocks[(r, v.col)]), key=lambda x: (x.o, x.u, x.v))
            if rows:
                run_block(v.kind, *(np.array([getattr(x, c) for x in rows]) for c in "uvr"), pi, p, qi, q, params)
    return {("p", int(i)): p[k] for k, i in enumerate(pi)} | {("q", int(i)): q[k] for k, i in enumerate(qi)}


@pytest.mark.parametrize(("algo", "n", "w"), [("narrow_only", 2, 0), ("hybrid_uniform", 2, 1), ("hybrid_full", 2, 1), ("hybrid_model", 1, 1), ("wide_only", 0, 2), ("strata", 3, 0)])
def test_rounds_equal_the_asynchronous_order(hours, algo, n, w):
    run = train(hours, P, algo, n, w, cost=speeds(1, 4), measure=False)
    rows = run.plan.assigned.selectExpr("u", "v", "r", "row_key", "bj", f"{order_expr('hash', 1)} as o").collect()
    assert len(rows) == hours.count() == sum(run.plan.nnz.values())
    want = serial_of(run.plan, rows, P)
    got = {(r.side, r.id): np.array(r.vec) for r in run.factors.collect()}
    assert got.keys() == want.keys() and all((got[k] == want[k]).all() for k in want)


def test_training_lowers_the_error_and_stops(spark):
    a, b = hash_split(rating_view(spark, "/root/testdata/sf0.001", "planted"), 98)
    run = train(a, MFParams(k=8, epochs=6, gamma=0.05, lam_p=0.01, lam_q=0.01), "hybrid_full", 2, 1, speeds(1, 5), b, AnyOf(TargetRMSE(0.01), RelChange(0.0), FixedEpochs(3)), start="sqrt_mean")
    assert len(run.trace) == 3
    assert run.trace[-1]["rmse_train"] < run.trace[0]["rmse_train"]
    als = baselines.als(a, MFParams(k=8, epochs=5, lam_p=0.05))
    assert measures.rmse(b, als).first().rmse < baselines.mean_model(a, b).first().rmse


def test_divergence_is_reported(hours):
    with pytest.raises(Exception, match="diverged"):
        train(hours, MFParams(k=4, epochs=1, gamma=1e200), "narrow_only", 2, 0, measure=False)


@pytest.mark.parametrize("rows", [[(1, 1, 2.0)], [(1, j, 1.0) for j in range(20)], [(i, 1, 1.0) for i in range(20)], [(i, i, 3.0) for i in range(3)]])
@pytest.mark.parametrize("algo", ["narrow_only", "hybrid_full"])
def test_degenerate_matrices(spark, rows, algo):
    r = spark.createDataFrame(rows, "u long, v long, r double")
    run = train(r, MFParams(k=1, epochs=1), algo, 2, 1, speeds(1, 3))
    assert run.factors.count() == len({u for u, _, _ in rows}) + len({v for _, v, _ in rows})
    assert math.isfinite(run.trace[0]["rmse_train"])


def test_serial_is_one_pass_in_order(hours):
    f = {(r.side, r.id): r.vec for r in sgd_serial(hours, MFParams(k=4, epochs=1), "given").collect()}
    rows = sorted(hours.collect(), key=lambda x: (x.u * 1000003 + x.v))
    pi, qi = np.array(sorted({x.u for x in rows})), np.array(sorted({x.v for x in rows}))
    p, q = init_vector("p", pi, 4, 1, 1.0), init_vector("q", qi, 4, 1, 1.0)
    narrow_kernel(np.searchsorted(pi, [x.u for x in rows]), np.searchsorted(qi, [x.v for x in rows]), np.array([x.r for x in rows]), p, q, MFParams(k=4))
    assert all((np.array(f[("p", int(i))]) == p[k]).all() for k, i in enumerate(pi))


def test_check_ratings(spark):
    bad = spark.createDataFrame([(1, 1, 2.0), (1, 1, 4.0), (None, 1, 1.0), (2, None, 1.0), (2, 2, None), (2, 3, float("nan")), (2, 4, float("inf"))], "u long, v long, r double")
    assert [tuple(x) for x in check_ratings(bad).collect()] == [(1, 1, 3.0)]
    assert check_ratings(bad, "count").first().r == 2.0


def test_cold_cells(spark):
    f = spark.createDataFrame([("p", 1, [1.0]), ("q", 1, [2.0])], "side string, id long, vec array<double>")
    r = spark.createDataFrame([(1, 1, 3.0), (9, 1, 5.0)], "u long, v long, r double")
    a, b = measures.rmse(r, f).first(), measures.rmse(r, f, "mean").first()
    assert (a.rmse, a.n, a.n_cold) == (1.0, 1, 1) and b.rmse == pytest.approx(math.sqrt(5.0))


def test_prefix_sum_and_codes(spark):
    df = spark.range(1000).selectExpr("id * 7 % 1000 as k", "id % 5 as x")
    got = [r.cum for r in prefix_sum(df, ["k"], F.col("x"), "cum").orderBy("k").collect()]
    assert got == np.cumsum([(k * 143 % 1000) % 5 for k in range(1000)]).tolist()
    assert [r.code for r in dense_codes(df, "k").orderBy("k").collect()] == list(range(1000))


def test_model_files(spark, hours):
    path = scratch_path(spark, "model")
    f = init_factors(hours, 4)
    model_io.save_model(f, P, path)
    g, params = model_io.load_model(spark, path)
    assert params == P and g.exceptAll(f.select("side", "id", "vec")).isEmpty() and g.count() == f.count()


def test_coordinate_descent_lowers_the_loss(hours):
    f = init_factors(hours, 2)
    after = baselines.ccd(hours, f, MFParams(k=2, epochs=1))
    assert losses.loss(hours, after, 0.05, 0.05).first().loss < losses.loss(hours, f, 0.05, 0.05).first().loss


def test_late_rows_are_dropped_and_a_stream_goes_on(spark):
    from blockmf.streaming import online as s

    path, out, state = scratch_path(spark, "late"), scratch_path(spark, "late-out"), scratch_path(spark, "late-state")
    make = lambda rows: spark.createDataFrame(rows, "event_id long, t string, user_id long, event_type string, value double, props string").selectExpr("event_id", "cast(t as timestamp_ntz) ts", "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(path)

    def go():
        w = s.tumbling(s.event_stream(spark, path), "1 hour")
        w.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
        return {(str(r.start), r.n) for r in spark.read.parquet(out).collect()}

    make([(1, "2024-01-01 00:10:00", 1, "a", 1.0, None), (2, "2024-01-01 03:00:00", 1, "a", 1.0, None)])
    assert go() == {("2024-01-01 00:00:00", 1)}
    make([(3, "2024-01-01 00:20:00", 1, "a", 1.0, None), (4, "2024-01-01 06:00:00", 1, "a", 1.0, None)])
    assert go() == {("2024-01-01 00:00:00", 1), ("2024-01-01 03:00:00", 1)}  # the late row is not counted; the run went on from its state


def test_rounds_never_shuffle_ratings(hours):
    """The plan of a pass: one exchange per round, of factors with their visit; ratings are only read by the lanes that work on them."""
    from blockmf.operators.executor import pin_ratings, run_rounds, write_state
    from blockmf.operators.train import initial_state, plan

    p = plan(hours, "hybrid_full", 2, 1, speeds(1, 4), 1)
    pinned = pin_ratings(p.assigned)
    state, _ = write_state(initial_state(hours, p, P, 0))
    after, kept = run_rounds(pinned, state, p.passes[0], p.rounds[0], P)
    assert len(kept) <= max(p.rounds[0]) + 1
    for frame in kept:
        text = frame._jdf.queryExecution().withCachedData().toString() + frame._jdf.queryExecution().analyzed().toString()
        assert "row_key" not in text and pinned.path.rsplit("/", 1)[-1] not in text
    plan_text = after._jdf.queryExecution().executedPlan().toString()
    assert "row_key" not in plan_text and after.count() == state.count()
    for frame in kept:
        frame.unpersist()


def test_blocks_are_read_in_order_and_in_steps(spark, hours):
    from blockmf.sources.blocks import in_batches, lay_out, read_blocks

    rows = hours.selectExpr("u", "v", "r", "u % 3 as row_key", "0 as bj", "v * 7 % 5 as o")
    layout = lay_out(rows)
    want = sorted((x.o, x.u, x.v) for x in rows.where("row_key != 1").collect())
    got = [(u, v) for part in in_batches(read_blocks(layout.path, (0, 2), 0, 50), 7) for u, v in zip(part[0].tolist(), part[1].tolist(), strict=True)]
    assert got == [(u, v) for _, u, v in want]
    sizes = [len(p[0]) for p in in_batches(read_blocks(layout.path, (1,), 0, 10), 7)]
    assert sum(sizes) == rows.where("row_key = 1").count() and all(s % 7 == 0 for s in sizes[:-1])
    assert list(read_blocks(layout.path, (9,), 0)) == []


def test_start_vectors_differ_and_orders_hold_for_any_id(spark):
    ids = np.array([0, 1, 10007, 20014, 2147483647, 2147483648, 10**12, 2**53])
    m = init_vector("p", ids, 8, 1, 1.0)
    assert len({tuple(x) for x in m.tolist()}) == len(ids) and (m >= 0).all() and (m < 1).all()
    r = spark.createDataFrame([(int(i), 1, 1.0) for i in ids], "u long, v long, r double")
    got = {x.id: x.vec for x in init_factors(r, 8).where("side = 'p'").collect()}
    assert all(got[int(i)] == x for i, x in zip(ids, m.tolist(), strict=True))
    far = spark.createDataFrame([(u, v) for u in (5, 4101, 10**7) for v in (5, 4101, 8197)], "u long, v long").selectExpr("u", "v", f"{order_expr('conflict_free', 1)} as o").collect()
    for x in far:
        assert not any(x.o == y.o and (x.u == y.u) != (x.v == y.v) for y in far)


def test_online_run_goes_on_after_a_restart(spark):
    """A run that stops after two of four files and is started again ends with the model of one run; a batch that is run again replaces its version."""
    from blockmf.streaming import online as s

    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").where("event_id < 200")
    f = init_factors(events.selectExpr("user_id as u", "cast(hour(ts) as long) as v", "value as r"), 4)
    paths, folder = [scratch_path(spark, x) for x in ("all", "some")], scratch_path(spark, "online")
    part = lambda i, path: events.where(f"event_id div 50 = {i}").coalesce(1).write.mode("append").parquet(path)
    for i in range(4):
        part(i, paths[0])
    whole = s.online_sgd(s.as_ratings(s.event_stream(spark, paths[0])), f, P)
    for i in range(2):
        part(i, paths[1])
    assert len(s.online_sgd(s.as_ratings(s.event_stream(spark, paths[1])), f, P, folder=folder)) == 3
    for i in range(2, 4):
        part(i, paths[1])
    again = s.online_sgd(s.as_ratings(s.event_stream(spark, paths[1])), f, P, folder=folder)
    assert len(again) == len(whole) == 5
    assert sorted(again[-1].collect()) == sorted(whole[-1].collect()) and sorted(again[2].collect()) == sorted(whole[2].collect())


def test_state_of_users_expires(spark):
    from blockmf.streaming import online as s

    path, out = scratch_path(spark, "ttl"), scratch_path(spark, "ttl-out")
    make = lambda rows: spark.createDataFrame(rows, "event_id long, t string, user_id long, event_type string, value double, props string").selectExpr("event_id", "cast(t as timestamp_ntz) ts", "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(path)
    for k, (user, t) in enumerate([(1, "2024-01-01 00:00:00"), (2, "2024-01-01 05:00:00"), (2, "2024-01-01 05:10:00"), (2, "2024-01-01 05:20:00")]):
        make([(k, t, user, "a", 20.0, None)])
    q = {h: [0.5] * 4 for h in range(24)}
    s.into_batches(s.per_user_state(s.as_ratings(s.event_stream(spark, path)), q, P, ttl="1 hour"), lambda b, i: b.withColumn("batch", F.lit(i)).write.mode("append").parquet(out), "ttl-state")
    rows = spark.read.parquet(out).orderBy("batch").collect()
    assert [r.n for r in rows if r.u == 2] == [1, 2, 3]
    assert [r.n for r in rows if r.u == 1] == [1, 0]  # forgotten once the watermark is an hour past its last rating


def test_runs_side_by_side_equal_runs_alone(spark, hours):
    import threading

    fit, test = hash_split(hours)
    met = threading.Barrier(2)

    def run(algo, wait=lambda: None):
        wait()
        return [(t["epoch"], t["virtual_s"], t["rmse_train"], t["rmse_test"]) for t in train(fit, P, algo, 2, 1, test=test, measure="test").trace]

    both = at_once(spark, [lambda x=a: run(x, lambda: met.wait(30)) for a in ("narrow_only", "hybrid_full")])
    assert both == [run("narrow_only"), run("hybrid_full")]
    assert all(t[2] is None and t[3] > 0 for x in both for t in x)
    with pytest.raises(ZeroDivisionError):
        at_once(spark, [lambda: 1 / 0, lambda: 1])
