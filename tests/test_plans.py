"""Grid rules, schedules, rounds, cost models, shares."""

import itertools
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from blockmf.operators.train import NARROW_RATE, WIDE_RATES, history_share, published_lanes, resolved, share
from blockmf.plans import balance as bal
from blockmf.plans import costmodel as cm
from blockmf.plans import grid as g
from blockmf.plans.rounds import compile_rounds, independent
from blockmf.plans.scheduler import Policy, _Clock, lanes_of, makespan, simulate, speeds


def even(rows, cols, n=1000):
    return {(i, j): n + (i * 37 + j * 11) % 29 for i in range(rows) for j in range(cols)}


def test_grid_rules():
    assert g.min_grid(16, 1) == (18, 17) and g.min_grid(16, 1, "square_plus_one") == (18, 18)
    assert g.final_grid(4, 2) == g.FinalGrid(9, 2, 3, 6)
    assert g.final_grid(16, 1) == g.FinalGrid(19, 1, 17, 17)
    assert g.final_grid(4, 2, steal=False) == g.FinalGrid(9, 2, 1, 4)
    assert g.final_grid(3, 0) == g.FinalGrid(4, 0, 1, 3) and g.final_grid(0, 2).narrow_rows == 0


def test_running_example_concentrates_on_one_row():
    nnz = {(i, j): 1000 for i in range(3) for j in range(4)}
    v = simulate(nnz, lanes_of(2, 1), speeds(1, 10), Policy("greedy", count="visits", tie="index"), passes=6)
    assert [(x.rows[0], x.col) for x in v[:3]] == [(0, 0), (1, 1), (2, 2)]
    early = [(x.rows[0], x.col) for x in v if x.kind == "wide" and x.t_start < 950]
    assert {r for r, _ in early} == {2} and {c for _, c in early} == {2, 3}


@pytest.mark.parametrize("n", range(2, 8))
def test_square_grid_starves_and_one_more_row_does_not(n):
    lanes = lanes_of(n - 1, 1)
    policy = Policy("greedy", count="visits", tie="index")
    square = simulate(even(n, n), lanes, speeds(1, 10.3), policy, passes=10)
    assert len({(x.rows[0], x.col) for x in square}) == n
    spare = simulate(even(n + 1, n), lanes, speeds(1, 10.3), policy, passes=40)
    assert len({(x.rows[0], x.col) for x in spare}) == (n + 1) * n


def overlapping(visits):
    return [(a, b) for a, b in itertools.combinations(visits, 2) if a.t_start < b.t_end - 1e-12 and b.t_start < a.t_end - 1e-12 and not independent(a, b)]


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 4), st.integers(1, 3), st.floats(1, 20), st.integers(0, 10**6), st.sampled_from(["both", "wide", "narrow", "dominant", "guarded", "auto"]), st.booleans())
def test_full_schedules_are_conflict_free_and_complete(n, w, speed, seed, steal, lookahead):
    f = g.final_grid(n, w)
    wide = w * f.sub
    r = random.Random(seed)
    nnz = {(i, j): r.randrange(1, 400) for i in range(wide + f.narrow_rows) for j in range(f.cols)}
    groups = tuple(tuple(range(i, i + f.sub)) for i in range(0, wide, f.sub))
    v = simulate(nnz, lanes_of(n, w), speeds(1, speed), Policy("static+steal", steal, seed=seed, lookahead=lookahead), 2, groups)
    assert not overlapping(v)
    count = {}
    for x in v:
        for row in x.rows:
            count[(row, x.col)] = count.get((row, x.col), 0) + 1
    assert set(count) == set(nnz) and set(count.values()) == {2}
    rounds = compile_rounds(v)
    for k in set(rounds):
        assert all(independent(a, b) for a, b in itertools.combinations([x for x, y in zip(v, rounds, strict=True) if y == k], 2))
    order = {x.visit: k for x, k in zip(v, rounds, strict=True)}
    for a, b in itertools.combinations(v, 2):
        if not independent(a, b):
            assert (order[a.visit] < order[b.visit]) == (a.t_start < b.t_start)


def test_auto_is_never_slower_than_static():
    r = random.Random(8)
    for _ in range(10):
        nnz = {(i, j): r.randrange(50, 900) for i in range(6) for j in range(5)}
        run = lambda name, steal: makespan(simulate(nnz, lanes_of(2, 1), speeds(1, 6), Policy(name, steal), 2, ((0, 1, 2),)))  # noqa: E731, B023
        assert run("static+steal", "auto") <= run("static", "none") + 1e-9


@pytest.mark.parametrize(("n", "w"), [(4, 2), (3, 1), (4, 1)])
def test_column_rule_is_sharp(n, w):
    """With n + 2 w + 1 columns look-ahead never fails; with two fewer it does."""
    def failures(cols):
        sub = -(-(n + w) // w)
        nnz = {(i, j): 200 + (i * 11 + j * 29) % 40 for i in range(w * sub + n + w) for j in range(cols)}
        groups = tuple(tuple(range(i, i + sub)) for i in range(0, w * sub, sub))
        clock = _Clock(nnz, lanes_of(n, w), speeds(1, 9), Policy("static", count="visits", lookahead=True), 8, groups)
        clock.run()
        return clock.failed_lookahead

    assert failures(n + 2 * w + 1) == 0
    assert failures(n + 2 * w - 1) > 0


def test_deque_and_strata():
    nnz = {(i, j): 100 * (1 + i * 4 + j) for i in range(5) for j in range(4)}
    v = simulate(nnz, lanes_of(1, 1), speeds(1, 4), Policy("deque"))
    assert v[0].nnz == 100 and v[1].nnz == max(nnz.values())
    s = simulate({(i, j): 10 for i in range(3) for j in range(3)}, lanes_of(3, 0), speeds(), Policy("strata"))
    assert sorted((k, x.rows[0], x.col) for x, k in zip(s, compile_rounds(s), strict=True)) == sorted((k, i, (i + k) % 3) for k in range(3) for i in range(3))


def test_history_share_follows_speed():
    v = simulate(even(4, 3), lanes_of(2, 1), speeds(1, 6), Policy("greedy"))
    assert history_share(v, 2, 1, 0.5) == pytest.approx(6 / 8)


def test_fits_recover_the_device(spark):
    probe = cm.device_probe(spark, "saturating", noise=0.01)
    tau = {(r.kind, r.stage): r.tau for r in cm.find_tau(probe).collect()}
    assert tau[("wide", "kernel")] == 2**20 and tau[("wide", "to")] == 2**18
    fit = {(r.kind, r.stage): r for r in cm.fit_piecewise(probe.where("kind = 'wide'"), "log").collect()}
    k = fit[("wide", "kernel")]
    assert k.a == pytest.approx(1e6, rel=0.01) and k.b == pytest.approx(-6e6, rel=0.01)
    model = cm.models(cm.fit_piecewise(probe.where("kind = 'wide' and stage = 'kernel'"), "log"))[("wide", "kernel")]
    for r in cm.average(probe.where("kind = 'wide' and stage = 'kernel'")).collect():
        assert model(r.size) == pytest.approx(r.seconds, rel=0.02)
    sizes = [2**i for i in range(8, 26)]
    assert all(model(a) <= model(b) + 1e-12 for a, b in itertools.pairwise(sizes))


def test_combine_and_balance():
    to, kernel, back = (lambda s: 3e-7 * s), (lambda s: 1e-7 * s), (lambda s: 1e-8 * s)
    assert cm.combine(to, kernel)(100) == cm.combine(to, kernel, back, "max3")(100) == pytest.approx(3e-5)
    assert cm.combine(to, kernel, back, "sum")(100) == pytest.approx(4.1e-5)
    w, n = (lambda s: 2e-7 * s + 0.01), (lambda s: 1e-6 * s)
    a = bal.balance(w, n, 1e7, 4, 2)
    assert a == pytest.approx(bal.balance_lines((2e-7, 0.01), (1e-6, 0), 1e7, 4, 2), abs=1e-9)
    best = bal.total_time(w, n, 1e7, a, 4, 2)
    assert all(best <= bal.total_time(w, n, 1e7, i / 200, 4, 2) + 1e-9 for i in range(201))
    assert bal.balance(w, n, 1e7, 4, 0) == 0 and bal.balance(w, n, 1e7, 0, 2) == 1
    s = lambda x: 2e-4 + x * 1e-8
    assert bal.balance(bal.per_block(s, 1000), n, 1e7, 4, 1) < bal.balance(s, n, 1e7, 4, 1)


def test_wider_lanes_are_faster_and_need_larger_blocks():
    narrow, wide = published_lanes(32), published_lanes(512)
    assert wide("wide", 10**6) < narrow("wide", 10**6) and wide("narrow", 1000) == narrow("narrow", 1000)
    for width, rate in WIDE_RATES.items():
        assert 1e8 / published_lanes(width)("wide", 1e8) == pytest.approx(rate)
    assert published_lanes(128, 50)("wide", 10**4) == published_lanes(128)("wide", 5 * 10**5)
    assert published_lanes(128)("narrow", 1e6) == pytest.approx(1e6 / NARROW_RATE)
    times = [published_lanes(128)("wide", 2**i) for i in range(30)]
    assert times == sorted(times)


def test_blocks_fit_their_budget(spark):
    r = g.placed(spark.range(20_000).selectExpr("id % 1000 as u", "(id * 7) % 1999 as v", "1.0D as r"), 0)
    for steal in (True, False):
        shape, rows, cols = g.region_grid(r, 0.4, 3, 1, steal, budget=200)
        a = g.assign_region_blocks(r, shape, rows, cols)
        mean = {x.region: x.m for x in a.groupBy("region", "bi", "bj").count().groupBy("region").agg({"count": "avg"}).withColumnRenamed("avg(count)", "m").collect()}
        assert all(m <= 210 for m in mean.values()) and len(mean) == 2
        small, _, _ = g.region_grid(r, 0.4, 3, 1, steal, budget=10**9)
        assert small == g.final_grid(3, 1, steal)
    assert g.finer_for(10**6, 100, 10**9) == 1 and g.finer_for(10**6, 100, 100) == 10


def test_more_wide_rows_than_wide_lanes():
    f = g.final_grid(3, 2, True, 2)
    wide = f.wide_rows * f.sub
    groups = tuple(tuple(range(i, i + f.sub)) for i in range(0, wide, f.sub))
    nnz = even(wide + f.narrow_rows, f.cols)
    for name, steal in (("static", "none"), ("static+steal", "auto")):
        policy = resolved(Policy(name, steal, lookahead=True), nnz, lanes_of(3, 2), speeds(1, 5), groups)
        v = simulate(nnz, lanes_of(3, 2), speeds(1, 5), policy, 1, groups)
        assert sorted((r, x.col) for x in v for r in x.rows) == sorted(nnz)


def test_share_sees_saturation_block_by_block():
    cost = published_lanes(128)
    own, whole, line = share("hybrid_model", cost, 10**6, 16, 1), share("hybrid_model", cost, 10**6, 16, 1, evaluate="whole"), share("hybrid_linear", cost, 10**6, 16, 1)
    assert own < whole and own < line  # small blocks do not fill a wide lane


def test_offline_model_on_the_data(spark):
    from blockmf.operators.params import MFParams
    from blockmf.sources.tables import rating_view

    r = rating_view(spark, "/root/testdata/sf0.001", "cust_part")
    fit = cm.estimate_costs(r, MFParams(k=8), sizes=(256, 512, 1024, 2048, 4096), repeats=2)
    assert {(x.kind, x.stage) for x in fit.collect()} == {("narrow", "kernel"), ("wide", "kernel"), ("wide", "to"), ("wide", "from")}
    cost = cm.cost_of(fit)
    assert 0 < cost("wide", 1000) <= cost("wide", 100_000) and 0 <= share("hybrid_full", cost, 10**6, 4, 1) <= 1


def test_a_threshold_at_the_first_size_gives_a_steady_speed(spark):
    rows = [("wide", "kernel", 100 * 2**i, 0, 100 * 2**i / 50.0) for i in range(4)]
    model = cm.models(cm.fit_piecewise(spark.createDataFrame(rows, cm.PROBE), "log"))["wide", "kernel"]
    assert [model(s) for s in (50, 100, 400, 10**4)] == pytest.approx([1.0, 2.0, 8.0, 200.0])


def test_plans_on_the_same_counts_count_their_blocks_once(spark, monkeypatch):
    """Wide lanes of any width have the same grids to choose from; stripes of a kept prefix sum are those of a fresh one."""
    from blockmf.operators import train as t

    asked, count = [], t.block_counts
    monkeypatch.setattr(t, "block_counts", lambda assigned: asked.append(1) or count(assigned))
    r = spark.range(6_000).selectExpr("id % 500 as u", "(id * 7) % 601 as v", "1.0D as r").cache()
    counts = g.id_counts(g.placed(r, 0))
    plans = [t.plan(r, "wide_only", 0, 1, published_lanes(width, 1000), 1, counts=counts) for width in (32, 128, 512)]
    assert len(asked) == 3 and len({p.makespan for p in plans}) == 3
    assert all(sum(p.nnz.values()) == 6_000 for p in plans) and plans[0].nnz == count(plans[0].assigned)
    border, wide, total = g.split_regions(None, 0.6, counts)
    part = counts[0].where(f"pu >= {border}").select("pu", "n")
    assert counts.stripes("row", 4, "narrow", wide, total) == g.balanced_stripes(part, "row", "pu", 4, "narrow")
    assert counts.total == total == 6_000 and 0 < wide <= 3_600
