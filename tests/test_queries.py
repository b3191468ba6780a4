"""Queries against their SQL on the smallest tables."""

import sys
from pathlib import Path

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.errors import AnalysisException

from blockmf.queries import all_queries, all_sql
from blockmf.sources.tables import TABLES

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def rows(frame: pd.DataFrame) -> list:
    def plain(v):
        if v is None or v is pd.NaT or v is pd.NA or isinstance(v, float) and v != v:
            return "null"
        return repr(float(v)) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    cols = sorted(frame.columns)
    return sorted(tuple(plain(v) for v in r) for r in frame[cols].astype(object).values.tolist())


@pytest.mark.parametrize("name", sorted(k for k in all_sql()))
def test_query_equals_sql(spark, duck, name):
    got, want = all_queries()[name](spark, SF).toPandas(), duck.sql(all_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


FROM_TABLES = ["base_classifier", *(f"cost_alpha_{x}" for x in ("edges", "grid", "linear", "methods", "saturating")), *(f"cost_combine_{h}_{d}" for h in ("max", "sum", "max3") for d in ("kernel_bound", "transfer_bound"))]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_query_reads_a_table(spark, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        all_queries()[name](spark, "/tmp/no-such-tables").collect()


def test_online_steps_over_all_events_are_serial(spark):
    """The whole stream against one loop over the events."""
    from blockmf.operators.factors import init_vector
    from blockmf.queries.streams import P1

    events = pd.read_parquet(f"{SF}/events.parquet").sort_values("event_id")
    sides = {"p": events["user_id"].tolist(), "q": events["ts"].dt.hour.tolist()}
    vec = {(s, i): init_vector(s, np.array([i]), P1.k, P1.seed, P1.scale)[0] for s, ids in sides.items() for i in set(ids)}
    g = P1.gamma * P1.grad_scale
    for u, v, value in zip(sides["p"], sides["q"], events["value"], strict=True):
        p, q = vec["p", u], vec["q", v]
        e = value / 20 - p @ q
        new_p = p + g * (e * q - P1.lam_p * p)
        vec["p", u], vec["q", v] = new_p, q + g * (e * (new_p if P1.q_sees == "new_p" else p) - P1.lam_q * q)
    got = {(r.side, r.id, r.pos): r.value for r in all_queries()["stream_online_sgd_all"](spark, SF).collect()}
    assert {k[:2] for k in got} == set(vec)
    assert got == pytest.approx({(*k, j): x for k, m in vec.items() for j, x in enumerate(m)}, abs=2e-6)


def test_workloads_report_what_the_schedules_say(spark):
    """The hybrid is ahead of either kind alone, wide lanes gain with their width, narrow lanes with their number; update counts are more even in two regions."""
    q = all_queries()
    gains = {r.setting: r for r in q["w4_gains"](spark, SF).collect()}
    assert sorted(gains) == [32, 64, 128, 256, 512] and gains[512].over_narrow > gains[32].over_narrow and gains[512].over_wide < gains[32].over_wide
    assert all(g.over_narrow > 1 for g in gains.values())
    skew = {r.algo: r for r in q["w7_grid_skew"](spark, SF).collect()}
    assert skew["hybrid_full"].cv < skew["hybrid_uniform"].cv
    shares = {(r.stands_for, r.algo): r for r in q["w8_cost_models"](spark, SF).collect()}
    assert len(shares) == 8 and shares["DS1", "hybrid_model"].wide_share < shares["DS1", "hybrid_linear"].wide_share
    assert all(r.seconds_20 > 0 for r in shares.values())


def test_views_are_planned_while_the_real_runs_go_on(spark, monkeypatch):
    import threading

    from blockmf.queries import workloads as w

    met = threading.Barrier(3)
    monkeypatch.setattr(w, "_passes_to_target", lambda spark, sf_dir: met.wait(30) >= 0 and {"narrow_only": 2, "wide_only": 3, "hybrid_full": 4})
    monkeypatch.setattr(w, "_plans", lambda spark, sf_dir, view, settings, algos: met.wait(30) >= 0 and [(view, a, s[0], 0.5, None) for s in settings for a in algos])
    got = {(r.view, r.algo, r.setting): (r.passes, r.target_s) for r in w.w5_vary_lanes(spark, SF).collect()}
    assert len(got) == 24 and got["planted", "hybrid_full", 16] == (4, 2.0) and got["cust_part", "narrow_only", 4] == (2, 1.0)


def test_entry_and_registry(spark):
    sys.path.insert(0, str(Path(__file__).resolve().parent.parent))
    import __spark_entry__ as e

    assert e.entry(spark).count() == 2
    assert set(e.oracle_sql()) <= set(e.queries())
