"""Training: algorithms by name, from ratings to a model and a trace.

algo: 'narrow_only', 'wide_only', 'hybrid_uniform' (uniform grid, any lane takes any block), 'strata' (fixed diagonals), 'hybrid_linear' and
'hybrid_model' (two regions, no stealing, share from lines or from the piecewise model), 'hybrid_full' (two regions, stealing),
'deque' and 'history' (dynamic baselines).
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockmf.operators.executor import pin_ratings, run_rounds, write_state
from blockmf.operators.factors import init_factors
from blockmf.operators.measures import rmse
from blockmf.operators.params import FixedEpochs, MFParams, Stop
from blockmf.plans import grid as g
from blockmf.plans.balance import balance, balance_lines, per_block
from blockmf.plans.costmodel import cost_of
from blockmf.plans.rounds import compile_rounds
from blockmf.plans.scheduler import Cost, Policy, Visit, lanes_of, makespan, simulate, speeds
from blockmf.session import remove

UNIFORM = {"narrow_only", "wide_only", "hybrid_uniform", "strata", "deque"}


@dataclass
class Plan:
    """A schedule and its layout: what run() needs, and what measures read."""

    assigned: DataFrame
    rows: list[g.Stripe]
    cols: list[g.Stripe]
    nnz: dict[tuple[int, int], int]
    groups: tuple[tuple[int, ...], ...]
    passes: list[list[Visit]]
    rounds: list[list[int]]
    alpha: float | None = None
    makespan: float = 0.0


@dataclass
class Run:
    factors: DataFrame
    trace: list[dict] = field(default_factory=list)
    plan: Plan | None = None


def as_cost(cost: Cost | DataFrame | None) -> Cost:
    """A cost function as it is, from a table of fits, or of the default speeds."""
    return speeds() if cost is None else cost_of(cost) if isinstance(cost, DataFrame) else cost


def share(algo: str, cost: Cost, nnz: int, n: int, w: int, lines: dict[str, tuple[float, float]] | None = None, evaluate: str = "block") -> float:
    """alpha for an algorithm of two regions.

    'hybrid_linear' fits straight lines to the times of disjoint parts (of nnz / 2, nnz / 4, ... nnz / 2^8 ratings) and takes them for the whole share; the others bisect
    the cost model, evaluated 'block' by block as the visits of a share will be (each kind's share in blocks of its grid), or on the 'whole' share."""
    if algo == "hybrid_linear" and n and w:
        if lines is None:
            x = np.array([max(1.0, nnz / 2**i) for i in range(1, 9)])
            lines = {kind: tuple(map(float, np.polyfit(x, [cost(kind, s) for s in x], 1))) for kind in ("narrow", "wide")}
        return balance_lines(lines["wide"], lines["narrow"], nnz, n, w)
    time_of = {kind: (lambda s, k=kind: cost(k, s)) for kind in ("narrow", "wide")}
    if evaluate == "block" and n and w:
        grid = g.final_grid(n, w, algo in ("hybrid_full", "history"))
        time_of = {"wide": per_block(time_of["wide"], grid.cols * grid.wide_rows), "narrow": per_block(time_of["narrow"], grid.cols * grid.narrow_rows)}
    return balance(time_of["wide"], time_of["narrow"], nnz, n, w)


def policy_of(algo: str, steal: str = "auto", tie: str = "hash", seed: int = 0, lookahead: bool = True) -> Policy:
    name = {"strata": "strata", "deque": "deque", "hybrid_linear": "static", "hybrid_model": "static", "hybrid_full": "static+steal", "history": "static+steal"}.get(algo, "greedy")
    return Policy(name, steal=steal, tie=tie, seed=seed, lookahead=lookahead and name.startswith("static"))


def block_counts(assigned: DataFrame) -> dict[tuple[int, int], int]:
    """Ratings per (row stripe, column stripe): metadata, one row per block."""
    return {(r["row_key"], r["bj"]): r["count"] for r in assigned.groupBy("row_key", "bj").count().collect()}


def plan(ratings: DataFrame, algo: str = "hybrid_full", n: int = 3, w: int = 1, cost: Cost | DataFrame | None = None, epochs: int = 2, seed: int = 0, tie: str = "hash", steal: str = "auto", by: str = "nnz", grid: tuple[int, int] | None = None, alpha: float | None = None, lookahead: bool = True, weights: str = "nnz", block_ratings: int = 1 << 24, search: list[tuple[int, int]] | None = None, counts: g.Counts | None = None) -> Plan:
    """A schedule for all passes. block_ratings: most ratings of a mean block; the grid gets finer until that holds, whatever the lanes need.
    weights: the clock charges a block by its ratings ('nnz'), or all blocks the same ('equal'), so that the schedule does not depend on the data.
    cost: a function, or a table of fits as estimate_costs() makes it. lookahead: wide lanes reserve the column of their next block."""
    cost = as_cost(cost)
    ratings = g.placed(ratings, seed)
    if algo == "narrow_only":
        w = 0
    elif algo == "wide_only":
        n = 0
    lanes = lanes_of(n, w)
    counts = counts or g.id_counts(ratings)
    total = counts.total
    if algo == "wide_only" and grid is None:  # the numbers of rows and columns are searched, the least makespan of a pass is kept
        tries = {s: plan(ratings.select("u", "v", "r"), algo, 0, w, cost, 1, seed, tie, steal, by, s, None, lookahead, weights, block_ratings, None, counts).makespan for s in search or [(w + 1, w), (2 * w + 1, 2 * w), (4 * w + 1, 4 * w)]}
        grid = min(tries, key=tries.get)
    policy = policy_of(algo, steal, tie, seed or 0, lookahead)
    if algo in UNIFORM:
        r, c = grid or ((n + w, n + w) if algo == "strata" else g.min_grid(n, w))
        finer = g.finer_for(total, r * c, block_ratings)
        r, c = r * finer, c * finer
        rows, cols = g.uniform_grid(ratings, r, c, by, counts)
        assigned = g.assign_blocks(ratings, rows, cols).withColumn("row_key", F.col("bi"))
        groups: tuple = ()
        alpha = None
    else:
        steals = algo in ("hybrid_full", "history")
        if alpha is None:
            alpha = share(algo, cost, total, n, w)
        shape, rows, cols = g.region_grid(ratings, alpha, n, w, steals, by, block_ratings, counts)
        assigned = g.assign_region_blocks(ratings, shape, rows, cols)
        n_wide = sum(s.region == "wide" for s in rows)
        groups = tuple(tuple(range(i, i + shape.sub)) for i in range(0, n_wide, shape.sub))
        if not n_wide or n_wide == len(rows):  # one region only
            policy, groups = replace(policy, name="greedy"), ()
    nnz = counts.once(("blocks", tuple(rows), tuple(cols)), lambda: block_counts(assigned))
    full = {(i, j): nnz.get((i, j), 0) for i in range(len(rows)) for j in range(len(cols))}
    clocked = full if weights == "nnz" else dict.fromkeys(full, 1)
    passes = [[replace(v, nnz=sum(full[r, v.col] for r in v.rows)) for v in visits] for visits in schedule(clocked, lanes, cost, policy, epochs, groups)]
    return Plan(assigned, rows, cols, full, groups, passes, [compile_rounds(v) for v in passes], alpha, sum(map(makespan, passes)))


def schedule(nnz: dict, lanes: list, cost: Cost, policy: Policy, epochs: int, groups: tuple) -> list[list[Visit]]:
    """Visits of each pass. Each pass is scheduled for itself: there is a synchronisation point between passes."""
    policy = resolved(policy, nnz, lanes, cost, groups)
    return [simulate(nnz, lanes, cost, replace(policy, seed=policy.seed + e), 1, groups) for e in range(epochs)]


def initial_state(ratings: DataFrame, p: Plan, params: MFParams, seed: int, start: str = "closed") -> DataFrame:
    factors = init_factors(ratings, params.k, params.seed, params.scale, start)
    placed = g.placed(factors.withColumn("u", F.col("id")).withColumn("v", F.col("id")), seed)
    stripe = F.when(F.col("side") == "p", g.stripe_of(F.col("pu"), p.rows)).otherwise(g.stripe_of(F.col("pv"), p.cols))
    return placed.select("side", "id", stripe.cast("int").alias("stripe"), "vec")


def train(ratings: DataFrame, params: MFParams, algo: str = "hybrid_full", n: int = 3, w: int = 1, cost: Cost | DataFrame | None = None, test: DataFrame | None = None, stop: Stop | None = None, seed: int = 0, start: str = "closed", order: str = "hash", measure: bool | str = True, **options) -> Run:
    """Plan, lay out, run pass by pass, measure after each pass until the stop rule holds. measure: False, or 'test' to leave out the training error."""
    if algo == "history":
        return _train_history(ratings, params, n, w, cost, test, seed, start, order, **options)
    p = plan(ratings, algo, n, w, cost, params.epochs, seed, **options)
    stop = stop or FixedEpochs(params.epochs)
    spark = ratings.sparkSession
    pinned = pin_ratings(p.assigned, order)
    state, path = write_state(initial_state(ratings, p, params, seed, start))
    trace: list[dict] = []
    began, virtual = time.perf_counter(), 0.0
    for e, (visits, rounds) in enumerate(zip(p.passes, p.rounds, strict=True)):
        state, path = _pass(pinned, state, path, visits, rounds, params)
        virtual += makespan(visits)
        row = {"algo": algo, "epoch": e + 1, "visits": len(visits), "rounds": max(rounds) + 1, "wall_s": time.perf_counter() - began, "virtual_s": virtual, "rmse_train": None, "rmse_test": None}
        if measure:
            if measure != "test" or test is None:
                row["rmse_train"] = rmse(ratings, state).first()["rmse"]
            row["rmse_test"] = rmse(test, state).first()["rmse"] if test is not None else row["rmse_train"]
        trace.append(row)
        if stop(trace):
            break
    pinned.remove(spark)
    return Run(state.select("side", "id", "vec"), trace, p)


def _pass(pinned, state: DataFrame, path: str, visits: list[Visit], rounds: list[int], params: MFParams) -> tuple[DataFrame, str]:
    """One pass; the factors before it are deleted once those after it are written."""
    after, kept = run_rounds(pinned, state, visits, rounds, params)
    written = write_state(after)
    for frame in kept:
        frame.unpersist()
    remove(state.sparkSession, path)
    return written


def _train_history(ratings, params, n, w, cost, test, seed, start, order, guess: float = 0.5, **options) -> Run:
    """The share of each pass follows from the speeds seen in the pass before."""
    cost, spark = as_cost(cost), ratings.sparkSession
    alpha, factors, trace, last, virtual, began = guess, None, [], None, 0.0, time.perf_counter()
    for e in range(params.epochs):
        last = plan(ratings, "hybrid_full", n, w, cost, 1, seed, alpha=alpha, **options)
        pinned = pin_ratings(last.assigned, order)
        if factors is None:
            first = initial_state(ratings, last, params, seed, start)
        else:
            again = g.placed(factors.withColumn("u", F.col("id")).withColumn("v", F.col("id")), seed)
            stripe = F.when(F.col("side") == "p", g.stripe_of(F.col("pu"), last.rows)).otherwise(g.stripe_of(F.col("pv"), last.cols))
            first = again.select("side", "id", stripe.cast("int").alias("stripe"), "vec")
        state, _ = _pass(pinned, *write_state(first), last.passes[0], last.rounds[0], params)
        pinned.remove(spark)
        factors = state.select("side", "id", "vec")
        score = rmse(test if test is not None else ratings, factors).first()["rmse"]
        virtual += makespan(last.passes[0])
        trace.append({"algo": "history", "epoch": e + 1, "visits": len(last.passes[0]), "rounds": max(last.rounds[0]) + 1, "wall_s": time.perf_counter() - began, "virtual_s": virtual, "rmse_train": score, "rmse_test": score})
        alpha = history_share(last.passes[0], n, w, alpha)
    return Run(factors, trace, last)


def history_share(visits: list[Visit], n: int, w: int, before: float) -> float:
    """Next share in proportion to the measured speeds of both kinds."""
    speed = {}
    for kind, lanes in (("narrow", n), ("wide", w)):
        mine = [v for v in visits if v.kind == kind]
        busy = sum(v.t_end - v.t_start for v in mine)
        speed[kind] = lanes * sum(v.nnz for v in mine) / busy if busy else 0.0
    total = sum(speed.values())
    return speed["wide"] / total if total else before


def trace_frame(spark, traces: list[dict]) -> DataFrame:
    rows = [(t["algo"], t["epoch"], t["visits"], t["rounds"], t["wall_s"], t["virtual_s"], t["rmse_train"], t["rmse_test"]) for t in traces]
    return spark.createDataFrame(rows, "algo string, epoch int, visits int, rounds int, wall_s double, virtual_s double, rmse_train double, rmse_test double")


def serial_equivalent(p: Plan) -> list[tuple[int, int, str]]:
    """(row stripe, column stripe, kind) in an order of single blocks whose serial run gives the same factors."""
    out = []
    for visits, rounds in zip(p.passes, p.rounds, strict=True):
        for _, v in sorted(zip(rounds, visits, strict=True), key=lambda x: (x[0], x[1].visit)):
            out += [(r, v.col, v.kind) for r in v.rows]
    return out


def resolved(policy: Policy, nnz: dict, lanes: list, cost: Cost, groups: tuple) -> Policy:
    """With steal = 'auto', the policy (no stealing, or one of the ways to steal) that makes the first pass shortest; it then holds for all passes."""
    if policy.name != "static+steal" or policy.steal != "auto":
        return policy
    tries = [replace(policy, name="static", steal="none")] + [replace(policy, steal=x) for x in ("both", "wide", "narrow", "dominant", "guarded")]
    return min(tries, key=lambda x: makespan(simulate(nnz, lanes, cost, x, 1, groups)))


def next_width(sizes: list[int], cost: Cost) -> int:
    """Least block size at which a wide lane's speed is within 2 % of its best among the sizes."""
    best = max(s / cost("wide", s) for s in sizes)
    return min(s for s in sizes if s / cost("wide", s) >= 0.98 * best)


#: Ratings per second of the published machine, from the seconds to a common error on DS3 (33 s with 16 narrow lanes; 170, 48 and 23 s
#: with a wide lane of 32, 128 and 512), times the passes that the whole method needs there (20 s to the target; 20 passes in 10.58 s).
DS3_RATINGS, DS3_PASSES = 104_215_016, 20 * 20 / 10.58
NARROW_RATE = DS3_RATINGS * DS3_PASSES / 33 / 16
WIDE_RATES = {32: DS3_RATINGS * DS3_PASSES / 170, 128: DS3_RATINGS * DS3_PASSES / 48, 512: DS3_RATINGS * DS3_PASSES / 23}
#: The wide lane's curve: speed grows with the logarithm of the block up to FULL ratings, from none at START (a tenth at least).
START, FULL = 1 << 12, 1 << 22


def wide_rate(width: int) -> float:
    """Full speed of a wide lane of a width, between the published ones by powers."""
    known = sorted(WIDE_RATES)
    return float(np.exp(np.interp(math.log(width), [math.log(x) for x in known], [math.log(WIDE_RATES[x]) for x in known])))


def published_lanes(width: int, stands_for: float = 1.0) -> Cost:
    """Seconds of a block on the published machine, where each rating of the block stands for `stands_for` ratings. One device for all workloads: narrow lanes
    steady, wide lanes saturating."""
    full = wide_rate(width)

    def cost(kind: str, nnz: float) -> float:
        size = nnz * stands_for
        if kind == "narrow" or size <= 0:
            return max(0.0, size) / NARROW_RATE
        return size / (full * min(1.0, max(0.1, math.log(size / START) / math.log(FULL / START))))

    return cost
