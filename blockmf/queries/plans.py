"""Grids, schedules, cost models and shares."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.functions.ids import dense_codes, mixed, permuted, prefix_sum
from blockmf.operators import measures
from blockmf.operators.train import plan
from blockmf.plans import balance as bal
from blockmf.plans import costmodel as cm
from blockmf.plans import grid as g
from blockmf.plans.rounds import compile_rounds
from blockmf.plans.scheduler import Policy, lanes_of, makespan, schedule_frame, simulate, speeds
from blockmf.sources.tables import rating_view, view_sql

QUERIES, SQL = {}, {}
CP = view_sql("cust_part")


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


def rows(spark: SparkSession, data: list[tuple], ddl: str) -> DataFrame:
    return spark.createDataFrame(data, ddl)


_NW = [(n, w) for n in (1, 2, 3, 4, 8, 16) for w in (1, 2, 4)]
_NW_SQL = "(VALUES " + ", ".join(f"({n}, {w})" for n, w in _NW) + ") t(n, w)"


@query(f"SELECT n, w, n + w + 1 AS n_rows, n + w AS n_cols, n + w + 1 AS strict_cols FROM {_NW_SQL}")
def grid_min_rule(spark, sf_dir):
    return rows(spark, [(n, w, *g.min_grid(n, w), g.min_grid(n, w, "square_plus_one")[1]) for n, w in _NW], "n int, w int, n_rows int, n_cols int, strict_cols int")


@query(f"SELECT n, w, n + 2 * w + 1 AS cols, w AS wide_rows, CAST(ceil((n + w) / w) AS INT) AS sub, n + w AS narrow_rows FROM {_NW_SQL}")
def grid_final(spark, sf_dir):
    return rows(spark, [(n, w, f.cols, f.wide_rows, f.sub, f.narrow_rows) for n, w in _NW for f in [g.final_grid(n, w)]], "n int, w int, cols int, wide_rows int, sub int, narrow_rows int")


@query("SELECT 9 AS cols, 2 AS wide_rows, 3 AS sub, 6 AS narrow_rows, round(1 / 18.0, 6) AS static_block, round(1 / 54.0, 6) AS dynamic_block")
def grid_final_4_2(spark, sf_dir):
    f = g.final_grid(4, 2)
    return rows(spark, [(f.cols, f.wide_rows, f.sub, f.narrow_rows, round(1 / (f.wide_rows * f.cols), 6), round(1 / (f.wide_rows * f.sub * f.cols), 6))], "cols int, wide_rows int, sub int, narrow_rows int, static_block double, dynamic_block double")


_ASSIGNED = f"""WITH r AS ({CP}), d AS (SELECT min(u) AS u0, max(u) - min(u) + 1 AS nu, min(v) AS v0, max(v) - min(v) + 1 AS nv FROM r),
ru AS (SELECT u, (SELECT max(i) FROM range(4) t(i) WHERE u0 + nu * i // 4 <= u) AS bi FROM (SELECT DISTINCT u FROM r), d),
rv AS (SELECT v, (SELECT max(i) FROM range(3) t(i) WHERE v0 + nv * i // 3 <= v) AS bj FROM (SELECT DISTINCT v FROM r), d),
a AS (SELECT u, v, CAST(bi AS INT) AS bi, CAST(bj AS INT) AS bj FROM r JOIN ru USING (u) JOIN rv USING (v))"""


def _assigned(spark, sf_dir, by="ids", seed=None):
    r = g.placed(rating_view(spark, sf_dir, "cust_part"), seed)
    return g.assign_blocks(r, *g.uniform_grid(r, 4, 3, by))


@query(_ASSIGNED + " SELECT u, v, bi, bj FROM a")
def grid_assign(spark, sf_dir):
    return _assigned(spark, sf_dir).select("u", "v", "bi", "bj")


@query(_ASSIGNED + " SELECT bi, bj, count(*) AS nnz, count(DISTINCT u) AS n_rows, count(DISTINCT v) AS n_cols, count(*) * 24 AS bytes FROM a GROUP BY bi, bj")
def grid_stats(spark, sf_dir):
    return g.block_stats(_assigned(spark, sf_dir)).drop("region", "sub")


@query(f"SELECT 'row' AS axis, CAST(i AS INT) AS idx, lo + n * i // 4 AS lo, lo + n * (i + 1) // 4 AS hi FROM range(4) t(i), (SELECT min(u) AS lo, max(u) - min(u) + 1 AS n FROM ({CP}) x) y")
def grid_uniform_ids(spark, sf_dir):
    r = g.placed(rating_view(spark, sf_dir, "cust_part"), None)
    return g.stripes_frame(spark, g.uniform_grid(r, 4, 3)[0]).drop("region")


@query(f"""WITH c AS (SELECT v, count(*) AS n FROM ({CP}) x GROUP BY v), s AS (SELECT v, n, sum(n) OVER (ORDER BY v) - n AS before, sum(n) OVER () AS total FROM c)
SELECT CAST(least(floor(before * 6 / total), 5) AS INT) AS idx, sum(n) AS nnz, count(*) AS ids FROM s GROUP BY 1""")
def grid_uniform_nnz(spark, sf_dir):
    r = g.placed(rating_view(spark, sf_dir, "cust_part"), None)
    counts = r.groupBy("pv").agg(F.count(F.lit(1)).alias("n"))
    idx = g.stripe_of(F.col("pv"), g.balanced_stripes(counts, "col", "pv", 6))
    return counts.groupBy(idx.alias("idx")).agg(F.sum("n").alias("nnz"), F.count(F.lit(1)).alias("ids"))


@query("WITH b AS (SELECT i AS bi, j AS bj FROM range(4) t(i), range(3) s(j)) SELECT a.bi AS bi_a, a.bj AS bj_a, b.bi AS bi_b, b.bj AS bj_b, CASE WHEN a.bi = b.bi THEN 'row' ELSE 'column' END AS shares FROM b a JOIN b ON (a.bi = b.bi AND a.bj < b.bj) OR (a.bj = b.bj AND a.bi < b.bi)")
def grid_conflicts(spark, sf_dir):
    return g.conflict_pairs(spark.sql("SELECT i AS bi, j AS bj FROM range(4) t(i), range(3) s(j)"))


@query(f"""WITH c AS (SELECT u, count(*) AS n FROM ({CP}) x GROUP BY u), s AS (SELECT u, sum(n) OVER (ORDER BY u) AS cum, sum(n) OVER () AS total FROM c)
SELECT max(u) + 1 AS border, max(cum) AS wide, max(total) AS total FROM s WHERE cum <= 0.6 * total""")
def grid_regions(spark, sf_dir):
    r = g.placed(rating_view(spark, sf_dir, "cust_part"), None)
    return rows(spark, [g.split_regions(r, 0.6)], "border long, wide long, total long")


@query(f"SELECT count(*) AS nnz, CAST(6 AS BIGINT) AS rows_used, CAST(5 AS BIGINT) AS cols_used FROM ({CP}) x")
def grid_subrows(spark, sf_dir):
    """Two narrow lanes, one wide lane: every rating lies in one block of 3 + 3 row stripes and 5 columns, and all stripes are used."""
    r = g.placed(rating_view(spark, sf_dir, "cust_part"), 3)
    shape, rs, cs = g.region_grid(r, 0.5, 2, 1)
    a = g.assign_region_blocks(r, shape, rs, cs)
    return a.agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("row_key").alias("rows_used"), F.countDistinct("bj").alias("cols_used"))


@query(f"WITH i AS (SELECT DISTINCT u FROM ({CP}) x), h AS (SELECT u, {mixed('u', 5)} AS h FROM i) SELECT u, row_number() OVER (ORDER BY h, u) - 1 AS place FROM h")
def permute_ids(spark, sf_dir):
    return permuted(rating_view(spark, sf_dir, "cust_part"), "u", 5)


@query("SELECT event_type, dense_rank() OVER (ORDER BY event_type) - 1 AS code FROM (SELECT DISTINCT event_type FROM events) x")
def encode_types(spark, sf_dir):
    return dense_codes(spark.read.parquet(f"{sf_dir}/events.parquet"), "event_type")


@query("SELECT c_custkey, round(sum(c_acctbal) OVER (ORDER BY c_custkey), 2) AS cum FROM customer")
def running_sum(spark, sf_dir):
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_acctbal")
    return prefix_sum(c, ["c_custkey"], F.col("c_acctbal").cast("decimal(18,2)"), "cum").select("c_custkey", F.col("cum").cast("double").alias("cum"))


# --- schedules ------------------------------------------------------------------------------------------------------

_EVEN = {(i, j): 1000 for i in range(3) for j in range(4)}


def _table(visits) -> str:
    """A schedule as a table in SQL text: the oracle recomputes what a query reports about it."""
    rounds = compile_rounds(visits)
    rows = ", ".join(f"({v.visit}, {v.lane_id}, '{v.kind}', {r}, {v.col}, {v.nnz}, '{v.phase}', {v.t_start!r}, {v.t_end!r}, {k})" for v, k in zip(visits, rounds, strict=True) for r in v.rows)
    return f"s(visit, lane, kind, i, j, nnz, phase, t0, t1, round) AS (SELECT visit, lane, kind, i, j, nnz, phase, CAST(t0 AS DOUBLE), CAST(t1 AS DOUBLE), round FROM (VALUES {rows}) t(visit, lane, kind, i, j, nnz, phase, t0, t1, round))"


def _frame(spark, visits) -> DataFrame:
    return schedule_frame(spark, visits, compile_rounds(visits))


_RUN = simulate(_EVEN, lanes_of(2, 1), speeds(1, 10), Policy("greedy", count="visits", tie="index"), passes=6)


@query(f"WITH {_table(_RUN)} SELECT i AS \"row\", count(*) FILTER (kind = 'wide') AS wide_visits, count(*) FILTER (t0 < 2000) AS early_visits FROM s GROUP BY i")
def sched_running_example(spark, sf_dir):
    """3 x 4 grid, two narrow lanes and a wide lane ten times as fast: while narrow lanes hold their blocks the wide lane goes over one row again and again."""
    f = _frame(spark, _RUN)
    return f.groupBy("row").agg(F.count_if(F.col("kind") == "wide").alias("wide_visits"), F.count_if(F.col("t_start") < 2000).alias("early_visits"))


@query("SELECT i AS \"row\", i AS col FROM range(3) t(i)")
def sched_square_starvation(spark, sf_dir):
    """On an L x L grid a lane that is free again finds only the block that it had."""
    v = simulate({(i, j): 1000 for i in range(3) for j in range(3)}, lanes_of(2, 1), speeds(1, 10.3), Policy("greedy", count="visits", tie="index"), passes=20)
    return schedule_frame(spark, v).select(F.col("row").cast("long").alias("row"), F.col("col").cast("long").alias("col")).distinct()


@query("SELECT CAST(12 AS BIGINT) AS blocks")
def sched_spare_row(spark, sf_dir):
    """One row of blocks more than lanes: every block is visited."""
    v = simulate({(i, j): 1000 for i in range(4) for j in range(3)}, lanes_of(2, 1), speeds(1, 10.3), Policy("greedy", count="visits", tie="index"), passes=20)
    return schedule_frame(spark, v).select("row", "col").distinct().agg(F.count(F.lit(1)).alias("blocks"))


_GROUPS = ((0, 1, 2), (3, 4, 5))
_REGIONS = {(i, j): (400 if i < 6 else 300) + (i * 7 + j * 13) % 50 for i in range(12) for j in range(9)}


_GREEDY = simulate({(i, j): 500 + (i * 31 + j * 17) % 97 for i in range(7) for j in range(6)}, lanes_of(4, 2), speeds(1, 7), Policy("greedy"), passes=3)
_STEAL = simulate(_REGIONS, lanes_of(4, 2), speeds(1, 4), Policy("static+steal", "both", lookahead=True), passes=3, groups=_GROUPS)
_AUTO = simulate(_REGIONS, lanes_of(4, 2), speeds(1, 4), Policy("static+steal", "auto"), passes=3, groups=_GROUPS)
_CONFLICT_SQL = """ SELECT (SELECT count(*) FROM (SELECT DISTINCT visit FROM s) x) AS visits, (SELECT count(*) FROM s a JOIN s b ON a.visit < b.visit AND a.t0 < b.t1 - 1e-12 AND b.t0 < a.t1 - 1e-12 AND (a.i = b.i OR a.j = b.j)) AS conflicts,
(SELECT count(*) FROM s a JOIN s b ON a.visit < b.visit AND a.round = b.round AND (a.i = b.i OR a.j = b.j)) AS shared"""


def _conflicts(frame: DataFrame) -> DataFrame:
    """Visits; pairs of their rows that overlap in time, and that are in one round, and share a stripe."""
    a = frame.select(*[F.col(c).alias(f"a_{c}") for c in ("visit", "row", "col", "t_start", "t_end", "round")])
    b = frame.select(*[F.col(c).alias(f"b_{c}") for c in ("visit", "row", "col", "t_start", "t_end", "round")])
    first, met = F.expr("a_visit < b_visit"), []
    for same in ("row", "col"):
        met.append(a.join(b, (F.col(f"a_{same}") == F.col(f"b_{same}")) & first & (F.lit(True) if same == "row" else F.expr("a_row != b_row"))))
    over = F.expr("a_t_start < b_t_end - 1e-12 AND b_t_start < a_t_end - 1e-12")
    found = met[0].unionByName(met[1]).agg(F.count_if(over).alias("conflicts"), F.count_if(F.col("a_round") == F.col("b_round")).alias("shared"))
    return frame.agg(F.countDistinct("visit").alias("visits")).crossJoin(found)  # one row each


@query(f"WITH {_table(_GREEDY)}{_CONFLICT_SQL}")
def sched_conflict_free(spark, sf_dir):
    return _conflicts(_frame(spark, _GREEDY))


@query(f"WITH {_table(_STEAL)}{_CONFLICT_SQL}")
def sched_full_conflict_free(spark, sf_dir):
    return _conflicts(_frame(spark, _STEAL))


@query("SELECT CAST(i AS INT) AS \"row\", CAST(j AS INT) AS col, CAST(3 AS BIGINT) AS updates FROM range(12) a(i), range(9) b(j)")
def sched_full_even(spark, sf_dir):
    """Every block (and sub-block) exactly once per pass."""
    return _frame(spark, _AUTO).groupBy("row", "col").agg(F.count(F.lit(1)).alias("updates"))


@query(f"WITH {_table(_STEAL)} SELECT round, count(DISTINCT visit) AS visits, count(DISTINCT i) AS \"rows\", count(DISTINCT j) AS cols, count(*) AS blocks FROM s GROUP BY round")
def sched_rounds_independent(spark, sf_dir):
    """Visits, row stripes, columns and blocks of each round: as many columns as visits, as many row stripes as blocks, so no two visits share a stripe."""
    return _frame(spark, _STEAL).groupBy("round").agg(F.countDistinct("visit").alias("visits"), F.countDistinct("row").alias("rows"), F.countDistinct("col").alias("cols"), F.count(F.lit(1)).alias("blocks"))


_UNI = simulate({(i, j): 1000 for i in range(4) for j in range(3)}, lanes_of(2, 1), speeds(1, 10), Policy("greedy", count="visits"), passes=12)
_TWO = simulate({(i, j): 1000 for i in range(6) for j in range(5)}, lanes_of(2, 1), speeds(1, 10), Policy("static", count="visits", steal="none"), passes=12, groups=((0, 1, 2),))


def _spread(name: str) -> str:
    return f"SELECT '{name}' AS grid, CAST(min(n) AS BIGINT) AS least, CAST(max(n) AS BIGINT) AS most, round(stddev_pop(n) / avg(n), 6) AS cv FROM (SELECT count(*) AS n FROM s WHERE t0 < 4000 GROUP BY i, j) c"


@query(f"SELECT * FROM (WITH {_table(_UNI)} {_spread('uniform')}) a UNION ALL SELECT * FROM (WITH {_table(_TWO)} {_spread('two_regions')}) b")
def sched_skew(spark, sf_dir):
    """Update counts after the same virtual time, by the same rule (least updated block first, ties by hash, equal counts not forced): uniform grid against two regions."""
    out = None
    for name, v in (("uniform", _UNI), ("two_regions", _TWO)):
        s = measures.update_skew(_frame(spark, v).where("t_start < 4000")).select(F.lit(name).alias("grid"), "least", "most", F.round("cv", 6).alias("cv"))
        out = s if out is None else out.unionByName(s)
    return out


_DEQUE = simulate({(i, j): 100 * (1 + i * 4 + j) for i in range(5) for j in range(4)}, lanes_of(2, 1), speeds(1, 4), Policy("deque"))


@query(f"WITH {_table(_DEQUE)} SELECT kind, min(nnz) AS least, max(nnz) AS most, round(corr(t0, nnz), 6) AS order_by_size FROM s GROUP BY kind")
def sched_deque(spark, sf_dir):
    """Narrow lanes take from the small end, wide lanes from the large end."""
    return _frame(spark, _DEQUE).groupBy("kind").agg(F.min("nnz").alias("least"), F.max("nnz").alias("most"), F.round(F.corr("t_start", F.col("nnz").cast("double")), 6).alias("order_by_size"))


@query("SELECT CAST(s AS INT) AS round, CAST(i AS INT) AS \"row\", CAST((i + s) % 3 AS INT) AS col FROM range(3) t(s), range(3) u(i)")
def sched_strata(spark, sf_dir):
    v = simulate({(i, j): 10 for i in range(3) for j in range(3)}, lanes_of(3, 0), speeds(), Policy("strata"))
    return schedule_frame(spark, v, compile_rounds(v)).select("round", "row", "col")


_SMALL_SHARE = {(i, j): 300 if i < 3 else 1500 for i in range(6) for j in range(5)}
_MODES = {(name, steal): simulate(_SMALL_SHARE, lanes_of(2, 1), speeds(1, 8), Policy(name, steal), 2, ((0, 1, 2),)) for name, steal in (("static", "none"), ("static+steal", "auto"), ("static+steal", "both"))}


@query(" UNION ALL ".join(f"SELECT * FROM (WITH {_table(v)} SELECT '{steal}' AS steal, round(max(t1), 6) AS makespan, count(DISTINCT visit) FILTER (phase = 'dynamic') AS stolen FROM s) m" for (_, steal), v in _MODES.items()))
def sched_stealing(spark, sf_dir):
    """Virtual time and stolen visits with a share that is too small for the wide lane: stealing shortens it, and 'auto' is never slower than none."""
    out = None
    for (_, steal), v in _MODES.items():
        s = _frame(spark, v).agg(F.lit(steal).alias("steal"), F.round(F.max("t_end"), 6).alias("makespan"), F.countDistinct(F.when(F.col("phase") == "dynamic", F.col("visit"))).alias("stolen"))
        out = s if out is None else out.unionByName(s)
    return out


@query("SELECT CAST(0 AS BIGINT) AS failures, CAST(54 AS BIGINT) AS narrow_blocks")
def sched_lookahead(spark, sf_dir):
    """With the column rule a wide lane always finds its next block (no failed reservation) and every narrow block (6 rows, 9 columns) is visited."""
    from blockmf.plans.scheduler import _Clock

    nnz = {(i, j): 200 + (i * 11 + j * 29) % 40 for i in range(12) for j in range(9)}
    clock = _Clock(nnz, lanes_of(4, 2), speeds(1, 9), Policy("static", count="visits", lookahead=True), 6, _GROUPS)
    seen = _frame(spark, clock.run()).where("row >= 6").select("row", "col").distinct().agg(F.count(F.lit(1)).alias("narrow_blocks"))
    return seen.select(F.lit(clock.failed_lookahead).cast("long").alias("failures"), "narrow_blocks")


@query("SELECT kind, CAST(n AS INT) AS lanes, round(busy, 4) AS busy, round(1 - busy / 7000.0, 4) AS idle FROM (VALUES ('narrow', 1, 7000.0), ('wide', 1, 3500.0)) t(kind, n, busy)")
def sched_lane_usage(spark, sf_dir):
    """Two lanes on literal visits."""
    s = rows(spark, [(0, 0, "narrow", 0, 0, 1, 4000, "static", 0.0, 4000.0, 0), (1, 1, "wide", 1, 1, 1, 35000, "static", 0.0, 3500.0, 0), (2, 0, "narrow", 0, 2, 1, 3000, "static", 4000.0, 7000.0, 1)], "visit long, lane_id int, kind string, row int, col int, n_rows int, nnz long, phase string, t_start double, t_end double, round int")
    return measures.lane_usage(s).groupBy("kind").agg(F.count(F.lit(1)).cast("int").alias("lanes"), F.round(F.sum("busy"), 4).alias("busy"), F.round(F.avg("idle"), 4).alias("idle"))


@query()
def sched_plan_of_view(spark, sf_dir):
    """The final method's schedule on the flagship view."""
    p = plan(rating_view(spark, sf_dir, "cust_part"), "hybrid_full", 4, 2, speeds(1, 6), 1)
    return schedule_frame(spark, p.passes[0], p.rounds[0]).select("visit", "lane_id", "kind", "row", "col", "nnz", "phase", "round")


# --- cost models ----------------------------------------------------------------------------------------------------

_AVG = "a AS (SELECT kind, stage, size, avg(seconds) AS seconds FROM p GROUP BY kind, stage, size)"
_TAU = """t AS (SELECT kind, stage, coalesce(min(CASE WHEN abs(nxt / speed - 1) < 0.02 THEN size END), max(size)) AS tau
FROM (SELECT kind, stage, size, size / seconds AS speed, lead(size / seconds) OVER (PARTITION BY kind, stage ORDER BY size) AS nxt FROM a) x GROUP BY kind, stage)"""


def _probe(device: str) -> str:
    return f"WITH p AS ({cm.device_sql(device)}), {_AVG}"


@query(f"WITH x AS (SELECT CAST(floor(((u * 7919 + v * 104729 + 1) % 1000003) * 8 / 1000003) AS INT) AS part FROM ({CP}) r), c AS (SELECT part, count(*) AS n FROM x GROUP BY part) SELECT part, sum(n) OVER (ORDER BY part) AS size FROM c")
def cost_parts_prefix(spark, sf_dir):
    return cm.prefix_sizes(cm.probe_parts(rating_view(spark, sf_dir, "cust_part"), 8))


@query(f"SELECT CAST(floor(((u * 7919 + v * 104729 + 1) % 1000003) * 8 / 1000003) AS INT) AS part, count(*) AS size FROM ({CP}) r GROUP BY 1")
def cost_parts_disjoint(spark, sf_dir):
    return cm.prefix_sizes(cm.probe_parts(rating_view(spark, sf_dir, "cust_part"), 8), "disjoint")


@query(_probe("saturating") + " SELECT kind, stage, 'line' AS form, round(regr_slope(seconds, size) * 1e9, 4) AS a, round(regr_intercept(seconds, size), 6) + 0.0 AS b, round(regr_r2(seconds, size), 6) AS r2 FROM a GROUP BY kind, stage")
def cost_linear_fit(spark, sf_dir):
    f = cm.fit_line(cm.device_probe(spark, "saturating"))
    return f.select("kind", "stage", "form", F.round(F.col("a") * 1e9, 4).alias("a"), (F.round("b", 6) + 0.0).alias("b"), F.round("r2", 6).alias("r2"))


@query(_probe("saturating") + f", {_TAU} SELECT * FROM t")
def cost_tau(spark, sf_dir):
    return cm.find_tau(cm.device_probe(spark, "saturating"))


def _piece_sql(curve: str, where: str) -> str:
    x = {"log": "ln(size)", "sqrtlog": "sqrt(ln(size))", "sqrt": "sqrt(size)"}[curve]
    return _probe("saturating") + f""", {_TAU}, s AS (SELECT a.*, tau, size / seconds AS speed, {x} AS x FROM a JOIN t USING (kind, stage))
SELECT kind, stage, tau, '{curve}' AS form, round(regr_slope(CASE WHEN size <= tau THEN speed END, CASE WHEN size <= tau THEN x END), 1) AS a, round(regr_intercept(CASE WHEN size <= tau THEN speed END, CASE WHEN size <= tau THEN x END), 0) AS b,
round(regr_slope(CASE WHEN size >= tau THEN seconds END, CASE WHEN size >= tau THEN size END) * 1e9, 4) AS line_a FROM s WHERE {where} GROUP BY kind, stage, tau"""


def _piece(spark, curve, where):
    f = cm.fit_piecewise(cm.device_probe(spark, "saturating"), curve).where(where)
    return f.select("kind", "stage", "tau", "form", F.round("a", 1).alias("a"), F.round("b", 0).alias("b"), F.round(F.col("line_a") * 1e9, 4).alias("line_a"))


@query(_piece_sql("sqrtlog", "stage IN ('to', 'from')"))
def cost_transfer_fit(spark, sf_dir):
    return _piece(spark, "sqrtlog", "stage in ('to', 'from')")


@query(_piece_sql("log", "kind = 'wide' AND stage = 'kernel'"))
def cost_kernel_fit(spark, sf_dir):
    return _piece(spark, "log", "kind = 'wide' and stage = 'kernel'")


@query(_piece_sql("sqrt", "kind = 'wide' AND stage = 'kernel'"))
def cost_kernel_sqrt(spark, sf_dir):
    return _piece(spark, "sqrt", "kind = 'wide' and stage = 'kernel'")


_SIZES = cm.table_sizes_sql(CP)


def _sizes(spark, sf_dir) -> tuple[DataFrame, int]:
    """Doubling prefixes of the flagship view, and the whole of it; each rating stands for cm.EACH."""
    sizes = cm.table_sizes(rating_view(spark, sf_dir, "cust_part"))
    return sizes, sizes.agg(F.max("size")).first()[0]


def _table_probe(device: str) -> str:
    return f"WITH sizes AS ({_SIZES}), p AS ({cm.device_sql(device, sizes='SELECT size FROM sizes')}), {_AVG}, z AS (SELECT max(size) AS nnz FROM sizes)"


def _combined(spark, sf_dir, how, device):
    p = cm.average(cm.table_probe(_sizes(spark, sf_dir)[0], device)).where("kind = 'wide'").groupBy("size").pivot("stage", ["to", "kernel", "from"]).agg(F.first("seconds"))
    e = {"max": F.greatest("to", "kernel"), "sum": F.col("to") + F.col("kernel") + F.col("from"), "max3": F.greatest("to", "kernel", "from")}[how]
    return p.select("size", F.round(e * 1e6, 3).alias("us"))


for _how, _e in (("max", "greatest(x, k)"), ("sum", "x + k + b"), ("max3", "greatest(x, k, b)")):
    for _d in ("transfer_bound", "kernel_bound"):
        _n = f"cost_combine_{_how}_{_d}"
        QUERIES[_n] = lambda spark, sf_dir, h=_how, d=_d: _combined(spark, sf_dir, h, d)
        SQL[_n] = _table_probe(_d) + f", w AS (SELECT size, max(seconds) FILTER (stage = 'to') AS x, max(seconds) FILTER (stage = 'kernel') AS k, max(seconds) FILTER (stage = 'from') AS b FROM a WHERE kind = 'wide' GROUP BY size) SELECT size, round(({_e}) * 1e6, 3) AS us FROM w"


_LINES = "fits AS (SELECT kind, regr_slope(seconds, size) AS a, regr_intercept(seconds, size) AS b FROM a WHERE stage = 'kernel' GROUP BY kind), l AS (SELECT max(a) FILTER (kind = 'narrow') AS na, max(b) FILTER (kind = 'narrow') AS nb, max(a) FILTER (kind = 'wide') AS wa, max(b) FILTER (kind = 'wide') AS wb FROM fits)"


@query(_table_probe("linear") + f", {_LINES}, g AS (SELECT nnz, i / 200.0 AS alpha, (wa * i / 200.0 * nnz + wb) / 2 AS tw, (na * (1 - i / 200.0) * nnz + nb) / 4 AS tn FROM l, z, range(201) t(i)) SELECT max(nnz) AS nnz, round(arg_min(alpha, abs(tw - tn)), 4) AS alpha, round(arg_min(greatest(tw, tn), abs(tw - tn)), 2) AS seconds FROM g")
def cost_alpha_grid(spark, sf_dir):
    sizes, nnz = _sizes(spark, sf_dir)
    f = cm.fit_line(cm.table_probe(sizes, "linear").where("stage = 'kernel'"))
    return bal.balance_grid(f, nnz, 4, 2).select(F.lit(nnz).cast("long").alias("nnz"), F.round("alpha", 4).alias("alpha"), F.round("seconds", 2).alias("seconds"))


@query(_table_probe("linear") + f", {_LINES} SELECT nnz, round(((na * nnz + nb) / 4 - wb / 2) / (nnz * (wa / 2 + na / 4)), 5) AS alpha FROM l, z")
def cost_alpha_linear(spark, sf_dir):
    sizes, nnz = _sizes(spark, sf_dir)
    f = {r["kind"]: (r["a"], r["b"]) for r in cm.fit_line(cm.table_probe(sizes, "linear").where("stage = 'kernel'")).collect()}
    return rows(spark, [(nnz, round(bal.balance_lines(f["wide"], f["narrow"], nnz, 4, 2), 5))], "nnz long, alpha double")


@query(_probe("linear") + f", {_LINES} SELECT i / 10.0 AS alpha, round(greatest((wa * i / 10.0 * 1e7 + wb) / 2, (na * (1 - i / 10.0) * 1e7 + nb) / 4), 4) AS seconds FROM l, range(11) t(i)")
def cost_total_time(spark, sf_dir):
    f = {r["kind"]: cm.Piecewise("line", r["a"], r["b"], 0, 0, 0) for r in cm.fit_line(cm.device_probe(spark, "linear").where("stage = 'kernel'")).collect()}
    return rows(spark, [(i / 10, round(bal.total_time(f["wide"], f["narrow"], 1e7, i / 10, 4, 2), 4)) for i in range(11)], "alpha double, seconds double")


@query(_probe("saturating") + ", f AS (SELECT kind, stage, regr_slope(seconds, size) AS s, regr_intercept(seconds, size) AS i FROM a GROUP BY kind, stage) SELECT kind, stage, round(avg(abs((s * size + i) / seconds - 1)), 4) AS mape FROM a JOIN f USING (kind, stage) GROUP BY kind, stage")
def cost_line_error(spark, sf_dir):
    p = cm.device_probe(spark, "saturating")
    return cm.model_error(p, cm.fit_line(p)).select("kind", "stage", F.round("mape", 4).alias("mape"))


@query(_probe("saturating") + f""", {_TAU}, s AS (SELECT a.size, a.seconds, tau, a.size / a.seconds AS speed, ln(a.size) AS x FROM a JOIN t USING (kind, stage) WHERE kind = 'wide' AND stage = 'kernel'),
f AS (SELECT regr_slope(CASE WHEN size <= tau THEN speed END, CASE WHEN size <= tau THEN x END) AS a, regr_intercept(CASE WHEN size <= tau THEN speed END, CASE WHEN size <= tau THEN x END) AS b, regr_slope(CASE WHEN size >= tau THEN seconds END, CASE WHEN size >= tau THEN size END) AS la,
regr_intercept(CASE WHEN size >= tau THEN seconds END, CASE WHEN size >= tau THEN size END) AS lb, regr_slope(seconds, size) AS sa, regr_intercept(seconds, size) AS sb FROM s)
SELECT round(avg(abs((sa * size + sb) / seconds - 1)), 4) AS line, round(avg(abs(CASE WHEN size > tau THEN la * size + lb ELSE size / (a * x + b) END / seconds - 1)), 4) AS own FROM s, f""")
def cost_model_wins(spark, sf_dir):
    """On a saturating device the piecewise model errs less than the line: mean relative errors of both."""
    p = cm.device_probe(spark, "saturating").where("kind = 'wide' and stage = 'kernel'")
    a = cm.model_error(p, cm.fit_line(p)).select("stage", F.round("mape", 4).alias("line"))
    b = cm.model_error(p, cm.fit_piecewise(p, "log")).select("stage", F.round("mape", 4).alias("own"))
    return a.join(b, "stage").select("line", "own")


@query(_probe("saturating") + " SELECT kind, stage, size, round(size / seconds, 0) AS speed FROM a")
def measure_throughput(spark, sf_dir):
    t = cm.throughput(cm.device_probe(spark, "saturating"))
    return t.select("kind", "stage", "size", F.round("speed", 0).alias("speed"))


@query(f"SELECT size, CAST(0 AS DOUBLE) AS no_wide, CAST(1 AS DOUBLE) AS no_narrow FROM ({_SIZES}) s")
def cost_alpha_edges(spark, sf_dir):
    """The share of each prefix of the flagship view where one kind of lanes is missing."""
    f = lambda s: s * 1e-6
    found = [r["size"] for r in _sizes(spark, sf_dir)[0].collect()]
    return rows(spark, [(s, bal.balance(f, f, s, 4, 0), bal.balance(f, f, s, 0, 2)) for s in found], "size long, no_wide double, no_narrow double")


@query(f"""WITH z AS (SELECT max(size) AS nnz FROM ({_SIZES}) s), g AS (SELECT i / 1000.0 AS alpha, abs((2e-7 * i / 1000.0 * nnz + 0.01) / 2 - 1e-6 * (1 - i / 1000.0) * nnz / 4) AS gap FROM z, range(1001) t(i))
SELECT 'grid' AS method, round(arg_min(alpha, gap), 5) AS alpha FROM g UNION ALL SELECT m, round((1e-6 * nnz / 4 - 0.01 / 2) / (nnz * (2e-7 / 2 + 1e-6 / 4)), 5) FROM z, (VALUES ('bisect'), ('closed')) t(m)""")
def cost_alpha_methods(spark, sf_dir):
    """The share by bisection, by a grid of 1,000 steps, and in closed form, on straight lines."""
    w, n = (lambda s: 2e-7 * s + 0.01), (lambda s: 1e-6 * s)
    nnz = _sizes(spark, sf_dir)[1]
    got = [("bisect", bal.balance(w, n, nnz, 4, 2)), ("grid", bal.balance(w, n, nnz, 4, 2, "grid")), ("closed", bal.balance_lines((2e-7, 0.01), (1e-6, 0.0), nnz, 4, 2))]
    return rows(spark, [(m, round(a, 5)) for m, a in got], "method string, alpha double")


_SAT = cm.DEVICES["saturating"]


@query(f"""WITH z AS (SELECT max(size) AS nnz FROM ({_SIZES}) s), g AS (SELECT nnz, i / 1000.0 AS alpha, CAST(nnz AS DOUBLE) * i / 1000.0 / 9.0 AS wide, CAST(nnz AS DOUBLE) * (1 - i / 1000.0) / 54.0 AS narrow FROM z, range(1, 1000) t(i)),
t AS (SELECT nnz, alpha, 9 * greatest({_SAT['wide', 'to'].replace('size', 'wide')}, {_SAT['wide', 'kernel'].replace('size', 'wide')}) AS tw, 54 * ({_SAT['narrow', 'kernel'].replace('size', 'narrow')}) / 5 AS tn FROM g)
SELECT max(nnz) AS nnz, round(arg_min(alpha, abs(tw - tn)), 2) AS alpha FROM t""")
def cost_alpha_saturating(spark, sf_dir):
    """The share on a saturating device, block by block: bisected on the device's closed form, which the grid in SQL must meet to 0.01."""
    import math

    kernel, to = (lambda s: s / (1e6 * math.log(min(s, 1048576)) - 6e6)), (lambda s: s / (4e6 * math.sqrt(math.log(min(s, 262144))) - 8e6))
    wide = bal.per_block(lambda s: max(to(s), kernel(s)) if s > 1000 else s * 1e-6, 9)
    nnz = _sizes(spark, sf_dir)[1]
    return rows(spark, [(nnz, round(bal.balance(wide, bal.per_block(lambda s: s * 1e-6, 54), nnz, 5, 1), 2))], "nnz long, alpha double")
