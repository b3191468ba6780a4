"""Training, loss, gradient and baseline queries. Small views, so that a recursive SQL run is an exact oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.operators import baselines, losses, measures
from blockmf.operators.factors import flat, init_expr, init_factors
from blockmf.operators.params import MFParams
from blockmf.operators.recommend import fold_in, similar, top_items
from blockmf.operators.serial import order_expr, recursive_sql, sgd_serial
from blockmf.operators.train import UNIFORM, policy_of, schedule, share, trace_frame, train
from blockmf.plans import grid as g
from blockmf.plans.rounds import compile_rounds
from blockmf.plans.scheduler import lanes_of, speeds
from blockmf.sources.tables import hash_split, rating_view, split_hash, view_sql

P = MFParams(k=4, epochs=2)
QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return keep


def steps_sql(view: str, order: str = "conflict_free", width: int = 1) -> str:
    """(step, u, v, r): conflict-free diagonals as steps, or batches of `width` ratings of a total order."""
    inner = f"SELECT *, {order_expr(order, P.seed)} AS o FROM ({view_sql(view)}) x"
    if order == "conflict_free":
        return f"SELECT dense_rank() OVER (ORDER BY o) AS step, u, v, r FROM ({inner}) y"
    return f"SELECT (row_number() OVER (ORDER BY o, u, v) - 1) // {width} + 1 AS step, u, v, r FROM ({inner}) y"


def _factor_sql(view: str, p: MFParams = P) -> str:
    """CTE text: f(side, id, vec) of the closed-form start."""
    part = lambda s, c: f"SELECT '{s}' AS side, id, list_transform(range({p.k}), lambda j: {init_expr(s, p.k, p.seed, p.scale)}) AS vec FROM (SELECT DISTINCT {c} AS id FROM r)"
    return f"r AS ({view_sql(view)}), f AS ({part('p', 'u')} UNION ALL {part('q', 'v')})"


def _joined_sql(view: str, p: MFParams = P) -> str:
    return f"WITH {_factor_sql(view, p)}, j AS (SELECT r.u, r.v, r.r, a.vec AS p, b.vec AS q, list_inner_product(a.vec, b.vec) AS hat FROM r JOIN f a ON a.side = 'p' AND a.id = r.u JOIN f b ON b.side = 'q' AND b.id = r.v)"


def _start(spark, sf_dir, view, p: MFParams = P):
    r = rating_view(spark, sf_dir, view)
    return r, init_factors(r, p.k, p.seed, p.scale)


# --- serial and block-parallel training -----------------------------------------------------------------------------


def _serial(name: str, view: str, p: MFParams, order: str = "conflict_free", kernel: str = "narrow", width: int = 1):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return flat(sgd_serial(rating_view(spark, sf_dir, view), p, order, kernel))

    QUERIES[name] = run
    SQL[name] = recursive_sql(steps_sql(view, order, width), p)


_serial("sgd_serial_user_type", "user_type", P)
_serial("sgd_serial_user_hour", "user_hour", P)
_serial("sgd_serial_new_p", "user_hour", MFParams(k=4, epochs=2, q_sees="new_p"))
_serial("sgd_serial_grad2", "user_hour", MFParams(k=4, epochs=2, grad_scale=2.0, gamma=0.005))
_serial("sgd_serial_given_order", "user_type", P, "given")
_serial("sgd_serial_hash_order", "user_type", P, "hash")
_serial("sgd_wide_sum_user_hour", "user_hour", MFParams(k=4, epochs=2, batch_width=128), "hash", "wide", 128)


def _trained(name: str, view: str, algo: str, n: int, w: int, p: MFParams = P, **options):
    """Flat factors of a block-parallel run. The tests compare such runs with the serial order of their own plan."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return flat(train(rating_view(spark, sf_dir, view), p, algo, n, w, **({"cost": speeds(1, 4), "measure": False} | options)).factors)

    QUERIES[name] = run


def visits_sql(view: str, algo: str, n: int, w: int, width: int, epochs: int, grid: tuple[int, int] | None = None) -> str:
    """(step, u, v, r) of a block-parallel run whose schedule does not depend on the data (stripes of equal id ranges, all blocks clocked alike): the visits stand
    in the text as a table; visits of a round are done at once, narrow ones rating by rating, wide ones batch by batch."""
    stripe = lambda x, lo, size, k: f"len(list_filter(range(1, {k}), lambda i: {x} - {lo} >= {size} * i // {k}))" if k > 1 else "0"
    cost = speeds(1, 5)
    if algo in UNIFORM:
        r, c = grid or g.min_grid(n, w)
        groups, row, head = (), stripe("u", "u0", "nu", r), ""
    else:
        f = g.final_grid(n, w, algo == "hybrid_full")
        wide, c = f.wide_rows * f.sub, f.cols
        r = wide + f.narrow_rows
        groups = tuple(tuple(range(i, i + f.sub)) for i in range(0, wide, f.sub))
        alpha = share(algo, cost, 1000, n, w)
        head = f""", k AS (SELECT u, sum(count(*)) OVER (ORDER BY u) AS cum FROM x GROUP BY u),
  e AS (SELECT max(u) FILTER (cum <= {alpha!r} * (SELECT count(*) FROM x)) + 1 AS border FROM k), d AS (SELECT border, border - u0 AS nw, min(u) AS n0, max(u) - min(u) + 1 AS nn FROM x, e, b WHERE u >= border GROUP BY border, u0)"""
        row = f"CASE WHEN u < border THEN {stripe('u', 'u0', 'nw', wide)} ELSE {wide} + {stripe('u', 'n0', 'nn', f.narrow_rows)} END"
    passes = schedule({(i, j): 1 for i in range(r) for j in range(c)}, lanes_of(n, w), cost, policy_of(algo), epochs, groups)
    visits = ", ".join(f"({p}, {k}, {v.visit}, {i}, {v.col}, {v.kind == 'wide'})" for p, vs in enumerate(passes) for v, k in zip(vs, compile_rounds(vs), strict=True) for i in v.rows)
    return f"""SELECT dense_rank() OVER (ORDER BY pass, round, n) AS step, u, v, r FROM (
  WITH x AS ({view_sql(view)}), b AS (SELECT min(u) AS u0, max(u) - min(u) + 1 AS nu, min(v) AS v0, max(v) - min(v) + 1 AS nv FROM x){head},
  s(pass, round, visit, i, j, wide) AS (VALUES {visits}), y AS (SELECT u, v, r, {row} AS i, {stripe('v', 'v0', 'nv', c)} AS j FROM x, b{', d' if head else ''})
  SELECT pass, round, u, v, r, (row_number() OVER (PARTITION BY pass, visit ORDER BY u, v) - 1) // CASE WHEN wide THEN {width} ELSE 1 END AS n FROM y JOIN s USING (i, j)) z"""


for _algo, _n, _w, _grid in (("narrow_only", 3, 0, None), ("wide_only", 0, 2, (3, 2)), ("hybrid_uniform", 2, 1, None), ("hybrid_linear", 2, 1, None), ("hybrid_model", 2, 1, None), ("hybrid_full", 2, 1, None), ("deque", 2, 1, None)):
    _trained(f"sgd_{_algo}_user_hour", "user_hour", _algo, _n, _w, MFParams(k=4, epochs=2, batch_width=64), by="ids", seed=None, order="given", weights="equal", cost=speeds(1, 5), grid=_grid)
    SQL[f"sgd_{_algo}_user_hour"] = recursive_sql(visits_sql("user_hour", _algo, _n, _w, 64, 2, _grid), MFParams(k=4, epochs=1))
_trained("sgd_history_user_hour", "user_hour", "history", 2, 1)
# The same algorithms on the flagship view: too long for recursive SQL; the tests compare such runs with the serial order of their own plan.
for _algo, _n, _w in (("narrow_only", 3, 0), ("wide_only", 0, 1), ("hybrid_uniform", 3, 1), ("hybrid_model", 3, 1), ("hybrid_full", 3, 1)):
    _trained(f"sgd_{_algo}_cust_part", "cust_part", _algo, _n, _w, MFParams(k=8, epochs=1, gamma=0.002), start="sqrt_mean")
# With equal id ranges, no scatter and three narrow lanes the diagonal schedule has a closed form: rounds s = 0, 1, 2 hold blocks (i, (i + s) mod 3).
_trained("sgd_strata_user_hour", "user_hour", "strata", 3, 0, MFParams(k=4, epochs=2), by="ids", seed=None, order="given")
_BLOCKS = f"""SELECT u, v, r, ((v - v0) * 3 // nv - (u - u0) * 3 // nu + 3) % 3 AS round, (u - u0) * 3 // nu AS bi, u * 1000003 + v AS o
  FROM ({view_sql('user_hour')}) x, (SELECT min(u) AS u0, max(u) - min(u) + 1 AS nu, min(v) AS v0, max(v) - min(v) + 1 AS nv FROM ({view_sql('user_hour')}) y)"""

SQL["sgd_strata_user_hour"] = recursive_sql(f"SELECT dense_rank() OVER (ORDER BY round, n) AS step, u, v, r FROM (SELECT *, row_number() OVER (PARTITION BY round, bi ORDER BY o) AS n FROM ({_BLOCKS}) b) c", P)


@query()
def sgd_full_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Test error per pass of the whole method on the planted view."""
    r = rating_view(spark, sf_dir, "planted")
    a, b = hash_split(r, 70)
    run = train(a, MFParams(k=8, epochs=2, gamma=0.02), "hybrid_full", 3, 1, cost=speeds(1, 4), test=b, start="sqrt_mean")
    return trace_frame(spark, run.trace).select("algo", "epoch", "visits", "rounds", F.round("rmse_test", 4).alias("rmse_test"))


@query(recursive_sql(steps_sql("user_hour"), MFParams(k=4, epochs=2)).replace("SELECT side, id, x.pos", "SELECT count(*) AS n, count(DISTINCT side) AS sides FROM (SELECT side, id, x.pos") + ") z")
def sgd_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flat(sgd_serial(rating_view(spark, sf_dir, "user_hour"), P, "conflict_free")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("side").alias("sides"))


# --- loss, gradient, full gradient descent, coordinate descent ------------------------------------------------------


@query(f"WITH {_factor_sql('user_hour')} SELECT side, id, x.pos AS pos, round(x.value, 6) AS value FROM (SELECT side, id, unnest(list_transform(range(4), lambda j: {{'pos': j, 'value': vec[j + 1]}})) AS x FROM f)")
def init_factor_values(spark, sf_dir):
    return flat(_start(spark, sf_dir, "user_hour")[1])


@query(_joined_sql("cust_part") + " SELECT u, v, round(r, 6) AS r, round(hat, 6) AS r_hat FROM j")
def score_cells(spark, sf_dir):
    return losses.score(*_start(spark, sf_dir, "cust_part")).select("u", "v", F.round("r", 6).alias("r"), F.round("r_hat", 6).alias("r_hat"))


@query(_joined_sql("cust_part") + " SELECT round(sum((r - hat) * (r - hat) + 0.05 * list_inner_product(p, p) + 0.05 * list_inner_product(q, q)), 2) AS loss FROM j")
def loss_per_cell(spark, sf_dir):
    return losses.loss(*_start(spark, sf_dir, "cust_part"), 0.05, 0.05).select(F.round("loss", 2).alias("loss"))


@query(_joined_sql("cust_part") + " SELECT round((SELECT sum((r - hat) * (r - hat)) FROM j) + (SELECT sum(0.05 * list_inner_product(vec, vec)) FROM f), 2) AS loss")
def loss_per_vector(spark, sf_dir):
    return losses.loss(*_start(spark, sf_dir, "cust_part"), 0.05, 0.05, "per_vector").select(F.round("loss", 2).alias("loss"))


@query(_joined_sql("user_hour") + " SELECT u, v, round((r - hat) * (r - hat) + 0.05 * list_inner_product(p, p) + 0.05 * list_inner_product(q, q), 6) AS loss FROM j")
def loss_of_cells(spark, sf_dir):
    from blockmf.operators.factors import with_vectors

    return with_vectors(*_start(spark, sf_dir, "user_hour")).select("u", "v", F.round(losses.cell_loss(0.05, 0.05), 6).alias("loss"))


@query(_joined_sql("user_hour") + " SELECT u, v, j.pos AS pos, round(0.05 * p[j.pos + 1] - (r - hat) * q[j.pos + 1], 6) AS gp, round(0.05 * q[j.pos + 1] - (r - hat) * p[j.pos + 1], 6) AS gq FROM (SELECT *, unnest(range(4)) AS pos FROM j) j")
def cell_gradient(spark, sf_dir):
    grad = losses.cell_gradients(*_start(spark, sf_dir, "user_hour"), P)
    return grad.select("u", "v", F.posexplode(F.arrays_zip("grad_p", "grad_q")).alias("pos", "g")).select("u", "v", F.col("pos").cast("long").alias("pos"), F.round("g.grad_p", 6).alias("gp"), F.round("g.grad_q", 6).alias("gq"))


def _sum_grad(j: str, k: int = 4) -> str:
    one = lambda s, key, a, b: f"SELECT '{s}' AS side, {key} AS id, pos, sum(0.05 * {a}[pos + 1] - (r - hat) * {b}[pos + 1]) AS g FROM (SELECT *, unnest(range({k})) AS pos FROM {j}) GROUP BY {key}, pos"
    return f"{one('p', 'u', 'p', 'q')} UNION ALL {one('q', 'v', 'q', 'p')}"


@query(_joined_sql("user_hour") + f" SELECT side, id, pos, round(g, 6) AS value FROM ({_sum_grad('j')})")
def sum_gradient(spark, sf_dir):
    return flat(losses.sum_gradients(*_start(spark, sf_dir, "user_hour"), P).withColumnRenamed("grad", "vec"))


def _gd_sql(passes: int) -> str:
    text = _joined_sql("user_hour").replace("j AS (", "j0 AS (").replace("WITH r AS", "WITH r AS")
    for i in range(passes):
        text += f", g{i} AS ({_sum_grad(f'j{i}')}), f{i + 1} AS (SELECT o.side, o.id, list(o.vec[g.pos + 1] - 0.01 * g.g ORDER BY g.pos) AS vec FROM {'f' if not i else f'f{i}'} o JOIN g{i} g ON g.side = o.side AND g.id = o.id GROUP BY o.side, o.id)"
        text += f", j{i + 1} AS (SELECT r.u, r.v, r.r, a.vec AS p, b.vec AS q, list_inner_product(a.vec, b.vec) AS hat FROM r JOIN f{i + 1} a ON a.side = 'p' AND a.id = r.u JOIN f{i + 1} b ON b.side = 'q' AND b.id = r.v)"
    return text + f" SELECT side, id, pos, round(vec[pos + 1], 6) AS value FROM (SELECT *, unnest(range(4)) AS pos FROM f{passes})"


@query(_gd_sql(2))
def gd_full_2(spark, sf_dir):
    r, f = _start(spark, sf_dir, "user_hour")
    return flat(losses.gd_full(r, f, P))


def _ccd_sql() -> str:
    """One sweep with k = 1: rows first, then columns."""
    p1 = MFParams(k=1)
    return _joined_sql("user_hour", p1) + """,
np AS (SELECT u AS id, sum(((r - p[1] * q[1]) + p[1] * q[1]) * q[1]) / (0.05 * count(*) + sum(q[1] * q[1])) AS x FROM j GROUP BY u),
nq AS (SELECT j.v AS id, sum(j.r * np.x) / (0.05 * count(*) + sum(np.x * np.x)) AS x FROM j JOIN np ON np.id = j.u GROUP BY j.v)
SELECT 'p' AS side, id, CAST(0 AS BIGINT) AS pos, round(x, 6) AS value FROM np UNION ALL SELECT 'q', id, 0, round(x, 6) FROM nq"""


@query(_ccd_sql())
def ccd_sweep(spark, sf_dir):
    p1 = MFParams(k=1)
    return flat(baselines.ccd_sweep(*_start(spark, sf_dir, "user_hour", p1), p1))


# --- accuracy and reference predictors ------------------------------------------------------------------------------


@query(_joined_sql("cust_part") + f" SELECT round(sqrt(avg((r - hat) * (r - hat))), 6) AS rmse, count(*) AS n, CAST(0 AS BIGINT) AS n_cold FROM j WHERE {split_hash()} < 70")
def rmse_test(spark, sf_dir):
    r, f = _start(spark, sf_dir, "cust_part")
    return measures.rmse(hash_split(r)[1], f).select(F.round("rmse", 6).alias("rmse"), "n", "n_cold")


@query(_joined_sql("cust_part") + f" SELECT round(sqrt(avg((r - hat) * (r - hat))), 6) AS rmse, count(*) AS n, CAST(0 AS BIGINT) AS n_cold FROM j WHERE {split_hash()} >= 70")
def rmse_train(spark, sf_dir):
    r, f = _start(spark, sf_dir, "cust_part")
    return measures.rmse(hash_split(r)[0], f).select(F.round("rmse", 6).alias("rmse"), "n", "n_cold")


@query(_joined_sql("cust_part") + " SELECT round(avg(abs(r - hat)), 6) AS mae FROM j")
def mae_cells(spark, sf_dir):
    return measures.mae(*_start(spark, sf_dir, "cust_part")).select(F.round("mae", 6).alias("mae"))


@query(f"WITH r AS ({view_sql('cust_part')}), m AS (SELECT avg(r) AS m FROM r WHERE {split_hash()} >= 70) SELECT round(sqrt(avg((r - m) * (r - m))), 6) AS rmse FROM r, m WHERE {split_hash()} < 70")
def base_mean(spark, sf_dir):
    a, b = hash_split(rating_view(spark, sf_dir, "cust_part"))
    return baselines.mean_model(a, b).select(F.round("rmse", 6).alias("rmse"))


@query(f"""WITH r AS ({view_sql('cust_part')}), t AS (SELECT * FROM r WHERE {split_hash()} >= 70), m AS (SELECT avg(r) AS m FROM t),
bu AS (SELECT u, avg(r - m) AS bu FROM t, m GROUP BY u), bv AS (SELECT v, avg(r - m - bu) AS bv FROM t JOIN bu USING (u), m GROUP BY v)
SELECT round(sqrt(avg(power(r - m - coalesce(bu, 0) - coalesce(bv, 0), 2))), 6) AS rmse FROM (SELECT * FROM r WHERE {split_hash()} < 70) x LEFT JOIN bu USING (u) LEFT JOIN bv USING (v), m""")
def base_bias(spark, sf_dir):
    a, b = hash_split(rating_view(spark, sf_dir, "cust_part"))
    return baselines.bias_model(a, b).select(F.round("rmse", 6).alias("rmse"))


@query()
def base_als(spark, sf_dir):
    a, b = hash_split(rating_view(spark, sf_dir, "planted"))
    m = baselines.als(a, MFParams(k=8, epochs=5))
    return measures.rmse(b, m).select((F.col("rmse") < 1.0).alias("good"), "n")


@query()
def base_classifier(spark, sf_dir):
    """Share classes of the blocks of the flagship view, in grids from one block to 32 x 32: how often the tree is right on widths k that it has not seen."""
    tasks = baselines.block_tasks(rating_view(spark, sf_dir, "cust_part"), speeds(1.0, 8.0, 1000.0), 4, 1)
    held = F.col("k") == 32  # tasks that the tree has not seen
    got = baselines.device_classifier(tasks.where(~held)).transform(tasks.where(held))
    return got.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("prediction") == F.col("label")).cast("int")), 2).alias("agreement"))


# --- views and splits -----------------------------------------------------------------------------------------------


def _view(name: str):
    def run(spark, sf_dir):
        return rating_view(spark, sf_dir, name).select("u", "v", F.round("r", 10).alias("r"))

    QUERIES[f"view_{name}"] = run
    SQL[f"view_{name}"] = f"SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v, round(r, 10) AS r FROM ({view_sql(name)}) x"


for _v in ("cust_part", "supp_part", "cust_supp", "user_type", "user_hour", "conv_turn", "doc_source", "planted"):
    _view(_v)
QUERIES["view_vec_dim"] = lambda spark, sf_dir: rating_view(spark, sf_dir, "vec_dim").select("u", "v", F.round("r", 6).alias("r"))
SQL["view_vec_dim"] = "SELECT vec_id AS u, i AS v, round(CAST(embedding[i + 1] AS DOUBLE), 6) AS r FROM (SELECT vec_id, embedding, unnest(range(len(embedding))) AS i FROM embeddings) x"
QUERIES["view_doc_term"] = lambda spark, sf_dir: rating_view(spark, sf_dir, "doc_term").select("u", "v", F.round("r", 6).alias("r"))
SQL["view_doc_term"] = """WITH w AS (SELECT doc_id AS u, unnest(regexp_extract_all(lower(text), '([a-z]+)', 1)) AS term FROM documents),
tf AS (SELECT u, term, ln(1 + count(*)) AS r FROM w GROUP BY u, term), t AS (SELECT term, row_number() OVER (ORDER BY term) - 1 AS v FROM (SELECT term FROM tf GROUP BY term HAVING count(*) >= 5))
SELECT u, v, round(r, 6) AS r FROM tf JOIN t USING (term)"""


@query(f"SELECT {split_hash()} < 70 AS test, count(*) AS n, round(sum(r), 4) AS total FROM ({view_sql('cust_part')}) x GROUP BY 1")
def split_hash_counts(spark, sf_dir):
    r = rating_view(spark, sf_dir, "cust_part").withColumn("test", F.expr(split_hash()) < 70)
    return r.groupBy("test").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("r"), 4).alias("total"))


@query("SELECT event_id, user_id FROM (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS n FROM events) x WHERE n = 1")
def split_leave_last(spark, sf_dir):
    from blockmf.sources.tables import leave_last_out, read_table

    return leave_last_out(read_table(spark, sf_dir, "events")).where("held").select("event_id", "user_id")


# --- recommendation -------------------------------------------------------------------------------------------------

_USERS = "SELECT DISTINCT u FROM r WHERE u % 100 = 0"


@query("WITH " + _factor_sql("cust_part") + """, s AS (SELECT a.id AS u, b.id AS v, list_inner_product(a.vec, b.vec) AS score FROM f a, f b WHERE a.side = 'p' AND b.side = 'q' AND a.id % 100 = 0),
k AS (SELECT *, row_number() OVER (PARTITION BY u ORDER BY score DESC, v) AS rank FROM s WHERE NOT EXISTS (SELECT 1 FROM r WHERE r.u = s.u AND r.v = s.v)) SELECT u, v, round(score, 6) AS score, rank FROM k WHERE rank <= 10""")
def rec_topk(spark, sf_dir):
    r, f = _start(spark, sf_dir, "cust_part")
    users = r.where("u % 100 = 0").select("u").distinct()
    return top_items(users, f, r.join(users, "u", "left_semi"), 10).select("u", "v", F.round("score", 6).alias("score"), F.col("rank").cast("long").alias("rank"))


@query("""WITH e AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS vec FROM embeddings), s AS (SELECT a.id AS q, b.id AS id, list_inner_product(a.vec, b.vec) / sqrt(list_inner_product(a.vec, a.vec) * list_inner_product(b.vec, b.vec)) AS sim FROM e a, e b WHERE a.id % 100 = 0 AND a.id != b.id)
SELECT q, id, round(sim, 5) AS sim, rank FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY sim DESC, id) AS rank FROM s) x WHERE rank <= 5""")
def rec_similar(spark, sf_dir):
    v = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))
    return similar(v, v.where("id % 100 = 0").select("id"), 5).select("q", "id", F.round("sim", 5).alias("sim"), F.col("rank").cast("long").alias("rank"))


def _solve_sql(k: int = 4) -> str:
    """Normal equations of each row's vector, solved by elimination: one step per vector element."""
    text = _joined_sql("user_hour") + f""", a0 AS (SELECT u, i, c, sum(CASE WHEN c < {k} THEN q[i + 1] * q[c + 1] ELSE q[i + 1] * r END) + CASE WHEN i = c THEN 0.05 * count(*) ELSE 0 END AS x
FROM j, range({k}) s(i), range({k + 1}) t(c) GROUP BY u, i, c)"""
    for s in range(k):
        text += f", a{s + 1} AS (SELECT a.u, a.i, a.c, CASE WHEN a.i = {s} THEN a.x ELSE a.x - m.x * t.x / d.x END AS x FROM a{s} a JOIN a{s} m ON m.u = a.u AND m.i = a.i AND m.c = {s} JOIN a{s} t ON t.u = a.u AND t.i = {s} AND t.c = a.c JOIN a{s} d ON d.u = a.u AND d.i = {s} AND d.c = {s})"
    return text + f" SELECT b.u, CAST(b.i AS INT) AS pos, round(b.x / d.x, 5) AS value FROM a{k} b JOIN a{k} d ON d.u = b.u AND d.i = b.i AND d.c = b.i WHERE b.c = {k}"


@query(_solve_sql())
def rec_fold_in(spark, sf_dir):
    r, f = _start(spark, sf_dir, "user_hour")
    return fold_in(r, f, 0.05).select("u", F.posexplode("vec").alias("pos", "value")).select("u", "pos", F.round("value", 5).alias("value"))


def _ranked(spark, sf_dir):
    r, f = _start(spark, sf_dir, "cust_part")
    a, b = hash_split(r, 200)
    users = r.where("u % 100 = 0").select("u").distinct()
    top = top_items(users, f, a.join(users, "u", "left_semi"), 10)
    return top, b.where("r >= 25").join(users, "u", "left_semi").select("u", "v")


_RANK_SQL = "WITH " + _factor_sql("cust_part") + f""", us AS ({_USERS}), a AS (SELECT * FROM r WHERE {split_hash()} >= 200), rel AS (SELECT u, v FROM r WHERE {split_hash()} < 200 AND r >= 25 AND u IN (SELECT u FROM us)),
s AS (SELECT x.id AS u, y.id AS v, list_inner_product(x.vec, y.vec) AS score FROM f x, f y WHERE x.side = 'p' AND y.side = 'q' AND x.id IN (SELECT u FROM us) AND NOT EXISTS (SELECT 1 FROM a WHERE a.u = x.id AND a.v = y.id)),
k AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY score DESC, v) AS rank FROM s) z WHERE rank <= 10),
per AS (SELECT k.u, count(rel.v) AS hits, sum(CASE WHEN rel.v IS NULL THEN 0 ELSE 1 / log2(k.rank + 1) END) AS dcg FROM k LEFT JOIN rel ON rel.u = k.u AND rel.v = k.v GROUP BY k.u),
w AS (SELECT u, count(*) AS m FROM rel GROUP BY u)"""


@query(_RANK_SQL + " SELECT round(avg(coalesce(hits, 0) / 10.0), 6) AS precision_at_k, round(avg(coalesce(hits, 0) / m), 6) AS recall_at_k, round(avg(coalesce(dcg, 0) / list_sum(list_transform(range(1, least(m, 10) + 1), lambda i: 1 / log2(i + 1)))), 6) AS ndcg_at_k FROM w LEFT JOIN per USING (u)")
def rec_quality(spark, sf_dir):
    got = measures.ranking_quality(*_ranked(spark, sf_dir), 10)
    return got.select(*[F.round(c, 6).alias(c) for c in got.columns])


@query(_RANK_SQL + " SELECT round(count(DISTINCT k.v) / (SELECT count(*) FROM f WHERE side = 'q'), 6) AS coverage FROM k")
def rec_coverage(spark, sf_dir):
    top, _ = _ranked(spark, sf_dir)
    items = rating_view(spark, sf_dir, "cust_part").agg(F.countDistinct("v").alias("m"))
    return top.agg(F.countDistinct("v").alias("n")).crossJoin(items).select(F.round(F.col("n") / F.col("m"), 6).alias("coverage"))  # one row each
