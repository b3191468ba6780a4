"""Operators around the methods: scans, joins, aggregates, windows, set operations, functions. DataFrame API here, SQL as oracle."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from blockmf.functions.vectors import dot, norm2, register
from blockmf.sources.tables import check_ratings, rating_view, read_table, view_sql

QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f"rel_{f.__name__}"] = f
        if sql is not None:
            SQL[f"rel_{f.__name__}"] = sql
        return f

    return keep


def t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return read_table(spark, sf_dir, name)


R2 = lambda c: F.round(c, 2)


@query("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_schema(spark, sf_dir):
    schema = T.StructType([T.StructField("n_nationkey", T.IntegerType()), T.StructField("n_name", T.StringType()), T.StructField("n_regionkey", T.IntegerType())])
    return spark.read.schema(schema).parquet(f"{sf_dir}/nation.parquet")


@query(f"SELECT count(*) AS n, round(sum(r), 2) AS total FROM ({view_sql('supp_part')}) x")
def triples_round_trip(spark, sf_dir):
    """Written as text lines and read again."""
    from blockmf.session import scratch_path
    from blockmf.sources import model_io

    path = scratch_path(spark, "triples")
    model_io.write_triples(rating_view(spark, sf_dir, "supp_part"), path)
    return model_io.read_triples(spark, path).agg(F.count(F.lit(1)).alias("n"), R2(F.sum("r")).alias("total"))


@query(f"SELECT count(*) AS n, round(sum(r), 2) AS total FROM ({view_sql('user_hour')}) x")
def triples_source(spark, sf_dir):
    from blockmf.session import scratch_path
    from blockmf.sources import triples

    triples.register(spark)
    path = scratch_path(spark, "triples")
    rating_view(spark, sf_dir, "user_hour").write.format("ratings_text").mode("append").save(path)
    return spark.read.format("ratings_text").load(path).agg(F.count(F.lit(1)).alias("n"), R2(F.sum("r")).alias("total"))


def _formats(fmt: str):
    def run(spark, sf_dir):
        from blockmf.session import scratch_path

        path = scratch_path(spark, fmt)
        c = t(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_acctbal")
        c.write.format(fmt).save(path)
        return spark.read.format(fmt).schema(c.schema).load(path)

    QUERIES[f"rel_source_{fmt}"] = run
    SQL[f"rel_source_{fmt}"] = "SELECT c_custkey, c_name, c_acctbal FROM customer"


for _f in ("csv", "json", "orc"):
    _formats(_f)


@query("SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey % 10 = 3")
def sink_bucketed(spark, sf_dir):
    """Partitioned and sorted sink, read back with partition pruning."""
    from blockmf.session import scratch_path

    path = scratch_path(spark, "parts")
    c = t(spark, sf_dir, "customer").withColumn("b", (F.col("c_custkey") % 10).cast("int"))
    c.repartition("b").sortWithinPartitions("c_custkey").write.partitionBy("b").parquet(path)
    return spark.read.parquet(path).where("b = 3").select("c_custkey", "c_mktsegment")


@query("SELECT l_orderkey AS k, CAST(l_quantity AS BIGINT) AS q, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def project(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_quantity").cast("long").alias("q"), F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("SELECT o_orderkey, o_orderpriority FROM orders WHERE o_totalprice BETWEEN 50000 AND 150000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'O%' AND o_custkey IS NOT NULL")
def filters(spark, sf_dir):
    return t(spark, sf_dir, "orders").where(F.col("o_totalprice").between(50000, 150000) & F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").like("O%") & F.col("o_custkey").isNotNull()).select("o_orderkey", "o_orderpriority")


_JOIN = "SELECT o_custkey, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"


def _join(hint: str):
    def run(spark, sf_dir):
        o, li = t(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), t(spark, sf_dir, "lineitem").select("l_orderkey", "l_extendedprice")
        j = li.join(o.hint(hint) if hint else o, F.col("l_orderkey") == F.col("o_orderkey"))
        return j.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), R2(F.sum("l_extendedprice")).alias("total"))

    QUERIES[f"rel_join_{hint}"] = run
    SQL[f"rel_join_{hint}"] = _JOIN


for _h in ("merge", "shuffle_hash"):
    _join(_h)


@query("SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark, sf_dir):
    n = t(spark, sf_dir, "nation").join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # fixed dimension tables
    return t(spark, sf_dir, "supplier").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name", "r_name")


_STRIPES = [(i, i * 200, (i + 1) * 200) for i in range(8)]


@query("WITH s AS (SELECT i AS idx, i * 200 AS lo, (i + 1) * 200 AS hi FROM range(8) t(i)) SELECT CAST(idx AS INT) AS idx, count(*) AS n FROM customer JOIN s ON c_custkey >= lo AND c_custkey < hi GROUP BY idx")
def join_range(spark, sf_dir):
    """Ids to stripes: the stripes are metadata of stated size, so their side is broadcast."""
    s = spark.createDataFrame(_STRIPES, "idx int, lo long, hi long")
    c = t(spark, sf_dir, "customer").select("c_custkey")
    return c.join(F.broadcast(s), (F.col("c_custkey") >= F.col("lo")) & (F.col("c_custkey") < F.col("hi"))).groupBy("idx").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT n_name, r_name FROM nation, region WHERE n_nationkey % 5 > r_regionkey")
def join_theta(spark, sf_dir):
    return t(spark, sf_dir, "nation").join(F.broadcast(t(spark, sf_dir, "region")), F.col("n_nationkey") % 5 > F.col("r_regionkey")).select("n_name", "r_name")


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def join_left(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT coalesce(a.k, b.k) AS k, a.n AS n_cust, b.n AS n_supp FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_nationkey < 20 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_nationkey > 5 GROUP BY 1) b ON a.k = b.k")
def join_full(spark, sf_dir):
    a = t(spark, sf_dir, "customer").where("c_nationkey < 20").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("n_cust"))
    b = t(spark, sf_dir, "supplier").where("s_nationkey > 5").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("n_supp"))
    return a.join(b, "k", "full")


@query("SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)")
def join_semi(spark, sf_dir):
    return t(spark, sf_dir, "part").join(t(spark, sf_dir, "lineitem").where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@query("SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)")
def join_anti(spark, sf_dir):
    return t(spark, sf_dir, "part").join(t(spark, sf_dir, "lineitem").where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey")


@query("SELECT e.event_id, p.event_id AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'click') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts >= p.ts")
def join_asof(spark, sf_dir):
    """Last purchase of the user at or before each click: a union in time order and a running last value, so each user's rows pass once."""
    e = t(spark, sf_dir, "events").where("event_type in ('click', 'purchase')").select("event_id", "user_id", "ts", "event_type")
    buy = F.col("event_type") == "purchase"
    w = Window.partitionBy("user_id").orderBy("ts", F.when(buy, 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("last_purchase", F.last(F.when(buy, F.col("event_id")), ignorenulls=True).over(w)).where(~buy).select("event_id", "last_purchase")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def join_interval(spark, sf_dir):
    """Equi-join on user and time bin (each row meets its own and the next bin), then the interval test."""
    e = t(spark, sf_dir, "events").select("event_id", "user_id", "ts").withColumn("bin", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 7_200_000_000))
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), F.explode(F.array(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), "bin")
    return a.join(b, ["user_id", "bin"]).where("tb > ta AND tb <= ta + INTERVAL 2 HOUR").select("a", "b")


@query("SELECT n_nationkey, i AS part FROM nation, range(3) t(i)")
def lateral_explode(spark, sf_dir):
    return t(spark, sf_dir, "nation").select("n_nationkey", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(2).cast("long"))).alias("part"))


@query("SELECT o_custkey, list_sort(list(o_orderkey)) [1] AS first_key, count(*) AS n FROM orders GROUP BY o_custkey")
def agg_collect(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.array_sort(F.collect_list("o_orderkey"))[0].alias("first_key"), F.count(F.lit(1)).alias("n"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"))


@query("SELECT true AS near_count, true AS near_median")
def agg_sketches(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem")
    return li.agg((F.abs(F.approx_count_distinct("l_partkey") / F.countDistinct("l_partkey") - 1) < 0.1).alias("near_count"), (F.abs(F.percentile_approx("l_quantity", 0.5, 1000) - F.percentile("l_quantity", 0.5)) <= 1).alias("near_median"))


for _kind in ("rollup", "cube"):
    def _cube(spark, sf_dir, kind=_kind):
        li = t(spark, sf_dir, "lineitem")
        return getattr(li, kind)("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), R2(F.sum("l_quantity")).alias("q"))

    QUERIES[f"rel_agg_{_kind}"] = _cube
    SQL[f"rel_agg_{_kind}"] = f"SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY {_kind}(l_returnflag, l_linestatus)"


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, sf_dir):
    a, b = F.col("l_returnflag"), F.col("l_linestatus")
    return t(spark, sf_dir, "lineitem").groupingSets([[a], [b], []], a, b).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, coalesce(sum(CASE WHEN event_type = 'click' THEN 1 END), 0) AS click, coalesce(sum(CASE WHEN event_type = 'purchase' THEN 1 END), 0) AS purchase FROM events GROUP BY user_id")
def pivot(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT p_partkey, 'size' AS what, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def unpivot(spark, sf_dir):
    p = t(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "what", "value")


@query("SELECT event_type, round(stddev_pop(value), 4) AS sd, round(var_samp(value), 3) AS var, round(corr(value, user_id), 4) AS cor, round(covar_pop(value, user_id), 2) AS cov, round(regr_slope(value, user_id), 6) AS slope FROM events GROUP BY 1")
def agg_moments(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.stddev_pop("value"), 4).alias("sd"), F.round(F.var_samp("value"), 3).alias("var"), F.round(F.corr("value", "user_id"), 4).alias("cor"), F.round(F.covar_pop("value", "user_id"), 2).alias("cov"), F.round(F.regr_slope("value", "user_id"), 6).alias("slope"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 4) AS med, round(quantile_cont(value, 0.9), 4) AS p90 FROM events GROUP BY 1")
def agg_quantiles(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 4).alias("med"), F.round(F.percentile("value", 0.9), 4).alias("p90"))


@query("SELECT l_returnflag, count(*) FILTER (l_quantity > 25) AS n_big, round(sum(CASE WHEN l_discount > 0.05 THEN l_extendedprice END), 2) AS s FROM lineitem GROUP BY 1")
def agg_conditional(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("n_big"), R2(F.sum(F.when(F.col("l_discount") > 0.05, F.col("l_extendedprice")))).alias("s"))


@query("SELECT s_nationkey, arg_max(s_suppkey, s_acctbal) AS richest, arg_min(s_suppkey, s_acctbal) AS poorest FROM supplier GROUP BY 1")
def agg_arg_extremes(spark, sf_dir):
    return t(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.max_by("s_suppkey", "s_acctbal").alias("richest"), F.min_by("s_suppkey", "s_acctbal").alias("poorest"))


@query("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr, ntile(3) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def window_ranks(spark, sf_dir):
    w, p = Window.partitionBy("o_custkey").orderBy("o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(p).cast("long").alias("rk"), F.dense_rank().over(p).cast("long").alias("dr"), F.ntile(3).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def window_values(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(full).alias("second"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS avg3, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW), 6) AS near FROM events")
def window_frames(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t(spark, sf_dir, "events").select("event_id", F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("avg3"), F.round(F.sum("value").over(w.rangeBetween(-500, 0)), 6).alias("near"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def sort_topk(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query("SELECT k, 'c' AS side FROM (SELECT DISTINCT c_nationkey AS k FROM customer) x UNION ALL SELECT k, 's' FROM (SELECT DISTINCT s_nationkey AS k FROM supplier) y")
def union_by_name(spark, sf_dir):
    a = t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).distinct().withColumn("side", F.lit("c"))
    b = t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k")).distinct().select(F.lit("s").alias("side"), "k")
    return a.unionByName(b)


@query("SELECT l_partkey AS k FROM lineitem WHERE l_quantity < 5 INTERSECT SELECT l_partkey FROM lineitem WHERE l_quantity > 45")
def intersect(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem")
    return li.where("l_quantity < 5").select(F.col("l_partkey").alias("k")).intersect(li.where("l_quantity > 45").select("l_partkey"))


@query("SELECT l_partkey AS k FROM lineitem WHERE l_quantity < 5 EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_quantity > 45")
def except_all(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem")
    return li.where("l_quantity < 5").select(F.col("l_partkey").alias("k")).exceptAll(li.where("l_quantity > 45").select("l_partkey"))


@query("SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE (l_orderkey * 7919 + l_partkey * 104729 + 3) % 1000 < 50")
def sample_hash(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").where("(l_orderkey * 7919 + l_partkey * 104729 + 3) % 1000 < 50").select("l_orderkey", "l_linenumber", "l_partkey")


@query("SELECT true AS about_a_tenth, true AS strata_kept")
def sample_random(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    n = e.agg(F.count(F.lit(1)).alias("n"))
    s = e.sample(0.1, 3).agg(F.count(F.lit(1)).alias("s"))
    b = e.sampleBy("event_type", {"click": 1.0}, 3).agg(F.count(F.lit(1)).alias("b"), F.count_if(F.col("event_type") != "click").alias("others"))
    return n.crossJoin(s).crossJoin(b).select((F.abs(F.col("s") / F.col("n") - 0.1) < 0.03).alias("about_a_tenth"), ((F.col("others") == 0) & (F.col("b") > 0)).alias("strata_kept"))  # one row each


@query("SELECT doc_id, length(text) AS n, lower(substring(trim(text), 1, 5)) AS head, len(string_split(text, ' ')) AS words, replace(source, 'src', 's') AS s, concat_ws('-', lang, source) AS ls FROM documents")
def strings(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.length("text").cast("long").alias("n"), F.lower(F.substring(F.trim("text"), 1, 5)).alias("head"), F.size(F.split("text", " ", -1)).cast("long").alias("words"), F.replace("source", F.lit("src"), F.lit("s")).alias("s"), F.concat_ws("-", "lang", "source").alias("ls"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, isodow(o_orderdate) AS dow, date_trunc('month', o_orderdate) AS mon, date_diff('day', CAST('1990-01-01' AS DATE), CAST(o_orderdate AS DATE)) AS days FROM orders")
def dates(spark, sf_dir):
    d = F.col("o_orderdate")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), (F.weekday(d) + 1).cast("long").alias("dow"), F.date_trunc("month", d).cast("timestamp_ntz").alias("mon"), F.datediff(d, F.lit("1990-01-01")).cast("long").alias("days"))


@query("SELECT event_id, round(abs(value - 50), 4) AS a, round(sqrt(value), 4) AS s, round(ln(value + 1), 4) AS l, round(exp(value / 100), 4) AS e, CAST(floor(value) AS BIGINT) AS f, CAST(ceil(value) AS BIGINT) AS c, greatest(value, 50.0) AS g, sign(value - 50) AS sg, user_id % 7 AS p FROM events")
def maths(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events").select("event_id", F.round(F.abs(v - 50), 4).alias("a"), F.round(F.sqrt(v), 4).alias("s"), F.round(F.ln(v + 1), 4).alias("l"), F.round(F.exp(v / 100), 4).alias("e"), F.floor(v).alias("f"), F.ceil(v).alias("c"), F.greatest(v, F.lit(50.0)).alias("g"), F.signum(v - 50).cast("int").alias("sg"), F.pmod("user_id", F.lit(7)).alias("p"))


@query("SELECT vec_id, round(list_inner_product(embedding, embedding), 4) AS n2, round(CAST(list_max(embedding) AS DOUBLE), 5) AS mx, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(CAST(embedding[3] AS DOUBLE), 5) AS third FROM embeddings")
def arrays(spark, sf_dir):
    e = F.col("embedding").cast("array<double>")
    return t(spark, sf_dir, "embeddings").select("vec_id", F.round(norm2(e), 4).alias("n2"), F.round(F.array_max(e), 5).alias("mx"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("pos"), F.round(F.element_at(e, 3), 5).alias("third"))


@query("SELECT user_id, event_type AS key, count(*) AS value FROM events GROUP BY 1, 2")
def maps(spark, sf_dir):
    """Sparse rows as maps, opened again."""
    per = t(spark, sf_dir, "events").groupBy("user_id", "event_type").count()
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return m.select("user_id", F.explode(F.transform_values("m", lambda k, v: v)).alias("key", "value"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT p_partkey, coalesce(nullif(p_size, 10), -1) AS size, CASE WHEN p_retailprice > 1000 THEN 'high' WHEN p_retailprice > 500 THEN 'mid' ELSE 'low' END AS class FROM part")
def conditionals(spark, sf_dir):
    p = F.col("p_retailprice")
    return t(spark, sf_dir, "part").select("p_partkey", F.coalesce(F.nullif("p_size", F.lit(10)), F.lit(-1)).alias("size"), F.when(p > 1000, "high").when(p > 500, "mid").otherwise("low").alias("class"))


_SUB = "SELECT o_orderkey FROM {o} o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {o}) AND o_custkey IN (SELECT c_custkey FROM {c} WHERE c_acctbal > 5000) AND EXISTS (SELECT 1 FROM {l} WHERE l_orderkey = o.o_orderkey AND l_quantity > 45)"


@query(_SUB.format(o="orders", c="customer", l="lineitem"))
def subqueries(spark, sf_dir):
    return spark.sql(_SUB, o=t(spark, sf_dir, "orders"), c=t(spark, sf_dir, "customer"), l=t(spark, sf_dir, "lineitem"))


@query("WITH RECURSIVE f(n, a, b) AS (SELECT 1, 1, 1 UNION ALL SELECT n + 1, b, a + b FROM f WHERE n < 15) SELECT n, a FROM f")
def recursive_cte(spark, sf_dir):
    return spark.sql("WITH RECURSIVE f(n, a, b) AS (SELECT 1, 1, 1 UNION ALL SELECT n + 1, b, a + b FROM f WHERE n < 15) SELECT n, a FROM f")


@query("SELECT vec_id, round(list_inner_product(embedding, embedding), 4) AS d FROM embeddings")
def sql_functions(spark, sf_dir):
    register(spark)
    return t(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e")).select("vec_id", F.round(F.expr("mf_dot(e, e)"), 4).alias("d"))


@query("SELECT event_id, round(value * 2 + 1, 4) AS x FROM events")
def udf_pandas(spark, sf_dir):
    from pyspark.sql.pandas.functions import PandasUDFType

    twice = F.pandas_udf(lambda s: s * 2 + 1, "double", PandasUDFType.SCALAR)
    return t(spark, sf_dir, "events").select("event_id", F.round(twice("value"), 4).alias("x"))


@query("SELECT event_type, round(sum(value * value), 3) AS s FROM events GROUP BY 1")
def udaf_pandas(spark, sf_dir):
    from pyspark.sql.pandas.functions import PandasUDFType

    squares = F.pandas_udf(lambda s: float((s * s).sum()), "double", PandasUDFType.GROUPED_AGG)
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.round(squares("value"), 3).alias("s"))


@query("SELECT CAST(i AS INT) AS bi, CAST(j AS INT) AS bj FROM range(6) t(i), range(9) u(j)")
def udtf_grid(spark, sf_dir):
    @F.udtf(returnType="bi int, bj int")
    class Cells:
        def eval(self, n: int, m: int):
            for i in range(n):
                for j in range(m):
                    yield i, j

    return Cells(F.lit(6), F.lit(9))


@query("SELECT user_id, count(*) AS n, round(max(value) - min(value), 4) AS spread FROM events GROUP BY 1")
def grouped_map(spark, sf_dir):
    import pyarrow as pa
    import pyarrow.compute as pc

    def spread(rows):
        v = rows.column("value")
        return pa.table({"user_id": [rows.column("user_id")[0].as_py()], "n": [rows.num_rows], "spread": [pc.max(v).as_py() - pc.min(v).as_py()]})

    return t(spark, sf_dir, "events").select("user_id", "value").groupBy("user_id").applyInArrow(spread, "user_id long, n long, spread double").withColumn("spread", F.round("spread", 4))


@query("SELECT s_nationkey AS k, count(*) AS n_supp, (SELECT count(*) FROM customer WHERE c_nationkey = s_nationkey) AS n_cust FROM supplier GROUP BY 1")
def cogrouped_map(spark, sf_dir):
    import pyarrow as pa

    def both(key, a, b):
        return pa.table({"k": pa.array([key[0].as_py()], pa.int32()), "n_supp": [a.num_rows], "n_cust": [b.num_rows]})

    a, b = t(spark, sf_dir, "supplier").select("s_nationkey"), t(spark, sf_dir, "customer").select("c_nationkey")
    return a.groupBy("s_nationkey").cogroup(b.groupBy("c_nationkey")).applyInArrow(both, "k int, n_supp long, n_cust long").where("n_supp > 0")


@query("SELECT CAST(6 AS BIGINT) AS parts, true AS pinned")
def partition_control(spark, sf_dir):
    """Rows of one stripe are in one partition."""
    c = t(spark, sf_dir, "customer").withColumn("stripe", (F.col("c_custkey") % 6).cast("int"))
    p = c.repartitionById(6, F.col("stripe")).withColumn("p", F.spark_partition_id())
    return p.groupBy("stripe").agg(F.countDistinct("p").alias("n")).agg(F.count(F.lit(1)).alias("parts"), (F.max("n") == 1).alias("pinned"))


@query("SELECT source, count(*) AS n, round(avg(n_chars), 4) AS mean FROM documents GROUP BY source")
def salted_aggregate(spark, sf_dir):
    """Two-level aggregate with a salt: a hot source is summed in several tasks first."""
    d = t(spark, sf_dir, "documents").withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(16)))
    part = d.groupBy("source", "salt").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("s"))
    return part.groupBy("source").agg(F.sum("n").alias("n"), F.sum("s").alias("s")).select("source", "n", F.round(F.col("s") / F.col("n"), 4).alias("mean"))


@query("SELECT count(*) AS n, round(sum(value), 2) AS total FROM events")
def observed(spark, sf_dir):
    """Metrics that are read off a running query."""
    from pyspark.sql import Observation

    o = Observation("events")
    t(spark, sf_dir, "events").observe(o, F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(o.get["n"], o.get["total"])], "n long, total double").select("n", R2("total").alias("total"))


for _rule, _fn in (("avg", "avg(l_quantity)"), ("sum", "sum(l_quantity)"), ("max", "max(l_quantity)"), ("count", "CAST(count(*) AS DOUBLE)")):
    def _dup(spark, sf_dir, rule=_rule):
        cells = t(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v"), F.col("l_quantity").alias("r"))
        return check_ratings(cells, rule).select("u", "v", F.round("r", 6).alias("r"))

    QUERIES[f"rel_cells_{_rule}"] = _dup
    SQL[f"rel_cells_{_rule}"] = f"SELECT l_suppkey AS u, l_partkey AS v, round({_fn}, 6) AS r FROM lineitem GROUP BY 1, 2"


@query(f"WITH r AS ({view_sql('user_hour')}), m AS (SELECT avg(r) AS m, min(r) AS lo, max(r) AS hi FROM r) SELECT u, v, round(r - m, 6) AS centred, round((r - lo) / (hi - lo), 6) AS unit, round(ln(1 + r), 6) AS logged, round(least(greatest(r, 1), 4), 6) AS clipped FROM r, m")
def transforms(spark, sf_dir):
    r = rating_view(spark, sf_dir, "user_hour")
    m = r.agg(F.avg("r").alias("m"), F.min("r").alias("lo"), F.max("r").alias("hi"))
    j = r.crossJoin(F.broadcast(m))  # one row
    return j.select("u", "v", F.round(F.col("r") - F.col("m"), 6).alias("centred"), F.round((F.col("r") - F.col("lo")) / (F.col("hi") - F.col("lo")), 6).alias("unit"), F.round(F.log1p("r"), 6).alias("logged"), F.round(F.least(F.greatest("r", F.lit(1.0)), F.lit(4.0)), 6).alias("clipped"))


@query("SELECT label, round(avg(list_inner_product(embedding, embedding)), 4) AS mean_norm FROM embeddings GROUP BY label")
def cached(spark, sf_dir):
    """A table that is used twice is kept for the time of use."""
    e = t(spark, sf_dir, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("e")).persist()
    e.count()
    got = e.groupBy("label").agg(F.round(F.avg(dot(F.col("e"), F.col("e"))), 4).alias("mean_norm"))
    return got
