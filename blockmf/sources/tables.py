"""Given tables, and the rating views on them: ratings(u BIGINT, v BIGINT, r DOUBLE), one row per observed cell.

Views are SQL with table names in braces, so that one text serves Spark and a DuckDB oracle. Arithmetic hashes use plain
BIGINT expressions, which both engines evaluate alike.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

#: Closed form of a vector element of the planted model: four latent columns, values in [-1, 1).
PLANTED = "((({id} * {a} + {j} * {b}) % 2003) / 1001.5E0 - 1)"


def planted_sql(pattern: str) -> str:
    p = [PLANTED.format(id="u", a=7919, j=j, b=613) for j in range(1, 5)]
    q = [PLANTED.format(id="v", a=104729, j=j, b=359) for j in range(1, 5)]
    dot = " + ".join(f"{a} * {b}" for a, b in zip(p, q, strict=True))
    return f"SELECT u, v, 3 + {dot} + 1E-1 * (((u * 31 + v * 17) % 1009) / 504.5E0 - 1) AS r FROM ({pattern}) cells"


_CUST_PART = "SELECT o_custkey AS u, l_partkey AS v, avg(l_quantity) AS r FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey GROUP BY o_custkey, l_partkey"
VIEWS = {
    "cust_part": _CUST_PART,
    "supp_part": "SELECT l_suppkey AS u, l_partkey AS v, avg(l_quantity) AS r FROM {lineitem} GROUP BY l_suppkey, l_partkey",
    "cust_supp": "SELECT o_custkey AS u, l_suppkey AS v, avg(l_quantity) AS r FROM {lineitem} JOIN {orders} ON l_orderkey = o_orderkey GROUP BY o_custkey, l_suppkey",
    "user_type": "SELECT user_id AS u, t AS v, avg(value) / 20 AS r FROM (SELECT user_id, value, dense_rank() OVER (ORDER BY event_type) - 1 AS t FROM {events}) e GROUP BY user_id, t",
    "user_hour": "SELECT user_id AS u, CAST(hour(ts) AS BIGINT) AS v, avg(value) / 20 AS r FROM {events} GROUP BY user_id, hour(ts)",
    "conv_turn": "SELECT conv_id AS u, turn AS v, CAST(max(length(text)) AS DOUBLE) AS r FROM {conversations} GROUP BY conv_id, turn",
    "doc_source": "SELECT doc_id AS u, CAST(substring(source, 4) AS BIGINT) AS v, CAST(n_chars AS DOUBLE) AS r FROM {documents}",
    "planted": planted_sql(f"SELECT u, v FROM ({_CUST_PART}) c"),
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def view_sql(name: str, **tables: str) -> str:
    """Text of a view for an engine that knows the tables by their names (or by the names given)."""
    return VIEWS[name].format(**({t: t for t in TABLES} | tables))


def rating_view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "doc_term":
        return doc_term(read_table(spark, sf_dir, "documents"))
    if name == "vec_dim":
        return read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("u"), F.posexplode("embedding").alias("v", "r")).select("u", F.col("v").cast("long").alias("v"), F.col("r").cast("double").alias("r"))
    text = VIEWS[name]
    used = {t: read_table(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in text}
    return spark.sql(text, **used).select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"), F.col("r").cast("double").alias("r"))


def doc_term(documents: DataFrame, least_df: int = 5) -> DataFrame:
    """Tokens of ASCII letters, ln(1 + tf), terms in at least least_df documents; terms are coded by rank of their text.

    Codes come from a sorted two-pass numbering (range partitions, then prefix sums of their sizes): no global window.
    """
    from blockmf.functions.ids import dense_codes

    words = documents.select(F.col("doc_id").alias("u"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"))).alias("term"))
    tf = words.groupBy("u", "term").agg(F.log1p(F.count(F.lit(1)).cast("double")).alias("r"))
    terms = tf.groupBy("term").count().where(F.col("count") >= least_df).select("term")
    return tf.join(dense_codes(terms, "term"), "term").select("u", F.col("code").alias("v"), "r")


def check_ratings(ratings: DataFrame, duplicates: str = "avg") -> DataFrame:
    """Clean ratings: rows without ids or with a value that is no finite number go; a cell that occurs several times becomes one by the rule."""
    rule = {"avg": F.avg("r"), "sum": F.sum("r"), "min": F.min("r"), "max": F.max("r"), "count": F.count("r").cast("double")}[duplicates]
    good = ratings.where("u is not null and v is not null and r is not null and not isnan(r)").where(F.abs("r") != float("inf"))
    return good.groupBy("u", "v").agg(rule.alias("r"))


def hash_split(ratings: DataFrame, test_permille: int = 70, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """(train, test) by an arithmetic hash of the cell: the same in any engine and any run."""
    h = F.expr(split_hash(seed))
    return ratings.where(h >= test_permille), ratings.where(h < test_permille)


def split_hash(seed: int = 1) -> str:
    return f"((u * 7919 + v * 104729 + {seed}) % 1000)"


def leave_last_out(events: DataFrame, n: int = 1) -> DataFrame:
    """events(user_id, ts, event_id, ...) with a column held: the last n events of each user."""
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id"))
    return events.withColumn("held", F.row_number().over(w) <= n)
