"""Other factorisations and reference predictors: alternating least squares, coordinate descent, means and biases, a device classifier."""

from __future__ import annotations

from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockmf.functions.vectors import dot
from blockmf.operators.factors import with_vectors
from blockmf.operators.params import MFParams
from blockmf.session import cut


def als(ratings: DataFrame, params: MFParams) -> DataFrame:
    """Alternating least squares of Spark's library; same factor table. Ids must be below 2^31."""
    from pyspark.ml.recommendation import ALS

    rows = ratings.select(F.col("u").cast("int").alias("u"), F.col("v").cast("int").alias("v"), F.col("r").cast("float").alias("r"))
    m = ALS(rank=params.k, maxIter=params.epochs, regParam=params.lam_p, userCol="u", itemCol="v", ratingCol="r", seed=params.seed, coldStartStrategy="drop").fit(rows)
    to = lambda df, s: df.select(F.lit(s).alias("side"), F.col("id").cast("long").alias("id"), F.col("features").cast("array<double>").alias("vec"))
    return to(m.userFactors, "p").unionByName(to(m.itemFactors, "q"))


def ccd_sweep(ratings: DataFrame, factors: DataFrame, params: MFParams) -> DataFrame:
    """One sweep of coordinate descent: column by column of the factors, first all row scalars, then all column scalars, each in closed form
    from the residuals: x = sum((e + x y) y) / (lam * cells + sum(y^2)). Penalties count per cell."""
    for j in range(params.k):
        for me, lam in (("p", params.lam_p), ("q", params.lam_q)):
            key, other = ("u", "q") if me == "p" else ("v", "p")
            rows = with_vectors(ratings, factors)
            e = F.col("r") - dot(F.col("p"), F.col("q"))
            x, y = F.col(me)[j], F.col(other)[j]
            new = rows.groupBy(F.col(key).alias("id")).agg((F.sum((e + x * y) * y) / (lam * F.count(F.lit(1)) + F.sum(y * y))).alias("new"))
            new = new.withColumn("side", F.lit(me))
            joined = factors.join(new, ["side", "id"], "left")
            vec = F.when(F.col("new").isNull(), F.col("vec")).otherwise(F.transform("vec", lambda a, i: F.when(i == j, F.col("new")).otherwise(a)))
            factors = cut(joined.select("side", "id", vec.alias("vec")), "ccd")
    return factors


def ccd(ratings: DataFrame, factors: DataFrame, params: MFParams) -> DataFrame:
    for _ in range(params.epochs):
        factors = ccd_sweep(ratings, factors, params)
    return factors


def mean_model(train: DataFrame, test: DataFrame) -> DataFrame:
    """One row: rmse of the global mean of the training cells."""
    mean = train.agg(F.avg("r").alias("m"))
    return test.crossJoin(F.broadcast(mean)).agg(F.sqrt(F.avg((F.col("r") - F.col("m")) ** 2)).alias("rmse"))  # one row


def bias_model(train: DataFrame, test: DataFrame) -> DataFrame:
    """One row: rmse of mean + row bias + column bias (each the mean deviation; none for unseen ids)."""
    mean = F.broadcast(train.agg(F.avg("r").alias("m")))
    bu = train.crossJoin(mean).groupBy("u").agg(F.avg(F.col("r") - F.col("m")).alias("bu"))
    bv = train.crossJoin(mean).join(bu, "u").groupBy("v").agg(F.avg(F.col("r") - F.col("m") - F.col("bu")).alias("bv"))
    rows = test.crossJoin(mean).join(bu, "u", "left").join(bv, "v", "left")
    hat = F.col("m") + F.coalesce("bu", F.lit(0.0)) + F.coalesce("bv", F.lit(0.0))
    return rows.agg(F.sqrt(F.avg((F.col("r") - hat) ** 2)).alias("rmse"))


def device_classifier(tasks: DataFrame, depth: int = 4):
    """Static assignment by a classifier: a decision tree from task features (n_rows, n_cols, nnz, k) to a class of shares, trained on labelled tasks
    (column label, 0 .. classes - 1). Returns the fitted pipeline model; transform() adds prediction."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import DecisionTreeClassifier
    from pyspark.ml.feature import VectorAssembler

    gather = VectorAssembler(inputCols=["n_rows", "n_cols", "nnz", "k"], outputCol="features")
    return Pipeline(stages=[gather, DecisionTreeClassifier(maxDepth=depth, labelCol="label", seed=1)]).fit(tasks)


def block_tasks(ratings: DataFrame, cost, n: int, w: int, classes: int = 5, halvings: int = 5) -> DataFrame:
    """Training tasks for the classifier: the blocks of the ratings in grids of 1, 2, 4 .. 2^halvings stripes each way (ids scattered), with the ids of their stripes; the
    label is the class of the balanced share under a cost model. The driver gets the blocks of the finest grid, the rows of coarser ones are sums of theirs."""
    from blockmf.functions.ids import PRIME, mixed
    from blockmf.plans.balance import balance

    spark, parts = ratings.sparkSession, 1 << halvings
    cells = cut(ratings.select("u", "v", *[F.expr(f"cast({mixed(c, i)} * {parts} div {PRIME} as int)").alias(f"b{c}") for i, c in enumerate("uv")]), "cells")
    blocks = {(r["bu"], r["bv"]): r["count"] for r in cells.groupBy("bu", "bv").count().collect()}
    ids = {c: {r[f"b{c}"]: r["count"] for r in cells.select(c, f"b{c}").distinct().groupBy(f"b{c}").count().collect()} for c in "uv"}
    rows = []
    for level in range(halvings + 1):
        nnz: Counter = Counter()
        held = {c: Counter() for c in "uv"}
        for (i, j), count in blocks.items():
            nnz[i >> level, j >> level] += count
        for c, stripes in ids.items():
            for i, count in stripes.items():
                held[c][i >> level] += count
        for (i, j), count in sorted(nnz.items()):
            alpha = balance(lambda s: cost("wide", s), lambda s: cost("narrow", s), count, n, w)
            rows += [(held["u"][i], held["v"][j], count, k, float(min(classes - 1, int(alpha * classes)))) for k in (8, 32, 128)]
    return spark.createDataFrame(rows, "n_rows long, n_cols long, nnz long, k int, label double")
