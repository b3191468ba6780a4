"""Prediction, objective, gradients and full gradient descent, all as joins, projections and aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockmf.functions.vectors import dot, norm2, plus
from blockmf.operators.factors import with_vectors
from blockmf.operators.params import MFParams
from blockmf.session import cut


def score(ratings: DataFrame, factors: DataFrame) -> DataFrame:
    """u, v, r, r_hat."""
    return with_vectors(ratings, factors).select("u", "v", "r", dot(F.col("p"), F.col("q")).alias("r_hat"))


def cell_loss(lam_p: float, lam_q: float) -> Column:
    """Loss of one observed cell, over columns r, p, q: squared residual and the penalties of its two vectors."""
    res = F.col("r") - dot(F.col("p"), F.col("q"))
    return res * res + lam_p * norm2(F.col("p")) + lam_q * norm2(F.col("q"))


def loss(ratings: DataFrame, factors: DataFrame, lam_p: float, lam_q: float, penalty: str = "per_cell") -> DataFrame:
    """One row: loss. penalty: counted for every observed cell, or once per vector."""
    rows = with_vectors(ratings, factors)
    if penalty == "per_cell":
        return rows.agg(F.sum(cell_loss(lam_p, lam_q)).alias("loss"))
    res = F.col("r") - dot(F.col("p"), F.col("q"))
    fit = rows.agg(F.sum(res * res).alias("part"))
    lam = F.when(F.col("side") == "p", lam_p).otherwise(lam_q)
    return fit.unionByName(factors.agg(F.sum(lam * norm2(F.col("vec"))).alias("part"))).agg(F.sum("part").alias("loss"))


def cell_gradients(ratings: DataFrame, factors: DataFrame, params: MFParams) -> DataFrame:
    """u, v, grad_p, grad_q of each cell's loss."""
    rows = with_vectors(ratings, factors).withColumn("e", F.col("r") - dot(F.col("p"), F.col("q")))
    g = params.grad_scale
    gp = F.zip_with("p", "q", lambda p, q: g * (params.lam_p * p - F.col("e") * q))
    gq = F.zip_with("p", "q", lambda p, q: g * (params.lam_q * q - F.col("e") * p))
    return rows.select("u", "v", gp.alias("grad_p"), gq.alias("grad_q"))


def sum_gradients(ratings: DataFrame, factors: DataFrame, params: MFParams) -> DataFrame:
    """side, id, grad: sums over the cells of a row or column. Elements are summed as rows, so partial aggregation applies."""
    cells = cell_gradients(ratings, factors, params)
    long = cells.select(F.lit("p").alias("side"), F.col("u").alias("id"), F.col("grad_p").alias("g")).unionByName(cells.select(F.lit("q").alias("side"), F.col("v").alias("id"), F.col("grad_q").alias("g")))
    sums = [F.sum(F.col("g")[j]).alias(f"g{j}") for j in range(params.k)]
    return long.groupBy("side", "id").agg(*sums).select("side", "id", F.array(*[f"g{j}" for j in range(params.k)]).alias("grad"))


def apply_step(factors: DataFrame, grads: DataFrame, gamma: float) -> DataFrame:
    stepped = factors.join(grads, ["side", "id"], "left")
    return stepped.select("side", "id", F.coalesce(plus(F.col("vec"), F.col("grad"), -gamma), "vec").alias("vec"))


def gd_full(ratings: DataFrame, factors: DataFrame, params: MFParams) -> DataFrame:
    """Full gradient descent: one step over the whole objective per pass. Lineage is cut each pass."""
    for _ in range(params.epochs):
        factors = cut(apply_step(factors, sum_gradients(ratings, factors, params), params.gamma), "gd")
    return factors


