"""Use of a model: top items for rows, similar items, folding in of new rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockmf.functions.vectors import cosine, dot
from blockmf.operators.factors import side


def top_items(users: DataFrame, factors: DataFrame, seen: DataFrame | None, k: int, block: int = 4096) -> DataFrame:
    """u, v, score, rank for the k best items of each user of a stated set users(u), without items that it has seen.

    Users and items are packed in blocks of about `block` vectors (one row each). A user block meets each item block once: a matrix product in
    Arrow, of which the k best of each user go on, so scores of all pairs never exist as rows."""
    p = users.select("u").distinct().join(side(factors, "p", "u", "p"), "u")
    q = side(factors, "q", "v", "q")
    parts = lambda df: max(1, -(-df.count() // block))
    had = seen.groupBy("u").agg(F.collect_set("v").alias("had")) if seen is not None else None
    mine = p.join(had, "u", "left") if had is not None else p.withColumn("had", F.lit(None).cast("array<bigint>"))
    packed_u = mine.groupBy(F.pmod(F.xxhash64("u"), F.lit(parts(p))).alias("ub")).agg(F.collect_list(F.struct("u", "p", F.coalesce("had", F.array().cast("array<bigint>")).alias("had"))).alias("users"))
    packed_v = q.groupBy(F.pmod(F.xxhash64("v"), F.lit(parts(q))).alias("vb")).agg(F.collect_list(F.struct("v", "q")).alias("items"))
    met = packed_u.crossJoin(packed_v).select("users", "items")  # blocks, not rows: (users / block) x (items / block)
    best = met.mapInArrow(_best_of_blocks(k), "u long, v long, score double")
    w = Window.partitionBy("u").orderBy(F.desc("score"), "v")
    return best.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def _best_of_blocks(k: int):
    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for people, items in zip(b.column(0), b.column(1), strict=True):
                a, c = people.values, items.values
                u, v = a.field("u").to_numpy(), c.field("v").to_numpy()
                p = a.field("p").flatten().to_numpy().reshape(len(u), -1)
                q = c.field("q").flatten().to_numpy().reshape(len(v), -1)
                score = p @ q.T
                order = np.argsort(v)
                lists = a.field("had")
                who = np.repeat(np.arange(len(u)), lists.value_lengths().to_numpy())
                had = lists.flatten().to_numpy()
                at = np.minimum(np.searchsorted(v[order], had), len(v) - 1)
                here = v[order][at] == had
                score[who[here], order[at[here]]] = -np.inf
                rank = np.lexsort((np.broadcast_to(v, score.shape), -score))[:, :k]
                rows = np.repeat(np.arange(len(u)), rank.shape[1])
                cols = rank.ravel()
                ok = np.isfinite(score[rows, cols])
                yield pa.RecordBatch.from_arrays([pa.array(u[rows[ok]]), pa.array(v[cols[ok]]), pa.array(score[rows, cols][ok])], ["u", "v", "score"])

    return best


def similar(vectors: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """vectors(id, vec), queries(id): q, id, sim, rank of the k most similar others by cosine, for a stated set of queries."""
    q = queries.select(F.col("id").alias("q")).join(vectors.select(F.col("id").alias("q"), F.col("vec").alias("qv")), "q")
    bound = 64 << 20  # bytes of the query vectors that each executor may hold
    size = q.agg(F.coalesce(F.sum(F.size("qv") * 8), F.lit(0))).first()[0]
    met = vectors.join(F.broadcast(q) if size <= bound else q).where("id != q").select("q", "id", cosine(F.col("qv"), F.col("vec")).alias("sim"))
    w = Window.partitionBy("q").orderBy(F.desc("sim"), "id")
    return met.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def fold_in(new: DataFrame, factors: DataFrame, lam: float) -> DataFrame:
    """Vectors of rows that the model does not know, by least squares with the column vectors fixed: u, vec. new(u, v, r)."""
    k = len(factors.first()["vec"])

    def solve(rows: pd.DataFrame) -> pd.DataFrame:
        q = np.array(rows["q"].tolist())
        a = q.T @ q + lam * len(rows) * np.eye(k)
        return pd.DataFrame({"u": [rows["u"].iloc[0]], "vec": [np.linalg.solve(a, q.T @ rows["r"].to_numpy()).tolist()]})

    return new.join(side(factors, "q", "v", "q"), "v").select("u", "r", "q").groupBy("u").applyInPandas(solve, "u long, vec array<double>")
