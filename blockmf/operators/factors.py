"""Factor tables: factors(side, id, vec); side 'p' for rows, 'q' for columns."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Constants of the closed-form start: any engine makes the same vectors. Remainders by a prime of 31 bits keep products in BIGINT; the multiplier
#: depends on the element, and ids above the prime count by their quotient too, so different ids have different vectors.
PRIME, STEP_ID, TURN_ID, STEP_HIGH, TURN_HIGH, STEP_J, SIDE = 2147483647, 1103515245, 715225739, 16807, 104729, 1181783497, 50331653


def _shift(side: str, seed: int) -> int:
    return seed * 7919 + (0 if side == "p" else SIDE)


def init_expr(side: str, k: int, seed: int, scale: float) -> str:
    """SQL text for one element, in id and j."""
    low = f"(id % {PRIME}) * (({STEP_ID} + j * {TURN_ID}) % {PRIME})"
    return f"(({low} + (id // {PRIME}) * ({STEP_HIGH} + j * {TURN_HIGH}) + (j + 1) * {STEP_J} + {_shift(side, seed)}) % {PRIME}) / {PRIME}.0 * {scale}"


def init_vector(side: str, ids: np.ndarray, k: int, seed: int, scale: float) -> np.ndarray:
    j, ids = np.arange(k, dtype=np.int64), ids.astype(np.int64)[:, None]
    low = (ids % PRIME) * ((STEP_ID + j * TURN_ID) % PRIME)
    return ((low + (ids // PRIME) * (STEP_HIGH + j * TURN_HIGH) + (j + 1) * STEP_J + _shift(side, seed)) % PRIME) / float(PRIME) * scale


def _closed(side: str, k: int, seed: int, scale: float) -> Column:
    high = F.expr(f"id div {PRIME}")

    def element(j: Column) -> Column:
        j = j.cast("long")
        low = (F.col("id") % PRIME) * ((j * TURN_ID + STEP_ID) % PRIME)
        return ((low + high * (j * TURN_HIGH + STEP_HIGH) + (j + 1) * STEP_J + _shift(side, seed)) % PRIME).cast("double") / float(PRIME) * scale

    return F.transform(F.sequence(F.lit(0), F.lit(k - 1)), element)


def init_factors(ratings: DataFrame, k: int, seed: int = 1, scale: float = 1.0, kind: str = "closed") -> DataFrame:
    """One vector per row and column that occurs. kind: 'closed' form of the id, 'rand' uniform, 'normal', or 'sqrt_mean': closed form
    scaled so that the mean prediction is the mean rating."""
    if kind == "sqrt_mean":
        mean = ratings.agg(F.avg("r")).first()[0] or 0.0
        scale = 2.0 * float(np.sqrt(max(mean, 1e-12) / k))
        kind = "closed"
    parts = []
    for side, col in (("p", "u"), ("q", "v")):
        ids = ratings.select(F.col(col).alias("id")).distinct()
        if kind == "closed":
            vec = _closed(side, k, seed, scale)
        else:
            draw = {"rand": F.rand, "normal": F.randn}[kind]
            vec = F.array(*[draw(seed * 1009 + j + (0 if side == "p" else 503)) * scale for j in range(k)])
        parts.append(ids.select(F.lit(side).alias("side"), "id", vec.alias("vec")))
    return parts[0].unionByName(parts[1])


def side(factors: DataFrame, which: str, id_name: str, vec_name: str) -> DataFrame:
    return factors.where(F.col("side") == which).select(F.col("id").alias(id_name), F.col("vec").alias(vec_name))


def with_vectors(ratings: DataFrame, factors: DataFrame, how: str = "inner") -> DataFrame:
    """ratings with columns p and q. Two equi-joins; Spark picks broadcast or merge by size."""
    return ratings.join(side(factors, "p", "u", "p"), "u", how).join(side(factors, "q", "v", "q"), "v", how)


def flat(factors: DataFrame, digits: int = 6) -> DataFrame:
    """(side, id, pos, value) rows for comparison."""
    return factors.select("side", "id", F.posexplode("vec").alias("pos", "value")).select("side", "id", F.col("pos").cast("long").alias("pos"), F.round("value", digits).alias("value"))
