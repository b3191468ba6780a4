"""Dense codes, permutations and prefix sums without a single-task window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blockmf.session import cut

#: Constants of the arithmetic hashes: remainders by a prime of 31 bits, so that products stay in BIGINT.
MULTIPLIER, SECOND, PRIME = 1103515245, 104729, 2147483647


def mixed(expr: str, seed: int = 0) -> str:
    """SQL text, equal in Spark and DuckDB: a scattered number below PRIME for a non-negative id expression."""
    return f"((({expr}) % {PRIME} * {MULTIPLIER} + ({expr}) % 997 * {SECOND} + {seed}) % {PRIME})"


def prefix_sum(df: DataFrame, order: list[str], value: Column, name: str = "cum") -> DataFrame:
    """df with the running sum of value (inclusive) in the order of distinct keys `order`.

    Two passes: range partitions are sorted and summed each for itself; the partitions' totals (one row each) are summed
    and added. The ranged rows are written once, so both passes see the same partitions.
    """
    ranged = df.withColumn("_v", value).repartitionByRange(*order).withColumn("_part", F.spark_partition_id())
    ranged = cut(ranged, "ranged")
    totals = ranged.groupBy("_part").agg(F.sum("_v").alias("_t"))
    before = totals.withColumn("_before", F.coalesce(F.sum("_t").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    local = F.sum("_v").over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return ranged.withColumn("_c", local).join(F.broadcast(before.select("_part", "_before")), "_part").withColumn(name, F.col("_c") + F.col("_before")).drop("_v", "_c", "_part", "_before")


def dense_codes(keys: DataFrame, name: str) -> DataFrame:
    """(name, code): distinct keys numbered from 0 in their order."""
    return prefix_sum(keys.select(name).distinct(), [name], F.lit(1), "_n").select(name, (F.col("_n") - 1).cast("long").alias("code"))


def permuted(ids: DataFrame, name: str, seed: int = 0) -> DataFrame:
    """(name, place): distinct non-negative ids in a seeded order, numbered from 0."""
    keyed = ids.select(name).distinct().withColumn("_h", F.expr(mixed(name, seed)))
    return prefix_sum(keyed, ["_h", name], F.lit(1), "_n").select(name, (F.col("_n") - 1).cast("long").alias("place"))
