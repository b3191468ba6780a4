"""Models and traces on disk."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.operators.params import MFParams


def save_model(factors: DataFrame, params: MFParams, path: str, segments: int = 8) -> None:
    """Parquet by side and segment (so that a reader of some ids prunes files), parameters as a one-row JSON text."""
    seg = F.pmod("id", F.lit(segments)).cast("int")
    factors.withColumn("seg", seg).repartition("side", "seg").sortWithinPartitions("id").write.mode("overwrite").partitionBy("side", "seg").parquet(f"{path}/factors")
    factors.sparkSession.createDataFrame([(params.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/params")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, MFParams]:
    factors = spark.read.parquet(f"{path}/factors").select("side", F.col("id").cast("long").alias("id"), "vec")
    return factors, MFParams.from_json(spark.read.text(f"{path}/params").first()[0])


def read_triples(spark: SparkSession, path: str, sep: str = r"\s+") -> DataFrame:
    """ratings from text lines 'u v r' with any separator; lines that are not so are dropped."""
    parts = F.split(F.trim("value"), sep)
    rows = spark.read.text(path).select(parts.alias("x")).where("size(x) >= 3")
    return rows.select(F.expr("try_cast(x[0] as bigint)").alias("u"), F.expr("try_cast(x[1] as bigint)").alias("v"), F.expr("try_cast(x[2] as double)").alias("r")).where("u is not null and v is not null and r is not null")


def write_triples(ratings: DataFrame, path: str, sep: str = " ") -> None:
    ratings.select(F.concat_ws(sep, "u", "v", "r").alias("value")).write.mode("overwrite").text(path)
