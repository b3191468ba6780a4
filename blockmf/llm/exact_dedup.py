"""Exact dedup: group by a 128-bit content hash, keep one stable id, compare bytes inside the groups.

Texts are equal when they are identical after lower-casing A-Z; a null text counts as empty. Partial
aggregation leaves at most one row per distinct text and map task before the shuffle, so a group that holds a
third of all rows does not load one task. The bytes are compared by carrying the least and the greatest text of
a group through that aggregate: they differ exactly if the hash collided, and such groups are then grouped by
their text.

Edge cases. Null text: as empty. Null id: never the id that stays unless all ids of the group are null.
Rows that repeat an id and its text are the same document: exact_groups() marks all of them as kept if that id stays, and
group_size counts rows; drop_copies() leaves one of them. Rows that repeat an id with different texts are told apart by their texts. Empty table: empty result. Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockmf.llm.common import ascii_lower, cut, text_or_empty


def content_hash(norm: Column) -> Column:
    return F.unhex(F.md5(norm))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stays: str = "min", hash_of: Callable[[Column], Column] = content_hash) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256. stays: 'min' or 'max' id of a group."""
    pick = {"min": F.min, "max": F.max}[stays]
    rows = docs.select(F.col(id_col).alias("id"), ascii_lower(text_or_empty(text_col)).alias("norm"))
    hashed = rows.withColumn("h", hash_of(F.col("norm")))
    groups = hashed.groupBy("h").agg(pick("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"), F.min("norm").alias("lo"), F.max("norm").alias("hi"))
    groups = cut(groups.select("h", "keep_id", "group_size", (F.col("lo") != F.col("hi")).alias("clash")), "exact-groups")
    # a group of a thousandth of the rows or more (so there are at most a thousand) meets its rows by broadcast; the others by hash, where the rows that
    # are served already are spread by their ids
    total = groups.agg(F.sum("group_size")).first()[0] or 0
    whole = groups.where(~F.col("clash")).select("h", "keep_id", "group_size")
    hot = whole.where(F.col("group_size") * 1000 >= total).select("h", F.col("keep_id").alias("hot_id"), F.col("group_size").alias("hot_size"))
    prints = hashed.select("id", "h", F.sha2("norm", 256).alias("text_sha256")).join(F.broadcast(hot), "h", "left")
    served = F.col("hot_size").isNotNull()
    spread = F.concat("h", F.when(served, F.coalesce(F.col("id").cast("string"), F.lit("-")).cast("binary")).otherwise(F.lit(b"")))
    cold = whole.where(F.col("group_size") * 1000 < total).withColumnRenamed("h", "key")
    met = prints.withColumn("key", spread).join(cold, "key", "left").where(served | F.col("group_size").isNotNull())
    found = met.select("id", "h", "text_sha256", F.when(served, F.col("hot_id")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce("hot_size", "group_size").alias("group_size"))
    if not groups.where("clash").isEmpty():
        bad = groups.where("clash").select("h")
        both = hashed.join(bad, "h", "left_semi")
        true_groups = both.groupBy("norm").agg(pick("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        split = both.join(true_groups, "norm").withColumn("text_sha256", F.sha2("norm", 256))
        found = found.unionByName(split.select(*found.columns))
    kept = F.col("id").eqNullSafe(F.col("keep_id"))
    return found.select(F.col("id").alias(id_col), "keep_id", "group_size", kept.alias("kept"), "text_sha256")


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stays: str = "max", hash_of: Callable[[Column], Column] = content_hash) -> DataFrame:
    """One row of docs for each distinct text, with all its columns: the one with the largest ('max') or smallest ('min') id. A row without an id stays
    only if no row of its group has one; of rows that repeat an id and its text, the greatest under a hash of their columns stays.
    One aggregate over content hashes, with a partial one before the shuffle; groups whose hash collided are grouped by their text."""
    plain = [F.col(f"`{f.name}`") for f in docs.schema.fields if "map<" not in f.dataType.simpleString() and f.dataType.simpleString() != "variant"]
    norm = ascii_lower(text_or_empty(text_col))
    named, number = F.col(id_col).isNotNull(), F.col(id_col)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), norm.alias("norm"), F.struct(named if stays == "max" else ~named, number, F.xxhash64(*plain)).alias("rank"))
    pick = {"min": F.min_by, "max": F.max_by}[stays]
    hashed = rows.withColumn("h", hash_of(F.col("norm")))
    groups = hashed.groupBy("h").agg(pick("row", "rank").alias("row"), F.min("norm").alias("lo"), F.max("norm").alias("hi"))
    groups = cut(groups.select("h", "row", (F.col("lo") != F.col("hi")).alias("clash")), "exact-rows")
    found = groups.where(~F.col("clash")).select("row.*")
    if not groups.where("clash").isEmpty():
        both = hashed.join(groups.where("clash").select("h"), "h", "left_semi")
        found = found.unionByName(both.groupBy("norm").agg(pick("row", "rank").alias("row")).select("row.*"))
    return found
