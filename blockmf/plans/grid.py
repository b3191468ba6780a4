"""Grids: rules for their size, uniform and two-region division, assignment of ratings to blocks, statistics, independence."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.functions.ids import mixed, prefix_sum
from blockmf.session import cut


def min_grid(n: int, w: int, rule: str = "refined") -> tuple[int, int]:
    """Least uniform grid for n narrow and w wide lanes. 'refined': one spare row of blocks over the lanes; 'square_plus_one': spare in both directions."""
    lanes = n + w
    return (lanes + 1, lanes) if rule == "refined" else (lanes + 1, lanes + 1)


@dataclass(frozen=True)
class FinalGrid:
    """Two regions that share their columns. sub: sub-rows of each wide row."""

    cols: int
    wide_rows: int
    sub: int
    narrow_rows: int


def final_grid(n: int, w: int, steal: bool = True, finer: int = 1) -> FinalGrid:
    """Columns: current and next block of each wide lane, one per narrow lane, one spare. With stealing, both regions must
    have rows for all lanes: narrow rows n + w, wide rows w with enough sub-rows each. finer: times as many rows and columns (see finer_for)."""
    cols = (n + 2 * w + 1) * finer
    if not steal:
        return FinalGrid(cols, w * finer, 1, n * finer)
    return FinalGrid(cols, w * finer, -(-(n + w) // w) if w else 1, (n + w) * finer if n else 0)


def finer_for(ratings: int, blocks: int, budget: int) -> int:
    """By how much rows and columns must grow so that a mean block of a grid of `blocks` blocks holds at most `budget` ratings."""
    return max(1, math.ceil(math.sqrt(ratings / max(1, blocks * budget))))


@dataclass(frozen=True)
class Stripe:
    """Ids (or their places) lo <= x < hi."""

    axis: str
    region: str
    idx: int
    lo: int
    hi: int


def even_stripes(axis: str, size: int, parts: int, region: str = "all", base: int = 0) -> list[Stripe]:
    """Stripes of equal id ranges."""
    at = [base + size * i // parts for i in range(parts + 1)]
    return [Stripe(axis, region, i, a, b) for i, (a, b) in enumerate(zip(at, at[1:], strict=False))]


def balanced_stripes(counts: DataFrame, axis: str, key: str, parts: int, region: str = "all") -> list[Stripe]:
    """Stripes of nearly equal numbers of ratings. counts(key, n) with one row per id; ids are cut where the prefix sum passes multiples of
    total / parts. The driver gets `parts` rows."""
    total = counts.agg(F.sum("n")).first()[0] or 0
    return _balanced(prefix_sum(counts, [key], F.col("n"), "cum"), total, axis, key, parts, region)


def _balanced(cum: DataFrame, total: int, axis: str, key: str, parts: int, region: str) -> list[Stripe]:
    cell = F.least(F.floor((F.col("cum") - F.col("n")) * parts / F.lit(max(total, 1))), F.lit(parts - 1)).cast("int")
    got = {r["idx"]: (r["lo"], r["hi"]) for r in cum.withColumn("idx", cell).groupBy("idx").agg(F.min(key).alias("lo"), (F.max(key) + 1).alias("hi")).collect()}
    out, at = [], min((lo for lo, _ in got.values()), default=0)
    for i in range(parts):
        lo, hi = got.get(i, (at, at))
        out.append(Stripe(axis, region, i, at if i else lo, hi))
        at = hi
    return out


def stripe_of(col: Column, stripes: list[Stripe]) -> Column:
    """Index of the stripe that holds an id: a binary search over constant bounds, so no join and a logarithmic number of tests."""

    def search(lo: int, hi: int) -> Column:
        if hi - lo == 1:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(col < stripes[mid].lo, search(lo, mid)).otherwise(search(mid, hi))

    return search(0, len(stripes))


def stripes_frame(spark: SparkSession, stripes: list[Stripe]) -> DataFrame:
    return spark.createDataFrame([(s.axis, s.region, s.idx, s.lo, s.hi) for s in stripes], "axis string, region string, idx int, lo long, hi long")


def placed(ratings: DataFrame, seed: int | None) -> DataFrame:
    """ratings with places pu, pv: the ids, or a seeded scatter of them (arithmetic, so no shuffle)."""
    if seed is None:
        return ratings.withColumn("pu", F.col("u")).withColumn("pv", F.col("v"))
    return ratings.withColumn("pu", F.expr(mixed("u", seed)).cast("long")).withColumn("pv", F.expr(mixed("v", seed + 1)).cast("long"))


class Counts:
    """(pu, n, cum) and (pv, n, cum): ratings per place of a row and of a column, and their prefix sums, written once. All that a grid needs to know of the ratings
    is in them, and what one grid has asked for (stripes, borders, ratings per block: some rows each) is kept for the next one."""

    def __init__(self, ratings: DataFrame):
        self.tables = tuple(cut(prefix_sum(ratings.groupBy(c).agg(F.count(F.lit(1)).alias("n")), [c], F.col("n"), "cum"), "counts") for c in ("pu", "pv"))
        self.total: int = self.tables[0].agg(F.max("cum")).first()[0] or 0
        self.kept: dict = {}

    def __getitem__(self, i: int) -> DataFrame:
        return self.tables[i]

    def once(self, key: tuple, ask):
        """What ask() returns, asked once per key."""
        if key not in self.kept:
            self.kept[key] = ask()
        return self.kept[key]

    def stripes(self, axis: str, parts: int, region: str = "all", after: int = 0, upto: int | None = None) -> list[Stripe]:
        """balanced_stripes() of the places whose ratings, in their order, are those from number `after` up to number `upto` (all by default)."""
        key, upto = ("pu" if axis == "row" else "pv"), self.total if upto is None else upto
        part = self.tables[axis == "col"].where((F.col("cum") > after) & (F.col("cum") <= upto)).withColumn("cum", F.col("cum") - after)
        return self.once((axis, parts, region, after, upto), lambda: _balanced(part, upto - after, axis, key, parts, region))


def id_counts(ratings: DataFrame) -> Counts:
    return Counts(ratings)


def uniform_grid(ratings: DataFrame, rows: int, cols: int, by: str = "ids", counts: Counts | None = None) -> tuple[list[Stripe], list[Stripe]]:
    """Row and column stripes over places. by: 'ids' equal ranges, 'nnz' equal numbers of ratings."""
    counts = counts or id_counts(ratings)
    if by == "nnz":
        return counts.stripes("row", rows), counts.stripes("col", cols)
    a, b, c, d = (x or 0 for i, p in enumerate(("pu", "pv")) for x in counts[i].agg(F.min(p), F.max(p)).first())
    return even_stripes("row", b - a + 1, rows, base=a), even_stripes("col", d - c + 1, cols, base=c)


def assign_blocks(ratings: DataFrame, rows: list[Stripe], cols: list[Stripe]) -> DataFrame:
    """Adds region, bi, bj, sub."""
    return ratings.withColumn("region", F.lit(rows[0].region)).withColumn("bi", stripe_of(F.col("pu"), rows)).withColumn("bj", stripe_of(F.col("pv"), cols)).withColumn("sub", F.lit(0))


def block_stats(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("region", "bi", "bj", "sub").agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("u").alias("n_rows"), F.countDistinct("v").alias("n_cols"), (F.count(F.lit(1)) * 24).alias("bytes"))


def conflict_pairs(blocks: DataFrame) -> DataFrame:
    """Pairs of different blocks that share a row stripe or a column stripe, by two equi-joins on the shared stripe (blocks are metadata)."""
    a = blocks.select(F.col("bi").alias("bi_a"), F.col("bj").alias("bj_a"))
    b = blocks.select(F.col("bi").alias("bi_b"), F.col("bj").alias("bj_b"))
    rows = a.join(b, F.col("bi_a") == F.col("bi_b")).where("bj_a < bj_b").withColumn("shares", F.lit("row"))
    cols = a.join(b, F.col("bj_a") == F.col("bj_b")).where("bi_a < bi_b").withColumn("shares", F.lit("column"))
    return rows.unionByName(cols)


def split_regions(ratings: DataFrame, alpha: float, counts: Counts | None = None) -> tuple[int, int, int]:
    """Place that parts wide rows (below) from narrow rows, so that wide rows hold at most a share alpha of the ratings: (border, wide ratings, all).
    Row counts and their prefix sum are tables; the driver gets one row."""
    counts = counts or id_counts(ratings)
    least, last, wide = counts.once(("border", alpha), lambda: counts[0].agg(F.min("pu"), *[F.max(F.when(F.col("cum") <= alpha * counts.total, F.col(c))) for c in ("pu", "cum")]).first())
    return (least or 0) if last is None else last + 1, wide or 0, counts.total


def region_grid(ratings: DataFrame, alpha: float, n: int, w: int, steal: bool = True, by: str = "nnz", budget: int | None = None, counts: Counts | None = None) -> tuple[FinalGrid, list[Stripe], list[Stripe]]:
    """Final division: (grid, row stripes, column stripes). Row stripes are numbered through: wide sub-rows first (wide row * sub + sub-row), then narrow rows."""
    grid = final_grid(n, w, steal)
    counts = counts or id_counts(ratings)
    border, wide, total = split_regions(ratings, alpha, counts)
    if budget:  # a wide block is a whole wide row in a column
        finer = max(finer_for(wide, grid.cols * max(1, grid.wide_rows), budget), finer_for(total - wide, grid.cols * max(1, grid.narrow_rows), budget))
        grid = final_grid(n, w, steal, finer)
    rows: list[Stripe] = []
    for region, cond, k in (("wide", F.col("pu") < border, grid.wide_rows * grid.sub), ("narrow", F.col("pu") >= border, grid.narrow_rows)):
        after, upto = (0, wide) if region == "wide" else (wide, total)
        if not k or after == upto:
            continue
        if by == "nnz":
            found = counts.stripes("row", k, region, after, upto)
        else:
            lo, hi = counts[0].where(cond).agg(F.min("pu"), F.max("pu")).first()
            found = even_stripes("row", hi - lo + 1, k, region, lo)
        rows += found
    if by == "nnz":
        cols = counts.stripes("col", grid.cols)
    else:
        lo, hi = counts[1].agg(F.min("pv"), F.max("pv")).first()
        cols = even_stripes("col", hi - lo + 1, grid.cols, base=lo)
    return grid, rows, cols


def assign_region_blocks(ratings: DataFrame, grid: FinalGrid, rows: list[Stripe], cols: list[Stripe]) -> DataFrame:
    """Adds row_key (number of the row stripe), region, bi, bj, sub."""
    n_wide = sum(s.region == "wide" for s in rows)
    key = stripe_of(F.col("pu"), rows)
    wide = F.col("row_key") < n_wide
    return (
        ratings.withColumn("row_key", key)
        .withColumn("region", F.when(wide, "wide").otherwise("narrow"))
        .withColumn("bi", F.when(wide, F.floor(F.col("row_key") / grid.sub)).otherwise(F.col("row_key") - n_wide).cast("int"))
        .withColumn("sub", F.when(wide, F.col("row_key") % grid.sub).otherwise(0).cast("int"))
        .withColumn("bj", stripe_of(F.col("pv"), cols))
    )
