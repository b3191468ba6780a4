"""Best-fit packing by linear grouping.

Documents become pieces of at most `capacity` tokens. The plan is made on the histogram of piece lengths alone (at
most `capacity` rows, however many pieces there are):
1. large lengths (over `small_share` of the capacity) are sorted and cut in groups of equal cardinality, and each is
   rounded up to the largest of its group;
2. sequences for the few rounded sizes are chosen as configurations: the fullest mixture of sizes that the pieces
   left allow is found by a knapsack over the rounded sizes and used as often as its scarcest size allows;
3. actual lengths take the places of their group, longest first; what rounding had set aside becomes free space;
4. small pieces go, longest first, to the fullest sequence that still has room (best fit).
All steps work on runs of equal sequences, so their cost depends on the number of lengths, not of pieces. Pieces
then find their places by their rank among the pieces of the same length: ranks come from prefix sums over
(partition, length) counts, so no task sees more than its own partition, and the plan's runs are a table of bounded size.

Edge cases. Null or empty text: the end id only. Texts longer than a sequence: cut in pieces of `capacity`; the
last may be shorter. Rows that repeat a document: packed each. Empty table: empty result. Extra columns are ignored.
"""

from __future__ import annotations

import bisect
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blockmf.llm.common import cut, lean, text_or_empty
from blockmf.llm.tokenize import piece_tokenizer


def _pieces(vocab: str, end_id: int, capacity: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        tok, part = piece_tokenizer(vocab), TaskContext.get().partitionId()
        seen: dict[int, int] = defaultdict(int)
        for b in batches:
            out = defaultdict(list)
            named = iter(b.column(0).to_pylist())
            for tokens, stops in tok.encode_many(b.column(1), end_id):
                tokens = tokens.astype("<u4")
                for lo, hi in zip([0, *stops[:-1].tolist()], stops.tolist(), strict=True):
                    doc = next(named)
                    for k, at in enumerate(range(lo, hi, capacity)):
                        x = tokens[at : min(at + capacity, hi)]
                        for name, v in (("doc_id", doc), ("piece", k), ("start", at - lo), ("length", len(x)), ("ids_crc32", zlib.crc32(x)), ("part", part), ("nth", seen[len(x)])):
                            out[name].append(v)
                        seen[len(x)] += 1
            yield pa.RecordBatch.from_pydict(dict(out), schema=_PIECE) if out else pa.RecordBatch.from_pylist([], schema=_PIECE)

    return lean(make)


_PIECE = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("part", pa.int32()), ("nth", pa.int64())])


def make_pieces(docs: DataFrame, vocab: str, capacity: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces with their number among those of equal length in their task (part, nth); written, so that a rerun cannot change them."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    made = rows.mapInArrow(_pieces(vocab, end_id, capacity), "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long")
    return cut(made, "pieces")


def _fullest(sizes: list[int], counts: list[int], capacity: int) -> list[int]:
    """Bounded knapsack: how many of each size make the fullest sequence. Larger sizes first among equals."""
    reach = np.zeros(capacity + 1, bool)
    reach[0] = True
    used = []  # per size: how many of it reach a sum first
    for s, c in zip(sizes, counts, strict=True):
        n = np.full(capacity + 1, -1, np.int32)
        n[reach] = 0
        for k in range(1, min(c, capacity // s) + 1):
            new = np.zeros(capacity + 1, bool)
            new[s:] = n[:-s] == k - 1
            new &= n < 0
            if not new.any():
                break
            n[new] = k
        used.append(n)
        reach = n >= 0
    at = int(np.flatnonzero(reach)[-1])
    take = [0] * len(sizes)
    for i in range(len(sizes) - 1, -1, -1):
        take[i] = int(used[i][at])
        at -= take[i] * sizes[i]
    return take


def plan_packing(histogram: dict[int, int], capacity: int = 2048, groups: int = 512, small_share: float = 0.2) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """histogram {length: pieces} -> (runs, sequences). A run (length, rank_from, rank_to, first_sequence, offset) places the pieces of a
    length with rank_from <= rank < rank_to at `offset` of sequences first_sequence, first_sequence + 1, ..."""
    least = max(1, int(capacity * small_share))
    large = sorted(((n, c) for n, c in histogram.items() if n > least and c), reverse=True)
    small = sorted(((n, c) for n, c in histogram.items() if n <= least and c), reverse=True)
    total = sum(c for _, c in large)
    # 1. groups of equal cardinality; a length that spans a border is split between groups
    rounded: list[list] = []  # [size, count, [(length, count), ...]]
    each, room = max(1, -(-total // groups)), 0
    for n, c in large:
        while c:
            if not room:
                rounded.append([n, 0, []])
                room = each
            k = min(c, room)
            rounded[-1][1] += k
            rounded[-1][2].append((n, k))
            c, room = c - k, room - k
    merged: list[list] = []
    for size, count, members in rounded:  # equal sizes are one size
        if merged and merged[-1][0] == size:
            merged[-1][1] += count
            merged[-1][2] += members
        else:
            merged.append([size, count, members])
    sizes, left = [m[0] for m in merged], [m[1] for m in merged]
    # 2. configurations
    chosen: list[tuple[list[int], int]] = []
    while any(left):
        live = [i for i, c in enumerate(left) if c]
        take = [0] * len(sizes)
        top = live[0]  # the largest size left is in the sequence; the knapsack fills the rest
        rest = capacity - sizes[top]
        fill = _fullest([sizes[i] for i in live], [left[i] - (i == top) for i in live], rest) if rest >= min(sizes[i] for i in live) else [0] * len(live)
        for i, k in zip(live, fill, strict=True):
            take[i] = k
        take[top] += 1
        times = min(left[i] // k for i, k in enumerate(take) if k)
        chosen.append((take, times))
        left = [c - k * times for c, k in zip(left, take, strict=True)]
    # 3. actual lengths in their places
    runs: list[tuple[int, int, int, int, int]] = []
    rank: dict[int, int] = defaultdict(int)
    stock = [list(reversed(m[2])) for m in merged]
    free: dict[int, list[list[int]]] = defaultdict(list)  # free space -> runs [first_sequence, count, offset]
    sequences = 0
    for take, times in chosen:
        open_runs = [[sequences, times, 0]]
        sequences += times
        for i, k in enumerate(take):
            for _ in range(k):
                after = []
                for first, count, at in open_runs:
                    while count:
                        n, c = stock[i][-1]
                        m = min(c, count)
                        runs.append((n, rank[n], rank[n] + m, first, at))
                        rank[n] += m
                        stock[i].pop()
                        if c > m:
                            stock[i].append((n, c - m))
                        after.append([first, m, at + n])
                        first, count = first + m, count - m
                open_runs = after
        for first, count, at in open_runs:
            free[capacity - at].append([first, count, at])
    # 4. best fit of the small ones
    spaces = sorted(free)
    for n, c in small:
        while c:
            i = bisect.bisect_left(spaces, n)
            if i == len(spaces):
                m = -(-c // (capacity // n))
                free[capacity].append([sequences, m, 0])
                sequences += m
                spaces.insert(bisect.bisect_left(spaces, capacity), capacity)
                continue
            space = spaces[i]
            first, count, at = free[space].pop()
            if not free[space]:
                del free[space], spaces[i]
            full = min(space // n, c)  # pieces for each sequence of the run
            m = min(count, c // full)
            for k in range(full):
                runs.append((n, rank[n], rank[n] + m, first, at + k * n))
                rank[n] += m
            c -= m * full
            for run in ([first, m, at + full * n], [first + m, count - m, at]):
                if run[1] and (s := capacity - run[2]):
                    if s not in free or not free[s]:
                        bisect.insort(spaces, s)
                    free[s].append(run)
    return runs, sequences


def pack(docs: DataFrame, vocab: str, capacity: int = 2048, end_id: int = 0, groups: int = 512) -> DataFrame:
    """docs -> doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    pieces = make_pieces(docs, vocab, capacity, end_id)
    counts = pieces.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    runs, _ = plan_packing(histogram, capacity, groups)
    # prefix sums of the counts: parts in blocks, so that one common length does not meet in one task
    block = F.floor(F.sqrt(F.col("part"))).cast("int")
    by_block = counts.groupBy("length", block.alias("block")).agg(F.sum("n").alias("n"))
    blocks = by_block.select("length", "block", (F.sum("n").over(Window.partitionBy("length").orderBy("block")) - F.col("n")).alias("before"))
    inner = counts.withColumn("block", block)
    inner = inner.withColumn("inside", F.sum("n").over(Window.partitionBy("length", "block").orderBy("part")) - F.col("n"))
    base = inner.join(blocks, ["length", "block"]).select("part", "length", (F.col("before") + F.col("inside")).alias("base"))
    ranked = pieces.join(base, ["part", "length"]).withColumn("rank", F.col("base") + F.col("nth"))
    by_length: dict[int, list] = defaultdict(list)
    for n, lo, hi, first, at in runs:
        by_length[n].append((lo, hi, first, at))
    lookup = spark.createDataFrame([(n, lo, hi, first, at) for n, rs in by_length.items() for lo, hi, first, at in sorted(rs)], "n long, lo long, hi long, first long, at long")
    placed = ranked.join(F.broadcast(lookup), (F.col("length") == F.col("n")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("first") + F.col("rank") - F.col("lo")).alias("sequence_id"), F.col("at").alias("offset"))
