"""Benchmark decontamination by pigeonhole edit matching.

Text and items are normalised: lower case, white space runs become one space. An item of m characters may occur with up to
k = max(floor(m * error_rate), 0) edits. It is split in k + 1 pieces; whoever holds the item with at most k edits
holds at least one piece unchanged. Items of any length are searched; those below 20 characters, which have no error budget, only
between word borders. An Aho-Corasick automaton finds all piece hits in a text; each hit names a window of the text in
which the item would lie, windows of one item that overlap are joined, and Myers' bit-parallel distance decides
whether a substring of the window is within k edits of the item.

Items come in blocks of bounded size (pieces per automaton), so the benchmark may be of any size: each block makes one pass
over the texts and is let go before the next one is made. Texts are never shuffled, and a row's decision is the same for one block and for many.

Edge cases. Null or empty text: clean. Null or empty items, and items of white space: no test items. Very
long texts: scanned whole, in time proportional to their length. Repeated items: each is reported. Rows that repeat an
id: one result row each, decided by its own text. Empty tables: no test item, all clean; or no rows.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockmf.llm.common import cut


def normalise(text: str) -> str:
    return " ".join(text.lower().split())


def pieces_of(item: str, edits: int) -> list[tuple[int, str]]:
    """edits + 1 pieces of nearly equal length, with their offsets."""
    n, parts = len(item), edits + 1
    at = [n * i // parts for i in range(parts + 1)]
    return [(a, item[a:b]) for a, b in zip(at, at[1:], strict=False)]


def myers(pattern: str, text: str, most: int) -> int | None:
    """Least edit distance of the pattern to any substring of text, if it is at most `most`."""
    m = len(pattern)
    if not m:
        return 0
    where: dict[str, int] = defaultdict(int)
    for i, c in enumerate(pattern):
        where[c] |= 1 << i
    full, top = (1 << m) - 1, 1 << (m - 1)
    plus, minus, score, best = full, 0, m, m
    for c in text:
        eq = where.get(c, 0)
        diag = (((eq & plus) + plus) ^ plus) | eq | minus
        up = minus | (~(diag | plus) & full)
        down = plus & diag
        if up & top:
            score += 1
        elif down & top:
            score -= 1
            if score < best:
                best = score
                if not best:
                    break
        up = (up << 1) & full
        down = (down << 1) & full
        plus = down | (~(diag | up) & full)
        minus = up & diag
    return best if best <= most else None


#: Items below so many characters (all without an error budget at 5 %) count only between word borders: "cat" is not in "concatenate".
WHOLE_WORDS = 20


class Matcher:
    def __init__(self, items: list[tuple[int, str]], error_rate: float):
        import ahocorasick

        self.items = items
        self.edits = [int(len(t) * error_rate) for _, t in items]
        where: dict[str, list] = defaultdict(list)
        for i, (_, t) in enumerate(items):
            for at, piece in pieces_of(t, self.edits[i]):
                where[piece].append((i, at))
        self.short = {i for i, (_, t) in enumerate(items) if len(t) < WHOLE_WORDS}
        self.automaton = ahocorasick.Automaton()
        for piece, owners in where.items():
            self.automaton.add_word(piece, (len(piece), owners))
        self.automaton.make_automaton()

    def find(self, text: str) -> list[tuple[int, int]]:
        """(item number, edits) of the items within their error budget."""
        text = normalise(text)
        windows: dict[int, list[list[int]]] = defaultdict(list)
        for end, (n, owners) in self.automaton.iter(text):
            start = end - n + 1
            for i, at in owners:
                if i in self.short and (start and text[start - 1].isalnum() or text[end + 1 : end + 2].isalnum()):
                    continue
                k, m = self.edits[i], len(self.items[i][1])
                lo, hi = start - at - k, start - at + m + k
                if (w := windows[i]) and lo <= w[-1][1] and lo >= w[-1][0]:
                    w[-1][1] = max(w[-1][1], hi)
                else:
                    w.append([lo, hi])
        found = []
        for i, spans in windows.items():
            best = None
            for lo, hi in spans:
                d = myers(self.items[i][1], text[max(0, lo) : hi], self.edits[i])
                if d is not None and (best is None or d < best):
                    best = d
                if best == 0:
                    break
            if best is not None:
                found.append((i, best))
        return sorted(found)


def _scan(items: list[tuple[int, str]], error_rate: float):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(items, error_rate)
        for b in batches:
            out = []
            for text in b.column(1):
                got = matcher.find(text.as_py()) if text.is_valid else []
                out.append(([items[i][0] for i, _ in got], min((d for _, d in got), default=None)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([sorted(x) for x, _ in out], pa.list_(pa.int64())), pa.array([d for _, d in out], pa.int32())], [b.schema.names[0], "items", "edits"])

    return scan


def item_blocks(benchmark: DataFrame, block_chars: int, id_col: str, text_col: str) -> Iterator[list[tuple[int, str]]]:
    """Normalised items in blocks of bounded size; only one block is in the driver's memory at a time."""
    rows = benchmark.select(F.col(id_col).cast("long"), F.col(text_col)).where(F.col(text_col).isNotNull()).orderBy(id_col)
    block, size = [], 0
    for r in rows.toLocalIterator():
        t = normalise(r[1])
        if not t:
            continue
        block.append((r[0], t))
        size += len(t)
        if size >= block_chars:
            yield block
            block, size = [], 0
    if block:
        yield block


def contamination(docs: DataFrame, benchmark: DataFrame, error_rate: float = 0.05, block_chars: int = 4_000_000, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """doc_id, contaminated, items (ids of the items found, ascending), edits (least of their distances): one row per row of docs.

    With several blocks of items, rows are numbered and written first; each block's hits are written by row number, and joined to the rows at the end."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    blocks = item_blocks(benchmark, block_chars, item_id, item_text)
    first, second = next(blocks, None), next(blocks, None)
    if first is None:
        found = rows.select("doc_id", F.array().cast("array<long>").alias("items"), F.lit(None).cast("int").alias("edits"))
    elif second is None:
        found = rows.mapInArrow(_scan(first, error_rate), f"doc_id {dict(rows.dtypes)['doc_id']}, items array<long>, edits int")
    else:
        numbered = cut(rows.withColumn("row", F.monotonically_increasing_id()), "numbered")
        hits = None
        for block in chain([first, second], blocks):
            part = numbered.select("row", "text").mapInArrow(_scan(block, error_rate), "row long, items array<long>, edits int")
            part = cut(part.where("edits is not null"), "block-hits")
            hits = part if hits is None else hits.unionByName(part)
        counted = hits.groupBy("row").agg(F.array_sort(F.flatten(F.collect_list("items"))).alias("items"), F.min("edits").alias("edits"))
        found = numbered.select("row", "doc_id").join(counted, "row", "left").select("doc_id", F.coalesce("items", F.array().cast("array<long>")).alias("items"), "edits")
    return found.select("doc_id", (F.size("items") > 0).alias("contaminated"), "items", "edits")


def clean_rows(docs: DataFrame, benchmark: DataFrame, error_rate: float = 0.05, block_chars: int = 4_000_000, text_col: str = "text") -> DataFrame:
    """The rows of docs that hold no benchmark item: a filter for each block, so texts stay where they are. Between blocks the rows left are written."""
    rows = docs
    for i, block in enumerate(item_blocks(benchmark, block_chars, "item_id", "text")):
        rows = (cut(rows, "clean") if i else rows).where(~_hit(block, error_rate)(F.col(text_col)))
    return rows


def _hit(items: list[tuple[int, str]], error_rate: float):
    held: list[Matcher] = []

    def hit(texts: Iterator) -> Iterator:
        import pandas as pd

        if not held:
            held.append(Matcher(items, error_rate))
        for s in texts:
            yield pd.Series([bool(t) and bool(held[0].find(t)) for t in s], dtype="bool")

    from pyspark.sql.pandas.functions import PandasUDFType

    return F.pandas_udf(hit, "boolean", PandasUDFType.SCALAR_ITER)
