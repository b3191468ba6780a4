"""Suffix-array dedup: remove every byte covered by a string of `length` bytes that also starts earlier.

A full suffix array of the corpus would move every suffix with its context. This one is sparse and still exact:
* Anchors. Of every `length`-byte window of a text, the positions whose `grain`-byte hash is least in the window are
  anchors. Equal windows have equal anchors, so two occurrences of a string of `length` bytes share an anchor at the same
  place in them: comparing the suffixes that start at anchors (about one in 25) finds all repeats.
* Sieve. Of each suffix only tokens travel: its leading bytes with a hash of its `grain` (one integer, ordered by the leading bytes), then a
  96-bit hash of all that surrounds the anchor (every window that holds it). Sampled splitters range-partition the suffixes by these
  tokens, and each bucket is sorted by multikey quicksort. An anchor whose surroundings repeat those of an earlier one is
  covered on all sides. Anchors whose leading token nobody shares start no repeat. The others are asked for their text.
* Suffix order. Asked anchors travel with their text (`length` bytes to the right, what fits to the left), to buckets by the same splitters.
  A bucket sorts the suffixes byte for byte by multikey quicksort, and likewise what stands before the anchors, read backwards. Common
  prefixes of neighbours in both orders tell for each place of the window around the anchor which suffixes hold the same string; all
  but the first one repeat. This compares bytes, not hashes.
* Boundaries. A run of one leading token that reaches a splitter goes on in the next bucket, so no bucket sees it whole. Such runs, and runs of more
  than `hot` suffixes (a passage that a third of all documents share has as many different surroundings), are split further: each window
  around their anchors is dealt by its own hash of 128 bits, and equal windows are combined before they travel.
* Map tasks keep only the first of equal suffixes they meet (pre-aggregation), so a text that makes up a third of all
  rows reaches a bucket once per map task.

Texts meet decisions in groups of documents of a few MB ("homes"); the exchange of texts by home is planned once and
reused by Spark. Rows travel as blobs (one per task and destination), not one by one.

Edge cases. Null or empty text, texts shorter than `length`: nothing removed. Very long texts: hashed in slices. Rows that repeat an id
with different texts: documents of their own, in the order of a hash of their texts. Rows that repeat id and text: one
document (nothing is removed between them). Null ids: before all others, each text a document of its own, in the order of a hash. Empty table: empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockmf.llm.common import cut, text_bytes, text_or_empty

U64 = np.uint64
_ODD = U64(0x9E3779B97F4A7C15 | 1)
_INV = U64(pow(int(_ODD), -1, 1 << 64))
SLICE = 1 << 20
_LUT = np.random.default_rng(20240901).integers(1, 1 << 63, (2, 256), dtype=np.uint64)[0]  # a value per byte


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> U64(31))
    x *= U64(0x7FB5D329728EA185)
    x ^= x >> U64(27)
    x *= U64(0x81DADEF4BC2DD44D)
    return x ^ (x >> U64(33))


class RangeHash:
    """Hashes of any byte range of a buffer in constant time: differences of prefix sums of byte values times powers of an odd number."""

    _pow: np.ndarray = np.ones(1, U64)
    _inv: np.ndarray = np.ones(1, U64)

    def __init__(self, data: np.ndarray, values: np.ndarray = _LUT):
        n = len(data)
        if len(RangeHash._pow) <= n:
            size = max(n + 1, SLICE + 4096)
            RangeHash._pow = np.concatenate([np.ones(1, U64), np.cumprod(np.full(size, _ODD))])
            RangeHash._inv = np.concatenate([np.ones(1, U64), np.cumprod(np.full(size, _INV))])
        self.sum = np.zeros(n + 1, U64)
        np.cumsum(values[data] * RangeHash._pow[:n], out=self.sum[1:])

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (self.sum[end] - self.sum[start]) * RangeHash._inv[start]

    def fixed(self, length: int, count: int) -> np.ndarray:
        """Of the ranges [i, i + length) for i < count."""
        return (self.sum[length : length + count] - self.sum[:count]) * RangeHash._inv[:count]


def _slide(x: np.ndarray, w: int, best) -> np.ndarray:
    """best (np.minimum or np.maximum) over x[i : i + w], for all i where that fits."""
    have, step = x, 1
    while step * 2 <= w:
        have = best(have[:-step], have[step:])
        step *= 2
    return best(have[: len(x) - w + 1], have[w - step :]) if w > step else have


def slices(doc_ends: np.ndarray, margin: int) -> Iterator[tuple[int, int, int, int]]:
    """Cut a buffer of documents in slices (from, to, keep_from, keep_to): neighbouring short documents together, a long one in overlapping parts."""
    start, n = 0, len(doc_ends)
    i = 0
    while i < n:
        j = i
        while j < n and doc_ends[j] - start <= SLICE:
            j += 1
        if j > i:
            end = int(doc_ends[j - 1])
            if end > start:
                yield start, end, start, end
            start, i = end, j
            continue
        lo, end = start, int(doc_ends[i])
        while lo < end:
            hi = min(end, lo + SLICE)
            yield max(start, lo - margin), min(end, hi + margin), lo, hi
            lo = hi
        start, i = end, i + 1


_SEEDS = np.random.default_rng(5).integers(1, 1 << 63, (3, 64), dtype=np.uint64)
_FIRST_BYTES = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [2**64 - 1], U64)


def words_at(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each position on as an integer, for any position; zeros follow the data."""
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    return np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))


def strong_hash(words: np.ndarray, lo: np.ndarray, hi: np.ndarray, most: int, seed: int) -> np.ndarray:
    """64-bit hash of the byte ranges [lo, hi) of at most `most` bytes: each word is mixed for itself, so structured texts do not cancel out."""
    out = np.zeros(len(lo), U64)
    top = len(words) - 1
    for j in range(-(-most // 8)):
        at = lo + 8 * j
        word = words[np.minimum(at, top)] & _FIRST_BYTES[np.clip(hi - at, 0, 8)]
        out += mix(word ^ _SEEDS[seed, j % 64] + U64(j))
    return mix(out ^ (hi - lo).astype(U64))


def lead_tokens(words: np.ndarray, at: np.ndarray, grain: int) -> np.ndarray:
    """First token of suffixes: four leading bytes, then 32 bits of a hash of the grain. Its order is that of the leading bytes."""
    text = (words[at] & U64(0xFFFFFFFF)).astype("<u4").byteswap().astype(U64)
    return (text << U64(32)) | (strong_hash(words, at, at + grain, grain, 0) >> U64(32))


def anchors(data: np.ndarray, ends: np.ndarray, length: int, grain: int) -> tuple[np.ndarray, ...]:
    """(document number, position in it, leading token, two tokens of the surroundings) of all anchors of a buffer of documents."""
    span = length - grain + 1
    starts = np.concatenate([[0], ends[:-1]]).astype(np.int64)
    out: list[tuple] = []
    for a, b, keep_a, keep_b in slices(ends, 2 * length):
        part = data[a:b]
        if len(part) < length:
            continue
        g = np.maximum((mix(RangeHash(part).fixed(grain, len(part) - grain + 1)) >> U64(32)).astype(np.uint32), 1)
        least = _slide(g, span, np.minimum)  # one per window
        first = np.searchsorted(ends, a, "right")
        last = np.searchsorted(ends, b, "left")
        for e in ends[first:last]:  # windows that reach into the next document choose nothing
            k = int(e) - a
            least[max(0, k - length + 1) : k] = 0
        wide = np.concatenate([np.zeros(span - 1, np.uint32), least, np.zeros(span - 1, np.uint32)])
        top = _slide(wide, span, np.maximum)  # for each position, over the windows that hold it
        at = np.flatnonzero(g == top)
        at = at[(at + a >= keep_a) & (at + a < keep_b)]
        doc = np.searchsorted(ends, at + a, "right")
        lo = np.maximum(starts[doc] - a, at - (length - grain))
        hi = np.minimum(ends[doc] - a, at + length)
        words = words_at(part)
        place = mix((at - lo).astype(U64) * U64(1 << 20) + (hi - at).astype(U64))
        around, extra = (mix(strong_hash(words, lo, hi, 2 * length - grain, k) ^ place) for k in (1, 2))
        out.append((doc, at + a - starts[doc], lead_tokens(words, at, grain), around, (extra >> U64(32)).astype(np.uint32)))
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, U64), np.zeros(0, U64), np.zeros(0, np.uint32)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _tie_order(rows: np.ndarray, keys: list[np.ndarray]) -> np.ndarray:
    """Rows in the order of the first token; only where it is equal, the next tokens are looked at."""
    first = keys[0][rows]
    order = np.argsort(first)
    rows, new = rows[order], np.concatenate([[True], np.diff(first[order]) != 0])
    for key in keys[1:]:
        tied = np.flatnonzero(~new | np.concatenate([~new[1:], [False]]))
        if not len(tied):
            break
        run, token = np.cumsum(new)[tied], key[rows[tied]]
        order = np.lexsort((token, run))
        rows[tied] = rows[tied[order]]
        token, run = token[order], run[order]
        new[tied[1:]] |= (token[1:] != token[:-1]) & (run[1:] == run[:-1])
    return rows


def multikey_order(keys: list[np.ndarray], cutoff: int = 1 << 16) -> np.ndarray:
    """Order of rows by several tokens: three-way quicksort on the first token, going on with the next token where it is equal."""
    n = len(keys[0])
    out = np.empty(n, np.int64)
    todo = [(np.arange(n), 0, 0)] if n else []
    while todo:
        rows, depth, at = todo.pop()
        if len(rows) <= cutoff or depth == len(keys) - 1:
            out[at : at + len(rows)] = _tie_order(rows, keys[depth:])
            continue
        token = keys[depth][rows]
        sample = np.sort(token[:: max(1, len(rows) // 63)])
        pivot = sample[len(sample) // 2]
        less, same = token < pivot, token == pivot
        parts = (rows[less], depth), (rows[same], depth + 1), (rows[~(less | same)], depth)
        for part, d in parts:
            if len(part):
                todo.append((part, d, at))
                at += len(part)
    return out


# --- blobs: columns of fixed types, one after the other -------------------------------------------------------------


def put(*columns: np.ndarray) -> bytes:
    return np.int64(len(columns[0])).tobytes() + b"".join(np.ascontiguousarray(c).tobytes() for c in columns)


def get(blob: bytes, *types) -> list[np.ndarray]:
    n, at, out = int(np.frombuffer(blob, np.int64, 1)[0]), 8, []
    for t in types:
        out.append(np.frombuffer(blob, t, n, at))
        at += n * np.dtype(t).itemsize
    return out


#: Columns of the blobs. A document is (id, tag): the tag tells rows of one id apart.
DOC = (np.int64, np.uint32)
SUFFIX, RANGE, ASK = (U64, U64, np.uint32, *DOC, np.uint32), (*DOC, np.uint32, np.uint32), (*DOC, np.uint32)
WINDOW, HIT = (U64, U64, *DOC, np.uint32), (*DOC, np.uint32, U64)
RANGES, ASKS, HOT_ASKS, CONTEXTS, WINDOWS, HITS, SUFFIXES = 1, 2, 3, 4, 5, 6, 7
_BLOB = pa.schema([("to", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())])
BLOB_DDL = "to int, kind int, blob binary"


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    to, kind, blob = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(to, pa.int32()), pa.array(kind, pa.int32()), pa.array(blob, pa.binary())], schema=_BLOB)


def home_of(doc: np.ndarray, tag: np.ndarray, homes: int) -> np.ndarray:
    x = doc.astype(np.int64).view(U64) ^ (tag.astype(U64) << U64(9))
    return ((x ^ (x >> U64(21)) ^ (x >> U64(42))).view(np.int64) % homes).astype(np.int32)


def home_column(homes: int) -> Column:
    """home_of() in Spark: bits folded, then the remainder by an odd number."""
    x = F.col("doc").bitwiseXOR(F.shiftleft(F.col("tag"), 9))
    return F.pmod(x.bitwiseXOR(F.shiftrightunsigned(x, 21)).bitwiseXOR(F.shiftrightunsigned(x, 42)), F.lit(homes).cast("long")).cast("int")


def _to_homes(kind: int, homes: int, doc: np.ndarray, tag: np.ndarray, *rest: np.ndarray) -> list[tuple]:
    if not len(doc):
        return []
    home = home_of(doc, tag, homes)
    order = np.argsort(home, kind="stable")
    at = np.flatnonzero(np.diff(home[order], prepend=-1))
    return [(int(home[order[s]]), kind, put(doc[order[s:e]], tag[order[s:e]], *(x[order[s:e]] for x in rest))) for s, e in zip(at, [*at[1:], len(order)], strict=True)]


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, end of each document) of a string column, without copies where Arrow allows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    column = column.cast(pa.large_string()).fill_null("")
    off = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off[1:] - off[0]


def _combine(lead, around, extra, doc, tag, pos):
    """Sort, and tell the first of equal suffixes from the others."""
    order = multikey_order([lead, around, extra, doc.view(U64) ^ U64(1 << 63), tag.astype(U64) << U64(32) | pos])
    lead, around, extra, doc, tag, pos = (x[order] for x in (lead, around, extra, doc, tag, pos))
    equal = (lead[1:] == lead[:-1]) & (around[1:] == around[:-1]) & (extra[1:] == extra[:-1])
    # what stands at the same place of the same document is one suffix, even if rows repeat it
    first = np.concatenate([[True], ~equal])
    head = np.maximum.accumulate(np.where(first, np.arange(len(lead)), 0))
    again = ~first & ((doc != doc[head]) | (tag != tag[head]) | (pos != pos[head]))
    return lead, around, extra, doc, tag, pos, first, again


def _groups(*keys: np.ndarray) -> np.ndarray:
    """Where runs of equal keys start in sorted rows."""
    if not len(keys[0]):
        return np.zeros(0, np.int64)
    return np.flatnonzero(np.concatenate([[True], np.logical_or.reduce([k[1:] != k[:-1] for k in keys])]))


def _cover(doc, tag, pos, length, grain):
    """Ranges of full cover around anchors; clipped to the text later. Joined where they overlap in a text."""
    order = np.lexsort((pos, tag, doc))
    doc, tag, pos = doc[order], tag[order], pos[order].astype(np.int64)
    lo, hi = np.maximum(pos - (length - grain), 0), pos + length
    apart = np.concatenate([[True], lo[1:] > hi[:-1]]) if len(doc) else np.zeros(0, bool)
    new = _groups(doc, tag, np.cumsum(apart))
    last = np.concatenate([new[1:], [len(doc)]]) - 1 if len(doc) else new
    return doc[new], tag[new], lo[new].astype(np.uint32), hi[last].astype(np.uint32)


def _find_suffixes(length: int, grain: int, splitters: np.ndarray, homes: int, keep: int = 1 << 21):
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def flush() -> pa.RecordBatch:
            columns = [np.concatenate(x) for x in zip(*held, strict=True)]
            held.clear()
            lead, around, extra, doc, tag, pos, first, again = _combine(*columns)
            rows = []
            # decided here; they pass through buckets dealt at random
            for i, r in enumerate(_to_homes(RANGES, homes, *_cover(doc[again], tag[again], pos[again], length, grain))):
                rows.append(((r[0] * 31 + i) % (len(splitters) + 1), r[1] + 16 * (r[0] + 1), r[2]))
            lead, around, *rest = (x[first] for x in (lead, around, extra, doc, tag, pos))
            cut_at = cuts(lead, around, splitters)
            for b, (s, e) in enumerate(zip([0, *cut_at], [*cut_at, len(lead)], strict=True)):
                if e > s:
                    rows.append((b, SUFFIXES, put(lead[s:e], around[s:e], *(x[s:e] for x in rest))))
            return _rows(rows)

        for b in batches:
            data, ends = text_buffer(b.column(2))
            ids, tags = (np.array(b.column(k), np.int64) for k in (0, 1))
            d, pos, lead, around, extra = anchors(data, ends, length, grain)
            if len(d):
                held.append((lead, around, extra, ids[d], tags[d].astype(np.uint32), pos.astype(np.uint32)))
                size += len(d)
            if size >= keep:
                yield flush()
                size = 0
        if held:
            yield flush()

    return find


def cuts(lead: np.ndarray, around: np.ndarray, splitters: np.ndarray) -> list[int]:
    """Where each splitter (leading token, surroundings token) falls in sorted suffixes."""
    out = []
    for s_lead, s_around in splitters:
        a, b = np.searchsorted(lead, s_lead, "left"), np.searchsorted(lead, s_lead, "right")
        out.append(int(a + np.searchsorted(around[a:b], s_around)))
    return out


def _sort_bucket(length: int, grain: int, splitters: np.ndarray, homes: int, hot: int):
    edge = np.unique(splitters[:, 0]) if len(splitters) else np.zeros(0, U64)

    def sort(bucket: pa.Table) -> pa.Table:
        rows = _passing(bucket, SUFFIXES)
        if (held := _gather(bucket, SUFFIXES, SUFFIX)) is not None:
            lead, _, _, doc, tag, pos, first, again = _combine(*held)
            rows += _to_homes(RANGES, homes, *_cover(doc[again], tag[again], pos[again], length, grain))
            lead, doc, tag, pos = lead[first], doc[first], tag[first], pos[first]
            start = _groups(lead)
            many = np.repeat(np.diff(np.concatenate([start, [len(lead)]])), np.diff(np.concatenate([start, [len(lead)]])))
            split = np.isin(lead, edge) | (many > hot)
            for kind, ask in ((ASKS, (many > 1) & ~split), (HOT_ASKS, split)):
                rows += _to_homes(kind, homes, doc[ask], tag[ask], pos[ask])
        return pa.Table.from_batches([_rows(rows)])

    return sort


def _passing(bucket: pa.Table, *but: int) -> list[tuple]:
    """Decisions that only pass through a bucket: their home is part of the kind."""
    return [(k // 16 - 1, k % 16, b.as_py()) for k, b in zip(bucket.column("kind").to_pylist(), bucket.column("blob"), strict=True) if k not in but]


def _merge_runs(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of ranges of one text."""
    order = np.argsort(lo, kind="stable")
    lo, hi = lo[order], np.maximum.accumulate(hi[order])
    new = np.flatnonzero(np.concatenate([[True], lo[1:] > hi[:-1]]))
    return lo[new], hi[np.concatenate([new[1:], [len(lo)]]) - 1]


def _gather(table: pa.Table, kind: int, types) -> list[np.ndarray] | None:
    found = [get(b.as_py(), *types) for k, b in zip(table.column("kind").to_pylist(), table.column("blob"), strict=True) if k == kind]
    return [np.concatenate(x) for x in zip(*found, strict=True)] if found else None


def _row_of(ids: np.ndarray, tags: np.ndarray, doc: np.ndarray, tag: np.ndarray) -> np.ndarray:
    """Number of the (first) row of each document (doc, tag); all of them are there."""
    code = np.unique(np.concatenate([ids, doc]), return_inverse=True)[1].astype(U64) << U64(32) | np.concatenate([tags, tag]).astype(U64)
    own, want = code[: len(ids)], code[len(ids) :]
    by = np.argsort(own, kind="stable")
    return by[np.searchsorted(own[by], want)]


def _context_rows(words, data, starts, ends, row, asked, length, grain, splitters) -> list[tuple]:
    """Asked anchors with their text, to the buckets of their leading tokens."""
    doc, tag, pos = asked
    span, at = length - grain, starts[row] + pos
    left, right = np.minimum(pos, span).astype(np.uint8), np.minimum(ends[row] - at, length).astype(np.uint8)
    to = np.searchsorted(splitters[:, 0], lead_tokens(words, at, grain)) if len(splitters) else np.zeros(len(at), np.int64)
    padded = np.concatenate([np.zeros(span, np.uint8), data, np.zeros(length, np.uint8)])
    order, rows = np.argsort(to, kind="stable"), []
    start = _groups(to[order])
    for s, e in zip(start, [*start[1:], len(order)], strict=True):
        i = order[s:e]
        text = padded[at[i][:, None] + np.arange(span + length)]
        rows.append((int(to[i[0]]), CONTEXTS, put(doc[i], tag[i], pos[i], left[i], right[i], text)))
    return rows


def _window_rows(words, starts, ends, ids, tags, row, asked, length, grain, parts) -> list[tuple]:
    """Hashes of all windows around anchors of long runs; the first of equal windows travels, the others are decided."""
    at = starts[row] + asked[2]
    flag = np.zeros(int(ends[-1]) + 1, np.int32)
    lo = np.maximum(at - (length - grain), starts[row])
    hi = np.minimum(at, ends[row] - length)
    ok = hi >= lo
    np.add.at(flag, lo[ok], 1)
    np.add.at(flag, hi[ok] + 1, -1)
    where = np.flatnonzero(np.cumsum(flag[:-1]) > 0)
    doc = np.searchsorted(ends, where, "right")
    main, second = (strong_hash(words, where, where + length, length, k) for k in (1, 2))
    docs, tag, pos = ids[doc], tags[doc].astype(np.uint32), (where - starts[doc]).astype(np.uint32)
    order = np.lexsort((pos, tag, docs, second, main))
    main, second, docs, tag, pos = (x[order] for x in (main, second, docs, tag, pos))
    first = np.zeros(len(main), bool)
    first[_groups(main, second)] = True
    again = ~first
    rows = [(h % parts, HITS + 16 * (h + 1), blob) for h, _, blob in _to_homes(HITS, parts, docs[again], tag[again], pos[again], np.ones(int(again.sum()), U64))]
    main, *rest = (x[first] for x in (main, second, docs, tag, pos))
    bounds = (np.arange(1, parts, dtype=np.float64) * (2.0**64 / parts)).astype(U64)
    cut_at = np.searchsorted(main, bounds)
    for p, (s, e) in enumerate(zip([0, *cut_at], [*cut_at, len(main)], strict=True)):
        if e > s:
            rows.append((p, WINDOWS, put(main[s:e], *(x[s:e] for x in rest))))
    return rows


def _look_closer(length: int, grain: int, splitters: np.ndarray, homes: int):
    """Texts of a home and the anchors that are asked for -> their contexts, or hashes of the windows that hold them."""

    def look(texts: pa.Table, blobs: pa.Table) -> pa.Table:
        rows: list[tuple] = []
        if texts.num_rows and blobs.num_rows:
            data, ends = text_buffer(texts.column("text"))
            ids, tags = (np.array(texts.column(c).combine_chunks(), np.int64) for c in ("doc", "tag"))
            starts, words = np.concatenate([[0], ends[:-1]]).astype(np.int64), words_at(data)
            if (asked := _gather(blobs, ASKS, ASK)) is not None:
                rows += _context_rows(words, data, starts, ends, _row_of(ids, tags, *asked[:2]), asked, length, grain, splitters)
            if (asked := _gather(blobs, HOT_ASKS, ASK)) is not None:
                rows += _window_rows(words, starts, ends, ids, tags, _row_of(ids, tags, *asked[:2]), asked, length, grain, homes)
        return pa.Table.from_batches([_rows(rows)])

    return look


def _prefix_classes(text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows of bytes sorted by multikey quicksort: (order, bytes that each has in common with the one before it)."""
    n, width = text.shape
    words = np.zeros((n, -(-width // 8) * 8), np.uint8)
    words[:, :width] = text
    order = multikey_order(list(np.ascontiguousarray(words.view(">u8").T).astype(U64)))
    differ = text[order[1:]] != text[order[:-1]]
    return order, np.concatenate([[0], np.where(differ.any(axis=1), differ.argmax(axis=1), width)])


def repeated_windows(text: np.ndarray, left: np.ndarray, right: np.ndarray, length: int, grain: int) -> np.ndarray:
    """Rows in document order, each the bytes around an anchor (left and right: how many of them are real) -> bit o is set if the
    window that starts o bytes before the anchor also stands in an earlier row."""
    n, span = len(text), length - grain
    mask = np.zeros(n, U64)
    after, common_after = _prefix_classes(text[:, span:])
    before, common_before = _prefix_classes(text[:, :span][:, ::-1])
    a, b = np.empty(n, np.int64), np.empty(n, np.int64)
    for o in range(span + 1):
        a[after] = np.cumsum(common_after < length - o)
        b[before] = np.cumsum(common_before < o)
        some = np.flatnonzero((left >= o) & (right >= length - o))
        kinds = a[some] * (n + 1) + b[some]
        repeats = np.ones(len(some), bool)
        repeats[np.unique(kinds, return_index=True)[1]] = False
        mask[some[repeats]] |= U64(1 << o)
    return mask


def _judge(length: int, grain: int, homes: int):
    def judge(bucket: pa.Table) -> pa.Table:
        rows = _passing(bucket, WINDOWS, CONTEXTS)
        if (held := _gather(bucket, CONTEXTS, (*ASK, np.uint8, np.uint8, np.dtype((np.void, 2 * length - grain))))) is not None:
            order = np.lexsort((held[2], held[1], held[0]))
            doc, tag, pos, left, right, text = (x[order] for x in held)
            mask = repeated_windows(text.view(np.uint8).reshape(len(doc), -1), left, right, length, grain)
            hit = mask != 0
            rows += _to_homes(HITS, homes, doc[hit], tag[hit], pos[hit], mask[hit])
        if (held := _gather(bucket, WINDOWS, WINDOW)) is not None:
            main, second, doc, tag, pos = held
            order = multikey_order([main, second, doc.view(U64) ^ U64(1 << 63), tag.astype(U64) << U64(32) | pos])
            hit = np.ones(len(order), bool)
            hit[_groups(main[order], second[order])] = False
            hit = order[hit]
            rows += _to_homes(HITS, homes, doc[hit], tag[hit], pos[hit], np.ones(len(hit), U64))
        return pa.Table.from_batches([_rows(rows)])

    return judge


_RESULT = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("removed", pa.list_(pa.int64()))])


def _apply(length: int):
    def apply(texts: pa.Table, blobs: pa.Table) -> pa.Table:
        data, ends = text_buffer(texts.column("text"))
        named, ids, tags = (texts.column(c).to_pylist() for c in ("doc_id", "doc", "tag"))
        starts = np.concatenate([[0], ends[:-1]]).astype(np.int64)
        found = []  # (doc, tag, lo, hi)
        if (x := _gather(blobs, RANGES, RANGE)) is not None:
            found.append((x[0], x[1], x[2].astype(np.int64), x[3].astype(np.int64)))
        if (x := _gather(blobs, HITS, HIT)) is not None:
            for o in range(64):
                hit = (x[3] >> U64(o) & U64(1)).astype(bool)
                p = x[2][hit].astype(np.int64) - o
                found.append((x[0][hit], x[1][hit], p, p + length))
        spans: dict[tuple[int, int], tuple] = {}
        if found:
            doc, tag, lo, hi = (np.concatenate(v) for v in zip(*found, strict=True))
            order = np.lexsort((tag, doc))
            doc, tag, lo, hi = doc[order], tag[order], lo[order], hi[order]
            at = _groups(doc, tag)
            spans = {(int(doc[s]), int(tag[s])): _merge_runs(lo[s:e], hi[s:e]) for s, e in zip(at, [*at[1:], len(doc)], strict=True)}
        out = []
        for i, (a, b) in enumerate(zip(starts.tolist(), ends.tolist(), strict=True)):
            text, n = data[a:b], b - a
            runs = spans.get((ids[i], tags[i]))
            if runs is None:
                out.append((named[i], n, 0, 0, hashlib.sha256(text).hexdigest(), []))
                continue
            s, e = np.minimum(runs[0], n), np.minimum(runs[1], n)
            kept, at = hashlib.sha256(), 0
            for x, y in zip(s.tolist(), e.tolist(), strict=True):
                kept.update(text[at:x])
                at = y
            kept.update(text[at:])
            out.append((named[i], n, int((e - s).sum()), len(s), kept.hexdigest(), np.stack([s, e], 1).ravel().tolist()))
        return pa.Table.from_pylist([dict(zip(_RESULT.names, r, strict=True)) for r in out], schema=_RESULT)

    return apply


def _sample_keys(length: int, grain: int, share: float):
    def sample(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, ends = text_buffer(b.column(2))
            _, _, lead, around, _ = anchors(data, ends, length, grain)
            pick = mix(lead ^ around) < U64(min(int(share * 2**64), 2**64 - 1))
            yield pa.RecordBatch.from_arrays([pa.array([put(lead[pick], around[pick])], pa.binary())], ["blob"])

    return sample


def sampled_splitters(rows: DataFrame, total: int, buckets: int, length: int, grain: int, sample_bytes: int = 16 << 20, sample_keys: int = 1 << 17) -> np.ndarray:
    """buckets - 1 splitters from a bounded sample of documents (sample_bytes) and of their suffixes (sample_keys)."""
    if buckets < 2 or not total:
        return np.zeros((0, 2), U64)
    share = min(1.0, sample_bytes / total)
    keys = min(1.0, sample_keys / (min(total, sample_bytes) / (length - grain) * 2))
    some = rows.sample(share, seed=11) if share < 1 else rows
    got = [get(r["blob"], U64, U64) for r in some.mapInArrow(_sample_keys(length, grain, keys), "blob binary").collect()]
    lead, around = (np.concatenate(x) for x in zip(*got, strict=True)) if got else (np.zeros(0, U64), np.zeros(0, U64))
    order = np.lexsort((around, lead))
    at = (np.arange(1, buckets) * len(order)) // buckets
    return np.unique(np.stack([lead[order][at], around[order][at]], 1), axis=0) if len(order) >= buckets else np.zeros((0, 2), U64)


def repeated_bytes(docs: DataFrame, length: int = 100, grain: int = 50, home_bytes: int = 4 << 20, bucket_bytes: int = 8 << 20, most: int = 400_000, hot: int = 100_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, removed (flat list of start, end of the removed runs) per document.

    Homes and buckets have about home_bytes and bucket_bytes of text, or more, so that there are at most `most` of each."""
    if not length - 63 <= grain < length <= 255 or grain < 8:
        raise ValueError("grain must be below length by at most 63, length at most 255")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    unnamed = F.shiftrightunsigned(F.xxhash64("text", F.lit(1)), 1).bitwiseOR(F.lit(-(1 << 63)))
    rows = rows.select(F.coalesce("doc_id", unnamed).alias("doc"), F.xxhash64("text").bitwiseAND(F.lit((1 << 32) - 1)).alias("tag"), "text", "doc_id")
    _, total = text_bytes(rows)
    homes, buckets = 1 + 2 * (min(total // home_bytes, most) // 2), 1 + min(total // bucket_bytes, most)
    keyed = rows.select("doc", "tag", "text")
    splitters = sampled_splitters(keyed, total, buckets, length, grain)
    suffixes = keyed.mapInArrow(_find_suffixes(length, grain, splitters, homes), BLOB_DDL)
    decided = cut(suffixes.groupBy("to").applyInArrow(_sort_bucket(length, grain, splitters, homes, hot), BLOB_DDL), "suffixes")
    texts = rows.select(home_column(homes).alias("home"), "doc", "tag", "doc_id", "text")
    asks = decided.where(F.col("kind").isin(ASKS, HOT_ASKS))
    closer = texts.groupBy("home").cogroup(asks.groupBy("to")).applyInArrow(_look_closer(length, grain, splitters, homes), BLOB_DDL)
    hits = closer.groupBy("to").applyInArrow(_judge(length, grain, homes), BLOB_DDL)
    verdicts = decided.where(F.col("kind") == RANGES).unionByName(hits)
    result = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, removed array<long>"
    return texts.groupBy("home").cogroup(verdicts.groupBy("to")).applyInArrow(_apply(length), result)
