"""MinHash near-dedup: improved consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard similarity.

A document is a weighted set of shingles of five words (words: runs without white space, A-Z in lower case). The weight of a
shingle is (1 + ln tf) * idf, with idf = 1 + damping * ln(1 / share) / ln(1 / rare): share is its exact document frequency over the number of
documents, and `rare` (1 / 1024) stands for all shares below it. So idf depends on shares alone, not on the size of the corpus, and only shingles
in at least that share of all documents need a table: there are at most (shingles of a mean document) / rare of them, however many documents there
are. They are found in two passes: counts per hash slot, which can only be too high, name the slots that may hold one; the shingles in these slots are then
counted exactly. The damping keeps idf in [1, 1 + damping]: with an undamped idf the shingles that a large
group of near copies shares would weigh next to nothing and the group would fall below the threshold.

1. Texts that are equal as shingle sequences (128-bit hash) form one class; its least id stands for it from here on.
2. Signatures: `bands` bands of `rows` samples by improved consistent weighted sampling. Samples of equal shingles and
   weights are equal, so two documents agree in a sample with a probability of their weighted Jaccard similarity.
3. Within a band bucket, members first meet `reps` of its members (least under as many hash orders), found by aggregates: pairs
   grow linearly. Those are kept that agree in so many samples of the whole signature as a pair at the threshold misses once in
   some thousand times (only the best one if all but one sample agree). Members that are sure of none of them meet
   again in finer buckets (of two bands), so that a bucket which mixes several groups comes apart.
4. Pairs are verified on the whole texts by weighted Jaccard similarity of at least `threshold`; connected components of the links.
5. What the representatives have left apart: all members of a bucket that are in different components meet, in blocks of bounded size (rows and bytes).
   At first each is verified with the most alike and the most central one of a block only (a hub of copies is central). Then, with the
   components grown, the blocks get the texts and verify, in the first bucket that a pair shares, every pair that agrees in enough samples and is still apart;
   only links leave a block, and no more than join its members. So the classes are the components of all links between documents that share a bucket.

Edge cases. Null or empty text, texts below `shingle` words: the words there are form one shingle; texts without words
are all equal. Rows that repeat an id: one document. Rows without an id: in no class. Very long texts: hashed in slices. Empty table: empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockmf.llm.common import cut, lean, text_bytes, text_or_empty
from blockmf.llm.components import connected_components
from blockmf.llm.suffix_dedup import U64, RangeHash, mix, text_buffer

RARE = 1 / 1024  # least share of documents that idf tells apart
CHUNK, CHUNK_BYTES = 1024, 16 << 20  # members of a bucket and bytes of their texts on either side of a block
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[9, 10, 11, 12, 13, 28, 29, 30, 31, 32]] = True

# Tables from which samples draw: index = 16 bits of a hash. r, ln c ~ Gamma(2, 1), beta uniform.
_rng = np.random.default_rng(7)
_R = _rng.gamma(2.0, 1.0, 1 << 16).astype(np.float32)
_LN_C = np.log(_rng.gamma(2.0, 1.0, 1 << 16)).astype(np.float32)


def shingles(data: np.ndarray, ends: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(document number, 64-bit hash) of each shingle occurrence in a buffer of documents, in order."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, U64)
    space = _IS_SPACE[data]
    doc_start = np.concatenate([[0], ends[:-1]])
    before = np.concatenate([[True], space[:-1]])
    before[doc_start[doc_start < len(data)]] = True
    after = np.concatenate([space[1:], [True]])
    after[ends[(ends > 0)] - 1] = True
    w_start, w_end = np.flatnonzero(~space & before), np.flatnonzero(~space & after) + 1
    if not len(w_start):
        return np.zeros(0, np.int64), np.zeros(0, U64)
    # words one after the other without spaces; a separator byte ends each, so that word borders count
    keep = ~space
    at = np.cumsum(keep) - 1
    number = np.cumsum(keep & before) - 1
    packed = np.zeros(int(at[-1]) + 1 + len(w_start), np.uint8)
    pos = at[keep] + number[keep]
    packed[pos] = _LOWER[data[keep]]
    lens = w_end - w_start
    p_end = np.cumsum(lens + 1)
    p_start = p_end - lens - 1
    doc = np.searchsorted(ends, w_start, "right")
    n_words = np.bincount(doc, minlength=len(ends))
    first_word = np.cumsum(n_words) - n_words
    last = np.minimum(np.arange(len(doc)) + size, (first_word + n_words)[doc])  # word after the shingle
    full = (last - np.arange(len(doc)) == size) | (np.arange(len(doc)) == first_word[doc])
    i = np.flatnonzero(full)
    out = np.empty(len(i), U64)
    step = 1 << 18
    for lo in range(0, len(i), step):  # prefix sums in slices
        part = i[lo : lo + step]
        a, b = int(p_start[part[0]]), int(p_end[last[part[-1]] - 1])
        h = RangeHash(packed[a:b])
        out[lo : lo + step] = mix(h(p_start[part] - a, p_end[last[part] - 1] - a))
    return doc[i], out


def _distinct(doc: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, shingle, times), ordered."""
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])])) if len(doc) else np.zeros(0, np.int64)
    return doc[new], h[new], np.diff(np.concatenate([new, [len(doc)]]))


def _cut_batch(data: np.ndarray, ends: np.ndarray, size: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Document ranges of about `size` bytes."""
    i = 0
    while i < len(ends):
        start = ends[i - 1] if i else 0
        j = max(i + 1, int(np.searchsorted(ends, start + size, "right")))
        yield i, j
        i = j


def _count_df(size: int, slots: int):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, docs = np.zeros(slots, np.int64), 0
        for b in batches:
            data, ends = text_buffer(b.column(0))
            docs += len(ends)
            for i, j in _cut_batch(data, ends):
                lo = int(ends[i - 1]) if i else 0
                _, h, _ = _distinct(*shingles(data[lo : int(ends[j - 1])], ends[i:j] - lo, size))
                table += np.bincount((h % U64(slots)).astype(np.int64), minlength=slots)
        used = np.flatnonzero(table)
        step = 1 << 16
        for lo in range(0, slots, step):
            u = used[(used >= lo) & (used < lo + step)]
            if len(u):
                part = np.zeros(step, "<i4")
                part[u - lo] = np.minimum(table[u], 2**31 - 1)
                yield pa.RecordBatch.from_pydict({"block": [lo // step], "counts": [part.tobytes()], "docs": [docs if lo == 0 else 0]}, schema=_COUNTS)
        if not len(used):
            yield pa.RecordBatch.from_pydict({"block": [0], "counts": [np.zeros(step, "<i4").tobytes()], "docs": [docs]}, schema=_COUNTS)

    return lean(count)


_COUNTS = pa.schema([("block", pa.int32()), ("counts", pa.binary()), ("docs", pa.int64())])


def _add_counts(parts: pa.Table) -> pa.Table:
    total = np.zeros(1 << 16, np.int64)
    for blob in parts.column("counts"):
        total += np.frombuffer(blob.as_py(), "<i4")
    docs = sum(parts.column("docs").to_pylist())
    return pa.Table.from_pydict({"block": [parts.column("block")[0].as_py()], "counts": [np.minimum(total, 2**31 - 1).astype("<i4").tobytes()], "docs": [docs]}, schema=_COUNTS)


@dataclass(frozen=True)
class Idf:
    """idf by shingle hash: a table of the shingles that are in at least a share `rare` of the documents; all others have the greatest value."""

    hashes: np.ndarray  # ascending
    values: np.ndarray
    most: float
    slots: np.ndarray  # of each hash slot, whether the table may hold one of its shingles

    def __call__(self, h: np.ndarray) -> np.ndarray:
        out = np.full(len(h), self.most, np.float32)
        if len(self.hashes):
            at = np.flatnonzero(self.slots[(h % U64(len(self.slots))).astype(np.intp)])
            place = np.minimum(np.searchsorted(self.hashes, h[at]), len(self.hashes) - 1)
            known = self.hashes[place] == h[at]
            out[at[known]] = self.values[place[known]]
        return out


def _count_exactly(size: int, maybe: np.ndarray, keep: int = 1 << 20):
    """Counts of the shingles in the slots that may hold a frequent one; summed in the task while there are at most `keep` of them."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        n = 0

        def flush() -> pa.RecordBatch:
            h, times = np.unique(np.concatenate(held), return_counts=True)
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(times.astype(np.int64))], ["h", "n"])

        for b in batches:
            data, ends = text_buffer(b.column(0))
            for i, j in _cut_batch(data, ends):
                lo = int(ends[i - 1]) if i else 0
                _, h, _ = _distinct(*shingles(data[lo : int(ends[j - 1])], ends[i:j] - lo, size))
                held.append(h[maybe[(h % U64(len(maybe))).astype(np.intp)]])
                n += len(held[-1])
                if n >= keep:
                    yield flush()
                    n = 0
        if n:
            yield flush()

    return lean(count)


def idf_table(docs: DataFrame, size: int = 5, damping: float = 0.25, rare: float = RARE, text_col: str = "text") -> Idf:
    """idf from the document frequencies of all documents. Slots travel in blocks and are summed in two steps; the driver gets one count per slot (their number
    depends on the mean length of the documents) and the table of frequent shingles."""
    ddl = "block int, counts binary, docs long"
    texts = docs.select(text_or_empty(text_col).alias("text"))
    n, total = text_bytes(texts)
    shingles_each = total / max(n, 1) / 4 + 1  # words have three letters and a space at least, on average
    slots = 1 << max(16, min(24, math.ceil(math.log2(2 * shingles_each / rare))))
    salted = texts.mapInArrow(_count_df(size, slots), ddl).withColumn("salt", F.pmod(F.xxhash64("counts"), F.lit(16)))
    some = salted.groupBy("block", "salt").applyInArrow(lambda t: _add_counts(t.drop_columns(["salt"])), ddl)
    df = np.zeros(slots, np.int32)
    for r in some.groupBy("block").applyInArrow(_add_counts, ddl).toLocalIterator():
        df[r["block"] << 16 : (r["block"] + 1) << 16] = np.frombuffer(r["counts"], "<i4")
    least = max(1, math.ceil(rare * n))
    maybe = df >= least
    counts = texts.mapInArrow(_count_exactly(size, maybe), "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where(F.col("n") >= least).toPandas()
    order = np.argsort(counts["h"].to_numpy().astype(np.int64).view(U64))
    h, share = counts["h"].to_numpy().astype(np.int64).view(U64)[order], counts["n"].to_numpy().astype(np.float64)[order] / max(n, 1)
    values = 1 + damping * np.log(1 / np.clip(share, rare, 1)) / math.log(1 / rare)
    return Idf(h, values.astype(np.float32), 1 + damping, maybe)


def icws(doc: np.ndarray, h: np.ndarray, ln_w: np.ndarray, n_docs: int, samples: int) -> np.ndarray:
    """(n_docs, samples) sample codes; rows of documents without shingles are 0."""
    out = np.zeros((n_docs, samples), np.uint32)
    if not len(doc):
        return out
    first = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
    who = doc[first]
    for k in range(samples):
        x = mix(h + U64((k * 0x632BE59BD9B4E019 + 0x9E3779B97F4A7C15) & (2**64 - 1)))
        r, ln_c = _R[(x & U64(0xFFFF)).astype(np.intp)], _LN_C[((x >> U64(16)) & U64(0xFFFF)).astype(np.intp)]
        beta = ((x >> U64(32)) & U64(0xFFFF)).astype(np.float32) * np.float32(1 / 65536)
        t = np.floor(ln_w / r + beta)
        ln_a = ln_c - r * (t - beta + 1)
        bits = (ln_a + np.float32(0)).view(np.int32)
        sortable = (bits ^ ((bits >> 31) & np.int32(0x7FFFFFFF))).astype(np.int64) + (1 << 31)
        code = (x >> U64(32)) ^ (t.astype(np.int64).astype(U64) * U64(0x9E3779B1)) & U64(0xFFFFFFFF)
        least = np.minimum.reduceat((sortable.astype(U64) << U64(32)) | (code & U64(0xFFFFFFFF)), first)
        out[who, k] = least.astype(np.uint32)
    return out


def _signatures(size: int, samples: int, idf: Idf):
    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, ends = text_buffer(b.column(1))
            for i, j in _cut_batch(data, ends):
                lo = int(ends[i - 1]) if i else 0
                doc, h = shingles(data[lo : int(ends[j - 1])], ends[i:j] - lo, size)
                n = j - i
                # fingerprint of the sequence of shingles: two sums of hashes mixed with their places
                first, end = np.searchsorted(doc, np.arange(n), "left"), np.searchsorted(doc, np.arange(n), "right")
                at = (np.arange(len(doc)) - first[doc] + 1).astype(U64)
                prints = []
                for odd in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
                    c = np.concatenate([np.zeros(1, U64), np.cumsum(mix(h ^ mix(at * U64(odd))), dtype=U64)])
                    prints.append(pa.array(mix(c[end] - c[first]).view(np.int64)))
                d, u, tf = _distinct(doc, h)
                ln_w = np.log((1 + np.log(tf.astype(np.float32))) * idf(u))
                code = icws(d, u, ln_w, n, samples)
                sig = pa.FixedSizeListArray.from_arrays(pa.array(code.view(np.int32).ravel()), samples).cast(pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, n), *prints, sig, pa.array(np.diff(ends[i:j], prepend=lo))], ["doc_id", "fp1", "fp2", "sig", "size"])

    return lean(sign)


def _weigh(text: str, size: int, idf: Idf) -> tuple[np.ndarray, np.ndarray]:
    raw = np.frombuffer(text.encode(), np.uint8)
    _, h = shingles(raw, np.array([len(raw)]), size)
    _, u, tf = _distinct(np.zeros(len(h), np.int64), h)
    return u, (1 + np.log(tf.astype(np.float64))) * idf(u)


def weighted_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    both, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    least = float(np.minimum(a[1][i], b[1][j]).sum())
    most = float(a[1].sum() + b[1].sum()) - least
    return least / most if most else 1.0


def _verify(size: int, idf: Idf):
    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple | None = None
        for batch in batches:
            sims = []
            for a, ta, tb in zip(batch.column(0).to_pylist(), batch.column(2), batch.column(3), strict=True):
                if last is None or last[0] != a:  # the merge join leaves pairs of one document together
                    last = (a, _weigh(ta.as_py(), size, idf))
                sims.append(weighted_jaccard(last[1], _weigh(tb.as_py(), size, idf)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sims, pa.float64())], ["b", "a", "sim"])

    return lean(verify)


def _met_reps(members: DataFrame, reps: int) -> DataFrame:
    """members(key, doc_id, sig, more columns) -> the same with met: array of (agree, rep), best first: samples shared with the bucket's representatives.
    The first representative is least under one order for all buckets, the others under orders of each bucket."""
    orders = [F.xxhash64(F.col("doc_id"), F.lit(0)) if t == 0 else F.xxhash64(F.col("doc_id"), F.col("key"), F.lit(t)) for t in range(reps)]
    of = [F.min(F.struct(o.alias("x"), F.col("doc_id").alias("i"), F.col("sig").alias("s"))).alias(f"r{t}") for t, o in enumerate(orders)]
    chosen = members.groupBy("key").agg(F.count(F.lit(1)).alias("n"), *of).where("n > 1")
    met = members.join(chosen.select("key", F.array(*[f"r{t}" for t in range(reps)]).alias("reps")), "key")
    agree = F.expr("transform(filter(reps, r -> r.i != doc_id), r -> struct(aggregate(zip_with(sig, r.s, (x, y) -> int(x = y)), 0, (a, e) -> a + e) as agree, r.i as rep))")
    return met.select(*members.columns, F.sort_array(F.array_distinct(agree), asc=False).alias("met"))


def candidate_pairs(heads: DataFrame, bands: int, rows: int, reps: int, least: int, sure: int) -> tuple[DataFrame, DataFrame]:
    """heads(doc_id, sig, size) -> buckets of two members and more (key, band, doc_id, sig, size); distinct pairs (a, b), a < b, with representatives."""
    samples = bands * rows
    keys = F.array(*[F.xxhash64(F.lit(i), F.slice("sig", i * rows + 1, rows)) for i in range(bands)])
    coarse = cut(_met_reps(heads.select(F.posexplode(keys).alias("band", "key"), "doc_id", "sig", "size"), reps), "buckets")
    loose = coarse.where(F.get("met", F.lit(0))["agree"] < sure).select("key", "doc_id", "sig")
    fine = _met_reps(loose.select(F.explode(F.transform(keys, lambda k: F.xxhash64("key", k))).alias("key"), "doc_id", "sig"), reps)
    # all that may be near; if the best is all but equal, what is near to it is near to its other neighbours through it
    kept = F.expr(f"if(get(met, 0).agree >= {samples - 1}, slice(met, 1, 1), filter(met, m -> m.agree >= {least}))")
    met = coarse.select("doc_id", kept.alias("met")).unionByName(fine.select("doc_id", kept.alias("met"))).select("doc_id", F.explode("met").alias("m"))
    return coarse.drop("met"), met.select(F.least("doc_id", "m.rep").alias("a"), F.greatest("doc_id", "m.rep").alias("b")).distinct()


def _block_pairs(agree: np.ndarray, ok: np.ndarray, both: bool) -> tuple[np.ndarray, np.ndarray]:
    """Places of the pairs of each row of a block (both: and of each column) with its most alike and its most central partner."""
    value = np.where(ok, agree, 0).astype(np.int64)
    rows, cols = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    for v, i, j in ((value, rows, cols), (value.T, cols, rows))[: 1 + both]:
        some = np.flatnonzero(v.any(axis=1))
        if len(some):
            central = v.sum(axis=0)
            i += [some, some]
            j += [v[some].argmax(axis=1), np.where(v[some] > 0, central, -1).argmax(axis=1)]
    return np.concatenate(rows), np.concatenate(cols)


def _apart(c, texts, i, j, size: int, idf: Idf, threshold: float) -> tuple[list[int], list[int]]:
    """Places of the pairs (i, j) of a block that are links and join what no link found before has joined. Each text is weighed once."""
    root = {x: x for x in c.tolist()}

    def find(x):
        while root[x] != x:
            root[x] = x = root[root[x]]
        return x

    weighed: dict[int, tuple] = {}

    def weight(k):
        if k not in weighed:
            weighed[k] = _weigh(texts[k].as_py(), size, idf)
        return weighed[k]

    left, right = [], []
    for x, y in zip(i.tolist(), j.tolist(), strict=True):
        a, b = find(c[x]), find(c[y])
        if a != b and weighted_jaccard(weight(x), weight(y)) >= threshold:
            root[a] = b
            left.append(x)
            right.append(y)
    return left, right


def _cross(samples: int, rows: int, least: int, verify: tuple | None):
    """verify: None for the pairs of each member with the most alike and the most central one; (size, idf, threshold) for all links."""

    def cross(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None  # the last block may go on in the next batch
        for batch in chain(batches, [None]):
            parts = [t for t in (held, None if batch is None else pa.Table.from_batches([batch])) if t is not None]
            if not parts or not (t := pa.concat_tables(parts).combine_chunks()).num_rows:
                continue
            key, x, y, chunk, both, doc, c, band = (t.column(n).to_numpy() for n in ("key", "x", "y", "chunk", "both", "doc_id", "c", "band"))
            starts = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (x[1:] != x[:-1]) | (y[1:] != y[:-1])]))
            ends = np.concatenate([starts[1:], [len(key)]])
            if batch is not None:
                held, starts, ends = t.slice(starts[-1]), starts[:-1], ends[:-1]
            sig = t.column("sig").combine_chunks().flatten().to_numpy().reshape(-1, samples)
            a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for lo, hi in zip(starts.tolist(), ends.tolist(), strict=True):
                at = np.arange(lo, hi)
                same = x[lo] == y[lo]
                left, right = (at, at) if same else (at[chunk[lo:hi] == x[lo]], at[chunk[lo:hi] == y[lo]])
                ok = c[left][:, None] != c[right]
                if same:
                    ok &= left[:, None] < right if verify else True
                if not ok.any():
                    continue
                agree, seen = np.zeros(ok.shape, np.int16), np.zeros(ok.shape, bool)
                for k in range(0, samples, rows):
                    equal = [sig[left, m][:, None] == sig[right, m] for m in range(k, k + rows)]
                    agree += np.sum(equal, axis=0, dtype=np.int16)
                    if verify and k // rows < band[lo]:
                        seen |= np.logical_and.reduce(equal)  # the pair meets in the bucket of an earlier band
                ok &= (agree >= least) & ~seen
                if verify:
                    i, j = np.nonzero(ok)
                    best = np.argsort(-agree[i, j], kind="stable")
                    i, j = _apart(c, t.column("text"), left[i[best]], right[j[best]], *verify)
                else:
                    i, j = _block_pairs(agree, ok, bool(both[lo]) and not same)
                    i, j = left[i], right[j]
                a.append(np.minimum(doc[i], doc[j]))
                b.append(np.maximum(doc[i], doc[j]))
            a, b = np.concatenate(a).astype(np.int64), np.concatenate(b).astype(np.int64)
            for lo in range(0, len(a), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(a[lo : lo + (1 << 16)]), pa.array(b[lo : lo + (1 << 16)])], ["a", "b"])

    return lean(cross)


def cross_pairs(buckets: DataFrame, label: DataFrame, samples: int, rows: int, least: int, base: DataFrame | None = None, verify: tuple | None = None) -> DataFrame:
    """buckets(key, band, doc_id, sig, size), label(doc_id, c) -> distinct pairs (a, b), a < b, of a bucket that are in different components c: candidates, or
    links if verify = (shingle size, idf, threshold) and base(doc_id, text) are given.

    The members of a bucket's largest component meet the others, and the others meet each other, in blocks of two chunks."""
    per = buckets.select("key", "doc_id", "size").join(label, "doc_id").groupBy("key", "c").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("b"))
    mixed = per.groupBy("key").agg(F.max(F.struct("n", "c", "b")).alias("most"), F.sum("n").alias("n"), F.sum("b").alias("b"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
    chunks = lambda n, b: f"int(greatest(1, ceil(({n}) / {CHUNK}), ceil(({b}) / {CHUNK_BYTES})))"
    sizes = mixed.select("key", F.col("most.c").alias("major"), F.expr(chunks("n - most.n", "b - most.b")).alias("gu"), F.expr(chunks("most.n", "most.b")).alias("gl"))
    members = buckets.join(sizes, "key").join(label, "doc_id")
    members = members.withColumn("chunk", F.expr("int(if(c = major, gu + pmod(xxhash64(doc_id, key), gl), pmod(xxhash64(doc_id, key), gu)))"))
    columns = ["doc_id", "c", "sig"]
    if verify:
        members, columns = members.join(base, "doc_id"), [*columns, "text"]
    blocks = F.expr("filter(transform(sequence(0, gu + gl - 1), i -> struct(least(i, chunk) as x, greatest(i, chunk) as y)), z -> z.x < gu)")
    dealt = members.select("key", "band", *columns, "chunk", "gu", F.explode(blocks).alias("z")).select("key", "z.x", "z.y", "chunk", F.expr("z.y < gu").alias("both"), "band", *columns)
    ordered = dealt.repartition("key", "x", "y").sortWithinPartitions("key", "x", "y")
    return ordered.mapInArrow(_cross(samples, rows, least, verify), "a long, b long").distinct()


def _merged(label: DataFrame, links: DataFrame) -> DataFrame:
    """label(doc_id, c) after the components that links (a, b) join have become one."""
    ends = links.join(label.select(F.col("doc_id").alias("a"), F.col("c").alias("ca")), "a").join(label.select(F.col("doc_id").alias("b"), F.col("c").alias("cb")), "b")
    comp = connected_components(ends, "ca", "cb")
    return cut(label.join(comp, label["c"] == comp["node"], "left").select("doc_id", F.coalesce("component", "c").alias("c")), "label")


def near_classes(docs: DataFrame, threshold: float = 0.8, size: int = 5, bands: int = 8, rows: int = 3, reps: int = 3, damping: float = 0.25, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, class_id (least id of the class) for each distinct id."""
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text")).where("doc_id is not null")
    idf = idf_table(base, size, damping=damping)
    samples = bands * rows
    spread = math.sqrt(samples * threshold * (1 - threshold))
    least, sure = math.floor(samples * threshold - 3.2 * spread), math.floor(samples * threshold - spread)
    signed = cut(base.mapInArrow(_signatures(size, samples, idf), "doc_id long, fp1 long, fp2 long, sig array<int>, size long"), "signatures")
    # copies meet their head by fingerprint and salt, so that a group of copies with a third of all rows is dealt over many tasks
    salted = signed.select("doc_id", "fp1", "fp2", F.pmod(F.xxhash64("doc_id"), F.lit(32)).alias("salt"))
    parts = salted.groupBy("fp1", "fp2", "salt").agg(F.min("doc_id").alias("least"))
    same = parts.groupBy("fp1", "fp2").agg(F.min("least").alias("head"))
    known = parts.select("fp1", "fp2", "salt").join(same, ["fp1", "fp2"])
    member = cut(salted.join(known, ["fp1", "fp2", "salt"]).select("doc_id", "head").distinct(), "heads")
    heads = signed.join(member.where("doc_id = head").select("doc_id"), "doc_id", "left_semi").select("doc_id", "sig", "size")
    buckets, pairs = candidate_pairs(heads, bands, rows, reps, least, sure)
    tried, label = cut(pairs, "pairs"), heads.select("doc_id", F.col("doc_id").alias("c"))
    label = _merged(label, _links(base, tried, size, idf, threshold))
    new = cut(cross_pairs(buckets, label, samples, rows, least).join(tried, ["a", "b"], "left_anti"), "cross")
    label = _merged(label, _links(base, new, size, idf, threshold))
    label = _merged(label, cut(cross_pairs(buckets, label, samples, rows, least, base, (size, idf, threshold)), "links"))
    classes = label.withColumnsRenamed({"doc_id": "head", "c": "class_id"})
    return member.join(classes, "head").select("doc_id", "class_id")


def _links(base: DataFrame, pairs: DataFrame, size: int, idf: Idf, threshold: float) -> DataFrame:
    return cut(verify_pairs(base, pairs, size, idf).where(F.col("sim") >= threshold).select("a", "b").distinct(), "links")


def verify_pairs(base: DataFrame, pairs: DataFrame, size: int, idf: Idf) -> DataFrame:
    """pairs (a, b) -> a, b, sim. Each text is read with its pairs only: texts go to their pairs by id, once for either side."""
    left = pairs.join(base.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")
    both = left.join(base.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
    ordered = both.select("b", "a", "text_b", "text_a")
    return ordered.mapInArrow(_verify(size, idf), "b long, a long, sim double").select("a", "b", "sim")


def drop_near_copies(docs: DataFrame, threshold: float = 0.8, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of docs that stay: of each class the document with the least id; rows without an id stay. Columns of docs may have any names."""
    keep = near_classes(docs, threshold, id_col=id_col, **options).where("doc_id = class_id").select(F.col("doc_id").alias("_kept_id"))
    unnamed = F.col(id_col).isNull()
    return docs.where(~unnamed).join(keep, F.col(id_col).cast("long") == F.col("_kept_id"), "left_semi").unionByName(docs.where(unnamed))
