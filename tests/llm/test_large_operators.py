"""Operators 7, 8, 9, 10 and the pipeline against brute force and on edge cases."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter
from functools import lru_cache

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockmf.llm import near_dedup, packing, suffix_dedup, token_files
from blockmf.llm.common import scratch_path
from blockmf.llm.tokenize import PieceTokenizer, vocabulary

DOCS = "doc_id long, text string"


@pytest.fixture(scope="module")
def sample(spark, sf):
    return [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]


def covered(rows, length=100):
    seen, out = set(), {}
    for d, t in sorted(rows):
        b = (t or "").encode()
        hit = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if (w := b[p : p + length]) in seen:
                hit[p : p + length] = b"\1" * length
            else:
                seen.add(w)
        runs = sum(1 for i, c in enumerate(hit) if c and (i == 0 or not hit[i - 1]))
        out[d] = (len(b), sum(hit), runs, hashlib.sha256(bytes(x for x, c in zip(b, hit, strict=True) if not c)).hexdigest())
    return out


def made_texts():
    r = random.Random(1)
    rows = [(1000 + i, x) for i, x in enumerate(["", None, "a" * 99, "a" * 100, "a" * 101, "a" * 350, "ab" * 200, "xyz" * 70, "q" * 5000])]
    base = "".join(r.choice("abcd éß") for _ in range(3000))
    for i in range(60):
        a, n = r.randrange(2500), r.choice([80, 99, 100, 101, 150, 180, 400])
        junk = lambda: "".join(r.choice("efgh") for _ in range(r.randrange(60)))
        rows.append((2000 + i * 7, junk() + base[a : a + n] + junk() + base[a + 50 : a + 50 + n]))
    return rows


@pytest.mark.parametrize("sizes", [{}, {"home_bytes": 1 << 15, "bucket_bytes": 1 << 15}, {"bucket_bytes": 1 << 15, "hot": 2}, {"bucket_bytes": 1 << 16, "hot": 0, "grain": 40}])
def test_suffix_dedup_is_brute_force(spark, sample, sizes):
    rows = sample[:150] + made_texts()
    docs = spark.createDataFrame(rows, DOCS).repartition(6).withColumn("home", F.lit("clash"))
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.repeated_bytes(docs, **sizes).collect()}
    assert got == covered(rows)


def test_suffix_dedup_slices_and_order(monkeypatch):
    """Anchors of a text cut in slices are those of the whole text; multikey quicksort sorts."""
    r = random.Random(3)
    data = np.frombuffer("".join(r.choice("abcdefg ") for _ in range(20_000)).encode(), np.uint8)
    ends = np.array([50, 700, 19_000, 20_000])
    whole = suffix_dedup.anchors(data, ends, 100, 50)
    monkeypatch.setattr(suffix_dedup, "SLICE", 1500)
    for a, b in zip(whole, suffix_dedup.anchors(data, ends, 100, 50), strict=True):
        assert (a == b).all()
    rng = np.random.default_rng(0)
    keys = [rng.integers(0, 5, 3000).astype(np.uint64) for _ in range(3)]
    order = suffix_dedup.multikey_order(keys, cutoff=10)
    rows = list(zip(*(k[order].tolist() for k in keys), strict=True))
    assert rows == sorted(rows) and sorted(order.tolist()) == list(range(3000))


def test_suffix_dedup_edges(spark):
    rows = [(1, "z" * 150), (1, "z" * 150), (None, "only"), (2, None)]
    got = sorted((r.doc_id or -1, r.n_bytes, r.n_removed) for r in suffix_dedup.repeated_bytes(spark.createDataFrame(rows, DOCS)).collect())
    assert got == [(-1, 4, 0), (1, 150, 149), (1, 150, 149), (2, 0, 0)]
    assert suffix_dedup.repeated_bytes(spark.createDataFrame([], DOCS)).count() == 0


@pytest.mark.parametrize("hot", [0, 100_000])
def test_suffix_dedup_repeated_and_null_ids(spark, hot):
    """Rows of one id with different texts, and rows without an id, are documents of their own: no row loses bytes of another one."""
    r = random.Random(8)
    text = lambda n: "".join(r.choice("abcdefgh ") for _ in range(n))
    a, b, c = text(600), text(600), text(600)
    rows = [(1, a), (7, a), (7, b), (7, c), (8, c[100:400] + b[:300]), (None, b[200:500] + "!"), (None, b[200:500] + "?"), (None, text(300)), (-1, c), (-1, text(200))]
    docs = spark.createDataFrame(rows, DOCS).repartition(4)
    tag = F.xxhash64("text").bitwiseAND(F.lit((1 << 32) - 1))
    null_first = F.shiftrightunsigned(F.xxhash64("text", F.lit(1)), 1).bitwiseOR(F.lit(-(1 << 63)))
    ordered = docs.orderBy(F.coalesce("doc_id", null_first), tag).collect()
    want = covered([(k, x.text) for k, x in enumerate(ordered)])
    got = suffix_dedup.repeated_bytes(docs, hot=hot, bucket_bytes=1 << 10).collect()
    key = lambda i, *rest: (i is None, i or 0, *rest)
    assert sorted(key(x.doc_id, x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in got) == sorted(key(i, *want[k]) for k, i in enumerate(x.doc_id for x in ordered))


def test_suffix_dedup_hot_passage(spark):
    """A passage in every document, with other surroundings each time, alone in its buckets."""
    r = random.Random(2)
    text = lambda n: "".join(r.choice("abcdefgh ") for _ in range(n))
    passage = text(160)
    rows = [(i, text(90) + passage + text(r.randrange(90))) for i in range(400)]
    docs = spark.createDataFrame(rows, DOCS).repartition(3)
    for hot in (50, 100_000):
        got = {x.doc_id: (x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in suffix_dedup.repeated_bytes(docs, hot=hot, bucket_bytes=1 << 12).collect()}
        assert got == covered(rows)


def plain_weights(texts, damping=0.25, rare=1 / 1024):
    """Weighted shingle sets by dictionaries, from the definition."""
    sets = []
    for t in texts:
        words = [w for w in re.split("[\t\n\x0b\x0c\r\x1c-\x20]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) if w]
        sets.append(Counter(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else Counter())
    df = Counter(s for x in sets for s in x)
    idf = lambda s: 1 + damping * math.log(1 / max(rare, df[s] / len(texts))) / math.log(1 / rare) if df[s] >= math.ceil(rare * len(texts)) else 1 + damping
    return [{s: (1 + math.log(n)) * idf(s) for s, n in x.items()} for x in sets]


def plain_jaccard(a, b):
    least = sum(min(w, b[s]) for s, w in a.items() if s in b)
    return least / (sum(a.values()) + sum(b.values()) - least) if a or b else 1.0


def test_weights_are_the_definition(spark, sample):
    texts = [t for _, t in sample[:300]]
    idf = near_dedup.idf_table(spark.createDataFrame(sample[:300], DOCS).repartition(3))
    plain, got = plain_weights(texts), [near_dedup._weigh(t or "", 5, idf) for t in texts]
    for i in range(len(texts)):
        assert got[i][1].sum() == pytest.approx(sum(plain[i].values()), rel=1e-5)
        for j in range(i):
            if a := near_dedup.weighted_jaccard(got[i], got[j]):
                assert a == pytest.approx(plain_jaccard(plain[i], plain[j]), abs=1e-5)


def test_weights_do_not_depend_on_the_number_of_documents(spark):
    """A corpus of three times the documents with the same shares has the same weights."""
    texts = [" ".join(f"w{(i * 7 + j) % 900}" for j in range(200)) for i in range(60)]
    one = near_dedup.idf_table(spark.createDataFrame(list(enumerate(texts)), DOCS), rare=0.05)
    three = near_dedup.idf_table(spark.createDataFrame(list(enumerate(texts * 3)), DOCS), rare=0.05)
    assert (one.hashes == three.hashes).all() and one.values == pytest.approx(three.values)


def test_near_dedup_is_brute_force(spark, sample):
    docs = spark.createDataFrame(sample, DOCS)
    got = {r.doc_id: r.class_id for r in near_dedup.near_classes(docs).collect()}
    w = dict(zip([d for d, _ in sample], plain_weights([t for _, t in sample]), strict=True))
    parent = {d: d for d in w}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in w:
        for b in w:
            if a < b and not w[a].keys().isdisjoint(w[b]) and plain_jaccard(w[a], w[b]) >= 0.8:
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    assert got == {d: root(d) for d in w}


@pytest.mark.parametrize("copies", [10, 100, 1000])
@pytest.mark.parametrize("chunk", [None, 64])
def test_near_dedup_star_is_brute_force(spark, copies, chunk, monkeypatch):
    """Copies near the original but not near each other: links that no representative has."""
    if chunk:
        monkeypatch.setattr(near_dedup, "CHUNK", chunk)
    r = random.Random(copies)
    words = [f"w{r.randrange(10**6)}" for _ in range(300)]
    texts = [words]
    for _ in range(copies):
        texts.append([*words])
        for i in r.sample(range(300), 5):
            texts[-1][i] = f"x{r.randrange(10**9)}"
    ids = r.sample(range(10 * copies), copies + 1)
    docs = spark.createDataFrame([(d, " ".join(t)) for d, t in zip(ids, texts, strict=True)], DOCS)
    w = plain_weights([" ".join(t) for t in texts])
    left, want = set(range(copies + 1)), {}
    while left:  # components by search over all pairs
        group, todo = set(), [left.pop()]
        while todo:
            a = todo.pop()
            group.add(a)
            near = {b for b in left if plain_jaccard(w[a], w[b]) >= 0.8}
            left -= near
            todo += near
        want |= {ids[a]: min(ids[b] for b in group) for a in group}
    assert len(set(want.values())) < copies / 5
    got = {x.doc_id: x.class_id for x in near_dedup.near_classes(docs).collect()}
    assert sum(got[d] != c for d, c in want.items()) == 0


def test_near_dedup_edges(spark):
    r = random.Random(5)
    words = [f"w{r.randrange(10**6)}" for _ in range(400)]
    near = [*words]
    near[100] = "other"
    rows = [(1, " ".join(words)), (2, "  ".join(words).upper()), (3, " ".join(near)), (4, None), (5, ""), (6, "two words"), (7, "Two  words"), (3, " ".join(near)), (None, "x"), (8, " ".join(words[:200])), (9, " ".join(words) * 40)]
    docs = spark.createDataFrame(rows, DOCS).withColumn("class_id", F.lit("clash"))
    got = {x.doc_id: x.class_id for x in near_dedup.near_classes(docs).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 6: 6, 7: 6, 8: 8, 9: 9}
    assert sorted((x.doc_id or -1) for x in near_dedup.drop_near_copies(docs).collect()) == [-1, 1, 4, 6, 8, 9]
    renamed = docs.withColumnsRenamed({"doc_id": "key", "text": "body"}).withColumn("doc_id", F.lit("clash"))
    assert sorted((x.key or -1) for x in near_dedup.drop_near_copies(renamed, id_col="key", text_col="body").collect()) == [-1, 1, 4, 6, 8, 9]
    assert near_dedup.near_classes(spark.createDataFrame([], DOCS)).count() == 0


def test_consistent_sampling_estimates_weighted_jaccard():
    rng = np.random.default_rng(1)
    h = rng.integers(0, 2**63, 400, dtype=np.uint64)
    a, b = rng.uniform(0.5, 2, 300), rng.uniform(0.5, 2, 300)
    x = near_dedup.icws(np.zeros(300, int), h[:300], np.log(a).astype(np.float32), 1, 4000)
    y = near_dedup.icws(np.zeros(300, int), h[100:], np.log(b).astype(np.float32), 1, 4000)
    wa, wb = np.zeros(400), np.zeros(400)
    wa[:300], wb[100:] = a, b
    true = np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()
    assert abs((x == y).mean() - true) < 0.04


@lru_cache
def library(name):
    """The library as it loads the vocabulary."""
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary(name))


def library_ids(name, text, dtype="<u2"):
    return np.array(library(name).encode(text, add_special_tokens=False).ids, dtype).tobytes()


ODD = ["", " ", "  a", "a  b", "a\n b", "a \nb", "a\n", "a ", "it's I'LL don't x", "é áb", "日本 語　x", "a\xa0b  c", "x\x1cy \x85z", "<|endoftext|> hi", "ΑΣ Σ ΣΑΣ", "İstanbul ǅ ß", "tab\tx \ty", "hello <|endoftext|> world", "a<|endoftext|>b <|startoftext|>", "<|ENDOFTEXT|> <|endoftext", "x <|startoftext|><|endoftext|>", "12 345 6.7", "👍🏽 a👍", "à la", "’ x", "word, word."]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_tokens_are_the_librarys(name, sample):
    import pyarrow as pa

    r = random.Random(9)
    texts = ODD + ["".join(r.choice(" ab'\n\tsT1é́.-  àŞ,") for _ in range(60)) for _ in range(400)] + [t or "" for _, t in sample[:60]]
    tok = PieceTokenizer(vocabulary(name), keep=300)  # so small that it is emptied often
    want = [library_ids(name, t) for t in texts]
    assert [tok.encode(t) for t in texts] == want
    got = [x.tobytes() for ids, ends in tok.encode_many(pa.array(texts), 0, size=5000) for x in np.split(ids, ends[:-1])]
    assert got == [w + b"\0\0" for w in want]


def test_token_files_round_trip(spark, sample):
    rows = sample[:80] + [(10**6 + i, t) for i, t in enumerate([None, "", "x " * 100_000, "a <|endoftext|> b"])]
    docs = spark.createDataFrame(rows, DOCS).repartition(3).withColumn("start", F.lit(0))
    path = vocabulary("byte_bpe_50k.json")
    folder = scratch_path(spark, "test-tokens")
    manifest = token_files.write_token_files(docs, folder, path, partitions=4)
    got = sorted(token_files.read_token_files(spark, folder, manifest).collect(), key=lambda r: r.doc_id)
    start = 0
    for (d, t), r in zip(sorted(rows), got, strict=True):
        ids = np.append(np.frombuffer(library_ids("byte_bpe_50k.json", t or ""), "<u2"), 0).astype("<u4")
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (d, start, len(ids), zlib.crc32(ids))
        start += len(ids)
    assert token_files.encode_to_files(spark.createDataFrame([], DOCS), path).count() == 0
    assert token_files.encode_to_files(spark.createDataFrame([(None, "a"), (1, "b"), (1, "b")], DOCS), path).count() == 3


def check_plan(histogram, capacity, groups=8):
    runs, n = packing.plan_packing(histogram, capacity, groups)
    place, count = {}, {}
    for size, lo, hi, first, at in runs:
        for i in range(hi - lo):
            place.setdefault(first + i, []).append((at, size))
        count[size] = count.get(size, 0) + hi - lo
    assert count == {k: v for k, v in histogram.items() if v}
    assert len(place) == n
    for spots in place.values():
        end = 0
        for at, size in sorted(spots):
            assert at == end
            end += size
        assert end <= capacity
    return n


def test_packing_plan():
    r = random.Random(1)
    for capacity in (10, 64, 2048):
        for _ in range(20):
            h = {r.randrange(1, capacity + 1): r.randrange(1, 50) for _ in range(r.randrange(1, 40))}
            n = check_plan(h, capacity)
            assert n <= 1.35 * sum(k * v for k, v in h.items()) / capacity + sum(v for k, v in h.items() if 2 * k > capacity) + 1
    assert check_plan({}, 2048) == 0 and check_plan({2048: 5}, 2048) == 5 and check_plan({1: 5000}, 2048) == 3
    lengths = {k: 3 for k in range(20, 1500, 7)}
    assert check_plan(lengths, 2048, 512) <= 1.01 * sum(k * v for k, v in lengths.items()) / 2048 + 1


def test_packing_query(spark, sample):
    rows = sample[:120] + [(10**6, None), (10**6 + 1, ""), (10**6 + 2, "long words here " * 4000), (10**6 + 3, "same"), (10**6 + 3, "same"), (10**6 + 4, "it <|endoftext|> IS <|startoftext|>x")]
    path = vocabulary("word_bpe_49k.json")
    got = packing.pack(spark.createDataFrame(rows, DOCS).repartition(5).withColumn("piece", F.lit("clash")), path).collect()
    want = []
    for d, t in rows:
        ids = np.append(np.frombuffer(library_ids("word_bpe_49k.json", t or ""), "<u2"), 0).astype("<u4")
        want += [(d, k, at, min(2048, len(ids) - at), zlib.crc32(ids[at : at + 2048])) for k, at in enumerate(range(0, len(ids), 2048))]
    assert sorted((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(want)
    spots = {}
    for r in got:
        spots.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for s in spots.values():
        end = 0
        for at, n in sorted(s):
            assert at == end
            end += n
        assert end <= 2048
    assert len(spots) <= 1.05 * sum(w[3] for w in want) / 2048 + 1
    assert packing.pack(spark.createDataFrame([], DOCS), path).count() == 0


FULL = "doc_id long, text string, lang string, source string, n_chars long"


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as c

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sizes = []
    for name, stage in c.STAGES[:-1]:
        out = stage(spark, docs, sf).persist()
        assert out.columns == docs.columns, name
        assert out.exceptAll(docs).isEmpty()
        sizes.append((docs.count(), out.count()))
        docs = out
    assert all(b <= a for a, b in sizes) and sizes[-1][1] > 0.6 * sizes[0][0]
    packed = c.STAGES[-1][1](spark, docs, sf)
    assert packed.select("doc_id").distinct().count() == docs.count()
    assert {r.doc_id for r in c.run(spark, sf).select("doc_id").distinct().collect()} == {r.doc_id for r in docs.select("doc_id").collect()}


def test_pipeline_stages_on_edges(spark, sf):
    import corpus_pipeline as c

    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, "ok text " * 50, "en", "s", 3), (3, "ok text " * 50, "en", "s", 3), (None, "no id here", None, "s", 1), (4, "w" * 200_000, "de", None, 2)]
    for data in (rows, []):
        docs = spark.createDataFrame(data, FULL).withColumn("quality", F.lit(1)).withColumn("_id", F.lit(2))
        for name, stage in c.STAGES:
            out = stage(spark, docs, sf)
            out.count()
            if name != "packing":
                assert out.columns == docs.columns


def test_pipeline_stages_keep_what_brute_force_keeps(spark, sf):
    """Each stage on all that its predecessor kept, against plain loops over the texts."""
    import corpus_pipeline as c
    from blockmf.llm import decontaminate, quality

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    stage = dict(c.STAGES)
    kept = stage["quality"](spark, docs, sf).collect()
    model = quality.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    assert sorted(r.doc_id for r in kept) == sorted(r.doc_id for r in quality.scored(docs, model).where("score >= 0.7").collect())
    extra = [(10_001, kept[0].text.upper().lower(), "en", "s", 1), (10_002, kept[0].text.swapcase(), "en", "s", 1), (None, kept[0].text, None, None, None), (None, "alone", None, None, None), (None, "ALONE", None, None, None)]
    texts = [tuple(r) for r in kept] + extra + [(20_000 + i, " ".join([*r.text.split()[:-1], "changed"]), "en", "s", 1) for i, r in enumerate(kept[:12])]
    made = spark.createDataFrame(texts, docs.schema)
    lower = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
    groups = {}
    for d, t, *_ in texts:
        groups.setdefault(lower(t), []).append(d)
    want = sorted((max((d for d in ids if d is not None), default=-1)) for ids in groups.values())
    exact = stage["exact_dedup"](spark, made, sf).persist()
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in exact.collect()) == want
    rows = [(r.doc_id, r.text) for r in exact.collect() if r.doc_id is not None]
    w = plain_weights([t for _, t in rows])
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if not w[i].keys().isdisjoint(w[j]) and plain_jaccard(w[i], w[j]) >= 0.8:
                parent[root(i)] = root(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[root(i)] = min(d, least.get(root(i), d))
    near = stage["near_dedup"](spark, exact, sf).persist()
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in near.collect()) == sorted([*least.values(), -1])
    items = [decontaminate.normalise(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    clean = [r.doc_id for r in near.collect() if not any(decontaminate.myers(b, decontaminate.normalise(r.text), len(b) // 20) is not None for b in items)]
    got = stage["decontaminate"](spark, near, sf)
    assert sorted(map(str, clean)) == sorted(str(r.doc_id) for r in got.collect())
    assert stage["packing"](spark, got, sf).select("doc_id").distinct().count() == len(set(clean))
