"""Token-id output: flat unsigned integer files with 64-bit document offsets, memory-mapped for reading.

Documents are range-partitioned by id and sorted, so part files are in ascending order of ids. Each task encodes
its documents and writes one data file and one index file under names of its own, then reports their names and
sizes; only files that a finished task has reported belong to the data set, so retries and speculative copies do
no harm. Partition bases come from prefix sums over the reported sizes (one row per part file). A data file holds
ids as 16-bit integers if the vocabulary fits, else 32-bit; an index file holds int64 pairs: document id, end offset.

Edge cases. Null or empty text: only the end id. Very long texts: encoded in bounded steps. Rows that repeat an id:
one document each, in unspecified but fixed order of their text hash. Null ids come first and read back as null. Empty
table: no part files, empty result.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.llm.common import scratch_path, text_or_empty
from blockmf.llm.tokenize import piece_tokenizer

NULL_ID = np.iinfo(np.int64).min


def file_system(uri: str):
    """(pyarrow file system, path) of a folder that all machines share."""
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        uri = f"file://{uri}"
    uri = uri.replace("file:///", "file:/").replace("file:/", "file:///")
    return fs.FileSystem.from_uri(uri)


def _writer(folder: str, vocab: str, end_id: int):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import uuid

        from pyspark import TaskContext

        tok = piece_tokenizer(vocab)
        fs, root = file_system(folder)
        part = TaskContext.get().partitionId()
        name = f"part-{part:06d}-{uuid.uuid4().hex}"
        ids, ends, at, data = [], [], 0, None
        for b in batches:
            if data is None and b.num_rows:
                fs.create_dir(root, recursive=True)
                data = fs.open_output_stream(f"{root}/{name}.ids")
            ids += [NULL_ID if x is None else x for x in b.column(0).to_pylist()]
            for tokens, stops in tok.encode_many(b.column(1), end_id):
                data.write(tokens.tobytes())
                ends += (stops + at).tolist()
                at += len(tokens)
        if data is not None:
            data.close()
            with fs.open_output_stream(f"{root}/{name}.idx") as out:
                out.write(np.array([ids, ends], "<i8").T.tobytes())
            yield pa.RecordBatch.from_pydict({"part": [part], "name": [name], "docs": [len(ids)], "tokens": [at], "width": [tok.dtype.itemsize]}, schema=_PART)

    return write


_PART = pa.schema([("part", pa.int32()), ("name", pa.string()), ("docs", pa.int64()), ("tokens", pa.int64()), ("width", pa.int32())])


def write_token_files(docs: DataFrame, folder: str, vocab: str, end_id: int = 0, partitions: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> list[dict]:
    """Write the files; returns the manifest (one entry per part file, with its base offsets) and stores it as manifest.json."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    by = ["doc_id"]
    rows = rows.repartitionByRange(partitions, *by) if partitions else rows.repartitionByRange(*by)
    rows = rows.sortWithinPartitions("doc_id", F.xxhash64("text"))
    done = rows.mapInArrow(_writer(folder, vocab, end_id), "part int, name string, docs long, tokens long, width int").collect()
    manifest, base, first = [], 0, 0
    for r in sorted((r.asDict() for r in done), key=lambda r: r["part"]):
        manifest.append(r | {"base": base, "first_doc": first})
        base, first = base + r["tokens"], first + r["docs"]
    fs, root = file_system(folder)
    fs.create_dir(root, recursive=True)
    with fs.open_output_stream(f"{root}/manifest.json") as out:
        out.write(json.dumps(manifest).encode())
    return manifest


def _open(fs, path: str):
    """Memory map of a local or mounted file, else its bytes."""
    from pyarrow import fs as pfs

    if isinstance(fs, pfs.LocalFileSystem):
        return pa.memory_map(path).read_buffer()
    with fs.open_input_file(path) as f:
        return f.read_buffer()


def read_part(folder: str, part: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document ids, end offsets in the part, token ids) of one part file, without copies."""
    fs, root = file_system(folder)
    index = np.frombuffer(_open(fs, f"{root}/{part['name']}.idx"), "<i8").reshape(-1, 2)
    return index[:, 0], index[:, 1], np.frombuffer(_open(fs, f"{root}/{part['name']}.ids"), f"<u{part['width']}")


def _reader(folder: str):
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for part in b.to_pylist():
                ids, ends, tokens = read_part(folder, part)
                starts = np.concatenate([[0], ends[:-1]])
                crc = [zlib.crc32(tokens[s:e].astype("<u4")) for s, e in zip(starts.tolist(), ends.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(ids, mask=ids == NULL_ID), pa.array(starts + part["base"]), pa.array(ends - starts), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return read


def read_token_files(spark: SparkSession, folder: str, manifest: list[dict]) -> DataFrame:
    """One row per document, from the files alone: doc_id, start, n_tokens, ids_crc32."""
    parts = spark.createDataFrame([(p["name"], p["width"], p["base"]) for p in manifest], "name string, width int, base long")
    return parts.repartition(max(1, len(manifest))).mapInArrow(_reader(folder), "doc_id long, start long, n_tokens long, ids_crc32 long")


def encode_to_files(docs: DataFrame, vocab: str, end_id: int = 0) -> DataFrame:
    folder = scratch_path(docs.sparkSession, "tokens")
    return read_token_files(docs.sparkSession, folder, write_token_files(docs, folder, vocab, end_id))
