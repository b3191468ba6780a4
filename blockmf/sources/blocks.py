"""Ratings laid out by block in the shared folder: one directory per (row stripe, column stripe), rows in visit order.

Laying out is the only shuffle of the ratings in a run. A visit opens the files of its own blocks and nothing else; a thread reads the next
batch while the lane works on the one before.
"""

from __future__ import annotations

import queue
import threading
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from blockmf.session import remove, scratch_path

BATCH = 1 << 18  # ratings per batch


@dataclass(frozen=True)
class Layout:
    path: str

    def remove(self, spark) -> None:
        remove(spark, self.path)


def lay_out(rows: DataFrame, name: str = "blocks") -> Layout:
    """rows(u, v, r, row_key, bj, o): o orders the ratings of a block, ties by u and v."""
    path = scratch_path(rows.sparkSession, name)
    dealt = rows.selectExpr("u", "v", "cast(r as double) r", "cast(o as long) o", "cast(row_key as int) row_key", "cast(bj as int) bj").repartition("row_key", "bj")
    dealt.sortWithinPartitions("row_key", "bj", "o", "u", "v").write.partitionBy("row_key", "bj").parquet(path)
    return Layout(path)


def _file_system(uri: str):
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        uri = f"file://{uri}"
    uri = uri.replace("file:///", "file:/").replace("file:/", "file:///").replace("s3a://", "s3://")
    return fs.FileSystem.from_uri(uri)


def block_files(path: str, row: int, col: int) -> tuple[object, list[str]]:
    from pyarrow import fs

    system, root = _file_system(path)
    found = system.get_file_info(fs.FileSelector(f"{root}/row_key={row}/bj={col}", allow_not_found=True))
    return system, sorted(f.path for f in found if f.path.endswith(".parquet"))


def _ahead(batches: Iterator, depth: int = 2) -> Iterator:
    """The items of an iterator, read by a thread up to `depth` ahead."""
    done, ready = object(), queue.Queue(depth)
    stop = threading.Event()

    def read() -> None:
        try:
            for x in batches:
                while not stop.is_set():
                    try:
                        ready.put(x, timeout=0.1)
                        break
                    except queue.Full:
                        continue
                if stop.is_set():
                    return
            ready.put(done)
        except BaseException as e:  # noqa: BLE001 - handed to the reader of the queue
            ready.put(e)

    threading.Thread(target=read, daemon=True).start()
    try:
        while (x := ready.get()) is not done:
            if isinstance(x, BaseException):
                raise x
            yield x
    finally:
        stop.set()


def read_blocks(path: str, rows: tuple[int, ...], col: int, batch: int = BATCH) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(u, v, r) of the ratings of a visit in their order. One stripe in one file streams; several are merged in memory (a block fits by its budget)."""
    import pyarrow as pa
    import pyarrow.parquet as pq

    system, files = None, []
    for r in rows:
        system, more = block_files(path, r, col)
        files += more
    if len(files) == 1:
        source = pq.ParquetFile(files[0], filesystem=system)
        for b in _ahead(source.iter_batches(batch, columns=["u", "v", "r"])):
            yield tuple(b.column(c).to_numpy() for c in ("u", "v", "r"))
    elif files:
        t = pa.concat_tables([pq.ParquetFile(f, filesystem=system).read(["u", "v", "r", "o"]) for f in files])
        o, u, v, r = (t.column(c).to_numpy() for c in ("o", "u", "v", "r"))
        order = np.lexsort((v, u, o))
        for lo in range(0, len(order), batch):
            at = order[lo : lo + batch]
            yield u[at], v[at], r[at]


def in_batches(parts: Iterator[tuple], width: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The same ratings in parts of a multiple of `width` (but for the last), so that batches of that width do not depend on how they were read."""
    held: list[np.ndarray] | None = None
    for part in parts:
        whole = [np.concatenate(x) for x in zip(held, part, strict=True)] if held else list(part)
        n = len(whole[0]) // width * width
        if n:
            yield tuple(x[:n] for x in whole)
        held = [x[n:] for x in whole] if n < len(whole[0]) else None
    if held:
        yield tuple(held)
