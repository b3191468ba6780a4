"""Runs a schedule on ratings that are laid out by block; rounds move the factors that they use, and nothing else.

Visits of a round share no stripe, so they run at once: the factors of the stripes that a round uses go to the partition of their visit (one
partition per visit), whose lane reads the ratings of its own blocks from the shared folder. What a round returns is kept, and later
rounds read each stripe where it was written last, so stripes that a round does not use are not touched. Between passes the factors are
written to the shared folder: lineage ends there, and a run can go on from any pass. Ratings are never shuffled after they are laid out.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockmf.operators.kernels import run_block, vectors
from blockmf.operators.params import MFParams
from blockmf.plans.scheduler import Visit
from blockmf.session import scratch_path
from blockmf.sources.blocks import Layout, in_batches, lay_out, read_blocks

STATE = "side string, id long, stripe int, vec array<double>"


def pin_ratings(ratings: DataFrame, order: str = "hash") -> Layout:
    """ratings(u, v, r, row_key, bj) laid out by block, in the visit order: the only shuffle of the ratings in a run."""
    from blockmf.operators.serial import order_expr

    return lay_out(ratings.withColumn("o", F.expr(order_expr(order, 1)).cast("long")))


def write_state(state: DataFrame, name: str = "state", path: str | None = None) -> tuple[DataFrame, str]:
    """state by side and stripe in the shared folder, so that a round reads its stripes only. What is at a given path is replaced."""
    path = path or scratch_path(state.sparkSession, name)
    state.repartition("side", "stripe").write.mode("overwrite").partitionBy("side", "stripe").parquet(path)
    return state.sparkSession.read.schema(STATE).parquet(path).select("side", "id", "stripe", "vec"), path


def _lane(params: MFParams, path: str, todo: dict[int, tuple[tuple[int, ...], int, str]]):
    """One partition: the factors of a visit, whose ratings are read and applied part by part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        state = pa.Table.from_batches(held).combine_chunks()
        for visit in np.unique(state.column("visit").to_numpy()).tolist():
            mine = state.filter(pa.compute.equal(state.column("visit"), visit)).combine_chunks()
            rows, col, kind = todo[visit]
            side, ids = mine.column("side").to_numpy(), mine.column("id").to_numpy()
            vec = np.array(mine.column("vec").combine_chunks().flatten()).reshape(len(ids), params.k)
            by_id = np.argsort(ids, kind="stable")
            at = {s: by_id[side[by_id] == s] for s in "pq"}
            p, q = vec[at["p"]], vec[at["q"]]
            for u, v, r in in_batches(read_blocks(path, rows, col), max(1, params.batch_width) if kind == "wide" else 1):
                run_block(kind, u, v, r, ids[at["p"]], p, ids[at["q"]], q, params)
            vec[at["p"]], vec[at["q"]] = p, q
            if not np.isfinite(vec).all():
                raise FloatingPointError(f"factors diverged in visit {visit}; use a smaller gamma")
            done = pa.Table.from_arrays([mine.column("side"), mine.column("id"), mine.column("stripe"), vectors(vec)], ["side", "id", "stripe", "vec"])
            yield from done.to_batches(max_chunksize=max(1, (8 << 20) // (8 * params.k)))

    return run


def _visit(use: dict[tuple[str, int], int]) -> str:
    """SQL text of the visit that uses a row's (side, stripe): constant maps."""
    by_side = {s: ", ".join(f"{i}, {x}" for (side, i), x in sorted(use.items()) if side == s) for s in "pq"}
    return f"if(side = 'p', element_at(map({by_side['p']}), stripe), element_at(map({by_side['q']}), stripe))"


def _stripes(keys: set[tuple[str, int]]) -> str:
    """SQL text: the row is of one of the (side, stripe). In terms of partition columns, so that others are not read."""
    by_side = {s: ", ".join(str(i) for side, i in sorted(keys) if side == s) for s in "pq"}
    return " OR ".join(f"(side = '{s}' AND stripe IN ({x}))" for s, x in by_side.items() if x) or "false"


def run_rounds(pinned: Layout, state: DataFrame, visits: list[Visit], rounds: list[int], params: MFParams) -> tuple[DataFrame, list[DataFrame]]:
    """state(side, id, stripe, vec) after all the visits, lazily, and the tables to unpersist once it is written. Visits without ratings are left out."""
    by_round: dict[int, list[Visit]] = defaultdict(list)
    for v, k in zip(visits, rounds, strict=True):
        if v.nnz:
            by_round[k].append(v)
    frames, newest = [state], {}  # (side, stripe) -> number of the frame that wrote it last; 0 if none did
    for k in sorted(by_round):
        now = by_round[k]
        use = {("p", r): i for i, v in enumerate(now) for r in v.rows} | {("q", v.col): i for i, v in enumerate(now)}
        sources: dict[int, set] = defaultdict(set)
        for key in use:
            sources[newest.get(key, 0)].add(key)
        parts = [frames[n].where(_stripes(keys)) for n, keys in sorted(sources.items())]
        dealt = reduce(DataFrame.union, parts).selectExpr("*", f"{_visit(use)} AS visit").repartitionById(len(now), "visit")
        todo = {i: (v.rows, v.col, v.kind) for i, v in enumerate(now)}
        frames.append(dealt.mapInArrow(_lane(params, pinned.path, todo), STATE).persist())
        newest |= dict.fromkeys(use, len(frames) - 1)
    last: dict[int, set] = defaultdict(set)
    for key, n in newest.items():
        last[n].add(key)
    parts = [frames[0].where(f"NOT ({_stripes(set(newest))})"), *(frames[n].where(_stripes(keys)) for n, keys in sorted(last.items()))]
    return reduce(DataFrame.union, parts), frames[1:]
