"""From an asynchronous schedule to rounds of independent visits.

The round of a visit is one more than the latest round that touched one of its row stripes or its column stripe. Visits of a round share no
stripe, so they commute; visits that share one keep their order. Running round after round gives bit for bit what the asynchronous run gives.
"""

from __future__ import annotations

from blockmf.plans.scheduler import Visit


def compile_rounds(visits: list[Visit]) -> list[int]:
    """Round of each visit, from 0, in the order of the visits given."""
    row_last: dict[int, int] = {}
    col_last: dict[int, int] = {}
    out: dict[int, int] = {}
    for v in sorted(visits, key=lambda v: (v.t_start, v.visit)):
        n = 1 + max(col_last.get(v.col, -1), max((row_last.get(r, -1) for r in v.rows), default=-1))
        col_last[v.col] = n
        for r in v.rows:
            row_last[r] = n
        out[v.visit] = n
    return [out[v.visit] for v in visits]


def independent(a: Visit, b: Visit) -> bool:
    return a.col != b.col and not set(a.rows) & set(b.rows)
