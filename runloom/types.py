"""Schemas of the engine. A run is a symbol and how often it repeats; neighbouring runs differ in symbol."""

from __future__ import annotations

from typing import NamedTuple

MATCH_DDL = "seq_id {id_type}, pattern_id long, start long, end long, end_run long"
COST_DDL = "seq_id {id_type}, n long, n_runs long, edges long, fail_hops long, pred_queries long, report_queries long, report_steps long, occ long"


class Run(NamedTuple):
    """sym is any hashable, ordered symbol; len at least 1."""

    sym: object
    len: int


Runs = tuple[Run, ...]


def runs_of(sequence) -> Runs:
    """Maximal runs of a Python sequence."""
    out: list[Run] = []
    for s in sequence:
        if out and out[-1].sym == s:
            out[-1] = Run(s, out[-1].len + 1)
        else:
            out.append(Run(s, 1))
    return tuple(out)


def pattern_runs(p) -> Runs:
    """A pattern given as runs, as a string, or as a sequence of symbols."""
    if len(p) and not isinstance(p, str) and isinstance(p[0], tuple):
        return normalised(p)
    return runs_of(p)


def normalised(runs) -> Runs:
    """Runs with equal neighbours merged and empty ones dropped."""
    out: list[Run] = []
    for s, n in runs:
        if n <= 0:
            continue
        if out and out[-1].sym == s:
            out[-1] = Run(s, out[-1].len + n)
        else:
            out.append(Run(s, n))
    return tuple(out)


def length(runs) -> int:
    return sum(r[1] for r in runs)
