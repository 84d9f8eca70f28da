"""Synchronous belief propagation: every message of an iteration from those of the last one."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..sources.tables import cut, forget, landed
from . import pairwise
from .messages import arity_of, beliefs, step, uniform, widest
from .model import FactorGraph

#: Rows above which every iteration lands, so that only one iteration's shuffle is held. Results are the same.
LANDED_ROWS = 2_000_000


@dataclass
class SyncResult:
    beliefs: DataFrame
    state: DataFrame | None
    log: list[tuple[int, float]]  # iteration, largest L1 change of a message
    converged: bool


def run(
    fg: FactorGraph,
    max_iter: int = 100,
    beta: float | None = 1e-5,
    damping: float = 0.0,
    space: str = "prob",
    every: int = 4,
    state: DataFrame | None = None,
    width: int | None = None,
    keep: bool = True,
) -> SyncResult:
    """Iterates until no message moves by more than beta (None: max_iter times). Lineage is cut, and convergence looked at, every ``every`` iterations.

    width: states of the widest variable, where the caller knows it. keep: whether the state is asked for; else it is None.
    Graphs of factors of at most two variables are run on ``pairwise``, from uniform messages, and their tables are computed once.
    """
    width, arity = width or widest(fg), arity_of(fg)
    if state is None and pairwise.fits(width, arity):
        return _run_ends(fg, max_iter, beta, damping, space, every, width, keep)
    state = cut(uniform(fg) if state is None else state)
    log, t = [], 0
    while t < max_iter:
        for _ in range(min(every, max_iter - t)):
            state = step(fg, state.drop("delta"), width, arity, damping, space)
            t += 1
        state = cut(state)
        moved = state.agg(F.max("delta")).first()[0] or 0.0
        log.append((t, moved))
        if beta is not None and moved <= beta:
            break
    return SyncResult(beliefs(fg, state, width), state if keep else None, log, beta is not None and bool(log) and log[-1][1] <= beta)


def _run_ends(fg: FactorGraph, max_iter: int, beta: float | None, damping: float, space: str, every: int, width: int, keep: bool) -> SyncResult:
    tracked = beta is not None or damping > 0
    values = pairwise.tables(fg, width)
    rows = pairwise.start(fg, width, keep)
    if tracked:
        rows = rows.withColumns({c: F.lit(0.0) for c in pairwise.named("q", width)})
    log, t, path, big = [], 0, None, True
    while t < max_iter:
        # The first iteration lands by itself: it grounds the graph and counts the rows.
        upto = t + 1 if big else min(max_iter, t - t % every + every)
        while t < upto:
            rows, t = pairwise.step(pairwise.gathered(rows) if t else rows, values, width, tracked, damping, space), t + 1
        seen = Observation()
        rows = rows.observe(seen, F.count(F.lit(1)).alias("rows"), (F.max("delta") if tracked else F.lit(None).cast("double")).alias("moved"))
        last, (rows, path) = path, landed(rows if keep else rows.drop("delta"), "iteration")
        if last:
            forget(fg.spark, last)
        big = seen.get["rows"] > LANDED_ROWS
        if tracked and (t % every == 0 or t == max_iter):
            log.append((t, seen.get["moved"] or 0.0))
            if beta is not None and log[-1][1] <= beta:
                break
    state = pairwise.edges(rows, fg, width) if keep else None
    return SyncResult(pairwise.beliefs(pairwise.gathered(rows), width), state, log, beta is not None and bool(log) and log[-1][1] <= beta)


def iterate(fg: FactorGraph, times: int, damping: float = 0.0, state: DataFrame | None = None) -> DataFrame:
    """The state after a fixed number of iterations, as one plan."""
    width, arity = widest(fg), arity_of(fg)
    state = uniform(fg) if state is None else state
    for _ in range(times):
        state = step(fg, state.drop("delta"), width, arity, damping)
    return state
