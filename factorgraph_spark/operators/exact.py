"""Exact marginals: chains, trees, small graphs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .model import FactorGraph


def _lse(x, axis):
    top = x.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis=axis, keepdims=True))).squeeze(axis)


def forward_backward(nodes: DataFrame, transition: list[float], states: int) -> DataFrame:
    """vid, state, belief of chains. nodes: chain, pos, vid, prior; transition: log table between neighbours.

    A chain is a group of one task: chains are bounded here (users, conversations). For one chain of any length use block_bp.
    """
    t = np.array(transition).reshape(states, states)

    def solve(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("pos")
        u = np.array(rows.column("prior").to_pylist())
        n = len(u)
        a, b = np.zeros((n, states)), np.zeros((n, states))
        a[0] = u[0]
        for k in range(1, n):
            a[k] = u[k] + _lse(a[k - 1][:, None] + t, 0)
            a[k] -= a[k].max()
        for k in range(n - 2, -1, -1):
            b[k] = _lse(t + (u[k + 1] + b[k + 1])[None, :], 1)
            b[k] -= b[k].max()
        p = a + b
        p = np.exp(p - _lse(p, 1)[:, None])
        vid = np.repeat(rows.column("vid").to_numpy(), states)
        return pa.table({"vid": vid, "state": np.tile(np.arange(states, dtype=np.int32), n), "belief": p.ravel()})

    return nodes.groupBy("chain").applyInArrow(solve, "vid long, state int, belief double")


def enumerate_all(fg: FactorGraph, max_states: int = 1 << 20) -> DataFrame:
    """vid, state, belief by summing over all assignments; for graphs with at most max_states of them."""
    variables = sorted((r["vid"], r["prior"]) for r in fg.variables.collect())
    cards = [len(p) for _, p in variables]
    if np.prod(cards, dtype=float) > max_states:
        raise ValueError(f"more than {max_states} assignments")
    at = {v: k for k, (v, _) in enumerate(variables)}
    joint = np.zeros(cards)
    for k, (_, p) in enumerate(variables):
        joint = joint + np.array(p).reshape([-1 if j == k else 1 for j in range(len(cards))])
    templates, scopes = fg.templates(), {}
    for r in fg.edges.collect():
        scopes.setdefault((r["fid"], r["potential_id"]), {})[r["slot"]] = at[r["vid"]]
    for (_, p), slots in scopes.items():
        axes = [slots[s] for s in range(len(slots))]
        table = np.array(templates[p][1]).reshape(templates[p][0])
        order = np.argsort(axes)
        shape = [1] * len(cards)
        for j in axes:
            shape[j] = cards[j]
        joint = joint + table.transpose(order).reshape(shape)
    w = np.exp(joint - joint.max())
    w /= w.sum()
    rows = [(v, s, float(x)) for k, (v, _) in enumerate(variables) for s, x in enumerate(w.sum(axis=tuple(j for j in range(len(cards)) if j != k)))]
    return fg.spark.createDataFrame(rows, "vid long, state int, belief double")


def snowflake_marginals(edges: list[tuple[DataFrame, float]], leaves: DataFrame) -> list[DataFrame]:
    """Log-odds at every level of a tree whose levels are tables, leaves first. edges: (child, parent), equality log-weight; leaves: id, odds.

    Up: a parent sums what its children pass on. Down: a child gets its parent's total without its own share. Two group-bys a level, whatever
    the number of children.
    """
    from ..functions.logspace import binary_message

    up = [leaves.select("id", "odds")]
    sent = []
    for e, w in edges:
        s = e.join(up[-1].withColumnRenamed("id", "child"), "child", "left").select("child", "parent", binary_message(F.lit(w), F.coalesce("odds", F.lit(0.0))).alias("m"))
        sent.append(s)
        up.append(s.groupBy(F.col("parent").alias("id")).agg(F.sum("m").alias("odds")))
    total = [up[-1]]
    for k in range(len(edges) - 1, -1, -1):
        w = edges[k][1]
        above = sent[k].join(total[0].select(F.col("id").alias("parent"), F.col("odds").alias("t")), "parent")
        down = above.select(F.col("child").alias("id"), binary_message(F.lit(w), F.col("t") - F.col("m")).alias("d"))
        total.insert(0, down.join(up[k], "id", "left").select("id", (F.coalesce("odds", F.lit(0.0)) + F.col("d")).alias("odds")))
    return total
