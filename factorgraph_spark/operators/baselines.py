"""What the block sweeper is compared with: one shared queue, a fixed order, and sampling."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.logspace import md5_uniform

from .kernel import Block, BPConfig
from .model import FactorGraph


def whole_block(fg: FactorGraph, cfg: BPConfig) -> Block:
    """The whole graph as one block on the driver; for graphs of a size that one processor can hold."""
    variables = [(r["vid"], r["card"], r["prior"]) for r in fg.variables.collect()]
    edges = [(r["fid"], r["vid"], r["slot"], r["potential_id"], 0, 0) for r in fg.edges.collect()]
    return block_of(variables, edges, fg.templates(), cfg)


def block_of(variables: list, edges: list, templates: dict, cfg: BPConfig) -> Block:
    """A whole graph's rows as one block."""
    b = Block(0, variables, edges, templates, cfg, 0.0)
    b.w_max = cfg.w_max if cfg.w_max is not None else min(1e5, 2 * float(b.work.sum()) / max(1, cfg.workers))
    return b


def shared_queue_sweep(fg: FactorGraph, volume: int = 50, beta: float = 1e-5, damping: float = 0.6, max_updates: int | None = None) -> Block:
    """The predecessor: one queue over all vertices, message residuals, sweeps of a fixed number of vertices."""
    b = whole_block(fg, BPConfig(beta=beta, damping=damping, residual="message", sweep="volume", volume=volume))
    b.run_sweeps(None, max_updates)
    return b


def round_robin(fg: FactorGraph, beta: float = 1e-5, damping: float = 0.0, passes: int = 1000) -> Block:
    """One vertex after another in order of id with the newest messages, until a pass moves no belief by more than beta."""
    b = whole_block(fg, BPConfig(beta=beta, damping=damping))
    for _ in range(passes):
        for k in range(len(b.ids)):
            b.update(k)
        if b.worst() <= beta:
            break
    return b


def block_beliefs(spark, b: Block) -> DataFrame:
    return spark.createDataFrame([(v, s, float(x)) for v, p in b.beliefs() for s, x in enumerate(p)], "vid long, state int, belief double")


def gibbs(fg: FactorGraph, samples: int = 125_000, burn_in: int = 25_000, chains: int = 4, seed: int = 42) -> DataFrame:
    """chain, vid, state, belief: counts of systematic Gibbs sweeps, chains in parallel.

    A sample is one sweep over all variables in order of id. The graph goes to every task, so it must be one that a processor can hold;
    colour_sweep works on graphs of any size.
    """
    variables = sorted((r["vid"], r["prior"]) for r in fg.variables.collect())
    at = {v: k for k, (v, _) in enumerate(variables)}
    templates, scopes = fg.templates(), {}
    for r in fg.edges.collect():
        scopes.setdefault((r["fid"], r["potential_id"]), {})[r["slot"]] = at[r["vid"]]
    around: list[list] = [[] for _ in variables]
    for (_, p), slots in sorted(scopes.items()):
        axes = [slots[s] for s in range(len(slots))]
        table = np.array(templates[p][1]).reshape(templates[p][0])
        for s, k in enumerate(axes):
            others = [axes[j] for j in range(len(axes)) if j != s]
            around[k].append((np.moveaxis(table, s, -1), others))
    packed = fg.spark.sparkContext.broadcast(([np.array(p) for _, p in variables], around, [v for v, _ in variables]))

    def sample(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        priors, near, ids = packed.value
        width = max(map(len, priors))
        for batch in batches:
            for chain in batch.column("id").to_pylist():
                rng = np.random.default_rng([seed, chain])
                x = [int(rng.integers(len(p))) for p in priors]
                counts = np.zeros((len(priors), width))
                for t in range(samples):
                    u = rng.random(len(priors))
                    for k, p in enumerate(priors):
                        logits = p
                        for table, others in near[k]:
                            logits = logits + table[tuple(x[j] for j in others)]
                        w = np.exp(logits - logits.max()).cumsum()
                        x[k] = int(np.searchsorted(w, u[k] * w[-1]))
                    if t >= burn_in:
                        counts[np.arange(len(x)), x] += 1
                b = counts / counts.sum(axis=1, keepdims=True)
                rows = [(chain, v, s, float(b[k, s])) for k, v in enumerate(ids) for s in range(len(priors[k]))]
                c = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.int32()), pa.array(c[3], pa.float64())], ["chain", "vid", "state", "belief"])

    return fg.spark.range(0, chains, 1, chains).mapInArrow(sample, "chain long, vid long, state int, belief double")


def gibbs_binary(fg: FactorGraph, samples: int = 125_000, burn_in: int = 25_000, chains: int = 4, seed: int = 42) -> DataFrame:
    """Like gibbs, for binary graphs of equality factors: variables of a colour are drawn together, so a sweep is a few matrix products."""
    variables = sorted((r["vid"], r["prior"][1] - r["prior"][0]) for r in fg.variables.collect())
    at = {v: k for k, (v, _) in enumerate(variables)}
    templates, scopes = fg.templates(), {}
    for r in fg.edges.collect():
        scopes.setdefault((r["fid"], r["potential_id"]), []).append(at[r["vid"]])
    n, pairs, weight = len(variables), [], []
    for (_, p), ends in scopes.items():
        t = templates[p][1]
        if templates[p][0] != [2, 2] or t[0] != t[3] or t[1] != t[2]:
            raise ValueError("not a graph of binary equality factors")
        pairs.append(sorted(ends))
        weight.append(t[0] - t[1])
    near: list[list[tuple[int, float]]] = [[] for _ in range(n)]
    for (a, b), w in zip(pairs, weight):
        near[a].append((b, w))
        near[b].append((a, w))
    colour = np.full(n, -1)
    for k in sorted(range(n), key=lambda k: -len(near[k])):
        taken = {colour[j] for j, _ in near[k]}
        colour[k] = next(c for c in range(n) if c not in taken)
    layers = []
    for c in range(colour.max() + 1):
        own = np.flatnonzero(colour == c)
        idx = np.array([j for k in own for j, _ in near[k]], dtype=np.int64)
        w = np.array([x for k in own for _, x in near[k]])
        starts = np.cumsum([0] + [len(near[k]) for k in own])
        layers.append((own, idx, w, starts))
    packed = fg.spark.sparkContext.broadcast((layers, np.array([o for _, o in variables]), [v for v, _ in variables]))

    def sample(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layers, odds, ids = packed.value
        for batch in batches:
            for chain in batch.column("id").to_pylist():
                rng = np.random.default_rng([seed, chain])
                x = rng.choice([-1.0, 1.0], len(ids))
                hits = np.zeros(len(ids))
                for t in range(samples):
                    for own, idx, w, starts in layers:
                        # An equality weight w adds w/2 * (+-1) to each side, so the odds move by w * x.
                        pull = np.concatenate(([0.0], np.cumsum(w * x[idx])))
                        field = odds[own] + pull[starts[1:]] - pull[starts[:-1]]
                        x[own] = np.where(rng.random(len(own)) < 1 / (1 + np.exp(-field)), 1.0, -1.0)
                    if t >= burn_in:
                        hits += x > 0
                b = hits / (samples - burn_in)
                ids2 = np.repeat(np.array(ids, dtype=np.int64), 2)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(2 * len(ids), chain)), pa.array(ids2), pa.array(np.tile(np.arange(2, dtype=np.int32), len(ids))), pa.array(np.stack([1 - b, b], axis=1).ravel())], ["chain", "vid", "state", "belief"])

    return fg.spark.range(0, chains, 1, chains).mapInArrow(sample, "chain long, vid long, state int, belief double")


def agreement(samples: DataFrame) -> DataFrame:
    """a, b, mean_l1: mean L1 distance per variable between every two chains."""
    s = samples.select("chain", "vid", "state", "belief")
    other = s.select(F.col("chain").alias("b"), "vid", "state", F.col("belief").alias("y"))
    both = s.withColumnRenamed("chain", "a").join(other, ["vid", "state"]).where("a < b")
    per = both.groupBy("a", "b", "vid").agg(F.sum(F.abs(F.col("belief") - F.col("y"))).alias("d"))
    return per.groupBy("a", "b").agg(F.avg("d").alias("mean_l1"))


def colour_sweep(states: DataFrame, links: DataFrame, odds: DataFrame, colour: DataFrame, chosen: int, chain: int, sweep: int, seed: int = 42) -> DataFrame:
    """states (vid, x in 0/1) after the variables of one colour are drawn anew; binary equality links (a, b, w). Draws come from md5, so a
    retried task and other engines draw the same."""
    both = links.select("a", "b", "w").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"), "w"))
    pull = both.join(states.toDF("b", "y"), "b").groupBy(F.col("a").alias("vid")).agg(F.sum(F.col("w") * (2 * F.col("y") - 1)).alias("pull"))
    rows = states.join(colour, "vid").join(odds, "vid").join(pull, "vid", "left")
    u = md5_uniform(F.concat_ws("|", F.lit(str(seed)), F.lit(str(chain)), F.lit(str(sweep)), F.col("vid").cast("string")))
    p = 1 / (1 + F.exp(-(F.col("odds") + F.coalesce("pull", F.lit(0.0)))))
    return rows.select("vid", F.when(F.col("colour") == chosen, F.when(u < p, 1).otherwise(0)).otherwise(F.col("x")).cast("int").alias("x"))
