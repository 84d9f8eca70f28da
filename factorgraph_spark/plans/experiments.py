"""The experiments as functions that return tables. Times over logical workers are modelled as the sum over rounds of the heaviest block's
work, and named so; wall seconds are given beside them."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import baselines, block_bp, metrics, partition
from ..operators.kernel import BPConfig
from ..operators.model import FactorGraph
from ..sources.tables import cut

#: Vertices of a block on which update counts are taken.
BLOCK_VERTICES = 40_000

_ABLATION = pa.schema([("residual", pa.string()), ("sweep", pa.string()), ("vertex_updates", pa.int64()), ("edge_updates", pa.int64()), ("max_residual", pa.float64()), ("converged", pa.bool_())])


def settled(fg: FactorGraph) -> FactorGraph:
    """The graph with its tables computed once."""
    return FactorGraph(cut(fg.variables), cut(fg.edges), cut(fg.potentials))


def table1(fg: FactorGraph, parts: int = 120, cfg: BPConfig | None = None, max_updates: int | None = 400_000) -> dict:
    """Relative communication cost and work balance of a cut with U = 1 against one with the update counts of a run.

    The run is the block sweeper's, on the blocks of the first cut or, where those are larger than BLOCK_VERTICES, on smaller ones. So neither
    the driver nor any one processor holds the graph. max_updates: a bound on the run; None: it must converge.
    """
    plain, took = metrics.timed_call(partition.multilevel, fg, parts)
    plain = cut(plain)
    blocks = -(-plain.count() // BLOCK_VERTICES)
    pieces = plain if blocks <= parts else partition.multilevel(fg, blocks)
    assign, cfg = pieces.select("vid", F.col("piece").alias("block")), replace(cfg or BPConfig(), max_rounds=5000)
    run = block_bp.run_converged(fg, assign, cfg) if max_updates is None else block_bp.run(fg, assign, cfg, max_updates)
    updates = cut(run.vertices.select("vid", "n_updates"))
    run.drop()
    informed = partition.multilevel(fg, parts, updates)
    costs, work = partition.edge_cost(fg, updates), partition.vertex_work(fg, updates)
    return {
        "parts": parts,
        "rel_com_cost": metrics.relative_cut(costs, plain, informed, "piece").first()[0],
        "rel_work_balance": metrics.relative_balance(work, plain, parts, "piece").first()[0],
        "informed_balance": metrics.relative_balance(work, informed, parts, "piece").first()[0],
        "partition_seconds": took,
    }


def deal_trials(costs: DataFrame, work: DataFrame, pieces: DataFrame, workers: int, over: int, trials: int) -> DataFrame:
    """over, trial, balance and cut_cost of random deals of the pieces (vid, piece) to workers; deals are partition.deal's, by trial."""
    spark = work.sparkSession
    order = Window.partitionBy("trial").orderBy(F.md5(F.concat_ws("|", F.col("piece").cast("string"), F.col("trial").cast("string")).cast("binary")), "piece")
    deals = spark.range(workers * over).toDF("piece").withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    deals = deals.withColumn("block", (F.row_number().over(order) - 1) % workers)
    # The deals only need the work of pieces and the cost between them.
    load = partition.loads(work, pieces, "piece").select(F.col("block").alias("piece"), "load")
    p = pieces.select("vid", "piece")
    between = costs.join(p.toDF("fid", "a"), "fid").join(p.toDF("vid", "b"), "vid").where("a != b").groupBy("a", "b").agg(F.sum("cost").alias("c"))
    held = deals.join(load, "piece").groupBy("trial", "block").agg(F.sum("load").alias("w"))
    balance = held.groupBy("trial").agg((workers * F.max("w") / F.sum("w")).alias("balance"))
    x, y = deals.select("trial", F.col("piece").alias("a"), F.col("block").alias("x")), deals.select("trial", F.col("piece").alias("b"), F.col("block").alias("y"))
    cost = between.join(x, "a").join(y, ["trial", "b"]).groupBy("trial").agg(F.sum(F.when(F.col("x") != F.col("y"), F.col("c")).otherwise(0.0)).alias("cut_cost"))
    return balance.join(cost, "trial").select(F.lit(over).alias("over"), "trial", "balance", "cut_cost")


def intervals(trials: DataFrame) -> DataFrame:
    """over, and mean and half width of the 95 % interval of balance and cut cost."""
    wide = lambda c: (1.96 * F.stddev(c) / F.sqrt(F.count(c))).alias(f"{c}_ci")
    return trials.groupBy("over").agg(F.avg("balance").alias("balance"), wide("balance"), F.avg("cut_cost").alias("cut_cost"), wide("cut_cost"))


def overpartition_trials(fg: FactorGraph, workers: int, ks=(1, 2, 5, 10), trials: int = 30, updates: DataFrame | None = None) -> DataFrame:
    """over, mean and half width of the 95 % interval of work balance and cut cost, over random deals of the pieces."""
    costs, work = cut(partition.edge_cost(fg, updates)), cut(partition.vertex_work(fg, updates))
    out = [deal_trials(costs, work, cut(partition.multilevel(fg, workers * k)), workers, k, trials) for k in ks]
    return intervals(reduce(DataFrame.unionByName, out))


def scaling(fg: FactorGraph, workers=(1, 2, 4, 8), overs=(1, 5), cfg: BPConfig | None = None, max_rounds: int = 200) -> DataFrame:
    """workers, over, rounds, modelled work, wall seconds, messages, updates, utilisation, convergence."""
    out = []
    for p in workers:
        for k in overs if p > 1 else overs[:1]:
            c = replace(cfg or BPConfig(), workers=p, over=k, max_rounds=max_rounds)
            r = block_bp.run(fg, cfg=c)
            log = r.round_log()
            m = metrics.modelled_time(log).first()
            used = metrics.utilisation(log, p).first()[0]
            r.drop()
            out.append((p, k, m["rounds"], m["modelled"], r.seconds, sum(x["sent"] for x in r.rounds), sum(x["vertex_updates"] for x in r.rounds), sum(x["edge_updates"] for x in r.rounds), used, r.converged))
    return fg.spark.createDataFrame(out, "workers int, over int, rounds long, modelled double, seconds double, messages long, vertex_updates long, edge_updates long, utilisation double, converged boolean")


def ablate(fg: FactorGraph, cfg: BPConfig | None = None, max_updates: int | None = None, points: int = 20) -> DataFrame:
    """residual, sweep, vertex_updates, edge_updates, max_residual along a run: the four combinations, all under one rule for gaps.

    Each runs to convergence, with a point every as many updates as the graph has vertices, and is given up (not converged) after 1,000
    updates per vertex. max_updates: a bound instead, with this many points up to it. Each is a task of its own, which holds the graph;
    the driver does not.
    """
    kinds = [(residual, sweep) for residual in ("message", "belief") for sweep in ("volume", "work")]
    templates, base = fg.templates(), cfg or BPConfig()
    # Arrow tables: Python rows of the same graph would be some twenty times as large.
    held = fg.spark.sparkContext.broadcast((fg.variables.select("vid", "card", "prior").toArrow(), fg.edges.select("fid", "vid", "slot", "potential_id").toArrow()))

    def points_of(residual: str, sweep: str) -> list[tuple]:
        rows = lambda t: zip(*(c.to_pylist() for c in t.columns))
        vs, es = held.value
        b = baselines.block_of(list(rows(vs)), [(*e, 0, 0) for e in rows(es)], templates, replace(base, residual=residual, sweep=sweep))
        out = []
        for k in range(1, (1000 if max_updates is None else points) + 1):
            b.run_sweeps(None, k * len(b.ids) if max_updates is None else k * max_updates // points)
            worst = b.worst()
            out.append((residual, sweep, b.vertex_updates, b.edge_updates, float(min(worst, 1e9)), bool(worst <= b.cfg.beta)))
            if worst <= b.cfg.beta:
                break
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column("id").to_pylist():
                yield pa.RecordBatch.from_pylist([dict(zip(_ABLATION.names, r)) for r in points_of(*kinds[k])], _ABLATION)

    schema = "residual string, sweep string, vertex_updates long, edge_updates long, max_residual double, converged boolean"
    return cut(fg.spark.range(0, len(kinds), 1, len(kinds)).mapInArrow(run, schema))


def accuracy_by_updates(fg: FactorGraph, reference: DataFrame, cfg: BPConfig | None = None, max_updates: int = 200_000, points: int = 10) -> DataFrame:
    """residual, vertex_updates, mean_l1 against a reference, for message and belief residuals."""
    ref = {}
    for r in reference.collect():
        ref.setdefault(r["vid"], {})[r["state"]] = r["belief"]
    out = []
    for residual in ("message", "belief"):
        b = baselines.whole_block(fg, replace(cfg or BPConfig(), residual=residual))
        for k in range(1, points + 1):
            b.run_sweeps(None, k * max_updates // points)
            d = [sum(abs(x - ref[v][s]) for s, x in enumerate(p)) for v, p in b.beliefs()]
            out.append((residual, b.vertex_updates, float(sum(d) / max(1, len(d)))))
            if b.worst() <= b.cfg.beta:
                break
    return fg.spark.createDataFrame(out, "residual string, vertex_updates long, mean_l1 double")


def accuracy_at_budget(fg: FactorGraph, reference: DataFrame, workers=(1, 2, 4, 8), budget: float = 1e5, cfg: BPConfig | None = None) -> DataFrame:
    """workers, mean_l1 when every worker has had the same modelled work (a budget of time for any number of workers)."""
    out = []
    for p in workers:
        c = replace(cfg or BPConfig(), workers=p, over=1 if p == 1 else (cfg or BPConfig()).over)
        r = block_bp.Result(fg, cut(block_bp.place(fg, partition.over_segment(fg, c.workers, c.over, c.seed, c.gamma), c)))
        spent = 0.0
        while spent < budget and not r.converged:
            n = len(r.rounds)
            r = block_bp.resume(r, c, max_rounds=len({x["round"] for x in r.rounds}) + 1)
            spent += max(x["work"] for x in r.rounds[n:])
        out.append((p, spent, metrics.mean_l1(r.beliefs, reference).first()[0], r.converged))
    return fg.spark.createDataFrame(out, "workers int, modelled double, mean_l1 double, converged boolean")


def search_k(fg: FactorGraph, workers: int, ks=(1, 2, 5, 10), cfg: BPConfig | None = None) -> int:
    """The over-partitioning factor with the least modelled work."""
    runs = [(metrics.modelled_time(block_bp.run(fg, cfg=replace(cfg or BPConfig(), workers=workers, over=k)).round_log()).first()["modelled"], k) for k in ks]
    return min(runs)[1]
