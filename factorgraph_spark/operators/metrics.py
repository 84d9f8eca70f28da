"""Cost and accuracy measures of runs and placements."""

from __future__ import annotations

import time
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import partition


def relative_cut(costs: DataFrame, assign: DataFrame, informed: DataFrame, column: str = "block") -> DataFrame:
    """Cut cost of a placement over that of the informed one, both with the true update counts in ``costs``."""
    a, b = partition.cut_cost(costs, assign, column), partition.cut_cost(costs, informed, column)
    return a.select(F.col("cut_cost").alias("x")).crossJoin(b.select(F.col("cut_cost").alias("y"))).select((F.col("x") / F.col("y")).alias("rel_com_cost"))  # one row each


relative_balance = partition.work_balance


def mean_l1(beliefs: DataFrame, reference: DataFrame) -> DataFrame:
    """mean_l1: L1 distance of two belief tables (vid, state, belief), averaged over variables."""
    both = beliefs.join(reference.withColumnRenamed("belief", "r"), ["vid", "state"])
    return both.groupBy("vid").agg(F.sum(F.abs(F.col("belief") - F.col("r"))).alias("d")).agg(F.avg("d").alias("mean_l1"), F.count(F.lit(1)).alias("variables"))


def update_histogram(vertices: DataFrame) -> DataFrame:
    """log2_updates, vertices: how many vertices were updated about so often."""
    return vertices.groupBy(F.floor(F.log2(F.greatest("n_updates", F.lit(1)))).cast("int").alias("log2_updates")).agg(F.count(F.lit(1)).alias("vertices"))


def half_split(first: DataFrame, total: DataFrame) -> DataFrame:
    """r: correlation of a vertex's updates in the first half of a run with those in the second; first, total: vid, n_updates."""
    both = first.select("vid", F.col("n_updates").alias("x")).join(total.select("vid", "n_updates"), "vid")
    return both.agg(F.corr("x", F.col("n_updates") - F.col("x")).alias("r"), F.count(F.lit(1)).alias("vertices"))


def active_blocks(rounds: DataFrame) -> DataFrame:
    return rounds.groupBy("round").agg(F.sum(F.col("active").cast("long")).alias("active"))


def network(rounds: DataFrame) -> DataFrame:
    """round, messages: external messages so far."""
    per = rounds.groupBy("round").agg(F.sum("sent").alias("s"))
    return per.select("round", F.sum("s").over(Window.orderBy("round")).alias("messages"))


def modelled_time(rounds: DataFrame) -> DataFrame:
    """modelled: sum over rounds of the heaviest block's work. Work, not seconds: it shows scaling that one machine's wall clock can't."""
    return rounds.groupBy("round").agg(F.max("work").alias("w")).agg(F.sum("w").alias("modelled"), F.count(F.lit(1)).alias("rounds"))


def utilisation(rounds: DataFrame, workers: int) -> DataFrame:
    """Share of worker rounds with work."""
    return rounds.agg((F.sum((F.col("vertex_updates") > 0).cast("int")) / (workers * F.count_distinct("round"))).alias("utilisation"))


def edge_vs_vertex_updates(rounds: DataFrame) -> DataFrame:
    per = rounds.groupBy("round").agg(F.sum("vertex_updates").alias("v"), F.sum("edge_updates").alias("e"))
    w = Window.orderBy("round")
    return per.select("round", F.sum("v").over(w).alias("vertex_updates"), F.sum("e").over(w).alias("edge_updates"))


def speedup(runs: DataFrame) -> DataFrame:
    """runs (workers, time) with speedup over one worker and whether it is at least linear."""
    one = runs.where("workers = 1").select(F.col("time").alias("t1"))
    return runs.crossJoin(F.broadcast(one)).select("workers", "time", (F.col("t1") / F.col("time")).alias("speedup"), (F.col("t1") / F.col("time") >= F.col("workers")).alias("linear"))


@contextmanager
def timed(out: dict, name: str):
    began = time.time()
    yield
    out[name] = time.time() - began


def timed_call(f: Callable, *args, **kw):
    began = time.time()
    return f(*args, **kw), time.time() - began
