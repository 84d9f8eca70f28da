"""Rewrites of a graph before it runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.logspace import add
from ..operators.model import FactorGraph


def absorb_unary(fg: FactorGraph) -> FactorGraph:
    """Factors of one variable become part of its prior: their message never changes."""
    p = F.broadcast(fg.potentials.where(F.size("cards") == 1).select("potential_id", "logpsi"))
    unary = fg.edges.join(p, "potential_id")
    width = fg.variables.agg(F.max("card")).first()[0] or 1
    sums = unary.groupBy("vid").agg(F.array(*[F.sum(F.get("logpsi", F.lit(s))) for s in range(width)]).alias("u"))
    v = fg.variables.join(sums, "vid", "left").select("vid", "card", F.when(F.col("u").isNull(), F.col("prior")).otherwise(add(F.col("prior"), F.slice("u", 1, F.col("card")))).alias("prior"))
    edges = fg.edges.join(F.broadcast(fg.potentials.where(F.size("cards") == 1).select("potential_id")), "potential_id", "left_anti")
    return FactorGraph(v, edges.select("fid", "vid", "slot", "card", "potential_id"), fg.potentials.where(F.size("cards") > 1))


def merge_parallel(fg: FactorGraph) -> FactorGraph:
    """Factors over the same variables in the same order become one: log tables add up."""
    scope = fg.edges.groupBy("fid", "potential_id").agg(F.transform(F.sort_array(F.collect_list(F.struct("slot", "vid"))), lambda x: x["vid"]).alias("scope"))
    groups = scope.groupBy("scope").agg(F.min("fid").alias("keep"), F.sort_array(F.collect_list("potential_id")).alias("ps"))
    kinds = groups.select("ps").distinct().withColumn("np", F.row_number().over(Window.orderBy("ps")).cast("long") - 1)
    parts = kinds.select("np", F.explode("ps").alias("potential_id")).join(F.broadcast(fg.potentials), "potential_id")
    longest = fg.potentials.agg(F.max(F.size("logpsi"))).first()[0] or 1
    made = parts.groupBy("np").agg(F.first("cards").alias("cards"), F.array(*[F.sum(F.get("logpsi", F.lit(s))) for s in range(longest)]).alias("l"))
    potentials = made.select(F.col("np").alias("potential_id"), "cards", F.filter("l", lambda x: x.isNotNull()).alias("logpsi"))
    kept = groups.join(F.broadcast(kinds), "ps").select(F.col("keep").alias("fid"), "np")
    edges = fg.edges.join(kept, "fid").select("fid", "vid", "slot", "card", F.col("np").alias("potential_id"))
    return FactorGraph(fg.variables, edges, potentials)


def drop_isolated(fg: FactorGraph) -> tuple[FactorGraph, DataFrame]:
    """The graph without variables that no factor touches, and those variables: their belief is their prior."""
    linked = fg.edges.select("vid").distinct()
    return FactorGraph(fg.variables.join(linked, "vid", "left_semi"), fg.edges, fg.potentials), fg.variables.join(linked, "vid", "left_anti")


def explain(fg: FactorGraph, workers: int, over: int, piece_bytes: int = 256 << 20) -> dict:
    """What a run would hold: sizes, bytes per piece, and the pieces that a bound on their size asks for."""
    n, m = fg.variables.count(), fg.edges.count()
    card = fg.variables.agg(F.max("card")).first()[0] or 1
    total = m * (2 * (16 + 8 * card) + 24)
    return {"variables": n, "edges": m, "largest_domain": card, "bytes": total, "bytes_per_piece": total / (workers * over), "pieces_needed": max(workers * over, -(-total // piece_bytes))}
