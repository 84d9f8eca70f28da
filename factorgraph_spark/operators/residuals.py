"""Residuals of vertices as table operations, and their histories."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.logspace import l1


def message_change(old: DataFrame, new: DataFrame) -> DataFrame:
    """fid, vid, delta: L1 change of every message (f2v)."""
    return old.select("fid", "vid", F.col("f2v").alias("o")).join(new.select("fid", "vid", F.col("f2v").alias("n")), ["fid", "vid"]).select("fid", "vid", l1(F.col("o"), F.col("n")).alias("delta"))


def largest_change(old: DataFrame, new: DataFrame) -> DataFrame:
    """max_delta: what the convergence test compares with beta."""
    return message_change(old, new).agg(F.max("delta").alias("max_delta"))


def by_message(old: DataFrame, new: DataFrame) -> DataFrame:
    """vid, residual: largest change of an inbound message."""
    return message_change(old, new).groupBy("vid").agg(F.max("delta").alias("residual"))


def inbound(rows: DataFrame) -> DataFrame:
    """The same from the ends of a tracked step (``pairwise``, gathered), which know their changes."""
    found = rows.groupBy("vid").agg(F.min("code").alias("least"), F.max("delta").alias("residual"))
    return found.where("least < 0 and residual is not null").drop("least")


def naive(before: DataFrame, after: DataFrame) -> DataFrame:
    """vid, residual: L1 distance of the belief (vid, state, belief) from that at the last update."""
    both = before.withColumnRenamed("belief", "b").join(after, ["vid", "state"])
    return both.groupBy("vid").agg(F.sum(F.abs(F.col("belief") - F.col("b"))).alias("residual"))


def accumulated(changes: DataFrame) -> DataFrame:
    """changes with residual: running sum of l1 since the vertex's last update. changes: vid, step, l1, updated (true where the vertex is
    updated at that step, after which it counts from zero)."""
    order = Window.partitionBy("vid").orderBy("step")
    life = F.sum(F.col("updated").cast("int")).over(order)
    rows = changes.withColumn("life", life).withColumn("counted", F.when(F.col("updated"), 0.0).otherwise(F.col("l1")))
    return rows.withColumn("residual", F.sum("counted").over(Window.partitionBy("vid", "life").orderBy("step"))).drop("life", "counted")
