"""Evidence that arrives as a stream of events: windows, late rows, a stateful forward filter, and beliefs brought up to date per batch."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import block_bp
from ..operators.kernel import BPConfig
from ..operators.model import FactorGraph, potts
from ..plans.gallery import EVENT_TYPES, STICKY, emission
from ..sources.tables import cut, fresh_path


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files of events as a stream; ts is a UTC timestamp."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling_counts(events: DataFrame, size: str = "1 hour", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding_counts(events: DataFrame, size: str = "2 hours", slide: str = "1 hour", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", size, slide), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def first_seen(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drained(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """What a streaming query gives once all present input is taken in (trigger "available now").

    mode: "complete" and "update" give the last version of every row that they wrote (by batch: complete writes all rows each time), "append"
    the rows as they became final. Batches land in the shared folder, so a batch that is run again replaces itself. With ``checkpoint`` the
    query goes on where an earlier call with that folder stopped.
    """
    spark = stream.sparkSession
    path, last = fresh_path(spark, "stream"), []

    def land(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        last.append(number)

    q = stream.writeStream.outputMode(mode).foreachBatch(land).option("checkpointLocation", checkpoint or fresh_path(spark, "stream-log")).trigger(availableNow=True).start()
    q.awaitTermination()
    found = spark.read.schema(stream.schema)
    if not last:
        return spark.createDataFrame([], stream.schema)
    return found.parquet(f"{path}/batch={max(last)}") if mode == "complete" else found.parquet(*[f"{path}/batch={k}" for k in sorted(set(last))])


def late_rows(events: DataFrame, high: str) -> DataFrame:
    """How many rows of a batch lie before the watermark ``high`` (a timestamp), by event type: what windowed counts would drop."""
    return events.where(F.col("ts") < F.lit(high).cast("timestamp")).groupBy("event_type").agg(F.count(F.lit(1)).alias("late"))


def forward_filter(events: DataFrame) -> DataFrame:
    """event_id, state, belief given the events of the same user so far. The state of a user is one message."""
    like, pair = np.log(np.array(emission())), np.array(potts(3, STICKY)).reshape(3, 3)
    column = {t: k for k, t in enumerate(EVENT_TYPES)}

    def step(key, batches, state: GroupState):
        import pandas as pd

        message = np.array(state.get[0]) if state.exists else np.zeros(3)
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for e, t in zip(rows["event_id"], rows["event_type"]):
            x = message + (like[:, column[t]] if t in column else 0)
            p = np.exp(x - x.max())
            out += [(int(e), s, float(v)) for s, v in enumerate(p / p.sum())]
            y = x[:, None] + pair
            message = np.log(np.exp(y - y.max()).sum(axis=0))
            message -= message.max()
        state.update((message.tolist(),))
        yield pd.DataFrame(out, columns=["event_id", "state", "belief"])

    rows = events.select("user_id", "event_id", "ts", "event_type")
    return rows.groupBy("user_id").applyInPandasWithState(step, "event_id long, state int, belief double", "message array<double>", "append", GroupStateTimeout.NoTimeout)


def incremental(fg: FactorGraph, result: block_bp.Result, evidence: DataFrame, cfg: BPConfig) -> block_bp.Result:
    """Goes on from a finished run after new evidence (vid, state, strength): only what the change reaches is updated again.

    The touched variables' sums take in the new odds and their residual grows by the change; messages, beliefs and everything else stay.
    Strengths of one variable's state add up. Each block gets the evidence of its own variables by a cogroup, whatever the number of rows.
    """
    import pickle

    found = evidence.groupBy("vid", "state").agg(F.sum("strength").alias("strength")).where("strength is not null")
    homes = block_bp._unpacked(result.state, lambda b: [(v, b.number) for v in b.ids[: b.n_var]], "vid long, block long")
    own = found.join(homes, "vid").select("block", "vid", "state", "strength")

    def touch(states: pa.Table, news: pa.Table) -> pa.Table:
        b = pickle.loads(states.column("body")[0].as_buffer())
        rows = sorted(zip(*(news.column(c).to_pylist() for c in ("vid", "state", "strength"))))
        for v, s, x in rows:
            k = b.where[v]
            b.prior[k, s] += x
            b.total[k, s] += x
            b.promote(k, b.residual[k] + 2 * math.tanh(abs(x)))
        body, worst = pa.array([pickle.dumps(b, 5)], pa.binary()), pa.array([b.worst()], pa.float64())
        return pa.table({"block": pa.array([b.number], pa.int64()), "body": body, "max_residual": worst})

    blocks = result.state.select("block", "body").groupBy("block")
    state = cut(blocks.cogroup(own.groupBy("block")).applyInArrow(touch, "block long, body binary, max_residual double"))
    return block_bp.resume(block_bp.Result(fg, state, list(result.rounds), mail=result.mail, mail_bytes=result.mail_bytes), cfg, max_rounds=len({r["round"] for r in result.rounds}) + cfg.max_rounds)


def each_batch(fg: FactorGraph, result: block_bp.Result, cfg: BPConfig, sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """For writeStream.foreachBatch: evidence in, beliefs out."""
    held = [result]

    def step(batch: DataFrame, number: int) -> None:
        held[0] = incremental(fg, held[0], batch, cfg)
        sink(held[0].beliefs, number)

    return step
