"""Streaming: the in-order sweep with a state per program, windows, and stream joins."""

from __future__ import annotations

import pickle
import uuid
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from critgraph.configs import Machine, P_INO
from critgraph.operators.kernels import LaneSweep
from critgraph.runtime import shared_dir, ship
from critgraph.sources.traces import from_events, op_code

OUT = "program_id int, cycles bigint, instrs bigint, late bigint, last_event bigint"


def events_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream (its schema is taken from the batch table, never inferred from data)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/event[s].parquet")
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need an instant


def sweep_stream(events: DataFrame, m: Machine = P_INO, idle: str = "10 minutes") -> DataFrame:
    """Per program and trigger: cycles and instructions so far. Constant state a program.

    Events of a program are taken in order of event_id; one at or before the last taken is late
    and only counted. After ``idle`` without events (by the watermark) a program's state goes.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    ship(events.sparkSession)
    minutes = int(idle.split()[0])

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        held, late, last = state.get if state.exists else (b"", 0, -1)
        sweep = LaneSweep([m], pickle.loads(held) if held else None)
        rows = pd.concat(list(frames)).sort_values("event_id")
        new = rows[rows["event_id"] > last]
        late += len(rows) - len(new)
        if len(new):
            t = pa.Table.from_pandas(new, preserve_index=False)
            cols = {c: t.column(c).to_pylist() for c in ("op", "src1", "src2", "dst", "addr", "imem", "dmem", "miss")}
            whole = lambda v: [None if x is None or x != x else int(x) for x in v]  # noqa: E731  pandas keeps nulls as NaN
            cols = {c: (v if c == "miss" else whole(v)) for c, v in cols.items()} | {"seq": list(range(len(new)))}
            sweep.feed(cols)
            last = int(new["event_id"].iloc[-1])
        state.update((pickle.dumps(sweep.s), late, last))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), int(rows["ts"].max().timestamp() * 1000)) + 60_000 * minutes)
        yield pd.DataFrame({"program_id": [key[0]], "cycles": [int(sweep.cycles()[0])], "instrs": [sweep.s["n"]], "late": [late], "last_event": [last]})

    d = from_events(events, numbered=False).withWatermark("ts", idle)
    d = d.select("program_id", "event_id", "ts", op_code(F.col("op_class")).alias("op"), "src1", "src2", "dst", "addr", F.col("imem_cycles").alias("imem"), F.col("dmem_cycles").alias("dmem"), F.col("mispredicted").alias("miss"))
    return d.groupBy("program_id").applyInPandasWithState(step, OUT, "held binary, late bigint, last bigint", "append", GroupStateTimeout.EventTimeTimeout)


def window_counts(events: DataFrame, size: str = "1 hour", delay: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """(start, program_id, n, mem_cycles) of tumbling (or sliding) windows, late rows beyond the watermark dropped."""
    d = from_events(events, numbered=False)
    if events.isStreaming:
        d = d.withWatermark("ts", delay)
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return d.groupBy(w.alias("w"), "program_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.coalesce("dmem_cycles", F.lit(0))).cast("bigint").alias("mem_cycles")).select(F.col("w.start").alias("start"), "program_id", "n", "mem_cycles")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """(user_id, start, finish, n) of session windows."""
    d = events.withWatermark("ts", delay) if events.isStreaming else events
    return d.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "n")


def distinct_events(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Events once each, repeats within the watermark dropped."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def with_static(events: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Stream-static join (a machine table, a code table)."""
    return events.join(static, key, "left")


def views_before_purchases(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: purchases with the same user's views of the time before."""
    e = events.withWatermark("ts", "10 minutes")
    v = e.where("event_type = 'view'").select(F.col("user_id").alias("v_user"), F.col("ts").alias("v_ts"), F.col("event_id").alias("view_id"))
    p = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id")
    return p.join(v, F.expr(f"user_id = v_user and v_ts <= ts and v_ts >= ts - interval {within}"))


def drained(stream: DataFrame) -> DataFrame:
    """All output (append mode) of a stream over what its source holds now, written as Parquet in the shared folder."""
    spark, at = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/critgraph-stream-{uuid.uuid4().hex}"
    q = stream.writeStream.format("parquet").option("path", f"{at}/rows").option("checkpointLocation", f"{at}/state").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/rows")


def final_state(updates: DataFrame) -> DataFrame:
    """The last update of each program."""
    return updates.groupBy("program_id").agg(F.max_by(F.struct("cycles", "instrs", "late"), "instrs").alias("s")).select("program_id", "s.cycles", "s.instrs", "s.late")
