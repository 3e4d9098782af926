"""Choice of a strategy by the size of programs, and pruning of lanes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.configs import Machine
from critgraph.operators import runs
from critgraph.plans import chunks

#: Instructions that one task sweeps in reasonable time.
TASK_ROWS = 5_000_000
#: Lanes of one vector sweep; more are run in groups over the same trace.
LANE_GROUP = 64


def longest_program(trace: DataFrame) -> int:
    return trace.groupBy("program_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0


def distinct_lanes(lanes: list[Machine]) -> tuple[list[Machine], list[int]]:
    """Lanes without those equal in all but name, and for each given lane its place among them."""
    kept, place, at = [], [], {}
    for m in lanes:
        key = repr(m.edit(name="", latency=dict(sorted(m.latency.items()))))
        if key not in at:
            at[key] = len(kept)
            kept.append(m)
        place.append(at[key])
    return kept, place


def choose(trace: DataFrame, lanes: list[Machine], limit: int = TASK_ROWS) -> str:
    """sweep | chunks | each | ooo_chunks."""
    long = longest_program(trace) > limit
    if all(m.core == "inorder" for m in lanes):
        return "chunks" if long else ("sweep" if len(lanes) > 1 else "each")
    return "ooo_chunks" if long else "each"


def run(trace: DataFrame, lanes: list[Machine], limit: int = TASK_ROWS) -> DataFrame:
    """(program_id, lane, cycles, instrs) by the chosen strategy, equal lanes run once."""
    kept, place = distinct_lanes(lanes)
    how = choose(trace, kept, limit)
    if how == "sweep":
        parts = [runs.run_lanes(trace, kept[i : i + LANE_GROUP]).withColumn("lane", (F.col("lane") + i).cast("int")) for i in range(0, len(kept), LANE_GROUP)]
    elif how == "each":
        parts = [runs.run_each(trace, kept)]
    else:
        one = chunks.run_chunked if how == "chunks" else lambda t, m: chunks.run_chunked_ooo(t, m).drop("chunks", "rerun")
        parts = [one(trace, m).withColumn("lane", F.lit(i)) for i, m in enumerate(kept)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    if len(kept) == len(lanes):
        return out
    spread = F.create_map(*(x for k in range(len(kept)) for x in (F.lit(k), F.array(*(F.lit(i) for i, p in enumerate(place) if p == k)))))
    return out.withColumn("lane", F.explode(spread[F.col("lane")])).select("program_id", "lane", "cycles", "instrs")
