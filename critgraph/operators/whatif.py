"""Scenarios: named edits of a machine, run as lanes of one pass."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.configs import Machine
from critgraph.operators import runs
from critgraph.plans import planner
from critgraph.schemas import TERM_OF_OP

TERMS = ("fetch", "branch_penalty", "decode", *sorted({TERM_OF_OP[o] for o in ("INT_ALU", "FP_ALU", "LOAD", "STORE", "BRANCH")}))


def front_end(m: Machine) -> dict[str, Machine]:
    """Base, ideal fetch, ideal prediction, both."""
    return {"base": m, "ideal_fetch": m.edit(ideal_fetch=True), "ideal_branch": m.edit(ideal_branch=True), "both": m.edit(ideal_fetch=True, ideal_branch=True)}


def limits(m: Machine) -> dict[str, Machine]:
    """Each term idealised alone (at the least cost its rule allows), and the front end's two together."""
    out = {"base": m}
    for t in TERMS:
        if t == "branch":
            out[t] = m.edit(ideal_branch=True)
        elif t == "load":
            out[t] = m.edit(memory=0)
        elif t in ("int", "fp", "store"):
            out[t] = m.set_term(t, 1)
        else:
            out[t] = m.set_term(t, 0)
    return out | {"front_end": m.edit(ideal_fetch=True, ideal_branch=True, penalty=0)}


def combine(*edits):
    """One edit (a function of a machine) made of several."""

    def both(m: Machine) -> Machine:
        for e in edits:
            m = e(m)
        return m

    return both


def drop(m: Machine, kind: str) -> Machine:
    """A rule that adds no edge."""
    fields = {"fetch_bw": "fbw", "dispatch_bw": "dbw", "issue_bw": "ibw", "commit_bw": "cbw", "rob": "rob", "iq": "iq"}
    if kind in fields:
        return m.edit(**{fields[kind]: None})
    return m.edit(lsq=None, lq=None, sq=None) if kind == "queue" else m.edit(units={}, depth={})


def compare(trace: DataFrame, scenarios: dict[str, Machine]) -> DataFrame:
    """(program_id, scenario, cycles, improvement, speedup) against the first scenario."""
    return runs.improvements(planner.run(trace, list(scenarios.values())), list(scenarios))


def secondary(trace: DataFrame, m: Machine, terms: tuple[str, ...] = ("fetch",)) -> DataFrame:
    """(program_id, stacked_saving, exact_saving): the critical path's cycles of ``terms`` against what idealising them saves."""
    stacked = runs.breakdown(trace, [m]).where(F.col("term").isin(*terms)).groupBy("program_id").agg(F.sum("cycles").alias("stacked_saving"))
    ideal = m
    for t in terms:
        ideal = ideal.edit(ideal_branch=True) if t == "branch" else ideal.set_term(t, 0)
    exact = planner.run(trace, [m, ideal]).groupBy("program_id").agg((F.max(F.when(F.col("lane") == 0, F.col("cycles"))) - F.max(F.when(F.col("lane") == 1, F.col("cycles")))).alias("exact_saving"))
    return exact.join(stacked, "program_id", "left").select("program_id", F.coalesce("stacked_saving", F.lit(0)).cast("bigint").alias("stacked_saving"), F.col("exact_saving").cast("bigint").alias("exact_saving"))
