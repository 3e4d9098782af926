"""The worked examples over the latencies of ``part``: every row is read, and the published results hold at 5 and 6 cycles."""

import pytest

from critgraph import queries as Q

#: At a multiply of 5 and a memory access of 6 cycles: what distinguishes a row -> its length.
WANT = {
    "crack_example": {("whole", "C1"): 13, ("cracked", "C1"): 9},
    "fu_blocking": {("blocking", "E0"): 6, ("blocking", "E1"): 11, ("blocking", "E2"): 16},
    "fu_depth": {("unlimited", "M4"): 10, ("depth 3", "M4"): 13, ("depth 3", "M3"): 17},
    "fu_pipelined": {("pipelined", "E0"): 6, ("pipelined", "E1"): 7, ("pipelined", "E2"): 8},
    "spec_branch": {("right", "C1"): 7, ("wrong", "C1"): 16},
    "toy_base": {("base",): 15},
    "toy_fused": {("fused, second register",): 11, ("fused, one register",): 14},
    "toy_path": {("M0", "E2"): 6, ("E2", "E3"): 5, ("M0", "M1"): 5},
    "toy_sql_path": {(3, "C"): 15},
    "toy_whatif": {("base",): 15, ("fast multiply",): 15, ("second register",): 15, ("both",): 12},
    "toy_without_mul": {("without multiplier",): 15},
}
KEYS = {"toy_path": ("src", "dst", "w"), "toy_sql_path": ("dst_seq", "dst_stage", "cp")}


@pytest.mark.parametrize("name", list(WANT))
def test_worked_example_over_parts(spark, sf, name):
    d = Q.QUERIES[name](spark, sf)
    rows = d.collect()
    label = ("case_name", "vertex") if "vertex" in d.columns else ("case_name",)
    *keys, value = KEYS.get(name, (*label, "cp" if "cp" in d.columns else "cycles"))
    got = {tuple(r[k] for k in keys): r[value] for r in rows if (r["mul"], r["memory"]) == (5, 6)}
    assert WANT[name].items() <= got.items()
    parts = {(r["mul"], r["memory"]): r["parts"] for r in rows}
    assert sum(parts.values()) == spark.read.parquet(f"{sf}/part.parquet").count()
