"""Programs of any length in the memory of a task."""

import tracemalloc

import pytest

from critgraph import queries as Q
from critgraph.configs import P_INO
from critgraph.operators import blocks, graph, kernels, runs, valuepred
from critgraph.sources import traces


def _rows(n: int, first: int = 0) -> dict[str, list]:
    i = range(first, first + n)
    return {
        "op": [(7 * k) % 9 for k in i], "seq": [*i], "src1": [k % 32 for k in i], "src2": [(3 * k) % 32 if k % 3 else None for k in i], "dst": [(5 * k) % 32 if (7 * k) % 9 < 7 else None for k in i],
        "addr": [64 * (k % 500) if (7 * k) % 9 in (6, 7) else None for k in i], "block_no": [k // 5 if k % 2000 < 1500 else k // 2000 * 400 + 399 for k in i], "predicated": [k // 5 % 7 == 0 for k in i],
    }


def test_block_program_fed_in_pieces_is_small():
    whole = blocks.BlockProgram(_rows(6000), 4, *blocks.FORMATS)
    p = blocks.BlockProgram(None, 4, *blocks.FORMATS)
    for at in range(0, 6000, 61):
        p.feed(_rows(min(61, 6000 - at), at))
    p.close()
    assert (p.op, p.starts, p.delays) == (whole.op, whole.starts, whole.delays) and max(b - a for a, b in zip(p.starts, p.starts[1:])) > blocks.MOST
    assert [p.run(f) for f in blocks.FORMATS] == [whole.run(f) for f in blocks.FORMATS]
    tracemalloc.start()
    q = blocks.BlockProgram(None, 4, "4seg")
    for at in range(0, 40000, 2000):
        q.feed(_rows(2000, at))
    q.close()
    q.run()
    most = tracemalloc.get_traced_memory()[1] / len(q.op)
    tracemalloc.stop()
    assert most < 130  # bytes an instruction, pieces and both passes included


@pytest.mark.parametrize("name", ["block_format_gains", "block_formats", "block_path_mix", "block_path_shares"])
def test_block_queries_hold_no_program_as_a_group(spark, sf, name):
    plan = Q.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "FlatMapGroups" not in plan


def test_vector_sweep_is_fed_in_pieces():
    n = 60_000
    cols = _rows(n) | {"imem": [1] * n, "dmem": [2] * n, "miss": [k % 97 == 0 for k in range(n)], "pc": [0] * n}
    lanes = [P_INO.edit(decode=1 + k % 3) for k in range(32)]
    tracemalloc.start()
    runs.swept(lanes, cols)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 60 << 20  # a matrix of the whole program alone takes 15 MB, and the sweep has many


def test_validity_searches_no_program_without_a_backward_edge(spark, sf, monkeypatch):
    monkeypatch.setattr(graph, "peel", lambda e: pytest.fail("nothing leads back"))
    assert Q.graph_valid(spark, sf).collect() == []


def test_slacks_leave_as_they_are_made():
    n = 20_000
    cols = _rows(n) | {"imem": [1] * n, "dmem": [2] * n, "miss": [k % 97 == 0 for k in range(n)], "pc": [0] * n}
    p = kernels.Program(cols, P_INO)
    end = kernels.run(p)
    tracemalloc.start()
    edges, least = 0, end
    for *_, spare in runs.edge_slacks(p, end):
        edges, least = edges + 1, min(least, spare)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert least == 0 and edges > 8 * n and most < 200 * n  # bytes: a list of the edges takes over 1,000 an instruction


def test_both_sweeps_read_the_trace_once(spark, sf):
    t = traces.from_lineitem(spark, sf).where("program_id < 4")
    rows = lambda d: sorted(tuple(r) for r in d.collect())
    both = valuepred.both_sweeps(t, Q.P_OOO)
    assert rows(both) == rows(valuepred.critical_sweep(t, Q.P_OOO).unionByName(valuepred.random_sweep(t, Q.P_OOO)))
    plan = Q.vp_knee(spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapGroupsInArrow" not in plan  # the sweeps are written once and read twice


def test_one_loop_gives_the_general_schedule():
    n = 3000
    cols = _rows(n) | {"imem": [k % 16 == 0 for k in range(n)], "dmem": [20 if k % 11 == 0 else 2 for k in range(n)], "miss": [k % 97 == 0 for k in range(n)], "pc": [0] * n}
    for m in (Q.P_OOO, Q.P_OOO.edit(window=16, predicted_permille=400), Q.P_OOO.edit(predicted_permille=400, predict_penalty=7)):
        a, b = kernels.Program(cols, m), kernels.Program(cols, m)
        kernels.sliding_active(a, m.window)
        kernels.sliding_updated(b, m.window)
        assert (a.F, a.D, a.E, a.C) == (b.F, b.D, b.E, b.C)


@pytest.mark.parametrize("forms", [("4seg",), blocks.FORMATS])
def test_block_program_keeps_no_run_but_the_last(forms):
    q = blocks.BlockProgram(None, 4, *forms)
    for at in range(0, 20000, 2000):
        q.feed(_rows(2000, at))
    q.close()
    tracemalloc.start()
    for f in (*forms, forms[0]):
        q.run(f)
    most = tracemalloc.get_traced_memory()[1] / len(q.op)
    tracemalloc.stop()
    assert most < 36  # bytes an instruction that runs take at most: lengths of one run and its order
    assert q.op.codes and sum(a.itemsize for a in (*q.up, q.where, *q.delays.values())) == 16 + 2 * len(forms)
