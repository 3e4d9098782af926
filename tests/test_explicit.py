"""The explicit graph made and swept as the trace streams by."""

import random
import tracemalloc

import pytest
from pyspark.sql import functions as F

from critgraph import queries as Q
from critgraph.configs import P_INO, P_OOO
from critgraph.operators import explicit, graph, kernels
from critgraph.runtime import configured
from critgraph.schemas import LOAD, OPS, STORE
from critgraph.sources import traces


def _rows(n: int, first: int = 0) -> dict[str, list]:
    r = random.Random(first)
    op = [r.choice((0, 0, 1, 1, 2, 3, 4, 5, 6, 7, 8)) for _ in range(n)]
    return {
        "op": op, "seq": [*range(first, first + n)], "src1": [r.choice((None, r.randrange(6))) for _ in op], "src2": [r.choice((None, r.randrange(6))) for _ in op],
        "dst": [r.choice((None, r.randrange(6))) if o not in (STORE, 8) else None for o in op], "addr": [8 * r.randrange(40) if o in (LOAD, STORE) else None for o in op],
        "imem": [int(k % 16 == 0) for k in range(n)], "dmem": [r.choice((2, 20)) for _ in op], "miss": [o == 8 and r.random() < 0.1 for o in op],
    }


def _trace(spark, cols):
    rows = [(p, s, OPS[o], a, b, d, x, i, m, w) for p in (0, 1) for o, s, a, b, d, x, i, m, w in zip(*(cols[k] for k in explicit.COLUMNS))]
    return spark.createDataFrame(rows, "program_id int, seq bigint, op_class string, src1 int, src2 int, dst int, addr bigint, imem_cycles int, dmem_cycles int, mispredicted boolean")


def _cycles(d):
    return {r[0]: r[1] for r in d.where("stage = 'C'").groupBy("program_id").agg(F.max("cp")).collect()}


def _streamed(d):
    return {(r["program_id"], r["lane"]): r["cycles"] for r in d.collect()}


@pytest.mark.parametrize("name", ["graph_longest", "ooo_explicit", "fuse_trace", "value_speculation"])
def test_no_edge_is_shuffled(spark, sf, name):
    plan = Q.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "FlatMapGroups" not in plan and "Join" not in plan.split("MapInArrow")[0]


@pytest.mark.parametrize("name", ["ooo_explicit", "fuse_trace", "value_speculation"])
def test_lines_are_dealt_by_order_part_and_program_once(spark, sf, name):
    with configured(spark, {"spark.sql.autoBroadcastJoinThreshold": "-1"}):
        plan = Q.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(program_id") == 1 and "REPARTITION" not in plan
    assert 0 < plan.index("SortMergeJoin [l_orderkey") < plan.index("SortMergeJoin [o_custkey")  # a join that comes later is made earlier


@pytest.mark.parametrize("m", [P_INO, P_OOO])
def test_edges_are_those_of_the_graph(spark, sf, m):
    t = traces.from_lineitem(spark, sf).where("program_id < 2").localCheckpoint()
    found = sorted(tuple(r) for r in graph.base_graph(t, m).collect())
    made = []
    for p in (0, 1):
        rules = explicit.Rules(m)
        for r in t.where(F.col("program_id") == p).orderBy("seq").collect():
            i, edges = rules.add(OPS.index(r.op_class), r.seq, r.src1, r.src2, r.dst, r.addr, r.imem_cycles, r.dmem_cycles, r.mispredicted)
            made += [(p, e[0].seq, explicit.NAMES[e[1]], i.seq, explicit.NAMES[e[2]], e[3], e[4]) for e in edges]
    assert sorted(made) == found and len({e[5] for e in made}) > 8


def test_longest_and_two_passes_on_odd_rows(spark):
    cols = _rows(700)
    t = _trace(spark, cols).localCheckpoint()
    assert _streamed(explicit.cycles(t, lambda: explicit.Longest(P_INO))) == {(p, 0): c for p, c in _cycles(graph.longest(graph.base_graph(t, P_INO))).items()}
    p = kernels.Program(cols, P_OOO)
    kernels.two_pass(p)
    assert _streamed(explicit.cycles(t, lambda: explicit.TwoPass(P_OOO))) == {(0, 0): p.C[-1], (1, 0): p.C[-1]}
    assert explicit.cycles(t.where("false"), lambda: explicit.Longest(P_INO)).count() == 0
    with pytest.raises(ValueError):
        explicit.Longest(P_OOO)


def test_fused_pairs_on_odd_rows(spark):
    cols = _rows(900, 3)
    for k in range(0, 900, 5):  # a product for the next row, in most cases gone with the row after it
        a, b = (1, 0) if k % 2 else (4, 3)
        cols["op"][k : k + 3], cols["dst"][k], cols["src1"][k + 1], cols["addr"][k : k + 3], cols["miss"][k : k + 3] = [a, b, 0], k % 6, k % 6, [None] * 3, [False] * 3
        cols["dst"][k + 2] = k % 6 if k % 4 else cols["dst"][k + 2]
        cols["dst"][k + 1] = k % 6 if k % 7 == 0 else cols["dst"][k + 1]
    t = _trace(spark, cols).localCheckpoint()
    pairs = graph.fusible_pairs(t)
    assert pairs.count() > 20
    old = _cycles(graph.longest(graph.fuse(graph.base_graph(t, P_INO), pairs, 4)))
    assert _streamed(explicit.cycles(t, lambda: explicit.Fused(P_INO, 4))) == {(p, 0): c for p, c in old.items()}


def test_edited_register_edges_on_odd_rows(spark):
    t = _trace(spark, _rows(500, 5)).localCheckpoint()
    e, loads = graph.base_graph(t, P_INO).localCheckpoint(), t.where("op_class = 'LOAD'").select("program_id", "seq")
    edits = (None, lambda i, w: None if i.op == LOAD else w, lambda i, w: w + 8 if i.op == LOAD else w)
    got = _streamed(explicit.cycles(t, lambda: explicit.Longest(P_INO, edits)))
    for k, g in enumerate((e, graph.predict_values(e, loads), graph.mispredict_values(e, loads, 8))):
        assert {p: c for (p, lane), c in got.items() if lane == k} == _cycles(graph.longest(g))


@pytest.mark.parametrize("sweep", [lambda: explicit.Longest(P_INO), lambda: explicit.TwoPass(P_OOO), lambda: explicit.Fused(P_INO, 4)])
def test_memory_does_not_grow_with_the_program(sweep):
    now = sweep()
    tracemalloc.start()
    peaks = []
    for k in range(12):
        now.feed(_rows(2000, 2000 * k))
        if k == 1:
            tracemalloc.reset_peak()
            peaks.append(tracemalloc.get_traced_memory()[0])
    now.cycles()
    peaks.append(tracemalloc.get_traced_memory()[0])
    tracemalloc.stop()
    assert peaks[1] < peaks[0] + 200_000  # bytes, for 20,000 more instructions
