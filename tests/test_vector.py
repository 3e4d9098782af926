"""Vector lanes against the scalar kernel, as the trace streams by."""

import random
import time
import tracemalloc

import pytest

from critgraph import queries as Q
from critgraph.configs import P_INO
from critgraph.operators import kernels as K
from critgraph.operators import runs
from test_kernels import program


def _cut(cols, size):
    for at in range(0, len(cols["op"]), size):
        yield {k: v[at : at + size] for k, v in cols.items()}


def _machines(r):
    width = lambda: r.choice([None, 1, 2, 3, 4])
    base = P_INO.edit(fbw=width(), ibw=width(), cbw=width(), lsq=r.choice([None, 1, 2, 5]), fu_policy=r.choice(["lru", "lru", "earliest"]), predicted_permille=r.choice([0, 0, 300]))
    base = base.edit(units={u: r.choice([1, 2, 3]) for u in base.units if r.random() < 0.8})
    ideal = r.random() < 0.3
    return [
        base.edit(
            latency={o: r.randrange(30) + 1 for o in base.latency}, decode=r.randrange(3), penalty=r.choice([0, 3, 9]), forward=r.choice([1, 2]), ideal_fetch=r.random() < 0.3,
            ideal_branch=ideal, memory=r.choice([None, None, 4]), blocking=r.choice([base.blocking, frozenset(), frozenset({"INT_ALU", "FP_DIV"})]),
        )
        for _ in range(3)
    ]


def test_sweeps_in_pieces_equal_whole_runs():
    r, plain = random.Random(5), 0
    for seed in range(200):
        cols, lanes = program(r.choice([1, 3, 40, 150]), seed, r.choice([2, 8, 32])), _machines(r)
        whole = [K.run(K.Program(cols, m)) for m in lanes]
        vector, scalars = K.LaneSweep(lanes), [K.ScalarSweep(m) for m in lanes]
        for piece in _cut(cols, r.choice([1, 7, 37, 1000])):
            for s in (vector, *scalars):
                s.feed(piece)
        assert vector.cycles().tolist() == whole == [s.cycles() for s in scalars]
        plain += vector.plain
    assert plain > 50  # those that sweep matrices


def test_sweep_of_more_than_a_matrix():
    cols = program(2 * K.ROWS + 7, 3, 32)
    lanes = [P_INO, P_INO.set_latency(FP_MUL=2, INT_DIV=30), P_INO.edit(memory=2)]
    sweep = K.LaneSweep(lanes)
    sweep.feed(cols)
    assert sweep.cycles().tolist() == [K.run(K.Program(cols, m)) for m in lanes]


def test_scalar_sweep_refuses_what_it_does_not_model():
    for m in (P_INO.edit(lq=4), P_INO.edit(depth={"fpu": 2}), Q.P_OOO):
        with pytest.raises(ValueError):
            K.ScalarSweep(m)


def test_scalar_sweep_is_small_and_cheaper_than_lists_of_lengths():
    n = 40_000
    cols = program(n, 1, 32)
    cols["addr"] = [64 * k if o in (6, 7) else None for k, o in enumerate(cols["op"])]  # a new address each
    parts = list(_cut(cols, 2000))
    whole = one = float("inf")
    for _ in range(3):
        a = time.process_time()
        cycles = K.run(K.Program(cols, P_INO))
        b = time.process_time()
        s = K.ScalarSweep(P_INO)
        for p in parts:
            s.feed(p)
        c = time.process_time()
        whole, one = min(whole, b - a), min(one, c - b)
    assert s.cycles() == cycles and one < 0.8 * whole
    tracemalloc.start()
    s = K.ScalarSweep(P_INO)
    for p in parts:
        s.feed(p)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 1 << 20 and len(s.store) < 100


def test_shares_are_alike_and_whole():
    assert runs.shares((1, 2, 4, 8, 16, 32)) == [[32], [16, 8], [4, 2, 1]]
    assert sorted(n for s in runs.shares((5, 1, 9)) for n in s) == [1, 5, 9]


def test_vector_speedup_streams_one_shuffled_trace(spark, sf):
    d = Q.vector_speedup(spark, sf)
    assert sorted(r.lanes for r in d.collect()) == [1, 2, 4, 8, 16, 32]
    plan = d._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    assert "FlatMapGroups" not in plan and plan.count("MapInArrow") == 3 and plan.count("Reused") == 2


def test_differing_lanes_raise():
    t = runs.Timed([P_INO])
    t.feed(program(50, 2))
    t.scalars[0].c += 1
    with pytest.raises(RuntimeError, match="differ"):
        t.row(4)
