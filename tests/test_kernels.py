"""Kernels against each other and against a generic longest path over the listed edges."""

import random

import numpy as np
import pytest

from critgraph.configs import P_INO, P_OOO
from critgraph.operators import kernels as K
from critgraph.operators.baselines import TickSimulator


def program(n, seed, registers=8):
    r = random.Random(seed)
    op = [r.choice([0, 0, 0, 1, 2, 3, 4, 5, 6, 6, 7, 8]) for _ in range(n)]
    reg = lambda p: r.randrange(registers) if r.random() < p else None
    return {
        "op": op, "seq": list(range(n)), "src1": [reg(0.8) for _ in op], "src2": [reg(0.4) for _ in op], "dst": [None if o in (7, 8) else reg(0.9) for o in op],
        "addr": [r.randrange(6) * 8 if o in (6, 7) else None for o in op], "imem": [r.choice([0, 0, 0, 1, 20]) for _ in op], "dmem": [r.choice([2, 2, 20]) if o in (6, 7) else None for o in op],
        "miss": [o == 8 and r.random() < 0.3 for o in op], "pc": [r.randrange(50) for _ in op],
    }


def generic(p):
    """Longest path by relaxing the listed edges until nothing changes."""
    stages = ("F", "E", "C") if p.D is None else ("F", "D", "E", "C")
    edges = [((w, ws), (i, s), sum(c for _, c in t)) for i in range(p.n) for s in stages for w, ws, _, _, t in K.parents(p, i, s)]
    at = {(i, s): 0 for i in range(p.n) for s in stages}
    for _ in range(len(at) + 1):
        changed = False
        for a, b, w in edges:
            if at[a] + w > at[b]:
                at[b], changed = at[a] + w, True
        if not changed:
            return at
    raise AssertionError("cycle")


MACHINES = [P_INO, P_INO.edit(lsq=None, units={}), P_INO.edit(depth={"fpu": 2}), P_OOO, P_OOO.edit(rob=12, window=8, ibw=2, lq=2, sq=2), P_OOO.edit(rob=16, iq=6, window=16), P_OOO.set_units(ialu=1, falu=1), P_INO.edit(fu_policy="earliest"), P_OOO.edit(fu_policy="earliest")]


@pytest.mark.parametrize("machine", MACHINES)
@pytest.mark.parametrize("method", ["two_pass", "active", "updated"])
def test_lengths_equal_generic_longest_path(machine, method):
    for seed in range(6):
        p = K.Program(program(60, seed), machine)
        K.run(p, method)
        at = generic(p)
        for s, own in (("F", p.F), ("E", p.E), ("C", p.C)):
            assert [at[i, s] for i in range(p.n)] == own


@pytest.mark.parametrize("machine", MACHINES)
def test_path_is_tight_and_sums_to_cycles(machine):
    for seed in range(6):
        p = K.Program(program(80, seed), machine)
        cycles = K.run(p)
        path = K.critical_path(p)
        assert sum(c for *_, t in path for _, c in t) == cycles
        assert path[0][2:4] == (p.n - 1, "C") and path[-1][:2] == (0, "F")


def test_vector_lanes_equal_single_runs():
    for seed in range(5):
        cols = program(200, seed)
        lanes = [P_INO, P_INO.edit(ideal_fetch=True), P_INO.edit(ideal_branch=True), P_INO.set_latency(FP_MUL=2, INT_DIV=30), P_INO.edit(memory=2), P_INO.edit(predicted_permille=300), P_INO.edit(forward=3)]
        whole = K.LaneSweep(lanes)
        whole.feed(cols)
        parts = K.LaneSweep(lanes)
        for at in range(0, 200, 37):
            parts.feed({k: v[at : at + 37] for k, v in cols.items()})
        single = [K.run(K.Program(cols, m)) for m in lanes]
        assert whole.cycles().tolist() == single == parts.cycles().tolist()


def test_vector_lanes_with_earliest_units():
    cols = program(200, 11)
    lanes = [P_INO.edit(fu_policy="earliest", latency={**P_INO.latency, "INT_DIV": k, "FP_DIV": 2 * k}) for k in (3, 9, 20)]
    sweep = K.LaneSweep(lanes)
    sweep.feed(cols)
    assert sweep.cycles().tolist() == [K.run(K.Program(cols, m)) for m in lanes]


def test_monotone_and_bounds():
    for seed in range(5):
        cols = program(150, seed)
        base = K.run(K.Program(cols, P_INO))
        assert K.run(K.Program(cols, P_INO.set_latency(INT_MUL=9))) >= base
        both = K.run(K.Program(cols, P_INO.edit(ideal_fetch=True, ideal_branch=True)))
        assert both <= K.run(K.Program(cols, P_INO.edit(ideal_fetch=True))) <= base
        assert both <= K.run(K.Program(cols, P_INO.edit(ideal_branch=True))) <= base
        assert base >= 150 // 2


@pytest.mark.parametrize("machine", [m for m in MACHINES if m.core == "ooo"])
def test_updated_list_and_ready_queue_agree(machine):
    moves = 0
    for seed in range(8):
        cols = program(160, seed, 24)
        for window in (4, 24, 10**6):
            a, b = K.Program(cols, machine), K.Program(cols, machine)
            assert K.sliding_updated(a, window) == K.sliding_active(b, window)
            assert (a.F, a.D, a.E, a.C) == (b.F, b.D, b.E, b.C)
            moves += a.moves
            assert 4 <= a.live <= 4 * (min(window, a.n) + 400)
    assert moves > 0


def test_window_of_whole_program_without_updates_is_two_pass():
    """The order is that of two passes; lengths are those at which entries were taken, and near the exact ones."""
    for seed in range(6):
        cols = program(90, seed)
        m = P_OOO.edit(rob=24, ibw=2, window=10**6)
        a, b = K.Program(cols, m), K.Program(cols, m)
        assert K.sliding_fixed(a, m.window) == K.two_pass(b) and 0.85 * b.C[-1] <= a.C[-1] <= 1.05 * b.C[-1]


def test_unlimited_resources_give_base_graph():
    for seed in range(4):
        cols = program(90, seed)
        m = P_OOO.without_resources()
        assert K.run(K.Program(cols, m), "active") == K.run(K.Program(cols, m), "base")


def test_all_values_predicted_wrongly_costs_more():
    cols = program(120, 3)
    right = K.run(K.Program(cols, P_INO.edit(predicted_permille=1000)))
    wrong = K.run(K.Program(cols, P_INO.edit(predicted_permille=1000, predict_penalty=8)))
    assert right <= K.run(K.Program(cols, P_INO)) <= wrong


@pytest.mark.parametrize("machine,limit", [(P_INO, 12), (P_OOO, 20)])
def test_tick_simulator_is_near(machine, limit):
    apart = []
    for seed in range(8):
        cols = program(300, seed, 24)
        a, b = K.run(K.Program(cols, machine)), TickSimulator(machine, cols, 300).run()
        apart.append(100 * abs(a - b) / b)
    assert np.mean(apart) < limit, apart


def test_empty_and_single():
    for m in (P_INO, P_OOO):
        assert K.run(K.Program(program(0, 0), m)) == 0
        assert K.run(K.Program(program(1, 0), m)) > 0
