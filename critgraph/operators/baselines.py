"""Comparators: tick-by-tick simulator, instruction counts, cycle stack, mechanistic model."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.configs import Machine
from critgraph.operators import kernels
from critgraph.operators.runs import _grouped
from critgraph.schemas import LOAD, STORE


class TickSimulator:
    """A core advanced cycle by cycle: fetch, dispatch, issue, write back, commit. No graph.

    Registers are renamed to the producing instruction; a reservation pool holds dispatched
    instructions, units are counted busy per cycle, and commit retires in order.
    """

    def __init__(self, m: Machine, cols: dict[str, list], limit: int):
        self.m, self.n = m, min(limit, len(cols["op"]))
        self.c = {k: v[: self.n] for k, v in cols.items() if k != "program_id"}

    def run(self) -> int:
        m, c, n = self.m, self.c, self.n
        if not n:
            return 0
        lat, blocking, unit = m.tables()
        in_order = m.core == "inorder"
        op = c["op"]
        time = [lat[o] + ((c["dmem"][i] or 0) if o == LOAD else 0) for i, o in enumerate(op)]
        wanted: list[tuple[int, ...]] = []
        rename, memory = {}, {}
        from_store: list[int | None] = []
        for i in range(n):
            wanted.append(tuple(rename[r] for r in (c["src1"][i], c["src2"][i]) if r is not None and r in rename))
            from_store.append(memory.get(c["addr"][i]) if op[i] == LOAD and c["addr"][i] is not None else None)
            if op[i] == STORE and c["addr"][i] is not None:
                memory[c["addr"][i]] = i
            if c["dst"][i] is not None:
                rename[c["dst"][i]] = i
        fetched_at, started, finished, retired = [None] * n, [None] * n, [None] * n, 0
        next_fetch, fetch_free, next_dispatch = 0, 0, 0
        pool: list[int] = []
        dispatched_at = [None] * n
        busy: dict[str, list[int]] = {u: [0] * k for u, k in m.units.items()}
        commits = [0] * n
        fetched = [0, -1]
        memory_open: list[int] = []
        tick = 0
        while retired < n:
            # commit
            room = m.cbw or n
            while retired < n and room and finished[retired] is not None and finished[retired] <= tick:
                commits[retired] = tick
                retired += 1
                room -= 1
            memory_open = [i for i in memory_open if i >= retired or (commits[i] > tick)]
            # fetch
            room = m.fbw or n
            while next_fetch < n and room:
                i = next_fetch
                if i and c["miss"][i - 1] and not m.ideal_branch:
                    if started[i - 1] is None:
                        break
                    earliest = started[i - 1] + time[i - 1] + m.penalty
                else:
                    earliest = fetch_free
                ready = (earliest if i else 0) + (0 if m.ideal_fetch or not i else c["imem"][i] or 0)
                if ready > tick:
                    break
                fetched_at[i] = tick
                fetch_free = tick
                next_fetch += 1
                room -= 1
            # dispatch
            if in_order:
                while next_dispatch < next_fetch:
                    dispatched_at[next_dispatch] = fetched_at[next_dispatch]
                    pool.append(next_dispatch)
                    next_dispatch += 1
            else:
                room = m.dbw or n
                while next_dispatch < next_fetch and room:
                    i = next_dispatch
                    if fetched_at[i] + m.decode > tick or i - retired >= (m.rob or n + 1):
                        break
                    if op[i] == LOAD and m.lq and sum(op[j] == LOAD for j in memory_open) >= m.lq:
                        break
                    if op[i] == STORE and m.sq and sum(op[j] == STORE for j in memory_open) >= m.sq:
                        break
                    if op[i] in (LOAD, STORE):
                        memory_open.append(i)
                    dispatched_at[i] = tick
                    pool.append(i)
                    next_dispatch += 1
                    room -= 1
            # issue
            room = m.ibw or n
            left = []
            stalled = False
            for at, i in enumerate(pool):
                if not room or stalled:
                    left.extend(pool[at:])
                    break
                go = dispatched_at[i] + (m.decode if in_order else 1) <= tick
                go = go and all(started[w] is not None and started[w] + time[w] <= tick for w in wanted[i])
                s = from_store[i]
                go = go and (s is None or (started[s] is not None and started[s] + m.forward <= tick))
                u = unit[op[i]]
                if go and u is not None:
                    go = any(t <= tick for t in busy[u])
                if go and in_order and m.lsq and op[i] in (LOAD, STORE):
                    go = len(memory_open) < m.lsq
                if not go:
                    left.append(i)
                    stalled = in_order
                    continue
                if u is not None:
                    k = min(range(len(busy[u])), key=lambda j: busy[u][j])
                    busy[u][k] = tick + (time[i] if blocking[op[i]] else 1)
                if in_order and op[i] in (LOAD, STORE):
                    memory_open.append(i)
                started[i], finished[i] = tick, tick + time[i]
                room -= 1
            pool = left
            tick += 1
        return commits[-1]


def tick_simulation(trace: DataFrame, m: Machine, limit: int = 2000) -> DataFrame:
    """(program_id, lane, cycles, instrs) of the first ``limit`` instructions of each program."""

    def fn(program, cols):
        sim = TickSimulator(m, cols, limit)
        yield program, 0, sim.run(), sim.n

    return _grouped(trace.where(F.col("seq") < limit), fn, "program_id int, lane int, cycles bigint, instrs bigint")


def counts(trace: DataFrame) -> DataFrame:
    """Instruction-set simulation: counts by class, no time."""
    return trace.groupBy("program_id", "op_class").agg(F.count(F.lit(1)).alias("n"))


def mechanistic(trace: DataFrame, m: Machine) -> DataFrame:
    """Penalty model: instructions over width plus events times their penalties (one aggregation)."""
    miss = F.col("mispredicted").cast("bigint") * (m.decode + m.penalty + m.latency["BRANCH"])
    data = F.when(F.col("op_class") == "LOAD", F.greatest(F.col("dmem_cycles") - 2, F.lit(0))).otherwise(0)
    d = trace.groupBy("program_id").agg(
        F.count(F.lit(1)).alias("instrs"), F.sum(miss + data + F.col("imem_cycles")).cast("bigint").alias("_events")
    )
    width = m.ibw or 1
    cycles = F.expr(f"(instrs + {width} - 1) div {width}") + F.col("_events")
    return d.select("program_id", cycles.cast("bigint").alias("cycles"), "instrs")


def cycle_stack(trace: DataFrame, m: Machine) -> DataFrame:
    """(program_id, term, cycles): each commit gap is charged to the term of the edge that binds the commit."""

    def fn(program, cols):
        p = kernels.Program(cols, m)
        kernels.run(p)
        total: dict[str, int] = {}
        for i in range(p.n):
            gap = p.C[i] - (p.C[i - 1] if i else 0)
            if not gap:
                continue
            _, _, _, _, terms = max(kernels.parents(p, i, "C"), key=lambda e: (e[3] + sum(c for _, c in e[4]), e[0], e[2]))
            term = terms[0][0] if terms else "order"
            total[term] = total.get(term, 0) + gap
        for term in sorted(total):
            yield program, term, total[term]

    return _grouped(trace, fn, "program_id int, term string, cycles bigint")
