"""Longest paths of the explicit graph without storing it: an instruction's edges are made when it comes, and its lengths follow at once.

The rules are those of ``graph`` (a test compares the edges), over a program's rows in order of seq. Edges name the
instructions they come from as objects, so an instruction is kept just as long as a rule can still name it (its
register is not yet overwritten, its place in a queue not yet taken), and a task's memory does not grow with the program but for
the last stores to each address. Nothing but the trace's narrow columns is shuffled.
"""

from __future__ import annotations

import heapq
from collections import deque
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql.functions import row_number

from critgraph.configs import Machine
from critgraph.operators.runs import arrow_types, kernel_columns, pieces
from critgraph.runtime import ship
from critgraph.schemas import CODE, LOAD, STORE

STAGES = F, D, E, C = range(4)
NAMES = "FDEC"
#: (source, source stage, stage, kind, weight): an edge into the instruction whose list it is in.
Edge = tuple["Instr", int, int, str, int]
COLUMNS = ("op", "seq", "src1", "src2", "dst", "addr", "imem", "dmem", "miss")
MULTIPLY_ADD = {CODE["INT_MUL"]: CODE["INT_ALU"], CODE["FP_MUL"]: CODE["FP_ALU"]}


class Instr:
    """An instruction and the lengths of its vertices, four a scenario; a fused pair shares one list of lengths."""

    __slots__ = ("seq", "op", "x", "miss", "at", "fused")

    def __init__(self, seq: int, op: int, x: int, miss: bool, scenarios: int):
        self.seq, self.op, self.x, self.miss, self.fused = seq, op, x, miss, False
        self.at = [0] * (4 * scenarios)


class Rules:
    """The edges into each next instruction of a program, by the stage they lead to; all rules but those along an issue order."""

    def __init__(self, m: Machine, scenarios: int = 1):
        if m.depth or m.iq or m.fu_policy != "lru":
            raise ValueError("unit depths, issue queues and earliest-free units have no rule here")
        self.m, self.scenarios, self.ordered = m, scenarios, m.core == "inorder"
        self.latency, self.blocking, self.unit = m.tables()
        self.writer: dict[int, Instr] = {}
        self.store: dict[int, Instr] = {}
        self.before: Instr | None = None
        line = lambda k: deque(maxlen=k) if k else None
        self.fetched, self.dispatched, self.issued, self.committed, self.rob = line(m.fbw), line(not self.ordered and m.dbw), line(self.ordered and m.ibw), line(m.cbw), line(not self.ordered and m.rob)
        self.queues = [(line(size), ops) for size, ops in ((m.lsq, (LOAD, STORE)), (m.lq, (LOAD,)), (m.sq, (STORE,))) if size]
        self.users = {u: deque(maxlen=k) for u, k in m.units.items()}

    def add(self, op, seq, src1, src2, dst, addr, imem, dmem, miss) -> tuple[Instr, list[Edge]]:
        m, before = self.m, self.before
        x = self.latency[op]
        if op == LOAD:
            x += m.memory if m.memory is not None else dmem or 0
        i = Instr(seq, op, x, bool(miss) and not m.ideal_branch, self.scenarios)
        out: list[Edge] = []
        put = out.append
        if before is not None:
            f = 0 if m.ideal_fetch else imem or 0
            put((before, E, F, "control", before.x + m.penalty + f) if before.miss else (before, F, F, "fetch", f))
        self._width(self.fetched, i, F, "fetch_bw", put)
        to = E if self.ordered else D
        put((i, F, to, "pipe", m.decode))
        if op == LOAD or op == STORE:
            for line, ops in self.queues:
                if op in ops:
                    if len(line) == line.maxlen:
                        put((line[0], C, to, "queue", 0))
                    line.append(i)
        if self.ordered:
            if self.issued is not None:
                if before is not None:
                    put((before, E, E, "issue", 0))
                self._width(self.issued, i, E, "issue_bw", put)
            if (u := self.unit[op]) is not None:
                users = self.users[u]
                if len(users) == users.maxlen:
                    put((users[0], E, E, "fu_occ", self.occupancy(users[0])))
                users.append(i)
        else:
            if before is not None:
                put((before, D, D, "dispatch", 0))
            self._width(self.dispatched, i, D, "dispatch_bw", put)
            if self.rob is not None:
                if len(self.rob) == self.rob.maxlen:
                    put((self.rob[0], C, D, "rob", 0))
                self.rob.append(i)
            put((i, D, E, "pipe", 1))
        if src1 is not None and (w := self.writer.get(src1)) is not None:
            put((w, E, E, "data_reg", w.x))
        if src2 is not None and src2 != src1 and (v := self.writer.get(src2)) is not None:
            put((v, E, E, "data_reg", v.x))
        if addr is not None:
            if op == LOAD and (w := self.store.get(addr)) is not None:
                put((w, E, E, "data_mem", m.forward))
            elif op == STORE:
                self.store[addr] = i
        if dst is not None:
            self.writer[dst] = i
        put((i, E, C, "pipe", x))
        if before is not None:
            put((before, C, C, "commit", 0))
        self._width(self.committed, i, C, "commit_bw", put)
        self.before = i
        return i, out

    def occupancy(self, i: Instr) -> int:
        return i.x if self.blocking[i.op] else 1

    @staticmethod
    def _width(line: deque | None, i: Instr, stage: int, kind: str, put: Callable) -> None:
        if line is not None:
            if len(line) == line.maxlen:
                put((line[0], stage, stage, kind, 1))
            line.append(i)


def relax(i: Instr, edges: list[Edge], at: int = 0) -> None:
    """Lengths of an instruction's vertices; its edges come by the stage they lead to."""
    own = i.at
    for src, s, t, _, w in edges:
        w += src.at[at + s]
        if w > own[at + t]:
            own[at + t] = w


class Longest:
    """Cycles of an in-order program in each scenario: the graph as it is, or with its register edges edited.

    An edit takes a register edge's source and weight and gives its new weight, or None where the edge goes.
    """

    def __init__(self, m: Machine, edits: tuple[Callable[[Instr, int], int | None] | None, ...] = (None,)):
        if m.core != "inorder":
            raise ValueError("an issue order is needed: TwoPass")
        self.rules, self.edits = Rules(m, len(edits)), edits
        self.most = [0] * len(edits)

    def feed(self, cols: dict[str, list]) -> None:
        for row in zip(*(cols[k] for k in COLUMNS)):
            self.take(*self.rules.add(*row))

    def take(self, i: Instr, edges: list[Edge]) -> None:
        for k, edit in enumerate(self.edits):
            mine = edges
            if edit is not None:
                mine = []
                for e in edges:
                    if e[3] == "data_reg":
                        if (w := edit(e[0], e[4])) is None:
                            continue
                        e = (*e[:4], w)
                    mine.append(e)
            relax(i, mine, 4 * k)
            if i.at[4 * k + C] > self.most[k]:
                self.most[k] = i.at[4 * k + C]

    def cycles(self) -> list[int]:
        return self.most


class Fused(Longest):
    """Cycles with every fusible pair (an adjacent multiply and add, the product read by no other) made one instruction of ``cycles``.

    Whether a pair is fusible is known when its register is written again, so rows wait for that.
    """

    def __init__(self, m: Machine, cycles: int):
        super().__init__(m)
        self.fused = cycles
        self.rows: deque = deque()  # entries: [row, undecided?, one instruction with the next?]
        self.products: dict[int, list] = {}  # undecided multiplies by register
        self.last: list | None = None

    def feed(self, cols: dict[str, list]) -> None:
        for row in zip(*(cols[k] for k in COLUMNS)):
            op, _, src1, src2, dst = row[:5]
            before = self.last
            if before is not None and before[1]:
                r = before[0][4]
                if op == MULTIPLY_ADD[before[0][0]] and r in (src1, src2):
                    before[2] = True
                else:
                    self._decide(r, False)
            for r in (src1, src2):
                if r in self.products and self.products[r] is not before:
                    self._decide(r, False)  # another reader
            if dst in self.products:
                self._decide(dst, self.products[dst][2])
            self.last = entry = [row, op in MULTIPLY_ADD and dst is not None, False]
            if entry[1]:
                self.products[dst] = entry
            self.rows.append(entry)
            self._leave()

    def _decide(self, r: int, fused: bool) -> None:
        entry = self.products.pop(r)
        entry[1], entry[2] = False, fused

    def _leave(self) -> None:
        """The rows before the first undecided one go on; a pair's second row is there when it is decided."""
        while self.rows and not self.rows[0][1]:
            row, _, fused = self.rows.popleft()
            i, edges = self.rules.add(*row)
            if fused:
                j, more = self.rules.add(*self.rows.popleft()[0])
                j.at, i.fused, j.fused = i.at, True, True
                edges = sorted(edges + more, key=lambda e: e[2])
            kept = [e for e in edges if e[0].at is not i.at or e[1] != e[2]]
            self.take(i, [(*e[:4], self.fused) if e[0].fused and e[1] == E and (e[2] != E or e[3] == "data_reg") else e for e in kept])

    def cycles(self) -> list[int]:
        for r in list(self.products):
            self._decide(r, self.products[r][2])
        self._leave()
        return self.most


class TwoPass:
    """Cycles of an out-of-order program: base lengths, issue order, lengths with the resource edges along it.

    No instruction still to come can execute before the last one's dispatch, so what executes up to then is in
    its place in the issue order (by base length, then seq) and goes on to the second pass.
    """

    def __init__(self, m: Machine):
        if m.core != "ooo":
            raise ValueError("an in-order program needs no issue order: Longest")
        self.rules, self.m = Rules(m, 2), m
        self.ready: list[tuple] = []  # heap of base length, place in the program, instruction
        self.n = 0
        self.front, self.back = deque(), deque()  # to be dispatched, to be committed: instruction and edges
        self.issued = deque(maxlen=m.ibw or 1)
        self.users = {u: deque(maxlen=k) for u, k in m.units.items()}
        self.edges: dict[int, list[Edge]] = {}  # into E, of instructions not yet executed
        self.most = [0]

    def feed(self, cols: dict[str, list]) -> None:
        ready = self.ready
        for row in zip(*(cols[k] for k in COLUMNS)):
            i, edges = self.rules.add(*row)
            relax(i, edges)
            i.at[4:] = (-1, -1, -1, -1)
            self.front.append((self.n, i, [e for e in edges if e[2] < E]))
            self.back.append((i, [e for e in edges if e[2] == C]))
            self.edges[self.n] = [e for e in edges if e[2] == E]
            heapq.heappush(ready, (i.at[E], self.n, i))
            self.n += 1
            while ready and ready[0][0] <= i.at[D]:
                self._execute(*heapq.heappop(ready)[1:])

    def _settle(self, i: Instr, stage: int, edges: list[Edge]) -> None:
        t = 0
        for src, s, to, _, w in edges:
            if to == stage:
                at = src.at[4 + s]
                if at < 0:
                    raise RuntimeError(f"the issue order runs against the base graph at {i.seq}")
                if at + w > t:
                    t = at + w
        i.at[4 + stage] = t

    def _execute(self, n: int, i: Instr) -> None:
        while i.at[4 + D] < 0:
            _, j, edges = self.front.popleft()
            self._settle(j, F, edges)
            self._settle(j, D, edges)
        edges = self.edges.pop(n)
        if self.m.ibw:
            if len(self.issued) == self.issued.maxlen:
                edges.append((self.issued[0], E, E, "issue_bw", 1))
            self.issued.append(i)
        if (u := self.rules.unit[i.op]) is not None:
            users = self.users[u]
            if len(users) == users.maxlen:
                edges.append((users[0], E, E, "fu_occ", self.rules.occupancy(users[0])))
            users.append(i)
        self._settle(i, E, edges)
        while self.back and self.back[0][0].at[4 + E] >= 0:
            j, edges = self.back.popleft()
            self._settle(j, C, edges)
            self.most[0] = max(self.most[0], j.at[4 + C])

    def cycles(self) -> list[int]:
        while self.ready:
            self._execute(*heapq.heappop(self.ready)[1:])
        return self.most


def in_order(columns: DataFrame) -> DataFrame:
    """Rows dealt by program and sorted by seq: a window over them asks for both, and where the trace's own windows have
    dealt and sorted them so, Spark does neither again (``repartition`` would)."""
    return columns.withColumn("_n", row_number().over(Window.partitionBy("program_id").orderBy("seq"))).where("_n > 0").drop("_n")


def cycles(trace: DataFrame, sweep: Callable[[], Longest | TwoPass]) -> DataFrame:
    """(program_id, lane, cycles) of the explicit graph, a lane a scenario of the sweep: one pass over the sorted trace."""
    ship(trace.sparkSession)
    schema = "program_id int, lane int, cycles bigint"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, now, out = None, None, []
        for program, cols, first in pieces(batches):
            if first:
                if now is not None:
                    out += [(at, k, c) for k, c in enumerate(now.cycles())]
                at, now = program, sweep()
            now.feed(cols)
        if now is not None:
            out += [(at, k, c) for k, c in enumerate(now.cycles())]
        yield pa.record_batch([pa.array(c, t) for c, t in zip(list(zip(*out)) or [[]] * 3, arrow_types(schema))], names=["program_id", "lane", "cycles"])

    return in_order(kernel_columns(trace)).mapInArrow(run, schema)
