"""Sequential kernels over one program: Python workers run them, one program (or chunk) at a time.

``Program`` holds a program's columns and what follows from the trace alone (last writers,
last stores, queue predecessors). ``inorder`` sweeps it in program order; ``schedule`` finds
an out-of-order issue order and the lengths that go with it; ``parents`` lists the edges that
end in a vertex with their lengths, so that paths, slack and the explicit graph all
share one statement of the rules. ``ScalarSweep`` is ``inorder`` fed in pieces, with a state of
constant size in place of lists of lengths; ``LaneSweep`` is its vector form: every value is an array over lanes.
"""

from __future__ import annotations

import heapq
from collections import deque
from itertools import chain, islice, repeat

import numpy as np

from critgraph.configs import Machine, predicted
from critgraph.schemas import BRANCH, LOAD, OPS, REGISTERS, STORE, TERM_OF_OP

NEG = -(10**15)
#: Instructions of a vector sweep's matrices, which a processor's cache should hold.
ROWS = 2500
TERM = [TERM_OF_OP[o] for o in OPS]
KINDS = ("pipe", "fetch", "control", "fetch_bw", "dispatch", "dispatch_bw", "rob", "queue", "iq", "data_reg", "data_mem", "issue", "issue_bw", "fu_occ", "fu_depth", "commit", "commit_bw")


class Program:
    """A program in order of seq, with machine-dependent latencies for one configuration."""

    def __init__(self, cols: dict[str, list], m: Machine, dropped: set[int] | None = None):
        self.m, self.n = m, len(cols["op"])
        self.seq = cols["seq"]
        op = self.op = cols["op"]
        lat, block, unit = m.tables()
        dm = cols["dmem"]
        mem = m.memory
        self.f = [0] * self.n if m.ideal_fetch else [x or 0 for x in cols["imem"]]
        self.x = [lat[o] + ((mem if mem is not None else d or 0) if o == LOAD else 0) for o, d in zip(op, dm)]
        self.occ = [x if block[o] else 1 for o, x in zip(op, self.x)]
        self.unit = [unit[o] for o in op]
        self.miss = [False] * self.n if m.ideal_branch else [bool(v) for v in cols["miss"]]
        self.writers(cols, m, dropped)

    def writers(self, cols, m: Machine, dropped: set[int] | None) -> None:
        """Positions of the last writer of each source and of the last store to a load's address; queue predecessors."""
        last, store = [-1] * REGISTERS, {}
        w1, w2, st = [-1] * self.n, [-1] * self.n, [-1] * self.n
        q = [-1] * self.n
        loads, stores, memory = deque(maxlen=m.lq or 1), deque(maxlen=m.sq or 1), deque(maxlen=m.lsq or 1)
        pc = cols.get("pc") or [0] * self.n
        self.cut = cut = [False] * self.n
        for i, (o, a, b, d, addr) in enumerate(zip(self.op, cols["src1"], cols["src2"], cols["dst"], cols["addr"])):
            if a is not None:
                w1[i] = last[a]
            if b is not None:
                w2[i] = last[b]
            if o == LOAD:
                if m.predicted_permille and predicted(self.seq[i], pc[i] or 0, m.predicted_permille):
                    cut[i] = True
                if addr is not None:
                    st[i] = store.get(addr, -1)
            if dropped and i in dropped:
                cut[i] = True
            if o == LOAD or o == STORE:
                for limit, line, mine in ((m.lsq, memory, True), (m.lq, loads, o == LOAD), (m.sq, stores, o == STORE)):
                    if limit and mine:
                        if len(line) == limit:
                            q[i] = line[0]
                        line.append(i)
                if o == STORE and addr is not None:
                    store[addr] = i
            if d is not None:
                last[d] = i
        self.w1, self.w2, self.st, self.q = w1, w2, st, q

    def reg(self, w: int) -> int:
        """Lag of the register edge from writer ``w``: none (NEG) if its value is rightly predicted."""
        if self.cut[w]:
            return NEG if self.m.predict_penalty is None else self.x[w] + self.m.predict_penalty
        return self.x[w]


def inorder(p: Program) -> tuple[list[int], list[int], list[int]]:
    """F, E and C lengths of an in-order core."""
    m, n = p.m, p.n
    F, E, C = [0] * n, [0] * n, [0] * n
    f, x, occ, unit, miss, w1, w2, st, q, cut = p.f, p.x, p.occ, p.unit, p.miss, p.w1, p.w2, p.st, p.q, p.cut
    fbw, ibw, cbw, d, pen, fw = m.fbw or n + 1, m.ibw or n + 1, m.cbw or n + 1, m.decode, m.penalty, m.forward
    rings = {u: deque(maxlen=k) for u, k in m.units.items()}
    p.fu = fu = [-1] * n
    depth = {u: deque(maxlen=k) for u, k in m.depth.items()}
    p.dep = dep = [-1] * n
    ordered = m.ibw is not None
    earliest = m.fu_policy == "earliest"
    for i in range(n):
        if i:
            t = (E[i - 1] + x[i - 1] + pen if miss[i - 1] else F[i - 1]) + f[i]
            if i >= fbw and F[i - fbw] >= t:
                t = F[i - fbw] + 1
            F[i] = t
        else:
            t = 0
        t += d
        if i and ordered:
            if E[i - 1] > t:
                t = E[i - 1]
            if i >= ibw and E[i - ibw] >= t:
                t = E[i - ibw] + 1
        for w in (w1[i], w2[i]):
            if w >= 0:
                v = E[w] + (p.reg(w) if cut[w] else x[w])
                if v > t:
                    t = v
        w = st[i]
        if w >= 0 and E[w] + fw > t:
            t = E[w] + fw
        u = unit[i]
        if u is not None:
            r = rings[u]
            if len(r) == r.maxlen:
                if earliest:
                    first_free(r, E, occ)
                fu[i] = w = r[0]
                if E[w] + occ[w] > t:
                    t = E[w] + occ[w]
            r.append(i)
            if u in depth:
                r = depth[u]
                if len(r) == r.maxlen:
                    dep[i] = w = r[0]
                    t = max(t, E[w] + x[w])
                r.append(i)
        w = q[i]
        if w >= 0 and C[w] > t:
            t = C[w]
        E[i] = t
        t += x[i]
        if i:
            if C[i - 1] > t:
                t = C[i - 1]
            if i >= cbw and C[i - cbw] >= t:
                t = C[i - cbw] + 1
        C[i] = t
    p.F, p.E, p.C, p.D, p.ib = F, E, C, None, None
    return F, E, C


def first_free(ring: deque, E: list, occ: list) -> None:
    """Bring the user whose unit is free first to the ring's old end (among equals, the one used longest ago)."""
    k = min(range(len(ring)), key=lambda j: E[ring[j]] + occ[ring[j]])
    w = ring[k]
    del ring[k]
    ring.appendleft(w)


class _Front:
    """Fetch, dispatch and commit of an out-of-order core, advanced as execution times become known."""

    def __init__(self, p: Program):
        n = p.n
        self.p, self.E = p, [None] * n
        self.F, self.D, self.C = [0] * n, [0] * n, [0] * n
        self.front = self.done = 0  # next to fetch; next to commit

    def commit(self) -> None:
        p, C, E, i = self.p, self.C, self.E, self.done
        cbw = p.m.cbw or p.n + 1
        while i < p.n and E[i] is not None:
            t = E[i] + p.x[i]
            if i:
                t = max(t, C[i - 1])
                if i >= cbw:
                    t = max(t, C[i - cbw] + 1)
            C[i] = t
            i += 1
        self.done = i

    def step(self) -> bool:
        """Fetch and dispatch one more instruction, if all it waits for is known."""
        p, i, m = self.p, self.front, self.p.m
        if i >= p.n:
            return False
        F, D, E, C = self.F, self.D, self.E, self.C
        t = 0
        if i:
            if p.miss[i - 1]:
                if E[i - 1] is None:
                    return False
                t = E[i - 1] + p.x[i - 1] + m.penalty + p.f[i]
            else:
                t = F[i - 1] + p.f[i]
            if m.fbw and i >= m.fbw:
                t = max(t, F[i - m.fbw] + 1)
        d = t + m.decode
        if i:
            d = max(d, D[i - 1])
            if m.dbw and i >= m.dbw:
                d = max(d, D[i - m.dbw] + 1)
        for w in (i - m.rob if m.rob else -1, p.q[i]):
            if w >= 0:
                if w >= self.done:
                    self.commit()
                    if w >= self.done:
                        return False
                d = max(d, C[w])
        if m.iq and i >= m.iq:
            if E[i - m.iq] is None:
                return False
            d = max(d, E[i - m.iq])
        F[i], D[i] = t, d
        self.front = i + 1
        return True


class _Resources:
    """The scoreboard: issue slots and units, in the order instructions are scheduled."""

    def __init__(self, p: Program):
        self.p = p
        self.slots = deque(maxlen=p.m.ibw or 1)
        self.rings = {u: deque(maxlen=k) for u, k in p.m.units.items()}
        self.deep = {u: deque(maxlen=k) for u, k in p.m.depth.items()}
        p.ib, p.fu, p.dep = [-1] * p.n, [-1] * p.n, [-1] * p.n

    def take(self, i: int, t: int, E: list) -> int:
        """The time at which i, ready at t, may execute."""
        p = self.p
        if p.m.ibw:
            if len(self.slots) == p.m.ibw:
                p.ib[i] = w = self.slots[0]
                t = max(t, E[w] + 1)
            self.slots.append(i)
        u = p.unit[i]
        if u is not None:
            r = self.rings[u]
            if len(r) == r.maxlen:
                if p.m.fu_policy == "earliest":
                    first_free(r, E, p.occ)
                p.fu[i] = w = r[0]
                t = max(t, E[w] + p.occ[w])
            r.append(i)
            if u in self.deep:
                r = self.deep[u]
                if len(r) == r.maxlen:
                    p.dep[i] = w = r[0]
                    t = max(t, E[w] + p.x[w])
                r.append(i)
        return t


def _ready(p: Program, i: int, D: list, E: list) -> int:
    """Length of E without resource edges; a rightly predicted writer need not be scheduled."""
    t = D[i] + 1
    for w in (p.w1[i], p.w2[i]):
        if w >= 0 and (r := p.reg(w)) != NEG:
            t = max(t, E[w] + r)
    if p.st[i] >= 0:
        t = max(t, E[p.st[i]] + p.m.forward)
    return t


def base_lengths(p: Program) -> list[int]:
    """E lengths of the graph without resource edges (first pass)."""
    fr = _Front(p)
    for i in range(p.n):
        if not fr.step():
            raise RuntimeError("the base graph is not in program order")
        fr.E[i] = _ready(p, i, fr.D, fr.E)
        fr.commit()
    p.F, p.D, p.E, p.C = fr.F, fr.D, fr.E, fr.C
    p.ib, p.fu, p.dep = [-1] * p.n, [-1] * p.n, [-1] * p.n
    return fr.E


def ranked_sweep(p: Program, order: list[int]) -> list[int]:
    """Lengths with resource edges laid along ``order`` (all parents of a vertex come before it there)."""
    fr, res = _Front(p), _Resources(p)
    for i in order:
        while fr.front <= i:
            if not fr.step():
                raise RuntimeError(f"the order runs against the base graph at {i}")
        fr.E[i] = res.take(i, _ready(p, i, fr.D, fr.E), fr.E)
    fr.commit()
    p.F, p.D, p.E, p.C = fr.F, fr.D, fr.E, fr.C
    return fr.C


def two_pass(p: Program) -> list[int]:
    """The issue order of the basic algorithm: base lengths, then seq."""
    E = base_lengths(p)
    order = sorted(range(p.n), key=lambda i: (E[i], i))
    ranked_sweep(p, order)
    return order


def _active_lru(p: Program, window: int) -> list[int]:
    """``sliding_active`` of least-recently-used units without depth or issue queue, all its rules in one loop."""
    n, m = p.n, p.m
    f, x, occ, unit, miss, w1, w2, st, q = p.f, p.x, p.occ, p.unit, p.miss, p.w1, p.w2, p.st, p.q
    fbw, dbw, cbw, ibw, rob = m.fbw or n + 1, m.dbw or n + 1, m.cbw or n + 1, m.ibw, m.rob or n + 1
    dec, pen, fw = m.decode, m.penalty, m.forward
    lag = [p.reg(w) if c else v for w, (c, v) in enumerate(zip(p.cut, x))] if any(p.cut) else x
    E: list = [None] * n
    F, D, C = [0] * n, [0] * n, [0] * n
    p.ib, p.fu, p.dep = ib, fu, _ = [-1] * n, [-1] * n, [-1] * n
    slots: deque = deque(maxlen=ibw or 1)
    rings = {u: deque(maxlen=k) for u, k in m.units.items()}
    ring_of = [None if u is None else rings[u] for u in unit]
    waits: dict[int, list[int]] = {}
    left: dict[int, int] = {}
    heap: list[int] = []  # length and position in one number
    order: list[int] = []
    shift = n.bit_length()
    mask = (1 << shift) - 1
    push, pop = heapq.heappush, heapq.heappop
    front = done = oldest = 0

    def commit(i: int) -> int:
        while i < n and (t := E[i]) is not None:
            t += x[i]
            if i:
                if C[i - 1] > t:
                    t = C[i - 1]
                if i >= cbw and C[i - cbw] >= t:
                    t = C[i - cbw] + 1
            C[i] = t
            i += 1
        return i

    def ready(i: int) -> int:
        t = D[i] + 1
        w = w1[i]
        if w >= 0 and (r := lag[w]) != NEG and E[w] + r > t:
            t = E[w] + r
        w = w2[i]
        if w >= 0 and (r := lag[w]) != NEG and E[w] + r > t:
            t = E[w] + r
        w = st[i]
        if w >= 0 and E[w] + fw > t:
            t = E[w] + fw
        return t << shift | i

    while len(order) < n:
        top = min(n, oldest + window)
        while front < top:
            i = front
            t = 0
            if i:
                if miss[i - 1]:
                    if E[i - 1] is None:
                        break
                    t = E[i - 1] + x[i - 1] + pen + f[i]
                else:
                    t = F[i - 1] + f[i]
                if i >= fbw and F[i - fbw] >= t:
                    t = F[i - fbw] + 1
                d = t + dec
                if D[i - 1] > d:
                    d = D[i - 1]
                if i >= dbw and D[i - dbw] >= d:
                    d = D[i - dbw] + 1
            else:
                d = dec
            w = max(i - rob, q[i])
            if w >= 0:
                if w >= done:
                    done = commit(done)
                    if w >= done:
                        break
                if C[w] > d:  # commits are in order: the later one binds
                    d = C[w]
            F[i], D[i] = t, d
            front = i + 1
            k = 0
            a, b, s = w1[i], w2[i], st[i]
            if a >= 0 and E[a] is None and (lag[a] != NEG or a == s):
                waits.setdefault(a, []).append(i)
                k = 1
            if b >= 0 and b != a and E[b] is None and (lag[b] != NEG or b == s):
                waits.setdefault(b, []).append(i)
                k += 1
            if s >= 0 and s != a and s != b and E[s] is None:
                waits.setdefault(s, []).append(i)
                k += 1
            if k:
                left[i] = k
            else:
                push(heap, ready(i))
        if not heap:
            raise RuntimeError("nothing to schedule")
        t = pop(heap)
        i = t & mask
        t >>= shift
        if ibw:
            if len(slots) == ibw:
                ib[i] = w = slots[0]
                if E[w] >= t:
                    t = E[w] + 1
            slots.append(i)
        r = ring_of[i]
        if r is not None:
            if len(r) == r.maxlen:
                fu[i] = w = r[0]
                if E[w] + occ[w] > t:
                    t = E[w] + occ[w]
            r.append(i)
        E[i] = t
        order.append(i)
        if i in waits:
            for j in waits.pop(i):
                if left[j] == 1:
                    del left[j]
                    push(heap, ready(j))
                else:
                    left[j] -= 1
        while oldest < n and E[oldest] is not None:
            oldest += 1
    commit(done)
    p.F, p.D, p.E, p.C = F, D, E, C
    return order


def sliding_active(p: Program, window: int) -> list[int]:
    """Sliding window with active re-prioritisation.

    Every lag into an E vertex is positive, so the least entry of an actively updated list
    never has an unscheduled parent. It is therefore enough to enter an instruction when its
    last parent is scheduled, with its final length; no entry is ever moved.
    """
    if p.m.fu_policy == "lru" and not p.m.depth and not p.m.iq:
        return _active_lru(p, window)
    n = p.n
    fr, res = _Front(p), _Resources(p)
    E, D = fr.E, fr.D
    waits: dict[int, list[int]] = {}
    left = [0] * n
    heap: list[tuple[int, int]] = []
    order: list[int] = []
    oldest = 0
    while len(order) < n:
        while fr.front < min(n, oldest + window) and fr.step():
            i = fr.front - 1
            k = 0
            for w in {p.w1[i], p.w2[i], p.st[i]}:
                if w >= 0 and E[w] is None and not (w != p.st[i] and p.reg(w) == NEG):
                    waits.setdefault(w, []).append(i)
                    k += 1
            left[i] = k
            if not k:
                heapq.heappush(heap, (_ready(p, i, D, E), i))
        if not heap:
            raise RuntimeError("nothing to schedule")
        t, i = heapq.heappop(heap)
        E[i] = res.take(i, t, E)
        order.append(i)
        for j in waits.pop(i, ()):
            left[j] -= 1
            if not left[j]:
                heapq.heappush(heap, (_ready(p, j, D, E), j))
        while oldest < n and E[oldest] is not None:
            oldest += 1
    fr.commit()
    p.F, p.D, p.E, p.C = fr.F, fr.D, fr.E, fr.C
    return order


class _Estimates:
    """F, D, E, C lengths of a window's instructions, from what is known or so far estimated of their parents."""

    def __init__(self, p: Program):
        self.p, n = p, p.n
        self.F, self.D, self.E, self.C = [0] * n, [0] * n, [0] * n, [0] * n
        self.res = _Resources(p)

    def front(self, i: int) -> tuple[int, int]:
        p, F, D, E, C = self.p, self.F, self.D, self.E, self.C
        m = p.m
        if not i:
            t, d = 0, m.decode
        else:
            t = (E[i - 1] + p.x[i - 1] + m.penalty if p.miss[i - 1] else F[i - 1]) + p.f[i]
            if m.fbw and i >= m.fbw and F[i - m.fbw] >= t:
                t = F[i - m.fbw] + 1
            d = max(t + m.decode, D[i - 1])
            if m.dbw and i >= m.dbw and D[i - m.dbw] >= d:
                d = D[i - m.dbw] + 1
        if m.rob and i >= m.rob and C[i - m.rob] > d:
            d = C[i - m.rob]
        if p.q[i] >= 0 and C[p.q[i]] > d:
            d = C[p.q[i]]
        if m.iq and i >= m.iq and E[i - m.iq] > d:
            d = E[i - m.iq]
        return t, d

    def committed(self, i: int) -> int:
        C, cbw = self.C, self.p.m.cbw
        c = self.E[i] + self.p.x[i]
        if i and C[i - 1] > c:
            c = C[i - 1]
        if cbw and i >= cbw and C[i - cbw] >= c:
            c = C[i - cbw] + 1
        return c

    def enter(self, i: int) -> int:
        self.F[i], self.D[i] = self.front(i)
        self.E[i] = _ready(self.p, i, self.D, self.E)
        self.C[i] = self.committed(i)
        return self.E[i]

    def keep(self) -> None:
        p = self.p
        p.F, p.D, p.E, p.C = self.F, self.D, self.E, self.C


def sliding_updated(p: Program, window: int) -> list[int]:
    """Sliding window whose list is updated: a length that scheduling raises is passed on to all descendants in the window.

    All instructions of the window are listed by the lengths known so far; p.moves counts the list entries that an
    update moved, p.live the most vertices held at once. ``sliding_active`` reaches the same order without moving entries.
    """
    n, m, s = p.n, p.m, _Estimates(p)
    F, D, E, C = s.F, s.D, s.E, s.C
    readers: list[list[int]] = [[] for _ in range(n)]  # entered instructions that take i's value, or i's place in a queue
    look = max(m.rob or 1, m.cbw or 1, m.dbw or 1, m.fbw or 1, m.iq or 1)
    done = [False] * n
    heap, order = [], []
    oldest = front = 0
    p.moves = p.live = 0

    def pass_on(i: int) -> None:
        """Recompute what i's new length reaches, in program order."""
        again: list[int] = []
        seen: set[int] = set()

        def reach(*them: int) -> None:
            for j in them:
                if j < front and j not in seen:
                    seen.add(j)
                    heapq.heappush(again, j)

        def spread(j: int, fd: bool, e: bool, c: bool) -> None:
            if fd:
                reach(j + 1, *(j + k for k in (m.fbw, m.dbw) if k))
            if e:
                reach(*(k for k in readers[j]), *((j + 1,) if p.miss[j] else ()), *((j + m.iq,) if m.iq else ()))
            if c:
                reach(j + 1, *(j + k for k in (m.cbw, m.rob) if k), *(k for k in readers[j]))

        c, C[i] = C[i], s.committed(i)
        spread(i, False, True, C[i] != c)
        while again:
            j = heapq.heappop(again)
            seen.discard(j)
            f, d = s.front(j)
            fd = f != F[j] or d != D[j]
            F[j], D[j] = f, d
            e = E[j]
            if not done[j]:
                E[j] = _ready(p, j, D, E)
                if E[j] != e:
                    p.moves += 1
                    heapq.heappush(heap, (E[j], j))
            c, C[j] = C[j], s.committed(j)
            spread(j, fd, E[j] != e, C[j] != c)

    while len(order) < n:
        while front < min(n, oldest + window):
            i = front
            for w in {p.w1[i], p.w2[i], p.st[i], p.q[i]}:
                if w >= 0:
                    readers[w].append(i)
            heapq.heappush(heap, (s.enter(i), i))
            front += 1
        p.live = max(p.live, 4 * (front - max(0, oldest - look)))
        t, i = heapq.heappop(heap)
        if done[i] or t != E[i]:  # an update has moved it
            continue
        done[i] = True
        order.append(i)
        E[i] = s.res.take(i, t, E)
        if E[i] != t:
            pass_on(i)
        while oldest < n and done[oldest]:
            readers[oldest] = []
            oldest += 1
    s.keep()
    return order


def sliding_fixed(p: Program, window: int) -> list[int]:
    """Sliding window without updates: an entry keeps its place, and only its own execution is renewed when it is taken.

    What a parent's delay does to instructions that are listed already is seen as far as the parent was taken before
    them; fetch and dispatch keep the lengths of entering. One pass: the lengths are those at which entries were taken.
    """
    n, m = p.n, p.m
    F, D, E, C = [0] * n, [0] * n, [0] * n, [0] * n
    f, x, miss, q, w1, w2, st, cut = p.f, p.x, p.miss, p.q, p.w1, p.w2, p.st, p.cut
    fbw, dbw, cbw, rob, iq = m.fbw or n + 1, m.dbw or n + 1, m.cbw or n + 1, m.rob or n + 1, m.iq or n + 1
    decode, pen, fw = m.decode, m.penalty, m.forward
    take = _Resources(p).take
    push, pop = heapq.heappush, heapq.heappop
    heap, order = [], []
    gone = [False] * n
    oldest = front = 0
    while len(order) < n:
        while front < n and front < oldest + window:
            i = front
            if i:
                t = (E[i - 1] + x[i - 1] + pen if miss[i - 1] else F[i - 1]) + f[i]
                if i >= fbw and F[i - fbw] >= t:
                    t = F[i - fbw] + 1
                d = t + decode
                if D[i - 1] > d:
                    d = D[i - 1]
                if i >= dbw and D[i - dbw] >= d:
                    d = D[i - dbw] + 1
                if i >= rob and C[i - rob] > d:
                    d = C[i - rob]
                if q[i] >= 0 and C[q[i]] > d:
                    d = C[q[i]]
                if i >= iq and E[i - iq] > d:
                    d = E[i - iq]
            else:
                t, d = 0, decode
            F[i], D[i] = t, d
            e = d + 1
            for w in (w1[i], w2[i]):
                if w >= 0:
                    v = E[w] + (p.reg(w) if cut[w] else x[w])
                    if v > e:
                        e = v
            if st[i] >= 0 and E[st[i]] + fw > e:
                e = E[st[i]] + fw
            E[i] = e
            c = e + x[i]
            if i:
                if C[i - 1] > c:
                    c = C[i - 1]
                if i >= cbw and C[i - cbw] >= c:
                    c = C[i - cbw] + 1
            C[i] = c
            push(heap, (e, i))
            front += 1
        e, i = pop(heap)
        for w in (w1[i], w2[i]):
            if w >= 0:
                v = E[w] + (p.reg(w) if cut[w] else x[w])
                if v > e:
                    e = v
        if st[i] >= 0 and E[st[i]] + fw > e:
            e = E[st[i]] + fw
        E[i] = e = take(i, e, E)
        if e + x[i] > C[i]:
            C[i] = e + x[i]
        gone[i] = True
        order.append(i)
        while oldest < n and gone[oldest]:
            c = E[oldest] + x[oldest]
            if oldest:
                if C[oldest - 1] > c:
                    c = C[oldest - 1]
                if oldest >= cbw and C[oldest - cbw] >= c:
                    c = C[oldest - cbw] + 1
            C[oldest] = c
            oldest += 1
    p.F, p.D, p.E, p.C = F, D, E, C
    return order


def run(p: Program, method: str = "") -> int:
    """Cycles of a program; p keeps the lengths. Methods of an out-of-order core: two_pass, active, updated, fixed, base."""
    if not p.n:
        return 0
    if p.m.core == "inorder":
        inorder(p)
    else:
        method = method or ("active" if p.m.active else "fixed")
        if method == "two_pass":
            two_pass(p)
        elif method == "base":
            base_lengths(p)
        else:
            {"active": sliding_active, "updated": sliding_updated, "fixed": sliding_fixed}[method](p, p.m.window)
    return p.C[-1]


def parents(p: Program, i: int, stage: str) -> list[tuple[int, str, str, int, list[tuple[str, int]]]]:
    """(source position, source stage, kind, source length, [(term, cycles)]) of each edge into a vertex of a run program."""
    m, out = p.m, []

    def add(w: int, s: str, kind: str, *terms: tuple[str, int]) -> None:
        at = {"F": p.F, "D": p.D, "E": p.E, "C": p.C}[s]
        out.append((w, s, kind, at[w], [*terms]))

    if stage == "F":
        if i:
            if p.miss[i - 1]:
                add(i - 1, "E", "control", (TERM[p.op[i - 1]], p.x[i - 1]), ("branch_penalty", m.penalty), ("fetch", p.f[i]))
            else:
                add(i - 1, "F", "fetch", ("fetch", p.f[i]))
            if m.fbw and i >= m.fbw:
                add(i - m.fbw, "F", "fetch_bw", ("fetch_bw", 1))
    elif stage == "D":
        add(i, "F", "pipe", ("decode", m.decode))
        if i:
            add(i - 1, "D", "dispatch")
            if m.dbw and i >= m.dbw:
                add(i - m.dbw, "D", "dispatch_bw", ("dispatch_bw", 1))
        if m.rob and i >= m.rob:
            add(i - m.rob, "C", "rob", ("rob_wait", 0))
        if p.q[i] >= 0:
            add(p.q[i], "C", "queue", ("queue_wait", 0))
        if m.iq and i >= m.iq:
            add(i - m.iq, "E", "iq", ("queue_wait", 0))
    elif stage == "E":
        if p.D is None:
            add(i, "F", "pipe", ("decode", m.decode))
            if i and m.ibw is not None:
                add(i - 1, "E", "issue")
                if i >= m.ibw:
                    add(i - m.ibw, "E", "issue_bw", ("issue_bw", 1))
            if p.q[i] >= 0:
                add(p.q[i], "C", "queue", ("queue_wait", 0))
        else:
            add(i, "D", "pipe", ("decode", 1))
            if p.ib[i] >= 0:
                add(p.ib[i], "E", "issue_bw", ("issue_bw", 1))
        for w in (p.w1[i], p.w2[i]):
            if w >= 0 and p.reg(w) != NEG:
                extra = p.reg(w) - p.x[w]
                add(w, "E", "data_reg", (TERM[p.op[w]], p.x[w]), *([("value_penalty", extra)] if extra else []))
        if p.st[i] >= 0:
            add(p.st[i], "E", "data_mem", ("forward", m.forward))
        if p.fu[i] >= 0:
            add(p.fu[i], "E", "fu_occ", ("fu_wait", p.occ[p.fu[i]]))
        if p.dep[i] >= 0:
            add(p.dep[i], "E", "fu_depth", (TERM[p.op[p.dep[i]]], p.x[p.dep[i]]))
    else:
        add(i, "E", "pipe", (TERM[p.op[i]], p.x[i]))
        if i:
            add(i - 1, "C", "commit")
            if m.cbw and i >= m.cbw:
                add(i - m.cbw, "C", "commit_bw", ("commit_bw", 1))
    return out


_ORD = {"F": 0, "D": 1, "E": 2, "C": 5}


def critical_path(p: Program) -> list[tuple[int, str, int, str, str, list[tuple[str, int]]]]:
    """Edges (source, stage, destination, stage, kind, terms) of the critical path, last first.

    Among equally binding parents the one of larger source position, then stage, then kind is taken.
    """
    out = []
    if not p.n:
        return out
    at = {"F": p.F, "D": p.D, "E": p.E, "C": p.C}
    i, s = p.n - 1, "C"
    while True:
        length = at[s][i]
        best = None
        for w, ws, kind, own, terms in parents(p, i, s):
            if own + sum(c for _, c in terms) == length:
                key = (w, _ORD[ws], kind)
                if best is None or key > best[0]:
                    best = (key, terms)
        if best is None:
            return out
        (w, o, kind), terms = best
        ws = "FDE??C"[o]
        out.append((w, ws, i, s, kind, terms))
        i, s = w, ws


class ScalarSweep:
    """In-order sweep of one configuration, fed in pieces; constant state.

    Each sweep finds an instruction's edges anew and takes the longest of them, as ``Program`` and ``inorder`` do.
    """

    def __init__(self, m: Machine):
        if m.core != "inorder" or m.lq or m.sq or m.depth:
            raise ValueError("a sweep is of an in-order core with one memory queue and no pipeline depths")
        self.m, self.n = m, 0
        self.f = self.e = self.c = self.y = 0  # the instruction before: what fetch follows, its issue, commit and end
        self.F, self.E, self.C = ([NEG] * (w or 0) for w in (m.fbw, m.ibw, m.cbw))
        self.reg, self.store = [NEG] * REGISTERS, {}
        self.q = deque([NEG] * (m.lsq or 1), maxlen=m.lsq or 1)
        self.lat, self.block, unit = m.tables()
        rings = {u: deque([NEG] * k, maxlen=k) for u, k in m.units.items() if not free_by_issue(m, u, self.block, unit)}
        self.rings = [rings.get(u) for u in unit]

    def feed(self, cols: dict[str, list]) -> None:
        """The next instructions of the program."""
        if not cols["op"]:
            return
        m = self.m
        imem = repeat(0) if m.ideal_fetch else cols["imem"] if self.n else chain([0], islice(cols["imem"], 1, None))
        miss = repeat(False) if m.ideal_branch else cols["miss"]
        # a list that grows while it is read lags behind by what it began with: the widths
        F, E, C = self.F, self.E, self.C
        behind = [line if line else repeat(NEG) for line in (F, E, C)]
        fetched, issued, committed = F.append, E.append, C.append
        f, e, c, y = self.f, self.e, self.c, self.y
        reg, store, q, rings, lat, block = self.reg, self.store, self.q, self.rings, self.lat, self.block
        dec, pen, fw, mem, lsq, ordered, earliest = m.decode, m.penalty, m.forward, m.memory, m.lsq, m.ibw is not None, m.fu_policy == "earliest"
        guess, seq, pc = m.predicted_permille, cols["seq"], cols.get("pc") or [0] * len(cols["op"])
        for i, o, a, b, d, addr, im, dm, mp, lf, le, lc in zip(range(len(cols["op"])), cols["op"], cols["src1"], cols["src2"], cols["dst"], cols["addr"], imem, cols["dmem"], miss, *behind):
            if im:
                f += im
            if lf >= f:
                f = lf + 1
            fetched(f)
            t = f + dec
            if ordered:
                if e > t:
                    t = e
                if le >= t:
                    t = le + 1
            if a is not None and reg[a] > t:
                t = reg[a]
            if b is not None and reg[b] > t:
                t = reg[b]
            x = lat[o]
            if o == LOAD:
                x += mem if mem is not None else dm or 0
                if addr in store and store[addr] > t:
                    t = store[addr]
                if q[0] > t:
                    t = q[0]
            elif o == STORE:
                if q[0] > t:
                    t = q[0]
            r = rings[o]
            if r is not None:
                if earliest:
                    k = r.index(min(r))
                    v = r[k]
                    del r[k]
                    r.appendleft(v)
                if r[0] > t:
                    t = r[0]
                r.append(t + (x if block[o] else 1))
            issued(t)
            e = t
            y = t + x
            if y > c:
                c = y
            if lc >= c:
                c = lc + 1
            committed(c)
            if d is not None:
                reg[d] = y
            if o == LOAD:
                if lsq:
                    q.append(c)
                if guess and d is not None and predicted(seq[i], pc[i] or 0, guess):
                    reg[d] = NEG if m.predict_penalty is None else y + m.predict_penalty
            elif o == STORE:
                if lsq:
                    q.append(c)
                if addr is not None:
                    store[addr] = t + fw
            if mp:
                f = y + pen
        self.f, self.e, self.c, self.y, self.n = f, e, c, y, self.n + len(cols["op"])
        for line, width in ((F, m.fbw), (E, m.ibw), (C, m.cbw)):
            del line[: len(line) - (width or 0)]
        if ordered:  # nothing issues before e any more
            self.store = {k: v for k, v in store.items() if v > e}

    def cycles(self) -> int:
        return self.c


def free_by_issue(m: Machine, u: str, block: list[bool], unit: list[str | None]) -> bool:
    """Whether units of class ``u`` never hold an instruction up: each is taken for a cycle, and no more are issued at once than there are units."""
    return bool(m.ibw) and m.units[u] >= m.ibw and not any(b for b, x in zip(block, unit) if x == u)


class LaneSweep:
    """In-order sweep of many configurations at once, fed in pieces; constant state.

    All lanes share one structure (widths, units, queues); weights differ by lane. The first axis of
    every state array is a state component, the last the lanes. ``shift`` lanes may carry unit
    states for the max-plus summary of a chunk.
    """

    def __init__(self, lanes: list[Machine], state: dict | None = None):
        m = lanes[0]
        if any(x.structure() != m.structure() for x in lanes) or m.core != "inorder":
            raise ValueError("lanes of one sweep share their structure")
        self.lanes, self.m, k = lanes, m, len(lanes)
        tables = [x.tables() for x in lanes]
        self.lat = np.array([t[0] for t in tables], np.int64).T.copy()
        self.block = np.array([t[1] for t in tables], bool).T.copy()
        self.unit = tables[0][2]
        self.decode, self.pen, self.fw = (np.array([getattr(x, a) for x in lanes], np.int64) for a in ("decode", "penalty", "forward"))
        self.fetch = np.array([0 if x.ideal_fetch else 1 for x in lanes], np.int64)
        self.ideal = np.array([x.ideal_branch for x in lanes], bool)
        self.all_ideal, self.no_ideal = bool(self.ideal.all()), not self.ideal.any()
        self.mem = np.array([1 if x.memory is None else 0 for x in lanes], np.int64)
        self.mem0 = np.array([x.memory or 0 for x in lanes], np.int64)
        self.permille = np.array([x.predicted_permille for x in lanes])
        self.predicts = bool(self.permille.any())
        self.earliest = m.fu_policy == "earliest"
        self.look = max(m.ibw or 1, (m.ibw or 1) * int(self.fw.max(initial=1)))
        #: whether weights are known before the sweep, so that whole pieces can be prepared as matrices
        self.plain = not self.predicts and not self.earliest and bool(m.ibw) and (self.all_ideal or self.no_ideal)
        self.rows = self.views = None  # of a piece's matrices, used again by the next of its size
        self.s = state or {
            "n": 0, "F": deque(maxlen=max(m.fbw or 1, 1)), "E": deque(maxlen=self.look), "C": deque(maxlen=max(m.cbw or 1, 1)),
            "reg": np.full((REGISTERS + 1, k), NEG, np.int64), "store": {}, "units": {u: deque(maxlen=c) for u, c in m.units.items()},
            "q": deque(maxlen=m.lsq or 1), "miss": False, "x": np.zeros(k, np.int64),
        }

    def feed(self, cols: dict[str, list]) -> None:
        """The next instructions of the program."""
        if self.plain:
            for at in range(0, len(cols["op"]), ROWS):
                self._feed_matrix({c: v[at : at + ROWS] for c, v in cols.items()})
        else:
            self._feed_rows(cols)

    def _offsets(self, f: list[int], before: int) -> list[list[int]]:
        """Fetch without mispredictions: what each of ``before`` earlier fetches adds up to at each later one, in (max, +)."""
        width, out = self.m.fbw, []
        for k in range(before):
            past = [NEG] * before
            past[k] = 0
            for x in f:
                t = past[-1] + x
                if width and len(past) >= width and past[-width] + 1 > t:
                    t = past[-width] + 1
                past.append(t)
            out.append(past[before:])
        return out

    def _follows(self, f: np.ndarray, begins: np.ndarray) -> np.ndarray:
        """Cycles of fetch since the last of ``begins``: after a wait a cycle begins, and then the width's number are fetched a cycle."""
        at, width = np.arange(len(f)), self.m.fbw or len(f) + 1
        fresh = np.flatnonzero(begins | (f > 0))  # first of its cycle
        run = np.cumsum(begins | (f > 0)) - 1
        total = f[fresh]
        total[1:] += (fresh[1:] - 1 - fresh[:-1]) // width
        total = np.cumsum(total)
        total -= np.maximum.accumulate(np.where(begins[fresh], total, 0))
        return total[run] + (at - fresh[run]) // width

    def _by_lane(self, rows: dict[int, np.ndarray]) -> np.ndarray:
        """Rows of lanes that fetch at the recorded cost (1) and ideally (0), as a matrix."""
        if len(rows) == 1:
            return next(iter(rows.values()))[:, None]
        return np.where(self.fetch == 1, rows[1][:, None], rows[0][:, None])

    def _feed_matrix(self, cols: dict[str, list]) -> None:
        """As _feed_rows. Between mispredictions fetch is closed in form.

        Issue moves on by a cycle every ``ibw`` instructions at least, so a value or unit that is ready so many
        instructions later in every lane no longer counts: ``until`` and ``held`` name the first that need not look.
        """
        s, m = self.s, self.m
        N, k = len(cols["op"]), len(self.lanes)
        ops, f = np.array(cols["op"]), np.array([x or 0 for x in cols["imem"]], np.int64)
        miss = [bool(x) for x in cols["miss"]] if self.no_ideal else [False] * N
        X = self.lat[ops]
        if len(load := np.flatnonzero(ops == LOAD)):
            dm = np.array([cols["dmem"][i] or 0 for i in load.tolist()], np.int64)
            X[load] += self.mem * dm[:, None] + self.mem0
        taken = np.where(self.block[ops], X, 1)
        unit, ibw, lsq = self.unit, m.ibw, m.lsq
        place = np.arange(N)
        until, held = ((place + ibw * x.max(axis=1)).tolist() for x in (X, taken))
        h = self.look
        b = max(m.cbw or 1, 1)
        if self.rows is None or len(self.rows[0]) != N:  # no state refers to them
            self.rows = tuple(np.empty((rows, k), np.int64) for rows in (N, N, h + N, b + N))
            self.views = tuple(map(list, self.rows))
        F, Y, E, C = self.rows
        Fr, Yr, Er, Cr = self.views
        for matrix, rows, before in ((E, h, s["E"]), (C, b, s["C"])):
            matrix[:rows] = NEG
            for j, row in enumerate(before):
                matrix[rows - len(before) + j] = row
        regs, fresh, store, units, q = list(s["reg"]), [N] * (REGISTERS + 1), s["store"], s["units"], s["q"]
        maximum, add = np.maximum, np.add
        one, tmp = np.ones(k, np.int64), np.empty(k, np.int64)

        late = s["miss"] and s["n"] and self.no_ideal
        begins = np.zeros(N, bool)
        begins[[0, *(i + 1 for i in range(N - 1) if miss[i])]] = True
        ends = [*np.flatnonzero(begins)[1:].tolist(), N]
        kinds = set(self.fetch.tolist())
        since = self._by_lane({own: self._follows(own * np.where(begins, 0, f), begins) for own in kinds})
        part = 0  # stretches between mispredictions that are fetched
        if s["n"] and not late:
            held_back = {own: self._offsets((own * f[: ends[0]]).tolist(), len(s["F"])) for own in kinds}
            F[: ends[0]] = NEG
            for j, start in enumerate(s["F"]):
                maximum(F[: ends[0]], start + self._by_lane({own: np.array(x[j], np.int64) for own, x in held_back.items()}), out=F[: ends[0]])
        else:
            add(since[: ends[0]], s["E"][-1] + s["x"] + self.pen + self.fetch * f[0] if late else np.zeros(k, np.int64), out=F[: ends[0]])
        F[: ends[0]] += self.decode

        for i, o, a1, a2, d, addr, mp, e, e1, e2, t, x, y, c, c1, c2 in zip(range(N), cols["op"], cols["src1"], cols["src2"], cols["dst"], cols["addr"], miss, Er[h:], Er[h - 1 :], Er[h - ibw :], Fr, X, Yr, Cr[b:], Cr[b - 1 :], Cr):
            maximum(t, e1, e)
            add(e2, one, tmp)
            maximum(e, tmp, e)
            if a1 is not None and fresh[a1] > i:
                maximum(e, regs[a1], e)
            if a2 is not None and fresh[a2] > i:
                maximum(e, regs[a2], e)
            u = unit[o]
            if u is not None:
                ring = units[u]
                if len(ring) == ring.maxlen:
                    w = ring[0]
                    if w.__class__ is not int:
                        maximum(e, w, e)
                    elif held[w] > i:
                        add(Er[h + w], taken[w], tmp)
                        maximum(e, tmp, e)
                ring.append(i)
            if o == LOAD or o == STORE:
                if o == LOAD and addr is not None and (w := store.get(addr)) is not None:
                    maximum(e, w[1] + self.fw, e)
                if lsq:
                    if len(q) == lsq:
                        maximum(e, q[0], e)
                    q.append(c)
                if o == STORE and addr is not None:
                    store[addr] = (s["n"] + i, e)
            add(e, x, y)
            maximum(y, c1, c)
            if m.cbw:
                add(c2, one, tmp)
                maximum(c, tmp, c)
            if d is not None:
                regs[d] = y
                fresh[d] = until[i]
            if mp and i + 1 < N:
                part += 1
                at, to = i + 1, ends[part]
                add(since[at:to], y + self.pen + self.fetch * f[at] + self.decode, F[at:to])
        n = s["n"] = s["n"] + N
        s["q"] = type(q)((w.copy() for w in q), maxlen=q.maxlen)
        s["reg"] = np.stack(regs)
        s["store"] = {x: (at, w.copy()) for x, (at, w) in store.items() if n - at <= self.look + 1}
        s["units"] = {u: type(r)((E[h + w] + taken[w] if w.__class__ is int else w.copy() for w in r), maxlen=r.maxlen) for u, r in units.items()}
        s["F"].extend((F[-s["F"].maxlen :] - self.decode).copy())
        s["E"].extend(E[h:][-s["E"].maxlen :].copy())
        s["C"].extend(C[b:][-s["C"].maxlen :].copy())
        s["miss"], s["x"] = bool(cols["miss"][-1]), X[-1].copy()

    def _feed_rows(self, cols: dict[str, list]) -> None:
        s, m = self.s, self.m
        F, E, C, reg, store, units, q = s["F"], s["E"], s["C"], s["reg"], s["store"], s["units"], s["q"]
        fbw, ibw, cbw, look = m.fbw, m.ibw, m.cbw, self.look
        miss, x, n = s["miss"], s["x"], s["n"]
        maximum = np.maximum
        pcs = cols.get("pc") or [0] * len(cols["op"])
        for o, a, b, d, addr, im, dm, mp, seq, pc in zip(cols["op"], cols["src1"], cols["src2"], cols["dst"], cols["addr"], cols["imem"], cols["dmem"], cols["miss"], cols["seq"], pcs):
            if n:
                t = F[-1]
                if miss and not self.all_ideal:
                    late = E[-1] + x + self.pen
                    t = late if self.no_ideal else np.where(self.ideal, t, late)
                if im:
                    t = t + self.fetch * im
                if fbw and n >= fbw:
                    t = maximum(t, F[0] + 1)
            else:
                t = np.zeros(len(self.lanes), np.int64)
            F.append(t)
            e = t + self.decode
            if n and ibw is not None:
                e = maximum(e, E[-1])
                if n >= ibw:
                    e = maximum(e, E[-ibw] + 1)
            if a is not None:
                maximum(e, reg[a], out=e)
            if b is not None:
                maximum(e, reg[b], out=e)
            if o == LOAD and addr is not None and (w := store.get(addr)) is not None:
                e = maximum(e, w[1] + self.fw)
            x = self.lat[o]
            if o == LOAD:
                x = x + self.mem * (dm or 0) + self.mem0
            u = self.unit[o]
            if u is not None:
                ring = units[u]
                if len(ring) == ring.maxlen:
                    if self.earliest:
                        held = np.sort(np.stack(ring), 0)
                        ring.extend(held)
                    e = maximum(e, ring[0])
            if m.lsq and (o == LOAD or o == STORE):
                if len(q) == m.lsq:
                    e = maximum(e, q[0])
            if u is not None:
                ring.append(e + np.where(self.block[o], x, 1))
            E.append(e)
            c = e + x
            if d is not None:
                if self.predicts and o == LOAD:
                    cut = np.array([predicted(seq, pc or 0, k) for k in self.permille.tolist()])
                    reg[d] = np.where(cut, NEG, c)
                else:
                    reg[d] = c
            if n:
                c = maximum(c, C[-1])
                if cbw and n >= cbw:
                    c = maximum(c, C[0] + 1)
            C.append(c)
            if o == STORE or o == LOAD:
                if m.lsq:
                    q.append(c)
                if o == STORE and addr is not None:
                    store[addr] = (n, e)
                    if len(store) > 4 * look + 64:  # an older store cannot bind any more
                        for key in [key for key, v in store.items() if n - v[0] > look + 1]:
                            del store[key]
            miss = bool(mp)
            n += 1
        s["miss"], s["x"], s["n"] = miss, x, n

    def cycles(self) -> np.ndarray:
        return self.s["C"][-1] if self.s["n"] else np.zeros(len(self.lanes), np.int64)


def columns(batch) -> dict[str, list]:
    """Kernel columns of an Arrow batch or table (op, seq, src1, src2, dst, addr, imem, dmem, miss, pc)."""
    return {k: batch.column(k).to_pylist() for k in ("op", "seq", "src1", "src2", "dst", "addr", "imem", "dmem", "miss", "pc")}


__all__ = ["BRANCH", "KINDS", "LaneSweep", "NEG", "Program", "ScalarSweep", "base_lengths", "columns", "critical_path", "inorder", "parents", "ranked_sweep", "run", "sliding_active", "sliding_fixed", "sliding_updated", "two_pass"]
