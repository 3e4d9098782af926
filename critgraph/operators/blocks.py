"""Block-structured cores: fetch and commit by block, inserted instructions, encodings.

DataFrame operators give counts, decode delays and edges of a block trace (columns
program_id, seq, block_no, slot, op_class, src1, src2, dst, ...); ``run_blocks`` evaluates the
block graph with its inserted READ, MOV and NULL instructions.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.configs import LATENCY, P_EDGE
from critgraph.operators.runs import arrow_types, kernel_columns
from critgraph.runtime import ship

MOST = 128  # instructions of a block
TARGETS = 2  # consumers an instruction can name
HEADER = 4  # bytes
FORMATS = ("4seg", "2seg", "contiguous", "contiguous+1")


def _within():
    return Window.partitionBy("program_id", "block_no").orderBy("slot")


def sizes(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, instrs, stores, writes, commit_cycles)."""
    last = F.row_number().over(Window.partitionBy("program_id", "block_no", "dst").orderBy(F.desc("slot"))) == 1
    d = trace.withColumn("_w", F.when(F.col("dst").isNotNull(), last).otherwise(False))
    d = d.groupBy("program_id", "block_no").agg(
        F.count(F.lit(1)).alias("instrs"), F.sum((F.col("op_class") == "STORE").cast("bigint")).alias("stores"), F.sum(F.col("_w").cast("bigint")).alias("writes")
    )
    s, w = P_EDGE["stores_per_cycle"], P_EDGE["writes_per_cycle"]
    return d.withColumn("commit_cycles", F.greatest(F.expr(f"(stores + {s - 1}) div {s}"), F.expr(f"(writes + {w - 1}) div {w}")).cast("bigint"))


def reads(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, n): READ instructions, one a register that is used before the block writes it."""
    use = trace.select("program_id", "block_no", "slot", F.explode(F.array_compact(F.array("src1", "src2"))).alias("reg"))
    first_use = use.groupBy("program_id", "block_no", "reg").agg(F.min("slot").alias("u"))
    first_write = trace.where("dst is not null").groupBy("program_id", "block_no", F.col("dst").alias("reg")).agg(F.min("slot").alias("w"))
    d = first_use.join(first_write, ["program_id", "block_no", "reg"], "left").where("w is null or w >= u")
    return d.groupBy("program_id", "block_no").agg(F.count(F.lit(1)).alias("n"))


def producers(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, slot, src_slot): the instruction within the block whose result another reads."""
    use = trace.select("program_id", "block_no", "slot", F.explode(F.array_distinct(F.array_compact(F.array("src1", "src2")))).alias("reg"), F.lit(None).cast("int").alias("w"))
    put = trace.where("dst is not null").select("program_id", "block_no", "slot", F.col("dst").alias("reg"), F.col("slot").alias("w"))
    before = Window.partitionBy("program_id", "block_no", "reg").orderBy("slot", F.col("w").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)
    d = use.unionByName(put).withColumn("src_slot", F.last("w", ignorenulls=True).over(before))
    return d.where("w is null and src_slot is not null").select("program_id", "block_no", "slot", "src_slot")


def movs(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, n): MOV instructions for results with more consumers than targets."""
    fan = producers(trace).groupBy("program_id", "block_no", "src_slot").agg(F.countDistinct("slot").alias("k"))
    return fan.where(F.col("k") > TARGETS).groupBy("program_id", "block_no").agg(F.sum(F.col("k") - TARGETS).cast("bigint").alias("n"))


def nulls(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, n): NULL instructions that balance the writes of predicated blocks.

    The taken path holds the instructions of even slot, the other those of odd slot; the lesser number of
    register and of memory writes is made up.
    """
    taken = F.col("slot") % 2 == 0
    n = lambda c: F.sum(F.when(c, 1).otherwise(0))
    reg, mem = F.col("dst").isNotNull(), F.col("op_class") == "STORE"
    d = trace.where("predicated").groupBy("program_id", "block_no").agg((F.abs(n(taken & reg) - n(~taken & reg)) + F.abs(n(taken & mem) - n(~taken & mem))).cast("bigint").alias("n"))
    return d.where("n > 0")


def mix(trace: DataFrame) -> DataFrame:
    """(program_id, class, n): committed instructions of a block program, inserted ones included."""
    own = trace.groupBy("program_id", F.col("op_class").alias("class")).agg(F.count(F.lit(1)).alias("n"))
    for name, d in (("READ", reads(trace)), ("MOV", movs(trace)), ("NULL", nulls(trace))):
        own = own.unionByName(d.groupBy("program_id").agg(F.sum("n").cast("bigint").alias("n")).select("program_id", F.lit(name).alias("class"), "n"))
    return own


def _fields(trace: DataFrame) -> DataFrame:
    """Bytes of each optional field: targets t, opcode o, immediate v."""
    fan = producers(trace).groupBy("program_id", "block_no", F.col("src_slot").alias("slot")).agg(F.countDistinct("slot").alias("_k"))
    d = trace.join(fan, ["program_id", "block_no", "slot"], "left")
    o = F.when(F.col("op_class").startswith("FP") | (F.col("op_class") == "INT_DIV"), 1).otherwise(0)
    return d.select("program_id", "block_no", "slot", F.when(F.col("_k") > 1, 2).otherwise(0).alias("t"), o.alias("o"), ((F.col("slot") % 4) * 2).cast("int").alias("v"))


def decode_delay(trace: DataFrame, per_cycle: int = P_EDGE["bytes_per_cycle"]) -> DataFrame:
    """(program_id, block_no, slot, format, delay): the cycle in which an instruction's bytes have arrived, by encoding."""
    upto = _within().rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy("program_id", "block_no")
    d = _fields(trace).withColumns({"i": F.row_number().over(_within()), "cnt": F.count(F.lit(1)).over(whole)})
    for c in ("t", "o", "v"):
        d = d.withColumns({f"c{c}": F.sum(c).over(upto), f"s{c}": F.sum(c).over(whole)})
    up = lambda e: F.expr(f"cast(({e} + {per_cycle - 1}) div {per_cycle} as int)")
    base = up("2 * i")
    optional = F.when(F.expr("t + o + v > 0"), up("2 * cnt + ct + co + cv")).otherwise(0)
    parts = [F.when(F.col("t") > 0, up("2 * cnt + ct")).otherwise(0), F.when(F.col("o") > 0, up("2 * cnt + st + co")).otherwise(0), F.when(F.col("v") > 0, up("2 * cnt + st + so + cv")).otherwise(0)]
    contiguous = up("2 * i + ct + co + cv")
    found = {"4seg": F.greatest(base, *parts), "2seg": F.greatest(base, optional), "contiguous": contiguous, "contiguous+1": contiguous + 1}
    rows = F.array(*(F.struct(F.lit(k).alias("format"), v.cast("int").alias("delay")) for k, v in found.items()))
    return d.select("program_id", "block_no", "slot", F.explode(rows).alias("r")).select("program_id", "block_no", "slot", "r.format", "r.delay")


def vertices(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, slot, stage): BF and BC a block, E an instruction."""
    b = trace.select("program_id", "block_no").distinct()
    ends = b.select("program_id", "block_no", F.lit(None).cast("int").alias("slot"), F.explode(F.array(F.lit("BF"), F.lit("BC"))).alias("stage"))
    return ends.unionByName(trace.select("program_id", "block_no", "slot", F.lit("E").alias("stage")))


def edges(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, slot, kind): BF to E of every instruction; E to BC of branches, stores and register writes."""
    needed = F.col("op_class").isin("BRANCH", "STORE") | F.col("dst").isNotNull()
    kinds = F.array_compact(F.array(F.lit("block_fetch"), F.when(needed, F.lit("block_commit"))))
    return trace.select("program_id", "block_no", "slot", F.explode(kinds).alias("kind"))


def chains(trace: DataFrame) -> DataFrame:
    """(program_id, block_no, next_no, kind, w): block to block edges; a block with a mispredicted branch redirects."""
    by = Window.partitionBy("program_id").orderBy("block_no")
    s = sizes(trace)
    miss = trace.groupBy("program_id", "block_no").agg(F.max(F.coalesce("mispredicted", F.lit(False)).cast("int")).alias("_m"))
    d = s.join(miss, ["program_id", "block_no"]).withColumn("next_no", F.lead("block_no").over(by)).where("next_no is not null")
    kind = F.when(F.col("_m") == 1, "redirect").otherwise("block_fetch")
    both = F.array(F.struct(kind.alias("kind"), F.lit(P_EDGE["hit"]).cast("bigint").alias("w")), F.struct(F.lit("block_commit").alias("kind"), F.col("commit_cycles").alias("w")))
    return d.select("program_id", "block_no", "next_no", F.explode(both).alias("r")).select("program_id", "block_no", "next_no", "r.kind", "r.w")


# -- evaluation ---------------------------------------------------------------------------


class Names:
    """Operation names in a byte each."""

    def __init__(self):
        self.codes = bytearray()

    def append(self, name: str) -> None:
        self.codes.append(schemas.CODE[name])

    def count(self, name: str) -> int:
        return self.codes.count(schemas.CODE[name])

    def __len__(self) -> int:
        return len(self.codes)

    def __getitem__(self, k: int) -> str:
        return schemas.OPS[self.codes[k]]

    def __iter__(self) -> Iterator[str]:
        return map(schemas.OPS.__getitem__, self.codes)

    def __eq__(self, other) -> bool:
        return self.codes == other.codes


class BlockProgram:
    """A program as blocks with inserted instructions, its costs by seeded statistics.

    Rows are fed in pieces, blocks one after the other; what is kept of an instruction are some 20 bytes in arrays and two more
    an encoding, and some 20 while it is run; the encodings share all but their delays.
    """

    def __init__(self, cols: dict[str, list] | None, program: int, *forms: str):
        self.forms, self.program = forms or FORMATS, program
        self.op = Names()
        self.up = tuple(array("i") for _ in range(3))  # parents, -1 for none
        self.where, self.starts = array("i"), array("i", [0])
        self.delays = {f: array("H") for f in self.forms}
        self.miss = bytearray()
        self.needed = bytearray()  # what the block's commit waits for: branches, stores, register writes
        self.held: dict[str, list] = {}
        self.writer: dict[int, int] = {}
        self.store: dict[int, int] = {}
        if cols is not None:
            order = sorted(range(len(cols["op"])), key=lambda i: cols["block_no"][i])
            self.feed({k: [v[i] for i in order] for k, v in cols.items()})
            self.close()

    @property
    def n_blocks(self) -> int:
        return len(self.starts) - 1

    @property
    def output(self) -> set[int]:
        return {k for k, x in enumerate(self.needed) if x}

    def parents(self, k: int) -> list[int]:
        return [u[k] for u in self.up if u[k] >= 0]

    def feed(self, cols: dict[str, list]) -> None:
        """The next rows, in order of block and seq; rows of a block that may go on are held."""
        if self.held:
            cols = {k: self.held[k] + v for k, v in cols.items()}
        b, at = cols["block_no"], 0
        while at < len(b):
            to = at + 1
            while to < len(b) and b[to] == b[at] and to - at < MOST:
                to += 1
            if to == len(b) and to - at < MOST:
                break
            self._block(cols, self.program, range(at, to), self.writer, self.store)
            at = to
        self.held = {k: v[at:] for k, v in cols.items()}

    def close(self) -> None:
        if self.held and self.held["op"]:
            self._block(self.held, self.program, range(len(self.held["op"])), self.writer, self.store)
        self.held, self.writer, self.store = {}, {}, {}

    def _block(self, cols, program, rows, writer, store) -> None:
        local: dict[int, int] = {}
        uses: dict[int, int] = {}  # targets that a result has taken
        mine: list[tuple[int, int | None]] = []
        # consumers that each result of the block will have: a result of more than TARGETS is handed on by MOVs
        made: dict[int, int] = {}
        wanted: dict[int, int] = {}
        for i in rows:
            for r in {cols["src1"][i], cols["src2"][i]} - {None}:
                if r in made:
                    wanted[made[r]] = wanted.get(made[r], 0) + 1
            if cols["dst"][i] is not None:
                made[cols["dst"][i]] = i
        left: dict[int, int] = {}  # consumers still to come, by the instruction or MOV that holds the result

        def add(op, parents, miss=False, seq=None):
            self.op.append(op)
            for j, u in enumerate(self.up):
                u.append(parents[j] if j < len(parents) else -1)
            self.miss.append(miss)
            self.needed.append(False)
            self.where.append(self.n_blocks)
            mine.append((len(self.op) - 1, seq))
            return len(self.op) - 1

        def value(reg):
            if reg not in local:
                local[reg] = add("READ", [writer[reg]] if reg in writer else [])
            v = local[reg]
            if self.op[v] != "READ" and uses.get(v, 0) == TARGETS - 1 and left[v] > 1:
                uses[v] = TARGETS
                local[reg] = m = add("MOV", [v])
                left[m] = left[v]
                v = m
            uses[v] = uses.get(v, 0) + 1
            left[v] = left.get(v, 0) - 1
            return v

        for i in rows:
            op = schemas.OPS[cols["op"][i]]
            parents = [value(r) for r in dict.fromkeys((cols["src1"][i], cols["src2"][i])) if r is not None]
            addr = cols["addr"][i]
            if op == "LOAD" and addr in store:
                parents.append(store[addr])
            seq = cols["seq"][i]
            k = add(op, parents, op == "BRANCH" and (6151 * seq + 3 + 31 * program) % 100 >= P_EDGE["branch_pct"], seq)
            if op == "STORE" and addr is not None:
                store[addr] = k
            if cols["dst"][i] is not None:
                local[cols["dst"][i]] = k
                left[k] = wanted.get(i, 0)
            if op in ("BRANCH", "STORE") or cols["dst"][i] is not None:
                self.needed[k] = True
        if cols.get("predicated") and cols["predicated"][rows[0]]:
            reg = [sum(cols["dst"][i] is not None for i in rows[j::2]) for j in (0, 1)]
            mem = [sum(schemas.OPS[cols["op"][i]] == "STORE" for i in rows[j::2]) for j in (0, 1)]
            for _ in range(abs(reg[0] - reg[1]) + abs(mem[0] - mem[1])):
                self.needed[add("NULL", [])] = True
        for reg, v in local.items():
            if self.op[v] != "READ":
                writer[reg] = v
        self.starts.append(len(self.op))
        for form in self.forms:
            self._delays(mine, uses, form)

    def _delays(self, mine, uses, form: str) -> None:
        """Arrival cycles of this block's instructions in an encoding."""
        per = P_EDGE["bytes_per_cycle"]
        t = [2 if uses.get(k, 0) > 1 else 0 for k, _ in mine]
        o = [1 if self.op[k].startswith("FP") or self.op[k] == "INT_DIV" else 0 for k, _ in mine]
        v = [(j % 4) * 2 for j in range(len(mine))]
        n, ct, co, cv, st, so = len(mine), 0, 0, 0, sum(t), sum(o)
        for j in range(n):
            ct, co, cv = ct + t[j], co + o[j], cv + v[j]
            if form.startswith("contiguous"):
                d = 2 * (j + 1) + ct + co + cv
            elif form == "2seg":
                d = max(2 * (j + 1), 2 * n + ct + co + cv if t[j] + o[j] + v[j] else 0)
            else:
                d = max(2 * (j + 1), 2 * n + ct if t[j] else 0, 2 * n + st + co if o[j] else 0, 2 * n + st + so + cv if v[j] else 0)
            self.delays[form].append(-(-(HEADER + d) // per) + (1 if form.endswith("+1") else 0))

    def run(self, form: str = "") -> int:
        """Cycles, with issue by readiness on limited units (two passes: order, then lengths)."""
        n = len(self.op)
        lat = array("i", (LATENCY[o] + (0 if o != "LOAD" else (P_EDGE["hit"] if (7919 * k + 13) % 100 < P_EDGE["dhit_pct"] else P_EDGE["miss"])) for k, o in enumerate(self.op)))
        unit = {"LOAD": "LSU", "STORE": "LSU", "BRANCH": "INT_ALU", "READ": "INT_ALU", "MOV": "INT_ALU", "NULL": "INT_ALU"}
        self.lat, self.delay = lat, self.delays[form or self.forms[0]]
        self.E = self.BF = self.BC = self.fu = None  # of the run before
        self._lengths(lat, range(n), None)
        order = np.argsort(np.frombuffer(self.E, np.int64), kind="stable")
        self.E = self.BF = self.BC = self.fu = None
        order = memoryview(order.astype(np.int32) if n < 1 << 31 else order)
        self._lengths(lat, order, unit)
        return self.BC[-1] if self.n_blocks else 0

    def _lengths(self, lat, order, unit) -> array:
        """Times are not negative: -1 stands for one not known yet."""
        n, nb, starts, needed = len(self.op), self.n_blocks, self.starts, self.needed
        unknown = lambda k: array("q", [-1]) * k
        E, BF, BC = unknown(n), unknown(nb), unknown(nb)
        self.fu = array("i", [-1]) * n if unit is not None else None
        rings: dict[str, list[int]] = {}
        segments = array("i", (-(-(starts[b + 1] - starts[b]) // P_EDGE["segment"]) for b in range(nb)))
        fetch = array("i", (P_EDGE["hit"] if (104729 * b + 7) % 100 < P_EDGE["ihit_pct"] else P_EDGE["miss"] for b in range(nb)))
        self.fetch, self.full = fetch, array("i", [-1]) * nb
        up1, up2, up3 = self.up
        ready_front = ready_back = 0

        def commit_one() -> bool:
            nonlocal ready_back
            b = ready_back
            awaited = [k for k in range(starts[b], starts[b + 1]) if needed[k]]
            if BF[b] < 0 or any(E[k] < 0 for k in awaited):
                return False
            t = max((E[k] + lat[k] for k in awaited), default=BF[b])
            if b:
                t = max(t, BC[b - 1] + self._commit(b - 1))
            BC[b] = t
            ready_back += 1
            return True

        def front_one() -> None:
            nonlocal ready_front
            b = ready_front
            t = 0
            if b:
                wrong = [k for k in range(starts[b - 1], starts[b]) if self.miss[k]]
                t = max((E[k] + lat[k] for k in wrong), default=BF[b - 1]) + fetch[b]
                room, j = 4 - segments[b], b - 1
                while j >= 0 and room >= segments[j]:
                    room -= segments[j]
                    j -= 1
                if j >= 0:
                    while ready_back <= j:
                        if not commit_one():
                            raise RuntimeError("a block waits for itself")
                    self.full[b] = j
                    t = max(t, BC[j])
            BF[b] = t
            ready_front += 1

        for k in order:
            b = self.where[k]
            while ready_front <= b:
                front_one()
            t = BF[b] + self.delay[k]
            s = starts[b]
            for w in (up1[k], up2[k], up3[k]):
                if w < 0:
                    continue
                cross = self.where[w] == b and (w - s) // P_EDGE["segment"] != (k - s) // P_EDGE["segment"]
                t = max(t, E[w] + lat[w] + cross)
            if unit is not None:
                u = unit.get(self.op[k], self.op[k])
                m = P_EDGE["units"].get(u, 8)
                ring = rings.setdefault(u, [])
                if len(ring) == m:
                    w = ring.pop(0)
                    self.fu[k] = w
                    t = max(t, E[w] + (lat[w] if self.op[w] in ("INT_DIV", "FP_DIV") else 1))
                ring.append(k)
            E[k] = t
        while ready_back < nb:
            commit_one()
        self.E, self.BF, self.BC = E, BF, BC
        return E

    def _commit(self, b: int) -> int:
        s, e = self.starts[b], self.starts[b + 1]
        stores = sum(self.op[k] == "STORE" for k in range(s, e))
        writes = sum(self.op[k] not in ("STORE", "BRANCH", "NULL") for k in range(s, e))
        return max(-(-stores // P_EDGE["stores_per_cycle"]), -(-writes // P_EDGE["writes_per_cycle"]))

    def path(self) -> Iterator[tuple[str, str, int]]:
        """(class, term, cycles) of the critical path of the last run, last first; class BLOCK for block events."""
        b, k, starts = self.n_blocks - 1, None, self.starts
        state = "BC"
        lat = self.lat
        while True:
            if state == "BC":
                k = max((j for j in range(starts[b], starts[b + 1]) if self.needed[j]), key=lambda j: (self.E[j] + lat[j], j), default=None)
                if k is not None and self.E[k] + lat[k] == self.BC[b]:
                    yield self.op[k], "execute", lat[k]
                    state = "E"
                elif self.BF[b] == self.BC[b]:
                    state = "BF"
                else:
                    yield "BLOCK", "block_commit", self._commit(b - 1)
                    b -= 1
            elif state == "E":
                b = self.where[k]
                s = starts[b]
                for w in sorted(self.parents(k), reverse=True):
                    cross = int(self.where[w] == b and (w - s) // P_EDGE["segment"] != (k - s) // P_EDGE["segment"])
                    if self.E[w] + lat[w] + cross == self.E[k]:
                        yield self.op[w], "execute", lat[w]
                        if cross:
                            yield self.op[k], "cross_segment", cross
                        k = w
                        break
                else:
                    w = self.fu[k]
                    if self.BF[b] + self.delay[k] == self.E[k]:
                        yield self.op[k], "decode", self.delay[k]
                        state = "BF"
                    elif w >= 0:
                        yield self.op[k], "fu_wait", self.E[k] - self.E[w]
                        k = w
                    else:
                        return
            else:
                if not b:
                    return
                wrong = [j for j in range(starts[b - 1], starts[b]) if self.miss[j]]
                if self.full[b] >= 0 and self.BC[self.full[b]] == self.BF[b]:
                    b, state = self.full[b], "BC"
                elif wrong:
                    k = max(wrong, key=lambda j: (self.E[j] + lat[j], j))
                    yield "BLOCK", "fetch", self.fetch[b]
                    yield self.op[k], "execute", lat[k]
                    state = "E"
                else:
                    yield "BLOCK", "fetch", self.fetch[b]
                    b -= 1


def _streamed(trace: DataFrame, forms: tuple[str, ...], fn, schema: str) -> DataFrame:
    """``fn`` (program number, BlockProgram) -> rows, once a program: its rows stream in, sorted by block."""
    ship(trace.sparkSession)
    names, types = [x.strip().split()[0] for x in schema.split(",")], arrow_types(schema)
    read = ("op", "seq", "src1", "src2", "dst", "addr", "block_no", "predicated")

    def batch(p: BlockProgram) -> pa.RecordBatch:
        p.close()
        cols = list(zip(*fn(p.program, p))) or [[]] * len(names)
        return pa.record_batch([pa.array(c, t) for c, t in zip(cols, types)], names=names)

    def run(batches):
        p = None
        for b in batches:
            ids = b.column("program_id").to_numpy(zero_copy_only=False)
            cuts = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
            for lo, hi in zip(cuts, cuts[1:]):
                if lo == hi:
                    continue
                if p is None or p.program != int(ids[lo]):
                    if p is not None:
                        yield batch(p)
                    p = BlockProgram(None, int(ids[lo]), *forms)
                p.feed({k: b.column(k).slice(lo, hi - lo).to_pylist() for k in read})
        if p is not None:
            yield batch(p)

    d = kernel_columns(_filled(trace), "block_no", "predicated").select("program_id", *read)
    return d.repartition("program_id").sortWithinPartitions("program_id", "block_no", "seq").mapInArrow(run, schema)


def run_blocks(trace: DataFrame, formats: tuple[str, ...] = FORMATS) -> DataFrame:
    """(program_id, format, cycles, instrs, blocks) of each encoding."""

    def fn(program, p):
        for f in formats:
            yield program, f, p.run(f), len(p.op), p.n_blocks

    return _streamed(trace, formats, fn, "program_id int, format string, cycles bigint, instrs bigint, blocks bigint")


def path_mix(trace: DataFrame, form: str = "4seg") -> DataFrame:
    """(program_id, class, term, instrs, cycles) along the critical path of a block program."""

    def fn(program, p):
        if not p.n_blocks:
            return
        p.run()
        total: dict[tuple[str, str], list[int]] = {}
        for c, term, cycles in p.path():
            x = total.setdefault((c, term), [0, 0])
            x[0] += 1
            x[1] += cycles
        for (c, term), (k, cycles) in sorted(total.items()):
            yield program, c, term, k, cycles

    return _streamed(trace, (form,), fn, "program_id int, class string, term string, instrs bigint, cycles bigint")


def shares(paths: DataFrame) -> DataFrame:
    """(program_id, read_mov_instrs, null_instrs, read_mov_cycles): shares of the critical path's instructions, and of its cycles of fetch, decode and execution."""
    n = lambda what, *of: F.sum(F.when(F.col("class").isin(*of), F.col(what)).otherwise(0))
    instrs = F.greatest(F.sum(F.when(F.col("class") != "BLOCK", F.col("instrs")).otherwise(0)), F.lit(1))
    staged = F.col("term").isin("fetch", "decode", "execute")
    cycles = F.greatest(F.sum(F.when(staged, F.col("cycles")).otherwise(0)), F.lit(1))
    own = F.sum(F.when(staged & F.col("class").isin("READ", "MOV"), F.col("cycles")).otherwise(0))
    return paths.groupBy("program_id").agg(F.round(n("instrs", "READ", "MOV") / instrs, 6).alias("read_mov_instrs"), F.round(n("instrs", "NULL") / instrs, 6).alias("null_instrs"), F.round(own / cycles, 6).alias("read_mov_cycles"))


def format_gains(runs: DataFrame, base: str = "4seg") -> DataFrame:
    """(format, average, maximum, minimum) over programs of the improvement over the format ``base``."""
    d = runs.join(runs.where(F.col("format") == base).select("program_id", F.col("cycles").alias("_base")), "program_id")
    gain = 1 - F.col("cycles") / F.col("_base")
    return d.groupBy("format").agg(*(F.round(f(gain), 6).alias(n) for n, f in (("average", F.avg), ("maximum", F.max), ("minimum", F.min))))


def _filled(trace: DataFrame) -> DataFrame:
    """A block trace with the columns that it may lack."""
    blank = {"imem_cycles": "int", "dmem_cycles": "int", "mispredicted": "boolean", "predicated": "boolean"}
    return trace.withColumns({c: F.lit(None).cast(t) for c, t in blank.items() if c not in trace.columns})
