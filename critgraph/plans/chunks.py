"""Programs larger than a task: chunks of a trace, combined exactly.

In order: every rule is linear in (max, +), so a chunk is a matrix from its entry state to
its exit state. The vector kernel computes it by sweeping unit states as lanes; matrices combine
associatively, in levels of ``FAN``. Out of order: scheduling depends on
the lengths, so chunks are run with a warm-up before and a look-ahead behind; where the state a
chunk starts from differs from its predecessor's (up to a shift), the chunk is run again with a longer warm-up.
"""

from __future__ import annotations

from collections import deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.configs import Machine
from critgraph.operators import kernels
from critgraph.operators.kernels import NEG, LaneSweep
from critgraph.operators.runs import kernel_columns
from critgraph.runtime import materialise, ship

FAN = 64


def layout(m: Machine) -> list[tuple]:
    """The state's components, in order: (part, place)."""
    look = max(m.ibw or 1, (m.ibw or 1) * m.forward)
    parts = [("F", i) for i in range(max(m.fbw or 1, 1))] + [("E", i) for i in range(look)] + [("C", i) for i in range(max(m.cbw or 1, 1))]
    parts += [("reg", r) for r in range(schemas.REGISTERS)] + [(("units", u), i) for u in sorted(m.units) for i in range(m.units[u])]
    return parts + [("q", i) for i in range(m.lsq or 1)]


def unpack(m: Machine, vectors: np.ndarray, halo: dict[str, list], n: int) -> dict:
    """Kernel state from component vectors (components x lanes) and the rows before the chunk."""
    k = vectors.shape[1]
    probe = LaneSweep([m])
    s = {"n": n, "reg": np.full((schemas.REGISTERS + 1, k), NEG, np.int64), "store": {}, "units": {u: deque(maxlen=c) for u, c in m.units.items()}, "q": deque(maxlen=m.lsq or 1)}
    for name, limit in (("F", probe.s["F"].maxlen), ("E", probe.look), ("C", probe.s["C"].maxlen)):
        s[name] = deque(maxlen=limit)
    for (part, at), v in zip(layout(m), vectors):
        if part == "reg":
            s["reg"][at] = v
        elif isinstance(part, tuple):
            s["units"][part[1]].append(v)
        else:
            s[part].append(v)
    s["miss"] = bool(halo["miss"][-1])
    o = halo["op"][-1]
    lat = m.latency[schemas.OPS[o]] + ((m.memory if m.memory is not None else halo["dmem"][-1] or 0) if o == schemas.LOAD else 0)
    s["x"] = np.full(k, lat, np.int64)
    rows = len(halo["op"])
    for j in range(max(0, rows - len(s["E"])), rows):
        if halo["op"][j] == schemas.STORE and halo["addr"][j] is not None:
            s["store"][halo["addr"][j]] = (n - rows + j, s["E"][len(s["E"]) - rows + j])
    return s


def pack(m: Machine, s: dict) -> np.ndarray:
    """Component vectors of a kernel state; rings that are not full yet are filled with NEG at the old end."""
    k = len(s["x"])
    blank = np.full(k, NEG, np.int64)

    def ring(d, size):
        return [blank] * (size - len(d)) + [np.maximum(v, NEG) for v in d]

    out = []
    for name in ("F", "E", "C"):
        out += ring(s[name], s[name].maxlen)
    out += list(s["reg"][: schemas.REGISTERS])
    for u in sorted(m.units):
        out += ring(s["units"][u], m.units[u])
    return np.stack(out + ring(s["q"], m.lsq or 1))


def times(a: np.ndarray, v: np.ndarray) -> np.ndarray:
    """The (max, +) product."""
    out = np.full((a.shape[0], v.shape[1]), NEG, np.int64)
    for j in range(a.shape[1]):
        np.maximum(out, a[:, j, None] + v[None, j], out=out)
    return np.maximum(out, NEG)


def _cut(trace: DataFrame, size: int, before: int, after: int = 0) -> DataFrame:
    """Kernel columns with chunk and halo: the rows around a chunk's border go to both chunks."""
    d = kernel_columns(trace).withColumn("_c", F.floor(F.col("seq") / size).cast("bigint"))
    at = F.col("seq") % size
    goes = [F.struct(F.col("_c").alias("chunk"), F.lit(0).alias("halo"))]
    for k in range(1, -(-before // size) + 1):
        goes.append(F.when(at >= k * size - before, F.struct((F.col("_c") + k).alias("chunk"), F.lit(-1).alias("halo"))))
    for k in range(1, -(-after // size) + 1):
        goes.append(F.when((at < after - (k - 1) * size) & (F.col("_c") >= k), F.struct((F.col("_c") - k).alias("chunk"), F.lit(1).alias("halo"))))
    return d.withColumn("_g", F.explode(F.array_compact(F.array(*goes)))).select(*d.drop("_c").columns, "_g.chunk", "_g.halo")


def _chunks(batches):
    """(program, chunk, columns, halo) of sorted batches, a chunk at a time."""
    held, key = [], None
    for b in batches:
        ids, cs = b.column("program_id").to_numpy(zero_copy_only=False), b.column("chunk").to_numpy(zero_copy_only=False)
        if not len(ids):
            continue
        cuts = [0, *(np.flatnonzero((ids[1:] != ids[:-1]) | (cs[1:] != cs[:-1])) + 1).tolist(), len(ids)]
        for lo, hi in zip(cuts, cuts[1:]):
            now = (int(ids[lo]), int(cs[lo]))
            if now != key and held:
                yield (*key, *_columns(held))
                held = []
            key = now
            held.append(b.slice(lo, hi - lo))
    if held:
        yield (*key, *_columns(held))


def _columns(held):
    t = pa.Table.from_batches(held)
    return kernels.columns(t), t.column("halo").to_pylist()


def run_chunked(trace: DataFrame, m: Machine, size: int = 100_000) -> DataFrame:
    """(program_id, lane, cycles, instrs) of an in-order core, exact, whatever the length of a program."""
    ship(trace.sparkSession)
    d = len(layout(m))
    look = max(m.ibw or 1, (m.ibw or 1) * m.forward)

    def summarise(batches):
        for program, chunk, cols, halo in _chunks(batches):
            h = sum(x == -1 for x in halo)
            own = {k: v[h:] for k, v in cols.items()}
            if chunk == 0:
                sweep = LaneSweep([m])
                sweep.feed(own)
                a = np.full((d, d), NEG, np.int64)
                a[:, :1] = pack(m, sweep.s)  # the first chunk's exit does not depend on an entry: a constant column
            else:
                unit = np.full((d, d), NEG, np.int64)
                np.fill_diagonal(unit, 0)
                sweep = LaneSweep([m] * d, unpack(m, unit, {k: v[:h] for k, v in cols.items()}, 10**9))
                sweep.feed(own)
                a = pack(m, sweep.s)
            yield pa.record_batch([pa.array([program], pa.int32()), pa.array([chunk], pa.int64()), pa.array([len(own["op"])], pa.int64()), pa.array([a.tobytes()], pa.binary())], names=["program_id", "chunk", "instrs", "a"])

    schema = "program_id int, chunk bigint, instrs bigint, a binary"
    cut = _cut(trace, size, look).repartition("program_id", "chunk").sortWithinPartitions("program_id", "chunk", "seq")
    parts = materialise(cut.mapInArrow(summarise, schema), "chunks")

    def combine(key, t):
        t = t.sort_by("chunk")
        whole = None
        for x in t.column("a").to_pylist():
            a = np.frombuffer(x, np.int64).reshape(d, d)
            whole = a if whole is None else times(a, whole)
        return pa.table({"program_id": pa.array([key[0].as_py()], pa.int32()), "chunk": pa.array([key[1].as_py()], pa.int64()), "instrs": pa.array([sum(t.column("instrs").to_pylist())], pa.int64()), "a": pa.array([whole.tobytes()], pa.binary())})

    while (parts.agg(F.max("chunk")).first()[0] or 0) > 0:
        level = parts.withColumn("_g", F.floor(F.col("chunk") / FAN).cast("bigint"))
        parts = materialise(level.groupBy("program_id", "_g").applyInArrow(combine, schema), "chunks")
    at_c = layout(m).index(("C", max(m.cbw or 1, 1) - 1))

    def last(batches):
        for b in batches:
            c = [int(np.frombuffer(x, np.int64).reshape(d, d)[at_c, 0]) for x in b.column("a").to_pylist()]
            yield pa.record_batch([b.column("program_id"), pa.array([0] * len(c), pa.int32()), pa.array(c, pa.int64()), b.column("instrs")], names=["program_id", "lane", "cycles", "instrs"])

    return parts.mapInArrow(last, schemas.RUN)


def run_chunked_ooo(trace: DataFrame, m: Machine, size: int = 20_000, warm: int | None = None, rounds: int = 8) -> DataFrame:
    """(program_id, lane, cycles, instrs, chunks, rerun) of an out-of-order core by speculative chunks.

    A chunk whose starting state equals its predecessor's end, up to a shift, is settled; the others are
    run again with four times the warm-up. With a warm-up as long as the program, every chunk is settled; if chunks are
    not after ``rounds``, ValueError is raised and no sum is given.

    The state at a border is the lengths F, D, E and C of the last ``rob`` instructions. Nothing older can bind: an
    instruction is dispatched after the commit of the one ``rob`` before it, hence after all that older ones have executed,
    freed their units and left their slots. So a reorder buffer is required.
    """
    if not m.rob:
        raise ValueError("without a reorder buffer a border's state has no bound")
    ship(trace.sparkSession)
    span = m.rob
    warm = warm or 2 * span
    schema = "program_id int, chunk bigint, delta bigint, instrs bigint, enters string, leaves string"

    def run(batches):
        for program, chunk, cols, halo in _chunks(batches):
            p = kernels.Program(cols, m)
            kernels.run(p)
            lo, hi = sum(x == -1 for x in halo), sum(x <= 0 for x in halo)

            def state(at):
                if not at:
                    return ""
                base = p.C[at - 1]
                return str(hash(tuple(x - base for arr in (p.F, p.D, p.E, p.C) for x in arr[max(0, at - span) : at])))

            start = p.C[lo - 1] if lo else 0
            yield pa.record_batch([pa.array([x], t) for x, t in zip((program, chunk, p.C[hi - 1] - start, hi - lo, state(lo), state(hi)), (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()))], names=["program_id", "chunk", "delta", "instrs", "enters", "leaves"])

    def sweep(rows: DataFrame, warm: int) -> DataFrame:
        return rows.repartition("program_id", "chunk").sortWithinPartitions("program_id", "chunk", "seq").mapInArrow(run, schema)

    done = materialise(sweep(_cut(trace, size, warm, 2 * m.window), warm), "ooo").withColumn("rerun", F.lit(0))
    for _ in range(rounds):
        w = Window.partitionBy("program_id").orderBy("chunk")
        off = done.withColumn("_before", F.lag("leaves").over(w)).where("chunk > 0 and enters <> _before").select("program_id", "chunk")
        off = materialise(off, "off")
        if not off.count():
            break
        warm *= 4
        # a chunk's end may have been wrong as well: its predecessor is run again with it
        again = off.union(off.select("program_id", (F.col("chunk") - 1).alias("chunk"))).distinct()
        rows = _cut(trace, size, warm, 2 * m.window).join(again, ["program_id", "chunk"], "left_semi")
        new = sweep(rows, warm).withColumn("rerun", F.lit(1))
        done = materialise(done.join(again, ["program_id", "chunk"], "left_anti").select(*new.columns).unionByName(new), "ooo")
    else:
        raise ValueError(f"chunks did not settle within {rounds} rounds")
    total = done.groupBy("program_id").agg(F.sum("delta").alias("cycles"), F.sum("instrs").alias("instrs"), F.count(F.lit(1)).alias("chunks"), F.sum("rerun").alias("rerun"))
    return total.select("program_id", F.lit(0).alias("lane"), "cycles", "instrs", "chunks", "rerun")
