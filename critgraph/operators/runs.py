"""Runs, paths and breakdowns of traces as DataFrames."""

from __future__ import annotations

import time
from array import array
from collections.abc import Iterator
from functools import reduce
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.configs import Machine
from critgraph.operators import kernels
from critgraph.runtime import ship
from critgraph.sources.traces import op_code


#: Instructions that a vector sweep is fed at a time: its matrices hold a value an instruction and lane.
PIECE = 10_000


def kernel_columns(trace: DataFrame, *more: str) -> DataFrame:
    """The columns a kernel reads; nothing else crosses into Python."""
    has = set(trace.columns)
    pc = F.col("pc").cast("bigint") if "pc" in has else F.lit(0).cast("bigint")
    return trace.select(
        F.col("program_id").cast("int").alias("program_id"), F.col("seq").cast("bigint").alias("seq"), op_code(F.col("op_class")).alias("op"), "src1", "src2", "dst", "addr",
        F.col("imem_cycles").alias("imem"), F.col("dmem_cycles").alias("dmem"), F.col("mispredicted").alias("miss"), pc.alias("pc"), *more,
    )


def by_structure(lanes: list[Machine]) -> list[list[tuple[int, Machine]]]:
    """Lanes that one vector sweep can share; equal lanes stay apart only by number."""
    groups: dict[tuple, list] = {}
    for k, m in enumerate(lanes):
        groups.setdefault(m.structure(), []).append((k, m))
    return list(groups.values())


def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, dict[str, list], bool]]:
    """(program, kernel columns, is it the program's first piece?) of batches sorted by program and seq."""
    before = None
    for b in batches:
        if not b.num_rows:
            continue
        ids = b.column("program_id").to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(ids[1:] != ids[:-1]) + 1).tolist(), len(ids)]
        for lo, hi in zip(cuts, cuts[1:]):
            now = int(ids[lo])
            yield now, kernels.columns(b.slice(lo, hi - lo)), now != before
            before = now


def run_lanes(trace: DataFrame, lanes: list[Machine]) -> DataFrame:
    """(program_id, lane, cycles, instrs) of in-order lanes: one pass over the sorted trace, constant state.

    Programs are dealt to tasks and streamed; a task holds a batch and the kernels' state,
    however long a program is.
    """
    ship(trace.sparkSession)
    groups = by_structure(lanes)

    def run(batches):
        open_at, sweeps, out = None, [], []

        def close():
            for g, s in zip(groups, sweeps):
                out.extend((open_at, k, int(c), s.s["n"]) for (k, _), c in zip(g, s.cycles()))

        for program, cols, first in pieces(batches):
            if first:
                if open_at is not None:
                    close()
                open_at, sweeps = program, [kernels.LaneSweep([m for _, m in g]) for g in groups]
            for s in sweeps:
                s.feed(cols)
        if open_at is not None:
            close()
        cols = list(zip(*out)) or [[]] * 4
        yield pa.record_batch([pa.array(c, k) for c, k in zip(cols, (pa.int32(), pa.int32(), pa.int64(), pa.int64()))], names=["program_id", "lane", "cycles", "instrs"])

    return kernel_columns(trace).repartition("program_id").sortWithinPartitions("program_id", "seq").mapInArrow(run, schemas.RUN)


def _grouped(trace: DataFrame, fn, schema: str, *more: str) -> DataFrame:
    """``fn`` (program, columns, table) -> rows, once a program whose rows fit a task (longer ones: plans.chunks)."""
    ship(trace.sparkSession)
    names = [x.strip().split()[0] for x in schema.split(",")]

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("seq")
        program = table.column("program_id")[0].as_py()
        cols = {k: table.column(k).to_pylist() for k in table.column_names if k != "program_id"}
        rows = list(fn(program, cols))
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * len(names), arrow_types(schema))], names=names)

    return kernel_columns(trace, *more).groupBy("program_id").applyInArrow(run, schema)


def _streamed(trace: DataFrame, fn, schema: str) -> DataFrame:
    """As _grouped for results longer than the program: columns are gathered from sorted batches, and rows leave as they are made."""
    ship(trace.sparkSession)
    names, types = [x.strip().split()[0] for x in schema.split(",")], arrow_types(schema)

    def out(program, cols):
        rows = iter(fn(program, cols))
        while some := list(islice(rows, PIECE)):
            yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*some), types)], names=names)

    def run(batches):
        at, cols = None, {}
        for program, more, first in pieces(batches):
            if first:
                if cols:
                    yield from out(at, cols)
                at, cols = program, {k: [] for k in more}
            for k, v in more.items():
                cols[k] += v
        if cols:
            yield from out(at, cols)

    return kernel_columns(trace).repartition("program_id").sortWithinPartitions("program_id", "seq").mapInArrow(run, schema)


def arrow_types(schema: str) -> list[pa.DataType]:
    kinds = {"int": pa.int32(), "bigint": pa.int64(), "string": pa.string(), "double": pa.float64(), "boolean": pa.bool_()}
    return [kinds[x.strip().split()[1]] for x in schema.split(",")]


def run_each(trace: DataFrame, lanes: list[Machine], method: str = "") -> DataFrame:
    """(program_id, lane, cycles, instrs): one sequential run a lane; any core and scheduling method."""

    def fn(program, cols):
        for k, m in enumerate(lanes):
            p = kernels.Program(cols, m)
            yield program, k, kernels.run(p, method), p.n

    return _grouped(trace, fn, schemas.RUN)


def run_shared_order(trace: DataFrame, lanes: list[Machine]) -> DataFrame:
    """Out-of-order lanes that all issue in lane 0's order: cheaper, and approximate for the others."""

    def fn(program, cols):
        p = kernels.Program(cols, lanes[0])
        yield program, 0, kernels.run(p), p.n
        order = sorted(range(p.n), key=lambda i: (p.E[i], i))
        for k, m in enumerate(lanes[1:], 1):
            q = kernels.Program(cols, m)
            try:
                kernels.ranked_sweep(q, order)
            except (RuntimeError, TypeError):  # lane 0's order runs against this lane's graph
                kernels.run(q)
            yield program, k, q.C[-1], q.n

    return _grouped(trace, fn, schemas.RUN)


def swept(lanes: list[Machine], cols: dict[str, list]) -> kernels.LaneSweep:
    """A vector sweep of a whole program, fed in pieces."""
    sweep = kernels.LaneSweep(lanes)
    for at in range(0, len(cols["op"]), PIECE):
        sweep.feed({k: v[at : at + PIECE] for k, v in cols.items()})
    return sweep


def shares(sizes: tuple[int, ...]) -> list[list[int]]:
    """Numbers of lanes in shares of about the work of the largest, which comes first; a vector sweep costs some eight scalar ones."""
    out, room = [], 0
    for n in sorted(sizes, reverse=True):
        if n + 8 > room:
            out.append([])
            room = max(sizes) + 8
        out[-1].append(n)
        room -= n + 8
    return out


class Timed:
    """The first n lanes swept at once and by the scalar kernel, fed with the same columns; CPU seconds of both."""

    def __init__(self, lanes: list[Machine]):
        self.lanes, self.vector_s, self.sequential_s = lanes, 0.0, 0.0
        self.vector = self.scalars = None

    def feed(self, cols: dict[str, list]) -> None:
        a = time.process_time()
        self.vector = self.vector or kernels.LaneSweep(self.lanes)
        self.vector.feed(cols)
        b = time.process_time()
        self.scalars = self.scalars or [kernels.ScalarSweep(m) for m in self.lanes]
        for s in self.scalars:
            s.feed(cols)
        c = time.process_time()
        self.vector_s += b - a
        self.sequential_s += c - b

    def row(self, program: int) -> tuple:
        if self.vector.cycles().tolist() != [s.cycles() for s in self.scalars]:
            raise RuntimeError(f"vector and scalar cycles of program {program} differ")
        return program, len(self.lanes), self.vector_s, self.sequential_s


def vector_times(trace: DataFrame, lanes: list[Machine], sizes: tuple[int, ...]) -> DataFrame:
    """(program_id, lanes, vector_s, sequential_s): CPU seconds of the first lanes swept at once, and of the scalar kernel lane by lane.

    Both are taken in the worker, on the same columns as they stream by: reading, shuffling and the job itself are in
    neither. A share of the sizes is a task of its own over the one shuffled trace.
    """
    spark = trace.sparkSession
    ship(spark)
    schema = "program_id int, lanes int, vector_s double, sequential_s double"

    def timed(share):
        def rows(program, runs):
            cols = zip(*(r.row(program) for r in runs))
            return pa.record_batch([pa.array(c, t) for c, t in zip(cols, arrow_types(schema))], names=["program_id", "lanes", "vector_s", "sequential_s"])

        def run(batches):
            at, runs = None, []
            for program, cols, first in pieces(batches):
                if first:
                    if runs:
                        yield rows(at, runs)
                    at, runs = program, [Timed(lanes[:n]) for n in share]
                for r in runs:
                    r.feed(cols)
            if runs:
                yield rows(at, runs)

        return run

    # A deal of its own, or each share would sort the lines and number them again; a fixed number of parts keeps small programs apart.
    parts = 8 * spark.sparkContext.defaultParallelism
    dealt = kernel_columns(trace).repartition(parts, F.col("program_id"), F.lit("sweeps")).sortWithinPartitions("program_id", "seq")
    return reduce(DataFrame.union, [dealt.mapInArrow(timed(share), schema) for share in shares(sizes)])


def per_instr(runs: DataFrame) -> DataFrame:
    return runs.withColumn("cyc_per_instr", F.round(F.col("cycles") / F.col("instrs"), 6))


def paths(trace: DataFrame, lanes: list[Machine], method: str = "") -> DataFrame:
    """The critical path of each program and lane, an edge's terms a row each; hop 0 is the first edge."""

    def fn(program, cols):
        for k, m in enumerate(lanes):
            p = kernels.Program(cols, m)
            kernels.run(p, method)
            found = kernels.critical_path(p)
            for hop, (w, ws, i, s, kind, terms) in enumerate(reversed(found)):
                for term, cycles in terms or [("order", 0)]:
                    yield program, k, hop, p.seq[w], ws, p.seq[i], s, kind, term, cycles

    return _grouped(trace, fn, schemas.PATH)


def breakdown(trace: DataFrame, lanes: list[Machine], method: str = "") -> DataFrame:
    """(program_id, lane, term, cycles): the critical path's cycles by term, summed where the path is found."""

    def fn(program, cols):
        for k, m in enumerate(lanes):
            p = kernels.Program(cols, m)
            kernels.run(p, method)
            total: dict[str, int] = {}
            for *_, terms in kernels.critical_path(p):
                for term, cycles in terms:
                    if cycles:
                        total[term] = total.get(term, 0) + cycles
            for term in sorted(total):
                yield program, k, term, total[term]

    return _grouped(trace, fn, "program_id int, lane int, term string, cycles bigint")


def edge_slacks(p: kernels.Program, end: int) -> Iterator[tuple]:
    """(source, stage, destination, stage, kind, w, slack) of every edge of a run program, by positions; edges that lead nowhere are left out.

    Vertices are met latest first; what is kept of each is the longest way from it to the end.
    """
    stages = ("F", "E", "C") if p.D is None else ("F", "D", "E", "C")
    place, n = {s: k for k, s in enumerate(stages)}, len(stages)
    at = np.empty((p.n, n), np.int64)
    for k, s in enumerate(stages):
        at[:, k] = {"F": p.F, "D": p.D, "E": p.E, "C": p.C}[s]
    order = np.argsort(at.reshape(-1), kind="stable")[::-1]
    tail = array("q", [-1]) * (p.n * n)  # -1: no way
    tail[-1] = 0
    for lo in range(0, len(order), PIECE):
        for v in order[lo : lo + PIECE].tolist():
            rest = tail[v]
            if rest < 0:
                continue
            i, s = v // n, stages[v % n]
            for w, ws, kind, own, terms in kernels.parents(p, i, s):
                c = sum(x for _, x in terms)
                u = w * n + place[ws]
                if rest + c > tail[u]:
                    tail[u] = rest + c
                yield w, ws, i, s, kind, c, end - own - c - rest


def slack(trace: DataFrame, m: Machine, method: str = "") -> DataFrame:
    """(program_id, src_seq, src_stage, dst_seq, dst_stage, kind, w, slack) of every edge."""

    def fn(program, cols):
        p = kernels.Program(cols, m)
        if p.n:
            end = kernels.run(p, method)
            for w, ws, i, s, *rest in edge_slacks(p, end):
                yield program, p.seq[w], ws, p.seq[i], s, *rest

    return _streamed(trace, fn, "program_id int, src_seq bigint, src_stage string, dst_seq bigint, dst_stage string, kind string, w bigint, slack bigint")


def work_counters(trace: DataFrame, m: Machine) -> DataFrame:
    """What the updated list costs: (program_id, instrs, live_vertices, list_entries), the last counting insertions and moves."""

    def fn(program, cols):
        p = kernels.Program(cols, m)
        kernels.sliding_updated(p, m.window)
        yield program, p.n, p.live, p.n + p.moves

    return _grouped(trace, fn, "program_id int, instrs bigint, live_vertices bigint, list_entries bigint")


def improvements(runs: DataFrame, names: list[str]) -> DataFrame:
    """(program_id, scenario, cycles, improvement, speedup) against lane 0."""
    base = runs.where("lane = 0").select("program_id", F.col("cycles").alias("_base"))
    named = F.element_at(F.array(*map(F.lit, names)), F.col("lane") + 1)
    d = runs.join(base, "program_id")
    return d.select(
        "program_id", named.alias("scenario"), "cycles", F.round(1 - F.col("cycles") / F.col("_base"), 6).alias("improvement"), F.round(F.col("_base") / F.col("cycles"), 6).alias("speedup")
    )


def interaction(runs: DataFrame) -> DataFrame:
    """(program_id, gain_a, gain_b, gain_both, interaction) of lanes base, a, b, both."""
    wide = runs.groupBy("program_id").pivot("lane", [0, 1, 2, 3]).agg(F.first("cycles"))
    c = [F.col(str(k)) for k in range(4)]
    return wide.select("program_id", (c[0] - c[1]).alias("gain_a"), (c[0] - c[2]).alias("gain_b"), (c[0] - c[3]).alias("gain_both"), (c[1] + c[2] - c[0] - c[3]).alias("interaction"))


def compared(model: DataFrame, reference: DataFrame) -> DataFrame:
    """(program_id, model, sim, diff_pct): absolute difference of cycles per instruction."""
    a = model.select("program_id", (F.col("cycles") / F.col("instrs")).alias("model"))
    b = reference.select("program_id", (F.col("cycles") / F.col("instrs")).alias("sim"))
    return a.join(b, "program_id").select("program_id", F.round("model", 6).alias("model"), F.round("sim", 6).alias("sim"), F.round(100 * F.abs(F.col("model") - F.col("sim")) / F.col("sim"), 6).alias("diff_pct"))


def geometric_mean(d: DataFrame, column: str, floor: float = 1e-6) -> DataFrame:
    """Geometric mean, average and maximum over programs; zero differences count as ``floor``."""
    return d.agg(F.round(F.exp(F.avg(F.log(F.greatest(F.col(column), F.lit(floor))))), 6).alias("geo_mean"), F.round(F.avg(column), 6).alias("average"), F.round(F.max(column), 6).alias("maximum"))


def top_critical(path_rows: DataFrame, k: int = 5) -> DataFrame:
    """The k instructions of most critical cycles of each program."""
    d = path_rows.groupBy("program_id", F.col("dst_seq").alias("seq")).agg(F.sum("w").alias("cycles"))
    rank = F.row_number().over(Window.partitionBy("program_id").orderBy(F.desc("cycles"), "seq"))
    return d.withColumn("rank", rank).where(F.col("rank") <= k)
