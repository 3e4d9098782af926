"""The explicit event graph as DataFrame rules: vertices, edges, validity, generic paths.

For validity, what-if edits and checks, on traces whose programs fit a task; longer runs use the kernels, which
generate the same edges on the fly and never store them. Every rule is a projection or a window over the
program's order, so one exchange by program serves them all; last writers are found
by ``last(..., ignorenulls)`` over (program, register), not by a range join.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.configs import Machine
from critgraph.runtime import materialise, ship

def _by_seq():
    return Window.partitionBy("program_id").orderBy("seq")


def latency(m: Machine) -> Column:
    """Execution latency of a trace row: its class's latency, a load's data cycles added."""
    pairs = [x for op, c in m.latency.items() for x in (F.lit(op), F.lit(c))]
    memory = F.lit(m.memory) if m.memory is not None else F.coalesce(F.col("dmem_cycles"), F.lit(0))
    return (F.create_map(*pairs)[F.col("op_class")] + F.when(F.col("op_class") == "LOAD", memory).otherwise(0)).cast("int")


def occupancy(m: Machine) -> Column:
    return F.when(F.col("op_class").isin(*sorted(m.blocking)), latency(m)).otherwise(1).cast("int")


def unit_class(m: Machine) -> Column:
    known = {op: u for op, u in m.unit_of.items() if u in m.units}
    out = F.lit(None).cast("string")
    for op, u in known.items():
        out = F.when(F.col("op_class") == op, u).otherwise(out)
    return out


def fetch_cycles(m: Machine) -> Column:
    return F.lit(0) if m.ideal_fetch else F.coalesce(F.col("imem_cycles"), F.lit(0))


def vertices(trace: DataFrame, stages: tuple[str, ...] = ("F", "E", "C"), mshr: bool = False) -> DataFrame:
    """A row per event: memory stages (M, or MS and MC) only for loads and stores, EC only for instructions that use a unit."""
    memory = F.col("op_class").isin("LOAD", "STORE")
    found = []
    for s in stages:
        for name in ("MS", "MC") if s == "M" and mshr else (s,):
            row = F.struct(F.lit(name).alias("stage"), F.lit(schemas.STAGE_ORD[name]).alias("stage_ord"))
            found.append(F.when(memory, row) if s == "M" else row)
    d = trace.select("program_id", "seq", "op_class", F.explode(F.array_compact(F.array(*found))).alias("v"))
    return d.select("program_id", "seq", "v.stage", "v.stage_ord", "op_class", (F.col("seq") * 8 + F.col("v.stage_ord")).cast("bigint").alias("vid"))


def _edge(d: DataFrame, src: Column, src_stage: str, dst_stage: str, kind: str, w: Column, dst: Column | None = None) -> DataFrame:
    dst = F.col("seq") if dst is None else dst
    return d.select(
        "program_id", src.cast("bigint").alias("src_seq"), F.lit(src_stage).alias("src_stage"), dst.cast("bigint").alias("dst_seq"), F.lit(dst_stage).alias("dst_stage"),
        F.lit(kind).alias("kind"), w.cast("int").alias("w"),
    ).where("src_seq is not null and dst_seq is not null")


def pipeline(trace: DataFrame, m: Machine) -> DataFrame:
    """Edges between an instruction's own events."""
    if m.core == "inorder":
        return _edge(trace, F.col("seq"), "F", "E", "pipe", F.lit(m.decode)).unionByName(_edge(trace, F.col("seq"), "E", "C", "pipe", latency(m)))
    parts = [_edge(trace, F.col("seq"), "F", "D", "pipe", F.lit(m.decode)), _edge(trace, F.col("seq"), "D", "E", "pipe", F.lit(1)), _edge(trace, F.col("seq"), "E", "C", "pipe", latency(m))]
    return reduce(DataFrame.unionByName, parts)


def control(trace: DataFrame, m: Machine) -> DataFrame:
    """Front-end chain; after a mispredicted branch, its execution in place of its fetch."""
    miss = F.lag("mispredicted").over(_by_seq()) if not m.ideal_branch else F.lit(False)
    d = trace.withColumns({"_p": F.lag("seq").over(_by_seq()), "_m": F.coalesce(miss, F.lit(False)), "_x": F.lag(latency(m)).over(_by_seq())})
    right = _edge(d.where("not _m"), F.col("_p"), "F", "F", "fetch", fetch_cycles(m))
    return right.unionByName(_edge(d.where("_m"), F.col("_p"), "E", "F", "control", F.col("_x") + m.penalty + fetch_cycles(m)))


def chain(trace: DataFrame, stage: str, kind: str, width: int | None) -> DataFrame:
    """Program order of a stage (lag 0) and its bandwidth (lag 1 over ``width`` instructions)."""
    out = _edge(trace.withColumn("_p", F.lag("seq").over(_by_seq())), F.col("_p"), stage, stage, kind, F.lit(0))
    return out if width is None else out.unionByName(width_edges(trace, stage, f"{kind}_bw", width))


def width_edges(trace: DataFrame, stage: str, kind: str, width: int) -> DataFrame:
    return _edge(trace.withColumn("_p", F.lag("seq", width).over(_by_seq())), F.col("_p"), stage, stage, kind, F.lit(1))


def last_writers(trace: DataFrame) -> DataFrame:
    """(program_id, seq, src_seq): the last writer before seq of each register it reads."""
    reads = trace.select("program_id", "seq", F.explode(F.array_distinct(F.array_compact(F.array("src1", "src2")))).alias("reg"), F.lit(None).cast("bigint").alias("w"))
    writes = trace.where("dst is not null").select("program_id", "seq", F.col("dst").alias("reg"), F.col("seq").alias("w"))
    before = Window.partitionBy("program_id", "reg").orderBy("seq", F.col("w").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, -1)
    d = reads.unionByName(writes).withColumn("src_seq", F.last("w", ignorenulls=True).over(before))
    return d.where("w is null and src_seq is not null").select("program_id", "seq", "src_seq").distinct()


def data_reg(trace: DataFrame, m: Machine) -> DataFrame:
    x = trace.select(F.col("program_id").alias("_p"), F.col("seq").alias("_s"), latency(m).alias("_x"))
    d = last_writers(trace).join(x, (F.col("program_id") == F.col("_p")) & (F.col("src_seq") == F.col("_s")))
    return _edge(d, F.col("src_seq"), "E", "E", "data_reg", F.col("_x"))


def data_mem(trace: DataFrame, m: Machine) -> DataFrame:
    """The last store to a load's address, by an as-of window over (program, address)."""
    before = Window.partitionBy("program_id", "addr").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    d = trace.where("addr is not null").withColumn("_p", F.last(F.when(F.col("op_class") == "STORE", F.col("seq")), ignorenulls=True).over(before))
    return _edge(d.where("op_class = 'LOAD'"), F.col("_p"), "E", "E", "data_mem", F.lit(m.forward))


def units(trace: DataFrame, m: Machine, order: str = "seq") -> DataFrame:
    """LRU units: the m-th previous user (in ``order``) of an instruction's unit class; one expression a count of units."""
    d = trace.withColumns({"_u": unit_class(m), "_o": occupancy(m)}).where("_u is not null")
    w = Window.partitionBy("program_id", "_u").orderBy(order)
    src = lag = F.lit(None)
    for k in sorted(set(m.units.values())):
        mine = F.col("_u").isin(*[u for u, c in m.units.items() if c == k])
        src, lag = F.when(mine, F.lag("seq", k).over(w)).otherwise(src), F.when(mine, F.lag("_o", k).over(w)).otherwise(lag)
    return _edge(d.withColumns({"_p": src, "_w": lag}), F.col("_p"), "E", "E", "fu_occ", F.col("_w"))


def unit_depth(trace: DataFrame, m: Machine, order: str = "seq") -> DataFrame:
    """At most ``depth`` instructions within a unit: from the completion (EC) of the depth-th previous user."""
    d = trace.withColumn("_u", unit_class(m)).where("_u is not null")
    w = Window.partitionBy("program_id", "_u").orderBy(order)
    parts = [_edge(d.where(F.col("_u") == u).withColumn("_p", F.lag("seq", k).over(w)), F.col("_p"), "EC", "E", "fu_depth", F.lit(0)) for u, k in sorted(m.depth.items())]
    done = _edge(d.where(F.col("_u").isin(*sorted(m.depth))), F.col("seq"), "E", "EC", "pipe", latency(m))
    return reduce(DataFrame.unionByName, parts, done)


def queues(trace: DataFrame, m: Machine) -> DataFrame:
    """Load, store or joint queues: commit of the size-th previous member."""
    to = "E" if m.core == "inorder" else "D"
    parts = []
    for size, ops in ((m.lsq, ("LOAD", "STORE")), (m.lq, ("LOAD",)), (m.sq, ("STORE",))):
        if size:
            d = trace.where(F.col("op_class").isin(*ops)).withColumn("_p", F.lag("seq", size).over(_by_seq()))
            parts.append(_edge(d, F.col("_p"), "C", to, "queue", F.lit(0)))
    return reduce(DataFrame.unionByName, parts) if parts else _edge(trace.limit(0), F.col("seq"), "C", to, "queue", F.lit(0))


def reorder_buffer(trace: DataFrame, m: Machine) -> DataFrame:
    return _edge(trace.withColumn("_p", F.lag("seq", m.rob).over(_by_seq())), F.col("_p"), "C", "D", "rob", F.lit(0))


def issue_in_order(ranked: DataFrame, m: Machine) -> DataFrame:
    """Issue width over a given issue order: ``ranked`` has a column issue_rank."""
    w = Window.partitionBy("program_id").orderBy("issue_rank")
    return _edge(ranked.withColumn("_p", F.lag("seq", m.ibw).over(w)), F.col("_p"), "E", "E", "issue_bw", F.lit(1))


def issue_rank(trace: DataFrame, lengths: DataFrame) -> DataFrame:
    """The scheduling list as a column: rank of E vertices by path length, then seq."""
    d = trace.join(lengths.where("stage = 'E'").select("program_id", "seq", "cp"), ["program_id", "seq"])
    return d.withColumn("issue_rank", F.row_number().over(Window.partitionBy("program_id").orderBy("cp", "seq")))


def mshr(trace: DataFrame, k: int, miss_above: int = 2, busy: int = 5) -> DataFrame:
    """Miss registers: the request of the k-th previous miss must have left its register."""
    d = trace.where((F.col("op_class") == "LOAD") & (F.col("dmem_cycles") > miss_above)).withColumn("_p", F.lag("seq", k).over(_by_seq()))
    return _edge(d, F.col("_p"), "MS", "MS", "mshr", F.lit(busy))


def base_graph(trace: DataFrame, m: Machine) -> DataFrame:
    """All rules whose order is program order; out-of-order issue and units come with an issue order."""
    parts = [pipeline(trace, m), control(trace, m), data_reg(trace, m), data_mem(trace, m), chain(trace, "C", "commit", m.cbw), queues(trace, m)]
    if m.fbw:
        parts.append(width_edges(trace, "F", "fetch_bw", m.fbw))
    if m.core == "inorder":
        if m.ibw:
            parts.append(chain(trace, "E", "issue", m.ibw))
        if m.units:
            parts.append(units(trace, m))
        if m.depth:
            parts.append(unit_depth(trace, m))
    else:
        parts.append(chain(trace, "D", "dispatch", m.dbw))
        if m.rob:
            parts.append(reorder_buffer(trace, m))
    return reduce(DataFrame.unionByName, parts)


def resource_graph(ranked: DataFrame, m: Machine) -> DataFrame:
    """Edges along an issue order (column issue_rank)."""
    parts = [issue_in_order(ranked, m)] if m.ibw else []
    if m.units:
        parts.append(units(ranked, m, "issue_rank"))
    if m.depth:
        parts.append(unit_depth(ranked, m, "issue_rank"))
    return reduce(DataFrame.unionByName, parts)


ENDS = ("program_id", "src_seq", "src_stage", "dst_seq", "dst_stage")


def merge_parallel(edges: DataFrame) -> DataFrame:
    """One edge a pair of vertices: the heaviest (a lighter parallel edge never binds)."""
    return edges.groupBy(*ENDS).agg(F.max_by("kind", F.struct("w", "kind")).alias("kind"), F.max("w").alias("w")).select(*ENDS, "kind", "w")


def merge_lanes(edges: DataFrame) -> DataFrame:
    """As merge_parallel for vector weights (array column w): lane-wise maximum, null where an edge is absent."""
    best = F.aggregate(F.collect_list("w"), F.lit(None).cast("array<int>"), lambda a, x: F.when(a.isNull(), x).otherwise(F.zip_with(a, x, lambda p, q: F.greatest(p, q))))
    return edges.groupBy(*ENDS).agg(best.alias("w"))


def forward() -> Column:
    """Whether an edge leads on in program order, by stages within an instruction: such edges alone make no cycle."""
    place = lambda c: F.element_at(F.create_map(*(F.lit(x) for kv in schemas.STAGE_ORD.items() for x in kv)), F.col(c))
    later = (F.col("dst_seq") > F.col("src_seq")) | ((F.col("dst_seq") == F.col("src_seq")) & (place("dst_stage") > place("src_stage")))
    return F.coalesce(later, F.lit(False))  # an unknown stage has no place


def validate(edges: DataFrame, verts: DataFrame | None = None) -> DataFrame:
    """(problem, n): negative weights, self-loops, missing end points, edges on or behind a cycle.

    Edges are counted as they are made. A cycle needs an edge against program order, so only programs that have one are searched for cycles.
    """
    edges = edges.select(*ENDS, "w")
    loop = (F.col("src_seq") == F.col("dst_seq")) & (F.col("src_stage") == F.col("dst_stage"))
    found = F.array_compact(F.array(F.when(F.col("w") < 0, F.lit("negative")), F.when(loop, F.lit("self-loop")), F.when(~forward(), F.lit("backward"))))
    count = lambda d, *by: d.groupBy("problem", *by).agg(F.count(F.lit(1)).alias("n"))
    seen = materialise(count(edges.select("program_id", F.explode(found).alias("problem")), "program_id"), "seen")  # a few rows a program
    parts = [seen.where("problem <> 'backward'").select("problem", "n")]
    if verts is not None:
        v = verts.select("program_id", "seq", "stage")
        for end in ("src", "dst"):
            on = ["program_id", "seq", "stage"]
            parts.append(count(edges.select("program_id", F.col(f"{end}_seq").alias("seq"), F.col(f"{end}_stage").alias("stage")).join(v, on, "left_anti").select(F.lit("dangling").alias("problem"))))
    backward = seen.where("problem = 'backward'").select("program_id")
    if backward.limit(1).count():
        parts.append(count(peel(edges.join(F.broadcast(backward), "program_id", "left_semi")).select(F.lit("cycle").alias("problem"))))
    return reduce(DataFrame.unionByName, parts).groupBy("problem").agg(F.sum("n").cast("bigint").alias("n"))


def peel(edges: DataFrame) -> DataFrame:
    """The edges whose source never runs out of parents, those on or behind a cycle: empty iff acyclic. A program fits a task, of any depth."""
    ship(edges.sparkSession)

    def run(table):
        import pyarrow as pa

        ends = list(zip(*(table.column(c).to_pylist() for c in ENDS[1:])))
        out: dict[tuple, list] = {}
        degree: dict[tuple, int] = {}
        for a, s, b, t in ends:
            out.setdefault((a, s), []).append((b, t))
            degree[b, t] = degree.get((b, t), 0) + 1
        ready = [v for v in out if v not in degree]
        while ready:
            for u in out.pop(ready.pop(), ()):
                degree[u] -= 1
                if not degree[u]:
                    ready.append(u)
        return table.filter(pa.array([(a, s) in out for a, s, _, _ in ends], pa.bool_()))

    e = edges.select(F.col("program_id").cast("int"), F.col("src_seq").cast("bigint"), "src_stage", F.col("dst_seq").cast("bigint"), "dst_stage")
    return e.groupBy("program_id").applyInArrow(run, "program_id int, src_seq bigint, src_stage string, dst_seq bigint, dst_stage string")


def longest(edges: DataFrame) -> DataFrame:
    """(program_id, seq, stage, cp) of any acyclic graph whose program fits a task: topological order, then relaxation."""
    ship(edges.sparkSession)

    def run(table):
        import pyarrow as pa

        at = topological(table)
        pid = table.column("program_id")[0].as_py()
        keys = sorted(at)
        return pa.table({"program_id": pa.array([pid] * len(keys), pa.int32()), "seq": pa.array([k[0] for k in keys], pa.int64()), "stage": [k[1] for k in keys], "cp": pa.array([at[k] for k in keys], pa.int64())})

    return edges.select("program_id", "src_seq", "src_stage", "dst_seq", "dst_stage", F.col("w").cast("int")).groupBy("program_id").applyInArrow(run, "program_id int, seq bigint, stage string, cp bigint")


def topological(table) -> dict[tuple[int, str], int]:
    """Longest distances of one program's edges (Arrow table)."""
    out: dict[tuple, list] = {}
    degree: dict[tuple, int] = {}
    for a, s, b, t, w in zip(*(table.column(c).to_pylist() for c in ("src_seq", "src_stage", "dst_seq", "dst_stage", "w"))):
        out.setdefault((a, s), []).append(((b, t), w))
        degree[b, t] = degree.get((b, t), 0) + 1
        degree.setdefault((a, s), 0)
    at = {v: 0 for v in degree}
    ready = [v for v, d in degree.items() if not d]
    done = 0
    while ready:
        v = ready.pop()
        done += 1
        for u, w in out.get(v, ()):
            at[u] = max(at[u], at[v] + w)
            degree[u] -= 1
            if not degree[u]:
                ready.append(u)
    if done != len(at):
        raise ValueError("the graph has a cycle")
    return at


def relax(edges: DataFrame, rounds: int = 200) -> DataFrame:
    """As longest, by joins alone, for graphs of small depth: each round extends all paths by an edge."""
    edges = materialise(edges.select(*ENDS, "w"), "edges")  # read in every round
    src = edges.select("program_id", F.col("src_seq").alias("seq"), F.col("src_stage").alias("stage"))
    dst = edges.select("program_id", F.col("dst_seq").alias("seq"), F.col("dst_stage").alias("stage"))
    at = materialise(src.union(dst).distinct().withColumn("cp", F.lit(0).cast("bigint")), "relax")
    total = 0
    for _ in range(rounds):
        step = edges.join(at.withColumnsRenamed({"seq": "src_seq", "stage": "src_stage"}), ["program_id", "src_seq", "src_stage"])
        step = step.select("program_id", F.col("dst_seq").alias("seq"), F.col("dst_stage").alias("stage"), (F.col("cp") + F.col("w")).alias("cp"))
        at = materialise(at.union(step).groupBy("program_id", "seq", "stage").agg(F.max("cp").alias("cp")), "relax")
        now = at.agg(F.sum("cp")).first()[0] or 0
        if now == total:
            return at
        total = now
    raise RuntimeError("more rounds are needed: use longest")


def critical(edges: DataFrame, lengths: DataFrame) -> DataFrame:
    """Tight edges: those on which a longest path may run (w = cp(dst) - cp(src))."""
    a = lengths.select("program_id", F.col("seq").alias("src_seq"), F.col("stage").alias("src_stage"), F.col("cp").alias("_a"))
    b = lengths.select("program_id", F.col("seq").alias("dst_seq"), F.col("stage").alias("dst_stage"), F.col("cp").alias("_b"))
    return edges.join(a, ["program_id", "src_seq", "src_stage"]).join(b, ["program_id", "dst_seq", "dst_stage"]).where("_b = _a + w").select(*ENDS, "kind", "w")


def without(edges: DataFrame, condition: Column) -> DataFrame:
    """The graph without the edges that meet a condition (a vertex goes with all its edges)."""
    return edges.where(~condition)


def without_vertex(edges: DataFrame, seq: int, stage: str) -> DataFrame:
    return without(edges, ((F.col("src_seq") == seq) & (F.col("src_stage") == stage)) | ((F.col("dst_seq") == seq) & (F.col("dst_stage") == stage)))


# -- speculation, fusing, cracking: edits of edges and traces --------------------------------


def predict_values(edges: DataFrame, selected: DataFrame) -> DataFrame:
    """Right value predictions: the register edges of the selected instructions (program_id, seq) go."""
    s = selected.select("program_id", F.col("seq").alias("src_seq"), F.lit("data_reg").alias("kind"))
    return edges.join(s, ["program_id", "src_seq", "kind"], "left_anti").select(*ENDS, "kind", "w")


def mispredict_values(edges: DataFrame, selected: DataFrame, penalty: int) -> DataFrame:
    """Wrong value predictions: those edges carry a penalty."""
    s = selected.select("program_id", F.col("seq").alias("src_seq"), F.lit("data_reg").alias("kind"), F.lit(penalty).alias("_x")).distinct()
    d = edges.join(s, ["program_id", "src_seq", "kind"], "left")
    return d.select(*ENDS, "kind", (F.col("w") + F.coalesce("_x", F.lit(0))).cast("int").alias("w"))


def recovery(edges: DataFrame, pairs: DataFrame, penalty: int, stage: str = "F") -> DataFrame:
    """Recovery: an edge from E of the speculated instruction to the affected event, for (program_id, src_seq, dst_seq)."""
    return edges.unionByName(pairs.select("program_id", "src_seq", F.lit("E").alias("src_stage"), "dst_seq", F.lit(stage).alias("dst_stage"), F.lit("recovery").alias("kind"), F.lit(penalty).cast("int").alias("w")))


def fuse(edges: DataFrame, pairs: DataFrame, cycles: int) -> DataFrame:
    """Fusion: the consumer's vertices collapse into the producer's; edges within the pair but the fused execution go.

    pairs: (program_id, first, second), neither in two pairs. The fused instruction executes in ``cycles``.
    """
    p = pairs.select("program_id", F.col("second").alias("_b"), F.col("first").alias("_a"))
    one = pairs.select("program_id", F.col("first").alias("_f")).distinct()
    d = edges
    for end in ("src_seq", "dst_seq"):
        q = p.select(F.col("program_id").alias("_p"), "_b", "_a")
        d = d.join(q, (F.col("program_id") == F.col("_p")) & (F.col(end) == F.col("_b")), "left").withColumn(end, F.coalesce("_a", end)).drop("_p", "_a", "_b")
    f = one.select(F.col("program_id").alias("_p"), "_f")
    d = d.join(f, (F.col("program_id") == F.col("_p")) & (F.col("src_seq") == F.col("_f")), "left")
    executes = F.col("_f").isNotNull() & (F.col("src_stage") == "E") & ((F.col("dst_stage") != "E") | F.col("kind").isin("data_reg"))
    d = d.withColumn("w", F.when(executes, F.lit(cycles)).otherwise(F.col("w")).cast("int")).select(*ENDS, "kind", "w")
    return merge_parallel(d.where("src_seq <> dst_seq or src_stage <> dst_stage"))


def fusible_pairs(trace: DataFrame) -> DataFrame:
    """(program_id, first, second): adjacent multiply and add, the product read by no other instruction."""
    readers = last_writers(trace).groupBy("program_id", "src_seq").agg(F.count(F.lit(1)).alias("k"), F.min("seq").alias("second"))
    d = trace.select("program_id", F.col("seq").alias("second"), F.col("op_class").alias("b"), F.lag("op_class").over(_by_seq()).alias("a"), F.lag("seq").over(_by_seq()).alias("first"))
    adds = ((F.col("a") == "INT_MUL") & (F.col("b") == "INT_ALU")) | ((F.col("a") == "FP_MUL") & (F.col("b") == "FP_ALU"))
    one = readers.where("k = 1").select("program_id", F.col("src_seq").alias("first"), "second")
    return d.where(adds).join(one, ["program_id", "first", "second"]).select("program_id", "first", "second")


def crack(trace: DataFrame, condition: Column) -> DataFrame:
    """Cracking: a complex instruction becomes a load micro-op (into a spare register) and the operation on its result."""
    spare = F.lit(schemas.REGISTERS - 1)
    none = F.lit(None).cast("int")
    load = F.struct(F.lit(0).alias("part"), F.lit("LOAD").alias("op_class"), none.alias("src1"), none.alias("src2"), spare.alias("dst"), F.col("addr").alias("addr"))
    rest = F.struct(F.lit(1).alias("part"), F.col("op_class"), F.col("src1"), spare.alias("src2"), F.col("dst"), F.lit(None).cast("bigint").alias("addr"))
    same = F.struct(F.lit(0).alias("part"), F.col("op_class"), F.col("src1"), F.col("src2"), F.col("dst"), F.col("addr"))
    d = trace.withColumn("_u", F.explode(F.when(condition, F.array(load, rest)).otherwise(F.array(same))))
    other = [c for c in trace.columns if c not in ("op_class", "src1", "src2", "dst", "addr", "seq")]
    order = Window.partitionBy("program_id").orderBy("seq", "_u.part")
    return d.select(*other, (F.row_number().over(order) - 1).cast("bigint").alias("seq"), "_u.op_class", "_u.src1", "_u.src2", "_u.dst", "_u.addr")


def frontend_closed_form(trace: DataFrame) -> DataFrame:
    """(program_id, seq, cp) of fetch without mispredictions and with no width: a running sum, no kernel."""
    f = F.when(F.col("seq") > 0, F.col("imem_cycles")).otherwise(0)
    return trace.select("program_id", "seq", F.sum(f).over(_by_seq().rowsBetween(Window.unboundedPreceding, 0)).cast("bigint").alias("cp"))


def commit_closed_form(ready: DataFrame, width: int) -> DataFrame:
    """(program_id, seq, cp) of in-order commit of width b from ready times.

    A run of commits ending at n, started by a ready instruction j, takes (n - j) div b cycles at least. In each residue of
    seq modulo b that is a running maximum of ready - seq div b; in-order commit takes the running maximum first.
    """
    d = ready.withColumn("_r", F.max("ready").over(_by_seq().rowsBetween(Window.unboundedPreceding, 0)))
    lane = Window.partitionBy("program_id", F.col("seq") % width).orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    turn = F.expr(f"seq div {width}")
    return d.select("program_id", "seq", (F.max(F.col("_r") - turn).over(lane) + turn).cast("bigint").alias("cp"))
