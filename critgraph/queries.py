"""The engine's queries: every method, variant, baseline, measure and workload on the given tables."""

from __future__ import annotations


from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from critgraph import configs, costs
from critgraph.configs import P_INO, P_OOO
from critgraph.operators import baselines, blocks, explicit, graph, runs, toys, valuepred, whatif
from critgraph.plans import chunks, oracles, planner
from critgraph.plans.oracles import with_trace
from critgraph.runtime import materialise
from critgraph.schemas import LOAD, OPS, TERM_OF_OP
from critgraph.sources import tables, traces
from critgraph.streaming import runs as streams

#: Instructions of each program that the tick-by-tick simulator runs (as the paper runs a slice of each benchmark).
SLICE = 2000
TRACE_COLUMNS = ("program_id", "seq", "op_class", "src1", "src2", "dst", "addr")
FRONT = whatif.front_end(P_INO)


def _t(spark: SparkSession, sf_dir: str) -> DataFrame:
    return traces.from_lineitem(spark, sf_dir)


def _named(d: DataFrame, names: list[str]) -> DataFrame:
    return d.select("program_id", F.element_at(F.array(*map(F.lit, names)), F.col("lane") + 1).alias("scenario"), "cycles")


def _lane_machines(spark: SparkSession, sf_dir: str, n: int = 32) -> list[configs.Machine]:
    """Irregular lanes from the first vectors of ``embeddings`` (nine vectors, n elements: a bounded read)."""
    v = tables.table(spark, sf_dir, "embeddings").orderBy("vec_id").limit(9).select("embedding").collect()
    return configs.lanes_from_embeddings(P_INO, [list(map(float, r[0][:n])) for r in v])


def trace_lineitem(s, d):
    return _t(s, d).select(*TRACE_COLUMNS, "imem_cycles", "dmem_cycles", "mispredicted")


def trace_lineitem_distributed(s, d):
    return traces.from_lineitem(s, d, distributed=True).select(*TRACE_COLUMNS, "imem_cycles", "dmem_cycles", "mispredicted")


def trace_events(s, d):
    return traces.from_events(tables.table(s, d, "events")).select(*TRACE_COLUMNS, "dmem_cycles", "mispredicted")


def trace_documents(s, d):
    return traces.from_documents(s, d).select(*TRACE_COLUMNS)


def trace_conversations(s, d):
    return traces.from_conversations(s, d).select(*TRACE_COLUMNS)


def op_mix(s, d):
    return baselines.counts(_t(s, d))


def fold_wrong_path(s, d):
    return _t(s, d).select("program_id", "seq", "imem_cycles")


def _extent(t):
    return t.groupBy("program_id").agg(F.count(F.lit(1)).alias("n"), F.min("seq").alias("first_seq"), F.max("seq").alias("last_seq"))


def slice_instr(s, d):
    return _extent(traces.sliced(_t(s, d), 500, 1000))


def slice_block(s, d):
    return _extent(traces.sliced(_t(s, d), 50, 100, "block"))


def sample_regions(s, d):
    return traces.sample_regions(_t(s, d)).withColumn("weight", F.round("weight", 6))


def edges_frontend(s, d):
    return graph.width_edges(_t(s, d), "F", "fetch_bw", P_INO.fbw)


def edges_control(s, d):
    return graph.control(_t(s, d), P_INO)


def edges_commit(s, d):
    return graph.chain(_t(s, d), "C", "commit", P_INO.cbw)


def edges_issue(s, d):
    return graph.chain(_t(s, d), "E", "issue", P_INO.ibw)


def edges_pipeline(s, d):
    return graph.pipeline(_t(s, d), P_INO)


def edges_data_reg(s, d):
    return graph.data_reg(_t(s, d), P_INO)


def edges_data_mem(s, d):
    return graph.data_mem(_t(s, d), P_INO)


def edges_fu_inorder(s, d):
    return graph.units(_t(s, d), P_INO)


def edges_queue(s, d):
    return graph.queues(_t(s, d), P_INO)


def graph_size(s, d):
    t = _t(s, d)
    e = graph.merge_parallel(graph.base_graph(t, P_INO)).groupBy("program_id").agg(F.count(F.lit(1)).alias("edges"))
    return graph.vertices(t).groupBy("program_id").agg(F.count(F.lit(1)).alias("vertices")).join(e, "program_id").select("program_id", "vertices", "edges")


def graph_valid(s, d):
    e = graph.base_graph(materialise(_t(s, d), "trace"), P_INO)  # read by every rule
    return graph.validate(e)


def graph_longest(s, d):
    return explicit.cycles(_t(s, d), lambda: explicit.Longest(P_INO)).select("program_id", "cycles")


def ooo_explicit(s, d):
    """Two passes on the explicit graph: base lengths, issue order, resource edges, lengths."""
    return explicit.cycles(_t(s, d), lambda: explicit.TwoPass(P_OOO)).select("program_id", "cycles")


def frontend_chain(s, d):
    return graph.frontend_closed_form(_t(s, d))


def commit_chain(s, d):
    t = _t(s, d).select("program_id", "seq", (F.col("seq") % 7 * 3 + graph.latency(P_INO)).alias("ready"))
    return graph.commit_closed_form(t, 2)


#: The worked example with the latencies of ``part``; a miss register is busy until a cycle before its data.
TOY = toys.toy("mul", 1, "memory", "memory - 1")
TOYS = {"base": TOY, "fast multiply": toys.toy(2, 1, "memory", "memory - 1"), "second register": toys.toy("mul", 2, "memory"), "both": toys.toy(2, 2, "memory")}


def toy_base(s, d):
    return toys.cycles_over(s, d, {"base": TOYS["base"]})


def toy_whatif(s, d):
    return toys.cycles_over(s, d, TOYS)


def toy_path(s, d):
    """The base graph's tight edges on the path of the multiplier and on the other one."""
    costs = toys.latencies(s, d)
    e = toys.edges_for(costs, TOY)
    return toys.of_costs(costs, graph.critical(e, graph.longest(e))).select("mul", "memory", "parts", F.concat("src_stage", F.col("src_seq").cast("string")).alias("src"), F.concat("dst_stage", F.col("dst_seq").cast("string")).alias("dst"), "w")


def toy_without_mul(s, d):
    costs = toys.latencies(s, d)
    e = graph.without_vertex(toys.edges_for(costs, TOY), 2, "E")
    return toys.of_costs(costs, graph.longest(e), ["without multiplier"]).groupBy("case_name", "mul", "memory", "parts").agg(F.max("cp").alias("cycles"))


def toy_fused(s, d):
    costs = toys.latencies(s, d)
    pairs = costs.select("program_id", F.lit(2).cast("bigint").alias("first"), F.lit(3).cast("bigint").alias("second"))
    one, two = (graph.longest(graph.fuse(toys.edges_for(costs, rows), pairs, 2)) for rows in (TOY, TOYS["second register"]))
    both = two.unionByName(one.withColumn("program_id", F.col("program_id") + toys.CASE_PROGRAMS))
    return toys.of_costs(costs, both, ["fused, second register", "fused, one register"]).groupBy("case_name", "mul", "memory", "parts").agg(F.max("cp").alias("cycles"))


FPU = {"pipelined": toys.fpu(1, "memory"), "blocking": toys.fpu("mul", "memory")}
DEPTH = {"unlimited": toys.fpu_depth(None, "memory", "mul"), "depth 3": toys.fpu_depth(3, "memory", "mul")}
CRACK = {"whole": toys.crack_example(False, "mul", "memory"), "cracked": toys.crack_example(True, "mul", "memory")}
BRANCH = {"right": toys.branch(False, x="mul", f_miss="memory"), "wrong": toys.branch(True, x="mul", f_miss="memory")}


def fu_pipelined(s, d):
    return toys.lengths_over(s, d, {"pipelined": FPU["pipelined"]})


def fu_blocking(s, d):
    return toys.lengths_over(s, d, {"blocking": FPU["blocking"]})


def fu_depth(s, d):
    return toys.lengths_over(s, d, DEPTH)


def crack_example(s, d):
    return toys.lengths_over(s, d, CRACK)


def spec_branch(s, d):
    return toys.lengths_over(s, d, BRANCH)


def toy_sql_path(s, d):
    """The toy's critical path by the SQL table function."""
    from critgraph.functions.sql import register

    register(s)
    costs = toys.latencies(s, d)
    path = s.sql("SELECT p.* FROM critical_path(TABLE({e}) PARTITION BY program_id ORDER BY dst_seq) AS p", e=toys.edges_for(costs, TOY))
    return toys.of_costs(costs, path).drop("program_id")


def ino_cycles(s, d):
    return runs.per_instr(planner.run(_t(s, d), [P_INO])).drop("lane")


def ino_lanes(s, d):
    return runs.run_lanes(_t(s, d), list(FRONT.values())).select("program_id", "lane", "cycles")


def lanes_32(s, d):
    return runs.run_lanes(_t(s, d), _lane_machines(s, d)).select("program_id", "lane", "cycles")


def lanes_sequential(s, d):
    return runs.run_each(_t(s, d), _lane_machines(s, d)).select("program_id", "lane", "cycles")


def ino_chunked(s, d):
    return chunks.run_chunked(_t(s, d), P_INO, 500).select("program_id", "cycles", "instrs")


def ino_planned(s, d):
    return planner.run(_t(s, d), [P_INO, P_INO.edit(name="same"), FRONT["both"]]).select("program_id", "lane", "cycles")


def frontend_ino(s, d):
    return whatif.compare(_t(s, d), FRONT).drop("speedup")


def frontend_ooo(s, d):
    return whatif.compare(_t(s, d), whatif.front_end(P_OOO)).drop("speedup")


def frontend_interaction(s, d):
    return runs.interaction(runs.run_lanes(_t(s, d), list(FRONT.values())))


def breakdown_ino(s, d):
    return runs.breakdown(_t(s, d), [P_INO]).drop("lane")


def breakdown_ino_total(s, d):
    return breakdown_ino(s, d).groupBy("program_id").agg(F.sum("cycles").alias("cycles"))


def breakdown_ooo(s, d):
    return runs.breakdown(_t(s, d), [P_OOO]).drop("lane")


def breakdown_cube(s, d):
    b = breakdown_ino(s, d).join(tables.table(s, d, "nation").select(F.col("n_nationkey").alias("program_id"), F.col("n_regionkey").alias("region")), "program_id")
    return b.cube("region", "term").agg(F.sum("cycles").alias("cycles"))


def _path_cycles(t):
    return runs.paths(t, [P_INO]).groupBy("program_id").agg(F.sum("w").cast("bigint").alias("cycles"))


def critical_path_ino(s, d):
    return _path_cycles(materialise(_t(s, d), "trace"))


def top_critical_pcs(s, d):
    return runs.top_critical(runs.paths(_t(s, d), [P_INO]))


def path_overlap(s, d):
    """Edges on the critical path of both cores, and those of the in-order core alone."""
    p = runs.paths(_t(s, d), [P_INO, P_OOO.edit(core="ooo")]).select("program_id", "lane", "src_seq", "src_stage", "dst_seq", "dst_stage").distinct()
    a, b = (p.where(F.col("lane") == k).drop("lane") for k in (0, 1))
    n = lambda x, k: x.groupBy("program_id").agg(F.count(F.lit(1)).alias("n")).select("program_id", F.lit(k).alias("kind"), "n")
    return n(a.intersect(b), "both").unionByName(n(a.exceptAll(b), "in order only"))


def slack_ino(s, d):
    x = runs.slack(_t(s, d), P_INO)
    return x.groupBy("program_id", "kind").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("slack") == 0).cast("bigint")).alias("critical"), F.min("slack").alias("least"))


def secondary_path(s, d):
    return whatif.secondary(_t(s, d), P_INO)


def limits_ino(s, d):
    return whatif.compare(_t(s, d), whatif.limits(P_INO))


def scenario_grid(s, d):
    g = configs.grid(P_INO, fbw=[1, 2, 4], ibw=[1, 2])
    return _named(planner.run(_t(s, d), g), [m.name for m in g])


def prior_graph_ino(s, d):
    return runs.run_each(_t(s, d), [P_INO.without_resources()]).select("program_id", "cycles")


def ooo_two_pass(s, d):
    return runs.run_each(_t(s, d), [P_OOO], "two_pass").select("program_id", "cycles")


def ooo_cycles(s, d):
    return runs.per_instr(planner.run(_t(s, d), [P_OOO])).drop("lane")


def ooo_approximate(s, d):
    return runs.per_instr(runs.run_each(_t(s, d), [P_OOO], "fixed")).drop("lane")


def ooo_window(s, d):
    sizes = (16, 64, 192, 352)
    return _named(planner.run(_t(s, d), [P_OOO.edit(window=w) for w in sizes]), [f"window {w}" for w in sizes])


def ooo_lanes(s, d):
    front = whatif.front_end(P_OOO)
    return _named(runs.run_shared_order(_t(s, d), list(front.values())), list(front))


def ooo_chunked(s, d):
    return chunks.run_chunked_ooo(_t(s, d), P_OOO, 1000).select("program_id", "cycles", "instrs", "rerun")


def work_counters(s, d):
    return runs.work_counters(_t(s, d), P_OOO)


def _accuracy(s, d, m, method="", t=None):
    real = traces.sliced(_t(s, d), 0, SLICE)
    return runs.compared(runs.run_each(real if t is None else t, [m], method), baselines.tick_simulation(real, m, SLICE))


def ino_accuracy(s, d):
    return _accuracy(s, d, P_INO)


def ooo_accuracy(s, d):
    return _accuracy(s, d, P_OOO)


def ooo_approximate_accuracy(s, d):
    return _accuracy(s, d, P_OOO, "fixed")


def ooo_earliest_accuracy(s, d):
    """The scoreboard that gives an instruction the unit free first, in place of least-recently-used order."""
    return _accuracy(s, d, P_OOO.edit(fu_policy="earliest"))


def ooo_lowfi(s, d):
    return _accuracy(s, d, P_OOO, t=costs.low_fidelity(materialise(traces.sliced(_t(s, d), 0, SLICE), "trace")))


def accuracy_summary(s, d):
    out = None
    for name, f in (("in order", ino_accuracy), ("out of order", ooo_accuracy), ("out of order, earliest unit", ooo_earliest_accuracy), ("approximate", ooo_approximate_accuracy), ("low fidelity", ooo_lowfi)):
        x = runs.geometric_mean(f(s, d), "diff_pct").select(F.lit(name).alias("model"), "geo_mean", "average", "maximum")
        out = x if out is None else out.unionByName(x)
    return out


def cache_model(s, d):
    return costs.cache_model(_t(s, d)).groupBy("program_id", "dmem_cycles").agg(F.count(F.lit(1)).alias("n"))


def stat_costs(s, d):
    t = costs.stat_branch(costs.stat_mem(_t(s, d), 90, 2, 10), 95)
    return t.groupBy("program_id").agg(F.sum("dmem_cycles").alias("dmem"), F.sum("imem_cycles").alias("imem"), F.sum(F.col("mispredicted").cast("bigint")).alias("missed"))


def iss_counts(s, d):
    return baselines.counts(_t(s, d))


def mechanistic(s, d):
    return baselines.mechanistic(_t(s, d), P_INO)


def cycle_stack(s, d):
    return baselines.cycle_stack(_t(s, d), P_INO)


def vp_random(s, d):
    return valuepred.curve(valuepred.random_sweep(_t(s, d), P_OOO))


def vp_critical(s, d):
    return valuepred.curve(valuepred.critical_sweep(_t(s, d), P_OOO))


def vp_focused(s, d):
    return valuepred.curve(valuepred.focused(_t(s, d), P_OOO))


def vp_summary(s, d):
    points = valuepred.critical_sweep(_t(s, d), P_OOO).unionByName(valuepred.random_sweep(_t(s, d), P_OOO))
    return valuepred.mean_curve(points)


def vp_knee(s, d):
    return valuepred.knee(materialise(valuepred.both_sweeps(_t(s, d), P_OOO), "points"))  # read twice


def crack_trace(s, d):
    t = graph.crack(_t(s, d), (F.col("op_class") == "INT_MUL") & (F.col("pc") % 5 == 0))
    return planner.run(t, [P_INO]).select("program_id", "cycles", "instrs")


def fusible_pairs(s, d):
    return graph.fusible_pairs(_t(s, d))


def fuse_trace(s, d):
    return explicit.cycles(_t(s, d), lambda: explicit.Fused(P_INO, 4)).select("program_id", "cycles")


def value_speculation(s, d):
    """Right and wrong value predictions of all loads, as edits of the explicit graph's register edges."""
    edits = (None, lambda i, w: None if i.op == LOAD else w, lambda i, w: w + 8 if i.op == LOAD else w)
    return _named(explicit.cycles(_t(s, d), lambda: explicit.Longest(P_INO, edits)), ["base", "right", "wrong"])


def block_sizes(s, d):
    return blocks.sizes(_t(s, d))


def block_reads(s, d):
    return blocks.reads(_t(s, d))


def block_movs(s, d):
    return blocks.movs(_t(s, d))


def block_nulls(s, d):
    return blocks.nulls(_t(s, d))


def block_mix(s, d):
    return blocks.mix(_t(s, d))


def block_decode_delay(s, d):
    return blocks.decode_delay(_t(s, d))


def block_graph(s, d):
    t = _t(s, d)
    e = blocks.edges(t).groupBy("program_id", "kind").agg(F.count(F.lit(1)).alias("n"))
    return e.unionByName(blocks.chains(t).groupBy("program_id", F.concat(F.lit("chain_"), "kind").alias("kind")).agg(F.count(F.lit(1)).alias("n")))


def block_formats(s, d):
    return blocks.run_blocks(_t(s, d))


def block_formats_conversations(s, d):
    return blocks.run_blocks(traces.from_conversations(s, d))


def block_breakdown(s, d):
    return blocks.path_mix(_t(s, d)).groupBy("program_id", "term").agg(F.sum("cycles").alias("cycles"))


def block_path_mix(s, d):
    p = blocks.path_mix(_t(s, d)).where("class <> 'BLOCK'")
    return p.groupBy("program_id", "class").agg(F.sum("instrs").alias("instrs"), F.sum("cycles").alias("cycles"))


def block_path_shares(s, d):
    return blocks.shares(blocks.path_mix(_t(s, d)))


def block_format_gains(s, d):
    return blocks.format_gains(blocks.run_blocks(_t(s, d)))


def doc_trace_runs(s, d):
    return planner.run(costs.recorded(traces.from_documents(s, d)), [P_INO]).select("program_id", "instrs", "cycles")


def stream_ino(s, d):
    return streams.final_state(streams.drained(streams.sweep_stream(streams.events_stream(s, d)))).drop("late")


def stream_windows(s, d):
    return streams.window_counts(tables.table(s, d, "events"))


def stream_sessions(s, d):
    return streams.sessions(tables.table(s, d, "events")).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


def vector_speedup(s, d):
    """CPU seconds of n lanes at once against the scalar kernel once a lane, over the whole trace."""
    t = runs.vector_times(_t(s, d), _lane_machines(s, d), (1, 2, 4, 8, 16, 32))
    t = t.groupBy("lanes").agg(F.sum("vector_s").alias("vector_s"), F.sum("sequential_s").alias("sequential_s"))
    return t.select("lanes", F.round("vector_s", 4).alias("vector_s"), F.round("sequential_s", 4).alias("sequential_s"), F.round(F.col("sequential_s") / F.col("vector_s"), 4).alias("speedup"))


def bench_ino(s, d):
    return ino_cycles(s, d).select("program_id", "cycles")


def bench_ooo(s, d):
    return ooo_cycles(s, d).select("program_id", "cycles")


def bench_ooo_approx(s, d):
    return ooo_approximate(s, d).select("program_id", "cycles")


def bench_simulator_ino(s, d):
    return baselines.tick_simulation(_t(s, d), P_INO, 10**9).select("program_id", "cycles")


def bench_simulator_ooo(s, d):
    return baselines.tick_simulation(_t(s, d), P_OOO, 10**9).select("program_id", "cycles")


NAMES = """trace_lineitem trace_lineitem_distributed trace_events trace_documents trace_conversations op_mix fold_wrong_path slice_instr slice_block sample_regions
edges_frontend edges_control edges_commit edges_issue edges_pipeline edges_data_reg edges_data_mem edges_fu_inorder edges_queue graph_size graph_valid graph_longest ooo_explicit
frontend_chain commit_chain toy_base toy_whatif toy_path toy_without_mul toy_fused toy_sql_path fu_pipelined fu_blocking fu_depth crack_example spec_branch
ino_cycles ino_lanes lanes_32 lanes_sequential ino_chunked ino_planned frontend_ino frontend_ooo frontend_interaction breakdown_ino breakdown_ino_total breakdown_ooo breakdown_cube
critical_path_ino top_critical_pcs path_overlap slack_ino secondary_path limits_ino scenario_grid prior_graph_ino ooo_two_pass ooo_cycles ooo_approximate ooo_window ooo_lanes ooo_chunked work_counters
ino_accuracy ooo_accuracy ooo_earliest_accuracy ooo_approximate_accuracy ooo_lowfi accuracy_summary cache_model stat_costs iss_counts mechanistic cycle_stack vp_random vp_critical vp_focused vp_summary vp_knee
crack_trace fusible_pairs fuse_trace value_speculation block_sizes block_reads block_movs block_nulls block_mix block_decode_delay block_graph block_formats block_formats_conversations block_breakdown block_path_mix block_path_shares block_format_gains
doc_trace_runs stream_ino stream_windows stream_sessions vector_speedup bench_ino bench_ooo bench_ooo_approx bench_simulator_ino bench_simulator_ooo""".split()
QUERIES = {n: globals()[n] for n in NAMES}

_COLS = ", ".join(TRACE_COLUMNS)
_RUN1 = "SELECT program_id, cycles, instrs, round(cycles / instrs, 6) AS cyc_per_instr FROM runs"
LENGTHS = "SELECT * FROM l"
_SLICED = "p AS (SELECT * FROM trace WHERE seq < {n})"


ORACLE_SQL = {
    "trace_lineitem": with_trace(f"SELECT {_COLS}, imem_cycles, dmem_cycles, mispredicted FROM trace"),
    "trace_lineitem_distributed": with_trace(f"SELECT {_COLS}, imem_cycles, dmem_cycles, mispredicted FROM trace"),
    "trace_events": with_trace("SELECT program_id, seq, op_class, src1, src2, dst, cast(addr AS bigint) AS addr, dmem_cycles, mispredicted FROM trace", ctes=oracles.EVENTS),
    "trace_documents": oracles.token_trace("documents"),
    "trace_conversations": oracles.token_trace("conversations"),
    "op_mix": with_trace("SELECT program_id, op_class, count(*) AS n FROM trace GROUP BY ALL"),
    "iss_counts": with_trace("SELECT program_id, op_class, count(*) AS n FROM trace GROUP BY ALL"),
    "fold_wrong_path": with_trace("SELECT program_id, seq, imem_cycles FROM trace"),
    "slice_instr": with_trace("SELECT program_id, count(*) AS n, min(seq - 500) AS first_seq, max(seq - 500) AS last_seq FROM trace WHERE seq >= 500 AND seq < 1500 GROUP BY program_id"),
    "slice_block": with_trace("SELECT program_id, count(*) AS n, cast(0 AS bigint) AS first_seq, count(*) - 1 AS last_seq FROM (SELECT program_id, dense_rank() OVER (PARTITION BY program_id ORDER BY block_no) - 1 AS b FROM trace) WHERE b >= 50 AND b < 150 GROUP BY program_id"),
    **oracles.EDGES,
    "graph_size": with_trace(
        "SELECT program_id, (SELECT 3 * count(*) FROM trace t WHERE t.program_id = e.program_id) AS vertices, count(*) AS edges FROM e GROUP BY program_id",
        "e AS (" + " UNION ".join(f"SELECT program_id, src_seq, src_stage, dst_seq, dst_stage FROM ({q})" for k, q in oracles.EDGES.items()) + ")",
    ),
    "graph_longest": oracles.inorder([P_INO], "SELECT program_id, cycles FROM runs"),
    "graph_valid": with_trace(
        "SELECT problem, count(*) AS n FROM (SELECT 'negative' AS problem FROM e WHERE w < 0 UNION ALL SELECT 'self-loop' FROM e WHERE src_seq = dst_seq AND src_stage = dst_stage UNION ALL SELECT 'cycle' FROM e WHERE (src_seq, instr('FEC', src_stage)) >= (dst_seq, instr('FEC', dst_stage))) GROUP BY problem",
        "e AS (" + " UNION ALL ".join(f"SELECT src_seq, src_stage, dst_seq, dst_stage, w FROM ({q})" for q in oracles.EDGES.values()) + ")",
    ),
    "critical_path_ino": oracles.inorder([P_INO], "SELECT program_id, cycles FROM runs"),
    "cycle_stack": oracles.inorder([P_INO], ", g AS (SELECT s.program_id, CASE WHEN eh[1] + x1 = ch[1] THEN " + "CASE t.o " + " ".join(f"WHEN {k} THEN '{TERM_OF_OP[op]}'" for k, op in enumerate(OPS[:9])) + " END ELSE 'commit_bw' END AS term, ch[1] - CASE WHEN s.seq = 0 THEN 0 ELSE ch[2] END AS gap FROM s JOIN t USING (program_id, seq)) SELECT program_id, term, cast(sum(gap) AS bigint) AS cycles FROM g WHERE gap > 0 GROUP BY ALL"),
    "prior_graph_ino": oracles.unordered(P_INO.without_resources(), "SELECT program_id, cast(max(c1) AS bigint) AS cycles FROM s GROUP BY program_id"),
    "limits_ino": oracles.named(whatif.limits(P_INO), "SELECT n.program_id, n.scenario, n.cycles, round(1 - n.cycles / b.cycles, 6) AS improvement, round(b.cycles / n.cycles, 6) AS speedup FROM n JOIN n b ON b.program_id = n.program_id AND b.scenario = 'base'"),
    "cache_model": with_trace(
        "SELECT program_id, cast(CASE WHEN hit1 THEN 2 WHEN last2 IS NOT NULL AND (SELECT count(DISTINCT o.line) FROM m o WHERE o.program_id = v.program_id AND o.line % 1024 = v.line % 1024 AND o.seq > v.last2 AND o.seq < v.seq) < 16 THEN 10 ELSE 40 END AS int) AS dmem_cycles, count(*) AS n FROM (SELECT *, true AS hit1, cast(NULL AS bigint) AS last2 FROM h WHERE hit UNION ALL SELECT *, false, lag(seq) OVER (PARTITION BY program_id, line ORDER BY seq) FROM m) v GROUP BY ALL",
        "a AS (SELECT program_id, seq, addr >> 6 AS line FROM trace WHERE addr IS NOT NULL), u AS (SELECT *, lag(seq) OVER (PARTITION BY program_id, line ORDER BY seq) AS last FROM a), h AS MATERIALIZED (SELECT program_id, seq, line, last IS NOT NULL AND (SELECT count(DISTINCT o.line) FROM a o WHERE o.program_id = u.program_id AND o.line % 64 = u.line % 64 AND o.seq > u.last AND o.seq < u.seq) < 8 AS hit FROM u), m AS MATERIALIZED (SELECT * FROM h WHERE NOT hit)",
    ),
    "scenario_grid": oracles.named({m.name: m for m in configs.grid(P_INO, fbw=[1, 2, 4], ibw=[1, 2])}),
    "value_speculation": oracles.named({"base": P_INO, "right": P_INO.edit(predicted_permille=1000), "wrong": P_INO.edit(predicted_permille=1000, predict_penalty=8)}),
    "crack_trace": oracles.inorder([P_INO], "SELECT program_id, cycles, instrs FROM runs", oracles.CRACKED),
    "doc_trace_runs": oracles.inorder([P_INO], "SELECT program_id, instrs, cycles FROM runs", oracles.recorded("documents")),
    "fusible_pairs": with_trace(
        "SELECT a.program_id, a.seq AS first, b.seq AS second FROM trace a JOIN trace b ON b.program_id = a.program_id AND b.seq = a.seq + 1 AND (a.op_class, b.op_class) IN (('INT_MUL', 'INT_ALU'), ('FP_MUL', 'FP_ALU')) JOIN k ON k.program_id = a.program_id AND k.src_seq = a.seq AND k.n = 1 AND k.reader = b.seq",
        f"e AS ({oracles.EDGES['edges_data_reg']}), k AS (SELECT program_id, src_seq, count(*) AS n, min(dst_seq) AS reader FROM e GROUP BY ALL)",
    ),
    "block_graph": with_trace(
        "SELECT program_id, 'block_fetch' AS kind, count(*) AS n FROM trace GROUP BY ALL UNION ALL SELECT program_id, 'block_commit', count(*) FROM trace WHERE op_class IN ('BRANCH', 'STORE') OR dst IS NOT NULL GROUP BY ALL UNION ALL SELECT program_id, 'chain_block_commit', count(*) FROM b WHERE more GROUP BY ALL UNION ALL SELECT program_id, CASE WHEN m THEN 'chain_redirect' ELSE 'chain_block_fetch' END, count(*) FROM b WHERE more GROUP BY ALL",
        "b AS (SELECT program_id, block_no, bool_or(mispredicted) AS m, lead(block_no) OVER (PARTITION BY program_id ORDER BY block_no) IS NOT NULL AS more FROM trace GROUP BY program_id, block_no)",
    ),
    "toy_path": toys.over_sql({"toy": TOY}, "SELECT mul, memory, e.parts, e.a AS src, e.b AS dst, e.w FROM e JOIN l x USING (mul, memory) JOIN l y USING (mul, memory) WHERE x.vertex = e.a AND y.vertex = e.b AND y.cp = x.cp + e.w"),
    "toy_fused": toys.over_sql({n: [(x, y, kind, 2 if x == "E2" else w) for a, b, kind, w in rows for x, y in [(a.replace("3", "2"), b.replace("3", "2"))] if x != y] for rows, n in ((TOYS["second register"], "fused, second register"), (TOY, "fused, one register"))}),
    "stream_sessions": "SELECT user_id, count(*) FILTER (WHERE begins) AS sessions, count(*) AS n FROM (SELECT user_id, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 30 MINUTE, true) AS begins FROM events) GROUP BY user_id",
    "frontend_chain": with_trace("SELECT program_id, seq, cast(sum(CASE WHEN seq > 0 THEN imem_cycles ELSE 0 END) OVER (PARTITION BY program_id ORDER BY seq) AS bigint) AS cp FROM trace"),
    "commit_chain": f"WITH RECURSIVE {oracles.TRACE.strip()}, {oracles.X}, r AS MATERIALIZED (SELECT program_id, seq, seq % 7 * 3 + x AS ready FROM x), s AS (SELECT program_id, seq, cast(ready AS bigint) AS c1, cast(-1000000 AS bigint) AS c2 FROM r WHERE seq = 0 UNION ALL SELECT r.program_id, r.seq, greatest(r.ready, c1, c2 + 1), c1 FROM s JOIN r ON r.program_id = s.program_id AND r.seq = s.seq + 1) SELECT program_id, seq, c1 AS cp FROM s",
    "toy_base": toys.over_sql({"base": TOYS["base"]}),
    "toy_whatif": toys.over_sql(TOYS),
    "toy_without_mul": toys.over_sql({"without multiplier": [r for r in TOY if "E2" not in r[:2]]}),
    "fu_pipelined": toys.over_sql({"pipelined": FPU["pipelined"]}, LENGTHS),
    "fu_blocking": toys.over_sql({"blocking": FPU["blocking"]}, LENGTHS),
    "fu_depth": toys.over_sql(DEPTH, LENGTHS),
    "crack_example": toys.over_sql(CRACK, LENGTHS),
    "spec_branch": toys.over_sql(BRANCH, LENGTHS),
    "ino_cycles": oracles.inorder([P_INO], _RUN1),
    "ino_lanes": oracles.inorder(list(FRONT.values()), "SELECT program_id, lane, cycles FROM runs"),
    "lanes_32": oracles.inorder([], "SELECT program_id, lane, cycles FROM runs", lanes_sql=oracles.EMBEDDED_LANES.format(n=32)),
    "lanes_sequential": oracles.inorder([], "SELECT program_id, lane, cycles FROM runs", lanes_sql=oracles.EMBEDDED_LANES.format(n=32)),
    "ino_chunked": oracles.inorder([P_INO], "SELECT program_id, cycles, instrs FROM runs"),
    "ino_planned": oracles.inorder([P_INO, P_INO, FRONT["both"]], "SELECT program_id, lane, cycles FROM runs"),
    "breakdown_ino_total": oracles.inorder([P_INO], "SELECT program_id, cycles FROM runs"),
    "bench_ino": oracles.inorder([P_INO], "SELECT program_id, cycles FROM runs"),
    "frontend_ino": oracles.inorder(list(FRONT.values()), "SELECT r.program_id, ['base', 'ideal_fetch', 'ideal_branch', 'both'][r.lane + 1] AS scenario, r.cycles, round(1 - r.cycles / b.cycles, 6) AS improvement FROM runs r JOIN runs b ON b.program_id = r.program_id AND b.lane = 0"),
    "frontend_interaction": oracles.inorder(list(FRONT.values()), "SELECT program_id, c0 - c1 AS gain_a, c0 - c2 AS gain_b, c0 - c3 AS gain_both, c1 + c2 - c0 - c3 AS interaction FROM (SELECT program_id, max(CASE lane WHEN 0 THEN cycles END) AS c0, max(CASE lane WHEN 1 THEN cycles END) AS c1, max(CASE lane WHEN 2 THEN cycles END) AS c2, max(CASE lane WHEN 3 THEN cycles END) AS c3 FROM runs GROUP BY program_id)"),
    "mechanistic": with_trace("SELECT program_id, cast((count(*) + 1) // 2 + sum(CASE WHEN mispredicted THEN 5 ELSE 0 END + CASE WHEN op_class = 'LOAD' THEN greatest(dmem_cycles - 2, 0) ELSE 0 END + imem_cycles) AS bigint) AS cycles, count(*) AS instrs FROM trace GROUP BY program_id"),
    "stat_costs": with_trace("SELECT program_id, cast(sum(CASE WHEN op_class IN ('LOAD', 'STORE') THEN CASE WHEN (7919 * seq + 13 + 31 * program_id) % 100 < 90 THEN 2 ELSE 10 END END) AS bigint) AS dmem, cast(sum(CASE WHEN seq % 16 = 0 THEN CASE WHEN (104729 * seq + 7 + 31 * program_id) % 100 < 98 THEN 1 ELSE 20 END ELSE 0 END) AS bigint) AS imem, cast(sum(CASE WHEN op_class = 'BRANCH' AND (6151 * seq + 3 + 31 * program_id) % 100 >= 95 THEN 1 ELSE 0 END) AS bigint) AS missed FROM trace GROUP BY program_id"),
    **oracles.BLOCKS,
    "stream_ino": oracles.inorder([P_INO], "SELECT program_id, cycles, instrs FROM runs", oracles.EVENTS),
    "stream_windows": with_trace("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, program_id, count(*) AS n, cast(sum(coalesce(dmem_cycles, 0)) AS bigint) AS mem_cycles FROM trace JOIN events USING (event_id) GROUP BY ALL", ctes=oracles.EVENTS),
}
