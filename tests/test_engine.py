"""Engine queries on the smallest tables: worked examples, invariants, and SQL oracles."""

import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

from critgraph import queries as Q
from critgraph.configs import P_INO, P_OOO
from critgraph.operators import blocks, graph, runs, toys, valuepred, whatif
from critgraph.plans import chunks, planner
from critgraph.sources import traces
from critgraph.streaming import runs as streams

SLOW = {"graph_size", "graph_longest", "trace_lineitem_distributed", "stream_ino"}


@pytest.fixture(scope="module")
def duck(sf):
    import os

    c = duckdb.connect()
    for f in os.listdir(sf):
        c.sql(f"create view {f.split('.')[0]} as select * from '{sf}/{f}'")
    return c


@pytest.fixture(scope="module")
def trace(spark, sf):
    t = traces.from_lineitem(spark, sf).persist()
    yield t
    t.unpersist()


def rows(df: pd.DataFrame) -> list:
    def cell(v):
        if v is None or v is pd.NA or v is pd.NaT or (isinstance(v, float) and v != v):
            return None
        return str(v) if isinstance(v, str) or hasattr(v, "isoformat") else round(float(v), 6)

    cols = sorted(df.columns)
    return cols, sorted((tuple(cell(v) for v in r) for r in df[cols].astype(object).itertuples(index=False, name=None)), key=str)


@pytest.mark.parametrize("name", [n for n in Q.ORACLE_SQL if n not in SLOW])
def test_query_equals_sql(spark, sf, duck, name):
    assert rows(Q.QUERIES[name](spark, sf).toPandas()) == rows(duck.sql(Q.ORACLE_SQL[name]).df())


def test_worked_example_totals(spark, sf):
    got = {r["case_name"]: r["cycles"] for r in toys.case_cycles(spark, toys.TOY_CASES).collect()}
    assert got == {"base": 15, "fast multiply": 15, "second register": 15, "both": 12}
    assert [toys.all_paths_longest(x) for x in toys.TOY_CASES.values()] == [15, 15, 15, 12]
    assert {r["case_name"]: r["cycles"] for r in Q.toy_fused(spark, sf).where("mul = 5 and memory = 6").collect()} == {"fused, second register": 11, "fused, one register": 14}
    path = {(r["src"], r["dst"]) for r in Q.toy_path(spark, sf).where("mul = 5 and memory = 6").collect()}
    assert {("F0", "E0"), ("E0", "M0"), ("M0", "E2"), ("E2", "E3"), ("E3", "M3"), ("M3", "C3"), ("M0", "M1"), ("M1", "C1"), ("C1", "C2"), ("C2", "C3")} <= path


def test_hazard_lengths(spark):
    at = lambda gap: [toys_len(spark, gap)[f"E{k}"] for k in range(3)]

    def toys_len(spark, gap):
        return {r["vertex"]: r["cp"] for r in toys.case_lengths(spark, {"x": toys.fpu(gap)}).collect()}

    assert at(1) == [3, 4, 5] and at(6) == [3, 9, 15]


def test_misprediction_grows_by_dispatch_execution_and_fetch(spark):
    got = {r["case_name"]: r["cycles"] for r in toys.case_cycles(spark, {"right": toys.branch(False), "wrong": toys.branch(True)}).collect()}
    assert got["wrong"] - got["right"] == 2 + 1 + (4 - 1)


def test_explicit_graph_equals_kernels(spark, trace):
    t = traces.sliced(trace, 0, 60).where("program_id < 6")
    for m in (P_INO, P_OOO):
        base = graph.base_graph(t, m)
        if m is P_OOO:
            base = base.unionByName(graph.resource_graph(graph.issue_rank(t, graph.longest(base)), m))
        got = {r["program_id"]: r["c"] for r in graph.longest(base).where("stage = 'C'").groupBy("program_id").agg(F.max("cp").alias("c")).collect()}
        want = {r["program_id"]: r["cycles"] for r in runs.run_each(t, [m], "two_pass").collect()}
        assert got == want


def test_validate_finds_faults(spark):
    bad = [("F0", "E0", "pipe", 1), ("E0", "F0", "pipe", 1), ("E0", "E0", "pipe", 0), ("F1", "E1", "pipe", -1)]
    e = toys.edges_of(spark, bad)
    verts = spark.createDataFrame([(0, 0, "F"), (0, 0, "E"), (0, 1, "F")], "program_id int, seq bigint, stage string")
    got = {r["problem"]: r["n"] for r in graph.validate(e, verts).collect()}
    assert got == {"negative": 1, "self-loop": 1, "dangling": 1, "cycle": 3}


def test_breakdown_and_slack(spark, trace):
    t = traces.sliced(trace, 0, 80)
    cycles = {(r["program_id"], r["lane"]): r["cycles"] for r in runs.run_each(t, [P_INO, P_OOO]).collect()}
    b = runs.breakdown(t, [P_INO, P_OOO]).groupBy("program_id", "lane").agg(F.sum("cycles").alias("c")).collect()
    assert {(r["program_id"], r["lane"]): r["c"] for r in b} == {k: v for k, v in cycles.items() if v}
    s = runs.slack(t, P_INO).toPandas()
    assert (s["slack"] >= 0).all() and (s.groupby("program_id")["slack"].min() == 0).all()


def test_chunks_equal_sweep(spark, trace):
    want = {r["program_id"]: r["cycles"] for r in runs.run_each(trace, [P_INO]).collect()}
    for size in (37, 400):
        assert {r["program_id"]: r["cycles"] for r in chunks.run_chunked(trace, P_INO, size).collect()} == want
    want = {r["program_id"]: r["cycles"] for r in runs.run_each(trace, [P_OOO]).collect()}
    got = {r["program_id"]: r["cycles"] for r in chunks.run_chunked_ooo(trace, P_OOO, 120).collect()}
    assert got == want


def test_planner_dedups_lanes(spark, trace):
    lanes = [P_INO, P_INO.edit(name="again"), P_INO.edit(ideal_fetch=True)]
    assert planner.distinct_lanes(lanes)[1] == [0, 0, 1]
    got = {(r["program_id"], r["lane"]): r["cycles"] for r in planner.run(trace, lanes).collect()}
    assert all(got[p, 0] == got[p, 1] for p, _ in got)
    assert planner.choose(trace, lanes, 10) == "chunks" and planner.choose(trace, [P_OOO], 10) == "ooo_chunks"


def test_idealising_never_costs_in_order(spark, trace):
    d = whatif.compare(trace, whatif.limits(P_INO))
    assert d.where("improvement < 0").count() == 0


def test_empty_trace(spark, trace):
    none = trace.where("false")
    for d in (runs.run_lanes(none, [P_INO]), runs.run_each(none, [P_OOO]), runs.paths(none, [P_INO]), chunks.run_chunked(none, P_INO, 10)):
        assert d.count() == 0


def test_stream_equals_batch_and_counts_late_rows(spark, sf, tmp_path):
    ev = spark.read.parquet(f"{sf}/events.parquet")
    half = ev.agg(F.expr("percentile_approx(event_id, 0.5)")).first()[0]
    for k, part in enumerate((ev.where(F.col("event_id") <= half), ev.where(F.col("event_id") > half), ev.where(F.col("event_id") == half))):
        part.coalesce(1).write.parquet(str(tmp_path / f"p{k}"))
    import os
    import shutil

    os.makedirs(tmp_path / "in" / "events.parquet")
    for k in range(3):
        src = next((tmp_path / f"p{k}").glob("part-*.parquet"))
        dst = tmp_path / "in" / "events.parquet" / f"{k}.parquet"
        shutil.copy(src, dst)
        os.utime(dst, (1_600_000_000 + k, 1_600_000_000 + k))
    got = {r["program_id"]: (r["cycles"], r["instrs"]) for r in streams.final_state(streams.drained(streams.sweep_stream(streams.events_stream(spark, str(tmp_path / "in"))))).collect()}
    want = {r["program_id"]: (r["cycles"], r["instrs"]) for r in runs.run_each(traces.from_events(ev), [P_INO]).collect()}
    assert got == want


def test_sources_and_sinks_round_trip(spark, trace, tmp_path):
    from critgraph.sources import tables

    t = traces.sliced(trace, 0, 20)
    t.write.option("header", True).csv(str(tmp_path / "csv"))
    t.write.json(str(tmp_path / "json"))
    tables.write_trace(t, str(tmp_path / "parquet"), 2)
    want = {r["program_id"]: r["cycles"] for r in runs.run_each(t, [P_INO]).collect()}
    for back in (tables.read_text_trace(spark, str(tmp_path / "csv")), tables.read_text_trace(spark, str(tmp_path / "json"), "json"), spark.read.parquet(str(tmp_path / "parquet"))):
        assert {r["program_id"]: r["cycles"] for r in runs.run_each(back, [P_INO]).collect()} == want


def test_sql_functions(spark):
    from critgraph.functions.sql import register

    register(spark)
    assert spark.sql("SELECT lane_max(array(1, null, 3), array(2, 2, null)) AS x").first()["x"] == [2, 2, 3]
    assert abs(spark.sql("SELECT geo_mean(v) AS g FROM VALUES (1.0D), (4.0D) AS t(v)").first()["g"] - 2.0) < 1e-9
    p = spark.sql("SELECT max(cp) AS c FROM critical_path(TABLE({e}) PARTITION BY program_id ORDER BY dst_seq)", e=toys.edges_of(spark, toys.toy()))
    assert p.first()["c"] == 15


def test_operators_take_the_whole_trace(spark, monkeypatch):
    """Queries of the explicit graph's operators on programs longer than any prefix, against the kernels and plain Python."""
    t = traces.sliced(traces.from_lineitem(spark, "/root/testdata/sf0.01"), 0, 1200).where("program_id in (1, 2)").persist()
    assert {r["count"] for r in t.groupBy("program_id").count().collect()} == {1200}
    monkeypatch.setattr(Q, "_t", lambda s, d: t)
    q = lambda n: Q.QUERIES[n](spark, "").collect()
    cycles = {r["program_id"]: r["cycles"] for r in q("ino_cycles")}
    for n in ("critical_path_ino", "graph_longest"):
        assert {r["program_id"]: r["cycles"] for r in q(n)} == cycles
    assert {r["program_id"]: r["cycles"] for r in q("value_speculation") if r["scenario"] == "base"} == cycles
    assert sum(r["n"] for r in q("slack_ino") if r["kind"] == "pipe") == 2 * 2 * 1200
    assert {r["program_id"]: r["instrs"] for r in q("crack_trace")} == {p: 1200 + t.where(f"program_id = {p} and op_class = 'INT_MUL' and pc % 5 = 0").count() for p in (1, 2)}
    two = {r["program_id"]: r["cycles"] for r in q("ooo_two_pass")}
    assert {r["program_id"]: r["cycles"] for r in q("ooo_explicit")} == two
    fused = {r["program_id"]: r["cycles"] for r in q("fuse_trace")}
    assert all(cycles[p] - 400 < fused[p] <= cycles[p] + 4 for p in cycles)
    steps = {(r["program_id"], r["kind"]): r["n"] for r in q("path_overlap")}
    found = {(r["program_id"], r["src_seq"], r["src_stage"], r["dst_seq"], r["dst_stage"]) for r in runs.paths(t, [Q.P_INO]).collect()}
    assert all(steps.get((p, "both"), 0) + steps.get((p, "in order only"), 0) == sum(x[0] == p for x in found) for p in cycles)
    assert q("graph_valid") == []
    bad = t.withColumn("imem_cycles", F.when(F.col("seq") == 1000, -90).otherwise(F.col("imem_cycles")))
    monkeypatch.setattr(Q, "_t", lambda s, d: bad)
    assert {r["problem"]: r["n"] for r in q("graph_valid")} == {"negative": 2}


def test_peel_finds_deep_cycles(spark):
    chain = [(1, k, "F", k + 1, "F", 1) for k in range(5000)]
    loop = [(1, 4000, "E", 4001, "E", 1), (1, 4001, "E", 4000, "E", 1), (1, 4001, "E", 4002, "E", 1), (1, 4002, "E", 4003, "E", 1)]
    e = lambda rows: spark.createDataFrame(rows, "program_id int, src_seq bigint, src_stage string, dst_seq bigint, dst_stage string, w int")
    assert graph.peel(e(chain)).count() == 0
    assert sorted((r["src_seq"], r["dst_seq"]) for r in graph.peel(e(chain + loop)).collect()) == [(4000, 4001), (4001, 4000), (4001, 4002), (4002, 4003)]


def test_edits_of_the_explicit_graph(spark):
    rows = [("F0", "E0", "pipe", 1), ("F0", "F1", "fetch", 1), ("F1", "E1", "pipe", 1)]
    e = toys.edges_of(spark, rows)
    pair = spark.createDataFrame([(0, 0, 1)], "program_id int, src_seq bigint, dst_seq bigint")
    late = graph.recovery(e, pair, 7)
    assert {(r["stage"], r["seq"]): r["cp"] for r in graph.longest(late).collect()} == {("F", 0): 0, ("E", 0): 1, ("F", 1): 8, ("E", 1): 9}
    lanes = e.withColumn("w", F.array(F.col("w"), F.col("w") * 2)).unionByName(e.where("kind = 'fetch'").withColumn("w", F.array(F.lit(None).cast("int"), F.lit(1))))
    got = {(r["src_seq"], r["src_stage"], r["dst_seq"], r["dst_stage"]): r["w"] for r in graph.merge_lanes(lanes).collect()}
    assert got == {(0, "F", 0, "E"): [1, 2], (0, "F", 1, "F"): [1, 2], (1, "F", 1, "E"): [1, 2]}
    both = whatif.combine(lambda m: m.set_latency(INT_MUL=1), lambda m: whatif.drop(m, "fetch_bw"))(Q.P_INO)
    assert both.latency["INT_MUL"] == 1 and both.fbw is None and whatif.drop(Q.P_INO, "queue").lsq is None and whatif.drop(Q.P_INO, "fu_occ").units == {}


def test_stream_joins_on_batches(spark):
    rows = [(1, 5, "view", "2024-01-01 10:00:00"), (2, 5, "purchase", "2024-01-01 10:30:00"), (3, 5, "purchase", "2024-01-01 12:00:00"), (4, 6, "purchase", "2024-01-01 10:10:00")]
    e = spark.createDataFrame(rows, "event_id bigint, user_id bigint, event_type string, ts string").withColumn("ts", F.to_timestamp("ts"))
    assert [(r["event_id"], r["view_id"]) for r in streams.views_before_purchases(e).collect()] == [(2, 1)]
    names = spark.createDataFrame([(5, "a")], "user_id bigint, name string")
    assert {(r["event_id"], r["name"]) for r in streams.with_static(e, names, "user_id").collect()} == {(1, "a"), (2, "a"), (3, "a"), (4, None)}


def test_one_rule_for_moves_and_commit(spark):
    """The block evaluator holds as many READ, MOV and NULL as the counting operators, and no commit waits for what writes nothing."""
    t = traces.from_lineitem(spark, "/root/testdata/sf0.001").persist()
    want = {(r["program_id"]): r["n"] for r in blocks.mix(t).groupBy("program_id").agg(F.sum("n").alias("n")).collect()}
    got = {r["program_id"]: r["instrs"] for r in blocks.run_blocks(t, ("4seg",)).collect()}
    assert got == want
    p = blocks.BlockProgram({"op": [0, 0, 0, 0, 0], "seq": [0, 1, 2, 3, 4], "src1": [None, 1, 1, 1, 1], "src2": [None, None, None, 1, None], "dst": [1, 2, 3, 4, None], "addr": [None] * 5, "block_no": [0] * 5, "predicated": [False] * 5}, 0, "4seg")
    assert p.op.count("MOV") == 2 and len(p.op) == 7 and len(p.output) == 4
    assert p.run() > 0 and sum(c for *_, c in p.path()) > 0
    s = blocks.shares(blocks.path_mix(t)).collect()
    assert len(s) == len(got) and all(0 <= r["read_mov_cycles"] <= 1 and 0 < r["read_mov_instrs"] <= 1 for r in s)
    gains = {r["format"]: r for r in blocks.format_gains(blocks.run_blocks(t)).collect()}
    assert gains["4seg"]["maximum"] == 0 and all(r["minimum"] <= r["average"] <= r["maximum"] for r in gains.values())


def test_value_prediction_keeps_steps_and_finds_the_knee(spark):
    t = traces.from_lineitem(spark, "/root/testdata/sf0.001").persist()
    points = valuepred.critical_sweep(t, Q.P_OOO).unionByName(valuepred.random_sweep(t, Q.P_OOO)).persist()
    c = valuepred.mean_curve(points).collect()
    assert {r["step"] for r in c if r["sweep"] == "critical" and r["pass"] == 1} == {20, 40, 60, 80, 100}
    k = {r["sweep"]: r for r in valuepred.knee(points).collect()}
    assert k["critical"]["coverage"] <= k["random"]["coverage"] and all(r["improvement"] >= 0.9 * r["best"] for r in k.values())


def test_chunks_out_of_order_settle_or_raise(spark):
    t = traces.from_lineitem(spark, "/root/testdata/sf0.001")
    with pytest.raises(ValueError):
        chunks.run_chunked_ooo(t, Q.P_OOO.edit(rob=None))
    with pytest.raises(ValueError):
        chunks.run_chunked_ooo(t, Q.P_OOO, 40, warm=1, rounds=1)
