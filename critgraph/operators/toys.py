"""Small graphs: the worked examples, as edges.

A weight is a number, or an expression over the columns of ``latencies``: then a graph is evaluated once for each pair
of latencies that the table ``part`` holds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.operators import graph
from critgraph.sources.tables import table

#: What a part's multiply and its memory access cost, in Spark and in DuckDB.
MUL, MEMORY = "1 + p_size % 8", "2 + p_partkey % 8"
CASE_PROGRAMS = 1000  # program numbers of a case


def edges_of(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Edges from (source, destination, kind, w), vertices written as stage and number."""
    out = [(0, int(a.lstrip("FDEMCBS")), a.rstrip("0123456789"), int(b.lstrip("FDEMCBS")), b.rstrip("0123456789"), kind, w) for a, b, kind, w in rows]
    return spark.createDataFrame(out, schemas.EDGE)


def ends_of(vertex: str) -> tuple[int, str]:
    return int(vertex.lstrip("FDEMCBS")), vertex.rstrip("0123456789")


def latencies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(program_id, mul, memory, parts): the pairs of latencies of all rows of ``part``, and how many rows have them."""
    d = table(spark, sf_dir, "part").groupBy(F.expr(MUL).cast("int").alias("mul"), F.expr(MEMORY).cast("int").alias("memory")).agg(F.count(F.lit(1)).alias("parts"))
    return d.select((F.col("mul") * 16 + F.col("memory")).alias("program_id"), "mul", "memory", "parts")


def edges_for(costs: DataFrame, rows: list[tuple], case: int = 0) -> DataFrame:
    """The edges ``rows`` once for each row of ``costs``, whose columns their weights may name."""
    structs = []
    for a, b, kind, w in rows:
        (i, s), (j, t) = ends_of(a), ends_of(b)
        structs.append(F.struct(F.lit(i).cast("bigint").alias("src_seq"), F.lit(s).alias("src_stage"), F.lit(j).cast("bigint").alias("dst_seq"), F.lit(t).alias("dst_stage"), F.lit(kind).alias("kind"), F.expr(str(w)).cast("int").alias("w")))
    return costs.select((F.col("program_id") + case * CASE_PROGRAMS).alias("program_id"), F.explode(F.array(*structs)).alias("e")).select("program_id", "e.*")


def of_costs(costs: DataFrame, d: DataFrame, names: list[str] | None = None) -> DataFrame:
    """``d`` with the latencies of its programs, and with ``names`` the case by the thousands of the program number."""
    d = d.withColumns({"_case": F.expr(f"program_id div {CASE_PROGRAMS}").cast("int"), "program_id": F.col("program_id") % CASE_PROGRAMS})
    d = d.join(costs, "program_id")
    return d.withColumn("case_name", F.element_at(F.array(*map(F.lit, names)), F.col("_case") + 1)).drop("_case") if names else d.drop("_case")


def lengths_over(spark: SparkSession, sf_dir: str, cases: dict[str, list[tuple]]) -> DataFrame:
    """(case_name, mul, memory, parts, vertex, cp) of each case under each pair of latencies."""
    costs = latencies(spark, sf_dir)
    frames = None
    for k, rows in enumerate(cases.values()):
        e = edges_for(costs, rows, k)
        frames = e if frames is None else frames.unionByName(e)
    return of_costs(costs, graph.longest(frames), list(cases)).select("case_name", "mul", "memory", "parts", F.concat("stage", F.col("seq").cast("string")).alias("vertex"), "cp")


def cycles_over(spark: SparkSession, sf_dir: str, cases: dict[str, list[tuple]]) -> DataFrame:
    return lengths_over(spark, sf_dir, cases).groupBy("case_name", "mul", "memory", "parts").agg(F.max("cp").alias("cycles"))


def plus(w: int | str, more: int | str) -> int | str:
    return w + more if isinstance(w, int) and isinstance(more, int) else f"{w} + {more}"


def toy(mul: int | str = 5, registers: int = 1, load: int | str = 6, busy: int | str = 5) -> list[tuple]:
    """Four instructions on the four-stage core: two missing loads, a multiply of the first, an add of the product."""
    execute, memory = (1, 1, mul, 1), (load, load, 1, 1)
    rows = [(f"F{i}", f"F{i + 1}", "fetch", 1) for i in range(3)] + [(f"C{i}", f"C{i + 1}", "commit", 1) for i in range(3)]
    for i in range(4):
        rows += [(f"F{i}", f"E{i}", "pipe", 1), (f"E{i}", f"M{i}", "pipe", execute[i]), (f"M{i}", f"C{i}", "pipe", memory[i])]
    rows += [("M0", "E2", "data_reg", load), ("E2", "E3", "data_reg", mul)]
    return rows + ([("M0", "M1", "mshr", busy)] if registers == 1 else [])


def toy_fused(spark: SparkSession, registers: int = 2, cycles: int = 2) -> DataFrame:
    """The toy with multiply and add fused into one instruction of ``cycles``."""
    pairs = spark.createDataFrame([(0, 2, 3)], "program_id int, first bigint, second bigint")
    return graph.fuse(edges_of(spark, toy(registers=registers)), pairs, cycles)


def fpu(gap: int | str, ready: int | str = 3) -> list[tuple]:
    """Three operations, the last ready a cycle after the others, on one unit that takes a new one every ``gap`` cycles; f2 goes first."""
    return [("F0", "E0", "pipe", ready), ("F0", "E1", "pipe", ready), ("F0", "E2", "pipe", plus(ready, 1)), ("E0", "E1", "fu_occ", gap), ("E1", "E2", "fu_occ", gap)]


def fpu_depth(depth: int | None, latency: int | str = 6, stall: int | str = 4) -> list[tuple]:
    """Five operations a cycle apart; the first is stalled inside the unit. At most ``depth`` are in it at a time."""
    rows = []
    for i in range(5):
        rows += [("F0", f"E{i}", "pipe", i), (f"E{i}", f"M{i}", "pipe", plus(latency, stall) if i == 0 else latency)]
        if depth and i >= depth:
            rows.append((f"M{i - depth}", f"E{i}", "fu_depth", 0))
    return rows


def crack_example(cracked: bool, mul: int | str = 5, load: int | str = 6) -> list[tuple]:
    """A multiply and a complex add that reads memory: whole, or with its load as an event of its own."""
    rows = [("F0", "F1", "fetch", 1), ("F0", "E0", "pipe", 1), ("E0", "C0", "pipe", mul), ("C0", "C1", "commit", 0)]
    if cracked:
        return [*rows, ("F1", "M1", "pipe", 1), ("M1", "E1", "data_reg", load), ("E0", "E1", "data_reg", mul), ("E1", "C1", "pipe", 1)]
    return [*rows, ("F1", "E1", "pipe", 1), ("E0", "E1", "data_reg", mul), ("E1", "C1", "pipe", plus(load, 1))]


def branch(wrong: bool, d: int = 2, x: int | str = 1, f: int = 1, f_miss: int | str = 4) -> list[tuple]:
    """A branch and the next instruction, rightly or wrongly predicted."""
    rows = [("F0", "E0", "pipe", d), ("E0", "C0", "pipe", x), ("F1", "E1", "pipe", d), ("E1", "C1", "pipe", 1), ("C0", "C1", "commit", 0)]
    return [*rows, ("E0", "F1", "control", plus(x, f_miss))] if wrong else [*rows, ("F0", "F1", "fetch", f)]


def all_paths_longest(rows: list[tuple]) -> int:
    """Exhaustive enumeration of paths (tiny graphs)."""
    out: dict[str, list] = {}
    for a, b, _, w in rows:
        out.setdefault(a, []).append((b, w))

    def walk(v: str) -> int:
        return max((w + walk(b) for b, w in out.get(v, ())), default=0)

    return max(walk(a) for a in out)


def cases_sql(cases: dict[str, list[tuple]]) -> str:
    """SQL for the longest path of each case: a recursive walk over literal edges."""
    values = ", ".join(f"('{c}', '{a}', '{b}', {w})" for c, rows in cases.items() for a, b, _, w in rows)
    return f"""
WITH RECURSIVE e(case_name, a, b, w) AS (SELECT * FROM (VALUES {values}) AS v),
p AS (SELECT DISTINCT case_name, a AS v, 0 AS n FROM e UNION SELECT p.case_name, e.b, p.n + e.w FROM p JOIN e ON e.case_name = p.case_name AND e.a = p.v)
SELECT case_name, cast(max(n) AS bigint) AS cycles FROM p GROUP BY case_name"""


def lengths_sql(cases: dict[str, list[tuple]]) -> str:
    return cases_sql(cases).replace("SELECT case_name, cast(max(n) AS bigint) AS cycles FROM p GROUP BY case_name", "SELECT case_name, v AS vertex, cast(max(n) AS bigint) AS cp FROM p GROUP BY case_name, v")


def over_sql(cases: dict[str, list[tuple]], select: str = "SELECT case_name, mul, memory, parts, cast(max(n) AS bigint) AS cycles FROM p GROUP BY ALL") -> str:
    """As cases_sql, for each pair of latencies of ``part``; ``l`` has each vertex's length as cp."""
    rows = ", ".join(f"{{'case_name': '{c}', 'a': '{a}', 'b': '{b}', 'w': cast({w} AS int)}}" for c, edges in cases.items() for a, b, _, w in edges)
    return f"""
WITH RECURSIVE q AS (SELECT cast({MUL} AS int) AS mul, cast({MEMORY} AS int) AS memory, count(*) AS parts FROM part GROUP BY 1, 2),
e AS (SELECT mul, memory, parts, unnest([{rows}], recursive := true) FROM q),
p AS (SELECT DISTINCT case_name, mul, memory, parts, a AS v, 0 AS n FROM e UNION SELECT p.case_name, p.mul, p.memory, p.parts, e.b, p.n + e.w FROM p JOIN e ON e.case_name = p.case_name AND e.mul = p.mul AND e.memory = p.memory AND e.a = p.v),
l AS (SELECT case_name, mul, memory, parts, v AS vertex, cast(max(n) AS bigint) AS cp FROM p GROUP BY ALL)
{select}"""


def case_lengths(spark: SparkSession, cases: dict[str, list[tuple]]) -> DataFrame:
    """(case_name, vertex, cp) of each case, all cases as programs of one frame."""
    names = list(cases)
    frames = None
    for k, c in enumerate(names):
        e = edges_of(spark, cases[c]).withColumn("program_id", F.lit(k))
        frames = e if frames is None else frames.unionByName(e)
    d = graph.longest(frames)
    return d.select(F.element_at(F.array(*map(F.lit, names)), F.col("program_id") + 1).alias("case_name"), F.concat("stage", F.col("seq").cast("string")).alias("vertex"), "cp")


def case_cycles(spark: SparkSession, cases: dict[str, list[tuple]]) -> DataFrame:
    return case_lengths(spark, cases).groupBy("case_name").agg(F.max("cp").alias("cycles"))


TOY_CASES = {"base": toy(), "fast multiply": toy(mul=2), "second register": toy(registers=2), "both": toy(2, 2)}
