"""SQL (DuckDB) that gives the rows of the engine's queries from the same tables."""

from __future__ import annotations

from critgraph.configs import LATENCY, P_INO, Machine
from critgraph.schemas import OPS

_MISS = "CASE n_regionkey WHEN 0 THEN 20 WHEN 1 THEN 4 WHEN 2 THEN 4 WHEN 3 THEN 2 ELSE 8 END"
_OP = """CASE WHEN wrong THEN NULL WHEN p_type = 'LARGE' THEN 'LOAD' WHEN p_type = 'PROMO' THEN 'BRANCH'
 WHEN p_type = 'MEDIUM' THEN CASE WHEN k < 2 THEN 'STORE' WHEN n_regionkey = 1 THEN 'LOAD' ELSE 'INT_ALU' END
 WHEN p_type = 'ECONOMY' THEN CASE WHEN k = 3 THEN 'INT_MUL' ELSE 'INT_ALU' END
 WHEN p_type = 'STANDARD' THEN CASE WHEN k = 3 THEN CASE WHEN n_regionkey = 3 THEN 'FP_MUL' ELSE 'INT_DIV' END ELSE 'INT_ALU' END
 ELSE CASE WHEN n_regionkey = 2 THEN 'INT_MUL' WHEN k < 2 THEN 'FP_ALU' WHEN k = 2 THEN 'FP_MUL' ELSE 'FP_DIV' END END"""

#: CTEs that end in ``trace``: the main trace.
TRACE = f"""
r0 AS (SELECT c_nationkey AS program_id, n_regionkey, p_type, p_size % 4 AS k, l_orderkey, l_linenumber, l_partkey, l_suppkey, o_orderpriority,
  (cast(round(l_tax * 100) AS int) = 4 AND cast(round(l_discount * 100) AS int) = 5) AS wrong, l_extendedprice, l_quantity, l_shipdate
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey),
r1 AS (SELECT *, count(*) OVER o - 1 - sum(cast(wrong AS bigint)) OVER o AS seq, sum(cast(wrong AS bigint)) OVER o AS w FROM r0
  WINDOW o AS (PARTITION BY program_id ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity, l_shipdate ROWS UNBOUNDED PRECEDING)),
r2 AS (SELECT *, {_OP} AS op_class, 5 * (w - coalesce(lag(w) OVER (PARTITION BY program_id ORDER BY seq), 0)) AS folded FROM r1 WHERE NOT wrong),
r3 AS (SELECT *, op_class = 'BRANCH' AND (31 * l_orderkey + 17 * l_partkey + 7 * l_linenumber) % 100 < {_MISS} AS mispredicted FROM r2),
r4 AS (SELECT *, seq % 16 = 0 OR coalesce(lag(mispredicted) OVER (PARTITION BY program_id ORDER BY seq), false) AS begins FROM r3),
trace AS (SELECT program_id, cast(seq AS bigint) AS seq, l_partkey AS pc, op_class, cast(l_suppkey % 32 AS int) AS src1,
  cast(CASE WHEN op_class <> 'LOAD' AND l_partkey % 4 <> 0 THEN (l_partkey + 5 * l_linenumber) % 32 END AS int) AS src2,
  cast(CASE WHEN op_class NOT IN ('STORE', 'BRANCH') THEN (7 * l_partkey + l_suppkey) % 32 END AS int) AS dst,
  cast(CASE WHEN op_class IN ('LOAD', 'STORE') THEN CASE WHEN l_partkey % 4 = 0 THEN (l_suppkey % 8) * 8 ELSE l_suppkey * 4096 + l_partkey * 64 END END AS bigint) AS addr,
  cast(CASE WHEN begins THEN CASE WHEN (13 * l_orderkey + 11 * l_partkey) % 100 < CASE WHEN n_regionkey = 0 THEN 60 ELSE 5 END THEN 20 ELSE 1 END ELSE 0 END + folded AS int) AS imem_cycles,
  cast(CASE WHEN op_class IN ('LOAD', 'STORE') THEN CASE WHEN (19 * l_orderkey + 23 * l_suppkey + 29 * l_linenumber) % 100 < CASE WHEN n_regionkey = 1 THEN 40 ELSE 8 END THEN 20 ELSE 2 END END AS int) AS dmem_cycles,
  mispredicted, l_orderkey AS block_no, cast(row_number() OVER (PARTITION BY program_id, l_orderkey ORDER BY seq) - 1 AS int) AS slot,
  o_orderpriority = '1-URGENT' AS predicated, n_regionkey FROM r4)"""

EVENTS = """
trace AS (SELECT cast(user_id % 10 AS int) AS program_id, row_number() OVER (PARTITION BY user_id % 10 ORDER BY event_id) - 1 AS seq, event_id, k % 32 AS src1, cast(NULL AS int) AS src2, op_class,
  CASE WHEN op_class NOT IN ('STORE', 'BRANCH') THEN cast((k * 3 + user_id) % 32 AS int) END AS dst, CASE WHEN op_class IN ('LOAD', 'STORE') THEN k * 8 END AS addr, 0 AS imem_cycles,
  CASE WHEN op_class IN ('LOAD', 'STORE') THEN cast(2 + cast(round(value * 100) AS bigint) % 7 AS int) END AS dmem_cycles, op_class = 'BRANCH' AND k % 20 = 0 AS mispredicted
  FROM (SELECT *, cast(json_extract_string(props, '$.k') AS int) AS k, CASE event_type WHEN 'view' THEN 'LOAD' WHEN 'click' THEN 'INT_ALU' WHEN 'purchase' THEN 'STORE' WHEN 'signup' THEN 'BRANCH' ELSE 'FP_ALU' END AS op_class FROM events))"""


def with_trace(select: str, more: str = "", ctes: str = TRACE) -> str:
    return f"WITH {ctes.strip()}{', ' + more if more else ''} {select}"


_TOKENS = """CASE len % 8 WHEN 0 THEN 'INT_ALU' WHEN 1 THEN 'INT_ALU' WHEN 2 THEN 'LOAD' WHEN 3 THEN 'BRANCH' WHEN 4 THEN 'STORE' WHEN 5 THEN 'FP_ALU' WHEN 6 THEN 'INT_MUL' ELSE 'FP_MUL' END"""


def token_trace(kind: str) -> str:
    if kind == "documents":
        inner = "SELECT doc_id AS key, unnest(string_split(text, ' ')) AS tok, unnest(range(len(string_split(text, ' ')))) AS pos FROM documents"
    else:
        inner = "SELECT conv_id AS key, turn, unnest(string_split(text, ' ')) AS tok, unnest(range(len(string_split(text, ' ')))) AS pos FROM conversations"
    order = "pos" if kind == "documents" else "row_number() OVER (PARTITION BY key ORDER BY turn, pos) - 1"
    return f"""
SELECT cast(key AS int) AS program_id, cast({order} AS bigint) AS seq, {_TOKENS} AS op_class, cast((pos + len) % 32 AS int) AS src1, cast((3 * pos) % 32 AS int) AS src2,
  CASE WHEN len % 8 NOT IN (3, 4) THEN cast((5 * pos + len) % 32 AS int) END AS dst, CASE WHEN len % 8 IN (2, 4) THEN cast((key % 16) * 64 + (len % 8) * 8 AS bigint) END AS addr
FROM (SELECT *, length(tok) AS len FROM ({inner}))"""


EMBEDDED_LANES = """SELECT cast(i AS int) AS lane, 1 AS ff, false AS ib, 3 AS pen, 1 AS dec, list(1 + cast(floor(abs(cast(e AS double)) * 40) AS int) ORDER BY v) AS lat, cast(NULL AS int) AS mem
  FROM (SELECT v, unnest(range({n})) AS i, unnest(embedding[1:{n}]) AS e FROM (SELECT embedding, row_number() OVER (ORDER BY vec_id) AS v FROM embeddings) WHERE v <= 9) GROUP BY i"""
_STRUCTURE = "2 AS fbw, 2 AS ibw, 2 AS cbw, 1 AS fw, cast(NULL AS int) AS vp"


def _null(x) -> str:
    return "NULL" if x is None else str(x)


def inorder(lanes: list[Machine], select: str, ctes: str = TRACE, lanes_sql: str = "") -> str:
    """The in-order recurrence, one step a seq; ``runs`` has (program_id, lane, cycles, instrs).

    Fetch, issue and commit widths may differ by lane (up to 4). Loads of a lane with ``predicted_permille`` 1000 are all
    predicted: rightly, or with a penalty.
    """
    low = -(10**12)
    units = ["ialu", "imul", "idiv", "fpu", "lsu"]
    u = "CASE " + " ".join(f"WHEN op_class = '{op}' THEN {units.index(c)}" for op, c in P_INO.unit_of.items()) + " END"
    o = "CASE " + " ".join(f"WHEN op_class = '{op}' THEN {OPS.index(op)}" for op in OPS[:9]) + " END"
    vp = lambda m: None if not m.predicted_permille else -1 if m.predict_penalty is None else m.predict_penalty
    values = ", ".join(
        f"({k}, {0 if m.ideal_fetch else 1}, {str(m.ideal_branch).lower()}, {m.penalty}, {m.decode}, {[m.latency[x] for x in OPS[:9]]}, {_null(m.memory)}, {m.fbw}, {m.ibw}, {m.cbw}, {m.forward}, {_null(vp(m))})" for k, m in enumerate(lanes)
    )
    whole = f"SELECT *, {_STRUCTURE} FROM ({lanes_sql})" if lanes_sql else f"SELECT * FROM (VALUES {values}) AS v"
    held = f"CASE WHEN o = 6 AND vp IS NOT NULL THEN CASE WHEN vp < 0 THEN cast({low} AS bigint) ELSE ne + x + vp END ELSE ne + x END"
    past = lambda head: f"[{head}, {low}, {low}, {low}]::bigint[]"
    return f"""
WITH RECURSIVE {ctes.strip()},
lanes(lane, ff, ib, pen, dec, lat, mem, fbw, ibw, cbw, fw, vp) AS ({whole}),
t AS MATERIALIZED (SELECT program_id, seq, src1, src2, dst, CASE WHEN op_class IN ('LOAD', 'STORE') THEN addr END AS addr, coalesce(imem_cycles, 0) AS f, coalesce(dmem_cycles, 0) AS dm, mispredicted AS miss, {u} AS u, {o} AS o FROM trace),
s AS (
 SELECT program_id, lane, seq, {past('0')} AS fh, {past('ne')} AS eh, {past('ne + x')} AS ch, cast(x AS bigint) AS x1, miss AS m1,
  CASE WHEN o = 7 THEN addr END AS a1, list_transform(range(32), lambda i: CASE WHEN i = dst THEN cast({held} AS bigint) ELSE cast({low} AS bigint) END) AS regs,
  list_transform(range(10), lambda i: CASE WHEN i = u * 2 + 1 THEN cast(ne + CASE WHEN o IN (2, 5) THEN x ELSE 1 END AS bigint) ELSE cast({low} AS bigint) END) AS us,
  cast({low} AS bigint) AS q2, CASE WHEN o IN (6, 7) THEN cast(ne + x AS bigint) ELSE cast({low} AS bigint) END AS q1
 FROM (SELECT *, dec AS ne, lat[o + 1] + CASE WHEN o = 6 THEN coalesce(mem, dm) ELSE 0 END AS x FROM t, lanes WHERE seq = 0)
 UNION ALL
 SELECT program_id, lane, seq, [nf] || fh[1:3], [ne] || eh[1:3], [nc] || ch[1:3], x, miss, CASE WHEN o = 7 THEN addr END,
  CASE WHEN dst IS NULL THEN regs ELSE regs[1:dst] || [{held}] || regs[dst + 2:32] END,
  us[1:u * 2] || [us[u * 2 + 2], ne + CASE WHEN o IN (2, 5) THEN x ELSE 1 END] || us[u * 2 + 3:10],
  CASE WHEN o IN (6, 7) THEN q1 ELSE q2 END, CASE WHEN o IN (6, 7) THEN nc ELSE q1 END
 FROM (SELECT *, greatest(ne + x, ch[1], ch[cbw] + 1) AS nc
  FROM (SELECT *, greatest(nf + dec, eh[1], eh[ibw] + 1, coalesce(regs[src1 + 1], {low}), coalesce(regs[src2 + 1], {low}), CASE WHEN o = 6 AND a1 = addr THEN eh[1] + fw ELSE {low} END, us[u * 2 + 1], CASE WHEN o IN (6, 7) THEN q2 ELSE {low} END) AS ne
   FROM (SELECT s.program_id, s.lane, t.seq, fh, eh, ch, a1, regs, us, q1, q2, t.src1, t.src2, t.dst, t.addr, t.miss, t.u, t.o, l.dec, l.fbw, l.ibw, l.cbw, l.fw, l.vp,
     cast(l.lat[t.o + 1] + CASE WHEN t.o = 6 THEN coalesce(l.mem, t.dm) ELSE 0 END AS bigint) AS x,
     greatest(CASE WHEN m1 AND NOT l.ib THEN eh[1] + x1 + l.pen ELSE fh[1] END + l.ff * t.f, fh[l.fbw] + 1) AS nf
    FROM s JOIN t ON t.program_id = s.program_id AND t.seq = s.seq + 1 JOIN lanes l ON l.lane = s.lane)))),
runs AS (SELECT program_id, cast(lane AS int) AS lane, cast(max(ch[1]) AS bigint) AS cycles, cast(max(seq) + 1 AS bigint) AS instrs FROM s GROUP BY program_id, lane)
{select}"""


def unordered(m: Machine, select: str) -> str:
    """The recurrence of an in-order core whose instructions wait for no issue order, unit or queue: fetch, data, commit.

    Any earlier store may bind, so the last store of each address is kept.
    """
    low = -(10**12)
    o = "CASE " + " ".join(f"WHEN op_class = '{op}' THEN {OPS.index(op)}" for op in OPS[:9]) + " END"
    lat = [m.latency[x] for x in OPS[:9]]
    return f"""
WITH RECURSIVE {TRACE.strip()},
t AS MATERIALIZED (SELECT program_id, seq, src1, src2, dst, addr, coalesce(imem_cycles, 0) AS f, mispredicted AS miss, {o} AS o, {lat}[{o} + 1] + CASE WHEN op_class = 'LOAD' THEN coalesce(dmem_cycles, 0) ELSE 0 END AS x FROM trace),
s AS (
 SELECT program_id, seq, cast(0 AS bigint) AS f1, cast({low} AS bigint) AS f2, cast({m.decode} AS bigint) AS e1, cast({m.decode} + x AS bigint) AS c1, cast({low} AS bigint) AS c2, x AS x1, miss AS m1,
  list_transform(range(32), lambda i: CASE WHEN i = dst THEN cast({m.decode} + x AS bigint) ELSE cast({low} AS bigint) END) AS regs,
  CASE WHEN o = 7 THEN MAP {{cast(addr AS bigint): cast({m.decode} AS bigint)}} ELSE MAP {{cast(-1 AS bigint): cast({low} AS bigint)}} END AS st FROM t WHERE seq = 0
 UNION ALL
 SELECT program_id, seq, nf, f1, ne, greatest(ne + x, c1, c2 + 1), c1, x, miss, CASE WHEN dst IS NULL THEN regs ELSE regs[1:dst] || [ne + x] || regs[dst + 2:32] END,
  CASE WHEN o = 7 THEN map_concat(st, MAP {{cast(addr AS bigint): ne}}) ELSE st END
 FROM (SELECT *, greatest(nf + {m.decode}, coalesce(regs[src1 + 1], {low}), coalesce(regs[src2 + 1], {low}), CASE WHEN o = 6 THEN coalesce(element_at(st, addr)[1], {low}) + {m.forward} ELSE {low} END) AS ne
  FROM (SELECT t.*, f1, c1, c2, regs, st, greatest(CASE WHEN m1 THEN e1 + x1 + {m.penalty} ELSE f1 END + t.f, f2 + 1) AS nf FROM s JOIN t ON t.program_id = s.program_id AND t.seq = s.seq + 1)))
{select}"""


def renamed(more: str, ctes: str = TRACE) -> str:
    """CTEs in which ``trace`` is made by ``more`` from the main trace, there called ``whole``."""
    return ctes.replace("trace AS (SELECT program_id", "whole AS (SELECT program_id") + f", trace AS ({more})"


def named(machines: dict[str, Machine], select: str = "SELECT program_id, scenario, cycles FROM n") -> str:
    """Runs of named machines: ``n`` has (program_id, scenario, cycles)."""
    return inorder(list(machines.values()), f", n AS (SELECT program_id, {list(machines)}[lane + 1] AS scenario, cycles FROM runs) {select}")


CRACKED = renamed("""SELECT program_id, row_number() OVER (PARTITION BY program_id ORDER BY seq, part) - 1 AS seq, op_class, src1, src2, dst, addr, imem_cycles, dmem_cycles, mispredicted FROM (
  SELECT program_id, seq, 0 AS part, CASE WHEN c THEN 'LOAD' ELSE op_class END AS op_class, CASE WHEN NOT c THEN src1 END AS src1, CASE WHEN NOT c THEN src2 END AS src2, CASE WHEN c THEN 31 ELSE dst END AS dst, addr, imem_cycles, dmem_cycles, mispredicted
  FROM (SELECT *, op_class = 'INT_MUL' AND pc % 5 = 0 AS c FROM whole)
  UNION ALL SELECT program_id, seq, 1, op_class, src1, 31, dst, NULL, imem_cycles, dmem_cycles, mispredicted FROM whole WHERE op_class = 'INT_MUL' AND pc % 5 = 0)""")


def recorded(kind: str) -> str:
    """CTEs that end in ``trace``: a token trace with statistical costs."""
    return f"""tokens AS ({token_trace(kind)}),
trace AS (SELECT program_id, seq, op_class, src1, src2, dst, addr,
  CASE WHEN seq % 16 = 0 THEN CASE WHEN (104729 * seq + 7 + 31 * program_id) % 100 < 98 THEN 1 ELSE 20 END ELSE 0 END AS imem_cycles,
  CASE WHEN op_class IN ('LOAD', 'STORE') THEN CASE WHEN (7919 * seq + 13 + 31 * program_id) % 100 < 90 THEN 2 ELSE 20 END END AS dmem_cycles,
  op_class = 'BRANCH' AND CASE WHEN toxic IS NOT NULL THEN toxic = 1 AND seq % 4 = 0 ELSE (6151 * seq + 3 + 31 * program_id) % 100 >= 95 END AS mispredicted FROM tokens LEFT JOIN labels ON doc_id = program_id)"""


_LAT = "CASE op_class " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in LATENCY.items()) + " END + CASE WHEN op_class = 'LOAD' THEN dmem_cycles ELSE 0 END"
X = f"x AS (SELECT *, {_LAT} AS x FROM trace)"
_E = "program_id, cast({src} AS bigint) AS src_seq, '{a}' AS src_stage, cast(seq AS bigint) AS dst_seq, '{b}' AS dst_stage, '{kind}' AS kind, cast({w} AS int) AS w"


def edge(src: str, a: str, b: str, kind: str, w: str) -> str:
    return _E.format(src=src, a=a, b=b, kind=kind, w=w)


_P = "PARTITION BY program_id ORDER BY seq"
EDGES = {
    "edges_frontend": with_trace(f"SELECT * FROM (SELECT {edge(f'lag(seq, 2) OVER ({_P})', 'F', 'F', 'fetch_bw', '1')} FROM trace) WHERE src_seq IS NOT NULL"),
    "edges_control": with_trace(
        f"""SELECT {edge('p', 'F', 'F', 'fetch', 'imem_cycles')} FROM y WHERE p IS NOT NULL AND NOT m UNION ALL SELECT {edge('p', 'E', 'F', 'control', f'px + {P_INO.penalty} + imem_cycles')} FROM y WHERE m""",
        f"{X}, y AS (SELECT *, lag(seq) OVER ({_P}) AS p, coalesce(lag(mispredicted) OVER ({_P}), false) AS m, lag(x) OVER ({_P}) AS px FROM x)",
    ),
    "edges_commit": with_trace(
        f"""SELECT * FROM (SELECT {edge(f'lag(seq) OVER ({_P})', 'C', 'C', 'commit', '0')} FROM trace UNION ALL SELECT {edge(f'lag(seq, 2) OVER ({_P})', 'C', 'C', 'commit_bw', '1')} FROM trace) WHERE src_seq IS NOT NULL"""
    ),
    "edges_pipeline": with_trace(f"SELECT {edge('seq', 'F', 'E', 'pipe', str(P_INO.decode))} FROM x UNION ALL SELECT {edge('seq', 'E', 'C', 'pipe', 'x')} FROM x", X),
    "edges_data_reg": with_trace(
        f"SELECT DISTINCT r.program_id, w.seq AS src_seq, 'E' AS src_stage, r.seq AS dst_seq, 'E' AS dst_stage, 'data_reg' AS kind, cast(w.x AS int) AS w FROM r ASOF JOIN w ON r.program_id = w.program_id AND r.reg = w.reg AND r.seq > w.seq",
        f"{X}, r AS (SELECT program_id, seq, src1 AS reg FROM x WHERE src1 IS NOT NULL UNION SELECT program_id, seq, src2 FROM x WHERE src2 IS NOT NULL), w AS (SELECT program_id, seq, dst AS reg, x FROM x WHERE dst IS NOT NULL)",
    ),
    "edges_data_mem": with_trace(
        "SELECT l.program_id, s.seq AS src_seq, 'E' AS src_stage, l.seq AS dst_seq, 'E' AS dst_stage, 'data_mem' AS kind, cast(1 AS int) AS w FROM l ASOF JOIN s ON l.program_id = s.program_id AND l.addr = s.addr AND l.seq > s.seq",
        "l AS (SELECT * FROM trace WHERE op_class = 'LOAD'), s AS (SELECT * FROM trace WHERE op_class = 'STORE')",
    ),
    "edges_issue": with_trace(
        f"""SELECT * FROM (SELECT {edge(f'lag(seq) OVER ({_P})', 'E', 'E', 'issue', '0')} FROM trace UNION ALL SELECT {edge(f'lag(seq, 2) OVER ({_P})', 'E', 'E', 'issue_bw', '1')} FROM trace) WHERE src_seq IS NOT NULL"""
    ),
    "edges_fu_inorder": with_trace(
        f"SELECT * FROM (SELECT {edge('lag(seq, 2) OVER (PARTITION BY program_id, u ORDER BY seq)', 'E', 'E', 'fu_occ', 'lag(occ, 2) OVER (PARTITION BY program_id, u ORDER BY seq)')} FROM y) WHERE src_seq IS NOT NULL",
        X + ", y AS (SELECT *, CASE " + " ".join(f"WHEN op_class = '{o}' THEN '{u}'" for o, u in P_INO.unit_of.items()) + " END AS u, CASE WHEN op_class IN ('INT_DIV', 'FP_DIV') THEN x ELSE 1 END AS occ FROM x)",
    ),
    "edges_queue": with_trace(
        f"SELECT * FROM (SELECT {edge(f'lag(seq, 2) OVER ({_P})', 'C', 'E', 'queue', '0')} FROM trace WHERE op_class IN ('LOAD', 'STORE')) WHERE src_seq IS NOT NULL"
    ),
}

_B = "PARTITION BY program_id, block_no"
PRODUCERS = f"""
use AS (SELECT program_id, block_no, slot, src1 AS reg FROM trace WHERE src1 IS NOT NULL UNION SELECT program_id, block_no, slot, src2 FROM trace WHERE src2 IS NOT NULL),
put AS (SELECT program_id, block_no, slot, dst AS reg FROM trace WHERE dst IS NOT NULL),
pr AS (SELECT DISTINCT u.program_id, u.block_no, u.slot, p.slot AS src_slot FROM use u ASOF JOIN put p ON u.program_id = p.program_id AND u.block_no = p.block_no AND u.reg = p.reg AND u.slot > p.slot),
fan AS (SELECT program_id, block_no, src_slot AS slot, count(*) AS k FROM pr GROUP BY ALL)"""
READS = "fr AS (SELECT u.program_id, u.block_no, u.reg, min(u.slot) AS u, (SELECT min(slot) FROM put p WHERE p.program_id = u.program_id AND p.block_no = u.block_no AND p.reg = u.reg) AS w FROM use u GROUP BY ALL), reads AS (SELECT program_id, block_no, count(*) AS n FROM fr WHERE w IS NULL OR w >= u GROUP BY ALL)"
MOVS = "movs AS (SELECT program_id, block_no, cast(sum(k - 2) AS bigint) AS n FROM fan WHERE k > 2 GROUP BY ALL)"
NULLS = """nulls AS (SELECT * FROM (SELECT program_id, block_no, cast(abs(sum(CASE WHEN dst IS NOT NULL THEN CASE WHEN slot % 2 = 0 THEN 1 ELSE -1 END ELSE 0 END)) + abs(sum(CASE WHEN op_class = 'STORE' THEN CASE WHEN slot % 2 = 0 THEN 1 ELSE -1 END ELSE 0 END)) AS bigint) AS n
  FROM trace WHERE predicated GROUP BY ALL) WHERE n > 0)"""


def up(e: str, per: int = 16) -> str:
    return f"(({e}) + {per - 1}) // {per}"


DELAY = f"""fields AS (SELECT t.program_id, t.block_no, t.slot, CASE WHEN k > 1 THEN 2 ELSE 0 END AS t, CASE WHEN op_class LIKE 'FP%' OR op_class = 'INT_DIV' THEN 1 ELSE 0 END AS o, (t.slot % 4) * 2 AS v
  FROM trace t LEFT JOIN fan f ON f.program_id = t.program_id AND f.block_no = t.block_no AND f.slot = t.slot),
cum AS (SELECT *, row_number() OVER w AS i, count(*) OVER ({_B}) AS cnt, sum(t) OVER w AS ct, sum(o) OVER w AS co, sum(v) OVER w AS cv, sum(t) OVER ({_B}) AS st, sum(o) OVER ({_B}) AS so FROM fields WINDOW w AS ({_B} ORDER BY slot ROWS UNBOUNDED PRECEDING)),
dl AS (SELECT *, {up('2 * i')} AS base, CASE WHEN t + o + v > 0 THEN {up('2 * cnt + ct + co + cv')} ELSE 0 END AS two, {up('2 * i + ct + co + cv')} AS one,
  greatest(CASE WHEN t > 0 THEN {up('2 * cnt + ct')} ELSE 0 END, CASE WHEN o > 0 THEN {up('2 * cnt + st + co')} ELSE 0 END, CASE WHEN v > 0 THEN {up('2 * cnt + st + so + cv')} ELSE 0 END) AS four FROM cum)"""

BLOCKS = {
    "block_sizes": with_trace(
        "SELECT program_id, block_no, instrs, stores, writes, cast(greatest((stores + 1) // 2, (writes + 3) // 4) AS bigint) AS commit_cycles FROM (SELECT program_id, block_no, count(*) AS instrs, cast(count(*) FILTER (WHERE op_class = 'STORE') AS bigint) AS stores, count(DISTINCT dst) AS writes FROM trace GROUP BY ALL)"
    ),
    "block_reads": with_trace("SELECT * FROM reads", PRODUCERS + ", " + READS),
    "block_movs": with_trace("SELECT * FROM movs", PRODUCERS + ", " + MOVS),
    "block_nulls": with_trace("SELECT * FROM nulls", NULLS),
    "block_mix": with_trace(
        "SELECT program_id, op_class AS class, count(*) AS n FROM trace GROUP BY ALL UNION ALL SELECT program_id, 'READ', cast(sum(n) AS bigint) FROM reads GROUP BY ALL UNION ALL SELECT program_id, 'MOV', cast(sum(n) AS bigint) FROM movs GROUP BY ALL UNION ALL SELECT program_id, 'NULL', cast(sum(n) AS bigint) FROM nulls GROUP BY ALL",
        ", ".join((PRODUCERS, READS, MOVS, NULLS)),
    ),
    "block_decode_delay": with_trace(
        "SELECT program_id, block_no, slot, '4seg' AS format, cast(greatest(base, four) AS int) AS delay FROM dl UNION ALL SELECT program_id, block_no, slot, '2seg', cast(greatest(base, two) AS int) FROM dl UNION ALL SELECT program_id, block_no, slot, 'contiguous', cast(one AS int) FROM dl UNION ALL SELECT program_id, block_no, slot, 'contiguous+1', cast(one + 1 AS int) FROM dl",
        PRODUCERS + ", " + DELAY,
    ),
}
