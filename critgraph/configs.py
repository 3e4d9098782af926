"""Machine descriptions (lanes), presets and their edits."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from critgraph.schemas import CODE, OPS, TERM_OF_OP

#: Default latencies.
LATENCY = {"INT_ALU": 1, "INT_MUL": 3, "INT_DIV": 9, "FP_ALU": 4, "FP_MUL": 6, "FP_DIV": 12, "LOAD": 1, "STORE": 1, "BRANCH": 1, "READ": 1, "MOV": 1, "NULL": 1}
BLOCKING = frozenset({"INT_DIV", "FP_DIV"})
IN_ORDER_UNITS = {"INT_ALU": "ialu", "BRANCH": "ialu", "INT_MUL": "imul", "INT_DIV": "idiv", "FP_ALU": "fpu", "FP_MUL": "fpu", "FP_DIV": "fpu", "LOAD": "lsu", "STORE": "lsu"}
OOO_UNITS = {"INT_ALU": "ialu", "BRANCH": "ialu", "INT_MUL": "imd", "INT_DIV": "imd", "FP_ALU": "falu", "FP_MUL": "fmd", "FP_DIV": "fmd", "LOAD": "lsu", "STORE": "lsu"}


@dataclass(frozen=True)
class Machine:
    """One configuration. A width or size of None is unlimited; a rule switched off adds no edge."""

    name: str
    core: str  # inorder | ooo
    fbw: int | None = 2
    dbw: int | None = None
    ibw: int | None = 2
    cbw: int | None = 2
    rob: int | None = None
    iq: int | None = None
    lq: int | None = None
    sq: int | None = None
    lsq: int | None = None
    units: dict[str, int] = field(default_factory=dict)
    unit_of: dict[str, str] = field(default_factory=dict)
    depth: dict[str, int] = field(default_factory=dict)
    fu_policy: str = "lru"  # lru | earliest: the unit used longest ago, or the one free first
    latency: dict[str, int] = field(default_factory=lambda: dict(LATENCY))
    blocking: frozenset[str] = BLOCKING
    decode: int = 1
    penalty: int = 3
    forward: int = 1
    window: int = 192
    active: bool = True
    ideal_fetch: bool = False
    ideal_branch: bool = False
    memory: int | None = None  # data-memory cycles for all accesses, in place of the recorded ones
    predicted_permille: int = 0  # loads whose register edges go (seeded choice)
    predict_penalty: int | None = None  # with it, the chosen edges stay and carry this penalty (wrong predictions)

    def edit(self, **changes) -> Machine:
        return replace(self, **changes)

    def set_latency(self, **by_op: int) -> Machine:
        return replace(self, latency={**self.latency, **by_op})

    def set_units(self, **m: int) -> Machine:
        return replace(self, units={**self.units, **m})

    def without_resources(self) -> Machine:
        """Prior graph tools: no structural hazards, no scheduling."""
        return replace(self, units={}, depth={}, lsq=None, lq=None, sq=None, rob=None, iq=None, ibw=None)

    def set_term(self, term: str, cycles: int) -> Machine:
        """All edges of a breakdown category cost ``cycles``."""
        if term == "fetch" and cycles == 0:
            return replace(self, ideal_fetch=True)
        if term == "decode":
            return replace(self, decode=cycles)
        if term == "branch_penalty":
            return replace(self, penalty=cycles)
        if term == "forward":
            return replace(self, forward=cycles)
        ops = [op for op, t in TERM_OF_OP.items() if t == term]
        if not ops:
            raise ValueError(f"no such term: {term}")
        out = replace(self, latency={**self.latency, **{op: cycles for op in ops}})
        return replace(out, memory=cycles) if term in ("load", "store") and cycles == 0 else out

    def structure(self) -> tuple:
        """What lanes of one vector run must share."""
        return (self.core, self.fbw, self.dbw, self.ibw, self.cbw, self.rob, self.iq, self.lq, self.sq, self.lsq, tuple(sorted(self.units.items())), tuple(sorted(self.unit_of.items())), tuple(sorted(self.depth.items())), self.fu_policy, self.window, self.active)

    def tables(self) -> tuple[list[int], list[bool], list[str | None]]:
        """By operation code: latency, blocking?, unit class."""
        return [self.latency[o] for o in OPS], [o in self.blocking for o in OPS], [self.unit_of.get(o) if self.unit_of.get(o) in self.units else None for o in OPS]


P_INO = Machine("P-InO", "inorder", units={"ialu": 2, "imul": 2, "idiv": 2, "fpu": 2, "lsu": 2}, unit_of=IN_ORDER_UNITS, lsq=2)
P_OOO = Machine(
    "P-OoO", "ooo", fbw=8, dbw=8, ibw=8, cbw=8, rob=192, lq=32, sq=32, units={"ialu": 6, "imd": 2, "falu": 4, "fmd": 2, "lsu": 4}, unit_of=OOO_UNITS,
    decode=2, penalty=8, window=192,
)
#: The block core: seeded statistics in place of recorded costs.
P_EDGE = {
    "segment": 32, "units": {"INT_ALU": 8, "INT_MUL": 2, "INT_DIV": 2, "FP_ALU": 2, "FP_MUL": 2, "FP_DIV": 1, "LSU": 2},
    "branch_pct": 95, "ihit_pct": 98, "dhit_pct": 90, "hit": 2, "miss": 10, "stores_per_cycle": 2, "writes_per_cycle": 4, "bytes_per_cycle": 16,
}


def lanes_from_embeddings(base: Machine, vectors: list[list[float]]) -> list[Machine]:
    """Irregular lanes: element i of vector v is lane i's latency of operation class v."""
    names = [OPS[k] for k in range(9)]
    return [base.edit(name=f"lane{i}", latency={**base.latency, **{names[v]: 1 + int(abs(x[i]) * 40) for v, x in enumerate(vectors[: len(names)])}}) for i in range(len(vectors[0]))]


def grid(base: Machine, **axes: list) -> list[Machine]:
    """The cross product of edits, one lane each."""
    out = [base]
    for key, values in axes.items():
        out = [m.edit(**{key: v}).edit(name=f"{m.name},{key}={v}") for m in out for v in values]
    return out


def predicted(seq: int, pc: int, permille: int, seed: int = 42) -> bool:
    """Seeded choice of loads whose value is predicted."""
    return (seq * 7919 + pc * 104729 + seed * 1299709) % 1000 < permille


__all__ = ["CODE", "LATENCY", "Machine", "P_EDGE", "P_INO", "P_OOO", "grid", "lanes_from_embeddings", "predicted"]
