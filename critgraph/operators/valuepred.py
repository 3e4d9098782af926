"""Value prediction: which loads to predict, and what it brings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.configs import Machine, predicted
from critgraph.operators import kernels
from critgraph.operators.runs import _grouped

CURVE = "program_id int, sweep string, pass int, step int, predicted bigint, loads bigint, base bigint, cycles bigint"


class Predicted:
    """A program under many choices of predicted loads: what follows from the trace alone is found once."""

    def __init__(self, cols: dict[str, list], m: Machine):
        self.p = kernels.Program(cols, m)
        self.loads = [i for i, o in enumerate(cols["op"]) if o == schemas.LOAD]
        self.pc, self.dmem, self.none = cols["pc"], cols["dmem"], self.p.cut
        self.base = kernels.run(self.p)
        self.all: int | None = None  # cycles with all loads predicted

    def run(self, chosen: set[int]) -> int:
        """Cycles with the values of ``chosen`` loads predicted."""
        if not chosen:
            return self.base
        if len(chosen) == len(self.loads) and self.all is not None:
            return self.all
        self.p.cut = cut = list(self.none)
        for i in chosen:
            cut[i] = True
        cycles = kernels.run(self.p)
        if len(chosen) == len(self.loads):
            self.all = cycles
        return cycles


def _random(x: Predicted, step: int):
    for percent in range(0, 101, step):
        chosen = {i for i in x.loads if predicted(x.p.seq[i], x.pc[i] or 0, 10 * percent)}
        yield "random", 0, percent, len(chosen), len(x.loads), x.base, x.run(chosen)


def _critical(x: Predicted, passes: int, step: int):
    """To be taken before other choices are run: the first critical path is that of the base run."""
    yield "critical", 0, 0, 0, len(x.loads), x.base, x.base
    chosen: set[int] = set()

    def part(new: list[int], number: int):
        for k in range(step, 101, step):
            take = new[: -(-len(new) * k // 100)]
            yield "critical", number, k, len(chosen) + len(take), len(x.loads), x.base, x.run(chosen | set(take))

    for number in range(1, passes + 1):
        new = [i for i in critical_loads(x.p) if i not in chosen]
        if not new:
            break
        new.sort(key=lambda i: ((x.p.seq[i] * 7919 + 42 * 1299709) % 100003, i))
        yield from part(new, number)
        chosen |= set(new)
    rest = sorted(set(x.loads) - chosen, key=lambda i: (-(x.dmem[i] or 0), i))
    if rest:
        yield from part(rest, passes + 1)


def _sweeps(trace: DataFrame, m: Machine, *of) -> DataFrame:
    def fn(program, cols):
        x = Predicted(cols, m)
        for sweep in of:
            for row in sweep(x):
                yield program, *row

    return _grouped(trace, fn, CURVE)


def random_sweep(trace: DataFrame, m: Machine, step: int = 10) -> DataFrame:
    """Seeded choice of loads, blind to criticality: a point every ``step`` percent."""
    return _sweeps(trace, m, lambda x: _random(x, step))


def critical_loads(p: kernels.Program) -> list[int]:
    """Loads a register edge of which lies on the critical path."""
    return sorted({w for w, ws, i, s, kind, _ in kernels.critical_path(p) if kind == "data_reg" and p.op[w] == schemas.LOAD})


def critical_sweep(trace: DataFrame, m: Machine, passes: int = 3, step: int = 20) -> DataFrame:
    """Critical loads first, in seeded random order and steps; then those newly critical, pass by pass; the rest by latency, longest first."""
    return _sweeps(trace, m, lambda x: _critical(x, passes, step))


def both_sweeps(trace: DataFrame, m: Machine) -> DataFrame:
    """The critical and the random sweep, over one reading of the trace and one base run."""
    return _sweeps(trace, m, lambda x: _critical(x, 3, 20), lambda x: _random(x, 10))


def focused(trace: DataFrame, m: Machine, coverage: int = 19, critical: int = 40) -> DataFrame:
    """The published focused point: ``critical`` percent of the first critical loads, filled with others to ``coverage`` percent."""

    def fn(program, cols):
        loads = [i for i, o in enumerate(cols["op"]) if o == schemas.LOAD]
        p = kernels.Program(cols, m)
        base = kernels.run(p)
        first = critical_loads(p)
        take = set(first[: len(first) * critical // 100])
        want = len(loads) * coverage // 100
        for i in loads:
            if len(take) >= want:
                break
            take.add(i)
        q = kernels.Program(cols, m, take)
        yield program, "focused", 0, coverage, len(take), len(loads), base, kernels.run(q)

    return _grouped(trace, fn, CURVE)


def curve(points: DataFrame) -> DataFrame:
    """(program_id, sweep, pass, step, coverage, improvement)."""
    return points.select("program_id", "sweep", "pass", "step", F.round(F.col("predicted") / F.greatest("loads", F.lit(1)), 6).alias("coverage"), F.round(1 - F.col("cycles") / F.col("base"), 6).alias("improvement"))


def mean_curve(points: DataFrame) -> DataFrame:
    """The curve averaged over programs, a point for each step of each pass, with the published reference points."""
    c = curve(points)
    d = c.groupBy("sweep", "pass", "step").agg(F.round(F.avg("coverage"), 6).alias("coverage"), F.round(F.avg("improvement"), 6).alias("improvement"))
    #: fixed values: the criticality-unaware and the focused reference of the paper, coverage and speed-up
    reference = points.sparkSession.createDataFrame([("reference_random", 0, 40, 0.40, 0.066), ("reference_focused", 0, 19, 0.19, 0.058)], "sweep string, pass int, step int, coverage double, improvement double")
    return d.unionByName(reference)


def knee(points: DataFrame, share: float = 0.9) -> DataFrame:
    """(sweep, coverage, improvement, best): the least mean coverage that brings ``share`` of the best mean improvement of a sweep."""
    d = mean_curve(points).where("sweep in ('random', 'critical')")
    best = d.groupBy("sweep").agg(F.max("improvement").alias("best"))
    near = d.join(F.broadcast(best), "sweep").where(F.col("improvement") >= share * F.col("best"))  # a row a sweep
    return near.groupBy("sweep", "best").agg(F.min(F.struct("coverage", "improvement")).alias("p")).select("sweep", "p.coverage", "p.improvement", "best")
