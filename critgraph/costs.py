"""Costs that are not recorded: seeded statistics and a functional cache model."""

from __future__ import annotations

from collections import OrderedDict

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from critgraph.operators.runs import arrow_types
from critgraph.runtime import ship


def seeded(a: int, b: int, modulus: int = 100) -> Column:
    """A number below ``modulus`` from the row's seq, the same in every engine."""
    return F.pmod(a * F.col("seq") + b + 31 * F.col("program_id"), F.lit(modulus))


def stat_mem(trace: DataFrame, hit_pct: int, hit: int, miss: int, ihit_pct: int = 98, imiss: int = 20) -> DataFrame:
    """Memory cycles by hit rates: data accesses, and the fetch at the start of each line."""
    data = F.when(F.col("op_class").isin("LOAD", "STORE"), F.when(seeded(7919, 13) < hit_pct, hit).otherwise(miss)).cast("int")
    line = F.when(F.col("seq") % 16 == 0, F.when(seeded(104729, 7) < ihit_pct, 1).otherwise(imiss)).otherwise(0).cast("int")
    return trace.withColumns({"dmem_cycles": data, "imem_cycles": line})


def stat_branch(trace: DataFrame, accuracy_pct: int) -> DataFrame:
    """Branch outcomes that match an overall accuracy only."""
    return trace.withColumn("mispredicted", (F.col("op_class") == "BRANCH") & (seeded(6151, 3) >= accuracy_pct))


def recorded(trace: DataFrame, hit_pct: int = 90, hit: int = 2, miss: int = 20, accuracy_pct: int = 95) -> DataFrame:
    """Recorded costs where present, statistics where they are null."""
    model = stat_branch(stat_mem(trace.withColumnsRenamed({c: f"_{c}" for c in ("imem_cycles", "dmem_cycles", "mispredicted")}), hit_pct, hit, miss), accuracy_pct)
    return model.withColumns({c: F.coalesce(f"_{c}", c) for c in ("imem_cycles", "dmem_cycles", "mispredicted")}).drop("_imem_cycles", "_dmem_cycles", "_mispredicted")


def calibrated_statistics(trace: DataFrame) -> DataFrame:
    """Lower-fidelity inputs: each program keeps only its overall rates of data hits, line hits and right predictions."""
    rates = trace.groupBy("program_id").agg(
        F.expr("cast(round(100.0 * sum(case when dmem_cycles > 2 then 1 else 0 end) / greatest(count(dmem_cycles), 1)) as int)").alias("_d"),
        F.expr("cast(round(100.0 * sum(case when imem_cycles > 1 then 1 else 0 end) / greatest(sum(case when imem_cycles > 0 then 1 else 0 end), 1)) as int)").alias("_i"),
        F.expr("cast(round(100.0 * sum(case when mispredicted then 1 else 0 end) / greatest(sum(case when is_branch then 1 else 0 end), 1)) as int)").alias("_b"),
    )
    d = trace.join(F.broadcast(rates), "program_id")  # a row a program
    return d.withColumns({
        "dmem_cycles": F.when(F.col("dmem_cycles").isNotNull(), F.when(seeded(7919, 13) < F.col("_d"), 20).otherwise(2)).cast("int"),
        "mispredicted": (F.col("op_class") == "BRANCH") & (seeded(6151, 3) < F.col("_b")),
        "imem_cycles": F.when(F.col("imem_cycles") > 0, F.when(seeded(104729, 7) < F.col("_i"), 20).otherwise(1)).otherwise(0).cast("int"),
    }).drop("_d", "_i", "_b")


class Level:
    """A set-associative LRU cache level."""

    def __init__(self, sets: int, ways: int, hit: int):
        self.sets, self.ways, self.hit = sets, ways, hit
        self.lines: list[OrderedDict] = [OrderedDict() for _ in range(sets)]

    def access(self, line: int) -> bool:
        own = self.lines[line % self.sets]
        if line in own:
            own.move_to_end(line)
            return True
        own[line] = True
        if len(own) > self.ways:
            own.popitem(last=False)
        return False


#: 32 KB first level (64-byte lines, 8 ways), 1 MB last level (16 ways).
LEVELS = ((64, 8, 2), (1024, 16, 10))
MEMORY = 40


def cache_model(trace: DataFrame, levels: tuple[tuple[int, int, int], ...] = LEVELS, memory: int = MEMORY) -> DataFrame:
    """(program_id, seq, dmem_cycles) of each access by a functional model of the hierarchy; state of fixed size."""
    ship(trace.sparkSession)
    schema = "program_id int, seq bigint, dmem_cycles int"

    def run(batches):
        import pyarrow as pa

        before, caches = None, []
        for b in batches:
            out = []
            for program, addr in zip(b.column(0).to_pylist(), b.column(2).to_pylist()):
                if program != before:
                    before, caches = program, [Level(*x) for x in levels]
                cost = memory
                for c in caches:
                    if c.access(addr >> 6):
                        cost = c.hit
                        break
                out.append(cost)
            yield pa.record_batch([b.column(0), b.column(1), pa.array(out, arrow_types(schema)[2])], names=["program_id", "seq", "dmem_cycles"])

    d = trace.where("addr is not null").select(F.col("program_id").cast("int"), F.col("seq").cast("bigint"), F.col("addr").cast("bigint"))
    return d.repartition("program_id").sortWithinPartitions("program_id", "seq").mapInArrow(run, schema)


def low_fidelity(trace: DataFrame) -> DataFrame:
    """Inputs of lower fidelity: data accesses by an own cache model (costs as recorded: a hit 2, a miss 20), the rest by overall rates."""
    own = cache_model(trace, ((64, 8, 2),), 20).withColumnRenamed("dmem_cycles", "_own")
    d = calibrated_statistics(trace).join(own, ["program_id", "seq"], "left")
    return d.withColumn("dmem_cycles", F.coalesce("_own", "dmem_cycles")).drop("_own")
