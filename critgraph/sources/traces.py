"""Instruction traces derived from the given tables, by integer arithmetic alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from critgraph import schemas
from critgraph.runtime import ranked
from critgraph.sources.tables import table

WRONG_PATH_CYCLES = 5
ORDER = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity", "l_shipdate")


def _by_region(values: dict[int, int], rest: int) -> Column:
    out = F.lit(rest)
    for region, v in values.items():
        out = F.when(F.col("n_regionkey") == region, v).otherwise(out)
    return out


def _op_class() -> Column:
    t, k, r = F.col("p_type"), F.col("p_size") % 4, F.col("n_regionkey")
    return (
        F.when(t == "LARGE", "LOAD").when(t == "PROMO", "BRANCH")
        .when(t == "MEDIUM", F.when(k < 2, "STORE").when(r == 1, "LOAD").otherwise("INT_ALU"))
        .when(t == "ECONOMY", F.when(k == 3, "INT_MUL").otherwise("INT_ALU"))
        .when(t == "STANDARD", F.when(k == 3, F.when(r == 3, "FP_MUL").otherwise("INT_DIV")).otherwise("INT_ALU"))
        .otherwise(F.when(r == 2, "INT_MUL").when(k < 2, "FP_ALU").when(k == 2, "FP_MUL").otherwise("FP_DIV"))
    )


def lineitem_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per executed or wrongly fetched instruction, not yet numbered.

    Only the columns that the trace needs leave the scans. An order's nation is found before its lines are joined, so
    no line is dealt by customer. The dimension tables are joined without hints: Spark broadcasts those whose size it
    knows to be small.
    """
    wrong = (F.round(F.col("l_tax") * 100).cast("int") == 4) & (F.round(F.col("l_discount") * 100).cast("int") == 5)
    li = table(spark, sf_dir, "lineitem").select(*ORDER, wrong.alias("wrong_path"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    part = table(spark, sf_dir, "part").select("p_partkey", "p_type", "p_size")
    homes = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))
    d = li.join(homes.drop("o_custkey", "c_custkey", "n_nationkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    return d.withColumns({"program_id": F.col("c_nationkey"), "op_class": _op_class()})


def from_lineitem(spark: SparkSession, sf_dir: str, distributed: bool = False) -> DataFrame:
    """The main trace, wrong-path fetches folded into the next correct-path row.

    ``distributed`` numbers the rows by range partitions instead of a window over each
    program; programs far larger than a task need it, and it gives the same rows.
    """
    d = lineitem_rows(spark, sf_dir)
    if distributed:
        every = ranked(d, ["program_id", *ORDER], "_pos")
        start = every.groupBy("program_id").agg(F.min("_pos").alias("_start"))
        d = ranked(every.where("not wrong_path"), ["_pos"], "_k")
        first = d.groupBy("program_id").agg(F.min("_k").alias("_k0"))
        d = d.join(first, "program_id").join(start, "program_id")
        # rows and correct rows before this one within the program differ by the wrong-path rows before it
        d = d.withColumns({"seq": F.col("_k") - F.col("_k0"), "_w": (F.col("_pos") - F.col("_start")) - (F.col("_k") - F.col("_k0"))})
    else:
        order = Window.partitionBy("program_id").orderBy(*ORDER)
        so_far = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
        d = d.withColumn("_w", F.sum(F.col("wrong_path").cast("bigint")).over(so_far)).withColumn("seq", F.row_number().over(order) - 1 - F.col("_w"))
        d = d.where("not wrong_path")
    op, pk, sk, ok, ln = (F.col(c) for c in ("op_class", "l_partkey", "l_suppkey", "l_orderkey", "l_linenumber"))
    memory = op.isin("LOAD", "STORE")
    miss = (op == "BRANCH") & ((31 * ok + 17 * pk + 7 * ln) % 100 < _by_region({0: 20, 1: 4, 2: 4, 3: 2}, 8))
    d = d.withColumn("mispredicted", miss)
    if distributed:  # the row before, by a join: no task sees a whole program
        d = d.join(d.select("program_id", (F.col("seq") + 1).alias("seq"), F.col("_w").alias("_w_before"), F.col("mispredicted").alias("_missed")), ["program_id", "seq"], "left")
    else:
        by_seq = Window.partitionBy("program_id").orderBy("seq")
        d = d.withColumns({"_w_before": F.lag("_w").over(by_seq), "_missed": F.lag("mispredicted").over(by_seq)})
    folded = WRONG_PATH_CYCLES * (F.col("_w") - F.coalesce("_w_before", F.lit(0)))
    begins = (F.col("seq") % 16 == 0) | F.coalesce("_missed", F.lit(False))
    line = F.when((13 * ok + 11 * pk) % 100 < _by_region({0: 60}, 5), 20).otherwise(1)
    block = Window.partitionBy("program_id", "l_orderkey").orderBy("seq")
    return d.select(
        "program_id", F.col("seq").cast("bigint").alias("seq"), pk.alias("pc"), op,
        (sk % 32).cast("int").alias("src1"),
        F.when((op != "LOAD") & (pk % 4 != 0), (pk + 5 * ln) % 32).cast("int").alias("src2"),
        F.when(~op.isin("STORE", "BRANCH"), (7 * pk + sk) % 32).cast("int").alias("dst"),
        F.when(memory, F.when(pk % 4 == 0, (sk % 8) * 8).otherwise(sk * 4096 + pk * 64)).cast("bigint").alias("addr"),
        F.floor(F.col("seq") / 16).cast("bigint").alias("iline"),
        (F.when(begins, line).otherwise(0) + folded).cast("int").alias("imem_cycles"),
        F.when(memory, F.when((19 * ok + 23 * sk + 29 * ln) % 100 < _by_region({1: 40}, 8), 20).otherwise(2)).cast("int").alias("dmem_cycles"),
        (op == "BRANCH").alias("is_branch"), "mispredicted", F.lit(False).alias("wrong_path"),
        ok.alias("block_no"), (F.row_number().over(block) - 1).cast("int").alias("slot"),
        (2 + F.when(op.startswith("FP") | (op == "INT_DIV"), 1).otherwise(0) + (ln % 4) * 2).cast("int").alias("n_bytes"),
        (F.col("o_orderpriority") == "1-URGENT").alias("predicated"),
    )


def from_events(events: DataFrame, numbered: bool = True) -> DataFrame:
    """The event trace (batch or stream; a stream is not numbered)."""
    k = F.get_json_object("props", "$.k").cast("int")
    op = F.when(F.col("event_type") == "view", "LOAD").when(F.col("event_type") == "click", "INT_ALU").when(F.col("event_type") == "purchase", "STORE").when(F.col("event_type") == "signup", "BRANCH").otherwise("FP_ALU")
    d = events.select(
        (F.col("user_id") % 10).cast("int").alias("program_id"), "event_id", "ts", op.alias("op_class"), (k % 32).cast("int").alias("src1"), F.lit(None).cast("int").alias("src2"),
        F.when(~op.isin("STORE", "BRANCH"), (k * 3 + F.col("user_id")) % 32).cast("int").alias("dst"), F.when(op.isin("LOAD", "STORE"), k * 8).cast("bigint").alias("addr"),
        F.lit(0).alias("imem_cycles"), F.when(op.isin("LOAD", "STORE"), 2 + F.round(F.col("value") * 100).cast("bigint") % 7).cast("int").alias("dmem_cycles"),
        ((op == "BRANCH") & (k % 20 == 0)).alias("mispredicted"),
    )
    if not numbered:
        return d
    return d.withColumn("seq", (F.row_number().over(Window.partitionBy("program_id").orderBy("event_id")) - 1).cast("bigint"))


def _token_columns(pos: Column, token: Column, key: Column) -> dict[str, Column]:
    n = F.length(token)
    op = F.element_at(F.array(*map(F.lit, ("INT_ALU", "INT_ALU", "LOAD", "BRANCH", "STORE", "FP_ALU", "INT_MUL", "FP_MUL"))), (n % 8 + 1).cast("int"))
    return {
        "op_class": op, "src1": ((pos + n) % 32).cast("int"), "src2": ((3 * pos) % 32).cast("int"),
        "dst": F.when(~op.isin("STORE", "BRANCH"), (5 * pos + n) % 32).cast("int"),
        "addr": F.when(op.isin("LOAD", "STORE"), (key % 16) * 64 + (n % 8) * 8).cast("bigint"), "iline": F.floor(pos / 16).cast("bigint"),
    }


def from_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One program per document: an instruction per token; outcomes recorded only where a label exists."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "toxic")
    d = docs.join(labels, "doc_id", "left").select("doc_id", "toxic", F.posexplode(F.split("text", " ", -1)).alias("pos", "token"))
    d = d.withColumns(_token_columns(F.col("pos").cast("bigint"), F.col("token"), F.col("doc_id")))
    outcome = F.when(F.col("op_class") == "BRANCH", F.when(F.col("toxic").isNotNull(), (F.col("toxic") == 1) & (F.col("pos") % 4 == 0)))
    return d.select(
        F.col("doc_id").cast("int").alias("program_id"), F.col("pos").cast("bigint").alias("seq"), "op_class", "src1", "src2", "dst", "addr", "iline",
        F.lit(None).cast("int").alias("imem_cycles"), F.lit(None).cast("int").alias("dmem_cycles"), outcome.alias("mispredicted"),
    )


def from_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The block trace: a block is a run of at most 128 tokens of a turn."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", F.posexplode(F.split("text", " ", -1)).alias("pos", "token"))
    c = c.withColumns(_token_columns(F.col("pos").cast("bigint"), F.col("token"), F.col("conv_id")))
    order = Window.partitionBy("conv_id").orderBy("turn", "pos")
    block = F.dense_rank().over(Window.partitionBy("conv_id").orderBy("turn", F.floor(F.col("pos") / 128)))
    return c.select(
        F.col("conv_id").cast("int").alias("program_id"), (F.row_number().over(order) - 1).cast("bigint").alias("seq"), "op_class", "src1", "src2", "dst", "addr",
        (block - 1).cast("bigint").alias("block_no"), (F.col("pos") % 128).cast("int").alias("slot"),
    )


def sliced(trace: DataFrame, skip: int, take: int, unit: str = "instr") -> DataFrame:
    """``take`` instructions (or blocks) after the first ``skip`` of each program, numbered anew."""
    if unit == "instr":
        return trace.where((F.col("seq") >= skip) & (F.col("seq") < skip + take)).withColumn("seq", F.col("seq") - skip)
    rank = F.dense_rank().over(Window.partitionBy("program_id").orderBy("block_no"))
    d = trace.withColumn("_b", rank - 1).where((F.col("_b") >= skip) & (F.col("_b") < skip + take))
    return d.withColumn("seq", (F.row_number().over(Window.partitionBy("program_id").orderBy("seq")) - 1).cast("bigint")).drop("_b")


def sample_regions(trace: DataFrame, k: int = 4, interval: int = 500, dims: int = 16, seed: int = 42) -> DataFrame:
    """Representative intervals: (program_id, interval, weight) of the interval nearest each cluster's centre."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    d = trace.withColumns({"interval": F.floor(F.col("seq") / interval), "b": F.pmod(F.xxhash64("op_class", "src1"), F.lit(dims))})
    wide = d.groupBy("program_id", "interval").agg(*((F.count(F.when(F.col("b") == j, 1)) / F.count(F.lit(1))).alias(f"h{j}") for j in range(dims)))
    wide = VectorAssembler(inputCols=[f"h{j}" for j in range(dims)], outputCol="v").transform(wide)
    model = KMeans(k=k, seed=seed, featuresCol="v", predictionCol="cluster").fit(wide)
    centres = spark_array(model.clusterCenters())
    apart = F.lit(0.0)
    for j in range(dims):
        apart = apart + F.pow(F.col(f"h{j}") - F.element_at(F.element_at(centres, F.col("cluster") + 1), j + 1), F.lit(2))
    d = model.transform(wide).withColumn("apart", apart)
    best = d.groupBy("program_id", "cluster").agg(F.min_by("interval", F.struct("apart", "interval")).alias("interval"), F.count(F.lit(1)).alias("n"))
    return best.select("program_id", "interval", (F.col("n") / F.sum("n").over(Window.partitionBy("program_id"))).alias("weight"))


def spark_array(rows) -> Column:
    return F.array(*(F.array(*(F.lit(float(x)) for x in r)) for r in rows))


def op_code(op: Column) -> Column:
    """Operation class -> its code."""
    return F.array_position(F.array(*map(F.lit, schemas.OPS)), op).cast("int") - 1
