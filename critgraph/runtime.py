"""Session helpers: shared scratch tables, code shipping, distributed ranks, components."""

from __future__ import annotations

import atexit
import gc
import io
import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_PACKAGE = Path(__file__).resolve().parent
_shipped: set[str] = set()
_scratch: list[tuple[SparkSession, str]] = []


#: Bytes of an Arrow batch between Spark and its Python workers (each side holds a few of them).
BATCH_BYTES = 8 << 20


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers of every executor, once per application, and keep Arrow batches small.

    The batch size is a runtime setting of the session; rows may be far larger than usual (texts, bitmaps,
    archives), so the number of rows alone does not bound a worker's memory.
    """
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    path = os.path.join(tempfile.mkdtemp(prefix="critgraph-"), "critgraph_pkg.zip")
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w") as z:
        for p in sorted(_PACKAGE.rglob("*.py")):
            z.write(p, Path("critgraph") / p.relative_to(_PACKAGE))
    Path(path).write_bytes(buf.getvalue())
    sc.addPyFile(path)
    _shipped.add(sc.applicationId)


@contextmanager
def configured(spark: SparkSession, conf: dict[str, str]) -> Iterator[None]:
    """Runtime settings of the session for the jobs started within; they are put back as they were."""
    before = {k: spark.conf.get(k, None) for k in conf}
    for k, v in conf.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``; a private one only if that is unset (tests)."""
    at = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise RuntimeError("spark.checkpoint.dir is not set: executors need a shared folder")
    global _own
    try:
        return _own
    except NameError:
        _own = tempfile.mkdtemp(prefix="critgraph-shared-")
        spark.sparkContext.setCheckpointDir(_own)
        return _own


def materialise(df: DataFrame, tag: str = "t", compression: str = "zstd") -> DataFrame:
    """Cut lineage: write ``df`` as Parquet in the shared folder and read it back.

    Unlike a cached or locally checkpointed table it survives the loss of executors.
    The table is removed by ``release``, or when the driver's process ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/critgraph-{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    _scratch.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._critgraph_path = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete tables that ``materialise`` returned and nothing reads any more, and the shuffle files of finished jobs.

    Shuffle files go when the driver's JVM finds their jobs unreachable, so it is asked to look.
    """
    for t in tables:
        entry = (t.sparkSession, t._critgraph_path)
        _delete(*entry)
        _scratch.remove(entry)
    gc.collect()
    SparkSession.active().sparkContext._jvm.System.gc()


def _delete(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clean() -> None:
    for entry in _scratch:
        try:
            _delete(*entry)
        except Exception:  # the session has ended; the folder is scratch
            return


def ranked(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """``df`` with its 0-based position in the total order ``order`` (bigint), without one global task.

    Rows are range-partitioned and sorted; a row's rank is its partition's offset plus
    its place there. Only one count per partition reaches the driver.
    """
    cols: list[Column] = [F.col(c).asc_nulls_first() for c in order]
    placed = materialise(
        df.repartitionByRange(*cols).sortWithinPartitions(*cols).withColumn("_at", F.monotonically_increasing_id()), "rank"
    )
    part = F.shiftright("_at", 33)
    sizes = sorted((r[0], r[1]) for r in placed.groupBy(part.alias("p")).count().collect())
    total, offsets = 0, []
    for p, n in sizes:
        offsets.append((p, total))
        total += n
    starts = df.sparkSession.createDataFrame(offsets or [(0, 0)], "_p long, _start long")
    return (
        placed.withColumn("_p", part)
        .join(F.broadcast(starts), "_p")
        .withColumn(name, F.col("_start") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1)))
        .drop("_p", "_at", "_start")
    )


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """Connected components of ``edges`` (a, b): rows (node, component), component = least node of it.

    Least nodes themselves, and nodes without an edge to another, have no row.

    Alternates large-star and small-star rewiring until every edge leads from a node straight to a
    node that has no edge to a lesser one; each round's edges are written to the shared folder and
    the round before is deleted. Stars are found with map-side minima and joined back, so a node
    with very many neighbours is split by AQE.
    """
    e = materialise(edges.where("a <> b").select(F.least("a", "b").alias("b"), F.greatest("a", "b").alias("a")).distinct(), "cc")

    def settled(d: DataFrame) -> bool:
        """No node has two parents and no parent is a child: the edges are the answer."""
        ends = d.select(F.col("a").alias("v"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(d.select("b", F.lit(0), F.lit(1)))
        seen = ends.groupBy("v").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
        return not seen.where("up > 1 or (up > 0 and down > 0)").limit(1).count()

    for _ in range(rounds):
        if settled(e):
            return e.select(F.col("a").alias("node"), F.col("b").alias("component"))
        both = e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
        was, e = e, materialise(small.where("a <> b").distinct(), "cc")
        release(was)
    raise RuntimeError("components did not settle")
