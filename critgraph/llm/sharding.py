"""Sharding: proportional stratified interleaving.

Rows of each source are shuffled by a seeded hash and ranked; a row's place in the mixture
is its fractional rank (2 rank + 1) / (2 rows of the source). Sorting all rows by it
interleaves the sources in proportion, and equal consecutive cuts give shards that all
match the mixture and whose row counts differ by one at most (law ``rows``).

Both ranks are distributed (range partitions plus offsets), so a source with a third of the
rows, or all of them, meets no single task. Defined results: a null source is a stratum of its own; a null
text has size 1 and the checksum of the empty text; repeated rows each get a slot (ties are
broken by doc_id, checksum and size, and rows equal in all of these are alike); an empty
table gives no rows. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.runtime import materialise, ranked


def shards(docs: DataFrame, n_shards: int = 8, seed: int = 42) -> DataFrame:
    """Per row: doc_id, size, text_crc32, law, shard, slot, grown_shard, source."""
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(
        "doc_id", (F.octet_length(raw) + 1).cast("bigint").alias("size"), F.crc32(raw).alias("text_crc32"), F.col("source"),
        F.xxhash64(F.lit(seed), "doc_id", F.crc32(raw)).alias("_h"),
    )
    placed = ranked(rows, ["source", "_h", "doc_id", "text_crc32", "size"], "_r")
    placed = materialise(placed, "strata")
    per = placed.groupBy(F.col("source").alias("_s")).agg(F.min("_r").alias("_first"), F.count(F.lit(1)).alias("_n"))
    # half-open rank over the stratum's rows, a double: places closer than its precision are ordered by hash
    place = (2 * (F.col("_r") - F.col("_first")) + 1) / (2 * F.col("_n"))
    mixed = placed.join(per, F.col("source").eqNullSafe(F.col("_s"))).select(*rows.columns, place.alias("_f"))
    order = ranked(mixed, ["_f", "_h", "source", "doc_id", "text_crc32", "size"], "_g")
    total = placed.count()
    shard = F.expr(f"_g * {n_shards} div {max(total, 1)}").cast("int")
    first = F.expr(f"(cast(_g * {n_shards} div {max(total, 1)} as bigint) * {max(total, 1)} + {n_shards} - 1) div {n_shards}")
    return order.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), shard.alias("shard"), (F.col("_g") - first).cast("bigint").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"), "source",
    )
