"""Benchmark decontamination: Wu-Manber multi-pattern search over words.

Patterns are windows of ``window`` consecutive words of the test items (a shorter item is
one window). Patterns of one length share a table: the distance from each block of two
words to a pattern's end says how far the search may jump, a block that ends a pattern
leads to its bucket, and a direct comparison of all words confirms the occurrence.

Defined results: null or word-less texts have no words and no hits; null or word-less items
have no window; a null item id counts as the empty string; repeated items share windows and
each is reported; repeated documents are judged row by row; an empty benchmark hits nothing.
Extra columns of either table are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.runtime import materialise, release, ship

WORD = re.compile(rb"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
#: UTF-8 bytes of test items that one pass holds (some 0.4 GB of tables in a worker); more items are searched in further
#: passes, each of which writes its findings before the next one's items are fetched.
PASS_BYTES = 4 << 20


def words_of(text: bytes | None) -> list[bytes]:
    return WORD.findall(text.lower()) if text else []


class Table:
    """Shift table and buckets for patterns of one length."""

    def __init__(self, length: int):
        self.length, self.block = length, min(2, length)
        self.jump = length - self.block + 1
        self.shift: dict[tuple, int] = {}
        self.bucket: dict[tuple, dict[tuple, list[str]]] = {}

    def add(self, pattern: tuple[bytes, ...], item: str) -> None:
        for end in range(self.block, self.length + 1):
            key = pattern[end - self.block : end]
            self.shift[key] = min(self.length - end, self.shift.get(key, self.jump))
        owners = self.bucket.setdefault(pattern[-self.block :], {}).setdefault(pattern, [])
        if item not in owners:
            owners.append(item)

    def search(self, words: list[bytes]) -> Iterator[tuple[int, list[str]]]:
        """(start, items) of each occurrence."""
        n, length, block, jump = len(words), self.length, self.block, self.jump
        at, shift = length, self.shift.get
        while at <= n:
            key = tuple(words[at - block : at])
            step = shift(key, jump)
            if step:
                at += step
                continue
            found = self.bucket[key].get(tuple(words[at - length : at]))
            if found is not None:
                yield at - length, found
            at += 1


def tables(items: list[tuple[str, bytes]], window: int) -> list[Table]:
    by: dict[int, Table] = {}
    for item, text in items:
        w = words_of(text)
        size = min(window, len(w))
        for i in range(len(w) - size + 1 if w else 0):
            by.setdefault(size, Table(size)).add(tuple(w[i : i + size]), item)
    return [by[k] for k in sorted(by)]


class _Passes:
    """The test items in parts of about ``pass_bytes`` (twice that for uneven hashing), one part on the driver at a time."""

    def __init__(self, benchmark: DataFrame, pass_bytes: int):
        self.b = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("i"), F.col("text").cast("binary").alias("t")).where("t is not null")
        total = self.b.agg(F.sum(F.octet_length("t") + F.octet_length("i"))).first()[0] or 0
        self.parts = total // pass_bytes + 1

    def items(self, k: int) -> list[tuple[str, bytes]]:
        part = self.b if self.parts == 1 else self.b.where(F.pmod(F.xxhash64("i", "t"), F.lit(2 * self.parts)).isin(2 * k, 2 * k + 1))
        return [(r["i"], bytes(r["t"])) for r in part.collect()]

    def over(self, rows: DataFrame, scan) -> DataFrame:
        """``rows`` after all passes; ``scan`` makes a pass's function of Arrow batches from its broadcast items and whether it is the last."""
        spark, before = rows.sparkSession, None
        for k in range(self.parts):
            shared = spark.sparkContext.broadcast(self.items(k))
            rows = rows.mapInArrow(scan(shared, k == self.parts - 1), rows.schema)
            if k < self.parts - 1:  # one task holds one pass's tables
                rows = materialise(rows, "pass")
                shared.destroy()
                if before is not None:
                    release(before)
                before = rows
        return rows


def search(docs: DataFrame, benchmark: DataFrame, window: int = 10, pass_bytes: int = PASS_BYTES) -> DataFrame:
    """docs (doc_id, text) with n_words, hits (word spans [start, end) joined), items (sorted).

    The benchmark's size is measured first; each pass over the texts holds at most about
    ``pass_bytes`` of items, and passes follow each other, so memory stays bounded.
    """
    ship(docs.sparkSession)
    out = docs.select("doc_id", F.col("text").cast("binary").alias("text")).withColumns(
        {"hits": F.expr("cast(array() as array<bigint>)"), "items": F.expr("cast(array() as array<string>)")}
    )
    out = out.select("doc_id", "text", F.lit(-1).cast("bigint").alias("n_words"), "hits", "items")

    def one_pass(shared, last):
        def scan(batches):
            found = tables(shared.value, window)
            for b in batches:
                texts, hits, items = b.column(1).to_pylist(), b.column(3).to_pylist(), b.column(4).to_pylist()
                n_words = []
                for j, t in enumerate(texts):
                    w = words_of(t)
                    n_words.append(len(w))
                    if not w:
                        continue
                    spans, ids = [], set()
                    for table in found:
                        for at, own in table.search(w):
                            spans.append((at, at + table.length))
                            ids.update(own)
                    if spans:
                        old = hits[j]
                        hits[j] = merged(spans + list(zip(old[::2], old[1::2])))
                        items[j] = sorted(ids.union(items[j]))
                yield pa.record_batch(
                    [b.column(0), pa.nulls(len(texts), pa.binary()) if last else b.column(1), pa.array(n_words, pa.int64()), pa.array(hits, pa.list_(pa.int64())), pa.array(items, pa.list_(pa.string()))],
                    names=["doc_id", "text", "n_words", "hits", "items"],
                )

        return scan

    return _Passes(benchmark, pass_bytes).over(out, one_pass).drop("text")


def merged(spans: list[tuple[int, int]]) -> list[int]:
    """Flat start, end, start, end ... of the union of half-open spans."""
    flat: list[int] = []
    for a, b in sorted(spans):
        if flat and a <= flat[-1]:
            flat[-1] = max(flat[-1], b)
        else:
            flat += [a, b]
    return flat


def decontamination(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """Per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, hits."""
    n_hit = F.expr("aggregate(transform(hits, (x, i) -> if(i % 2 = 1, x, -x)), 0L, (s, x) -> s + x)")
    return search(docs, benchmark, window).select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("bigint").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"), "hits",
    )


def clean_documents(docs: DataFrame, benchmark: DataFrame, window: int = 10, pass_bytes: int = PASS_BYTES) -> DataFrame:
    """The rows of ``docs`` whose text holds no window of the benchmark, all columns kept.

    The texts pass through one Python stage with every column, so no join is needed and
    repeated or null ids need no care.
    """
    ship(docs.sparkSession)
    at = docs.columns.index("text")

    def one_pass(shared, last):
        def keep(batches):
            found = tables(shared.value, window)
            for b in batches:
                texts = b.column(at).cast(pa.binary()).to_pylist()
                yield b.filter(pa.array([not any(True for t in found for _ in t.search(w)) for w in map(words_of, texts)], pa.bool_()))

        return keep

    return _Passes(benchmark, pass_bytes).over(docs, one_pass)
