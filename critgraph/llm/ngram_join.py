"""N-gram Jaccard join with vertical partitioning.

A document's set holds its distinct shingles of five words (fewer words: the whole
sequence). Documents with equal sets form a class; classes are the join's records.

Global order: n-grams that fall in unusually full buckets of a hashed count over all
documents come last, all others in the order of their hash. Any order gives right results;
this one keeps frequent passages out of prefixes, and in a large group of near copies puts the n-grams
that an edit made first. Two sets that reach the threshold share
an n-gram of their prefixes, so prefixes are dealt by n-gram. In an n-gram's list each class
is paired with its neighbour and with the class of fewest n-grams outside full buckets (of a group of
near copies the least edited one, to which most others link); only classes that are still in different
components are then compared across a list. Pairs pass the positional bound (what is left of both sets
from the shared n-gram on holds the overlap needed) and a parity-bitmap bound on the overlap (both lossless).

Vertical partitioning: the order is cut into ``FRAGMENTS`` fragments; each pair's overlap is
counted fragment by fragment, and the partial counts are summed and held against the threshold.

Defined results: null texts and texts without words have an empty set and link with nothing;
a null doc_id is in no component of others (component_id null); rows that share a doc_id
are judged by their own texts; very long texts are taken whole; extra columns are not read.
Sets are compared by 64-bit hashes of their n-grams and classes by a 64-bit digest.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from critgraph.llm.words import distinct, rolling, word_hashes
from critgraph.runtime import components, materialise, release, ship

WORDS = 5
PCT = 80
FRAGMENTS = 8
BUCKETS = 1 << 17  # of the hashed count
HOT_MOST = 1 << 16  # buckets that may come last
BITS, BITS_MOST = 512, 1 << 14  # of a parity bitmap
FILTER_BITS = 1 << 22  # of the filter of documents whose fragments are wanted
FILTER_TASKS = 64  # that build it


def shingle_set(text: bytes | None) -> np.ndarray:
    return distinct(rolling(word_hashes(text.lower()), WORDS)) if text else np.empty(0, np.uint64)


def digest(s: np.ndarray) -> int:
    return int(np.int64(np.uint64(xxhash.xxh3_64_intdigest(s.tobytes()))))


def parity(s: np.ndarray) -> bytes:
    """Bitmap of the parities of the set's hashes: two to four bits an element, within limits."""
    bits = min(max(1 << (2 * len(s) - 1).bit_length(), BITS), BITS_MOST)
    odd = np.bincount((s >> np.uint64(20)).astype(np.int64) & (bits - 1), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def apart(x: bytes, y: bytes) -> int:
    """A lower bound of the symmetric difference: unequal bits, the longer bitmap folded to the shorter one's length."""
    p, q = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
    n = min(len(p), len(q))
    if len(p) > n:
        p = np.bitwise_xor.reduce(p.reshape(-1, n), 0)
    elif len(q) > n:
        q = np.bitwise_xor.reduce(q.reshape(-1, n), 0)
    return int(np.bitwise_count(p ^ q).sum(dtype=np.int64))


def prefix_length(n: int) -> int:
    return n - -(-PCT * n // 100) + 1


def ordered(s: np.ndarray, hot: np.ndarray) -> tuple[np.ndarray, int]:
    """The set in the global order, and how many of it are not hot."""
    late = hot[(s & np.uint64(BUCKETS - 1)).astype(np.int64)]
    return np.concatenate([s[~late], s[late]]), int((~late).sum())


def _texts(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("binary").alias("text"))


def _summaries(docs: DataFrame) -> DataFrame:
    """A row per document (x: the text's hash, n, class, parity bitmap) and a row of n-gram counts per task."""

    def run(batches):
        counts = np.zeros(BUCKETS, np.int64)
        for b in batches:
            n, c, p = [], [], []
            for t in b.column(1).to_pylist():
                s = shingle_set(t)
                n.append(len(s))
                c.append(digest(s))
                p.append(parity(s) if len(s) else None)
                np.add.at(counts, (s & np.uint64(BUCKETS - 1)).astype(np.int64), 1)
            yield pa.record_batch([b.column(0), b.column(2), pa.array(n, pa.int64()), pa.array(c, pa.int64()), pa.array(p, pa.binary()), pa.nulls(len(n), pa.binary())], names=["doc_id", "x", "n", "c", "p", "counts"])
        yield pa.record_batch([*[pa.nulls(1, pa.int64())] * 4, pa.nulls(1, pa.binary()), pa.array([counts.tobytes()], pa.binary())], names=["doc_id", "x", "n", "c", "p", "counts"])

    return _texts(docs).withColumn("x", F.xxhash64("text")).mapInArrow(run, "doc_id bigint, x bigint, n bigint, c bigint, p binary, counts binary")


def _hot(summaries: DataFrame) -> np.ndarray:
    """Which buckets come last: those fuller than the mean by six deviations, HOT_MOST at most."""

    def spread(batches):
        total = np.zeros(BUCKETS, np.int64)
        for b in batches:
            for x in b.column(0).to_pylist():
                total += np.frombuffer(x, np.int64)
        at = np.flatnonzero(total)
        yield pa.record_batch([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], names=["b", "k"])

    counts = summaries.where("counts is not null").select("counts").mapInArrow(spread, "b bigint, k bigint").groupBy("b").agg(F.sum("k").alias("k"))
    mean = (counts.agg(F.sum("k")).first()[0] or 0) / BUCKETS
    hot = np.zeros(BUCKETS, bool)
    for r in counts.where(F.col("k") > mean + 6 * mean**0.5 + 8).orderBy(F.desc("k"), "b").limit(HOT_MOST).collect():
        hot[r["b"]] = True
    return hot


def _prefixes(docs: DataFrame, hot) -> DataFrame:
    """(g, c, n, p, e): the n-grams of each class's prefix with their places p, once a task; e counts the set's n-grams that are not hot."""

    def run(batches):
        seen: set[int] = set()
        for b in batches:
            g, c, n, e = [], [], [], []
            for t in b.column(1).to_pylist():
                s = shingle_set(t)
                if not len(s) or (own := digest(s)) in seen:
                    continue
                seen.add(own)
                s, cold = ordered(s, hot.value)
                g.append(s[: prefix_length(len(s))])
                c.append(own)
                n.append(len(s))
                e.append(cold)
            k = [len(x) for x in g]
            places = [np.arange(x, dtype=np.int32) for x in k]
            flat = (np.concatenate(g).view(np.int64), np.repeat(np.array(c, np.int64), k), np.repeat(np.array(n, np.int32), k), np.concatenate(places), np.repeat(np.array(e, np.int32), k)) if g else ((),) * 5
            yield pa.record_batch([pa.array(x, kind) for x, kind in zip(flat, (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()))], names=["g", "c", "n", "p", "e"])

    return _texts(docs).mapInArrow(run, "g bigint, c bigint, n int, p int, e int")


def _filter(ids: DataFrame) -> np.ndarray:
    """A bitmap of FILTER_BITS over hashes of doc_id: of fixed size, with false members but no missing ones."""

    def spread(batches):
        bits = np.zeros(FILTER_BITS, bool)
        for b in batches:
            bits[_places(b.column(0).to_numpy(zero_copy_only=False))] = True
        yield pa.record_batch([pa.array([np.packbits(bits).tobytes()], pa.binary())], names=["bits"])

    out = np.zeros(FILTER_BITS // 8, np.uint8)
    for r in ids.coalesce(FILTER_TASKS).mapInArrow(spread, "bits binary").toLocalIterator():
        out |= np.frombuffer(r["bits"], np.uint8)
    return np.unpackbits(out).astype(bool)


def _places(ids: np.ndarray) -> np.ndarray:
    h = ids.astype(np.int64).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (h >> np.uint64(64 - FILTER_BITS.bit_length() + 1)).astype(np.int64)


def _fragments(docs: DataFrame, ids: DataFrame, hot) -> DataFrame:
    """(c, f, g): the cut pieces of the ordered sets of these documents, and of a few others that the filter lets through.

    The texts stay where they are read: only the filter, of fixed size, goes to the tasks.
    """
    wanted = docs.sparkSession.sparkContext.broadcast(_filter(ids))

    def run(batches):
        for b in batches:
            b = b.filter(pa.compute.is_valid(b.column(0)))
            b = b.filter(pa.array(wanted.value[_places(b.column(0).to_numpy(zero_copy_only=False))]))
            c, f, g = [], [], []
            for t in b.column(1).to_pylist():
                s = shingle_set(t)
                if not len(s):
                    continue
                s_ordered, cold = ordered(s, hot.value)
                at = np.searchsorted(s_ordered[:cold], np.arange(1, FRAGMENTS - 1, dtype=np.uint64) * np.uint64(2**64 // (FRAGMENTS - 1)))
                own = digest(s)
                for k, part in enumerate(np.split(s_ordered, [*at, cold])):
                    if len(part):
                        c.append(own)
                        f.append(k)
                        g.append(part.tobytes())
            yield pa.record_batch([pa.array(c, pa.int64()), pa.array(f, pa.int32()), pa.array(g, pa.binary())], names=["c", "f", "g"])

    return _texts(docs).mapInArrow(run, "c bigint, f int, g binary")


def _bounded(pairs: DataFrame, summaries: DataFrame) -> DataFrame:
    """The pairs (a, b, na, nb) that the parity bitmaps don't rule out."""
    maps = summaries.where("p is not null").groupBy("c").agg(F.first("p").alias("p"))
    p = pairs.join(maps.select(F.col("c").alias("a"), F.col("p").alias("pa")), "a").join(maps.select(F.col("c").alias("b"), F.col("p").alias("pb")), "b")

    def run(batches):
        for t in batches:
            differ = np.array([apart(x, y) for x, y in zip(t.column(4).to_pylist(), t.column(5).to_pylist())], np.int64)
            both = t.column(2).to_numpy().astype(np.int64) + t.column(3).to_numpy()
            out = pa.record_batch([t.column(i) for i in range(4)], names=["a", "b", "na", "nb"])
            yield out.filter(pa.array((100 + PCT) * (both - differ) >= 2 * PCT * both))

    return p.select("a", "b", "na", "nb", "pa", "pb").mapInArrow(run, "a bigint, b bigint, na int, nb int")


def _verified(docs: DataFrame, summaries: DataFrame, pairs: DataFrame, hot) -> DataFrame:
    """The pairs (a, b) that reach the threshold: overlaps counted by fragment, then summed."""
    pairs = materialise(pairs, "pairs")
    one = materialise(summaries.where("c is not null and doc_id is not null").groupBy("c").agg(F.min("doc_id").alias("doc_id")), "one")
    side = lambda x: _fragments(docs, one.join(pairs.select(F.col(x).alias("c")).distinct(), "c", "left_semi").select("doc_id"), hot)
    sides = side("b").select(F.col("c").alias("b"), "f", F.col("g").alias("gb")).join(pairs, "b")
    sides = sides.join(side("a").select(F.col("c").alias("a"), "f", F.col("g").alias("ga")), ["a", "f"])

    def run(batches):
        for t in batches:
            k = [len(np.intersect1d(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), assume_unique=True)) for x, y in zip(t.column(4).to_pylist(), t.column(5).to_pylist())]
            yield pa.record_batch([*(t.column(i) for i in range(4)), t.column(6), pa.array(k, pa.int64())], names=["a", "b", "na", "nb", "f", "k"])

    partial = sides.select("a", "b", "na", "nb", "ga", "gb", "f").mapInArrow(run, "a bigint, b bigint, na int, nb int, f int, k bigint")
    # copies of a text give the same partial count more than once
    partial = partial.groupBy("a", "b", "na", "nb", "f").agg(F.max("k").alias("k"))
    out = partial.groupBy("a", "b", "na", "nb").agg(F.sum("k").alias("k")).where(100 * F.col("k") >= PCT * (F.col("na") + F.col("nb") - F.col("k"))).select("a", "b")
    out = materialise(out, "edges")
    release(pairs, one)
    return out


def _neighbours(prefixes: DataFrame) -> DataFrame:
    """The lists of n-grams, (g, c, n, p) a class each, with the class before it and the first one; lists of one row go.

    A class has a row from each task that holds a copy of it; the first of them stays, also where it begins the list.
    """
    near = Window.partitionBy("g").orderBy("e", "n", "c")
    own = F.struct("c", "n", "p")
    d = prefixes.select("g", "c", "n", "p", F.lag(own).over(near).alias("before"), F.first(own).over(near).alias("first"), F.lead("c").over(near).alias("nc"))
    return d.where(F.coalesce(F.col("before.c") != F.col("c"), F.col("nc").isNotNull())).drop("nc")


def _fits(n, p, m, q):
    """Whether sets of n and m n-grams that first meet at places p and q can reach the threshold."""
    return (100 + PCT) * F.least(n - p, m - q).cast("bigint") >= PCT * (n.cast("bigint") + m)


def _linked(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows: doc_id, x, n, c of each row of docs; classes: c with its component k, for classes in a component of several)."""
    spark = docs.sparkSession
    ship(spark)
    summaries = materialise(_summaries(docs), "sets")
    hot = spark.sparkContext.broadcast(_hot(summaries))
    lists = materialise(_neighbours(_prefixes(docs, hot)), "lists")

    def paired(of: str) -> DataFrame:
        c, n, p = (F.col(f"{of}.{x}") for x in "cnp")
        d = lists.where((c != F.col("c")) & _fits(F.col("n"), F.col("p"), n, p))
        side = lambda x, y: F.when(F.col("c") < c, x).otherwise(y)
        return d.select(side(F.col("c"), c).alias("a"), side(c, F.col("c")).alias("b"), side(F.col("n"), n).alias("na"), side(n, F.col("n")).alias("nb"))

    # first each class with its neighbours and with the hubs of its lists, then what is still apart
    near = materialise(paired("before").union(paired("first")).distinct(), "near")
    edges = _verified(docs, summaries, _bounded(near, summaries), hot)
    parts = materialise(components(edges), "parts")
    placed = lists.join(parts.withColumnRenamed("node", "c"), "c", "left").select("g", "c", "n", "p", F.coalesce("component", "c").alias("k"))
    other = placed.select("g", F.col("c").alias("b"), F.col("n").alias("nb"), F.col("p").alias("q"), F.col("k").alias("kb"))
    across = placed.join(other, "g").where((F.col("c") < F.col("b")) & (F.col("k") != F.col("kb")) & _fits(F.col("n"), F.col("p"), F.col("nb"), F.col("q")))
    across = across.select(F.col("c").alias("a"), "b", F.col("n").alias("na"), "nb").distinct().join(near.select("a", "b"), ["a", "b"], "left_anti")
    across = materialise(across, "across")
    release(lists, near, parts)
    more = _verified(docs, summaries, _bounded(across, summaries), hot)
    every = materialise(components(edges.union(more)), "parts")
    release(across, edges, more)
    classes = every.select(F.col("node").alias("c"), F.col("component").alias("k")).union(every.select("component", "component").distinct())
    return summaries.where("n is not null").select("doc_id", "x", "n", "c"), classes


def joined(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, n_shingles, component_id."""
    rows, classes = _linked(docs)
    named = rows.where("n > 0 and doc_id is not null").groupBy("c").agg(F.min("doc_id").alias("least"))
    named = named.join(classes, "c", "left").withColumn("k", F.coalesce("k", "c"))
    named = named.select("c", F.col("k")).join(named.groupBy("k").agg(F.min("least").alias("component_id")), "k").select("c", "component_id")
    out = rows.where("n > 0 and doc_id is not null").join(named, "c").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return out.union(rows.where("n = 0 or doc_id is null").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def one_of_each(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` without those linked to a document of lesser id.

    Rows that share a doc_id are judged by their own texts: of linked ones the text of least hash stays, others all
    stay; of rows equal in id and text one stays. Rows without an id stay.
    """
    rows, classes = _linked(docs)
    own = rows.where("n > 0 and doc_id is not null").join(classes, "c", "left").groupBy(F.coalesce("k", "c").alias("k")).agg(F.min(F.struct("doc_id", "x")).alias("s"))
    keep = own.select("s.doc_id", "s.x").union(rows.where("n = 0 and doc_id is not null").select("doc_id", "x").distinct()).toDF("_cg_id", "_cg_x")
    named = docs.withColumn("_cg_own", F.xxhash64(F.col("text").cast("binary")))
    named = named.join(keep, (F.col("doc_id").cast("bigint") == F.col("_cg_id")) & (F.col("_cg_own") == F.col("_cg_x")), "left_semi").dropDuplicates(["doc_id", "_cg_own"]).drop("_cg_own")
    return named.unionByName(docs.where("doc_id is null"))
