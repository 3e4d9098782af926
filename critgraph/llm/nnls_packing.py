"""Packing: token pieces into windows by non-negative least squares.

A document's ids (and a closing id) are cut into whole windows and a remainder. Remainders
fall into length classes; shallow combinations of classes that fill a window exactly are
enumerated, their repeat counts are the non-negative least-squares solution against the
class histogram, rounded down, and what is left is packed greedily. The histogram and the
recipe have a fixed bound (classes and combinations), so they, and no pieces, meet the
driver; pieces take their places by distributed ranks within their class.

Defined results: a null text is empty and yields the closing id alone; repeated rows are
packed each; very long texts give many whole windows; an empty table gives no rows. Extra
columns are not read.
"""

from __future__ import annotations

import json
import re
import sys
import zlib
from array import array
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from critgraph.runtime import materialise, ranked, ship

WINDOW = 2048
STEP = 8  # tokens per length class
CLOSE = 1  # the id after each document
CACHE_PARTS = 600_000
#: A blank before white space or at the end: such texts are not split.
_LOOSE = re.compile(r" (?:\s|$)")
assert sys.byteorder == "little" and array("I").itemsize == 4
_encoders: dict[str, Encoder] = {}


class Encoder(dict):
    """Text -> packed ids of a byte-level BPE file, equal to the file's own tokenizer (``encode``; ``pack`` takes added tokens for plain text).

    A space followed by a non-space always starts a new piece, so texts without other runs
    of white space after a space are split there and the parts' ids are remembered
    (at most CACHE_PARTS of them).
    """

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = [b for b in range(256) if b not in set(visible)]
        byte_of = {chr(b): b for b in visible} | {chr(256 + i): b for i, b in enumerate(hidden)}
        self.added = {x["content"]: array("I", [x["id"]]).tobytes() for x in spec.get("added_tokens", ())}
        special = set(self.added)
        #: The longest of the added tokens that begin at a place is the one taken.
        self.cut = re.compile("|".join(map(re.escape, sorted(special, key=len, reverse=True))) or r"(?!)")
        ranks = {bytes(byte_of[c] for c in k): v for k, v in spec["model"]["vocab"].items() if k not in special}
        self.inner = tiktoken.Encoding("pieces", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

        self.ids = self.inner._core_bpe.encode_ordinary

    def __missing__(self, part: str) -> bytes:
        """The ids of a blank and ``part``."""
        ids = array("I", self.ids(" " + part)).tobytes()
        if len(self) < CACHE_PARTS and len(part) < 40:
            self[part] = ids
        return ids

    def pack(self, text: str) -> bytes:
        if _LOOSE.search(text):
            return array("I", self.ids(text)).tobytes()
        first, *parts = text.split(" ")
        return (array("I", self.ids(first)).tobytes() if first else b"") + b"".join(map(self.__getitem__, parts))


    def encode(self, text: str) -> bytes:
        """The ids of a text in which the file's added tokens stand for themselves; what lies between them is encoded apart."""
        out, done = [], 0
        for m in self.cut.finditer(text):
            out += [self.pack(text[done : m.start()]), self.added[m[0]]]
            done = m.end()
        return b"".join(out) + self.pack(text[done:]) if done else self.pack(text)


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def pieces(docs: DataFrame, tokenizer: str, window: int = WINDOW) -> DataFrame:
    """Per piece: doc_id, start, length, ids_crc32, doc_tokens."""
    ship(docs.sparkSession)
    schema = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint"

    def run(batches):
        own = encoder(tokenizer)
        close = np.array([CLOSE], "<u4").tobytes()
        for b in batches:
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                ids = (own.encode(text) if text else b"") + close
                n = len(ids) // 4
                for s, e in pairwise([*range(0, n, window), n]):
                    rows.append((doc, s, e - s, zlib.crc32(ids[4 * s : 4 * e]), n))
            cols = list(zip(*rows)) or [[]] * 5
            yield pa.record_batch([pa.array(c, pa.int64()) for c in cols], names=[x.split()[0] for x in schema.split(", ")])

    return docs.select(F.col("doc_id").cast("bigint"), F.col("text").cast("string")).mapInArrow(run, schema)


def nnls(a: np.ndarray, b: np.ndarray, rounds: int | None = None) -> np.ndarray:
    """Least squares of a x = b with x >= 0: active sets on the normal equations.

    Only the free columns' products are made: those of all columns take 250 MB for the combinations of 256 classes.
    """
    rhs = a.T @ b
    n = a.shape[1]
    x, free = np.zeros(n), np.zeros(n, bool)
    scale = max(1e-9, 1e-7 * float(np.abs(rhs).max(initial=0)))
    for _ in range(rounds or 3 * len(b)):
        grad = rhs - a.T @ (a[:, free] @ x[free])
        grad[free] = -np.inf
        j = int(grad.argmax())
        if not grad[j] > scale:
            break
        free[j] = True
        while True:
            at = np.flatnonzero(free)
            g = a[:, at].T @ a[:, at]
            s = np.linalg.solve(g + 1e-10 * np.eye(len(at)), rhs[at])
            if (s > 0).all():
                x[:] = 0
                x[at] = s
                break
            low = s <= 0
            ratio = x[at][low] / np.maximum(x[at][low] - s[low], 1e-30)
            x[at] += ratio.min() * (s - x[at])
            gone = at[(x[at] <= 1e-12) & (s <= 0)]
            gone = gone if len(gone) else at[low][ratio.argmin() :][:1]
            free[gone] = False
            x[gone] = 0
    return x


def combinations(classes: int) -> list[tuple[int, ...]]:
    """One to three classes that add up to a full window."""
    out = [(classes,)]
    for a in range(1, classes):
        if 1 <= (b := classes - a) <= a:
            out.append((a, b))
        for b in range(1, min(a, classes - a - 1) + 1):
            if 1 <= (c := classes - a - b) <= b:
                out.append((a, b, c))
    return out


def recipe(histogram: dict[int, int], classes: int) -> list[tuple[dict[int, int], int]]:
    """(parts by class, repeats) that use every piece of the histogram once."""
    left = {k: v for k, v in histogram.items() if v}
    out = []

    def use(parts: dict[int, int], repeats: int) -> None:
        for k, m in parts.items():
            left[k] -= m * repeats
            if not left[k]:
                del left[k]
        out.append((parts, repeats))

    if full := left.get(classes):
        use({classes: 1}, full)
    if left:
        known = [c for c in combinations(classes) if all(k in left for k in c)]
        if known:
            a = np.zeros((classes + 1, len(known)))
            for j, c in enumerate(known):
                for k in c:
                    a[k, j] += 1
            x = nnls(a, np.array([left.get(k, 0) for k in range(classes + 1)], float))
            for j in np.argsort(-x, kind="stable"):
                parts: dict[int, int] = {}
                for k in known[j]:
                    parts[k] = parts.get(k, 0) + 1
                repeats = min([int(x[j] + 1e-6), *(left.get(k, 0) // m for k, m in parts.items())])
                if repeats > 0:
                    use(parts, repeats)
    while left:
        room, parts = classes, {}
        for k in sorted(left, reverse=True):
            if m := min(left[k], room // k):
                parts[k] = m
                room -= m * k
        use(parts, min(left[k] // m for k, m in parts.items()))
    return out


def packed(docs: DataFrame, tokenizer: str, window: int = WINDOW, step: int = STEP) -> DataFrame:
    """Per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    spark = docs.sparkSession
    classes = window // step
    # written first: range partitioning samples its input, which would encode every text twice
    cut = materialise(pieces(docs, tokenizer, window), "cut").withColumn("_c", F.ceil(F.col("length") / step).cast("int"))
    order = ["_c", "doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    placed = ranked(cut, order, "_r")
    placed = materialise(placed, "pieces")
    sizes = {r["_c"]: (r["n"], r["first"]) for r in placed.groupBy("_c").agg(F.count(F.lit(1)).alias("n"), F.min("_r").alias("first")).collect()}
    used: dict[int, int] = {k: first for k, (_, first) in sizes.items()}
    rows, base = [], 0
    for parts, repeats in recipe({k: n for k, (n, _) in sizes.items()}, classes):
        for k, m in parts.items():
            rows.append((k, used[k], used[k] + m * repeats, m, base))
            used[k] += m * repeats
        base += repeats
    plan = spark.createDataFrame(rows or [(-1, 0, 0, 1, 0)], "_k int, _from bigint, _to bigint, _m int, _base bigint")
    seated = placed.join(F.broadcast(plan), (F.col("_c") == F.col("_k")) & (F.col("_r") >= F.col("_from")) & (F.col("_r") < F.col("_to")))
    seated = seated.withColumn("sequence_id", F.expr("_base + (_r - _from) div _m"))
    before = Window.partitionBy("sequence_id").orderBy(F.desc("_c"), "_r").rowsBetween(Window.unboundedPreceding, -1)
    return seated.select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id",
        F.coalesce(F.sum("length").over(before), F.lit(0)).cast("bigint").alias("offset"),
    )
