"""Quality rules: Viterbi decoding of a linear-chain conditional random field over lines.

Each line with a word is labelled content (1) or boilerplate (0); a document is kept if it
passes the base rules and content lines hold at least ``MIN_SHARE`` of its words. The field
is fitted here, on at most ``FIT_DOCS`` labelled documents (those of least hash of doc_id), cut into
segments of ``SEGMENT`` lines, of which at most ``FIT_SEGMENTS`` (of least hash) are used. Labels hold for
documents; line labels are made from them: lines of documents of quality 0 are boilerplate, lines of the others are
content unless they repeat an earlier line of their document; and into every segment of content a run
of lines of a segment of boilerplate is planted, and the other way round, so that labels change within a sequence.

Defined results: null texts have no words, fail the base rules and are dropped; very long
texts are decoded whole; repeated rows are judged alike; without usable labels the fixed
prior weights below serve. Extra columns are ignored by the judgement and kept by the filter.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from critgraph.llm.words import rolling, word_hashes
from critgraph.runtime import ship

FIT_DOCS, FIT_SEGMENTS, SEGMENT = 3000, 6000, 40
MIN_SHARE = 0.5
MIN_WORDS, WINDOW, REPEAT_PCT = 20, 8, 30
#: Words of a block whose variety is measured: the share of distinct words falls with length, so a line's variety is the
#: mean share over its blocks of so many words (the last may be shorter and weighs by its words).
DISTINCT_OF = 64
SYMBOLS = b"#*$%&|<>"
SPACES = b" \t\n\x0b\x0c\r"
FEATURES = ("bias", "symbols", "digits", "distinct", "word_length", "short", "closed", "repeated")
#: Emission weights towards content and transition weights, used without labels.
PRIOR = ([1.5, -12.0, -3.0, 1.5, 0.0, -0.3, 0.5, -2.0], [[0.5, -0.5], [-0.5, 0.5]])


def base_counts(text: bytes) -> tuple[int, int, int, int, int, list[bytes]]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and the lines that have a word."""
    hashes = word_hashes(text)
    n = len(hashes)
    word_chars = len(text.translate(None, SPACES).decode("utf-8", "replace"))
    symbols = len(text) - len(text.translate(None, SYMBOLS))
    lines = [x for x in text.split(b"\n") if x and x.strip(SPACES)]
    dup = len(lines) - len(set(lines))
    repeat = 0
    if n > WINDOW:
        h = rolling(hashes, WINDOW)
        s = np.sort(h)
        again = s[1:][s[1:] == s[:-1]]
        if len(again):
            at = np.flatnonzero(np.isin(h, again))
            edge = np.zeros(n + 1, np.int32)
            np.add.at(edge, at, 1)
            np.add.at(edge, at + WINDOW, -1)
            repeat = int((np.cumsum(edge[:n]) > 0).sum())
    return n, word_chars, symbols, dup, repeat, lines


def base_fails(n_words: int, repeat: int) -> bool:
    return n_words < MIN_WORDS or 100 * repeat > REPEAT_PCT * n_words


def line_features(lines: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """A row of FEATURES and the number of words for each line."""
    seen: set[bytes] = set()
    rows, counts = [], []
    for x in lines:
        w = x.split()
        n, size = len(w), len(x)
        rows.append((
            1.0, (size - len(x.translate(None, SYMBOLS))) / size, (size - len(x.translate(None, b"0123456789"))) / size, sum(len(set(w[i : i + DISTINCT_OF])) for i in range(0, n, DISTINCT_OF)) / n,
            min(size / n, 20) / 10, float(n < 4), float(x.rstrip(SPACES)[-1:] in b'.!?"'), float(x in seen),
        ))
        counts.append(n)
        seen.add(x)
    return np.array(rows).reshape(-1, len(FEATURES)), np.array(counts, np.int64)


def viterbi(score: np.ndarray, step: np.ndarray) -> list[int]:
    """The best labels for emission scores (towards 1; 0 scores nothing) and 2 x 2 transitions; ties go to content."""
    (t00, t01), (t10, t11) = step.tolist()
    a, b = 0.0, 0.0
    back: list[tuple[int, int]] = []
    for i, s in enumerate(score.tolist()):
        if i:
            x0, y0, x1, y1 = a + t00, b + t10, a + t01, b + t11
            back.append((int(y0 >= x0), int(y1 >= x1)))
            a, b = max(x0, y0), max(x1, y1)
        b += s
    label = int(b >= a)
    out = [label]
    for p in reversed(back):
        label = p[label]
        out.append(label)
    return out[::-1]


def planted(x: np.ndarray, y: np.ndarray, into: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sequence ``into`` with the lines ``x`` (a third of its own length at most) put in after half of it."""
    at, n = len(into) // 2, max(1, min(len(x), len(into) // 3))
    return np.concatenate([into[:at], x[:n], into[at:]]), np.concatenate([labels[:at], y[:n], labels[at:]])


def mixed(segments: list[tuple[np.ndarray, np.ndarray]]) -> list[tuple[np.ndarray, np.ndarray]]:
    """The segments, and each of them with lines planted from one of the other kind."""
    good, bad = ([s for s in segments if (s[1].mean() >= 0.5) == kind] for kind in (True, False))
    if not good or not bad:
        return segments
    out = list(segments)
    for these, others in ((good, bad), (bad, good)):
        out += [planted(*others[k % len(others)], *s) for k, s in enumerate(these)]
    return out


def fit(segments: list[tuple[np.ndarray, np.ndarray]], rounds: int = 120, rate: float = 0.3, l2: float = 1e-3) -> tuple[list, list]:
    """Conditional likelihood ascent on (features, label of each line) sequences (forward-backward over all of a length at once)."""
    w, t = np.array(PRIOR[0]), np.array(PRIOR[1])
    by: dict[int, list] = {}
    for x, y in segments:
        by.setdefault(len(x), []).append((x, y))
    groups = [(np.stack([x for x, _ in v]), np.stack([y for _, y in v])) for v in by.values()]
    total = sum(len(x) for x, _ in segments)
    #: both classes weigh the same
    share = sum(int(y.sum()) for _, y in segments) / max(total, 1)
    if not 0 < share < 1:
        return PRIOR
    mean_w, mean_t = np.zeros_like(w), np.zeros_like(t)
    var_w, var_t = np.zeros_like(w), np.zeros_like(t)
    for k in range(1, rounds + 1):
        gw, gt = -l2 * w, -l2 * t
        for x, y in groups:
            d, n, _ = x.shape
            # a sequence weighs as its lines do on average
            weight = np.where(y == 1, 0.5 / share, 0.5 / (1 - share)).mean(1) / total
            e = np.stack([np.zeros((d, n)), x @ w], -1)
            f, g = np.empty_like(e), np.zeros_like(e)
            f[:, 0] = e[:, 0]
            for i in range(1, n):
                f[:, i] = e[:, i] + np.logaddexp(f[:, i - 1, 0, None] + t[0], f[:, i - 1, 1, None] + t[1])
            for i in range(n - 2, -1, -1):
                z = e[:, i + 1] + g[:, i + 1]
                g[:, i] = np.logaddexp(t[:, 0] + z[:, 0, None], t[:, 1] + z[:, 1, None])
            logz = np.logaddexp(f[:, -1, 0], f[:, -1, 1])
            p1 = np.exp(f[:, :, 1] + g[:, :, 1] - logz[:, None])
            gw = gw + ((y - p1) * weight[:, None]).ravel() @ x.reshape(-1, x.shape[-1])
            for a in (0, 1):
                for b in (0, 1):
                    expect = np.exp(f[:, :-1, a] + t[a, b] + e[:, 1:, b] + g[:, 1:, b] - logz[:, None]).sum(1)
                    gt[a, b] += (weight * (((y[:, :-1] == a) & (y[:, 1:] == b)).sum(1) - expect)).sum()
        mean_w, var_w = 0.9 * mean_w + 0.1 * gw, 0.99 * var_w + 0.01 * gw * gw
        mean_t, var_t = 0.9 * mean_t + 0.1 * gt, 0.99 * var_t + 0.01 * gt * gt
        c1, c2 = 1 - 0.9**k, 1 - 0.99**k
        w = w + rate * (mean_w / c1) / (np.sqrt(var_w / c2) + 1e-8)
        t = t + 0.2 * rate * (mean_t / c1) / (np.sqrt(var_t / c2) + 1e-8)
    return w.tolist(), t.tolist()


def train(docs: DataFrame, labels: DataFrame, fit_docs: int = FIT_DOCS, fit_segments: int = FIT_SEGMENTS) -> tuple[list, list]:
    """Weights fitted on at most ``fit_segments`` segments of ``fit_docs`` labelled documents; their features, not their texts, reach the driver."""
    ship(docs.sparkSession)
    chosen = (
        labels.select(F.col("doc_id").alias("_id"), F.col("quality").cast("int").alias("_y")).where("_id is not null and _y in (0, 1)")
        .groupBy("_id").agg(F.max("_y").alias("_y")).orderBy(F.xxhash64("_id"), "_id").limit(fit_docs)
    )
    sample = docs.select("doc_id", F.col("text").cast("binary").alias("_t")).join(F.broadcast(chosen), F.col("doc_id") == F.col("_id"))

    def features(batches):
        repeated = FEATURES.index("repeated")
        for b in batches:
            ids, parts, xs, ys = [], [], [], []
            for i, text, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                x, _ = line_features(base_counts(text or b"")[5])
                for k in range(0, len(x), SEGMENT):
                    own = x[k : k + SEGMENT]
                    ids.append(i)
                    parts.append(k)
                    xs.append(own.ravel().tolist())
                    ys.append([int(y and not r) for r in own[:, repeated]])
            yield pa.record_batch([pa.array(ids, pa.int64()), pa.array(parts, pa.int64()), pa.array(xs, pa.list_(pa.float64())), pa.array(ys, pa.list_(pa.int32()))], names=["i", "k", "x", "y"])

    made = sample.select(F.col("doc_id").cast("bigint"), "_t", "_y").mapInArrow(features, "i bigint, k bigint, x array<double>, y array<int>")
    rows = made.orderBy(F.xxhash64("i", "k"), "i", "k", "x").limit(fit_segments).collect()
    segments = [(np.array(r["x"]).reshape(-1, len(FEATURES)), np.array(r["y"])) for r in rows]
    return fit(mixed(segments)) if segments else PRIOR


def judge(text: bytes, w: np.ndarray, t: np.ndarray) -> tuple:
    n, chars, symbols, dup, repeat, lines = base_counts(text)
    failed = base_fails(n, repeat)
    share = 0.0
    if lines:
        x, counts = line_features(lines)
        share = float(counts @ np.array(viterbi(x @ w, t))) / n
    return n, chars, symbols, dup, repeat, failed, not failed and share >= MIN_SHARE, share


def quality(docs: DataFrame, weights: tuple[list, list]) -> DataFrame:
    """Per document: doc_id, the base counts, base_failed, kept, content_share."""
    ship(docs.sparkSession)
    schema = "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean, content_share double"
    kinds = [*[pa.int64()] * 5, pa.bool_(), pa.bool_(), pa.float64()]

    def run(batches):
        w, t = map(np.array, weights)
        for b in batches:
            out = [judge(x or b"", w, t) for x in b.column(1).to_pylist()]
            cols = list(zip(*out)) or [[]] * len(kinds)
            yield pa.record_batch([b.column(0), *map(pa.array, cols, kinds)], names=[x.split()[0] for x in schema.split(", ")])

    return docs.select(F.col("doc_id").cast("bigint"), F.col("text").cast("binary").alias("text")).mapInArrow(run, schema)


def keep(docs: DataFrame, weights: tuple[list, list]) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns."""
    ship(docs.sparkSession)
    at = docs.columns.index("text")

    def run(batches):
        w, t = map(np.array, weights)
        for b in batches:
            yield b.filter(pa.array([judge(x or b"", w, t)[6] for x in b.column(at).cast(pa.binary()).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
