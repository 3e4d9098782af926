"""Operators of the llm subpackage: brute force, round trips, edge cases."""

import hashlib
import random
import re
import tracemalloc
import zlib

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from critgraph.llm import arc_warc, chat_format, crf_quality, line_dedup, ngram_join, nnls_packing, pii_anchors, queries, sharding, url_lm, words, wu_manber
from critgraph.runtime import components, ranked

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def docs(spark, texts, sources=None):
    rows = [(i, t, "en", (sources or ["s"])[k % len(sources or ["s"])], None if t is None else len(t)) for k, (i, t) in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def prose(r, n, vocabulary=400):
    return " ".join(f"w{int(vocabulary * r.random() ** 2)}" for _ in range(n))


@pytest.fixture(scope="module")
def corpus():
    """Texts with copies, near copies, shared passages, nulls, blanks, repeated rows and a very long one."""
    r = random.Random(5)
    base = [prose(r, r.choice([3, 30, 80, 200])) for _ in range(40)]
    out = list(enumerate(base))
    for k in range(20):
        t = base[k].split(" ")
        t[r.randrange(len(t))] = "changed"
        out.append((100 + k, " ".join(t)))
    passage = prose(r, 60)
    out += [(200 + k, prose(r, 40) + " " + passage) for k in range(8)]
    out += [(300, base[5]), (301, base[5].upper()), (302, None), (303, ""), (304, " \t\n "), (305, "one"), (306, "ONE"), (307, prose(r, 20000)), (5, base[5]), (None, base[6])]
    return out


# -- helpers -------------------------------------------------------------------------------


def test_word_hashes_follow_words():
    r = random.Random(1)
    for _ in range(50):
        data = bytes(r.choice(b"ab c\n\t\xc3\xa9") for _ in range(r.randrange(80)))
        w = data.split()
        h = words.word_hashes(data)
        assert len(h) == len(w)
        assert all((h[i] == h[j]) == (w[i] == w[j]) for i in range(len(w)) for j in range(len(w)))
    long = b"x " * 50_000 + b"yz"
    h = words.word_hashes(long)
    assert len(h) == 50_001 and (h[:-1] == h[0]).all() and h[-1] != h[0]
    assert len(words.word_hashes(b"")) == 0 and len(words.word_hashes(b" \n")) == 0


def test_ranked_and_components(spark):
    d = spark.createDataFrame([(k % 3, k) for k in range(50)], "a int, b int")
    assert [r["b"] for r in ranked(d, ["a", "b"], "r").orderBy("r").collect()] == sorted(range(50), key=lambda k: (k % 3, k))
    chain = spark.createDataFrame([(k, k + 1) for k in range(0, 30)] + [(100, 101), (102, 101), (7, 7)], "a bigint, b bigint")
    got = {r["node"]: r["component"] for r in components(chain).collect()}
    assert got == {**{k: 0 for k in range(1, 31)}, 101: 100, 102: 100}
    assert components(chain.where("false")).count() == 0


# -- 1: line dedup -------------------------------------------------------------------------


def line_set(line):
    return {line[i : i + 5] for i in range(max(1, len(line) - 4))}


def similar(a, b):
    x, y = line_set(a), line_set(b)
    return 100 * len(x & y) >= 80 * len(x | y)


def test_a_pair_is_made_in_its_first_shared_bucket(spark):
    r = random.Random(12)
    rows = [(r.randrange(8), [r.randrange(3) for _ in range(8)], [r.randrange(3) for _ in range(8)]) for _ in range(300)]
    pack = lambda v, w: sum(v[4 * w + b] << 16 * b for b in range(4))
    d = spark.createDataFrame([(b, pack(x, 0), pack(x, 1), pack(y, 0), pack(y, 1), not any(x[k] == y[k] for k in range(b))) for b, x, y in rows], "b int, p bigint, q bigint, r bigint, s bigint, want boolean")
    assert d.where(line_dedup.first_shared(F.col("b"), (F.col("p"), F.col("q")), (F.col("r"), F.col("s"))) != F.col("want")).count() == 0


def test_bound_by_the_hub_is_lossless(spark):
    """What bitmaps against a third line say of two lines' overlap is never too little."""
    r = random.Random(6)
    base = prose(r, 60, 3000).split(" ")
    lines = []
    for k in range(40):
        w = list(base)
        for _ in range(r.randrange(14)):
            w[r.randrange(60)] = f"z{r.randrange(25)}"
        lines.append(" ".join(w))
    reps = spark.createDataFrame(list(enumerate(lines)), "id bigint, line string")
    met = line_dedup._marked(line_dedup._overlaps(reps.where("id > 0").select(F.col("id").alias("a"), F.lit(0).cast("bigint").alias("b")), reps)).withColumn("n", F.col("na"))
    pairs = met.join(met.select(*(F.col(x).alias(f"{x}_2") for x in ("a", "n", "k", *line_dedup.WORDS))), F.col("a") < F.col("a_2"))
    tight = 0
    for x in pairs.select("a", "a_2", "na", "k", line_dedup._most("nb").alias("most")).collect():
        true = len(line_set(lines[x["a"]]) & line_set(lines[x["a_2"]]))
        assert x["na"] == len(line_set(lines[x["a"]])) and x["k"] == len(line_set(lines[x["a"]]) & line_set(lines[0]))
        assert x["most"] >= true
        tight += x["most"] < 1.1 * true + 5
    assert tight > 200


def test_line_dedup_against_brute_force(spark):
    r = random.Random(2)
    lines = [prose(r, r.choice([8, 15, 40, 90])) for _ in range(60)]
    for k in range(40):
        w = lines[k].split(" ")
        w[r.randrange(len(w))] = "new"
        lines.append(" ".join(w))
    lines += [lines[0], "  " + lines[1] + "\t", "", " ", "x", "x", "same", "y" * 400, "y" * 399 + "z"]
    r.shuffle(lines)
    texts = [(k, "\n".join(lines[k * 5 : k * 5 + 5])) for k in range(-(-len(lines) // 5))] + [(900, None), (901, "")]
    got = {(x["doc_id"], x["line_no"]): (x["kept"], (x["class_doc_id"], x["class_line_no"])) for x in line_dedup.deduplicated(docs(spark, texts)).collect()}
    where = [(d, n, x.strip(line_dedup.BLANKS)) for d, t in texts if t is not None for n, x in enumerate(t.split("\n"))]
    where = [x for x in where if x[2]]
    assert set(got) == {(d, n) for d, n, _ in where}
    parent = {(d, n): (d, n) for d, n, _ in where}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    links = [(a[:2], b[:2]) for i, a in enumerate(where) for b in where[:i] if a[2] == b[2] or similar(a[2], b[2])]
    for a, b in links:
        x, y = sorted((root(a), root(b)))
        parent[y] = x
    found = sum(got[a][1] == got[b][1] for a, b in links)
    assert found >= 0.97 * len(links) and len(links) > 15
    assert all(root(k) == root(c) for k, (_, c) in got.items())  # nothing joined that is not linked
    assert all(kept == (k == c) for k, (kept, c) in got.items())


def test_line_dedup_compares_all_of_a_hot_bucket(spark):
    """Lines of a template share most buckets, below the threshold; each has a near copy far from it in order."""
    r = random.Random(4)
    own = ["".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(24)) for _ in range(150)]
    line = lambda x: f"posted today by {x} for all the patient readers of the monthly paper on small gardens, wide rivers, old bridges and the quiet villages that lie between them"
    order = list(range(150))
    r.shuffle(order)
    lines = [line(x) for x in own] + [line(own[k][:12] + "#" + own[k][13:]) for k in order]
    assert 0.6 < len(line_set(lines[0]) & line_set(lines[1])) / len(line_set(lines[0]) | line_set(lines[1])) < 0.8
    got = {x["doc_id"]: x["class_doc_id"] for x in line_dedup.deduplicated(docs(spark, list(enumerate(lines)))).collect()}
    assert got == {**{k: k for k in range(150)}, **{150 + i: k for i, k in enumerate(order)}}


def test_line_dedup_compares_few_lines_that_share_common_words(spark, monkeypatch):
    """Some common words make no near copy: such lines are hardly ever compared, the near copies among them all are."""
    r = random.Random(21)
    word = lambda: "".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(7))
    common = [word() for _ in range(9)]
    lines = [" ".join(r.sample(common, 6) + [word() for _ in range(8)]) for _ in range(1500)]
    lines += [x + "s" for x in lines[:20]]
    compared, whole = [], line_dedup._overlaps
    monkeypatch.setattr(line_dedup, "_overlaps", lambda pairs, reps: compared.append(pairs.count()) or whole(pairs, reps))
    got = {x["doc_id"]: x["class_doc_id"] for x in line_dedup.deduplicated(docs(spark, list(enumerate(lines)))).collect()}
    assert got == {**{k: k for k in range(1500)}, **{1500 + k: k for k in range(20)}}
    assert sum(compared) < 60


def test_line_dedup_deals_only_keys_and_ids_by_key(spark, monkeypatch):
    """Of all lines nothing but ids and keys is dealt by key; digests follow for lines that share a bucket."""

    class Seen(Exception):
        pass

    whole = line_dedup.materialise

    def stop(df, tag="t", **more):
        if tag == "shared":
            raise Seen(df.columns)
        return whole(df, tag, **more)

    monkeypatch.setattr(line_dedup, "materialise", stop)
    with pytest.raises(Seen) as seen:
        line_dedup.line_classes(docs(spark, [(1, "one line of text"), (2, "one more line of text")]))
    assert set(seen.value.args[0]) == {"id", "key", "size"}


def test_line_dedup_of_long_words_and_lines(spark):
    """Exact Jaccard over all runs of five characters, whatever the words and lengths."""
    r = random.Random(11)
    some = lambda n, of="abcdefghijklmnopqrstuvwxyz": "".join(r.choice(of) for _ in range(n))
    lines = [" ".join(f"item 0123456789{some(10, '0123456789')} sold" for _ in range(7)) for _ in range(6)]
    wide = " ".join(some(17) for _ in range(10))
    lines += [wide, wide + " a b", "ab" * 200, "ab" * 201 + "a"]
    for n in (100, 124, 125, 126, 300):
        x = some(n, "abcdefg hi")
        lines += [x.strip(), x[: n // 2].strip() + x[n // 2 + 1 :].rstrip()]
    sets = [{x[i : i + 5] for i in range(max(1, len(x) - 4))} for x in lines]
    parent = list(range(len(lines)))

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for i, a in enumerate(sets):
        for k, b in enumerate(sets[:i]):
            if 100 * len(a & b) >= 80 * len(a | b):
                x, y = sorted((root(i), root(k)))
                parent[y] = x
    got = {x["doc_id"]: x["class_doc_id"] for x in line_dedup.deduplicated(docs(spark, list(enumerate(lines)))).collect()}
    assert got == {i: root(i) for i in range(len(lines))} and len(set(got.values())) < len(lines) - 5


def test_dedup_lines_rewrites_texts(spark):
    line = "the quick brown fox jumps over the lazy dog near the river bank today"
    rows = [(1, f"{line}\nfirst own line here\n\nx"), (2, f"second own line, quite another one\n{line}"), (3, line), (4, None), (5, ""), (1, f"{line}\nfirst own line here\n\nx"), (None, f"{line}\nnobody's line of text without an id")]
    d = docs(spark, rows).withColumnsRenamed({"lang": "occ", "source": "keeper"})
    out = line_dedup.dedup_lines(d)
    assert out.columns == d.columns
    got = sorted(((r["doc_id"], r["text"], r["n_chars"]) for r in out.collect()), key=str)
    one = f"{line}\nfirst own line here\n\nx"
    two = "second own line, quite another one"
    none = "nobody's line of text without an id"
    assert got == sorted([(1, one, len(one)), (1, one, len(one)), (2, two, len(two)), (4, None, None), (5, "", 0), (None, none, len(none))], key=str)
    assert line_dedup.dedup_lines(d.where("false")).count() == 0


# -- 2: n-gram join --------------------------------------------------------------------------


def test_ngram_join_against_brute_force(spark, corpus):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()

    sets = [(i, shingles(t)) for i, t in corpus]
    named = [(i, s) for i, s in sets if i is not None and s]
    parent = {i: i for i, _ in named}

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for k, (i, a) in enumerate(named):
        for j, b in named[:k]:
            if 100 * len(a & b) >= 80 * len(a | b):
                x, y = sorted((root(i), root(j)))
                parent[y] = x
    want = sorted([(i, len(s), None if i is None else root(i) if s else i) for i, s in sets], key=str)
    got = ngram_join.joined(docs(spark, corpus).withColumnsRenamed({"lang": "component_id", "source": "c"}))
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got.collect()), key=str) == want
    one = ngram_join.one_of_each(docs(spark, corpus))
    kept = [r["doc_id"] for r in one.collect()]
    assert sorted(k for k in kept if k is not None) == sorted({i for i, s in sets if i is not None and (not s or root(i) == i)}) and kept.count(None) == 1


def test_ngram_join_of_many_near_copies(spark):
    r = random.Random(9)
    base = prose(r, 120, 5000).split(" ")
    rows = []
    for k in range(60):
        t = list(base)
        t[r.randrange(120)] = f"k{k}"
        rows.append((k, " ".join(t)))
    got = {r["component_id"] for r in ngram_join.joined(docs(spark, rows)).collect()}
    assert got == {0}
    assert ngram_join.joined(docs(spark, rows).where("false")).count() == 0


def test_lists_keep_a_first_class_with_copies(spark):
    rows = [(7, 1, 9, 0, 9)] * 2 + [(7, 2, 9, 1, 9), (7, 3, 9, 0, 9), (8, 4, 9, 0, 9), (9, 5, 9, 0, 9), *[(9, 6, 8, 0, 8)] * 3]
    got = ngram_join._neighbours(spark.createDataFrame(rows, "g bigint, c bigint, n int, p int, e int")).collect()
    assert sorted((r["g"], r["c"], r["before"]["c"] if r["before"] else 0, r["first"]["c"]) for r in got) == [(7, 1, 0, 1), (7, 2, 1, 1), (7, 3, 2, 1), (9, 5, 6, 6), (9, 6, 0, 6)]


def test_ngram_join_of_a_group_with_loose_members(spark):
    """Near copies of up to nine edits, of which the most edited ones link with few or none."""
    r = random.Random(21)
    base = prose(r, 150, 5000).split(" ")
    rows = []
    for k in range(150):
        t = list(base)
        for _ in range(r.randrange(10)):
            t[r.randrange(150)] = f"k{r.randrange(40)}"
        rows.append((k, " ".join(t)))
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (t.split(" ") for _, t in rows)]
    parent = list(range(len(rows)))

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for i, a in enumerate(sets):
        for k, b in enumerate(sets[:i]):
            if 100 * len(a & b) >= 80 * len(a | b):
                x, y = sorted((root(i), root(k)))
                parent[y] = x
    got = {x["doc_id"]: x["component_id"] for x in ngram_join.joined(docs(spark, rows)).collect()}
    assert got == {k: root(k) for k in range(150)} and 5 < len(set(got.values())) < 140


def test_one_of_each_keeps_unlinked_texts_of_one_id(spark):
    r = random.Random(8)
    a, b = prose(r, 60), prose(r, 60)
    rows = [(1, a), (1, b), (1, a), (2, a), (3, b), (4, ""), (4, a), (None, a), (None, a)]
    got = sorted(((x["doc_id"], x["text"]) for x in ngram_join.one_of_each(docs(spark, rows)).collect()), key=str)
    assert got == sorted([(1, a), (1, b), (4, ""), (None, a), (None, a)], key=str)


def test_parity_is_a_lower_bound():
    r = np.random.default_rng(3)
    for n, m, same in ((10, 12, 8), (300, 350, 280), (5000, 4200, 4000)):
        pool = np.unique(r.integers(0, 2**63, n + m, dtype=np.uint64))
        a, b = pool[:n], np.concatenate([pool[:same], pool[n : n + m - same]])
        assert ngram_join.apart(ngram_join.parity(np.sort(a)), ngram_join.parity(np.sort(b))) <= len(np.setxor1d(a, b))


# -- 3: quality --------------------------------------------------------------------------------


def test_quality_base_counts_against_brute_force(spark, corpus):
    extra = [(500, "a b c d e f g h i j\n" * 5), (501, "x # $ % & | < > *\nx # $ % & | < > *"), (502, "é é\n\n é é\n é é")]
    got = {(r["doc_id"], r["n_words"]): r for r in crf_quality.quality(docs(spark, corpus + extra), crf_quality.PRIOR).collect()}
    for i, t in corpus + extra:
        t = t or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        win = [tuple(w[k : k + 8]) for k in range(len(w) - 7)]
        many = {x for x in set(win) if win.count(x) > 1} if len(win) < 3000 else set()
        hit = {k + j for k, x in enumerate(win) if x in many for j in range(8)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        r = got[i, len(w)]
        assert (r["word_chars"], r["n_symbols"], r["n_dup_lines"]) == (sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)))
        assert len(win) >= 3000 or r["n_repeat_words"] == len(hit)
        assert r["base_failed"] == (len(w) < 20 or 100 * r["n_repeat_words"] > 30 * len(w)) and not (r["base_failed"] and r["kept"])


def test_variety_is_of_the_whole_line():
    line = lambda w: " ".join(w).encode()
    at = crf_quality.FEATURES.index("distinct")
    varied = [f"w{k}" for k in range(64)]
    rows, _ = crf_quality.line_features([line(varied), line(varied + ["a", "b"] * 992), line(varied * 31), line(varied[:10]), line(varied + ["x"])])
    assert rows[:, at].tolist() == [1.0, (64 + 31 * 2) / 2048, 1.0, 1.0, 1.0]


def test_viterbi_is_the_best_of_all_labellings():
    from itertools import product

    r = np.random.default_rng(4)
    for _ in range(40):
        s, t = r.normal(size=6), r.normal(size=(2, 2))
        value = lambda y: sum(s[i] for i in range(6) if y[i]) + sum(t[a][b] for a, b in zip(y, y[1:]))
        assert abs(value(crf_quality.viterbi(s, t)) - max(value(y) for y in product((0, 1), repeat=6))) < 1e-9


def test_field_parts_mixed_documents(spark):
    """Documents with boilerplate between content: the share lies between 0 and 1 and follows what was planted."""
    sf = "/root/testdata/sf0.01"
    d, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    w = crf_quality.train(d, labels)
    r = random.Random(3)
    good = lambda: " ".join("".join(r.choice("abcdeghilmnorstu") for _ in range(r.randrange(2, 9))) for _ in range(12)).capitalize() + "."
    bad = lambda: " ".join("### $$$ *** %%% 12 | 7 |".split()[r.randrange(7)] for _ in range(12))
    texts = [(k, "\n".join([*(good() for _ in range(10 - k)), *(bad() for _ in range(2 * k)), *(good() for _ in range(10 - k))])) for k in range(11)]
    got = {x["doc_id"]: (x["content_share"], x["kept"]) for x in crf_quality.quality(docs(spark, texts), w).collect()}
    assert all(abs(got[k][0] - (1 - k / 10)) < 0.11 for k in range(11)), got
    assert [got[k][1] for k in (0, 2, 8, 10)] == [True, True, False, False]
    # a labelled null text, and documents of any length, take part without harm
    extra = spark.createDataFrame([(10**6, None), (10**6 + 1, "\n".join(good() for _ in range(700)))], "doc_id bigint, text string")
    more = spark.createDataFrame([(10**6, 1), (10**6 + 1, 1)], "doc_id bigint, quality int")
    assert len(crf_quality.train(extra, more.withColumn("quality", F.col("doc_id") % 2), fit_segments=5)[0]) == len(crf_quality.FEATURES)


def test_quality_model_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.01"
    d, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    odd = labels.where("doc_id % 2 = 1")
    w = crf_quality.train(d, labels.where("doc_id % 2 = 0"))
    got = crf_quality.quality(d, w).join(odd.select("doc_id", "quality"), "doc_id").where("not base_failed").collect()
    good = [r["kept"] for r in got if r["quality"] == 1]
    bad = [r["kept"] for r in got if r["quality"] == 0]
    assert sum(good) >= 0.99 * len(good) and (not bad or sum(bad) <= 0.3 * len(bad)), (len(good), sum(good), len(bad), sum(bad))
    assert crf_quality.train(d.where("false"), labels) == crf_quality.PRIOR and crf_quality.train(d, labels.where("false")) == crf_quality.PRIOR
    kept = crf_quality.keep(d.withColumnRenamed("lang", "kept"), w)
    assert kept.count() == crf_quality.quality(d, w).where("kept").count()


# -- 4: URLs -------------------------------------------------------------------------------------


def test_url_rules_and_models(spark):
    urls = ["http://www.Example.com/en/1", "https://a.example.com/en/2", "http://x.com/a", "http://b.net/es/5?q", "http://b.net/fr/", "http://b.net/en/1", "http://c.org/en/#t", "nothing", None, "", "http://spam.org", "http://x.com"]
    pages = spark.createDataFrame([(k, u, "h", "z") for k, u in enumerate(urls)] + [(0, urls[0], "h", "z")], "page_id bigint, url string, html string, verdict string")
    got = {r["page_id"]: r for r in url_lm.judged(pages).collect()}
    assert [(got[k]["rule"], got[k]["verdict"]) for k in range(5)] == [("www.example.com/en/", "allow"), ("example.com/en/", "block"), ("com/", "allow"), ("net/es/", "block"), ("net/fr/", "block")]
    assert got[0]["host"] == "www.example.com" and got[3]["path"] == "/es/5" and got[6]["path"] == "/en/"
    assert all((got[k]["host"], got[k]["path"], got[k]["rule"]) == ("", "", None) for k in (7, 8, 9)) and got[11]["rule"] is None
    assert url_lm.judged(pages).count() == len(urls) + 1 and url_lm.judged(pages.where("false")).count() == 0
    # scores, threshold and verdicts against a plain computation
    import math
    from collections import Counter

    many = [f"http://{r}.{h}/{p}/{k}" for k, (r, h, p) in enumerate([("www", "example.com", "en"), ("b", "net", "fr"), ("shop", "x.com", "Straße"), ("c", "net", "es"), ("é", "org", "日本"), ("d", "info", "fr")] * 9)] + [*urls, urls[0], "x" * 3000]
    pages = spark.createDataFrame([(k, u) for k, u in enumerate(many)], "page_id bigint, url string")
    got = {r["page_id"]: r for r in url_lm.judged(pages).collect()}
    held = {r["page_id"] for r in pages.where(F.pmod(F.xxhash64("url"), F.lit(url_lm.FOLDS)) == 0).collect()}
    allow = {k: got[k]["verdict"] == "allow" for k in got if got[k]["rule"]}
    pad = lambda u: "\x02" * 4 + (u or "") + "\x03"
    n = {m: Counter() for m in (True, False)}
    for k, m in allow.items():
        if k not in held:
            s = pad(many[k])
            n[m].update(s[i - o : i + 1] for i in range(4, len(s)) for o in range(5))
    signs = len({c for u in many for c in pad(u)[4:]})

    def p(m, g):
        low = 1 / (signs + 1)
        for o in range(5):
            ctx = g[4 - o : 4]
            own = [v for k, v in n[m].items() if len(k) == o + 1 and k[:-1] == ctx]
            if own:
                low = (n[m][g[4 - o :]] + len(own) * low) / (sum(own) + len(own))
        return low

    for k in [0, 1, 4, 5, *range(54, len(many) - 1)]:
        s = pad(many[k])
        want = sum(math.log(p(True, s[i - 4 : i + 1]) / p(False, s[i - 4 : i + 1])) for i in range(4, len(s))) / (len(s) - 4)
        assert abs(got[k]["score"] - want) < 1e-6
    cut = got[0]["threshold"]
    part = lambda x, m: [allow[k] for k in held if k in allow and (got[k]["score"] >= x) == m]
    worth = lambda x: sum(part(x, True)) / max(1, sum(allow[k] for k in held if k in allow)) + part(x, False).count(False) / max(1, sum(not allow[k] for k in held if k in allow))
    assert {allow[k] for k in held if k in allow} == {True, False} and worth(cut) >= max(worth(got[k]["score"]) for k in held) - 1e-9
    assert all((got[k]["verdict"] == "allow") == (got[k]["score"] >= cut) for k in got if not got[k]["rule"])
    one = pages.where("url like '%fr%'").union(spark.createDataFrame([(None, None)], pages.schema)).withColumn("gram", F.lit(1))
    assert {r["score"] for r in url_lm.judged(one).collect()} == {0.0}


# -- 5: decontamination ----------------------------------------------------------------------------


def test_wu_manber_against_brute_force(spark):
    r = random.Random(8)
    items = [(k, prose(r, r.choice([12, 25])).upper()) for k in range(12)] + [(50, "only three words"), (51, "solo"), (52, None), (53, "--- !!"), (50, "only three words")]
    texts = []
    for k in range(60):
        w = prose(r, r.choice([0, 5, 50, 300])).split(" ")
        if k % 3 == 0:
            own = re.findall(r"[a-z0-9]+", items[k % 12][1].lower())
            at = r.randrange(len(w) + 1)
            w[at:at] = own[: r.choice([9, 10, 11])]
        texts.append((k, " ".join(w)))
    texts += [(90, "x only-three,WORDS solo"), (91, None), (92, ""), (93, "pre " * 3000 + "solo")]
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    lower = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
    pats = {}
    for i, t in items:
        w = word.findall(lower(t))
        for k in range(max(1, len(w) - 9) if w else 0):
            pats.setdefault(tuple(w[k : k + 10]), set()).add(str(i))
    d = docs(spark, texts)
    b = spark.createDataFrame(items, "item_id bigint, text string")
    for small in (wu_manber.PASS_BYTES, 300):
        got = {x["doc_id"]: x for x in wu_manber.search(d, b, pass_bytes=small).collect()}
        for i, t in texts:
            w, hit, ids = word.findall(lower(t)), set(), set()
            for n in {len(p) for p in pats}:
                for k in range(len(w) - n + 1):
                    if (own := pats.get(tuple(w[k : k + n]))):
                        hit |= set(range(k, k + n))
                        ids |= own
            x = got[i]
            spans = list(zip(x["hits"][::2], x["hits"][1::2]))
            assert x["n_words"] == len(w) and {k for a, e in spans for k in range(a, e)} == hit and x["items"] == sorted(ids)
    out = {x["doc_id"]: x for x in wu_manber.decontamination(d, b).collect()}
    assert out[90]["n_hit"] == 4 and out[90]["items_sha256"] == hashlib.sha256(b"50,51").hexdigest() and not out[91]["contaminated"]
    clean = {x["doc_id"] for x in wu_manber.clean_documents(d, b).collect()}
    assert clean == {i for i, x in out.items() if not x["contaminated"]}
    assert clean == {x["doc_id"] for x in wu_manber.clean_documents(d.withColumn("hits", F.lit(1)), b, pass_bytes=300).collect()}
    assert wu_manber.decontamination(d, b.where("false")).where("contaminated").count() == 0 and wu_manber.decontamination(d.where("false"), b).count() == 0


# -- 6: sharding -------------------------------------------------------------------------------------


def test_shards_match_the_mixture(spark):
    rows = [(k % 400, f"t{k}" if k % 50 else None) for k in range(403)]
    d = docs(spark, rows, ["hot", "hot", "hot", "b", None])
    got = sharding.shards(d).collect()
    by = {s: [r for r in got if r["shard"] == s] for s in range(8)}
    sizes = [len(v) for v in by.values()]
    assert sum(sizes) == 403 and max(sizes) - min(sizes) <= 1
    for s, v in by.items():
        assert sorted(r["slot"] for r in v) == list(range(len(v)))
        assert abs(sum(r["source"] == "hot" for r in v) - 403 * 0.6 / 8) <= 2
    want = sorted((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows)
    assert sorted((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want
    assert sharding.shards(d.where("false")).count() == 0
    # places against a plain computation from the same hashes
    raw = F.coalesce("text", F.lit("")).cast("binary")
    keyed = [(r["source"], r["h"], r["doc_id"], r["c"], r["n"]) for r in d.select("source", "doc_id", F.crc32(raw).alias("c"), (F.octet_length(raw) + 1).cast("bigint").alias("n"), F.xxhash64(F.lit(42), "doc_id", F.crc32(raw)).alias("h")).collect()]
    mixed = []
    for s in {x[0] for x in keyed}:
        own = sorted(x[1:] for x in keyed if x[0] == s)
        mixed += [((2 * k + 1) / (2 * len(own)), x[0], s or "", *x[1:]) for k, x in enumerate(own)]
    want = [(x[3], x[4], g * 8 // 403, g - -(-(g * 8 // 403) * 403 // 8)) for g, x in enumerate(sorted(mixed))]
    assert sorted((r["doc_id"], r["text_crc32"], r["shard"], r["slot"]) for r in got) == sorted(want)


# -- 7: chat ---------------------------------------------------------------------------------------------


def test_chat_round_trip_and_parts(spark):
    media = "see https://a.b/x.PNG, (http://c/d.e.mp3) and https://f/g.pdf.\ufeff"
    rows = [(1, 0, "user", "a < b \\l \\b </turn>\n<turn x>\n"), (1, 1, "assistant", "\\<\\\\ok"), (1, 1, "assistant", "\\<\\\\ok"), (1, None, None, None), (2, 0, "we>\nird<", "é x"), (None, 0, "assistant", "null id"),
            (3, 0, "user", media), (3, 1, "assistant", "\ufeff" + media + " <part image:0>"), (3, 2, "assistant", "😀" * 5000)]
    c = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumn("flat", F.lit(1)).withColumn("parts", F.lit("x"))
    f = chat_format.formatted(chat_format.typed_turns(c))
    back = {r["conv_id"]: [(t["role"], t["text"]) for t in r["t"]] for r in f.select("conv_id", chat_format.parsed(f["formatted"], f["attachments"]).alias("t")).collect()}
    assert back[1] == [("", ""), ("user", rows[0][3]), ("assistant", rows[1][3]), ("assistant", rows[1][3])] and back[2] == [("we>\nird<", "é x")]
    assert back[3] == [r[2:] for r in rows[6:]]
    got = {r["conv_id"]: r for r in chat_format.read_back(f).collect()}
    for k in (1, 3, None):
        said = "".join(r[3] for r in rows if r[0] == k and r[2] == "assistant")
        assert got[k]["loss_chars"] == len(said) and got[k]["loss_sha256"] == hashlib.sha256(said.encode()).hexdigest()
    assert (got[3]["n_attachments"], got[3]["expanded_tokens"]) == (6, 2 * (256 + 25 + 512)) and got[2]["loss_spans"] == ""
    form = {r["conv_id"]: r for r in f.collect()}
    assert "see <part image:0>, (<part audio:1>) and <part document:2>." in form[3]["formatted"]
    assert [[a["ref"] for a in t] for t in form[3]["attachments"]] == [["https://a.b/x.PNG", "http://c/d.e.mp3", "https://f/g.pdf"]] * 2 + [[]]
    for r in form.values():
        assert all(r["formatted"][: s["start"]].endswith("<turn assistant>\n") and r["formatted"][s["end"] :].startswith("\n</turn>\n") for s in r["loss_spans"])
    parts = [("text", "see ", None, None), ("image", None, "img://1", 3), ("text", " and <", None, None), ("audio", None, "a.wav", None), ("o>d", None, "o", 9)]
    t = spark.createDataFrame([(7, 0, "user", parts), (7, 1, "assistant", None)], f"conv_id bigint, turn bigint, role string, parts {chat_format.PARTS}")
    r = chat_format.formatted(t).first()
    assert "see <part image:0> and \\l<part audio:1><part o\\gd:2>" in r["formatted"] and r["expanded_tokens"] == 3 * 256 + 25
    assert [(a["type"], a["ref"], a["tokens"]) for a in r["attachments"][0]] == [("image", "img://1", 768), ("audio", "a.wav", 25), ("o>d", "o", 0)]
    assert chat_format.read_back(chat_format.formatted(chat_format.typed_turns(c.where("false")))).count() == 0


# -- 8: packing ----------------------------------------------------------------------------------------------


def test_encoder_equals_the_tokenizer():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    t = Tokenizer.from_file(path)
    t.encode_special_tokens = True
    own = nnls_packing.encoder(path)
    r = random.Random(6)
    texts = ["", " ", "a", " a", "a ", "a  b", "a \n b", "\n \n", "don't we'll  x's", "<|endoftext|> a", "naïve Überfluß 12345 67", "tab\t x", "a  b  c", "x" * 5000]
    texts += ["".join(r.choice("ab  \n.,'s1é　") for _ in range(60)) for _ in range(300)]
    for x in texts:
        assert np.frombuffer(own.pack(x), "<u4").tolist() == t.encode(x, add_special_tokens=False).ids, repr(x)


def test_encoder_equals_the_tokenizer_with_its_defaults():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    t, own = Tokenizer.from_file(path), nnls_packing.encoder(path)
    r = random.Random(7)
    texts = ["a <|endoftext|> b", "<|endoftext|>", "x<|endoftext|><|endoftext|>  y ", " <|endoftext|>\n", "<|endoftext|", "<|endoftext|>a"]
    texts += ["".join(r.choice(["<|endoftext|>", "ab", " ", "  ", "\n", "é", "<|", "'s", "12"]) for _ in range(20)) for _ in range(200)]
    for x in texts:
        assert np.frombuffer(own.encode(x), "<u4").tolist() == t.encode(x, add_special_tokens=False).ids, repr(x)


def test_pieces_take_added_tokens(spark):
    from tokenizers import Tokenizer

    path, text = queries.tokenizer_path(), "a <|endoftext|> b"
    ids = [*Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids, nnls_packing.CLOSE]
    r = nnls_packing.pieces(docs(spark, [(1, text)]), path).first()
    assert (r["doc_tokens"], r["ids_crc32"]) == (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))


def test_packing_places_every_id_once(spark, corpus):
    path = queries.tokenizer_path()
    d = docs(spark, corpus)
    got = nnls_packing.packed(d, path).collect()
    own = nnls_packing.encoder(path)
    want = sorted((str(i), len(own.pack(t or "")) // 4 + 1) for i, t in corpus)
    ends = {}
    for r in got:
        if r["start"] + r["length"] == r["doc_tokens"]:
            ends[str(r["doc_id"]), len(ends)] = r["doc_tokens"]
    assert sorted((k[0], v) for k, v in ends.items()) == want
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for v in by.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= 2048
    for i, t in corpus:
        ids = own.pack(t or "") + np.array([1], "<u4").tobytes()
        mine = [r for r in got if r["doc_id"] == i and r["doc_tokens"] == len(ids) // 4]
        assert all(r["ids_crc32"] == zlib.crc32(ids[4 * r["start"] : 4 * (r["start"] + r["length"])]) for r in mine)
    assert nnls_packing.packed(d.where("false"), path).count() == 0


def test_recipe_uses_the_histogram_with_little_padding():
    r = np.random.default_rng(1)
    h = {int(k): int(v) for k, v in zip(*np.unique(np.clip(r.gamma(2, 40, 5000).astype(int) + 1, 1, 256), return_counts=True))}
    plan = nnls_packing.recipe(h, 256)
    used: dict = {}
    for parts, n in plan:
        assert sum(k * m for k, m in parts.items()) <= 256
        for k, m in parts.items():
            used[k] = used.get(k, 0) + m * n
    assert used == h
    total = sum(k * v for k, v in h.items())
    assert sum(n for _, n in plan) * 256 <= 1.03 * total
    assert nnls_packing.recipe({200: 9}, 256) == [({200: 1}, 9)] and nnls_packing.recipe({}, 256) == []


def test_recipe_is_small():
    """The products of all combinations' columns with one another alone take 250 MB."""
    h = {k: 200000 // k + 1 for k in range(1, 257)}
    tracemalloc.start()
    plan = nnls_packing.recipe(h, 256)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 60 << 20
    assert all(sum(parts.get(k, 0) * r for parts, r in plan) == n for k, n in h.items())


def test_nnls_is_optimal():
    r = np.random.default_rng(2)
    for _ in range(20):
        a, b = r.random((6, 10)), r.normal(size=6)
        x = nnls_packing.nnls(a, b)
        g = a.T @ (b - a @ x)
        assert (x >= 0).all() and (g <= 1e-5).all() and np.abs(g[x > 1e-9]).max(initial=0) < 1e-5


# -- 9: WARC ---------------------------------------------------------------------------------------------------


def test_arc_versions_and_warc_round_trip(spark, tmp_path):
    for version in (1, 2):
        data = arc_warc.arc_head(version) + arc_warc.arc_record(version, "http://a/ b\n", b"x\r\n\r\ny\n") + arc_warc.arc_record(version, None, b"")
        first, second = arc_warc.parse_arc(data)
        assert first["payload"] == b"x\r\n\r\ny\n" and first["url"] == "http://a/%20b%0A" and second["payload"] == b"" and second["url"] == "about:blank"
        with pytest.raises(ValueError):
            list(arc_warc.parse_arc(data[:-3]))
    big, small = "é" * 60, "s" * 99
    rows = [(5, "u5", big), (3, "u3", big), (9, None, big), (1, "u1", small), (2, "u2", small), (4, "u4", None), (7, "u7", ""), (3, "u3", big)]
    p = spark.createDataFrame(rows, "page_id bigint, url string, html string").selectExpr("*", "'x' as member", "1 as archive")
    got = sorted((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in arc_warc.round_trip(p).collect())
    want = sorted((i, len((h or "").encode()), hashlib.sha256((h or "").encode()).hexdigest(), "revisit" if h == big and i != 3 else "response", 3 if h == big and i != 3 else None) for i, _, h in rows)
    assert got == want
    import gzip

    legacy = arc_warc.lay_down(p.repartition(2), 200)
    (tmp_path / "arc").mkdir()
    (tmp_path / "warc").mkdir()
    arc_warc.export(legacy, str(tmp_path / "arc"))
    old = {f.name: list(arc_warc.parse_arc(gzip.decompress(f.read_bytes()))) for f in (tmp_path / "arc").iterdir()}
    assert sum(map(len, old.values())) == len(rows) and len(old) > 2 and max(map(len, old.values())) > 1
    assert {len(x) for records in old.values() for x in records} == {7, 12}  # both versions, with body and payload
    arc_warc.export(arc_warc.convert(arc_warc.materialise(legacy)), str(tmp_path / "warc"))
    every = [h for f in (tmp_path / "warc").iterdir() for h, _ in arc_warc.parse_warc(gzip.decompress(f.read_bytes()))]
    found = [h for h in every if h["WARC-Type"] != "warcinfo"]
    assert len(found) == len(rows) and len(every) == len(rows) + len(old) and all(h["WARC-Date"] == "2020-01-01T00:00:00Z" for h in every)
    ids = {h["WARC-Record-ID"]: h for h in every}
    assert len(ids) == len(every)  # repeated rows too have identifiers of their own
    assert all((h["WARC-Type"] == "revisit") == ("WARC-Refers-To" in h) for h in found)
    assert all(ids[h["WARC-Refers-To"]]["WARC-Payload-Digest"] == h["WARC-Payload-Digest"] for h in found if "WARC-Refers-To" in h)
    odd = b"http://a/\xff 0.0.0.0 20200101000000 text/html 2\nhi\n"
    assert [(x["url"], x["payload"], x["body"]) for x in arc_warc.parse_arc(odd)] == [("http://a/\xff", b"", b"hi")]
    huge = spark.createDataFrame([(1, "u", "x" * 5_000_000), (2, "v", "x" * 5_000_000), (None, None, None)], "page_id bigint, url string, html string")
    assert sorted((r["page_id"] or 0, r["payload_bytes"], r["refers_to"]) for r in arc_warc.round_trip(huge).collect()) == [(0, 0, None), (1, 5_000_000, None), (2, 5_000_000, 1)]
    assert arc_warc.round_trip(p.where("false")).count() == 0


# -- 10: PII -----------------------------------------------------------------------------------------------------


def base_spans(t):
    out = []
    out += [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m[0])
        s = sum((int(c) if k % 2 == 0 else sum(divmod(2 * int(c), 10))) for k, c in enumerate(reversed(d)))
        if 12 <= len(d) <= 19 and s % 10 == 0:
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= sum(c.isdigit() for c in m[0]) <= 15]
    return sorted(out)


def test_pii_base_against_regular_expressions(spark):
    r = random.Random(7)
    parts = ["a@b.co", "x.y@", "@", "+1 (234) 555-7713", "+12", "10.0.0.1", "999.1.1.1", "1.2.3.4.5.6.7.8", "4111 1111 1111 1111", "4111-1111-1111-1112", " ", "-", ".", "é", "7", "a", "..", "+", "@c.d", "a@b.c@d.e", "\U0001f600"]
    texts = ["".join(r.choice(parts) for _ in range(r.randrange(1, 14))) for _ in range(3000)]
    a = pii_anchors.automaton()
    for t in texts:
        assert [x for x in pii_anchors.spans(t, a) if x[1] < 4] == base_spans(t), t
    got = pii_anchors.personal_data(docs(spark, [(1, "mail a@b.co now"), (2, None), (3, ""), (1, "mail a@b.co now")])).collect()
    assert sorted((x["doc_id"], x["n_email"], x["spans"]) for x in got) == [(1, 1, "email:5:11"), (1, 1, "email:5:11"), (2, 0, ""), (3, 0, "")]
    assert pii_anchors.personal_data(docs(spark, [(1, "x")]).where("false")).count() == 0


def test_pii_method_kinds(spark):
    a = pii_anchors.automaton()
    say = lambda t: [(pii_anchors.KINDS[k], t[s:e]) for s, k, e in pii_anchors.spans(t, a) if k >= 4]
    assert say("see https://a.org/x?y=1. and www.b.net, ok") == [("url", "https://a.org/x?y=1"), ("url", "www.b.net")]
    assert say("account no: AB-123456 here") == [("account", "AB-123456")] and say("IBAN DE89 3704 0044 0532 0130 00 x")[0] == ("account", "DE89 3704 0044 0532 0130 00")
    assert say("lives at 12 Long Street today") == [("address", "12 Long Street")] and say("Hauptstraße 5 hier") == [("address", "Hauptstraße 5")]
    assert say("at 7 Mill Road or Rathausplatz 3a") == [("address", "7 Mill Road"), ("address", "Rathausplatz 3a")]
    assert say("true 5 accounts of streets without numbers, password to come") == []
    d = pii_anchors.masked(docs(spark, [(1, "mail a@b.co now"), (2, None)])).collect()
    assert [r["text"] for r in sorted(d, key=lambda r: r["doc_id"])] == ["mail <email> now", None]


def test_pii_ibans_end_where_they_end():
    a = pii_anchors.automaton()
    say = lambda t: [t[s:e] for s, k, e in pii_anchors.spans(t, a) if pii_anchors.KINDS[k] == "account"]
    code = "DE89 3704 0044 0532 0130 00"
    assert say(f"IBAN for bank transfers to us: {code}") == [code]
    assert say(f"pay to {code} today") == [code] and say(f"pay to {code} TODAY OR 2 LATER") == [code] and say("x GB82WEST12345698765432.") == ["GB82WEST12345698765432"]
    assert say(f"iban {code}, konto {code}") == [code, code]
    assert say("pay to DE88 3704 0044 0532 0130 00 today") == [] and say("XDE89370400440532013000") == []


# -- queries and pipeline --------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(queries.ORACLE_SQL))
def test_query_equals_sql(spark, name):
    sf = "/root/testdata/sf0.001"
    c = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "labels", "conversations"):
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    want = c.sql(queries.ORACLE_SQL[name]).df()
    got = queries.QUERIES[name](spark, sf).toPandas()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    cell = lambda v: None if v is None or v is pd.NA or v != v else str(v).removesuffix(".0")
    flat = lambda d: sorted((tuple(map(cell, r)) for r in d[cols].astype(object).itertuples(index=False, name=None)), key=str)
    assert flat(got) == flat(want)


def test_pipeline_stages(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    d = spark.read.parquet(f"{sf}/documents.parquet")
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    sizes = [d.count()]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        before = d
        d = stage(spark, d, sf)
        if k < 4:
            assert d.columns == before.columns and set(d.columns) == set(before.columns)
            d = d.persist()
            sizes.append(d.count())
            if k == 0:
                kept = {r["doc_id"] for r in d.collect()}
                long = {r["doc_id"] for r in crf_quality.quality(before, crf_quality.PRIOR).where("not base_failed").collect()}
                assert all(i in kept for i in long if labels.get(i) == 1)
            if k == 2:
                x = ngram_join.joined(d)
                assert x.where("n_shingles > 0 and doc_id <> component_id").count() == 0
            if k == 3:
                assert wu_manber.decontamination(d, spark.read.parquet(f"{sf}/benchmark.parquet")).where("contaminated").count() == 0
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 0.4 * sizes[0]
    assert d.count() >= sizes[-1]
