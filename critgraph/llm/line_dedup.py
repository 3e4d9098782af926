"""Line dedup: fuzzy lines by MinHash, in DataFrame functions alone.

Lines are compared without the blanks around them. Equal lines form one class first, with
map-side combining, and go on as one occurrence.

Character shingles: the distinct runs of ``RUN`` code points at all positions of the line, whatever its length.
Signatures: minima of the hashed shingles under ``BANDS * ROWS`` permutations (32 bits of the hash times an odd number: with
an xor in its place, a few common words far from others by their hash gave most minima), in all of which shingles that begin
the line or follow a blank come first. So a line with ``LEAST`` of these or more needs no others; a line with fewer than ``FEW`` has a
signature of all its shingles (those in between have both, so similar lines share a kind).
Banding: each band of ROWS minima is a bucket. In a bucket a line is paired with the hub first: the line that
shares buckets with most others. Then it is paired with every line of the
bucket that is still in another component, unless bounds rule the pair out: signatures must agree in ``AGREE`` of
``DIGEST`` minima at least, each known by four bits (lines of Jaccard 0.8 agree in 26 of 32 on average, and 1 in 1,000 of them in fewer than 19),
and what is known of both lines against the hub (sizes, and bitmaps of what each lacks and has besides) must leave room
for the overlap needed (lossless). A pair that shares several buckets is made in the first of them, told by 16 bits of each
key (1 in 10,000 pairs seems to share an earlier one).
Verification: exact Jaccard of the full shingle sets, at least ``THRESHOLD`` percent. Distributed
union-find joins verified pairs; each component keeps its first occurrence.

Defined results: null texts have no line; a line without a sign other than blanks is kept and
in no class; lines shorter than a shingle are one shingle; repeated rows (same doc_id, same
text) are one document and share the decisions, as do lines of equal number and content in
different texts of one doc_id; lines of rows without an id come after all others. Extra columns are
kept by ``dedup_lines`` and clash with nothing (internal names start with _cg).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from critgraph.runtime import components, configured, materialise, release

RUN = 5
BANDS, ROWS = 8, 4
THRESHOLD = 80
DIGEST, AGREE = 32, 19
FEW, LEAST = 12, 6
MARKS = 8  # words of 64 bits of a bitmap
#: The JVM compiles no method of more bytes: a larger join runs as many small ones, not as one that stays interpreted.
COMPILED = {"spark.sql.codegen.hugeMethodLimit": "8000"}
#: Up to so many pairs, the ids of their lines are sent to all tasks (16 MB); beyond, texts and ids are shuffled.
SENT_PAIRS = 1 << 20
DIGESTS = ("g", "f")
BLANKS = " \t\r\x0b\x0c"


def _lines(docs: DataFrame) -> DataFrame:
    """One row per line with a sign: d, x (text hash), n, the place in the order of occurrences, the trimmed line and its hash.

    ``occ`` orders occurrences by doc_id and line; rows without an id come last and are told apart by their text.
    """
    d = docs.select(F.col("doc_id").cast("bigint").alias("d"), F.xxhash64("text").alias("x"), F.posexplode(F.split("text", "\n", -1)).alias("n", "l"))
    d = d.select("d", "x", "n", F.btrim("l", F.lit(BLANKS)).alias("line")).where("line <> ''")
    big = F.coalesce(F.col("d").cast("decimal(20,0)"), F.expr("18446744073709551616BD") + F.col("x").cast("decimal(20,0)"))
    return d.select("d", "x", "n", (big * F.lit(2**31).cast("decimal(10,0)") + F.col("n")).cast("decimal(32,0)").alias("occ"), "line", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(17), "line").alias("h2"))


def all_runs(line: Column) -> Column:
    """The runs at all positions; a shorter line is one run."""
    return F.when(F.length(line) < RUN, F.array(line)).otherwise(F.regexp_extract_all(line, F.lit(r"(?s)(?=(.{%d}))" % RUN), F.lit(1)))


def word_runs(line: Column) -> Column:
    """The runs that begin the line or follow a blank."""
    return F.regexp_extract_all(line, F.lit(r"(?s)(?<!\S)(?=(.{%d}))" % RUN), F.lit(1))


def shingle_set(line: Column) -> Column:
    return F.array_distinct(F.transform(all_runs(line), lambda s: F.xxhash64(s)))


def _seeds() -> list[int]:
    x, out = 88172645463325252, []
    for _ in range(BANDS * ROWS):
        x ^= (x << 13) & (2**64 - 1)
        x ^= x >> 7
        x ^= (x << 17) & (2**64 - 1)
        out.append(x & (2**31 - 1) | 1)
    return out


def permuted(h: Column, c: int) -> Column:
    """The place of a 32-bit hash in the permutation of the odd number c (below 2**31, so the product fits a bigint)."""
    return (h * F.lit(c).cast("bigint")).bitwiseAND(F.lit(2**32 - 1))


def agreement(own: tuple[Column, ...], other: tuple[Column, ...]) -> Column:
    """How many of the DIGEST minima (four bits each, sixteen to a word) are equal in both digests."""
    out = F.lit(DIGEST)
    for x, y in zip(own, other):
        x = x.bitwiseXOR(y)
        x = x.bitwiseOR(F.shiftrightunsigned(x, 1))
        x = x.bitwiseOR(F.shiftrightunsigned(x, 2))
        out = out - F.bit_count(x.bitwiseAND(F.lit(0x1111111111111111)))
    return out


def signatures(lines: DataFrame) -> DataFrame:
    """A row for each distinct line: id, h1, h2, occ (its first), k (how many), line, kinds (a list of kind, keys, one a band, and digest g, f).

    The texts are shuffled once: the minima are gathered by the same keys, and meet the texts by them. What is exploded
    carries no text. The lowest bit of a hash tells the kind of signature, as that of a key does; the next bits of a key are its band.
    """
    reps = lines.groupBy("h1", "h2").agg(F.min("occ").alias("occ"), F.count(F.lit(1)).alias("k"), F.first("line").alias("line"))
    # all columns of reps are asked for (the condition holds), so that the join below reads the same exchange; arrays are
    # exploded once as a whole, so that they are computed once
    whole = F.when(F.col("occ").isNotNull() & (F.col("k") > 0), F.col("line"))
    words = reps.select("h1", "h2", whole.alias("line"), F.explode_outer(F.array(word_runs(whole))).alias("w"))
    of = lambda runs, kind: F.transform(runs, lambda s: F.xxhash64(s).bitwiseAND(F.lit(-2)).bitwiseOR(F.lit(kind)))
    none = F.expr("cast(array() as array<bigint>)")
    hashes = F.concat(F.when(F.size("w") >= LEAST, of(F.col("w"), 0)).otherwise(none), F.when(F.size("w") < FEW, of(all_runs(F.col("line")), 1)).otherwise(none))
    hashed = words.select("h1", "h2", F.explode_outer(hashes).alias("h"))
    hashed = hashed.select("h1", "h2", F.col("h").bitwiseAND(F.lit(1)).alias("kind"), F.shiftrightunsigned("h", 32).alias("h"))
    mins = hashed.groupBy("h1", "h2", "kind").agg(*(F.min(permuted(F.col("h"), c)).alias(f"m{k}") for k, c in enumerate(_seeds())))
    keys = F.array(*(F.xxhash64(*(f"m{b * ROWS + r}" for r in range(ROWS))).bitwiseAND(F.lit(-2 * BANDS)).bitwiseOR(F.lit(2 * b)).bitwiseOR(F.col("kind")) for b in range(BANDS)))
    digest = []
    for w, name in enumerate(DIGESTS):
        g = F.lit(0).cast("bigint")
        for j in range(16):
            g = g.bitwiseOR(F.shiftleft(F.shiftrightunsigned(f"m{16 * w + j}", 12).bitwiseAND(F.lit(15)), 4 * j))
        digest.append(g.alias(name))
    kinds = mins.groupBy("h1", "h2").agg(F.collect_list(F.struct("kind", keys.alias("keys"), *digest)).alias("kinds"))
    return reps.join(kinds, ["h1", "h2"]).withColumn("id", F.monotonically_increasing_id())


def first_shared(band: Column, own: tuple[Column, Column], other: tuple[Column, Column]) -> Column:
    """Whether no band before ``band`` has equal keys, from 16 bits of each key, four bands to a word."""
    out = F.lit(True)
    for w, (x, y) in enumerate(zip(own, other)):
        d = x.bitwiseXOR(y)
        for s in (8, 4, 2, 1):
            d = d.bitwiseOR(F.shiftrightunsigned(d, s))
        before = [sum(1 << 16 * b for b in range(4) if 4 * w + b < k) for k in range(BANDS)]
        mask = F.element_at(F.array(*(F.lit(v).cast("bigint") for v in before)), band + 1)
        out = out & (d.bitwiseAND(mask) == mask)
    return out


def _fits(n, m, k) -> Column:
    """Whether sets of n and m shingles, of which k at most are shared, can reach the threshold."""
    return (100 + THRESHOLD) * k >= THRESHOLD * (n + m)


def _overlaps(pairs: DataFrame, reps: DataFrame) -> DataFrame:
    """(a, b, na, nb, k, lacks, besides): sizes and overlap of the shingle sets of each pair's lines, what a lacks of b and has besides."""
    pairs = pairs if hasattr(pairs, "_critgraph_path") else materialise(pairs, "pairs")
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    texts = reps.select("id", "line").join(F.broadcast(ids) if pairs.count() <= SENT_PAIRS else ids, "id", "left_semi")
    both = pairs.join(texts.select(F.col("id").alias("a"), F.col("line").alias("la")), "a").join(texts.select(F.col("id").alias("b"), F.col("line").alias("lb")), "b")
    sets = both.select("a", "b", F.explode_outer(F.array(F.struct(shingle_set(F.col("la")).alias("a"), shingle_set(F.col("lb")).alias("b")))).alias("s"))
    apart = F.struct(F.array_except("s.b", "s.a").alias("lacks"), F.array_except("s.a", "s.b").alias("besides"))
    d = sets.select("a", "b", F.size("s.a").alias("na"), F.size("s.b").alias("nb"), F.explode_outer(F.array(apart)).alias("d"))
    return d.select("a", "b", "na", "nb", (F.col("nb") - F.size("d.lacks")).alias("k"), "d.lacks", "d.besides")


def _marked(overlaps: DataFrame) -> DataFrame:
    """Overlaps with bitmaps (words l0.., x0..) in place of what a lacks of b and has besides."""
    both = F.concat(F.transform("lacks", lambda h: h.bitwiseAND(F.lit(-2))), F.transform("besides", lambda h: h.bitwiseOR(F.lit(1))))
    e = overlaps.select("b", "a", "na", "nb", "k", F.explode_outer(both).alias("h"))
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.shiftrightunsigned("h", 8).bitwiseAND(F.lit(63)).cast("int"))
    of = lambda kind, word: F.shiftrightunsigned("h", 14).bitwiseAND(F.lit(MARKS - 1)) * 2 + F.col("h").bitwiseAND(F.lit(1)) == 2 * word + kind
    words = [F.coalesce(F.bit_or(F.when(of(kind, j), bit)), F.lit(0).cast("bigint")).alias(f"{n}{j}") for kind, n in enumerate("lx") for j in range(MARKS)]
    return e.groupBy("b", "a", "na", "nb", "k").agg(*words)


WORDS = [f"{n}{j}" for n in "lx" for j in range(MARKS)]


def _most(size: str, of: str = "", other: str = "_2") -> Column:
    """A bound of the overlap of two lines from each one's size n, overlap k with the hub and bitmaps, and the hub's size.

    The columns of the two are told apart by the endings ``of`` and ``other``.
    """
    at = lambda n, end: F.col(f"{n}{end}")
    bits = lambda f: sum((F.bit_count(f(j)) for j in range(1, MARKS)), F.bit_count(f(0)))
    missing = F.greatest(bits(lambda j: at(f"l{j}", of).bitwiseOR(at(f"l{j}", other))), F.col(size) - at("k", of), F.col(size) - at("k", other))
    only = lambda p, q: bits(lambda j: at(f"x{j}", p).bitwiseAND(F.bitwise_not(at(f"x{j}", q))))
    own = F.least(at("n", of) - at("k", of) - only(of, other), at("n", other) - at("k", other) - only(other, of))
    return F.col(size) - missing + own


def line_classes(docs: DataFrame) -> DataFrame:
    """Per line with a sign: d, x, n, occ, and keeper: the occurrence its class keeps."""
    lines = _lines(docs)
    reps = materialise(signatures(lines), "lines")
    release()
    size = F.count(F.lit(1)).over(Window.partitionBy("key"))
    bits = lambda w: reduce(lambda a, b: a.bitwiseOR(b), (F.shiftleft(F.shiftrightunsigned(F.get("s.keys", F.lit(4 * w + b)), 4).bitwiseAND(F.lit(0xFFFF)), 16 * b) for b in range(4)))
    # keys and ids alone are dealt by key; digests follow for the lines that share one
    shared = reps.select("id", F.explode("kinds").alias("s")).select("id", F.explode("s.keys").alias("key"))
    shared = materialise(shared.withColumn("size", size).where("size > 1"), "shared")
    signed = reps.select("id", F.explode("kinds").alias("s")).select("id", "s.kind", *(f"s.{x}" for x in DIGESTS), bits(0).alias("p"), bits(1).alias("q"))
    company = shared.groupBy("id").agg(F.sum("size").alias("company"))
    known = shared.withColumn("kind", F.col("key").bitwiseAND(F.lit(1))).join(signed.join(company, "id"), ["id", "kind"])
    hub = F.first(F.struct("id", *DIGESTS)).over(Window.partitionBy("key").orderBy(F.desc("company"), "id"))
    band = F.shiftright("key", 1).bitwiseAND(F.lit(BANDS - 1)).cast("int").alias("band")
    bands = materialise(known.select("id", *DIGESTS, "p", "q", band, "key", "size", hub.alias("hub")), "buckets")
    release(shared)
    near = bands.where((F.col("id") != F.col("hub.id")) & (agreement(tuple(map(F.col, DIGESTS)), tuple(F.col(f"hub.{x}") for x in DIGESTS)) >= AGREE))
    met = materialise(_marked(_overlaps(near.select(F.col("id").alias("a"), F.col("hub.id").alias("b")).distinct(), reps)), "met")
    linked = lambda d: d.where(_fits(F.col("na"), F.col("nb"), F.col("k"))).select("a", "b")
    # then all that share a bucket, are still apart and are not ruled out; in a bucket of two nothing is left to compare
    parts = materialise(components(linked(met)).withColumnRenamed("node", "id"), "parts")
    placed = bands.where("size > 2").select("id", *DIGESTS, "p", "q", "band", "key", F.col("hub.id").alias("hub")).where("id <> hub").join(parts, "id", "left").withColumn("c", F.coalesce("component", "id"))
    whole = Window.partitionBy("key")
    placed = placed.withColumn("parted", F.min("c").over(whole) != F.max("c").over(whole)).where("parted").drop("component", "parted")
    placed = placed.join(met.select(F.col("a").alias("id"), F.col("b").alias("hub"), F.col("na").alias("n"), "k", F.col("nb").alias("hub_n"), *WORDS), ["id", "hub"], "left").drop("hub")
    placed = materialise(placed, "placed")
    release(bands, parts)
    other = placed.select(F.col("key"), *(F.col(x).alias(f"{x}_2") for x in ("id", *DIGESTS, "p", "q", "c", "n", "k", *WORDS)))
    possible = first_shared(F.col("band"), (F.col("p"), F.col("q")), (F.col("p_2"), F.col("q_2"))) & (agreement(tuple(map(F.col, DIGESTS)), tuple(F.col(f"{x}_2") for x in DIGESTS)) >= AGREE)
    possible = possible & F.coalesce(_fits(F.col("n"), F.col("n_2"), _most("hub_n")), F.lit(True))
    across = placed.join(other, (placed["key"] == other["key"]) & (F.col("id_2") < F.col("id")) & (F.col("c") != F.col("c_2")) & possible)
    with configured(docs.sparkSession, COMPILED):
        across = materialise(across.select(F.col("id").alias("a"), F.col("id_2").alias("b")).distinct(), "across")
    more = materialise(_overlaps(across, reps).drop("lacks", "besides"), "met")
    release(placed, across)
    joined = components(linked(met).union(linked(more)))
    member = materialise(joined.select(F.col("node").alias("id"), "component").union(joined.select("component", "component").distinct()), "parts")
    release(met, more)
    # classes of one occurrence, which keep themselves, go no further
    several = reps.select("id", "h1", "h2", "occ", "k").join(member, "id", "left").where("k > 1 or component is not null").select("h1", "h2", "occ", F.coalesce("component", "id").alias("c"))
    several = materialise(several, "classes")
    release(reps, member)
    kept = several.join(several.groupBy("c").agg(F.min("occ").alias("keeper")), "c").select("h1", "h2", "keeper")
    out = lines.select("d", "x", "n", "occ", "h1", "h2").join(kept, ["h1", "h2"], "left")
    return out.select("d", "x", "n", "occ", F.coalesce("keeper", "occ").alias("keeper"))


def deduplicated(docs: DataFrame) -> DataFrame:
    """Per line with a sign: doc_id, line_no, kept, class_doc_id, class_line_no."""
    of, unit = F.col("keeper"), F.lit(2**31).cast("decimal(10,0)")
    doc = F.floor(of / unit).cast("decimal(22,0)")
    named = F.when(doc < F.expr("9223372036854775808BD"), doc.cast("bigint"))
    return line_classes(docs).select(
        F.col("d").alias("doc_id"), F.col("n").alias("line_no"), (F.col("occ") == of).alias("kept"), named.alias("class_doc_id"), (of - doc * unit).cast("int").alias("class_line_no")
    )


def dedup_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with the lines that are not kept taken out of the texts; a text that loses all its lines goes.

    n_chars, where present, is set to the new length.
    """
    gone = line_classes(docs).where("occ <> keeper").groupBy(F.coalesce("d", F.lit(0)).alias("_cg_d"), F.col("d").isNull().alias("_cg_z"), F.col("x").alias("_cg_x")).agg(F.collect_set("n").alias("_cg_gone"))
    on = (F.coalesce(docs["doc_id"].cast("bigint"), F.lit(0)) == gone["_cg_d"]) & (docs["doc_id"].isNull() == gone["_cg_z"]) & (F.xxhash64(docs["text"]) == gone["_cg_x"])
    d = docs.join(gone, on, "left")
    # exploded, so that a text is split once and not for each of its lines
    d = d.withColumn("_cg_parts", F.explode_outer(F.array(F.when(F.col("_cg_gone").isNotNull(), F.split("text", "\n", -1)))))
    left = F.array_except(F.sequence(F.lit(0), F.size("_cg_parts") - 1), F.col("_cg_gone"))
    text = F.array_join(F.transform(left, lambda i: F.get(F.col("_cg_parts"), i)), "\n")
    d = d.withColumn("_cg_text", F.when(F.col("_cg_gone").isNull(), F.col("text")).otherwise(text))
    d = d.where(F.col("_cg_gone").isNull() | (F.btrim("_cg_text", F.lit(BLANKS + "\n")) != ""))
    cols = [F.col("_cg_text").alias("text") if c == "text" else (F.when(F.col("_cg_gone").isNull(), F.col("n_chars")).otherwise(F.length("_cg_text")).cast(docs.schema["n_chars"].dataType).alias("n_chars") if c == "n_chars" else docs[c]) for c in docs.columns]
    return d.select(*cols)
