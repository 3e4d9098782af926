"""URL filters: ratio of two character language models, in DataFrame functions alone.

Rules (host with its subdomains, path prefix; the longest fitting rule wins) settle some
URLs. The accepted and the rejected ones train two variable-order Markov models over code points as they stand (orders 0
to ``ORDER``, Witten-Bell smoothing, an unseen context falling back to the shorter one). Every
other URL is judged by the mean log-likelihood difference per character against a
threshold calibrated on the rule-settled URLs of one fold, which trains no model (one in ``FOLDS`` by hash).

Counts cover all rows. Grams, their counts and their ratios are tables that grow with the pages: each order's
probabilities come from the order below by joins on the gram and on its context, and URLs meet the ratios by a join on the gram. Counts are
combined before they are shuffled; the grams that every URL has are dealt out by Spark's handling of skewed joins.

Defined results: a null URL or one without "://" has an empty host and path, fits no rule
and is judged as the text it has; with only one kind of training URL all differences are 0; with only one kind in the
calibrating fold the threshold is 0; ties go to allow;
repeated rows are judged alike, rows without an id like others; very long URLs are scored whole; an empty table gives no row; extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from critgraph.runtime import materialise, release

#: The rules of the query (allow?, host, path prefix).
RULES = ((True, "com", "/"), (False, "example.com", "/en/"), (True, "www.example.com", "/en/"), (False, "net", "/es/"), (False, "net", "/fr/"))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ORDER, FOLDS = 4, 5
#: Signs for the place before a URL's first character and after its last.
BEFORE, AFTER = "\x02", "\x03"
BINS = 400  # of the calibration histogram, over differences of -4 to 4


def host_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, UPPER, LOWER), F.lit("")), F.coalesce(path, F.lit(""))


def rule_of(host: Column, path: Column, rules) -> tuple[Column, Column]:
    """(rule string, allow?) of the longest rule that fits; nulls if none does."""
    fits = [((host == h) | host.endswith("." + h)) & path.startswith(p) for _, h, p in rules]
    ranked = sorted(range(len(rules)), key=lambda k: -len(rules[k][1] + rules[k][2]))
    if not ranked:
        return F.lit(None).cast("string"), F.lit(None).cast("boolean")
    name = F.coalesce(*(F.when(fits[k], F.lit(rules[k][1] + rules[k][2])) for k in ranked))
    allow = F.coalesce(*(F.when(fits[k], F.lit(rules[k][0])) for k in ranked))
    return name, allow


def grams(url: Column) -> Column:
    """The runs of ORDER + 1 signs that end at each character of a URL and behind it."""
    padded = F.concat(F.lit(BEFORE * ORDER), F.coalesce(url, F.lit("")), F.lit(AFTER))
    return F.regexp_extract_all(padded, F.lit(r"(?s)(?=(.{%d}))" % (ORDER + 1)), F.lit(1))


MODELS = ("acc", "rej")


def probabilities(counts: DataFrame, order: int = ORDER) -> DataFrame:
    """(gram, p_acc, p_rej): the last sign's smoothed probability after the signs before it, from (gram, acc, rej)."""
    if order:
        lower = counts.groupBy(F.substring("gram", 2, order).alias("gram")).agg(*(F.sum(x).alias(x) for x in MODELS))
        below = probabilities(lower, order - 1).select(F.col("gram").alias("_low"), *(F.col(f"p_{x}").alias(f"_p_{x}") for x in MODELS))
        seen = counts.groupBy(F.substring("gram", 1, order).alias("_ctx"))
        seen = seen.agg(*(f(x).alias(f"{k}_{x}") for x in MODELS for k, f in (("n", F.sum), ("t", lambda y: F.sum((F.col(y) > 0).cast("int"))))))
        d = counts.withColumns({"_ctx": F.substring("gram", 1, order), "_low": F.substring("gram", 2, order)}).join(seen, "_ctx").join(below, "_low")
    else:  # one row of totals; an unseen sign has its share of one sign more than there are
        r = counts.agg(F.count(F.lit(1)), *(F.sum(x) for x in MODELS), *(F.sum((F.col(x) > 0).cast("int")) for x in MODELS)).first()
        d = counts.withColumns({f"{k}_{x}": F.lit(r[1 + i + 2 * j] or 0) for i, x in enumerate(MODELS) for j, k in enumerate("nt")})
        d = d.withColumns({f"_p_{x}": F.lit(1.0 / (r[0] + 1)) for x in MODELS})
    own = lambda x: F.when(F.col(f"n_{x}") > 0, (F.col(x) + F.col(f"t_{x}") * F.col(f"_p_{x}")) / (F.col(f"n_{x}") + F.col(f"t_{x}"))).otherwise(F.col(f"_p_{x}"))
    return d.select("gram", *(own(x).alias(f"p_{x}") for x in MODELS))


def judged(pages: DataFrame, rules=RULES) -> DataFrame:
    """Per row: page_id, host, path, rule, verdict, score (mean difference a character), threshold."""
    host, path = host_path(F.col("url"))
    name, allow = rule_of(F.col("host"), F.col("path"), rules)
    rows = pages.select("page_id", "url").withColumns({"host": host, "path": path}).withColumns({"rule": name, "_allow": allow})
    rows = rows.withColumns({"_row": F.monotonically_increasing_id(), "_held": F.pmod(F.xxhash64("url"), F.lit(FOLDS)) == 0})
    rows = materialise(rows, "urls")  # the html is read past once
    spelt = rows.withColumn("gram", F.explode(grams(F.col("url"))))
    taught = lambda kind: F.sum((F.col("_allow").eqNullSafe(kind) & ~F.col("_held")).cast("bigint"))
    counts = materialise(spelt.groupBy("gram").agg(taught(True).alias("acc"), taught(False).alias("rej")), "grams")
    kinds = rows.where(~F.col("_held") & F.col("_allow").isNotNull()).select("_allow").distinct().count()
    ratio = F.log("p_acc") - F.log("p_rej") if kinds == 2 else F.lit(0.0)
    ratios = materialise(probabilities(counts).select("gram", ratio.alias("ratio")), "ratios")
    scores = spelt.select("_row", "gram").join(ratios, "gram").groupBy("_row").agg(F.round(F.avg("ratio"), 9).alias("score"))
    scored = materialise(rows.join(scores, "_row").drop("url", "_row"), "scored")
    release(rows, counts, ratios)
    cut = calibrated(scored.where("_held"))
    verdict = F.when(F.coalesce(F.col("_allow"), F.col("score") >= cut), "allow").otherwise("block")
    return scored.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "score", F.lit(cut).alias("threshold"))


def calibrated(scored: DataFrame) -> float:
    """The difference that best parts the rule-settled URLs (balanced), by a histogram of BINS counts."""
    bin_of = F.least(F.greatest(F.floor((F.col("score") + 4) * (BINS / 8)), F.lit(0)), F.lit(BINS - 1)).cast("int")
    rows = scored.where("_allow is not null").groupBy(bin_of.alias("b")).agg(F.sum(F.col("_allow").cast("bigint")).alias("a"), F.sum((~F.col("_allow")).cast("bigint")).alias("r")).collect()
    acc, rej = [0] * BINS, [0] * BINS
    for x in rows:
        acc[x["b"]], rej[x["b"]] = x["a"], x["r"]
    if not sum(acc) or not sum(rej):
        return 0.0
    best, at, below_a, below_r = -1.0, [], 0, 0
    for k in range(BINS + 1):
        worth = (sum(acc) - below_a) / sum(acc) + below_r / sum(rej)
        if worth > best + 1e-12:
            best, at = worth, [k]
        elif worth >= best - 1e-12:
            at.append(k)
        if k < BINS:
            below_a, below_r = below_a + acc[k], below_r + rej[k]
    return round(at[len(at) // 2] * (8 / BINS) - 4, 6)
