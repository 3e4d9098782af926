"""The ten queries over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from critgraph.llm import arc_warc, chat_format, crf_quality, line_dedup, ngram_join, nnls_packing, pii_anchors, sharding, url_lm, wu_manber

TOKENIZER = "byte_bpe_50k.json"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return str(public_tokenizers.path(TOKENIZER))


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.deduplicated(table(spark, sf_dir, "documents"))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.joined(table(spark, sf_dir, "documents"))


def op3_quality_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return crf_quality.quality(docs, crf_quality.train(docs, table(spark, sf_dir, "labels")))


def op4_url_language_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_lm.judged(table(spark, sf_dir, "pages"))


def op5_wu_manber(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wu_manber.decontamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("hits")


def op6_stratified_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shards(table(spark, sf_dir, "documents"))


def op7_chat_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("bigint"), F.col("turn").cast("bigint"), "role", "text")
    extra = spark.range(2).select(
        F.lit(-7).cast("bigint").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit("\\### Assistant: </turn> ok").alias("text"),
    )
    return chat_format.read_back(chat_format.formatted(chat_format.typed_turns(rows.unionByName(extra))))


def op8_nnls_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nnls_packing.packed(table(spark, sf_dir, "documents"), tokenizer_path())


def op9_arc_to_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return arc_warc.round_trip(table(spark, sf_dir, "pages")).drop("target_uri", "record_id")


def op10_pii_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_anchors.personal_data(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_line_dedup, op2_ngram_jaccard_join, op3_quality_crf, op4_url_language_models, op5_wu_manber, op6_stratified_shards, op7_chat_parts, op8_nnls_packing, op9_arc_to_warc, op10_pii_anchors, pipeline)}

_LOWER = f"translate(coalesce(text, ''), '{url_lm.UPPER}', '{url_lm.LOWER}')"
ORACLE_SQL = {
    "op2_ngram_jaccard_join": rf"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
        ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
k AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM g a JOIN g b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM k JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * k >= 80 * (a.n + b.n - k)),
z AS (SELECT x, y FROM e UNION ALL SELECT y, x FROM e),
r AS (SELECT doc_id AS s, doc_id AS t FROM n UNION SELECT s, y FROM r JOIN z ON t = x),
c AS (SELECT s, min(t) AS c FROM r GROUP BY s)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c.c, d.doc_id) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN c ON c.s = d.doc_id""",
    "op7_chat_parts": rf"""
WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
l AS (SELECT *, regexp_extract_all(text, '{chat_format.MEDIA}') AS links, regexp_replace(text, '{chat_format.MEDIA}', '', 'g') AS bare FROM t),
k AS (SELECT *, list_transform(links, lambda x: {" ".join(f"CASE WHEN regexp_matches(x, '(?i)(?:{e})$') THEN '{n}' ELSE" for n, e in chat_format.ENDINGS.items())} 'text' {"END " * len(chat_format.ENDINGS)}) AS kinds FROM l),
e AS (SELECT *, length(role) + length(regexp_replace(role, '[^\\<>]', '', 'g')) AS r,
  length(bare) + length(regexp_replace(bare, '[^\\<]', '', 'g')) + coalesce(list_sum(list_transform(kinds, lambda x, i: length('<part ' || x || ':' || (i - 1) || '>'))), 0) AS f FROM k),
c AS (SELECT *, sum(r + f + 17) OVER (PARTITION BY conv_id ORDER BY turn, role, text ROWS UNBOUNDED PRECEDING) - 9 AS stop FROM e)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  cast(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS bigint) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  cast(sum(r + f + 17) AS bigint) AS formatted_chars, cast(sum(len(links)) AS bigint) AS n_attachments,
  cast(sum(coalesce(list_sum(list_transform(kinds, lambda x: {" ".join(f"CASE WHEN x = '{n}' THEN {k} ELSE" for n, k in chat_format.UNIT_TOKENS.items())} 0 {"END " * len(chat_format.UNIT_TOKENS)})), 0)) AS bigint) AS expanded_tokens,
  coalesce(string_agg(cast(stop - f AS bigint) || ':' || cast(stop AS bigint), ',' ORDER BY stop) FILTER (WHERE role = 'assistant'), '') AS loss_spans
FROM c GROUP BY conv_id""",
    "op5_wu_manber": r"""
WITH dw AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
bw AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
p AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, unnest(list_transform(range(1, len(w) - least(len(w), 10) + 2), lambda i: array_to_string(w[i:i + least(len(w), 10) - 1], ' '))) AS g FROM bw WHERE len(w) > 0),
l AS (SELECT DISTINCT n FROM p),
pos AS (SELECT doc_id, n, w, unnest(range(1, len(w) - n + 2)) AS i FROM dw, l),
h AS (SELECT pos.doc_id, pos.i, pos.n, p.item_id FROM pos JOIN p ON p.n = pos.n AND p.g = array_to_string(pos.w[pos.i:pos.i + pos.n - 1], ' ')),
c AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS j FROM h) GROUP BY doc_id),
m AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS s FROM (SELECT DISTINCT doc_id, cast(item_id AS varchar) AS item_id FROM h) GROUP BY doc_id)
SELECT dw.doc_id, cast(len(w) AS bigint) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN c ON c.doc_id = dw.doc_id LEFT JOIN m ON m.doc_id = dw.doc_id""",
    "op9_arc_to_warc": """
WITH p AS (SELECT page_id, sha256(coalesce(html, '')) AS payload_digest, cast(strlen(coalesce(html, '')) AS bigint) AS payload_bytes FROM pages),
f AS (SELECT payload_digest, min(page_id) AS first FROM p WHERE payload_bytes >= 100 GROUP BY 1)
SELECT page_id, payload_bytes, p.payload_digest, CASE WHEN first < page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN first < page_id THEN first END AS refers_to
FROM p LEFT JOIN f ON f.payload_digest = p.payload_digest""",
}
