"""The ten operators as queries over their whole tables, with SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, fingerprints, licenses, mixing, packing, pii, quality, simhash, topk, urlfilter
from .common import read


def op1_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of all documents and of their edited texts."""
    return fingerprints.compare_with_edits(read(spark, sf_dir, "documents"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality scores of all documents."""
    docs = read(spark, sf_dir, "documents")
    return quality.score(docs, quality.fit(docs, read(spark, sf_dir, "labels")))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that the mix takes of every document."""
    return mixing.taken_words(read(spark, sf_dir, "documents"))


def op4_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 best inner products of every twentieth vector against all others."""
    found = topk.top_k(read(spark, sf_dir, "embeddings"), "vec_id % 20 = 0")
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents' pieces in sequences of 1024 tokens, with the certificates of their partitions."""
    found = packing.pieces(read(spark, sf_dir, "documents"))
    return packing.pack(found.select("doc_id", "piece", "start", "length", packing.crc_of_ids()))


def op6_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every turn of every conversation from every participant's perspective."""
    return chat.perspectives(read(spark, sf_dir, "conversations"))


def op7_urlfilter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts on all pages' URLs."""
    return urlfilter.judge(read(spark, sf_dir, "pages"), urlfilter.rules_table(spark))


def op8_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data in all documents."""
    return pii.report(read(spark, sf_dir, "documents"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints and near-duplicate components of all documents."""
    return simhash.near_duplicates(read(spark, sf_dir, "documents"))


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """License detections in all documents."""
    found = licenses.scan(read(spark, sf_dir, "documents"))
    return found.withColumn("n_detections", F.size("detections").cast("long")).drop("detections")


def edited_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of operator 1's result that SQL can express."""
    return op1_winnowing(spark, sf_dir).select("doc_id", "n_chars", "edited_sha256")


def mixing_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of operator 3's result that SQL can express."""
    return op3_mixing(spark, sf_dir).select("doc_id", "size", "source_size", F.round("target", 4).alias("target"))


def license_phrases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of operator 10's result that SQL can express."""
    return op10_licenses(spark, sf_dir).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The corpus pipeline at the top of the repository."""
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    f.__name__: f
    for f in (
        op1_winnowing,
        op2_quality,
        op3_mixing,
        op4_topk,
        op5_packing,
        op6_chat,
        op7_urlfilter,
        op8_pii,
        op9_simhash,
        op10_licenses,
        edited_texts,
        mixing_targets,
        license_phrases,
        pipeline,
    )
}

_RULES = " UNION ALL ".join(
    f"SELECT '{v}' AS said, '{h}' AS rule_host, '{p}' AS rule_path" for v, h, p in urlfilter.RULES
)

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PHRASES = " UNION ALL ".join(
    f"SELECT [{', '.join(repr(w) for w in phrase.split())}] AS phrase, '{label}' AS label" for phrase, label in licenses.PHRASES.items()
)

ORACLES = {
    "edited_texts": """
WITH t AS (SELECT doc_id, coalesce(text, '') AS text, row_number() OVER (ORDER BY doc_id DESC NULLS LAST, coalesce(text, '')) AS n FROM documents),
e AS (SELECT doc_id, text, length(text) AS n_chars, coalesce(lead(text) OVER (ORDER BY n), first_value(text) OVER (ORDER BY n)) AS following FROM t)
SELECT doc_id, CAST(n_chars AS BIGINT) AS n_chars,
  sha256(substring(text, 1, n_chars - n_chars // 2) || substring(following, 1, n_chars // 2)) AS edited_sha256 FROM e
""",
    "mixing_targets": """
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS size FROM documents),
s AS (SELECT source, sum(size) AS words, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS n FROM d GROUP BY source),
w AS (SELECT *, CAST(CASE n % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS DOUBLE) AS w, 2.0::DOUBLE * words AS cap, 1.5::DOUBLE * sum(words) OVER () AS shared FROM s),
o AS (SELECT *, row_number() OVER (ORDER BY cap / w, n) AS place FROM w),
l AS (SELECT *, (shared - coalesce(sum(cap) OVER (ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
  / sum(w) OVER (ORDER BY place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM o),
f AS (SELECT min_by(level, place) AS level FROM l WHERE level <= cap / w)
SELECT doc_id, CAST(size AS BIGINT) AS size, CAST(words AS BIGINT) AS source_size, round(least(cap, coalesce(l.w * f.level, cap)), 4) AS target
FROM d JOIN l ON d.source IS NOT DISTINCT FROM l.source, f
""",
    "license_phrases": f"""
WITH t AS (SELECT doc_id, row_number() OVER () AS row,
  regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS words FROM documents),
p AS ({_PHRASES}),
u AS (SELECT row, words, unnest(range(len(words))) AS i FROM t WHERE list_has_any(words, ['license', 'by'])),
m AS (SELECT row, i, label FROM u JOIN p ON words[i + 1] = phrase[1] AND list_slice(words, i + 1, i + len(phrase)) = phrase),
g AS (SELECT row, count(*) AS n, min(i) AS low, max(i) AS high, array_to_string(list_sort(list(DISTINCT label)), ',') AS labels FROM m GROUP BY row)
SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(coalesce(n, 0) AS BIGINT) AS n_base, CAST(low AS BIGINT) AS first_word,
  CAST(high AS BIGINT) AS last_word, coalesce(labels, '') AS base_labels FROM t LEFT JOIN g USING (row)
""",
    "op4_topk": """
WITH numbered AS (
  SELECT row_number() OVER () AS row, vec_id, embedding FROM embeddings WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
), parts AS (
  SELECT row, vec_id, generate_subscripts(embedding, 1) AS i, unnest(embedding) AS x FROM numbered
), whole AS (
  SELECT row FROM parts GROUP BY row HAVING count(*) = count(x) AND bool_and(isfinite(x))
), v AS (
  SELECT row, vec_id, i, CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT) AS x FROM parts SEMI JOIN whole USING (row)
), scores AS (
  SELECT q.row AS query_row, c.row AS row, any_value(q.vec_id) AS query_id, any_value(c.vec_id) AS vec_id, CAST(sum(q.x * c.x) AS BIGINT) AS score
  FROM v q JOIN v c ON q.i = c.i AND q.row <> c.row
  WHERE q.vec_id % 20 = 0 GROUP BY 1, 2
), ranked AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_row ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
  FROM scores
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 20
""",
    "op6_chat": """
WITH t AS (
  SELECT conv_id, turn, coalesce(role, 'unknown') AS speaker, replace(coalesce(text, ''), '<|', '<||') AS text FROM conversations
), p AS (
  SELECT DISTINCT conv_id, speaker AS assistant FROM t WHERE speaker <> 'system'
), r AS (
  SELECT t.conv_id, p.assistant, t.turn, t.speaker, t.text,
    CASE WHEN t.speaker = 'system' THEN 'system' WHEN t.speaker = p.assistant THEN 'assistant' ELSE 'user' END AS role
  FROM t JOIN p ON t.conv_id IS NOT DISTINCT FROM p.conv_id
), h AS (
  SELECT *, '<|' || role || CASE WHEN role = 'user' THEN ' name=' ||
    replace(replace(replace(replace(replace(speaker, '%', '%25'), '|', '%7C'), '<', '%3C'), '>', '%3E'), chr(10), '%0A')
    ELSE '' END || '|>' || chr(10) AS head FROM r
), s AS (
  SELECT *, head || text || chr(10) || '<|end|>' || chr(10) AS segment FROM h
)
SELECT conv_id, assistant, turn, role, CASE WHEN role = 'user' THEN speaker END AS name, segment,
  CASE WHEN role = 'assistant' THEN CAST(length(head) AS BIGINT) ELSE CAST(0 AS BIGINT) END AS mask_start,
  CASE WHEN role = 'assistant' THEN CAST(length(segment) - 1 AS BIGINT) ELSE CAST(0 AS BIGINT) END AS mask_end,
  CAST(coalesce(sum(length(segment)) OVER (PARTITION BY conv_id, assistant ORDER BY turn NULLS FIRST, speaker, text
    ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS dialogue_start
FROM s
""",
    "op7_urlfilter": f"""
WITH rules AS ({_RULES}), u AS (
  SELECT page_id, coalesce(position('://' IN url), 0) AS p, url, row_number() OVER () AS row FROM pages
), s AS (
  SELECT row, page_id,
    CASE WHEN p > 0 THEN translate(regexp_extract(substr(url, p + 3), '^[^/?#]*'),
      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') ELSE '' END AS host,
    CASE WHEN p > 0 THEN regexp_extract(substr(url, p + 3), '^[^/?#]*([^?#]*)', 1) ELSE '' END AS path
  FROM u
), m AS (
  SELECT s.row, rule_host || rule_path AS rule, said,
    row_number() OVER (PARTITION BY s.row ORDER BY length(rule_host || rule_path) DESC) AS n
  FROM s JOIN rules ON (host = rule_host OR ends_with(host, '.' || rule_host)) AND starts_with(path, rule_path)
)
SELECT page_id, host, path, rule, coalesce(said, CASE WHEN host = '' THEN 'block' ELSE 'allow' END) AS verdict
FROM s LEFT JOIN (SELECT * FROM m WHERE n = 1) best ON s.row = best.row
""",
}
