"""The registered queries opN_<name> and, where SQL can express them, the same in DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, embedding_dup, language_id, license_scan, near_dup, packing, substring_dup, token_counts, toxicity, warc
from .common import bucket_of, text_batches


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    text_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str) -> str:
    """A file of the public tokenizers package; any other folder works through the operators' own parameters."""
    import public_tokenizers

    return public_tokenizers.path(name)


def pre_token_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return packing.pack(docs, tokenizer_path("byte_bpe_50k.json"), tokenizer_path(packing.RANKS), pre_token_pattern(), 2048)


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text"))


def op3_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"), 2, 80)


def op4_embedding_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dup.near_vectors(table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label"), 0.93)


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dup.removal(table(spark, sf_dir, "documents").select("doc_id", "text"), 20)


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = F.coalesce(bucket_of("doc_id", 5) == 0, F.lit(False))
    model = language_id.train(docs.where(~held).select("doc_id", "text", "lang"))
    return language_id.predict(docs, model).withColumn("held_out", held).select("doc_id", "held_out", "lang_pred", "score")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    held = F.coalesce(bucket_of("doc_id", 4) == 2, F.lit(False))
    model = toxicity.train(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic").where(~held))
    return toxicity.score(docs, model, 0.3).withColumn("held_out", held).select("doc_id", "held_out", "score", "predicted")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages").select("page_id", "url", "html"), 0)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(table(spark, sf_dir, "documents").select("doc_id", "text"), tokenizer_path("word_bpe_49k.json"), 2048)


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents").select("doc_id", "text"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_best_fit_packing": op1_best_fit_packing,
    "op2_decontamination": op2_decontamination,
    "op3_near_duplicates": op3_near_duplicates,
    "op4_embedding_near_dup": op4_embedding_near_dup,
    "op5_substring_dedup": op5_substring_dedup,
    "op6_language_id": op6_language_id,
    "op7_toxicity": op7_toxicity,
    "op8_warc": op8_warc,
    "op9_token_counts": op9_token_counts,
    "op10_license_scan": op10_license_scan,
}

_SHINGLES = """
words AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM documents),
sets AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 2 THEN [w[1]] ELSE list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) END AS s FROM words)"""

_TEMPLATE_ROWS = ", ".join("(" + ", ".join("'" + x.replace("'", "''") + "'" for x in (name, text)) + ")" for name, texts in license_scan.TEMPLATES.items() for text in texts)
_BIGRAMS = "CASE WHEN len(w) > 1 THEN list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) ELSE w END"

ORACLE_SQL: dict[str, str] = {
    "op10_license_scan": f"""
WITH templates(license, t) AS (VALUES {_TEMPLATE_ROWS}),
tw AS (SELECT license, regexp_extract_all(lower(t), '[a-z0-9]+') AS w FROM templates),
tg AS (SELECT license, {_BIGRAMS} AS g FROM tw),
paragraphs AS (SELECT doc_id, text, unnest(regexp_split_to_array(text, '\\n[^\\S\\n]*\\n\\s*')) AS p FROM documents WHERE text IS NOT NULL),
pieces AS (SELECT doc_id, unnest(string_split(p, chr(10))) AS s FROM paragraphs UNION ALL SELECT doc_id, p FROM paragraphs UNION ALL SELECT doc_id, text FROM documents WHERE text IS NOT NULL),
pw AS (SELECT doc_id, regexp_extract_all(lower(s), '[a-z0-9]+') AS w FROM (SELECT DISTINCT doc_id, s FROM pieces)),
pg AS (SELECT doc_id, {_BIGRAMS} AS g FROM pw WHERE len(w) BETWEEN 1 AND 2000),
scored AS (SELECT doc_id, license, 2 * len(list_intersect(pg.g, tg.g)) / (len(pg.g) + len(tg.g)) AS dice FROM pg JOIN tg ON len(pg.g) <= len(tg.g) * 1.5001 AND len(tg.g) <= len(pg.g) * 1.5001)
SELECT doc_id, license, CAST(max(dice) AS DOUBLE) AS dice FROM scored WHERE dice >= 0.8 GROUP BY doc_id, license""",
    "op3_near_duplicates": f"""
WITH RECURSIVE {_SHINGLES},
items AS (SELECT doc_id, len(s) AS n, unnest(s) AS x FROM sets),
links AS (SELECT a.doc_id AS u, b.doc_id AS v FROM items a JOIN items b ON a.x = b.x AND a.doc_id <> b.doc_id AND a.n * 100 >= b.n * 80 AND b.n * 100 >= a.n * 80
  GROUP BY 1, 2 HAVING 100 * count(*) >= 80 * (min(a.n) + min(b.n) - count(*))),
reach AS (SELECT doc_id AS u, doc_id AS v FROM sets UNION SELECT r.u, l.v FROM reach r JOIN links l ON r.v = l.u),
comp AS (SELECT u AS doc_id, min(v) AS component_id FROM reach GROUP BY u)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM sets JOIN comp USING (doc_id)""",
    "op4_embedding_near_dup": """
WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
ok AS (SELECT * FROM v WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (SELECT a.vec_id AS u, b.vec_id AS v FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= 0.93),
reach AS (SELECT vec_id AS u, vec_id AS v FROM v UNION SELECT r.u, l.v FROM reach r JOIN links l ON r.v = l.u),
comp AS (SELECT u AS vec_id, min(v) AS component_id FROM reach GROUP BY u),
n AS (SELECT u AS vec_id, count(*) AS n_links FROM links GROUP BY u)
SELECT vec_id, CAST(coalesce(n_links, 0) AS BIGINT) AS n_links, component_id, vec_id = component_id AS kept FROM comp LEFT JOIN n USING (vec_id)""",
    "op5_substring_dedup": """
WITH words AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM documents),
windows AS (SELECT doc_id, i AS start, array_to_string(w[i:i + 19], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS i FROM words WHERE len(w) >= 20)),
again AS (SELECT doc_id, start FROM (SELECT doc_id, start, row_number() OVER (PARTITION BY k ORDER BY doc_id, start) AS r FROM windows) WHERE r > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(start, start + 20)) AS p FROM again),
lost AS (SELECT doc_id, list(p) AS ps FROM gone GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(len(ps), 0) AS BIGINT) AS n_removed,
  sha256(CASE WHEN ps IS NULL THEN array_to_string(w, ' ') ELSE coalesce(array_to_string(list_transform(list_filter(range(1, len(w) + 1), lambda i: NOT list_contains(ps, i)), lambda i: w[i]), ' '), '') END) AS kept_sha256
FROM words LEFT JOIN lost USING (doc_id)""",
    "op8_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, octet_length(encode(html)) AS payload_bytes, sha1(html) AS hex, min(page_id) OVER (PARTITION BY sha1(html)) AS first_id FROM p)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes,
  array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    CAST((CAST('0x' || substr(hex, CAST((i // 4) * 5 + 1 AS BIGINT), 5) AS BIGINT) >> CAST(15 - 5 * (i % 4) AS INTEGER)) & 31 AS INTEGER) + 1, 1)), '') AS payload_digest,
  CASE WHEN page_id > first_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id > first_id THEN first_id END AS refers_to
FROM d""",
}
