"""The ten operators applied to the given tables, with SQL where it can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import decontam, jaccard, licenses, linededup, packing, secrets, topk, toxicity, urlrules, warc
from .shared import shared_dir, table

#: fixed rules of the url query: host, path, verdict
URL_RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]
#: rows that a model may learn from
TRAIN = "crc32(cast(doc_id as string)) % 5 <> 0"


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _verified(batches):
    """Page rows of archive records: a response's figures come from the payload
    itself, a revisit's from its headers."""
    import pyarrow as pa

    number = lambda urn: None if urn is None or urn.endswith(":null") else int(urn.rpartition(":")[2])
    for batch in batches:
        kind, rid, ref, length, told, payload = (c.to_pylist() for c in batch.columns)
        size = [len(p or b"") if k == "response" else n for k, n, p in zip(kind, length, payload)]
        sha = [warc.digest(p or b"") if k == "response" else d for k, d, p in zip(kind, told, payload)]
        yield pa.RecordBatch.from_arrays([pa.array([number(x) for x in rid], pa.int64()), pa.array(size, pa.int64()), pa.array(sha, pa.string()), pa.array(kind, pa.string()), pa.array([number(x) for x in ref], pa.int64())], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared_dir(spark)
    warc.write_archives(warc.archive_rows(table(spark, sf_dir, "pages")), folder)
    back = warc.read_archives(spark, folder, partition_bytes=8 << 20).where(F.col("record_type").isin("response", "revisit"))
    return back.select("record_type", "record_id", "refers_to", "payload_length", "payload_digest", "payload").mapInArrow(_verified, "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint")


def op2_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_report(table(spark, sf_dir, "documents"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train_model(docs, table(spark, sf_dir, "labels"), TRAIN)
    held = F.crc32(F.col("doc_id").cast("string")) % 5 == 0
    span = lambda x: F.concat_ws(":", x["start"].cast("string"), x["stop"].cast("string"))
    scored = toxicity.score_documents(docs, model, spans_at=0.5)
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.array_join(F.transform("spans", span), ",").alias("spans"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.drop_recurring_lines(table(spark, sf_dir, "documents").select("doc_id", "text"), counts=True)
    return out.select("doc_id", "text", "n_records", "n_dropped")


def op5_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.jaccard_components(table(spark, sf_dir, "documents"), shingle=4, num=85, den=100)


def op6_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urlrules.judge_urls(table(spark, sf_dir, "pages"), URL_RULES)


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.decontamination_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = licenses.license_matches(table(spark, sf_dir, "documents"), licenses.known_licenses(spark))
    return out.select("doc_id", "digest", "license", F.array_join("line_licenses", ",").alias("line_licenses"))


def op10_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.exact_top_k(table(spark, sf_dir, "embeddings"), "id % 50 = 0")


QUERIES = {f.__name__: f for f in (op1_warc, op2_secret_ownership, op3_toxicity, op4_line_dedup, op5_ngram_jaccard, op6_url_rules, op7_packing, op8_decontamination, op9_licenses, op10_top_k)}

_CANON = "lower(coalesce(text, ''))"
_CANON = f"regexp_replace({_CANON}, '(?m)^[ \\t]*(?:copyright|\\(c\\)|©)[^\\n]*$', ' ', 'g')"
for _one, _other in licenses.SPELLINGS:
    _CANON = f"regexp_replace({_CANON}, '{_one}', '{_other}', 'g')"
_CANON = f"trim(regexp_replace({_CANON}, '[^a-z0-9\\x{{80}}-\\x{{10ffff}}]+', ' ', 'g'))"
_NOTICES = ", ".join("('{}', '{}')".format(a, b.replace("'", "''")) for a, b in licenses.NOTICES)

ORACLE_SQL = {
    "op6_url_rules": """
WITH parts AS (
  SELECT page_id, CASE WHEN url IS NULL OR position('://' IN url) = 0 THEN '' ELSE regexp_extract(substr(url, position('://' IN url) + 3), '^[^?#]*') END AS rest FROM pages),
split AS (
  SELECT page_id, translate(regexp_extract(rest, '^[^/]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '/.*$', 0, 's') AS path FROM parts),
rules(rh, rp, rv) AS (VALUES """
    + ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in URL_RULES)
    + """),
hits AS (
  SELECT page_id, host, path, rh || rp AS rule, rv, row_number() OVER (PARTITION BY page_id ORDER BY length(rh || rp) DESC NULLS LAST, length(rh) DESC) AS n
  FROM split LEFT JOIN rules ON (host = rh OR suffix(host, '.' || rh)) AND prefix(path, rp))
SELECT page_id, host, path, rule, coalesce(rv, 'allow') AS verdict FROM hits WHERE n = 1""",
    "op9_licenses": f"""
WITH known AS (
  SELECT sha256(form) AS d, min(license) AS license FROM (SELECT license, {_CANON} AS form FROM (VALUES {_NOTICES}) AS n(license, text)) GROUP BY 1),
whole AS (SELECT doc_id, {_CANON} AS form FROM documents),
lines AS (
  SELECT doc_id, {_CANON} AS form FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS text FROM documents)),
named AS (
  SELECT doc_id, string_agg(DISTINCT license, ',' ORDER BY license) AS line_licenses FROM lines JOIN known ON sha256(form) = d AND form <> '' GROUP BY doc_id)
SELECT doc_id, CASE WHEN form <> '' THEN sha256(form) END AS digest, k.license, coalesce(line_licenses, '') AS line_licenses
FROM whole LEFT JOIN known k ON form <> '' AND sha256(form) = k.d LEFT JOIN named USING (doc_id)""",
    "op10_top_k": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings WHERE embedding IS NOT NULL),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
    "op5_ngram_jaccard": r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS t FROM documents),
sets AS (
  SELECT doc_id, CASE WHEN len(t) = 0 THEN [] WHEN len(t) < 4 THEN [array_to_string(t, ' ')] ELSE list_distinct(list_transform(range(1, len(t) - 2), lambda i: array_to_string(t[i:i + 3], ' '))) END AS s FROM w),
items AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
links AS (
  SELECT a.doc_id AS u, b.doc_id AS v FROM items a JOIN items b ON a.g = b.g AND a.doc_id <> b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
reach AS (SELECT doc_id AS u, doc_id AS v FROM documents UNION SELECT r.u, l.v FROM reach r JOIN links l ON r.v = l.u),
low AS (SELECT u, min(v) AS c FROM reach GROUP BY u)
SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, c AS component_id FROM sets JOIN low ON u = doc_id""",
    "op8_decontamination": r"""
WITH dw AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS t FROM documents),
bw AS (
  SELECT DISTINCT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS t FROM benchmark),
win AS (
  SELECT DISTINCT item_id, m, array_to_string(t[i:i + m - 1], ' ') AS g FROM (SELECT item_id, t, least(len(t), 10) AS m, unnest(range(1, len(t) - least(len(t), 10) + 2)) AS i FROM bw WHERE len(t) > 0)),
sizes AS (SELECT DISTINCT m FROM win),
runs AS (SELECT doc_id, m, i, array_to_string(t[i:i + m - 1], ' ') AS g FROM (SELECT doc_id, t, m, unnest(range(1, len(t) - m + 2)) AS i FROM dw, sizes WHERE len(t) >= m)),
hits AS (SELECT doc_id, runs.m, i, item_id FROM runs JOIN win ON runs.g = win.g AND runs.m = win.m),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + m)) AS p FROM hits) GROUP BY doc_id),
named AS (SELECT doc_id, count(DISTINCT CAST(item_id AS VARCHAR)) AS n_items, string_agg(DISTINCT CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS ids FROM hits GROUP BY doc_id)
SELECT doc_id, CAST(len(t) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN covered USING (doc_id) LEFT JOIN named USING (doc_id)""",
}
