"""The ten queries over whole tables, and SQL that gives the same rows where SQL can."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontam, kdtree, langid, minmax, packing, secrets, topk, toxicity, urls
from .common import table


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return secrets.scan(docs, secrets.fit(docs))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.predict(docs, langid.fit(docs))


def op4_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "\\### Assistant: </turn> ok"
    extra = spark.range(2).select(
        F.lit(-7).cast("long").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit(said).alias("text"),
    )
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra)
    return chat.digests(chat.render(chat.reconstruct(chat.log(rows))))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op7_kd_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kdtree.shard(table(spark, sf_dir, "documents")).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("bytes").alias("law"),
        F.col("shard").cast("int").alias("shard"),
        F.col("slot").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op8_minmax_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minmax.near_duplicates(table(spark, sf_dir, "documents"))


def op9_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return topk.search(vectors, vectors.where("vec_id % 50 = 0"))


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages have no fetch time and no list is given: the day is page_id mod 366, the list example_list()."""
    captures = table(spark, sf_dir, "pages").select("page_id", "url", F.pmod("page_id", F.lit(366)).alias("fetch_day"))
    return urls.judge(captures, urls.example_list(urls.located(captures))).select(
        "page_id", "host", "fetch_day", "n_matches", "matched", "blocked"
    )


QUERIES = {f.__name__: f for f in (op1_best_fit_packing, op2_secret_scan, op3_language_id, op4_chat_formatting, op5_decontamination, op6_toxicity, op7_kd_sharding, op8_minmax_dedup, op9_top_k, op10_url_filter)}

LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLES = {
    "op4_chat_formatting": r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
s AS (
  SELECT *, length(text)
    + length(text) - length(replace(text, '\', ''))
    + length(text) - length(regexp_replace(text, '#+', '#', 'g'))
    + (length(text) - length(replace(text, '</turn>', ''))) // 7 AS body FROM t)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn, role, text), '')) AS loss_sha256,
  CAST(sum(4 + length(role) + 2 + body + 8) AS BIGINT) AS formatted_chars
FROM s GROUP BY conv_id""",
    "op5_decontamination": rf"""
WITH w AS (SELECT doc_id, regexp_extract_all({LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (SELECT item_id, regexp_extract_all({LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
p AS (SELECT DISTINCT item_id, least(13, len(ws)) AS m, array_to_string(ws[i : i + least(13, len(ws)) - 1], ' ') AS k
  FROM (SELECT item_id, ws, unnest(range(1, greatest(1, len(ws) - 12) + 1)) AS i FROM b WHERE len(ws) > 0)),
h AS (SELECT d.doc_id, d.i, d.m, p.item_id FROM (
    SELECT doc_id, m, i, array_to_string(ws[i : i + m - 1], ' ') AS k FROM (
      SELECT doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) AS i FROM w, (SELECT DISTINCT m FROM p) WHERE len(ws) >= m)) d
  JOIN p ON p.m = d.m AND p.k = d.k),
n AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + m)) AS j FROM h) GROUP BY doc_id),
g AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS xs
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM h) GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
  sha256(coalesce(xs, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(ws) AS contaminated
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN g USING (doc_id)""",
    "op8_minmax_dedup": rf"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({LOWER}, '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i : i + 4], ' ') AS k
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(1, len(ws) - 4) + 1)) AS i FROM w WHERE len(ws) > 0)),
c AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
i AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS x FROM s a JOIN s b ON a.k = b.k AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM i JOIN c ca ON ca.doc_id = a JOIN c cb ON cb.doc_id = b WHERE 100 * x >= 75 * (ca.n + cb.n - x)),
e AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
r AS (SELECT doc_id AS a, doc_id AS z FROM documents UNION SELECT e.b, r.z FROM r JOIN e ON e.a = r.a)
SELECT d.doc_id, coalesce(c.n, 0) AS n_shingles, m.z AS component_id, d.doc_id = m.z AS kept
FROM documents d LEFT JOIN c USING (doc_id) JOIN (SELECT a, min(z) AS z FROM r GROUP BY a) m ON m.a = d.doc_id""",
    "op9_top_k": """
WITH v AS (SELECT vec_id, [floor(256 * CAST(x AS DOUBLE)) FOR x IN embedding] AS q FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0),
s AS (SELECT a.vec_id AS query_id, b.vec_id, CAST(list_inner_product(a.q, b.q) AS BIGINT) AS score
  FROM v a JOIN v b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5""",
    "op10_url_filter": r"""
WITH c AS (SELECT page_id, url, page_id % 366 AS fetch_day,
    nullif(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)', 1)), '') AS host,
    nullif(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?[^/:?#]+(?::[0-9]*)?/([^/?#]*)', 1), '') AS part FROM pages),
x AS (SELECT DISTINCT host AS pattern, 'hosts' AS list, 3 AS m FROM c WHERE host IS NOT NULL
  UNION ALL SELECT DISTINCT regexp_replace(host, '^[^.]*\.', ''), 'domains', 2 FROM c WHERE host IS NOT NULL
  UNION ALL SELECT DISTINCT host || '/' || part, 'paths', 4 FROM c WHERE host IS NOT NULL AND part IS NOT NULL),
n AS (SELECT pattern, list, m, CAST('0x' || substr(md5(pattern), 1, 7) AS BIGINT) AS n FROM x),
e AS (SELECT pattern, list, n % 200 AS day, 1 AS o FROM n WHERE n % m = 0
  UNION ALL SELECT pattern, list, n % 200 + 60, 0 FROM n WHERE n % m = 0 AND n % 7 < 4
  UNION ALL SELECT pattern, list, n % 200 + 120, 1 FROM n WHERE n % m = 0 AND n % 5 = 0),
k AS (SELECT page_id, fetch_day, unnest(list_distinct(list_filter(list_concat([array_to_string(string_split(host, '.')[i:], '.') FOR i IN range(1, len(string_split(host, '.')) + 1)], [host || '/' || part]), lambda z: z IS NOT NULL))) AS pattern
  FROM c WHERE host IS NOT NULL),
a AS (SELECT k.page_id, k.pattern, e.list, arg_max(e.o, e.day) AS o FROM k JOIN e ON e.pattern = k.pattern AND e.day <= k.fetch_day GROUP BY ALL),
g AS (SELECT page_id, count(*) AS n_matches, string_agg(DISTINCT pattern, ' ' ORDER BY pattern) AS matched FROM a WHERE o = 1 GROUP BY page_id)
SELECT c.page_id, host, fetch_day, coalesce(n_matches, 0) AS n_matches, coalesce(matched, '') AS matched, n_matches IS NOT NULL AS blocked
FROM c LEFT JOIN g USING (page_id)""",
}
