"""Queries of this subpackage for the driver, with production parameters over whole tables."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dpgrid.llm import bpe, dart_minhash, embedding_dedup, line_dedup, packing, quality_knn, quality_rules, token_files, url_filters, warc

WORD_BPE = "word_bpe_49k.json"
BYTE_BPE = "byte_bpe_50k.json"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: The rules that the url query is given.
URL_RULES = [
    url_filters.Rule("org", "/", "allow"),
    url_filters.Rule("example.org", "/es/", "block"),
    url_filters.Rule("example.org", "/en/1", "block"),
    url_filters.Rule("com", "/fr/", "allow"),
    url_filters.Rule("com", "/de/", "block"),
]


def op1_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages").select("page_id", "url")
    return url_filters.judge(pages, URL_RULES).select("page_id", "host", "path", "rule", "verdict", "blocked")


def op2_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.embedding_components(_table(spark, sf_dir, "embeddings"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality_rules.train(docs, _table(spark, sf_dir, "labels"))
    return quality_rules.apply_rules(docs, model).select("doc_id", *quality_rules.COUNTS, "base_failed", "probability", "kept")


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.dedup_lines(docs).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.token_files(_table(spark, sf_dir, "documents"), public_tokenizers.path(WORD_BPE), end_id=2)


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive(_table(spark, sf_dir, "pages"))


def op7_dart_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dart_minhash.near_duplicates(_table(spark, sf_dir, "documents"))


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_table(spark, sf_dir, "documents"), public_tokenizers.path(BYTE_BPE), end_id=0)


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.bpe_digests(_table(spark, sf_dir, "documents"), public_tokenizers.path(WORD_BPE))


def op10_quality_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality_knn.train(docs.where(~quality_knn.held_out()), _table(spark, sf_dir, "labels").where(~quality_knn.held_out()))
    return quality_knn.score(docs, model).select("doc_id", quality_knn.held_out().alias("held_out"), "score", "predicted")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    made = (op1_url_filters, op2_embedding_dedup, op3_quality_rules, op4_line_dedup, op5_token_files, op6_warc, op7_dart_minhash, op8_packing, op9_bpe, op10_quality_knn)
    return {f.__name__: f for f in made}


#: Brute force within labels; quadratic, so for the smaller tables only, which is where it is run.
OP2_SQL = r"""
WITH RECURSIVE e AS (
  SELECT vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
p AS (SELECT a.vec_id AS a, b.vec_id AS b FROM e a JOIN e b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.v) = len(b.v)
      WHERE list_cosine_similarity(a.v, b.v) >= 0.98),
r AS (SELECT vec_id AS v, vec_id AS c FROM embeddings UNION SELECT p.b, r.c FROM r JOIN p ON p.a = r.v)
SELECT m.vec_id, (SELECT count(*) FROM p WHERE p.a = m.vec_id) AS n_links, min(r.c) AS component_id, m.vec_id = min(r.c) AS kept
FROM embeddings m JOIN r ON r.v = m.vec_id GROUP BY m.vec_id
"""

OP6_SQL = r"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
s AS (SELECT page_id, html, strlen(html) AS payload_bytes, sha1(html) AS payload_digest FROM p),
w AS (SELECT html, max(page_id) AS owner FROM s WHERE payload_bytes >= 1000 GROUP BY html)
SELECT s.page_id, s.payload_bytes, s.payload_digest,
       CASE WHEN w.owner <> s.page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN w.owner <> s.page_id THEN w.owner END AS refers_to
FROM s LEFT JOIN w ON w.html = s.html
"""

#: The lines of every document with their keys; blank characters and cases as the operator takes them.
OP4_SQL = r"""
WITH d AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents),
l AS (SELECT doc_id, unnest(lines) AS line, unnest(range(len(lines))) AS pos FROM d),
k AS (SELECT doc_id, pos, line, translate(regexp_replace(line, '^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$', '', 'g'),
        'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
f AS (SELECT key, max(doc_id) AS last_doc FROM k WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
m AS (SELECT k.doc_id, k.pos, k.line, f.key IS NOT NULL AND f.last_doc <> k.doc_id AS gone FROM k LEFT JOIN f USING (key))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""


#: All pairs that share a window, compared in full: lesser counts over greater ones.
OP7_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+') AS ws FROM documents WHERE text IS NOT NULL),
s AS (SELECT doc_id, g, count(*) AS k FROM (SELECT doc_id, array_to_string(ws[i : i + least(5, len(ws)) - 1], ' ') AS g
      FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM w WHERE len(ws) > 0)) GROUP BY doc_id, g),
c AS (SELECT array_to_string(ws, ' ') AS t, min(doc_id) AS rep, list(doc_id) AS members FROM w WHERE len(ws) > 0 GROUP BY t),
r AS (SELECT s.doc_id, g, k, sum(k) OVER (PARTITION BY s.doc_id) AS n FROM s JOIN c ON c.rep = s.doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b FROM r a JOIN r b ON a.g = b.g AND a.doc_id <> b.doc_id
      GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 9 * sum(least(a.k, b.k)) >= 4 * (a.n + b.n)),
k AS (SELECT rep AS v, rep AS comp FROM c UNION SELECT p.b, k.comp FROM k JOIN p ON p.a = k.v),
m AS (SELECT v, min(comp) AS comp FROM k GROUP BY v),
f AS (SELECT unnest(c.members) AS doc_id, c.rep, m.comp FROM c JOIN m ON m.v = c.rep)
SELECT d.doc_id, coalesce(f.rep, d.doc_id) AS copy_of, coalesce(f.comp, d.doc_id) AS component_id, coalesce(f.comp = d.doc_id, true) AS kept
FROM documents d LEFT JOIN f ON f.doc_id = d.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_embedding_dedup": OP2_SQL, "op4_line_dedup": OP4_SQL, "op6_warc": OP6_SQL, "op7_dart_minhash": OP7_SQL}
