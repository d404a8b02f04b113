"""Registered queries of the training-data operators, and their DuckDB SQL.

Every query runs its operator over whole tables; nothing is sampled or capped.
SQL is given where DuckDB can express the result; the other queries are compared
with brute force, an exact round trip or held-out accuracy in ``tests/llm``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.llm import decontaminate, hmm, jaccard, langid, licenses, mtree, packing, sstable, substring, warc_audit

# Fixed values of the damage that the audit query rehearses.
CORRUPT = (97, 13)
MISSING = (193, 7)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_mtree_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = mtree.integer_vectors(table(spark, sf_dir, "embeddings"))
    return mtree.top_k(spark, vectors, F.col("vec_id") % 50 == 0, k=5)


def op2_hmm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    learns = F.crc32(F.col("doc_id").cast("string")) % 10 != 0
    scored = hmm.score_texts(spark, table(spark, sf_dir, "documents"), learns)
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 10 == 0, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op3_sstable_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sstable.encode_to_shards(spark, table(spark, sf_dir, "documents"))


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = jaccard.similar_groups(spark, table(spark, sf_dir, "documents"), shingle=3, similarity=(90, 100))
    return groups.select("doc_id", "n_shingles", "component_id")


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan_licenses(spark, table(spark, sf_dir, "documents")).drop("notices")


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    fold = F.crc32(F.col("doc_id").cast("string")) % 4
    model = langid.learn(spark, docs, fold != 2)
    found = langid.identify(spark, docs, model, keep=["doc_id"])
    held_out = F.coalesce(fold == 2, F.lit(False))
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score", "rejected")


def op7_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = substring.dedup_substrings(spark, table(spark, sf_dir, "documents"), width=13)
    return kept.select("doc_id", "n_words", "n_removed", "kept_sha256")


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.decontaminate(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), width=10)
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def rehearsed_damage(records: DataFrame) -> DataFrame:
    """Overwrite the first octet of some bodies and drop some records, chosen by identifier."""
    hit = F.col("record_id") % CORRUPT[0] == CORRUPT[1]
    broken = F.when(hit & (F.length("body") > 0), F.regexp_replace("record", r"(?s)(\r\n\r\n).", "$1~")).otherwise(F.col("record"))
    return records.where(F.coalesce(F.col("record_id") % MISSING[0] != MISSING[1], F.lit(True))).withColumn("record", broken)


def op9_warc_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_audit.audit_report(spark, table(spark, sf_dir, "pages"), rehearsed_damage)


def op10_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(spark, table(spark, sf_dir, "documents"), width=2048)


QUERIES = {
    "op1_mtree_topk": op1_mtree_topk,
    "op2_hmm_score": op2_hmm_score,
    "op3_sstable_shards": op3_sstable_shards,
    "op4_jaccard_join": op4_jaccard_join,
    "op5_license_scan": op5_license_scan,
    "op6_language_id": op6_language_id,
    "op7_substring_dedup": op7_substring_dedup,
    "op8_decontaminate": op8_decontaminate,
    "op9_warc_fixity": op9_warc_fixity,
    "op10_pack": op10_pack,
}

OP1_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(x::double * 256)) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.e, c.e)::bigint AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank, vec_id, score FROM s)
SELECT query_id, rank::int AS rank, vec_id, score FROM r WHERE rank <= 5"""

_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

OP8_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all({_LOWER}, '{_ALNUM}') AS w FROM documents),
b AS (SELECT coalesce(item_id::varchar, '') AS item_id, regexp_extract_all({_LOWER}, '{_ALNUM}') AS w FROM benchmark),
g AS (SELECT DISTINCT item_id, least(len(w), 10) AS n, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS gram
  FROM (SELECT item_id, w, unnest(generate_series(1, greatest(len(w) - 9, 1))) AS i FROM b WHERE len(w) > 0)),
n AS (SELECT DISTINCT n FROM g),
h AS (SELECT rid, i, n, array_to_string(w[i : i + n - 1], ' ') AS gram FROM (SELECT rid, w, n, unnest(generate_series(1, len(w) - n + 1)) AS i FROM d, n WHERE len(w) >= n)),
m AS (SELECT rid, i, g.n, item_id FROM h JOIN g ON h.gram = g.gram AND h.n = g.n),
c AS (SELECT rid, count(DISTINCT p) AS n_hit FROM (SELECT rid, unnest(generate_series(i, i + n - 1)) AS p FROM m) GROUP BY rid),
t AS (SELECT rid, list_sort(list_distinct(list(item_id))) AS items FROM m GROUP BY rid)
SELECT doc_id, len(w)::bigint AS n_words, coalesce(n_hit, 0)::bigint AS n_hit, coalesce(len(items), 0)::bigint AS n_items,
  sha256(coalesce(array_to_string(items, ','), '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (rid) LEFT JOIN t USING (rid)"""

OP9_SQL = f"""
WITH r AS (SELECT page_id, replace(replace(coalesce(url, ''), chr(13), '%0D'), chr(10), '%0A') AS url, coalesce(html, '') AS body FROM pages),
w AS (SELECT page_id, body, 'WARC/1.0' || chr(13) || chr(10) || 'WARC-Type: response' || chr(13) || chr(10) || 'WARC-Target-URI: ' || url || chr(13) || chr(10)
  || 'WARC-Record-ID: <urn:page:' || coalesce(page_id::varchar, '') || '>' || chr(13) || chr(10) || 'Content-Type: text/html' || chr(13) || chr(10)
  || 'Content-Length: ' || octet_length(encode(body)) || chr(13) || chr(10) || chr(13) || chr(10) || body || chr(13) || chr(10) || chr(13) || chr(10) AS rec FROM r),
s AS (SELECT page_id, body, floor(page_id / {warc_audit.FILE_IDS})::bigint AS warc_file, octet_length(encode(rec))::bigint AS record_octets, sha256(rec) AS sha256 FROM w)
SELECT page_id, warc_file, (sum(record_octets) OVER (PARTITION BY warc_file ORDER BY page_id) - record_octets)::bigint AS record_offset, record_octets, sha256,
  CASE WHEN page_id % {MISSING[0]} = {MISSING[1]} THEN 'missing' WHEN page_id % {CORRUPT[0]} = {CORRUPT[1]} AND body <> '' THEN 'corrupt' ELSE 'ok' END AS status
FROM s"""

OP4_SQL = r"""
WITH RECURSIVE w AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT rid, array_to_string(w[i : i + least(len(w), 3) - 1], ' ') AS g FROM (SELECT rid, w, unnest(generate_series(1, greatest(len(w) - 2, 1))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT rid, count(*) AS n FROM s GROUP BY rid),
o AS (SELECT a.rid AS x, b.rid AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.rid <> b.rid GROUP BY ALL),
e AS (SELECT x, y FROM o JOIN n p ON p.rid = x JOIN n q ON q.rid = y WHERE 100 * k >= 90 * (p.n + q.n - k)),
r(rid, other) AS (SELECT rid, rid FROM w UNION SELECT r.rid, e.y FROM r JOIN e ON e.x = r.other),
c AS (SELECT r.rid, min(w.doc_id) AS component_id FROM r JOIN w ON w.rid = r.other GROUP BY r.rid)
SELECT doc_id, coalesce(n, 0)::bigint AS n_shingles, component_id FROM w JOIN c USING (rid) LEFT JOIN n USING (rid)"""

OP7_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT rid, doc_id, i, array_to_string(w[i : i + 12], ' ') AS gram FROM (SELECT rid, doc_id, w, unnest(generate_series(1, len(w) - 12)) AS i FROM d WHERE len(w) >= 13)),
m AS (SELECT rid, i, doc_id > min(doc_id) OVER (PARTITION BY gram) AS gone FROM g),
c AS (SELECT DISTINCT rid, unnest(generate_series(i, i + 12)) AS p FROM m WHERE gone),
x AS (SELECT d.rid, unnest(w) AS word, generate_subscripts(w, 1) AS p FROM d),
k AS (SELECT x.rid, string_agg(word, ' ' ORDER BY x.p) AS kept, count(*) AS n_kept FROM x LEFT JOIN c ON x.rid = c.rid AND x.p = c.p WHERE c.p IS NULL GROUP BY x.rid)
SELECT doc_id, len(w)::bigint AS n_words, (len(w) - coalesce(n_kept, 0))::bigint AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (rid)"""

ORACLE_SQL = {
    "op4_jaccard_join": OP4_SQL,
    "op7_substring_dedup": OP7_SQL,
    "op1_mtree_topk": OP1_SQL,
    "op5_license_scan": licenses.oracle_sql(),
    "op8_decontaminate": OP8_SQL,
    "op9_warc_fixity": OP9_SQL,
}
