"""The registered queries of the operators and their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from .common import table
from .cotrain import score_quality, train_quality
from .decontaminate import decontaminate
from .neardup import near_duplicates
from .packing import pack
from .secrets import scan_secrets
from .sharding import shard_by_bytes
from .simhash import _unsigned_hex, fingerprint_report
from .substrings import remove_repeats
from .toxicity import held_out, score_toxicity, train_toxicity
from .warc import capture_histories


def op1_packing(spark, sf_dir):
    pieces = pack(table(spark, sf_dir, "documents").select("doc_id", "text"), with_ids=False)
    return pieces.select("row.doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_tokens")


def op2_decontamination(spark, sf_dir):
    docs, items = table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark")
    found = decontaminate(spark, docs, items)
    names = F.array_sort(F.transform("items", lambda x: x.cast("string")))
    return found.select(
        "row.doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(names, ",").cast("binary"), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


def op3_sharding(spark, sf_dir):
    text = F.coalesce("text", F.lit(""))
    placed = shard_by_bytes(spark, table(spark, sf_dir, "documents").select("doc_id", "text"), 24)
    return placed.select(
        "doc_id",
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.lit("bytes").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op4_substring_dedup(spark, sf_dir):
    return remove_repeats(spark, table(spark, sf_dir, "documents")).drop("kept_text")


def op5_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = score_toxicity(spark, docs, train_toxicity(spark, docs, table(spark, sf_dir, "labels")))
    return found.select("row.doc_id", held_out(F.col("row.doc_id")).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op6_quality_cotraining(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    found = score_quality(spark, docs.select("doc_id", "text", "lang", "source", "n_chars"), train_quality(spark, docs, table(spark, sf_dir, "labels")))
    return found.select("row.doc_id", held_out(F.col("row.doc_id")).alias("held_out"), "text_score", "meta_score", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op7_warc(spark, sf_dir):
    found = capture_histories(spark, table(spark, sf_dir, "pages"))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "urlkey", "timestamp", "history_order")


def op8_secret_scan(spark, sf_dir):
    found = scan_secrets(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("row.doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans")


def op9_document_fingerprints(spark, sf_dir):
    return fingerprint_report(spark, table(spark, sf_dir, "documents"))


def op10_simhash_neardup(spark, sf_dir):
    found = near_duplicates(spark, table(spark, sf_dir, "documents"), width=3, radius=3)
    return found.select("doc_id", _unsigned_hex(F.col("fp")).alias("fingerprint"), "component_id")


QUERIES = {
    "op1_packing": op1_packing,
    "op2_decontamination": op2_decontamination,
    "op3_sharding": op3_sharding,
    "op4_substring_dedup": op4_substring_dedup,
    "op5_toxicity": op5_toxicity,
    "op6_quality_cotraining": op6_quality_cotraining,
    "op7_warc": op7_warc,
    "op8_secret_scan": op8_secret_scan,
    "op9_document_fingerprints": op9_document_fingerprints,
    "op10_simhash_neardup": op10_simhash_neardup,
}

#: Windows of ten words; every word of a document in an occurrence of one is hit.
_OP2 = r"""
WITH words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), items AS (
  SELECT item_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE text IS NOT NULL AND item_id IS NOT NULL
), grams AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') AS g
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM items WHERE len(w) > 0)
), sizes AS (SELECT DISTINCT n FROM grams),
places AS (
  SELECT doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') AS g
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM words, sizes WHERE len(w) >= n)
), hits AS (SELECT p.doc_id, p.n, p.i, g.item_id FROM places p JOIN grams g ON p.g = g.g AND p.n = g.n),
covered AS (SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS k FROM hits) GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hits) GROUP BY doc_id)
SELECT w.doc_id, CAST(len(w.w) AS BIGINT) AS n_words, CAST(coalesce(c.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n.n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(n.names, '')) AS items_sha256, coalesce(c.n_hit, 0) > 0 AS contaminated
FROM words w LEFT JOIN covered c USING (doc_id) LEFT JOIN named n USING (doc_id)
"""

_OP4 = r"""
WITH words AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
places AS (SELECT doc_id, i, md5(array_to_string(w[i : i + 49], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS i FROM words WHERE len(w) >= 50)),
firsts AS (SELECT g, min(doc_id) AS first_id FROM places GROUP BY g),
gone AS (SELECT DISTINCT p.doc_id, unnest(range(p.i, p.i + 50)) AS k FROM places p JOIN firsts f USING (g) WHERE f.first_id < p.doc_id),
lost AS (SELECT doc_id, list(k) AS ks, count(*) AS n_removed FROM gone GROUP BY doc_id)
SELECT w.doc_id, CAST(len(w.w) AS BIGINT) AS n_words, CAST(coalesce(l.n_removed, 0) AS BIGINT) AS n_removed,
  sha256(array_to_string(CASE WHEN l.ks IS NULL THEN w.w ELSE list_transform(list_filter(range(1, len(w.w) + 1), lambda k: NOT list_contains(l.ks, k)), lambda k: w.w[k]) END, ' ')) AS kept_sha256
FROM words w LEFT JOIN lost l USING (doc_id)
"""

#: Base32 from the hexadecimal SHA-1: each five digits make four letters. The order of captures is that of their sorted keys.
_OP7 = """
WITH paid AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
hashed AS (SELECT page_id, CAST(octet_length(b) AS BIGINT) AS payload_bytes, sha1(b) AS h FROM paid),
named AS (
  SELECT page_id, payload_bytes, list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    CAST(((CAST('0x' || substr(h, CAST((i // 4) * 5 + 1 AS BIGINT), 5) AS BIGINT) >> CAST((3 - i % 4) * 5 AS INTEGER)) & 31) + 1 AS BIGINT), 1)), 'string_agg', '') AS payload_digest
  FROM hashed
), heads AS (SELECT payload_digest, max(page_id) AS head FROM named GROUP BY payload_digest),
parts AS (
  SELECT page_id, regexp_extract(u, '^[a-z][a-z0-9+.-]*://([^/?#]*)', 1) AS host, regexp_extract(u, '^[a-z][a-z0-9+.-]*://[^/?#]*([^?#]*)', 1) AS path, regexp_extract(u, '(\\?[^#]*)', 1) AS query
  FROM (SELECT page_id, lower(trim(coalesce(url, ''))) AS u FROM pages)
), keys AS (
  SELECT page_id, array_to_string(list_reverse(string_split(regexp_replace(regexp_replace(regexp_replace(host, '^.*@', ''), ':[0-9]*$', ''), '^www[0-9]*\\.', ''), '.')), ',') || ')'
    || CASE WHEN path = '' THEN '/' ELSE path END || query AS urlkey,
    strftime(TIMESTAMP '2024-01-01 00:00:00' + to_seconds(page_id % 2147483648), '%Y%m%d%H%M%S') AS timestamp
  FROM parts
), ordered AS (SELECT page_id, urlkey, timestamp, row_number() OVER (ORDER BY urlkey, timestamp, page_id) - 1 AS history_order FROM keys)
SELECT n.page_id, n.payload_bytes, n.payload_digest, CASE WHEN n.page_id = h.head THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN n.page_id = h.head THEN NULL ELSE h.head END AS refers_to, o.urlkey, o.timestamp, CAST(o.history_order AS BIGINT) AS history_order
FROM named n JOIN heads h USING (payload_digest) JOIN ordered o USING (page_id)
"""

ORACLES: dict[str, str] = {"op7_warc": _OP7, "op2_decontamination": _OP2, "op4_substring_dedup": _OP4}
