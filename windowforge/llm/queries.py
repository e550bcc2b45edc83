"""The operators over their whole tables, with production parameters, and the SQL they can be held against."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import bpe_round_trip
from .common import table
from .exact_dedup import exact_groups
from .jaccard import jaccard_groups
from .licenses import PHRASES, TEMPLATES, license_scan, template_pattern
from .nndescent import nearest
from .packing import pack
from .quality import classify
from .secret_scan import secret_scan
from .token_counts import token_counts
from .warc import BASE32, warc_round_trip


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_round_trip(table(spark, sf_dir, "pages"))


def op2_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_groups(table(spark, sf_dir, "documents"))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))


def op4_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"))


def op5_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_round_trip(table(spark, sf_dir, "documents"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(table(spark, sf_dir, "documents"), keep="max")


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan(table(spark, sf_dir, "documents"))


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(table(spark, sf_dir, "documents"))


def license_sql() -> str:
    """The scan by regular expressions over the words instead of automata."""
    phrase = lambda p: " AND ".join(f"w[i + {k + 1}] = '{x}'" for k, x in enumerate(p.split()))
    base = " UNION ALL ".join(f"SELECT '{label}' AS label, list_filter(range(len(w)), lambda i: {phrase(p)}) AS hits, doc_id FROM t" for p, label in PHRASES.items())
    own = " UNION ALL ".join(f"SELECT doc_id, '{label}' AS label FROM t WHERE " + " OR ".join(f"regexp_matches(joined, '{template_pattern(x)}')" for x in templates) for label, templates in TEMPLATES.items())
    return f"""
        WITH l AS (SELECT doc_id, {LOWERED} AS n FROM documents),
             t AS (SELECT doc_id, regexp_extract_all(n, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w, ' ' || array_to_string(w, ' ') || ' ' AS joined FROM l),
             b AS ({base}),
             f AS (SELECT doc_id, label, unnest(hits) AS i FROM b),
             g AS (SELECT doc_id, count(*) AS n_base, min(i) AS first_word, max(i) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM f GROUP BY doc_id),
             o AS ({own}),
             a AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM (SELECT * FROM o UNION SELECT doc_id, label FROM f) GROUP BY doc_id)
        SELECT t.doc_id, len(w) AS n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
               CASE WHEN t.doc_id IN (SELECT doc_id FROM o) THEN 1.0::DOUBLE WHEN n_base > 0 THEN 0.5 ELSE 0 END AS score
        FROM t LEFT JOIN g USING (doc_id) LEFT JOIN a USING (doc_id)"""


QUERIES = {
    "op1_warc": op1_warc,
    "op2_jaccard": op2_jaccard,
    "op3_token_counts": op3_token_counts,
    "op4_nearest": op4_nearest,
    "op5_bpe_round_trip": op5_bpe_round_trip,
    "op6_quality": op6_quality,
    "op7_exact_dedup": op7_exact_dedup,
    "op8_packing": op8_packing,
    "op9_secrets": op9_secrets,
    "op10_licenses": op10_licenses,
}

LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLE_SQL = {
    "op1_warc": f"""
        WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
             d AS (SELECT page_id, octet_length(encode(h)) AS payload_bytes, sha1(h) AS x, min(page_id) OVER (PARTITION BY h) AS first FROM p)
        SELECT page_id, payload_bytes,
               list_aggregate(list_transform(range(32), lambda i:
                   substr('{BASE32}', 1 + (((('0x' || substr(x, 5 * (i // 4)::BIGINT + 1, 5))::BIGINT) >> (15 - 5 * (i % 4))) & 31)::BIGINT, 1)), 'string_agg', '') AS payload_digest,
               CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
               CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to
        FROM d""",
    "op2_jaccard": f"""
        WITH RECURSIVE t AS (SELECT doc_id, regexp_extract_all({LOWERED}, '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
             s AS (SELECT doc_id, unnest(list_distinct(CASE WHEN len(w) >= 5 THEN list_transform(range(len(w) - 4), lambda i: array_to_string(list_slice(w, i + 1, i + 5), ' '))
                   WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END)) AS g FROM t),
             n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
             p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
             e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 75 * (x.n + y.n - i)),
             h AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
             r(node, root) AS (SELECT a, a FROM h UNION SELECT h.b, r.root FROM r JOIN h ON r.node = h.a),
             c AS (SELECT node, min(root) AS root FROM r GROUP BY 1)
        SELECT t.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c.root, t.doc_id) AS component_id FROM t LEFT JOIN n USING (doc_id) LEFT JOIN c ON c.node = t.doc_id""",
    "op7_exact_dedup": f"""
        WITH t AS (SELECT doc_id, {LOWERED} AS n FROM documents)
        SELECT doc_id, max(doc_id) OVER (PARTITION BY n) AS keep_id, count(*) OVER (PARTITION BY n) AS group_size,
               doc_id = max(doc_id) OVER (PARTITION BY n) AS kept, sha256(n) AS text_sha256
        FROM t""",
}

ORACLE_SQL["op10_licenses"] = license_sql()
