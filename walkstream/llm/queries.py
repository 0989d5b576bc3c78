"""The registered queries of the training-data operators and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import langid, media, mixing, near_dup, pii, sentence_pieces, token_counts, url_filter, vector_search, warc
from ..session import ship
from .common import Workspace, load

#: Rules of the URL query: host, path, action (fixed values).
RULES = (
    ("com", "/en/", "block"),
    ("example.com", "/en/7", "allow"),
    ("net", "/de/", "allow"),
    ("example.net", "/de/8", "block"),
    ("org", "/es/", "block"),
)


def op1_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages").select("page_id", "url")
    return url_filter.judge(pages, RULES).select("page_id", "host", "path", "rule", "verdict")


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3))
    model = langid.train(docs.where(fold != 1).select("text", "lang"))
    found = langid.identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", F.coalesce(fold == 1, F.lit(False)).alias("held_out"), "lang_pred", "score")


def op3_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.media_features(media.store_texts(load(spark, sf_dir, "documents").select("doc_id", "text")))


def op4_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    coded = sentence_pieces.encode(docs, verify=True)
    n = (F.octet_length("piece_ids") / 4).cast("long")
    return coded.select("doc_id", n.alias("n_pieces"), F.sha2("piece_ids", 256).alias("ids_sha256"), "round_trip")


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    found = pii.find(docs, pii.fit(docs))

    def count(kind: str) -> Column:
        return F.size(F.filter("base_spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = [count(kind) for kind in pii.KINDS]
    return found.select("doc_id", *counts, F.sha2(pii.span_text(F.col("base_spans")), 256).alias("base_sha256"), pii.span_text(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text", "source")
    mixed = mixing.mix(docs, Workspace(spark, "mixing"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def op7_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings").select("vec_id", vector_search.quantise(F.col("embedding")).alias("v"))
    return vector_search.top_k(rows, rows.where(F.col("vec_id") % 50 == 0), k=5)


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return token_counts.count_tokens(docs).select("doc_id", "n_words", "n_tokens", "n_unknown")


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages").select("page_id", "url", "html")
    read = warc.read_archives(warc.write_archives(pages, Workspace(spark, "warc")))
    return read.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return near_dup.link(docs, Workspace(spark, "near_dup"), percent=85)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (op1_url_filters, op2_language_id, op3_media_columns, op4_sentencepiece, op5_pii, op6_mixing, op7_topk_search, op8_token_counts, op9_warc, op10_near_dup)
    return {f.__name__: lambda spark, sf_dir, f=f: f(ship(spark), sf_dir) for f in named}


_RULE_ROWS = ", ".join(f"('{h}', '{p}', '{a}')" for h, p, a in RULES)

OP1_SQL = f"""
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id,
    translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut
), rules(rh, rp, action) AS (VALUES {_RULE_ROWS}
), fits AS (
  SELECT page_id, rh || rp AS rule, action,
    row_number() OVER (PARTITION BY page_id ORDER BY length(rh || rp) DESC, action) AS k
  FROM parts JOIN rules ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp)
)
SELECT p.page_id, host, path, rule, coalesce(action, 'allow') AS verdict
FROM parts p LEFT JOIN (SELECT * FROM fits WHERE k = 1) f ON p.page_id = f.page_id
"""

#: Water filling in closed form: sources are cut at their cap in the order of size / weight.
OP6_SQL = r"""
WITH d AS (
  SELECT doc_id, source, text, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS n, (ARRAY[3.0e0, 1.0e0, 2.0e0])[(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS w FROM d GROUP BY source
), o AS (
  SELECT *, 2.0e0 * n AS top, 1.5e0 * sum(n) OVER () AS budget, row_number() OVER (ORDER BY n / w, source NULLS LAST) AS k FROM s
), c AS (
  SELECT *, budget - coalesce(sum(top) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0e0) AS room, sum(w) OVER (ORDER BY k ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS free FROM o
), cut AS (
  SELECT min(k) AS k FROM c WHERE NOT room * w / free > top
), t AS (
  SELECT c.source, n, CASE WHEN c.k < coalesce(cut.k, 1 << 40) THEN top ELSE (SELECT room FROM c x WHERE x.k = cut.k) * w / (SELECT free FROM c x WHERE x.k = cut.k) END AS target FROM c CROSS JOIN cut
), e AS (
  SELECT source, n, target, CASE WHEN n > 0 THEN CAST(floor(target / n) AS BIGINT) ELSE 0 END AS epochs FROM t
), r AS (
  SELECT *, CASE WHEN n > 0 THEN CAST(round_even(target - epochs * n, 0) AS BIGINT) ELSE 0 END AS rest FROM e
), keyed AS (
  SELECT doc_id, source, size, -ln((CAST('0x' || substr(md5(concat_ws(':', '0', CAST(doc_id AS VARCHAR), text)), 1, 13) AS BIGINT) + 0.5e0) / 4503599627370496.0e0)
    / greatest(0.25e0, least(2.0e0, coalesce(length(text) / nullif(size, 0) / 6.0e0, 1.0e0))) AS es_key FROM d
), run AS (
  SELECT *, coalesce(sum(size) OVER (PARTITION BY source ORDER BY es_key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM keyed
)
SELECT doc_id, size, n AS source_size, target, CAST(epochs * size + greatest(0, least(size, rest - before)) AS BIGINT) AS taken
FROM run JOIN r ON run.source IS NOT DISTINCT FROM r.source
"""

#: SHA-1 in base 32: five hexadecimal digits make four characters.
OP9_SQL = """
WITH h AS (
  SELECT page_id, coalesce(html, '') AS body, sha1(coalesce(html, '')) AS hex FROM pages
), d AS (
  SELECT page_id, CAST(strlen(body) AS BIGINT) AS payload_bytes, array_to_string(list_transform(range(0, 32),
    lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(hex, CAST(5 * (i // 4) + 1 AS INTEGER), 5) AS BIGINT) >> CAST(15 - 5 * (i % 4) AS INTEGER)) & 31 AS INTEGER) + 1, 1)), '') AS payload_digest FROM h
), l AS (
  SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS least_id FROM d
)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = least_id THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> least_id THEN least_id END AS refers_to FROM l
"""

OP7_SQL = """
WITH q AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings WHERE embedding IS NOT NULL
), scored AS (
  SELECT a.vec_id AS query_id, b.vec_id AS vec_id,
    CAST(list_sum(list_transform(range(1, len(a.v) + 1), lambda i: a.v[i] * b.v[i])) AS BIGINT) AS score
  FROM q a JOIN q b ON a.vec_id <> b.vec_id AND a.vec_id % 50 = 0
), ranked AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM scored
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 5
"""

OP10_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
    ELSE list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))) END AS sh FROM w
), n AS (SELECT doc_id, len(sh) AS k FROM s
), flat AS (SELECT doc_id, unnest(sh) AS g FROM s
), pairs AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM flat a JOIN flat b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2
), links AS (
  SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.k + y.k - c)
), reach(node, root) AS (
  SELECT doc_id, doc_id FROM n
  UNION
  SELECT links.b, reach.root FROM reach JOIN links ON links.a = reach.node
), comp AS (SELECT node, min(root) AS root FROM reach GROUP BY node)
SELECT n.doc_id, CAST(n.k AS BIGINT) AS n_shingles, comp.root AS component_id, n.doc_id = comp.root AS kept FROM n JOIN comp ON comp.node = n.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_url_filters": OP1_SQL, "op6_mixing": OP6_SQL, "op9_warc": OP9_SQL, "op7_topk_search": OP7_SQL, "op10_near_dup": OP10_SQL}
