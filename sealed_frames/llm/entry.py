"""Queries of the training-data operators and, where SQL can express them, their DuckDB text."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import ann, embedding_dedup, html_extract, minhash, mixing, ngram_lm, sentencepiece_codec, toxicity, url_filter, warc
from .runtime import read

TOKENIZERS = "/opt/tokenizers"
PIECES = "piece_bpe_32k.model"


def piece_file() -> str:
    """The piece model of the installed vocabularies; else of their usual folder."""
    try:
        import public_tokenizers
    except ModuleNotFoundError:
        return f"{TOKENIZERS}/{PIECES}"
    return public_tokenizers.path(PIECES)


QUERIES = {}
SQL = {}


def query(fn):
    QUERIES[fn.__name__] = fn
    return fn


@query
def op1_html_extraction(spark, sf_dir):
    """Main text of every page."""
    return html_extract.main_text(read(spark, sf_dir, "pages"))


@query
def op2_toxicity(spark, sf_dir):
    """Toxicity of every document, learnt from the labelled rows outside the held-out fold."""
    return toxicity.held_out_scores(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


@query
def op3_minhash_dedup(spark, sf_dir):
    """Near-duplicate documents: two-word shingles, similarity 0.8."""
    return minhash.near_duplicates(read(spark, sf_dir, "documents"), words=2, percent=80)


SQL["op3_minhash_dedup"] = r"""
WITH RECURSIVE toks AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                    '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) >= 2 THEN list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])
                                    WHEN len(w) = 1 THEN [w[1]] ELSE [] END) AS s FROM toks),
items AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
pairs AS (
  SELECT a.doc_id AS u, b.doc_id AS v FROM items a JOIN items b ON a.g = b.g AND a.doc_id < b.doc_id
  WHERE 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
links AS (SELECT u, v FROM pairs UNION SELECT v, u FROM pairs),
reach AS (SELECT u AS doc_id, u AS r FROM links UNION SELECT l.v, reach.r FROM reach JOIN links l ON l.u = reach.doc_id),
roots AS (SELECT doc_id, min(r) AS root FROM reach GROUP BY doc_id)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, coalesce(root, s.doc_id) AS component_id,
       coalesce(root, s.doc_id) = s.doc_id AS kept
FROM sets s LEFT JOIN roots USING (doc_id)
"""


@query
def op6_sentencepiece(spark, sf_dir):
    """Ids and decoded text of every document, as digests."""
    return sentencepiece_codec.encode_decode(read(spark, sf_dir, "documents"), piece_file())


@query
def op7_ngram_lm(spark, sf_dir):
    """Log-probability of every document under a trigram model of the other folds."""
    return ngram_lm.held_out_scores(read(spark, sf_dir, "documents"))


@query
def op4_mixing(spark, sf_dir):
    """Words that the mixture takes of every document."""
    return mixing.mix(read(spark, sf_dir, "documents")).drop("source")


SQL["op4_mixing"] = r"""
WITH rows AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) AS place FROM documents),
sums AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM rows GROUP BY source),
ranked AS (SELECT *, source_size * 3 AS cap,
  CAST([5, 2, 1][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS INT)] AS DOUBLE) AS w FROM sums),
leveled AS (SELECT *, CAST(sum(source_size) OVER () - coalesce(sum(cap) OVER before, 0) AS DOUBLE)
                      / (sum(w) OVER () - coalesce(sum(w) OVER before, 0)) AS level FROM ranked
  WINDOW before AS (ORDER BY cap / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
aims AS (SELECT source, source_size, least(CAST(cap AS DOUBLE), max(level) OVER () * w) AS target FROM leveled),
budgets AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS passes FROM aims),
run AS (SELECT r.*, source_size, target, passes, target - CAST(passes * source_size AS DOUBLE) AS budget,
  sum(size) OVER (PARTITION BY r.source ORDER BY place) AS upto, sum(size) OVER (PARTITION BY r.source, place) AS here
  FROM rows r JOIN budgets b ON r.source IS NOT DISTINCT FROM b.source)
SELECT doc_id, size, source_size, target,
  CAST(size * (passes + CASE WHEN CAST(2 * upto - here AS DOUBLE) <= 2 * budget THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM run
"""


@query
def op5_warc(spark, sf_dir):
    """Archives of all pages, written and read back."""
    return warc.archive_round_trip(read(spark, sf_dir, "pages")).drop("url")


SQL["op5_warc"] = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha256(coalesce(html, '')) AS d FROM pages),
g AS (SELECT *, min(page_id) OVER (PARTITION BY d) AS first FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, d AS payload_digest,
  CASE WHEN n >= 100 AND first <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN n >= 100 AND first <> page_id THEN first END AS refers_to FROM g
"""

#: (verdict, host, path)
URL_RULES = (
    ("block", "com", "/en/"),
    ("allow", "example.com", "/en/7"),
    ("allow", "net", "/de/"),
    ("block", "example.net", "/de/8"),
    ("block", "org", "/es/"),
)


@query
def op9_url_filter(spark, sf_dir):
    """Verdict of every page's url."""
    return url_filter.judge(read(spark, sf_dir, "pages"), URL_RULES)


_FITS = " ".join(
    f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{v} {h}{p}'"
    for v, h, p in sorted(URL_RULES, key=lambda r: (-r[1].count("."), -len(r[2])))
)
SQL["op9_url_filter"] = f"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
        regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
r AS (SELECT *, CASE {_FITS} END AS hit FROM h)
SELECT page_id, host, path, split_part(hit, ' ', 2) AS rule, CASE WHEN hit IS NULL THEN 'allow' ELSE split_part(hit, ' ', 1) END AS verdict FROM r
"""


@query
def op10_embedding_dedup(spark, sf_dir):
    """Links and components of all vectors at cosine 0.95."""
    return embedding_dedup.close_vectors(read(spark, sf_dir, "embeddings"))


SQL["op10_embedding_dedup"] = """
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
ok AS (SELECT vec_id, e FROM v WHERE e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0
       AND list_dot_product(e, e) > 0),
u AS (SELECT vec_id, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) AS e FROM ok),
links AS (SELECT a.vec_id AS x, b.vec_id AS y FROM u a JOIN u b ON a.vec_id <> b.vec_id AND list_dot_product(a.e, b.e) >= 0.95),
reach AS (SELECT x AS vec_id, x AS r FROM links UNION SELECT l.y, reach.r FROM reach JOIN links l ON l.x = reach.vec_id),
roots AS (SELECT vec_id, min(r) AS root FROM reach GROUP BY vec_id),
counts AS (SELECT x AS vec_id, count(*) AS n FROM links GROUP BY x)
SELECT v.vec_id, coalesce(n, 0) AS n_links, coalesce(root, v.vec_id) AS component_id, coalesce(root, v.vec_id) = v.vec_id AS kept
FROM v LEFT JOIN counts USING (vec_id) LEFT JOIN roots USING (vec_id)
"""


@query
def op8_nearest_neighbours(spark, sf_dir):
    """20 neighbours by inner product of every 20th vector."""
    return ann.neighbours(read(spark, sf_dir, "embeddings"))
