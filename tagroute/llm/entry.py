"""The corpus operators' queries over the given tables, with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import jpeg_thumbs, piece_sampling, quality_pu, role_repair, toxicity_ws, warc_revisit
from .decontam_sa import contamination
from .secret_ownership import BASE_PATTERNS, OPAQUE_PATTERN, scan, told
from .shingle_join import shingle_components
from .suffix_dedup import drop_repeats


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_pu_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: a quality score of its whole text, learnt from positive and unlabelled rows outside the held-out fold."""
    docs = _documents(spark, sf_dir)
    model = quality_pu.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    held = F.coalesce(F.crc32(F.col("id").cast("string")) % 4 == 2, F.lit(False))
    return quality_pu.score(docs, model).select(F.col("id").alias("doc_id"), held.alias("held_out"), "score", F.when(F.col("score") >= 0.7, 1).otherwise(0).alias("predicted"))


def op2_revisit_resolution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per revisit record of a crawl over `pages`: its base response, what became of it, and the merged headers."""
    found = warc_revisit.resolve(warc_revisit.records_of_pages(spark.read.parquet(f"{sf_dir}/pages.parquet")))
    said = F.array_join(F.array_sort(F.transform(F.map_entries("headers"), lambda e: F.concat_ws(": ", e["key"], e["value"]))), "; ")
    return found.select("rec_id", "canonical", "ts", "status", "base_id", "digest", said.alias("headers"))


def op3_jpeg_thumbnails(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: its text stored as the DC levels of a JPEG, read back, with digests and thumbnail hash."""
    return jpeg_thumbs.features(jpeg_thumbs.store(_documents(spark, sf_dir))).withColumnRenamed("id", "doc_id")


def op4_weak_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: a toxicity score of its whole text, learnt by weak supervision from rows outside the held-out fold."""
    docs = _documents(spark, sf_dir)
    model = toxicity_ws.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    held = F.coalesce(F.crc32(F.col("id").cast("string")) % 5 == 0, F.lit(False))
    return toxicity_ws.score(docs, model).select(F.col("id").alias("doc_id"), held.alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def op5_suffix_tree_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: words, words in repeated windows of 35, and a digest of what stays."""
    return drop_repeats(_documents(spark, sf_dir), keep_text=False).withColumnRenamed("id", "doc_id")


def op6_secret_ownership(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: secrets by kind, a digest of the base spans, and all spans with those of owner-specific tokens."""
    found = scan(_documents(spark, sf_dir))
    return found.select(F.col("id").alias("doc_id"), "n_assign", "n_access", "n_hex", F.sha2(told(F.col("base")), 256).alias("base_sha256"), told(F.col("spans")).alias("spans"), "n_live", "n_shared")


def op7_role_repair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per turn: its role and its piece of the rendering after the cheapest repair of its conversation."""
    return role_repair.repair(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


def op8_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: size of its set of 5-word shingles, and the least document that links of Jaccard 0.8 reach."""
    return shingle_components(_documents(spark, sf_dir)).select(F.col("id").alias("doc_id"), "n_shingles", "component_id")


def op9_suffix_array_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: words, words in windows of test items, the items found, and the longest match."""
    found = contamination(_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), keep_text=False)
    return found.select(F.col("id").alias("doc_id"), "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated", "longest")


def op10_sampled_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: pieces of a sampled segmentation, a digest of them, and whether decoding gives the text back."""
    return piece_sampling.round_trip(_documents(spark, sf_dir), piece_sampling.default_model()).withColumnRenamed("id", "doc_id")


QUERIES = {f.__name__: f for f in (op1_pu_quality, op2_revisit_resolution, op3_jpeg_thumbnails, op4_weak_toxicity, op5_suffix_tree_dedup, op6_secret_ownership, op7_role_repair, op8_ngram_jaccard_join, op9_suffix_array_decontamination, op10_sampled_pieces)}


def _sql_text(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def _secrets_sql() -> str:
    """The secret scan by cutting texts at matches, one kind after the other."""
    kinds = [*((k, p, g, n) for k, p, g, n in BASE_PATTERNS), ("opaque", OPAQUE_PATTERN, 0, 24)]
    spans = " UNION ALL ".join(
        f"SELECT doc_id, source, lang, {rank} AS rank, '{kind}' AS kind, unnest(list_transform(range(1, len(w) + 1), lambda i: "
        "{'s': list_sum(g[1:i]) + coalesce(list_sum(list_transform(w[1:i - 1], lambda x: length(x))), 0), 'n': length(w[i]), 'v': v[i]})) AS m "
        f"FROM (SELECT doc_id, source, lang, regexp_extract_all(text, {_sql_text(pattern)}, 0) AS w, regexp_extract_all(text, {_sql_text(pattern)}, {group}) AS v, "
        f"list_transform(regexp_split_to_array(text, {_sql_text(pattern)}), lambda x: length(x)) AS g FROM t)"
        for rank, (kind, pattern, group, _) in enumerate(kinds)
    )
    least = "CASE kind " + " ".join(f"WHEN '{k}' THEN {n}" for k, _, _, n in kinds) + " END"
    at = "kind || ':' || CAST(s AS VARCHAR) || ':' || CAST(e AS VARCHAR)"
    return f"""
WITH t AS (SELECT doc_id, source, lang, coalesce(text, '') AS text FROM documents),
found AS (SELECT doc_id, source, lang, rank, kind, CAST(m.s AS BIGINT) AS s, CAST(m.s + m.n AS BIGINT) AS e, m.v AS v FROM ({spans})
  WHERE length(m.v) >= {least} AND (kind <> 'opaque' OR (regexp_matches(m.v, '[A-Z]') AND regexp_matches(m.v, '[a-z]') AND regexp_matches(m.v, '[0-9]')))),
owned AS (SELECT v, count(DISTINCT source) + max(CASE WHEN source IS NULL THEN 1 ELSE 0 END) AS owners, count(DISTINCT {{'s': source, 'l': lang}}) AS repos FROM found GROUP BY v),
judged AS (SELECT f.*, o.owners <= 1 AND o.repos <= 2 AS live FROM found f JOIN owned o ON f.v = o.v),
summed AS (SELECT doc_id, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
  string_agg({at}, ',' ORDER BY s, rank) FILTER (kind <> 'opaque') AS base, string_agg({at}, ',' ORDER BY s, rank) FILTER (kind <> 'opaque' OR live) AS spans,
  count(DISTINCT v) FILTER (live) AS n_live, count(DISTINCT v) FILTER (NOT live) AS n_shared FROM judged GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256,
  coalesce(spans, '') AS spans, coalesce(n_live, 0) AS n_live, coalesce(n_shared, 0) AS n_shared
FROM documents d LEFT JOIN summed USING (doc_id)
"""


def _canonical_sql(url: str) -> str:
    rest = f"regexp_replace(regexp_replace({url}, '#.*$', ''), '^[A-Za-z][A-Za-z0-9+.-]*://', '')"
    host = f"regexp_replace(regexp_replace(lower(regexp_extract({rest}, '^([^/?]*)', 1)), ':(80|443)$', ''), '^www[0-9]*[.]', '')"
    path = f"regexp_replace(regexp_extract({rest}, '^[^/?]*([^?]*)', 1), '/(index[.]html?)?$', '')"
    query = f"array_to_string(list_sort(list_filter(string_split(regexp_extract({rest}, '[?](.*)$', 1), '&'), lambda p: p <> '' AND NOT regexp_matches(p, '{warc_revisit.TRACKING}'))), '&')"
    return f"{host} || {path} || CASE WHEN {query} <> '' THEN '?' || {query} ELSE '' END"


def _revisits_sql() -> str:
    host = "regexp_extract(url, '^[a-z]+://([^/]+)', 1)"
    version = f"{host} || '-' || CAST(page_id // 200 AS VARCHAR)"
    permitted = ", ".join(f"'{h}'" for h in warc_revisit.PERMITTED_HEADERS)
    return f"""
WITH p AS (SELECT page_id, url, html FROM pages WHERE url IS NOT NULL),
records AS (
  SELECT page_id * 4 AS rec_id, 'response' AS rec_type, url, page_id * 100 AS ts, md5(html) AS etag, CAST(page_id AS VARCHAR) AS last_modified, sha256(html) AS digest,
    ['Content-Type: text/html', 'Date: ' || CAST(page_id * 100 AS VARCHAR), 'ETag: ' || md5(html), 'Server: origin'] AS headers FROM p
  UNION ALL SELECT page_id * 4 + 1, 'revisit', regexp_replace(url, '#.*$', '') || '#again', page_id * 100 + 1000 * (1 + page_id % 5),
    CASE WHEN page_id % 7 = 0 THEN 'other' WHEN page_id % 3 = 0 THEN NULL ELSE md5(html) END, CASE WHEN page_id % 6 = 0 THEN NULL ELSE CAST(page_id AS VARCHAR) END, CASE WHEN page_id % 12 = 0 THEN NULL ELSE sha256(html) END,
    ['date: ' || CAST(page_id * 100 + 1000 AS VARCHAR), 'Cache-Control: max-age=60', 'Content-Length: 0', 'Set-Cookie: a=b'] FROM p
  UNION ALL SELECT page_id * 4 + 2, 'revisit', upper(regexp_extract(url, '^([a-z]+://[^/]+)', 1)) || regexp_extract(url, '^[a-z]+://[^/]+(.*)$', 1), page_id * 100 - 50, md5(html), NULL, NULL, ['Date: ' || CAST(page_id AS VARCHAR)] FROM p WHERE page_id % 11 = 0
  UNION ALL SELECT page_id * 4 + 3, CASE WHEN page_id % 50 = 0 THEN 'response' ELSE 'revisit' END, 'http://' || {host} || ':80/robots.txt', page_id * 100 + 7, {version}, NULL, md5({version}), ['Date: ' || CAST(page_id * 100 AS VARCHAR), 'Vary: accept'] FROM p),
named AS (SELECT *, {_canonical_sql('url')} AS canonical FROM records),
joined AS (SELECT *, last_value(CASE WHEN rec_type = 'response' THEN {{'id': rec_id, 'etag': etag, 'last_modified': last_modified, 'digest': digest, 'headers': headers}} END IGNORE NULLS)
  OVER (PARTITION BY canonical ORDER BY ts, rec_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS base FROM named),
judged AS (SELECT *, CASE WHEN base IS NULL THEN 'orphan' WHEN etag IS NOT NULL THEN CASE WHEN etag IS NOT DISTINCT FROM base.etag THEN 'resolved' ELSE 'mismatch' END
  WHEN last_modified IS NOT NULL THEN CASE WHEN last_modified IS NOT DISTINCT FROM base.last_modified THEN 'resolved' ELSE 'mismatch' END
  WHEN digest IS NOT NULL THEN CASE WHEN digest IS NOT DISTINCT FROM base.digest THEN 'resolved' ELSE 'mismatch' END ELSE 'unchecked' END AS status,
  list_filter(headers, lambda h: lower(string_split(h, ': ')[1]) IN ({permitted})) AS renewed FROM joined WHERE rec_type = 'revisit')
SELECT rec_id, canonical, ts, status, base.id AS base_id, CASE WHEN status = 'resolved' THEN base.digest END AS digest,
  CASE WHEN status = 'resolved' THEN array_to_string(list_sort(list_concat(list_filter(base.headers, lambda h: NOT list_contains(list_transform(renewed, lambda r: lower(string_split(r, ': ')[1])), lower(string_split(h, ': ')[1]))), renewed)), '; ') END AS headers
FROM judged
"""


#: Words by ASCII white space, and by everything but ASCII letters, digits and bytes from 0x80 on; A-Z alone is lower-cased.
_BY_SPACE = "regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _runs(column: str, at: str, count: str) -> str:
    return f"array_to_string({column}[{at}:{at} + {count} - 1], ' ')"


def _repeats_sql(length: int = 35) -> str:
    return f"""
WITH w AS (SELECT doc_id, {_BY_SPACE} AS ws FROM documents),
starts AS (SELECT doc_id, p, {_runs("ws", "p", str(length))} AS words FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - {length - 2})) AS p FROM w)),
again AS (SELECT words FROM starts GROUP BY words HAVING count(*) > 1),
deep AS (SELECT doc_id, p FROM starts WHERE words IN (SELECT words FROM again)),
placed AS (SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS i FROM w),
judged AS (SELECT placed.*, coalesce(i - max(p) OVER (PARTITION BY placed.doc_id ORDER BY i) < {length}, false) AS gone FROM placed LEFT JOIN deep ON placed.doc_id = deep.doc_id AND i = p)
SELECT w.doc_id, len(ws) AS n_words, coalesce(n, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM w LEFT JOIN (SELECT doc_id, count(*) FILTER (gone) AS n, string_agg(word, ' ' ORDER BY i) FILTER (NOT gone) AS kept FROM judged GROUP BY doc_id) USING (doc_id)
"""


def _join_sql(k: int = 5, percent: int = 80) -> str:
    """Links from counts of common shingles, then the least document that each reaches."""
    return f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\\x20\\x09-\\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, {_runs("ws", "p", str(k))} AS shingle FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - {k - 2}, 2))) AS p FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
common AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
links AS (SELECT a, b FROM common JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= {percent} * (x.n + y.n - c)),
reach AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT reach.a, l.b FROM reach JOIN (SELECT a, b FROM links UNION ALL SELECT b, a FROM links) l ON reach.b = l.a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, r.least AS component_id
FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT a, min(b) AS least FROM reach GROUP BY a) r ON r.a = d.doc_id
"""


def _contamination_sql(window: int = 10) -> str:
    words = f"regexp_extract_all({_LOWER}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
    return f"""
WITH i AS (SELECT CAST(item_id AS VARCHAR) AS item, {words} AS ws FROM benchmark),
asked AS (SELECT item, p AS q, least(len(ws), {window}) AS n, {_runs("ws", "p", str(window))} AS words FROM (SELECT item, ws, unnest(range(1, greatest(len(ws) - {window - 2}, 2))) AS p FROM i WHERE len(ws) > 0)),
w AS (SELECT doc_id, {words} AS ws FROM documents),
sizes AS (SELECT DISTINCT n FROM asked),
starts AS (SELECT doc_id, p, n, {_runs("ws", "p", "n")} AS words FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS p FROM w, sizes)),
hits AS (SELECT doc_id, p, starts.n, item, q FROM starts JOIN asked ON starts.words = asked.words AND starts.n = asked.n),
matches AS (SELECT doc_id, max(size) AS longest FROM (SELECT doc_id, count(*) + n - 1 AS size FROM (SELECT doc_id, n, item, p - q AS off, p - row_number() OVER (PARTITION BY doc_id, n, item, p - q ORDER BY p) AS run FROM (SELECT DISTINCT * FROM hits)) GROUP BY doc_id, n, item, off, run) GROUP BY doc_id),
words AS (SELECT doc_id, count(DISTINCT x) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS x FROM hits) GROUP BY doc_id),
items AS (SELECT doc_id, count(DISTINCT item) AS n_items, array_to_string(list_sort(list(DISTINCT item)), ',') AS told FROM hits GROUP BY doc_id)
SELECT doc_id, len(ws) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(told, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated, coalesce(longest, 0) AS longest
FROM w LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id) LEFT JOIN matches USING (doc_id)
"""


ORACLE_SQL: dict[str, str] = {
    "op2_revisit_resolution": _revisits_sql(), "op5_suffix_tree_dedup": _repeats_sql(), "op6_secret_ownership": _secrets_sql(),
    "op8_ngram_jaccard_join": _join_sql(), "op9_suffix_array_decontamination": _contamination_sql(),
}
