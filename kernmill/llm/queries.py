"""Registered queries of the training-data operators and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, decontaminate, html_text, near_dedup, neighbours, quality, secret_scan, sequence_packing, token_binary, toxicity


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; null ids fall in no fold."""
    return F.crc32(doc_id.cast("string").cast("binary")) % parts


def _scored(rows: DataFrame, held: Column, least: float) -> DataFrame:
    return rows.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))


def op1_near_duplicates(spark, sf_dir):
    return near_dedup.near_duplicates(_read(spark, sf_dir, "documents"), shingle_words=3, percent=85)


def op2_nearest_neighbours(spark, sf_dir):
    vectors = _read(spark, sf_dir, "embeddings")
    return neighbours.nearest(vectors, vectors.where("vec_id % 100 = 0"), 10)


def op3_main_text(spark, sf_dir):
    return html_text.extract(_read(spark, sf_dir, "pages"))


def op4_toxicity(spark, sf_dir):
    docs, labels = _read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels")
    model = toxicity.fit(docs, labels, lambda i: fold(i, 3) != 1)
    return _scored(toxicity.score(docs, model), fold(F.col("doc_id"), 3) == 1, 0.7)


def op5_decontamination(spark, sf_dir):
    return decontaminate.contamination(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark"))


def op6_chat_format(spark, sf_dir):
    return chat.format_chats(_read(spark, sf_dir, "conversations"))


def op7_token_matrices(spark, sf_dir):
    return token_binary.pack_matrices(_read(spark, sf_dir, "documents"))


def op8_secret_scan(spark, sf_dir):
    return secret_scan.report(_read(spark, sf_dir, "documents"))


def op9_quality(spark, sf_dir):
    docs, labels = _read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels")
    net = quality.fit(docs, labels, lambda i: fold(i, 5) != 0)
    return _scored(quality.score(docs, net), fold(F.col("doc_id"), 5) == 0, 0.3)


def op10_pack_sequences(spark, sf_dir):
    return sequence_packing.pack(_read(spark, sf_dir, "documents"), with_ids=False)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_near_duplicates, op2_nearest_neighbours, op3_main_text, op4_toxicity, op5_decontamination, op6_chat_format, op7_token_matrices, op8_secret_scan, op9_quality, op10_pack_sequences)
}

_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_DOC_WORDS = "list_filter(string_split_regex(" + _LOWER.format("coalesce(text, '')") + r", '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda w: w <> '')"

_OP1 = rf"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex({_LOWER.format("coalesce(text, '')")}, '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents WHERE doc_id IS NOT NULL),
sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' '))) END AS s FROM words),
names AS (SELECT s, min(doc_id) AS rep FROM sets WHERE len(s) > 0 GROUP BY s),
tokens AS (SELECT rep, len(s) AS n, unnest(s) AS g FROM names),
rare AS (SELECT t.rep, t.n, t.g FROM tokens t JOIN (SELECT g FROM tokens GROUP BY g HAVING count(*) > 1) USING (g)),
pairs AS (
  SELECT a.rep AS x, b.rep AS y, any_value(a.n) AS n, any_value(b.n) AS m, count(*) AS c
  FROM rare a JOIN rare b ON a.g = b.g AND a.rep < b.rep GROUP BY a.rep, b.rep),
links AS (SELECT x, y FROM pairs WHERE 100 * c >= 85 * (n + m - c)),
edges AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
reach(x, y) AS (SELECT rep, rep FROM names UNION SELECT r.x, e.y FROM reach r JOIN edges e ON r.y = e.x),
comp AS (SELECT x, min(y) AS c FROM reach GROUP BY x)
SELECT d.doc_id, CAST(len(d.s) AS BIGINT) AS n_shingles, coalesce(c.c, d.doc_id) AS component_id, d.doc_id = coalesce(c.c, d.doc_id) AS kept
FROM sets d LEFT JOIN names n ON d.s = n.s LEFT JOIN comp c ON c.x = n.rep
"""

_OP2 = """
WITH v AS (
  SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
d AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, sqrt(list_reduce(list_transform(list_zip(q.e, c.e), lambda z: (z[1] - z[2]) * (z[1] - z[2])), lambda a, b: a + b)) AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 100 = 0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS INTEGER) AS rank, vec_id, score FROM d)
SELECT * FROM r WHERE rank <= 10
"""

_OP5 = f"""
WITH docs AS (SELECT doc_id, {_DOC_WORDS} AS w FROM documents),
items AS (SELECT CAST(item_id AS VARCHAR) AS item_id, {_DOC_WORDS} AS w FROM benchmark),
wins AS (
  SELECT DISTINCT item_id, 10 AS k, array_to_string(w[i:i + 9], ' ') AS run FROM (SELECT item_id, w, unnest(range(1, len(w) - 8)) AS i FROM items WHERE len(w) >= 10)
  UNION SELECT item_id, len(w), array_to_string(w, ' ') FROM items WHERE len(w) BETWEEN 1 AND 9),
lens AS (SELECT DISTINCT k FROM wins),
places AS (
  SELECT doc_id, k, i, array_to_string(w[i:i + k - 1], ' ') AS run
  FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM docs, lens WHERE len(w) >= k)),
found AS (SELECT a.doc_id, a.i, a.k, wins.item_id FROM places a JOIN wins ON a.k = wins.k AND a.run = wins.run),
hit AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM found) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n, sha256(string_agg(item_id, ',' ORDER BY item_id COLLATE "C")) AS h FROM (SELECT DISTINCT doc_id, item_id FROM found) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(hit.n, 0) AS BIGINT) AS n_hit, CAST(coalesce(its.n, 0) AS BIGINT) AS n_items,
  coalesce(its.h, sha256('')) AS items_sha256, coalesce(hit.n, 0) > 0 AS contaminated
FROM docs d LEFT JOIN hit USING (doc_id) LEFT JOIN its USING (doc_id)
""".replace(' COLLATE "C"', "")

_OP6 = f"""
WITH t AS (SELECT DISTINCT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations WHERE conv_id IS NOT NULL),
steps AS (
  SELECT conv_id, row_number() OVER w AS n, count(*) OVER (PARTITION BY conv_id) AS total,
    string_agg(length(role)::VARCHAR || chr(31) || length(text)::VARCHAR || chr(31) || role || text, chr(31)) OVER w AS prefix,
    string_agg('{chat.OPEN}' || role || chr(10) || text || '<|im_end|>' || chr(10), '') OVER w AS body
  FROM t WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)),
whole AS (SELECT * FROM steps WHERE n = total),
first AS (SELECT prefix, min(conv_id) AS conv_id FROM whole GROUP BY prefix)
SELECT w.conv_id, CAST(w.total AS BIGINT) AS n_turns, w.body AS text FROM whole w JOIN first f ON f.conv_id = w.conv_id
WHERE w.prefix NOT IN (SELECT prefix FROM steps WHERE n < total)
"""


def _duck_spans(pattern: str, kind: int, group: int, least: int) -> str:
    quoted = pattern.replace("'", "''")
    return f"""
  SELECT doc_id, {kind} AS kind, begin, begin + length(m[i]) AS stop, v[i] AS value FROM (
    SELECT doc_id, m, v, i, list_sum(list_transform(p[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:i - 1], lambda x: length(x))), 0) AS begin FROM (
      SELECT doc_id, m, v, p, unnest(range(1, len(m) + 1)) AS i FROM (
        SELECT doc_id, regexp_extract_all(text, '{quoted}') AS m, regexp_extract_all(text, '{quoted}', {group}) AS v, string_split_regex(text, '{quoted}') AS p FROM docs)))
  WHERE length(v[i]) >= {least}"""


_OP8 = f"""
WITH docs AS (SELECT doc_id, coalesce(text, '') AS text, coalesce(source, '') AS source FROM documents),
base AS ({_duck_spans(secret_scan.ASSIGN, 0, 2, 6)} UNION ALL {_duck_spans(secret_scan.ACCESS, 1, 0, 20)} UNION ALL {_duck_spans(secret_scan.HEX, 2, 0, 24)}),
opaque AS ({_duck_spans(secret_scan.OPAQUE, 3, 0, 32)}),
apart AS (
  SELECT * FROM opaque o WHERE regexp_matches(value, '[0-9]') AND regexp_matches(value, '[A-Za-z]')
    AND NOT EXISTS (SELECT 1 FROM base b WHERE b.doc_id = o.doc_id AND b.begin < o.stop AND o.begin < b.stop)),
found AS (SELECT * FROM base UNION ALL SELECT * FROM apart),
held AS (SELECT value, count(DISTINCT source) AS owners FROM found JOIN docs USING (doc_id) GROUP BY value),
judged AS (SELECT f.*, owners <= {secret_scan.LIVE_OWNERS} AS live, ['assign', 'access', 'hex', 'opaque'][kind + 1] || ':' || begin::VARCHAR || ':' || stop::VARCHAR AS name FROM found f JOIN held USING (value)),
per AS (
  SELECT doc_id, count(*) FILTER (kind = 0) AS a, count(*) FILTER (kind = 1) AS c, count(*) FILTER (kind = 2) AS h,
    string_agg(name, ',' ORDER BY begin, kind) FILTER (kind < 3) AS base, string_agg(name, ',' ORDER BY begin, kind) AS every,
    count(*) FILTER (live) AS n_live, count(*) FILTER (NOT live) AS n_copied
  FROM judged WHERE kind < 3 OR live GROUP BY doc_id)
SELECT d.doc_id, CAST(coalesce(a, 0) AS BIGINT) AS n_assign, CAST(coalesce(c, 0) AS BIGINT) AS n_access, CAST(coalesce(h, 0) AS BIGINT) AS n_hex, sha256(coalesce(base, '')) AS base_sha256,
  coalesce(every, '') AS spans, CAST(coalesce(n_live, 0) AS BIGINT) AS n_live, CAST(coalesce(n_copied, 0) AS BIGINT) AS n_copied
FROM docs d LEFT JOIN per p ON p.doc_id = d.doc_id
"""

ORACLES: dict[str, str] = {"op1_near_duplicates": _OP1, "op2_nearest_neighbours": _OP2, "op5_decontamination": _OP5, "op6_chat_format": _OP6, "op8_secret_scan": _OP8}
