"""One query for each operator of this subpackage, over its whole table, and SQL where SQL can say it."""

from __future__ import annotations

import re
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession

from . import audio, bpe, exact_dedup, html_main, langid, licenses, mixing, probminhash, quality, quotes
from .common import read_table

#: The vocabulary file; a parameter of the operator.
BPE_FILE = "byte_bpe_50k.json"


def bpe_path(name: str = BPE_FILE) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = exact_dedup.exact_duplicates(read_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


OP1_SQL = r"""
WITH t AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents
), g AS (
  SELECT body, min(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY body
)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, sha256(t.body) AS text_sha256
FROM t JOIN g ON t.body = g.body
"""


def op8_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read_table(spark, sf_dir, "documents")).drop("copies")


#: The rows of a mix, from a table ``docs(doc_id, source, words, tag)``.
MIX_CTES = r"""
 keyed AS (
  SELECT *, CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS src,
         (words >> greatest(length(bin(words)) - 4, 0)) << greatest(length(bin(words)) - 4, 0) AS cls
  FROM docs
), per AS (
  SELECT src, CAST(sum(words) AS BIGINT) AS source_size FROM keyed GROUP BY src
), weighed AS (
  SELECT src, source_size, CAST(source_size * 3 AS DOUBLE) AS cap,
         CASE (row_number() OVER (ORDER BY src) - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS w
  FROM per
), shares AS (
  SELECT *, (CAST(sum(source_size) OVER () AS DOUBLE)
             - coalesce(sum(cap) OVER (ORDER BY cap / w, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
          / (sum(w) OVER () - coalesce(sum(w) OVER (ORDER BY cap / w, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) AS share
  FROM weighed
), goals AS (
  SELECT src, source_size,
         CASE WHEN cap / w <= share THEN cap ELSE max(CASE WHEN cap / w > share THEN share END) OVER () * w END AS target,
         CAST(('0x' || substr(md5('mix-1:' || src), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE AS shift
  FROM shares
), cells AS (
  SELECT src, cls, CAST(ceil(sqrt(count(*))) AS BIGINT) AS fan FROM keyed GROUP BY src, cls
), ranked AS (
  SELECT k.*, g.source_size, g.target, g.shift,
         CASE WHEN g.source_size > 0 THEN g.target / g.source_size ELSE 0.0 END AS rate,
         row_number() OVER (PARTITION BY k.src ORDER BY k.cls, tag % fan, words, doc_id NULLS LAST, tag) AS place
  FROM keyed k JOIN cells c ON k.src = c.src AND k.cls = c.cls JOIN goals g ON k.src = g.src
), mixed AS (
  SELECT *, CAST(floor(shift + rate * place) - floor(shift + rate * (place - 1)) AS BIGINT) AS copies FROM ranked
)
"""

OP8_SQL = (
    r"""
WITH docs AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS words,
         CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '') || ':' || coalesce(text, '')), 1, 8) AS BIGINT) AS tag
  FROM documents
),"""
    + MIX_CTES
    + "SELECT doc_id, words AS size, source_size, target, CAST(words * copies AS BIGINT) AS taken FROM mixed"
)


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return probminhash.near_duplicates(read_table(spark, sf_dir, "documents")).select("doc_id", "class_id", "class_size", "kept", "n_links")


@lru_cache
def _page_model():
    return html_main.train()


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_main.extract(read_table(spark, sf_dir, "pages"), _page_model())


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return langid.predict(docs, langid.fit(docs))


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode(read_table(spark, sf_dir, "documents"), bpe_path(), with_ids=False)


def op5_audio_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audio.audio_features(read_table(spark, sf_dir, "documents"), keep_tensors=False)


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(read_table(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return quality.predict(docs, quality.fit(docs, read_table(spark, sf_dir, "labels")))


def op9_chat_quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotes.link_quotes(read_table(spark, sf_dir, "conversations"))


def _templates_sql() -> str:
    rows = ((name, licenses.bigrams(licenses.normal_words(text))) for name, text in licenses.TEMPLATES)
    return ", ".join("('" + name + "', [" + ", ".join(f"'{g}'" for g in grams) + "])" for name, grams in rows)


OP6_SQL = (
    r"""
WITH t(name, grams) AS (VALUES """
    + _templates_sql()
    + r"""), norm AS (
  SELECT doc_id, row_number() OVER () AS rid,
         regexp_replace(regexp_replace(regexp_replace(lower(coalesce(text, '')), '[^\p{L}\p{N}
]+', ' ', 'g'), ' *
 *', chr(10), 'g'), '^[ 
]+|[ 
]+$', '', 'g') AS body
  FROM documents
), parts AS (
  SELECT rid, unnest(list_concat(list_concat(string_split_regex(body, '
+'),
         list_transform(string_split_regex(body, '

+'), lambda p: replace(p, chr(10), ' '))), [regexp_replace(body, '
+', ' ', 'g')])) AS p
  FROM norm
), words AS (
  SELECT rid, p, string_split(p, ' ') AS w FROM (SELECT DISTINCT rid, p FROM parts)
), grams AS (
  SELECT rid, p, list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM words WHERE len(w) > 1
), dice AS (
  SELECT rid, p, t.name, 2.0::DOUBLE * len(list_intersect(g, t.grams)) / (len(g) + len(t.grams)) AS dice
  FROM grams JOIN t ON len(t.grams) >= len(g) * (0.8::DOUBLE / 1.2::DOUBLE) - 1e-9 AND len(t.grams) <= len(g) * (1.2::DOUBLE / 0.8::DOUBLE) + 1e-9
), best AS (
  SELECT rid, count(DISTINCT p) AS n_hits, string_agg(DISTINCT name, ',' ORDER BY name) AS licences, min(struct_pack(m := -dice, n := name)) AS top
  FROM dice WHERE dice >= 0.8 GROUP BY rid
)
SELECT norm.doc_id, coalesce(n_hits, 0) AS n_hits, coalesce(licences, '') AS licences, top.n AS best_licence, -top.m AS best_dice
FROM norm LEFT JOIN best ON norm.rid = best.rid
"""
)

def _place_sql(turn: str) -> str:
    return f"(CASE WHEN {turn} >= 0 THEN lpad(CAST({turn} AS VARCHAR), 19, '0') ELSE '-' || lpad(CAST(CAST({turn} AS HUGEINT) + 9223372036854775808 AS VARCHAR), 19, '0') END)"


_OP9 = r"""
WITH RECURSIVE m AS (
  SELECT conv_id AS conv, turn, role, coalesce(text, '') AS text, regexp_matches(coalesce(text, ''), '(?m)^[ 	]*>') AS has FROM conversations
), q AS (
  SELECT DISTINCT conv, turn, text FROM m WHERE has
), l AS (
  SELECT conv, turn, text, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM q
), k AS (
  SELECT *, length(regexp_replace(regexp_extract(line, '^[ 	]*((?:>[ 	]?)+)', 1), '[^>]', '', 'g')) AS level,
         trim(regexp_replace(line, '^[ 	]*((?:>[ 	]?)+)', '')) AS said FROM l
), n AS (
  SELECT *, lead(level, 1, 0) OVER w AS next, lag(level, 1, -1) OVER w AS before FROM k WINDOW w AS (PARTITION BY conv, turn, text ORDER BY pos)
), r AS (
  SELECT *, sum(CASE WHEN level <> before THEN 1 ELSE 0 END) OVER (PARTITION BY conv, turn, text ORDER BY pos) AS run FROM n
), runs AS (
  SELECT conv, turn, text, run, level, string_agg(said, ' ' ORDER BY pos) AS said, string_agg(line, chr(10) ORDER BY pos) AS lines
  FROM r WHERE NOT (level = 0 AND next > 0 AND regexp_matches(line, '(?i)wrote:[ 	]*$')) GROUP BY ALL
), own AS (
  SELECT conv, turn, text, regexp_replace(coalesce(string_agg(CASE WHEN level = 0 THEN lines END, chr(10) ORDER BY run), ''), '^\s+|\s+$', '', 'g') AS own,
         count(*) FILTER (WHERE level > 0) AS n_quotes, max(level) AS max_level
  FROM runs GROUP BY conv, turn, text
), passages AS (
  SELECT conv, turn, text, level, trim(regexp_replace(lower(said), '[^\p{L}\p{N}]+', ' ', 'g')) AS unit FROM runs WHERE level > 0 AND conv IS NOT NULL AND turn IS NOT NULL
), said AS (
  SELECT conv, turn, text AS own FROM m WHERE NOT has AND conv IN (SELECT conv FROM passages)
  UNION ALL SELECT conv, turn, own FROM own
), units AS (
  SELECT conv, min(turn) AS from_turn, trim(regexp_replace(lower(part), '[^\p{L}\p{N}]+', ' ', 'g')) AS unit
  FROM (SELECT conv, turn, unnest(list_concat(list_concat([own], string_split_regex(own, '
[ 	]*
')), string_split(own, chr(10)))) AS part FROM said)
  WHERE conv IS NOT NULL AND turn IS NOT NULL GROUP BY ALL
), links AS (
  SELECT p.conv, p.turn, p.text, count(*) AS n_linked, max(CASE WHEN level = 1 THEN struct_pack(n := length(p.unit), f := from_turn) END) AS top
  FROM passages p JOIN units u ON p.conv = u.conv AND p.unit = u.unit AND u.from_turn < p.turn WHERE p.unit <> '' GROUP BY p.conv, p.turn, p.text
), up AS (
  SELECT conv, turn, min(top.f) AS up FROM links WHERE top IS NOT NULL GROUP BY conv, turn
), walk AS (
  SELECT conv, turn, up AS top_turn, place(up) || '/' || place(turn) AS path FROM up
  UNION ALL
  SELECT walk.conv, walk.turn, up.up, place(up.up) || '/' || walk.path FROM walk JOIN up ON walk.conv = up.conv AND walk.top_turn = up.turn
), ends AS (
  SELECT conv, turn, min(top_turn) AS root, max_by(path, length(path)) AS path FROM walk GROUP BY conv, turn
)
SELECT m.conv AS conv_id, m.turn, m.role, CASE WHEN has THEN own.own ELSE m.text END AS own_text,
       coalesce(n_quotes, 0) AS n_quotes, coalesce(n_linked, 0) AS n_linked, coalesce(max_level, 0) AS max_level, top.f AS parent_turn,
       CASE WHEN m.conv IS NOT NULL THEN coalesce(root, m.turn) END AS root_turn,
       CASE WHEN m.conv IS NOT NULL THEN coalesce(ends.path, place(m.turn)) END AS reply_path
FROM m LEFT JOIN own ON m.conv IS NOT DISTINCT FROM own.conv AND m.turn IS NOT DISTINCT FROM own.turn AND m.text = own.text
LEFT JOIN links ON m.conv = links.conv AND m.turn = links.turn AND m.text = links.text
LEFT JOIN ends ON m.has AND m.conv = ends.conv AND m.turn = ends.turn
"""
OP9_SQL = re.sub(r"place\(([a-z.]+)\)", lambda m: _place_sql(m[1]), _OP9)

QUERIES = {
    "op1_exact_dedup": op1_exact_dedup,
    "op2_html_extraction": op2_html_extraction,
    "op3_language_id": op3_language_id,
    "op4_bpe": op4_bpe,
    "op5_audio_features": op5_audio_features,
    "op6_license_scan": op6_license_scan,
    "op7_quality": op7_quality,
    "op8_mix_sources": op8_mix_sources,
    "op9_chat_quotes": op9_chat_quotes,
    "op10_near_duplicates": op10_near_duplicates,
}

SQL = {"op1_exact_dedup": OP1_SQL, "op6_license_scan": OP6_SQL, "op8_mix_sources": OP8_SQL, "op9_chat_quotes": OP9_SQL}
