"""The text operators as queries over whole tables, and DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mfaccel.llm import bpe, decontaminate, digest, license_scan, lm_tables, nbsvm, quotes, sharding, simhash, toxicity
from mfaccel.llm.common import fresh_path, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.digest(decontaminate.flag(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sixteen arrivals of different sizes, compacted; each document as the store gives it back."""
    docs = table(spark, sf_dir, "documents")
    store = sharding.ShardStore(spark, fresh_path(spark, "shards"), docs.schema)
    spot = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(64))
    arrival = F.when(spot < 32, spot % 4).when(spot < 56, 4 + spot % 6).otherwise(10 + spot % 6)
    store.append_each(docs, F.format_string("%02d", arrival))
    store.compact()
    store.vacuum()
    return store.read().select("doc_id", "lang", "source", F.length("text").cast("long").alias("n_chars"), F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))


def op3_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target: the documents that are labelled as good."""
    good = table(spark, sf_dir, "labels").groupBy("doc_id").agg((F.min("quality") == 1).alias("target"))
    return lm_tables.score(table(spark, sf_dir, "documents"), good)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return nbsvm.score(docs, nbsvm.fit(docs, table(spark, sf_dir, "labels")))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


def op6_quotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reply-ordered threads; reply_conv and reply_turn are -1 where a message replies to none."""
    return quotes.reply_ordered(quotes.linked(table(spark, sf_dir, "conversations"))).fillna(-1, ["reply_conv", "reply_turn"])


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op9_license(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(table(spark, sf_dir, "documents"))


def tokenizer_file() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(table(spark, sf_dir, "documents"), *tokenizer_file())


def op10_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest.against_next(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Query]:
    found = (
        op1_decontamination, op2_sharding, op3_lm_score, op4_quality, op5_simhash,
        op6_quotation, op7_toxicity, op8_bpe, op9_license, op10_digest,
    )
    return {f.__name__: f for f in found}


_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP1_SQL = f"""
WITH item_words AS (SELECT item_id, {_WORDS} AS w FROM benchmark),
item_windows AS (
  SELECT DISTINCT item_id, len(g) AS n, g AS g
  FROM (SELECT item_id, w[i : i + least(10, len(w)) - 1] AS g
        FROM (SELECT item_id, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS i FROM item_words WHERE len(w) > 0))),
sizes AS (SELECT DISTINCT n FROM item_windows),
doc_words AS (SELECT doc_id, {_WORDS} AS w FROM documents),
doc_windows AS (
  SELECT doc_id, n, i, w[i : i + n - 1] AS g
  FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM doc_words, sizes WHERE len(w) >= n)),
found AS (SELECT d.doc_id, d.n, d.i, b.item_id FROM doc_windows d JOIN item_windows b ON d.n = b.n AND d.g = b.g),
hit AS (SELECT doc_id, count(DISTINCT k) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS k FROM (SELECT DISTINCT doc_id, n, i FROM found)) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS names
          FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM found) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit,
       CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(names, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AS contaminated
FROM doc_words LEFT JOIN hit USING (doc_id) LEFT JOIN items USING (doc_id)
"""


OP2_SQL = "SELECT doc_id, lang, source, CAST(length(text) AS BIGINT) AS n_chars, sha256(text) AS text_sha256 FROM documents"


_MARKS = r"^((?:[ \t]?>)+)"


def _units_sql(source: str, text: str, keep: str) -> str:
    """Keys and sizes of the whole of a text, its paragraphs and its lines."""
    parts = rf"list_concat([{text}], string_split_regex({text}, '\n[ \t]*\n'), string_split({text}, chr(10)))"
    plain = r"trim(regexp_replace(lower(unit), '\s+', ' ', 'g'))"
    return f"SELECT {keep}, sha256({plain}) AS key, length(unit) AS size FROM (SELECT {keep}, unnest({parts}) AS unit FROM {source}) WHERE {plain} <> ''"


OP6_SQL = rf"""
WITH RECURSIVE whole AS (
  SELECT conv_id AS conv, turn, arg_min(role, (coalesce(text, ''), role)) AS role, min(coalesce(text, '')) AS text
  FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL GROUP BY conv_id, turn
  UNION ALL SELECT conv_id, turn, role, coalesce(text, '') FROM conversations WHERE conv_id IS NULL OR turn IS NULL),
m AS MATERIALIZED (SELECT row_number() OVER () AS no, * FROM whole),
cut AS (SELECT no, string_split_regex(text, '\r?\n') AS parts FROM m WHERE contains(text, '>')),
lines AS MATERIALIZED (
  SELECT no, i, length(regexp_replace(regexp_extract(line, '{_MARKS}', 1), '[^>]', '', 'g')) AS level, regexp_replace(line, '{_MARKS}[ \t]?', '') AS body
  FROM (SELECT no, unnest(parts) AS line, unnest(range(0, len(parts))) AS i FROM cut)),
near_lines AS (SELECT *, lag(level) OVER w AS before, lead(level) OVER w AS after FROM lines WINDOW w AS (PARTITION BY no ORDER BY i)),
own AS (
  SELECT no, trim(string_agg(body, chr(10) ORDER BY i)) AS own FROM near_lines
  WHERE level = 0 AND NOT (coalesce(after, 0) > 0 AND regexp_matches(body, '(?i)^\s*(on .*wrote|.*(?:schrieb|écrit|escribió))\s*:\s*$')) GROUP BY no),
runs AS (SELECT *, sum(CASE WHEN before = level THEN 0 ELSE 1 END) OVER (PARTITION BY no ORDER BY i) AS run FROM near_lines),
passages AS MATERIALIZED (SELECT no, level, min(i) AS spot, string_agg(body, chr(10) ORDER BY i) AS text FROM runs WHERE level > 0 GROUP BY no, level, run),
parsed AS MATERIALIZED (
  SELECT no, conv, turn, role, CASE WHEN contains(text, '>') THEN coalesce(own, '') ELSE text END AS own,
    coalesce((SELECT max(level) FROM lines l WHERE l.no = m.no), 0) AS max_level, (SELECT count(*) FROM passages p WHERE p.no = m.no) AS n_quotes
  FROM m LEFT JOIN own USING (no)),
named AS (SELECT * FROM parsed WHERE conv IS NOT NULL AND turn IS NOT NULL),
quotes AS MATERIALIZED (SELECT n.conv, n.turn, q.* FROM ({_units_sql('passages', 'text', 'no, level, spot')}) q JOIN named n USING (no)),
originals AS (SELECT * FROM ({_units_sql('named', 'own', 'conv, turn')}) WHERE key IN (SELECT key FROM quotes)),
near AS (SELECT key, conv, min(turn) AS near_turn FROM originals GROUP BY key, conv),
ranked AS (SELECT *, row_number() OVER (PARTITION BY key ORDER BY conv) AS rk FROM near),
far AS (SELECT key, conv AS far_conv, near_turn AS far_turn FROM ranked WHERE rk = 1),
further AS (SELECT key, conv AS next_conv, near_turn AS next_turn FROM ranked WHERE rk = 2),
found AS (
  SELECT q.*, CASE WHEN near_turn < q.turn THEN (q.conv, near_turn) WHEN far_conv <> q.conv THEN (far_conv, far_turn) WHEN next_conv IS NOT NULL THEN (next_conv, next_turn) END AS dest
  FROM quotes q LEFT JOIN near n ON q.key = n.key AND q.conv = n.conv LEFT JOIN far f ON q.key = f.key LEFT JOIN further s ON q.key = s.key),
links AS MATERIALIZED (
  SELECT conv, turn, dest[1] AS to_conv, dest[2] AS to_turn, n_linked FROM (
    SELECT conv, turn, arg_min(dest, (-size, level, spot, dest)) AS dest, count(DISTINCT (level, spot)) AS n_linked
    FROM found WHERE dest IS NOT NULL GROUP BY conv, turn)),
walk AS (
  SELECT conv, turn, to_conv AS tc, to_turn AS tt, 1 AS d FROM links
  UNION ALL SELECT w.conv, w.turn, l.to_conv, l.to_turn, d + 1 FROM walk w JOIN links l ON l.conv = w.tc AND l.turn = w.tt WHERE d < 2000),
tops AS (SELECT conv, turn, max(d) AS d, arg_max((tc, tt), d) AS top, least(min((tc, tt)), (conv, turn)) AS low FROM walk GROUP BY conv, turn)
SELECT *, row_number() OVER (ORDER BY root_conv NULLS FIRST, root_turn NULLS FIRST, depth NULLS LAST, conv_id NULLS FIRST, turn NULLS FIRST, role NULLS FIRST, text) AS place FROM (
SELECT p.conv AS conv_id, p.turn, role, own AS text, CAST(max_level AS INTEGER) AS max_level, CAST(n_quotes AS INTEGER) AS n_quotes,
  CAST(coalesce(n_linked, 0) AS BIGINT) AS n_linked, coalesce(to_conv, -1) AS reply_conv, coalesce(to_turn, -1) AS reply_turn,
  CASE WHEN d IS NULL THEN p.conv WHEN d < 2000 THEN top[1] ELSE low[1] END AS root_conv,
  CASE WHEN d IS NULL THEN p.turn WHEN d < 2000 THEN top[2] ELSE low[2] END AS root_turn,
  CAST(CASE WHEN d IS NULL THEN 0 WHEN d < 2000 THEN d END AS BIGINT) AS depth
FROM parsed p LEFT JOIN links l ON p.conv = l.conv AND p.turn = l.turn LEFT JOIN tops t ON p.conv = t.conv AND p.turn = t.turn)
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_decontamination": OP1_SQL, "op2_sharding": OP2_SQL, "op6_quotation": OP6_SQL}
