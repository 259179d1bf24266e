"""Queries of this subpackage: name -> (spark, sf_dir) -> DataFrame, and the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.packing import pack_documents

    return pack_documents(documents(spark, sf_dir), tokenizer_path(), keep_ids=False).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op1_weak_supervision_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.pii import KINDS, SECRET, find, joined

    of = lambda kind, column: F.size(F.filter(column, lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    found = find(documents(spark, sf_dir))
    return found.select(
        "doc_id", *[of(k, "base") for k in KINDS[:SECRET]], F.sha2(joined("base"), 256).alias("base_sha256"), joined("spans").alias("spans"),
        of(KINDS[SECRET], "spans"), F.size("spans").cast("long").alias("n_spans"), (F.size("spans") > 0).alias("found"),
    )


def op2_line_crf_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.line_quality import rate

    return rate(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op3_simhash_anchor_covering(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.simhash import near_duplicates

    return near_duplicates(documents(spark, sf_dir)).select("doc_id", F.lpad(F.lower(F.hex("fingerprint")), 16, "0").alias("fingerprint"), "component_id")


def op8_positional_index_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.decontaminate import decontaminate, items_digest, n_hit

    found = decontaminate(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return found.select(
        "doc_id", "n_words", n_hit("hits").alias("n_hit"), F.size("items").cast("long").alias("n_items"), items_digest("items").alias("items_sha256"), (F.size("items") > 0).alias("contaminated"),
        F.size("near_items").cast("long").alias("n_near_items"),
    )


def op9_sampled_splitters(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.sharding import shard

    placed = shard(documents(spark, sf_dir))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_word_crf_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.language import identify

    return identify(documents(spark, sf_dir))


def op5_quotation_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.quotations import order_replies

    return order_replies(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


def op6_subword_embedding_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.quality_model import classify

    return classify(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op10_deletion_neighbourhood_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusdedup.llm.line_dedup import dedup_lines

    found = dedup_lines(documents(spark, sf_dir))
    return found.select("doc_id", F.size("dropped_lines").cast("long").alias("n_dropped"), F.array_join(F.transform("dropped_lines", lambda x: x.cast("string")), ",").alias("dropped_lines"), F.sha2("text", 256).alias("text_sha256"))


OP10_SQL = """
WITH raw AS (
  SELECT doc_id, i AS line_no, string_split(text, chr(10))[i + 1] AS line
  FROM documents, unnest(range(len(string_split(text, chr(10))))) AS t(i)
), lines AS (
  SELECT doc_id, line_no, line, lower(trim(regexp_replace(line, '[ \t\r\f\v]+', ' ', 'g'))) AS norm FROM raw
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY norm ORDER BY doc_id, line_no) AS k FROM lines WHERE norm <> ''
), firsts AS (
  SELECT norm, {'d': doc_id, 'l': line_no} AS ord, string_split(norm, ' ') AS w FROM ranked WHERE k = 1 AND len(string_split(norm, ' ')) >= 5
), lacking AS (
  SELECT norm, ord, i, md5(array_to_string(w[1:i] || w[i + 2:], ' ')) AS rest FROM firsts, unnest(range(len(w))) AS t(i)
), near AS (
  SELECT norm FROM (SELECT norm, ord, min(ord) OVER (PARTITION BY rest, i) AS head FROM lacking) WHERE ord > head
  UNION SELECT a.norm FROM lacking a JOIN firsts b ON a.rest = md5(b.norm) WHERE b.ord < a.ord
  UNION SELECT b.norm FROM lacking a JOIN firsts b ON a.rest = md5(b.norm) WHERE a.ord < b.ord
), dropped AS (
  SELECT doc_id, line_no FROM ranked WHERE k > 1 OR norm IN (SELECT norm FROM near)
), per_doc AS (
  SELECT doc_id, count(*) AS n, string_agg(CAST(line_no AS VARCHAR), ',' ORDER BY line_no) AS nos FROM dropped GROUP BY doc_id
), kept AS (
  SELECT doc_id, string_agg(line, chr(10) ORDER BY line_no) AS text FROM lines l
  WHERE NOT EXISTS (SELECT 1 FROM dropped x WHERE x.doc_id = l.doc_id AND x.line_no = l.line_no) GROUP BY doc_id
)
SELECT d.doc_id, CAST(coalesce(p.n, 0) AS BIGINT) AS n_dropped, coalesce(p.nos, '') AS dropped_lines, CASE WHEN d.text IS NULL THEN NULL ELSE sha256(coalesce(k.text, '')) END AS text_sha256
FROM documents d LEFT JOIN per_doc p USING (doc_id) LEFT JOIN kept k USING (doc_id)
"""


def _units_sql(rows: str, body: str, least: int) -> str:
    """Rows with each passage's whole, paragraphs and lines as hash and number of characters."""
    plain = lambda x: f"trim(regexp_replace(lower({x}), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'))"
    kept = lambda x: f"CASE WHEN {plain(x)} <> '' THEN {plain(x)} ELSE trim(regexp_replace(lower({x}), '\\s+', ' ', 'g')) END"
    parts = f"unnest([{body}] || string_split_regex({body}, '\\n[ \\t]*\\n') || string_split({body}, chr(10)))"
    return f"SELECT * FROM (SELECT *, md5({kept('x')}) AS hash, length({kept('x')}) AS chars FROM (SELECT *, {parts} AS x FROM ({rows}))) WHERE chars > 0 AND (length({plain('x')}) >= {least} OR hash = md5({kept(body)}))"


_MARKS = r"^[ \t]*((?:>[ \t]?)+)"
OP5_SQL = rf"""
WITH RECURSIVE own AS (
  SELECT DISTINCT conv_id AS c, turn AS t, text FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL AND regexp_matches(text, '(?m){_MARKS}')
), lines AS (
  SELECT c, t, text, i AS no, string_split(text, chr(10))[i + 1] AS raw FROM own, unnest(range(len(string_split(text, chr(10))))) AS u(i)
), leveled AS (
  SELECT *, length(regexp_replace(regexp_extract(raw, '{_MARKS}', 1), '[^>]', '', 'g')) AS lv, regexp_replace(raw, '{_MARKS}', '') AS line FROM lines
), turned AS (
  SELECT *, CASE WHEN lv IS DISTINCT FROM lag(lv) OVER (PARTITION BY c, t, text ORDER BY no) THEN 1 ELSE 0 END AS changed FROM leveled
), runs AS (
  SELECT *, sum(changed) OVER (PARTITION BY c, t, text ORDER BY no) AS run FROM turned
), bodies AS (
  SELECT c, t, text, run, lv, string_agg(line, chr(10) ORDER BY no) AS body FROM runs GROUP BY c, t, text, run, lv
), bared AS (
  SELECT c, t, text, run, lv, CASE WHEN lv = 0 AND lead(lv, 1, 0) OVER (PARTITION BY c, t, text ORDER BY run) > 0
    THEN regexp_replace(body, '(?:^|\n)[ \t]*(?:On|Am|Le|El|Il|Op)\b[^\n]*:\s*$', '') ELSE body END AS body FROM bodies
), cleaned AS (
  SELECT c, t, text, regexp_replace(coalesce(string_agg(body, chr(10) ORDER BY run) FILTER (WHERE lv = 0), ''), '^\s+|\s+$', '', 'g') AS clean, max(lv) AS levels FROM bared GROUP BY c, t, text
), quoted AS (
  SELECT DISTINCT c, t, lv, hash, chars FROM ({_units_sql("SELECT c, t, lv, body FROM bared WHERE lv > 0", "body", 5)})
), said AS (
  SELECT m.conv_id AS c, m.turn AS t, coalesce(k.clean, m.text) AS body FROM conversations m LEFT JOIN cleaned k ON m.conv_id = k.c AND m.turn = k.t AND m.text = k.text WHERE m.text IS NOT NULL
), sources AS (
  SELECT c, hash, min(t) AS source FROM ({_units_sql("SELECT * FROM said WHERE t IS NOT NULL", "body", 0)}) GROUP BY c, hash
), met AS (
  SELECT q.c, q.t, q.lv, source, sum(chars) AS w FROM quoted q JOIN sources USING (c, hash) WHERE source < q.t GROUP BY ALL
), answers AS (
  SELECT c, t, source AS parent FROM met QUALIFY row_number() OVER (PARTITION BY c, t ORDER BY lv, w DESC, source DESC) = 1
), up AS (
  SELECT c, t, parent AS root, 1 AS depth FROM answers UNION ALL SELECT u.c, u.t, a.parent, u.depth + 1 FROM up u JOIN answers a ON a.c = u.c AND a.t = u.root
), tree AS (
  SELECT c, t, arg_max(root, depth) AS root, max(depth) AS depth FROM up GROUP BY c, t
), placed AS (
  SELECT m.conv_id, m.turn, m.role, coalesce(k.clean, m.text) AS text, coalesce(k.levels, 0) AS quote_levels, a.parent AS parent_turn, coalesce(x.depth, 0) AS depth, coalesce(x.root, m.turn) AS root
  FROM conversations m LEFT JOIN cleaned k ON m.conv_id = k.c AND m.turn = k.t AND m.text = k.text LEFT JOIN answers a ON m.conv_id = a.c AND m.turn = a.t LEFT JOIN tree x ON m.conv_id = x.c AND m.turn = x.t
)
SELECT conv_id, turn, role, text, CAST(quote_levels AS INTEGER) AS quote_levels, parent_turn, CAST(depth AS INTEGER) AS depth,
  CASE WHEN conv_id IS NOT NULL AND turn IS NOT NULL THEN row_number() OVER (PARTITION BY conv_id, turn IS NULL ORDER BY root, turn, role NULLS FIRST, text NULLS FIRST) - 1 END AS reply_no
FROM placed
"""


def quote_free_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations in reply order without quotes, as op5 orders them, in parts of a bounded number of messages."""
    from corpusdedup.llm.quotations import conversations

    found = conversations(op5_quotation_linking(spark, sf_dir))
    return found.select("conv_id", "part", "n_messages", F.md5("text").alias("digest"))


CONVERSATIONS_SQL = f"""
WITH told AS (SELECT conv_id, reply_no // 256 AS part, reply_no, coalesce(role, '') || ':' || chr(10) || coalesce(text, '') AS line FROM ({OP5_SQL}) WHERE reply_no IS NOT NULL)
SELECT conv_id, part, count(*) AS n_messages, md5(string_agg(line, chr(10) || chr(10) ORDER BY reply_no)) AS digest FROM told GROUP BY conv_id, part
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {**{k: f for k, f in globals().items() if k.startswith("op") and callable(f)}, "quote_free_conversations": quote_free_conversations}


def oracle_sql() -> dict[str, str]:
    return {"op10_deletion_neighbourhood_lines": OP10_SQL, "op5_quotation_linking": OP5_SQL, "quote_free_conversations": CONVERSATIONS_SQL}
