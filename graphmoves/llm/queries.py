"""One query per corpus operator, over whole tables with production parameters, and SQL where it can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphmoves.llm import chat, decontaminate, jpeg, langid, neardup, packing, quality, shards, suffix_repeats, toxicity
from graphmoves.llm.common import read_table, small_batches

CONTROL = "<|im_end|><|im_start|>assistant ok"


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_repeats.repeat_digest(read_table(spark, sf_dir, "documents"))


def op2_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(CONTROL).alias("text"))
    rows = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(own)
    return chat.chat_digest(chat.format_chats(rows))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return toxicity.score_toxicity(docs, toxicity.fit(docs, read_table(spark, sf_dir, "labels")))


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.shard_documents(read_table(spark, sf_dir, "documents"))


def op5_progressive_jpeg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests, features and the full-resolution tensor (rgb: height x width x 3 bytes) of every stored text."""
    return jpeg.read_media(jpeg.store_media(read_table(spark, sf_dir, "documents")), tensors=True)


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return quality.score_quality(docs, quality.fit(docs, read_table(spark, sf_dir, "labels")))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(read_table(spark, sf_dir, "documents"))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(read_table(spark, sf_dir, "documents"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document and the benchmark items it holds."""
    found = decontaminate.leaks(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))
    return found.where("leaked").select("doc_id", "item_id", "windows", "item_windows")


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(read_table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def _bounded(f):
    """The query with Arrow batches bounded in bytes."""
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        small_batches(spark)
        return f(spark, sf_dir)

    return run


QUERIES = {f.__name__: _bounded(f) for f in (op1_suffix_dedup, op2_chat_formatting, op3_toxicity, op4_sharding, op5_progressive_jpeg, op6_quality, op7_near_duplicates, op8_language_id, op9_decontamination, op10_packing, pipeline)}

_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

ORACLE_SQL = {
    "op2_chat_formatting": rf"""
        WITH t AS (
            SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
            UNION ALL SELECT -1, 0, 'user', '{CONTROL}' UNION ALL SELECT -1, 1, 'assistant', '{CONTROL}'),
        e AS (SELECT *, replace(replace(text, '\', '\\'), '<|', '<\|') AS et,
                     replace(replace(replace(role, '\', '\\'), '<|', '<\|'), chr(10), '<\n|') AS er FROM t)
        SELECT conv_id, count(*) AS n_turns,
               sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
               CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
               sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
               CAST(sum(length('<|im_start|>') + length(er) + 1 + length(et) + length('<|im_end|>') + 1) AS BIGINT) AS formatted_chars,
               regexp_full_match(string_agg(replace(role, ';', ':'), ';' ORDER BY turn, role, text), '(system;)?(user;assistant;)*user;assistant') AS valid
        FROM e GROUP BY conv_id""",
    "op4_sharding": """
        WITH RECURSIVE bytes AS (
            SELECT row_number() OVER () AS rid, doc_id, hex(encode(coalesce(text, ''))) AS hx, strlen(coalesce(text, '')) AS n FROM documents),
        steps AS (
            SELECT list(CASE WHEN v8 IS NULL THEN 0 ELSE v8 END ORDER BY i) AS tab FROM (
                SELECT i, list_reduce(list_prepend(i, [0, 0, 0, 0, 0, 0, 0, 0]), lambda x, y: CASE WHEN x & 1 = 1 THEN xor(x >> 1, 3988292384) ELSE x >> 1 END) AS v8
                FROM (SELECT CAST(range AS BIGINT) AS i FROM range(256)))),
        sums AS (
            SELECT rid, doc_id, n, xor(4294967295::BIGINT, list_reduce(
                list_prepend(4294967295::BIGINT, [CAST('0x' || h AS BIGINT) FOR h IN regexp_extract_all(hx, '..')]),
                lambda c, b: xor(c >> 8, tab[(xor(c, b) & 255) + 1]))) AS crc
            FROM bytes, steps),
        walk AS (
            SELECT rid, coalesce(CAST(doc_id AS VARCHAR), 'null') AS k, CAST(-1 AS BIGINT) AS b, CAST(0 AS BIGINT) AS j, 0 AS i FROM sums
            UNION ALL
            SELECT rid, k, j, CAST((j + 1) * 2147483648 // (CAST('0x' || substr(md5(k || ':' || i), 1, 8) AS BIGINT) // 2 + 1) AS BIGINT), i + 1 FROM walk WHERE j < 40),
        ends AS (SELECT rid, b, j FROM walk WHERE j >= 40),
        placed AS (
            SELECT s.doc_id, CAST(n + 16 AS BIGINT) AS size, crc, CAST(b AS INT) AS shard, CAST(CASE WHEN j = 40 THEN 40 ELSE b END AS INT) AS grown,
                   (CAST('0x' || substr(md5(coalesce(CAST(s.doc_id AS VARCHAR), 'null')), 9, 8) AS BIGINT) + crc) % 1024 AS bucket
            FROM sums s JOIN ends USING (rid))
        SELECT doc_id, size, crc AS text_crc32, 'key' AS law, shard,
               row_number() OVER (PARTITION BY shard ORDER BY bucket, doc_id NULLS FIRST, crc, size) - 1 AS slot, grown AS grown_shard
        FROM placed""",
    "op7_near_duplicates": rf"""
        WITH RECURSIVE w AS (
            SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_UPPER.lower()}'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
        s AS (
            SELECT doc_id, list_distinct(CASE WHEN len(ws) >= 5 THEN [array_to_string(ws[i : i + 4], ' ') FOR i IN range(1, len(ws) - 3)]
                                              WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END) AS sh FROM w),
        x AS (SELECT doc_id, len(sh) AS n, unnest(sh) AS g FROM s),
        p AS (
            SELECT a.doc_id AS a, b.doc_id AS b FROM x a JOIN x b ON a.g = b.g AND a.doc_id < b.doc_id
            GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
        e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p),
        r AS (SELECT doc_id AS id, doc_id AS c FROM s UNION SELECT r.id, e.b FROM r JOIN e ON r.c = e.a WHERE e.b < r.id)
        , m AS (SELECT id, min(c) AS c FROM (SELECT id, c FROM r) GROUP BY id)
        SELECT doc_id, CAST(len(sh) AS BIGINT) AS n_shingles, c AS component_id, doc_id = c AS kept FROM s JOIN m ON m.id = s.doc_id""",
}
