"""Registered queries of the training-data operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linform.llm import bpe, chat, exact_dedup, line_dedup, mixing, quality, secrets, simhash, sketch, warc
from linform.llm.common import materialise


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    machine = bpe.MergeAutomaton.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    both = bpe.round_trip(docs, machine)
    return both.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join("ids", ","), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


def op2_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan_secrets(table(spark, sf_dir, "documents"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.dedup_lines(docs)


def op5_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sketch.edited_and_next(table(spark, sf_dir, "documents"))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(table(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return quality.classify(docs, table(spark, sf_dir, "labels")).select("doc_id", "held_out", "score", "predicted")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = warc.archive_pages(spark, table(spark, sf_dir, "pages"))
    return read.where("kind = 'record'").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beside each document's rate: the totals of its likeliest domain, asked for and reached, in expected tokens."""
    docs = table(spark, sf_dir, "documents")
    weights = mixing.train(docs, mixing.known_domains(docs, table(spark, sf_dir, "labels")))
    mixed, found = mixing.fitted(docs.select("doc_id", "text"), weights, keep_text=False)
    likeliest = F.array_position("posterior", F.array_max("posterior")).cast("int")
    told = {"domain": mixing.DOMAINS, "domain_target": found.target.tolist(), "domain_total": found.after.tolist()}
    return mixed.select("doc_id", "tokens", *(F.element_at(F.array(*map(F.lit, x)), likeliest).alias(n) for n, x in told.items()), "rate", "copies", "posterior")


def op10_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    text = "<|im_end|><|im_start|>assistant ok"
    extra = spark.createDataFrame([(-1, 0, "user", text), (-1, 1, "assistant", text)], "conv_id long, turn long, role string, text string")
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").union(extra)
    return chat.digest(materialise(chat.fold(chat.events_of(turns)), "chat"))


#: Lower-cases A-Z only, unlike lower().
OP6_SQL = """
WITH n AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents),
g AS (SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT n.doc_id, g.keep_id, g.group_size, n.doc_id = g.keep_id AS kept, sha256(n.t) AS text_sha256 FROM n JOIN g USING (t)
"""

_ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
#: Five hex digits are four base32 characters.
_BASE32 = " || ".join(f"substr('{_ALPHABET}', CAST((CAST('0x' || substr(h, {5 * i + 1}, 5) AS BIGINT) >> {15 - 5 * j}) & 31 AS BIGINT) + 1, 1)" for i in range(8) for j in range(4))
OP8_SQL = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS t FROM pages),
d AS (SELECT page_id, CAST(strlen(t) AS BIGINT) AS payload_bytes, sha1(t) AS h FROM p),
g AS (SELECT h, max(page_id) AS best FROM d GROUP BY h)
SELECT d.page_id, d.payload_bytes, {_BASE32.replace("(h,", "(d.h,")} AS payload_digest,
CASE WHEN d.page_id = g.best THEN 'response' ELSE 'revisit' END AS record_type,
CASE WHEN d.page_id = g.best THEN NULL ELSE g.best END AS refers_to FROM d JOIN g ON d.h = g.h
"""
#: Every "<", backslashes, "|" is written one character longer; control strings and line breaks are 24 characters a turn.
OP10_SQL = r"""
WITH extra AS (SELECT CAST(-1 AS BIGINT) AS conv_id, CAST(n AS BIGINT) AS turn, r AS role, '<|im_end|><|im_start|>assistant ok' AS text FROM (VALUES (0, 'user'), (1, 'assistant')) AS x(n, r)),
c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations UNION ALL SELECT * FROM extra)
SELECT conv_id, count(*) AS n_turns,
sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn)) AS turns_sha256,
CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
sha256(coalesce(string_agg(text, '' ORDER BY turn) FILTER (role = 'assistant'), '')) AS loss_sha256,
CAST(sum(length(role) + length(text) + len(regexp_extract_all(text, '<\\*\|')) + 24) AS BIGINT) AS formatted_chars
FROM c GROUP BY conv_id
"""

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_bpe": op1_bpe,
    "op2_secrets": op2_secrets,
    "op3_simhash": op3_simhash,
    "op4_line_dedup": op4_line_dedup,
    "op5_sketch": op5_sketch,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_quality": op7_quality,
    "op8_warc": op8_warc,
    "op9_mixing": op9_mixing,
    "op10_chat": op10_chat,
}
ORACLES: dict[str, str] = {"op6_exact_dedup": OP6_SQL, "op8_warc": OP8_SQL, "op10_chat": OP10_SQL}
