"""Corpus pipeline: five stages over documents, each written before the next one reads it.

Every stage takes rows as they come: null texts count as empty, null ids, languages, sources and lengths are kept as
they are, rows that repeat an id are rows of their own (near duplicates leave one row of a group, whatever their ids),
ties go by id (null last), then by the row's place in the table that the stage before wrote. Columns beside those of
documents are dropped by the first stage, so none can clash with those that a stage adds. Very long texts are
processed whole. An empty table gives an empty result of the same columns at each stage; an empty labels table leaves
the classifiers without knowledge: scores of one half, which the quality stage keeps, and domains equally likely.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linform.llm import bpe, line_dedup, mixing, quality, simhash
from linform.llm.common import materialise
from linform.llm.queries import table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def filter_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; it learns from the labelled documents of the corpus."""
    known = quality.known_labels(table(spark, sf_dir, "labels"), "quality")
    return quality.score(docs, quality.train(table(spark, sf_dir, "documents"), known)).where("score >= 0.3").select(*COLUMNS)


def delete_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of line runs go; a text of which nothing is left goes whole, as its lines are kept elsewhere."""
    out = line_dedup.dedup_lines(docs.select(*COLUMNS))
    left = out.where((F.col("n_deleted") == 0) | line_dedup.is_solid("text"))
    return left.withColumn("n_chars", F.when(F.col("n_deleted") == 0, F.col("n_chars")).otherwise(F.length("text").cast("long"))).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The row of least id stays, one alone, of each group of texts that share at least 0.8 of their five-word shingles.

    Candidates are links of SimHash fingerprints of those shingles within radius 3, and bands of least hashes for the
    similar texts that lie further apart; an exact check of the shingles follows both."""
    rows = materialise(docs.select(*COLUMNS).withColumn("row", F.monotonically_increasing_id()), "rows")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row"))  # a null id is the largest
    keep = rows.select("row", "doc_id").join(simhash.similar_groups(rows, "row"), "row").groupBy("root").agg(first.alias("first"))
    return rows.join(keep.select("first.row"), "row", "left_semi").select(*COLUMNS)


def mix_domains(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many copies of each document as its rate says (rows that repeat an id: the most of them); clean documents stay
    at least once, toxic ones go."""
    corpus = table(spark, sf_dir, "documents")
    weights = mixing.train(corpus, mixing.known_domains(corpus, table(spark, sf_dir, "labels")))
    rated = mixing.mix(docs.select("doc_id", "text"), weights, keep_clean=True, temper=0.95, keep_text=False).groupBy("doc_id").agg(F.max("copies").alias("copies")).where("copies > 0")
    joined = docs.join(rated.withColumnRenamed("doc_id", "of"), docs["doc_id"].eqNullSafe(F.col("of")))
    return joined.withColumn("nth", F.explode(F.sequence(F.lit(1), "copies"))).select(*COLUMNS)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text, and whether they decode to it."""
    import public_tokenizers

    machine = bpe.MergeAutomaton.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    made = bpe.round_trip(docs.select(*COLUMNS), machine)
    same = F.col("decoded") == F.coalesce("text", F.lit(""))
    return made.select("doc_id", "lang", "source", "n_chars", F.size("ids").cast("long").alias("n_tokens"), "ids", same.alias("round_trip"))


STAGES = [
    ("quality classifier", filter_quality),
    ("line dedup", delete_repeated_lines),
    ("SimHash near-dedup", drop_near_duplicates),
    ("mixing sources to target weights", mix_domains),
    ("BPE encoding and decoding", encode_tokens),
]

#: The stages learn models and follow chains of links, which SQL does not express; tests hold them to brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(*COLUMNS)
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialise(docs, f"stage-{i}")
    return docs
