"""A corpus pipeline of five operators; counted as part of ``nearfield.llm``.

Each stage takes (spark, docs, sf_dir) and returns the documents it keeps, with the columns of ``documents``; the
last returns the encoded documents. ``run`` applies them all, each stage's result written and read again.

Every stage takes nulls in any column, empty texts, repeated rows and an empty table: a null text is an empty one; rows
without doc_id pass the Jaccard join, and lose a shared line as one document; a null source is a source of its own.
Documents without words are never mixed in.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.llm import jaccard_groups, line_dedup, mixing, pieces, toxicity
from nearfield.llm.queries import CATEGORIES, tokenizer_path
from nearfield.llm.shared import cut, remove_folder, shared_folder

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def toxic_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain calls toxic go."""
    chain = toxicity.learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), CATEGORIES)
    return toxicity.predict(docs.select(*COLUMNS), chain).where(~F.col("is_toxic")).select(*COLUMNS)


def lines_once(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of three or more documents stay in one; n_chars follows the text."""
    kept = line_dedup.dedup_lines(docs.select(*COLUMNS))
    return kept.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def near_copies_out(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document stays of those linked by a Jaccard similarity of 0.8 over five-word shingles."""
    return jaccard_groups.drop_near_copies(docs.select(*COLUMNS), words=5, percent=80)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents, each as often as the mix takes its words (0 to 2 times, rounded half up)."""
    taken = mixing.mix(docs).groupBy("doc_id").agg(F.sum("size").alias("_size"), F.sum("taken").alias("_taken"))
    taken = taken.select(F.col("doc_id").alias("_id"), mixing.copies("_size", "_taken").alias("_copies"))
    rows = docs.select(*COLUMNS).join(taken.where("_copies > 0"), F.col("doc_id").eqNullSafe(F.col("_id")))
    return rows.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every document left: doc_id, ids (packed), their number, how many are bytes, crc32, round trip."""
    return pieces.encode_pieces(docs, tokenizer_path("piece_bpe_32k.model"))


STAGES = [("toxicity", toxic_out), ("line_dedup", lines_once), ("jaccard_join", near_copies_out), ("mixing", mixed), ("pieces", encoded)]

#: The classifier and the piece encoder are no SQL; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``, through Parquet in the shared folder, which is emptied on the way."""
    folder = shared_folder(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for number, (_, stage) in enumerate(STAGES[:-1]):
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{folder}/{number}")
        docs = spark.read.schema(out.schema).parquet(f"{folder}/{number}")
        if number:
            remove_folder(spark, f"{folder}/{number - 1}")
    last = cut(STAGES[-1][1](spark, docs, sf_dir))
    remove_folder(spark, folder)
    return last
