"""A corpus pipeline: quality rules, near-duplicate removal, repeated-passage removal, source mixing, BPE ids.

Each stage takes (spark, docs, sf_dir); docs has the columns of documents. run() writes each stage's result as Parquet in the
shared folder and rereads it as the next stage's docs, so a lost executor costs one stage at most.

Null, empty and very long texts, repeated rows, empty tables and further columns of docs are handled as the
operators' docstrings say; rows with one id, or without, are documents of their own; further columns pass through the stages that keep
documents, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from georank.llm import bpe, jaccard, mixing, quality, suffixes
from georank.llm.common import shared_path
from georank.plans.shipping import ship


def _rows(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """The documents whose place in docs is one of `row`: rows are told apart by it, as ids can repeat or be null."""
    placed = docs.select(F.monotonically_increasing_id().alias("row"), F.struct(*[docs[c].alias(f"c{i}") for i, c in enumerate(docs.columns)]).alias("doc"))
    return placed.join(rows, "row").select(*[F.col(f"doc.c{i}").alias(c) for i, c in enumerate(docs.columns)], *[F.col(c) for c in rows.columns if c != "row"])


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return _rows(docs, quality.judge(docs).filter("kept").select("row"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates (five-word shingles, Jaccard 0.8) stays: that with the smallest id, of several the first."""
    return _rows(docs, jaccard.classes(docs, width=5, percent=80).filter("first").select("row"))


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Bytes of passages that occur elsewhere go; documents stay, if need be with no text."""
    left = suffixes.remove(docs).select(*docs.columns)
    return left.withColumn("n_chars", F.char_length("text").cast("long")) if "n_chars" in docs.columns else left


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes its words, in whole copies that keep each source's words near its target."""
    copies = mixing.copies(mixing.mix_blocks(docs)[0]).withColumnRenamed("copies", "__copies")
    return _rows(docs, copies).withColumn("__copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__copies")))).select(*docs.columns)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of each document of the mix, with digests of the ids and of what they decode to."""
    import public_tokenizers

    return bpe.encode(docs, public_tokenizers.path("word_bpe_49k.json"), keep=("doc_id",), digests=True)


STAGES = [
    ("quality rules", quality_rules),
    ("near duplicates", near_duplicates),
    ("repeated passages", repeated_passages),
    ("source mix", source_mix),
    ("token ids", token_ids),
]

#: Robust estimates and BPE are beyond SQL. Tests hold the near-duplicate stage's rows and the robust distances against brute
#: force; of the other stages, only the operators are compared, not the stages' rows.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = shared_path(spark, name.replace(" ", "-"))
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
