"""The corpus pipeline: quality rules, near-duplicates, decontamination, personal data, token ids.

Each stage takes (spark, docs, sf_dir) and works on all documents that the stage before it kept; the
driver of the pipeline writes its result as Parquet and rereads it as the next stage's input.
All stages but the last return the columns of ``documents``.

Defined results: a stage treats null and empty texts as its operator does; repeated rows are copies
of one another, of which near_duplicates keeps one; other columns pass through, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ranksort.llm import decontamination, pii, quality, queries, sentencepiece, simhash
from ranksort.llm.storage import materialize, release, unused

#: Near-duplicates by five-word shingles: fingerprints of 8 words in blocks of 16 bits.  Texts of a similarity of 0.8
#: differ in 77 of the 512 bits on average, and 8 more or less.
SHINGLE, LANES, WIDTH, BUDGET = 5, 8, 16, 84
#: Texts that agree in 4 of 5 of their distinct shingles or more are all linked, also those whose fingerprints miss each other.
SHARE = (4, 5)


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rule and the repetition limits."""
    work = unused(docs.columns, "work")
    return quality.assess(docs, result=work).where(quality.kept(work)).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component: the one with the smallest id; of rows that repeat that id, one.

    Rows without an id cannot be named by a component and are left alone.  The join and the choice
    among repeated ids share one shuffle of the texts.
    """
    groups = simhash.near_duplicates(docs.select("doc_id", "text"), budget=BUDGET, shingle=SHINGLE, lanes=LANES, width=WIDTH, share=SHARE)
    first = groups.where(F.col("doc_id") == F.col("component_id")).select("doc_id").distinct()
    chosen = docs.join(first, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    return chosen.unionByName(docs.where("doc_id is null")).select(*docs.columns)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that overlap no benchmark item."""
    work, benchmark = unused(docs.columns, "work"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return decontamination.find_overlaps(docs, benchmark, result=work).where(F.size(work) == 0).select(*docs.columns)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with each personal span replaced by its kind; n_chars follows the text."""
    work = unused(docs.columns, "work")
    clean = pii.redact(F.col("text"), F.col(work))
    found = pii.find_spans(docs, result=work).withColumn("text", F.when(F.col("text").isNotNull(), clean))
    return found.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, ids and n_tokens of each document, and whether the ids decode to its text."""
    model = sentencepiece.load_model(queries.PIECES)
    return sentencepiece.encode_checked(docs, model)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("decontaminate", decontaminate),
    ("personal_data", personal_data),
    ("token_ids", token_ids),
]

#: Repeats, fingerprints and ids are beyond SQL; the tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
        release(*before)
        before = [docs]
    return docs
