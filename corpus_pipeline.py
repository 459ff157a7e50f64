"""The corpus pipeline: each stage reads all that the one before kept; all but the last return the columns of documents.

1. language_id (operator 3): learns profiles from the labelled rows at hand and drops documents without a letter and
   those that are far from every profile; without any profile it drops the letterless only. 2. exact_dedup (4): one of equal texts stays. 3. near_dedup (6): five-word
   shingles, similarity of 0.8 or more; one document of each group stays. 4. secret_scan (8): owner-specific secrets
   are masked in the text, widely copied examples stay, no document goes. 5. packing (5): pieces of sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from episodic.llm import exact_dedup, langid, near_dedup, secrets
from episodic.llm.queries import pack_documents
from episodic.llm.runtime import materialize, passing
from episodic.shipping import ship

#: A document below this score is nearer to no language than random letters are.
LEAST_SCORE = 0.1


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a language; null and empty texts and those without a letter go. Repeated rows are judged alike.

    Where no row has both a language and a text with letters there is nothing to judge by: every text with a letter stays.
    """
    ship(spark)
    profiles = langid.learn_profiles(docs)
    if not profiles:
        return docs.filter(langid.has_letter()(F.col("text")))
    said = docs.withColumn("__said", langid.language_of(profiles)(F.col("text")))
    return said.filter((F.col("__said.lang_pred") != "und") & (F.col("__said.score") >= LEAST_SCORE)).drop("__said")


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of texts equal up to white space the document with the smallest id."""
    ship(spark)
    return exact_dedup.drop_exact_copies(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents that links of similarity 0.8 or more join the one with the smallest id."""
    ship(spark)
    return near_dedup.drop_near_copies(docs)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, with owner-specific secrets masked and n_chars brought up to date where text changed."""
    ship(spark)
    masked = secrets.redact_live(docs)
    if "n_chars" in docs.columns:
        masked = masked.withColumn("n_chars", F.when(F.col("n_chars").isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)))
    return masked.select(*docs.columns)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each piece of each document, as operator 5 gives them."""
    ship(spark)
    return pack_documents(docs)


STAGES = [
    ("language_id", language_id),
    ("exact_dedup", exact_stage),
    ("near_dedup", near_stage),
    ("secret_scan", secret_stage),
    ("packing", packing_stage),
]

#: Language profiles, near-duplicate groups and token ids have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        with passing(f"stage-{name}"):
            docs = materialize(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
