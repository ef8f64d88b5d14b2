"""Cleaning of a document collection in stages.

Each stage takes ``(spark, docs, sf_dir)`` and works on all that the stage before it kept; its result is written as
Parquet and read again. All stages but the last return the columns of ``docs``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tokenweave.llm import bpe, decontaminate, ngram_jaccard, queries, substring_dedup, toxicity
from tokenweave.llm.common import Scratch, documents


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is under 0.5; the model learns from labelled documents among them."""
    model = queries.toxicity_model(spark, docs, sf_dir)
    return docs.where(toxicity.scored(docs, model) < 0.5)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by a Jaccard similarity of 0.8 or more over 5-word shingles the one with the smallest id.

    Documents without words stay; of rows that repeat id and text one stays.
    """
    scratch = Scratch(spark)
    found = scratch.finish(ngram_jaccard.jaccard_components(docs, width=5, num=80, den=100, scratch=scratch))
    kept = found.where("doc_id <=> component_id").select(F.col("doc_id").alias("kept_id")).distinct()
    return docs.join(kept, docs.doc_id.eqNullSafe(kept.kept_id), "left_semi").dropDuplicates(["doc_id", "text"])


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without words of 20-word windows that begin earlier too; a changed text has one blank between
    words and its ``n_chars`` is counted anew, others stay as they are."""
    carry = [c for c in docs.columns if c not in ("doc_id", "text")]
    scratch = Scratch(spark)
    kept = scratch.finish(substring_dedup.dedup_substrings(docs, carry=carry, unchanged=True, scratch=scratch))
    changed = F.col("n_removed") > 0
    columns = {"text": F.col("kept")} | ({"n_chars": F.when(changed, F.length("kept")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)} if "n_chars" in carry else {})
    return kept.select(*[columns[c].alias(c) if c in columns else F.col(c) for c in docs.columns])


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark passage."""
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``doc_id, n_tokens, ids`` of every document."""
    coded = bpe.encode(docs, queries.tokenizer_path())
    return coded.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids")


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard", keep_one_of_near_copies),
    ("substring_dedup", drop_repeated_passages),
    ("decontamination", drop_contaminated),
    ("bpe", encode_tokens),
]
#: SQL can't express the classifier and the tokenizer; the tests hold run() against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, one after the other, over the documents."""
    scratch, docs = Scratch(spark), documents(spark, sf_dir)
    for name, stage in STAGES:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return docs
