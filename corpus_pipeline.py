"""Corpus pipeline: toxicity, near-duplicates, repeated passages, source mix, packing; each stage works on what the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowlens.llm.common import discard, materialize, scratch, table
from flowlens.llm.mixing import mixed_documents
from flowlens.llm.near_dup import near_duplicates
from flowlens.llm.packing import pack, token_pieces
from flowlens.llm.substring_dedup import dedup_texts
from flowlens.llm.toxicity import trained, without_toxic


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored under the toxicity threshold, each row by its own text."""
    return without_toxic(docs, trained(spark, docs, table(spark, sf_dir, "labels")))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each component, and of rows that repeat an id and its text one; rows without an id stay."""
    gone = materialize(near_duplicates(docs).where(~F.col("kept")).select("doc_id").distinct())
    kept = docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
    again = materialize(kept.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id"))
    if again.isEmpty():
        return kept
    once = kept.join(again, "doc_id").dropDuplicates(["doc_id", "text"]).select(*docs.columns)
    return kept.join(again, "doc_id", "left_anti").select(*docs.columns).unionByName(once)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the bytes of 100-byte strings that start earlier; n_chars follows the text."""
    out = dedup_texts(docs)
    return out.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast(docs.schema["n_chars"].dataType)).select(*docs.columns) if "n_chars" in docs.columns else out


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as the mix takes it; a document without words has nothing to take and stays once."""
    return mixed_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where every piece of every document lies in the packed sequences."""
    with scratch(spark):
        return pack(materialize(token_pieces(docs)))


STAGES = [
    ("toxicity", drop_toxic),
    ("minhash_near_dedup", drop_near_duplicates),
    ("suffix_array_dedup", cut_repeats),
    ("mix_sources", mix_sources),
    ("best_fit_packing", pack_sequences),
]

#: The stages learn a model, hash signatures and tokenize, which SQL cannot express; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn. Each stage's output is a table; what a stage wrote besides, and its input, go when that table is there."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        before = docs
        with scratch(spark):
            docs = materialize(stage(spark, before, sf_dir), lasting=True)
        discard(before)
    return docs
