"""A corpus pipeline of five stages, each written as Parquet before the next one reads it.

Toxic documents go; one document of each near-duplicate group stays (the smallest
id); strings of 50 bytes that a smaller id has go; secrets are replaced by marks;
what is left is packed into sequences. All stages but the last return the columns
of documents, with n_chars renewed where a text changes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm import jaccard, packing, runlength, secrets, toxicity
from pathload.llm.common import free_name, staged, table

#: Near duplicates: words of a shingle and hundredths of similarity.
SHINGLE_WORDS, SIMILARITY = 5, 80


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the lexicon, learned from the labels, scores below its threshold."""
    model = toxicity.learn(toxicity.labelled(docs, table(spark, sf_dir, "labels")))
    return toxicity.without_toxic(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group; equal rows count as one; rows without an id stay."""
    found = jaccard.jaccard_components(docs, SHINGLE_WORDS, SIMILARITY)
    stay = found.where("doc_id = component_id").select("doc_id").distinct()
    return docs.join(stay, "doc_id", "left_semi").select(*docs.columns).dropDuplicates().unionByName(docs.where("doc_id is null"))


def drop_repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the strings that a smaller id has, cut at whole characters."""
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    done = runlength.drop_repeated_bytes(docs, 50, carry=rest, whole_characters=True)
    kept = free_name("kept", ("doc_id", *rest))
    return _renewed(done.withColumn("text", F.decode(f"`{kept}`", "UTF-8")), docs)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with every secret's span replaced by a mark of its kind."""
    return _renewed(secrets.with_redacted(docs), docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each document's tokens go."""
    return packing.pack(staged(packing.token_pieces(docs)))


def _renewed(done: DataFrame, docs: DataFrame) -> DataFrame:
    if "n_chars" in docs.columns:
        done = done.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return done.select(*(f"`{c}`" for c in docs.columns))


STAGES = [
    ("toxicity", drop_toxic),
    ("jaccard_join", drop_near_duplicates),
    ("suffix_dedup", drop_repeated_strings),
    ("secret_scan", mask_secrets),
    ("packing", pack_sequences),
]

#: SQL can't express the learned lexicon and the packing; tests compare every stage with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
