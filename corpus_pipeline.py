"""The corpus pipeline: from raw documents to packed sequences, stage by stage.

Every stage takes all that its predecessor kept. Rows whose doc_id is null are
judged like others where a stage needs no id and pass where it does.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgecsr.llm import dart_minhash, packing, quality, suffix_array, toxicity
from edgecsr.llm.common import materialize, read


def packed_rows(docs: DataFrame, *more) -> DataFrame:
    """Whole rows as one column, so that no name of theirs meets a name made here; then doc_id, text and ``more``."""
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    return docs.select(row, F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *more)


def reject_toxic(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain does not call toxic."""
    chain = toxicity.train(docs, read(spark, sf_dir, "labels"))
    return toxicity.score(packed_rows(docs), chain, ["row"]).where(~F.col("toxic")).select("row.*")


def reject_low_quality(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the two co-trained views together call good."""
    model = quality.train(docs, read(spark, sf_dir, "labels"))
    views = [F.col(c) for c in ("lang", "source", "n_chars") if c in docs.columns]
    return quality.score(packed_rows(docs, *views), model, ["row"]).where("keep").select("row.*")


def drop_near_duplicates(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates: the one with the least id; of equal rows one. Rows without an id stay."""
    found = dart_minhash.classed(docs)
    others = found.where(F.col("id") != F.col("class")).select(F.col("id.doc_id").alias("doc_id"), F.col("id.text_hash").alias("text_hash"))
    keyed = packed_rows(docs, F.xxhash64(F.col("text").cast("string")).alias("text_hash"))
    kept = keyed.join(others, ["doc_id", "text_hash"], "left_anti")
    named = F.col("doc_id").isNotNull()
    if keyed.where(named).groupBy("doc_id", "text_hash").count().where("count > 1").isEmpty():
        return kept.select("row.*")
    return kept.where(named).dropDuplicates(["doc_id", "text_hash"]).select("row.*").union(kept.where(~named).select("row.*"))


def cut_repeats(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the byte strings that also start in a document of smaller id; n_chars follows the text."""
    shorter = suffix_array.remove_repeats(docs, with_text=True).where("n_removed > 0").select("doc_id", "text_hash", "kept_text").distinct()
    keyed = packed_rows(docs, F.xxhash64(F.col("text").cast("string")).alias("text_hash"))
    joined = keyed.join(shorter, ["doc_id", "text_hash"], "left")
    new = {"text": F.coalesce("kept_text", "row.text"), "n_chars": F.when(F.col("kept_text").isNull(), F.col("row.n_chars")).otherwise(F.length("kept_text").cast("long"))}
    return joined.select(*[new[c].cast(docs.schema[c].dataType).alias(c) if c in new else F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def pack_sequences(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all texts, packed into sequences of 1024 tokens."""
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), added=packing.added_tokens(public_tokenizers.path("byte_bpe_50k.json")))


STAGES = [
    ("toxicity", reject_toxic),
    ("quality", reject_low_quality),
    ("near_dedup", drop_near_duplicates),
    ("suffix_dedup", cut_repeats),
    ("packing", pack_sequences),
]

#: Trained models and signatures have no SQL; tests/llm compares the stages with brute force.
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
