"""A corpus pipeline of five stages; each takes and returns a table, written and read again in between."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkwalk.llm import neardup, packing, pii, substring, toxicity
from linkwalk.llm.storage import cut

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _changed(docs: DataFrame, text) -> DataFrame:
    """Documents with a new text, and their length in code points where the text changed."""
    new = docs.withColumn("new_", text)
    same = F.col("new_").eqNullSafe(F.col("text"))
    return new.select("doc_id", F.col("new_").alias("text"), "lang", "source", F.when(same, F.col("n_chars")).otherwise(F.length("new_").cast("long")).alias("n_chars"))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose expected severity is below one half stay."""
    model = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity.score(docs.select(COLUMNS), model).where(~F.col("toxic")).select(COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays: that of the least id."""
    return neardup.near_duplicates(docs.select(COLUMNS)).where("kept").select(COLUMNS)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that occur earlier go; other words stay, joined by one space where anything went."""
    out = substring.remove_repeats(docs.select(COLUMNS))
    return _changed(out, F.when(F.col("n_removed") > 0, F.col("kept_text")).otherwise(F.col("text")))


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans of personal data are replaced by their kind."""
    found = pii.find_pii(docs.select(COLUMNS))
    return _changed(found, pii.redact(F.col("text"), F.col("pii")))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces, packed into sequences of at most 1024."""
    special = packing.special_tokens(public_tokenizers.path("byte_bpe_50k.json"))
    return packing.pack(packing.pieces(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, special))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_copies),
    ("substrings", cut_repeats),
    ("personal_data", mask_personal_data),
    ("packing", pack_sequences),
]

#: Fitting, similarity classes and packing have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
