"""A corpus from raw documents to packed windows, in stages that each call one operator of labelsketch.llm.

Every stage takes the documents that the one before it left and is written as Parquet before the next one reads it.
Quality rules drop what they reject; of each near-duplicate group the document of the least id stays; contaminated
documents go; personal data is replaced by the name of its kind; packing returns the pieces.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from labelsketch.llm import decontaminate, near_dedup, packing, pii, quality
from labelsketch.llm.common import read_table, shared_dir
from labelsketch.llm.queries import tokenizer


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the quality rules keep, with the columns of docs.

    Null and empty texts fail the base rules and go; equal texts share a verdict, whatever their ids, nulls included. Very
    long texts are measured whole. Columns of any name pass through; no documents give none.
    """
    return quality.kept_rows(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, that of the least id, with the columns of docs.

    Texts without words are like no other and stay. Where ids repeat or are missing each row is judged by its own text; ties go
    to the row that comes first, and of rows with the same id and text one stays. Columns of any name pass through; no
    documents give none.
    """
    return near_dedup.kept_rows(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents without any window of the benchmark, with the columns of docs.

    Null and empty texts hold no window and stay; equal texts share a verdict, whatever their ids. Very long texts are searched
    whole. Columns of any name pass through; an empty benchmark keeps all, no documents give none.
    """
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), "text")
    found = decontaminate.contamination(packed, read_table(spark, sf_dir, "benchmark"), ["__row"])
    return found.filter("not contaminated").select("__row.*")


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced by the name of its kind, with the columns of docs.

    n_chars, where there is one, is counted anew in its own type. Null texts stay null. Rows are handled one by one, so repeats
    and missing ids change nothing. Columns of any other name pass through; no documents give none.
    """
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), "text")
    found = pii.redacted(packed)
    old = {c: F.col("__row").getField(c) for c in docs.columns}
    changed = {"text": F.col("__redacted")}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.length("__redacted").cast(docs.schema["n_chars"].dataType)
    return found.select(*[changed.get(c, old[c]).alias(c) for c in docs.columns])


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of packed sequences with their token ids (little-endian unsigned 32-bit), ready to be trained on.

    A null text counts as empty and is its end id alone. Repeated rows are packed once each. Very long texts are cut into many
    pieces, other columns are dropped, no documents give no pieces.
    """
    return packing.packed(docs, tokenizer("byte_bpe_50k.json"), with_ids=True)


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("personal_data", personal_data), ("packing", pack)]

#: SQL can't tokenise; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    base = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{base}/{name}")
        docs = spark.read.parquet(f"{base}/{name}")
    return docs
