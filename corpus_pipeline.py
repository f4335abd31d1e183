"""A training corpus from raw documents: toxicity, language, repeated lines, near-duplicates, packing.

Each stage takes (spark, docs, sf_dir); its result is written as Parquet and read again as the next one's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relml.llm import common, langid, linededup, neardup, packing, toxicity
from relml.llm.queries import _path


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score below 0.7 stay.  The classifier learns from rows of docs that are labelled."""
    model = toxicity.train(docs, common.load(spark, sf_dir, "labels"), lambda i: ~common.held_out(i, 3, 1))
    return toxicity.keep_clean(docs, model)


def drop_unknown_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with letters, in which one of the languages stands out, stay."""
    return langid.keep_known(docs, langid.train(docs, ~common.held_out("doc_id", 4, 2)))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents stay; later copies of repeated runs leave their texts, and n_chars follows."""
    out = linededup.drop_repeats(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("__removed") > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the least id of each group stays.  SimHash's links, as op10 has them, and shared bands of least values
    for the pairs that it misses are candidates; links are five-word shingles of similarity 0.8 or more, by an exact check."""
    return neardup.keep_first(docs, fingerprints=True)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs, _path("byte_bpe_50k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("language_id", drop_unknown_language),
    ("line_dedup", drop_repeated_lines),
    ("simhash_near_dedup", drop_near_duplicates),
    ("packing", pack_sequences),
]

#: The stages hold trained models and tokenizers, which SQL can't express; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, past = common.load(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        path = common.new_path(spark, name)
        with common.scratch(spark):  # a stage's own tables go once its result is stored
            docs = common.settle(stage(spark, docs, sf_dir), name, path)
        if past:
            common.delete(spark, past)
        past = path
    return STAGES[-1][1](spark, docs, sf_dir)
