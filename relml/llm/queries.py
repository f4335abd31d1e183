"""One query per operator, with production parameters, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, common, langid, linededup, media, packing, sharding, simhash, token_counts, toxicity


def _path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_ann_cross_polytope(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(common.load(spark, sf_dir, "embeddings"), F.col("id") % 20 == 0)


def op2_unigram_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(common.load(spark, sf_dir, "documents"), _path("piece_bpe_32k.model"))


def op3_vector_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(common.load(spark, sf_dir, "documents"), _path("byte_bpe_50k.json"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.load(spark, sf_dir, "documents")
    model = toxicity.train(docs, common.load(spark, sf_dir, "labels"), lambda i: ~common.held_out(i, 3, 1))
    out = toxicity.score_documents(docs, model)
    return out.select("doc_id", common.held_out("doc_id", 3, 1).alias("held_out"), "score", "predicted")


def op5_word_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.load(spark, sf_dir, "documents")
    file = _path("word_bpe_49k.json")
    return bpe.encode_digests(docs, file, bpe.build_lexicon(spark, bpe.frequent_words(docs), file))


def op6_minimax_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(common.load(spark, sf_dir, "documents"))


def op7_media_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = common.new_path(spark, "archives")
    media.write_archives(common.load(spark, sf_dir, "documents"), folder)
    return media.media_features(media.read_archives(spark, folder))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.load(spark, sf_dir, "documents")
    model = langid.train(docs, ~common.held_out("doc_id", 4, 2))
    out = langid.predict(docs, model)
    return out.select("doc_id", common.held_out("doc_id", 4, 2).alias("held_out"), "lang_pred", "score")


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.drop_repeats(common.load(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.col("__lines").alias("n_lines"), F.col("__removed").alias("n_removed"), F.crc32(F.col("text").cast("binary")).alias("kept_crc32"))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(common.load(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_ann_cross_polytope, op2_unigram_token_counts, op3_vector_packing, op4_toxicity, op5_word_bpe, op6_minimax_shards, op7_media_archive, op8_language_id, op9_line_dedup, op10_simhash, pipeline)}

ORACLES: dict[str, str] = {}
