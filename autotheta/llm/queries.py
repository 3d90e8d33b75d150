"""The ten operators on the tables they are meant for, and their equivalents in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from autotheta.llm import decontaminate as _decontaminate, linededup, maxent, mixing, neardup, oracles, perplexity, quality, tokens, toxicity, warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def held_out() -> Column:
    """The rows labels are not learnt from."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2


def op1_toxic_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = toxicity.score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), train=~held_out())
    return out.select("doc_id", held_out().alias("held_out"), "score", "predicted", "n_words", F.size("passages").cast("bigint").alias("n_passages"))


def op2_warc_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.read_archives(warc.write_archives(table(spark, sf_dir, "pages"))).drop("url")


def op3_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_sources(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "copies")


def op4_token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.read_shards(tokens.write_shards(table(spark, sf_dir, "documents"), tokenizer_path(), end_id=2))


def op5_maxent_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 10 == 0
    scores = maxent.score_language_model(table(spark, sf_dir, "documents"), train_on=~held)
    return scores.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op6_perplexity_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return perplexity.perplexity_filter(table(spark, sf_dir, "documents"))


def op7_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return quality.quality_by_site(docs, labels, host=F.col("source"), path=F.concat_ws("/", "source", F.coalesce("lang", F.lit(""))), train=~held_out())


def op8_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = linededup.drop_boilerplate_lines(table(spark, sf_dir, "documents"), min_sites=10)
    return out.select("doc_id", F.md5(F.coalesce("text", F.lit(""))).alias("text_md5"), "n_lines", "n_removed")


def op9_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), size=3, num=85, den=100)


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    hits = _decontaminate.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), size=10)
    return hits.select("doc_id", "n_words", "n_hit", F.size("items").cast("bigint").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


QUERIES = {f.__name__: f for f in (op1_toxic_segments, op2_warc_pages, op3_mix_sources, op4_token_records, op5_maxent_model, op6_perplexity_rules, op7_site_quality, op8_line_spread, op9_near_duplicates, op10_decontaminate)}
ORACLE: dict[str, str] = {"op2_warc_pages": oracles.WARC, "op8_line_spread": oracles.LINE_DEDUP, "op9_near_duplicates": oracles.NEAR_DUPLICATES, "op10_decontaminate": oracles.DECONTAMINATE}
