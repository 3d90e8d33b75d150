"""The corpus pipeline: toxicity, near duplicates, benchmark passages, mixing, token output.

STAGES lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame that is
written as Parquet and read again as the docs of the next. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from autotheta.llm import decontaminate, mixing, neardup, tokens, toxicity
from autotheta.llm.queries import held_out, table, tokenizer_path
from autotheta.sources.shared import keep

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _keyed(docs: DataFrame) -> tuple[DataFrame, bool]:
    """COLUMNS of ``docs`` with a ``key`` of each row, and whether the key is the id.

    It is where ids are whole and stand once. Else rows are numbered in the order of ids and texts, null ids last, so
    that rows of one id with different texts are different documents.
    """
    docs = docs.select(*COLUMNS)
    odd = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 OR doc_id IS NULL")
    if odd.limit(1).count() == 0:
        return docs.withColumn("key", F.col("doc_id")), True
    order = [F.asc_nulls_last("doc_id"), F.col("text"), F.col("lang"), F.col("source")]
    rows = docs.repartitionByRange(*order).sortWithinPartitions(*order)
    return keep(rows.withColumn("key", F.monotonically_increasing_id()), "keyed"), False


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity score of 0.3 or more go. Labels are learnt outside the held-out rows."""
    rows, plain = _keyed(docs)
    labels = table(spark, sf_dir, "labels").where(~held_out())
    if not plain:
        labels = labels.join(rows.select("doc_id", "key"), "doc_id").select(F.col("key").alias("doc_id"), "toxic")
    verdict = toxicity.score_toxicity(rows, labels, id_col="key")
    bad = verdict.where("predicted = 1").select(F.col("doc_id").alias("key"))
    return rows.join(bad, "key", "left_anti").select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group linked by five-word shingles at a similarity of 0.8 the least id stays, of equal ids one row."""
    rows, _ = _keyed(docs)
    verdict = neardup.near_duplicates(rows, size=5, num=80, den=100, id_col="key")
    gone = verdict.where("NOT kept").select(F.col("doc_id").alias("key"))
    return rows.join(gone, "key", "left_anti").select(*COLUMNS)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold ten words in a row of a benchmark item go."""
    rows, _ = _keyed(docs)
    verdict = decontaminate.decontaminate(rows, table(spark, sf_dir, "benchmark"), size=10, id_col="key")
    bad = verdict.where("n_hit > 0").select(F.col("doc_id").alias("key"))
    return rows.join(bad, "key", "left_anti").select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it: none, one or more rows."""
    rows = keep(docs.select(*COLUMNS).withColumn("row", F.monotonically_increasing_id()), "rows")
    copies = mixing.mix_sources(rows, row_col="row").where("copies > 0").select("row", "copies")
    mixed = rows.join(copies, "row").withColumn("copy", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("copies"))))
    return mixed.select(*COLUMNS)


def token_records(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids as binary records in ascending id order, read back: ``doc_id, start, n_tokens, ids_crc32``."""
    return tokens.read_shards(tokens.write_shards(docs, tokenizer_path(), end_id=2))


STAGES = [
    ("toxicity", drop_toxic),
    ("near duplicates", drop_near_duplicates),
    ("benchmark decontamination", drop_contaminated),
    ("mixing", mix),
    ("token output", token_records),
]
#: Calibrated scores, dependent rounding and tokenizer ids are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = keep(docs, "stage")
    return docs
