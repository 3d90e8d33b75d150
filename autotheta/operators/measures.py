"""Accuracy and dataset measures, each one aggregation over pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from autotheta.operators.objectives import running


def _f1(tp, n, total):
    p = F.when(n > 0, tp / n).otherwise(0.0)
    r = F.when(total > 0, tp / total).otherwise(0.0)
    return p.alias("precision"), r.alias("recall"), F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0).alias("f1")


def accuracy(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """``tp, n_join, n_true, precision, recall, f1`` of joined pairs."""
    marked = pairs.select("r", "s").distinct().join(truth.distinct().withColumn("hit", F.lit(1)), ["r", "s"], "left")
    found = marked.agg(F.count(F.lit(1)).alias("n_join"), F.count("hit").alias("tp"))
    total = truth.distinct().agg(F.count(F.lit(1)).alias("n_true"))
    row = found.crossJoin(total)
    return row.select("tp", "n_join", "n_true", *_f1(F.col("tp"), F.col("n_join"), F.col("n_true")))


def accuracy_curve(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """The same at every similarity value: ``key, n_join, tp, precision, recall, f1``."""
    marked = pairs.select("r", "s", "key").join(truth.distinct().withColumn("hit", F.lit(1)), ["r", "s"], "left")
    return _curve(marked.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.count("hit").alias("t")), truth)


def accuracy_curve_of(joins: DataFrame, true_keys: DataFrame, truth: DataFrame) -> DataFrame:
    """The same from counts ``key, n`` of pairs and the keys of the true pairs that share anything."""
    counts = joins.select("key", "n", F.lit(0).cast("bigint").alias("t")).unionByName(true_keys.select("key", F.lit(0).cast("bigint").alias("n"), F.lit(1).cast("bigint").alias("t")))
    return _curve(counts.groupBy("key").agg(F.sum("n").alias("n"), F.sum("t").alias("t")), truth)


def _curve(by_level: DataFrame, truth: DataFrame) -> DataFrame:
    rows = running(by_level, {"n_join": "n", "tp": "t"}).select("key", "n_join", "tp").crossJoin(truth.distinct().agg(F.count(F.lit(1)).alias("n_true")))
    return rows.select("key", "n_join", "tp", *_f1(F.col("tp"), F.col("n_join"), F.col("n_true")))


def best_f1_threshold(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """The value of best F1 against the truth, the largest of ties (of F1 to 12 digits)."""
    return accuracy_curve(pairs, truth).orderBy(F.desc(F.round("f1", 12)), F.desc("key")).limit(1)


def at_threshold(pairs: DataFrame, truth: DataFrame, theta) -> DataFrame:
    return accuracy(pairs.where(F.col("key") >= theta), truth)


def dataset_stats(r: DataFrame, s: DataFrame, truth: DataFrame | None) -> DataFrame:
    """Sizes, longest and mean text of both sides, number of true pairs."""

    def side(df: DataFrame, x: str) -> DataFrame:
        n = F.length(F.coalesce("text", F.lit("")))
        return df.agg(F.count(F.lit(1)).alias(f"n_{x}"), F.max(n).cast("bigint").alias(f"max_{x}"), F.round(F.avg(n), 6).alias(f"avg_{x}"))

    out = side(r, "r").crossJoin(side(s, "s"))
    return out.crossJoin(truth.distinct().agg(F.count(F.lit(1)).alias("n_true"))) if truth is not None else out
