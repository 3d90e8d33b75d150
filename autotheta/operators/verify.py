"""Verification of met pairs no further than a band of thresholds needs.

What a pair has seen and the places of its last meeting bound its key from both sides, and more meetings of lower bands tighten
them. Only pairs that may lie in the band and are not yet placed by their bounds are looked at behind the last meeting. The
bounds are columns of the join that finds the pairs, so a pair that is put off costs no element.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from autotheta.functions.sims import SetSimilarity
from autotheta.operators.simjoin import most_possible

#: Thresholds of a band among which pairs are placed by their bounds; with more, keys are completed.
GRID = 64


def merge_meetings(waiting: DataFrame, met: DataFrame, columns: list[str]) -> DataFrame:
    """Pairs with all that they have seen so far, and what of it they had seen before; exact overlaps and keys stay."""
    zero, none = F.lit(0).cast("bigint"), {"o": F.lit(None).cast("bigint"), "key": F.lit(None).cast("double")}
    both = met.withColumns({"was": zero, **none}).unionByName(waiting.withColumn("was", F.col("seen")))
    return both.groupBy(*columns).agg(F.sum("seen").alias("seen"), F.max("i").alias("i"), F.max("j").alias("j"), F.sum("was").alias("was"), F.max("o").alias("o"), F.max("key").alias("key"))


def placed(key: Column, grid: list[float]) -> Column:
    """The greatest threshold of an ascending ``grid`` that a key reaches, or null."""
    return F.array_max(F.filter(F.array(*[F.lit(x) for x in grid]), lambda x: x <= key))


def classify(pairs: DataFrame, sim: SetSimilarity, low: float, bounds: str, grid: list[float] | None) -> DataFrame:
    """Add ``top``, the greatest key still possible, and ``fate``.

    ``later``: the band cannot hold the pair. ``in``: its key is known and in the band, or both bounds lie between the same two
    thresholds of ``grid`` (then ``key`` is the lower one, and ``o`` is null). ``open``: its rest has to be looked at.
    """
    top = F.coalesce("key", most_possible(sim, low, bounds))
    least = F.coalesce("key", sim.least(F.col("seen"), F.col("nr"), F.col("ns")))
    rows = pairs.withColumns({"top": top, "least": least})
    known = F.col("key").isNotNull() | (F.col("least") == F.col("top"))
    fate = F.when(F.col("top") < low, "later")
    if grid is None:
        rows = rows.withColumn("fate", fate.when(known, "in").otherwise("open"))
        return rows.withColumn("key", F.when(known, F.col("top")).otherwise(F.col("key"))).drop("least")
    at = placed(F.col("least"), grid)
    rows = rows.withColumns({"at": at, "fate": fate.when(at.eqNullSafe(placed(F.col("top"), grid)) & at.isNotNull(), "in").otherwise("open")})
    return rows.withColumn("key", F.when(F.col("fate") == "in", F.col("at")).otherwise(F.col("key"))).drop("least", "at")


def due_band(top, lows: list[float]):
    """Number of the band (lows in descending order) that holds a best possible key; their count if none does."""
    ascending = np.array(lows[::-1])
    if isinstance(top, (int, float, np.ndarray)):
        return len(lows) - np.searchsorted(ascending, top, "right")
    return F.aggregate(F.array(*[F.lit(float(x)) for x in lows]), F.lit(0), lambda n, x: n + (top < x).cast("int"))
