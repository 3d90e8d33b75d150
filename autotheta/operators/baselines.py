"""Tuning a threshold by labels: the baselines of the experiments, with the truth in the place of a human."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from autotheta.operators.measures import accuracy_curve, best_f1_threshold
from autotheta.sources.shared import keep


def sampled(id_: Column, rate: float, seed: str = "sample") -> Column:
    """A deterministic sample by the hash of the id."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit(seed), id_.cast("string"))), 1, 6), 16, 10).cast("bigint")
    return h % 10000 < round(rate * 10000)


@dataclass
class Tuned:
    theta: DataFrame
    labels: int


def tune_by_sampling(pairs: DataFrame, truth: DataFrame, size_r: int, size_s: int, r_ids: DataFrame, s_ids: DataFrame, rate: float, seed: str = "sample") -> DataFrame:
    """``key, labels``: the best threshold on a sample of the larger side, all of whose pairs are labelled.

    No row if no sampled pair shares anything.
    """
    side = "r" if size_r >= size_s else "s"
    ids, other = (r_ids, size_s) if side == "r" else (s_ids, size_r)
    n = ids.where(sampled(F.col("id"), rate, seed)).agg((F.count(F.lit(1)) * other).cast("bigint").alias("labels"))
    take = sampled(F.col(side), rate, seed)
    return best_f1_threshold(pairs.where(take), truth.where(take)).select("key", "f1").crossJoin(n)


@dataclass
class ActiveRun:
    theta: float | None
    labels: int
    trace: list[tuple[int, float]] = field(default_factory=list)
    asked: list[tuple[int, int, bool]] = field(default_factory=list)


class _Near:
    """Labelled pairs around thresholds: read in windows of the ``size`` nearest above and below, again when one is left."""

    def __init__(self, marked: DataFrame, size: int):
        self.marked, self.size = marked, size
        self.rows: dict[tuple[int, int], tuple[float, int, bool]] = {}
        self.low, self.high = np.inf, -np.inf

    def read(self, theta: float) -> None:
        above = self.marked.where(F.col("key") >= theta).orderBy("key", "h", "r", "s").limit(self.size).collect()
        below = self.marked.where(F.col("key") < theta).orderBy(F.desc("key"), "h", "r", "s").limit(self.size).collect()
        self.rows = {(x["r"], x["s"]): (x["key"], x["h"], x["hit"]) for x in above + below}
        # Inside these ends nothing is missing.
        self.high = above[-1]["key"] if len(above) == self.size else np.inf
        self.low = below[-1]["key"] if len(below) == self.size else -np.inf

    def nearest(self, theta: float, asked: set[tuple[int, int]]) -> tuple[int, int] | None:
        for again in (False, True):
            if again or not self.low < theta < self.high:
                self.read(theta)
            free = [(abs(key - theta), -key, h, *pair) for pair, (key, h, _) in self.rows.items() if pair not in asked]
            best = min(free, default=None)
            if again or (best is not None and self.low < theta - best[0] and theta + best[0] < self.high):
                return best[3:] if best is not None else None
        return None


def tune_by_active(pairs: DataFrame, truth: DataFrame, budget: int) -> ActiveRun:
    """Label the pair that the current threshold is least sure of, again and again; of ties that of highest similarity,
    then of least hash of its ids.

    The classifier is the threshold of best F1 on the labelled pairs (of ties the largest); unsure is near to it; the first
    is the middle of the range. Only pairs that share something are asked for, each once, and its own label is looked
    up. The driver holds the pairs around the threshold, 2 * ``budget`` + 2 at a time, never all levels.
    """
    hit = truth.select("r", "s").distinct().withColumn("hit", F.lit(True))
    marked = keep(pairs.select("r", "s", "key", F.xxhash64("r", "s").alias("h")).join(hit, ["r", "s"], "left").withColumn("hit", F.coalesce("hit", F.lit(False))), "marked")
    ends = marked.agg(F.min("key").alias("low"), F.max("key").alias("high"), F.count(F.lit(1)).alias("n")).first()
    if not ends["n"]:
        return ActiveRun(None, 0)
    theta, run, near, asked, labels = float((ends["high"] + ends["low"]) / 2), ActiveRun(None, 0), _Near(marked, budget + 1), set(), []
    while run.labels < min(budget, ends["n"]):
        pair = near.nearest(theta, asked)
        key, _, yes = near.rows[pair]
        asked.add(pair)
        labels.append((key, yes))
        run.labels += 1
        run.asked.append((*pair, yes))
        theta = best_threshold(labels)
        run.trace.append((run.labels, theta))
    run.theta = theta
    return run


def best_threshold(labels: list[tuple[float, bool]]) -> float:
    """The value of best F1 among labelled ``(key, is true)``, the largest of ties."""
    ordered = sorted(labels, key=lambda x: -x[0])
    total, tp, best = sum(y for _, y in ordered), 0, (-1.0, 0.0)
    for k, (key, yes) in enumerate(ordered, 1):
        tp += yes
        if k == len(ordered) or ordered[k][0] != key:
            best = max(best, (2 * tp / max(1, k + total), key))
    return best[1]


def labels_to_match(run: ActiveRun, curve: list[tuple[float, float]], f1: float, within: float = 0.01) -> int | None:
    """Labels after which a trace's threshold stays within ``within`` of an F1; ``curve`` is (key, f1)."""
    value = dict(curve)
    good = [value.get(theta, 0.0) >= f1 - within for _, theta in run.trace]
    for k in range(len(good)):
        if all(good[k:]):
            return run.trace[k][0]
    return None


def label_cost(labels: int, seconds_each: float = 1.0, join_seconds: float = 0.0) -> float:
    """End-to-end seconds of a label-driven approach."""
    return labels * seconds_each + join_seconds


def perturbed(theta: Column, by: float) -> Column:
    """A threshold moved, within 0 and 1."""
    return F.least(F.greatest(theta + F.lit(by), F.lit(0.0)), F.lit(1.0))


def sensitivity(pairs: DataFrame, truth: DataFrame, by: float = 0.1) -> DataFrame:
    """``shift, theta, f1`` at the best threshold and ``by`` above and below it; below the last value 0 pairs more."""
    curve = accuracy_curve(pairs, truth)
    best = best_f1_threshold(pairs, truth).select(F.col("key").alias("best"))
    shifts = F.explode(F.array(*[F.struct(F.lit(n).alias("shift"), F.lit(x).alias("x")) for n, x in (("above", by), ("best", 0.0), ("below", -by))]))
    three = best.select("best", shifts.alias("e")).select(F.col("e.shift").alias("shift"), perturbed(F.col("best"), 0.0).alias("best"), F.least(F.greatest(F.col("best") + F.col("e.x"), F.lit(0.0)), F.lit(1.0)).alias("theta"))
    # The join at theta is that at the least value of at least theta.
    hit = three.join(curve, F.col("key") >= F.col("theta"), "left").groupBy("shift", "theta").agg(F.min_by("f1", "key").alias("f1"))
    return hit.select("shift", "theta", F.coalesce("f1", F.lit(0.0)).alias("f1"))
