"""Toxic passages as maximum-scoring segments.

Tokens are scored by their log-odds between toxic and other labelled documents, with Dirichlet priors that
come from the token's first bytes: a rare token is drawn to what its beginning says, that to no difference.
Scores are shrunk by their standard error and lowered by a drift, so that the expected score of other text is
negative. One linear scan a document then finds all maximal segments of positive score. Their significance
follows the extreme-value law of such maxima: scaled by lambda, less the logarithm of length times K. The sum
statistic of the highest segments, on that scale, becomes a probability by a logistic curve. The curve is fitted on
the labelled sample by FOLDS: each is scored by what the others alone teach.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from autotheta.llm import textkit
from autotheta.sources.shared import keep, map_arrow

#: Labelled documents the scores are learnt from at most (those of least hash); their tokens are all that a model scores.
TRAIN_ROWS, FOLDS = 60_000, 5
PREFIX, WEAK, STRONG, SHRINK, EFFECT, DRIFT = 4, 4.0, 36.0, 1.0, 1.0, 0.2


def prefix_hash(data: np.ndarray, w: textkit.Words, kind: textkit.WordClass = textkit.ALNUM_LOWER) -> np.ndarray:
    """Hash of the first PREFIX bytes of each word."""
    out = np.zeros(len(w), np.uint64)
    for k in range(PREFIX):
        at = w.start + k
        inside = at < w.end
        out[inside] = textkit.mix(out[inside] * textkit.U(31) + kind.table[data[at[inside]]])
    return out


def _token_counts(rows: DataFrame, ids: np.ndarray, toxic: np.ndarray, fold: np.ndarray) -> DataFrame:
    """``h, g, fold, toxic_docs, other_docs, other_tokens`` over the labelled documents; g is the prefix."""
    shared = rows.sparkSession.sparkContext.broadcast((ids, toxic, fold))
    names = ["h", "g", "fold", "toxic_docs", "other_docs", "other_tokens"]

    def run(batches):
        known, is_toxic, folds = shared.value
        parts: list = []

        def add_up(parts):
            key = np.concatenate([p[0] for p in parts])
            first, back = np.unique(key, return_index=True, return_inverse=True)[1:]
            sums = [np.bincount(back, np.concatenate([p[k] for p in parts])).astype(np.int64) for k in (4, 5, 6)]
            return (key[first], *(np.concatenate([p[k] for p in parts])[first] for k in (1, 2, 3)), *sums)

        for b in batches:
            number = b.column(0).fill_null(-1).to_numpy()
            at = np.minimum(np.searchsorted(known, number), len(known) - 1)
            hit = known[at] == number
            label, of = is_toxic[at[hit]], folds[at[hit]]
            text = b.column(1).filter(pa.array(hit))
            for lo, hi, data, offsets in textkit.blocks(text):
                w = textkit.words(data, offsets, textkit.ALNUM_LOWER)
                if not len(w):
                    continue
                row = np.repeat(np.arange(hi - lo), np.diff(w.split))
                key = textkit.mix(w.hash + row.astype(np.uint64) * textkit.U(0x9E3779B97F4A7C15))
                first, tokens = np.unique(key, return_index=True, return_counts=True)[1:]
                bad, f = label[lo:hi][row[first]].astype(np.float64), of[lo:hi][row[first]]
                of_fold = textkit.mix(w.hash[first] + f.astype(np.uint64))
                parts.append((of_fold, w.hash[first], prefix_hash(data, w)[first], f, bad, 1 - bad, tokens * (1 - bad)))
                if len(parts) >= 8:
                    parts = [add_up(parts)]
        if parts:
            out = add_up(parts)[1:]
            for a in range(0, len(out[0]), 200_000):
                yield pa.RecordBatch.from_arrays([pa.array(x[a : a + 200_000].view(np.int64)) for x in out], names)

    counted = map_arrow(rows, run, "h bigint, g bigint, fold bigint, toxic_docs bigint, other_docs bigint, other_tokens bigint")
    return counted.groupBy("h", "g", "fold").agg(*[F.sum(c).alias(c) for c in names[3:]])


@dataclass
class Scores:
    """Scores by token and, for tokens without one, by prefix; both sorted by hash. Others have score 0."""

    tokens: np.ndarray
    token_score: np.ndarray
    prefixes: np.ndarray
    prefix_score: np.ndarray

    def of(self, data: np.ndarray, w: textkit.Words) -> np.ndarray:
        out = np.zeros(len(w))
        if not len(w):
            return out
        rest = np.ones(len(w), bool)
        for h, keys, values in ((w.hash, self.tokens, self.token_score), (prefix_hash(data, w), self.prefixes, self.prefix_score)):
            if len(keys):
                k = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
                hit = rest & (keys[k] == h)
                out[hit] = values[k[hit]]
                rest &= ~hit
        return out - DRIFT


def _log_odds(toxic, other, prior_toxic, prior_other, n_toxic: float, n_other: float):
    """Log-odds with a prior, moved towards 0 by SHRINK standard errors; 0 below EFFECT, where topics differ, not tone."""
    a, b = toxic + prior_toxic, other + prior_other
    delta, error = F.log(a / n_toxic) - F.log(b / n_other), F.sqrt(1 / a + 1 / b)
    shrunk = F.signum(delta) * F.greatest(F.lit(0.0), F.abs(delta) - SHRINK * error)
    return F.when(F.abs(shrunk) >= EFFECT, shrunk).otherwise(0.0)


def learn(counts: DataFrame, toxic: np.ndarray) -> tuple[Scores, float]:
    """Scores and lambda from counts by token (and fold, if there are several) and the labels of their documents."""
    n_toxic, n_other = max(1.0, float(toxic.sum())), max(1.0, float(len(toxic) - toxic.sum()))
    counts = counts.groupBy("h", "g").agg(*[F.sum(c).alias(c) for c in ("toxic_docs", "other_docs", "other_tokens")])
    share = n_toxic / (n_toxic + n_other)
    # Priors: of a prefix no difference, of a token its prefix.
    by_prefix = counts.groupBy("g").agg(F.sum("toxic_docs").alias("gt"), F.sum("other_docs").alias("go"))
    prefix_score = _log_odds(F.col("gt"), F.col("go"), F.lit((WEAK + STRONG) * share), F.lit((WEAK + STRONG) * (1 - share)), n_toxic, n_other)
    by_prefix = keep(by_prefix.withColumn("g_score", prefix_score), "prefixes")
    joined = counts.join(by_prefix, "g")
    seen = F.col("gt") - F.col("toxic_docs") + F.col("go") - F.col("other_docs")
    strength = WEAK + STRONG * seen / (seen + 50.0)
    prior_toxic = strength * (F.col("gt") - F.col("toxic_docs") + 2 * share) / (seen + 2.0)
    prior_other = strength * (F.col("go") - F.col("other_docs") + 2 * (1 - share)) / (seen + 2.0)
    scored = keep(joined.withColumn("score", _log_odds(F.col("toxic_docs"), F.col("other_docs"), prior_toxic, prior_other, n_toxic, n_other)).select("h", "score", "g_score", "other_tokens"), "scores")
    # No more than the sample's own tokens; where both scores are 0 none need be kept.
    top = scored.where(F.abs("score") + F.abs("g_score") > 0).select("h", "score").toArrow()
    prefixes = by_prefix.where(F.abs("g_score") > 0).select("g", "g_score").toArrow()

    def sorted_by_hash(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        h = t.column(0).to_numpy().astype(np.int64).view(np.uint64)
        order = np.argsort(h)
        return h[order], t.column(1).to_numpy()[order]

    histogram = scored.groupBy(F.round("score", 1).alias("s")).agg(F.sum("other_tokens").alias("n")).toArrow()
    lam = solve_lambda(histogram["s"].to_numpy() - DRIFT, histogram["n"].to_numpy().astype(float))
    return Scores(*sorted_by_hash(top), *sorted_by_hash(prefixes)), lam


def solve_lambda(score: np.ndarray, weight: np.ndarray) -> float:
    """The positive root of ``sum(p * exp(lambda * score)) = 1``; 1 where there is none."""
    keep_ = weight > 0
    if not keep_.any() or score[keep_].max() <= 0 or (score * weight).sum() >= 0:
        return 1.0
    s, p = score[keep_], weight[keep_] / weight[keep_].sum()
    low, high = 1e-6, 1.0
    while (p * np.exp(np.minimum(700, high * s))).sum() < 1 and high < 64:
        high *= 2
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if (p * np.exp(np.minimum(700, mid * s))).sum() < 1 else (low, mid)
    return high


def maximal_segments(score: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments ``(from, to, sum)``, in order, in linear time.

    Each candidate keeps the running sums before and after it. A new one joins the nearest earlier one
    whose sum before is smaller, if that one's sum after is smaller too, with all that lies between.
    """
    found: list[list] = []  # from, to, sum before, sum after, index of the nearest earlier one with a smaller sum before
    sums = np.concatenate([[0.0], np.cumsum(score)])
    for i in np.flatnonzero(score > 0).tolist():
        item = [i, i + 1, float(sums[i]), float(sums[i + 1]), -1]
        while True:
            j = len(found) - 1
            while j >= 0 and found[j][2] >= item[2]:
                j = found[j][4]
            if j < 0 or found[j][3] >= item[3]:
                item[4] = j
                found.append(item)
                break
            item[0], item[2] = found[j][0], found[j][2]
            del found[j:]
    return [(a, b, after - before) for a, b, before, after, _ in found]


def pooled(scores: list[float], lam: float, n_words: int) -> float:
    """The best sum statistic over the 1, 2, ... highest segments of a text, in units of its extreme-value law."""
    best, total, log_n = -math.log(max(1, n_words)), 0.0, math.log(max(1, n_words))
    for r, s in enumerate(sorted(scores, reverse=True), 1):
        total += lam * s - log_n + math.log(r)
        best = max(best, total)
    return best


def segments(rows: DataFrame, scores: Scores, lam: float) -> DataFrame:
    """``doc_id, n_words, best, pooled, spans``: maximal segments of each text with a score of 1 / lambda or more."""
    shared = rows.sparkSession.sparkContext.broadcast(scores)
    span = pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64()), ("score", pa.float64())]))

    def run(batches):
        for b in batches:
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                w = textkit.words(data, offsets, textkit.ALNUM_LOWER)
                s = shared.value.of(data, w)
                best, spans = np.zeros(hi - lo), [[] for _ in range(hi - lo)]
                x = -np.log(np.maximum(1, np.diff(w.split)))
                for r in np.unique(np.searchsorted(w.split, np.flatnonzero(s > 0), "right") - 1).tolist():
                    found = maximal_segments(s[w.split[r] : w.split[r + 1]])
                    best[r] = max(x[2] for x in found)
                    x[r] = pooled([z for _, _, z in found], lam, int(w.split[r + 1] - w.split[r]))
                    spans[r] = [{"from": a, "to": e, "score": z} for a, e, z in found if lam * z >= 1]
                yield pa.RecordBatch.from_arrays([b.column(0)[lo:hi], pa.array(np.diff(w.split)), pa.array(best), pa.array(x), pa.array(spans, span)], ["doc_id", "n_words", "best", "pooled", "spans"])

    return map_arrow(rows, run, "doc_id bigint, n_words bigint, best double, pooled double, spans array<struct<from: bigint, to: bigint, score: double>>")


def fit_logistic(x: np.ndarray, positive: np.ndarray, negative: np.ndarray) -> tuple[float, float]:
    """Slope and intercept of a logistic curve on counted bins, with half a row of either kind in each."""
    w, b = 0.5, 0.0
    y1, y0 = positive + 1e-3, negative + 1e-3
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(w * x + b, -30, 30)))
        g, q = y1 - (y1 + y0) * p, (y1 + y0) * p * (1 - p)
        hessian = np.array([[(q * x * x).sum() + 0.1, (q * x).sum()], [(q * x).sum(), q.sum() + 0.1]])
        step = np.linalg.solve(hessian, np.array([(g * x).sum() - 0.1 * w, g.sum() - 0.1 * b]))
        size = min(1.0, 2.0 / max(1e-9, float(np.abs(step).max())))
        w, b = w + size * step[0], b + size * step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(w), float(b)


def train_labels(labels: DataFrame, label_col: str, train: Column | None, limit: int, id_col: str = "doc_id") -> tuple[np.ndarray, np.ndarray]:
    """Sorted ids and 0/1 labels of at most ``limit`` labelled documents, those of least hash."""
    rows = labels.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(label_col).cast("int").alias("y")).where("doc_id IS NOT NULL AND y IS NOT NULL")
    if train is not None:
        rows = rows.where(train)
    t = rows.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(limit).toArrow()
    ids, y = t["doc_id"].to_numpy().astype(np.int64), t["y"].to_numpy().astype(np.int64)
    order = np.argsort(ids)
    return ids[order], y[order]


def folds(ids: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Fold of each labelled document, by the hash of its id within its kind, so that both kinds are in all folds."""
    order = np.lexsort((ids, textkit.mix(ids.astype(np.int64).view(np.uint64)), y))
    place = np.empty(len(ids), np.int64)
    place[order] = np.arange(len(ids))
    return place % FOLDS


def score_toxicity(docs: DataFrame, labels: DataFrame, train: Column | None = None, label_col: str = "toxic", threshold: float = 0.3, limit: int = TRAIN_ROWS, e_value: float = 0.01, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, score, predicted, n_words, best, passages``, one row per input row.

    ``score`` is the probability that a text is toxic, ``passages`` its word ranges that a text of its length holds by
    chance less than ``e_value`` times. ``train`` limits the labels learnt from, as a condition on ``doc_id``.
    Null, empty and wordless texts get the score of a text without any toxic sign. Repeated labels of a
    document count as toxic if one is; null labels and ids are left out. Without labels of both kinds all
    scores are 0. Repeated rows each get their row; other columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    ids, y = train_labels(labels, label_col, train, limit)
    if not len(ids) or y.min() == y.max():
        none = F.array().cast("array<struct<from: bigint, to: bigint, score: double>>")
        return rows.select("doc_id", F.lit(0.0).alias("score"), F.lit(0).alias("predicted"), F.lit(0).cast("bigint").alias("n_words"), F.lit(0.0).alias("best"), none.alias("passages"))
    spark = docs.sparkSession
    sample = spark.createDataFrame(pa.table({"i": ids, "y": y}))
    labelled = keep(rows.join(F.broadcast(sample), F.col("doc_id") == F.col("i")).select("doc_id", "text"), "labelled")  # TRAIN_ROWS documents at most
    fold = folds(ids, y)
    counts = keep(_token_counts(labelled, ids, y, fold), "tokens")
    scores, lam = learn(counts, y)
    found = keep(segments(rows, scores, lam), "segments")
    squeezed = F.least(F.greatest("pooled", F.lit(-12.0)), F.lit(30.0))
    bins, mean, weight = {}, 0.0, 0
    for f in range(FOLDS):
        if not (fold == f).any():
            continue
        scores, lam_h = learn(counts.where(F.col("fold") != f), y[fold != f])
        mine = F.broadcast(spark.createDataFrame(pa.table({"i": ids[fold == f], "y": y[fold == f]})))
        seen = segments(labelled.join(mine, F.col("doc_id") == F.col("i"), "left_semi"), scores, lam_h).join(mine, F.col("doc_id") == F.col("i"))
        scaled = F.lit(lam_h) * F.col("best") - F.log(F.greatest(F.col("n_words"), F.lit(1)).cast("double"))
        plain = (F.col("y") == 0) & (F.col("best") > 0)
        grouped = seen.groupBy(F.round(squeezed * 4).alias("x")).agg(F.sum("y").alias("y1"), F.sum(1 - F.col("y")).alias("y0"), F.sum(F.when(plain, scaled)).alias("scaled"), F.count_if(plain).alias("plain"))
        for r in grouped.collect():  # 170 rows at most
            y1, y0 = bins.get(r["x"], (0, 0))
            bins[r["x"]] = (y1 + r["y1"], y0 + r["y0"])
            mean, weight = mean + (r["scaled"] or 0.0), weight + r["plain"]
    x = np.array(sorted(bins), float)
    y1, y0 = (np.array([bins[k][j] for k in sorted(bins)], float) for j in (0, 1))
    x = x / 4
    location = (mean / weight if weight else 0.0) - 0.5772  # ln K, from the mean of the law
    slope, intercept = fit_logistic(x, y1, y0)
    score = 1 / (1 + F.exp(-(F.lit(slope) * squeezed + intercept)))
    expected = F.lit(math.log(e_value))
    passages = F.filter("spans", lambda s: F.log(F.greatest(F.col("n_words"), F.lit(1)).cast("double")) + location - lam * s["score"] <= expected)
    return found.select("doc_id", score.alias("score"), (score >= threshold).cast("int").alias("predicted"), "n_words", "best", passages.alias("passages"))
