"""Quality by hierarchical empirical Bayes: a document's own evidence, its path's and its host's.

A logistic classifier on a dozen counts of the text gives each document's evidence. Hosts and paths pool
the evidence of their documents; by grouped aggregation each host's rate is shrunk to the global one and each path's
to its host's, the more the fewer documents there are and the less sites differ. A document's score adds its own log-odds and
those by which its path, without the document itself, differs from the rest.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from autotheta.llm import textkit
from autotheta.llm.toxicity import train_labels
from autotheta.sources.shared import keep, map_arrow

#: Labelled documents that the classifier is fitted on at most (those of least hash).
TRAIN_ROWS = 60_000
#: Words of a window in which distinct ones are counted.
WINDOW = 200
_UPPER, _LOWER, _DIGIT, _SIGN, _STOP, _LINE, _WIDE = (np.zeros(256, np.float32) for _ in range(7))
_UPPER[65:91] = 1
_LOWER[97:123] = 1
_DIGIT[48:58] = 1
_SIGN[list(b"#*$%&|<>{}[]=_~^@\\!?")] = 1
_STOP[list(b".,;:")] = 1
_LINE[10] = 1
_WIDE[0xC0:] = 1
FEATURES = ("log_words", "word_length", "upper", "digits", "signs", "stops", "lines", "wide", "distinct", "same_as_before", "long_words", "short_text", "very_short", "signs_any", "upper_most")


def measure(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """FEATURES of each row."""
    w = textkit.words(data, offsets, textkit.SPACED_LOWER)
    n = np.diff(w.split).astype(float)
    size = np.maximum(1, np.diff(offsets)).astype(float)

    def share(kind: np.ndarray) -> np.ndarray:
        c = np.concatenate([[0.0], np.cumsum(kind[data], dtype=np.float64)])
        return c[offsets[1:]] - c[offsets[:-1]]

    row = np.repeat(np.arange(len(n)), np.diff(w.split))
    h = w.hash if w.hash is not None else np.zeros(0, np.uint64)
    # Mean share of distinct words over the windows of WINDOW words, cut one after the other, so that length does not
    # matter; a text's last window ends with it and overlaps the one before, so that all are full where the text is.
    count = np.diff(w.split)
    windows = -(-count // WINDOW)
    of = np.repeat(np.arange(len(count)), windows)
    place = WINDOW * (np.arange(len(of)) - (np.cumsum(windows) - windows)[of])
    length = np.minimum(WINDOW, count[of])
    begin = w.split[:-1][of] + np.minimum(place, count[of] - length)
    inside = np.repeat(np.arange(len(of)), length)
    key = textkit.mix(h[textkit._ranges(begin, length)] + inside.astype(np.uint64) * textkit.U(0x9E3779B97F4A7C15))
    one = np.unique(key, return_index=True)[1]
    share_of = np.bincount(inside[one], minlength=len(of)) / np.maximum(1, length)
    distinct = np.bincount(of, share_of, minlength=len(n)) / np.maximum(1, windows)
    same = np.zeros(len(h))
    if len(h) > 1:
        same[1:] = (h[1:] == h[:-1]) & (row[1:] == row[:-1])
    total = lambda x: np.bincount(row, x, minlength=len(n))
    length = (w.end - w.start).astype(float)
    letters = np.maximum(1, share(_UPPER) + share(_LOWER))
    upper, signs = share(_UPPER) / letters, share(_SIGN) / size
    return np.stack([np.log1p(n), total(length) / np.maximum(1, n), upper, share(_DIGIT) / size, signs, share(_STOP) / size, share(_LINE) / np.maximum(1, n), share(_WIDE) / size, distinct, total(same) / np.maximum(1, n), total((length > 20).astype(float)) / np.maximum(1, n), (n < 20).astype(float), (n < 5).astype(float), (signs > 0.05).astype(float), (upper > 0.5).astype(float)], axis=1)


def fit(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Mean, scale and weights (the intercept last) of a logistic regression by Newton steps."""
    mean, scale = x.mean(0), x.std(0) + 1e-9
    z = np.hstack([np.clip((x - mean) / scale, -8, 8), np.ones((len(x), 1))])
    w = np.zeros(z.shape[1])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        hessian = (z * (p * (1 - p) + 1e-6)[:, None]).T @ z + ridge * np.eye(len(w))
        step = np.linalg.solve(hessian, z.T @ (y - p) - ridge * w)
        w = w + step * min(1.0, 3.0 / max(1e-9, float(np.abs(step).max())))
        if np.abs(step).max() < 1e-7:
            break
    return mean, scale, w


def _features(rows: DataFrame, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids, in order, and FEATURES of the documents with these ids (no more than the bounded sample)."""
    shared = rows.sparkSession.sparkContext.broadcast(ids)

    def run(batches):
        for b in batches:
            known = b.column(0).is_valid().to_numpy(zero_copy_only=False)
            b = b.filter(pa.array(known & np.isin(b.column(0).fill_null(0).to_numpy(), shared.value)))
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                x = measure(data, offsets)
                yield pa.RecordBatch.from_arrays([b.column(0)[lo:hi], pa.array(x.tolist(), pa.list_(pa.float64()))], ["doc_id", "x"])

    # Of rows that share an id the least features count, whichever the order.
    t = map_arrow(rows.select("doc_id", "text"), run, "doc_id bigint, x array<double>").groupBy("doc_id").agg(F.min("x").alias("x")).toArrow()
    found = t["doc_id"].to_numpy().astype(np.int64)
    order = np.argsort(found)
    return found[order], np.array(t["x"].to_pylist(), float).reshape(-1, len(FEATURES))[order]


def _evidence(rows: DataFrame, model: tuple) -> DataFrame:
    """``doc_id, host, path, evidence``: log-odds of good quality by the text alone."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        mean, scale, w = shared.value
        for b in batches:
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                z = np.clip((measure(data, offsets) - mean) / scale, -8, 8) @ w[:-1] + w[-1]
                yield pa.RecordBatch.from_arrays([b.column(0)[lo:hi], b.column(2)[lo:hi], b.column(3)[lo:hi], pa.array(np.clip(z, -20, 20))], ["doc_id", "host", "path", "evidence"])

    return map_arrow(rows, run, "doc_id bigint, host string, path string, evidence double")


def _strength(groups: DataFrame, good: str, n: str, mean: str) -> Column | float:
    """Pseudo-documents of the prior by moments: the less groups differ beyond chance, the more."""
    r = groups.agg(F.sum(F.col(n) * F.pow(F.col(good) / F.col(n) - F.col(mean), 2)).alias("v"), F.sum(F.col(mean) * (1 - F.col(mean))).alias("chance"), F.sum(n).alias("n"), F.avg(F.col(mean) * (1 - F.col(mean))).alias("m")).first()
    if not r["n"]:
        return 10.0
    between = max(1e-4, (r["v"] - r["chance"]) / r["n"])
    return float(min(1000.0, max(1.0, r["m"] / between - 1)))


def quality_by_site(docs: DataFrame, labels: DataFrame, host: Column, path: Column, train: Column | None = None, label_col: str = "quality", threshold: float = 0.5, limit: int = TRAIN_ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, host, path, evidence, host_rate, path_rate, score, kept``, one row per input row.

    ``host`` and ``path`` are expressions over ``docs``; a path belongs to its host. ``train`` limits the labels
    by a condition on ``doc_id``. Rates are posterior means of good documents, the document itself left out. Null
    hosts and paths are groups of their own; null and wordless texts have the evidence of empty texts. Without
    labels of both kinds evidence is 0 and all is kept. Repeated rows count each; other columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"), host.cast("string").alias("host"), path.cast("string").alias("path"))
    ids, y = train_labels(labels, label_col, train, limit)
    model = (np.zeros(len(FEATURES)), np.ones(len(FEATURES)), np.zeros(len(FEATURES) + 1))
    if len(ids) and y.min() != y.max():
        found, x = _features(rows, ids)
        y = y[np.searchsorted(ids, found)]
        if len(y) and y.min() != y.max():
            model = fit(x, y)
    d = keep(_evidence(rows, model), "evidence").withColumn("p", 1 / (1 + F.exp(-F.col("evidence"))))
    by_path = keep(d.groupBy("host", "path").agg(F.sum("p").alias("good"), F.count(F.lit(1)).alias("n")), "paths")
    by_host = by_path.groupBy("host").agg(F.sum("good").alias("host_good"), F.sum("n").alias("host_n"))
    mean = by_host.agg((F.sum("host_good") / F.sum("host_n")).alias("m")).first()["m"]
    mean = min(1 - 1e-6, max(1e-6, mean if mean is not None else 0.5))
    by_host = by_host.withColumn("mean", F.lit(mean))
    k_host = _strength(by_host, "host_good", "host_n", "mean")
    by_host = by_host.withColumn("host_mean", (F.col("host_good") + k_host * mean) / (F.col("host_n") + k_host)).withColumnRenamed("host", "h_")
    sites = by_path.join(by_host, F.col("host").eqNullSafe(F.col("h_"))).select(F.col("host").alias("h_"), F.col("path").alias("p_"), "good", "n", "host_good", "host_n", "host_mean")
    k_path = _strength(sites, "good", "n", "host_mean")
    out = d.join(sites, F.col("host").eqNullSafe(F.col("h_")) & F.col("path").eqNullSafe(F.col("p_")))
    host_rate = (F.col("host_good") - F.col("p") + k_host * mean) / (F.col("host_n") - 1 + k_host)
    out = out.withColumn("host_rate", host_rate)
    out = out.withColumn("path_rate", (F.col("good") - F.col("p") + k_path * F.col("host_rate")) / (F.col("n") - 1 + k_path))
    inside = F.least(F.greatest("path_rate", F.lit(1e-6)), F.lit(1 - 1e-6))
    score = 1 / (1 + F.exp(-(F.col("evidence") + F.log(inside / (1 - inside)) - float(np.log(mean / (1 - mean))))))
    return out.select("doc_id", "host", "path", "evidence", "host_rate", "path_rate", score.alias("score"), (score >= threshold).alias("kept"))
