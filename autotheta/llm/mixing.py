"""Mixing sources to target weights by pivotal dependent rounding.

Every document of a source is due the same real number of copies, its source's target over its size.
The whole part is given to all; the fractional parts are rounded in pairs: mass (words) moves at random
from one document of a pair to the other until one of them is whole, which keeps each document's
expectation and the source's sum of words. Groups of a source round what they hold and pass one
remaining fraction on; remainders meet in a tree of fixed fan-in, so no task sees more than a group.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from autotheta.llm import textkit
from autotheta.sources.shared import keep, map_arrow

#: Expected documents in a group of the first round, and remainders in one of the later rounds.
GROUP_ROWS, FAN_IN = 2000, 64


def sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", row_col: str | None = None) -> DataFrame:
    """``doc_id, source, size, row``: words of each text, 0 for null; ``row`` is carried along."""

    def count(batches):
        for b in batches:
            out = [np.zeros(0, np.int64)]
            for _, _, data, offsets in textkit.blocks(b.column(2)):
                out.append(np.diff(textkit.bounds(data, offsets, textkit.SPACED).split))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(np.concatenate(out)), b.column(3)], ["doc_id", "source", "size", "row"])

    rows = docs.select(F.col(id_col).cast("bigint").alias("i"), F.col(source_col).cast("string").alias("s"), F.col(text_col).cast("string").alias("t"), F.col(row_col).cast("bigint").alias("r") if row_col else F.lit(0).cast("bigint").alias("r"))
    return map_arrow(rows, count, "doc_id bigint, source string, size bigint, row bigint")


def targets(sized: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0) -> DataFrame:
    """``source, place, n_docs, source_size, target``: the weights, repeated over the sources in code-point
    order (null last), share the sum of all sizes; no target is above ``cap`` times its source's size, and
    what is cut goes to the others by weight. One row a source: the windows see no documents.
    """
    every = Window.partitionBy()
    order = Window.orderBy(F.asc_nulls_last("source"))
    w = F.array(*[F.lit(float(x)) for x in weights])
    s = sized.groupBy("source").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("size").alias("source_size"))
    s = s.withColumn("place", F.row_number().over(order)).withColumn("w", F.element_at(w, ((F.col("place") - 1) % len(weights) + 1).cast("int")))
    s = s.withColumn("most", F.col("source_size") * F.lit(float(cap))).withColumn("full_at", F.col("most") / F.col("w"))
    before = Window.orderBy("full_at", "place").rowsBetween(Window.unboundedPreceding, -1)
    s = s.withColumn("level", (F.sum("source_size").over(every) - F.coalesce(F.sum("most").over(before), F.lit(0.0))) / (F.sum("w").over(every) - F.coalesce(F.sum("w").over(before), F.lit(0.0))))
    level = F.min(F.when(F.col("level") <= F.col("full_at"), F.struct("full_at", "place", "level"))).over(every)["level"]
    s = s.withColumn("target", F.least(F.col("most"), F.col("w") * F.coalesce(level, F.lit(0.0))))
    return s.select("source", "place", "n_docs", "source_size", "target")


def _draws(ids: np.ndarray, seed: int, level: int) -> np.ndarray:
    h = textkit.mix(ids.astype(np.int64).view(np.uint64) * textkit.U(0xD1342543DE82EF95) + textkit.U((seed * 1000003 + level * 7919 + 1) & (2**64 - 1)))
    return (textkit.mix(h) >> textkit.U(11)).astype(np.float64) / float(1 << 53)


def pivot(p: np.ndarray, size: np.ndarray, draw: np.ndarray) -> np.ndarray:
    """Round ``p`` in (0, 1) in order; at most one stays fractional. Keeps ``sum(p * size)`` but for rounding errors."""
    p = p.astype(np.float64).copy()
    held = -1
    for i in range(len(p)):
        if not 1e-12 < p[i] < 1 - 1e-12:
            p[i] = round(p[i])
            continue
        if held < 0:
            held = i
            continue
        a, b = held, i
        up, down = min(size[a] * (1 - p[a]), size[b] * p[b]), min(size[a] * p[a], size[b] * (1 - p[b]))
        move = up if draw[i] * (up + down) < down else -down
        p[a], p[b] = p[a] + move / size[a], p[b] - move / size[b]
        held = -1
        for k in (a, b):
            if not 1e-12 < p[k] < 1 - 1e-12:
                p[k] = round(p[k])
            else:
                held = k
    return p


def _round(rows: DataFrame, seed: int, level: int, last: bool) -> DataFrame:
    def run(t: pa.Table) -> pa.Table:
        ids = t["doc_id"].combine_chunks().fill_null(0).to_numpy()
        size, p = t["size"].to_numpy(), t["part"].to_numpy()
        order = np.lexsort((t["row"].to_numpy(), ids, -size))  # large first: what stays fractional at the end is then small
        draw, out = _draws(ids, seed, level), p.copy()
        out[order] = pivot(p[order], size[order], draw[order])
        if last:
            rest = (out > 0) & (out < 1)  # one document of a source at most: to the nearer side of the target
            out[rest] = (out[rest] + 1e-9 * (_draws(ids, seed, level + 100)[rest] - 0.5) > 0.5).astype(np.float64)
        return t.set_column(t.schema.get_field_index("part"), "part", pa.array(out))

    return rows.groupBy("place", "bucket").applyInArrow(run, rows.schema)


def mix_sources(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0, seed: int = 17, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", row_col: str | None = None) -> DataFrame:
    """Copies of every document in the mix: ``doc_id, size, source_size, target, copies, taken, row``.

    One row per input row. ``copies`` is whole and at most ``ceil(cap)``; the words taken of a source miss its
    target by less than its largest document. Draws depend on the seed and the ids alone, so reruns agree.
    Texts that are null or without words have size 0 and ``taken`` 0; a null source is a source, the last;
    a null id counts as 0 for the draws; repeated rows are documents of their own; an empty table gives no
    rows. ``row_col`` may name a key of rows to carry along. Other columns are ignored.
    """
    sized = keep(sizes(docs, id_col, text_col, source_col, row_col), "sizes")
    source = keep(targets(sized, weights, cap), "targets")
    most = source.agg(F.max("n_docs")).first()[0] or 0
    s = source.withColumnRenamed("source", "source_")
    rows = sized.join(s, sized["source"].eqNullSafe(s["source_"])).withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
    rows = rows.withColumn("whole", F.floor(F.col("rate") + F.lit(1e-9))).withColumn("part", F.greatest(F.lit(0.0), F.col("rate") - F.col("whole")))
    buckets = F.ceil(F.col("n_docs") / GROUP_ROWS)
    rows = rows.select("doc_id", "row", "size", "source_size", "target", "place", "whole", "part", F.pmod(F.xxhash64("doc_id", "row", "size", F.lit(seed)), buckets).alias("bucket"))
    idle = rows.where("size = 0").withColumn("part", F.lit(0.0))
    left, level, buckets_left, done = rows.where("size > 0"), 0, math.ceil(most / GROUP_ROWS), []
    while True:
        out = keep(_round(left, seed, level, buckets_left <= 1), "round")
        if buckets_left <= 1:
            done.append(out)
            break
        done.append(out.where("part = 0 OR part = 1"))
        left = out.where("part > 0 AND part < 1").withColumn("bucket", F.floor(F.col("bucket") / FAN_IN))
        level, buckets_left = level + 1, math.ceil(buckets_left / FAN_IN)
    mixed = idle
    for x in done:
        mixed = mixed.unionByName(x)
    copies = (F.col("whole") + F.col("part")).cast("bigint")
    return mixed.select("doc_id", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"), "row")
