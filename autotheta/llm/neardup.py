"""Near-duplicate detection on word shingles with bottom-k sketches from one hash function.

A document's set is its distinct word shingles; its sketch the ``k`` least shingle hashes, in order. Equal sets
are one class and are never compared. Inverted lists over the retained values generate overlaps: a list's key is a
run of neighbouring retained values, as values that two sets share are neighbours in both sketches wherever no
unshared one falls between. With similarity t and runs of 4 among 80 values the chance that a linked pair shares
none is below 1e-9 at t = 0.85 and 1e-7 at 0.8; sets small enough that unshared elements could cut every
run get shorter runs as well, so that they always meet.

In a list, all are compared with one leader first; the verified links are contracted. What is then still in
different components of one list meets by an exact prefix filter on the full sets. Pairs pass an estimate from the union of their sketches
(within 8 standard errors of the threshold: a linked pair fails it with a chance below 1e-11 at 0.85 and at 0.8) and are then
verified on their full sets.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from autotheta.llm import textkit
from autotheta.operators.graph import components
from autotheta.sources.shared import keep, map_arrow

#: Retained values, the run length of a key, bits of the filter of candidate documents (its size is fixed), leaders tried, and
#: standard errors by which an estimate may miss the threshold.
K, RUN, FILTER_BITS, LEADERS, SIGMAS = 80, 4, 1 << 26, 2, 8.0


def run_limits(num: int, den: int, run: int = RUN) -> dict[int, int]:
    """For each run length the set size up to which shorter runs are needed: sets of ``n`` or fewer elements
    that meet ``num/den`` may share no longer run."""
    out = {}
    for length in range(run, 1, -1):
        worst = 0
        for shared in range(1, 4000):
            apart = shared * (den - num) // num
            if -(-shared // (apart + 1)) < length and apart:
                worst = max(worst, shared + apart)
            elif shared < length:
                worst = max(worst, shared + apart)
        out[length - 1] = worst if worst < 3900 else 1 << 30
    return out


def row_sets(data: np.ndarray, offsets: np.ndarray, size: int):
    """Sorted distinct shingle hashes of each row."""
    h, split = textkit.shingles(textkit.words(data, offsets, textkit.SPACED_LOWER), size)
    for s, e in zip(split[:-1].tolist(), split[1:].tolist(), strict=True):
        u = np.sort(h[s:e])
        yield u[np.concatenate([[True], u[1:] != u[:-1]])] if len(u) else u


def sketches(docs: DataFrame, size: int, k: int = K) -> DataFrame:
    """``doc_id, n, digest, sketch``: set size, a digest of the whole set, the k least values."""

    def run(batches):
        for b in batches:
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                n, digest, sketch = [], [], []
                for u in row_sets(data, offsets, size):
                    n.append(len(u))
                    digest.append(hashlib.blake2b(u.tobytes(), digest_size=16).digest() if len(u) else None)
                    sketch.append(u[:k].tobytes())
                yield pa.RecordBatch.from_arrays([b.column(0)[lo:hi], pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(sketch, pa.binary())], ["doc_id", "n", "digest", "sketch"])

    return map_arrow(docs, run, "doc_id bigint, n bigint, digest binary, sketch binary")


def _keys(classes: DataFrame, num: int, den: int, run: int) -> DataFrame:
    """``key, rep, n`` for every run of retained values."""
    limits = run_limits(num, den, run)

    def make(batches):
        for b in batches:
            ids, sizes, sk = b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()
            for at in range(0, len(ids), 2000):
                key, rep, n = [], [], []
                for i, m, raw in zip(ids[at : at + 2000], sizes[at : at + 2000], sk[at : at + 2000], strict=True):
                    v = np.frombuffer(raw, np.uint64)
                    made = []
                    for length in [run, *(x for x, most in limits.items() if m <= most)]:
                        if len(v) >= length:
                            h = np.full(len(v) - length + 1, length, np.uint64)
                            for j in range(length):
                                h = textkit.mix(h * textkit.U(textkit._BASE) + v[j : len(v) - length + 1 + j])
                            made.append(h)
                    if made:
                        made = np.unique(np.concatenate(made))
                        key.append(made)
                        rep.append(np.full(len(made), i, np.int64))
                        n.append(np.full(len(made), m, np.int64))
                if key:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(key).view(np.int64)), pa.array(np.concatenate(rep)), pa.array(np.concatenate(n))], ["key", "rep", "n"])

    return map_arrow(classes.select("rep", "n", "sketch"), make, "key bigint, rep bigint, n bigint")


def _candidate_filter(reps: DataFrame) -> np.ndarray:
    """One bit for the hash of each id; FILTER_BITS / 8 bytes whatever the number of ids."""
    words = FILTER_BITS // 64
    bit = F.pmod(F.xxhash64("rep"), F.lit(FILTER_BITS))
    rows = reps.select(F.floor(bit / 64).cast("int").alias("w"), F.expr("shiftleft(1L, cast(pmod(pmod(xxhash64(rep), %d), 64) AS INT))" % FILTER_BITS).alias("x")).groupBy("w").agg(F.bit_or("x").alias("x"))
    t = rows.toArrow()
    out = np.zeros(words, np.int64)
    out[t["w"].to_numpy()] = t["x"].to_numpy()
    return np.unpackbits(out.view(np.uint8), bitorder="little").view(bool)


def _full_sets(docs: DataFrame, reps: DataFrame, size: int) -> DataFrame:
    """``rep, elements`` for the documents of ``reps`` (and a few more that share their filter bit)."""
    bits = docs.sparkSession.sparkContext.broadcast(np.packbits(_candidate_filter(reps)))

    def run(batches):
        wanted = np.unpackbits(bits.value).view(bool)
        for b in batches:
            b = b.filter(pa.array(wanted[b.column(2).to_numpy()]))
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                sets = [u.tobytes() for u in row_sets(data, offsets, size)]
                yield pa.RecordBatch.from_arrays([b.column(0)[lo:hi], pa.array(sets, pa.binary())], ["rep", "elements"])

    rows = docs.select("doc_id", "text", F.pmod(F.xxhash64("doc_id"), F.lit(FILTER_BITS)).alias("bit"))
    return map_arrow(rows, run, "rep bigint, elements binary")


def shared_count(a: np.ndarray, b: np.ndarray) -> int:
    """Common elements of two sorted sets."""
    both = np.concatenate([a, b])
    both.sort(kind="stable")
    return int(np.count_nonzero(both[1:] == both[:-1]))


def _linked(pairs: DataFrame, classes: DataFrame, sets: DataFrame, num: int, den: int, k: int) -> DataFrame:
    """The pairs ``(a, b)`` that reach ``num/den``, by estimate and then exactly."""
    least = num / den - SIGMAS * math.sqrt(num / den * (1 - num / den) / k)

    def near(batches):
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                union = np.sort(np.concatenate([x, y]))
                same = union[1:] == union[:-1]
                of = int(np.searchsorted(np.cumsum(np.concatenate([[True], ~same])), k, "right")) if len(union) else 0
                seen = of - int(np.count_nonzero(same[: max(0, of - 1)]))
                good.append(np.count_nonzero(same[: max(0, of - 1)]) >= least * min(k, seen))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(good, pa.bool_()))

    def exact(batches):
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = shared_count(x, y)
                good.append(den * both >= num * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(good, pa.bool_()))

    def beside(p: DataFrame, t: DataFrame, key: str, value: str) -> DataFrame:
        one, two = t.select(F.col(key).alias("a_"), F.col(value).alias("x")), t.select(F.col(key).alias("b_"), F.col(value).alias("y"))
        return p.join(one, F.col("a") == F.col("a_")).join(two, F.col("b") == F.col("b_")).select("a", "b", "x", "y")

    likely = keep(map_arrow(beside(pairs, classes, "rep", "sketch"), near, "a bigint, b bigint"), "likely")
    return map_arrow(beside(likely, sets, "rep", "elements"), exact, "a bigint, b bigint")


def _prefix_pairs(left: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """Pairs ``(a, b)`` of ``rep, n, c`` rows in different components c that may reach ``num/den``; none is lost.

    Elements are ordered by how many of these sets hold them, rare first. Two sets of that similarity share one
    of the first ``n - ceil(n * num / den) + 1`` of each, and the first that they share leaves enough behind it.
    What thousands of sets have in common is frequent, so it joins only sets that consist of little else.
    """

    def spread(batches):
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                values = [np.frombuffer(x, np.int64) for x in part.column(3).to_pylist()]
                count = np.array([len(v) for v in values])
                yield pa.RecordBatch.from_arrays([*(pa.array(np.repeat(part.column(k).to_numpy(), count)) for k in range(3)), pa.array(np.concatenate(values))], ["rep", "n", "c", "x"])

    held = sets.join(left.withColumnRenamed("rep", "r_"), F.col("rep") == F.col("r_")).select("rep", "n", "c", "elements")
    elements = keep(map_arrow(held, spread, "rep bigint, n bigint, c bigint, x bigint"), "elements")
    often = elements.groupBy("x").agg(F.count(F.lit(1)).alias("f")).where("f > 1").withColumnRenamed("x", "x_")
    ranked = elements.join(often, F.col("x") == F.col("x_"), "left").select("rep", "n", "c", "x", F.coalesce("f", F.lit(1)).alias("f"))
    ranked = ranked.withColumn("at", F.row_number().over(Window.partitionBy("rep").orderBy("f", "x")))
    prefix = F.col("n") - F.floor((F.col("n") * num + den - 1) / den) + 1
    heads = keep(ranked.where((F.col("at") <= prefix) & (F.col("f") > 1)).select("rep", "n", "c", "x", "at"), "heads")
    one, two = (heads.select("x", *(F.col(v).alias(f"{v}_{t}") for v in ("rep", "n", "c", "at"))) for t in "ab")
    needed = (F.col("n_a") + F.col("n_b")) * num
    most = F.least(F.col("n_a") - F.col("at_a"), F.col("n_b") - F.col("at_b")) + 1
    close = F.least("n_a", "n_b") * F.lit(den) >= F.greatest("n_a", "n_b") * F.lit(num)
    pairs = one.join(two, "x").where("rep_a < rep_b AND c_a <> c_b").where(close & (most * (num + den) >= needed))
    return pairs.select(F.col("rep_a").alias("a"), F.col("rep_b").alias("b")).distinct()


def near_duplicates(docs: DataFrame, size: int = 5, num: int = 80, den: int = 100, k: int = K, run: int = RUN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_shingles, component_id, kept``: one row per input row.

    Documents whose sets of ``size``-word shingles have a Jaccard similarity of ``num/den`` or more are linked;
    ``component_id`` is the least id reachable, ``kept`` marks the document that has it. A text of fewer words
    is one shingle; null and wordless texts have no set and stand alone. A null id is kept and not linked. Ids
    name documents: rows that repeat an id are one document and share its component. Other columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    made = keep(sketches(rows, size, k), "sketches")
    has = made.where("digest IS NOT NULL AND doc_id IS NOT NULL")
    classes = keep(has.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.min("n").alias("n"), F.min("sketch").alias("sketch")), "classes")
    keys = _keys(classes, num, den, run)
    lead = keys.groupBy("key").agg(F.min(F.struct("rep", "n")).alias("lead"), F.max("rep").alias("most")).where("lead.rep <> most").select(F.col("key").alias("k_"), F.col("lead.rep").alias("lead"), F.col("lead.n").alias("lead_n"))
    lists = keep(keys.join(lead, F.col("key") == F.col("k_")).select("key", "rep", "n", "lead", "lead_n"), "lists")

    def comparable(x: str, y: str):
        return (F.least(x, y) * F.lit(den) >= F.greatest(x, y) * F.lit(num))

    def best(met: DataFrame) -> DataFrame:
        """Of the leaders ``a`` that ``b`` meets, the LEADERS that it shares most lists with; the rest is left to the last stage."""
        most = Window.partitionBy("b").orderBy(F.desc("shared"), "a")
        ranked = met.groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared")).withColumn("rank", F.row_number().over(most))
        return ranked.where(F.col("rank") <= LEADERS).select("a", "b")

    first = keep(best(lists.where(F.col("rep") != F.col("lead")).where(comparable("n", "lead_n")).select(F.col("lead").alias("a"), F.col("rep").alias("b"))), "pairs")
    sets = keep(_full_sets(rows, lists.select("rep").distinct(), size), "sets")
    links = keep(_linked(first, classes, sets, num, den, k), "links")

    def with_components(found: DataFrame) -> DataFrame:
        c = components(found)
        return lists.join(c, F.col("rep") == F.col("node"), "left").select("key", "rep", "n", F.coalesce("component", "rep").alias("c"))

    # A second leader, drawn by hash among those outside the first one's component.
    at = keep(with_components(links), "lists")
    per = at.groupBy("key").agg(F.min("c").alias("c0"), F.max("c").alias("c1"), F.max(F.struct(F.xxhash64("c"), F.xxhash64("rep"), "rep", "n", "c")).alias("l")).where("c0 <> c1").select(F.col("key").alias("k_"), "l")
    met = at.join(per, F.col("key") == F.col("k_")).where("c <> l.c").where(comparable("n", "l.n")).select(F.col("l.rep").alias("a"), F.col("rep").alias("b"))
    second = keep(best(met).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct().join(first, ["a", "b"], "left_anti"), "pairs")
    links = keep(links.unionByName(_linked(second, classes, sets, num, den, k)), "links")

    # What still lies in different components under one key: all of these that can be linked at all.
    at = keep(with_components(links), "lists")
    open_keys = at.groupBy("key").agg(F.min("c").alias("c0"), F.max("c").alias("c1")).where("c0 <> c1").select("key")
    left = keep(at.join(open_keys, "key", "left_semi").select("rep", "n", "c").distinct(), "open")
    rest = _prefix_pairs(left, sets, num, den).join(first.unionByName(second), ["a", "b"], "left_anti")
    links = keep(links.unionByName(_linked(rest, classes, sets, num, den, k)), "links")

    of = components(links)
    named = classes.select("digest", "rep").join(of, F.col("rep") == F.col("node"), "left").select(F.col("digest").alias("d_"), F.coalesce("component", "rep").alias("component"))
    out = made.select("doc_id", "n", "digest").join(named, F.col("digest") == F.col("d_"), "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id"))
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))
