"""Similarity joins and the operators on their pairs ``r, s, o, nr, ns, key``."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from autotheta.functions.sims import SetSimilarity, edit_similarity
from autotheta.operators.sets import SALTS, Prepared, postings
from autotheta.sources.shared import ship

PAIR = ("r", "s", "nr", "ns")


def pair_columns(p: Prepared) -> list[str]:
    """Columns that name a pair: ids and sizes, and the weights of both classes where equal sets are collapsed."""
    return [*PAIR, "wr", "ws"] if p.collapsed else [*PAIR]


def _keyed(pairs: DataFrame, sim: SetSimilarity) -> DataFrame:
    return pairs.withColumn("key", sim.key(F.col("o"), F.col("nr"), F.col("ns")))


def _side(sets: DataFrame, side: str) -> DataFrame:
    """``id, n, toks`` (and ``w``) with the names of a side."""
    return sets.select(*(F.col(c).alias(x) for c, x in (("id", side), ("n", f"n{side}"), ("w", f"w{side}"), ("toks", f"t{side}")) if c in sets.columns))


def brute_force_pairs(p: Prepared, sim: SetSimilarity) -> DataFrame:
    """Every pair of both sides, those that share nothing left out: the baseline, and the only cross join."""
    pairs = _side(p.r, "r").crossJoin(_side(p.s, "s")).select(*pair_columns(p), F.size(F.array_intersect("tr", "ts")).cast("bigint").alias("o"))
    return _keyed(pairs.where("o > 0"), sim)


def sharing_pairs(p: Prepared, sim: SetSimilarity) -> DataFrame:
    """The same pairs by counting shared elements: an equi-join on elements, no cross join."""
    r, s = (_side(x, n).withColumn("t", F.explode(f"t{n}")).drop(f"t{n}") for x, n in ((p.r, "r"), (p.s, "s")))
    return _keyed(_meet(p, r, s).groupBy(*pair_columns(p)).agg(F.count(F.lit(1)).alias("o")), sim)


def _meet(p: Prepared, r: DataFrame, s: DataFrame) -> DataFrame:
    """Join postings on their element ``t``; those of hot elements are dealt over SALTS tasks, s's once to each."""
    if p.hot is None:
        return r.join(s, "t")
    hot = F.col("t") >= p.hot
    r = r.withColumn("salt", F.when(hot, F.pmod(F.xxhash64("r"), F.lit(SALTS))).otherwise(0).cast("int"))
    s = s.withColumn("salt", F.explode(F.when(hot, F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))))
    return r.join(s, ["t", "salt"]).drop("salt")


def meetings(p: Prepared, sim: SetSimilarity, low: float, high: float | None = None, bounds: str = "tight", index: str = "prefix") -> DataFrame:
    """Pairs that meet in a shared element whose caps are ``low`` or more (key space) on both sides, and where.

    ``seen`` counts these elements, ``i`` and ``j`` are the places of the last one: elements before it are all seen, as
    both sets are in one order. ``high``: only elements that do not have ``high`` on both sides; so a descending run meets each
    shared element once. ``index="full"`` indexes all elements of s instead of its prefix.
    """
    names = {"id": "{0}", "n": "n{0}", "w": "w{0}", "cap": "c{0}", "pos": "{1}", "t": "t"}

    def side(sets: DataFrame, x: str, at: str, cut: float | None) -> DataFrame:
        rows = postings(sets, sim, x, bounds, cut)
        return rows.select(*(F.col(c).alias(names[c].format(x, at)) for c in rows.columns))

    pr, ps = side(p.r, "r", "i", low), side(p.s, "s", "j", low if index == "prefix" else None)
    if high is None:
        met = _meet(p, pr, ps)
    else:  # what is new on either side meets all that is there by now
        met = _meet(p, pr.where(F.col("cr") < high), ps).unionByName(_meet(p, pr.where(F.col("cr") >= high), ps.where(F.col("cs") < high)))
    return met.groupBy(*pair_columns(p)).agg(F.count(F.lit(1)).alias("seen"), F.max("i").cast("bigint").alias("i"), F.max("j").cast("bigint").alias("j"))


def most_possible(sim: SetSimilarity, low: float | None = None, bounds: str = "tight"):
    """Greatest key that a met pair can have, from what it has seen and the places where it stands.

    All that is shared up to the last meeting is seen; behind it both rests could be shared. ``low``: the elements
    behind both prefixes of that key are all that the lesser prefix leaves open. The sizes of both sets bound it too.
    """
    nr, ns, seen = F.col("nr"), F.col("ns"), F.col("seen")
    rest = F.least(nr - F.col("i"), ns - F.col("j"))
    if low is not None:
        rest = F.least(rest, F.greatest(sim.rest_at_most(low, nr, "r", bounds), sim.rest_at_most(low, ns, "s", bounds)))
    return sim.key(F.least(seen + rest, nr, ns), nr, ns)


def candidates(p: Prepared, sim: SetSimilarity, low: float, high: float | None = None, bounds: str = "tight", index: str = "prefix") -> DataFrame:
    """Pairs of ``meetings`` that can still reach ``low``."""
    return meetings(p, sim, low, high, bounds, index).where(most_possible(sim, low if index == "prefix" else None, bounds) >= low)


def with_sets(pairs: DataFrame, p: Prepared) -> DataFrame:
    """Pairs with both ordered sets, ids joined first and arrays attached after."""
    r, s = p.r.select(F.col("id").alias("r"), F.col("toks").alias("tr")), p.s.select(F.col("id").alias("s"), F.col("toks").alias("ts"))
    return pairs.join(r, "r").join(s, "s")


def verify_eager(pairs: DataFrame, p: Prepared, sim: SetSimilarity) -> DataFrame:
    """Exact overlap and key of pairs, from the whole sets."""
    return _keyed(with_sets(pairs, p).withColumn("o", F.size(F.array_intersect("tr", "ts")).cast("bigint")).drop("tr", "ts"), sim)


def verify_rest(pairs: DataFrame, p: Prepared, sim: SetSimilarity) -> DataFrame:
    """The same for met pairs: what is seen and what both sets share behind the last meeting."""
    behind = [F.slice(t, F.col(at) + 1, F.greatest(F.col(n) - F.col(at), F.lit(0))) for t, at, n in (("tr", "i", "nr"), ("ts", "j", "ns"))]
    return _keyed(with_sets(pairs, p).withColumn("o", F.col("seen") + F.size(F.array_intersect(*behind))).drop("tr", "ts"), sim)


def threshold_join(p: Prepared, sim: SetSimilarity, theta: float | str, bounds: str = "tight", index: str = "prefix") -> DataFrame:
    """All pairs of similarity ``theta`` (> 0) or more: index, candidates of the prefixes, verification."""
    low = sim.key_of(theta)
    return verify_rest(candidates(p, sim, low, None, bounds, index), p, sim).where(F.col("key") >= low).select(*pair_columns(p), "o", "key")


def expand(pairs: DataFrame, p: Prepared) -> DataFrame:
    """Pairs of objects from those of classes."""
    if not p.collapsed:
        return pairs
    r, s = (m.select(F.col("rep").alias(x), F.col("id").alias(f"{x}_")) for m, x in ((p.members_r, "r"), (p.members_s, "s")))
    out = pairs.join(r, "r").join(s, "s").drop("r", "s", "wr", "ws")
    return out.withColumnsRenamed({"r_": "r", "s_": "s"}).select("r", "s", *(c for c in pairs.columns if c not in ("r", "s", "wr", "ws")))


def level(pairs: DataFrame, key: float) -> DataFrame:
    """Pairs of exactly this key."""
    return pairs.where(F.col("key") == key)


def band(pairs: DataFrame, low: float, high: float) -> DataFrame:
    """Pairs from ``low`` up to, not including, ``high``."""
    return pairs.where((F.col("key") >= low) & (F.col("key") < high))


def cover(pairs: DataFrame, side: str) -> DataFrame:
    return pairs.select(side).distinct()


def top_partners(pairs: DataFrame, side: str, k: int = 1) -> DataFrame:
    """For each object of a side the partners of its ``k`` best ranks, ties included."""
    rank = F.rank().over(Window.partitionBy(side).orderBy(F.desc("key")))
    return pairs.withColumn("rank", rank).where(F.col("rank") <= k)


def best(pairs: DataFrame, side: str) -> DataFrame:
    """``side, best``: the key at which each object is first covered."""
    return pairs.groupBy(side).agg(F.max("key").alias("best"))


def threshold_values(pairs: DataFrame) -> DataFrame:
    return pairs.select("key").distinct()


def pivotal_thresholds(pairs: DataFrame) -> DataFrame:
    """Keys at which some pair is the best of both its ends."""
    br, bs = best(pairs, "r").withColumnRenamed("best", "best_r"), best(pairs, "s").withColumnRenamed("best", "best_s")
    return pairs.join(br, "r").join(bs, "s").where("key = best_r AND key = best_s").select("key").distinct()


def not_joined_count(pairs: DataFrame, size_r: int, size_s: int) -> DataFrame:
    # The product is made here: as a product of literals it would be one of 32-bit integers.
    return pairs.agg((F.lit(size_r * size_s).cast("bigint") - F.count(F.lit(1))).alias("n"))


#: Edits up to which strings meet in what is left of them after deletions; the number of remainders grows with its power.
MOST_EDITS = 2


def edit_join(objects: DataFrame, share: float) -> DataFrame:
    """``r, s, sim`` (r < s) of ``id, text`` rows whose edit distance is at most ``share`` of the longer text.

    Texts that are d edits apart have a common remainder after d deletions at most in each, so remainders are joined by
    equality and only what meets is compared; no pair is lost. Null texts are in no pair. More than MOST_EDITS are an error.
    """
    rows = objects.where("text IS NOT NULL").select("id", "text")
    longest = rows.agg(F.max(F.length("text"))).first()[0] or 0
    edits = int(share * longest + 1e-9)
    if edits > MOST_EDITS:
        raise ValueError(f"{edits} edits are too many")
    left = rows.select("id", "text", F.col("text").alias("rest"))
    for _ in range(edits):
        n = F.length("rest")
        fewer = F.when(n > 0, F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.concat(F.substring("rest", F.lit(1), i - 1), F.substring("rest", i + 1, F.length("rest")))))
        left = left.select("id", "text", F.explode(F.array_distinct(F.concat(F.array("rest"), F.coalesce(fewer, F.array().cast("array<string>"))))).alias("rest")).distinct()
    one, two = (left.select(F.col("id").alias(x), F.col("text").alias(f"t{x}"), "rest") for x in "rs")
    met = one.join(two, "rest").where("r < s").select("r", "s", "tr", "ts").distinct()
    near = F.levenshtein("tr", "ts") <= F.lit(share) * F.greatest(F.length("tr"), F.length("ts"))
    return met.where(near).select("r", "s", edit_similarity(F.col("tr"), F.col("ts")).alias("sim"))


def vector_join(r: DataFrame, s: DataFrame, theta: float, blocks: int = 8, rows: int = 2048) -> DataFrame:
    """``r, s, sim`` of ``id, vector`` rows of both sides with a cosine of ``theta`` or more (to 4 digits).

    Vectors have no rare element to meet in, so blocks of both sides are multiplied: each row goes to every block of the
    other side, ``blocks`` times ``blocks`` tasks hold a block of either, and only pairs that reach ``theta`` leave one. Null vectors
    and those of length 0 are in no pair.
    """
    ship(r.sparkSession)
    norm = F.aggregate("vector", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    one, two = (x.where(norm > 0).select("id", "vector", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias(mine)).withColumn(other, every) for x, mine, other in ((r, "a", "b"), (s, "b", "a")))

    def multiply(x: pa.Table, y: pa.Table) -> pa.Table:
        def unit(t: pa.Table) -> np.ndarray:
            v = np.array(t["vector"].to_pylist(), float).reshape(len(t), -1)
            return v / np.linalg.norm(v, axis=1, keepdims=True)

        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        if len(x) and len(y):
            u, w, ids, others = unit(x), unit(y), x["id"].to_numpy(), y["id"].to_numpy()
            for at in range(0, len(u), rows):
                cosine = np.round(u[at : at + rows] @ w.T, 4)
                i, j = np.nonzero(cosine >= theta)
                out.append((ids[at + i], others[j], cosine[i, j]))
        return pa.table(dict(zip(("r", "s", "sim"), (np.concatenate(c) for c in zip(*out, strict=True)), strict=True)))

    return one.groupBy("a", "b").cogroup(two.groupBy("a", "b")).applyInArrow(multiply, "r bigint, s bigint, sim double")
