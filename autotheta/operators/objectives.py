"""Objectives over result sets, from one profile of all similarity levels.

A level's row says what the pairs of exactly that key add: pairs, objects first covered on either side, edges of a
maximum spanning forest. Sums from the top give the state at every threshold. A forest on c covered objects with
f edges has c - f components, so the number of matched groups needs no component search a threshold.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window, functions as F

from autotheta.operators.graph import spanning_forest
from autotheta.sources.shared import discard, keep


@dataclass(frozen=True)
class Objective:
    """Score of a state: a Column over n_join, cov_r, cov_s, classes, forest, mutual, size_r, size_s; higher is better.

    ``classes`` are the covered objects of both sides, equal sets that were collapsed counted once.
    ``pivots_valid``: the largest threshold of best score is always among the pivotal ones. ``bound``: what no lower
    threshold can exceed, or None; needed to stop early. ``needs_joins``: the score or its bound reads n_join.
    """

    name: str
    score: Column
    bound: Column | None
    pivots_valid: bool
    needs_forest: bool = False
    needs_joins: bool = True


def _uncovered() -> Column:
    return F.least(F.col("size_r") - F.col("cov_r"), F.col("size_s") - F.col("cov_s"))


def group_count() -> Objective:
    """Matched groups: components with an edge. Suits many-to-many data."""
    score = F.col("classes") - F.col("forest")
    return Objective("group_count", score, score + _uncovered(), True, True, False)


def outer_size() -> Objective:
    """Minus the size of the full outer join. Suits one-to-one data."""
    score = F.col("cov_r") + F.col("cov_s") - F.col("n_join") - F.col("size_r") - F.col("size_s")
    return Objective("outer_size", score, score + _uncovered(), True)


def mutual_pairs() -> Objective:
    """Pairs that are best for both their ends, less the others: an objective of a user's own, without a bound."""
    return Objective("mutual_pairs", 2 * F.col("mutual") - F.col("n_join"), None, False)


OBJECTIVES = {"group_count": group_count, "outer_size": outer_size, "mutual_pairs": mutual_pairs}


DELTAS = ("d_join", "d_r", "d_s", "d_classes", "d_forest", "d_mutual")
_SUMS = {"n_join": "d_join", "cov_r": "d_r", "cov_s": "d_s", "classes": "d_classes", "forest": "d_forest", "mutual": "d_mutual"}


def _weighted(pairs: DataFrame) -> DataFrame:
    one = F.lit(1).cast("bigint")
    return pairs.withColumns({c: one for c in ("wr", "ws") if c not in pairs.columns})


def _covers(pairs: DataFrame, side: str) -> DataFrame:
    """``side, best, w``: the key at which each object is first covered."""
    return pairs.groupBy(side).agg(F.max("key").alias("best"), F.max(f"w{side}").alias("w"))


def _level_rows(joins: DataFrame, near: DataFrame, new_r: DataFrame, new_s: DataFrame, forest: DataFrame | None) -> DataFrame:
    """What pairs add at each key: ``joins`` counts them, ``near`` are those that can be best for both ends, and given are
    the objects that they cover first and the forest edges that they bring."""
    def part(rows: DataFrame, key: str, **sums: str) -> DataFrame:
        return rows.groupBy(F.col(key).alias("key")).agg(*(F.expr(f"sum({v})").alias(k) for k, v in sums.items())).selectExpr("key", *(c if c in sums else f"0L AS {c}" for c in DELTAS))

    br, bs = new_r.selectExpr("r", "best AS best_r"), new_s.selectExpr("s", "best AS best_s")
    top = near.join(br, "r").join(bs, "s").where("key = best_r AND key = best_s")
    events = part(joins, "key", d_join="n").unionByName(part(new_r, "best", d_r="w", d_classes="1L")).unionByName(part(new_s, "best", d_s="w", d_classes="1L")).unionByName(part(top, "key", d_mutual="n"))
    if forest is not None:
        events = events.unionByName(part(forest, "key", d_forest="1L"))
    return events.groupBy("key").agg(*(F.sum(x).alias(x) for x in DELTAS))


def levels(pairs: DataFrame, forest: bool = True) -> DataFrame:
    """``key, d_join, d_r, d_s, d_classes, d_forest, d_mutual`` of every level; d_mutual > 0 marks the pivotal ones."""
    pairs = _weighted(pairs).withColumn("n", F.expr("wr * ws"))
    return _level_rows(pairs, pairs, _covers(pairs, "r"), _covers(pairs, "s"), spanning_forest(pairs) if forest else None)


@dataclass
class Parts:
    """Pairs as a score needs them: ``joins`` (key, n), ``covers`` (side, id, best, w), ``near`` (r, s, key, n) with all pairs that are
    best for both ends, ``edges`` (r, s, key) with a maximum spanning forest."""

    joins: DataFrame
    covers: DataFrame
    near: DataFrame
    edges: DataFrame


def parts_of(pairs: DataFrame) -> Parts:
    pairs = _weighted(pairs).withColumn("n", F.expr("wr * ws"))
    both = [_covers(pairs, x).select(F.lit(x).alias("side"), F.col(x).alias("id"), "best", "w") for x in "rs"]
    return Parts(pairs, both[0].unionByName(both[1]), pairs, pairs.select("r", "s", "key"))


class ScoreState:
    """The state above a falling threshold: it grows by the pairs of a band and is never made again from all pairs.

    Kept are the objects covered so far and, where groups are counted, a spanning forest of all pairs: no more than a row
    an object each. A band's pairs lie below all earlier ones, so what they cover first is what is not covered yet, and
    earlier forest edges stay.
    """

    def __init__(self, forest: bool):
        self.covered: DataFrame | None = None
        self.needs_forest = forest
        self.forest: DataFrame | None = None
        self._old: DataFrame | None = None
        self.base = dict.fromkeys(_SUMS, 0)

    def extend(self, extra: DataFrame | Parts) -> DataFrame:
        """The levels of a band's pairs; the running totals of ``base`` are those above the band until ``close``."""
        if not isinstance(extra, Parts):
            extra = parts_of(extra)
        new = extra.covers
        new = keep(new if self.covered is None else new.join(self.covered, ["side", "id"], "left_anti"), "covers")
        self.covered = new.select("side", "id") if self.covered is None else self.covered.unionByName(new.select("side", "id"))
        new_r, new_s = (new.where(F.col("side") == x).select(F.col("id").alias(x), "best", "w") for x in "rs")
        edges = None
        if self.needs_forest:
            band = extra.edges
            grown = keep(spanning_forest(band if self.forest is None else self.forest.unionByName(band)), "forest")
            edges = grown if self.forest is None else grown.join(self.forest.select("r", "s"), ["r", "s"], "left_anti")
            self._old, self.forest = self.forest, grown
        return _level_rows(extra.joins, extra.near, new_r, new_s, edges)

    def close(self, got) -> None:
        """Take the sums of the band's levels into the totals."""
        self.base = {n: self.base[n] + (got[n] or 0) for n in self.base}
        if self.needs_forest:
            discard(self._old)


def level_sums(rows: DataFrame):
    """How many levels there are and what they add in all, as one row."""
    return rows.selectExpr("count(*) AS levels", *(f"sum({d}) AS {n}" for n, d in _SUMS.items())).first()


#: Ranges of keys that running sums go through in two steps: inside a range, and over the ranges. FEW levels go in one.
RANGES, FEW = 4096, 50_000


def running(rows: DataFrame, sums: dict[str, str], how: str = "sum", first: dict[str, int] | None = None, levels: int | None = None) -> DataFrame:
    """Running sums (or ``max``) of columns over ``key`` from the top, with ``first`` before the highest.

    Ranges of keys are summed on their own, each in a window of its own, and their totals, RANGES rows at most, in
    one more; so no task sees all levels, unless their number is known to be small.
    """
    first = {n: x for n, x in (first or {}).items() if x is not None}
    many = levels is None or levels > FEW
    inside = f"({'PARTITION BY range_ ' if many else ''}ORDER BY key DESC ROWS UNBOUNDED PRECEDING)"

    def joined(n: str, *parts: str) -> str:
        parts = [*parts, *([f"{first[n]}L"] if n in first else [])]
        return parts[0] if len(parts) == 1 else f"greatest({', '.join(parts)})" if how == "max" else " + ".join(parts)

    if not many:
        return rows.selectExpr("*", *(f"{joined(n, f'{how}({c}) OVER {inside}')} AS {n}" for n, c in sums.items()))
    rows = rows.selectExpr("*", f"floor(key * {RANGES}) AS range_")
    totals = rows.groupBy("range_").agg(*(F.expr(f"{how}({c}) AS {n}") for n, c in sums.items()))
    totals = totals.selectExpr("range_", *(f"{how}({n}) OVER (ORDER BY range_ DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS {n}_before" for n in sums))
    out = rows.selectExpr("*", *(f"{how}({c}) OVER {inside} AS {n}_inside" for n, c in sums.items())).join(F.broadcast(totals), "range_")
    missing = "" if how == "max" else ", 0L"
    whole = {n: joined(n, f"{n}_inside", f"coalesce({n}_before{missing})") for n in sums}
    return out.selectExpr(*(f"`{c}`" for c in rows.columns if c != "range_"), *(f"{e} AS {n}" for n, e in whole.items()))


def profile(level_rows: DataFrame, size_r: int, size_s: int, base: dict[str, int] | None = None, levels: int | None = None) -> DataFrame:
    """State at every level; ``base`` is that above the highest one, ``levels`` how many they are if that is known."""
    if "d_classes" not in level_rows.columns:
        level_rows = level_rows.selectExpr("*", "d_r + d_s AS d_classes")
    state = running(level_rows, _SUMS, first=base, levels=levels)
    return state.selectExpr("key", "d_mutual > 0 AS pivotal", *(f"cast({n} AS bigint) AS {n}" for n in _SUMS), f"{size_r}L AS size_r", f"{size_s}L AS size_s")


def scored(state: DataFrame, objective: Objective) -> DataFrame:
    bound = objective.bound if objective.bound is not None else F.lit(None)
    return state.withColumns({"h": objective.score.cast("bigint"), "bound": bound.cast("bigint")})


def choose(rows: DataFrame) -> DataFrame:
    """The best row; of equal scores that of the largest threshold."""
    return rows.orderBy(F.desc("h"), F.desc("key")).limit(1)


def until_stop(rows: DataFrame, best: int | None = None, levels: int | None = None) -> DataFrame:
    """Rows with ``top``, the best score so far (``best`` before the first), and ``stops``: no lower one can exceed it."""
    return running(rows, {"top": "h"}, "max", {"top": best}, levels).selectExpr("*", "coalesce(bound <= top, false) AS stops")


def stop_point(rows: DataFrame, printed: bool = False) -> DataFrame:
    """``evaluated, pivots``: thresholds looked at until the bound is no better than the best score so far.

    ``printed``: the bound is looked at only where a threshold does not improve the score: where the best one, of
    equal ones the first, lies above.
    """
    rows = keep(rows.select("key", "h", "bound"), "thresholds")
    r = until_stop(rows, levels=rows.count())
    stops = F.col("stops")
    if printed:
        r = keep(r, "stops")
        first = r.groupBy("top").agg(F.max("key").alias("k_")).withColumnRenamed("top", "t_")
        r = r.join(first, F.col("top") == F.col("t_"))
        stops &= F.col("key") < F.col("k_")
    last = r.agg(F.max(F.when(stops, F.col("key"))).alias("last"))
    return r.crossJoin(F.broadcast(last)).agg(F.count_if(F.col("key") >= F.coalesce("last", F.lit(-1.0))).alias("evaluated"), F.count(F.lit(1)).alias("pivots"))


def outer_result(pairs: DataFrame, r: DataFrame, s: DataFrame) -> DataFrame:
    """Full outer join of both sides' ids under the joined pairs: ``r, s``."""
    kept = pairs.select("r", "s")
    only_r = r.select(F.col("id").alias("r")).join(kept, "r", "left_anti").select("r", F.lit(None).cast("bigint").alias("s"))
    only_s = s.select(F.col("id").alias("s")).join(kept, "s", "left_anti").select(F.lit(None).cast("bigint").alias("r"), "s")
    return kept.unionByName(only_r).unionByName(only_s)
