"""The join that chooses its threshold: bands of thresholds from the top, one pass over all that is needed.

Each band extends the joined pairs by those whose key lies in it, found from new postings and from pairs that were put
off; the score's state grows by these pairs alone. What the driver sees of a band is one row: the best threshold so far and where
the run may stop. It ends when no lower threshold can score better. Results of a band are written to the shared
folder, so plans do not grow and lost executors cost little.

Sides in blocks are joined without a shuffle of meetings or pairs: tasks sum up what the pairs of a band add to the score. There
bands are cut into narrower steps, so that a run ends soon after the threshold from which no lower one can score better.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, functions as F

from autotheta.functions.sims import SetSimilarity
from autotheta.operators.blocks import COVER_R, COVER_S, EDGE, JOIN, MUTUAL, WHOLE, Blocks, block_join, level_parts
from autotheta.operators.objectives import Objective, Parts, ScoreState, level_sums, levels, profile, scored, until_stop
from autotheta.operators.sets import Prepared
from autotheta.operators.simjoin import candidates, expand, meetings, pair_columns, pivotal_thresholds, sharing_pairs, verify_eager, verify_rest
from autotheta.operators.verify import GRID, classify, merge_meetings, placed
from autotheta.sources.shared import discard, keep

#: Bands that are run at most, each a few jobs.
MOST_BANDS = 1000


@dataclass
class Result:
    """``pairs`` of the chosen threshold (theta None: nothing is joined), the evaluated thresholds, what it took, and how many
    pairs there are."""

    pairs: DataFrame
    theta: float | None
    score: int | None
    evaluated: DataFrame | None
    metrics: dict[str, float] = field(default_factory=dict)
    size: int = 0


#: Caps of the search for best partners.
STEPS = (0.8, 0.6, 0.4, 0.2, 0.1, 0.0)


def top_search(p: Prepared, sim: SetSimilarity, bounds: str = "tight", floor: float = 0.0) -> tuple[DataFrame, DataFrame]:
    """Best key of every object that shares anything, ``side, id, best``, and ``r, s, key`` of all verified pairs.

    By deepening search: a round goes on to the next lower cap only for objects whose best key is below the last cap, as
    what has not met yet cannot beat the others'. A pair that is best for both ends meets while both are searched, so it
    is among the verified ones. Keys below ``floor`` are not searched for.
    """
    found: DataFrame | None = None
    verified: DataFrame | None = None
    high = None
    for low in [x for x in STEPS if x > floor] + [floor]:
        if found is None:
            met = candidates(p, sim, low, high, bounds)
        else:  # one end at least is still searched
            done = {x: found.where((F.col("side") == x) & (F.col("best") >= high)).select("id") for x in "RS"}
            open_r, done_r, open_s = p.r.join(done["R"], "id", "left_anti"), p.r.join(done["R"], "id", "left_semi"), p.s.join(done["S"], "id", "left_anti")
            met = meetings(replace(p, r=open_r), sim, low, high, bounds).unionByName(meetings(replace(p, r=done_r, s=open_s), sim, low, high, bounds))
        # A pair of an earlier round is verified again only if more of its shared elements meet in this one.
        pairs = keep(verify_eager(met.select(*pair_columns(p)), p, sim).where("key > 0").select("r", "s", "key"), "verified")
        ends = F.explode(F.array(*(F.struct(F.lit(x.upper()).alias("side"), F.col(x).alias("id")) for x in "rs"))).alias("end")
        new = pairs.select(ends, "key").groupBy("end.side", "end.id").agg(F.max("key").alias("best"))
        grown = keep(new if found is None else found.unionByName(new).groupBy("side", "id").agg(F.max("best").alias("best")), "top")
        discard(found)
        found, verified, high = grown, pairs if verified is None else verified.unionByName(pairs), low
        counts = {r["side"]: r["n"] for r in found.where(F.col("best") >= low).groupBy("side").agg(F.count(F.lit(1)).alias("n")).collect()}
        if counts.get("R", 0) >= p.size_r and counts.get("S", 0) >= p.size_s:
            break
    return found, verified


def _best_of_both(pairs: DataFrame, found: DataFrame) -> DataFrame:
    """Pairs whose key is the best found for both ends."""
    r, s = (found.where(F.col("side") == x.upper()).select(F.col("id").alias(x), F.col("best").alias(f"best_{x}")) for x in "rs")
    return pairs.join(r, "r").join(s, "s").where("key = best_r AND key = best_s").select("r", "s", "key")


def pivots_by_search(p: Prepared, sim: SetSimilarity, bounds: str = "tight", floor: float = 0.0) -> DataFrame:
    """Pivotal keys: those of pairs that the search found best for both ends."""
    found, verified = top_search(p, sim, bounds, floor)
    return _best_of_both(verified, found).select("key").where(F.col("key") >= floor).distinct()


def plan_bands(bands: int | str, pivots: DataFrame | None, floor: float) -> list[float]:
    """Lower ends of the bands, descending, the last at ``floor`` (0: anything shared).

    ``"pivot"``: one band a pivotal threshold, an error beyond MOST_BANDS. A number: as many pivots in each, or equal widths
    if there are none yet.
    """
    if bands == "pivot" and pivots is not None:
        lows = [r["key"] for r in pivots.where(F.col("key") >= floor).orderBy(F.desc("key")).limit(MOST_BANDS + 1).collect()]
        if len(lows) > MOST_BANDS:
            raise ValueError(f"more than {MOST_BANDS} pivotal thresholds: give a number of bands")
    elif pivots is not None:
        cut = pivots.where(F.col("key") >= floor).agg(F.percentile_approx("key", [k / bands for k in range(bands - 1, 0, -1)] or [0.0], 10000).alias("q")).first()["q"] or []
        lows = sorted({float(x) for x in cut}, reverse=True)
    else:
        lows = [1 - (k + 1) / bands for k in range(bands - 1)]
    tail = max(floor, 5e-324)
    return [x for x in lows if x > tail] + [tail]


def _grid(pivots: DataFrame | None, low: float, high: float | None) -> list[float] | None:
    """The band's pivots in ascending order if they are known and GRID at most."""
    if pivots is None:
        return None
    inside = pivots.where((F.col("key") >= low) & (F.col("key") < (high if high is not None else 2.0)))
    found = sorted(r["key"] for r in inside.limit(GRID + 1).collect())
    return found if found and len(found) <= GRID else None


def _evaluate(score: ScoreState, extra: DataFrame | Parts, p: Prepared | Blocks, objective: Objective, pivots: str, top: dict | None, stop_early: bool):
    """The band's thresholds that were looked at, one row with their number, the best and where the run may stop, and the band's sums."""
    level_rows = keep(score.extend(extra), "levels")
    sums = level_sums(level_rows)
    in_band = scored(profile(level_rows, p.size_r, p.size_s, score.base, sums["levels"]), objective)
    if pivots != "all":
        in_band = in_band.where("pivotal")
    in_band = until_stop(in_band, top["h"] if top else None, sums["levels"])
    end = in_band.agg(F.max(F.when(F.col("stops") & F.lit(stop_early), F.col("key"))).alias("last"))
    seen = in_band.crossJoin(F.broadcast(end)).where(F.col("key") >= F.coalesce("last", F.lit(-1.0)))
    best = seen.agg(F.count(F.lit(1)).alias("n"), F.max(F.struct("h", "key", "n_join")).alias("best"), F.max("last").alias("last")).first()
    score.close(sums)
    return seen, best, sums


#: Keys at which bands of blocks are cut besides their own ends: each step is a pass over both sides.
CUTS = [0.5**k for k in range(1, 7)]
#: Of these, those down to which a lazy pass goes that compares whole sets: its time hardly depends on where it ends.
REACH = CUTS[2::3]
#: Pairs of lower keys are not counted by their keys where the score does not ask for it; they have most of all keys.
COUNTED = 0.25


def _parts(rows: DataFrame, low: float | None = None, high: float | None = None) -> Parts:
    """Rows of ``level_parts``, of keys from ``low`` up to ``high``, as parts of a score."""
    covers = rows.where(F.col("kind").isin(COVER_R, COVER_S)).groupBy(F.when(F.col("kind") == COVER_R, "r").otherwise("s").alias("side"), F.col("a").alias("id")).agg(F.max("key").alias("best"), F.max("n").alias("w"))
    inside = lambda x, key: x if low is None else x.where((F.col(key) >= low) & (F.col(key) < (2.0 if high is None else high)))
    pairs = lambda kind, *c: inside(rows.where(F.col("kind") == kind), "key").select(F.col("a").alias("r"), F.col("b").alias("s"), "key", *c)
    return Parts(inside(rows.where(F.col("kind") == JOIN), "key").select("key", "n"), inside(covers, "best"), pairs(MUTUAL, "n"), pairs(EDGE))


def block_pivots(b: Blocks, sim: SetSimilarity, low: float, bounds: str = "tight") -> DataFrame:
    """Pivotal keys of ``low`` or more: of the pairs that are best for both ends."""
    parts = _parts(keep(level_parts(b, sim, low, joins=False, bounds=bounds), "parts"))
    r, s = (parts.covers.where(F.col("side") == x).select(F.col("id").alias(x), F.col("best").alias(f"best_{x}")) for x in "rs")
    return parts.near.join(r, "r").join(s, "s").where("key = best_r AND key = best_s").select("key").distinct()


def _join_blocks(b: Blocks, sim: SetSimilarity, objective: Objective, pivots: str, verify: str, bands: int | str, floor: float, bounds: str, stop_early: bool) -> Result:
    began = time.time()
    low_key = sim.key_of(floor) if floor else 0.0
    tail = max(low_key, 5e-324)
    known = keep(block_pivots(b, sim, tail, bounds), "pivots") if pivots == "topk" or bands == "pivot" else None
    lows = [tail] if bands == "pivot" else plan_bands(bands, known, low_key)
    once = verify == "heap"  # one pass meets every pair, and the bands take from its sums
    if not once:
        lows = sorted({*lows, *(x for x in CUTS if x > tail)}, reverse=True)
    every = keep(level_parts(b, sim, tail, forest=objective.needs_forest, whole=True, bounds=bounds), "parts") if once else None
    joins = True if once or verify != "lazy" or objective.needs_joins or pivots == "all" else COUNTED
    score, looked_at, top, high, rows, reach = ScoreState(objective.needs_forest), None, None, None, every, tail if once else 2.0
    metrics = {"bands": 0, "values": 0, "evaluated": 0, "passes": int(once) + (known is not None)}
    stopped = False
    for low in lows:
        metrics["bands"] += 1
        if low < reach:
            metrics["passes"] += 1
            discard(rows)
            reach = low if verify != "lazy" or low >= WHOLE else max(x for x in [*REACH, tail] if x <= low)
            rows = keep(level_parts(b, sim, reach, high, joins, objective.needs_forest, whole=verify == "eager", bounds=bounds), "parts")
        seen, best, sums = _evaluate(score, _parts(rows, low, high), b, objective, pivots, top, stop_early)
        if joins is not True:
            seen = seen.withColumn("n_join", F.when(F.col("key") >= joins, F.col("n_join")))
        metrics["evaluated"] += best["n"]
        metrics["values"] += sums["levels"]
        looked_at = seen if looked_at is None else looked_at.unionByName(seen)
        if best["best"] is not None and (top is None or best["best"]["h"] > top["h"]):
            top = best["best"].asDict()
        high = low
        stopped = best["last"] is not None
        if stopped:
            break
    discard(rows)
    pairs = block_join(b, sim, top["key"] if top else 1.0, bounds=bounds)
    if top and joins is not True and top["key"] < joins:
        metrics["passes"] += 1
        top["n_join"] = level_parts(b, sim, top["key"], covers=False, bounds=bounds).agg(F.sum("n")).first()[0]
    metrics |= {"stopped": float(stopped), "seconds": time.time() - began}
    if top is None:
        return Result(pairs.limit(0), None, None, looked_at, metrics)
    return Result(pairs, sim.value(top["key"]), top["h"], looked_at, metrics, top["n_join"])


def auto_join(p: Prepared | Blocks, sim: SetSimilarity, objective: Objective, pivots: str = "fused", verify: str = "eager", bands: int | str = 5, floor: float = 0.0, bounds: str = "tight", stop_early: bool = True) -> Result:
    """Find the largest threshold of best score and its pairs.

    ``pivots``: ``topk`` finds the pivotal thresholds first, ``fused`` inside each band, ``all`` looks at every value.
    ``verify``: ``eager`` compares open candidates anew in every band, ``heap`` once and keeps their keys, ``lazy`` only pairs
    that their bounds leave open, and with known pivots only as far as to say between which of them a pair lies (the
    result's pairs are completed at the end). An objective that does not allow pivots gets all values. Nothing at or
    above ``floor``: an empty result with theta None.

    With both sides in blocks ``eager`` compares all pairs in full in every step, ``heap`` once in all, ``lazy`` only those
    that their prefixes leave open, as long as the threshold leaves a prefix.
    """
    began = time.time()
    if not objective.pivots_valid:
        pivots = "all"
    if isinstance(p, Blocks):
        return _join_blocks(p, sim, objective, pivots, verify, bands, floor, bounds, stop_early)
    low_key = sim.key_of(floor) if floor else 0.0
    known = keep(pivots_by_search(p, sim, bounds, low_key), "pivots") if pivots == "topk" or bands == "pivot" else None
    lows = plan_bands(bands, known, low_key)
    columns = pair_columns(p)
    score = ScoreState(objective.needs_forest)
    joined: DataFrame | None = None
    waiting: DataFrame | None = None
    looked_at: DataFrame | None = None
    top: dict | None = None
    metrics = {"candidates": 0, "tokens_scanned": 0, "verified": 0, "postponed": 0, "pruned": 0, "placed": 0, "bands": 0, "values": 0, "evaluated": 0}
    high: float | None = None
    stopped = False
    for low in lows:
        metrics["bands"] += 1
        grid = _grid(known if pivots == "topk" else None, low, high) if verify == "lazy" else None
        met = meetings(p, sim, low, high, bounds)
        if joined is not None:
            met = met.join(joined.select("r", "s"), ["r", "s"], "left_anti")
        if verify == "lazy":
            empty = met.withColumns({"was": F.lit(0).cast("bigint"), "o": F.lit(None).cast("bigint"), "key": F.lit(None).cast("double")})
            rows = keep(classify(empty if waiting is None else merge_meetings(waiting, met, columns), sim, low, bounds, grid), "met")
            looked = verify_rest(rows.where("fate = 'open'").drop("o", "key", "top"), p, sim).withColumn("top", F.col("key"))
            looked = looked.withColumn("fate", F.when(F.col("key") >= low, "in").otherwise("later"))
            if grid:
                looked = looked.withColumn("key", F.when(F.col("fate") == "in", placed(F.col("key"), grid)).otherwise(F.col("key")))
            # What can reach no band any more is dropped.
            alive = rows.where("fate <> 'open'").unionByName(looked.select(*rows.columns)).where(F.col("top") >= lows[-1])
            state = keep(alive, "state")
            extra, waiting = state.where("fate = 'in'").select(*columns, "o", "key"), state.where("fate = 'later'").select(*columns, "seen", "i", "j", "o", "key")
            n = rows.agg(F.count(F.lit(1)).alias("n"), F.sum(2 * (F.col("seen") - F.col("was"))).alias("seen"), *(F.count_if(F.col("fate") == x).alias(x) for x in ("open", "in")), F.count_if(F.col("top") < lows[-1]).alias("pruned"), F.sum(F.when(F.col("fate") == "open", F.col("nr") - F.col("i") + F.col("ns") - F.col("j"))).alias("rest")).first()
            metrics["candidates"] = max(metrics["candidates"], n["n"])
            metrics["tokens_scanned"] += (n["seen"] or 0) + (n["rest"] or 0)
            for name, x in (("verified", n["open"]), ("placed", n["in"]), ("pruned", n["pruned"]), ("postponed", n["n"] - n["open"] - n["in"] - n["pruned"])):
                metrics[name] += x
            discard(rows)
        else:
            new = met.select(*columns) if waiting is None else met.select(*columns).join(waiting.select("r", "s"), ["r", "s"], "left_anti")
            if verify == "heap":  # every pair's key is made when it is met
                new = verify_eager(new, p, sim).withColumn("met", F.lit(1))
                state = keep(new if waiting is None else new.unionByName(waiting.withColumn("met", F.lit(0))), "state")
                fits = F.lit(True)
            else:  # sizes alone keep some pairs below the band: they are not looked at, but wait
                both = new.withColumn("met", F.lit(1)) if waiting is None else new.withColumn("met", F.lit(1)).unionByName(waiting.select(*columns).withColumn("met", F.lit(0)))
                fits = sim.key(F.least("nr", "ns"), F.col("nr"), F.col("ns")) >= low
                both = keep(both, "candidates")
                none = {"o": F.lit(None).cast("bigint"), "key": F.lit(0.0)}
                looked = verify_eager(both.where(fits), p, sim)
                state = keep(looked.unionByName(both.where(~fits).withColumns(none).select(*looked.columns)), "state")
                discard(both)
            extra, waiting = state.where(F.col("key") >= low).select(*columns, "o", "key"), state.where(F.col("key") < low).select(*columns, "o", "key")
            read = fits if verify == "eager" else F.col("met") == 1
            n = state.agg(F.sum("met").alias("met"), F.count_if(read).alias("n"), F.sum(F.when(read, F.col("nr") + F.col("ns"))).alias("read")).first()
            metrics["candidates"] += n["met"] or 0
            metrics["verified"] += n["n"]
            metrics["tokens_scanned"] += n["read"] or 0
        joined = extra if joined is None else joined.unionByName(extra)
        # All that is joined lies at or above the band's end, so its levels are final.
        seen, best, sums = _evaluate(score, extra, p, objective, pivots, top, stop_early)
        metrics["evaluated"] += best["n"]
        looked_at = seen if looked_at is None else looked_at.unionByName(seen)
        if best["best"] is not None and (top is None or best["best"]["h"] > top["h"]):
            top = best["best"].asDict()
        metrics["values"] += sums["levels"]
        last = best["last"]
        high = low
        if last is not None:
            stopped = True
            break
    if top is None:
        return Result(expand(joined.limit(0), p), None, None, looked_at, metrics | {"stopped": float(stopped), "seconds": time.time() - began})
    pairs = joined.where(F.col("key") >= top["key"])
    if verify == "lazy" and known is not None:  # pairs that were placed by their bounds get their keys now
        pairs = keep(pairs.where("o IS NOT NULL").unionByName(verify_eager(pairs.where("o IS NULL").select(*columns), p, sim).select(*pairs.columns)), "pairs")
        pairs = pairs.withColumn("key", sim.key(F.col("o"), F.col("nr"), F.col("ns")))
    return Result(expand(pairs, p), sim.value(top["key"]), top["h"], looked_at, metrics | {"stopped": float(stopped), "seconds": time.time() - began}, top["n_join"])


def brute_force(p: Prepared, sim: SetSimilarity, objective: Objective, pairs: DataFrame | None = None) -> Result:
    """Every pair, every value a threshold: the baseline."""
    began = time.time()
    pairs = keep(pairs if pairs is not None else sharing_pairs(p, sim), "pairs")
    rows = keep(scored(profile(levels(pairs, objective.needs_forest), p.size_r, p.size_s), objective), "profile")
    best = rows.orderBy(F.desc("h"), F.desc("key")).first()
    n = rows.count()
    metrics = {"evaluated": n, "values": n, "seconds": time.time() - began}
    if best is None:
        return Result(expand(pairs, p), None, None, rows, metrics)
    return Result(expand(pairs.where(F.col("key") >= best["key"]), p), sim.value(best["key"]), best["h"], rows, metrics, best["n_join"])


def report(p: Prepared, sim: SetSimilarity, objective: Objective, pairs: DataFrame) -> DataFrame:
    """One declarative plan without a loop: theta*, score and size of its join from all sharing pairs' profile."""
    rows = scored(profile(levels(pairs, objective.needs_forest), p.size_r, p.size_s), objective)
    if objective.pivots_valid:
        rows = rows.where("pivotal")
    return rows.orderBy(F.desc("h"), F.desc("key")).limit(1).withColumn("objective", F.lit(objective.name)).select("objective", F.round(sim.value(F.col("key")), 6).alias("theta"), "h", "n_join", "cov_r", "cov_s")


__all__ = ["Result", "auto_join", "brute_force", "pivotal_thresholds", "pivots_by_search", "plan_bands", "report", "top_search"]
