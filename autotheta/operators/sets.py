"""Objects as sets in one global order, rare elements first, and their postings."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

from autotheta.functions.sims import SetSimilarity
from autotheta.functions.text import TOKENIZERS, elements
from autotheta.sources.shared import discard, keep


def require_columns(df: DataFrame, *names: str) -> None:
    missing = [n for n in names if n not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing in {df.columns}")


def sizes_of(r: DataFrame, s: DataFrame, check: bool = True) -> tuple[int, int]:
    """Objects of both sides, in one job. ``check``: ids name objects, so it is an error if one is null or stands twice."""
    rows = r.select(F.lit("r").alias("side"), "id").unionByName(s.select(F.lit("s").alias("side"), "id"))
    if check:
        each = rows.groupBy("side", "id").agg(F.count(F.lit(1)).alias("c"))
        per = each.groupBy("side").agg(F.sum("c").alias("n"), (F.count_if(F.col("id").isNull()) + F.count_if(F.col("c") > 1)).alias("bad"))
    else:
        per = rows.groupBy("side").agg(F.count(F.lit(1)).alias("n"), F.lit(0).alias("bad"))
    found = {x["side"]: x for x in per.collect()}
    if any(x["bad"] for x in found.values()):
        raise ValueError("ids must be unique and not null")
    return tuple(found[x]["n"] if x in found else 0 for x in "rs")


def token_frequencies(*sides: DataFrame) -> DataFrame:
    """``tok, df``: in how many objects of all sides an element is."""
    rows = sides[0].select("tok")
    for s in sides[1:]:
        rows = rows.unionByName(s.select("tok"))
    return rows.groupBy("tok").agg(F.count(F.lit(1)).alias("df"))


def order_tokens(frequencies: DataFrame) -> DataFrame:
    """``tok, df, t``: numbers that follow the order (df, tok), without gathering it in one task."""
    ranged = frequencies.repartitionByRange("df", "tok").sortWithinPartitions("df", "tok")
    return keep(ranged.withColumn("t", F.monotonically_increasing_id()), "order")


def ordered_sets(side: DataFrame, order: DataFrame) -> DataFrame:
    """``id, toks, n`` with toks in global order."""
    return side.join(order.select("tok", "t"), "tok").groupBy("id").agg(F.array_sort(F.collect_list("t")).alias("toks")).withColumn("n", F.size("toks").cast("bigint"))


def collapse(sets: DataFrame) -> DataFrame:
    """Classes of equal sets: ``rep`` (least id), ``weight``, ``toks``, ``n``."""
    return sets.groupBy("toks").agg(F.min("id").alias("rep"), F.count(F.lit(1)).alias("weight"), F.first("n").alias("n"))


#: Objects that hold an element from which on its postings are dealt over SALTS tasks.
HOT, SALTS = 100_000, 16


@dataclass
class Prepared:
    """Both sides as ordered sets ``id, toks, n``, their counts of objects (with those that have no element), and the order.

    Where equal sets are collapsed, ``id`` is the least of a class, ``w`` its number of objects and ``members_r``,
    ``members_s`` give ``rep, id`` of each object. ``hot``: the number of the first element that HOT objects hold, if any does.
    """

    r: DataFrame
    s: DataFrame
    size_r: int
    size_s: int
    order: DataFrame
    members_r: DataFrame | None = None
    members_s: DataFrame | None = None
    hot: int | None = None

    @property
    def collapsed(self) -> bool:
        return self.members_r is not None


def _classes(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Sets by class, with weights, and the members of each class."""
    c = keep(collapse(sets), "classes")
    members = keep(sets.select("id", "toks").join(c.select("rep", "toks"), "toks").select("rep", "id"), "members")
    return c.select(F.col("rep").alias("id"), "toks", "n", F.col("weight").alias("w")), members


def prepare(r: DataFrame, s: DataFrame, tokens: str | Column = "words", bag: bool = False, check: bool = True, collapsed: bool = False, hot: int = HOT) -> Prepared:
    """Tokenise ``id, text`` of both sides. Objects without elements stay in the counts and are in no pair.

    ``check``: ids that are null or stand twice are an error. ``collapsed``: equal sets of a side are compared once.
    """
    require_columns(r, "id", "text")
    require_columns(s, "id", "text")
    n = sizes_of(r, s, check)
    column = TOKENIZERS[tokens](F.col("text")) if isinstance(tokens, str) else tokens
    both = [elements(x, column, bag).withColumn("side", F.lit(name)) for x, name in ((r, "r"), (s, "s"))]
    each = keep(both[0].unionByName(both[1]), "elements")
    order = order_tokens(token_frequencies(each))
    sets = each.join(order.select("tok", "t"), "tok").groupBy("side", "id").agg(F.array_sort(F.collect_list("t")).alias("toks")).withColumn("n", F.size("toks").cast("bigint"))
    sets = keep(sets, "sets")
    discard(each)
    sr, ss = (sets.where(F.col("side") == x).select("id", "toks", "n") for x in "rs")
    mr = ms = None
    if collapsed:
        (sr, mr), (ss, ms) = _classes(sr), _classes(ss)
    first = order.where(F.col("df") >= hot).agg(F.min("t")).first()[0]
    return Prepared(sr, ss, *n, order, mr, ms, first)


def postings(sets: DataFrame, sim: SetSimilarity, side: str, bounds: str = "tight", low: float | None = None) -> DataFrame:
    """``t, id, pos, n, cap``: an inverted index whose caps serve every threshold.

    ``low``: only the places whose cap reaches it; sets are cut before they are spread. Weights are kept where there are some.
    """
    toks = F.col("toks") if low is None else F.slice("toks", 1, sim.prefix_at_most(low, F.col("n"), side, bounds))
    more = ["w"] if "w" in sets.columns else []
    rows = sets.select("id", "n", *more, F.posexplode(toks).alias("p", "t")).withColumn("pos", F.col("p") + 1)
    rows = rows.select("t", "id", "pos", "n", *more, sim.cap(F.col("pos"), F.col("n"), side, bounds).alias("cap"))
    return rows if low is None else rows.where(F.col("cap") >= low)
