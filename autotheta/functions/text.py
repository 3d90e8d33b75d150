"""Text to tokens, as Column expressions; sets and bags as rows of elements."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

#: Between a token and its occurrence number in a bag.
OCCURRENCE = "\x1f"


def word_tokens(c: Column) -> Column:
    """Runs of letters and digits, lower-cased. Null gives an empty array."""
    return F.filter(F.split(F.lower(F.coalesce(c, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def space_tokens(c: Column) -> Column:
    """Parts between single spaces, as written."""
    return F.filter(F.split(F.coalesce(c, F.lit("")), " "), lambda x: x != "")


def qgram_tokens(c: Column, q: int = 2, pad: str | None = None) -> Column:
    """Substrings of length ``q``; with ``pad``, of the text between ``q - 1`` copies of it. Shorter texts have none."""
    c = F.coalesce(c, F.lit(""))
    if pad is not None:
        c = F.when(c != "", F.concat(F.lit(pad * (q - 1)), c, F.lit(pad * (q - 1)))).otherwise(c)
    n = F.length(c)
    return F.when(n >= q, F.transform(F.sequence(F.lit(1), F.greatest(n - q + 1, F.lit(1))), lambda i: F.substring(c, i, F.lit(q)))).otherwise(F.array().cast("array<string>"))


def char_tokens(c: Column) -> Column:
    """Distinct characters."""
    return F.array_distinct(F.filter(F.split(F.coalesce(c, F.lit("")), ""), lambda x: x != ""))


TOKENIZERS = {"words": word_tokens, "spaces": space_tokens, "qgrams": qgram_tokens, "chars": char_tokens}


def as_set(tokens: Column) -> Column:
    return F.array_distinct(tokens)


def elements(objects: DataFrame, tokens: Column, bag: bool = False) -> DataFrame:
    """``id, tok`` of every element. A bag's element is its token with the number of the occurrence, from the
    second on, so that shared elements of two bags are the sum of the lesser counts."""
    rows = objects.select("id", F.explode(tokens).alias("tok"))
    if not bag:
        return rows.distinct()
    many = rows.groupBy("id", "tok").agg(F.count(F.lit(1)).alias("c"))
    each = many.select("id", "tok", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("c"))).alias("occ"))
    return each.select("id", F.when(F.col("occ") == 1, F.col("tok")).otherwise(F.concat("tok", F.lit(OCCURRENCE), F.col("occ").cast("string"))).alias("tok"))


def prefix(tokens: Column, k: Column | int) -> Column:
    """The first ``k`` tokens in global order."""
    return F.slice(tokens, 1, k if isinstance(k, Column) else F.lit(k))
