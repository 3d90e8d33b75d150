"""Line dedup by distinct-site spread, in DataFrame functions only.

Lines are named by two 64-bit hashes. Lines that stand often enough to matter get a HyperLogLog sketch of
their sites, merged by aggregation. Estimates clearly under or over the limit decide at once; lines near it
get an exact distinct count. Lines on enough sites are boilerplate and leave every text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from autotheta.sources.shared import keep


def _lines(docs: DataFrame) -> DataFrame:
    """``row, site, at, line, h1, h2`` of every line that is not blank."""
    lines = docs.select("row", "site", F.posexplode(F.split("text", "\n")).alias("at", "line")).where("trim(line) <> ''")
    return lines.withColumns({"h1": F.xxhash64("line"), "h2": F.xxhash64(F.lit(1), "line")})


def boilerplate(lines: DataFrame, min_sites: int, lg_k: int = 12, sigmas: float = 6.0) -> DataFrame:
    """``h1, h2, n_sites, exact`` of the lines on ``min_sites`` or more distinct sites.

    The sketch's relative standard error is about 1.04 / sqrt(2^lg_k); estimates within ``sigmas`` of these
    of the limit are counted exactly, so the decision is wrong with a chance of about 1e-9 a line.
    """
    band = sigmas * 1.04 / (2 ** (lg_k / 2))
    pairs = lines.select("h1", "h2", "site")
    often = pairs.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_sites).select("h1", "h2")
    some = keep(pairs.join(often, ["h1", "h2"], "left_semi"), "lines")
    spread = keep(some.groupBy("h1", "h2").agg(F.hll_sketch_estimate(F.hll_sketch_agg("site", F.lit(lg_k))).alias("estimate")), "spread")
    sure = spread.where(F.col("estimate") > min_sites * (1 + band) + 1).select("h1", "h2", F.col("estimate").cast("bigint").alias("n_sites"), F.lit(False).alias("exact"))
    near = spread.where((F.col("estimate") <= min_sites * (1 + band) + 1) & (F.col("estimate") >= min_sites * (1 - band) - 1)).select("h1", "h2")
    counted = some.join(near, ["h1", "h2"], "left_semi").distinct().groupBy("h1", "h2").agg(F.count("site").alias("n_sites")).where(F.col("n_sites") >= min_sites)
    return sure.unionByName(counted.withColumn("exact", F.lit(True)))


def drop_boilerplate_lines(docs: DataFrame, min_sites: int = 10, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source", lg_k: int = 12) -> DataFrame:
    """``doc_id, text, n_lines, n_removed``: texts without the lines that stand on ``min_sites`` sites or more.

    One row per input row. Lines are cut at ``\\n`` and compared as written; blank ones stay and count as no
    line. A null site is no site; a null text stays null with no lines; a text that loses all its lines is
    what its blank lines leave. Repeated rows are documents of their own, as a line's sites are distinct.
    Empty tables give no rows. Other columns are ignored.
    """
    rows = keep(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(site_col).cast("string").alias("site")).withColumn("row", F.monotonically_increasing_id()), "rows")
    lines = _lines(rows)
    found = keep(boilerplate(lines.where("site IS NOT NULL"), min_sites, lg_k), "boilerplate")
    # Only rows that hold a boilerplate line change; the rest never meet a shuffle with their text.
    cut = lines.join(found.select("h1", "h2"), ["h1", "h2"], "left_semi").groupBy("row").agg(F.collect_set("at").alias("cut"))
    text = F.array_join(F.filter(F.split("text", "\n"), lambda x, i: ~F.array_contains("cut", i)), "\n")
    out = rows.join(cut, "row", "left")
    n_lines = F.coalesce(F.size(F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")), F.lit(0)).cast("bigint")
    n_lines = F.when(F.col("text").isNull(), F.lit(0).cast("bigint")).otherwise(n_lines)
    return out.select("doc_id", F.when(F.col("cut").isNull(), F.col("text")).otherwise(text).alias("text"), n_lines.alias("n_lines"), F.coalesce(F.size("cut"), F.lit(0)).cast("bigint").alias("n_removed"))
