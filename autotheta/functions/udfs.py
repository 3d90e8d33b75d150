"""The surface for functions of a user's own: each has a built-in twin that it is compared with."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from autotheta.operators.objectives import levels
from autotheta.operators.simjoin import sharing_pairs
from autotheta.plans.workloads import OUTER_SQL, STATE_SQL, W, fixture, pairs_sql
from autotheta.sources.shared import map_arrow

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def _add(name: str, sql: str):
    def add(f):
        QUERIES[name], ORACLE[name] = f, sql
        return f

    return add


def _read(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


@_add("udf_scalar_pandas", "SELECT l_orderkey, l_linenumber, l_quantity * 2 + 1 AS x FROM lineitem")
def udf_scalar_pandas(spark, d):
    @F.pandas_udf("double")
    def twice(v: pd.Series) -> pd.Series:
        return v * 2 + 1

    return _read(spark, d, "lineitem").select("l_orderkey", "l_linenumber", twice("l_quantity").alias("x"))


@_add("udf_scalar_arrow", "SELECT c_custkey, length(c_name) AS n FROM customer")
def udf_scalar_arrow(spark, d):
    @F.udf("bigint", useArrow=True)
    def length(x: str) -> int:
        return len(x)

    return _read(spark, d, "customer").select("c_custkey", length("c_name").alias("n"))


@_add("udf_grouped_map", "SELECT c_nationkey, c_custkey, round(c_acctbal - avg(c_acctbal) OVER (PARTITION BY c_nationkey), 4) AS off FROM customer")
def udf_grouped_map(spark, d):
    def centre(t: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"c_nationkey": t.c_nationkey, "c_custkey": t.c_custkey, "off": (t.c_acctbal - t.c_acctbal.mean())})

    rows = _read(spark, d, "customer").groupBy("c_nationkey").applyInPandas(centre, "c_nationkey int, c_custkey bigint, off double")
    return rows.withColumn("off", F.round("off", 4))


@_add("udf_map_arrow", "SELECT p_partkey, p_size * 10 AS x FROM part")
def udf_map_arrow(spark, d):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(b.column(1).to_numpy() * 10, pa.int64())], ["p_partkey", "x"])

    return map_arrow(_read(spark, d, "part").select("p_partkey", "p_size"), run, "p_partkey bigint, x bigint")


@_add("udaf_pandas", "SELECT event_type, round(max(value) - min(value), 6) AS spread FROM events GROUP BY event_type")
def udaf_pandas(spark, d):
    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return _read(spark, d, "events").groupBy("event_type").agg(F.round(spread("value"), 6).alias("spread"))


def register_udtfs(spark: SparkSession) -> None:
    """For SQL: ``qgrams(text, q)``, position and substring, a row each; ``auto_report(TABLE(levels), size_r, size_s)``, the
    chosen threshold and its score by outer size from rows ``key, d_join, d_r, d_s`` in descending order of keys."""

    @F.udtf(returnType="pos int, gram string")
    class QGrams:
        def eval(self, text: str, q: int):
            for i in range(len(text or "") - q + 1):
                yield i + 1, text[i : i + q]

    @F.udtf(returnType="theta double, h bigint, n_join bigint")
    class AutoReport:
        def __init__(self):
            self.best, self.joined, self.covered = None, 0, 0

        def eval(self, row, size_r: int, size_s: int):
            self.joined += row["d_join"]
            self.covered += row["d_r"] + row["d_s"]
            h = self.covered - self.joined - size_r - size_s
            if self.best is None or h > self.best[1]:
                self.best = (row["key"], h, self.joined)

        def terminate(self):
            if self.best is not None:
                yield self.best

    spark.udtf.register("qgrams", QGrams)
    spark.udtf.register("auto_report", AutoReport)


@_add("udtf_auto_report", f"WITH RECURSIVE {pairs_sql('w5', truth=False)}, {STATE_SQL}, {OUTER_SQL} SELECT round(key, 6) AS theta, h::BIGINT AS h, n_join FROM scored ORDER BY scored.h DESC, scored.key DESC LIMIT 1")
def udtf_auto_report(spark, d):
    """The levels' rows, few beside the pairs', go through one Python table function in SQL."""
    register_udtfs(spark)
    f = fixture("w5", spark, d)
    levels(sharing_pairs(f.prepared, W["w5"].sim), forest=False).createOrReplaceTempView("autotheta_levels")
    rows = spark.sql(f"SELECT * FROM auto_report(TABLE(SELECT key, d_join, d_r, d_s FROM autotheta_levels) WITH SINGLE PARTITION ORDER BY (key DESC), {f.prepared.size_r}, {f.prepared.size_s})")
    return rows.select(F.round("theta", 6).alias("theta"), "h", "n_join")


@_add("udtf_qgrams", "SELECT s_suppkey, i::INT AS pos, substr(s_name, i, 3) AS gram FROM (SELECT s_suppkey, s_name, unnest(range(1, length(s_name) - 1)) AS i FROM supplier)")
def udtf_qgrams(spark, d):
    register_udtfs(spark)
    return spark.sql(f"SELECT s_suppkey, pos, gram FROM parquet.`{d}/supplier.parquet`, LATERAL qgrams(s_name, 3)")


@_add("udf_cogroup", "SELECT n_regionkey AS k, count(*) AS nations, (SELECT count(*) FROM region WHERE r_regionkey = n_regionkey) AS regions FROM nation GROUP BY n_regionkey")
def udf_cogroup(spark, d):
    def both(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [key[0]], "nations": [len(a)], "regions": [len(b)]})

    n, r = _read(spark, d, "nation").select(F.col("n_regionkey").alias("k")), _read(spark, d, "region").select(F.col("r_regionkey").alias("k"))
    return n.groupBy("k").cogroup(r.groupBy("k")).applyInPandas(both, "k int, nations bigint, regions bigint")
