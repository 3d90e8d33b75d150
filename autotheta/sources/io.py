"""Sources and sinks: round trips through every file format, a Python data source for candidate dumps, result sinks."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from autotheta.sources.shared import new_path, ship

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def _add(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


def _part(spark: SparkSession, d: str) -> DataFrame:
    return spark.read.parquet(f"{d}/part.parquet").select("p_partkey", "p_name", "p_size", "p_retailprice")


def _round_trip(spark: SparkSession, d: str, kind: str, **options) -> DataFrame:
    df, path = _part(spark, d), new_path(spark, kind)
    df.write.format(kind).options(**options).save(path)
    return spark.read.format(kind).schema(df.schema).options(**options).load(path)


for _kind, _options in (("csv", {"header": True}), ("json", {}), ("orc", {})):
    _add(f"io_{_kind}", "SELECT p_partkey, p_name, p_size, p_retailprice FROM part")(lambda spark, d, k=_kind, o=_options: _round_trip(spark, d, k, **o))


@_add("io_text", "SELECT p_name AS value, count(*) AS n FROM part GROUP BY p_name")
def io_text(spark, d):
    path = new_path(spark, "text")
    _part(spark, d).select(F.col("p_name").alias("value")).write.text(path)
    return spark.read.text(path).groupBy("value").agg(F.count(F.lit(1)).alias("n"))


@_add("io_partitioned", "SELECT o_orderkey, year(o_orderdate)::INT AS y FROM orders WHERE year(o_orderdate) = 1995")
def io_partitioned(spark, d):
    path = new_path(spark, "orders")
    orders = spark.read.parquet(f"{d}/orders.parquet").withColumn("y", F.year("o_orderdate"))
    orders.repartition("y").write.partitionBy("y").parquet(path)
    return spark.read.parquet(path).where("y = 1995").select("o_orderkey", "y")


@_add("io_bucketed", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey")
def io_bucketed(spark, d):
    """Orders in buckets of the customer, so that later joins and groups on it need no shuffle."""
    name = "autotheta_" + new_path(spark, "b").rpartition("-")[2]
    spark.read.parquet(f"{d}/orders.parquet").write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", new_path(spark, "bucketed")).saveAsTable(name)
    return spark.table(name).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))


class CandidateSource(DataSource):
    """Candidate dumps: text files of ``r<TAB>s<TAB>key`` lines, a partition a file. Option ``path``: files, comma-separated."""

    @classmethod
    def name(cls) -> str:
        return "autotheta_candidates"

    def schema(self) -> str:
        return "r bigint, s bigint, key double"

    def reader(self, schema) -> DataSourceReader:
        return CandidateReader(self.options["path"].split(","))


class CandidateReader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(p) for p in self.paths]

    def read(self, partition: InputPartition) -> Iterator:
        """Record batches: a file is read block by block."""
        import pyarrow as pa
        from pyarrow import csv

        from autotheta.sources.shared import open_store

        kinds = {"r": pa.int64(), "s": pa.int64(), "key": pa.float64()}
        store, path = open_store(partition.value)
        if not store.get_file_info(path).size:
            return
        with store.open_input_stream(path) as f:
            yield from csv.open_csv(f, csv.ReadOptions(use_threads=False, column_names=list(kinds)), csv.ParseOptions(delimiter="\t", quote_char=False), csv.ConvertOptions(column_types=kinds))


def dump_candidates(pairs: DataFrame, path: str) -> list[str]:
    """Write ``r, s, key`` as candidate dumps, a file a task; their paths."""
    from pyarrow import fs

    from autotheta.sources.shared import open_store

    pairs.select(F.concat_ws("\t", *(F.coalesce(F.col(c).cast("string"), F.lit("")) for c in ("r", "s", "key")))).write.text(path)
    store, root = open_store(path)
    return [f"{path}/{x.base_name}" for x in store.get_file_info(fs.FileSelector(root)) if x.base_name.startswith("part-")]


@_add("src_candidates", "SELECT o_orderkey AS r, o_custkey AS s, o_totalprice AS key FROM orders")
def src_candidates(spark, d):
    """Orders and their customers as candidates: dumped to text and read again by the source."""
    ship(spark)
    pairs = spark.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("r"), F.col("o_custkey").alias("s"), F.col("o_totalprice").alias("key"))
    spark.dataSource.register(CandidateSource)
    return spark.read.format("autotheta_candidates").load(",".join(dump_candidates(pairs, new_path(spark, "candidates"))))


def write_result(pairs: DataFrame, path: str) -> None:
    """Joined pairs by band of 0.1, for readers that want the surest first."""
    pairs.withColumn("band", F.floor(F.col("key") * 10).cast("int")).write.partitionBy("band").parquet(path)


@_add("sink_result")
def sink_result(spark, d):
    from autotheta.plans.workloads import W, fixture
    from autotheta.operators.simjoin import sharing_pairs

    path = new_path(spark, "result")
    write_result(sharing_pairs(fixture("w5", spark, d).prepared, W["w5"].sim), path)
    return spark.read.parquet(path).where("band >= 4").select("r", "s", F.round("key", 6).alias("key"))
