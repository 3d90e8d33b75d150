"""Streams over events and documents replayed as files: each ends with what its batch twin gives."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F

from autotheta.functions.text import TOKENIZERS, elements
from autotheta.operators import objectives, simjoin
from autotheta.plans.workloads import OUTER_SQL, STATE_SQL, W, pairs_sql, sides
from autotheta.sources.shared import keep, new_path

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def _add(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = sql
        return f

    return add


def replay(df: DataFrame, parts: list | None = None) -> DataFrame:
    """A stream over ``df`` written as files; ``parts`` are conditions, a file each, in this order, one a batch."""
    spark, path = df.sparkSession, new_path(df.sparkSession, "replay")
    for k, part in enumerate(parts or [F.lit(True)]):
        df.where(part).coalesce(1).write.mode("append").parquet(path)
        if k + 1 < len(parts or []):
            time.sleep(1.1)  # files are read in the order of their times, of seconds
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end of what is there; the rows of the last (complete) or of all batches."""
    spark, out = stream.sparkSession, new_path(stream.sparkSession, "stream")
    schema = stream.schema

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{'all' if mode == 'complete' else number}")

    q = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", new_path(spark, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(schema).parquet(f"{out}/*")


def _events(spark: SparkSession, d: str) -> DataFrame:
    e = spark.read.parquet(f"{d}/events.parquet")
    return e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")


_HOUR = "epoch_us(ts) // 3600000000"


@_add("stream_tumbling", f"SELECT {_HOUR} AS hour, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    s = replay(_events(spark, d), [F.col("event_id") % 2 == 0, F.col("event_id") % 2 == 1]).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return run(s, "complete").select(F.expr("unix_micros(window.start) div 3600000000").alias("hour"), "event_type", "n", F.round("total", 4).alias("total"))


@_add("stream_sliding", f"SELECT h AS hour, count(*) AS n FROM (SELECT unnest([{_HOUR} - 1, {_HOUR}]) AS h FROM events) GROUP BY h")
def stream_sliding(spark, d):
    s = replay(_events(spark, d)).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return run(s, "complete").select(F.expr("unix_micros(window.start) div 3600000000").alias("hour"), "n")


@_add("stream_session", """SELECT user_id, count(*) AS n, epoch_us(min(ts)) AS first FROM (SELECT user_id, ts, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k
  FROM (SELECT user_id, ts, event_id, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS cut FROM events)) GROUP BY user_id, k""")
def stream_session(spark, d):
    s = replay(_events(spark, d), [F.col("event_id") % 2 == 0, F.col("event_id") % 2 == 1]).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return run(s, "complete").select("user_id", "n", F.unix_micros("session_window.start").alias("first"))


_CUT = "(SELECT min(ts) + (max(ts) - min(ts)) / 2 FROM events)"


@_add("stream_watermark_late", f"SELECT {_HOUR} AS hour, count(*) AS n FROM events WHERE ts >= {_CUT} GROUP BY 1 HAVING (hour + 1) * 3600000000 <= (SELECT epoch_us(max(ts)) FROM events) - 3600000000")
def stream_watermark_late(spark, d):
    """New events in two files, old ones in a third: those are too late and count no more.

    A batch drops what is older than the watermark that the batch before evicted by, so it takes two before.
    """
    e = _events(spark, d)
    cut = e.agg((F.min(F.unix_micros("ts")) + (F.max(F.unix_micros("ts")) - F.min(F.unix_micros("ts"))) / 2).cast("bigint")).first()[0]
    new = F.unix_micros("ts") >= cut
    even = F.col("event_id") % 2 == 0
    s = replay(e, [new & even, new & ~even, ~new]).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return run(s).select(F.expr("unix_micros(window.start) div 3600000000").alias("hour"), "n")


@_add("stream_dedup", "SELECT event_id, user_id FROM events")
def stream_dedup(spark, d):
    e = _events(spark, d)
    return run(replay(e.unionByName(e)).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


@_add("stream_static_join", "SELECT e.event_id, c.c_name FROM events e JOIN customer c ON e.user_id = c.c_custkey")
def stream_static_join(spark, d):
    c = spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_name")
    return run(replay(_events(spark, d)).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"))


@_add("stream_stream_join", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 6 HOUR")
def stream_stream_join(spark, d):
    e = _events(spark, d)
    v = replay(e.where("event_type = 'view'")).withWatermark("ts", "2 hours").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("ts").alias("tv"))
    p = replay(e.where("event_type = 'purchase'")).withWatermark("ts", "2 hours").select(F.col("event_id").alias("purchase_id"), "user_id", "ts")
    return run(v.join(p, F.expr("u = user_id AND ts >= tv AND ts <= tv + INTERVAL 6 HOURS")).select("view_id", "purchase_id"))


def _batches(stream: DataFrame, f) -> None:
    q = stream.writeStream.foreachBatch(f).option("checkpointLocation", new_path(stream.sparkSession, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()


@_add("stream_simjoin", f"WITH {pairs_sql('w4', truth=False)} SELECT r, s, o FROM pairs WHERE o >= 10")
def stream_simjoin(spark, d):
    """Arriving documents against the benchmark, whose elements are indexed once: shared words of both bags, 10 or more."""
    w = W["w4"]
    r, s, _ = sides(w, spark, d)
    tokens = TOKENIZERS[w.tokens](F.col("text"))
    index = keep(elements(s, tokens, w.bag).select(F.col("id").alias("s"), "tok"), "index")
    out = new_path(spark, "simjoin")

    def join(batch: DataFrame, number: int) -> None:
        e = elements(batch, tokens, w.bag).select(F.col("id").alias("r"), "tok")
        e.join(index, "tok").groupBy("r", "s").agg(F.count(F.lit(1)).alias("o")).where("o >= 10").write.mode("overwrite").parquet(f"{out}/{number}")

    _batches(replay(r, [F.col("id") % 2 == 0, F.col("id") % 2 == 1]), join)
    return spark.read.parquet(f"{out}/*")


@_add("stream_profile", f"WITH RECURSIVE {pairs_sql('w2', truth=False)}, {STATE_SQL}, {OUTER_SQL} SELECT round(key, 9) AS key, n_join, cov_r, cov_s, h::BIGINT AS h FROM scored")
def stream_profile(spark, d):
    """The outer size's profile over arriving objects of one side: level counts add up, first covers take the maximum.

    Both are commutative, so the order of arrival does not matter and rows need no watermark. The order of
    elements plays no part in counting shared ones.
    """
    w = W["w2"]
    r, s, _ = sides(w, spark, d)
    tokens = TOKENIZERS[w.tokens](F.col("text"))
    es = keep(elements(s, tokens, w.bag).select(F.col("id").alias("s"), "tok"), "index")
    ns = keep(es.groupBy("s").agg(F.count(F.lit(1)).alias("ns")), "sizes")
    out = new_path(spark, "profile")

    def merge(batch: DataFrame, number: int) -> None:
        er = elements(batch, tokens, w.bag).select(F.col("id").alias("r"), "tok")
        nr = er.groupBy("r").agg(F.count(F.lit(1)).alias("nr"))
        pairs = er.join(es, "tok").groupBy("r", "s").agg(F.count(F.lit(1)).alias("o")).join(nr, "r").join(ns, "s")
        pairs = pairs.select("r", "s", w.sim.key(F.col("o"), F.col("nr"), F.col("ns")).alias("key"))
        pairs = keep(pairs, "pairs")
        pairs.groupBy("key").agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{out}/join/{number}")
        simjoin.best(pairs, "r").groupBy(F.col("best").alias("key")).agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{out}/r/{number}")
        simjoin.best(pairs, "s").write.mode("overwrite").parquet(f"{out}/s/{number}")

    _batches(replay(r, [F.col("id") % 3 == k for k in range(3)]), merge)
    zero = F.lit(0).cast("bigint")
    join = spark.read.parquet(f"{out}/join/*").select("key", F.col("n").alias("d_join"), zero.alias("d_r"), zero.alias("d_s"))
    cr = spark.read.parquet(f"{out}/r/*").select("key", zero.alias("d_join"), F.col("n").alias("d_r"), zero.alias("d_s"))
    cs = spark.read.parquet(f"{out}/s/*").groupBy("s").agg(F.max("best").alias("key")).select("key", zero.alias("d_join"), zero.alias("d_r"), F.lit(1).cast("bigint").alias("d_s"))
    rows = join.unionByName(cr).unionByName(cs).groupBy("key").agg(*(F.sum(x).alias(x) for x in ("d_join", "d_r", "d_s"))).withColumns({"d_forest": zero, "d_mutual": zero})
    scored = objectives.scored(objectives.profile(rows, r.count(), s.count()), objectives.outer_size())
    return scored.select(F.round("key", 9).alias("key"), "n_join", "cov_r", "cov_s", "h")


@_add("stream_modes", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_modes(spark, d):
    """Update mode over two batches: the last row of each key counts."""
    out = new_path(spark, "modes")
    s = replay(_events(spark, d), [F.col("event_id") % 2 == 0, F.col("event_id") % 2 == 1]).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/{number}")

    q = s.writeStream.foreachBatch(write).outputMode("update").option("checkpointLocation", new_path(spark, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{out}/*").groupBy("event_type").agg(F.max_by("n", "batch").alias("n"))


