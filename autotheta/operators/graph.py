"""Connected components and spanning forests of edge tables.

Partitions first shrink what they hold to a forest (at most one edge a vertex); alternating star steps then
link every vertex to the least of its component. Forests merge in a tree whose levels are jobs of their own; only
what is known to fit a task (FOREST_ROWS edges) ends in one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from autotheta.sources.shared import discard, keep, map_arrow


class DisjointSets:
    """Union-find over integer labels, path halving, the least label as root."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        up = self.up
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def _local_stars(edges: DataFrame) -> DataFrame:
    """Edges ``(a, b)``, b < a, that join the same vertices, with one edge a vertex and partition at most."""

    def run(batches):
        sets = DisjointSets()
        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sets.join(a, b)
        pairs = [(x, sets.find(x)) for x in list(sets.up)]
        pairs = [(x, r) for x, r in pairs if x != r]
        for at in range(0, len(pairs), 100_000):
            part = np.array(pairs[at : at + 100_000], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(part[:, 0]), pa.array(part[:, 1])], ["a", "b"])

    return map_arrow(edges.select(F.col("a").cast("bigint"), F.col("b").cast("bigint")), run, "a bigint, b bigint")


def components(edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """``node, component`` of every vertex of ``edges(a, b)``; the component is its least vertex.

    Loops and repeated edges do not matter; nulls are left out; no edges give no rows. If ``max_rounds`` are not
    enough, that is an error: no part of a result is returned.
    """
    stars = keep(_local_stars(edges.where("a IS NOT NULL AND b IS NOT NULL AND a <> b")), "stars")
    before = None
    for _ in range(max_rounds):
        both = stars.unionByName(stars.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("u"), F.least("a", "m").alias("m"))
        large = both.where("b > a").join(least, F.col("a") == F.col("u")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = keep(large, "stars")
        discard(stars)
        small = large.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "u")
        linked = large.join(small, F.col("a") == F.col("u"))
        stars = keep(linked.select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").unionByName(linked.select("a", F.col("m").alias("b"))).distinct(), "stars")
        discard(large)
        now = stars.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before or not now[0]:
            break
        before = now
    else:
        raise RuntimeError(f"components are not complete after {max_rounds} rounds")
    out = stars.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return out.unionByName(out.select(F.col("component").alias("node"), "component").distinct())


def _local_forest(edges: DataFrame) -> DataFrame:
    """What a maximum spanning forest of each partition keeps of ``a, b, key, r, s``."""

    def run(batches):
        parts = [b for b in batches if b.num_rows]
        if not parts:
            return
        t = pa.Table.from_batches(parts)
        order = np.lexsort((t["s"].to_numpy(), t["r"].to_numpy(), -t["key"].to_numpy()))
        sets, kept = DisjointSets(), []
        a, b = t["a"].to_numpy()[order].tolist(), t["b"].to_numpy()[order].tolist()
        for i, x, y in zip(order.tolist(), a, b, strict=True):
            if sets.join(x, y):
                kept.append(i)
        yield from t.take(pa.array(kept, pa.int64())).combine_chunks().to_batches()

    return map_arrow(edges, run, "a bigint, b bigint, key double, r bigint, s bigint")


def _grow(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges, best first, that join what ``label`` holds apart, and the labels after them: each component takes its
    first edge, and what these edges join is one component in the next round."""
    taken, at = [], np.arange(len(a))
    while True:
        x, y = label[a[at]], label[b[at]]
        apart = x != y
        at, x, y = at[apart], x[apart], y[apart]
        if not len(at):
            return np.concatenate([np.zeros(0, np.int64), *taken]), label
        first = np.full(len(label), len(a))
        place = np.arange(len(at))
        for ends in (x, y):  # of repeated labels the last assignment stays, which is the first edge
            mine = np.full(len(label), len(a))
            mine[ends[::-1]] = place[::-1]
            first = np.minimum(first, mine)
        roots = np.flatnonzero(first < len(a))
        edge = first[roots]
        taken.append(at[np.unique(edge)])
        up = np.arange(len(label))
        up[roots] = np.where(x[edge] == roots, y[edge], x[edge])
        loops = roots[(up[up[roots]] == roots) & (roots < up[roots])]
        up[loops] = loops
        while (up[up] != up).any():
            up = up[up]
        label = up[label]


def forest_of(n: int, a: np.ndarray, b: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A maximum spanning forest of edges of ``n`` vertices. The best edges come first, twice as many in every step, and
    of the rest only those between components that are still apart."""
    label, out, size = np.arange(n), [], 4 * n
    while len(key):
        if len(key) > size:
            cut = len(key) - size
            order = np.argpartition(key, cut)
            top, rest = order[cut:], order[:cut]
        else:
            top, rest = np.arange(len(key)), np.zeros(0, np.int64)
        top = top[np.argsort(-key[top], kind="stable")]
        taken, label = _grow(label, a[top], b[top])
        out.append([x[top[taken]] for x in (a, b, key)])
        rest = rest[label[a[rest]] != label[b[rest]]]
        a, b, key, size = a[rest], b[rest], key[rest], 2 * size
    return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (a, b, key)


#: Edges that one task reduces to a forest at most; beyond, rounds of joins contract the graph first.
#: FEW edges are not worth a tree.
FOREST_ROWS, FAN_IN, FEW = 4_000_000, 8, 100_000


def _fan_in(edges: DataFrame, forest_rows: int) -> int:
    """Forests that a task can hold at once: none has as many edges as there are vertices."""
    ends = edges.select("a").unionByName(edges.select(F.col("b").alias("a")))
    return min(FAN_IN, forest_rows // max(1, ends.distinct().count()))


def spanning_forest(pairs: DataFrame, forest_rows: int = FOREST_ROWS) -> DataFrame:
    """``r, s, key`` of a maximum spanning forest of the bipartite graph of ``pairs``.

    Ends are told apart by side: r has even labels, s odd ones. Partitions reduce what they hold to a forest and
    merge by FAN_IN, or as many as have room in a task, until one is left. Where two forests may be too large for a task, each
    component first takes its best edge in every round (ties by ids) and is contracted, all in joins.
    """
    edges = pairs.select((F.col("r") * 2).alias("a"), (F.col("s") * 2 + 1).alias("b"), "key", "r", "s")
    edges = keep(_local_forest(edges), "forest")
    done: DataFrame | None = None
    fan = FAN_IN
    n = edges.count()
    while n > forest_rows and (fan := _fan_in(edges, forest_rows)) < 2:
        both = edges.select("a", "b", "key", "r", "s").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "key", "r", "s"))
        order = F.struct("key", -F.col("r"), -F.col("s"))
        chosen = keep(both.groupBy("a").agg(F.max_by(F.struct("b", "key", "r", "s"), order).alias("e")).select("a", "e.*"), "chosen")
        taken = chosen.select("r", "s", "key").distinct()
        done = taken if done is None else done.unionByName(taken)
        c = components(chosen.select("a", "b"))
        ca, cb = c.select(F.col("node").alias("a"), F.col("component").alias("na")), c.select(F.col("node").alias("b"), F.col("component").alias("nb"))
        edges = keep(_local_forest(edges.join(ca, "a").join(cb, "b").where("na <> nb").select(F.col("na").alias("a"), F.col("nb").alias("b"), "key", "r", "s")), "forest")
        n = edges.count()
    parts = edges.rdd.getNumPartitions() if n > FEW else 1
    if n <= FEW:
        edges = _local_forest(edges.coalesce(1))
    while parts > 1:  # every level is written, so its merges run side by side
        parts = -(-parts // fan)
        merged = keep(_local_forest(edges.coalesce(parts)), "forest")
        discard(edges)
        edges = merged
    out = edges.select("r", "s", "key")
    return out if done is None else done.unionByName(out)


def pair_groups(pairs: DataFrame) -> DataFrame:
    """``side, id, group_id``: matched groups of joined pairs; a group is named by its least r."""
    c = components(pairs.select((F.col("r") * 2).alias("a"), (F.col("s") * 2 + 1).alias("b")))
    least = c.where(F.pmod("node", F.lit(2)) == 0).groupBy("component").agg(F.min(F.expr("node div 2")).alias("group_id"))
    rows = c.join(least, "component")
    even = F.pmod("node", F.lit(2)) == 0
    return rows.select(F.when(even, "R").otherwise("S").alias("side"), F.expr("CASE WHEN pmod(node, 2) = 0 THEN node div 2 ELSE (node - 1) div 2 END").alias("id"), "group_id")
