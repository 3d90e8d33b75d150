"""Joins by blocks against brute force; their queries neither spread copies nor shuffle meetings."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from autotheta.functions import sims
from autotheta.operators import graph, simjoin
from autotheta.operators import objectives as O
from autotheta.functions.text import TOKENIZERS
from autotheta.operators.blocks import _frequencies, _hashed, _write, block_join, keys_of, level_parts, links, write_blocks
from autotheta.operators.graph import DisjointSets, forest_of
from autotheta.operators.measures import accuracy_curve, accuracy_curve_of
from autotheta.operators.sets import prepare
from autotheta.plans import framework
from autotheta.sources.shared import CLEANUP_CONF, keep
from tests.conftest import SF


def _texts(spark, seed, n, first=0):
    r = random.Random(seed)
    rows = [(first + k, " ".join(r.choices("abcdefgh", k=r.randint(0, 9)))) for k in range(n)] + [(first + n, None), (first + n + 1, "a b c"), (first + n + 2, "c b a")]
    return spark.createDataFrame(rows, "id bigint, text string")


@pytest.mark.parametrize("bag,index,bounds", [(True, "prefix", "tight"), (False, "full", "paper")])
def test_block_join_by_brute_force(spark, bag, index, bounds):
    r, s = _texts(spark, 1, 40), _texts(spark, 2, 30, 100)
    p, b = prepare(r, s, "words", bag), write_blocks(r, s, "words", bag, block=40)
    assert len(b.r.blocks) > 1
    for sim in (sims.jaccard(), sims.overlap(), sims.dice(), sims.cosine(), sims.tversky("0.1"), sims.tversky("0")):
        every = {(x.r, x.s, x.o, x.nr, x.ns): x.key for x in simjoin.brute_force_pairs(p, sim).collect()}
        for low in (5e-324, 0.3, 0.5, 2 / 3, 1.0):
            got = block_join(b, sim, low, bounds=bounds, index=index).collect()
            assert len(got) == len({(x.r, x.s) for x in got})
            assert {(x.r, x.s, x.o, x.nr, x.ns): x.key for x in got} == {k: v for k, v in every.items() if v >= low}


def test_links_count_copies_without_their_pairs(spark):
    rows = [(k, "a b c d e") for k in range(300)] + [(300, "a b c d"), (301, "x"), (302, ""), (303, None)]
    got = {x.id: (x.class_id, x.links) for x in links(write_blocks(spark.createDataFrame(rows, "id bigint, text string")), sims.jaccard(), 0.8).collect()}
    assert got == {k: (0, 300) for k in range(300)} | {300: (300, 300), 301: (301, 0)}


def test_selfjoin_has_a_row_a_document(spark):
    assert entry.queries()["selfjoin_dups"](spark, SF).count() == spark.read.parquet(f"{SF}/documents.parquet").count()


@pytest.mark.parametrize("name", ["simjoin_dice", "simjoin_tversky", "simjoin_jaccard", "simjoin_cosine", "threshold_join_full_index", "level_set", "band"])
def test_meetings_are_not_shuffled(spark, name):
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(r" not in plan and "hashpartitioning(t" not in plan


def test_negatives_of_many_objects(spark):
    """More pairs of objects than 32 bits count."""
    got = simjoin.not_joined_count(spark.range(3), 89_176, 89_332)
    assert got.dtypes == [("n", "bigint")] and got.first()[0] == 89_176 * 89_332 - 3
    assert simjoin.not_joined_count(spark.range(0), 0, 5).first()[0] == 0


@pytest.fixture(scope="module")
def both(spark):
    r, s = _texts(spark, 3, 40), _texts(spark, 4, 30, 100)
    return r, s, prepare(r, s, "words", True), write_blocks(r, s, "words", True, block=40)


@pytest.mark.parametrize("name,args", [("group_count", ("fused", "eager", 2)), ("group_count", ("topk", "lazy", 3)), ("group_count", ("fused", "heap", 2)), ("outer_size", ("all", "eager", 2)), ("outer_size", ("topk", "lazy", "pivot"))])
def test_chosen_threshold_by_blocks(spark, both, name, args):
    """Sides in blocks give what brute force gives; copies are in classes, and some texts are empty or null."""
    _, _, p, b = both
    assert len(b.r.blocks) > 1
    for sim in (sims.jaccard(), sims.tversky("0.1")):
        want = framework.brute_force(p, sim, O.OBJECTIVES[name](), simjoin.brute_force_pairs(p, sim))
        got = framework.auto_join(b, sim, O.OBJECTIVES[name](), *args)
        assert (got.theta, got.score, got.size) == (want.theta, want.score, want.pairs.count())
        assert sorted((x.r, x.s, x.key) for x in got.pairs.collect()) == sorted((x.r, x.s, x.key) for x in want.pairs.collect())


def test_levels_of_blocks(spark, both):
    """Sums of the tasks are the levels of all pairs, in bands too."""
    _, _, p, b = both
    row = lambda x: tuple(x[c] for c in ("key", *(c for c in O.DELTAS if c != "d_classes" and c != "d_forest")))
    pairs = simjoin.sharing_pairs(p, sims.jaccard()).persist()
    want, state, got = O.levels(pairs).collect(), O.ScoreState(True), []
    for low, high in ((0.3, None), (5e-324, 0.3)):
        rows = state.extend(framework._parts(level_parts(b, sims.jaccard(), low, high, forest=True).persist())).persist()
        got += rows.collect()
        state.close(O.level_sums(rows))
    assert sorted(map(row, got)) == sorted(map(row, want))
    groups = lambda found: [(x.key, x.d_classes - x.d_forest) for x in sorted(found, key=lambda x: -x.key)]
    assert [(k, sum(n for _, n in groups(got)[: i + 1])) for i, (k, _) in enumerate(groups(got))] == [(k, sum(n for _, n in groups(want)[: i + 1])) for i, (k, _) in enumerate(groups(want))]


def test_one_pass_serves_bands_of_whole_sets(spark, both, monkeypatch):
    """Below WHOLE a lazy run compares sets once for several bands; pairs of low keys are counted if their threshold is chosen."""
    _, _, p, b = both
    sim, calls = sims.jaccard(), []
    monkeypatch.setattr(framework, "level_parts", lambda *a, **k: calls.append(a[2]) or level_parts(*a, **k))
    want = framework.brute_force(p, sim, O.group_count(), simjoin.brute_force_pairs(p, sim))
    got = framework.auto_join(b, sim, O.group_count(), "fused", "lazy", 2, stop_early=False)
    assert (got.theta, got.score, got.size) == (want.theta, want.score, want.pairs.count())
    assert calls == [0.125, 0.5**6, 5e-324] and got.metrics["bands"] == 7
    monkeypatch.setattr(framework, "COUNTED", 2.0)
    got = framework.auto_join(b, sim, O.group_count(), "fused", "lazy", 2)
    assert (got.theta, got.score, got.size) == (want.theta, want.score, want.pairs.count()) and calls[-1] == want.theta
    assert got.evaluated.where("n_join IS NOT NULL").count() == 0


def test_blocks_leave_no_shuffle_files(spark):
    env = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get()
    files = lambda: {f.getPath() for f in spark.sparkContext._jvm.scala.jdk.javaapi.CollectionConverters.asJava(env.blockManager().diskBlockManager().getAllFiles()) if f.getName().startswith("shuffle_")}
    texts, before = _texts(spark, 5, 200), spark.conf.get(CLEANUP_CONF, None)
    sets = keep(_hashed(texts, TOKENIZERS["words"](F.col("text")), False), "hashed")
    order, were = spark.sparkContext.broadcast(_frequencies(sets)), files()
    assert _write(sets, order, 40).blocks
    assert files() <= were and spark.conf.get(CLEANUP_CONF, None) == before


def test_pairs_counted_from_a_key_on(spark, both):
    _, _, _, b = both
    rows = [{(x.key, x.n) for x in level_parts(b, sims.jaccard(), 0.2, None, joins, covers=False).groupBy("kind", "key").agg(F.sum("n").alias("n")).collect()} for joins in (True, 0.4)]
    assert rows[1] == {x for x in rows[0] if x[0] >= 0.4} and len(rows[1]) < len(rows[0])


def test_forests_merge_where_vertices_are_few(spark, monkeypatch):
    """Many edges of few vertices need no rounds of joins."""
    rng = np.random.default_rng(8)
    rows = [(int(r), int(s), int(k) / 8) for r, s, k in zip(rng.integers(0, 10, 2000), rng.integers(0, 10, 2000), rng.integers(1, 9, 2000), strict=True)]
    pairs = spark.createDataFrame(rows, "r bigint, s bigint, key double").repartition(12)
    want = sorted(x.key for x in graph.spanning_forest(pairs).collect())
    monkeypatch.setattr(graph, "FEW", 10)
    monkeypatch.setattr(graph, "components", None)
    assert sorted(x.key for x in graph.spanning_forest(pairs, 60).collect()) == want


def test_no_blocks(spark):
    empty = write_blocks(spark.createDataFrame([(1, None)], "id bigint, text string"), spark.createDataFrame([], "id bigint, text string"))
    for v in ("lazy", "heap"):
        assert framework.auto_join(empty, sims.jaccard(), O.group_count(), "fused", v, 2).theta is None


def test_forest_by_union_find():
    rng = np.random.default_rng(6)
    for n, m in ((1, 0), (5, 4), (40, 30), (40, 900), (300, 20_000)):
        a, b, key = rng.integers(0, n, m), rng.integers(0, n, m), rng.integers(1, 8, m) / 8
        sets, want = DisjointSets(), []
        for k in np.argsort(-key, kind="stable").tolist():
            if sets.join(int(a[k]), int(b[k])):
                want.append(key[k])
        x, y, got = forest_of(n, a, b, key)
        again = DisjointSets()
        assert sorted(got) == sorted(want) and all(again.join(i, j) for i, j in zip(x.tolist(), y.tolist(), strict=True))


def test_curve_from_counts(spark, both):
    r, s, p, b = both
    pairs = simjoin.sharing_pairs(p, sims.jaccard()).persist()
    truth = pairs.where("key > 0.4 AND (r + s) % 3 <> 0").select("r", "s").unionByName(spark.createDataFrame([(40, 130), (0, 130)], "r bigint, s bigint"))
    joins = level_parts(b, sims.jaccard(), 5e-324, covers=False)
    got = accuracy_curve_of(joins, keys_of(truth, r, s, sims.jaccard(), "words", True), truth).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, accuracy_curve(pairs, truth).collect()))


@pytest.mark.parametrize("name", ["auto_join_collapsed_outer_size", "auto_join_w3_lazy", "auto_join_fused_heap_outer_size", "accuracy_curve"])
def test_pairs_are_not_written(spark, monkeypatch, name):
    """Neither meetings nor pairs leave a task."""
    for f in ("meetings", "sharing_pairs", "verify_eager"):
        monkeypatch.setattr(framework, f, None)
    monkeypatch.setattr(simjoin, "sharing_pairs", None)
    assert entry.queries()[name](spark, SF).count() >= 1
