"""The worked example, equivalence of all variants, lemmas on random joins, edge cases."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from autotheta.functions import sims
from autotheta.operators import objectives as O
from autotheta.operators import simjoin
from autotheta.operators.graph import components, pair_groups, spanning_forest
from autotheta.operators.sets import prepare
from autotheta.plans import framework
from tests.conftest import SF

TOY_R, TOY_S = "db_ms vldb dbs db dblp_".split(), "dbms_ dbms pvldb vl_db _db".split()


def side(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "id bigint, text string")


@pytest.fixture(scope="module")
def toy(spark):
    p = prepare(side(spark, TOY_R), side(spark, TOY_S), "chars")
    return p, simjoin.sharing_pairs(p, sims.jaccard()).persist()


def test_toy_profile(toy):
    p, pairs = toy
    state = O.profile(O.levels(pairs), 5, 5).withColumn("hc", O.group_count().score).withColumn("outer", -O.outer_size().score).orderBy(F.desc("key"))
    got = [(r.n_join, r.cov_r, r.cov_s, r.hc, r.outer, r.pivotal) for r in state.collect()]
    assert got[:6] == [(1, 1, 1, 1, 9, True), (4, 2, 4, 2, 8, True), (5, 3, 4, 2, 8, False), (8, 5, 5, 3, 8, True), (11, 5, 5, 1, 11, False), (13, 5, 5, 1, 13, False)]
    assert [x[4] for x in got[6:]] == [15, 19, 22, 24, 25]


def test_toy_operators(toy):
    _, pairs = toy
    assert {TOY_R[r.r] for r in simjoin.cover(pairs.where("key >= 0.75D"), "r").collect()} == {"db_ms", "dbs", "vldb"}
    assert {(TOY_R[r.r], TOY_S[r.s]) for r in simjoin.level(pairs, 0.75).collect()} == {("dbs", "dbms")}
    assert {TOY_S[r.s] for r in simjoin.top_partners(pairs, "r").where("r = 1").collect()} == {"pvldb", "vl_db"}
    assert simjoin.band(pairs, 0.9, 2.0).count() == 1 and pairs.where("key >= 0.8D").count() == 4


VARIANTS = [("topk", "lazy", "pivot", "group_count"), ("fused", "lazy", 3, "outer_size"), ("all", "heap", 2, "group_count"), ("topk", "lazy", 2, "outer_size"), ("fused", "eager", 1, "group_count")]
WANTED = {"group_count": (2 / 3, 3), "outer_size": (0.8, -8)}


@pytest.mark.parametrize("pivots,verify,bands,name", VARIANTS)
def test_toy_variants(toy, pivots, verify, bands, name):
    p, _ = toy
    r = framework.auto_join(p, sims.jaccard(), O.OBJECTIVES[name](), pivots, verify, bands)
    assert (r.theta, r.score) == WANTED[name]
    assert r.pairs.count() == {"group_count": 8, "outer_size": 4}[name]


@pytest.mark.parametrize("bounds,collapsed,hot", [("paper", False, 10**6), ("tight", True, 3)])
def test_variants_agree(spark, bounds, collapsed, hot):
    """All ways give the pairs of brute force: equal sets collapsed or not, elements dealt over tasks or not."""
    rng = random.Random(5)
    words = [f"w{k}" for k in range(12)]
    r, s = ([" ".join(rng.sample(words, rng.randint(1, 6))) for _ in range(12)] for _ in "rs")
    r[3], s[4], s[5] = r[2], r[2], r[2]
    plain = prepare(side(spark, r), side(spark, s), "words")
    p = prepare(side(spark, r), side(spark, s), "words", collapsed=collapsed, hot=hot)
    assert (p.hot is None) == (hot > 24)
    for sim, o, args in ((sims.tversky("0.1"), O.group_count(), ("fused", "lazy", 3)), (sims.jaccard(), O.group_count(), ("topk", "lazy", 2)), (sims.jaccard(), O.outer_size(), ("topk", "heap", 2)), (sims.dice(), O.outer_size(), ("fused", "eager", 2))):
        want = framework.brute_force(plain, sim, o, simjoin.brute_force_pairs(plain, sim))
        got = framework.auto_join(p, sim, o, *args, bounds=bounds)
        assert (got.theta, got.score) == (want.theta, want.score)
        pairs = lambda x: sorted((y.r, y.s, round(y.key, 9)) for y in x.pairs.collect())
        assert pairs(got) == pairs(want)


def test_state_grows_by_bands(spark):
    """What bands add one after the other is what all pairs together give, and so are the totals."""
    rng = random.Random(9)
    every = {(rng.randrange(9), rng.randrange(9)): rng.choice([0.1, 0.25, 0.5, 0.5, 0.75, 1.0]) for _ in range(40)}
    pairs = spark.createDataFrame([(r, s, k) for (r, s), k in every.items()], "r bigint, s bigint, key double").repartition(3)
    row = lambda x: tuple(x[c] for c in ("key", *O.DELTAS))
    want = sorted(row(x) for x in O.levels(pairs).collect())
    state, got = O.ScoreState(True), []
    for low, high in ((0.5, 2), (0.2, 0.5), (0, 0.2)):
        rows = state.extend(pairs.where((F.col("key") >= low) & (F.col("key") < high))).persist()
        got += [row(x) for x in rows.collect()]
        state.close(O.level_sums(rows))
    assert sorted(got) == want
    assert state.base["n_join"] == len(every) and state.base["forest"] == sum(x[5] for x in want)


def test_running_sums_in_ranges(spark):
    rows = spark.createDataFrame([(k / 97, (k * 7) % 11) for k in range(1, 97)], "key double, x bigint")
    for how in ("sum", "max"):
        one, two = (sorted((r.key, r.y) for r in O.running(rows, {"y": "x"}, how, {"y": 5}, n).collect()) for n in (None, 96))
        assert one == two and len(one) == 96


def test_bounds_of_met_pairs(spark):
    """At every cap what a pair can still reach is no less than its key, and what it has seen no more."""
    rng = random.Random(3)
    words = [f"w{k}" for k in range(20)]
    r, s = ([" ".join(rng.sample(words, rng.randint(1, 9))) for _ in range(15)] for _ in "rs")
    p = prepare(side(spark, r), side(spark, s), "words")
    for sim in (sims.jaccard(), sims.tversky("0.1"), sims.cosine()):
        true = simjoin.sharing_pairs(p, sim).select("r", "s", F.col("key").alias("true"), F.col("o"))
        for low in (0.7, 0.3):
            met = simjoin.meetings(p, sim, low)
            rows = met.withColumn("top", simjoin.most_possible(sim, low)).join(true, ["r", "s"]).collect()
            assert rows and all(x.top >= x.true - 1e-12 and x.seen <= x.o for x in rows)
            assert {(x.r, x.s) for x in rows} >= {(x.r, x.s) for x in true.where(F.col("true") >= low).collect()}


def test_edit_join_by_brute_force(spark):
    rng = random.Random(8)
    texts = [None, "", "a", "b", "ab"] + ["".join(rng.choice("abc") for _ in range(rng.randint(8, 11))) for _ in range(60)]

    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    near = {(i, j) for j, b in enumerate(texts) for i, a in enumerate(texts[:j]) if a is not None and b is not None and distance(a, b) <= 0.2 * max(len(a), len(b))}
    assert {(x.r, x.s) for x in simjoin.edit_join(side(spark, texts), 0.2).collect()} == near
    with pytest.raises(ValueError):
        simjoin.edit_join(side(spark, texts), 0.5)


def test_shared_folder_is_required_on_a_cluster():
    from types import SimpleNamespace

    from autotheta.sources.shared import shared_dir

    context = SimpleNamespace(master="spark://host:7077", applicationId="x", getConf=lambda: SimpleNamespace(get=lambda k: None))
    with pytest.raises(ValueError):
        shared_dir(SimpleNamespace(conf=SimpleNamespace(get=lambda k, d: None), sparkContext=context))


def components_by_hand(edges):
    up = {}

    def find(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        up[find(a)] = find(b)
    return len({find(x) for x in list(up)})


def test_lemmas_and_bounds_by_hand():
    """Pure Python: pivots hold the largest best threshold, bounds are sound, forests count groups."""
    rng = random.Random(11)
    for _ in range(300):
        nr, ns = rng.randint(1, 5), rng.randint(1, 5)
        sim = {(r, s): rng.choice([0.2, 0.4, 0.5, 0.8, 1.0]) for r in range(nr) for s in range(ns) if rng.random() < 0.7}
        if not sim:
            continue
        levels = sorted(set(sim.values()), reverse=True)
        best_r, best_s = ({x: max(v for k, v in sim.items() if k[i] == x) for x in {k[i] for k in sim}} for i in (0, 1))
        pivots = {v for (r, s), v in sim.items() if v == best_r[r] == best_s[s]}
        assert len(pivots) <= min(nr, ns)
        for score in ("group", "outer"):
            h, bound = {}, {}
            for t in levels:
                j = [k for k, v in sim.items() if v >= t]
                cr, cs = {r for r, _ in j}, {s for _, s in j}
                h[t] = components_by_hand([(("r", r), ("s", s)) for r, s in j]) if score == "group" else len(cr) + len(cs) - len(j) - nr - ns
                bound[t] = h[t] + min(nr - len(cr), ns - len(cs))
            star = max(levels, key=lambda t: (h[t], t))
            assert star in pivots
            assert all(h[low] <= bound[t] for t, low in itertools.product(levels, levels) if low < t)


def test_forest_and_components(spark):
    rng = random.Random(2)
    rows = [(rng.randrange(30), rng.randrange(30), rng.choice([0.1, 0.5, 0.9])) for _ in range(120)]
    pairs = spark.createDataFrame(rows, "r bigint, s bigint, key double").repartition(5)
    small, joins = spanning_forest(pairs), spanning_forest(pairs, forest_rows=3)
    count = lambda f: sorted((r["key"], r["n"]) for r in f.groupBy("key").agg(F.count(F.lit(1)).alias("n")).collect())
    assert count(small) == count(joins)
    n = components_by_hand([(("r", r), ("s", s)) for r, s, _ in rows])
    assert pair_groups(pairs).select("group_id").distinct().count() == n
    chain = spark.createDataFrame([(k, k + 1) for k in range(200)], "a bigint, b bigint").repartition(7)
    got = components(chain)
    assert got.count() == 201 and got.select("component").distinct().collect()[0][0] == 0


@pytest.mark.parametrize("r,s,theta", [([], ["a b"], None), (["a"], ["b"], None), ([None, ""], ["x"], None), (["a b"], ["a b"], 1.0), (["a", "a"], ["a", "a"], 1.0)])
def test_edges(spark, r, s, theta):
    p = prepare(spark.createDataFrame(list(enumerate(r)), "id bigint, text string"), side(spark, s), "words")
    assert p.size_r == len(r)
    for o in (O.outer_size(), O.group_count()):
        assert framework.auto_join(p, sims.jaccard(), o, bands=2).theta == theta


def test_duplicate_ids_fail(spark):
    rows = spark.createDataFrame([(1, "a"), (1, "b")], "id bigint, text string")
    with pytest.raises(ValueError):
        prepare(rows, rows, check=True)
    with pytest.raises(ValueError):
        prepare(rows.select("id"), rows)


def test_metamorphic(spark):
    texts = ["red apple pie", "green apple", "blue sky", "red sky at night", "apple pie recipe"]
    others = ["apple pie red", "sky blue", "night sky", "green green apple"]
    sim = sims.jaccard()
    a = framework.brute_force(prepare(side(spark, texts), side(spark, others), bag=True), sim, O.outer_size())
    b = framework.brute_force(prepare(side(spark, others), side(spark, texts), bag=True), sim, O.outer_size())
    assert (a.theta, a.score) == (b.theta, b.score)
    lonely = framework.brute_force(prepare(side(spark, [*texts, "zzz"]), side(spark, others), bag=True), sim, O.outer_size())
    assert (lonely.theta, lonely.score) == (a.theta, a.score - 1)


def test_lazy_reads_less(spark):
    from autotheta.plans.workloads import W, fixture

    f = fixture("w3", spark, SF)
    lazy, heap = (framework.auto_join(f.prepared, W["w3"].sim, O.outer_size(), "fused", v, 2) for v in ("lazy", "heap"))
    assert (lazy.theta, lazy.score) == (heap.theta, heap.score) and lazy.metrics["tokens_scanned"] < heap.metrics["tokens_scanned"]
    assert lazy.metrics["verified"] < lazy.metrics["candidates"] and lazy.evaluated.count() == lazy.metrics["evaluated"]


def test_plans(spark):
    """No cross join outside brute force; caps are filtered before postings meet."""
    p = prepare(side(spark, ["a b c", "b c d"]), side(spark, ["a b", "c d"]))
    plan = simjoin.threshold_join(p, sims.jaccard(), "0.5")._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    brute = simjoin.brute_force_pairs(p, sims.jaccard())._jdf.queryExecution().toString()
    assert "Cartesian" in brute or "NestedLoop" in brute


def test_active_learning_by_hand(spark):
    """The same choices over all pairs in memory; labels are the pairs' own."""
    from autotheta.operators.baselines import best_threshold, labels_to_match, tune_by_active
    from autotheta.operators.measures import accuracy_curve
    from autotheta.plans.workloads import W, fixture

    f = fixture("w2", spark, SF)
    pairs = simjoin.sharing_pairs(f.prepared, W["w2"].sim).persist()
    run = tune_by_active(pairs, f.c, 60)
    rows = [(x.key, x.h, x.r, x.s) for x in pairs.select("key", F.xxhash64("r", "s").alias("h"), "r", "s").collect()]
    true, asked, labels, theta = {(x.r, x.s) for x in f.c.collect()}, set(), [], (max(rows)[0] + min(rows)[0]) / 2
    for n, at in run.trace:
        key, _, r, s = min((x for x in rows if x[2:] not in asked), key=lambda x: (abs(x[0] - theta), -x[0], x[1:]))
        asked.add((r, s))
        labels.append((key, (r, s) in true))
        assert run.asked[n - 1] == (r, s, (r, s) in true)
        theta = best_threshold(labels)
        assert theta == at
    assert len(run.trace) == 60
    curve = [(x.key, x.f1) for x in accuracy_curve(pairs, f.c).collect()]
    best = dict(curve)[run.theta]
    n = labels_to_match(run, curve, best, 0.01)
    assert 1 <= n <= 60 and all(dict(curve)[t] >= best - 0.01 for k, t in run.trace if k >= n)
    assert labels_to_match(run, curve, 2.0, 0.01) is None
