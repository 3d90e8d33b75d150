"""Null, empty, long and repeated rows, empty tables and clashing columns: a defined result, no crash."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from autotheta.llm import decontaminate, linededup, maxent, mixing, neardup, perplexity, quality, queries, tokens, toxicity, warc
from tests.conftest import SF

#: Names that the operators use inside.
CLASH = ("key", "row", "size", "n", "digest", "part", "place", "score", "spans", "h", "t", "i", "x", "line", "at", "chunk", "component", "copies")
ROWS = [(1, "plain words of a text", "en", "a"), (2, None, "en", "a"), (3, "", None, "b"), (4, " \t\n ", "fr", None), (5, "same same", "en", "b"), (5, "same same", "en", "b"), (None, "no id here", "en", "b"), (None, None, None, None), (6, "long " * 60_000, "de", "a"), (7, "émoji 😀 ünd", "de", "c"), (8, "plain words of a text", "en", "a")]


def table(spark, rows):
    df = spark.createDataFrame([(*r, len(r[1] or "")) for r in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    return df.withColumns({c: F.lit("clash") for c in CLASH})


def labels(spark, rows=((1, 1, 0), (5, 0, 1), (7, 1, 0), (7, None, None), (None, 1, 1), (9, 0, 1))):
    return spark.createDataFrame(list(rows), "doc_id bigint, quality int, toxic int")


def bench(spark, rows=((1, "plain words of a text"), (2, None), (None, "same same"), (3, ""))):
    return spark.createDataFrame(list(rows), "item_id bigint, text string")


OPERATORS = {
    "toxicity": lambda s, d: toxicity.score_toxicity(d, labels(s)),
    "toxicity without labels": lambda s, d: toxicity.score_toxicity(d, labels(s).limit(0)),
    "warc": lambda s, d: warc.read_archives(warc.write_archives(d.withColumnRenamed("doc_id", "page_id").withColumns({"url": F.col("source"), "html": F.col("text")}))),
    "mixing": lambda s, d: mixing.mix_sources(d),
    "tokens": lambda s, d: tokens.read_shards(tokens.write_shards(d, queries.tokenizer_path())),
    "maxent": lambda s, d: maxent.score_language_model(d, F.col("doc_id") > 2, rounds=2),
    "maxent without training": lambda s, d: maxent.score_language_model(d, F.lit(False), rounds=2),
    "perplexity": lambda s, d: perplexity.perplexity_filter(d),
    "quality": lambda s, d: quality.quality_by_site(d, labels(s), F.col("source"), F.col("lang")),
    "lines": lambda s, d: linededup.drop_boilerplate_lines(d, min_sites=2),
    "near duplicates": lambda s, d: neardup.near_duplicates(d, 3, 85, 100),
    "decontamination": lambda s, d: decontaminate.decontaminate(d, bench(s)),
    "decontamination in blocks": lambda s, d: decontaminate.decontaminate(d, bench(s), block_bytes=10),
}


@pytest.mark.parametrize("name", sorted(OPERATORS))
@pytest.mark.parametrize("rows", [ROWS, []], ids=["odd rows", "no rows"])
def test_one_row_each(spark, name, rows):
    out = OPERATORS[name](spark, table(spark, rows)).collect()
    assert len(out) == len(rows)


def test_defined_results(spark):
    d = table(spark, ROWS)
    near = {(r.doc_id, r.n_shingles): r for r in neardup.near_duplicates(d, 3, 85, 100).collect()}
    assert near[8, 3].component_id == 1 and not near[8, 3].kept and near[2, 0].component_id == 2
    assert near[None, 1].component_id is None and near[None, 1].kept
    lines = {r.doc_id: r for r in linededup.drop_boilerplate_lines(d, min_sites=2).collect()}
    assert lines[2].text is None and lines[2].n_lines == 0
    hits = {r.doc_id: r for r in decontaminate.decontaminate(d, bench(spark)).collect()}
    assert hits[1].n_hit == 5 and hits[1]["items"] == ["1"] and hits[5].n_hit == 0 and hits[2].n_words == 0
    mixed = mixing.mix_sources(d).collect()
    assert all(r.taken == 0 for r in mixed if r.size == 0)
    kept = {r.doc_id: r.kept for r in perplexity.perplexity_filter(d).collect()}
    assert not kept[2] and not kept[6]


def test_no_benchmark(spark):
    d = table(spark, ROWS)
    assert all(r.n_hit == 0 for r in decontaminate.decontaminate(d, bench(spark).limit(0)).collect())


@pytest.mark.parametrize("rows", [ROWS, []], ids=["odd rows", "no rows"])
@pytest.mark.parametrize("k", range(len(corpus_pipeline.STAGES)), ids=[n for n, _ in corpus_pipeline.STAGES])
def test_stages(spark, k, rows):
    docs = table(spark, rows)
    out = corpus_pipeline.STAGES[k][1](spark, docs, SF)
    if k < len(corpus_pipeline.STAGES) - 1:
        assert out.columns == list(corpus_pipeline.COLUMNS)
    found = out.collect()
    if not rows:
        assert found == []
    elif k == 1:
        ids = [r.doc_id for r in found]
        assert sorted(x for x in ids if x is not None) == [1, 2, 3, 4, 5, 6, 7] and ids.count(None) == 2


def test_pipeline_by_hand(spark, tmp_path):
    """Every stage's decision, made again without Spark's operators where a rule says it all."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    verdict = {r.doc_id for r in toxicity.score_toxicity(docs, queries.table(spark, SF, "labels"), train=~queries.held_out()).where("predicted = 1").collect()}
    one = corpus_pipeline.STAGES[0][1](spark, docs, SF).persist()
    assert {r.doc_id for r in one.collect()} == {r.doc_id for r in docs.collect()} - verdict
    from tests.llm.test_operators import jaccard_links

    rows = one.collect()
    _, links = jaccard_links([r.text for r in rows], 5, 80, 100)
    label = {r.doc_id: r.doc_id for r in rows}
    for _ in rows:
        for a, b in links:
            x, y = rows[a].doc_id, rows[b].doc_id
            label[x] = label[y] = min(label[x], label[y])
    two = corpus_pipeline.STAGES[1][1](spark, one, SF).persist()
    assert sorted(r.doc_id for r in two.collect()) == sorted({*label.values()})
    three = corpus_pipeline.STAGES[2][1](spark, two, SF).persist()
    assert {r.doc_id for r in three.collect()} <= {r.doc_id for r in two.collect()}
    four = corpus_pipeline.STAGES[3][1](spark, three, SF).persist()
    times = four.groupBy("doc_id").count().agg(F.max("count")).first()[0]
    assert times <= 3
    five = corpus_pipeline.STAGES[4][1](spark, four, SF).collect()
    assert len(five) == four.count() and [r.start for r in sorted(five, key=lambda r: r.start)][0] == 0
    assert len(corpus_pipeline.run(spark, SF).collect()) == len(five)


def test_stages_keep_rows_of_one_id_apart(spark):
    """Negative ids beside null ones, and one id with two texts: only copies and near copies go."""
    words = " ".join(f"w{k}" for k in range(30))
    rows = [(-1, "some text", "en", "a"), (None, "other text here", "en", "a"), (-2, "third text", "en", "a"), (5, "one thing", "en", "a"), (5, "and another", "en", "a"), (5, "one thing", "en", "a"), (6, words, "en", "a"), (None, words + " x", "en", "a")]
    docs = table(spark, rows)
    found = sorted((r.doc_id is None, r.doc_id or 0, r.text) for r in corpus_pipeline.STAGES[1][1](spark, docs, SF).collect())
    want = {(r[0], r[1]) for r in rows if r[0] is not None} | {(None, "other text here")}
    assert found == sorted((i is None, i or 0, t) for i, t in want)
    assert corpus_pipeline.STAGES[0][1](spark, docs, SF).count() == len(rows)
