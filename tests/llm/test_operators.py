"""Each operator against brute force or its SQL on the smallest tables."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from autotheta.llm import decontaminate, exchange, linededup, maxent, mixing, neardup, perplexity, queries, quality, textkit, tokens, toxicity, warc
from tests.conftest import SF
from tests.oracle import connect, same

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SPACED = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def documents(spark):
    return [(r.doc_id, r.text, r.source) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]


@pytest.mark.parametrize("name", sorted(queries.ORACLE))
def test_sql(spark, name):
    same(spark, connect(SF), SF, queries.QUERIES[name], queries.ORACLE[name])


def test_words_equal_by_text_only():
    texts = ["Red  apple\tRED", None, "", "éa apple " + "x" * 600_000 + " red", " nbsp\x1cjoined"]
    data, offsets = textkit.text_rows(pa.array(texts))
    w = textkit.words(data, offsets, textkit.SPACED_LOWER)
    want = [SPACED.findall((t or "").translate(LOW)) for t in texts]
    assert np.diff(w.split).tolist() == [len(x) for x in want]
    by_hash = collections.defaultdict(set)
    for h, word in zip(w.hash.tolist(), [x for row in want for x in row], strict=True):
        by_hash[h].add(word)
    assert all(len(v) == 1 for v in by_hash.values()) and len(by_hash) == len({x for row in want for x in row})
    h, split = textkit.shingles(w, 3)
    assert np.diff(split).tolist() == [max(len(x) - 2, int(len(x) > 0)) for x in want] and len(h) == split[-1]


def test_op1_held_out_accuracy(spark):
    sf = SF.replace("0.001", "0.01")
    got = queries.op1_toxic_segments(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    tp = sum(r.predicted and r.toxic for r in got)
    assert tp / max(1, sum(r.predicted for r in got)) >= 0.8 and tp / sum(r.toxic for r in got) >= 0.8
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got)


def test_op1_segments_by_brute_force():
    """Disjoint maximal segments: the first is the best one, and the search goes on to its left and right."""

    def search(s, lo, hi):
        best = max(((sum(s[a:b]), -a, -b) for a in range(lo, hi) for b in range(a + 1, hi + 1)), default=(0, 0, 0))
        if best[0] <= 0:
            return []
        a, b = -best[1], -best[2]
        return search(s, lo, a) + [(a, b)] + search(s, b, hi)

    rng = random.Random(1)
    for _ in range(200):
        s = [rng.choice([-3, -2, -1, 1, 2, 4]) + rng.random() * 1e-3 for _ in range(rng.randint(0, 14))]
        assert [(a, b) for a, b, _ in toxicity.maximal_segments(np.array(s, float))] == search(s, 0, len(s))


def test_op1_lambda():
    lam = toxicity.solve_lambda(np.array([-1.0, 1.0]), np.array([0.75, 0.25]))
    assert abs(0.75 * math.exp(-lam) + 0.25 * math.exp(lam) - 1) < 1e-6 and lam > 0.1


@pytest.mark.parametrize("step", [61, 1000, 1 << 20])
def test_op2_ranges_own_each_record_once(tmp_path, step):
    nested = warc.record("response", 7, "http://x/", b"inner" * 9, None)
    parts = [warc.record("response", k, f"http://x/\n{k}", (nested if k % 5 == 0 else b"body") * (k % 7), None) for k in range(120)]
    path = str(tmp_path / "a.warc.gz")
    open(path, "wb").write(b"".join(parts))
    size = sum(map(len, parts))
    got = [warc.describe(raw)[0] for lo in range(0, size, step) for _, raw in warc.read_range(path, lo, lo + step)]
    assert got == list(range(120))


def test_op2_reader_goes_on_after_damage(tmp_path):
    parts = [warc.record("response", k, "http://x/", b"body" * 50, None) for k in range(20)]
    raw = bytearray(b"".join(parts))
    at = len(parts[0]) + 20
    raw[at : at + 8] = b"\0" * 8
    path = str(tmp_path / "b.warc.gz")
    open(path, "wb").write(raw)
    got = [warc.describe(x)[0] for _, x in warc.read_range(path, 0, len(raw))]
    assert set(got) >= set(range(2, 20)) and len(got) == len(set(got))


def test_op2_equal_payloads(spark):
    rows = [(1, "u", "same"), (2, "u", "same"), (3, "u", None), (4, "u", ""), (5, None, "only"), (6, "u", "same")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    got = {r.page_id: (r.record_type, r.refers_to, r.payload_bytes, r.payload_digest) for r in warc.read_archives(warc.write_archives(pages), 100).collect()}
    assert {k: v[:2] for k, v in got.items()} == {1: ("revisit", 6), 2: ("revisit", 6), 3: ("revisit", 4), 4: ("response", None), 5: ("response", None), 6: ("response", None)}
    assert got[1][2] == 4 and got[1][3] == got[6][3] == warc.digest32(b"same")
    plain = warc.read_archives(warc.write_archives(pages, min_revisit_bytes=5)).collect()
    assert all(r.record_type == "response" for r in plain)


def test_op3_mix(spark, documents):
    got = {r.doc_id: r for r in queries.op3_mix_sources(spark, SF).collect()}
    again = {r.doc_id: r.taken for r in queries.op3_mix_sources(spark, SF).collect()}
    assert {k: r.taken for k, r in got.items()} == again
    size, of = collections.Counter(), collections.defaultdict(list)
    for i, t, s in documents:
        n = len(SPACED.findall(t or ""))
        assert got[i].size == n and got[i].taken <= 3 * n
        size[s] += n
        of[s].append(i)
    # Targets by filling up: raise the level until all is given out.
    weight = {s: (1, 2, 3)[k % 3] for k, s in enumerate(sorted(size))}
    left, open_, target = sum(size.values()), set(size), {}
    while True:
        level = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if weight[s] * level > 3 * size[s]}
        if not full:
            target |= {s: weight[s] * level for s in open_}
            break
        for s in full:
            target[s] = 3 * size[s]
            left -= 3 * size[s]
        open_ -= full
    for s, ids in of.items():
        assert all(abs(got[i].target - target[s]) < 1e-6 * target[s] + 1e-9 and got[i].source_size == size[s] for i in ids)
        assert abs(sum(got[i].taken for i in ids) - target[s]) <= max(got[i].size for i in ids) / 2 + 1e-6


def test_op3_pivot_keeps_mass_and_means():
    rng = np.random.default_rng(3)
    p, size = rng.random(40), rng.integers(1, 100, 40).astype(float)
    total = np.zeros(40)
    for _ in range(3000):
        out = mixing.pivot(p, size, rng.random(40))
        assert ((out > 0) & (out < 1)).sum() <= 1 and abs((out - p) @ size) < 1e-6
        total += out
    assert np.abs(total / 3000 - p).max() < 0.05


def test_op4_round_trip(spark, documents):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(queries.tokenizer_path())
    rows = [*documents[:60], (-3, "It's <|endoftext|> 7even 77 don't ﬁne İstanbul ÉTÉ straße!! 東京 áb c d", "s"), (-2, None, "s"), (-1, " \n\t", "s")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    manifest = tokens.write_shards(docs, queries.tokenizer_path())
    got = sorted((r.start, r.doc_id, r.n_tokens, r.ids_crc32) for r in tokens.read_shards(manifest).collect())
    want, at = [], 0
    for i, text, _ in sorted(rows):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        want.append((at, i, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    assert got == want
    shard = manifest.first()
    every = list(tokens.records(shard.path))
    picked = list(tokens.records(shard.path, [len(every) - 1, 0]))
    assert [i for i, _ in picked] == [every[-1][0], every[0][0]] and (picked[0][1] == every[-1][1]).all()


def test_op4_damage_is_found(spark, tmp_path):
    raw = bytearray(tokens.MAGIC + tokens.frame(5, 2, b"\1\0\2\0"))
    raw[-6] ^= 1
    path = str(tmp_path / "x.rec")
    open(path, "wb").write(raw)
    with pytest.raises(ValueError):
        list(tokens.records(path))


def test_op5_base_and_held_out_score(spark, documents):
    got = {r.doc_id: r for r in queries.op5_maxent_model(spark, SF).collect()}
    words = {i: [*SPACED.findall((t or "").translate(LOW)), None] for i, t, _ in documents}
    held = {i: zlib.crc32(str(i).encode()) % 10 == 0 for i in words}
    c = collections.Counter(w for i, ws in words.items() if not held[i] for w in ws)
    n, v = sum(c.values()), len(c)
    for i, ws in words.items():
        r = got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(ws), sum(c[w] > 0 for w in ws), n)
        assert abs(r.base_score - sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws)) < 1e-6 * len(ws)
        assert r.score <= 0
    assert sum(got[i].score for i in words if held[i]) > sum(got[i].base_score for i in words if held[i])


def test_op5_probabilities_add_up(spark):
    """Over the whole vocabulary and the unknown word, for a few histories."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(60).select(F.col("doc_id").alias("i"), F.col("text").alias("t"), F.lit(True).alias("train"))
    chunks = maxent._chunks(docs).persist()
    m = maxent.train(chunks, rounds=2)
    rows = chunks.select("chunk", "words").collect()
    assert len(rows) == 1
    words = np.frombuffer(rows[0]["words"], np.uint64)
    count, of = maxent._load(m.shape.folder, rows[0]["chunk"], len(words))
    place = maxent._places(words, m.shape.top)
    cls = np.where(words == maxent.END_HASH, maxent.END, np.where(place >= 0, place + 1, maxent.count_class(count, of)))
    logs = maxent.log_classes(m.weights, np.array([0, (2 << 8) | 1, (6 << 16) | (5 << 8) | 3]))
    p = np.exp(logs)
    inside = np.where(cls >= maxent.REST, count / m.class_total[cls], 1.0)
    empty = np.setdiff1d(np.arange(maxent.CLASSES), np.unique(cls))
    unknown = np.arange(maxent.REST, maxent.REST + maxent.GROUPS)
    total = (p[:, cls] * inside).sum(1) + p[:, unknown].sum(1) + p[:, np.setdiff1d(empty, unknown)].sum(1)
    assert np.allclose(total, 1, atol=1e-4)


def test_op5_features_of_words(spark):
    """Words beyond the frequent ones are told apart as previous and as skipped words, though class and count are the same."""
    rng = random.Random(3)
    frequent = [f"f{k}" for k in range(maxent.TOP + 20)]
    texts = [" ".join(rng.sample(frequent, 60)) for _ in range(60)]
    for k in range(30):
        texts += [f"a{k} b{k} {x} c{k} {y} d{k}" for x, y in (rng.sample(frequent, 2) for _ in range(3))]
    asked = [f"a{k} b{j}" for k in range(5) for j in (k, k + 5)] + [f"c{k} never d{j}" for k in range(5) for j in (k, k + 5)]
    rows = spark.createDataFrame([(k, t, k < len(texts)) for k, t in enumerate(texts + asked)], "doc_id bigint, text string, train boolean").repartition(3, "doc_id")
    got = {r.doc_id: r.score for r in maxent.score_language_model(rows, F.col("train"), rounds=2).collect()}
    scores = np.array([got[len(texts) + k] for k in range(len(asked))]).reshape(-1, 2)
    assert (scores[:, 0] > scores[:, 1] + 0.5).all()


def test_op5_word_pairs_by_brute_force(spark):
    """Counts of pairs and contexts over several chunks, weights of every pair of classes, and sums of probabilities."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(60).select(F.col("doc_id").alias("i"), F.col("text").alias("t"), (F.col("doc_id") % 4 > 0).alias("train"))
    rows = docs.unionByName(spark.createDataFrame([(1000, "", True), (1001, "one", True), (1002, None, False)], docs.schema)).repartition(3, "i")
    chunks = maxent._chunks(rows).persist()
    m, parts = maxent.train(chunks, rounds=1), chunks.collect()
    assert len(parts) == 3
    pairs, classes = {maxent.NEXT: collections.Counter(), maxent.SKIP: collections.Counter()}, set()
    for r in parts:
        words, split, token = np.frombuffer(r["words"], np.uint64), np.frombuffer(r["split"], np.int64), np.frombuffer(r["tokens"], np.uint32)
        train = np.frombuffer(r["train"], bool)
        history = m.shape.histories(*maxent._load(m.shape.folder, r["chunk"], len(words)), words, split, token)[2]
        classes |= set((history & 0xFFFF)[np.repeat(train, np.diff(split))].tolist())
        for k in np.flatnonzero(train):
            text = [int(maxent.END_HASH)] * 2 + words[token[split[k] : split[k + 1]]].tolist()
            pairs[maxent.NEXT].update(zip(text[1:], text[2:]))
            pairs[maxent.SKIP].update(zip(text, text[2:]))
    assert set(m.weights.pairs.tolist()) == classes
    whole = {kind: collections.Counter() for kind in pairs}
    followers = {kind: collections.Counter() for kind in pairs}
    for kind, found in pairs.items():
        for (a, _), n in found.items():
            whole[kind][a] += n
            followers[kind][a] += 1
    for r in parts:
        words, split, token = np.frombuffer(r["words"], np.uint64), np.frombuffer(r["split"], np.int64), np.frombuffer(r["tokens"], np.uint32)
        count, _, following, skip_following, last = (x.astype(np.int64) for x in exchange.answers(m.shape.folder, r["chunk"])[maxent.WORD])
        skips = np.where(words == maxent.END_HASH, last, count - last)
        for k, w in enumerate(words.tolist()):
            assert (count[k], following[k]) == (whole[maxent.NEXT][w], followers[maxent.NEXT][w])
            assert (skips[k], skip_following[k]) == (whole[maxent.SKIP][w], followers[maxent.SKIP][w])
        got = exchange.answers(m.pairs.folder, r["chunk"])
        for kind, context in zip((maxent.NEXT, maxent.SKIP), maxent._neighbours(words, split, token)):
            _, _, at = exchange.distinct(maxent._keys(words, context, token, m.pairs.shift))
            assert got[kind][0][at].tolist() == [pairs[kind][x] for x in zip(words[context].tolist(), words[token].tolist())]
    # All words and an unknown one, after two words, over any model below.
    words = sorted({w for _, w in pairs[maxent.NEXT]}) + [1]
    below = np.random.default_rng(5).dirichlet(np.ones(len(words)))
    for b, a in random.Random(6).sample(sorted(pairs[maxent.NEXT]), 20):
        seen = [np.array([pairs[kind][x, w] for w in words]) for kind, x in ((maxent.SKIP, b), (maxent.NEXT, a))]
        context = [tuple(np.full(len(words), c[kind][x]) for c in (whole, followers)) for kind, x in ((maxent.SKIP, b), (maxent.NEXT, a))]
        p = maxent._with_words(below, seen, context, [m.pairs.discount[kind] for kind in (maxent.SKIP, maxent.NEXT)])
        assert abs(p.sum() - 1) < 1e-9 and (p > 0).all()


def test_op6_counts(spark, documents):
    got = {r.doc_id: r for r in queries.op6_perplexity_rules(spark, SF).collect()}
    for i, t, _ in documents:
        t = t or ""
        w, seen, dup = SPACED.findall(t), set(), 0
        for line in t.split("\n"):
            if SPACED.search(line):
                dup += line in seen
                seen.add(line)
        runs = collections.Counter(tuple(w[k : k + 8]) for k in range(len(w) - 7))
        inside = {j for k in range(len(w) - 7) if runs[tuple(w[k : k + 8])] > 1 for j in range(k, k + 8)}
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(inside))
        assert r.base_failed == (len(w) < 20 or 100 * len(inside) > 30 * len(w)) and not (r.base_failed and r.kept)
    good = spark.read.parquet(f"{SF}/labels.parquet").where("quality = 1").select("doc_id").collect()
    fair = [got[r.doc_id] for r in good if not got[r.doc_id].base_failed]
    assert sum(r.kept for r in fair) >= 0.97 * len(fair)


def test_op6_symbols_by_hand():
    """Probabilities over all symbols add up to 1 after every symbol, seen or not."""
    rng = np.random.default_rng(2)
    table = rng.poisson(0.4, (perplexity.SYMBOLS, perplexity.SYMBOLS)).astype(float)
    table[5] = 0
    assert np.allclose(perplexity.symbol_model(table).sum(1), 1)
    top = np.array([3, 9], np.uint64)
    shift = np.uint64(8)
    got = perplexity.symbols(top, np.array([3 << 8, 4 << 8, 9 << 8], np.uint64), np.array([1, 2, 3], np.uint8), shift)
    assert got.tolist() == [perplexity.END + 1, 2, perplexity.END + 2]


def test_op7_quality(spark):
    out = queries.op7_site_quality(spark, SF).join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id").collect()
    assert sum(r.kept == bool(r.quality) for r in out) >= 0.95 * len(out)
    # A path's rate lies between its own documents' and its host's.
    d = spark.createDataFrame([(k, "good text of words here and there, fine. " * 3, "h1", "p1") for k in range(9)] + [(k, "BAD### $$$ ***", "h1", "p2") for k in range(9, 18)], "doc_id bigint, text string, host string, path string")
    y = spark.createDataFrame([(k, int(k < 9)) for k in range(18)], "doc_id bigint, quality int")
    r = {x.doc_id: x for x in quality.quality_by_site(d, y, F.col("host"), F.col("path")).collect()}
    assert r[0].path_rate > r[0].host_rate > r[9].path_rate and r[0].kept and not r[9].kept


def test_op8_near_the_limit(spark):
    rows = [(k, f"line {n}\nown {k} {n}", f"site{k}") for n in (3, 4, 5, 40) for k in range(n)]
    docs = spark.createDataFrame([(i, t, s) for i, (_, t, s) in enumerate(rows)], "doc_id bigint, text string, source string")
    got = linededup.drop_boilerplate_lines(docs, min_sites=4).collect()
    for r in got:
        n = int(rows[r.doc_id][1].split("\n")[0].split()[1])
        assert r.n_removed == (n >= 4) and ("line" in r.text) == (n < 4)
    plan = linededup.drop_boilerplate_lines(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def jaccard_links(texts, size, num, den):
    sets = []
    for t in texts:
        w = SPACED.findall((t or "").translate(LOW))
        sets.append({tuple(w[k : k + size]) for k in range(max(1, len(w) - size + 1))} if w else set())
    links = [(a, b) for a in range(len(sets)) for b in range(a) if sets[a] and den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b])]
    return sets, links


@pytest.mark.parametrize("size,num", [(3, 85), (5, 80), (2, 50)])
def test_op9_brute_force(spark, size, num):
    rng = random.Random(size)
    words = [f"w{k}" for k in range(60)]
    texts, passage = [None, "", "  ", "one", "one", "one two"], [rng.choice(words) for _ in range(40)]
    for _ in range(12):
        base = [rng.choice(words) for _ in range(rng.choice([4, 7, 12, 30, 90]))]
        for _ in range(rng.choice([1, 2, 5, 12])):
            copy = list(base)
            for _ in range(rng.choice([0, 1, 1, 2, 4])):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            texts.append(" ".join(copy))
    texts += [" ".join(passage + [rng.choice(words) for _ in range(rng.choice([5, 30]))]) for _ in range(15)]
    sets, links = jaccard_links(texts, size, num, 100)
    label = list(range(len(texts)))
    for _ in texts:
        for a, b in links:
            label[a] = label[b] = min(label[a], label[b])
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    got = {r.doc_id: r for r in neardup.near_duplicates(docs, size, num, 100).collect()}
    assert [got[k].n_shingles for k in range(len(texts))] == [len(s) for s in sets]
    assert [got[k].component_id for k in range(len(texts))] == label
    assert all(got[k].kept == (label[k] == k) for k in range(len(texts)))


def test_op9_run_lengths_are_safe():
    for num in (85, 80, 70):
        limits = neardup.run_limits(num, 100)
        for shared in range(1, 60):
            apart = shared * (100 - num) // num
            longest = -(-shared // (apart + 1))  # at least, however the unshared elements fall
            n = shared + apart
            lengths = [neardup.RUN, *(x for x, most in limits.items() if n <= most)]
            assert apart == 0 or min(lengths) <= longest


def test_op10_blocks_agree(spark):
    docs, bench = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "benchmark"))
    bench = bench.unionByName(spark.createDataFrame([(900, "it is"), (901, None), (902, "..."), (None, "it is the")], "item_id bigint, text string"))
    one, many = (sorted((r.doc_id, r.n_words, r.n_hit, tuple(r["items"])) for r in decontaminate.decontaminate(docs, bench, block_bytes=b).collect()) for b in (1 << 20, 2000))
    assert one == many and any(x[2] for x in one)
    assert all("900" in x[3] or x[2] == 0 or x[3] for x in one)


def test_op10_digest():
    assert decontaminate.items_digest([]) == hashlib.sha256(b"").hexdigest()
    assert decontaminate.items_digest(["2", "10"]) == hashlib.sha256(b"10,2").hexdigest()


def test_op6_words_by_hand(spark):
    """Word probabilities against modified Kneser-Ney written out; random words of the same shapes are no clean text."""
    rng = random.Random(6)
    letters = "abcdefghijklmnopqrstuvwxyz"
    pool = ["".join(rng.choice(letters) for _ in range(rng.randint(3, 7))) for _ in range(600)]

    def text():
        at, out = rng.randrange(600), []
        for _ in range(60):
            out.append(pool[at])
            at = (at * 7 + rng.randrange(4)) % 600
        return " ".join(out)

    clean = [text() for _ in range(200)]
    junk = [" ".join("".join(rng.choice(letters) for _ in w) for w in t.split()) for t in clean[:6]]
    rows = spark.createDataFrame([(k, "en", t) for k, t in enumerate(clean + junk)], "doc_id bigint, lang string, text string")
    got = {r.doc_id: r for r in perplexity.perplexity_filter(rows).collect()}
    assert sum(got[k].kept for k in range(200)) >= 196 and not any(got[200 + k].kept for k in range(6))

    # Again with two languages, one of them null, and chunks of a few texts.
    texts = [(k, ["en", None][k % 3 == 0], t) for k, t in enumerate([*clean[:60], "", "one", "one"])]
    docs = spark.createDataFrame(texts, "doc_id bigint, lang string, text string").repartition(3)
    docs = exchange.stable(docs.select(F.col("doc_id").alias("i"), F.coalesce(F.concat(F.lit("="), "lang"), F.lit("")).alias("language"), "text", F.xxhash64("lang", "text").alias("t")))
    model = perplexity.train(docs)
    half = {r.i: r.t & 1 for r in docs.collect()}
    got = {r.doc_id: r for r in perplexity.measures(docs, model).collect()}

    def discounted(counts):
        of = collections.Counter(counts.values())
        d = [0.0, *perplexity.discounts(*(of[k] for k in (1, 2, 3, 4)))]
        whole, rest = collections.Counter(), collections.Counter()
        for g, n in counts.items():
            whole[g[:-1]] += n
            rest[g[:-1]] += d[min(n, 3)]
        return lambda g, low: ((counts[g] - d[min(counts[g], 3)] if g in counts else 0.0) + rest[g[:-1]] * low) / whole[g[:-1]] if whole[g[:-1]] else low

    for language in ("en", None):
        mine = [(i, ["<s>", *(t or "").split(), "</s>"]) for i, g, t in texts if g == language]
        name = "=en" if language else ""
        words = collections.Counter(w for _, ws in mine for w in ws[1:-1])
        data, offsets = textkit.text_rows(pa.array([" ".join(words)]))
        cut = textkit.words(data, offsets, textkit.SPACED)
        shape = dict(zip(words, perplexity.shapes(data, cut).tolist(), strict=True)) | {"<s>": perplexity.START, "</s>": perplexity.END}
        # Frequent words are symbols of their own; their numbers follow from the model's keys.
        seed = textkit.mix(np.array([int.from_bytes(name.encode()[-8:], "little")], np.uint64) + np.array([len(name)], np.uint64) * textkit.U(0xA0761D6478BD642F))
        keys = dict(zip(words, textkit.mix(cut.hash + seed[0]), strict=True))
        least = sorted(words.values())[-min(perplexity.WORDS, len(words))]
        symbol = {w: int(perplexity.symbols(model.top[name], np.array([keys[w]], np.uint64), np.array([x], np.uint8), model.plan.shift)[0]) if w in keys else x for w, x in shape.items()}
        assert all(symbol[w] > perplexity.END for w, n in words.items() if n > least)
        assert sum(x > perplexity.END for x in symbol.values()) == min(perplexity.WORDS, len(words))
        counts = np.zeros((perplexity.SYMBOLS, perplexity.SYMBOLS))
        for _, ws in mine:
            for v, w in zip(ws, ws[1:]):
                counts[symbol[v], symbol[w]] += 1
        p0 = perplexity.symbol_model(counts)
        two = [collections.Counter((v, w) for i, ws in mine if half[i] == h for v, w in zip(ws, ws[1:])) for h in (0, 1)]
        one = [collections.Counter((w,) for _, w in t) for t in two]
        types = [collections.Counter(symbol[w] for (w,) in x) for x in one]
        for i, ws in mine:
            h = 1 - half[i]
            p2, p1 = discounted(two[h]), discounted(one[h])
            logs = []
            for v, w in zip(ws, ws[1:]):
                share = types[h][symbol[w]] + 1 if symbol[w] < perplexity.START else 1
                logs.append(-math.log10(p2((v, w), p1((w,), p0[symbol[v], symbol[w]] / share))))
            assert got[i].log_perplexity == pytest.approx(sum(logs) / len(logs), rel=1e-3)


def test_op7_distinct_of_whole_text():
    """Repetition beyond the first 200 words counts; the share does not fall with length alone."""
    varied = [f"w{k}" for k in range(200)]
    texts = [varied, varied + ["a", "b"] * 1500, varied * 10, varied + ["x"] * 10, [], ["a", "a", "b"]]
    data, offsets = textkit.text_rows(pa.array([" ".join(x) for x in texts]))
    got = quality.measure(data, offsets)[:, quality.FEATURES.index("distinct")]
    assert got.tolist() == pytest.approx([1, (1 + 15 * 0.01) / 16, 1, (1 + 191 / 200) / 2, 0, 2 / 3])


def test_op5_top_words_are_exact(spark, monkeypatch):
    """Words that are frequent over all chunks but not among the best of each are found."""
    monkeypatch.setattr(maxent, "TOP", 3)
    rng = random.Random(4)
    texts = []
    for k in range(8):  # of each chunk other words are first, "steady" is fourth everywhere
        texts.append(" ".join([f"a{k}"] * 9 + [f"b{k}"] * 9 + [f"c{k}"] * 9 + ["steady"] * 8 + [f"r{rng.randrange(50)}" for _ in range(20)]))
    rows = spark.createDataFrame([(k, t, True) for k, t in enumerate(texts)], "i bigint, t string, train boolean").repartition(8, "i")
    chunks = maxent._chunks(rows).persist()
    data, offsets = textkit.text_rows(pa.array(["steady"]))
    steady = textkit.words(data, offsets, textkit.SPACED_LOWER).hash[0]
    counts = collections.Counter(w for t in texts for w in t.split())
    assert counts.most_common(1)[0][0] == "steady" and maxent._top_words(chunks)[0] == steady


def brute_hits(text, items, size):
    words = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    w, hit, names = words.findall(text.translate(LOW)), set(), set()
    for name, item in items:
        x = words.findall(item.translate(LOW))
        for k in range(max(1, len(x) - size + 1)) if x else ():
            window = x[k : k + size]
            for at in range(len(w) - len(window) + 1):
                if w[at : at + len(window)] == window:
                    hit.update(range(at, at + len(window)))
                    names.add(name)
    return len(hit), sorted(names)


def test_op10_repetitive_items_and_texts(spark, monkeypatch):
    """Equal windows count once, candidates come piece by piece, and results are those of brute force."""
    monkeypatch.setattr(decontaminate, "CANDIDATES", 64)
    rng = random.Random(10)
    items = [("1", "ja " * 40), ("2", "ja " * 12 + "nein"), ("2", "ja " * 12), ("3", " ".join(rng.choice(["a", "b"]) for _ in range(30))), ("4", "a b a"), ("5", "...")]
    texts = ["ja " * 300, "nein " + "ja " * 9, " ".join(rng.choice(["a", "b"]) for _ in range(200)), "x a b a y", ""]
    w = decontaminate.build_windows(items, 10, {})
    assert len(w.begin) == len({tuple(x) for _, t in items for x in [t.split()[k : k + 10] for k in range(max(1, len(t.split()) - 9))] if x != ["..."]})
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    bench = spark.createDataFrame(items, "item_id string, text string")
    got = {r.doc_id: (r.n_hit, list(r["items"])) for r in decontaminate.decontaminate(docs, bench).collect()}
    assert got == {k: brute_hits(t, items, 10) for k, t in enumerate(texts)}


def test_op10_long_repetitive_text(spark):
    docs = spark.createDataFrame([(1, "ja " * 20_000)], "doc_id bigint, text string")
    bench = spark.createDataFrame([(1, "ja " * 20_000), (2, "ja " * 20_000)], "item_id bigint, text string")
    r = decontaminate.decontaminate(docs, bench).collect()[0]
    assert r.n_hit == 20_000 and list(r["items"]) == ["1", "2"]


def test_op7_by_brute_force(spark):
    """Evidence, rates and scores written out; ids beyond 2**53 keep their labels."""
    rng = random.Random(7)
    big = 2**53
    rows = []
    for k in range(60):
        good = k % 3 > 0
        text = " ".join(rng.choice(["word", "other", "text", "of", "the"]) + ("." if rng.random() < 0.1 else "") for _ in range(40)) if good else "BAD## $$ " * rng.randint(2, 9)
        rows.append((big + k, text, f"h{k % 4}", f"p{k % 7}", int(good)))
    docs = spark.createDataFrame([x[:4] for x in rows], "doc_id bigint, text string, host string, path string")
    labels = spark.createDataFrame([(x[0], x[4]) for x in rows], "doc_id bigint, quality int")
    got = {r.doc_id: r for r in quality.quality_by_site(docs, labels, F.col("host"), F.col("path")).collect()}
    data, offsets = textkit.text_rows(pa.array([x[1] for x in rows]))
    x = quality.measure(data, offsets)
    mean, scale, w = quality.fit(x, np.array([r[4] for r in rows]))
    z = np.clip(np.clip((x - mean) / scale, -8, 8) @ w[:-1] + w[-1], -20, 20)
    p = 1 / (1 + np.exp(-z))
    m = p.mean()

    def groups(key):
        out = collections.defaultdict(list)
        for r, v in zip(rows, p, strict=True):
            out[key(r)].append(v)
        return out

    def strength(of, expected):
        n = sum(len(v) for v in of.values())
        spread = sum(len(v) * (sum(v) / len(v) - expected[k]) ** 2 for k, v in of.items()) - sum(expected[k] * (1 - expected[k]) for k in of)
        return min(1000.0, max(1.0, np.mean([expected[k] * (1 - expected[k]) for k in of]) / max(1e-4, spread / n) - 1))

    hosts, paths = groups(lambda r: r[2]), groups(lambda r: r[2:4])
    k_host = strength(hosts, dict.fromkeys(hosts, m))
    host_mean = {h: (sum(v) + k_host * m) / (len(v) + k_host) for h, v in hosts.items()}
    k_path = strength(paths, {k: host_mean[k[0]] for k in paths})
    for r, v, e in zip(rows, p, z, strict=True):
        a, b = hosts[r[2]], paths[r[2:4]]
        host_rate = (sum(a) - v + k_host * m) / (len(a) - 1 + k_host)
        path_rate = (sum(b) - v + k_path * host_rate) / (len(b) - 1 + k_path)
        odds = e + math.log(path_rate / (1 - path_rate)) - math.log(m / (1 - m))
        x = got[r[0]]
        assert (x.evidence, x.host_rate, x.path_rate) == pytest.approx((e, host_rate, path_rate), rel=1e-6)
        assert x.score == pytest.approx(1 / (1 + math.exp(-odds)), rel=1e-6)


def test_op2_hot_payload_with_a_repeated_largest_id(spark):
    pages = spark.createDataFrame([(k % 400, "u", "hot") for k in range(401)] + [(399, "u", "hot")], "page_id bigint, url string, html string")
    got = warc.read_archives(warc.write_archives(pages)).collect()
    assert sorted(r.page_id for r in got if r.record_type == "response") == [399, 399]
    assert all(r.refers_to == 399 for r in got if r.record_type == "revisit") and len(got) == 402


def test_op1_folds_hold_both_kinds():
    y = np.array([0] * 50 + [1] * 10)
    fold = toxicity.folds(np.arange(60), y)
    assert all((y[fold == f] == 1).sum() == 2 and (y[fold == f] == 0).sum() == 10 for f in range(toxicity.FOLDS))
