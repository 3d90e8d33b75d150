"""A maximum-entropy language model: n-gram and skip features of words over those of classes, class-factored softmax.

Texts are cut into chunks, each with a dictionary of its own: what later passes need of the corpus (counts, classes) is looked up
by dictionary entry or distinct pair of words, not by token, and comes back to a chunk as one file. Below lies a model of classes,

    Q(token | history) = P(class | history) * P(token | class)

The most frequent words are classes of their own; others are classed by count and by community, the group of frequent
words that their documents use. A training token is classed by its count less one, so the classes of rare and
unknown words get the share that they have in new text. P(class | history) is a softmax over the
classes of the previous token, of the one before (skip), of both (n-gram), and the community that prevails
in the text so far. Every pair of classes has weights of its own. Sufficient statistics, counts of (history, class), cover all training
tokens; every round each task adds up the gradient over its share of them. A pair's histories are in one share, which makes the
step of its weights; one update of the others follows from the sum.

Over Q stand features of the words themselves, without a bound on their number: every pair of a word and the next one, and of
a word and the one after that, that training texts have. Of all distributions with a pair's discounted frequency as its part beside what the
model below gives, the one nearest to the model below has weights that follow from counts:

    P(w | h) = (n(a, w) - d) / n(a) + d * followers(a) / n(a) * (the model below)(w | h)

for skips over Q first, then for next words. A token's probability needs the counts of its own two pairs and of its two contexts only,
and all words and the unknown one add up to 1.
"""

from __future__ import annotations

import math
import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyarrow.fs import FileSelector
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from autotheta.llm import exchange, textkit
from autotheta.sources.shared import delete, discard, keep, map_arrow, new_path, open_store, release

#: Text bytes of a chunk; words with a class of their own; communities; rounds; rows of packed statistics.
CHUNK, TOP, GROUPS, ROUNDS, SHARES = 4 << 20, 200, 6, 6, 16
#: Upper ends of the bins of counts that class the other words; below the first is the unknown word.
BINS = np.array([1, 2, 8, 64, 1024])
#: Classes: the end, TOP words, then bins x communities, the unknown word's bin first.
END, REST = 0, TOP + 1
CLASSES = REST + len(BINS) * GROUPS + GROUPS
END_HASH = np.uint64(0x5851F42D4C957F2D)


def _chunks(rows: DataFrame) -> DataFrame:
    """Rows ``chunk, ids, train, split, tokens, words, counts``: a dictionary and the texts as entries of it."""
    names = ["chunk", "ids", "nulls", "train", "split", "tokens", "words", "counts"]

    def pack(ids, nulls, train, parts, lengths):
        hashes = np.concatenate(parts)
        n = np.concatenate(lengths)
        split = np.concatenate([[0], np.cumsum(n)])
        words, tokens = np.unique(hashes, return_inverse=True)
        train = np.concatenate(train)
        counts = np.bincount(tokens[np.repeat(train, n)], minlength=len(words))
        blobs = [np.concatenate(ids), np.concatenate(nulls), train, split.astype(np.int64), tokens.astype(np.uint32), words, counts.astype(np.uint32)]
        return pa.RecordBatch.from_arrays([pa.array([uuid.uuid4().int >> 66]), *(pa.array([x.tobytes()], pa.binary()) for x in blobs)], names)

    def run(batches):
        held: tuple[list, ...] = ([], [], [], [], [])
        size = 0
        for b in batches:
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                w = textkit.words(data, offsets, textkit.SPACED_LOWER)
                hashes = w.hash if w.hash is not None else np.zeros(0, np.uint64)
                ids = b.column(0)[lo:hi]
                held[0].append(ids.fill_null(0).to_numpy().astype(np.int64))
                held[1].append(ids.is_null().to_numpy(zero_copy_only=False))
                held[2].append(b.column(2)[lo:hi].to_numpy(zero_copy_only=False).astype(bool))
                held[3].append(np.insert(hashes, w.split[1:], END_HASH))
                held[4].append(np.diff(w.split) + 1)
                size += len(data)
                if size >= CHUNK:
                    yield pack(*held)
                    held, size = ([], [], [], [], []), 0
        if held[0]:
            yield pack(*held)

    return map_arrow(rows, run, "chunk bigint, ids binary, nulls binary, train binary, split binary, tokens binary, words binary, counts binary")


def _array(x, kind) -> np.ndarray:
    return np.frombuffer(x.as_py(), kind)


def _top_words(chunks: DataFrame) -> np.ndarray:
    """The TOP most frequent words, by exact counts, without a shuffle of all words.

    The TOP best of each chunk are summed first. The last of the TOP best sums is no more than the true count
    of the last word sought, so each of these has its share of it by the number of chunks in some chunk at least. Those that
    have are few, and are counted in all chunks.
    """

    def select(least: float):
        def run(batches):
            for b in batches:
                for k in range(b.num_rows):
                    h, n = _array(b.column(0)[k], np.uint64), _array(b.column(1)[k], np.uint32)
                    at = np.flatnonzero((n > 0) & (n >= least) & (h != END_HASH))
                    if not least:
                        at = at[np.lexsort((h[at], -n[at].astype(np.int64)))[:TOP]]
                    yield pa.RecordBatch.from_arrays([pa.array(h[at].view(np.int64)), pa.array(n[at].astype(np.int64))], ["h", "n"])

        return run

    def total(found: DataFrame) -> DataFrame:
        return found.groupBy("h").agg(F.sum("n").alias("n"))

    words = chunks.select("words", "counts")
    some = total(map_arrow(words, select(0), "h bigint, n bigint")).orderBy(F.desc("n"), "h").limit(TOP).agg(F.min("n").alias("n"), F.count(F.lit(1)).alias("words")).first()
    if not some["words"]:
        return np.zeros(0, np.uint64)
    least = some["n"] / chunks.count() if some["words"] == TOP else 1
    wanted = np.sort(map_arrow(words, select(least), "h bigint, n bigint").select("h").distinct().toArrow()["h"].to_numpy().astype(np.int64).view(np.uint64))
    shared = chunks.sparkSession.sparkContext.broadcast(wanted)

    def count(batches):
        for b in batches:
            for k in range(b.num_rows):
                h, n = _array(b.column(0)[k], np.uint64), _array(b.column(1)[k], np.uint32)  # in order of h
                at = np.minimum(np.searchsorted(h, shared.value), len(h) - 1)
                mine = np.flatnonzero((h[at] == shared.value) & (n[at] > 0)) if len(h) else np.zeros(0, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(shared.value[mine].view(np.int64)), pa.array(n[at[mine]].astype(np.int64))], ["h", "n"])

    return total(map_arrow(words, count, "h bigint, n bigint")).orderBy(F.desc("n"), "h").limit(TOP).toArrow()["h"].to_numpy().astype(np.int64).view(np.uint64)


def _places(words: np.ndarray, top: np.ndarray) -> np.ndarray:
    """Index in ``top`` of each word, -1 for others."""
    order = np.argsort(top)
    if not len(top):
        return np.full(len(words), -1)
    k = np.minimum(np.searchsorted(top[order], words), len(top) - 1)
    return np.where(top[order][k] == words, order[k], -1)


def _communities(chunks: DataFrame, top: np.ndarray) -> np.ndarray:
    """Community of each top word, from how often two stand in one document (a TOP x TOP table)."""
    if len(top) < 2 * GROUPS:
        return np.zeros(len(top), np.int64)

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                place = _places(_array(b.column(0)[k], np.uint64), top)
                split, token = _array(b.column(1)[k], np.int64), _array(b.column(2)[k], np.uint32)
                row, p = np.repeat(np.arange(len(split) - 1), np.diff(split)), place[token]
                table = np.zeros((len(top), len(top)))
                for at in range(0, len(split) - 1, 2000):
                    here = (row >= at) & (row < at + 2000) & (p >= 0)
                    x = np.zeros((min(2000, len(split) - 1 - at), len(top)), np.float32)
                    x[row[here] - at, p[here]] = 1
                    table += x.T @ x
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(top))), pa.array(table.tolist(), pa.list_(pa.float64()))], ["i", "row"])

    parts = map_arrow(chunks.select("words", "split", "tokens"), run, "i bigint, row array<double>")
    table = np.zeros((len(top), len(top)))
    added = parts.groupBy("i").agg(F.array(*[F.sum(F.col("row")[j]) for j in range(len(top))]).alias("row")) if len(top) <= 64 else parts.select("i", F.posexplode("row").alias("j", "n")).groupBy("i", "j").agg(F.sum("n").alias("n"))
    t = added.toArrow()
    if "j" in t.column_names:
        table[t["i"].to_numpy(), t["j"].to_numpy()] = t["n"].to_numpy()
    else:
        table[t["i"].to_numpy()] = np.array(t["row"].to_pylist())
    return cluster(table, GROUPS)


def cluster(table: np.ndarray, groups: int) -> np.ndarray:
    """Groups of items by their normalised co-occurrence: spectral coordinates, then k-means from far points."""
    n = np.maximum(np.diag(table), 1)
    affinity = table / np.sqrt(np.outer(n, n))
    d = np.sqrt(np.maximum(affinity.sum(1), 1e-9))
    values, vectors = np.linalg.eigh(affinity / np.outer(d, d))
    x = vectors[:, -groups:]
    x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    centres = [x[int(np.argmax(n))]]
    for _ in range(groups - 1):
        centres.append(x[int(np.argmin(np.max([np.abs(x @ c) for c in centres], axis=0)))])
    c = np.array(centres)
    for _ in range(30):
        of = np.argmax(x @ c.T, axis=1)
        for g in range(groups):
            if (of == g).any():
                m = x[of == g].mean(0)
                c[g] = m / max(1e-12, np.linalg.norm(m))
    return np.argmax(x @ c.T, axis=1)


def _document_groups(split: np.ndarray, p: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Community of each document, and the prevailing one before each token (GROUPS: none yet)."""
    n = len(p)
    row = np.repeat(np.arange(len(split) - 1, dtype=np.int32), np.diff(split))
    best, lead, of_doc, top_doc = np.zeros(n, np.int32), np.full(n, GROUPS, np.uint8), np.zeros(len(split) - 1, np.int64), np.zeros(len(split) - 1, np.int64)
    mine = np.where(p >= 0, group[np.maximum(p, 0)] if len(group) else 0, -1).astype(np.int8)
    for g in range(GROUPS):
        c = np.concatenate([[0], np.cumsum(mine == g, dtype=np.int32)])
        before = c[:-1] - c[split[:-1]][row]
        better = before > best
        best[better], lead[better] = before[better], g
        total = c[split[1:]] - c[split[:-1]]
        more = total > top_doc
        top_doc[more], of_doc[more] = total[more], g
    return of_doc, lead


def count_class(count: np.ndarray, group: np.ndarray) -> np.ndarray:
    """Class of words that are not top words, by training count."""
    return REST + np.searchsorted(BINS, count, "right") * GROUPS + group


def _neighbours(words: np.ndarray, split: np.ndarray, token: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Entries of the previous token and of the one before, the end's where a text has none."""
    end = np.searchsorted(words, END_HASH)
    one, two = np.full(len(token), end, np.int32), np.full(len(token), end, np.int32)
    one[1:], two[2:] = token[:-1], token[:-2]
    starts = split[:-1]
    one[starts], two[starts] = end, end
    two[np.minimum(starts + 1, len(token) - 1)[np.diff(split) > 1]] = end
    return one, two


#: Kinds of word features: the word after the previous one, and after the one before that.
NEXT, SKIP, WORD = "next", "skip", "word"


def _keys(words: np.ndarray, context: np.ndarray, token: np.ndarray, shift: np.uint64) -> np.ndarray:
    return textkit.mix(words[context] * textkit.U(0x9E3779B97F4A7C15) + words[token]) >> shift


def _pair_questions(plan: exchange.Plan):
    """Distinct word pairs of each chunk, of both kinds, with their training counts."""

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                words, split, token = _array(b.column(1)[k], np.uint64), _array(b.column(2)[k], np.int64), _array(b.column(3)[k], np.uint32)
                train = np.repeat(_array(b.column(4)[k], bool), np.diff(split)).astype(np.uint32)
                for kind, context in zip((NEXT, SKIP), _neighbours(words, split, token), strict=True):
                    keys = _keys(words, context, token, plan.shift)
                    order, first, _ = exchange.distinct(keys)
                    yield from exchange.question(b.column(0)[k].as_py(), kind, keys[order[first]], [np.add.reduceat(train[order], first)], plan)

    return run


def _own_pairs(kind, keys, counts, first, at):
    """Training count of each pair, and who is first to hold it; how many pairs occur once and twice."""
    total = np.add.reduceat(counts[0].astype(np.int64), first)
    new = np.zeros(len(at), np.uint8)
    new[first] = total > 0
    return [total[at].astype(np.uint32), new], np.array([int((total == k).sum()) for k in (1, 2)])


def _answers(folder: str, chunk: int, kind: str, n: int) -> list[np.ndarray]:
    got = exchange.answers(folder, chunk)[kind]
    if len(got[0]) != n:
        raise ValueError("an answer is not to the question of its chunk")
    return got


def _word_questions(plan: exchange.Plan, pair_plan: exchange.Plan, pairs: str, top: np.ndarray, group: np.ndarray):
    """For each entry of each dictionary: training count, community, and what makes it a context of word features.

    The community is the one that its documents in the chunk have most. As a context a word has its distinct followers of both
    kinds, each counted where the pair was met first, and its tokens that no skip begins with (of the end: the skips that begin with it).
    """

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                chunk = b.column(0)[k].as_py()
                words, split, token = _array(b.column(1)[k], np.uint64), _array(b.column(2)[k], np.int64), _array(b.column(3)[k], np.uint32)
                train, count = np.repeat(_array(b.column(4)[k], bool), np.diff(split)), _array(b.column(5)[k], np.uint32)
                of_doc, _ = _document_groups(split, _places(words, top)[token], group)
                cell = token.astype(np.int64) * GROUPS + np.repeat(of_doc, np.diff(split))
                g = np.argmax(np.bincount(cell, minlength=len(words) * GROUPS).reshape(-1, GROUPS), axis=1)
                got, followers = exchange.answers(pairs, chunk), []
                one, two = _neighbours(words, split, token)
                for kind, context in ((NEXT, one), (SKIP, two)):
                    order, first, _ = exchange.distinct(_keys(words, context, token, pair_plan.shift))
                    if len(got[kind][1]) != len(first):
                        raise ValueError("an answer is not to the question of its chunk")
                    followers.append(np.bincount(context[order[first[got[kind][1] > 0]]], minlength=len(words)))
                skips, end = np.bincount(two[train], minlength=len(words)), np.searchsorted(words, END_HASH)
                last = count - skips
                last[end] = skips[end]
                yield from exchange.question(chunk, WORD, words >> plan.shift, [count, g.astype(np.uint8), *(x.astype(np.uint32) for x in (*followers, last))], plan)

    return run


def _own_words(top: np.ndarray, shift: np.uint64):
    """Answers by word: the sums, and the community that most tokens vote for.

    Totals: training tokens of each class of words, of all, and the distinct training words.
    """

    def answer(kind, keys, counts, first, at):
        n, g = counts[0].astype(np.int64), counts[1]
        c, *sums = (np.add.reduceat(x.astype(np.int64), first) for x in (n, *counts[2:]))
        of = np.argmax(np.stack([np.add.reduceat(np.where(g == k, n, 0), first) for k in range(GROUPS)]), axis=0)
        plain = (c > 0) & (keys != END_HASH >> shift) & (_places(keys, top >> shift) < 0)
        by_class = np.bincount(count_class(c[plain], of[plain]), c[plain], minlength=CLASSES).astype(np.int64)
        return [c[at].astype(np.uint32), of[at].astype(np.uint8), *(x[at].astype(np.uint32) for x in sums)], np.concatenate([by_class, [c.sum(), (c > 0).sum()]])

    return answer


def _load(folder: str, chunk: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Training count and community of each entry of a chunk."""
    count, of = _answers(folder, chunk, WORD, n)[:2]
    return count.astype(np.int64), of.astype(np.int64)


@dataclass
class Shape:
    """What classes a token: top words and their communities, and the files of looked-up entries."""

    top: np.ndarray
    group: np.ndarray
    folder: str

    def histories(self, count: np.ndarray, of: np.ndarray, words: np.ndarray, split: np.ndarray, token: np.ndarray):
        """By entry, from its count and community: class, class when it is left out of the counts; by token: packed history."""
        place = _places(words, self.top)
        fixed = np.where(words == END_HASH, END, np.where(place >= 0, place + 1, -1))
        known = np.where(fixed >= 0, fixed, count_class(count, of)).astype(np.uint8)
        left_out = np.where(fixed >= 0, fixed, count_class(np.maximum(count - 1, 0), of)).astype(np.uint8)
        # As history a word has its class in the counts, whether its text is in them or not.
        one, two = (known[x].astype(np.int32) for x in _neighbours(words, split, token))
        history = (two << 8) | one
        history |= _document_groups(split, place[token], self.group)[1].astype(np.int32) << 16
        return known, left_out, history


def features(history: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features of each history: rows of the dense weights (previous, skip, community), and the number of the pair."""
    one, two, lead = history & 255, (history >> 8) & 255, history >> 16
    return np.stack([one, 256 + two, 512 + lead], axis=1), history & 0xFFFF


#: Dense rows: previous classes, skipped classes, communities.
ROWS = 528


@dataclass
class Weights:
    """Weights of the classes' features: dense rows, and a row of its own for every pair that training texts have."""

    rows: np.ndarray
    pairs: np.ndarray
    of_pairs: np.ndarray

    def of(self, pair: np.ndarray) -> np.ndarray:
        """Rows of pairs; 0 where no training text has the pair."""
        if not len(self.pairs):
            return np.zeros((len(pair), CLASSES), np.float32)
        k = np.minimum(np.searchsorted(self.pairs, pair), len(self.pairs) - 1)
        return self.of_pairs[k].astype(np.float32) * (self.pairs[k] == pair)[:, None]


def log_classes(weights: Weights, history: np.ndarray) -> np.ndarray:
    """log P(class | history)."""
    f, pair = features(history)
    x = weights.rows[f[:, 0]] + weights.rows[f[:, 1]] + weights.rows[f[:, 2]] + weights.of(pair)
    x -= x.max(1, keepdims=True)
    return x - np.log(np.exp(x).sum(1, keepdims=True))


def _statistics(chunks: DataFrame, shape: Shape) -> DataFrame:
    """``history, class, n`` over all training tokens."""
    shared = chunks.sparkSession.sparkContext.broadcast(shape)

    def run(batches):
        for b in batches:
            for k in range(b.num_rows):
                words, split, token = _array(b.column(1)[k], np.uint64), _array(b.column(2)[k], np.int64), _array(b.column(3)[k], np.uint32)
                train = np.repeat(_array(b.column(4)[k], bool), np.diff(split))
                _, cls, history = shared.value.histories(*_load(shared.value.folder, b.column(0)[k].as_py(), len(words)), words, split, token)
                key, n = np.unique((history.astype(np.int64) << 8 | cls[token])[train], return_counts=True)
                del words, split, token, train, cls, history
                release()
                for at in range(0, len(key), 200_000):
                    yield pa.RecordBatch.from_arrays([pa.array(key[at : at + 200_000]), pa.array(n[at : at + 200_000])], ["key", "n"])

    return map_arrow(chunks.select("chunk", "words", "split", "tokens", "train"), run, "key bigint, n bigint").groupBy("key").agg(F.sum("n").alias("n"))


def _shares(stats: DataFrame) -> DataFrame:
    """``share, key, n``: the statistics as arrays in SHARES rows; a pair's histories are in one of them."""

    def run(batches):
        parts = [[b.column(k).to_numpy() for k in range(3)] for b in batches]
        if not parts:
            return
        share, key, n = (np.concatenate(x) for x in zip(*parts, strict=True))
        for s in np.unique(share):
            mine = np.flatnonzero(share == s)
            mine = mine[np.argsort(key[mine])]
            yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([key[mine].tobytes()], pa.binary()), pa.array([n[mine].tobytes()], pa.binary())], ["share", "key", "n"])

    share = F.pmod(F.hash(F.shiftright("key", 8).bitwiseAND(0xFFFF)), F.lit(SHARES))
    return map_arrow(stats.select(share.alias("share"), "key", "n").repartition(SHARES, "share"), run, "share int, key binary, n binary")


def _step(weights: np.ndarray, seen: np.ndarray, expected: np.ndarray) -> np.ndarray:
    """One step along the gradient, scaled by the counts it is made of; four features share a history."""
    step = (seen - expected - 0.05 * weights) / (4 * (0.5 * (seen + expected) + 0.5))
    return (weights + np.clip(1.5 * step, -1.0, 1.0) * (seen.sum(1, keepdims=True) > 0)).astype(np.float32)


def _read_pairs(path: str) -> tuple[np.ndarray, np.ndarray]:
    store, root = open_store(path)
    with store.open_input_stream(root, compression=None) as f:
        raw = f.read()
    n = len(raw) // (4 + 4 * CLASSES)
    return np.frombuffer(raw, np.int32, n), np.frombuffer(raw, np.float32, n * CLASSES, 4 * n).reshape(n, CLASSES)


def _round(shares: DataFrame, weights: np.ndarray, before: str | None, after: str) -> tuple[np.ndarray, np.ndarray, float]:
    """Observed and expected class counts of the dense rows, and the log-likelihood (base 10).

    A share has all histories of its pairs, so it makes the step of their weights itself: it reads them from the folder
    ``before`` (None: all 0) and writes them to ``after``.
    """
    shared = shares.sparkSession.sparkContext.broadcast(weights)

    def run(batches):
        seen, expected, score, some = np.zeros((ROWS, CLASSES)), np.zeros((ROWS, CLASSES)), 0.0, False
        for b in batches:
            for k in range(b.num_rows):
                share, key, n = b.column(0)[k].as_py(), _array(b.column(1)[k], np.int64), _array(b.column(2)[k], np.int64)
                history, at = np.unique(key >> 8, return_inverse=True)  # in order of the keys
                cls, some = key & 255, True
                pairs = np.unique(history & 0xFFFF).astype(np.int32)
                w = Weights(shared.value, pairs, np.zeros((len(pairs), CLASSES), np.float32) if before is None else _read_pairs(f"{before}/{share}")[1])
                pair_seen, pair_expected = np.zeros((len(pairs), CLASSES)), np.zeros((len(pairs), CLASSES))
                for lo in range(0, len(history), 2048):
                    part = history[lo : lo + 2048]
                    a, z = np.searchsorted(at, [lo, lo + len(part)])
                    table = np.zeros((len(part), CLASSES))
                    table[at[a:z] - lo, cls[a:z]] = n[a:z]
                    logs, (f, pair) = log_classes(w, part), features(part)
                    score += float((table * logs).sum())
                    model = np.exp(logs) * table.sum(1, keepdims=True)
                    for feature, x, y in (*((f[:, j], seen, expected) for j in range(f.shape[1])), (np.searchsorted(pairs, pair), pair_seen, pair_expected)):
                        rank = np.argsort(feature, kind="stable")
                        rows, first = np.unique(feature[rank], return_index=True)
                        x[rows] += np.add.reduceat(table[rank], first)
                        y[rows] += np.add.reduceat(model[rank], first)
                store, root = open_store(after)
                store.create_dir(root, recursive=True)
                name = f"{root}/{uuid.uuid4().hex}.part"
                with store.open_output_stream(name, compression=None) as f:
                    f.write(pairs.tobytes())
                    f.write(_step(w.of_pairs, pair_seen, pair_expected).tobytes())
                store.move(name, f"{root}/{share}")
        if some:
            yield pa.RecordBatch.from_arrays([pa.array([x.astype(np.float32).tobytes()], pa.binary()) for x in (seen, expected)] + [pa.array([score])], ["seen", "expected", "score"])

    t = map_arrow(shares, run, "seen binary, expected binary, score double").toArrow()  # SHARES rows at most
    seen, expected = (sum((np.frombuffer(x, np.float32).astype(float) for x in t[c].to_pylist()), np.zeros(ROWS * CLASSES)).reshape(ROWS, CLASSES) for c in ("seen", "expected"))
    return seen, expected, float(t["score"].to_numpy().sum()) / np.log(10)


@dataclass
class Words:
    """Word features: folder and key bits of the pairs' counts, discount of each kind."""

    folder: str
    shift: np.uint64
    discount: dict[str, float]


@dataclass
class Model:
    shape: Shape
    weights: Weights
    class_total: np.ndarray
    n: int
    v: int
    #: Log-likelihood of the classes of all training tokens before each round.
    scores: list[float]
    pairs: Words


def train(chunks: DataFrame, rounds: int = ROUNDS) -> Model | None:
    """Fit all parts; None if there is no training token."""
    spark: SparkSession = chunks.sparkSession
    n_chunks = chunks.count()
    # Words have 62 bits; of 2**21 absent pairs about one meets another one. A part is some chunks' keys.
    word_plan = exchange.Plan(max(4, n_chunks // 4), 62)
    pair_plan = exchange.Plan(max(4, n_chunks // 2), min(62, 41 + math.ceil(math.log2(max(1, n_chunks)))))
    top = _top_words(chunks)
    group = _communities(chunks, top)
    shape, pairs = Shape(top, group, new_path(spark, "entries")), new_path(spark, "pairs")
    columns = ["chunk", "words", "split", "tokens", "train"]
    few = exchange.ask(map_arrow(chunks.select(columns), _pair_questions(pair_plan), exchange.SENT), pair_plan, _own_pairs, np.add, pairs)
    asked = map_arrow(chunks.select(*columns, "counts"), _word_questions(word_plan, pair_plan, pairs, top, group), exchange.SENT)
    total = exchange.ask(asked, word_plan, _own_words(top, word_plan.shift), np.add, shape.folder).get(WORD, np.zeros(CLASSES + 2, np.int64))
    class_total, n, v = np.maximum(1, total[:CLASSES]).astype(float), int(total[CLASSES]), int(total[CLASSES + 1])
    if not n:
        return None
    discount = {kind: min(0.95, max(0.05, x[0] / max(1, x[0] + 2 * x[1]))) for kind, x in few.items()}
    shares = keep(_shares(_statistics(chunks, shape)), "statistics")
    rows, scores, before = np.zeros((ROWS, CLASSES), np.float32), [], None
    for _ in range(rounds):
        after = new_path(spark, "weights")
        seen, expected, score = _round(shares, rows, before, after)
        scores.append(score)
        rows = _step(rows, seen, expected)
        if before is not None:
            delete(spark, before)
        before = after
    discard(shares)
    weights = Weights(rows, np.zeros(0, np.int32), np.zeros((0, CLASSES), np.float16))
    if before is not None:
        store, root = open_store(before)
        found = [_read_pairs(f"{before}/{x.base_name}") for x in store.get_file_info(FileSelector(root)) if not x.base_name.endswith(".part")]
        number = np.concatenate([x for x, _ in found])
        order = np.argsort(number)
        weights = Weights(rows, number[order], np.concatenate([x.astype(np.float16) for _, x in found])[order])
        delete(spark, before)
    return Model(shape, weights, class_total, n, v, scores, Words(pairs, pair_plan.shift, discount))


def _with_words(p: np.ndarray, seen: list, context: list, discount: list) -> np.ndarray:
    """Probabilities of tokens with their word features, from ``p`` without: those of skips first, then of next words.

    ``seen``: counts of each token's pair; ``context``: tokens and distinct followers of its first word, by kind.
    """
    for n, (whole, followers), d in zip(seen, context, discount, strict=True):
        own = np.maximum(n - d, 0.0) / np.maximum(1, whole)
        p = np.where(whole > 0, own + d * followers / np.maximum(1, whole) * p, p)
    return p


def _score(chunks: DataFrame, model: Model) -> DataFrame:
    shared = chunks.sparkSession.sparkContext.broadcast(model)
    names = ["doc_id", "n_tokens", "n_known", "train_tokens", "base_score", "score"]

    def run(batches):
        m = shared.value
        for b in batches:
            for k in range(b.num_rows):
                words, split, token = _array(b.column(1)[k], np.uint64), _array(b.column(2)[k], np.int64), _array(b.column(3)[k], np.uint32)
                chunk = b.column(0)[k].as_py()
                count, of, followers, skip_followers, last = (x.astype(np.int64) for x in _answers(m.shape.folder, chunk, WORD, len(words)))
                cls, _, history = m.shape.histories(count, of, words, split, token)
                base = np.log10((count + 0.1) / (m.n + 0.1 * (m.v + 1)))[token]
                inside = (np.log(np.maximum(count, 1)) - np.log(m.class_total[cls]))[token]
                known, cls, logs = (count > 0)[token], cls[token].astype(np.int64), np.empty(len(token))
                distinct, at = np.unique(history, return_inverse=True)
                order = np.argsort(at, kind="stable")
                ends = np.searchsorted(at[order], np.arange(0, len(distinct) + 2048, 2048))
                for j, lo in enumerate(range(0, len(distinct), 2048)):
                    mine = order[ends[j] : ends[j + 1]]
                    table = log_classes(m.weights, distinct[lo : lo + 2048])
                    unknown = np.log(np.exp(table[:, REST : REST + GROUPS]).sum(1))
                    c, row = cls[mine], at[mine] - lo
                    plain = table[row, c] + np.where(c >= REST, inside[mine], 0.0)
                    logs[mine] = np.where(known[mine], plain, np.where(c >= REST, unknown[row], table[row, c]))
                skips = np.where(words == END_HASH, last, count - last)
                got, seen = exchange.answers(m.pairs.folder, chunk), {}
                one, two = _neighbours(words, split, token)
                for kind, context in ((SKIP, two), (NEXT, one)):
                    _, first, at = exchange.distinct(_keys(words, context, token, m.pairs.shift))
                    if len(got[kind][0]) != len(first):
                        raise ValueError("an answer is not to the question of its chunk")
                    seen[kind] = got[kind][0][at]
                p = _with_words(np.exp(logs), [seen[SKIP], seen[NEXT]], [(skips[two], skip_followers[two]), (count[one], followers[one])], [m.pairs.discount[x] for x in (SKIP, NEXT)])
                ids, nulls = _array(b.column(4)[k], np.int64), _array(b.column(5)[k], bool)
                add = lambda x: np.add.reduceat(x, split[:-1])  # noqa: E731  every text has its end
                arrays = [pa.array(ids, mask=nulls), pa.array(np.diff(split)), pa.array(add(known.astype(np.int64))), pa.array(np.full(len(ids), m.n)), pa.array(add(base)), pa.array(add(np.log10(p)))]
                made = pa.RecordBatch.from_arrays(arrays, names)
                del words, split, token, count, of, followers, skip_followers, last, skips, got, seen, one, two, p, cls, history, base, inside, known, logs, distinct, at, order, ids, nulls, arrays
                release()  # what a chunk took is not needed by the next
                yield made

    rows = chunks.select("chunk", "words", "split", "tokens", "ids", "nulls")
    return map_arrow(rows, run, "doc_id bigint, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double")


def score_language_model(docs: DataFrame, train_on: Column, id_col: str = "doc_id", text_col: str = "text", rounds: int = ROUNDS) -> DataFrame:
    """``doc_id, n_tokens, n_known, train_tokens, base_score, score``, one row per input row.

    The model learns from the rows of ``train_on`` (null: no) and scores all. Tokens are words between ASCII
    white space, A-Z lowered, and one end a text. ``score`` is the model's log10 probability of the text over the training
    vocabulary and one unknown word, ``base_score`` that of add-0.1 unigrams. Null and wordless texts consist of
    their end; null ids stay null; repeated rows count as often as they stand. Without training tokens the
    scores are those of a vocabulary of one unknown word, 0. Other columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("i"), F.col(text_col).cast("string").alias("t"), F.coalesce(train_on, F.lit(False)).alias("train"))
    chunks = keep(_chunks(rows), "chunks", "zstd")
    model = train(chunks, rounds)
    if model is None:
        n = F.size(F.filter(F.split(F.coalesce("t", F.lit("")), "[\\x20\\x09-\\x0D]+"), lambda x: x != "")) + 1
        zero = F.lit(0).cast("bigint")
        return rows.select(F.col("i").alias("doc_id"), n.cast("bigint").alias("n_tokens"), zero.alias("n_known"), zero.alias("train_tokens"), F.lit(0.0).alias("base_score"), F.lit(0.0).alias("score"))
    return _score(chunks, model)
