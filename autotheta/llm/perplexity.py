"""Quality rules by n-gram perplexity: a modified Kneser-Ney model of words a language, and its bands.

The model is of order 2. Every word counts as itself: all bigrams of all texts are counted as hashes in sorted
arrays that are dealt out by range (``exchange``), so no table has a bound and none is in one place; contexts and
continuations follow from the counts of each distinct bigram and are counted by word in the same way. Texts fall into two halves
by their hash and each half is scored by the counts of the other, so that a text (or its exact copies) does not vouch
for itself. Below single words lies a model of symbols, of order 2 too and dense: a language's most frequent words are symbols of
their own, all others the class of their shape (length, capitals, marks, digits), evenly spread over the words of the class.
It has the mass of words that the other half lacks.

A document's log-perplexities, of words and of their symbols, are compared with its language's bands around the
medians. A band's width follows from the spread of single words, divided by the document's length, and the spread
of documents.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from autotheta.llm import exchange, textkit
from autotheta.llm.exchange import distinct
from autotheta.llm.textkit import U
from autotheta.sources.shared import delete, keep, map_arrow, new_path

#: Bytes of text of a chunk: what a task has in memory at once.
CHUNK = 16 << 20
#: Symbols: shapes of words are 0 to 125, then the start and the end of a text, and a language's WORDS most frequent words.
START, END, WORDS, SYMBOLS = 126, 127, 128, 256
_MARKS = np.zeros(256, bool)
_MARKS[[b for b in range(0x21, 0x7F) if not chr(b).isalnum()]] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_SIGNS = np.zeros(256, bool)
_SIGNS[list(b"#*$%&|<>")] = True


def shapes(data: np.ndarray, w: textkit.Words) -> np.ndarray:
    """Class of each word: 7 lengths x 3 kinds of capitals x 3 kinds of marks x 2 of digits."""

    def count(kind: np.ndarray) -> np.ndarray:
        c = np.concatenate([[0], np.cumsum(kind[data], dtype=np.int32)])
        return c[w.end] - c[w.start]

    if not len(w):
        return np.zeros(0, np.int64)
    upper, marks, last = count(_UPPER), count(_MARKS), data[w.end - 1]
    length = np.searchsorted([2, 3, 5, 8, 12, 18], w.end - w.start, "right")
    capital = np.where(upper == 0, 0, np.where((upper == 1) & _UPPER[data[w.start]], 1, 2))
    mark = np.where(marks == 0, 0, np.where((marks == 1) & ((last == 46) | (last == 44)), 1, 2))
    return ((length * 3 + capital) * 3 + mark) * 2 + (count(_DIGIT) > 0)


@dataclass
class Chunk:
    """Words of some texts: each with the word before it and both shapes, ends of texts included.

    ``language`` and ``half`` are by row, ``row`` by word; languages are numbered in the chunk only.
    """

    number: int
    languages: list[str]
    language: np.ndarray
    half: np.ndarray
    row: np.ndarray
    before: np.ndarray
    word: np.ndarray
    shape_before: np.ndarray
    shape: np.ndarray
    rest: list[tuple]

    def by_language(self) -> Iterator[tuple[str, np.ndarray]]:
        """Places of the words of each language."""
        of = self.language[self.row]
        for g, name in enumerate(self.languages):
            at = np.flatnonzero(of == g)
            if len(at):
                yield name, at

    def bigrams(self, at: np.ndarray, shift: np.uint64) -> np.ndarray:
        return textkit.mix(self.before[at] * U(0x9E3779B97F4A7C15) + self.word[at]) >> shift


def _chunk(number: int, held: list[tuple]) -> Chunk:
    """``held``: ids, languages, halves, words, shapes and further values of blocks of rows."""
    names = sorted({x for part in held for x in part[1]})
    place = {x: g for g, x in enumerate(names)}
    language = np.array([place[x] for part in held for x in part[1]], np.int32)
    half = np.concatenate([part[2] for part in held])
    n = np.concatenate([np.diff(part[3].split) for part in held])
    # Words of one spelling in two languages are two words.
    seeds = np.array([int.from_bytes(x.encode()[-8:], "little") for x in names], np.uint64) if names else np.zeros(0, np.uint64)
    seeds = textkit.mix(seeds + np.array([len(x.encode()) for x in names], np.uint64) * U(0xA0761D6478BD642F))
    row = np.repeat(np.arange(len(n), dtype=np.int32), n + 1)
    end = np.cumsum(n + 1) - 1
    inner = np.ones(len(row), bool)
    inner[end] = False
    word = np.full(len(row), END, np.uint64)
    word[inner] = np.concatenate([p[3].hash if p[3].hash is not None else np.zeros(0, np.uint64) for p in held])
    shape = np.full(len(row), END, np.uint8)
    shape[inner] = np.concatenate([p[4] for p in held])
    word = textkit.mix(word + seeds[language[row]])
    before, shape_before = np.empty_like(word), np.empty_like(shape)
    before[1:], shape_before[1:] = word[:-1], shape[:-1]
    start = end - n
    before[start], shape_before[start] = textkit.mix(U(START) + seeds[language]), START
    return Chunk(number, names, language, half, row, before, word, shape_before, shape, [(p[0], p[3].split, *p[5:]) for p in held])


def chunks(batches, more=None) -> Iterator[Chunk]:
    """The texts of ``i, language, text, t`` batches in chunks of CHUNK bytes; ``more`` adds values by block."""
    held, size, ordinal = [], 0, 0
    for b in batches:
        names, half = b.column(1).to_pylist(), b.column(3).to_numpy() & 1
        for lo, hi, data, offsets in textkit.blocks(b.column(2)):
            if held and size + len(data) > CHUNK:
                c = _chunk(exchange.chunk_id(ordinal), held)
                held, size, ordinal = [], 0, ordinal + 1
                yield c
                del c
            w = textkit.words(data, offsets, textkit.SPACED)
            w_shapes = shapes(data, w).astype(np.uint8)
            extra = more(data, offsets, w) if more else ()
            w.start = w.end = None
            held.append((b.column(0)[lo:hi], names[lo:hi], half[lo:hi], w, w_shapes, *extra))
            size += len(data)
    if held:
        c = _chunk(exchange.chunk_id(ordinal), held)
        del held
        yield c


def discounts(n1: float, n2: float, n3: float, n4: float) -> tuple[float, float, float]:
    """The three discounts of modified Kneser-Ney from counts of counts; 0.5, 1, 1.5 where these have gaps."""
    if min(n1, n2, n3) <= 0:
        return 0.5, 1.0, 1.5
    y = n1 / (n1 + 2 * n2)
    d = 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3
    return tuple(min(max(x, 0.05), k + 0.95) for k, x in enumerate(d))


def _interpolated(count: np.ndarray, lower: np.ndarray) -> np.ndarray:
    """Discounted rows of ``count`` (contexts x symbols) with the rest of each row's mass on ``lower``."""
    d = np.array([0.0, *discounts(*(float((count == k).sum()) for k in (1, 2, 3, 4)))])
    cut = d[np.minimum(count, 3).astype(np.int64)]
    total = count.sum(-1, keepdims=True)
    rest = np.where(total > 0, cut.sum(-1, keepdims=True) / np.maximum(total, 1), 1.0)
    return np.where(total > 0, (count - cut) / np.maximum(total, 1), 0.0) + rest * lower


@dataclass
class Model:
    """What is known of a language beside its words: discounts and totals by half, and log10 probabilities of symbols.

    ``d2`` and ``d1``: discounts of bigrams and of words, ``rest1`` the share of words' mass that goes to symbols, ``m`` the number
    of distinct bigrams, ``types`` the distinct words of a symbol, ``top`` the keys of the most frequent words.
    """

    plan: exchange.Plan
    d2: dict[str, np.ndarray]
    d1: dict[str, np.ndarray]
    m: dict[str, np.ndarray]
    rest1: dict[str, np.ndarray]
    types: dict[str, np.ndarray]
    top: dict[str, np.ndarray]
    logs: dict[str, np.ndarray]
    bigram_files: str
    word_files: str


def symbol_model(count: np.ndarray) -> np.ndarray:
    """Probabilities of a symbol after another one, from their counts: modified Kneser-Ney, dense."""
    one = _interpolated((count > 0).sum(0)[None, :].astype(float), np.full((1, SYMBOLS), 1 / SYMBOLS))
    return _interpolated(count, one)


def _bigram_questions(plan: exchange.Plan):
    """Distinct bigrams of each chunk with their counts: all, and those of the second half."""

    def run(batches):
        for c in chunks(batches):
            for name, at in c.by_language():
                keys = c.bigrams(at, plan.shift)
                order, first, _ = distinct(keys)
                n, b = _own_counts(c, at[order], first)
                yield from exchange.question(c.number, name, keys[order[first]], [n, b], plan)

    return run


def _own_counts(c: Chunk, ordered: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Occurrences in the chunk, all and those of the second half."""
    n = np.diff(np.append(first, len(ordered)))
    return n.astype(np.uint32), np.add.reduceat(c.half[c.row[ordered]], first).astype(np.uint32)


def symbols(top: np.ndarray, words: np.ndarray, shape: np.ndarray, shift: np.uint64) -> np.ndarray:
    """Symbol of each word; ``top`` are the keys of the most frequent words in order of their keys."""
    if not len(top):
        return shape
    key = words >> shift
    k = np.minimum(np.searchsorted(top, key), len(top) - 1)
    return np.where(top[k] == key, END + 1 + k, shape).astype(np.uint8)


def _symbol_counts(top: dict[str, np.ndarray], shift: np.uint64):
    """``language, k, n``: pairs of symbols."""

    def run(batches):
        for c in chunks(batches):
            for name, at in c.by_language():
                one, two = (symbols(top[name], w[at], x[at], shift).astype(np.int64) for w, x in ((c.before, c.shape_before), (c.word, c.shape)))
                n = np.bincount(one * SYMBOLS + two, minlength=SYMBOLS * SYMBOLS)
                k = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(k), pa.string()), pa.array(k), pa.array(n[k])], ["language", "k", "n"])

    return run


def _own_bigrams(kind, keys, counts, first, at):
    """Counts of both halves in the other chunks and who is first to hold a bigram; how many bigrams occur 1 to 4 times.

    A chunk that is not the first needs a half's count only where the bigram stands in its texts of the other half.
    """
    n, b = (c.astype(np.int64) for c in counts)
    totals = [np.add.reduceat(x, first) for x in (n - b, b)]
    new = np.zeros(len(at), np.uint8)
    new[first] = 1
    few = np.array([[int((t == k).sum()) for k in (1, 2, 3, 4)] for t in totals])
    others = (np.where((other > 0) | (new > 0), t[at] - x, 0) for t, x, other in zip(totals, (n - b, b), (b, n - b), strict=True))
    return [*(x.astype(np.uint32) for x in others), new], few


@dataclass
class Known:
    """Distinct bigrams of one language in a chunk and their words, with all that the owners of bigrams said.

    ``entry`` is the number of each word's bigram, ``one`` a place of each bigram; ``v`` and ``w`` number its words, ``words`` has
    their keys. ``own`` are counts of words in this chunk: as context by half, followers that occur 1, 2 and more times by half,
    forerunners by half; a bigram's kind counts where it was met first.
    """

    entry: np.ndarray
    one: np.ndarray
    total: list[np.ndarray]
    v: np.ndarray
    w: np.ndarray
    words: np.ndarray
    own: list[np.ndarray]


def _known(c: Chunk, at: np.ndarray, got: list[np.ndarray], shift: np.uint64) -> Known:
    order, first, entry = distinct(c.bigrams(at, shift))
    if len(got[0]) != len(first):
        raise ValueError("the texts were cut into other chunks than before")
    n, b = _own_counts(c, at[order], first)
    one = at[order[first]]
    del order, first
    own = [n - b, b]
    total = [x + y for x, y in zip(got, own)]
    new = got[2].astype(bool)
    keys = np.concatenate([c.before[one] >> shift, c.word[one] >> shift])
    order, begin, where = distinct(keys)
    v, w, m = where[: len(one)], where[len(one) :], len(begin)
    kinds = [(t == k if k < 3 else t > 2) & new for t in total for k in (1, 2, 3)]
    sums = [*(np.bincount(v, x, m) for x in own), *(np.bincount(v[x], minlength=m) for x in kinds), *(np.bincount(w[(t > 0) & new], minlength=m) for t in total)]
    return Known(entry, one, total, v, w, keys[order[begin]], [x.astype(np.uint32) for x in sums])


#: Places in ``Known.own``.
_CONTEXT, _KINDS, _FORERUNNERS = slice(0, 2), slice(2, 8), slice(8, 10)


def _word_questions(plan: exchange.Plan, folder: str):
    """Counts of each chunk's words, and their shapes (START for words that only begin a bigram)."""

    def run(batches):
        for c in chunks(batches):
            got = exchange.answers(folder, c.number)
            for name, at in c.by_language():
                k = _known(c, at, got.pop(name), plan.shift)
                shape = np.full(len(k.words), START, np.uint8)
                shape[k.w] = c.shape[k.one]
                yield from exchange.question(c.number, name, k.words, [*k.own, shape], plan)

    return run


#: Steps of a share as it is sent.
SHARE = 65535


def _own_words(d2: dict[str, np.ndarray]):
    """Answers by word: occurrences as context and forerunners in the other chunks, and the share that goes to the
    lower order, by half, where the word stands in the chunk's texts of the other half. (Each word but the end is a context.)"""

    def answer(kind, keys, counts, first, at):
        totals = [np.add.reduceat(c.astype(np.int64), first) for c in counts[:10]]
        shape = np.minimum.reduceat(counts[10], first)
        whole, kinds, m = totals[_CONTEXT], totals[_KINDS], totals[_FORERUNNERS]
        out, sums = [], []
        for h in (0, 1):
            cut = sum(d2[kind][h][k] * kinds[3 * h + k].astype(float) for k in range(3))
            out.append(np.round(SHARE * np.minimum(1.0, cut / np.maximum(1, whole[h]))).astype(np.uint16)[at])
            few = np.array([int((m[h] == k).sum()) for k in (1, 2, 3, 4)])
            sums.append((few, int((m[h] > 2).sum()), int(m[h].sum()), np.bincount(shape[m[h] > 0], minlength=SYMBOLS)))
        # The most frequent words of the part; those of the language are among them. Starts and ends are no words.
        n = np.where(shape < START, whole[0] + whole[1], 0)
        often = np.lexsort((keys, -n))[:WORDS]
        top = [(int(n[k]), int(keys[k]), int(shape[k]), bool(m[0][k] > 0), bool(m[1][k] > 0)) for k in often if n[k]]
        needed = [(counts[1 - h] > 0) | (counts[10] == END) for h in (0, 1)] * 3
        others = [(t[at] - own).astype(np.uint32) for t, own in zip((*whole, *m), (*counts[_CONTEXT], *counts[_FORERUNNERS]), strict=True)]
        return [np.where(k, x, 0).astype(x.dtype) for k, x in zip(needed, (*others, *out), strict=True)], (sums, top)

    return answer


def _merge_words(x: tuple, y: tuple) -> tuple:
    sums = [tuple(a + b for a, b in zip(x[0][h], y[0][h], strict=True)) for h in (0, 1)]
    return sums, sorted([*x[1], *y[1]], key=lambda t: (-t[0], t[1]))[:WORDS]


def train(rows: DataFrame) -> Model:
    """The model of ``i, language, text, t`` rows; to be scored from the same rows with the same splits."""
    plan, spark = exchange.plan(rows), rows.sparkSession
    bigram_files, word_files = new_path(spark, "bigrams"), new_path(spark, "words")
    few = exchange.ask(map_arrow(rows, _bigram_questions(plan), exchange.SENT), plan, _own_bigrams, np.add, bigram_files)
    d2 = {name: np.array([discounts(*x[h].tolist()) for h in (0, 1)]) for name, x in few.items()}
    asked = exchange.ask(map_arrow(rows, _word_questions(plan, bigram_files), exchange.SENT), plan, _own_words(d2), _merge_words, word_files)
    found, often = {name: x[0] for name, x in asked.items()}, {name: x[1] for name, x in asked.items()}
    d1 = {name: np.array([discounts(*x[h][0].tolist()) for h in (0, 1)]) for name, x in found.items()}
    m = {name: np.array([int(x[h][2]) for h in (0, 1)]) for name, x in found.items()}
    rest1 = {name: np.array([(d1[name][h] @ [x[h][0][0], x[h][0][1], x[h][1]]) / m[name][h] if m[name][h] else 1.0 for h in (0, 1)]) for name, x in found.items()}
    types, top = {}, {}
    for name, x in found.items():
        # A shape's mass is shared by its words, but for the most frequent ones, and one more that was never seen.
        types[name] = np.array([np.where(np.arange(SYMBOLS) < START, x[h][3] + 1, 1) for h in (0, 1)])
        for _, _, shape, *known in often[name]:
            types[name][[h for h in (0, 1) if known[h]], shape] -= 1
        top[name] = np.sort(np.array([k for _, k, *_ in often[name]], np.uint64))
    counted = map_arrow(rows, _symbol_counts(top, plan.shift), "language string, k bigint, n bigint").groupBy("language", "k").agg(F.sum("n").alias("n"))
    tables = {name: np.zeros(SYMBOLS * SYMBOLS) for name in few}
    t = counted.toArrow()  # languages x SYMBOLS x SYMBOLS rows at most
    for name, table in tables.items():
        mine = t.filter(pc.equal(t["language"], name))
        table[mine["k"].to_numpy()] = mine["n"].to_numpy()
    logs = {name: np.log10(symbol_model(t.reshape(SYMBOLS, SYMBOLS))).astype(np.float32) for name, t in tables.items()}
    return Model(plan, d2, d1, m, rest1, types, top, logs, bigram_files, word_files)


def probabilities(c: Chunk, model: Model) -> tuple[np.ndarray, np.ndarray]:
    """log10 probability of each word of a chunk by the counts of the other half, and of its symbol."""
    bigrams, words = exchange.answers(model.bigram_files, c.number), exchange.answers(model.word_files, c.number)
    p, s = np.zeros(len(c.word), np.float32), np.zeros(len(c.word), np.float32)
    for name, at in c.by_language():
        k = _known(c, at, bigrams.pop(name), model.plan.shift)
        got = words.pop(name)
        if len(got[0]) != len(k.words):
            raise ValueError("the texts were cut into other chunks than before")
        symbol_before, symbol = (symbols(model.top[name], x[k.one], y[k.one], model.plan.shift) for x, y in ((c.before, c.shape_before), (c.word, c.shape)))
        by_symbol = model.logs[name][symbol_before, symbol]
        s[at] = by_symbol[k.entry]
        base, by_half = 10.0**by_symbol, []
        for h in (0, 1):
            n, whole, m = k.total[h], (got[h] + k.own[_CONTEXT][h])[k.v], (got[2 + h] + k.own[_FORERUNNERS][h])[k.w]
            own2 = np.where(n > 0, (n - np.array([0.0, *model.d2[name][h]])[np.minimum(n, 3)]) / np.maximum(1, whole), 0.0)
            own1 = (m - np.array([0.0, *model.d1[name][h]])[np.minimum(m, 3)]) / max(1, model.m[name][h])
            low = own1 + model.rest1[name][h] * base / model.types[name][h][symbol]
            by_half.append(np.log10(own2 + np.where(whole > 0, got[4 + h][k.v] / SHARE, 1.0) * low).astype(np.float32))
        p[at] = np.where(c.half[c.row[at]] == 0, by_half[1][k.entry], by_half[0][k.entry])
    return p, s


def _counts(data, offsets, w):
    """Base counts of a block's rows: characters in words, signs, repeated lines, words in repeated windows."""

    def by_row(kind: np.ndarray) -> np.ndarray:
        c = np.concatenate([[0], np.cumsum(kind, dtype=np.int64)])
        return c[offsets[1:]] - c[offsets[:-1]]

    letters = by_row((data & 0xC0) != 0x80) - by_row(~textkit.SPACED.inside[data])
    raw = data.tobytes()
    lines = [duplicate_lines(raw[x:y]) for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
    hashes = w.hash if w.hash is not None else np.zeros(0, np.uint64)
    return letters, by_row(_SIGNS[data]), np.array(lines, np.int64), repeated_words(hashes, w.split)


def measures(rows: DataFrame, model: Model) -> DataFrame:
    """Base counts and mean and variance of the log10 probabilities of words and symbols of every row: one scan."""
    shared = rows.sparkSession.sparkContext.broadcast(model)
    names = ["doc_id", "language", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "log_perplexity", "log_square", "shape_log_perplexity", "shape_log_square"]

    def run(batches):
        for c in chunks(batches, _counts):
            n = len(c.language)
            size = np.bincount(c.row, minlength=n)
            means = []
            for x in probabilities(c, shared.value):
                mean = np.bincount(c.row, -x, n) / size
                means += [mean, np.maximum(0.0, np.bincount(c.row, x.astype(float) ** 2, n) / size - mean**2)]
            at = 0
            for ids, split, *counts in c.rest:
                to = at + len(ids)
                language = pa.array([c.languages[g] for g in c.language[at:to]], pa.string())
                yield pa.RecordBatch.from_arrays([ids, language, pa.array(np.diff(split)), *map(pa.array, counts), *(pa.array(x[at:to]) for x in means)], names)
                at = to

    return map_arrow(rows, run, "doc_id bigint, language string, " + ", ".join(f"{x} bigint" for x in names[2:7]) + ", " + ", ".join(f"{x} double" for x in names[7:]))


def repeated_words(hashes: np.ndarray, split: np.ndarray, size: int = 8) -> np.ndarray:
    """By row, words inside windows of ``size`` words that occur twice or more in the row."""
    n, count = len(hashes), np.diff(split)
    out = np.zeros(len(count), np.int64)
    if n < size:
        return out
    row = np.repeat(np.arange(len(count)), count)
    h = np.zeros(n - size + 1, np.uint64)
    for k in range(size):
        h = textkit.mix(h * textkit.U(0x9E3779B97F4A7C15) + hashes[k : n - size + 1 + k])
    whole = row[: n - size + 1] == row[size - 1 :]
    at = np.flatnonzero(whole)
    key = textkit.mix(h[at] + row[at].astype(np.uint64) * textkit.U(0xE7037ED1A0B428DB))
    ordered = np.sort(key)
    twice = np.unique(ordered[1:][ordered[1:] == ordered[:-1]])
    if not len(twice):
        return out
    k = np.minimum(np.searchsorted(twice, key), len(twice) - 1)
    at = at[twice[k] == key]
    cover = np.zeros(n + 1, np.int64)
    np.add.at(cover, at, 1)
    np.add.at(cover, at + size, -1)
    inside = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
    return inside[split[1:]] - inside[split[:-1]]


def duplicate_lines(text: bytes) -> int:
    """Lines with a word that equal an earlier line."""
    lines = text.split(b"\n")
    if len(lines) < 2:
        return 0
    seen, n = set(), 0
    for x in lines:
        if x in seen:
            n += bool(x.split())
        else:
            seen.add(x)
    return n


def perplexity_filter(docs: DataFrame, z: float = 6.0, z_symbols: float = 4.5, min_words: int = 20, repeat_percent: int = 30, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Counts, perplexity, band and verdict of every document; one row per input row.

    Returns ``doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, log_perplexity,
    lower, upper, shape_log_perplexity, shape_lower, shape_upper, kept``. A document is kept if it has ``min_words``
    words, at most ``repeat_percent`` % of them in repeated 8-word windows, a log10 perplexity of its words that is not
    above its language's band, and one of their symbols inside the band of these. Below the words' band lies what
    other texts nearly repeat, which is no fault of the text. Every language has a model of its own, null too.
    Null and wordless texts fail the base. Bands leave out documents that fail the
    base; a language without others has no band and rejects none. Repeated rows count as often as they
    stand. Empty tables give no rows. Other columns are ignored.
    """
    text, lang = F.col(text_col).cast("string"), F.col(lang_col).cast("string")
    rows = docs.select(F.col(id_col).cast("bigint").alias("i"), F.coalesce(F.concat(F.lit("="), lang), F.lit("")).alias("language"), text.alias("text"), F.xxhash64(lang, text).alias("t"))
    rows = exchange.stable(rows)
    with exchange.same_splits(docs.sparkSession):
        model = train(rows)
        m = keep(measures(rows, model), "measures")
    for path in (model.bigram_files, model.word_files):
        delete(docs.sparkSession, path)
    m = m.withColumn("base_failed", (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > repeat_percent * F.col("n_words")))
    good = m.where("NOT base_failed")
    # Perplexities of words and of symbols have a band each.
    for of, wide in (("", z), ("shape_", z_symbols)):
        value, square = f"{of}log_perplexity", f"{of}log_square"
        middle = good.groupBy("language").agg(F.percentile_approx(value, 0.5, 10000).alias("mid"), F.percentile_approx(square, 0.5, 10000).alias("per_word"))
        off = good.join(F.broadcast(middle), "language").withColumn("off", F.abs(F.col(value) - F.col("mid")))
        # Spread of documents: the median distance of those long enough that single words hardly add to it.
        spread = off.groupBy("language").agg(F.percentile_approx(F.when(F.col("n_words") >= 300, F.col("off")), 0.5, 10000).alias("off"))
        band = middle.join(spread, "language").select(F.col("language").alias("g"), "mid", "per_word", (1.4826 * F.coalesce("off", F.lit(0.05))).alias("tau"))
        width = F.lit(wide) * F.sqrt(F.col("per_word") / (F.col("n_words") + 1) + F.col("tau") * F.col("tau"))
        m = m.join(F.broadcast(band), F.col("language") == F.col("g"), "left").withColumns({f"{of}lower": F.col("mid") - width, f"{of}upper": F.col("mid") + width}).drop("g", "mid", "per_word", "tau")
    inside = F.coalesce(F.col("log_perplexity") <= F.col("upper"), F.lit(True)) & F.coalesce(F.col("shape_log_perplexity").between(F.col("shape_lower"), F.col("shape_upper")), F.lit(True))
    return m.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "log_perplexity", "lower", "upper", "shape_log_perplexity", "shape_lower", "shape_upper", (~F.col("base_failed") & inside).alias("kept"))
