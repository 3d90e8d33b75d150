"""Benchmark decontamination by a prefix-filtered join of item windows with documents.

A window is a run of ``size`` words of an item (a shorter item is one window). As a window must be contained
whole, its necessary prefix is one token: its rarest word by count over all documents. Documents are
probed only where such a word stands; the position of the word in the window and the length of the
document bound where the window can lie, and the words of the survivors are compared one by one.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from autotheta.llm import textkit
from autotheta.llm.textkit import _ranges
from autotheta.sources.shared import keep, map_arrow

#: Bytes of item texts that are broadcast at once; a larger benchmark is joined in blocks of about this size.
BLOCK_BYTES = 8 << 20
#: Candidates that are compared at once.
CANDIDATES = 1 << 20


@dataclass
class Windows:
    """Distinct windows: words of all, where each begins, its length, its key word's place.

    The items that hold window ``k`` are ``item[item_split[k] : item_split[k + 1]]``, places in ``names``; ``by_key`` has the windows in
    the order of their key words, ``maybe`` one bit for the last 16 of a key word's.
    """

    words: np.ndarray
    begin: np.ndarray
    length: np.ndarray
    place: np.ndarray
    item: np.ndarray
    item_split: np.ndarray
    names: list[str]
    keys: np.ndarray
    by_key: np.ndarray
    key_split: np.ndarray
    maybe: np.ndarray


def _item_words(texts: list[str | None]) -> textkit.Words:
    data, offsets = textkit.text_rows(pa.array(texts, pa.large_string()))
    return textkit.words(data, offsets, textkit.ALNUM_LOWER)


def build_windows(items: list[tuple[str, str]], size: int, count: dict[int, int]) -> Windows:
    """Windows of all items, each once however often items hold it."""
    found = _item_words([t for _, t in items])
    names = sorted({n for n, _ in items})
    number = {n: k for k, n in enumerate(names)}
    n = np.diff(found.split)
    per = np.where(n >= size, n - size + 1, (n > 0).astype(np.int64))
    item = np.repeat(np.array([number[x] for x, _ in items], np.int64), per)
    begin = np.repeat(found.split[:-1], per) + _ranges(np.zeros(len(per), np.int64), per)
    length = np.minimum(size, np.repeat(n, per))
    # Windows by content: sort by length and words, and compare neighbours.
    cells = [np.where(k < length, found.hash[np.minimum(begin + k, len(found) - 1)], textkit.U(0)) for k in range(int(length.max(initial=0)))]
    order = np.lexsort((item, *reversed(cells), length)) if len(begin) else np.zeros(0, np.int64)
    new = np.ones(len(order), bool)
    if len(order):
        new[1:] = length[order][1:] != length[order][:-1]
        for c in cells:
            new[1:] |= c[order][1:] != c[order][:-1]
    held = item[order]
    once = new.copy()
    once[1:] |= held[1:] != held[:-1]
    first = order[new]
    of = (np.cumsum(new) - 1)[once]
    begin, length, item = begin[first], length[first], held[once]
    item_split = np.searchsorted(of, np.arange(len(first) + 1))
    rare = np.array([count.get(int(h), 0) for h in found.hash] if found.hash is not None else [], np.int64)
    place = np.array([int(np.argmin(rare[b : b + k])) for b, k in zip(begin, length, strict=True)], np.int64)
    key = found.hash[begin + place] if len(begin) else np.zeros(0, np.uint64)
    by_key = np.argsort(key, kind="stable")
    keys, first = np.unique(key[by_key], return_index=True)
    maybe = np.zeros(1 << 16, bool)
    maybe[(keys & textkit.U(0xFFFF)).astype(np.int64)] = True
    return Windows(found.hash, begin, length, place, item, item_split, names, keys, by_key, np.append(first, len(by_key)), maybe)


def match(found: textkit.Words, w: Windows) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(row, first word, window)`` of every occurrence of a window inside a row.

    Candidates are made and compared CANDIDATES at a time, so memory does not follow from how often a key word stands
    in a text or how many windows share it. Distinct windows of one length cannot lie at one place, so the
    result has ``size`` rows a word at most.
    """
    none = np.zeros(0, np.int64)
    if not len(w.keys) or not len(found):
        return none, none, none
    at = np.flatnonzero(w.maybe[(found.hash & textkit.U(0xFFFF)).astype(np.int64)])
    k = np.minimum(np.searchsorted(w.keys, found.hash[at]), len(w.keys) - 1)
    hit = w.keys[k] == found.hash[at]
    at, k = at[hit], k[hit]
    many = w.key_split[k + 1] - w.key_split[k]
    ends = np.cumsum(many)
    out, total, lo = [(none, none, none)], int(ends[-1]) if len(ends) else 0, 0
    while lo < total:  # candidates lo to hi of all, in their order
        hi = min(total, lo + CANDIDATES)
        place = np.arange(lo, hi)
        of = np.searchsorted(ends, place, "right")
        window = w.by_key[w.key_split[k[of]] + place - (ends[of] - many[of])]
        word = at[of]
        row = np.searchsorted(found.split, word, "right") - 1
        first = word - w.place[window]
        fits = (first >= found.split[row]) & (first + w.length[window] <= found.split[row + 1])
        row, first, window = row[fits], first[fits], window[fits]
        for i in range(int(w.length.max())):
            inside = np.minimum(i, w.length[window] - 1)
            same = found.hash[first + inside] == w.words[w.begin[window] + inside]
            row, first, window = row[same], first[same], window[same]
        out.append((row, first, window))
        lo = hi
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _probe(docs: DataFrame, windows: Windows) -> DataFrame:
    """``doc_id, digest, n_words, spans, items`` of each row; spans are hit word ranges, joined."""
    shared = docs.sparkSession.sparkContext.broadcast(windows)

    def probe(batches):
        for b in batches:
            for lo, hi, data, offsets in textkit.blocks(b.column(1)):
                found, w = textkit.words(data, offsets, textkit.ALNUM_LOWER), shared.value
                row, first, window = match(found, w)
                spans: list[list[dict]] = [[] for _ in range(hi - lo)]
                items: list[list[str]] = [[] for _ in range(hi - lo)]
                order = np.lexsort((first, row))
                for r, s, e in zip(row[order].tolist(), (first - found.split[row])[order].tolist(), (first - found.split[row] + w.length[window])[order].tolist(), strict=True):
                    if spans[r] and spans[r][-1]["to"] >= s:
                        spans[r][-1]["to"] = max(e, spans[r][-1]["to"])
                    else:
                        spans[r].append({"from": s, "to": e})
                pairs = np.unique(np.stack([row, window]), axis=1)
                held = w.item_split[pairs[1] + 1] - w.item_split[pairs[1]]
                pairs = np.unique(np.stack([np.repeat(pairs[0], held), w.item[_ranges(w.item_split[pairs[1]], held)]]), axis=1)
                for r, i in zip(*pairs.tolist(), strict=True):  # names are in order
                    items[r].append(w.names[i])
                yield pa.RecordBatch.from_arrays(
                    [b.column(0)[lo:hi], b.column(2)[lo:hi], pa.array(np.diff(found.split)), pa.array(spans, pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())]))), pa.array(items, pa.list_(pa.string()))],
                    ["doc_id", "digest", "n_words", "spans", "items"],
                )

    return map_arrow(docs, probe, "doc_id bigint, digest bigint, n_words bigint, spans array<struct<from: bigint, to: bigint>>, items array<string>")


def _word_counts(docs: DataFrame, wanted: np.ndarray) -> dict[int, int]:
    """How often each wanted word stands in the documents; the result is no larger than ``wanted``."""
    shared = docs.sparkSession.sparkContext.broadcast(wanted)

    def count(batches):
        total = np.zeros(len(shared.value) + 1, np.int64)
        maybe = np.zeros(1 << 20, bool)
        maybe[(shared.value & textkit.U(0xFFFFF)).astype(np.int64)] = True
        for b in batches:
            for _, _, data, offsets in textkit.blocks(b.column(1)):
                h = textkit.words(data, offsets, textkit.ALNUM_LOWER).hash
                if h is None:
                    continue
                h = h[maybe[(h & textkit.U(0xFFFFF)).astype(np.int64)]]
                k = np.minimum(np.searchsorted(shared.value, h), len(shared.value) - 1)
                k[shared.value[k] != h] = len(shared.value)
                total += np.bincount(k, minlength=len(total))
        at = np.flatnonzero(total[:-1])
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["at", "n"])

    rows = map_arrow(docs, count, "at bigint, n bigint").groupBy("at").agg(F.sum("n").alias("n")).collect()
    return {int(wanted[r["at"]]): r["n"] for r in rows}


def decontaminate(docs: DataFrame, benchmark: DataFrame, size: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Where documents repeat benchmark items: ``doc_id, n_words, n_hit, spans, items``, one row per input row.

    ``spans`` are ranges of words inside occurring windows, ``n_hit`` their words, ``items`` the ids (as strings,
    sorted, distinct) of items with an occurring window. Words are runs of ASCII letters (A-Z lowered), digits
    and characters beyond ASCII. Null or wordless texts have no hits; items that are null, wordless or
    without an id match nothing; repeated items count once by id; repeated documents each get a row; empty
    tables give no rows or no hits. Other columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("bigint").alias("i"), F.col(text_col).cast("string").alias("t"))
    rows = rows.withColumn("d", F.lit(0).cast("bigint"))
    items = benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(item_text_col).cast("string").alias("text")).where("item IS NOT NULL AND text IS NOT NULL")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(1, -(-total // block_bytes))
    results = []
    if parts > 1:  # blocks of the same document must meet again
        rows = rows.withColumn("d", F.xxhash64(F.coalesce("t", F.lit(""))))
    for k in range(parts):
        block = [(r["item"], r["text"]) for r in items.where(F.pmod(F.xxhash64("item", "text"), F.lit(parts)) == k).collect()]
        vocabulary = np.unique(_item_words([t for _, t in block]).hash) if block else None
        count = _word_counts(rows, vocabulary) if vocabulary is not None and len(vocabulary) else {}
        results.append(_probe(rows, build_windows(block, size, count) if block else build_windows([("", "")], size, {})))
    out = results[0]
    if parts > 1:
        for x in results[1:]:
            out = out.unionByName(x.where("size(spans) > 0"))
        out = keep(out, "hits")
        hit = out.where("size(spans) > 0").groupBy("doc_id", "digest").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_set("spans")))).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
        first = results[0].select(F.col("doc_id").alias("i_"), F.col("digest").alias("d_"), "n_words")
        out = first.join(hit, F.col("i_").eqNullSafe(F.col("doc_id")) & (F.col("d_") == F.col("digest")), "left").select(F.col("i_").alias("doc_id"), "n_words", "spans", F.coalesce("items", F.array().cast("array<string>")).alias("items"))
        joined = F.aggregate(
            F.coalesce("spans", F.array().cast("array<struct<from: bigint, to: bigint>>")), F.array().cast("array<struct<from: bigint, to: bigint>>"),
            lambda a, x: F.when((F.size(a) > 0) & (F.element_at(a, -1)["to"] >= x["from"]), F.concat(F.slice(a, 1, F.greatest(F.size(a) - 1, F.lit(0))), F.array(F.struct(F.element_at(a, -1)["from"].alias("from"), F.greatest(F.element_at(a, -1)["to"], x["to"]).alias("to"))))).otherwise(F.concat(a, F.array(x))),
        )
        out = out.withColumn("spans", joined)
    n_hit = F.aggregate("spans", F.lit(0).cast("bigint"), lambda a, x: a + x["to"] - x["from"])
    return out.select("doc_id", "n_words", n_hit.alias("n_hit"), "spans", "items")


def items_digest(names: list[str]) -> str:
    return hashlib.sha256(",".join(sorted(names)).encode()).hexdigest()
