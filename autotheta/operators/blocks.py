"""Set joins by blocks of sets, for tables whose meetings are too many to be shuffled.

Sets are hashed, equal ones of a side become one class, and classes are written to the shared folder in blocks of
similar sizes, each set with its rare elements first. A task holds a block of one side and reads those blocks of the
other whose sizes allow the threshold. Meetings of the prefixes are counted in arrays, and what both prefixes and the rests
behind them leave open is compared in full, so only joined pairs leave a task. At low thresholds whole sets meet:
frequent elements as a product of matrices, the others by postings. ``level_parts`` sums pairs up by their keys inside the
tasks, so that not even joined pairs leave one.

Elements are 64-bit hashes; the order is by counts of hash buckets, which changes the work but no result.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from autotheta.functions.sims import SetSimilarity
from autotheta.functions.text import TOKENIZERS
from autotheta.operators.graph import forest_of
from autotheta.operators.sets import require_columns, sizes_of
from autotheta.sources.shared import discard, keep, map_arrow, new_path, open_store, shuffles_deleted

#: Elements and sets of a block, buckets of counts, cells and meetings that are counted at once, blocks of a work item.
BLOCK, SETS, BUCKETS, CELLS, MEETS, ITEM = 1 << 20, 1 << 14, 1 << 18, 1 << 22, 1 << 22, 8
#: Work items from which on they hold more blocks than one.
SPREAD = 256
_SHIFT = np.uint64(64 - 18)
#: Below this key whole sets meet, and nothing is left to compare: the prefixes are most of the sets then, and matrices are faster.
WHOLE = 0.6
#: Elements that one in so many sets of a block holds, and SCARCE at least, are columns of a matrix of so many cells at most.
DENSE, SCARCE, MATRIX = 24, 4, 1 << 24
#: Rows of levels, pairs and edges that are held before they are summed up.
HELD = 1 << 20


def _mix(x: np.ndarray) -> np.ndarray:
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def _binary(data: np.ndarray, split: np.ndarray) -> pa.Array:
    """Rows of bytes from one array of values."""
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(split) - 1, [None, pa.py_buffer((split * data.itemsize).astype(np.int64)), pa.py_buffer(np.ascontiguousarray(data))])


def _values(column: pa.Array, kind: type = np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """All values of rows of bytes, and where each row begins."""
    column = column.cast(pa.large_binary())
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    values = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]].view(kind) if data is not None else np.zeros(0, kind)
    return values, (offsets - offsets[0]) // np.dtype(kind).itemsize


def hash_sets(values: np.ndarray, lengths: np.ndarray, bag: bool) -> tuple[np.ndarray, np.ndarray]:
    """Distinct elements of each row, ascending; a bag's further occurrences are elements of their own."""
    row = np.repeat(np.arange(len(lengths)), lengths)
    order = np.lexsort((values, row))
    v, row = values[order], row[order]
    first = np.ones(len(v), bool)
    first[1:] = (v[1:] != v[:-1]) | (row[1:] != row[:-1])
    if bag:
        at = np.arange(len(v))
        occ = (at - np.maximum.accumulate(np.where(first, at, 0))).astype(np.uint64)
        v = np.where(occ > 0, _mix(v + occ * np.uint64(0x9E3779B97F4A7C15)), v)
        v = v[np.lexsort((v, row))]
    else:
        v, row = v[first], row[first]
    return v, np.searchsorted(row, np.arange(len(lengths) + 1))


def _hashed(objects: DataFrame, tokens: Column, bag: bool) -> DataFrame:
    """``n, d, toks, ids``: the sets of a batch, equal ones once, with a digest to sort by; without those that are empty."""

    def run(batches):
        for b in batches:
            lists = b.column(1)
            values = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
            lengths = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
            v, split = hash_sets(values, lengths, bag)
            total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(v, dtype=np.uint64)])
            digest = (total[split[1:]] - total[split[:-1]]).view(np.int64)
            of: dict[bytes, list[int]] = {}
            first: dict[bytes, int] = {}
            ids = b.column(0).to_pylist()
            for k in np.flatnonzero(np.diff(split)):
                key = v[split[k] : split[k + 1]].tobytes()
                of.setdefault(key, []).append(ids[k])
                first.setdefault(key, k)
            at = np.array(list(first.values()), np.int64)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.diff(split)[at].astype(np.int64)), pa.array(digest[at]), pa.array(list(of), pa.binary()), pa.array([np.array(x, np.int64).tobytes() for x in of.values()], pa.binary())],
                ["n", "d", "toks", "ids"],
            )

    rows = objects.select("id", F.transform(tokens, lambda t: F.xxhash64(t)).alias("h"))
    return map_arrow(rows, run, "n bigint, d bigint, toks binary, ids binary")


def _frequencies(*sides: DataFrame) -> np.ndarray:
    """In how many sets the elements of each bucket are."""

    def run(batches):
        n = np.zeros(BUCKETS, np.int64)
        for b in batches:
            n += np.bincount((_values(b.column(0))[0] >> _SHIFT).astype(np.int64), minlength=BUCKETS)
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(n[at])], ["b", "n"])

    rows = map_arrow(sides[0].select("toks"), run, "b bigint, n bigint")
    for x in sides[1:]:
        rows = rows.unionByName(map_arrow(x.select("toks"), run, "b bigint, n bigint"))
    found = rows.groupBy("b").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(BUCKETS, np.int64)
    out[found["b"].to_numpy()] = found["n"].to_numpy()
    return out


@dataclass
class Files:
    """The blocks of a side: ``path, low, high`` (sizes of its sets)."""

    blocks: list[tuple[str, int, int]]


def _write(sets: DataFrame, frequencies, block: int) -> Files:
    folder = new_path(sets.sparkSession, "blocks")

    def run(batches):
        store, root = open_store(folder)
        toks, members, held = [], [], 0

        def flush():
            n = np.array([len(x) // 8 for x in toks])
            split = np.concatenate([[0], np.cumsum(n)])
            v = np.frombuffer(b"".join(toks), np.uint64)
            ids = [np.frombuffer(b"".join(x), np.int64) for x in members]
            at = np.concatenate([[0], np.cumsum([len(x) for x in ids])])
            # Elements are numbered here once, so that no task that reads the block has to sort them; the first row has them all.
            distinct, number = np.unique(v, return_inverse=True)
            by = np.lexsort((distinct, frequencies.value[(distinct >> _SHIFT).astype(np.int64)]))
            place = np.empty(len(by), np.int64)
            place[by] = np.arange(len(by))
            number = by[np.sort(np.repeat(np.arange(len(n)), n) * len(by) + place[number]) % len(by)]
            names = _binary(distinct, np.concatenate([[0], np.full(len(n), len(distinct))]))
            out = pa.RecordBatch.from_arrays([pa.array([int(x.min()) for x in ids], pa.int64()), _binary(number.astype(np.int32), split), names, _binary(np.concatenate(ids), at)], ["rep", "numbers", "distinct", "ids"])
            store.create_dir(root, recursive=True)
            name = f"{root}/{uuid.uuid4().hex}.arrow"
            with store.open_output_stream(name) as f, pa.ipc.new_stream(f, out.schema) as w:
                w.write_batch(out)
            return pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name.rpartition('/')[2]}"]), pa.array([int(n.min())]), pa.array([int(n.max())])], ["path", "low", "high"])

        last, of = None, {}
        for b in batches:
            for n, d, t, i in zip(*(b.column(k).to_pylist() for k in range(4)), strict=True):
                if (n, d) != last:
                    if held >= block or len(toks) >= SETS:
                        yield flush()
                        toks, members, held = [], [], 0
                    last, of = (n, d), {}
                if t not in of:
                    of[t] = len(toks)
                    toks.append(t)
                    members.append([])
                    held += n
                members[of[t]].append(i)
        if toks:
            yield flush()

    # Rows of equal sets have equal sizes and digests, so they are in one task, side by side.
    with shuffles_deleted(sets.sparkSession):
        rows = map_arrow(sets.repartitionByRange("n", "d").sortWithinPartitions("n", "d"), run, "path string, low bigint, high bigint").collect()
    return Files(sorted((tuple(r) for r in rows), key=lambda x: x[1:]))


@dataclass
class Blocks:
    """Both sides in blocks (the same for a join with itself), the counts that order elements, and the counts of objects."""

    r: Files
    s: Files
    frequencies: object
    size_r: int
    size_s: int

    @property
    def alone(self) -> bool:
        return self.r is self.s


def write_blocks(r: DataFrame, s: DataFrame | None = None, tokens: str = "words", bag: bool = False, block: int = BLOCK) -> Blocks:
    """Blocks of ``id, text`` of both sides, or of one that is joined with itself. Ids that are null or stand twice are an error."""
    both = [x for x in (r, s) if x is not None]
    for x in both:
        require_columns(x, "id", "text")
    n = sizes_of(r, s if s is not None else r.limit(0))
    sets = [keep(_hashed(x, TOKENIZERS[tokens](F.col("text")), bag), "hashed") for x in both]
    shared = r.sparkSession.sparkContext.broadcast(_frequencies(*sets))
    files = []
    for x in sets:
        files.append(_write(x, shared, block))
        discard(x)
    return Blocks(files[0], files[-1], shared, *n)


class Block:
    """A block in memory."""

    def __init__(self, path: str):
        store, root = open_store(path)
        with store.open_input_stream(root) as f:
            batch = pa.ipc.open_stream(f).read_next_batch()
        self.rep = batch.column(0).to_numpy()
        self.number, self.split = _values(batch.column(1), np.int32)
        self.distinct = _values(batch.column(2))[0]
        self.ids, self.members = _values(batch.column(3), np.int64)
        self.n, self.w = np.diff(self.split), np.diff(self.members)

    def prefix(self, sim: SetSimilarity, low: float, side: str, bounds: str = "tight") -> np.ndarray:
        """Places of each set of which one at least is shared with any partner of key ``low``."""
        need = np.ceil(self.n * sim.least_share(low, side, bounds) - 1e-9 * self.n).astype(np.int64)
        return self.n - np.clip(need, 1, self.n) + 1

    def places(self, rows: np.ndarray, length: np.ndarray) -> np.ndarray:
        """Where the first elements of rows stand."""
        return np.arange(length.sum()) + np.repeat(self.split[rows] - np.concatenate([[0], np.cumsum(length)[:-1]]), length)

    @cached_property
    def toks(self) -> np.ndarray:
        return self.distinct[self.number]

    @cached_property
    def keyed(self) -> np.ndarray:
        """Row and number of each element as one number, ascending."""
        return np.sort(np.repeat(np.arange(len(self.n)), self.n) * len(self.distinct) + self.number)

    def find(self, other: Block) -> tuple[np.ndarray, np.ndarray]:
        """The numbers that the other block's distinct elements have here, and whether they are here at all."""
        at = np.minimum(np.searchsorted(self.distinct, other.distinct), len(self.distinct) - 1)
        return at, self.distinct[at] == other.distinct

    def overlaps(self, rows: np.ndarray, other: Block, others: np.ndarray) -> np.ndarray:
        """Shared elements of pairs of rows."""
        out = np.zeros(len(rows), np.int64)
        if not len(rows):
            return out
        numbers, known = (x[other.number] for x in self.find(other))
        ends = np.cumsum(other.n[others])
        lo = 0
        while lo < len(rows):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + MEETS, "right")))
            length = other.n[others[lo:hi]]
            at = other.places(others[lo:hi], length)
            pair = np.repeat(np.arange(hi - lo), length)[known[at]]
            at = at[known[at]]
            want = rows[lo:hi][pair] * len(self.distinct) + numbers[at]
            k = np.minimum(np.searchsorted(self.keyed, want), len(self.keyed) - 1)
            out[lo:hi] = np.bincount(pair[self.keyed[k] == want], minlength=hi - lo)
            lo = hi
        return out


class Postings:
    """The prefixes of a block by element; rows of an element ascend, and so do their sizes."""

    def __init__(self, block: Block, length: np.ndarray):
        row = np.repeat(np.arange(len(length)), length)
        t = block.toks[block.places(np.arange(len(length)), length)]
        order = np.argsort(t, kind="stable")
        self.distinct, number = np.unique(t[order], return_inverse=True)
        self.row = row[order]
        self.at = number * len(length) + self.row


def _allowed(r: Block, s: Block, sim: SetSimilarity, low: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """First and last but one row of r for each of s whose sizes allow the key; they ascend by size, and the greatest key rises
    to the equal size and falls after it."""
    sizes = np.unique(s.n)
    allowed = [np.flatnonzero(sim.key(np.minimum(r.n, x), r.n, np.full(len(r.n), x)) >= low) for x in sizes]
    of = np.searchsorted(sizes, s.n)
    least, most = (np.array([f(x) for x in allowed], np.int64)[of] for f in (lambda x: x[0] if len(x) else 0, lambda x: x[-1] + 1 if len(x) else 0))
    return least, np.minimum(most, np.arange(len(s.n))) if same else most


class Dense:
    """A whole block by element: a matrix of its frequent elements, and postings of all others."""

    def __init__(self, block: Block):
        count = np.bincount(block.number, minlength=len(block.distinct))
        often = np.flatnonzero(count >= max(SCARCE, len(block.n) / DENSE))
        most = max(1, MATRIX // len(block.n))
        if len(often) > most:
            often = often[np.argsort(-count[often], kind="stable")[:most]]
        self.column = np.full(len(block.distinct), -1, np.int32)
        self.column[often] = np.arange(len(often))
        row, c = np.repeat(np.arange(len(block.n), dtype=np.int32), block.n), self.column[block.number]
        self.matrix = np.zeros((len(block.n), len(often)), np.float32)
        self.matrix[row[c >= 0], c[c >= 0]] = 1
        self.row = row[c < 0][np.argsort(block.number[c < 0], kind="stable")]
        count[often] = 0
        self.count, self.begin = count, np.cumsum(count) - count


def meet_whole(r: Block, d: Dense, s: Block, sim: SetSimilarity, low: float, same: bool = False):
    """Yield ``i, j, o`` as ``match`` does, from all elements of both blocks."""
    place, hit = r.find(s)
    column, met, begin = np.where(hit, d.column[place], -1)[s.number], np.where(hit, d.count[place], 0)[s.number], d.begin[place][s.number]
    total = np.concatenate([[0], np.cumsum(met)])[s.split]
    least, most = _allowed(r, s, sim, low, same)
    of_r, of_s = r.n.astype(np.float32), s.n.astype(np.float32)
    rows = max(1, min(CELLS // len(r.n), MATRIX // max(1, d.matrix.shape[1])))
    j1 = 0
    while j1 < len(s.n):
        j0 = j1
        j1 = min(j0 + rows, max(j0 + 1, int(np.searchsorted(total, total[j0] + MEETS, "right")) - 1), len(s.n))
        fit = most[j0:j1] > least[j0:j1]
        if not fit.any():
            continue
        i0, i1 = int(least[j0:j1][fit].min()), int(most[j0:j1].max())
        a, b = s.split[j0], s.split[j1]
        row, c, m = np.repeat(np.arange(j1 - j0), s.n[j0:j1]), column[a:b], met[a:b]
        x = np.zeros((j1 - j0, d.matrix.shape[1]), np.float32)
        x[row[c >= 0], c[c >= 0]] = 1
        o = x @ d.matrix[i0:i1].T
        some = np.flatnonzero(m)
        if len(some):
            m, width = m[some], i1 - i0
            i = d.row[np.arange(m.sum()) + np.repeat(begin[a:b][some] - np.concatenate([[0], np.cumsum(m)[:-1]]), m)]
            cell = np.repeat(row[some] * width - i0, m) + i
            if width < len(r.n):
                cell = cell[(i >= i0) & (i < i1)]
            if len(cell) * 4 < o.size:
                np.add.at(o.reshape(-1), cell, np.float32(1))
            else:
                o += np.bincount(cell, minlength=o.size).reshape(o.shape)
        # Counts are exact in 32 bits; what is needed is not, so what may reach the key is looked at again.
        need = sim.needed(low, of_r[None, i0:i1], of_s[j0:j1, None])
        need *= np.float32(1 - 1e-5)
        good = o >= np.maximum(need, np.float32(0.5), out=need)
        if same:
            good &= np.arange(i0, i1)[None] < np.arange(j0, j1)[:, None]
        at = np.flatnonzero(good)
        j, i = np.divmod(at, i1 - i0)
        i, j, o = i + i0, j + j0, o.reshape(-1)[at].astype(np.int64)
        sure = sim.key(o, r.n[i], s.n[j]) >= low
        if sure.all():
            if len(i):
                yield i, j, o
        elif sure.any():
            yield i[sure], j[sure], o[sure]


def match(r: Block, pr: np.ndarray, index: Postings | Dense, s: Block, sim: SetSimilarity, low: float, frequencies: np.ndarray, same: bool = False, bounds: str = "tight", full: bool = False):
    """Yield ``i, j, o`` of all pairs of rows whose key is ``low`` or more; ``same``: of one block, i < j; ``full``: all elements of s meet."""
    if isinstance(index, Dense):
        yield from meet_whole(r, index, s, sim, low, same)
        return
    ps = s.n if full else s.prefix(sim, low, "s", bounds)
    rows = np.repeat(np.arange(len(ps)), ps)
    t = s.toks[s.places(np.arange(len(ps)), ps)]
    number = np.searchsorted(index.distinct, t)
    hit = index.distinct[np.minimum(number, len(index.distinct) - 1)] == t
    rows, number = rows[hit], number[hit]
    least, most = _allowed(r, s, sim, low, same)
    begin = np.searchsorted(index.at, number * len(r.n) + least[rows])
    met = np.maximum(np.searchsorted(index.at, number * len(r.n) + most[rows]) - begin, 0)
    ends = np.searchsorted(rows, np.arange(len(s.n)), "right")
    total = np.concatenate([[0], np.cumsum(met)])
    last_r, last_s = (b.toks[b.split[:-1] + p - 1] for b, p in ((r, pr), (s, ps)))
    often_r, often_s = (frequencies[(x >> _SHIFT).astype(np.int64)] for x in (last_r, last_s))
    j0, most_rows = 0, max(1, CELLS // max(1, len(r.n)))
    while j0 < len(s.n):
        before = total[ends[j0 - 1] if j0 else 0]
        j1 = min(j0 + most_rows, max(j0 + 1, int(np.searchsorted(total[ends], before + MEETS, "right"))), len(s.n))
        a, b = (ends[j0 - 1] if j0 else 0), ends[j1 - 1]
        n = met[a:b]
        if n.sum():
            at = np.arange(n.sum()) + np.repeat(begin[a:b] - np.concatenate([[0], np.cumsum(n)[:-1]]), n)
            cell = np.repeat(rows[a:b] - j0, n) * len(r.n) + index.row[at]
            if len(cell) * 8 < (j1 - j0) * len(r.n):
                cell, seen = np.unique(cell, return_counts=True)
            else:
                seen = np.bincount(cell)
                cell = np.flatnonzero(seen)
                seen = seen[cell]
            j, i = cell // len(r.n) + j0, cell % len(r.n)
            # Behind the lesser of both last places all could be shared.
            first = full | (often_r[i] < often_s[j]) | ((often_r[i] == often_s[j]) & (last_r[i] < last_s[j]))
            o = np.minimum(seen + np.where(first, r.n[i] - pr[i], s.n[j] - ps[j]), np.minimum(r.n[i], s.n[j]))
            good = sim.key(o, r.n[i], s.n[j]) >= low
            i, j = i[good], j[good]
            o = r.overlaps(i, s, j)
            good = sim.key(o, r.n[i], s.n[j]) >= low
            i, j, o = i[good], j[good], o[good]
            if len(i):
                yield i, j, o
        j0 = j1


def _work(b: Blocks, sim: SetSimilarity, low: float) -> list[tuple[str, list[str]]]:
    """A block of r and blocks of s whose sizes allow the key."""
    out = []
    for k, (path, least, most) in enumerate(b.r.blocks):
        fit = []
        for p, a, z in b.s.blocks[k:] if b.alone else b.s.blocks:
            # The closest sizes of both ranges, which bound the key.
            x, y = (most, a) if most < a else (least, z) if z < least else (1, 1)
            if float(sim.key(min(x, y), x, y)) >= low:
                fit.append(p)
        out.append((path, fit))
    each = min(ITEM, max(1, sum(len(fit) for _, fit in out) // SPREAD))
    return [(path, fit[at : at + each]) for path, fit in out for at in range(0, len(fit), each)]


def _run(b: Blocks, sim: SetSimilarity, low: float, schema: str, give, bounds: str = "tight", full: bool = False, whole: bool = False) -> DataFrame:
    """Rows that ``give(r, others)`` makes of a work item, a block of r and ``s, same, found`` of some of s; ``found`` yields pairs.

    ``whole``: all elements of all pairs meet, as they do below the key WHOLE.
    """
    from pyspark.sql import SparkSession

    spark = SparkSession.active()
    shared, work, alone = b.frequencies, _work(b, sim, low), b.alone

    def run(batches):
        for batch in batches:
            for path, others in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                r = Block(path)
                pr = r.prefix(sim, low, "r", bounds)
                index = Dense(r) if whole or low < WHOLE else Postings(r, pr)

                def pairs(path=path, others=others, r=r, pr=pr, index=index):
                    for p in others:
                        s, same = Block(p) if p != path else r, alone and p == path
                        yield s, same, match(r, pr, index, s, sim, low, shared.value, same, bounds, full)

                yield from give(r, pairs())

    items = spark.createDataFrame(work, "path string, others array<string>")
    return map_arrow(items.repartition(max(1, min(len(work), 2000))), run, schema)


def block_join(b: Blocks, sim: SetSimilarity, low: float, expanded: bool = True, bounds: str = "tight", index: str = "prefix") -> DataFrame:
    """``r, s, o, nr, ns, key`` of all pairs whose key is ``low`` (> 0) or more; of objects, or if not ``expanded`` of the least of
    each class, with its numbers of objects ``wr, ws``. ``index="full"`` indexes all elements of s instead of its prefix."""

    def give(r: Block, others):
        for s, _, found in others:
            yield from spread(r, s, found)

    def spread(r: Block, s: Block, found):
        for i, j, o in found:
            if not expanded:
                columns = [r.rep[i], s.rep[j], o, r.n[i], s.n[j], r.w[i], s.w[j]]
                yield from _cut(columns, names)
                continue
            for at in range(0, len(i), 100_000):
                x, y = i[at : at + 100_000], j[at : at + 100_000]
                lo, n = 0, r.w[x] * s.w[y]
                ends = np.cumsum(n)
                while lo < len(x):  # copies are spread a bounded number of pairs at once
                    hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + MEETS, "right")))
                    m = n[lo:hi]
                    k = np.arange(m.sum()) - np.repeat(np.concatenate([[0], np.cumsum(m)[:-1]]), m)
                    p, q = np.repeat(x[lo:hi], m), np.repeat(y[lo:hi], m)
                    columns = [r.ids[r.members[p] + k // s.w[q]], s.ids[s.members[q] + k % s.w[q]], np.repeat(o[at : at + 100_000][lo:hi], m), r.n[p], s.n[q]]
                    yield from _cut(columns, names)
                    lo = hi

    names = ["r", "s", "o", "nr", "ns"] + ([] if expanded else ["wr", "ws"])
    rows = _run(b, sim, low, ", ".join(f"{x} bigint" for x in names), give, bounds, index == "full")
    return rows.withColumn("key", sim.key(F.col("o"), F.col("nr"), F.col("ns")))


def _cut(columns: list[np.ndarray], names: list[str]):
    for at in range(0, len(columns[0]), 100_000):
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(x[at : at + 100_000]).astype(np.int64)) for x in columns], names)


def classes(f: Files) -> DataFrame:
    """``id, class_id, w``: each object that has an element, the least of its class and the objects of it."""
    from pyspark.sql import SparkSession

    def run(batches):
        for batch in batches:
            for path in batch.column(0).to_pylist():
                x = Block(path)
                yield from _cut([x.ids, np.repeat(x.rep, x.w), np.repeat(x.w, x.w)], ["id", "class_id", "w"])

    items = SparkSession.active().createDataFrame([(p,) for p, _, _ in f.blocks], "path string")
    return map_arrow(items.repartition(max(1, len(f.blocks))), run, "id bigint, class_id bigint, w bigint")


def links(b: Blocks, sim: SetSimilarity, low: float) -> DataFrame:
    """For a join with itself ``id, class_id, links``: the other objects of key ``low`` or more, equal ones among them."""

    def give(r: Block, others):
        for s, _, found in others:
            a, z = np.zeros(len(r.n), np.int64), np.zeros(len(s.n), np.int64)
            for i, j, _ in found:
                a += np.bincount(i, s.w[j], len(a)).astype(np.int64)
                z += np.bincount(j, r.w[i], len(z)).astype(np.int64)
            for x, n in ((r, a), (s, z)):
                at = np.flatnonzero(n)
                yield from _cut([x.rep[at], n[at]], ["class_id", "n"])

    near = _run(b, sim, low, "class_id bigint, n bigint", give).groupBy("class_id").agg(F.sum("n").alias("n"))
    return classes(b.r).join(near, "class_id", "left").select("id", "class_id", (F.coalesce("n", F.lit(0)) + F.col("w") - 1).alias("links"))


def _counted(key: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """As ``_summed`` of one part; most counts are 1, and their keys need but be sorted."""
    one = n == 1
    k = np.sort(key[one])
    at = np.flatnonzero(np.concatenate([np.ones(min(1, len(k)), bool), k[1:] != k[:-1]]))
    return _summed([k[at], key[~one]], [np.diff(at, append=len(k)), n[~one]]) if not one.all() else (k[at], np.diff(at, append=len(k)))


def _summed(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    key, at = np.unique(np.concatenate([np.zeros(0), *keys]), return_inverse=True)
    n = np.zeros(len(key), np.int64)
    np.add.at(n, at, np.concatenate([np.zeros(0, np.int64), *counts]))
    return key, n


#: What a row of ``level_parts`` is.
JOIN, COVER_R, COVER_S, MUTUAL, EDGE = range(5)


def level_parts(b: Blocks, sim: SetSimilarity, low: float, high: float | None = None, joins: bool | float = True, forest: bool = False, covers: bool = True, whole: bool = False, bounds: str = "tight") -> DataFrame:
    """What pairs of classes with a key from ``low`` (> 0) up to, not including, ``high`` add to a score, summed up in each task.

    Rows ``kind, a, b, key, n``. JOIN: ``n`` pairs of objects of a key; ``joins``: False, or the least key of which they are counted. COVER_R, COVER_S: the best key of a class ``a`` of ``n``
    objects in a task. MUTUAL: a pair ``a, b`` that is best for both its ends in its task, with its pairs of objects. EDGE: of a
    maximum spanning forest of a task's pairs.
    """

    counted = 0.0 if joins is True else joins

    def give(r: Block, others):
        levels, counts, held = [], [], 0
        best_r, best_s, ends = np.zeros(len(r.n)), [], []
        none = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        mutual, edges, loose = none, none, []
        first = len(r.n)  # a row of s has its number in the item

        def still(i, j, key, best):
            good = (key == best_r[i]) & (key == best[j - len(r.n)])
            return i[good], j[good], key[good]

        for s, _, found in others:
            best = np.zeros(len(s.n))
            ends.append(s)
            best_s.append(best)
            near = []
            for i, j, o in found:
                key = sim.key(o, r.n[i], s.n[j])
                if high is not None:
                    good = key < high
                    i, j, key = i[good], j[good], key[good]
                if joins:
                    n = r.w[i] * s.w[j]
                    k, n = _counted(key, n) if counted <= low else _counted(key[key >= counted], n[key >= counted])
                    levels.append(k)
                    counts.append(n)
                    held += len(k)
                    if held > HELD:
                        k, n = _summed(levels, counts)
                        levels, counts, held = [k], [n], 0
                if covers:
                    np.maximum.at(best_r, i, key)
                    np.maximum.at(best, j, key)
                    good = (key == best_r[i]) & (key == best[j])
                    near.append((i[good], j[good], key[good]))
                    if sum(len(x[0]) for x in near) > HELD:
                        i_, j_, k_ = (np.concatenate(x) for x in zip(*near, strict=True))
                        good = (k_ == best_r[i_]) & (k_ == best[j_])
                        near = [(i_[good], j_[good], k_[good])]
                if forest:
                    loose.append((i, j + first, key))
                    if sum(len(x[0]) for x in loose) > HELD:
                        edges, loose = forest_of(first + len(s.n), *(np.concatenate(x) for x in zip(edges, *loose, strict=True))), []
            mutual = tuple(np.concatenate(x) for x in zip(mutual, *((i, j + first, k) for i, j, k in near), strict=True))
            first += len(s.n)
            mutual = still(*mutual, np.concatenate(best_s))
        if forest:
            edges = forest_of(first, *(np.concatenate(x) for x in zip(edges, *loose, strict=True)))
        reps, weights = (np.concatenate([np.zeros(0, np.int64), *(getattr(x, c) for x in ends)]) for c in ("rep", "w"))
        best = np.concatenate([np.zeros(0), *best_s])
        key, n = _summed(levels, counts)
        yield from rows(JOIN, np.zeros(len(key), np.int64), np.zeros(len(key), np.int64), key, n)
        for kind, rep, w, top in ((COVER_R, r.rep, r.w, best_r), (COVER_S, reps, weights, best)):
            at = np.flatnonzero(top)
            yield from rows(kind, rep[at], np.zeros(len(at), np.int64), top[at], w[at])
        for kind, (i, j, key) in ((MUTUAL, mutual), (EDGE, edges)):
            j = j - len(r.n)
            yield from rows(kind, r.rep[i], reps[j], key, r.w[i] * weights[j])

    def rows(kind: int, a, c, key, n):
        for at in range(0, len(key), 100_000):
            part = [np.full(len(key[at : at + 100_000]), kind, np.int8), *(np.ascontiguousarray(x[at : at + 100_000]) for x in (a, c, key, n))]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in part], ["kind", "a", "b", "key", "n"])

    return _run(b, sim, low, "kind tinyint, a bigint, b bigint, key double, n bigint", give, bounds, whole=whole)


def keys_of(pairs: DataFrame, r: DataFrame, s: DataFrame, sim: SetSimilarity, tokens: str = "words", bag: bool = False) -> DataFrame:
    """``r, s, key`` of given pairs of ``id, text`` rows that share anything."""

    def run(batches):
        for x in batches:
            ends = []
            for k in (2, 3):
                lists = x.column(k)
                values = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
                ends.append(hash_sets(values, lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), bag))
            v = np.concatenate([e for e, _ in ends])
            row = np.concatenate([np.repeat(np.arange(x.num_rows), np.diff(split)) for _, split in ends])
            order = np.lexsort((v, row))
            v, row = v[order], row[order]
            o = np.bincount(row[1:][(v[1:] == v[:-1]) & (row[1:] == row[:-1])], minlength=x.num_rows)
            at = np.flatnonzero(o)
            key = sim.key(o[at], np.diff(ends[0][1])[at], np.diff(ends[1][1])[at])
            yield pa.RecordBatch.from_arrays([x.column(0).take(pa.array(at)), x.column(1).take(pa.array(at)), pa.array(key, pa.float64())], ["r", "s", "key"])

    both = pairs.select("r", "s").distinct()
    for name, side in (("r", r), ("s", s)):
        both = both.join(side.select(F.col("id").alias(name), F.transform(TOKENIZERS[tokens](F.col("text")), lambda t: F.xxhash64(t)).alias(f"t{name}")), name)
    return map_arrow(both.select("r", "s", "tr", "ts"), run, "r bigint, s bigint, key double")
