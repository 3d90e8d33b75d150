"""Counts of hashed keys that come back to the chunks of text that asked for them.

A chunk is what one task reads of the texts, up to a bound of bytes. It sends each of its distinct keys once, with
its own counts, to the part that owns the key's range. The owner adds the chunks' counts up and answers every chunk in the
order of its keys, so an answer carries no key. Answers lie in the owners' files in the shared folder, and a chunk's own file says
where; so they are written once and never shuffled. A key that a third of all texts hold is therefore one entry a chunk, not a hot key.

Sorted keys travel as differences of hashes, in byte planes that are compressed: about three bytes a key.
``Plan`` gives the hashes as many bits as keep the chance that a key meets another one the same at every size of input.
The texts are scanned again for every step instead of being written. The scans must cut them into the same
chunks: ``stable`` writes inputs that are no plain scan of files, ``same_splits`` keeps the session's splits the
same while executors come and go, and an answer whose length is not that of its question raises.
"""

from __future__ import annotations

import contextlib
import functools
import math
import pickle
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from autotheta.sources.shared import keep, map_arrow, open_store

SPLITS = "spark.sql.files.minPartitionNum"
SENT = "chunk bigint, part int, kind string, n int, keys binary, counts binary"
_ANSWER = "chunk bigint, part int, kind string, n int, counts binary, total binary"


def stable(docs: DataFrame) -> DataFrame:
    """``docs`` if it is a deterministic scan of files, else written and read again."""
    plan = docs._jdf.queryExecution().optimizedPlan()
    todo, kinds = [plan], set()
    while todo:
        node = todo.pop()
        kinds.add(node.getClass().getSimpleName())
        todo += [node.children().apply(k) for k in range(node.children().size())]
    return docs if kinds <= {"Project", "Filter", "LogicalRelation"} and plan.deterministic() else keep(docs, "rows")


@contextlib.contextmanager
def same_splits(spark: SparkSession):
    """Files are cut for a fixed number of cores meanwhile, whatever executors there are at the time."""
    before = spark.conf.get(SPLITS, None)
    if before is None:
        spark.conf.set(SPLITS, str(max(1, spark.sparkContext.defaultParallelism)))
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(SPLITS)


@dataclass(frozen=True)
class Plan:
    """Owners of keys, and bits of a key. A chunk has some 2**22 keys; of 2**14 absent keys about one meets another one."""

    parts: int
    bits: int

    @property
    def shift(self) -> np.uint64:
        return np.uint64(64 - self.bits)

    @property
    def width(self) -> int:
        """Keys in the range of a part."""
        return -(-(1 << self.bits) // self.parts)


def plan(rows: DataFrame) -> Plan:
    """Half as many owners as there are splits, so a part holds about two chunks' keys."""
    splits = rows.rdd.getNumPartitions()
    return Plan(max(4, splits // 2), min(62, 36 + math.ceil(math.log2(max(1, splits)))))


def _squeeze(x: np.ndarray) -> bytes | None:
    return pa.compress(np.ascontiguousarray(x).tobytes(), "zstd", asbytes=True) if x.any() else None


def _stretch(raw: bytes | None, n: int) -> np.ndarray:
    return np.frombuffer(pa.decompress(raw, n, "zstd"), np.uint8) if raw is not None else np.zeros(n, np.uint8)


def pack(arrays: list[np.ndarray]) -> bytes:
    """Arrays of unsigned numbers: which are not 0, a bit each, and the byte planes of those less 1, compressed."""
    out = []
    for x in arrays:
        some = x > 0
        rest = x[some] - x.dtype.type(1)
        planes = rest.view(np.uint8).reshape(len(rest), x.itemsize).T
        out.append((x.dtype.str, len(x), len(rest), _squeeze(np.packbits(~some)), [_squeeze(p) for p in planes]))
    return pickle.dumps(out, protocol=5)


def unpack(raw: bytes) -> list[np.ndarray]:
    out = []
    for kind, n, m, none, planes in pickle.loads(raw):
        some = ~np.unpackbits(_stretch(none, -(-n // 8)), count=n).view(bool)
        rest = np.stack([_stretch(p, m) for p in planes], axis=1) if m else np.zeros((0, len(planes)), np.uint8)
        x = np.zeros(n, kind)
        x[some] = rest.view(kind).ravel() + x.dtype.type(1)
        out.append(x)
    return out


def distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``order, first, at``: a sorting order, the places in it where a new key begins, the number of each key by element."""
    order = np.argsort(keys, kind="stable")
    ordered = keys[order]
    new = np.ones(len(keys), bool)
    new[1:] = ordered[1:] != ordered[:-1]
    first = np.flatnonzero(new)
    at = np.empty(len(keys), np.int32)
    at[order] = np.cumsum(new, dtype=np.int32) - 1
    return order, first, at


def question(chunk: int, kind: str, keys: np.ndarray, counts: list[np.ndarray], plan: Plan) -> Iterator[pa.RecordBatch]:
    """Rows of a chunk's sorted distinct keys, one a part."""
    cut = np.searchsorted(keys, np.arange(1, plan.parts, dtype=np.uint64) * np.uint64(plan.width))
    cut = [0, *cut.tolist(), len(keys)]
    for p in range(plan.parts):
        lo, hi = cut[p], cut[p + 1]
        if lo < hi:
            steps = np.diff(keys[lo:hi], prepend=np.uint64(p * plan.width))
            row = [[chunk], [p], [kind], [hi - lo], [pack([steps])], [pack([c[lo:hi] for c in counts])]]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(row, (pa.int64(), pa.int32(), pa.string(), pa.int32(), pa.binary(), pa.binary()), strict=True)], ["chunk", "part", "kind", "n", "keys", "counts"])


def _groups(batches, size_of: Callable) -> Iterator[list[dict]]:
    """Rows of consecutive equal ``size_of``; a group is what a task holds at once."""
    held: list[dict] = []
    for b in batches:
        for row in b.to_pylist():
            if held and size_of(held[0]) != size_of(row):
                yield held
                held = []
            held.append(row)
    if held:
        yield held


def ask(sent: DataFrame, plan: Plan, answer: Callable, merge: Callable, folder: str) -> dict[str, object]:
    """Exchange questions for answers; returns the total of every kind, ``merge`` of two at a time.

    ``answer(kind, keys, counts, first, at)`` gets the distinct keys of a part and its entries in their order: the counts,
    where each key begins, and the number of the key of each entry. It returns arrays by entry and a total of any kind. The
    answers of a chunk are found by ``answers`` then. A chunk's file is moved to its name when it is whole.
    """
    width, parts = plan.width, plan.parts

    def own(batches):
        for rows in _groups(batches, lambda r: (r["part"], r["kind"])):
            part, kind = rows[0]["part"], rows[0]["kind"]
            rows.sort(key=lambda r: r["chunk"])
            keys = np.concatenate([np.cumsum(unpack(r["keys"])[0]) + np.uint64(part * width) for r in rows])
            packed = [unpack(r["counts"]) for r in rows]
            counts = [np.concatenate(c) for c in zip(*packed, strict=True)]
            del packed
            order, first, _ = distinct(keys)
            new = np.zeros(len(keys), bool)
            new[first] = True
            out, total = answer(kind, keys[order[first]], [c[order] for c in counts], first, np.cumsum(new) - 1)
            back = np.empty(len(order), np.int64)
            back[order] = np.arange(len(order))
            out, at, size, name = [x[back] for x in out], 0, 0, uuid.uuid4().hex
            places = []
            store, root = open_store(folder)
            store.create_dir(root, recursive=True)
            with store.open_output_stream(f"{root}/{name}", compression=None) as f:
                for r in rows:
                    blob = pack([x[at : at + r["n"]] for x in out])
                    f.write(blob)
                    places.append(pickle.dumps((name, size, len(blob))))
                    at, size = at + r["n"], size + len(blob)
            # A repeated attempt writes a file of another name, and its rows say so.
            columns = [[r["chunk"] for r in rows], [part] * len(rows), [kind] * len(rows), [r["n"] for r in rows], places, [None] * len(rows)]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(columns, (pa.int64(), pa.int32(), pa.string(), pa.int32(), pa.binary(), pa.binary()), strict=True)], ["chunk", "part", "kind", "n", "counts", "total"])
            # Totals travel as chunks below 0, dealt over all tasks of the next step.
            yield pa.RecordBatch.from_arrays([pa.array([-1 - part]), pa.array([part], pa.int32()), pa.array([kind]), pa.array([0], pa.int32()), pa.array([None], pa.binary()), pa.array([pickle.dumps(total)], pa.binary())], ["chunk", "part", "kind", "n", "counts", "total"])

    def write(batches):
        store, root = open_store(folder)
        totals: dict[str, object] = {}
        for rows in _groups(batches, lambda r: r["chunk"]):
            if rows[0]["chunk"] < 0:
                for r in rows:
                    x = pickle.loads(r["total"])
                    totals[r["kind"]] = merge(totals[r["kind"]], x) if r["kind"] in totals else x
                continue
            store.create_dir(root, recursive=True)
            name = f"{root}/{uuid.uuid4().hex}.part"
            with store.open_output_stream(name, compression=None) as f:
                pickle.dump([(r["kind"], r["n"], *pickle.loads(r["counts"])) for r in sorted(rows, key=lambda r: (r["kind"], r["part"]))], f, protocol=5)
            store.move(name, f"{root}/chunk-{rows[0]['chunk']}")
        for kind, x in totals.items():
            yield pa.RecordBatch.from_arrays([pa.array([kind]), pa.array([pickle.dumps(x)], pa.binary())], ["kind", "total"])

    def add(t: pa.Table) -> pa.Table:  # one row a task at most
        return pa.table({"kind": [t["kind"][0].as_py()], "total": pa.array([pickle.dumps(functools.reduce(merge, map(pickle.loads, t["total"].to_pylist())))], pa.binary())})

    owned = map_arrow(sent.repartition(parts, "part").sortWithinPartitions("part", "kind"), own, _ANSWER)
    rows = map_arrow(owned.repartition(parts, "chunk").sortWithinPartitions("chunk"), write, "kind string, total binary")
    return {r["kind"]: pickle.loads(r["total"]) for r in rows.groupBy("kind").applyInArrow(add, "kind string, total binary").collect()}


def answers(folder: str, chunk: int) -> dict[str, list[np.ndarray]]:
    """By kind, the answers to a chunk's keys in their order."""
    store, root = open_store(folder)
    with store.open_input_stream(f"{root}/chunk-{chunk}", compression=None) as f:
        places = pickle.loads(f.read())
    out: dict[str, list] = {}
    for kind, n, name, at, size in places:
        with store.open_input_file(f"{root}/{name}") as f:
            f.seek(at)
            got = unpack(f.read(size))
        if any(len(x) != n for x in got):
            raise ValueError("an answer is damaged")
        out.setdefault(kind, []).append(got)
    return {kind: [np.concatenate(x) for x in zip(*parts, strict=True)] for kind, parts in out.items()}


def chunk_id(ordinal: int) -> int:
    """Number of the ``ordinal``-th chunk of the running task."""
    return (TaskContext.get().partitionId() << 20) | ordinal
