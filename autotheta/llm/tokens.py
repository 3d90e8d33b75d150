"""Token-ID output: length-delimited binary records with masked checksums, and an offset index.

File format (little-endian). A shard starts with the 8 bytes ``TOKREC01``. A record is

    length u64 | masked crc32 of those 8 bytes u32 | payload | masked crc32 of the payload u32

and its payload ``doc_id i64 | null id u8 | bytes an id u8 | ids``. Ids take 2 bytes where all fit, else 4. The
index beside the shard (``.idx``) has ``offset u64, length u64, n_tokens u64`` for every record, so that
records can be read in any order without a scan of the shard.
"""

from __future__ import annotations

import os
import re
import struct
import uuid
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F

from autotheta.llm import textkit
from autotheta.sources.shared import keep, map_arrow, new_path, open_store

MAGIC = b"TOKREC01"
_HEAD = struct.Struct("<QI")
_ROW = struct.Struct("<qBB")
#: Distinct space-separated pieces whose ids a Python worker remembers (about 200 bytes each).
CACHE_PIECES = 1_000_000


def masked(data: bytes) -> int:
    """crc32 turned and shifted, so that a checksum of data that holds checksums stays independent."""
    c = zlib.crc32(data)
    return (((c >> 15) | (c << 17)) + 0xA282EAD8) & 0xFFFFFFFF


def frame(doc_id: int | None, width: int, ids: bytes) -> bytes:
    """A record of the file format."""
    payload = _ROW.pack(doc_id or 0, doc_id is None, width) + ids
    length = struct.pack("<Q", len(payload))
    return b"".join((length, struct.pack("<I", masked(length)), payload, struct.pack("<I", masked(payload))))


class PieceEncoder(dict):
    """Ids of texts by a tokenizer that never joins over ASCII space, remembered by space-separated piece.

    Correct for tokenizers that drop white space before they split (all pieces between spaces are then
    encoded on their own); ``whole=True`` encodes whole texts for any other. Pieces of plain letters go to
    the tokenizer's model directly where its lower-casing and splitting leave them as one lower-case word
    (tried at the start); all others to the tokenizer as they are. Maps a piece to its little-endian ids.
    """

    def __init__(self, path: str, whole: bool = False):
        super().__init__()
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.whole = Tokenizer.from_file(path), whole
        self.model, self.code = self.tokenizer.model, "H" if self.tokenizer.get_vocab_size() <= 1 << 16 else "I"
        self.width = 2 if self.code == "H" else 4
        tried = ("a", "Mixed", "UPPER", "zqxjkvbw", "internationalisation", "Ärger", "ÉÀÈÿþß", "straßeÑ")
        self.plain = all(self._any(x) == self._letters(x) for x in tried) and all(self._any(x + y) == self._any(x) + self._any(y) for x in tried for y in (".", ",", "!!", ".)", "###"))

    def _any(self, text: str) -> bytes:
        return array(self.code, self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _letters(self, word: str) -> bytes:
        shown = word.lower() if word.isascii() else word.lower().encode().decode("latin-1").translate(BYTE_CHARS)
        return array(self.code, [t.id for t in self.model.tokenize(shown)]).tobytes()

    def __missing__(self, p: bytes) -> bytes:
        if not self.plain or not (m := LETTERS(p)):
            ids = self._any(p.decode())
        elif m[2]:
            ids = self[m[1]] + (self[m[2]] if m[2] in self else self.setdefault(m[2], self._any(m[2].decode())))
        else:
            ids = self._letters(p.decode())
        self[p] = ids
        return ids

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Little-endian ids of each text."""
        if self.whole:
            return [self._any(t.decode()) for t in texts]
        out = []
        for t in texts:
            if len(self) > CACHE_PIECES:
                self.clear()
            out.append(b"".join(map(self.__getitem__, t.split())))
        return out


#: A word of letters up to U+00FF and the marks behind it; no apostrophe, as those can join with letters.
LETTERS = re.compile(rb"((?:[A-Za-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+)([.,;:!?)*#%&$]*)").fullmatch
#: Characters that stand for bytes in byte-level models: printable Latin-1 for itself, others from U+0100 on.
_SHOWN = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
BYTE_CHARS = {b: b if b in _SHOWN else 256 + sum(x not in _SHOWN for x in range(b)) for b in range(256)}
_ENCODERS: dict[tuple[str, bool], PieceEncoder] = {}


def encoder(path: str, whole: bool) -> PieceEncoder:
    """The encoder of this Python worker, which later tasks find as the earlier ones left it."""
    if (path, whole) not in _ENCODERS:
        _ENCODERS[path, whole] = PieceEncoder(path, whole)
    return _ENCODERS[path, whole]


def write_shards(docs: DataFrame, tokenizer: str, end_id: int | None = 2, target: str | None = None, id_col: str = "doc_id", text_col: str = "text", whole: bool = False) -> DataFrame:
    """Write the ids of all texts in ascending id order; return the manifest ``shard, path, n_docs, n_tokens, first_id``.

    A task writes one shard under a name of its own attempt; only shards of the manifest count, so a
    repeated or lost attempt leaves nothing that is read. Null texts are empty, null ids come first,
    repeated rows become records of their own, an empty table writes no shard. Other columns are ignored.
    """
    spark = docs.sparkSession
    target = target or new_path(spark, "tokens")
    rows = docs.select(F.col(id_col).cast("bigint").alias("i"), F.col(text_col).cast("string").alias("t"))
    rows = rows.repartitionByRange(F.col("i").asc_nulls_first()).sortWithinPartitions(F.col("i").asc_nulls_first(), "t")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, out, index = encoder(tokenizer, whole), None, []
        end = b"" if end_id is None else array(coder.code, [end_id]).tobytes()
        store, root = open_store(target)
        n_docs = n_tokens = at = 0
        path, first = "", None
        for b in batches:
            ids = b.column(0).to_pylist()
            for lo, hi, data, offsets in textkit.blocks(b.column(1), 1 << 20):
                raw = data.tobytes()
                texts = [raw[s:e] for s, e in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                made = []
                for doc_id, body in zip(ids[lo:hi], coder.encode(texts), strict=True):
                    body += end
                    made.append(frame(doc_id, coder.width, body))
                    index.append((at + len(MAGIC), len(made[-1]) - 16, len(body) // coder.width))
                    at += len(made[-1])
                    n_tokens += len(body) // coder.width
                if out is None:
                    store.create_dir(root, recursive=True)
                    path, first = f"{root}/shard-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.rec", ids[lo]
                    out = store.open_output_stream(path, compression=None)
                    out.write(MAGIC)
                out.write(b"".join(made))
                n_docs += hi - lo
        if out is not None:
            out.close()
            with store.open_output_stream(path + ".idx", compression=None) as f:
                f.write(np.array(index, "<u8").tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in ((TaskContext.get().partitionId(), pa.int64()), (f"{target}/{path.rpartition('/')[2]}", pa.string()), (n_docs, pa.int64()), (n_tokens, pa.int64()), (first, pa.int64()))], ["shard", "path", "n_docs", "n_tokens", "first_id"])

    return keep(map_arrow(rows, write, "shard bigint, path string, n_docs bigint, n_tokens bigint, first_id bigint"), "manifest")


def _parse(f, where: str) -> tuple[int | None, np.ndarray]:
    head = f.read(12)
    length, crc = _HEAD.unpack(head)
    if masked(head[:8]) != crc:
        raise ValueError(f"{where}: damaged length")
    payload = f.read(length)
    if len(payload) != length or masked(payload) != struct.unpack("<I", f.read(4))[0]:
        raise ValueError(f"{where}: damaged record")
    doc_id, null, width = _ROW.unpack_from(payload)
    return None if null else doc_id, np.frombuffer(payload, f"<u{width}", offset=_ROW.size)


def records(path: str, numbers: list[int] | None = None) -> Iterator[tuple[int | None, np.ndarray]]:
    """``(id, token ids)`` of a shard, all in order or those numbered, found by the index. Checks every checksum."""
    store, p = open_store(path)
    if numbers is None:
        with store.open_input_stream(p, compression=None) as f:
            size, at = store.get_file_info(p).size, len(MAGIC)
            if f.read(len(MAGIC)) != MAGIC:
                raise ValueError(f"{path}: not a shard")
            while at < size:
                doc_id, ids = _parse(f, path)
                at += 16 + _ROW.size + ids.nbytes
                yield doc_id, ids
        return
    with store.open_input_stream(p + ".idx", compression=None) as f:
        index = np.frombuffer(f.read(), "<u8").reshape(-1, 3)
    with store.open_input_file(p) as f:
        for k in numbers:
            f.seek(int(index[k, 0]))
            yield _parse(f, path)


def read_shards(manifest: DataFrame) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every record, read from the files of a manifest.

    ``start`` is the number of ids before the record in all shards; ``ids_crc32`` the crc32 of the ids as
    32-bit integers. The running sum is over shards, not records.
    """
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    files = manifest.withColumn("base", F.coalesce(F.sum("n_tokens").over(before), F.lit(0))).select("path", "base")

    def read(batches):
        for b in batches:
            for path, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                out, at = [], base
                for doc_id, ids in records(path):
                    out.append((doc_id, at, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    at += len(ids)
                    if len(out) == 20_000:
                        yield _batch(out)
                        out = []
                if out:
                    yield _batch(out)

    # One file a task, whatever the size of the manifest.
    tasks = max(1, min(100_000, manifest.count()))
    return map_arrow(files.repartition(tasks, "path"), read, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "start", "n_tokens", "ids_crc32"])
