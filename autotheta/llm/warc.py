"""WARC archives: a writer with revisit records and a splittable reader.

Every record is a gzip member of its own. The writer needs no order: a task writes one archive under a name of
its attempt, and only archives of the manifest count. The reader cuts files into byte ranges; a task looks
for the gzip magic from the start of its range, takes a candidate only if it decompresses to a WARC header, and
then reads member after member. It owns every record that starts inside its range, and no other.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from autotheta.sources.shared import keep, map_arrow, new_path, open_store

GZIP, VERSION = b"\x1f\x8b\x08", b"WARC/1.1"
#: Bytes of a reader's range, and of one read.
RANGE, READ = 8 << 20, 1 << 20
#: Parts over which the rows of one payload are dealt.
SALTS = 256
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def digest32(payload: bytes) -> str:
    """Bare upper-case base32 SHA-1."""
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(kind: str, number: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One record, compressed. The id in its urn is the page's; a revisit has the HTTP head but no payload."""
    clean = (url or "").translate({10: "%0A", 13: "%0D"})
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http + (payload if kind == "response" else b"")
    head = [f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if number is None else number}>", f"WARC-Target-URI: {clean}", "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{digest32(payload)}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    if kind == "revisit":
        head += [f"WARC-Refers-To: <urn:page:{'' if refers_to is None else refers_to}>", f"WARC-Profile: {REVISIT_PROFILE}"]
    raw = VERSION + b"\r\n" + "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"
    z = zlib.compressobj(6, zlib.DEFLATED, 31)
    return z.compress(raw) + z.flush()


def choose_revisits(pages: DataFrame, min_revisit_bytes: int = 0) -> DataFrame:
    """``page_id, url, html, target``: target is the response's id for a revisit, else null.

    Of rows with equal payloads of ``min_revisit_bytes`` or more, the largest id is the response. Rows of one
    payload are dealt over SALTS parts, so that a payload that a third of all rows share fills no task.
    """
    rows = pages.withColumn("payload", F.coalesce("html", F.lit(""))).withColumn("digest", F.sha2("payload", 256)).withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)))
    part = rows.where(F.octet_length("payload") >= min_revisit_bytes).groupBy("digest", "salt").agg(F.max("page_id").alias("most"), F.count(F.lit(1)).alias("n"))
    whole = part.groupBy("digest").agg(F.max("most").alias("target"), F.sum("n").alias("rows"), F.collect_set("salt").alias("salts")).where("rows > 1")
    chosen = whole.select(F.col("digest").alias("d_"), F.explode("salts").alias("s_"), "target")
    joined = rows.join(chosen, (F.col("digest") == F.col("d_")) & (F.col("salt") == F.col("s_")), "left")
    return joined.select("page_id", "url", "html", F.when(~F.col("page_id").eqNullSafe(F.col("target")), F.col("target")).alias("target"))


def write_archives(pages: DataFrame, target: str | None = None, min_revisit_bytes: int = 0, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Write a record for every row; return the manifest ``path, n_records, n_bytes``.

    A null payload is empty; a null url is an empty one; a null id is an empty id, and it is a revisit where
    an equal payload has an id. Rows that repeat the largest id of a payload are all responses. An empty
    table writes no archive. Other columns are ignored.
    """
    target = target or new_path(pages.sparkSession, "warc")
    rows = choose_revisits(pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html")), min_revisit_bytes)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, n, size = None, 0, 0
        store, root = open_store(target)
        name = f"pages-{uuid.uuid4().hex}-{TaskContext.get().partitionId():06d}.warc.gz"
        for b in batches:
            for at in range(0, b.num_rows, 64):
                part = b.slice(at, 64).to_pylist()
                made = b"".join(record("response" if r["target"] is None else "revisit", r["page_id"], r["url"], (r["html"] or "").encode(), r["target"]) for r in part)
                if out is None:
                    store.create_dir(root, recursive=True)
                    out = store.open_output_stream(f"{root}/{name}", compression=None)
                out.write(made)
                n, size = n + len(part), size + len(made)
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_arrays([pa.array([f"{target}/{name}"]), pa.array([n]), pa.array([size])], ["path", "n_records", "n_bytes"])

    return keep(map_arrow(rows, write, "path string, n_records bigint, n_bytes bigint"), "manifest")


class _Bytes:
    """A file's bytes from a position on, read as they are needed."""

    def __init__(self, f, at: int, size: int):
        self.f, self.base, self.data, self.size = f, at, b"", size

    def more(self) -> bool:
        self.f.seek(self.base + len(self.data))
        got = self.f.read(min(READ, self.size - self.base - len(self.data)))
        self.data += got
        return bool(got)

    def drop(self, n: int) -> None:
        self.data, self.base = self.data[n:], self.base + n


def _looks_like_record(data: bytes) -> bool:
    try:
        return zlib.decompressobj(31).decompress(data[: 1 << 14], 64).startswith(b"WARC/1.")
    except zlib.error:
        return False


def read_range(path: str, start: int, end: int) -> Iterator[tuple[int, bytes]]:
    """``(offset, record)`` of all records that begin in ``[start, end)`` of a file."""
    store, p = open_store(path)
    size = store.get_file_info(p).size
    with store.open_input_file(p) as f:
        buf, sure = _Bytes(f, start, size), False
        while buf.base < min(end, size):
            while len(buf.data) < 1 << 14 and buf.more():
                pass
            if not sure:
                k = buf.data.find(GZIP)
                if k < 0 or buf.base + k >= end:
                    if k >= 0 or len(buf.data) < 3 or not buf.data:
                        return
                    buf.drop(max(1, len(buf.data) - 2))
                    if buf.base + len(buf.data) >= size:
                        return
                    continue
                buf.drop(k)
                while len(buf.data) < 1 << 14 and buf.more():
                    pass
                if not _looks_like_record(buf.data):
                    buf.drop(1)
                    continue
            z, parts, at = zlib.decompressobj(31), [], 0
            try:
                while True:
                    parts.append(z.decompress(buf.data[at:]))
                    at = len(buf.data)
                    if z.eof or not buf.more():
                        break
            except zlib.error:
                z = None
            if z is None or not z.eof:  # damaged: look for the next record
                sure = False
                buf.drop(1)
                continue
            body = b"".join(parts)
            used = len(buf.data) - len(z.unused_data)
            if body.startswith(b"WARC/1."):
                yield buf.base, body
            buf.drop(used)
            sure = buf.data[:3] == GZIP if len(buf.data) >= 3 else True


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields (names in lower case) and block of a record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in head.decode("utf-8", "replace").split("\r\n")[1:])}
    return fields, rest[: int(fields.get("content-length", 0))]


def describe(raw: bytes) -> tuple[int | None, int, str, str, int | None, str]:
    """``page_id, payload_bytes, payload_digest, record_type, refers_to, url``; a response's payload is checked against its digest."""
    fields, block = parse(raw)
    number = lambda x: int(x) if (x := x.strip("<>").rpartition(":")[2]) else None
    head, _, payload = block.partition(b"\r\n\r\n")
    length = next((int(x.split(b":")[1]) for x in head.split(b"\r\n") if x.lower().startswith(b"content-length:")), len(payload))
    digest = fields.get("warc-payload-digest", "").rpartition(":")[2]
    if fields["warc-type"] == "response" and (len(payload) != length or digest32(payload) != digest):
        raise ValueError(f"damaged payload of {fields.get('warc-record-id')}")
    return number(fields["warc-record-id"]), length, digest, fields["warc-type"], number(fields["warc-refers-to"]) if "warc-refers-to" in fields else None, fields.get("warc-target-uri", "")


SCHEMA = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, url string"


def read_archives(manifest: DataFrame, range_bytes: int = RANGE) -> DataFrame:
    """The records of all archives of a manifest, byte range by byte range."""
    ranges = manifest.select("path", "n_bytes", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n_bytes") - 1, F.lit(range_bytes).cast("bigint"))).alias("start"))

    def read(batches):
        names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url"]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]
        for b in batches:
            for path, start in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), strict=True):
                rows = []
                for _, raw in read_range(path, start, start + range_bytes):
                    rows.append(describe(raw))
                    if len(rows) == 5000:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                        rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    tasks = manifest.agg(F.sum(F.ceil(F.col("n_bytes") / range_bytes))).first()[0] or 1
    return map_arrow(ranges.repartition(int(min(tasks, 100_000)), "path", "start"), read, SCHEMA)


def list_archives(spark: SparkSession, folder: str) -> DataFrame:
    """A manifest of foreign archives: all ``.warc.gz`` files of a folder."""
    from pyarrow import fs

    store, root = open_store(folder)
    rows = [(f"{folder.rstrip('/')}/{i.base_name}", None, i.size) for i in store.get_file_info(fs.FileSelector(root)) if i.base_name.endswith(".warc.gz")]
    return spark.createDataFrame(rows, "path string, n_records bigint, n_bytes bigint")
