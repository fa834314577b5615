"""WARC archives (operator 9): write, normalise monolithic gzip streams, index, read back.

* :func:`record_plan` decides which captures are responses and which revisit an equal
  payload, from digests alone (the group sizes never matter: one ``min`` per digest).
* :func:`monolithic` lays a partition's records into archives, each *one* gzip stream.
* :func:`normalise` inflates such a stream once, front to back, and writes every record as
  a gzip member of its own, with a sidecar index of (offset, length, record id).
* :func:`write_archives` puts archives and sidecar indexes as files into a folder that all
  executors reach, and gives a manifest of them.
* :func:`read_archives` opens single members through the indexes and parses them.

Files are named by their content and moved into place when whole, so that a task which runs
again writes the same files. Folders are URIs of a store that Arrow's file systems open
(local mounts, object stores, HDFS where its library is installed).

Defined results: a null payload is an empty one; null and empty urls give an empty target
URI; rows that repeat a page id and payload are each written, and where they tie for the
smallest id of their payload all of them are responses; a null page id never leads a group
that has another id (a group of null ids only consists of responses). Empty tables give
no archives. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

#: Payloads under this size are always stored in full.
MIN_REVISIT_BYTES = 100
#: An archive is closed when its records exceed this many bytes before compression.
ARCHIVE_BYTES = 8 << 20
#: zlib level of both the monolithic stream and the members.
LEVEL = 1

#: Parts over which the pages of one digest are dealt.
PARTS = 16

MANIFEST = "archive string, sidecar string, n_records long, n_bytes long"
ARCHIVES = "archive string, data binary, index binary"
RECORDS = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def record_plan(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """Rows with payload bytes, digest and, for repeats of a large payload, the id they refer to."""
    payload = F.coalesce(F.col(payload_col).cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), payload.alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    large = F.octet_length("payload") >= MIN_REVISIT_BYTES
    leads = (
        rows.filter(large).groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).filter("n > 1 and first_id is not null").select("digest", "first_id")
    )
    # A digest that many pages share is dealt over parts, its one lead is copied to each.
    rows = rows.withColumn("part", F.pmod(F.xxhash64("page_id", "url"), F.lit(PARTS)).cast("int"))
    leads = leads.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(PARTS - 1))))
    out = rows.join(leads, ["digest", "part"], "left")
    refers = F.when(large & ~F.col("page_id").eqNullSafe(F.col("first_id")), F.col("first_id"))
    return out.select("page_id", "url", "payload", "digest", refers.alias("refers_to"))


def _record(page_id, url: str, payload: bytes, digest: str, refers_to) -> bytes:
    kind = "response" if refers_to is None else "revisit"
    head = [
        "WARC/1.1",
        f"WARC-Type: {kind}",
        f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Target-URI: {url}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"X-Payload-Bytes: {len(payload)}",
        "Content-Type: text/html; charset=utf-8",
    ]
    if refers_to is not None:
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: identical-payload-digest"]
        payload = b""
    head.append(f"Content-Length: {len(payload)}")
    return "\r\n".join(head).encode() + b"\r\n\r\n" + payload + b"\r\n\r\n"


def parse_record(data: bytes | memoryview) -> tuple[dict[str, str], bytes]:
    """Headers (lower-case names) and payload of one record at the start of the data."""
    data = bytes(data)
    end = data.index(b"\r\n\r\n")
    head = data[:end].decode().split("\r\n")
    if not head[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = {k.lower(): v for k, _, v in (x.partition(": ") for x in head[1:])}
    return fields, data[end + 4 : end + 4 + int(fields["content-length"])]


def _gzip() -> "zlib._Compress":
    return zlib.compressobj(LEVEL, zlib.DEFLATED, 31)


class _Packer:
    """Collects records into whole-file gzip streams of bounded size."""

    def __init__(self):
        self.z, self.parts, self.size = _gzip(), [], 0

    def add(self, record: bytes) -> None:
        self.parts.append(self.z.compress(record))
        self.size += len(record)

    def close(self) -> bytes:
        self.parts.append(self.z.flush())
        data = b"".join(self.parts)
        self.__init__()
        return data


def monolithic(batches: Iterator[pa.RecordBatch]) -> Iterator[bytes]:
    """The rows of a partition as gzip streams, each holding many records in one member."""
    packer = _Packer()
    for batch in batches:
        for i in range(batch.num_rows):
            page_id, url, payload, digest, refers = (batch.column(k)[i].as_py() for k in range(5))
            uri = "".join(" " if c in "\r\n" else c for c in url or "")
            packer.add(_record(page_id, uri, payload, digest, refers))
            if packer.size >= ARCHIVE_BYTES:
                yield packer.close()
    if packer.size:
        yield packer.close()


def inflate_records(stream: bytes, chunk: int = 1 << 18) -> Iterator[bytes]:
    """Whole records of a gzip stream (of one member or many), inflated once in bounded steps."""
    buffer, done, need = bytearray(), 0, 0
    inflater = zlib.decompressobj(31)
    view, at = memoryview(stream), 0
    while at < len(view) or inflater.unconsumed_tail:
        block = inflater.unconsumed_tail or view[at : at + chunk]
        if not inflater.unconsumed_tail:
            at += len(block)
        buffer += inflater.decompress(block, chunk * 4)
        if inflater.eof:
            at -= len(inflater.unused_data)
            inflater = zlib.decompressobj(31)
        while True:
            if not need:
                end = buffer.find(b"\r\n\r\n", done)
                if end < 0:
                    break
                head = bytes(buffer[done:end]).lower()
                length = int(head.rpartition(b"\r\ncontent-length:")[2].split(b"\r\n")[0])
                need = end + 4 + length + 4 - done
            if len(buffer) - done < need:
                break
            yield bytes(buffer[done : done + need])
            done, need = done + need, 0
        if done > chunk:
            del buffer[:done]
            done = 0
    if len(buffer) > done:
        raise ValueError("the stream ends inside a record")


def normalise(stream: bytes) -> tuple[bytes, bytes]:
    """(archive with one gzip member a record, index of packed (offset, length) pairs)."""
    out, index, offset = [], [], 0
    for record in inflate_records(stream):
        z = _gzip()
        member = z.compress(record) + z.flush()
        index.append(struct.pack("<QQ", offset, len(member)))
        out.append(member)
        offset += len(member)
    return b"".join(out), b"".join(index)


def members(data: bytes, index: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Random access through the sidecar index: each member alone."""
    for offset, length in struct.iter_unpack("<QQ", index):
        yield parse_record(zlib.decompress(data[offset : offset + length], 31))


def _put(store: fs.FileSystem, path: str, data: bytes) -> None:
    """A whole file or none, whatever becomes of the task."""
    part = f"{path}.{uuid.uuid4().hex}.part"
    with store.open_output_stream(part, compression=None) as f:
        f.write(data)
    store.move(part, path)


def _get(store: fs.FileSystem, path: str) -> bytes:
    with store.open_input_file(path) as f:
        return f.read()


def _writing(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = fs.FileSystem.from_uri(folder)
        for stream in monolithic(batches):
            data, index = normalise(stream)
            name = hashlib.sha256(data).hexdigest()[:32]
            _put(store, f"{path}/{name}.warc.gz", data)
            _put(store, f"{path}/{name}.idx", index)
            yield pa.RecordBatch.from_pydict({"archive": [f"{name}.warc.gz"], "sidecar": [f"{name}.idx"], "n_records": pa.array([len(index) // 16], pa.int64()), "n_bytes": pa.array([len(data)], pa.int64())})

    return run


_OUT = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload", pa.binary())])


def _urn(x: str | None) -> int | None:
    digits = (x or "")[len("<urn:page:") : -1]
    return int(digits) if digits else None


def _reading(folder: str):
    def flush(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _OUT.types)], schema=_OUT)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = fs.FileSystem.from_uri(folder)
        for batch in batches:
            for archive, sidecar in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                rows, size = [], 0
                for head, payload in members(_get(store, f"{path}/{archive}"), _get(store, f"{path}/{sidecar}")):
                    kind = head["warc-type"]
                    claimed, n = head["warc-payload-digest"].removeprefix("sha256:"), int(head["x-payload-bytes"])
                    if kind == "response" and (hashlib.sha256(payload).hexdigest() != claimed or len(payload) != n):
                        raise ValueError("a payload differs from its digest")
                    rows.append((_urn(head["warc-record-id"]), head["warc-target-uri"], n, claimed, kind, _urn(head.get("warc-refers-to")), payload if kind == "response" else None))
                    size += len(payload)
                    if size > ARCHIVE_BYTES // 2 or len(rows) >= 5000:
                        yield flush(rows)
                        rows, size = [], 0
                if rows:
                    yield flush(rows)

    return run


class Archives:
    """A folder of archives and the manifest (archive, sidecar, n_records, n_bytes) of its files."""

    def __init__(self, folder: str, manifest: DataFrame):
        self.folder, self.manifest = folder, manifest


def write_archives(plan: DataFrame, folder: str) -> Archives:
    """Archives and sidecar indexes of a record plan as files of a shared folder."""
    store, path = fs.FileSystem.from_uri(folder)
    store.create_dir(path, recursive=True)
    rows = plan.select("page_id", "url", "payload", "digest", "refers_to")
    return Archives(folder, cut(rows.mapInArrow(_writing(folder), MANIFEST)))


def read_archives(archives: Archives) -> DataFrame:
    """One row per record; the payload of a revisit is null."""
    return archives.manifest.select("archive", "sidecar").mapInArrow(_reading(archives.folder), RECORDS)


def read_member(folder: str, archive: str, index: str, number: int) -> tuple[dict[str, str], bytes]:
    """One record by its number: reads its member's bytes alone."""
    store, path = fs.FileSystem.from_uri(folder)
    with store.open_input_file(f"{path}/{index}") as f:
        offset, length = struct.unpack("<QQ", f.read_at(16, 16 * number))
    with store.open_input_file(f"{path}/{archive}") as f:
        return parse_record(zlib.decompress(f.read_at(length, offset), 31))


def normalise_archives(streams: DataFrame, data_col: str = "data") -> DataFrame:
    """Rewrite any table of whole-file gzip WARC streams (binary column) record by record."""

    def run(batches):
        for batch in batches:
            for name, stream in zip(batch.column(0), batch.column(1)):
                data, index = normalise(stream.as_py() or b"")
                yield pa.RecordBatch.from_pydict({"archive": [name.as_py()], "data": [data], "index": [index]}, schema=pa.schema([("archive", pa.string()), ("data", pa.binary()), ("index", pa.binary())]))

    return streams.select(F.sha2(F.col(data_col), 256).alias("archive"), F.col(data_col).alias("data")).mapInArrow(run, ARCHIVES)
