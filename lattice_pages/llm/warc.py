"""WARC archives: writing, normalising and reading.

``write_archives`` writes one WARC file per task, as a single gzip stream. The
normaliser inflates such a whole-file stream once, rewrites every record as a gzip
member of its own, and writes a sidecar index of (id, offset, length), so that one
record can be read by its offset. ``read_records`` reads normalised archives through
their indexes.

Payloads that occur more than once are stored once: the row with the largest id is the
response, the others are revisits that name it. A revisit keeps the HTTP header of
its payload (with its length) and the digest, no body.

Files are written under another name in the shared folder and renamed when whole, with
a name that depends on the attempt; only files named in a finished task's output are
read, so lost executors and repeated attempts leave no duplicates. Any path that
``pyarrow.fs`` can open will do. Records are streamed: memory holds one record at a time.

Defined results: a null payload counts as empty; rows that repeat id and payload are
written once each, all as responses if theirs is the largest id; a null id sorts lowest; an
empty table gives no files and an empty table. Columns other than id, url and payload are not read.
"""

from __future__ import annotations

import base64
import hashlib
import io
import json
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lattice_pages.session import fresh_path, materialize

LEVEL = 3
CHUNK = 1 << 20
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "1970-01-01T00:00:00Z"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _uri(page_id: int | None) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def _page(uri: str) -> int | None:
    text = uri[len("<urn:page:") : -1]
    return int(text) if text else None


def record(page_id: int | None, url: str, payload: bytes, digest: str, refers_to: tuple[int | None] | None) -> bytes:
    """One WARC record; ``refers_to``: a one-tuple for a revisit, None for a response."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    body = http if refers_to else http + payload
    target = "".join(c if c > " " else f"%{ord(c):02X}" for c in url)
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if refers_to else 'response'}", f"WARC-Record-ID: {_uri(page_id)}", f"WARC-Target-URI: {target}", f"WARC-Date: {DATE}", f"WARC-Payload-Digest: sha1:{digest}"]
    if refers_to:
        head += [f"WARC-Refers-To: {_uri(refers_to[0])}", f"WARC-Profile: {PROFILE}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    return "\r\n".join(head).encode("utf-8") + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse_head(head: bytes) -> dict[str, str]:
    lines = head.decode("utf-8").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
    return {k.lower(): v for k, _, v in (x.partition(": ") for x in lines[1:]) if k}


def parse_body(head: dict[str, str], body: bytes) -> tuple[int, str, bytes]:
    """(payload length, digest, stored payload): a response's are computed, a revisit's are read."""
    http, _, payload = body.partition(b"\r\n\r\n")
    said = head["warc-payload-digest"].removeprefix("sha1:")
    if head["warc-type"] == "response":
        if base32_sha1(payload) != said:
            raise ValueError(f"payload digest differs: {head['warc-record-id']}")
        return len(payload), said, payload
    n = next(int(x.split(":")[1]) for x in http.decode("utf-8").split("\r\n") if x.lower().startswith("content-length"))
    return n, said, b""


def split_records(chunks: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes, bytes]]:
    """(head, whole record, body) of each record of an inflated stream."""
    held = bytearray()
    for more in chunks:
        held += more
        at = 0
        while (end := held.find(b"\r\n\r\n", at)) >= 0:
            head = parse_head(bytes(held[at:end]))
            stop = end + 4 + int(head["content-length"])
            if len(held) < stop + 4:
                break
            yield head, bytes(held[at : stop + 4]), bytes(held[end + 4 : stop])
            at = stop + 4
        del held[:at]
    if held:
        raise ValueError("the archive ends within a record")


def inflate(f, size: int = CHUNK) -> Iterator[bytes]:
    """The content of a gzip file of one or more members, read once from start to end."""
    z = zlib.decompressobj(31)
    while raw := f.read(size):
        while raw:
            yield z.decompress(raw)
            raw = z.unused_data
            if z.eof:
                z = zlib.decompressobj(31)


def member(data: bytes, level: int = LEVEL) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def normalise(source, target, level: int = LEVEL) -> list[tuple[str, int, int]]:
    """Rewrite a gzip WARC stream with one member per record; returns (record id, offset, length)."""
    index, at = [], 0
    for head, whole, _ in split_records(inflate(source)):
        packed = member(whole, level)
        target.write(packed)
        index.append((head["warc-record-id"], at, len(packed)))
        at += len(packed)
    return index


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path)


def write_archives(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """Write the archives; ``path, records`` of each (materialized)."""
    payload = F.coalesce(F.col(payload_col), F.lit("")).cast("binary")
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(url_col), F.lit("")).alias("url"), payload.alias("payload"), F.sha1(payload).alias("sha"))
    keys = pages.select(F.col(id_col).cast("long").alias("id"), F.sha1(payload).alias("sha"))
    first = keys.groupBy("sha").agg(F.max("id").alias("first"))
    rows = rows.join(first, "sha").select("id", "url", "payload", "first", F.col("id").eqNullSafe(F.col("first")).alias("own"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import uuid

        path, z, out, n = "", None, None, 0
        fs = None
        for b in batches:
            for page_id, url, body, first_id, own in zip(*(c.to_pylist() for c in b.columns)):
                if out is None:
                    path = f"{folder}/{uuid.uuid4().hex}.warc.gz"
                    fs, place = _open(path)
                    fs.create_dir(place.rsplit("/", 1)[0], recursive=True)
                    out, z = fs.open_output_stream(place + ".part", compression=None), zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
                out.write(z.compress(record(page_id, url, body, base32_sha1(body), None if own else (first_id,))))
                n += 1
        if out is not None:
            out.write(z.flush())
            out.close()
            fs.move(place + ".part", place)
            yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([n], pa.int64())], ["path", "records"])

    return materialize(rows.mapInArrow(run, "path string, records long"), "archives")


def normalise_archives(archives: DataFrame) -> DataFrame:
    """One normalised file and index per archive: ``path, index, records`` (materialized)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path in b.column(0).to_pylist():
                fs, place = _open(path)
                import uuid

                new = place.removesuffix(".warc.gz") + f".{uuid.uuid4().hex[:8]}.members"
                with fs.open_input_stream(place, compression=None) as source, fs.open_output_stream(new + ".part", compression=None) as target:
                    index = normalise(source, target)
                with fs.open_output_stream(new + ".idx.part", compression=None) as target:
                    target.write("".join(json.dumps(x) + "\n" for x in index).encode())
                fs.move(new + ".part", new + ".warc.gz")
                fs.move(new + ".idx.part", new + ".idx")
                base = path[: -len(place)]
                yield pa.RecordBatch.from_arrays([pa.array([base + new + ".warc.gz"]), pa.array([base + new + ".idx"]), pa.array([len(index)], pa.int64())], ["path", "index", "records"])

    n = archives.sparkSession.sparkContext.defaultParallelism
    return materialize(archives.select("path").repartition(4 * n).mapInArrow(run, "path string, index string, records long"), "normalised")


def read_at(f, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """One record of a normalised archive: its head and body."""
    f.seek(offset)
    data = zlib.decompress(f.read(length), 31)
    head, whole, body = next(split_records(iter([data])))
    return head, body


def read_records(normalised: DataFrame, keep_payload: bool = False) -> DataFrame:
    """Records of normalised archives, each read at the offset its index gives."""
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", *["payload"] * keep_payload]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), *[pa.binary()] * keep_payload]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, index in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                fs, place = _open(path)
                rows: list[tuple] = []
                with fs.open_input_file(place) as f, fs.open_input_stream(_open(index)[1], compression=None) as lines:
                    for line in io.TextIOWrapper(lines, encoding="utf-8"):
                        record_id, offset, length = json.loads(line)
                        head, body = read_at(f, offset, length)
                        if head["warc-record-id"] != record_id:
                            raise ValueError(f"the index of {path} is not its own")
                        n, digest, payload = parse_body(head, body)
                        to = _page(head["warc-refers-to"]) if "warc-refers-to" in head else None
                        rows.append((_page(record_id), n, digest, head["warc-type"], to, payload)[: len(names)])
                        if len(rows) >= (64 if keep_payload else 4096):
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)
                            rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)

    ddl = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long" + ", payload binary" * keep_payload
    n = normalised.sparkSession.sparkContext.defaultParallelism
    return normalised.select("path", "index").repartition(4 * n).mapInArrow(run, ddl)


def archive_roundtrip(pages: DataFrame, folder: str | None = None, keep_payload: bool = False) -> DataFrame:
    """Write, normalise, read back; ``folder``: where the archives stay."""
    folder = folder or fresh_path(pages.sparkSession, "warc")
    return read_records(normalise_archives(write_archives(pages, folder)), keep_payload)
