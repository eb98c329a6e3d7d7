"""WARC archives and a normaliser for monolithic gzip.

Pages become WARC records: a response with its payload, or a revisit without payload that refers to the response with the same digest. A writer task packs its records
into one gzip stream per archive, as naive tools do. The normaliser inflates such a whole-file stream once, in pieces of bounded size, cuts it into records as they
come, writes every record again as a gzip member of its own, and beside the archive an index with a line per record: offset, length, type, digest and
target. With the index any record can be read alone; the reader seeks to a member, inflates it and parses it.

Archives live in the shared folder the session names (or any folder that pyarrow's file systems reach); a file is written under a temporary name and moved into place,
so a task that is run again replaces what it left. Payloads cross the network once, to meet the row of their digest's group; a group that is large is split by the join.

Defined cases: null html is an empty payload; records with equal payloads, empty ones too, are grouped; a null page id is ordered last, and where all ids of a group are null each is a
response; rows that repeat the smallest id of their group are all responses; payloads below `least` bytes are always responses; an empty table makes no archive; other
columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..io import fresh_path, join_small, read_table, spread, stash
from .common import whole

PIECE = 1 << 20
#: Fixed values of the format.
VERSION, CRLF = b"WARC/1.1", b"\r\n"
REVISIT = b"http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = b"2024-01-01T00:00:00Z"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, digest: str, payload: bytes, refers_to: int | None, revisit: bool) -> bytes:
    """One WARC record. Its payload length stands in a header of its own, since a revisit has no payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    block = http if revisit else http + payload
    clean = (url or "").replace("\r", "%0D").replace("\n", "%0A").encode("utf-8", "replace")
    name = lambda i: b"<urn:page:" + (b"none" if i is None else str(i).encode()) + b">"
    head = [
        VERSION,
        b"WARC-Type: " + (b"revisit" if revisit else b"response"),
        b"WARC-Record-ID: " + name(page_id),
        b"WARC-Date: " + DATE,
        b"WARC-Target-URI: " + clean,
        b"WARC-Payload-Digest: sha1:" + digest.encode(),
        b"X-Payload-Length: " + str(len(payload)).encode(),
        b"Content-Type: application/http; msgtype=response",
        b"Content-Length: " + str(len(block)).encode(),
    ]
    if revisit:
        head += [b"WARC-Profile: " + REVISIT, b"WARC-Refers-To: " + name(refers_to)]
    return CRLF.join(head) + CRLF + CRLF + block + CRLF + CRLF


def parse_head(head: bytes) -> dict[bytes, bytes]:
    lines = head.split(CRLF)
    if lines[0] != VERSION:
        raise ValueError("not a WARC record")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in lines[1:])}


def inflate(read) -> Iterator[bytes]:
    """The content of a gzip stream of one or more members, in pieces of bounded size."""
    d = zlib.decompressobj(31)
    while data := read(PIECE):
        while data:
            yield d.decompress(data, PIECE)
            data = d.unconsumed_tail or d.unused_data
            if d.eof:
                d = zlib.decompressobj(31)
    if tail := d.flush():
        yield tail


def records(pieces: Iterator[bytes]) -> Iterator[tuple[bytes, dict[bytes, bytes]]]:
    """Whole records (bytes, head fields) of a stream. What is held is one record and a piece."""
    buf, at = bytearray(), 0
    need_head = True
    head: dict[bytes, bytes] = {}
    total = 0
    for piece in pieces:
        buf += piece
        while True:
            if need_head:
                end = buf.find(CRLF + CRLF, at)
                if end < 0:
                    break
                head = parse_head(bytes(buf[at:end]))
                total = end + 4 - at + int(head[b"content-length"]) + 4
                need_head = False
            if len(buf) - at < total:
                break
            yield bytes(buf[at : at + total]), head
            at += total
            need_head = True
        del buf[:at]
        at = 0
    if buf:
        raise ValueError("the archive ends inside a record")


def _page(name: bytes) -> int | None:
    said = name.removeprefix(b"<urn:page:").removesuffix(b">")
    return None if said in (b"none", b"") else int(said)


def _place(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri)


def _publish(fs: pafs.FileSystem, path: str, write) -> None:
    """Write under a name of this attempt's own, then move."""
    temp = f"{path}.{uuid.uuid4().hex}"
    with fs.open_output_stream(temp, compression=None) as f:
        write(f)
    fs.move(temp, path)


def grouped(pages: DataFrame, least: int = 0, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, payload, digest, refers_to, revisit). Only digests that occur twice are joined back; where they are few, payloads stay where they are."""
    payload = F.encode(whole(html_col), "UTF-8")
    base = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), payload.alias("payload"), F.sha1(payload).alias("digest"))
    first = base.groupBy(F.col("digest").alias("again")).agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("again", "first")
    revisit = F.coalesce((F.octet_length("payload") >= least) & F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")), F.lit(False))
    return join_small(base, stash(first, "repeated"), F.col("digest") == F.col("again")).select("page_id", "url", "payload", F.when(revisit, F.col("first")).alias("refers_to"), revisit.alias("revisit"))


def write_monolithic(rows: DataFrame, folder: str) -> DataFrame:
    """One gzip stream per task; returns (archive) of what was written."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = _place(folder)
        name = f"part-{TaskContext.get().partitionId():06d}.warc.gz"
        first = next(batches, None)
        while first is not None and not first.num_rows:
            first = next(batches, None)
        if first is None:
            return
        fs.create_dir(root, recursive=True)

        def write(f) -> None:
            z = zlib.compressobj(6, zlib.DEFLATED, 31)
            _pack(first, z, f)
            for b in batches:
                _pack(b, z, f)
            f.write(z.flush())

        _publish(fs, f"{root}/{name}", write)
        yield pa.RecordBatch.from_arrays([pa.array([name], pa.string())], names=["archive"])

    return rows.mapInArrow(run, "archive string")


def _pack(batch: pa.RecordBatch, z, f) -> None:
    cols = [batch.column(c) for c in ("page_id", "url", "payload", "refers_to", "revisit")]
    for k in range(batch.num_rows):
        page_id, url, payload, refers, revisit = (c[k].as_py() for c in cols)
        if out := z.compress(record(page_id, url, base32_sha1(payload), payload, refers, revisit)):
            f.write(out)


INDEX = "archive string, offset long, length long, record_type string, page_id long, digest string"


def normalise(archives: DataFrame, source: str, target: str, remove: bool = False) -> DataFrame:
    """Rewrites each archive of `source` with a gzip member per record under `target`, with its sidecar index `<archive>.idx`; returns (archive, records). remove: the
    original goes once archive and index are in place; a task that is run again finds the index and counts from it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (fs, root), (out_fs, out_root) = _place(source), _place(target)
        out_fs.create_dir(out_root, recursive=True)
        for b in batches:
            for name in b.column("archive").to_pylist():
                lines: list[bytes] = []
                if remove and fs.get_file_info(f"{root}/{name}").type == pafs.FileType.NotFound:
                    with out_fs.open_input_stream(f"{out_root}/{name}.idx", compression=None) as f:
                        lines = f.read().split(b"\n")[:-1]
                    yield pa.RecordBatch.from_arrays([pa.array([name], pa.string()), pa.array([len(lines)], pa.int64())], names=["archive", "records"])
                    continue

                def write(f, name: str = name, lines: list[bytes] = lines) -> None:
                    at = 0
                    with fs.open_input_stream(f"{root}/{name}", compression=None) as src:
                        for data, head in records(inflate(src.read)):
                            z = zlib.compressobj(6, zlib.DEFLATED, 31)
                            member = z.compress(data) + z.flush()
                            f.write(member)
                            lines.append(b"\t".join([str(at).encode(), str(len(member)).encode(), head[b"warc-type"], head[b"warc-record-id"], head[b"warc-payload-digest"], head[b"warc-target-uri"]]))
                            at += len(member)

                _publish(out_fs, f"{out_root}/{name}", write)
                _publish(out_fs, f"{out_root}/{name}.idx", lambda f, lines=lines: f.write(b"\n".join([*lines, b""])))
                if remove:
                    fs.delete_file(f"{root}/{name}")
                yield pa.RecordBatch.from_arrays([pa.array([name], pa.string()), pa.array([len(lines)], pa.int64())], names=["archive", "records"])

    return archives.mapInArrow(run, "archive string, records long")


def read_index(archives: DataFrame, folder: str) -> DataFrame:
    """(INDEX) rows of the sidecars."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = _place(folder)
        for b in batches:
            for name in b.column("archive").to_pylist():
                with fs.open_input_stream(f"{root}/{name}.idx", compression=None) as f:
                    rows = [x.split(b"\t") for x in f.read().split(b"\n")[:-1]]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([name] * len(rows), pa.string()), pa.array([int(r[0]) for r in rows], pa.int64()), pa.array([int(r[1]) for r in rows], pa.int64()), pa.array([r[2].decode() for r in rows], pa.string()), pa.array([_page(r[3]) for r in rows], pa.int64()), pa.array([r[4].decode() for r in rows], pa.string())],
                    names=["archive", "offset", "length", "record_type", "page_id", "digest"],
                )

    return archives.mapInArrow(run, INDEX)


def read_members(index: DataFrame, folder: str) -> DataFrame:
    """Reads the records that index rows name, each by seeking to its member: (page_id, url, record_type, payload_bytes, payload_digest, refers_to, payload).
    The digest of a response is computed from what was read; that of a revisit stands in its head."""
    schema = "page_id long, url string, record_type string, payload_bytes long, payload_digest string, refers_to long, payload binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = _place(folder)
        name, f = None, None
        for whole_batch in batches:
            for at in range(0, whole_batch.num_rows, 256):
                b = whole_batch.slice(at, 256)
                rows: list[tuple] = []
                for archive, offset, length in zip(*(b.column(c).to_pylist() for c in ("archive", "offset", "length")), strict=True):
                    if archive != name:
                        if f is not None:
                            f.close()
                        name, f = archive, fs.open_input_file(f"{root}/{archive}")
                    f.seek(offset)
                    data = zlib.decompress(f.read(length), 31)
                    cut = data.index(CRLF + CRLF)
                    head = parse_head(data[:cut])
                    block = data[cut + 4 : cut + 4 + int(head[b"content-length"])]
                    payload = block[block.index(CRLF + CRLF) + 4 :]
                    kind = head[b"warc-type"].decode()
                    said = head[b"warc-payload-digest"].removeprefix(b"sha1:").decode()
                    if kind == "response" and said != base32_sha1(payload):
                        raise ValueError(f"{archive} at {offset}: the payload does not have its digest")
                    rows.append((_page(head[b"warc-record-id"]), head[b"warc-target-uri"].decode(), kind, int(head[b"x-payload-length"]), said, _page(head.get(b"warc-refers-to", b"")), payload if kind == "response" else None))
                kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True) if rows else [[]] * 7, kinds, strict=True)], names=["page_id", "url", "record_type", "payload_bytes", "payload_digest", "refers_to", "payload"])
        if f is not None:
            f.close()

    return index.mapInArrow(run, schema)


def archive(pages: DataFrame, folder: str, least: int = 0, **cols: str) -> DataFrame:
    """Write pages as monolithic archives, normalise them, and return the index, stashed."""
    raw, out = f"{folder}/monolithic", f"{folder}/normalised"
    written = stash(write_monolithic(grouped(spread(pages), least, **cols), raw), "written")
    done = stash(normalise(spread(written), raw, out, remove=True), "normalised")
    return stash(read_index(done.select("archive"), out), "index")


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = fresh_path(spark, "warc")
    index = archive(read_table(spark, sf_dir, "pages", ["page_id", "url", "html"]), folder)
    back = read_members(index, f"{folder}/normalised")
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")
