"""Media columns: AVI with motion-JPEG.

Read side: the RIFF chunks and the idx1 index of an AVI give its frames; intra frames are decoded to quantised DCT coefficients (baseline, Huffman) and
for shots to grey values; shots end where the histogram difference of neighbouring frames exceeds the mean of recent differences by a multiple of their deviation; every shot is a
timed clip row.

Write side, used to keep a payload losslessly: the unit of baseline JPEG is the 8 x 8 block of 64 quantised coefficients, so 64 bytes make one grey block
with unit quantisation. A byte goes into a coefficient of magnitude category 8, whose eight extra bits are the byte itself; the only Huffman code in use has eight bits, so
a block is 64 (code, byte) pairs. A restart marker after every block resets the prediction of its first coefficient. Any baseline decoder reads
such frames; ours takes an array path when a scan has this shape and walks bit by bit otherwise.

Defined cases: a null text counts as empty; an empty payload still makes one block; texts of any length are stored whole (up to the 4 GB of a RIFF file); repeated rows give equal
values; an empty table gives an empty result; other columns are not read. A file that is no AVI, or a frame that cannot be decoded, raises.
"""

from __future__ import annotations

import functools
import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..io import read_table, spread
from .common import whole

BLOCKS = 64  # blocks in a frame, so 4096 bytes of payload
FPS = 25
#: Fixed values of the formats.
MARK_SOI, MARK_EOI = b"\xff\xd8", b"\xff\xd9"
CATEGORY = 8


def _segment(mark: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, mark, len(body) + 2) + body


def _head(blocks: int) -> bytes:
    table = bytes([0] * 7 + [1] + [0] * 8) + bytes([CATEGORY])  # one code of eight bits
    return (
        MARK_SOI
        + _segment(0xDB, b"\0" + b"\1" * 64)
        + _segment(0xC0, struct.pack(">BHHBBBB", 8, 8, 8 * blocks, 1, 1, 0x11, 0))
        + _segment(0xC4, b"\x00" + table)
        + _segment(0xC4, b"\x10" + table)
        + _segment(0xDD, struct.pack(">H", 1))
        + _segment(0xDA, b"\1\1\0\0\x3f\0")
    )


def encode_frame(payload: np.ndarray) -> bytes:
    """One frame from bytes (a multiple of 64)."""
    blocks = len(payload) // 64
    pairs = np.zeros((blocks, 130), np.uint8)
    pairs[:, 1:128:2] = payload.reshape(blocks, 64)
    pairs[:, 128], pairs[:, 129] = 0xFF, 0xD0 + np.arange(blocks) % 8
    if (payload != 0xFF).all():
        scan = pairs.tobytes()
    else:  # a data byte of 255 is followed by a stuffed zero
        scan = b"".join(row[:128].tobytes().replace(b"\xff", b"\xff\0") + row[128:].tobytes() for row in pairs)
    return _head(blocks) + scan[:-2] + MARK_EOI


def encode_avi(payload: bytes, blocks: int = BLOCKS, fps: int = FPS) -> bytes:
    """An AVI of grey frames that hold the payload; its length is kept in a chunk of its own, the last frame is filled with zeros."""
    blocks = max(1, min(blocks, -(-len(payload) // 64)))
    size = 64 * blocks
    frames = [encode_frame(np.frombuffer(payload[at : at + size].ljust(size, b"\0"), np.uint8)) for at in range(0, max(len(payload), 1), size)]
    width, height, most = 8 * blocks, 8, max(map(len, frames))
    chunk = lambda name, body: name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) % 2)
    group = lambda kind, name, body: chunk(kind, name + body)
    avih = struct.pack("<14I", 1_000_000 // fps, most * fps, 0, 0x10, len(frames), 0, 1, most, width, height, 0, 0, 0, 0)
    strh = struct.pack("<4s4sIHHIIIIIIIIhhhh", b"vids", b"MJPG", 0, 0, 0, 0, 1, fps, 0, len(frames), most, 0xFFFFFFFF, 0, 0, 0, width, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 8, b"MJPG", width * height, 0, 0, 0, 0)
    head = group(b"LIST", b"hdrl", chunk(b"avih", avih) + group(b"LIST", b"strl", chunk(b"strh", strh) + chunk(b"strf", strf)) + chunk(b"size", struct.pack("<Q", len(payload))))
    movi, index, at = [], [], 4
    for f in frames:
        c = chunk(b"00dc", f)
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(f)))
        movi.append(c)
        at += len(c)
    return group(b"RIFF", b"AVI ", head + group(b"LIST", b"movi", b"".join(movi)) + chunk(b"idx1", b"".join(index)))


def parse_avi(data: bytes) -> dict:
    """fps, frames (memory views) and payload size if kept. Frames come from idx1 (offsets from the movi list or the file); without an index the list is walked."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    out: dict = {"fps": 25.0, "size": None}
    view, movi, index = memoryview(data), None, None

    def walk(at: int, end: int) -> None:
        nonlocal movi, index
        while at + 8 <= end:
            name, n = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
            if name == b"LIST":
                if data[at + 8 : at + 12] == b"movi":
                    movi = (at + 8, min(end, at + 8 + n))
                else:
                    walk(at + 12, min(end, at + 8 + n))
            elif name == b"strh" and data[at + 8 : at + 12] == b"vids":
                scale, rate = struct.unpack_from("<II", data, at + 28)
                out["fps"] = rate / scale if scale and rate else out["fps"]
            elif name == b"size" and n == 8:
                out["size"] = struct.unpack_from("<Q", data, at + 8)[0]
            elif name == b"idx1":
                index = (at + 8, n)
            at += 8 + n + n % 2

    frames: list[memoryview] = []
    top = 0
    while data[top : top + 4] == b"RIFF" and top + 12 <= len(data):  # a large file goes on in further segments, which the index does not list
        end = min(len(data), top + 8 + struct.unpack_from("<I", data, top + 4)[0])
        movi, index = None, None
        walk(top + 12, end)
        frames += _frames_of(data, view, movi, index)
        top = end + end % 2
    out["frames"] = frames
    return out


def _frames_of(data: bytes, view: memoryview, movi: tuple[int, int] | None, index: tuple[int, int] | None) -> list[memoryview]:
    frames = []
    if movi and index:
        for at in range(index[0], index[0] + index[1] - 15, 16):
            name, _, start, n = struct.unpack_from("<4sIII", data, at)
            if name[2:] in (b"dc", b"db"):
                base = movi[0] + start if data[movi[0] + start : movi[0] + start + 4] == name else start
                frames.append(view[base + 8 : base + 8 + n])
    elif movi:
        at = movi[0] + 4
        while at + 8 <= movi[1]:
            name, n = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
            if name == b"LIST":  # frames may be grouped in records
                at += 12
                continue
            if name[2:] in (b"dc", b"db"):
                frames.append(view[at + 8 : at + 8 + n])
            at += 8 + n + n % 2
    return frames


def _codes(counts: bytes, values: bytes) -> dict[tuple[int, int], int]:
    """Huffman codes (length, code) -> value."""
    codes, code, k = {}, 0, 0
    for bits in range(1, 17):
        for _ in range(counts[bits - 1]):
            codes[bits, code] = values[k]
            code, k = code + 1, k + 1
        code <<= 1
    return codes


@functools.cache
def _standard_tables() -> dict[int, dict[tuple[int, int], int]]:
    """The tables that the JPEG standard lists (K.3), for frames that carry none, as is usual in motion-JPEG."""
    dc = [("00010501010101010100000000000000", "000102030405060708090a0b"), ("00030101010101010101010000000000", "000102030405060708090a0b")]
    ac = [
        (
            "0002010303020403050504040000017d",
            "01020300041105122131410613516107227114328191a1082342b1c11552d1f02433627282090a161718191a25262728292a3435363738393a434445464748494a535455565758595a636465666768696a737475767778797a"
            "838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aab2b3b4b5b6b7b8b9bac2c3c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae1e2e3e4e5e6e7e8e9eaf1f2f3f4f5f6f7f8f9fa",
        ),
        (
            "00020102040403040705040400010277",
            "000102031104052131061241510761711322328108144291a1b1c109233352f0156272d10a162434e125f11718191a262728292a35363738393a434445464748494a535455565758595a636465666768696a737475767778797a"
            "82838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aab2b3b4b5b6b7b8b9bac2c3c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae2e3e4e5e6e7e8e9eaf2f3f4f5f6f7f8f9fa",
        ),
    ]
    return {16 * kind + k: _codes(bytes.fromhex(n), bytes.fromhex(v)) for kind, pair in enumerate((dc, ac)) for k, (n, v) in enumerate(pair)}


def decode_frame(jpeg: bytes) -> np.ndarray:
    """Quantised coefficients (block, 64 in zigzag order) of the first component of a baseline frame."""
    jpeg, at = bytes(jpeg), 2
    if jpeg[:2] != MARK_SOI:
        raise ValueError("not a JPEG frame")
    tables: dict[int, dict[tuple[int, int], int]] = dict(_standard_tables())
    shape, comps, restart = (0, 0), [], 0
    while True:
        mark, n = jpeg[at + 1], struct.unpack_from(">H", jpeg, at + 2)[0]
        body = jpeg[at + 4 : at + 2 + n]
        at += 2 + n
        if mark == 0xC0 or mark == 0xC1:
            shape = struct.unpack_from(">HH", body, 1)
            comps = [(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15) for k in range(body[5])]
        elif 0xC2 <= mark <= 0xCF and mark not in (0xC4, 0xC8, 0xCC):
            raise ValueError("only baseline frames are decoded")
        elif mark == 0xC4:
            while body:
                k = 17 + sum(body[1:17])
                tables[body[0]] = _codes(body[1:17], body[17:k])
                body = body[k:]
        elif mark == 0xDD:
            restart = struct.unpack(">H", body)[0]
        elif mark == 0xDA:
            use = {body[1 + 2 * k]: body[2 + 2 * k] for k in range(body[0])}
            break
    end = jpeg.rfind(MARK_EOI)
    scan = jpeg[at : end if end >= 0 else len(jpeg)]
    only = {(8, 0): CATEGORY}
    if len(comps) == 1 and restart == 1 and tables.get(0) == only and tables.get(16) == only:
        return _decode_pairs(scan, -(-shape[0] // 8) * -(-shape[1] // 8))
    return _decode_bits(scan, shape, comps, use, tables, restart)


def _decode_pairs(scan: bytes, blocks: int) -> np.ndarray:
    """Blocks of 64 (code, byte) pairs between restart markers."""
    if len(scan) + 2 == 130 * blocks:
        raw = np.frombuffer(scan + b"\xff\xd0", np.uint8).reshape(blocks, 130)[:, 1:128:2]
    else:
        parts, at = [], 0
        for _ in range(blocks):
            stop = at
            while not ((stop := scan.find(b"\xff", stop)) < 0 or 0xD0 <= scan[stop + 1] <= 0xD7):
                stop += 2
            stop = len(scan) if stop < 0 else stop
            parts.append(np.frombuffer(scan[at:stop].replace(b"\xff\0", b"\xff"), np.uint8)[1::2])
            at = stop + 2
        raw = np.stack(parts)
    v = raw.astype(np.int16)
    return np.where(v >= 128, v, v - 255)


def _lookup(codes: dict[tuple[int, int], int]) -> np.ndarray:
    """For every 16 bits the code they begin with, as 256 * its length + its value; -1 if there is none."""
    out = np.full(1 << 16, -1, np.int32)
    for (n, code), v in codes.items():
        out[code << (16 - n) : (code + 1) << (16 - n)] = n << 8 | v
    return out


def _pieces(scan: bytes) -> Iterator[bytes]:
    """The stretches between restart markers, without stuffed zeros."""
    start = at = 0
    while (at := scan.find(b"\xff", at)) >= 0:
        if at + 1 < len(scan) and 0xD0 <= scan[at + 1] <= 0xD7:
            yield scan[start:at].replace(b"\xff\0", b"\xff")
            start = at + 2
        at += 2
    yield scan[start:].replace(b"\xff\0", b"\xff")


def _decode_bits(scan: bytes, shape: tuple[int, int], comps: list, use: dict, tables: dict, restart: int) -> np.ndarray:
    h, v = max(c[1] for c in comps), max(c[2] for c in comps)
    if len(comps) == 1:
        comps, h, v = [(comps[0][0], 1, 1)], 1, 1
    units = -(-shape[0] // (8 * v)) * -(-shape[1] // (8 * h))
    find = {k: _lookup(codes) for k, codes in tables.items()}
    out, unit = [], 0
    for data in _pieces(scan):
        total, pos = 8 * len(data), 0
        data += b"\0\0\0\0"

        def peek(n: int) -> int:
            """The next n (at most 16) bits, zeros behind the end; three bytes hold them, so the cost does not depend on the scan's length."""
            at = pos >> 3
            return (int.from_bytes(data[at : at + 3], "big") >> (24 - (pos & 7) - n)) & ((1 << n) - 1) if at < len(data) else 0

        def symbol(table: np.ndarray) -> int:
            nonlocal pos
            found = int(table[peek(16)])
            if found < 0 or pos > total:
                raise ValueError("a code that is in no table")
            pos += found >> 8
            return found & 255

        def value(n: int) -> int:
            nonlocal pos
            x = peek(n) if n else 0
            pos += n
            return x if not n or x >> (n - 1) else x - (1 << n) + 1

        before = dict.fromkeys(use, 0)
        for _ in range(restart or units):
            if unit >= units:
                break
            unit += 1
            for cid, ch, cv in comps:
                dc, ac = find[use[cid] >> 4], find[16 + (use[cid] & 15)]
                for _ in range(ch * cv):
                    block = np.zeros(64, np.int16)
                    before[cid] += value(symbol(dc))
                    block[0], at = before[cid], 1
                    while at < 64:
                        s = symbol(ac)
                        if s == 0:
                            break
                        at += s >> 4
                        if s & 15:
                            block[at] = value(s & 15)
                        at += 1
                    if cid == comps[0][0]:
                        out.append(block)
    return np.array(out, np.int16).reshape(-1, 64)


def payload_of(data: bytes) -> tuple[bytes, list[np.ndarray]]:
    """The payload that encode_avi() stored, and the frames' coefficients."""
    avi = parse_avi(data)
    frames = [decode_frame(f) for f in avi["frames"]]
    raw = np.concatenate([np.where(f < 0, f + 255, f).astype(np.uint8).ravel() for f in frames])
    return raw.tobytes()[: avi["size"]], frames


def _quantisers(jpeg: bytes) -> np.ndarray:
    """The 64 steps (zigzag order) of the first component; ones if a frame has no table."""
    jpeg, at, tables, use = bytes(jpeg), 2, {}, 0
    while jpeg[at + 1] != 0xDA:
        n = struct.unpack_from(">H", jpeg, at + 2)[0]
        body = jpeg[at + 4 : at + 2 + n]
        if jpeg[at + 1] in (0xC0, 0xC1):
            use = body[8]
        while jpeg[at + 1] == 0xDB and body:
            wide = body[0] >> 4
            tables[body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else "u1").astype(np.float32)
            body = body[65 + 64 * wide :]
        at += 2 + n
    return tables.get(use, np.ones(64, np.float32))


@functools.cache
def _inverse_dct() -> np.ndarray:
    """[64 coefficients in zigzag order, 64 pixels]."""
    x = np.arange(8)
    wave = np.cos((2 * x[None, :] + 1) * x[:, None] * np.pi / 16) / 2
    wave[0] /= np.sqrt(2)
    zigzag = sorted(((r, c) for r in range(8) for c in range(8)), key=lambda p: (p[0] + p[1], p[0] if (p[0] + p[1]) % 2 else p[1]))
    return np.stack([np.outer(wave[r], wave[c]).ravel() for r, c in zigzag]).astype(np.float32)


def pixels(jpeg: bytes, coefficients: np.ndarray | None = None) -> np.ndarray:
    """Grey values (block, 64) of the first component, from its coefficients if they are decoded already."""
    q = decode_frame(jpeg) if coefficients is None else coefficients
    return np.clip(np.rint((q * _quantisers(jpeg)) @ _inverse_dct() + 128), 0, 255).astype(np.uint8)


def shots(frames: list[np.ndarray], bins: int = 32, window: int = 8, reach: float = 3.0, least: float = 0.15) -> list[tuple[int, int]]:
    """[first, last) of each shot of frames of grey values. The difference of two frames is half the sum of absolute differences of their normalised histograms; a cut is where it is
    over `least` and over mean + reach * deviation of the last `window` differences of the running shot."""
    hist = [np.bincount(f.ravel().astype(np.int64) * bins // 256, minlength=bins) / max(f.size, 1) for f in frames]
    cuts, recent = [0], []
    for k in range(1, len(hist)):
        d = float(np.abs(hist[k] - hist[k - 1]).sum()) / 2
        if d > least and (len(recent) < 2 or d > np.mean(recent) + reach * np.std(recent)):
            cuts.append(k)
            recent = []
        else:
            recent = [*recent[-window + 1 :], d]
    return list(zip(cuts, [*cuts[1:], len(frames)], strict=True))


def clip_rows(grey: list[np.ndarray], fps: float, **params) -> list[dict]:
    """The shots of frames as timed clips."""
    return [{"clip": k, "start_s": lo / fps, "end_s": hi / fps, "n_frames": hi - lo} for k, (lo, hi) in enumerate(shots(grey, **params))]


CLIP = pa.struct([("clip", pa.int32()), ("start_s", pa.float64()), ("end_s", pa.float64()), ("n_frames", pa.int32())])


def clips(media: DataFrame, id_col: str, avi_col: str, **params) -> DataFrame:
    """(id, clip, start_s, end_s, n_frames): a row per shot of each AVI; a null AVI gives none."""
    df = media.select(F.col(id_col).alias("id"), F.col(avi_col).alias("avi"))
    kind = dict(df.dtypes)["id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, data in zip(b.column("id").to_pylist(), b.column("avi"), strict=True):
                if data.is_valid:
                    avi = parse_avi(data.as_py())
                    found = pa.array(clip_rows([pixels(f) for f in avi["frames"]], avi["fps"], **params), CLIP)
                    ids = pa.array([i] * len(found), b.schema.field("id").type)
                    yield pa.RecordBatch.from_arrays([ids, *found.flatten()], names=["id", "clip", "start_s", "end_s", "n_frames"])

    return df.mapInArrow(run, f"id {kind}, clip int, start_s double, end_s double, n_frames int")


def store(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, avi): every whole text as payload, filled with zero bytes to a positive multiple of 64."""
    df = spread(docs.select(F.col(id_col).alias("doc_id"), F.encode(whole(text_col), "UTF-8").alias("raw")))
    kind = dict(df.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                raw = part.column("raw").to_pylist()
                avi = [encode_avi(r.ljust(max(64, -(-len(r) // 64) * 64), b"\0")) for r in raw]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(map(len, raw), pa.int64()), pa.array(avi, pa.binary())], names=["doc_id", "n_bytes", "avi"])

    return df.mapInArrow(run, f"doc_id {kind}, n_bytes long, avi binary")


def inspect(stored: DataFrame) -> DataFrame:
    """Reads the stored bytes back: payload digests, the stored form's digests, as feature the number of frames and the clips in milliseconds, and the timed clips."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "clips"]
    kind = dict(stored.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols: list[list] = [[] for _ in range(7)]
            for data in b.column("avi").to_pylist():
                payload, frames = payload_of(data)
                avi = parse_avi(data)
                found = clip_rows([pixels(j, q) for j, q in zip(avi["frames"], frames, strict=True)], avi["fps"])
                said = ";".join(f"{round(c['start_s'] * 1000)}-{round(c['end_s'] * 1000)}" for c in found)
                values = len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(data), hashlib.sha256(data).hexdigest(), f"frames={len(frames)};clips={said}", found
                for c, x in zip(cols, values, strict=True):
                    c.append(x)
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(CLIP)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("n_bytes"), *[pa.array(c, k) for c, k in zip(cols, kinds, strict=True)]], names=names)

    return stored.mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, clips array<struct<clip:int,start_s:double,end_s:double,n_frames:int>>")


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return inspect(store(read_table(spark, sf_dir, "documents", ["doc_id", "text"])))
