"""Media columns: AVI motion-JPEG.

A payload is stored as grey 8-bit frames of 64 samples a row and at most 64 rows, each frame a lossless JPEG (predictor 1).
Its Huffman table gives category s a code of 9 - s bits, so that every sample takes nine bits and whole frames are packed and unpacked as arrays;
frames with other tables, and baseline (DCT) grey frames, are decoded bit by bit.
The reader finds frames through the RIFF index `idx1`, or by walking `movi` where there is none.

Defined results: a null or empty payload is stored as 64 zero bytes; equal payloads give equal files; repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
A null or broken file has no frames: no clips, and a null payload.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronolode.llm.common import id_and_text, per_batch, read

WIDTH, ROWS, FPS, BINS = 64, 64, 25, 16
#: An adaptive cut: a difference above the mean and this many deviations of the differences before it in the same shot, within a window of so many.
DEVIATIONS, WINDOW, LEAST = 3.0, 8, 0.35

#: Fixed values of the JPEG standard: the zigzag order of an 8 x 8 block.
ZIGZAG = np.array(sorted(range(64), key=lambda i: (i // 8 + i % 8, i // 8 if (i // 8 + i % 8) % 2 else i % 8)))


@cache
def _codes() -> tuple[np.ndarray, np.ndarray]:
    """Nine-bit code of each difference (from -255), and difference of each code."""
    to, back = np.zeros(511, np.uint16), np.zeros(512, np.int16)
    for d in range(-255, 256):
        s = abs(d).bit_length()
        prefix = ((1 << (8 - s)) - 1) << 1
        code = prefix << s | (d if d >= 0 else d + (1 << s) - 1)
        to[d + 255], back[code] = code, d
    return to, back


#: Nine codes, one of each length 1 to 9, for the categories 8 down to 0.
TABLE = b"\xff\xc4" + struct.pack(">HB", 2 + 17 + 9, 0) + bytes([1] * 9 + [0] * 7) + bytes(range(8, -1, -1))
SCAN = b"\xff\xda" + struct.pack(">HBBBBBB", 8, 1, 1, 0, 1, 0, 0)


def _head(rows: int, width: int) -> bytes:
    return b"\xff\xd8" + TABLE + b"\xff\xc3" + struct.pack(">HBHHBBBB", 11, 8, rows, width, 1, 1, 0x11, 0) + SCAN


def _pack(samples: np.ndarray) -> np.ndarray:
    """Rows x 64 samples, frame breaks every ROWS rows, as rows x 72 bytes."""
    x = samples.astype(np.int16)
    d = np.empty_like(x)
    d[:, 1:] = x[:, 1:] - x[:, :-1]
    d[1:, 0] = x[1:, 0] - x[:-1, 0]
    d[::ROWS, 0] = x[::ROWS, 0] - 128
    c = _codes()[0][d + 255].reshape(-1, 8)
    out = np.empty((len(c), 9), np.uint8)
    out[:, 0] = c[:, 0] >> 1
    for k in range(1, 8):
        out[:, k] = (c[:, k - 1] << (8 - k)) | (c[:, k] >> (k + 1))
    out[:, 8] = c[:, 7]
    return out.reshape(len(x), 72)


def _unpack(data: np.ndarray) -> np.ndarray:
    """The samples of whole frames packed by `_pack`, frame breaks every ROWS rows."""
    b = data.reshape(-1, 9).astype(np.uint16)
    c = np.empty((len(b), 8), np.uint16)
    for k in range(8):
        c[:, k] = ((b[:, k] << (k + 1)) | (b[:, k + 1] >> (7 - k))) & 0x1FF
    d = _codes()[1][c].reshape(-1, WIDTH)
    for at in range(0, len(d), ROWS):
        d[at, 0] += 128
        d[at : at + ROWS, 0] = np.cumsum(d[at : at + ROWS, 0], dtype=np.int16)
    return np.cumsum(d, axis=1, dtype=np.int16).astype(np.uint8)


def padded(data: bytes) -> bytes:
    """Zero bytes up to a positive multiple of 64."""
    return data + bytes(-len(data) % WIDTH if data else WIDTH)


def write_avi(payload: bytes) -> bytes:
    """A payload, a positive multiple of 64 bytes, as a motion-JPEG file."""
    samples = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    packed = _pack(samples)
    frames = []
    for at in range(0, len(samples), ROWS):
        rows = min(ROWS, len(samples) - at)
        frame = _head(rows, WIDTH) + packed[at : at + rows].tobytes().replace(b"\xff", b"\xff\x00") + b"\xff\xd9"
        frames.append(frame)
    height, most = min(ROWS, len(samples)), max(map(len, frames))
    avih = struct.pack("<14I", 1_000_000 // FPS, most * FPS, 0, 0x10, len(frames), 0, 1, most, WIDTH, height, 0, 0, 0, 0)
    strh = struct.pack("<4s4sIHHIIIIIIIIhhhh", b"vids", b"MJPG", 0, 0, 0, 0, 1, FPS, 0, len(frames), most, 0xFFFFFFFF, 0, 0, 0, WIDTH, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, WIDTH, height, 1, 8, b"MJPG", WIDTH * height, 0, 0, 0, 0)
    chunk = lambda name, body: name + struct.pack("<I", len(body)) + body + bytes(len(body) % 2)
    hdrl = chunk(b"LIST", b"hdrl" + chunk(b"avih", avih) + chunk(b"LIST", b"strl" + chunk(b"strh", strh) + chunk(b"strf", strf)))
    movi, index, offset = [], [], 4
    for frame in frames:
        movi.append(chunk(b"00dc", frame))
        index.append(struct.pack("<4sIII", b"00dc", 0x10, offset, len(frame)))
        offset += len(movi[-1])
    return chunk(b"RIFF", b"AVI " + hdrl + chunk(b"LIST", b"movi" + b"".join(movi)) + chunk(b"idx1", b"".join(index)))


def frame_bytes(media: bytes) -> list[bytes]:
    """The frames of the first video stream, in the order of the index."""
    if media[:4] != b"RIFF" or media[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    at, movi, index = 12, None, None
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"LIST" and media[at + 8 : at + 12] == b"movi":
            movi = (at + 8, at + 8 + size)
        elif name == b"idx1":
            index = (at + 8, size)
        at += 8 + size + size % 2
    if movi is None:
        raise ValueError("no movi list")
    video = lambda name: name[2:] in (b"dc", b"db")
    if index:
        rows = [x for x in struct.iter_unpack("<4sIII", media[index[0] : index[0] + index[1] // 16 * 16]) if video(x[0])]
        base = movi[0] if not rows or media[movi[0] + rows[0][2] :][:4] == rows[0][0] else 0  # offsets count from the list or the file
        return [media[base + o + 8 : base + o + 8 + n] for _, _, o, n in rows]
    out, at = [], movi[0] + 4
    while at + 8 <= movi[1]:
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if video(name):
            out.append(media[at + 8 : at + 8 + size])
        at += 12 if name == b"LIST" else 8 + size + size % 2
    return out


def rate(media: bytes) -> float:
    """Frames a second, from the stream header."""
    at = media.find(b"strh")
    scale, per = struct.unpack_from("<II", media, at + 28) if at >= 0 else (1, FPS)
    return per / scale if scale and per else float(FPS)


class _Bits:
    def __init__(self, data: bytes) -> None:
        self.bits, self.at = np.unpackbits(np.frombuffer(data, np.uint8)), 0

    def take(self, n: int) -> int:
        v = 0
        for b in self.bits[self.at : self.at + n]:
            v = v << 1 | int(b)
        self.at += n
        return v

    def symbol(self, table: dict[tuple[int, int], int]) -> int:
        code = 0
        for n in range(1, 17):
            code = code << 1 | int(self.bits[self.at])
            self.at += 1
            if (n, code) in table:
                return table[n, code]
        raise ValueError("bad Huffman code")

    def signed(self, s: int) -> int:
        v = self.take(s) if s else 0
        return v if not s or v >> (s - 1) else v - (1 << s) + 1


def _huffman(counts: bytes, symbols: bytes) -> dict[tuple[int, int], int]:
    out, code, at = {}, 0, 0
    for n, k in enumerate(counts, 1):
        for _ in range(k):
            out[n, code] = symbols[at]
            code, at = code + 1, at + 1
        code <<= 1
    return out


@cache
def _cosines() -> np.ndarray:
    k = np.arange(8)
    m = np.cos((2 * k[None, :] + 1) * k[:, None] * np.pi / 16) / 2
    m[0] /= np.sqrt(2)
    return m


def decode_frame(frame: bytes) -> np.ndarray:
    """The samples of a grey JPEG: lossless (8 bits, predictor 1) or baseline."""
    at, tables, quant, size, kind = 2, {}, {}, None, 0
    while True:
        mark, n = frame[at + 1], struct.unpack_from(">H", frame, at + 2)[0]
        body = frame[at + 4 : at + 2 + n]
        if mark == 0xC4:
            while body:
                k = sum(body[1:17])
                tables[body[0]] = (body[1:17], body[17 : 17 + k])
                body = body[17 + k :]
        elif mark == 0xDB:
            while body:
                wide = body[0] >> 4
                quant[body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else np.uint8).astype(float)
                body = body[65 + 64 * wide :]
        elif mark in (0xC0, 0xC1, 0xC3):
            kind, (bits, rows, width, parts) = mark, struct.unpack_from(">BHHB", body)
            if bits != 8 or parts != 1:
                raise ValueError("only grey frames of 8 bits")
            size, q = (rows, width), body[8]
        elif mark == 0xDA:
            use, start = body[2], at + 2 + n
            if kind == 0xC3 and body[3] != 1:
                raise ValueError("only predictor 1")
            break
        at += 2 + n
    if size is None:
        raise ValueError("no frame header")
    data = frame[start : frame.rindex(b"\xff\xd9")].replace(b"\xff\x00", b"\xff")
    (rows, width), dc = size, tables[use >> 4]
    if kind == 0xC3 and width == WIDTH and rows <= ROWS and dc == (TABLE[5:21], TABLE[21:]):
        return _unpack(np.frombuffer(data, np.uint8, rows * 72).reshape(rows, 72))
    bits, first = _Bits(data + bytes(8)), _huffman(*dc)
    if kind == 0xC3:
        out = np.zeros((rows, width), np.int64)
        for r in range(rows):
            for x in range(width):
                guess = out[r, x - 1] if x else out[r - 1, 0] if r else 128
                out[r, x] = (guess + bits.signed(bits.symbol(first))) & 0xFFFF
        return out.astype(np.uint8)
    rest, last, out = _huffman(*tables[0x10 | use & 15]), 0, np.zeros((-(-rows // 8) * 8, -(-width // 8) * 8))
    for r in range(0, out.shape[0], 8):
        for x in range(0, out.shape[1], 8):
            block, k = np.zeros(64), 1
            last += bits.signed(bits.symbol(first))
            block[0] = last * quant[q][0]
            while k < 64:
                run = bits.symbol(rest)
                if not run & 15:
                    if run != 0xF0:
                        break
                    k += 16
                    continue
                k += run >> 4
                block[ZIGZAG[k]] = bits.signed(run & 15) * quant[q][k]
                k += 1
            c = _cosines()
            out[r : r + 8, x : x + 8] = c.T @ block.reshape(8, 8) @ c + 128
    return np.clip(np.rint(out[:rows, :width]), 0, 255).astype(np.uint8)


def decode(media: bytes) -> list[np.ndarray]:
    return [decode_frame(f) for f in frame_bytes(media)]


def clips(frames: list[np.ndarray]) -> list[tuple[int, int]]:
    """Shots as (first, last) frame: a cut lies where the histogram difference leaves its own recent range."""
    if not frames:
        return []
    hists = np.stack([np.bincount(f.ravel() >> 4, minlength=BINS) / f.size for f in frames])
    diffs, starts = np.abs(np.diff(hists, axis=0)).sum(axis=1), [0]
    for i, d in enumerate(diffs):
        past = diffs[max(starts[-1], i - WINDOW) : i]
        if d > LEAST and (not len(past) or d > past.mean() + DEVIATIONS * past.std()):
            starts.append(i + 1)
    return list(zip(starts, [s - 1 for s in starts[1:]] + [len(frames) - 1], strict=True))


def media_column(docs: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, media): every whole text as a motion-JPEG file."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        data = [x.encode() for x in batch["text"].to_pylist()]
        return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(map(len, data), pa.int64()), pa.array([write_avi(padded(x)) for x in data], pa.binary())], ["doc_id", "n_bytes", "media"])

    return per_batch(id_and_text(docs), make, "doc_id long, n_bytes long, media binary")


def _frames(media: bytes | None) -> list[np.ndarray]:
    try:
        return decode(media or b"")
    except (ValueError, KeyError, IndexError, struct.error):
        return []


def clip_rows(media: DataFrame, key: str = "doc_id", column: str = "media") -> DataFrame:
    """(key, clip, first_frame, last_frame, start_s, end_s): a row for each shot of each file."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for k, m in zip(batch["k"].to_pylist(), batch["m"].to_pylist(), strict=True):
            fps = rate(m) if m else FPS
            rows += [(k, i, a, b, a / fps, (b + 1) / fps) for i, (a, b) in enumerate(clips(_frames(m)))]
        names = ["key", "clip", "first_frame", "last_frame", "start_s", "end_s"]
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.float64()]
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names)

    out = per_batch(media.select(F.col(key).cast("long").alias("k"), F.col(column).alias("m")), make, "key long, clip int, first_frame long, last_frame long, start_s double, end_s double")
    return out.withColumnRenamed("key", key)


def features(frames: list[np.ndarray], fps: float) -> str:
    """Frame count, shape, shots with their times in milliseconds, and the samples' histogram."""
    shots = ",".join(f"{round(1000 * a / fps)}-{round(1000 * (b + 1) / fps)}" for a, b in clips(frames))
    total = sum(np.bincount(f.ravel() >> 4, minlength=BINS) for f in frames)
    return f"frames={len(frames)};width={frames[0].shape[1]};shots={shots};hist={','.join(map(str, total))}"


def read_back(media: DataFrame) -> DataFrame:
    """Digests and features of what the files hold, as read from their bytes."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for m in batch["media"].to_pylist():
            frames = _frames(m)
            data = b"".join(f.tobytes() for f in frames)
            rows.append((len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-64:]), len(m), hashlib.sha256(m).hexdigest(), features(frames, rate(m))) if frames else (None,) * 6)
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([batch["doc_id"], batch["n_bytes"], *(pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds))], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return per_batch(media, make, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_back(media_column(read(spark, sf_dir, "documents")))


def clips_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The timed clips of every document's file."""
    return clip_rows(media_column(read(spark, sf_dir, "documents")))
