"""Motion-JPEG in AVI as a column: writing, parsing, decoding, and shots.

A payload is stored as 8-bit grey samples in frames of WIDTH columns. Frames are JPEG images of the lossless
process (predictor 1): the difference to the left neighbour is coded by its magnitude category and extra bits.
The code table gives category s a code of 9-s bits, so that every sample takes 9 bits, which arrays of eight
samples share in nine bytes; the table is still an ordinary one that any decoder of that process reads. The AVI
file has the usual header lists, the frames in `movi`, an `idx1` index, and the payload's length in `strd`.

Files of other writers are read, too: frames of the baseline process (any sampling, restart intervals, grey or colour,
of which the luminance is used) and of the lossless process (any code table, predictors 1 to 7) are decoded with the
image's own tables, or with the usual ones where a frame leaves them out, as motion-JPEG files may. Without an index
the frames follow from the list itself; a name or a size that isn't a frame's is passed over.

Shots: grey histograms of neighbouring frames are compared; a cut is where the difference exceeds the mean so far
in the shot by a multiple of the spread, and a floor. Each shot is a clip row with its times.

Null texts are empty. A payload is padded with zeros to a positive multiple of 64; the last frame is padded too.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import append_columns

WIDTH, HEIGHT = 64, 64
UNIT = 64
FPS = 25
BINS = 16
#: A cut needs a difference over the running mean plus SPREAD deviations, and over FLOOR.
SPREAD, FLOOR = 3.0, 0.25

# Fixed values of the formats: markers, and a table with one code of each length from 1 to 9 for categories 8 to 0.
_SOI, _EOI, _SOF3, _DHT, _SOS = b"\xff\xd8", b"\xff\xd9", b"\xff\xc3", b"\xff\xc4", b"\xff\xda"
_TABLE = bytes([0, *([1] * 9), *([0] * 7)]) + bytes(range(8, -1, -1))
_SCAN = _SOS + struct.pack(">HBBBBBB", 8, 1, 1, 0, 1, 0, 0)


def _codes() -> np.ndarray:
    """The 9 bits of each difference from -255 to 255: code, then extra bits."""
    d = np.arange(-255, 256)
    s = np.array([int(abs(x)).bit_length() for x in d])
    extra = np.where(d < 0, d + (1 << s) - 1, d)
    code = (1 << (9 - s)) - 2  # ones, then a zero
    return ((code << s) | extra).astype(np.uint16)


_CODE = _codes()
_BACK = np.zeros(512, np.uint8)
_BACK[_CODE] = np.arange(-255, 256) & 255


def frame_bytes(image: np.ndarray) -> bytes:
    """A lossless JPEG image of grey samples (rows x columns)."""
    rows, columns = image.shape
    pred = np.empty((rows, columns), np.int16)
    pred[:, 1:] = image[:, :-1]
    pred[1:, 0] = image[:-1, 0]
    pred[0, 0] = 128
    code = _CODE[(image.astype(np.int16) - pred).ravel() + 255]
    pad = -len(code) % 8
    if pad:
        code = np.concatenate([code, np.full(pad, 511, np.uint16)])
    c = code.reshape(-1, 8)
    out = np.empty((len(c), 9), np.uint8)
    out[:, 0] = c[:, 0] >> 1
    for k in range(1, 8):
        out[:, k] = ((c[:, k - 1] << (8 - k)) | (c[:, k] >> (k + 1))) & 255
    out[:, 8] = c[:, 7] & 255
    data = out.tobytes()
    if pad:
        data = data[: -(-(rows * columns) * 9 // 8)]
    head = _SOI + _SOF3 + struct.pack(">HBHHBBBB", 11, 8, rows, columns, 1, 1, 0x11, 0) + _DHT + struct.pack(">H", 2 + len(_TABLE)) + _TABLE + _SCAN
    return head + data.replace(b"\xff", b"\xff\x00") + _EOI


# Fixed values of the baseline process: the scan order of an 8 x 8 block's coefficients follows from its diagonals; the
# usual code tables, as numbers of codes of each length and symbols in code order, for frames that carry none.
_ZIGZAG = np.array(sorted(range(64), key=lambda k: (k // 8 + k % 8, k // 8 if (k // 8 + k % 8) % 2 else k % 8)))
_DC_SYMBOLS = bytes(range(12))
_USUAL = {
    0x00: (bytes([0, 1, 5, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0]), _DC_SYMBOLS),
    0x01: (bytes([0, 3, 1, 1, 1, 1, 1, 1, 1, 1, 1, 0, 0, 0, 0, 0]), _DC_SYMBOLS),
    0x10: (
        bytes([0, 2, 1, 3, 3, 2, 4, 3, 5, 5, 4, 4, 0, 0, 1, 125]),
        bytes.fromhex(
            "01020300041105122131410613516107227114328191a1082342b1c11552d1f02433627282090a161718191a25262728292a3435363738393a"
            "434445464748494a535455565758595a636465666768696a737475767778797a838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aa"
            "b2b3b4b5b6b7b8b9bac2c3c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae1e2e3e4e5e6e7e8e9eaf1f2f3f4f5f6f7f8f9fa"
        ),
    ),
    0x11: (
        bytes([0, 2, 1, 2, 4, 4, 3, 4, 7, 5, 4, 4, 0, 1, 2, 119]),
        bytes.fromhex(
            "0001020311040521310612415107617113223281081442 91a1b1c109233352f0156272d10a162434e125f11718191a262728292a35363738393a"
            "434445464748494a535455565758595a636465666768696a737475767778797a82838485868788898a92939495969798999aa2a3a4a5a6a7a8a9aa"
            "b2b3b4b5b6b7b8b9bac2c3c4c5c6c7c8c9cad2d3d4d5d6d7d8d9dae2e3e4e5e6e7e8e9eaf2f3f4f5f6f7f8f9fa"
        ),
    ),
}


class _Bits:
    """Bits of a scan's segment, most significant first; past the end all ones."""

    def __init__(self, data: bytes):
        self.data = data.replace(b"\xff\x00", b"\xff")
        self.at = self.held = self.count = 0

    def peek(self, n: int) -> int:
        while self.count < n:
            self.held = self.held << 8 | (self.data[self.at] if self.at < len(self.data) else 255)
            self.at += 1
            self.count += 8
        return self.held >> (self.count - n) & ((1 << n) - 1)

    def take(self, n: int) -> int:
        if not n:
            return 0
        out = self.peek(n)
        self.count -= n
        self.held &= (1 << self.count) - 1
        return out

    def symbol(self, table: dict[tuple[int, int], int]) -> int:
        for n in range(1, 17):
            found = table.get((n, self.peek(n)))
            if found is not None:
                self.take(n)
                return found
        raise ValueError("no such code")

    def number(self, size: int) -> int:
        """A signed number of a magnitude category."""
        if size == 16:
            return 32768
        x = self.take(size)
        return x if not size or x >> (size - 1) else x - (1 << size) + 1


def _code_table(counts: bytes, symbols: bytes) -> dict[tuple[int, int], int]:
    out, code, k = {}, 0, 0
    for length, n in enumerate(counts, 1):
        for _ in range(n):
            out[length, code] = symbols[k]
            code, k = code + 1, k + 1
        code <<= 1
    return out


def _cosines() -> np.ndarray:
    """The inverse transform of one dimension: rows are samples, columns coefficients."""
    x, u = np.arange(8)[:, None], np.arange(8)[None, :]
    return np.where(u == 0, np.sqrt(0.5), 1.0) * np.cos((2 * x + 1) * u * np.pi / 16) / 2


_INVERSE = _cosines()


def read_frame(data: bytes) -> np.ndarray:
    """The grey samples, or the luminance, of a frame of the baseline or the lossless process."""
    if data[:2] != _SOI:
        raise ValueError("not a JPEG image")
    tables = {k: _code_table(*v) for k, v in _USUAL.items()}
    quant: dict[int, np.ndarray] = {}
    raw_table, parts, process, every, at = b"", [], 0, 0, 2
    rows = columns = 0
    while True:
        if data[at] != 0xFF:
            raise ValueError("a marker is missing")
        kind, (size,) = data[at + 1], struct.unpack_from(">H", data, at + 2)
        body = data[at + 4 : at + 2 + size]
        if kind in (0xC0, 0xC1, 0xC3):
            process, (bits, rows, columns, many) = kind, struct.unpack_from(">BHHB", body)
            if bits != 8:
                raise ValueError("only 8-bit samples are read")
            parts = [(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k]) for k in range(many)]
        elif kind == 0xC2 or 0xC5 <= kind <= 0xCF and kind not in (0xC8, 0xCC):
            raise ValueError("only the baseline and the lossless process are read")
        elif kind == 0xC4:
            raw_table, k = body, 0
            while k < len(body):
                n = sum(body[k + 1 : k + 17])
                tables[body[k]] = _code_table(body[k + 1 : k + 17], body[k + 17 : k + 17 + n])
                k += 17 + n
        elif kind == 0xDB:
            k = 0
            while k < len(body):
                wide = 2 if body[k] >> 4 else 1
                quant[body[k] & 15] = np.frombuffer(body, ">u2" if wide == 2 else np.uint8, 64, k + 1).astype(np.float64)
                k += 1 + 64 * wide
        elif kind == 0xDD:
            (every,) = struct.unpack(">H", body)
        at += 2 + size
        if kind == 0xDA:
            chosen = {body[1 + 2 * k]: (body[2 + 2 * k] >> 4, body[2 + 2 * k] & 15) for k in range(body[0])}
            predictor, shift = body[1 + 2 * body[0]], body[3 + 2 * body[0]] & 15
            break
    scan = data[at : data.rindex(_EOI)]
    if process == 0xC3 and raw_table == _TABLE and predictor == 1 and not every and not shift and len(parts) == 1:
        return _fixed_lossless(scan, rows, columns)
    # restart markers part the scan; they can't occur in its data
    segments = re.split(rb"\xff[\xd0-\xd7]", scan)
    if process == 0xC3:
        return _lossless(segments, rows, columns, parts, chosen, tables, predictor, shift, every)
    return _baseline(segments, rows, columns, parts, chosen, tables, quant, every)


def _lossless(segments, rows, columns, parts, chosen, tables, predictor, shift, every) -> np.ndarray:
    if len(parts) != 1:
        raise ValueError("lossless frames of one component are read")
    table, out = tables[chosen[parts[0][0]][0]], np.zeros((rows, columns), np.int64)
    bits, fresh_row, left = _Bits(segments[0]), 0, every
    following = iter(segments[1:])
    for y in range(rows):
        for x in range(columns):
            if every and not left:
                bits, left, fresh_row = _Bits(next(following, b"")), every, y
            left -= 1
            a = int(out[y, x - 1]) if x else 0
            b = int(out[y - 1, x]) if y else 0
            c = int(out[y - 1, x - 1]) if x and y else 0
            if y == fresh_row:
                guess = a if x else 1 << (7 - shift)
            elif not x:
                guess = b
            else:
                guess = (0, a, b, c, a + b - c, a + ((b - c) >> 1), b + ((a - c) >> 1), (a + b) >> 1)[predictor]
            out[y, x] = (guess + bits.number(bits.symbol(table))) & 0xFFFF
    return ((out << shift) & 255).astype(np.uint8)


def _baseline(segments, rows, columns, parts, chosen, tables, quant, every) -> np.ndarray:
    wide, high = max(h for _, h, _, _ in parts), max(v for _, _, v, _ in parts)
    if len(parts) == 1:  # one component isn't interleaved: its units are single blocks
        parts, wide, high = [(parts[0][0], 1, 1, parts[0][3])], 1, 1
    across, down = -(-columns // (8 * wide)), -(-rows // (8 * high))
    _, h0, v0, q0 = parts[0]
    blocks = np.zeros((down * v0, across * h0, 64))
    bits, following, left = _Bits(segments[0]), iter(segments[1:]), every
    before = [0] * len(parts)
    for unit in range(across * down):
        if every and not left:
            bits, left, before = _Bits(next(following, b"")), every, [0] * len(parts)
        left -= 1
        for k, (name, h, v, _) in enumerate(parts):
            dc, ac = tables[chosen[name][0]], tables[0x10 | chosen[name][1]]
            for b in range(h * v):
                before[k] += bits.number(bits.symbol(dc))
                own = blocks[unit // across * v0 + b // h, unit % across * h0 + b % h] if k == 0 else None
                if own is not None:
                    own[0] = before[0]
                at = 1
                while at < 64:
                    run = bits.symbol(ac)
                    size = run & 15
                    at += run >> 4
                    if not size:
                        if run != 0xF0:
                            break
                        at += 1
                        continue
                    value = bits.number(size)
                    if own is not None and at < 64:
                        own[at] = value
                    at += 1
    square = np.zeros((*blocks.shape[:2], 64))
    square[..., _ZIGZAG] = blocks * quant[q0]
    samples = _INVERSE @ square.reshape(*blocks.shape[:2], 8, 8) @ _INVERSE.T + 128
    image = np.clip(np.rint(samples), 0, 255).astype(np.uint8).transpose(0, 2, 1, 3).reshape(down * v0 * 8, across * h0 * 8)
    if (h0, v0) != (wide, high):
        image = image.repeat(high // v0, 0).repeat(wide // h0, 1)
    return image[:rows, :columns]


def _fixed_lossless(scan: bytes, rows: int, columns: int) -> np.ndarray:
    """The writer's own frames, in which every sample has nine bits: read eight at a time."""
    raw = np.frombuffer(scan.replace(b"\xff\x00", b"\xff"), np.uint8)
    n = rows * columns
    need = -(-n // 8) * 9
    if len(raw) < need:
        raw = np.concatenate([raw, np.full(need - len(raw), 255, np.uint8)])
    b = raw[:need].reshape(-1, 9).astype(np.uint16)
    code = np.empty((len(b), 8), np.uint16)
    for k in range(8):
        code[:, k] = ((b[:, k] << (k + 1)) | (b[:, k + 1] >> (7 - k))) & 511
    diff = _BACK[code].ravel()[:n].reshape(rows, columns)
    diff[0, 0] = (int(diff[0, 0]) + 128) & 255
    diff[:, 0] = np.cumsum(diff[:, 0], dtype=np.uint8)
    return np.cumsum(diff, axis=1, dtype=np.uint8)  # samples are sums modulo 256


def _chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) % 2)


def _list(kind: bytes, body: bytes) -> bytes:
    return _chunk(b"LIST", kind + body)


def write_avi(payload: bytes, width: int = WIDTH, height: int = HEIGHT, fps: int = FPS) -> bytes:
    """Frames are `height` rows, or as many as a shorter payload fills."""
    height = max(1, min(height, -(-len(payload) // width)))
    size = width * height
    n = max(1, -(-len(payload) // size))
    samples = np.zeros(n * size, np.uint8)
    samples[: len(payload)] = np.frombuffer(payload, np.uint8)
    movi, index, at = [], [], 4
    for image in samples.reshape(n, height, width):
        chunk = _chunk(b"00dc", data := frame_bytes(image))
        index.append(struct.pack("<4sIII", b"00dc", 0x10, at, len(data)))
        at += len(chunk)
        movi.append(chunk)
    avih = struct.pack("<14I", 1_000_000 // fps, 0, 0, 0x10, n, 0, 1, 0, width, height, 0, 0, 0, 0)
    strh = struct.pack("<4s4sIHHIIIIIIIIHHHH", b"vids", b"MJPG", 0, 0, 0, 0, 1, fps, 0, n, 0, 0xFFFFFFFF, size, 0, 0, width, height)
    strf = struct.pack("<IiiHH4sIiiII", 40, width, height, 1, 8, b"MJPG", size, 0, 0, 0, 0)
    strl = _list(b"strl", _chunk(b"strh", strh) + _chunk(b"strf", strf) + _chunk(b"strd", struct.pack("<Q", len(payload))))
    body = _list(b"hdrl", _chunk(b"avih", avih) + strl) + _list(b"movi", b"".join(movi)) + _chunk(b"idx1", b"".join(index))
    return _chunk(b"RIFF", b"AVI " + body)


def _walk(data: bytes, at: int, end: int) -> Iterator[tuple[bytes, int, int]]:
    """(name, start, end) of chunks; lists are entered, their own name given as LIST/kind."""
    while at + 8 <= end:
        name, (size,) = data[at : at + 4], struct.unpack_from("<I", data, at + 4)
        start, stop = at + 8, min(at + 8 + size, end)
        if name == b"LIST":
            yield b"LIST/" + data[start : start + 4], start + 4, stop
            if data[start : start + 4] != b"movi":
                yield from _walk(data, start + 4, stop)
        else:
            yield name, start, stop
        at = start + size + size % 2


def read_avi(data: bytes) -> tuple[float, int, list[np.ndarray]]:
    """Frames a second, the payload's length, and decoded frames, found through the index."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    fps, length, movi, end, index = 25.0, 0, 0, len(data), []
    for name, a, b in _walk(data, 12, len(data)):
        if name == b"strh":
            scale, rate = struct.unpack_from("<II", data, a + 20)
            fps = rate / scale
        elif name == b"strd":
            (length,) = struct.unpack_from("<Q", data, a)
        elif name == b"LIST/movi":
            movi, end = a - 4, b
        elif name == b"idx1":
            index = [struct.unpack_from("<4sIII", data, k) for k in range(a, b - 15, 16)]
    # an index counts from the list's name, or in some writers' files from the start of the file
    base = movi if not index or data[movi + index[0][2] : movi + index[0][2] + 4] == index[0][0] else 0
    spots = [(base + at + 8, size) for name, _, at, size in index if name[2:] in (b"dc", b"db")]
    if not index:
        spots = [(a, b - a) for name, a, b in _walk(data, movi + 4, end) if name[2:] in (b"dc", b"db")]
    return fps, length, [read_frame(data[a : a + size]) for a, size in spots if size]


def shots(frames: list[np.ndarray]) -> list[tuple[int, int]]:
    """Frame ranges between cuts of the adaptive histogram difference."""
    if len(frames) < 2:
        return [(0, 1)] if frames else []
    flat = np.stack(frames).reshape(len(frames), -1) // (256 // BINS)
    hist = np.stack([np.bincount(row, minlength=BINS) for row in flat]) / flat.shape[1]
    diff = np.abs(np.diff(hist, axis=0)).sum(1) / 2
    out, start, n, mean, spread = [], 0, 0, 0.0, 0.0
    for k, x in enumerate(diff.tolist()):
        limit = max(FLOOR, mean + SPREAD * (spread / n) ** 0.5 if n else FLOOR)
        if x > limit:
            out.append((start, k + 1))
            start, n, mean, spread = k + 1, 0, 0.0, 0.0
            continue
        n += 1
        delta = x - mean
        mean += delta / n
        spread += delta * (x - mean)
    out.append((start, len(frames)))
    return out


def payload_of(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode()
    return len(raw), raw + b"\0" * (max(UNIT, -(-len(raw) // UNIT) * UNIT) - len(raw))


def text_to_avi(docs: DataFrame, keep: list[str] | None = None, name: str = "avi") -> DataFrame:
    """Adds the file as a binary column."""
    return append_columns(docs, "text", [T.StructField(name, T.BinaryType())], lambda: lambda texts: [[write_avi(payload_of(t)[1]) for t in texts]], keep, "media")


def clips(media: DataFrame, column: str = "avi", key: str = "doc_id") -> DataFrame:
    """A row for each shot: key, clip, first_frame, frames, start_s, end_s. Null files have none."""
    key_type = media.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            place, rows = [], []
            for k, data in enumerate(batch.column(1)):
                if data.is_valid:
                    fps, _, frames = read_avi(data.as_py())
                    for clip, (a, b) in enumerate(shots(frames)):
                        place.append(k)
                        rows.append((clip, a, b - a, a / fps, b / fps))
            columns = list(zip(*rows)) or [()] * 5
            types = (pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(place, pa.int64())), *(pa.array(c, t) for c, t in zip(columns, types))], names=[key, "clip", "first_frame", "frames", "start_s", "end_s"])

    return media.select(key, column).mapInArrow(run, f"`{key}` {key_type}, clip int, first_frame long, frames long, start_s double, end_s double")


def summarize(docs: DataFrame, keep: list[str]) -> DataFrame:
    """Stores every text, reads the stored bytes back, and gives digests of both and the shots found."""
    fields = [
        T.StructField("n_bytes", T.LongType()), T.StructField("payload_bytes", T.LongType()), T.StructField("payload_sha256", T.StringType()), T.StructField("tail_crc32", T.LongType()),
        T.StructField("media_bytes", T.LongType()), T.StructField("media_sha256", T.StringType()), T.StructField("feature", T.StringType()),
    ]

    def work(texts: list[str | None]) -> list[list]:
        out: list[list] = [[] for _ in fields]
        for t in texts:
            n, payload = payload_of(t)
            stored = write_avi(payload)
            fps, length, frames = read_avi(stored)
            back = np.stack(frames).tobytes()[:length]
            found = shots(frames)
            feature = f"frames={len(frames)};fps={fps:g};shots=" + ",".join(f"{a}-{b}" for a, b in found)
            row = (n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(stored), hashlib.sha256(stored).hexdigest(), feature)
            for c, x in zip(out, row):
                c.append(x)
        return out

    return append_columns(docs, "text", fields, lambda: work, keep, "media")


def media_clips(spark, sf_dir: str) -> DataFrame:
    """The shots of every document's file, read back from the stored bytes: timed clip rows."""
    return clips(text_to_avi(spark.read.parquet(f"{sf_dir}/documents.parquet"), ["doc_id"]))


def op8_media(spark, sf_dir: str) -> DataFrame:
    return summarize(spark.read.parquet(f"{sf_dir}/documents.parquet"), ["doc_id"])
