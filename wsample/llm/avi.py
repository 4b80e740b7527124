"""Motion-JPEG AVI media columns: write, parse, decode, and cut into shots.

Frames are lossless JPEG (process 14, 8-bit, one component, left predictor), so a decoded frame is the
stored samples exactly.  Its Huffman table gives category c a code of 9 - c bits, which with the c bits
that follow makes nine bits a sample: a conforming table that numpy packs and unpacks without a bit loop.
Files by other writers may use any table; those go through a general decoder.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, text_of

WIDTH, MOST_ROWS, FPS = 64, 64, 25
#: Histogram bins of a frame, frames on each side that a cut is held against, and how far above them it must stand.
BINS, AROUND, TIMES = 16, 4, 2.0
#: Codes a length for categories 0 to 8 of 9 to 1 bits: one code of each length; values shortest first.
_COUNTS = bytes([1] * 9 + [0] * 7)
_VALUES = bytes(range(8, -1, -1))


def _head(rows: int, columns: int) -> bytes:
    """Markers before the scan's data."""
    frame = struct.pack(">BHHB3B", 8, rows, columns, 1, 1, 0x11, 0)
    table = b"\x00" + _COUNTS + _VALUES
    scan = struct.pack(">B2B3B", 1, 1, 0x00, 1, 0, 0)
    return b"\xff\xd8" + b"".join(b"\xff" + m + struct.pack(">H", len(x) + 2) + x for m, x in ((b"\xc3", frame), (b"\xc4", table), (b"\xda", scan)))


#: Huffman code of each category, left-aligned before the category's own bits: all ones but the last bit of a code.
_CODE = np.array([(1 << (9 - c)) - 2 for c in range(9)], np.int64)


def _differences(image: np.ndarray) -> np.ndarray:
    """Samples (frames, rows, columns) minus their prediction: the sample to the left, above for the first column, 128 for the first."""
    x = image.astype(np.int16)
    d = x.copy()
    d[:, :, 1:] -= x[:, :, :-1]
    d[:, 1:, 0] -= x[:, :-1, 0]
    d[:, 0, 0] -= 128
    return d


def encode_frames(images: np.ndarray) -> list[bytes]:
    """JPEG files of uint8 images (frames, rows, columns)."""
    frames, rows, columns = images.shape
    d = _differences(images).reshape(frames, -1)
    size = np.frexp(np.abs(d).astype(np.float32))[1].astype(np.int64)  # bits of the magnitude
    extra = np.where(d < 0, d - 1, d).astype(np.int64) & ((1 << size) - 1)
    word = (_CODE[size] << size | extra).astype(">u2")
    bits = np.unpackbits(word.view(np.uint8).reshape(frames, -1, 2), axis=2)[:, :, 7:].reshape(frames, -1)
    spare = -bits.shape[1] % 8
    if spare:
        bits = np.concatenate([bits, np.ones((frames, spare), np.uint8)], axis=1)
    data, head = np.packbits(bits, axis=1), _head(rows, columns)
    return [head + x.tobytes().replace(b"\xff", b"\xff\x00") + b"\xff\xd9" for x in data]


def _segments(jpeg: bytes) -> tuple[dict[int, bytes], bytes]:
    """Marker segments, and the scan's data without stuffing."""
    if jpeg[:2] != b"\xff\xd8":
        raise ValueError("not a JPEG frame")
    at, found = 2, {}
    while True:
        mark, size = jpeg[at + 1], int.from_bytes(jpeg[at + 2 : at + 4], "big")
        found[mark] = jpeg[at + 4 : at + 2 + size]
        at += 2 + size
        if mark == 0xDA:
            return found, jpeg[at : jpeg.rindex(b"\xff\xd9")].replace(b"\xff\x00", b"\xff")


def _bit_by_bit(data: bytes, counts: bytes, values: bytes, n: int) -> np.ndarray:
    """Differences under any Huffman table."""
    codes, code, at = {}, 0, 0
    for length, many in enumerate(counts, 1):
        for _ in range(many):
            codes[length, code] = values[at]
            code, at = code + 1, at + 1
        code <<= 1
    bits = np.unpackbits(np.frombuffer(data, np.uint8)).tolist()
    out, p = [], 0
    for _ in range(n):
        code = length = 0
        while (length, code) not in codes:
            code, length, p = code << 1 | bits[p], length + 1, p + 1
            if length > 16:
                raise ValueError("no such code")
        size = codes[length, code]
        if size > 15:
            raise ValueError("no such category")
        value = 0
        for b in bits[p : p + size]:
            value = value << 1 | b
        p += size
        out.append(value if not size or value >> size - 1 else value - (1 << size) + 1)
    return np.array(out, np.int16)


def decode_frame(jpeg: bytes) -> np.ndarray:
    """uint8 image (rows, columns) of a one-component lossless frame with the left predictor."""
    found, data = _segments(jpeg)
    precision, rows, columns, parts = struct.unpack(">BHHB", found[0xC3][:6])
    if precision != 8 or parts != 1 or found[0xDA][-3] != 1:
        raise ValueError("only 8-bit frames of one component with the left predictor")
    n, table = rows * columns, found[0xC4]
    usual = table[1:17] == _COUNTS and table[17:26] == _VALUES
    if not 0 < n * (9 if usual else 1) <= 8 * len(data):
        raise ValueError("fewer bits than samples")
    if usual:
        bits = np.unpackbits(np.frombuffer(data, np.uint8), count=9 * n).reshape(n, 9)
        wide = np.zeros((n, 16), np.uint8)
        wide[:, 7:] = bits
        word = np.packbits(wide, axis=1).view(">u2").ravel().astype(np.int16)
        # leading ones of nine bits are 8 - size
        gap = 511 - word
        size = np.where(gap > 0, np.frexp(gap.astype(np.float32))[1] - 1, 0).astype(np.int16)
        value = word & ((1 << size) - 1)
        d = np.where((size > 0) & (value >> np.maximum(size - 1, 0) == 0), value - (1 << size) + 1, value)
    else:
        d = _bit_by_bit(data, table[1:17], table[17:], n)
    d = d.reshape(rows, columns).astype(np.int64)
    d[0, 0] += 128
    d[:, 0] = np.cumsum(d[:, 0])
    return (np.cumsum(d, axis=1) & 255).astype(np.uint8)


def _chunk(name: bytes, data: bytes) -> bytes:
    return name + struct.pack("<I", len(data)) + data + b"\0" * (len(data) % 2)


def write_avi(payload: bytes) -> bytes:
    """An AVI of the payload (a positive multiple of 64 bytes) as grey frames 64 wide and up to 64 high.

    The last frame is filled up with zeros; the payload's length stands in the information list.
    """
    n = len(payload)
    rows = min(n // WIDTH, MOST_ROWS)
    frames = -(-n // (rows * WIDTH))
    samples = np.zeros(frames * rows * WIDTH, np.uint8)
    samples[:n] = np.frombuffer(payload, np.uint8)
    coded: list[bytes] = []
    images = samples.reshape(frames, rows, WIDTH)
    for lo in range(0, frames, 64):
        coded += encode_frames(images[lo : lo + 64])
    most = max(map(len, coded))
    header = _chunk(b"avih", struct.pack("<14I", 1_000_000 // FPS, most * FPS, 0, 0x10, frames, 0, 1, most, WIDTH, rows, 0, 0, 0, 0))
    stream = _chunk(b"strh", b"vidsMJPG" + struct.pack("<IHHIIIIIIIIHHHH", 0, 0, 0, 0, 1, FPS, 0, frames, most, 0xFFFFFFFF, 0, 0, 0, WIDTH, rows))
    form = _chunk(b"strf", struct.pack("<IiiHH4sIiiII", 40, WIDTH, rows, 1, 8, b"MJPG", WIDTH * rows, 0, 0, 0, 0))
    headers = _chunk(b"LIST", b"hdrl" + header + _chunk(b"LIST", b"strl" + stream + form))
    info = _chunk(b"LIST", b"INFO" + _chunk(b"ISBJ", b"%d\0" % n))
    index, at, movie = [], 4, []
    for x in coded:
        index.append(b"00dc" + struct.pack("<III", 0x10, at, len(x)))
        movie.append(_chunk(b"00dc", x))
        at += len(movie[-1])
    return _chunk(b"RIFF", b"AVI " + headers + info + _chunk(b"LIST", b"movi" + b"".join(movie)) + _chunk(b"idx1", b"".join(index)))


@dataclass(frozen=True)
class Movie:
    width: int
    height: int
    micros: int
    length: int | None
    frames: list[tuple[int, int]]  # offset and size of each in the file
    data: bytes


def parse_avi(data: bytes) -> Movie:
    """Headers and the frame table, from the index or, without one, by walking the movie list."""
    if data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("not an AVI file")
    found: dict[bytes, tuple[int, int]] = {}

    def walk(at: int, end: int) -> None:
        while at + 8 <= min(end, len(data)):
            name, size = data[at : at + 4], int.from_bytes(data[at + 4 : at + 8], "little")
            if name == b"LIST":
                kind = data[at + 8 : at + 12]
                found[kind] = (at + 12, size - 4)
                if kind != b"movi":
                    walk(at + 12, at + 8 + size)
            else:
                found[name] = (at + 8, size)
            at += 8 + size + size % 2

    walk(12, 8 + int.from_bytes(data[4:8], "little"))
    main = struct.unpack_from("<14I", data, found[b"avih"][0])
    base, size = found[b"movi"]
    frames: list[tuple[int, int]] = []
    if b"idx1" in found:
        at, n = found[b"idx1"]
        table = np.frombuffer(data, "<u4", n // 4, at).reshape(-1, 4)
        # offsets count from the list's name, or in some writers from the file's start
        whole = len(table) and data[base - 4 + int(table[0, 2]) : base + int(table[0, 2])] != data[at : at + 4]
        frames = [((int(x) if whole else base - 4 + int(x)) + 8, int(k)) for tag, _, x, k in table if int(tag).to_bytes(4, "little")[2:] in (b"dc", b"db")]
    else:
        at = base
        while at + 8 <= min(base + size, len(data)):
            k = int.from_bytes(data[at + 4 : at + 8], "little")
            if data[at + 2 : at + 4] in (b"dc", b"db"):
                frames.append((at + 8, k))
            at += 8 + k + k % 2
    length = int(data[found[b"ISBJ"][0] :][: found[b"ISBJ"][1]].split(b"\0")[0]) if b"ISBJ" in found else None
    return Movie(main[8], main[9], main[0], length, frames, data)


def decode(movie: Movie) -> np.ndarray:
    """uint8 images (frames, rows, columns)."""
    return np.stack([decode_frame(movie.data[at : at + n]) for at, n in movie.frames])


def payload_of(movie: Movie, images: np.ndarray) -> bytes:
    data = images.tobytes()
    return data if movie.length is None else data[: movie.length]


def shot_starts(images: np.ndarray) -> list[int]:
    """First frames of the shots.

    Successive histograms differ by half their L1 distance as a share of the samples.  A difference opens a shot if it
    stands ``TIMES`` deviations above the mean of those around it, is the largest of them, and is not negligible.
    """
    flat = images.reshape(len(images), -1) // (256 // BINS)
    hist = np.stack([np.bincount(x, minlength=BINS) for x in flat])
    d = np.abs(np.diff(hist, axis=0)).sum(axis=1) / (2 * flat.shape[1])
    starts = [0]
    for i, x in enumerate(d):
        near = np.concatenate([d[max(0, i - AROUND) : i], d[i + 1 : i + 1 + AROUND]])
        if x > 0.05 and (not len(near) or (x > near.mean() + TIMES * near.std() and x >= near.max())):
            starts.append(i + 1)
    return starts


def padded(text: str) -> tuple[int, bytes]:
    data = text.encode()
    return len(data), data + bytes(-len(data) % 64 or 64 * (not data))


def to_media(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media): each whole text as an AVI file.  A null text is empty: 64 zero bytes."""

    def make(batch: pa.RecordBatch) -> pa.RecordBatch:
        parts = [padded(x) for x in batch.column(1).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([n for n, _ in parts], pa.int64()), pa.array([write_avi(x) for _, x in parts], pa.binary())], ["doc_id", "n_bytes", "media"])

    kind = docs.schema[id_col].dataType.simpleString()
    return by_batch(docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")), make, f"doc_id {kind}, n_bytes long, media binary", size_by="text")


def _read(data: bytes | None) -> tuple[Movie, np.ndarray] | None:
    """A file and its frames, none if the file is damaged, has no frame or is of another kind."""
    try:
        movie = parse_avi(data or b"")
        images = decode(movie)
    except (ValueError, IndexError, KeyError, RecursionError, struct.error):
        return None
    return (movie, images) if images.size else None


def _spans(movie: Movie, images: np.ndarray) -> list[tuple[int, int, int, float, float]]:
    """(clip, first frame, frames, start and end in seconds) of each shot."""
    starts, s = shot_starts(images), movie.micros / 1e6
    return [(k, lo, hi - lo, lo * s, hi * s) for k, (lo, hi) in enumerate(zip(starts, [*starts[1:], len(images)], strict=True))]


def media_features(media: DataFrame) -> DataFrame:
    """Digests of the payload that the stored bytes hold, a feature string and the timed clips, one row a file.

    ``clips`` has ``first frame:frames:start:end`` a shot, times in milliseconds, comma-joined.  A null or damaged file has its
    size and digest (null for a null) and null for all that would be read from its frames.
    """

    def read(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for data in batch.column(2).to_pylist():
            stored = (None, None) if data is None else (len(data), hashlib.sha256(data).hexdigest())
            found = _read(data)
            if found is None:
                rows.append((None, None, None, *stored, None, None))
                continue
            movie, images = found
            payload, shots = payload_of(movie, images), _spans(movie, images)
            mean = int(images.sum(dtype=np.int64) * 1000 // images.size)
            feature = f"{movie.width}x{movie.height};frames={len(images)};shots={len(shots)};cuts={','.join(str(x[1]) for x in shots[1:])};mean={mean}"
            timed = ",".join(f"{first}:{n}:{round(1000 * lo)}:{round(1000 * hi)}" for _, first, n, lo, hi in shots)
            rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), *stored, feature, timed))
        columns = list(zip(*rows, strict=True))
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "clips"])

    kind = media.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, clips string"
    return by_batch(media.select("doc_id", "n_bytes", "media"), read, schema, size_by="media")


def clips(media: DataFrame) -> DataFrame:
    """(doc_id, clip_no, first_frame, n_frames, start_s, end_s): one row a shot of each file; none of a null or damaged one."""

    def cut(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = [(i, _read(data)) for i, data in enumerate(batch.column(1).to_pylist())]
        shots = [(i, x) for i, one in found if one for x in _spans(*one)]
        kinds = [pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64()]
        columns = list(zip(*(x for _, x in shots), strict=True)) or [[]] * 5
        return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array([i for i, _ in shots], pa.int64())), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], ["doc_id", "clip_no", "first_frame", "n_frames", "start_s", "end_s"])

    kind = media.schema["doc_id"].dataType.simpleString()
    return by_batch(media.select("doc_id", "media"), cut, f"doc_id {kind}, clip_no int, first_frame int, n_frames int, start_s double, end_s double", size_by="media")
