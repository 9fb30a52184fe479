"""Media columns as baseline JPEG: writing bytes as DC coefficients, and reading DC-only luminance thumbnails.

A payload byte v is an 8 x 8 block of the sample v: with a DC step of 8 its quantised DC coefficient is v - 128, so a
DC-only thumbnail gives the payload back exactly. Frames are WIDE blocks wide; each row of blocks is a restart interval.
A frame holds at most MAX_ROWS rows; a longer payload is a chain of frames, one after the other.

The reader parses the markers, Huffman-decodes the scan and sums the DC differences of the first component. Restart
intervals don't depend on each other, so those of many images with equal tables are decoded in step with numpy. The
general reader goes symbol by symbol; it takes any baseline JPEG: subsampled colour, AC coefficients, no restarts.

Null or empty text: 192 spaces. Equal texts give equal values. Rows with the same or no doc_id are treated one by one.
Damaged media raise ValueError in `read_frames`; `read_media` gives nulls for them. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K

K.ship(__name__)

WIDE, MAX_ROWS, BLOCK, STEP = 192, 8191, 8, 8
DC_COUNTS = (0, 1, 5, 1, 1, 1, 0, 0, 0, 0, 0, 0, 0, 0, 0, 0)  # code lengths of the difference categories 0 to 8
SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, width int, height int, n_frames int"


def dc_symbols() -> list[int]:
    """Categories of text's differences, the frequent ones first."""
    return [4, 5, 6, 3, 7, 2, 1, 0, 8]


def huffman(counts, symbols) -> tuple[np.ndarray, np.ndarray]:
    """Lookup by the next 16 bits: code length (0: no code) and symbol."""
    length, symbol, code, k = np.zeros(1 << 16, np.uint8), np.zeros(1 << 16, np.uint8), 0, 0
    for n, c in enumerate(counts, 1):
        for _ in range(c):
            a, b = code << (16 - n), (code + 1) << (16 - n)
            length[a:b], symbol[a:b] = n, symbols[k]
            code, k = code + 1, k + 1
        code <<= 1
    return length, symbol


def dc_codes() -> tuple[np.ndarray, np.ndarray]:
    """Bits and their number for each difference -255..255, with the end-of-block bit behind."""
    code, k, of = 0, 0, {}
    for n, c in enumerate(DC_COUNTS, 1):
        for _ in range(c):
            of[dc_symbols()[k]] = (code, n)
            code, k = code + 1, k + 1
        code <<= 1
    bits, size = np.zeros(511, np.uint64), np.zeros(511, np.int64)
    for d in range(-255, 256):
        cat = abs(d).bit_length()
        c, n = of[cat]
        bits[d + 255] = ((c << cat) | (d if d >= 0 else d + (1 << cat) - 1)) << 1
        size[d + 255] = n + cat + 1
    return bits, size


def header(rows: int) -> bytes:
    part = lambda marker, body: struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body
    return (
        b"\xff\xd8"
        + part(0xDB, bytes([0, STEP]) + bytes([1] * 63))
        + part(0xC0, struct.pack(">BHHBBBB", 8, rows * BLOCK, WIDE * BLOCK, 1, 1, 0x11, 0))
        + part(0xC4, bytes([0x00, *DC_COUNTS, *dc_symbols()]))
        + part(0xC4, bytes([0x10, 1, *[0] * 15, 0x00]))
        + part(0xDD, struct.pack(">H", WIDE))
        + part(0xDA, bytes([1, 1, 0x00, 0, 63, 0]))
    )


def entropy_rows(samples: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each row's coded bytes (flat, with stuffing) and their number; all rows advance in step."""
    bits, size = K.cached("dc codes", dc_codes)
    rows = len(samples)
    diff = np.diff(samples.astype(np.int16), axis=1, prepend=np.int16(128)).T + 255
    out = np.zeros((rows, WIDE * 18 // 32 + 2), ">u4")
    acc, free, word = np.zeros(rows, np.uint64), np.full(rows, 64, np.int64), np.zeros(rows, np.int64)
    half, low = np.uint64(32), np.uint64(0xFFFFFFFF)
    for column in diff:
        free -= size[column]
        acc |= bits[column] << free.astype(np.uint64)
        full = np.flatnonzero(free <= 32)
        out[full, word[full]] = (acc[full] >> half).astype(np.uint32)
        acc[full] = (acc[full] & low) << half
        word[full] += 1
        free[full] += 32
    used = 64 - free
    pad = (np.uint64(1) << free.astype(np.uint64)) - np.uint64(1)
    pad[free == 64] = np.uint64(2**64 - 1)
    out[np.arange(rows), word] = ((acc | pad) >> half).astype(np.uint32)
    count = word * 4 + (used + 7) // 8
    flat = out.view(np.uint8).reshape(rows, -1)
    keep = np.arange(flat.shape[1]) < count[:, None]
    body, row = flat[keep], np.repeat(np.arange(rows), count)
    stuffed = np.flatnonzero(body == 255)
    return np.insert(body, stuffed + 1, 0), count + np.bincount(row[stuffed], minlength=rows)


def write_media(payloads: list[bytes]) -> list[bytes]:
    """A chain of baseline frames for each payload; lengths are positive multiples of WIDE."""
    rows = [len(p) // WIDE for p in payloads]
    body, count = entropy_rows(np.frombuffer(b"".join(payloads), np.uint8).reshape(-1, WIDE))
    ends = np.cumsum(count)
    first = np.cumsum(rows) - rows
    place = np.concatenate([np.arange(r) % MAX_ROWS for r in rows])
    last = np.concatenate([(np.arange(r) % MAX_ROWS == MAX_ROWS - 1) | (np.arange(r) == r - 1) for r in rows])
    gap = np.flatnonzero(~last)
    marked = np.insert(body, np.repeat(ends[gap], 2), np.stack([np.full(len(gap), 255), 0xD0 + place[gap] % 8], 1).astype(np.uint8).ravel()).tobytes()
    ends = ends + 2 * np.cumsum(~last)
    out = []
    for r, f in zip(rows, first.tolist(), strict=True):
        frames = []
        for a in range(0, r, MAX_ROWS):
            b = min(r, a + MAX_ROWS)
            frames.append(header(b - a) + marked[int(ends[f + a - 1]) if f + a else 0 : int(ends[f + b - 1])] + b"\xff\xd9")
        out.append(b"".join(frames))
    return out


class Frame:
    """What a frame's markers say, and where its scan lies."""

    def __init__(self, data: bytes, at: int):
        if data[at : at + 2] != b"\xff\xd8":
            raise ValueError("no start of image")
        self.quant, self.tables, self.restart, at = {}, {}, 0, at + 2
        while True:
            while data[at : at + 2] == b"\xff\xff":
                at += 1
            if at + 4 > len(data) or data[at] != 0xFF:
                raise ValueError("marker expected")
            marker, size = data[at + 1], struct.unpack_from(">H", data, at + 2)[0]
            body = data[at + 4 : at + 2 + size]
            at += 2 + size
            if marker == 0xDB:
                k = 0
                while k < len(body):
                    wide = body[k] >> 4
                    self.quant[body[k] & 15] = struct.unpack_from(">H", body, k + 1)[0] if wide else body[k + 1]
                    k += 1 + 64 * (1 + wide)
            elif marker == 0xC0 or marker == 0xC1:
                depth, self.height, self.width, n = struct.unpack_from(">BHHB", body)
                if depth != 8:
                    raise ValueError("8-bit samples only")
                self.parts = [(body[6 + 3 * i], body[7 + 3 * i] >> 4, body[7 + 3 * i] & 15, body[8 + 3 * i]) for i in range(n)]
            elif marker in (0xC2, 0xC3, *range(0xC5, 0xC8), *range(0xC9, 0xD0)) and marker != 0xCC:
                raise ValueError("not a baseline image")
            elif marker == 0xC4:
                k = 0
                while k < len(body):
                    n = sum(body[k + 1 : k + 17])
                    self.tables[body[k]] = (bytes(body[k + 1 : k + 17]), bytes(body[k + 17 : k + 17 + n]))
                    k += 17 + n
            elif marker == 0xDD:
                self.restart = struct.unpack_from(">H", body)[0]
            elif marker == 0xDA:
                self.scan = {body[1 + 2 * i]: (body[2 + 2 * i] >> 4, body[2 + 2 * i] & 15) for i in range(body[0])}
                self.start = self.end = at
                break
        while True:
            self.end = data.find(b"\xff", self.end)
            if self.end < 0 or self.end + 1 >= len(data):
                raise ValueError("no end of image")
            if data[self.end + 1] == 0 or 0xD0 <= data[self.end + 1] <= 0xD7:
                self.end += 2
                continue
            break
        self.next = self.end + 2 if data[self.end : self.end + 2] == b"\xff\xd9" else len(data)

    def simple(self) -> bool:
        """One component without AC codes but the end of block, a restart at each row."""
        if len(self.parts) != 1 or self.restart != -(-self.width // BLOCK) or len(self.scan) != 1:
            return False
        dc, ac = next(iter(self.scan.values()))
        counts, symbols = self.tables.get(16 + ac, (b"", b""))
        return symbols == b"\0" and counts[0] == 1 and max(self.tables[dc][1], default=99) <= 11


def decode_in_step(segments: list[np.ndarray], blocks: int, table) -> np.ndarray:
    """DC values [segment, block] of restart intervals of one component, DC table `table`, and a one-bit end of block."""
    size = np.array([len(s) + 8 for s in segments])
    flat = np.zeros(int(size.sum()), np.uint8)
    base = np.cumsum(size) - size
    flat[np.repeat(base, size - 8) + np.arange(int((size - 8).sum())) - np.repeat(np.cumsum(size - 8) - (size - 8), size - 8)] = np.concatenate(segments)
    w = flat.astype(np.uint32)
    window = (w[:-3] << 24) | (w[1:-2] << 16) | (w[2:-1] << 8) | w[3:]
    length, symbol = table
    at, value, out = base * 8, np.zeros(len(segments), np.int32), np.empty((blocks, len(segments)), np.int32)
    total = (length + symbol + 1).astype(np.int64)
    for k in range(blocks):
        peek = window[at >> 3] << (at & 7).astype(np.uint32)
        code = peek >> 16
        cat = symbol[code].astype(np.uint32)
        extra = ((peek << length[code].astype(np.uint32)).astype(np.uint64) >> (np.uint64(32) - cat)).astype(np.int32)
        low = np.int32(1) << np.maximum(cat.astype(np.int32) - 1, 0)
        value += np.where((extra < low) & (cat > 0), extra - 2 * low + 1, extra)
        out[k] = value
        at += total[code]
    if (at > (base + size - 8) * 8).any():
        raise ValueError("scan ends early")
    return out.T


def intervals(data: bytes, frame: Frame) -> list[np.ndarray]:
    """A scan's restart intervals without stuffing."""
    scan = np.frombuffer(data, np.uint8, frame.end - frame.start, frame.start)
    ff = np.flatnonzero(scan[:-1] == 255)
    after = scan[ff + 1]
    marks = ff[after >= 0xD0]
    keep = np.ones(len(scan), bool)
    keep[ff[after == 0] + 1] = False
    keep[marks], keep[marks + 1] = False, False
    ends = np.cumsum(keep)[np.r_[marks, len(scan) - 1]]
    return np.split(scan[keep], ends[:-1])


def decode_any(data: bytes, frame: Frame) -> np.ndarray:
    """DC values of the first component of any baseline scan, symbol by symbol."""
    tall, wide = max(p[2] for p in frame.parts), max(p[1] for p in frame.parts)
    one = len(frame.parts) == 1
    rows, cols = (-(-frame.height // (BLOCK * (1 if one else tall)))), (-(-frame.width // (BLOCK * (1 if one else wide))))
    v0, h0 = (1, 1) if one else (frame.parts[0][2], frame.parts[0][1])
    out = np.zeros((rows * v0, cols * h0), np.int32)
    luts = {k: huffman(*t) for k, t in frame.tables.items()}
    bits, at, number = 0, 0, 0

    def take(n: int) -> int:
        nonlocal at
        at += n
        if at > total:
            raise ValueError("scan ends early")
        return (bits >> (total + 32 - at)) & ((1 << n) - 1)

    def symbol(lut) -> int:
        nonlocal at
        code = (bits >> (total + 32 - at - 16)) & 0xFFFF
        if not lut[0][code]:
            raise ValueError("no such code")
        at += int(lut[0][code])
        return int(lut[1][code])

    for segment in intervals(data, frame):
        bits, total, at, past = int.from_bytes(segment.tobytes(), "big") << 32, 8 * len(segment), 0, dict.fromkeys(frame.scan, 0)
        for _ in range(frame.restart or rows * cols):
            if number == rows * cols:
                break
            for k, (part, h, v, _) in enumerate(frame.parts):
                dc, ac = frame.scan[part]
                for b in range(1 if one else h * v):
                    cat = symbol(luts[dc])
                    extra = take(cat) if cat else 0
                    past[part] += extra if not cat or extra >> (cat - 1) else extra - (1 << cat) + 1
                    if k == 0:
                        out[number // cols * v0 + b // h0, number % cols * h0 + b % h0] = past[part]
                    done = 1
                    while done < 64:
                        s = symbol(luts[16 + ac])
                        if s == 0:
                            break
                        done += (s >> 4) + 1
                        take(s & 15)
            number += 1
    return out


def read_frames(media: list[bytes]) -> list[list[tuple[int, int, np.ndarray]]]:
    """For each chain of frames: (width, height, DC-only luminance thumbnail as bytes of samples)."""
    frames, groups = [], {}
    for k, data in enumerate(media):
        at, own = 0, []
        while at < len(data):
            f = Frame(data, at)
            own.append(f)
            at = f.next
            if f.simple():
                groups.setdefault((f.restart, f.tables[next(iter(f.scan.values()))[0]]), []).append((k, f))
        if not own:
            raise ValueError("no image")
        frames.append(own)
    dc = {}
    for (blocks, table), members in groups.items():
        parts = [intervals(media[k], f) for k, f in members]
        values = decode_in_step([s for p in parts for s in p], blocks, huffman(*table))
        for (_, f), rows in zip(members, np.split(values, np.cumsum([len(p) for p in parts])[:-1]), strict=True):
            dc[id(f)] = rows
    out = []
    for data, own in zip(media, frames, strict=True):
        found = []
        for f in own:
            value = dc[id(f)] if id(f) in dc else decode_any(data, f)
            mean = np.clip((value * f.quant[f.parts[0][3]] + 4) // 8 + 128, 0, 255).astype(np.uint8)
            found.append((f.width, f.height, mean))
        out.append(found)
    return out


def thumbnail_hash(thumb: np.ndarray) -> str:
    """64 bits: which of 8 x 9 area means is larger than its left neighbour."""
    cut_y = np.linspace(0, thumb.shape[0], 9).astype(int)
    cut_x = np.linspace(0, thumb.shape[1], 10).astype(int)
    p = np.zeros((thumb.shape[0] + 1, thumb.shape[1] + 1), np.int64)
    p[1:, 1:] = np.cumsum(np.cumsum(thumb, 0, dtype=np.int64), 1)
    y0, y1 = np.minimum(cut_y[:-1], thumb.shape[0] - 1), np.maximum(cut_y[1:], cut_y[:-1] + 1)
    x0, x1 = np.minimum(cut_x[:-1], thumb.shape[1] - 1), np.maximum(cut_x[1:], cut_x[:-1] + 1)
    y1, x1 = np.minimum(y1, thumb.shape[0]), np.minimum(x1, thumb.shape[1])
    y0, x0 = np.minimum(y0, y1 - 1), np.minimum(x0, x1 - 1)
    total = p[y1][:, x1] - p[y0][:, x1] - p[y1][:, x0] + p[y0][:, x0]
    mean = total / ((y1 - y0)[:, None] * (x1 - x0)[None, :])
    return np.packbits(mean[:, 1:] > mean[:, :-1]).tobytes().hex()


def features(frames) -> tuple[str, int, int]:
    hashes = [thumbnail_hash(t) for _, _, t in frames]
    mark = hashes[0] if len(hashes) == 1 else hashlib.sha256("".join(hashes).encode()).hexdigest()[:16]
    width, height = max(f[0] for f in frames), sum(f[1] for f in frames)
    return f"{width}x{height}:{mark}", width, height


def store_partition(frames):
    for frame in frames:
        ids = K.row_ids(frame["doc_id"])
        texts = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in frame["text"]]
        for a, b in K.chunks(texts, [len(t) + WIDE for t in texts], 1 << 21):
            payloads = [t.ljust(max(1, -(-len(t) // WIDE)) * WIDE, b" ") for t in texts[a:b]]
            media = write_media(payloads)
            rows = []
            for doc, text, stored, read in zip(ids[a:b], texts[a:b], media, read_frames(media), strict=True):
                back = b"".join([t.tobytes() for _, _, t in read])
                feature, width, height = features(read)
                rows.append((doc, len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-16:]), len(stored), hashlib.sha256(stored).hexdigest(), feature, width, height, len(read)))
            yield K.id_frame(rows, [x.split()[0] for x in SCHEMA.split(", ")])


def encode_media(docs: DataFrame) -> DataFrame:
    """doc_id and `media`: the text's bytes as baseline JPEG."""

    def encode(frames):
        for frame in frames:
            texts = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in frame["text"]]
            for a, b in K.chunks(texts, [len(t) + WIDE for t in texts], 1 << 21):
                media = write_media([t.ljust(max(1, -(-len(t) // WIDE)) * WIDE, b" ") for t in texts[a:b]])
                yield pd.DataFrame({"doc_id": pd.array(K.row_ids(frame["doc_id"].iloc[a:b]), "Int64"), "media": media})

    return K.id_text(docs).mapInPandas(encode, "doc_id long, media binary")


def read_media(media: DataFrame, key: str = "doc_id", column: str = "media") -> DataFrame:
    """`key`, width, height, n_frames, thumbnail_hash, thumbnail (samples) of any baseline JPEG column; nulls where it can't be read."""

    def read(frames):
        for frame in frames:
            rows = []
            for k, data in zip(frame["key"], frame["media"], strict=True):
                try:
                    own = read_frames([bytes(data)])[0]
                    feature, width, height = features(own)
                    rows.append((k, width, height, len(own), feature.split(":")[1], b"".join(t.tobytes() for _, _, t in own)))
                except (ValueError, TypeError, KeyError, IndexError, struct.error, AttributeError):
                    rows.append((k, None, None, None, None, None))
            out = pd.DataFrame(rows, columns=["key", "width", "height", "n_frames", "thumbnail_hash", "thumbnail"])
            yield out.astype({"width": "Int64", "height": "Int64", "n_frames": "Int64", "key": frame["key"].dtype})

    kind = dict(media.dtypes)[key]
    found = media.select(F.col(key).alias("key"), F.col(column).cast("binary").alias("media")).mapInPandas(read, f"key {kind}, width int, height int, n_frames int, thumbnail_hash string, thumbnail binary")
    return found.withColumnRenamed("key", key)


def op6_jpeg_media(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return K.id_text(docs).mapInPandas(store_partition, SCHEMA)
