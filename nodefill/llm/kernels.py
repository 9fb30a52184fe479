"""Numpy kernels over bytes and words, and the small Spark helpers the operators share.

Functions that run in Python workers are shipped by value, so executors need no copy of this package.
"""

from __future__ import annotations

import math
import re
import sys
import types
import zlib

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.session import cut, shared_folder  # noqa: F401

U = np.uint64
INDEX_BITS = 28
INDEX_MASK = U((1 << INDEX_BITS) - 1)
CHUNK = 1 << 20
PLACES = 1 << 24
MULT_A, MULT_B = 0x9E3779B97F4A7C15, 0xD1342543DE82EF95


def ship(name: str) -> None:
    """Let workers receive the functions of module `name` by value."""
    cloudpickle.register_pickle_by_value(sys.modules[name])


ship(__name__)


def cached(key, build):
    """What `build` makes, once for each Python process."""
    store = sys.modules.setdefault("_nodefill_kept", types.ModuleType("_nodefill_kept")).__dict__
    if key not in store:
        store[key] = build()
    return store[key]


def byte_table(seed: int, lower: bool = False) -> np.ndarray:
    table = np.random.default_rng(seed).integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
    if lower:
        table[65:91] = table[97:123]
    return table


BYTES, LOWER = byte_table(7), byte_table(7, lower=True)
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True
SPACES = re.compile(rb"[\t-\r ]")

_powers: dict = {}


def powers(mult: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """mult**i and its inverse power mod 2**64 for i < n."""
    have = _powers.get(mult)
    if have is None or len(have[0]) < n:
        size = max(n, CHUNK // 4)
        inverse = pow(mult, -1, 1 << 64)
        have = tuple(np.multiply.accumulate(np.r_[U(1), np.full(size - 1, m, np.uint64)]) for m in (mult, inverse))
        _powers[mult] = have
    return have[0][:n], have[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U(32))
    h *= U(0xD6E8FEB86659FD93)
    h ^= h >> U(32)
    h *= U(0xD6E8FEB86659FD93)
    h ^= h >> U(32)
    return h


def prefix(values: np.ndarray, mult: int) -> np.ndarray:
    """Polynomial prefix sums, length n + 1."""
    out = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * powers(mult, len(values))[0], out=out[1:])
    return out


def grams(values: np.ndarray, k: int, mult: int = MULT_A) -> np.ndarray:
    """Hash of values[i:i+k] for each i; shorter than values by k - 1."""
    if len(values) < k:
        return np.zeros(0, np.uint64)
    p = prefix(values, mult)
    return mix((p[k:] - p[:-k]) * powers(mult, len(values))[1][: len(values) - k + 1])


def sliding_min(a: np.ndarray, w: int) -> np.ndarray:
    """min(a[i:i+w]) for each whole window."""
    step, out = 1, a
    while 2 * step <= w:
        out = np.minimum(out[:-step], out[step:])
        step *= 2
    return np.minimum(out[: len(out) - (w - step)], out[w - step :]) if w > step else out


def owners(h: np.ndarray, w: int) -> np.ndarray:
    """Place of the leftmost smallest hash in each window of w hashes: the window's own minimiser.

    Places fill the low bits, so long inputs go in runs that overlap by a window; a window's place depends on its hashes only.
    """
    out = []
    for at in range(0, max(1, len(h) - w + 1), PLACES):
        part = h[at : at + PLACES + w - 1]
        keyed = (part & ~INDEX_MASK) | np.arange(len(part), dtype=np.uint64)
        out.append((sliding_min(keyed, w) & INDEX_MASK).astype(np.int64) + at)
    return np.concatenate(out)


def words(joined: bytes, lower: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, start and end of each word `[^\\x20\\x09-\\x0D]+`; `joined` ends in white space. Long inputs go in runs cut at white space."""
    runs, at = [], 0
    while at < len(joined) or not runs:
        cut = SPACES.search(joined, at + 8 * CHUNK)
        to = cut.end() if cut else len(joined)
        h, start, end = run_words(joined[at:to] if to - at < len(joined) else joined, lower)
        runs.append((h, start + at, end + at))
        at = to
    return runs[0] if len(runs) == 1 else tuple(np.concatenate(x) for x in zip(*runs, strict=True))


def run_words(joined: bytes, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    buf = np.frombuffer(joined, np.uint8)
    gap = SPACE[buf]
    edge = np.flatnonzero(np.diff(np.r_[True, gap].view(np.int8)))
    start, end = edge[::2], edge[1::2]
    p = prefix((LOWER if lower else BYTES)[buf], MULT_A)
    return mix((p[end] - p[start]) * powers(MULT_A, len(buf))[1][start]) ^ (end - start).astype(np.uint64), start, end


def chunks(parts: list, sizes, limit: int = CHUNK):
    """Runs of neighbours whose sizes sum to about `limit`; one longer than that stands alone."""
    at, room = 0, limit
    for i, n in enumerate(sizes):
        if n > room and i > at:
            yield at, i
            at, room = i, limit
        room -= n
    if at < len(parts):
        yield at, len(parts)


def pieces_of_long(texts: list[bytes], limit: int, overlap: int):
    """(text, start, bytes) for each text, long ones cut into pieces of `limit` bytes that share `overlap` bytes with the next."""
    for i, t in enumerate(texts):
        for at in range(0, max(1, len(t) - overlap), limit):
            yield i, at, t if len(t) <= limit + overlap else t[at : at + limit + overlap]


def word_chunk(texts: list[bytes], lower: bool = False):
    """Word hashes, starts, ends of several texts, and the bounds of each text's words and bytes."""
    joined = b"\n".join([*texts, b""])
    offset = np.r_[0, np.cumsum([len(t) + 1 for t in texts])]
    h, s, e = words(joined, lower)
    return h, s, e, np.searchsorted(s, offset), offset


def input_bytes(docs: DataFrame) -> int:
    """Bytes of the texts and 16 a row, by a summing pass over their column: files say little, as they are compressed."""
    size = F.coalesce(F.octet_length(F.col("text").cast("string")), F.lit(0)).cast("long")
    return int(docs.agg(F.sum(size + 16)).first()[0] or 0)


def bucket_count(size: int) -> int:
    """Buckets of 0.8 MB that grow with the root of the input up to 64 MB: blocks of a shuffle then stay few and tasks small."""
    each = min(64e6, max(0.8e6, 0.8e6 * math.sqrt(size / 16e6)))
    return max(4, math.ceil(size / each))


def id_text(docs: DataFrame, *more: Column) -> DataFrame:
    """doc_id and text as strings: a null among long integers would come to pandas as floats."""
    return docs.select(*more, F.col("doc_id").cast("long").cast("string").alias("doc_id"), F.col("text").cast("string").alias("text"))


def doc_buckets(docs: DataFrame, n: int, rest: bool = False) -> DataFrame:
    """(bucket, doc_id, text), with `rest` also the other columns as a struct: the one exchange of texts that all later steps share.

    Buckets go by doc_id and text, so rows without an id, or with one id, spread; only rows alike in both share a bucket.
    """
    bucket = F.pmod(F.xxhash64(F.col("doc_id").cast("long"), F.col("text").cast("string")), F.lit(n)).cast("int").alias("bucket")
    return id_text(docs, bucket, *[F.struct(*[F.col(f"`{c}`") for c in docs.columns if c != "text"]).alias("rest")] * rest)


def row_ids(column) -> list:
    return [None if i is None or i != i else int(i) for i in column]


def id_frame(rows: list[tuple], columns: list[str]) -> pd.DataFrame:
    """Rows as a frame whose first column is an id: whole numbers and nulls, which pandas would else turn into floats."""
    out = pd.DataFrame([r[1:] for r in rows], columns=columns[1:])
    out.insert(0, columns[0], pd.array([r[0] for r in rows], "Int64"))
    return out


def row_order(frame) -> tuple[list, list[bytes], list[int]]:
    ids = row_ids(frame["doc_id"])
    texts = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in frame["text"]]
    return ids, texts, sorted(range(len(ids)), key=lambda i: (ids[i] is None, ids[i] or 0, texts[i]))


def in_order(frame) -> tuple[list, np.ndarray, list[bytes]]:
    """Doc ids (None kept), ids with None as the largest long, and texts as bytes, by id and text."""
    ids, texts, order = row_order(frame)
    ids, texts = [ids[i] for i in order], [texts[i] for i in order]
    return ids, np.array([2**63 - 1 if i is None else i for i in ids], np.int64), texts


def col_or_null(docs: DataFrame, name: str, kind: str) -> Column:
    return F.col(name).cast(kind) if name in docs.columns else F.lit(None).cast(kind)


def spans_of(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True."""
    edge = np.flatnonzero(np.diff(np.r_[False, mask, False].view(np.int8)))
    return edge[::2], edge[1::2]


def cover(n: int, starts: np.ndarray, width: int) -> np.ndarray:
    """Mask of the places covered by [s, s + width)."""
    return np.cumsum(np.bincount(starts, minlength=n + 1)[:n] - np.bincount(starts + width, minlength=n + 1)[:n]) > 0


def pack_ints(values: np.ndarray) -> bytes:
    """Counts as the narrowest unsigned type that holds them, compressed."""
    kind = next(t for t in ("<u1", "<u2", "<u4", "<u8") if not len(values) or values.max() <= np.iinfo(t).max)
    return kind[-1].encode() + zlib.compress(values.astype(kind).tobytes(), 1)


def unpack_ints(blob: bytes) -> np.ndarray:
    return np.frombuffer(zlib.decompress(blob[1:]), f"<u{chr(blob[0])}").astype(np.int64)
