"""Removal of word windows that repeat across documents, with a count-min prefilter.

Each partition sketches the minimisers of its windows. A window repeats only if its minimiser does, so the
merged sketch overestimates every window's count. The second pass groups exactly, by 128-bit BLAKE2 digests of the words'
bytes, only the windows whose estimate is two documents or more; no repeated window is lost.
The sketch that is broadcast has a bit for each counter, at most SKETCH_MAX_BITS x DEPTH bits (96 MB).

Null or empty text: no words. Null doc_id: the document is returned unchanged and removes nothing. Rows with the
same doc_id don't remove each other's windows. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .kernels import U

K.ship(__name__)

WINDOW, GRAM = 50, 8
DEPTH, SKETCH_MIN_BITS, SKETCH_MAX_BITS, BLOCK_BITS = 3, 16, 28, 16
DEPTH_MULT = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], np.uint64)


@dataclass
class Windows:
    """Whole windows of some texts: document index, first word, minimiser's hash."""

    doc: np.ndarray
    first: np.ndarray
    anchor: np.ndarray


def windows_of(texts: list[bytes], window: int, gram: int) -> Windows:
    found = []
    for a, b in K.chunks(texts, [len(t) + 1 for t in texts]):
        h, _, _, bounds, _ = K.word_chunk(texts[a:b])
        if len(h) < window:
            continue
        g = K.grams(h, gram)
        own = K.owners(g, window - gram + 1)
        doc = np.repeat(np.arange(b - a), np.diff(bounds))
        ok = np.flatnonzero(doc[: len(own)] == doc[window - 1 :])
        found.append((doc[ok] + a, ok - bounds[doc[ok]], g[own[ok]]))
    if not found:
        none = np.zeros(0, np.uint64)
        return Windows(none.astype(np.int64), none.astype(np.int64), none)
    return Windows(*(np.concatenate(x) for x in zip(*found, strict=True)))


def digests_of(texts: list[bytes], doc: np.ndarray, first: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Two halves of the digest of each window (doc ascending): of its words joined by one space."""
    found, bounds = [], np.searchsorted(doc, np.arange(len(texts) + 1))
    for t, a, b in zip(texts, bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        if b > a:
            own = t.split()
            end = np.cumsum(np.fromiter(map(len, own), np.int64, len(own)) + 1)
            start, joined = np.r_[0, end[:-1]], b" ".join(own)
            found += [hashlib.blake2b(joined[i:j], digest_size=16).digest() for i, j in zip(start[first[a:b]].tolist(), (end[first[a:b] + window - 1] - 1).tolist(), strict=True)]
    both = np.frombuffer(b"".join(found), np.uint64).reshape(-1, 2)
    return both[:, 0], both[:, 1]


def cells_of(anchors: np.ndarray, depth: int, bits: int) -> np.ndarray:
    return ((anchors * DEPTH_MULT[depth]) ^ (anchors >> U(29))) * U(0x9FB21C651E98DF25) >> U(64 - bits)


def sketch_part(frames, window: int, gram: int, bits: int):
    """Sketch of one partition: for each depth and block, the cells that anchors of one or of more documents hit."""
    anchors, docs = [], []
    for frame in frames:
        _, ids, texts = K.in_order(frame)
        w = windows_of(texts, window, gram)
        new = np.flatnonzero(np.r_[True, (w.anchor[1:] != w.anchor[:-1]) | (w.doc[1:] != w.doc[:-1])][: len(w.anchor)])
        anchors.append(w.anchor[new])
        docs.append(ids[w.doc[new]])
    if not anchors:
        return
    h, d = np.concatenate(anchors), np.concatenate(docs)
    order = np.argsort(h, kind="stable")
    h, d = h[order], d[order]
    first = np.flatnonzero(np.r_[True, h[1:] != h[:-1]][: len(h)])
    many = np.minimum.reduceat(d, first) != np.maximum.reduceat(d, first) if len(h) else np.zeros(0, bool)
    h = h[first]
    rows = []
    for depth in range(DEPTH):
        cell = cells_of(h, depth, bits).astype(np.int64)
        order = np.argsort(cell, kind="stable")
        cell, twice = cell[order], many[order]
        at = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]][: len(cell)])
        if not len(at):
            continue
        count = np.diff(np.r_[at, len(cell)])
        flag = np.logical_or.reduceat(twice, at) | (count > 1)
        cell = cell[at]
        block = cell >> BLOCK_BITS
        cut = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
        for i, j in zip(cut, np.r_[cut[1:], len(cell)], strict=True):
            low = (cell[i:j] & ((1 << BLOCK_BITS) - 1)).astype("<u2")
            rows.append((depth, int(block[i]), low.tobytes() + np.packbits(flag[i:j]).tobytes(), int(j - i)))
    yield pd.DataFrame(rows, columns=["depth", "block", "cells", "n"])


def merge_block(key: tuple[Any, ...], frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Sum of the partitions' counters of one block, saturated at two, as a bitmap of counters of two or more; a batch of partitions at a time."""
    count = np.zeros(1 << BLOCK_BITS, np.uint8)
    for frame in frames:
        for blob, n in zip(frame["cells"], frame["n"], strict=True):
            cell = np.frombuffer(blob, "<u2", n)
            more = np.unpackbits(np.frombuffer(blob, np.uint8, -1, 2 * n), count=n)
            count[cell] = np.minimum(2, count[cell] + 1 + more)
    yield pd.DataFrame([(int(key[0]), int(key[1]), np.packbits(count > 1).tobytes())], columns=["depth", "block", "bitmap"])


def merged_sketch(docs: DataFrame, window: int, gram: int, bits: int) -> np.ndarray:
    """Bitmaps [depth, cells / 8] of counters of two or more; its size is bounded by `bits`, not by the corpus."""
    parts = K.id_text(docs)
    parts = parts.mapInPandas(lambda frames: sketch_part(frames, window, gram, bits), "depth int, block int, cells binary, n int")
    blocks = parts.groupBy("depth", "block").applyInPandas(merge_block, "depth int, block int, bitmap binary").collect()
    sketch = np.zeros((DEPTH, 1 << bits >> 3), np.uint8)
    for depth, block, bitmap in blocks:
        part = sketch[depth, block << BLOCK_BITS >> 3 :][: 1 << BLOCK_BITS >> 3]
        part[:] = np.frombuffer(bitmap, np.uint8)[: len(part)]
    return sketch


def estimated_repeated(anchors: np.ndarray, sketch: np.ndarray, bits: int) -> np.ndarray:
    out = np.ones(len(anchors), bool)
    for depth in range(DEPTH):
        cell = cells_of(anchors, depth, bits)
        out &= (sketch[depth][(cell >> U(3)).astype(np.int64)] >> (U(7) - (cell & U(7))).astype(np.uint8) & 1).astype(bool)
    return out


def candidates(frame, window, gram, sketch, bits):
    """The windows estimated repeated of a bucket, sorted by digest: their place, and which of them are the first of their digest, with its halves."""
    ids, keys, texts = K.in_order(frame)
    w = windows_of(texts, window, gram)
    real = np.array([i is not None for i in ids], bool)
    pick = np.flatnonzero(estimated_repeated(w.anchor, sketch, bits) & real[w.doc] if len(w.doc) else np.zeros(0, bool))
    h1, h2 = digests_of(texts, w.doc[pick], w.first[pick], window)
    by = np.lexsort((keys[w.doc[pick]], h2, h1))
    order, h1, h2 = pick[by], h1[by], h2[by]
    new = np.r_[True, (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])][: len(order)]
    return ids, keys, texts, w, order, new, h1[new], h2[new]


def second_pass(frame, window, gram, sketch, bits, shard_bits):
    _, keys, _, w, order, new, h1, h2 = candidates(frame, window, gram, sketch, bits)
    least = keys[w.doc[order[new]]]
    cut = np.searchsorted(h1 >> U(64 - shard_bits), np.arange((1 << shard_bits) + 1, dtype=np.uint64))
    bucket = int(frame["bucket"].iloc[0])
    rows = [(s, bucket, h1[i:j].tobytes() + h2[i:j].tobytes() + least[i:j].tobytes()) for s, (i, j) in enumerate(zip(cut[:-1], cut[1:], strict=True)) if j > i]
    return pd.DataFrame(rows, columns=["shard", "bucket", "windows"])


def group_shard(frame):
    """Exact grouping: answers each bucket with a bit for each of its windows that starts in a smaller document elsewhere."""
    parts = [np.frombuffer(b, np.uint64).reshape(3, -1) for b in frame["windows"]]
    size = [p.shape[1] for p in parts]
    h1, h2, least = (np.concatenate([p[i] for p in parts]) for i in range(3))
    least = least.view(np.int64)
    order = np.lexsort((least, h2, h1))
    a, b, c = h1[order], h2[order], least[order]
    head = np.flatnonzero(np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
    covered = np.zeros(len(a), bool)
    covered[order] = np.repeat(c[head], np.diff(np.r_[head, len(a)])) < c
    cut = np.r_[0, np.cumsum(size)]
    rows = [(int(k), int(s), np.packbits(covered[i:j]).tobytes()) for k, s, i, j in zip(frame["bucket"], frame["shard"], cut[:-1], cut[1:], strict=True) if covered[i:j].any()]
    return pd.DataFrame(rows, columns=["bucket", "shard", "covered"])


def finish(frame, answers, window, gram, sketch, bits, shard_bits, with_text):
    """Removes the covered words of a bucket's documents."""
    columns = ["doc_id", "n_words", "n_removed", "kept_sha256", *["kept"] * with_text]
    if not len(frame):
        return pd.DataFrame({c: [] for c in columns})
    ids, keys, texts, w, order, new, h1, _ = candidates(frame, window, gram, sketch, bits)
    at = order[new]
    cut = np.searchsorted(h1 >> U(64 - shard_bits), np.arange((1 << shard_bits) + 1, dtype=np.uint64))
    elsewhere = np.zeros(len(at), bool)
    for s, blob in zip(answers["shard"], answers["covered"], strict=True):
        elsewhere[cut[s] : cut[s + 1]] = np.unpackbits(np.frombuffer(blob, np.uint8), count=cut[s + 1] - cut[s])
    which = np.cumsum(new) - 1
    here = keys[w.doc[at]][which] < keys[w.doc[order]] if len(order) else np.zeros(0, bool)
    hit = order[here | elsewhere[which]] if len(order) else order
    by = hit[np.lexsort((w.first[hit], w.doc[hit]))]
    bounds = np.searchsorted(w.doc[by], np.arange(len(texts) + 1))
    rows = []
    for k, (i, t) in enumerate(zip(ids, texts, strict=True)):
        kept = own = t.split()
        if bounds[k + 1] > bounds[k]:
            gone = K.cover(len(own), w.first[by[bounds[k] : bounds[k + 1]]], window)
            kept = [x for x, g in zip(own, gone.tolist(), strict=True) if not g]
        rest = b" ".join(kept)
        rows.append((i, len(own), len(own) - len(kept), hashlib.sha256(rest).hexdigest(), *[rest.decode("utf-8", "replace")] * with_text))
    return K.id_frame(rows, columns)


def remove_repeated_windows(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and `kept`, the words left, with `with_text`) of every document."""
    size = K.input_bytes(docs)
    bits = int(min(SKETCH_MAX_BITS, max(SKETCH_MIN_BITS, np.ceil(np.log2(max(size, 1) / 16)))))
    n = K.bucket_count(size)
    shard_bits = max(2, int(np.ceil(np.log2(n))))
    shared = docs.sparkSession.sparkContext.broadcast(merged_sketch(docs, window, gram, bits))
    texts = K.doc_buckets(docs, n)
    found = texts.groupBy("bucket").applyInPandas(lambda f: second_pass(f, window, gram, shared.value, bits, shard_bits), "shard int, bucket int, windows binary")
    answers = found.groupBy("shard").applyInPandas(group_shard, "bucket int, shard int, covered binary")
    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", kept string" * with_text
    both = texts.groupBy("bucket").cogroup(answers.groupBy("bucket"))
    return both.applyInPandas(lambda f, a: finish(f, a, window, gram, shared.value, bits, shard_bits, with_text), schema)


def op9_count_min_window_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeated_windows(spark.read.parquet(f"{sf_dir}/documents.parquet"))


ORACLES = {
    "op9_count_min_window_dedup": r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 48, 1))) AS i FROM d),
g AS (SELECT doc_id, i, md5(array_to_string(w[i:i + 49], ' ')) AS k FROM s),
m AS (SELECT k, min(doc_id) AS least FROM g GROUP BY k),
c AS (SELECT g.doc_id, g.i FROM g JOIN m USING (k) WHERE m.least < g.doc_id),
p AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM d),
r AS (SELECT p.doc_id, p.p, max(c.i) AS last FROM p ASOF LEFT JOIN c ON p.doc_id = c.doc_id AND p.p >= c.i GROUP BY ALL),
q AS (SELECT doc_id, list(p ORDER BY p) FILTER (last IS NULL OR last + 49 < p) AS keep FROM r GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(len(keep), 0) AS BIGINT) AS n_removed,
       sha256(coalesce(array_to_string(list_transform(keep, lambda x: w[x]), ' '), '')) AS kept_sha256
FROM d LEFT JOIN q USING (doc_id)"""
}
