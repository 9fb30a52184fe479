"""Removal of byte strings that repeat across documents, with a logarithmic family of suffix arrays.

`SuffixFamily` takes batches in ascending document order. A batch gets a suffix array of its window starts (suffixes
sorted by their first `window` bytes), is merge-scanned against each existing level for matches of a whole window,
and joins the family; levels of equal size merge, so sizes grow geometrically and each suffix is merged O(log n) times.

The family is sharded so that all occurrences of a window meet. Every window of 50 bytes has a minimiser, a hashed
16-gram, and a window can repeat only if its minimiser does. First the buckets exchange only minimiser hashes; a
window goes to a shard only if its minimiser occurs in two documents. Neighbouring windows with one minimiser travel as
one string to the shard of that minimiser. Minimisers with more than HOT occurrences are frequent by chance: their
windows travel singly, sharded by content, so that no shard gathers them. Each bucket sends equal strings once.

Null or empty text: no bytes. Null doc_id: the document is returned unchanged and removes nothing. Rows with the same
doc_id don't remove each other's bytes. Other columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .kernels import U

K.ship(__name__)

WINDOW, GRAM, HOT, BATCH = 50, 16, 4096, 1 << 18


class SuffixFamily:
    """Levels of (sorted suffix keys, smallest document of each)."""

    def __init__(self, window: int = WINDOW):
        self.window, self.levels = window, []

    def suffixes(self, text: np.ndarray, starts: np.ndarray) -> np.ndarray:
        rows = np.lib.stride_tricks.sliding_window_view(text, self.window)[starts]
        return np.ascontiguousarray(rows).view(f"S{self.window}").ravel()

    def add(self, text: np.ndarray, starts: np.ndarray, docs: np.ndarray) -> np.ndarray:
        """Which of the batch's suffixes match one of a smaller document, in an earlier batch or in this one. docs ascends over all batches."""
        key = self.suffixes(text, starts)
        array = np.argsort(key, kind="stable")
        key = key[array]
        head = np.flatnonzero(np.r_[True, key[1:] != key[:-1]][: len(key)])
        run = np.diff(np.r_[head, len(key)])
        key, least = key[head], docs[array[head]]
        for keys, docs_of in self.levels:
            at = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
            least = np.where(keys[at] == key, np.minimum(least, docs_of[at]), least)
        matched = np.empty(len(starts), bool)
        matched[array] = np.repeat(least, run) < docs[array]
        self.push(key, least)
        return matched

    def push(self, key: np.ndarray, least: np.ndarray) -> None:
        while self.levels and len(self.levels[-1][0]) <= 2 * len(key):
            other, docs = self.levels.pop()
            key, least = np.concatenate([other, key]), np.concatenate([docs, least])
            order = np.argsort(key, kind="stable")
            key, least = key[order], least[order]
            new = np.r_[True, key[1:] != key[:-1]][: len(key)]
            key, least = key[new], least[new]
        if len(key):
            self.levels.append((key, least))


def anchored(texts: list[bytes], window: int, gram: int):
    """For each chunk of texts: joined bytes, the runs of windows with one minimiser (start there, windows), the run's place in its text, its text and minimiser hash.

    Very long texts go in pieces that overlap by a window less one byte, so each window lies in exactly one.
    """
    owner, begin, parts = zip(*K.pieces_of_long(texts, 4 * K.CHUNK, window - 1), strict=True) if texts else ((), (), ())
    owner, begin = np.array(owner, np.int64), np.array(begin, np.int64)
    for a, b in K.chunks(parts, [len(t) + 1 for t in parts]):
        joined = b"\0".join([*parts[a:b], b""])
        offset = np.r_[0, np.cumsum([len(t) + 1 for t in parts[a:b]])]
        if len(joined) < window:
            continue
        g = K.grams(K.BYTES[np.frombuffer(joined, np.uint8)], gram)
        own = K.owners(g, window - gram + 1)
        ok = np.zeros(len(own), bool)
        for i, j in zip(offset[:-1], offset[1:] - window, strict=True):
            ok[i : max(i, j)] = True
        new = np.r_[True, (own[1:] != own[:-1]) | (ok[1:] != ok[:-1])]
        start = np.flatnonzero(new)
        size = np.diff(np.r_[start, len(own)])
        keep = ok[start]
        start, size = start[keep], size[keep]
        part = np.searchsorted(offset, start, side="right") - 1
        yield joined, start, size, start - offset[part] + begin[a + part], owner[a + part], K.mix(g[own[start]] ^ U(K.MULT_B))  # minimisers are small; mixed, they spread over the shards


def distinct_runs(frame, window, gram, answers):
    """The runs of a bucket whose minimiser repeats.

    Answers ids, texts, and in order of first sight: {string: number}, its smallest document, its shard's hash,
    and each occurrence as (text, start in the text, windows, number).
    """
    ids, keys, texts = K.in_order(frame)
    known = np.concatenate([np.frombuffer(b, np.uint64) for b in answers]) if len(answers) else np.zeros(0, np.uint64)
    hot = np.sort(known[1::2][known[1::2] != 0]) if len(known) else known
    known = np.sort(known[::2])
    number, least, shard, seen = {}, [], [], []
    for joined, start, size, place, text, h in anchored(texts, window, gram):
        if not len(known):
            break
        at = np.minimum(np.searchsorted(known, h), len(known) - 1)
        pick = np.flatnonzero((known[at] == h) & np.array([i is not None for i in ids], bool)[text])
        if len(hot):
            wide = hot[np.minimum(np.searchsorted(hot, h[pick]), len(hot) - 1)] == h[pick]
        else:
            wide = np.zeros(len(pick), bool)
        parts = [(pick[~wide], start[pick[~wide]], size[pick[~wide]])]
        place = place - start
        if wide.any():
            w = pick[wide]
            each = np.repeat(w, size[w])
            parts.append((each, start[each] + np.arange(len(each)) - np.repeat(np.cumsum(size[w]) - size[w], size[w]), np.ones(len(each), np.int64)))
        for k, (which, first, count) in enumerate(parts):
            for s, n, t, x, p in zip(first.tolist(), count.tolist(), text[which].tolist(), h[which].tolist(), place[which].tolist(), strict=True):
                piece = joined[s : s + n + window - 1]
                i = number.setdefault((n, piece) if k else piece, len(number))
                if i == len(least):
                    least.append(keys[t])
                    shard.append((zlib.crc32(piece) * 0x9E3779B97F4A7C15) & (2**64 - 1) if k else x)
                seen.append((t, s + p, n, i))
    return ids, keys, texts, number, least, shard, seen


def first_pass(frame, window, gram, shard_bits):
    """A bucket's distinct minimiser hashes, with their occurrences up to 255, and more than one document as the top bit."""
    _, keys, texts = K.in_order(frame)
    parts = [(h, keys[text]) for *_, text, h in anchored(texts, window, gram)]
    if not parts:
        return pd.DataFrame({"shard": [], "bucket": [], "anchors": []})
    h, doc = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(h, kind="stable")
    h, doc = h[order], doc[order]
    head = np.flatnonzero(np.r_[True, h[1:] != h[:-1]][: len(h)])
    if not len(head):
        return pd.DataFrame({"shard": [], "bucket": [], "anchors": []})
    many = np.minimum.reduceat(doc, head) != np.maximum.reduceat(doc, head)
    count = np.minimum(127, np.diff(np.r_[head, len(h)])).astype(np.uint8) | (many.astype(np.uint8) << 7)
    h = h[head]
    cut = np.searchsorted(h >> U(64 - shard_bits), np.arange((1 << shard_bits) + 1, dtype=np.uint64))
    bucket = int(frame["bucket"].iloc[0])
    return pd.DataFrame([(s, bucket, h[i:j].tobytes() + count[i:j].tobytes()) for s, (i, j) in enumerate(zip(cut[:-1], cut[1:], strict=True)) if j > i], columns=["shard", "bucket", "anchors"])


def repeated_anchors(frame):
    """Answers each bucket with its minimisers that two documents hold, as pairs (hash, hash if frequent, else 0)."""
    size = [len(b) // 9 for b in frame["anchors"]]
    h = np.concatenate([np.frombuffer(b, np.uint64, n) for b, n in zip(frame["anchors"], size, strict=True)])
    c = np.concatenate([np.frombuffer(b, np.uint8, n, 8 * n) for b, n in zip(frame["anchors"], size, strict=True)])
    order = np.argsort(h, kind="stable")
    a = h[order]
    head = np.flatnonzero(np.r_[True, a[1:] != a[:-1]])
    run = np.diff(np.r_[head, len(a)])
    total = np.add.reduceat((c[order] & 127).astype(np.int64), head)
    many = (run > 1) | (np.maximum.reduceat(c[order], head) > 127)
    rep, hot = np.empty(len(h), bool), np.empty(len(h), bool)
    rep[order], hot[order] = np.repeat(many, run), np.repeat(total > HOT, run)
    rows, at = [], 0
    for bucket, n in zip(frame["bucket"], size, strict=True):
        own, wide = h[at : at + n], hot[at : at + n]
        pick = rep[at : at + n]
        if pick.any():
            rows.append((int(bucket), np.stack([own[pick], np.where(wide[pick], own[pick], U(0))], 1).tobytes()))
        at += n
    return pd.DataFrame(rows, columns=["bucket", "answer"])


def second_pass(frame, answers, window, gram, shard_bits):
    """The strings of a bucket's repeated runs, for the shards: counts, numbers, smallest documents and the strings themselves."""
    if not len(frame) or not len(answers):
        return pd.DataFrame({"shard": [], "bucket": [], "runs": []})
    _, _, _, number, least, shard, _ = distinct_runs(frame, window, gram, list(answers["answer"]))
    if not number:
        return pd.DataFrame({"shard": [], "bucket": [], "runs": []})
    pieces = [p[1] if isinstance(p, tuple) else p for p in number]
    shard = (np.array(shard, np.uint64) >> U(64 - shard_bits)).astype(np.int64)
    order = np.argsort(shard, kind="stable")
    cut = np.searchsorted(shard[order], np.arange((1 << shard_bits) + 1))
    least = np.array(least, "<i8")
    size = np.array([len(p) for p in pieces], "<u4")
    bucket, rows = int(frame["bucket"].iloc[0]), []
    for s, (i, j) in enumerate(zip(cut[:-1], cut[1:], strict=True)):
        if j > i:
            own = order[i:j]
            blob = np.uint32(j - i).tobytes() + own.astype("<u4").tobytes() + size[own].tobytes() + least[own].tobytes() + b"".join([pieces[k] for k in own.tolist()])
            rows.append((s, bucket, zlib.compress(blob, 1)))
    return pd.DataFrame(rows, columns=["shard", "bucket", "runs"])


def scan_shard(frame, window):
    """Feeds a shard's strings to a suffix family in document order; answers each bucket with (number, bits of matched windows)."""
    number, size, least, bucket, text = [], [], [], [], []
    for k, blob in zip(frame["bucket"], frame["runs"], strict=True):
        blob = zlib.decompress(blob)
        n = int(np.frombuffer(blob, "<u4", 1)[0])
        number.append(np.frombuffer(blob, "<u4", n, 4))
        size.append(np.frombuffer(blob, "<u4", n, 4 + 4 * n).astype(np.int64))
        least.append(np.frombuffer(blob, "<i8", n, 4 + 8 * n))
        bucket.append(np.full(n, k, np.int64))
        text.append(np.frombuffer(blob, np.uint8, -1, 4 + 16 * n))
    number, size, least, bucket, text = (np.concatenate(x) for x in (number, size, least, bucket, text))
    begin = np.cumsum(size) - size
    order = np.lexsort((number, bucket, least))
    windows = size[order] - window + 1
    total = np.cumsum(windows)
    family, mask = SuffixFamily(window), np.zeros(len(order), np.uint64)
    at = 0
    while at < len(order):
        to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + BATCH, side="right")))
        own, w = order[at:to], windows[at:to]
        which = np.repeat(np.arange(len(own)), w)
        step = np.arange(len(which)) - np.repeat(np.cumsum(w) - w, w)
        hit = family.add(text, begin[own][which] + step, least[own][which])
        np.bitwise_or.at(mask, own[which[hit]], U(1) << step[hit].astype(np.uint64))
        at = to
    rows = []
    for k in np.unique(bucket[mask != 0]).tolist():
        pick = np.flatnonzero((bucket == k) & (mask != 0))
        rows.append((int(k), number[pick].astype("<u4").tobytes() + mask[pick].tobytes()))
    return pd.DataFrame(rows, columns=["bucket", "matched"])


def finish(frame, answers, window, gram, with_text):
    """Removes the covered bytes of a bucket's documents. Answers of both kinds arrive in one frame; with_text: only the texts left, in order of id and text."""
    columns = ["kept"] if with_text else ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
    if not len(frame):
        return pd.DataFrame({c: [] for c in columns})
    first = answers["answer"].notna() if len(answers) else []
    ids, keys, texts, number, least, _, seen = distinct_runs(frame, window, gram, list(answers["answer"][first]) if len(answers) else [])
    mask = np.zeros(len(number), np.uint64)
    for blob in answers["matched"][~first] if len(answers) else []:
        n = len(blob) // 12
        mask[np.frombuffer(blob, "<u4", n)] = np.frombuffer(blob[4 * n :], np.uint64)
    hits = [[] for _ in texts]
    bits = mask.tolist()
    for t, s, n, i in seen:
        m = (1 << n) - 1 if least[i] < keys[t] else bits[i]
        if m:
            hits[t].append((s, m))
    rows = []
    for i, t, own in zip(ids, texts, hits, strict=True):
        a = b = np.zeros(0, np.int64)
        if own:
            start = np.array([s for s, _ in own], np.int64)
            m = np.array([m for _, m in own], np.uint64)
            which, step = np.nonzero((m[:, None] >> np.arange(64, dtype=np.uint64)) & U(1))
            a, b = K.spans_of(K.cover(len(t), start[which] + step, window))
        if with_text:
            rows.append((cut_characters(t, a, b) if own else None,))
        else:
            kept = b"".join([t[x:y] for x, y in zip([0, *b.tolist()], [*a.tolist(), len(t)], strict=True)]) if own else t
            rows.append((i, len(t), len(t) - len(kept), len(a), hashlib.sha256(kept).hexdigest()))
    return pd.DataFrame(rows, columns=columns) if with_text else K.id_frame(rows, columns)


def cut_characters(text: bytes, starts: np.ndarray, ends: np.ndarray) -> str:
    """The text without the spans; a character that a span cuts stays whole."""
    parts, at = [], 0
    for a, b in zip(starts.tolist(), ends.tolist(), strict=True):
        while a < b and text[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(text) and text[b] & 0xC0 == 0x80:
            b -= 1
        parts.append(text[at:a])
        at = b
    return b"".join([*parts, text[at:]]).decode("utf-8", "replace")


def answers_of(texts: DataFrame, window: int, gram: int, bits: int) -> DataFrame:
    """What each bucket has to know: its repeated minimisers, and the matched windows of its strings."""
    anchors = texts.groupBy("bucket").applyInArrow(arrow(lambda f: first_pass(f, window, gram, bits), [("shard", "int32"), ("bucket", "int32"), ("anchors", "binary")]), "shard int, bucket int, anchors binary")
    repeated = anchors.groupBy("shard").applyInPandas(repeated_anchors, "bucket int, answer binary")
    runs = texts.groupBy("bucket").cogroup(repeated.groupBy("bucket")).applyInArrow(arrow(lambda f, a: second_pass(f, a, window, gram, bits + 2), [("shard", "int32"), ("bucket", "int32"), ("runs", "binary")]), "shard int, bucket int, runs binary")
    matched = runs.groupBy("shard").applyInPandas(lambda f: scan_shard(f, window), "bucket int, matched binary")
    return repeated.withColumn("matched", F.lit(None).cast("binary")).unionByName(matched.withColumn("answer", F.lit(None).cast("binary")))


def frame_of(table: pa.Table) -> pd.DataFrame:
    return pd.DataFrame({c: table[c].to_pylist() for c in ("bucket", "doc_id", "text")}) if "text" in table.column_names else table.to_pandas()


def arrow(function, fields):
    """A function of frames as one of Arrow tables: columns that it doesn't use are never converted."""
    schema = pa.schema([(n, getattr(pa, t)()) for n, t in fields])
    table = lambda frame: pa.Table.from_pandas(frame, schema=schema, preserve_index=False)
    if function.__code__.co_argcount == 1:
        return lambda own: table(function(frame_of(own)))
    return lambda own, answers: table(function(frame_of(own), frame_of(answers)))


def remove_repeated_bytes(docs: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document. window - gram must be below 64."""
    n = K.bucket_count(K.input_bytes(docs))
    bits = max(2, int(np.ceil(np.log2(n))))
    texts = K.doc_buckets(docs, n)
    both = texts.groupBy("bucket").cogroup(answers_of(texts, window, gram, bits).groupBy("bucket"))
    fields = [("doc_id", "int64"), ("n_bytes", "int64"), ("n_removed", "int64"), ("n_spans", "int64"), ("kept_sha256", "string")]
    return both.applyInArrow(arrow(lambda f, a: finish(f, a, window, gram, False), fields), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def rewrite_documents(docs: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """The documents, all columns, with the text that is left; a character that a span cuts stays whole. n_chars follows a changed text."""
    n = K.bucket_count(K.input_bytes(docs))
    bits = max(2, int(np.ceil(np.log2(n))))
    texts = K.doc_buckets(docs, n, rest=True)
    both = texts.groupBy("bucket").cogroup(answers_of(texts, window, gram, bits).groupBy("bucket"))

    def rows(table: pa.Table, answers: pa.Table) -> pa.Table:
        frame = frame_of(table)
        *_, order = K.row_order(frame)
        kept = finish(frame, answers.to_pandas(), window, gram, True)["kept"].tolist()
        own = table.take(pa.array(order, pa.int64()))
        return pa.table({"text": own["text"], "kept": pa.array(kept, pa.string()), "rest": own["rest"]})

    rest = texts.schema["rest"].dataType.simpleString()
    out = both.applyInArrow(rows, f"text string, kept string, rest {rest}")
    columns = []
    for c in docs.columns:
        if c == "text":
            columns.append(F.coalesce("kept", "text").alias("text"))
        elif c == "n_chars":
            columns.append(F.when(F.col("kept").isNotNull(), F.length("kept").cast(dict(docs.dtypes)[c])).otherwise(F.col("rest.n_chars")).alias(c))
        else:
            columns.append(F.col("rest").getField(c).alias(c))
    return out.select(*columns)


def op4_suffix_family_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeated_bytes(spark.read.parquet(f"{sf_dir}/documents.parquet"))


ORACLES = {
    "op4_suffix_family_dedup": r"""
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
s AS (SELECT doc_id, x, unnest(range(0, greatest(length(x) // 2 - 49, 0))) AS i FROM d),
g AS (SELECT doc_id, i, md5(substr(x, CAST(2 * i + 1 AS BIGINT), 100)) AS k FROM s),
m AS (SELECT k, min(doc_id) AS least FROM g GROUP BY k),
c AS (SELECT g.doc_id, g.i FROM g JOIN m USING (k) WHERE m.least < g.doc_id),
o AS (SELECT doc_id, i, i - lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS gap FROM c),
r AS (SELECT doc_id, i, sum(CASE WHEN gap <= 50 THEN 0 ELSE 1 END) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM o),
u AS (SELECT doc_id, run, min(i) AS a, max(i) + 50 AS b FROM r GROUP BY ALL),
v AS (SELECT u.doc_id, u.run, u.a, u.b, lag(u.b, 1, 0) OVER (PARTITION BY u.doc_id ORDER BY u.a) AS before FROM u),
k AS (SELECT v.doc_id, string_agg(substr(x, CAST(2 * before + 1 AS BIGINT), CAST(2 * (a - before) AS BIGINT)), '' ORDER BY a) AS kept, max(b) AS tail, sum(b - a) AS removed, count(*) AS spans FROM v JOIN d USING (doc_id) GROUP BY v.doc_id)
SELECT d.doc_id, CAST(length(x) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(spans, 0) AS BIGINT) AS n_spans,
       sha256(unhex(coalesce(kept || substr(x, CAST(2 * tail + 1 AS BIGINT)), x))) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)"""
}
