"""Hierarchical multi-length packing of documents into training sequences.

A document's ids are followed by END. Whole windows of the longest tier leave it first; the rest is routed to the
smallest tier that holds it. Each tier's pieces open windows of its size, longest first; a window's gap is filled with
the longest pieces that fit from its own and the shorter tiers, and at last by cutting a piece, so windows are full.
Only the last window of a partition can stay short; it counts as one of the longest tier and is padded.
Sequences of a tier are dealt to step groups by attention cost, to and fro, so that the groups' costs balance.

Partitions are packed where they are read: no exchange, and memory bounded by POOL_IDS ids besides a batch of texts.
Sequence and group numbers hold the partition, so they are stable when a task runs again over the same input split.
Null or empty text: the one id END. Rows with the same or no doc_id are packed one by one. Other columns are ignored.
"""

from __future__ import annotations

import base64
import bisect
import re
import zlib

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K

K.ship(__name__)

TIERS, END, POOL_IDS, GROUP, WAIT = (256, 512, 1024, 2048), 1, 1 << 21, 8, 64
LONG_SPACE = re.compile("[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]{4096,}")  # fixed: Unicode white space, as the pattern's \s has it
ADDED = {"<|endoftext|>": 50256}  # fixed value of the vocabulary
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, tier int, step_group long, attention_cost long"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def byte_pair_encoder(path: str):
    """The vocabulary as ranks; gives the same ids as its JSON form in `tokenizers`, six times as fast."""

    def build():
        import public_tokenizers
        import tiktoken

        with open(path, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        return tiktoken.Encoding("vocabulary", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    return K.cached(("bpe", path), build)


def encode_text(encoder, text: str, added: dict[str, int] | None = None) -> np.ndarray:
    """Ids of a text of any shape; an added token becomes its id wherever it stands, and what lies between is encoded by itself.

    The pattern looks ahead over white space, which the regex engine can't do over very long runs. A run is one piece but
    for its last character, which belongs to what follows, so a long run is cut out and merged by itself.
    """
    if added:
        pieces = re.split("(" + "|".join(map(re.escape, sorted(added, key=len, reverse=True))) + ")", text)
        if len(pieces) > 1:
            return np.concatenate([np.array([added[p]], np.uint32) if k % 2 else encode_text(encoder, p) for k, p in enumerate(pieces)])
    encode, parts, at = encoder.encode_to_numpy, [], 0
    for run in LONG_SPACE.finditer(text):
        end = run.end() if run.end() == len(text) else run.end() - 1
        parts += [encode(text[at : run.start()], disallowed_special=()), np.array(encoder._encode_single_piece(text[run.start() : end]), np.uint32)]
        at = end
    parts.append(encode(text[at:], disallowed_special=()))
    return np.concatenate(parts) if len(parts) > 1 else parts[0]


class Packer:
    """Pools of pieces by length, and the sequences made of them."""

    def __init__(self, tiers, first: int):
        self.tiers, self.pool, self.held = tuple(sorted(tiers)), [], 0
        self.next, self.group = first, first
        self.done, self.rows = {t: [] for t in self.tiers}, []

    def put(self, doc, start: int, ids: np.ndarray, total: int, number: int) -> None:
        bisect.insort(self.pool, (len(ids), number, start, doc, ids, total))
        self.held += len(ids)

    def add(self, doc, ids: np.ndarray, number: int) -> None:
        longest, at = self.tiers[-1], 0
        while len(ids) - at >= longest:
            self.emit(longest, [(doc, at, ids[at : at + longest], len(ids))])
            at += longest
        if at < len(ids):
            self.put(doc, at, ids[at:], len(ids), number)

    def take(self, room: int):
        """The longest piece that fits, or else the shortest, cut."""
        k = bisect.bisect_right(self.pool, (room, float("inf")))
        n, number, start, doc, ids, total = self.pool.pop(k - 1 if k else 0)
        self.held -= n
        if n > room:
            self.put(doc, start + room, ids[room:], total, number)
            ids = ids[:room]
        return doc, start, ids, total

    def pack(self, until: int) -> None:
        """Packs the longest pieces until the pool holds at most `until` ids."""
        while self.pool and self.held > until:
            n = self.pool[-1][0]
            tier = self.tiers[bisect.bisect_left(self.tiers, n)]
            if self.held < tier:
                tier = next((t for t in reversed(self.tiers) if t <= self.held), self.tiers[-1])
            parts, room = [], tier
            if n <= room:
                parts.append(self.take(n))
                room -= n
            while room and self.pool:
                parts.append(self.take(room))
                room -= len(parts[-1][2])
            self.emit(self.tiers[-1] if room else tier, parts)

    def emit(self, tier: int, parts) -> None:
        cost = sum(len(p[2]) ** 2 for p in parts)
        self.done[tier].append((cost, self.next, parts))
        self.next += 1
        if len(self.done[tier]) >= WAIT * GROUP:
            self.deal(tier)

    def deal(self, tier: int) -> None:
        """Deals a tier's sequences to step groups: by falling cost, to and fro."""
        queue, self.done[tier] = sorted(self.done[tier], key=lambda s: (-s[0], s[1])), []
        groups = max(1, len(queue) // GROUP)
        for k, (cost, number, parts) in enumerate(queue):
            lap, place = divmod(k, groups)
            group, offset = self.group + (groups - 1 - place if lap % 2 else place), 0
            for doc, start, ids, total in parts:
                self.rows.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), total, number, offset, tier, group, cost))
                offset += len(ids)
        self.group += groups

    def flush(self) -> pd.DataFrame:
        rows, self.rows = self.rows, []
        return K.id_frame(rows, [x.split()[0] for x in SCHEMA.split(", ")])


def pack_partition(frames, path: str, tiers, end: int, added=None):
    encoder = byte_pair_encoder(path)
    packer, number = Packer(tiers, TaskContext.get().partitionId() << 36), 0
    for frame in frames:
        for doc, text in zip(frame["doc_id"], frame["text"], strict=True):
            ids = encode_text(encoder, text, added) if isinstance(text, str) and text else np.zeros(0, np.uint32)
            packer.add(None if doc is None or doc != doc else int(doc), np.r_[ids, np.uint32(end)].astype(np.uint32), number)
            number += 1
            if packer.held > POOL_IDS:
                packer.pack(POOL_IDS // 2)
        yield packer.flush()
    packer.pack(0)
    for tier in packer.tiers:
        packer.deal(tier)
    yield packer.flush()


def pack_documents(docs: DataFrame, vocabulary: str | None = None, tiers=TIERS, end: int = END, added: dict[str, int] | None = None) -> DataFrame:
    """A row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, tier, step_group, attention_cost.

    `added` maps tokens that are read as one id inside texts; without it they are ordinary text, so no text can forge one.
    """
    path = vocabulary or default_vocabulary()
    source = K.id_text(docs)
    return source.mapInPandas(lambda frames: pack_partition(frames, path, tiers, end, added), SCHEMA)


def op1_hierarchical_packing(spark, sf_dir: str) -> DataFrame:
    """The ids that `tokenizers` gives by its default, which reads the vocabulary's added token inside texts."""
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), added=ADDED)
