"""N-best segmentation over the piece lattice of a SentencePiece model, and decoding.

Spaces become the mark U+2581 and one is put in front. If no piece has a mark after another character or a line end beside
one (checked; for other models a whole text is one word), the lattice of a text has cut points before each word, and the
N best paths of the text are the N best sums over its words. For every distinct word, forward and backward Viterbi scores give the best path and the loss of the second best; both are
computed for all words of a batch at once. At most N - 1 words of a text can differ from their best path in its N best
(those with the least loss, ties to the earlier), so only these are searched: a backward A-star search from the word's
end, in which the forward Viterbi score of the place still to reach is the exact heuristic, gives their N best paths in
order. A heap then merges them into the N best of the text. Whole texts take part; nothing is pruned. Words of more than
LONG characters, such as a text without spaces, get a lattice of their own, found for all places at once by piece length.

Piece scores are the model's own. Characters without a piece become their bytes, at UNKNOWN below the least score each.
Null or empty text: one path without pieces, score 0. A text with fewer than N paths has that many rows. Other columns
are ignored; rows with the same or no doc_id are treated one by one.
"""

from __future__ import annotations

import heapq
import re
import zlib
from itertools import count

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .kernels import U

K.ship(__name__)

MARK, N_BEST, UNKNOWN, SLOT_BITS, CELLS, LONG = "▁", 5, 10.0, 20, 1 << 21, 512
SCHEMA = "doc_id long, rank int, score double, n_pieces long, ids_crc32 long, decodes boolean"
WORDS = re.compile(f"{MARK}*[^{MARK}\n]+|{MARK}+|\n")


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class Pieces:
    """The model's pieces with their scores, and a hash table of them by code points."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        n = model.get_piece_size()
        self.text = [model.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        self.score = {self.text[i]: (float(model.get_score(i)), i) for i in plain}
        self.bytes = {int(self.text[i][1:-1], 16): i for i in range(n) if model.is_byte(i)}
        usual = [s for s, _ in self.score.values() if s > -1e8]
        self.missing = min(usual) - UNKNOWN
        self.longest = max(map(len, self.score))
        self.cuts = not any(MARK in p.lstrip(MARK) or ("\n" in p and len(p) > 1) for p in self.score)
        self.spell = [self.text[i].replace(MARK, " ").encode() for i in range(n)]
        for b, i in self.bytes.items():
            self.spell[i] = bytes([b])
        for i in set(range(n)) - set(plain) - set(self.bytes.values()):
            self.spell[i] = b""
        self.tables, left = [], [(self.hash_of(p), i, s) for p, (s, i) in self.score.items()]
        while left:
            shift = U(64 - SLOT_BITS - len(self.tables))
            key, ids, score, rest = np.zeros(1 << (64 - int(shift)), np.uint64), np.zeros(1 << (64 - int(shift)), np.int32), np.zeros(1 << (64 - int(shift))), []
            for h, i, s in left:
                at = h >> int(shift)
                if key[at]:
                    rest.append((h, i, s))
                else:
                    key[at], ids[at], score[at] = h, i, s
            self.tables.append((shift, key, ids, score))
            left = rest

    @staticmethod
    def hash_of(piece: str) -> int:
        return int(K.grams(K.mix(np.array([ord(c) for c in piece], np.uint64) + U(1)), len(piece))[0])

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores; -1 and -inf where there is no such piece."""
        ids, score = np.full(len(h), -1, np.int32), np.full(len(h), -np.inf)
        for shift, key, i, s in self.tables:
            at = (h >> shift).astype(np.int64)
            hit = np.flatnonzero(key[at] == h)
            ids[hit], score[hit] = i[at[hit]], s[at[hit]]
        return ids, score

    def byte_ids(self, char: str) -> list[int]:
        return [self.bytes[b] for b in char.encode("utf-8", "surrogatepass")] if self.bytes else [0]


def pieces_of(path: str) -> Pieces:
    return K.cached(("pieces", path), lambda: Pieces(path))


def search(word: str, pieces: Pieces, n: int) -> list[tuple[float, list[int]]]:
    """The n best paths of a word: forward Viterbi, then A-star from its end."""
    if len(word) > LONG:
        return LongWord(word, pieces).n_best(n)
    size, arcs, forward = len(word), [[] for _ in range(len(word) + 1)], [0.0] + [-np.inf] * len(word)
    for end in range(1, size + 1):
        for start in range(max(0, end - pieces.longest), end):
            if found := pieces.score.get(word[start:end]):
                arcs[end].append((start, *found))
        if not any(start == end - 1 for start, _, _ in arcs[end]):
            arcs[end].append((end - 1, pieces.missing, -1))
        forward[end] = max(forward[start] + score for start, score, _ in arcs[end])
    return best_first(word, pieces, n, forward, lambda end: arcs[end])


def best_first(word: str, pieces: Pieces, n: int, forward, arcs) -> list[tuple[float, list[int]]]:
    """A-star from the end over arcs(end), each (start, score, id). Of equal sums the newest goes on first, so ties don't widen the search."""
    order, found = count(0, -1), []
    agenda = [(round(-float(forward[-1]), 7), next(order), len(word), 0.0, None)]
    while agenda and len(found) < n:
        _, _, at, behind, path = heapq.heappop(agenda)
        if at == 0:
            ids, link = [], path
            while link:
                (start, i), link = link
                ids += [i] if i >= 0 else pieces.byte_ids(word[start])
            found.append((behind, ids))
            continue
        for start, score, i in arcs(at):
            heapq.heappush(agenda, (round(-(float(forward[start]) + score + behind), 7), next(order), start, score + behind, ((start, i), path)))
    return found


class LongWord:
    """The lattice of one long word: its arcs by end, found by hash for a piece length at a time, and Viterbi scores both ways."""

    def __init__(self, word: str, pieces: Pieces):
        self.word, self.pieces, size = word, pieces, len(word)
        self.code = np.frombuffer(word.encode("utf-32-le", "surrogatepass"), np.uint32)
        values, parts = K.mix(self.code.astype(np.uint64) + U(1)), []
        for length in range(1, min(pieces.longest, size) + 1):
            ids, score = pieces.find(K.grams(values, length))
            if length == 1:
                score[ids < 0] = pieces.missing
            start = np.flatnonzero(score > -np.inf)
            parts.append((start + length, start, score[start], ids[start]))
        end, self.start, self.score, self.ids = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.lexsort((self.start, end))
        self.end, self.start, self.score, self.ids = end[order], self.start[order], self.score[order], self.ids[order]
        self.bounds = np.searchsorted(self.end, np.arange(size + 2)).tolist()
        self.forward = self.viterbi(self.start.tolist(), self.score.tolist(), self.end.tolist(), size, 0)
        back = self.viterbi(self.end[::-1].tolist(), self.score[::-1].tolist(), self.start[::-1].tolist(), size, size, by=np.argsort(-self.start[::-1], kind="stable").tolist())
        self.best = float(self.forward[size])
        self.gap = self.best - (self.forward[self.start] + self.score + back[self.end])

    @staticmethod
    def viterbi(origin: list, score: list, to: list, size: int, first: int, by=None) -> np.ndarray:
        """Best sums from `first` on; arcs come in an order in which their origins are settled before."""
        best = [-np.inf] * (size + 1)
        best[first] = 0.0
        for k in range(len(to)) if by is None else by:
            s = best[origin[k]] + score[k]
            if s > best[to[k]]:
                best[to[k]] = s
        return np.array(best)

    def path(self) -> tuple[float, np.ndarray, np.ndarray]:
        """Loss of the second best path, and tokens and first characters of the best; of equal arcs the shortest."""
        on = self.gap <= 1e-9 * (1 + abs(self.best))
        ways = np.bincount(self.start[on], minlength=len(self.word))
        loss = 0.0 if (ways > 1).any() else float(self.gap[~on].min(initial=np.inf))
        order = np.flatnonzero(on)[::-1]  # ends rise with the index, so the shortest arc of a start is written last
        via = np.zeros(len(self.word), np.int64)
        via[self.start[order]] = order
        end, at, arcs = self.end.tolist(), 0, []
        while at < len(self.word):
            k = int(via[at])
            arcs.append(k)
            at = end[k]
        return loss, self.ids[arcs].astype(np.int64), self.code[self.start[arcs]]

    def n_best(self, n: int) -> list[tuple[float, list[int]]]:
        arcs = lambda end: zip(*(x[self.bounds[end] : self.bounds[end + 1]].tolist() for x in (self.start, self.score, self.ids)), strict=True)
        return best_first(self.word, self.pieces, n, self.forward, arcs)


def group_lattice(code: np.ndarray, pieces: Pieces):
    """Words of one length, code points [n, size]: best score, loss of the second best path, and per word the tokens of the best path.

    Columns are places, so every step is one operation over all words.
    """
    n, size = code.shape
    longest = min(pieces.longest, size)
    values = K.mix(code.T.astype(np.uint64) + U(1))
    power, inverse = K.powers(K.MULT_A, size + 1)
    prefix = np.zeros((size + 1, n), np.uint64)
    np.cumsum(values * power[:size, None], axis=0, out=prefix[1:])
    score, ids = {}, {}
    forward, back = np.full((size + 1, n), -np.inf), np.full((size + 1, n), -np.inf)
    forward[0], back[size] = 0.0, 0.0
    for end in range(1, size + 1):
        for length in range(1, min(longest, end) + 1):
            start = end - length
            i, s = pieces.find(K.mix((prefix[end] - prefix[start]) * inverse[start]))
            if length == 1:
                s[i < 0] = pieces.missing
            score[start, length], ids[start, length] = s, i
            np.maximum(forward[end], forward[start] + s, out=forward[end])
    for start in range(size - 1, -1, -1):
        for length in range(1, min(longest, size - start) + 1):
            np.maximum(back[start], back[start + length] + score[start, length], out=back[start])
    best = forward[size]
    exact = 1e-9 * (1 + np.abs(best))
    loss, via = np.full(n, np.inf), np.zeros((size, n), np.int32)
    for start in range(size):
        ways = np.zeros(n, np.int32)
        for length in range(min(longest, size - start), 0, -1):
            gap = best - (forward[start] + score[start, length] + back[start + length])
            on = gap <= exact
            ways += on
            via[start][on] = length  # of equal arcs the shortest
            np.minimum(loss, np.where(on, np.inf, gap), out=loss)
        loss[ways > 1] = 0.0
    row, at, rows, tokens, chars = np.arange(n), np.zeros(n, np.int64), [], [], []
    table = np.full((size, longest + 1, n), -1, np.int32)
    for (start, length), i in ids.items():
        table[start, length] = i
    while len(row):
        length = via[at, row]
        rows.append(row)
        tokens.append(table[at, length, row])
        chars.append(code[row, at])
        at = at + length
        stay = at < size
        row, at = row[stay], at[stay]
    row, token, char = (np.concatenate(x) for x in (rows, tokens, chars))
    order = np.argsort(row, kind="stable")
    return best, loss, row[order], token[order].astype(np.int64), char[order]


def lattice(words: list[str], pieces: Pieces):
    """For each word: best score, loss of the second best path, and the ids of the best path (flat, with bounds)."""
    size = np.array([len(w) for w in words], np.int64)
    best, loss = np.zeros(len(words)), np.zeros(len(words))
    parts = []
    by_size = np.argsort(size, kind="stable")
    cut = np.flatnonzero(np.r_[True, np.diff(size[by_size]) > 0])
    for a, b in zip(cut, np.r_[cut[1:], len(words)], strict=True):
        wide = int(size[by_size[a]])
        if wide > LONG:
            for k in by_size[a:b].tolist():
                long = LongWord(words[k], pieces)
                loss[k], token, char = long.path()
                best[k] = long.best
                parts.append((np.full(len(token), k), token, char))
            continue
        step = max(1, CELLS // (wide * min(wide, pieces.longest)))
        for i in range(a, b, step):
            own = by_size[i : min(b, i + step)]
            code = np.frombuffer("".join([words[k] for k in own.tolist()]).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(own), wide)
            best[own], loss[own], row, token, char = group_lattice(code, pieces)
            parts.append((own[row], token, char))
    row, token, char = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(row, kind="stable")
    row, token, char = row[order], token[order], char[order]
    wide = np.where(token >= 0, 1, np.select([char < 0x80, char < 0x800, char < 0x10000], [1, 2, 3], 4) if pieces.bytes else 1)
    flat = np.repeat(token, wide)
    if (token < 0).any():
        flat[flat < 0] = [i for c in char[token < 0].tolist() for i in pieces.byte_ids(chr(c))]
    return best, loss, flat.astype("<u4"), np.r_[0, np.cumsum(np.bincount(row, weights=wide, minlength=len(words)).astype(np.int64))]


def merge(best: float, lists: list[list[tuple[float, list[int]]]], n: int) -> list[tuple[float, tuple[int, ...]]]:
    """The n best sums over lists that each fall in score."""
    first = (0,) * len(lists)
    agenda, seen, found = [(-best, first)], {first}, []
    while agenda and len(found) < n:
        cost, at = heapq.heappop(agenda)
        found.append((-cost, at))
        for k, ranked in enumerate(lists):
            if at[k] + 1 < len(ranked):
                to = (*at[:k], at[k] + 1, *at[k + 1 :])
                if to not in seen:
                    seen.add(to)
                    heapq.heappush(agenda, (cost + ranked[at[k]][0] - ranked[at[k] + 1][0], to))
    return found


def words_of(text: str, pieces: Pieces) -> list[str]:
    marked = MARK + text.replace(" ", MARK) if text else ""
    return WORDS.findall(marked) if pieces.cuts else [marked] * bool(marked)


def n_best(texts: list[str], pieces: Pieces, n: int):
    """For each text its n best (score, ids), and whether the best ids decode to the text."""
    number: dict[str, int] = {}
    places = [np.array([number.setdefault(w, len(number)) for w in words_of(t, pieces)], np.int64) for t in texts]
    words = list(number)
    if not words:
        return [([(0.0, np.zeros(0, "<u4"))], True) for _ in texts]
    best, loss, flat, bounds = lattice(words, pieces)
    spell, tokens = pieces.spell, flat.tolist()
    same = np.array([b"".join([spell[i] for i in tokens[a:b]]) == w.replace(MARK, " ").encode("utf-8", "surrogatepass") for w, a, b in zip(words, bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)])
    width = np.diff(bounds)
    ranked: dict[int, list] = {}
    out = []
    for text, own in zip(texts, places, strict=True):
        total = float(best[own].sum())
        wide = width[own]
        ends = np.cumsum(wide)
        begin = ends - wide
        ids = flat[np.repeat(bounds[own] - begin, wide) + np.arange(int(ends[-1]) if len(ends) else 0)]
        losses = loss[own]
        can = np.flatnonzero(losses < np.inf)
        if len(can) >= n:
            limit = np.partition(losses[can], n - 2)[n - 2] if n > 1 else -1.0
            can = can[losses[can] <= limit]
            can = can[np.argsort(losses[can], kind="stable")][: n - 1]
        lists = [ranked[k] if k in ranked else ranked.setdefault(k, search(words[k], pieces, n)) for k in own[can].tolist()]
        paths = []
        for score, at in merge(total, lists, n):
            changes = sorted((int(begin[c]), int(ends[c]), lists[k][at[k]][1]) for k, c in enumerate(can.tolist()) if at[k] or len(paths) == 0)
            parts, done = [], 0
            for a, b, new in changes:
                parts += [ids[done:a], np.array(new, "<u4")]
                done = b
            paths.append((score, np.concatenate([*parts, ids[done:]]).astype("<u4")))
        out.append((paths, bool(same[own].all()) and MARK not in text))
    return out


def decode(ids, pieces: Pieces) -> str:
    """The text of ids; the space in front that encoding added goes."""
    spell = pieces.spell
    text = b"".join([spell[i] for i in ids]).decode("utf-8", "replace")
    return text[1:] if text.startswith(" ") else text


def segment_partition(frames, path: str, n: int):
    pieces = pieces_of(path)
    for frame in frames:
        ids = K.row_ids(frame["doc_id"])
        texts = [t if isinstance(t, str) else "" for t in frame["text"]]
        for a, b in K.chunks(texts, [len(t) + 1 for t in texts], 1 << 22):
            rows = []
            for doc, (paths, whole) in zip(ids[a:b], n_best(texts[a:b], pieces, n), strict=True):
                for rank, (score, path_ids) in enumerate(paths, 1):
                    rows.append((doc, rank, score, len(path_ids), zlib.crc32(path_ids.tobytes()), whole))
            yield K.id_frame(rows, ["doc_id", "rank", "score", "n_pieces", "ids_crc32", "decodes"])


def segment_documents(docs: DataFrame, model: str | None = None, n: int = N_BEST) -> DataFrame:
    """A row for each document and rank: score, number of pieces, crc32 of the ids, and whether the best path's ids decode to the text (a text that itself holds the mark doesn't)."""
    path = model or default_model()
    source = K.id_text(docs)
    return source.mapInPandas(lambda frames: segment_partition(frames, path, n), SCHEMA)


def op2_nbest_segmentation(spark, sf_dir: str) -> DataFrame:
    return segment_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
