"""The advancing front in one task: whole generations in numpy, with the same result as one point at a time.

The queue is first in, first out, so all points of a generation are expanded before any of the next. A candidate is
therefore lost to older generations, whose points are all known, or to candidates of its own generation that come before
it: the survivors are the first maximal independent set in (parent, direction) order.
"""

from __future__ import annotations

import itertools
import sys

import numpy as np
from pyspark import cloudpickle

from ..functions import geometry as G

cloudpickle.register_pickle_by_value(sys.modules[__name__])
cloudpickle.register_pickle_by_value(G)


class Buckets:
    """A dense grid of chains of points over a box; cells of the given side."""

    def __init__(self, low, high, side: float):
        self.low, self.side = np.asarray(low, float) - side, float(side)
        self.shape = np.maximum(1, np.ceil((np.asarray(high, float) - self.low) / side).astype(np.int64) + 2)
        self.step = np.r_[1, np.cumprod(self.shape[:-1])].astype(np.int64)
        self.head = np.full(int(np.prod(self.shape)), -1, np.int32)
        self.next = np.full(1024, -1, np.int32)
        near = sorted(itertools.product((-1, 0, 1), repeat=len(self.low)), key=lambda o: sum(map(abs, o)))
        self.offsets = np.array([np.dot(o, self.step) for o in near])

    def cell(self, p: np.ndarray) -> np.ndarray:
        return np.clip(((p - self.low) / self.side).astype(np.int64), 1, self.shape - 2) @ self.step

    def add(self, index: np.ndarray, p: np.ndarray) -> None:
        if not len(index):
            return
        if index.max() >= len(self.next):
            self.next = np.r_[self.next, np.full(max(len(self.next), int(index.max()) + 1 - len(self.next)), -1, np.int32)]
        cell = self.cell(p)
        order = np.argsort(cell, kind="stable")
        c, i = cell[order], index[order]
        first = np.r_[True, c[1:] != c[:-1]]
        self.next[i[1:][~first[1:]]] = i[:-1][~first[1:]]
        self.next[i[first]] = self.head[c[first]]
        last = np.r_[first[1:], True]
        self.head[c[last]] = i[last]

    def pairs(self, p: np.ndarray, done: np.ndarray | None = None):
        """(query, point) for all points in the neighbouring cells, nearest cells first, a link of every chain at a time. Queries that the caller marks in `done` are left out from then on."""
        cell = self.cell(p)
        live = np.arange(len(p))
        for o in self.offsets:
            if done is not None:
                live = live[~done[live]]
            at = self.head[cell[live] + o]
            some = at >= 0
            q, i = live[some], at[some]
            while len(q):
                yield q, i
                i = self.next[i]
                some = i >= 0 if done is None else (i >= 0) & ~done[q]
                q, i = q[some], i[some]


class Index:
    """Points in one grid for each octave of radius, so that a look-up meets only the 3^d cells around it."""

    def __init__(self, low, high, least: float, most: float):
        octaves = max(1, int(np.ceil(np.log2(most / least) + 1e-9)) or 1)
        self.least, self.grids = least, [Buckets(low, high, least * 2.0 ** (k + 1)) for k in range(octaves)]

    def octave(self, r: np.ndarray) -> np.ndarray:
        return np.clip(np.floor(np.log2(r / self.least)).astype(int), 0, len(self.grids) - 1)

    def add(self, index, p) -> None:
        for g in self.grids:
            g.add(index, p)

    def blocked(self, p: np.ndarray, r: np.ndarray, points: np.ndarray) -> np.ndarray:
        """Which candidates lie within their radius of a point."""
        out, octave, limit = np.zeros(len(p), bool), self.octave(r), r * r * G.SLACK
        for k, grid in enumerate(self.grids):
            own = np.flatnonzero(octave == k)
            if len(own):
                hit, at, within = np.zeros(len(own), bool), p[own], limit[own]
                for q, i in grid.pairs(at, hit):
                    d = at[q] - points[i]
                    hit[q[np.einsum("ij,ij->i", d, d) < within[q]]] = True
                out[own] = hit
        return out


def conflicts(p: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(blocker, blocked): an earlier candidate within the later one's radius."""
    if len(p) < 2:
        return np.zeros(0, int), np.zeros(0, int)
    side = r.max()
    cell = np.floor(p / side).astype(np.int64)
    cell -= cell.min(0) - 1
    step = np.r_[1, np.cumprod((cell.max(0) + 3)[:-1])]
    key = cell @ step
    order = np.argsort(key, kind="stable")
    sorted_key = key[order]
    a, b = [], []
    for o in itertools.product((-1, 0, 1), repeat=p.shape[1]):
        to = key + np.dot(o, step)
        i, j = np.searchsorted(sorted_key, to), np.searchsorted(sorted_key, to, side="right")
        n = j - i
        q = np.repeat(np.arange(len(p)), n)
        other = order[np.repeat(i, n) + np.arange(len(q)) - np.repeat(np.cumsum(n) - n, n)]
        keep = other < q
        q, other = q[keep], other[keep]
        d = p[q] - p[other]
        close = np.einsum("ij,ij->i", d, d) < r[q] ** 2 * G.SLACK
        a.append(other[close])
        b.append(q[close])
    return np.concatenate(a), np.concatenate(b)


def first_independent(n: int, blocker: np.ndarray, blocked: np.ndarray) -> np.ndarray:
    """Greedy acceptance in order: True for those that no accepted earlier one blocks. The order is that of the edges; where it is that of the numbers, one walk does."""
    if (blocker < blocked).all():
        order = np.argsort(blocked, kind="stable")
        kept = [True] * n
        for a, b in zip(blocker[order].tolist(), blocked[order].tolist(), strict=True):
            if kept[a]:  # settled, as all edges into a came before
                kept[b] = False
        return np.array(kept, bool)
    state = np.zeros(n, np.int8)  # 0 open, 1 accepted, -1 lost
    waits = np.zeros(n, bool)
    waits[blocked] = True
    state[~waits] = 1
    waiting = np.flatnonzero(waits)
    while len(waiting):
        lost = blocked[state[blocker] == 1]
        state[lost[state[lost] == 0]] = -1
        live = (state[blocker] == 0) & (state[blocked] == 0)
        blocker, blocked = blocker[live], blocked[live]
        waits[waiting] = False
        waits[blocked] = True
        waiting = waiting[state[waiting] == 0]
        state[waiting[~waits[waiting]]] = 1
        waiting = waiting[waits[waiting]]
    return state == 1


def fill(region, spacing, seeds: np.ndarray, seed_ids: np.ndarray, n_c: int = 12, exclusion: str = "parent", rotate: bool = True, allowed=None, around=None, seed_radii=None, limit: int = 0, salt: int = 0) -> dict:
    """All points that the front places from the seeds, in order.

    allowed: further test of candidates, such as the own cell. around: points that block but don't expand.
    exclusion: whose spacing is the radius, the parent's or the candidate's own (then the parent is exempt), or
    `literal`: the candidate's own, the parent included. limit: stop after the generation that passes it.
    salt: makes ids of children differ from those that the same parents had in a fill at another spacing.
    `open` in the result: points with a candidate inside the region that only `allowed` refused.
    """
    dim = region.dim
    u = G.banks(dim, n_c, rotate)
    nct = u.shape[1]
    index = Index(region.low, region.high, spacing.least * 0.999, spacing.most * 1.001)
    around = np.zeros((0, dim)) if around is None else np.asarray(around, float).reshape(-1, dim)
    points = np.concatenate([around, np.asarray(seeds, float).reshape(-1, dim)])
    n0, n = len(around), len(around) + len(seeds)
    index.add(np.arange(n), points)
    h = spacing.at(points)
    refused = [np.zeros(len(seeds), bool)]
    columns = {k: [v] for k, v in {"pid": np.asarray(seed_ids, np.int64), "parent": np.full(len(seeds), -1, np.int64), "cand": np.full(len(seeds), -1), "gen": np.zeros(len(seeds), int), "seed_id": np.asarray(seed_ids, np.int64), "r": h[n0:] if seed_radii is None else np.asarray(seed_radii, float)}.items()}
    counts = dict.fromkeys(("expanded", "candidates", "outside", "close", "sibling", "placed"), 0)
    front, ids, roots, gen = np.arange(n0, n), np.asarray(seed_ids, np.int64), np.asarray(seed_ids, np.int64), 0
    while len(front) and not (limit and n - n0 >= limit):
        gen += 1
        bank = np.mod(G.xxhash_long(ids), 16)
        c = (points[front][:, None, :] + h[front][:, None, None] * u[bank]).reshape(-1, dim)
        src = np.repeat(np.arange(len(front)), nct)
        j = np.tile(np.arange(nct), len(front))
        counts["expanded"] += len(front)
        counts["candidates"] += len(c)
        ok = ((c >= np.array(region.low)) & (c <= np.array(region.high))).all(1)
        ok[ok] = region.test(c[ok])
        counts["outside"] += int((~ok).sum())
        c, src, j = c[ok], src[ok], j[ok]
        r = h[front][src] if exclusion == "parent" else spacing.at(c)
        if exclusion == "candidate":
            close = np.zeros(len(c), bool)
            octave, limit2 = index.octave(r), r * r * G.SLACK
            for k, grid in enumerate(index.grids):
                own = np.flatnonzero(octave == k)
                for q, i in grid.pairs(c[own]) if len(own) else ():
                    d = c[own[q]] - points[i]
                    close[own[q]] |= (np.einsum("ij,ij->i", d, d) < limit2[own[q]]) & (i != front[src[own[q]]])
        else:
            close = index.blocked(c, r, points)
        counts["close"] += int(close.sum())
        c, src, j, r = c[~close], src[~close], j[~close], r[~close]
        if allowed is not None and len(c):  # after the look-up, as that leaves few
            ok = allowed(c)
            refused[-1][src[~ok]] = True
            counts["outside"] += int((~ok).sum())
            c, src, j, r = c[ok], src[ok], j[ok], r[ok]
        keep = first_independent(len(c), *conflicts(c, r))
        counts["sibling"] += int((~keep).sum())
        c, src, j, r = c[keep], src[keep], j[keep], r[keep]
        new = np.arange(n, n + len(c))
        index.add(new, c)
        points, h = np.concatenate([points, c]), np.concatenate([h, spacing.at(c)])
        parent, roots = ids[src], roots[src]
        ids = G.child_id(parent, j + (salt << 20))
        for k, v in zip(("pid", "parent", "cand", "gen", "seed_id", "r"), (ids, parent, j, np.full(len(c), gen), roots, r), strict=True):
            columns[k].append(v)
        refused.append(np.zeros(len(c), bool))
        front, n = new, n + len(c)
    counts["placed"] = n - n0
    out = {k: np.concatenate(v) for k, v in columns.items()}
    return out | {"pos": points[n0:], "h": h[n0:], "open": np.concatenate(refused), "counts": counts, "generations": gen}
