"""Exact top-k by inner product: a Voronoi join of queries and data.

Vectors become integers, floor(256 x). Pivots are a sample by hash, a sixteenth of the root of the number of rows, between PIVOTS
and MAX_PIVOTS; each row belongs to its nearest pivot. Rows of a cell are packed into blocks of at most BLOCK rows, sorted by their distance to the pivot, and queries into
blocks of their own cell. Each query block is first solved in one block of its own cell; the k-th scores found are lower
bounds. With q = p + a and x = p' + b, |q.x - p.p'| is at most |a||p'| + |b||p| + |a||b|: from the cells' summaries this
gives an upper bound of each cell for each query block, and only the cells that can still reach the block's bound are sent
to it. Each (query block, data block) pair is solved locally; the best k of a query over its pairs are the result.

A cell with a third of all rows is many blocks, each a row of its own, so no task gathers it. Scores: float64 where that is
exact, else whole numbers of any size; beyond a long they end at its limits. Vectors of different lengths have no inner
product: each length that occurs is a join of its own. Vectors null, empty or with null or non-finite components take no part.
Equal scores: smaller vec_id first. Fewer candidates than k: all of them. Null vec_id takes no part; other columns are ignored.
Repeated rows are a candidate each, and a query's repeats ask once more each, as in the query's SQL. Equal rows become one
row with its number before blocks are packed, so bounds and local ranks count different rows, and the last rank all.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K

K.ship(__name__)

LARGEST = 2.0**1015  # 256 times it is finite
PIVOTS, MAX_PIVOTS, BLOCK, QUERY_BLOCK, K_BEST, EVERY, SCALE = 64, 4096, 2048, 256, 5, 50, 256


def integers(vectors: DataFrame) -> DataFrame:
    """vec_id and its integer components, without the vectors that take no part."""
    v = F.col("embedding").cast("array<double>")
    ok = F.col("vec_id").isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vectors.filter(ok).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(v, whole).alias("v"))


def whole(x):
    """floor(256 x) as a double; from 2^52 on a double is a whole number already, and one too large to be scaled stays finite."""
    big = F.abs(x) >= float(2**52)
    return F.when(big, F.greatest(F.least(x, F.lit(LARGEST)), F.lit(-LARGEST)) * SCALE).otherwise(F.floor(x * SCALE).cast("double"))


def lengths_of(rows: DataFrame) -> list[tuple[int, int]]:
    """(length, rows) of the vectors, most rows first."""
    found = rows.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n")).filter("n > 1").collect()
    return sorted(((r["d"], r["n"]) for r in found), key=lambda x: (-x[1], x[0]))


def choose_pivots(rows: DataFrame, n: int) -> np.ndarray:
    """A sample by hash, without equal vectors: at most n rows come to the driver."""
    found = rows.select("v").orderBy(F.xxhash64("vec_id"), "vec_id").limit(n).collect()
    return np.unique(np.array([r["v"] for r in found]), axis=0)


def pack_cells(frames, pivots, every):
    """Blocks of one partition: (cell, kind 0 data or 1 query, ids, repeats, matrix, least and largest distance to the pivot)."""
    held: dict = {}

    def block(key):
        ids, times, rows, far = (np.concatenate(x) for x in zip(*held.pop(key), strict=True))
        order = np.lexsort((ids, far))
        step = QUERY_BLOCK if key[1] else BLOCK
        return [(*key, ids[o].tobytes(), times[o].tobytes(), rows[o].astype("<f4" if np.abs(rows).max(initial=0) < 2**24 else "<f8").tobytes(), len(o), float(far[o[0]]), float(far[o[-1]])) for o in (order[i : i + step] for i in range(0, len(order), step))]

    columns = ["cell", "kind", "ids", "times", "matrix", "n", "near", "far"]
    with np.errstate(over="ignore"):
        norm = (pivots**2).sum(1)
    for frame in frames:
        if not len(frame):
            continue
        ids, times = frame["vec_id"].to_numpy(np.int64), frame["m"].to_numpy(np.int64)
        rows = np.stack(frame["v"].to_list())
        with np.errstate(over="ignore", invalid="ignore"):
            d2 = np.nan_to_num(norm[None, :] - 2 * rows @ pivots.T + (rows**2).sum(1)[:, None], nan=np.inf)
        cell = d2.argmin(1)
        far = np.sqrt(np.maximum(0, d2[np.arange(len(cell)), cell]))
        for c in np.unique(cell).tolist():
            for kind, mask in ((0, cell == c), (1, (cell == c) & (ids % every == 0))):
                if mask.any():
                    held.setdefault((c, kind), []).append((ids[mask], times[mask], rows[mask], far[mask]))
        full = [k for k, v in held.items() if sum(len(x[0]) for x in v) >= 4 * BLOCK]
        if full:
            yield pd.DataFrame([r for k in full for r in block(k)], columns=columns)
    if held:
        yield pd.DataFrame([r for k in list(held) for r in block(k)], columns=columns)


def solve(qids, q, xids, x, k):
    """Places and scores of the best k of x for each q but itself: score falling, then vec_id rising."""
    scores = q @ x.T if exact(q, x) else whole_scores(q, x)
    scores[qids[:, None] == xids[None, :]] = -np.inf
    take = min(k, scores.shape[1])
    if scores.dtype == object:  # rare: whole numbers beyond a double's
        best = [sorted(range(len(xids)), key=lambda j: (-row[j], xids[j]))[:k] for row in scores]
        return [(np.array([j for j in own if row[j] > -np.inf], np.int64), [row[j] for j in own if row[j] > -np.inf]) for own, row in zip(best, scores, strict=True)]
    kth = -np.partition(-scores, take - 1, axis=1)[:, take - 1] if take else np.zeros(len(q))
    out = []
    for i in range(len(q)):
        at = np.flatnonzero((scores[i] >= kth[i]) & (scores[i] > -np.inf))
        order = np.lexsort((xids[at], -scores[i][at]))[:k]
        out.append((at[order], scores[i][at[order]]))
    return out


def exact(q: np.ndarray, x: np.ndarray) -> bool:
    """Whether every partial sum of the inner products is a whole number below 2^53."""
    return float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * q.shape[1] < 2.0**53


def whole_scores(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Inner products as whole numbers of any size, cut to the range of a long (-inf may be put in)."""
    big = lambda a: np.array([[int(v) for v in r] for r in a.tolist()], object).reshape(a.shape)
    return np.clip(big(q) @ big(x).T, -(2**63), 2**63 - 1)


def decode_block(blob: bytes, n: int, dim: int) -> np.ndarray:
    return np.frombuffer(blob, "<f4" if len(blob) == 4 * n * dim else "<f8").reshape(n, dim).astype(float)


def first_bounds(frames, k, dim):
    """Each query block's least k-th score within one block of its own cell."""
    for frame in frames:
        rows = []
        for r in frame.itertuples():
            bound = -np.inf
            if r.x_ids is not None:
                found = solve(np.frombuffer(r.ids, np.int64), decode_block(r.matrix, r.n, dim), np.frombuffer(r.x_ids, np.int64), decode_block(r.x_matrix, r.x_n, dim), k)
                bound = min((float(s[k - 1]) if len(s) >= k else -np.inf) for _, s in found)
            rows.append((r.block, r.cell, r.far, float(bound)))
        yield pd.DataFrame(rows, columns=["block", "cell", "far", "bound"])


def reachable(frames, pivots, summary):
    """The cells each query block still needs, from the pivots and the cells' radii."""
    with np.errstate(over="ignore"):
        norm, dots = np.sqrt((pivots**2).sum(1)), pivots @ pivots.T
    for frame in frames:
        rows = []
        for r in frame.itertuples():
            with np.errstate(over="ignore", invalid="ignore"):
                upper = dots[r.cell] + r.far * norm + summary * norm[r.cell] + r.far * summary
                rows += [(r.block, int(c)) for c in np.flatnonzero(~(upper + 1e-6 * (1 + np.abs(upper)) < r.bound) & (summary >= 0))]
        yield pd.DataFrame(rows, columns=["block", "to"])


def local_best(frames, k, dim):
    for frame in frames:
        rows = []
        for r in frame.itertuples():
            qids, xids, asked, held = (np.frombuffer(b, np.int64) for b in (r.ids, r.x_ids, r.times, r.x_times))
            best = solve(qids, decode_block(r.matrix, r.n, dim), xids, decode_block(r.x_matrix, r.x_n, dim), k)
            for q, m, (at, scores) in zip(qids.tolist(), asked.tolist(), best, strict=True):
                rows += [(q, int(xids[i]), int(s), min(k, m * int(held[i]))) for i, s in zip(at, scores, strict=True)]
        yield pd.DataFrame(rows, columns=["query_id", "vec_id", "score", "times"])


def needed_pairs(rows: DataFrame, dim: int, count: int, k: int, every: int, pivots: int | None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Blocks of data, blocks of queries, and (block, to): the cells that each query block still has to be solved with."""
    p = choose_pivots(rows, pivots or max(PIVOTS, min(MAX_PIVOTS, int(count**0.5 / 16))))
    fields = "cell int, kind int, ids binary, times binary, matrix binary, n int, near double, far double"
    once = rows.groupBy("vec_id", "v").agg(F.count("*").alias("m"))
    packed = K.cut(once.mapInPandas(lambda f: pack_cells(f, p, every), fields).withColumn("block", F.xxhash64("cell", "kind", "ids", "matrix")))
    data, queries = packed.filter("kind = 0"), packed.filter("kind = 1")
    summary = np.full(len(p), -1.0)
    for cell, far in data.groupBy("cell").agg(F.max("far")).collect():
        summary[cell] = far
    near = data.groupBy("cell").agg(F.min_by(F.struct("ids", "matrix", "n"), F.col("near") - F.col("n") * 1e-9).alias("x"))
    own = queries.join(near, "cell", "left").select("block", "cell", "far", "ids", "matrix", "n", F.col("x.ids").alias("x_ids"), F.col("x.matrix").alias("x_matrix"), F.col("x.n").alias("x_n"))
    bounds = own.mapInPandas(lambda f: first_bounds(f, k, dim), "block long, cell int, far double, bound double")
    return data, queries, bounds.mapInPandas(lambda f: reachable(f, p, summary), "block long, to int")


def top_k_of_length(rows: DataFrame, dim: int, count: int, k: int, every: int, pivots: int | None) -> DataFrame:
    data, queries, needs = needed_pairs(rows, dim, count, k, every, pivots)
    x = data.select(F.col("cell").alias("to"), F.col("ids").alias("x_ids"), F.col("times").alias("x_times"), F.col("matrix").alias("x_matrix"), F.col("n").alias("x_n"))
    pairs = queries.select("block", "ids", "times", "matrix", "n").join(needs, "block").join(x, "to")
    best = pairs.mapInPandas(lambda f: local_best(f, k, dim), "query_id long, vec_id long, score long, times long").withColumn("times", F.explode(F.sequence(F.lit(1).cast("long"), "times")))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def voronoi_top_k(vectors: DataFrame, k: int = K_BEST, every: int = EVERY, pivots: int | None = None) -> DataFrame:
    """query_id, rank, vec_id, score of each query's k best."""
    K.shared_folder(vectors.sparkSession)
    rows, out = integers(vectors), None
    for dim, count in lengths_of(rows):
        one = top_k_of_length(rows.filter(F.size("v") == dim), dim, count, k, every, pivots)
        out = one if out is None else out.unionByName(one)
    return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score long") if out is None else out


def op5_voronoi_knn(spark, sf_dir: str) -> DataFrame:
    return voronoi_top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


ORACLES = {
    "op5_voronoi_knn": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, x.vec_id, CAST(list_dot_product(q.v, x.v) AS BIGINT) AS score FROM v q JOIN v x ON q.vec_id % 50 = 0 AND q.vec_id <> x.vec_id),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5"""
}
