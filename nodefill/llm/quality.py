"""Quality scores from positive and unlabelled documents: non-negative unbiased risk.

Trusted positives are labelled documents of the training fold with quality 1; unlabelled are documents of that fold
whatever their label. The class prior is the share of quality 1 among the fold's labelled documents. Training minimises
prior * R+(positives) + max(0, R-(unlabelled) - prior * R-(positives)), after WARM steps of the logistic loss with the
bounded sigmoid loss, which bears a prior that is a little too high; when the second term falls under zero, its gradient
is followed backwards, so the estimate of the negatives' risk stays non-negative.

The model is linear over features of the whole text: frequencies of byte-class pairs, word statistics, and repetition.
It is fitted on at most POSITIVES + UNLABELLED documents, chosen by hash of doc_id, one text each (documented bound); every document is
scored where it is read, without an exchange. labels, lang, source and doc_id are no inputs of a score.

Null or empty text: features of an empty text. Without any positive label the score is the prior, or 0.5 without labels.
A doc_id with labels 0 and 1 is no positive. Null doc_id: held out. Rows are scored one by one. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K

K.ship(__name__)

POSITIVES, UNLABELLED, FOLDS, THRESHOLD, STEPS, WARM, RATE, DECAY = 8000, 16000, 5, 0.3, 600, 100, 0.05, 1e-4
CLASSES = 12


def byte_classes() -> np.ndarray:
    """0 control, 1 lower, 2 upper, 3 digit, 4 space, 5 line end, 6 stop or comma, 7 other ends, 8 quotes and brackets, 9 signs, 10 hyphens, 11 beyond ASCII."""
    table = np.zeros(256, np.int64)
    for k, chars in ((1, b"abcdefghijklmnopqrstuvwxyz"), (2, b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"), (3, b"0123456789"), (4, b" \t"), (5, b"\n\r"), (6, b".,"), (7, b"!?;:"), (8, b"\"'()[]{}`"), (9, b"#$%&*+/<=>@\\^|~"), (10, b"-_")):
        table[list(chars)] = k
    table[128:] = 11
    return table


def features(texts: list[bytes]) -> np.ndarray:
    """One row of features for each text."""
    table, out = byte_classes(), []
    for a, b in K.chunks(texts, [len(t) + 1 for t in texts]):
        joined = b"\n".join([*texts[a:b], b""])
        n = b - a
        size = np.array([len(t) for t in texts[a:b]])
        offset = np.r_[0, np.cumsum(size + 1)]
        kind = table[np.frombuffer(joined, np.uint8)]
        doc = np.repeat(np.arange(n), size + 1)
        pair = np.bincount(doc[:-1] * CLASSES**2 + kind[:-1] * CLASSES + kind[1:], minlength=n * CLASSES**2).reshape(n, -1)
        h, start, end = K.words(joined)
        bounds = np.searchsorted(start, offset)
        lines = np.flatnonzero(np.frombuffer(joined, np.uint8) == 10)
        line_bounds = np.searchsorted(lines, offset)
        tri = K.grams(h, 3)
        hp = K.prefix(K.BYTES[np.frombuffer(joined, np.uint8)], K.MULT_B)
        inverse = K.powers(K.MULT_B, len(joined))[1]
        begin = np.r_[0, lines[:-1] + 1]
        line = K.mix((hp[lines] - hp[begin]) * inverse[begin])
        wide = end - start
        rows = []
        for i in range(n):
            p, q = bounds[i], bounds[i + 1]
            u, v = line_bounds[i], line_bounds[i + 1]
            m, own = q - p, np.maximum(1, q - p)
            trigrams = tri[p : max(p, q - 2)]
            full = line[u:v][(lines[u:v] - begin[u:v]) > 0]
            rows.append((np.log1p(m) / 5, wide[p:q].sum() / own / 8, len(np.unique(h[p:q])) / own, len(np.unique(trigrams)) / max(1, len(trigrams)), len(np.unique(full)) / max(1, len(full)), np.log1p(len(full)) / 3, wide[p:q].max(initial=0) > 40, m == 0))
        out.append(np.hstack([np.sqrt(pair / np.maximum(1, size)[:, None]), np.array(rows, float).reshape(n, -1)]))
    return np.concatenate(out).astype(np.float32) if out else np.zeros((0, CLASSES**2 + 8), np.float32)


def fit_non_negative(p: np.ndarray, u: np.ndarray, prior: float, steps: int = STEPS) -> tuple[np.ndarray, float]:
    """Weights and bias over raw features, by Adam on the non-negative risk."""
    mean, scale = u.mean(0), u.std(0) + 0.02
    x, z = (p - mean) / scale, (u - mean) / scale
    theta = np.r_[np.zeros(x.shape[1]), np.log(prior / (1 - prior))]
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, steps + 1):
        gp, gu = (1 / (1 + np.exp(-np.clip(a @ theta[:-1] + theta[-1], -30, 30))) for a in (x, z))
        of = lambda a, w: np.r_[a.T @ w, w.sum()] / len(a)
        if step <= WARM:
            negative = -np.log(np.maximum(1e-12, 1 - gu)).mean() + prior * np.log(np.maximum(1e-12, 1 - gp)).mean()
            gain, rise = of(x, gp - 1), of(z, gu) - prior * of(x, gp)
        else:
            negative = gu.mean() - prior * gp.mean()
            gain, rise = -of(x, gp * (1 - gp)), of(z, gu * (1 - gu)) - prior * of(x, gp * (1 - gp))
        grad = prior * gain + rise if negative >= 0 else -rise
        grad[:-1] += DECAY * theta[:-1]
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        theta -= RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    w = theta[:-1] / scale
    return w, float(theta[-1] - mean @ w)


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % FOLDS == 0


def blobs(frames):
    for frame in frames:
        rows = features([t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in frame["text"]])
        yield pd.DataFrame({"kind": frame["kind"], "x": [r.tobytes() for r in rows]})


def train(docs: DataFrame, labels: DataFrame) -> tuple[np.ndarray, float] | float:
    """Weights and bias, or the constant score if there is nothing to learn from."""
    fold = labels.filter(~held_out(F.col("doc_id")) & F.col("quality").isin(0, 1)).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("q"))
    n, good = fold.agg(F.count("*"), F.sum("q")).first()
    if not n or not good:
        return 0.5 if not n else 0.0
    prior = min(0.99, max(0.01, good / n))
    by = F.xxhash64("doc_id", F.lit(3))
    positives = fold.filter("q = 1").select("doc_id").orderBy(by, "doc_id").limit(POSITIVES).withColumn("kind", F.lit(1))
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id")).filter(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).distinct()
    unlabelled = ids.orderBy(by, "doc_id").limit(UNLABELLED).withColumn("kind", F.lit(0))
    chosen = F.broadcast(positives.unionByName(unlabelled))  # at most POSITIVES + UNLABELLED rows of two numbers
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(chosen, "doc_id")
    source = source.groupBy("kind", "doc_id").agg(F.min("text").alias("text"))  # a repeated doc_id counts once, by its least text, so the bound holds
    rows = source.select("kind", "text").mapInPandas(blobs, "kind int, x binary").collect()
    x = {k: np.array([np.frombuffer(r["x"], np.float32) for r in rows if r["kind"] == k], float) for k in (0, 1)}
    return fit_non_negative(x[1], x[0], prior) if len(x[0]) and len(x[1]) else prior


def scores(texts, model) -> np.ndarray:
    if isinstance(model, float):
        return np.full(len(texts), model)
    rows = features([t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in texts])
    return 1 / (1 + np.exp(-np.clip(rows @ model[0] + model[1], -30, 30)))


def score_quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted (1 from THRESHOLD on) of every document."""
    model = train(docs, labels)
    source = K.id_text(docs, held_out(F.col("doc_id").cast("long")).alias("held_out"))

    def run(frames):
        for frame in frames:
            score = scores(frame["text"], model)
            yield frame[["held_out"]].assign(doc_id=pd.array(K.row_ids(frame["doc_id"]), "Int64"), score=score, predicted=(score >= THRESHOLD).astype("int32"))

    return source.mapInPandas(run, "doc_id long, held_out boolean, score double, predicted int").select("doc_id", "held_out", "score", "predicted")


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents with predicted 1, all columns as they are, row by row: nulls in any column, repeated rows and empty texts are judged like others.

    Rows are filtered as Arrow batches, so no column passes through another type.
    """
    model = train(docs, labels)

    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array(scores(batch.column("text").to_pylist(), model) >= THRESHOLD))

    return docs.mapInArrow(run, docs.schema)


def op3_positive_unlabelled_quality(spark, sf_dir: str) -> DataFrame:
    return score_quality(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
