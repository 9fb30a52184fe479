"""Near-duplicate classes: improved consistent weighted sampling over TF-IDF shingles, banded, verified.

Shingles are five words, A-Z lower-cased; shorter texts are one shingle. A shingle's weight is its count in the
document times 1 + DAMP * idf. idf is -log2 of the share of documents that hold it, over 20, cut to 0..1; document
counts come from a count-min sketch over all documents (2 x 2^20 cells whatever the corpus), so frequent shingles are
known as such. A shingle of every document weighs its count, the rarest 1 + DAMP times that. DAMP is small so that one edit
among thousands of copies, whose common shingles are frequent and its own are not, doesn't outweigh what they share.

Equal texts are one class before anything else. Each class gets BANDS x ROWS samples; two classes that share a band are
candidates. In each band bucket, members are compared to one of them, the bucket's hub, and the rest of the links follow
from components: after each round, buckets whose members lie in several components get another hub. A bucket of n members
makes n - 1 pairs a round. These rounds only save work: what is still in several components after ROUNDS of them
is joined exactly (`remaining_pairs`), so each two candidates are either of one class or
known to be below SIMILARITY. Links are kept only if their weighted Jaccard similarity, computed from all their
shingles, is SIMILARITY or more.

A class is known by its least doc_id and its text's digest, so two texts under one doc_id are two classes, each with its
own links, and results don't depend on the order of rows. Buckets of more than HOT classes are met in SALTS shares: their
members are dealt over them, and the bucket's one hub goes to each.

Null or empty text: no shingles; such texts are copies of each other and of nothing else. Null doc_id: returned with a
null class. Rows with the same doc_id and text are copies of one class. Other columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .kernels import U

K.ship(__name__)

SHINGLE, SIMILARITY, BANDS, ROWS, DAMP, ROUNDS = 5, 0.8, 12, 3, 0.1, 3
HOT, SALTS = 256, 64
CELL_BITS, SKETCH_BLOCK, POOL_BITS = 20, 14, 16
CELL_MULT = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)


def shingles(texts: list[bytes], k: int):
    """For each text the hashes of its distinct shingles, ascending, and their counts."""
    for a, b in K.chunks(texts, [len(t) + 1 for t in texts]):
        h, _, _, bounds, _ = K.word_chunk(texts[a:b], lower=True)
        g = K.grams(h, k)
        for i, j in zip(bounds[:-1], bounds[1:], strict=True):
            if j - i >= k:
                yield np.unique(g[i : j - k + 1], return_counts=True)
            elif j > i:
                yield K.grams(h[i:j], int(j - i)), np.ones(1, np.int64)
            else:
                yield h[:0], np.zeros(0, np.int64)


def cells(h: np.ndarray, depth: int) -> np.ndarray:
    return (h * U(CELL_MULT[depth]) >> U(64 - CELL_BITS)).astype(np.int64)


def sketch_part(frames, k: int):
    """Document counts of one partition's shingles, by blocks of cells."""
    count, n = np.zeros((2, 1 << CELL_BITS), np.int64), 0
    for frame in frames:
        texts = [t.encode("utf-8", "surrogatepass") for t in frame["text"] if isinstance(t, str)]
        n += len(frame)
        for h, _ in shingles(texts, k):
            for depth in (0, 1):
                np.add.at(count[depth], cells(h, depth), 1)
    size = 1 << SKETCH_BLOCK
    rows = [(d, b, K.pack_ints(count[d, b * size : (b + 1) * size])) for d in (0, 1) for b in range((1 << CELL_BITS) // size)] if n else []
    yield pd.DataFrame([*rows, (-1, 0, K.pack_ints(np.array([n])))], columns=["depth", "block", "cells"])


def add_blocks(key, frame):
    total = sum(K.unpack_ints(b) for b in frame["cells"])
    return pd.DataFrame([(int(key[0]), int(key[1]), K.pack_ints(total))], columns=["depth", "block", "cells"])


def idf_table(docs: DataFrame, k: int) -> np.ndarray:
    """idf in 0..255 for each [depth, cell] of the merged sketch: 2 MB whatever the corpus."""
    schema = "depth int, block int, cells binary"
    parts = docs.select(F.col("text").cast("string").alias("text")).mapInPandas(lambda frames: sketch_part(frames, k), schema)
    count, n = np.zeros((2, 1 << CELL_BITS), np.int64), 0
    for depth, block, blob in parts.groupBy("depth", "block").applyInPandas(add_blocks, schema).collect():
        if depth < 0:
            n = int(K.unpack_ints(blob)[0])
        else:
            count[depth, block << SKETCH_BLOCK :][: 1 << SKETCH_BLOCK] = K.unpack_ints(blob)
    share = np.log2(np.maximum(1, n) / np.maximum(1, count)) / 20
    return np.rint(np.clip(share, 0, 1) * 255).astype(np.uint8)


def weights(h: np.ndarray, tf: np.ndarray, idf: np.ndarray) -> np.ndarray:
    """The sketch overestimates counts, so the larger of the two depths' idf is the nearer."""
    return tf * (1 + DAMP / 255 * np.maximum(idf[0][cells(h, 0)], idf[1][cells(h, 1)]))


def pools() -> np.ndarray:
    """ln c, r and beta for each pool entry; a shingle and a sample number pick theirs by hash."""
    rng = np.random.default_rng(11)
    n = 1 << POOL_BITS
    return np.stack([np.log(rng.gamma(2, 1, n)), rng.gamma(2, 1, n), rng.random(n)]).astype(np.float32)


def samples(h: np.ndarray, w: np.ndarray, n: int, first: np.ndarray | None = None) -> np.ndarray:
    """n consistent weighted samples of each text: the hash of (shingle, level) of least a, ln a = ln c - r (t - beta) - r.

    h and w hold the texts one after the other, from the places `first` on; no text is empty.
    """
    log_c, r, beta = K.cached("icws", pools)
    first = np.zeros(1, np.int64) if first is None else first
    size = np.diff(np.r_[first, len(h)])
    log_w = np.log(w).astype(np.float32)
    out = np.empty((len(first), n), np.uint64)
    for i in range(n):
        # c from its own hash bits beside the pool's, so that long texts don't run out of values
        x = h * U((0x9E3779B97F4A7C15 * (2 * i + 1)) & (2**64 - 1))
        at = (x >> U(64 - POOL_BITS)).astype(np.int64)
        own = r[at]
        t = np.floor(log_w / own + beta[at])
        a = log_c[((x >> U(20)) & U((1 << POOL_BITS) - 1)).astype(np.int64)] - own * (t - beta[at] + 1)
        least = np.flatnonzero(a == np.repeat(np.minimum.reduceat(a, first), size))
        k = least[np.searchsorted(least, first)]
        out[:, i] = h[k] ^ (t[k].astype(np.int64).astype(np.uint64) * U(0xD6E8FEB86659FD93))
    return out


def signatures(frames, k: int, idf, bands: int, rows: int):
    """doc_id, the text's digest, and a hash for each band; one row for equal texts of a batch, with their doc_ids."""
    for frame in frames:
        groups: dict[bytes, list] = {}
        ids, _, texts = K.in_order(frame)
        for i, t in zip(ids, texts, strict=True):
            if i is not None:
                groups.setdefault(t, []).append(i)
        texts, members = list(groups), list(groups.values())
        band: list = [[] for _ in texts]
        found = list(shingles(texts, k))
        full = [i for i, (h, _) in enumerate(found) if len(h)]
        for x, y in K.chunks(full, [len(found[i][0]) for i in full], 1 << 17):
            own = full[x:y]
            h, tf = (np.concatenate([found[i][j] for i in own]) for j in (0, 1))
            first = np.r_[0, np.cumsum([len(found[i][0]) for i in own])[:-1]].astype(np.int64)
            s = samples(h, weights(h, tf, idf), bands * rows, first).reshape(len(own), bands, rows)
            mixed = s[:, :, 0].copy()
            for j in range(1, rows):
                mixed = K.mix(mixed) + s[:, :, j]
            mixed = K.mix(mixed + np.arange(bands, dtype=np.uint64)).view(np.int64)
            for i, row in zip(own, mixed.tolist(), strict=True):
                band[i] = row
        yield pd.DataFrame({"digest": [hashlib.md5(t).digest() for t in texts], "members": members, "bands": band})


def vectors(frames, k: int):
    """class_id (or doc_id, if the frames have no classes) and the text's shingles with their counts."""
    for frame in frames:
        names = frame["class_id" if "class_id" in frame else "doc_id"]
        texts = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in frame["text"]]
        yield pd.DataFrame([(int(i), h.tobytes() + tf.astype("<u4").tobytes()) for i, (h, tf) in zip(names, shingles(texts, k), strict=True)], columns=["class_id", "vector"])


def jaccard(a: bytes, b: bytes, idf) -> float:
    na, nb = len(a) // 12, len(b) // 12
    h = np.concatenate([np.frombuffer(a, np.uint64, na), np.frombuffer(b, np.uint64, nb)])
    tf = np.concatenate([np.frombuffer(a, "<u4", na, 8 * na), np.frombuffer(b, "<u4", nb, 8 * nb)]).astype(float)
    w = weights(h, tf, idf)
    order = np.argsort(h, kind="stable")
    h, w = h[order], w[order]
    same = np.flatnonzero(h[1:] == h[:-1])
    least = np.minimum(w[same], w[same + 1]).sum()
    return float(least / (w.sum() - least)) if len(w) else 0.0


def verified(frames, idf, similarity: float):
    for frame in frames:
        pairs = [jaccard(a, b, idf) for a, b in zip(frame["va"], frame["vb"], strict=True)]
        frame = frame.assign(similarity=pairs)
        yield frame.loc[frame["similarity"] >= similarity - 1e-9, ["a", "b", "similarity"]]


def prefixes(frames, idf, similarity: float):
    """Each class's weight and its rarest shingles, as many as a partner of `similarity` can't do without.

    With all shingles in one order and w the sum of minima that the similarity asks for, two sets share one of those before
    less than w of either is left. A partner that weighs no less asks for 2 s / (1 + s) of the weight, any partner for s:
    the first `short` shingles do for the former, all of them for the latter. `rest` is the weight from each of them on: from
    their first common shingle on, both need the weight that the similarity asks them to share.
    """
    for frame in frames:
        rows = []
        for blob in frame["vector"]:
            n = len(blob) // 12
            h, tf = np.frombuffer(blob, np.uint64, n), np.frombuffer(blob, "<u4", n, 8 * n).astype(float)
            w = weights(h, tf, idf)
            order = np.lexsort((h, -np.maximum(idf[0][cells(h, 0)], idf[1][cells(h, 1)]).astype(int)))
            left = w.sum() - np.cumsum(w[order])
            short, long = (int((left >= share * w.sum() * (1 - 1e-6)).sum()) + 1 for share in (2 * similarity / (1 + similarity), similarity))
            rows.append((float(w.sum()), short, h[order[:long]].view(np.int64), (left + w[order])[:long]))
        size, short, keys, rest = zip(*rows, strict=True) if rows else ((), (), (), ())
        yield frame[["class_id", "component", "hs"]].assign(size=size, short=short, keys=keys, rest=rest)


def salt_of(name: str, hot: str):
    """The share of a hot group that a row goes to."""
    return F.when(F.col(hot), F.pmod(F.xxhash64(name, F.lit(5)), F.lit(SALTS)).cast("int")).otherwise(0)


def salts(hot: str):
    """All shares, for the row that a group's members meet."""
    return F.explode(F.when(F.col(hot), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))).alias("salt")


def remaining_pairs(own: DataFrame, vector: DataFrame, idf, similarity: float) -> DataFrame:
    """(a, b): every pair of different components that shares a bucket, but those that can't reach the similarity."""
    open_ = own.groupBy("band", "h").agg(F.min("component").alias("x"), F.max("component").alias("y"), F.max("hot").alias("is_hot")).filter("x <> y").select("band", "h", salts("is_hot"))
    left = own.withColumn("salt", salt_of("class_id", "hot")).join(open_, ["band", "h", "salt"]).groupBy("class_id", "component").agg(F.collect_set("h").alias("hs"))
    schema = "class_id long, component long, hs array<long>, size double, short int, keys array<long>, rest array<double>"
    keyed = K.cut(left.join(vector, "class_id").mapInPandas(lambda f: prefixes(f, idf.value, similarity), schema))
    x = keyed.select(F.col("class_id").alias("a"), F.col("component").alias("ca"), F.col("hs").alias("ha"), F.col("size").alias("na"), F.explode(F.slice(F.arrays_zip("keys", "rest"), F.lit(1), F.col("short"))).alias("ka")).withColumn("key", F.col("ka.keys"))
    y = keyed.select(F.col("class_id").alias("b"), F.col("component").alias("cb"), F.col("hs").alias("hb"), F.col("size").alias("nb"), F.explode(F.arrays_zip("keys", "rest")).alias("kb")).withColumn("key", F.col("kb.keys"))
    fits = (F.col("ca") != F.col("cb")) & (F.struct("na", "a") < F.struct("nb", "b")) & (F.col("na") >= F.col("nb") * (similarity - 1e-6)) & F.arrays_overlap("ha", "hb")
    common = F.least("ka.rest", "kb.rest") >= (F.col("na") + F.col("nb")) * (similarity / (1 + similarity) - 1e-6)
    return x.join(y, "key").filter(fits & common).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(class_id, component): the least class of each component. Labels spread over links and then jump, so chains halve."""
    both = K.cut(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    # classes with more than a thousandth of all links: at most a thousand
    hot = K.cut(both.groupBy("b").agg(F.count("*").alias("n")).filter(F.col("n") > max(HOT, both.count() // 1000)).select("b", F.lit(True).alias("hot")))
    both = K.cut(both.join(F.broadcast(hot), "b", "left").withColumn("hot", F.coalesce("hot", F.lit(False))).select("a", "b", salt_of("a", "hot").alias("salt")))
    labels = K.cut(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("v"), F.least("a", "m").alias("l")))
    while True:
        given = labels.withColumnRenamed("v", "b").join(F.broadcast(hot), "b", "left").select("b", "l", salts("hot"))
        near = both.join(given, ["b", "salt"]).groupBy("a").agg(F.min("l").alias("m"))
        step = labels.join(near, F.col("v") == F.col("a")).select("v", F.least("l", "m").alias("n"), "l")
        jump = step.select(F.col("v").alias("p"), F.col("n").alias("q"))
        new = K.cut(step.join(jump, F.col("n") == F.col("p"), "left").select("v", F.least("n", F.coalesce("q", "n")).alias("n"), "l"))
        if not new.filter("n <> l").limit(1).count():
            return new.select(F.col("v").alias("class_id"), F.col("n").alias("component"))
        labels = new.select("v", F.col("n").alias("l"))


def keyed_classes(local: DataFrame) -> tuple[DataFrame, bool]:
    """A row for each text: digest, least (its least doc_id), bands, class_id; and whether any doc_id is the least one of several texts.

    class_id is that doc_id; of several texts under it, all but that with the least digest get a hash of both instead.
    """
    classes = K.cut(local.groupBy("digest").agg(F.min("least").alias("least"), F.first("bands").alias("bands")))
    shared = K.cut(classes.groupBy("least").agg(F.min("digest").alias("own"), F.count("*").alias("n")).filter("n > 1").select("least", "own"))
    if not shared.limit(1).count():
        return classes.withColumn("class_id", F.col("least")), False
    key = F.when(F.col("own").isNull() | (F.col("own") == F.col("digest")), F.col("least")).otherwise(F.xxhash64("least", "digest"))
    return classes.join(shared, "least", "left").withColumn("class_id", key).drop("own"), True


def named_classes(known: DataFrame, several: bool) -> DataFrame:
    """known (digest, least, class_id, component) with `name`, the least doc_id of the component, and `first`, whether it is the class that gives it."""
    if not several:
        return known.select("*", F.col("component").alias("name"), (F.col("component") == F.col("class_id")).alias("first"))
    least = known.groupBy("component").agg(F.min(F.struct("least", "digest")).alias("at"))
    return known.join(least, "component").select(known["*"], F.col("at.least").alias("name"), ((F.col("at.least") == F.col("least")) & (F.col("at.digest") == F.col("digest"))).alias("first"))


def hub_pairs(own: DataFrame, turn: int) -> DataFrame:
    """(a, b, hub, salt): each open bucket's members against its hub; one hub for all bands at first, which makes equal pairs, then a hub of its own for each."""
    rank = F.col("class_id") if turn == 0 else F.xxhash64("class_id", "band", F.lit(turn))
    hubs = own.groupBy("band", "h").agg(F.min_by(F.struct("class_id", "component"), rank).alias("hub"), F.min("component").alias("x"), F.max("component").alias("y"), F.max("hot").alias("is_hot")).filter("x <> y")
    hubs = hubs.select("band", "h", "hub", salts("is_hot"))
    pairs = own.withColumn("salt", salt_of("class_id", "hot")).join(hubs, ["band", "h", "salt"]).filter("component <> hub.component")
    pairs = pairs.select(F.least("class_id", "hub.class_id").alias("a"), F.greatest("class_id", "hub.class_id").alias("b"), F.struct(F.col("hub.class_id").alias("hub"), "salt").alias("to"))
    return pairs.groupBy("a", "b").agg(F.min("to").alias("to")).select("a", "b", "to.hub", "to.salt")


def verified_pairs(pairs: DataFrame, vector: DataFrame, idf, similarity: float) -> DataFrame:
    """The pairs (a, b, hub, salt) that are similar. A hub's vector is copied to the salts that ask for it, so no key gathers its pairs."""
    wanted = pairs.select("hub", "salt").distinct()
    hub = wanted.join(vector.select(F.col("class_id").alias("hub"), F.col("vector").alias("vb")), "hub")
    other = pairs.withColumn("class_id", F.when(F.col("hub") == F.col("a"), F.col("b")).otherwise(F.col("a")))
    both = other.join(vector.select("class_id", F.col("vector").alias("va")), "class_id").join(hub, ["hub", "salt"]).select("a", "b", "va", "vb")
    return both.mapInPandas(lambda f: verified(f, idf.value, similarity), "a long, b long, similarity double")


def near_duplicates(docs: DataFrame, k: int = SHINGLE, similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS, rounds: int = ROUNDS, with_digest: bool = False) -> DataFrame:
    """A row for each row: doc_id, class_id (least doc_id of its near-duplicate class), n_links (verified links of its text), copy_of (least doc_id with the same text).

    with_digest: also `digest`, the text's MD5, and `first`, whether it is the text that the class keeps.
    """
    spark = docs.sparkSession
    K.shared_folder(spark)
    source = K.id_text(docs)
    idf = spark.sparkContext.broadcast(idf_table(source, k))
    found = source.mapInPandas(lambda f: signatures(f, k, idf.value, bands, rows), "digest binary, members array<long>, bands array<long>")
    local = K.cut(found.select("digest", F.array_min("members").alias("least"), "members", "bands"))
    # equal texts of different batches: their bands are equal too; the members stay spread over the batches' rows
    classes, several = keyed_classes(local)
    keyed = classes.select("class_id", F.posexplode("bands").alias("band", "h"))
    shared = keyed.groupBy("band", "h").agg(F.count("*").alias("n")).filter("n > 1")
    total = classes.count()
    # buckets of more than a thousandth of all classes: at most a thousand a band, which a broadcast bears at any size
    hot = K.cut(shared.filter(F.col("n") > max(HOT, total // 1000)).select("band", "h"))
    marked = keyed.join(F.broadcast(hot.withColumn("hot", F.lit(True))), ["band", "h"], "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
    small = marked.filter("NOT hot").join(shared.select("band", "h"), ["band", "h"])
    buckets = K.cut(small.unionByName(marked.filter("hot")))
    wanted = buckets.select("class_id").distinct()
    asked = classes.join(wanted, "class_id", "left_semi").select("class_id", F.col("least").alias("its_id"), F.col("digest").alias("its_digest"))
    digest = F.unhex(F.md5(F.coalesce(source["text"], F.lit("")).cast("binary")))
    texts = source.join(asked, (source["doc_id"].cast("long") == F.col("its_id")) & (digest == F.col("its_digest"))).select("class_id", "text")
    vector = K.cut(texts.mapInPandas(lambda f: vectors(f, k), "class_id long, vector binary").dropDuplicates(["class_id"]))
    links, label, tested = None, wanted.select("class_id", F.col("class_id").alias("component")), None
    for turn in range(rounds + 1):
        own = buckets.join(label, "class_id", "left").select("band", "h", "hot", "class_id", F.coalesce("component", "class_id").alias("component"))
        pairs = hub_pairs(own, turn) if turn < rounds else remaining_pairs(own, vector, idf, similarity).select("a", "b", F.col("b").alias("hub"), F.pmod(F.xxhash64("a"), F.lit(SALTS)).cast("int").alias("salt"))
        if tested is not None:
            pairs = pairs.join(tested, ["a", "b"], "left_anti")
        pairs = K.cut(pairs)
        new = K.cut(verified_pairs(pairs, vector, idf, similarity))
        tested = pairs.select("a", "b") if tested is None else tested.union(pairs.select("a", "b"))
        if new.limit(1).count():
            links = new if links is None else links.unionByName(new)
            label = components(links)
    if links is None:
        links = spark.createDataFrame([], "a long, b long, similarity double")
    degree = links.select(F.explode(F.array("a", "b")).alias("class_id")).groupBy("class_id").agg(F.count("*").alias("n_links"))
    known = classes.select("digest", "least", "class_id").join(label, "class_id", "left").join(degree, "class_id", "left").withColumn("component", F.coalesce("component", "class_id"))
    # the members are listed last: till then a text has one row a batch, however many copies there are
    known = local.select("digest", "members").join(named_classes(known, several), "digest").withColumn("doc_id", F.explode("members"))
    columns = [F.col("doc_id"), F.col("name").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.col("least").alias("copy_of"), F.col("digest"), F.col("first")]
    kinds = (("doc_id", "long"), ("class_id", "long"), ("n_links", "long"), ("copy_of", "long"), ("digest", "binary"), ("first", "boolean"))
    nameless = docs.filter(F.col("doc_id").cast("long").isNull()).select(*[F.lit(None).cast(t).alias(c) for c, t in kinds])
    out = known.select(*columns).unionByName(nameless)
    return out if with_digest else out.drop("digest", "first")


def op7_weighted_minhash(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
