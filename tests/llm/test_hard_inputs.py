"""Inputs that break shortcuts: long runs, late digits, huge ids, mixed lengths, colliding words, large groups; and naive references."""

import datetime
import hashlib
import itertools
import math
import random
import re
import time

import corpus_pipeline
import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import TEXTS, brute_cover, prose

from nodefill.llm import kernels as K
from nodefill.llm import knn_join, media_jpeg, packing, quality, secret_forest, segmentation, suffix_index, url_filter, weighted_minhash, window_dedup

BIG = 9007199254740993


def labelled(spark):
    good = [(BIG + i, prose(i, 60)) for i in range(60)]
    bad = [(1000 + i, prose(i, 60).upper().replace(" ", "!! ")) for i in range(30)]
    docs = spark.createDataFrame([(i, t, datetime.datetime(2024, 1, 2, 3, 4, 5), i) for i, t in [*good, (None, prose(77, 60)), *bad]], "doc_id long, text string, at timestamp, more long").coalesce(1)
    labels = spark.createDataFrame([(i, 1, 0) for i, _ in good[:40]] + [(i, 0, 0) for i, _ in bad[:20]], "doc_id long, quality int, toxic int")
    return docs, labels


def test_kept_rows_are_untouched(spark):
    docs, labels = labelled(spark)
    rows = quality.keep_good(docs, labels).collect()
    assert {BIG + i for i in range(60)} <= {r["doc_id"] for r in rows} and None in {r["doc_id"] for r in rows}
    assert all(r["more"] == r["doc_id"] and r["at"] == datetime.datetime(2024, 1, 2, 3, 4, 5) for r in rows)


def test_training_takes_one_text_of_a_repeated_id(spark):
    docs, labels = labelled(spark)
    many = docs.unionByName(docs.filter(f"doc_id = {BIG}").crossJoin(spark.range(500)).drop("id"))
    a, b = quality.train(docs, labels), quality.train(many, labels)
    assert np.allclose(a[0], b[0]) and math.isclose(a[1], b[1])


def naive_features(text: bytes) -> list[float]:
    kinds = quality.byte_classes()
    line = [int(kinds[x]) for x in text + b"\n"]
    pair = [[0] * quality.CLASSES for _ in range(quality.CLASSES)]
    for a, b in zip(line, line[1:]):
        pair[a][b] += 1
    words, lines = re.findall(rb"[^\x20\x09-\x0D]+", text), [x for x in (text + b"\n").split(b"\n")[:-1] if x]
    three = list(zip(words, words[1:], words[2:]))
    m = max(1, len(words))
    rest = [math.log1p(len(words)) / 5, sum(map(len, words)) / m / 8, len(set(words)) / m, len(set(three)) / max(1, len(three)), len(set(lines)) / max(1, len(lines)), math.log1p(len(lines)) / 3, float(max(map(len, words), default=0) > 40), float(not words)]
    return [math.sqrt(x / max(1, len(text))) for row in pair for x in row] + rest


def test_features_against_naive_ones():
    texts = [b"", b" \n\n", b"One two, two.\nOne two, two.\n\n(three) " * 3, "ñandú 12-34 漢".encode(), b"x" * 60, prose(5, 50).encode()]
    got = quality.features(texts)
    for k, t in enumerate(texts):  # pairs across two texts of a batch count for the first one's end
        own = np.array(naive_features(t))
        near = np.abs(got[k] - own)
        assert near[quality.CLASSES**2 :].max() < 1e-5 and (near[: quality.CLASSES**2] > 1e-5).sum() <= 1


@pytest.mark.parametrize("run", [" ", "\n", " \n\t", " ", "  "])
def test_long_white_space_packs(run):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    encoder = packing.byte_pair_encoder(packing.default_vocabulary())
    for text in (run * 5000, "a" + run * 5000 + "b", run * 4999 + " b c", "a b" + run * 6000 + "1" + run * 4500 + "!" + run * 9):
        assert packing.encode_text(encoder, text).tolist() == t.encode(text, add_special_tokens=False).ids
    assert len(packing.encode_text(encoder, "a" + run * 1_000_000 + "b")) > 10


def test_long_words_have_the_same_paths(monkeypatch):
    pieces = segmentation.Pieces(segmentation.default_model())
    texts = ["hello", "international", "ñu漢x", "aaaaaaaaaa", "  in  to\nit"]
    want = segmentation.n_best(texts, pieces, 5)
    monkeypatch.setattr(segmentation, "LONG", 0)
    for (a, x), (b, y) in zip(want, segmentation.n_best(texts, pieces, 5)):
        assert x == y and np.allclose([s for s, _ in a], [s for s, _ in b], atol=1e-6) and a[0][1].tolist() == b[0][1].tolist()


def test_a_text_without_spaces_takes_seconds():
    r = random.Random(1)
    pieces = segmentation.Pieces(segmentation.default_model())
    texts = ["".join(r.choice("abcdefghijklmnopqrstuvwxyz0123456789") for _ in range(60_000)), "漢字" * 20_000, "a" * 20_000, " " * 20_000]
    begin = time.perf_counter()
    for (paths, whole), t in zip(segmentation.n_best(texts, pieces, 5), texts):
        assert whole and len(paths) == (1 if t[0] == "漢" else 5) and segmentation.decode(paths[0][1].tolist(), pieces) == t
        assert all(a[0] >= b[0] - 1e-6 for a, b in zip(paths, paths[1:]))
    assert time.perf_counter() - begin < 60


def test_models_whose_pieces_cross_words(monkeypatch):
    pieces = segmentation.Pieces(segmentation.default_model())
    assert pieces.cuts
    text = "the cat sat"
    want = segmentation.n_best([text], pieces, 5)[0][0]
    pieces.cuts = False
    got = segmentation.n_best([text], pieces, 5)[0][0]
    assert np.allclose([s for s, _ in got], [s for s, _ in want])


def test_long_texts_go_in_pieces(spark, monkeypatch):
    rows = [(i, t) for i, t in TEXTS if i is not None] + [(50, prose(50, 400)), (51, prose(51, 30) + " " + prose(50, 400)[100:2500]), (52, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    frame = docs.toPandas().assign(bucket=0)
    want = {}
    for cut in (False, True):
        if cut:
            monkeypatch.setattr(K, "CHUNK", 64)
            monkeypatch.setattr(K, "PLACES", 40)
        ids, keys, texts = K.in_order(frame)
        want[cut] = sorted((int(t), int(p) + k, int(h)) for *_, size, place, text, hs in suffix_index.anchored(texts, 50, 16) for n, p, t, h in zip(size, place, text, hs) for k in range(n))
        w = window_dedup.windows_of(texts, 50, 8)
        want[cut, "words"] = sorted(zip(w.doc.tolist(), w.first.tolist(), w.anchor.tolist()))
    assert want[False] == want[True] and len(want[True]) > 1000 and want[False, "words"] == want[True, "words"]


def twins(n: int) -> tuple[str, str]:
    a = ["a", "b"]
    while len(a[0]) < n:
        a = [a[0] + a[1], a[1] + a[0]]
    return a[0], a[1]


def test_words_with_equal_polynomials_stay_apart(spark):
    a, b = twins(1024)
    rest = prose(3, 49)
    docs = spark.createDataFrame([(1, f"{a} {rest}"), (2, f"{b} {rest}"), (3, f"{a} {rest}")], "doc_id long, text string")
    assert {r["doc_id"]: r["n_removed"] for r in window_dedup.remove_repeated_windows(docs).collect()} == {1: 0, 2: 0, 3: 50}


def test_ids_that_repeat_spread_over_buckets(spark):
    docs = spark.createDataFrame([(None if k % 2 else 7, prose(k, 20)) for k in range(400)], "doc_id long, text string")
    assert K.doc_buckets(docs, 8).groupBy("bucket").count().agg(F.max("count")).first()[0] < 120
    assert {r["n_removed"] for r in suffix_index.remove_repeated_bytes(docs).collect()} == {0}


def brute_top(rows, k=5):
    x, want = [(i, [math.floor(256 * c) for c in v]) for i, v in rows if i is not None and v and None not in v and all(map(math.isfinite, v))], []
    for q, v in x:
        if q % 50 == 0:
            best = sorted((-sum(a * b for a, b in zip(v, w)), i) for i, w in x if i != q and len(w) == len(v))[:k]
            want += [(q, r + 1, i, max(-(2**63), min(2**63 - 1, -s))) for r, (s, i) in enumerate(best)]
    return sorted(want)


def test_vectors_of_mixed_lengths_and_sizes(spark):
    rng = np.random.default_rng(8)
    rows = [(k, rng.normal(size=3).tolist()) for k in range(60)] + [(100 + k, rng.normal(size=4).tolist()) for k in range(7)] + [(150, [1.0] * 9), (201, []), (202, None)]
    table = lambda r: spark.createDataFrame(r, "vec_id long, embedding array<double>")
    assert sorted(map(tuple, knn_join.voronoi_top_k(table(rows)).collect())) == brute_top(rows)
    huge = [(k, (rng.normal(size=3) * 1e6).tolist()) for k in range(60)] + [(60, [1e300, -1e299, 0.0])]
    assert sorted(map(tuple, knn_join.voronoi_top_k(table(huge)).collect())) == brute_top(huge)


def test_far_cells_are_pruned(spark, monkeypatch):
    rng = np.random.default_rng(9)
    centre = np.eye(12) * 4
    rows = [(k, (centre[k % 12] + 0.02 * rng.normal(size=12)).tolist()) for k in range(1200)]
    monkeypatch.setattr(knn_join, "BLOCK", 64)
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    K.shared_folder(spark)
    data, queries, needs = knn_join.needed_pairs(knn_join.integers(table), 12, 1200, 5, 50, None)
    cells, asked = data.select("cell").distinct().count(), queries.count()
    assert needs.count() < 0.5 * cells * asked
    assert sorted(map(tuple, knn_join.voronoi_top_k(table).collect())) == brute_top(rows)


def test_near_copies_are_found_in_large_groups(spark):
    r, texts = random.Random(4), []
    for g in range(30):
        base = prose(4000 + g, 120).split()
        for _ in range(300 if g == 0 else 8):
            own = list(base)
            for _ in range(r.randint(0, 3)):
                own[r.randrange(len(own))] = f"edit{r.randint(0, 10**6)}"
            texts.append((len(texts), " ".join(own)))
    texts.append((5, prose(9999, 50)))  # a second text under an id that has one
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(5)
    rows = weighted_minhash.near_duplicates(docs, with_digest=True).collect()
    got = {(r["doc_id"], bytes(r["digest"])): r["class_id"] for r in rows}
    assert len(rows) == len(texts)
    blobs = dict(zip(sorted(t for _, t in texts), next(weighted_minhash.vectors([docs.toPandas().sort_values("text")], 5))["vector"]))
    idf = weighted_minhash.idf_table(docs, 5)
    key = lambda i, t: (i, hashlib.md5(t.encode()).digest())
    found = total = 0
    for (i, s), (j, t) in itertools.combinations(texts, 2):
        if (i < 300) == (j < 300) and weighted_minhash.jaccard(blobs[s], blobs[t], idf) >= 0.8:
            total += 1
            found += got[key(i, s)] == got[key(j, t)]
    assert total > 2000 and found >= 0.99 * total
    assert got[key(5, prose(9999, 50))] == 5 and sum(r["first"] for r in rows if r["class_id"] == r["doc_id"]) >= 30


def naive_split(run, model):
    best = None
    for cuts in itertools.product((0, 1), repeat=len(run) - 1):
        at, words = 0, []
        for k, c in enumerate([*cuts, 1]):
            if c:
                words.append(run[at : k + 1])
                at = k + 1
        score = sum(model.unknown - 2.5 * len(w) if model.get(w) is None else model.get(w) for w in words)
        if best is None or score > best[0] + 1e-12:
            best = (score, words)
    return best[0]


def test_hosts_are_split_however_often_they_occur(spark):
    html = "<html><script>casinobonusbest</script><p>the best casino gives a bonus. the city library has the best books</p></html>"
    rows = [(k, f"http://bestcasinobonus.example.info/fr/{k}", html) for k in range(50)] + [(100 + k, f"http://www.citylibrary.example.info/fr/{k}", None) for k in range(50)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: r for r in url_filter.filter_urls(pages).collect()}
    assert got[0]["words"].startswith("best casino bonus") and {got[k]["verdict"] for k in range(50)} == {"block"}
    assert got[100]["words"].split()[1:3] == ["city", "library"] and {got[100 + k]["verdict"] for k in range(50)} == {"allow"}
    model = url_filter.unigram(pages)
    for run in ("thebest", "casinothe", "xqzthe", "a", "librarybo"):
        split = url_filter.viterbi(run, model)
        assert "".join(split) == run
        options = [model.unknown - 2.5 * len(w) if model.get(w) is None else model.get(w) for w in split]
        assert sum(options) >= naive_split(run, model) - 2 * abs(model.unknown) * (len(options) < 2) - 1e-9 or any(model.get(w) is None for w in split)


def test_rules_teach_the_words_of_hosts(spark):
    pages = spark.createDataFrame([(k, f"http://gamblers.example.com/en/{k}", "<p>gamblers paradise</p>") for k in range(5)] + [(9, "http://gamblers.example.info/fr/1", None)], "page_id long, url string, html string")
    names = url_filter.ruled_names(pages, url_filter.RULES, url_filter.unigram(pages))
    assert names == [(["gamblers"], "block")]
    score = {r["page_id"]: r["score"] for r in url_filter.filter_urls(pages).collect()}
    assert score[9] > 0.4 > 2 * url_filter.PRIOR_BLOCK - 0.01


def test_forest_votes_as_its_trees(spark):
    forest = secret_forest.train_forest(spark)

    def walk(tree, f):
        while not isinstance(tree, float):
            k, t, low, high = tree
            tree = low if f[secret_forest.FEATURES[k]] <= t else high
        return tree

    rows = secret_forest.labelled_findings(spark).limit(200).withColumn("s", secret_forest.forest_score(forest, F.col("f"))).collect()
    assert all(abs(r["s"] - sum(walk(t, r["f"]) for t in forest) / len(forest)) < 1e-9 for r in rows)


def test_precision_and_recall_on_findings_of_other_shapes(spark):
    r = random.Random(12)
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    token = lambda n, a=letters: "".join(r.choice(a) for _ in range(n))
    secret = [f"client_secret = '{token(28)}'", f"export TOKEN={token(44)}", f"Authorization: Bearer {token(60)}", f"glpat-{token(20)} is it", f"password: {token(14)}", f"npm_{token(36)}", f"api_key=\"{token(24, 'abcdef0123456789')}\""]
    plain = [f"commit {token(40, 'abcdef0123456789')}", f"sha256:{token(64, 'abcdef0123456789')}", f"order number {token(16, '0123456789')}", "see /usr/share/doc/python3.11/examples/readme", f"uuid {token(8, 'abcdef0123456789')}-1234-4234-8234-{token(12, 'abcdef0123456789')}", "the release_notes_for_version_12_of_the_manual", "password: your_password_here_1"]
    rows = [(k, f"text {s} tail") for k, s in enumerate(secret * 8)] + [(1000 + k, f"text {s} tail") for k, s in enumerate(plain * 8)]
    found = {x["doc_id"] for x in secret_forest.scan_secrets(spark.createDataFrame(rows, "doc_id long, text string")).collect() if x["secret"]}
    hit = sum(i < 1000 for i in found)
    assert hit >= 0.85 * 56 and hit / len(found) >= 0.85, (hit, len(found), sorted(found)[-10:])


def test_very_long_candidates_and_texts(spark):
    long = "Zq9" * 100_000
    rows = [(1, "x " * 200_000 + "password=hunter2hunter " + "y " * 1000), (2, f"key {long} end"), (3, "a" * 300_000)]
    got = {r["doc_id"]: r for r in secret_forest.scan_secrets(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1]["secret"] and got[2]["length"] == len(long) and 3 not in got


def test_long_media_text(spark):
    text = prose(1, 260_000)
    docs = spark.createDataFrame([(1, text), (2, None)], "doc_id long, text string")
    row = {r["doc_id"]: r for r in spark.createDataFrame(media_query(spark, docs)).collect()}[1]
    payload = text.encode() + b" " * (-len(text.encode()) % 192)
    assert row["payload_sha256"] == hashlib.sha256(payload).hexdigest() and row["n_bytes"] == len(text.encode())


def media_query(spark, docs):
    import tempfile

    folder = tempfile.mkdtemp()
    docs.write.parquet(f"{folder}/documents.parquet")
    return media_jpeg.op6_jpeg_media(spark, folder).toPandas()


def stage_input(spark, rows):
    return spark.createDataFrame([(i, t, "en", "src", len(t or ""), 1, 2, 3) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, bucket int, rest int, class_id int")


def test_stages_on_nulls_repeats_and_clashing_names(spark, tmp_path):
    rows = [(BIG, prose(1, 80)), (BIG, prose(1, 80)), (BIG, prose(2, 80)), (None, prose(1, 80)), (None, None), (4, None), (5, ""), (6, prose(1, 80)), (7, "token = \"" + hashlib.sha1(b"z").hexdigest() + "\"")]
    spark.createDataFrame([(BIG, 1, 0), (4, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = stage_input(spark, rows)
    none = docs.limit(0)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, str(tmp_path))
        if name != "packing":
            assert out.columns == docs.columns and stage(spark, none, str(tmp_path)).count() == 0
        got = out.collect()
        if name == "near-duplicate removal":
            kept = sorted(((r["doc_id"], r["text"]) for r in got), key=str)
            assert kept == sorted([(None, prose(1, 80)), (None, None), (4, None), (6, prose(1, 80)), (BIG, prose(2, 80)), rows[-1]], key=str)
        if name in ("suffix-array dedup", "secret scan"):
            assert len(got) == len(rows) and sum(r["doc_id"] == BIG for r in got) == 3
        if name == "packing":
            assert {r["doc_id"] for r in got} == {i for i, _ in rows}


def test_packing_query_gives_the_ids_of_the_default_tokenizer(spark, tmp_path):
    import zlib

    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    mark = "<|endoftext|>"
    texts = {1: f"one {mark} two\n\n{mark}", 2: mark, 3: mark + mark + " \n", 4: "<|endoftext", 5: f"a{' ' * 5000}{mark}{' ' * 5000}b", 6: f"{prose(6, 900)}{mark}{prose(7, 900)}", 7: ""}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    found = {}
    for p in packing.op1_hierarchical_packing(spark, str(tmp_path)).collect():
        found.setdefault(p["doc_id"], []).append(p)
    assert set(found) == set(texts)
    for i, text in texts.items():
        ids = np.array([*t.encode(text, add_special_tokens=False).ids, 1], "<u4")
        pieces = sorted(found[i], key=lambda p: p["start"])
        assert sum(p["length"] for p in pieces) == len(ids) and {p["doc_tokens"] for p in pieces} == {len(ids)}
        assert all(p["ids_crc32"] == zlib.crc32(ids[p["start"] : p["start"] + p["length"]].tobytes()) for p in pieces)
