"""The stages on planted cases: junk goes, one of each group stays, repeated passages and secrets go, the rest is packed."""

import hashlib

import corpus_pipeline
from test_operators import SHARED, prose


def test_pipeline(spark, tmp_path):
    key = hashlib.sha1(b"p").hexdigest()
    rows = [(i, prose(i, 90)) for i in range(60)]
    rows += [(100 + i, prose(i, 90).upper().replace(" ", "!! ")) for i in range(30)]
    rows += [(200, prose(1, 90)), (201, prose(2, 90) + " end"), (202, prose(350, 40) + " " + SHARED), (203, SHARED + " " + prose(351, 40)), (204, f"{prose(352, 60)} token = \"{key}\" {prose(353, 60)}"), (205, None), (206, "")]
    docs = spark.createDataFrame([(i, t, "en", "src0", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(60)] + [(100 + i, 0, 0) for i in range(30)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    seen = {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        seen[name] = {r["doc_id"]: r["text"] for r in docs.collect()} if k < 4 else None
        if k < 4:
            assert set(docs.columns) == {"doc_id", "text", "lang", "source", "n_chars"}
    first = seen["quality classifier"]
    assert not any(100 <= i < 130 for i in first) and all(i in first for i in range(60))
    second = seen["near-duplicate removal"]
    assert 200 not in second and 201 not in second and all(i in second for i in range(60)) and 203 in second
    third = seen["suffix-array dedup"]
    assert SHARED in third[202] and SHARED[2:-2] not in third[203] and third[203].endswith(prose(351, 40))
    fourth = seen["secret scan"]
    assert key not in fourth[204] and prose(352, 60) in fourth[204]
    assert {r["doc_id"] for r in docs.collect()} == set(fourth)
    total = corpus_pipeline.run(spark, str(tmp_path)).count()
    assert total == docs.count()
