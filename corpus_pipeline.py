"""Five stages from raw documents to packed training sequences.

Each stage takes (spark, docs, sf_dir) and works on everything its predecessor kept. All but the last return the
columns of documents; n_chars follows the text where a stage changes it.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nodefill.llm import packing, quality, secret_forest, suffix_index, weighted_minhash
from nodefill.llm.kernels import shared_folder


def quality_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the positive-unlabelled classifier rejects go."""
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def near_duplicate_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The text of the smallest doc_id of each class stays (of two texts under it, that with the smaller digest).

    A row that is repeated stays once: of rows with this doc_id and text, the first by a hash of all columns. Null texts are
    copies of empty ones. Rows without doc_id stay. Columns may have any name but this stage's own, which start with two underscores.
    """
    found = weighted_minhash.near_duplicates(docs, with_digest=True)
    keep = found.filter("first AND copy_of = doc_id").select(F.col("doc_id").alias("__keep_id__"), F.lower(F.hex("digest")).alias("__keep_digest__")).distinct()
    digest = F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    same = F.xxhash64(*[F.to_json(F.struct(F.col(f"`{c}`"))) if "map<" in kind or kind == "variant" else F.col(f"`{c}`") for c, kind in docs.dtypes])
    first = F.row_number().over(Window.partitionBy("doc_id", digest).orderBy(same))
    named = docs.filter("doc_id IS NOT NULL").join(keep, (F.col("doc_id") == F.col("__keep_id__")) & (digest == F.col("__keep_digest__")), "left_semi")
    named = named.withColumn("__turn__", first).filter("__turn__ = 1")
    return named.select(*[F.col(f"`{c}`") for c in docs.columns]).unionByName(docs.filter("doc_id IS NULL"))


def suffix_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Byte strings of 50 or more that a smaller doc_id holds go; characters that a cut would split stay whole."""
    return suffix_index.rewrite_documents(docs)


def secret_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets become a mark."""
    return secret_forest.redact(docs)


def packing_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 2048 tokens."""
    return packing.pack_documents(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("near-duplicate removal", near_duplicate_stage),
    ("suffix-array dedup", suffix_stage),
    ("secret scan", secret_stage),
    ("packing", packing_stage),
]
ORACLE_SQL = None


def run(spark, sf_dir: str) -> DataFrame:
    """The last stage's rows; between stages, Parquet in the cluster's shared folder."""
    shared_folder(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(f"{folder}/{k}")
            docs = spark.read.parquet(f"{folder}/{k}")
    return docs
