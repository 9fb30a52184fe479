"""Cutting lineage and looking at plans."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame


def shared_folder(spark) -> str:
    """The checkpoint folder that the cluster names; without such a setting a local master, as in tests, uses a folder of this machine, and a cluster is refused."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoints-"))
    return context.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """The rows without their lineage: a table in the checkpoint folder, so that lost executors can't lose them.

    Unlike a checkpoint it is computed once, and its size is known: a checkpoint keeps the estimate of its plan, which
    grows with each join of a loop.
    """
    path = f"{shared_folder(df.sparkSession)}/cut-{uuid.uuid4().hex}"
    df.write.option("parquet.block.size", 16 << 20).parquet(path)  # small row groups: a writer holds one in memory
    return df.sparkSession.read.schema(df.schema).parquet(path)


def plan_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def plan_counts(df: DataFrame) -> dict:
    """How often each kind of physical operator that matters for scale occurs."""
    text = plan_of(df)
    kinds = ("CartesianProduct", "BroadcastNestedLoopJoin", "BroadcastHashJoin", "SortMergeJoin", "ShuffledHashJoin", "Exchange", "Window", "MapInPandas", "FlatMapGroupsInPandas")
    return {k: len(re.findall(rf"\b{k}\b", text)) for k in kinds}
