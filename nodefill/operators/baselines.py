"""What fills are compared with: lattices, random points, darts, grouped cells, relaxation."""

from __future__ import annotations

import itertools

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..plans.session import cut
from . import front
from .grid import AXES, knn
from .measures import probe_lattice
from .thin import thin


def fill_lattice(spark, region, h: float) -> DataFrame:
    return probe_lattice(spark, region, h)


def fill_random(spark, region, n: int, seed: int = 1) -> DataFrame:
    """n draws in the box, those inside kept; coordinates from hashes, so the same on any number of partitions."""
    u = lambda k: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(1 << 40)).cast("double") / F.lit(float(1 << 40))
    cols = [(F.lit(float(a)) + F.lit(float(b - a)) * u(k)).alias(AXES[k]) for k, (a, b) in enumerate(zip(region.low, region.high, strict=True))]
    points = spark.range(n).select(F.col("id").alias("pid"), *cols, *[F.lit(0.0).alias(k) for k in AXES[region.dim :]])
    return points.filter(region.contains())


def fill_darts(spark, region, spacing, pool: int, seed: int = 1) -> DataFrame:
    """Darts in order: a dart stays unless one that stayed lies within its spacing."""
    darts = fill_random(spark, region, pool, seed).withColumn("h", spacing.column())
    return thin(darts.withColumn("r", F.col("h")), region.dim, spacing.most * 1.0001)


def fill_grouped(spark, region, spacing, k: int = 30, seed: int = 3) -> DataFrame:
    """Square cells in 2^dim groups; cells of a group lie apart and throw k darts a point side by side, groups one after the other."""
    dim = region.dim
    side = spacing.most * 2.0
    shape = [int((b - a) / side) + 1 for a, b in zip(region.low, region.high, strict=True)]
    cells = pd.DataFrame(list(itertools.product(*map(range, shape))), columns=[f"i{d}" for d in range(dim)])
    cells["cell"] = np.arange(len(cells))
    points = None
    for group in itertools.product((0, 1), repeat=dim):
        own = cells[np.logical_and.reduce([cells[f"i{d}"] % 2 == group[d] for d in range(dim)])]
        todo = spark.createDataFrame(own)
        schema = "pid long, x double, y double, z double, h double, r double"

        def throw(todo_frame, near):
            low = np.array([todo_frame[f"i{d}"].iloc[0] * side + region.low[d] for d in range(dim)])
            rng = np.random.default_rng([seed, int(todo_frame["cell"].iloc[0])])
            n = max(1, int(k * (side / spacing.least) ** dim))
            darts = low + rng.random((n, dim)) * side
            darts = darts[region.test(darts)]
            r = spacing.at(darts)
            if len(near) and len(darts):
                around = near[list("xyz"[:dim])].to_numpy(float)
                d2 = ((darts[:, None, :] - around[None]) ** 2).sum(2).min(1)
                darts, r = darts[d2 >= r * r * G.SLACK], r[d2 >= r * r * G.SLACK]
            keep = front.first_independent(len(darts), *front.conflicts(darts, r))
            pos = np.zeros((int(keep.sum()), 3))
            pos[:, :dim] = darts[keep]
            return pd.DataFrame({"pid": int(todo_frame["cell"].iloc[0]) * 1_000_000 + np.arange(len(pos)), "x": pos[:, 0], "y": pos[:, 1], "z": pos[:, 2], "h": r[keep], "r": r[keep]})

        if points is None:
            new = todo.groupBy("cell").applyInPandas(lambda f: throw(f, []), schema)
        else:
            near = points
            for d in range(dim):
                i = (F.col(AXES[d]) - region.low[d]) / side
                near = near.withColumn(f"c{d}", F.explode(F.sequence(F.floor(i - 0.5).cast("int"), F.floor(i + 0.5).cast("int"))))
            stride = [int(np.prod(shape[d + 1 :])) for d in range(dim)]
            near = near.withColumn("cell", sum((F.col(f"c{d}") * stride[d] for d in range(dim)), F.lit(0)).cast("long"))
            near = near.filter(F.expr(" AND ".join(f"c{d} >= 0 AND c{d} < {shape[d]}" for d in range(dim)))).drop(*[f"c{d}" for d in range(dim)])
            new = todo.groupBy("cell").cogroup(near.groupBy("cell")).applyInPandas(lambda t, n: throw(t, n) if len(t) else pd.DataFrame(columns=["pid", "x", "y", "z", "h", "r"]), schema)
        points = cut(new if points is None else points.unionByName(new))
    return points


def relax(points: DataFrame, iters: int, dim: int, side: float, k: int = 6, step: float = 0.1) -> DataFrame:
    """Repulsion from the k nearest, weighted with the inverse square distance."""
    for _ in range(iters):
        near = knn(points, points, k, dim, side, same=True).join(points.select(F.col("pid").alias("nbr"), *[F.col(c).alias(f"n{c}") for c in AXES[:dim]]), "nbr").join(points, "pid")
        push = near.groupBy("pid").agg(*[F.sum((F.col(c) - F.col(f"n{c}")) / (F.col("dist") * F.col("dist"))).alias(f"f{c}") for c in AXES[:dim]], F.avg("dist").alias("m"))
        size = F.sqrt(sum((F.col(f"f{c}") * F.col(f"f{c}") for c in AXES[:dim]), F.lit(0.0)))
        moved = points.join(push, "pid", "left").withColumn("size", size)
        points = cut(moved.select("pid", *[F.when(F.col("size") > 0, F.col(c) + step * F.col("m") * F.col(f"f{c}") / F.col("size")).otherwise(F.col(c)).alias(c) for c in AXES[:dim]], *[c for c in points.columns if c not in ("pid", *AXES[:dim])]))
    return points
