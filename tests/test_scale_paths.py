"""The ways that only large inputs take, forced on small ones, give the same rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from nodefill.functions import geometry as G
from nodefill.operators import front, grid, measures, pde, thin
from nodefill.operators import spark_fill as fills
from nodefill.plans import session, workloads
from nodefill.sources import points_io


def cloud(spark, n, seed=1):
    rng = np.random.default_rng(seed)
    return spark.createDataFrame([(k, *map(float, p), 0.0, 0.15) for k, p in enumerate(rng.random((n, 2)))], "pid long, x double, y double, z double, r double")


def test_thinning_by_rounds(spark, monkeypatch):
    p = cloud(spark, 150)
    want = sorted(r["pid"] for r in thin.thin(p, 2, 0.15).collect())
    monkeypatch.setattr(thin, "ONE_TASK_ROWS", 40)
    assert sorted(r["pid"] for r in thin.thin(p, 2, 0.15).collect()) == want
    pairs = session.plan_counts(thin.close_pairs(p, 2, 0.15))
    assert pairs["CartesianProduct"] == 0


def test_settling_by_rounds(spark, monkeypatch):
    p = session.cut(cloud(spark, 80, 2))
    edges = thin.close_pairs(p, 2, 0.15)
    want = sorted(r["pid"] for r in fills.settle(p.select("pid"), edges).collect())
    monkeypatch.setattr(fills, "ONE_TASK", 10)
    assert sorted(r["pid"] for r in fills.settle(p.select("pid"), edges).collect()) == want == sorted(r["pid"] for r in thin.thin(p, 2, 0.15).collect())


def test_refill_by_blocks(spark, monkeypatch):
    region, s = workloads.spacing_of_size("clover2d", 300)
    seeds, _ = fills.bootstrap_iterative(workloads.first_seed(spark, region), region, s, 300, 5)
    monkeypatch.setattr(fills, "ONE_TASK_POINTS", 10)
    monkeypatch.setattr(fills, "BLOCK_POINTS", 60)
    p = session.cut(fills.fill_parallel(seeds, region, s, 4, "colour"))
    assert tuple(measures.invariants(p, region, s).first()) == (0, 0, 0) and p.select("pid").distinct().count() == p.count()


def test_greedy_order_without_sorted_edges():
    p, r = np.random.default_rng(3).random((200, 2)), np.full(200, 0.2)
    a, b = front.conflicts(p, r)
    want = []
    for k in range(200):
        if not any(((p[k] - p[j]) ** 2).sum() < 0.04 * G.SLACK for j in want):
            want.append(k)
    assert np.flatnonzero(front.first_independent(200, a, b)).tolist() == want
    flip = 199 - np.arange(200)
    assert sorted(flip[front.first_independent(200, flip[a], flip[b])[flip]].tolist()) != [] and np.flatnonzero(front.first_independent(200, flip[a], flip[b])[flip]).tolist() == want


def test_sectors_reach_as_far_as_needed(spark):
    rows = [(k, k * 0.01, 0.0, 0.0) for k in range(60)] + [(100, 0.3, 5.0, 0.0)]
    p = spark.createDataFrame(rows, "pid long, x double, y double, z double")
    got = {(r["pid"], r["sector"]): r["nbr"] for r in pde.sector_stencils(p, 4, 2, 0.05).collect()}
    assert got[0, 0] == 1 and all(got[k, 0 if k <= 30 else 1] is not None for k in range(60)) and 100 in {v for (k, _), v in got.items() if k == 40}
    walls = spark.createDataFrame([(0.105, -1.0, 0.105, 1.0)], "x1 double, y1 double, x2 double, y2 double")
    seen = [r["nbr"] for r in pde.visible_stencils(p, walls, 4, 0.02).filter("pid = 10").orderBy("rank").collect()]
    assert seen == [9, 8, 7, 6]


def test_indexed_search_makes_few_rows(spark):
    p = cloud(spark, 200, 4)
    s = p.filter("pid < 12").select(F.col("pid").alias("seed_id"), "x", "y", "z")
    key = lambda out: sorted((r["pid"], r["rank"], r["nbr"]) for r in out.collect())
    assert key(grid.indexed_knn(p, p, s, 3, 2, same=True)) == key(grid.knn(p, p, 3, 2, 0.2, same=True))


def test_validity_guard(spark):
    region = G.REGIONS["clover2d"]()
    rows = [(0.5, 0.2, 0.1), (None, 0.2, 0.1), (0.5, float("nan"), 0.1), (float("inf"), 0.2, 0.1), (0.5, 0.2, 0.0), (0.5, 0.2, None), (50.0, 0.2, 0.1)]
    faults = [None, "coordinate", "coordinate", "coordinate", "spacing", "spacing", "outside"]
    for row, want in zip(rows, faults, strict=True):
        p = spark.createDataFrame([(*row, 0.0)], "x double, y double, h double, z double")
        assert p.select(points_io.fault(p, region)).first()[0] == want
        if want is None:
            assert points_io.require_valid(p, region).count() == 1
        else:
            with pytest.raises(Exception, match="invalid point: " + want):
                points_io.require_valid(p, region).collect()


def test_sorted_export_is_one_order(spark, tmp_path):
    p = cloud(spark, 400).repartition(5)
    points_io.write_sorted(p, str(tmp_path / "out"), "x")
    back = spark.read.parquet(str(tmp_path / "out")).groupBy("_metadata.file_name").agg(F.min("x").alias("a"), F.max("x").alias("b")).orderBy("file_name").collect()
    assert all(u["b"] <= v["a"] for u, v in zip(back[:-1], back[1:], strict=True))
