"""Geometry, front, fills, joins, measures and baselines on hand-checked cases and invariants."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from nodefill.functions import geometry as G
from nodefill.operators import front, grid, measures, pde, thin
from nodefill.operators import spark_fill as fills
from nodefill.plans import session, workloads
from nodefill.sources import points_io

SEED = "seed_id long, x double, y double, z double"


def seeds(spark, *rows):
    return spark.createDataFrame([(k + 1, *map(float, p), *[0.0] * (3 - len(p))) for k, p in enumerate(rows)], SEED)


def test_formulas():
    r = lambda t: 1.5 - np.cos(3 * t - np.pi / 2) ** 3
    assert np.allclose([r(0), r(np.pi / 6), r(np.pi / 2)], [1.5, 0.5, 2.5])
    assert G.clover_spacing(0.3).at(np.array([[0.0, 0.0]]))[0] == 0.3
    for name, make in G.REGIONS.items():
        region, s = make(), G.SPACINGS[name](1.0)
        assert region.test(np.array([region.inside], float))[0], name
        p = np.random.default_rng(0).uniform(region.low, region.high, (4000, region.dim))
        p = p[region.test(p)]
        h = s.at(p)
        assert len(p) and h.min() >= s.least * 0.999 and h.max() <= s.most * 1.001 and s.most / s.least < 5.3


def test_sql_and_numpy_agree(spark):
    for name, make in G.REGIONS.items():
        region, s = make(), G.SPACINGS[name](0.7)
        p = np.random.default_rng(1).uniform(region.low, region.high, (500, region.dim))
        rows = [(k, *map(float, q), *[0.0] * (3 - region.dim)) for k, q in enumerate(p)]
        out = spark.createDataFrame(rows, "pid long, x double, y double, z double").withColumn("ok", region.contains()).withColumn("h", s.column()).orderBy("pid").collect()
        ok = region.test(p)
        assert [r["ok"] for r in out] == ok.tolist(), name
        assert np.allclose(np.array([r["h"] for r in out])[ok], s.at(p)[ok], atol=2e-6)


def test_directions():
    for dim, n in ((1, 2), (2, 12), (3, 44), (4, 114)):
        u = G.sphere(dim, 12)
        assert len(u) == n and np.allclose((u**2).sum(1), 1)
    assert np.allclose((G.banks(3, 12) ** 2).sum(2), 1)


def test_hash_is_sparks(spark):
    v = [0, 1, -5, 2**62, 123456789]
    rows = spark.createDataFrame([(x,) for x in v], "a long").select(F.xxhash64("a"), F.xxhash64("a", F.lit(3).cast("long"))).collect()
    assert G.xxhash_long(np.array(v)).tolist() == [r[0] for r in rows]
    assert G.child_id(np.array(v), np.full(5, 3)).tolist() == [r[1] for r in rows]


def test_worked_fills():
    line = front.fill(G.box((0,), (10,)), G.constant(1.0), [[5.0]], [1])
    assert sorted(np.round(line["pos"][:, 0]).tolist()) == list(range(11)) and line["generations"] == 6
    square = front.fill(G.box((-1, -1), (1, 1)), G.constant(1.0), [[0.0, 0.0]], [1], n_c=4, rotate=False)
    assert len(square["pid"]) == 9 and np.bincount(square["gen"]).tolist() == [1, 4, 4]
    hexagon = front.fill(G.ellipsoid((0, 0), (1.5, 1.5)), G.constant(1.0), [[0.0, 0.0]], [1], n_c=6, rotate=False)
    assert len(hexagon["pid"]) == 7 and np.allclose(np.hypot(*hexagon["pos"][1:].T), 1)
    stall = front.fill(G.clover2d(), G.clover_spacing(0.2), [[0.0, 0.0]], [1], exclusion="literal")
    assert len(stall["pid"]) == 1


def brute_front(region, s, seed, n_c):
    """One point at a time from a queue."""
    pts, h, ids, at = [np.array(seed, float)], [s.at(np.array([seed], float))[0]], [1], 0
    u = G.banks(region.dim, n_c)
    while at < len(pts):
        for j, d in enumerate(u[int(G.xxhash_long(np.array([ids[at]]))[0]) % 16]):
            c = pts[at] + h[at] * d
            if region.test(c[None])[0] and all(((c - p) ** 2).sum() >= h[at] ** 2 * G.SLACK for p in pts):
                pts.append(c)
                h.append(s.at(c[None])[0])
                ids.append(int(G.child_id(np.array([ids[at]]), np.array([j]))[0]))
        at += 1
    return ids, np.array(pts)


@pytest.mark.parametrize("region,s", [(G.clover2d(), G.clover_spacing(0.2)), (G.clover3d(), G.clover3d_spacing(0.7)), (G.box((0, 0), (3, 2)), G.constant(0.3))])
def test_generations_equal_the_queue(region, s):
    ids, pts = brute_front(region, s, region.inside, 12)
    out = front.fill(region, s, [region.inside], [1])
    assert out["pid"].tolist() == ids and np.array_equal(out["pos"], pts)


def test_rounds_equal_the_kernel(spark):
    for exclusion in ("parent", "candidate"):
        region, s = G.clover2d(), G.clover_spacing(0.4)
        a = fills.fill_sequential(seeds(spark, (0, 0), (0.1, 0.3)), region, s, exclusion=exclusion)
        b = fills.fill_rounds(seeds(spark, (0, 0), (0.1, 0.3)), region, s, exclusion=exclusion)
        key = ["pid", "parent", "gen", "x", "y", "h"]
        x, y = (sorted(map(tuple, f.select(*key).collect())) for f in (a, b))
        assert len(x) > 15 and x == y


@pytest.mark.parametrize("border", ["flag", "colour"])
def test_parallel_fills(spark, border):
    region, s = workloads.spacing_of_size("clover2d", 500)
    start, log = fills.bootstrap_iterative(workloads.first_seed(spark, region), region, s, 500, 6)
    assert log[-1][2] >= 6 and all(b[1] == a[1] / 2 for a, b in zip(log, log[1:]))
    p = session.cut(fills.fill_parallel(start, region, s, 4, border))
    assert tuple(measures.invariants(p, region, s).first()) == (0, 0, 0)
    assert 250 < p.count() < 1000


def test_three_dimensions_and_levels(spark):
    region, s = workloads.spacing_of_size("maze3d", 1200)
    p = session.cut(fills.fill_sequential(workloads.first_seed(spark, region), region, s))
    assert tuple(measures.invariants(p, region, s).first()) == (0, 0, 0) and 600 < p.count() < 2400
    region, s = workloads.spacing_of_size("heatsink2d", 300)
    q = session.cut(fills.fill_multilevel(workloads.first_seed(spark, region), region, s, 1, 4))
    assert measures.outside(q, region).first()[0] == 0 and measures.unfilled(q, region, s).first()[0] == 0
    assert q.select("level").distinct().count() == 2


def test_edges_of_fills(spark):
    region, s = G.clover2d(), G.clover_spacing(0.4)
    assert fills.fill_sequential(spark.createDataFrame([], SEED), region, s).count() == 0
    assert fills.fill_sequential(seeds(spark, (9, 9)), region, s).count() == 0
    assert fills.fill_rounds(seeds(spark, (9, 9)), region, s).count() == 0
    with pytest.raises(ValueError):
        fills.fill_cells(seeds(spark, (0, 0), (0.1, 0.1)), region, s, max_seeds=1)


def test_greedy_order():
    p, r = np.array([[0.0], [0.6], [1.2]]), np.ones(3)
    assert front.first_independent(3, *front.conflicts(p, r)).tolist() == [True, False, True]
    assert front.first_independent(3, *front.conflicts(p[[1, 0, 2]], r)).tolist() == [True, False, False]
    far = np.array([[0.0], [1.5]])
    assert front.first_independent(2, *front.conflicts(far, np.array([2.0, 1.0]))).tolist() == [True, True]
    assert front.first_independent(2, *front.conflicts(far[::-1], np.array([1.0, 2.0]))).tolist() == [True, False]


def test_knn_forms_agree(spark):
    rng = np.random.default_rng(4)
    pts = rng.random((300, 3))
    df = spark.createDataFrame([(k, *map(float, p)) for k, p in enumerate(pts)], "pid long, x double, y double, z double")
    s = spark.createDataFrame([(k, *map(float, p)) for k, p in enumerate(rng.random((7, 3)))], SEED)
    d2 = ((pts[:, None] - pts[None]) ** 2).sum(2)
    np.fill_diagonal(d2, np.inf)
    want = {(i, k + 1): int(j) for i in range(300) for k, j in enumerate(np.argsort(d2[i], kind="stable")[:4])}
    for out in (grid.knn(df, df, 4, 3, 0.05, same=True), grid.indexed_knn(df, df, s, 4, 3, same=True)):
        assert {(r["pid"], r["rank"]): r["nbr"] for r in out.collect()} == want


def test_many_seeds_are_not_broadcast(spark):
    rng = np.random.default_rng(6)
    df = spark.createDataFrame([(k, *map(float, p), 0.0) for k, p in enumerate(rng.random((200, 2)))], "pid long, x double, y double, z double")
    s = spark.createDataFrame([(k, *map(float, p), 0.0) for k, p in enumerate(rng.random((30, 2)))], SEED)
    key = lambda out: sorted((r["pid"], r["cell_id"]) for r in out.collect())
    assert key(grid.assign_cells(df, s, 2)) == key(grid.assign_cells(df, s, 2, limit=10))
    ids = lambda out: sorted((r["pid"], tuple(c["seed_id"] for c in r["cells"])) for r in out.collect())
    assert ids(grid.nearest_cells(df, s, 2)) == ids(grid.nearest_cells(df, s, 2, limit=10))


def test_distance_joins_have_no_products(spark):
    df = spark.range(100).selectExpr("id AS pid", "rand(1) AS x", "rand(2) AS y", "0D AS z")
    counts = session.plan_counts(grid.radius_join(df, df, 0.1, 2))
    assert counts["CartesianProduct"] == 0 and counts["BroadcastNestedLoopJoin"] == 0
    d = fills.expand(fills.seed_points(seeds(spark, (0, 0)), G.clover2d(), G.constant(0.5)), fills.directions(spark, 2, 12), 2)
    assert session.plan_counts(d)["BroadcastHashJoin"] == 1


def test_thinning(spark):
    rows = [(1, 0.0, 0.0, 0.0, 1.0), (2, 0.5, 0.0, 0.0, 1.0), (3, 1.2, 0.0, 0.0, 1.0), (4, 0.0, 0.0, 0.0, 1.0)]
    df = spark.createDataFrame(rows, "pid long, x double, y double, z double, r double")
    assert sorted(r["pid"] for r in thin.thin(df, 2, 1.0).collect()) == [1, 3]
    assert thin.thin(df.limit(0), 2, 1.0).count() == 0
    v = spark.createDataFrame([(k, [float(k), 0.0]) for k in range(10)], "pid long, v array<double>")
    assert sorted(r["pid"] for r in thin.thin_vectors(v, 1.5).collect()) == [0, 2, 4, 6, 8]


def test_iterative_solver_agrees_with_dense(spark):
    _, matrix, rhs, _, _ = workloads.poisson_system(spark, 80)
    a = {r["i"]: r["v"] for r in pde.solve(matrix, rhs).collect()}
    b = {r["i"]: r["v"] for r in pde.solve(matrix, rhs, "bicgstab", 1e-9, 60).collect()}
    assert max(abs(a[i] - b[i]) for i in a) < 1e-5


def test_files(spark, tmp_path):
    df = spark.createDataFrame([(k, k * 0.5, -k * 0.25, 0.0) for k in range(20)], points_io.SCHEMA)
    for kind in ("parquet", "csv", "json", "orc"):
        points_io.write_points(df, f"{tmp_path}/{kind}", kind)
        assert sorted(map(tuple, points_io.read_points(spark, f"{tmp_path}/{kind}", kind).collect())) == sorted(map(tuple, df.collect()))
    points_io.write_points(df, f"{tmp_path}/text", "text")
    assert sorted(r["x"] for r in points_io.read_points(spark, f"{tmp_path}/text", "text").collect()) == [k * 0.5 for k in range(20)]
    points_io.write_points(df.withColumn("level", F.col("pid") % 2), f"{tmp_path}/by", by="level")
    assert spark.read.parquet(f"{tmp_path}/by").filter("level = 1").count() == 10
    corners = "v 0 0 0\nv 1 0 0\nv 0 1 0\nv 0 0 1\nf 1 2 3\nf 1 2 4\nf 1 3 4\nf 2 3 4\n"
    (tmp_path / "mesh.txt").write_text(corners)
    faces = points_io.read_mesh(spark, f"{tmp_path}/mesh.txt")
    assert faces.count() == 4
    p = spark.createDataFrame([(1, 0.2, 0.2, 0.2), (2, 0.6, 0.6, 0.2), (3, 0.1, 0.1, -0.5)], points_io.SCHEMA)
    assert [r["pid"] for r in points_io.inside_mesh(p, faces).collect()] == [1]


def test_stream_equals_batch(spark, tmp_path):
    from nodefill.streaming import spacing as streams

    rows = [(u, 100 * u + k, f"2024-01-01 {k // 3:02d}:{(k % 3) * 20:02d}:00") for u in range(3) for k in range(40)]
    ev = spark.createDataFrame(rows, "user_id long, event_id long, t string").selectExpr("user_id", "event_id", "timestamp(t) AS ts")
    for k in range(4):
        ev.filter(f"hour(ts) div 4 = {k}").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    want = sorted(map(tuple, streams.spaced_batch(ev, 3000).collect()))
    stream = streams.spaced_stream(spark.readStream.schema(ev.schema).parquet(f"{tmp_path}/in"), 3000)
    got = sorted(map(tuple, streams.run_to_table(stream, "spaced", f"{tmp_path}/cp").collect()))
    assert got == want and len(want) < len(rows)


def test_entry_imports_without_a_session():
    import os
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 150 and set(o) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=120)


def test_farthest_first_sees_all_seeds_and_rounds_do_not_end_early(spark):
    many = spark.range(100_001).select(F.col("id").alias("seed_id"), (F.col("id") % 10 / 10.0).alias("x"), F.lit(0.0).alias("y"), F.when(F.col("id") == 100_000, 9.0).otherwise(0.0).alias("z"))
    assert [r["seed_id"] for r in fills.reduce_seeds(many, 3, "farthest").orderBy("z", "seed_id").collect()] == [0, 9, 100_000]
    same = many.filter("seed_id IN (0, 10, 20)")
    assert {r["seed_id"] for r in fills.reduce_seeds(same, 5, "farthest").collect()} == {0, 10, 20}
    with pytest.raises(RuntimeError):
        fills.fill_rounds(seeds(spark, (0, 0)), G.clover2d(), G.clover_spacing(0.2), max_rounds=1)
    ids = [(i, j, 4.0 if i == j else 1.0 + i / (1 + j)) for i in range(4) for j in range(4)]
    a, b = spark.createDataFrame(ids, "i long, j long, w double"), spark.createDataFrame([(i, 1.0 + i) for i in range(4)], "i long, v double")
    with pytest.raises(RuntimeError):
        pde.solve(a, b, "bicgstab", steps=1)
