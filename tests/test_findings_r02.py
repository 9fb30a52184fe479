"""Findings of round 2: equal places and keys, copies that no driver can hold, ties."""

import numpy as np
import pytest

from nodefill import catalogue
from nodefill.functions import geometry as G
from nodefill.operators import grid, measures, thin
from nodefill.plans import session

SMALL = "/root/testdata/sf0.001"


def table(spark, path, name, rows, schema):
    spark.createDataFrame(rows, schema).coalesce(1).write.mode("overwrite").parquet(f"{path}/{name}.parquet")


def test_equal_balances_give_the_smallest_key(spark, tmp_path):
    rows = [(k, 0, b) for k, b in ((9, 5.0), (4, 1.0), (3, 5.0), (7, 1.0), (1, None), (5, 3.0), (8, 5.0), (6, 1.0))] + [(2, 1, None)]
    table(spark, tmp_path, "customer", rows, "c_custkey long, c_nationkey int, c_acctbal double")
    got = {tuple(r) for r in catalogue.queries()["op_nearest_seed"](spark, str(tmp_path)).collect()}
    assert got == {(0, 4, 3), (1, None, None)}


@pytest.mark.parametrize("name", ["prune_close_candidate", "prune_close_parent"])
def test_copied_points_are_not_broadcast(spark, name):
    out = catalogue.queries()[name](spark, SMALL)
    kinds = [line for line in session.plan_of(out).splitlines() if "LeftAnti" in line]
    assert kinds and all("SortMergeJoin" in line for line in kinds)


def test_pairs_of_copies_are_counted_not_made(spark):
    assert session.plan_counts(catalogue.queries()["violations"](spark, SMALL))["BroadcastHashJoin"] == 0
    rows = [(k, 0.0, 0.0, 0.0, 1.0) for k in range(40)] + [(100 + k, 0.6, 0.0, 0.0, 0.5 + 0.5 * (k % 2)) for k in range(6)]
    p = spark.createDataFrame(rows, "pid long, x double, y double, z double, r double")
    assert measures.violations(p, 2, 1.0).first()[0] == 40 * 39 // 2 + 6 * 5 // 2 + 40 * 3
    w = p.withColumn("worker_id", (p.pid % 2).cast("int"))
    assert [tuple(r) for r in measures.front_collisions(w, 1.0, 2).collect()] == [(0, 1, 23 * 23)]


@pytest.mark.parametrize("name", ["knn_part_ties", "distance_histogram", "gradient_recovery"])
def test_searches_of_copies_make_few_pairs(spark, tmp_path, monkeypatch, name):
    table(spark, tmp_path, "part", [(k, 5, 905.0 + k // 100) for k in range(300)], "p_partkey long, p_size int, p_retailprice double")
    table(spark, tmp_path, "customer", [(k, 5, 2000.0 + k // 100) for k in range(300)], "c_custkey long, c_nationkey int, c_acctbal double")
    made, join = [], grid.radius_join
    monkeypatch.setattr(grid, "radius_join", lambda *a: made.append((out := session.cut(join(*a))).count()) or out)
    catalogue.queries()[name](spark, str(tmp_path)).collect()
    assert 0 < sum(made) < 300


@pytest.mark.parametrize("name", ["border_distance", "border_flags", "cell_neighbours", "front_collisions", "front_crossings", "front_snapshots"])
def test_points_do_not_meet_seeds_row_by_row(spark, name):
    assert session.plan_counts(catalogue.queries()[name](spark, SMALL))["BroadcastNestedLoopJoin"] == 0


@pytest.mark.parametrize("name", ["distance_histogram", "gradient_recovery"])
def test_searches_among_themselves_read_places_once(spark, monkeypatch, name):
    steps, cut, join = [], grid.cut, grid.radius_join
    monkeypatch.setattr(grid, "cut", lambda df: steps.append("cut") or cut(df))
    monkeypatch.setattr(grid, "radius_join", lambda *a: steps.append("join") or join(*a))
    catalogue.queries()[name](spark, SMALL)
    assert steps[: steps.index("join")] == ["cut"]


def test_one_file_s_points_meet_seeds_in_many_tasks(spark, tmp_path):
    table(spark, tmp_path, "points", [(k, k / 7, 0.0, 0.0) for k in range(50)], "pid long, x double, y double, z double")
    p, s = spark.read.parquet(f"{tmp_path}/points.parquet"), spark.createDataFrame([(1, 0.0, 0.0, 0.0), (2, 5.0, 0.0, 0.0)], "seed_id long, x double, y double, z double")
    assert p.rdd.getNumPartitions() == 1
    for out in (grid.assign_cells(p, s, 2), grid.nearest_cells(p, s, 2)):
        assert out.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism > 1


@pytest.mark.parametrize("name", ["border_flags", "cell_neighbours", "front_collisions", "front_crossings", "front_snapshots"])
def test_nearest_seeds_are_found_once(spark, name):
    plan = session.plan_of(catalogue.queries()[name](spark, SMALL)).split("== Initial Plan ==")[0]
    ways = 2 if name == "front_collisions" else 1  # both sides of its join; the second is read from the first's exchange
    assert plan.count("ArrowEvalPython") <= ways


def test_nearest_seeds_with_copies_and_missing_places(spark):
    p = spark.createDataFrame([(1, 0.2, 0.0, 0.0), (2, None, 0.0, 0.0), (3, 5.0, 5.0, 0.0)], "pid long, x double, y double, z double")
    s = spark.createDataFrame([(7, 0.0, 0.0, 0.0), (4, 0.0, 0.0, 0.0), (5, 0.0, 0.0, 0.0), (9, 5.0, 5.0, 0.0), (1, None, 0.0, 0.0)], "seed_id long, x double, y double, z double")
    got = {r["pid"]: [c["seed_id"] for c in r["cells"]] for r in grid.nearest_cells(p, s, 2).collect()}
    assert got == {1: [4, 5], 2: [4, 5], 3: [9, 4]}
    assert {r["pid"]: (r["cell_id"], r["seed_dist"]) for r in grid.assign_cells(p, s, 2).collect()} == {1: (4, 0.2), 2: (4, None), 3: (9, 0.0)}


def test_edges_between_places_and_their_copies(spark):
    p = spark.createDataFrame([(k, float(k % 2), 0.0, 0.0) for k in range(40)] + [(50, 9.0, 0.0, 0.0)], "pid long, x double, y double, z double")
    got = [tuple(r) for r in thin.place_links(p, 2, 2.0).collect()]
    assert sorted(r for r in got if r[2] == "near") == [(0, 1, "near")] and sorted(r[:2] for r in got if r[2] == "copy") == sorted((k % 2, k) for k in range(2, 40))
    assert session.plan_counts(catalogue.queries()["conflict_edges"](spark, SMALL))["BroadcastHashJoin"] == 0


@pytest.mark.parametrize("most", [200_000, 25])
def test_radii_that_differ_at_one_place(spark, monkeypatch, most):
    monkeypatch.setattr(thin, "ONE_TASK_ROWS", most)
    monkeypatch.setattr(thin, "close_pairs", None)
    monkeypatch.setattr(thin, "octave_pairs", None, raising=False)
    rng = np.random.default_rng(7)
    at, r = rng.random((60, 2)).round(1), rng.choice([0.05, 0.12, 0.3, 1.7], 60, p=[0.5, 0.3, 0.19, 0.01])
    want = []
    for k in range(60):
        if not any(((at[k] - at[j]) ** 2).sum() < r[k] ** 2 * G.SLACK for j in want):
            want.append(k)
    p = spark.createDataFrame([(k, *map(float, at[k]), 0.0, float(r[k])) for k in range(60)], "pid long, x double, y double, z double, r double")
    assert sorted(x["pid"] for x in thin.thin_octaves(p, 2, 0.1, 2).collect()) == want
    assert sorted(x["pid"] for x in thin.thin(p, 2, 2.0).collect()) == want


@pytest.mark.parametrize("numbers", [1_500_000, 1])
def test_vectors_without_pairs(spark, monkeypatch, numbers):
    monkeypatch.setattr(thin, "BLOCK_NUMBERS", numbers)
    monkeypatch.setattr(thin, "CHUNK", 40)
    monkeypatch.setattr(thin, "vector_pairs", None, raising=False)
    rng = np.random.default_rng(8)
    v = [row.tolist() for row in rng.random((90, 3)).round(2)] + [[0.5, 0.5, 0.5]] * 5 + [[0.5, 0.5, 0.8]]
    want = []
    for k, a in enumerate(v):
        if not any(sum((x - y) ** 2 for x, y in zip(a, v[j], strict=True)) ** 0.5 < 0.3 for j in want):
            want.append(k)
    odd = [(200, None), (201, None), (202, [float("nan"), 0.5, 0.5]), (203, [0.5, 0.5])]
    df = spark.createDataFrame([*enumerate(v), *odd], "pid long, v array<double>")
    assert sorted(x["pid"] for x in thin.thin_vectors(df, 0.3).collect()) == want + [200, 201, 202, 203]


def test_mesh_with_large_order_keys(spark, tmp_path):
    day = "1998-06-03"
    rows = [(k * 10**9, 1, 1, 25.0 + k, 52950.0, day) for k in range(1, 4)]
    line = spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_linenumber int, l_quantity double, l_extendedprice double, day string")
    line.withColumn("l_shipdate", line.day.cast("timestamp_ntz")).drop("day").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert [tuple(r) for r in catalogue.queries()["inside_mesh_parity"](spark, str(tmp_path)).collect()] == [(0,)]


def test_ties_of_a_table_s_rows(spark, tmp_path):
    table(spark, tmp_path, "customer", [(5, 10.0), (6, -3.0), (7, None)], "c_custkey long, c_acctbal double")
    assert sorted(map(tuple, catalogue.queries()["cell_ties"](spark, str(tmp_path)).collect())) == [(5, 1), (6, 1), (7, 1)]


@pytest.mark.parametrize("name", G.REGIONS)
def test_regions_with_line_ids_over_a_long(spark, tmp_path, name):
    lines = spark.read.parquet(f"{SMALL}/lineitem.parquet")
    lines.withColumn("l_orderkey", lines.l_orderkey + 10**6).write.parquet(f"{tmp_path}/lineitem.parquet")
    inside = catalogue.queries()["inside_" + name]
    near, far = inside(spark, SMALL), inside(spark, str(tmp_path))
    assert dict(near.dtypes)["last"] == "bigint" and near.count() > 1
    shift = 10**6 * 8 * 200003 * 10000019
    assert {(r["stripe"], r["n"], int(r["last"])) for r in far.collect()} == {(r["stripe"], r["n"], r["last"] + shift) for r in near.collect()}


@pytest.mark.parametrize("name", G.REGIONS)
def test_regions_work_out_places_once(spark, monkeypatch, name):
    made, cut = [], session.cut
    monkeypatch.setattr(catalogue, "cut", lambda df: made.append(df) or cut(df))
    catalogue.queries()["inside_" + name](spark, SMALL)
    made.append(catalogue.queries()["spacing_" + name](spark, SMALL))
    assert [df._jdf.queryExecution().optimizedPlan().toString().count("date_diff") + df._jdf.queryExecution().optimizedPlan().toString().count("datediff") for df in made] == [1, 1]


def lines(spark, path, rows):
    """Lines of (quantity, price, day)."""
    df = spark.createDataFrame([(k, 1, 1, *r) for k, r in enumerate(rows)], "l_orderkey long, l_partkey long, l_linenumber int, l_quantity double, l_extendedprice double, day int")
    df.selectExpr("* EXCEPT (day)", "CAST(DATE '1995-01-01' + day AS TIMESTAMP_NTZ) AS l_shipdate").write.parquet(f"{path}/lineitem.parquet")


def orders(spark, path, rows):
    """Orders of (key, customer, total, day)."""
    df = spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double, day int")
    df.selectExpr("* EXCEPT (day)", "CAST(DATE '1995-01-01' + day AS TIMESTAMP_NTZ) AS o_orderdate").write.parquet(f"{path}/orders.parquet")


def rows_of(spark, name, path):
    return sorted(map(tuple, catalogue.queries()[name](spark, str(path)).collect()), key=str)


def test_directions_that_lines_ask_for(spark, tmp_path):
    lines(spark, tmp_path, [(q, 1.0, 0) for q in (4.0, 4.0, 1.0, None, 0.5)])
    assert rows_of(spark, "directions_2d", tmp_path) == sorted([(1, 0, 1.0, 0.0, 1), (4, 0, 1.0, 0.0, 2), (4, 1, 0.0, 1.0, 2), (4, 2, -1.0, 0.0, 2), (4, 3, 0.0, -1.0, 2)], key=str)


def test_rings_that_lines_ask_for(spark, tmp_path):
    lines(spark, tmp_path, [(q, 1.0, 0) for q in (12.0, 1.0, 12.0)])
    rings = {(n_c, uz): n for n_c, uz, n in rows_of(spark, "directions_3d", tmp_path)}
    assert rings == {(1, 0.707107): 1, (1, -0.707107): 1} | {(12, s * uz): n for s in (1, -1) for uz, n in ((0.965926, 3), (0.707107, 8), (0.258819, 11))}


def test_numbers_of_directions_that_lines_ask_for(spark, tmp_path):
    lines(spark, tmp_path, [(q, 1.0, 0) for q in (12.0, 1.0, 12.0)])
    assert rows_of(spark, "directions_nd_count", tmp_path) == sorted([(12, 1, 2), (12, 2, 12), (12, 3, 44), (12, 4, 114), (1, 1, 2), (1, 2, 1), (1, 3, 2), (1, 4, 4)], key=str)


def test_area_that_lines_cover(spark, tmp_path):
    lines(spark, tmp_path, [(1.0, 52950.0, 1250), (2.0, 52950.5, 1250), (1.0, 0.0, 1250), (1.0, 54100.0, 1250), (1.0, None, 1250)])
    assert rows_of(spark, "domain_area", tmp_path) == [(0.005,)]


@pytest.mark.parametrize("name, wanted", [("bootstrap_iterative_log", (True, True, True)), ("bootstrap_once_count", (True,))])
def test_bootstraps_from_orders(spark, tmp_path, name, wanted):
    orders(spark, tmp_path, [(9, 1, 250000.0, 1200), (7, 1, 250000.0, 1200), (3, 1, 0.0, 1200), (4, 2, 251000.0, 1080), (5, 2, None, 1080)])
    assert rows_of(spark, name, tmp_path) == [(4, *wanted), (7, *wanted)]


def test_polygons_through_orders(spark, tmp_path):
    orders(spark, tmp_path, [(5, 1, 0.0, 0), (6, 1, 100000.0, 0), (7, 2, 300000.0, 480), (8, 3, 0.0, 0), (9, 3, 0.0, 240), (10, 3, 0.0, 240)])
    assert rows_of(spark, "boundary_polygon", tmp_path) == [(1, 4, 2.0, 0.0), (2, 1, 3.0, None), (3, 3, 0.0, -1.0)]


def test_curve_through_orders(spark, tmp_path):
    orders(spark, tmp_path, [(k, 1, (k % 20000) / 100, 0) for k in range(30000)] + [(-1, 1, None, 0)])
    n, gap, spaced = rows_of(spark, "boundary_clover", tmp_path)[0]
    assert (n, spaced) == (164, True) and 0.1 < gap < 0.102


@pytest.mark.parametrize("limit", [20_000, 1])
def test_points_without_a_place_near_many_seeds(spark, limit):
    p = spark.createDataFrame([(1, 0.2, 0.0, 0.0), (2, None, 0.0, 0.0), (3, 5.0, 5.0, 0.0)], "pid long, x double, y double, z double")
    s = spark.createDataFrame([(7, 0.0, 0.0, 0.0), (4, 0.0, 0.0, 0.0), (9, 5.0, 5.0, 0.0), (8, 1.0, 0.0, 0.0)], "seed_id long, x double, y double, z double")
    got = {r["pid"]: [(c["seed_id"], c["d2"]) for c in r["cells"]] for r in grid.nearest_cells(p, s, 2, 2, limit).collect()}
    assert got == {1: [(4, 0.2 * 0.2), (7, 0.2 * 0.2)], 2: [(4, None), (7, None)], 3: [(9, 0.0), (8, 41.0)]}
    assert {r["pid"]: (r["cell_id"], r["seed_dist"]) for r in grid.assign_cells(p, s, 2, limit).collect()} == {1: (4, 0.2), 2: (4, None), 3: (9, 0.0)}


@pytest.mark.parametrize("name", ["prune_close_candidate", "prune_close_parent"])
def test_candidates_are_numbered_by_integers(spark, name):
    assert dict(catalogue.queries()[name](spark, SMALL).dtypes)["cand"] == "int"
