"""Queries for the experiments: each returns whether the reported behaviour shows."""

from __future__ import annotations

import math
import uuid

import numpy as np
from pyspark.sql import functions as F

from .catalogue import query
from .functions import geometry as G
from .operators import grid, measures
from .operators import spark_fill as fills
from .operators.surface import fill_surface
from .plans import session, workloads
from .sources import points_io
from .sources.tables import load, view


@query("workload_sequential_trace", "SELECT TRUE AS children_at_h, TRUE AS at_most_all_directions")
def workload_sequential_trace(spark, d):
    """What the 72nd expanded point places."""
    region, s = workloads.spacing_of_size("clover2d", 400)
    p = session.cut(fills.fill_sequential(workloads.first_seed(spark, region), region, s))
    kids = workloads.sequential_trace(spark, 72, 400)
    at = kids.join(p.select(F.col("pid").alias("parent"), F.col("x").alias("px"), F.col("y").alias("py"), F.col("h").alias("ph")), "parent")
    gap = F.abs(F.sqrt((F.col("x") - F.col("px")) * (F.col("x") - F.col("px")) + (F.col("y") - F.col("py")) * (F.col("y") - F.col("py"))) / F.col("ph") - 1)
    return at.agg(F.coalesce(F.max(gap) < 1e-9, F.lit(True)).alias("children_at_h"), (F.count("*") <= 12).alias("at_most_all_directions"))


@query("workload_cells", "SELECT TRUE AS at_least_asked, TRUE AS all_assigned")
def workload_cells(spark, d):
    """Four seeds asked for, at least as many obtained, and every row of the big cloud in a cell."""
    seeds, _ = workloads.bootstrap(spark, d, 1000, 4)
    p = view(spark, d, "pv_line2").filter(G.clover2d().contains())
    at = grid.assign_cells(p, seeds, 2)
    return at.agg(F.count_if(F.col("cell_id").isNull()).alias("lost")).join(F.broadcast(seeds.agg(F.count("*").alias("n")))).select((F.col("n") >= 4).alias("at_least_asked"), (F.col("lost") == 0).alias("all_assigned"))


@query("workload_direction_sweep", "SELECT TRUE AS more_directions_pack_no_worse, CAST(4 AS BIGINT) AS settings")
def workload_direction_sweep(spark, d):
    """More directions pack more evenly up to a point: the mean normalised distance doesn't grow."""
    out = workloads.direction_sweep(spark, (6, 12, 20, 30), 600)
    return out.agg((F.max(F.when(F.col("n_c") == 30, F.col("mean_dist"))) <= F.max(F.when(F.col("n_c") == 6, F.col("mean_dist"))) + 0.05).alias("more_directions_pack_no_worse"), F.count("*").alias("settings"))


@query("workload_bootstrap_sweep", "SELECT TRUE AS enough_seeds, TRUE AS counts_alike")
def workload_bootstrap_sweep(spark, d):
    """However many cells, at least the seeds asked for, and about the same number of points."""
    out = workloads.bootstrap_sweep(spark, (1, 2, 4), 1500)
    return out.agg(F.bool_and(F.col("obtained") >= F.col("requested")).alias("enough_seeds"), (F.max("placed") < 1.25 * F.min("placed")).alias("counts_alike"))


@query("workload_scaling")
def workload_scaling(spark, d):
    """Runs and their speedup and efficiency; times vary, so there is no SQL."""
    return measures.speedup(workloads.scaling(spark, "clover2d", (1000, 4000), 8))


@query("workload_overhead")
def workload_overhead(spark, d):
    """Seconds per placed point: the cell-parallel form with one part and no bootstrap against the sequential one."""
    rows = []
    for n in (1000, 4000):
        region, s = workloads.spacing_of_size("clover2d", n)
        seed = workloads.first_seed(spark, region)
        for _ in range(3):
            rows.append(workloads.timed("sequential", n, 1, lambda seed=seed, region=region, s=s: fills.fill_sequential(seed, region, s).count()))
            rows.append(workloads.timed("parallel1", n, 1, lambda seed=seed, region=region, s=s: fills.fill_cells(seed, region, s, 1, "none").count()))
    return measures.overhead(spark.createDataFrame(rows, "method string, size long, workers long, seconds double, placed long"))


@query("workload_step_times")
def workload_step_times(spark, d):
    return measures.step_shares(workloads.step_times(spark, 200))


@query("workload_bootstrap_share")
def workload_bootstrap_share(spark, d):
    """Measured seconds, so no SQL."""
    return measures.bootstrap_share(workloads.bootstrap_steps(spark, (1, 4)))


@query("workload_same_seeds", "SELECT TRUE AS counts_alike, TRUE AS regularity_alike")
def workload_same_seeds(spark, d):
    """From the same bootstrapped seeds, the sequential fill and the cell-parallel one are nearly alike."""
    region, s = workloads.spacing_of_size("clover2d", 800)
    seeds = session.cut(fills.bootstrap_iterative(workloads.first_seed(spark, region), region, s, 800, 8)[0])
    one, many = session.cut(fills.fill_sequential(seeds, region, s)), session.cut(fills.fill_parallel(seeds, region, s, 4, "flag"))
    a, b = (measures.local_regularity(measures.normalized_distances(p, 3, 2, s.most)).first() for p in (one, many))
    return spark.createDataFrame([(abs(a["n"] - b["n"]) < 0.1 * a["n"], abs(a["mean_dist"] - b["mean_dist"]) < 0.05 * a["mean_dist"])], "counts_alike boolean, regularity_alike boolean")


@query("fill_surface_sphere", "SELECT TRUE AS on_sphere, TRUE AS spaced, TRUE AS about_as_many")
def fill_surface_sphere(spark, d):
    """A band of the unit sphere by longitude and latitude."""
    band = G.box((0.0, -1.0), (6.0, 1.0))
    place = lambda p: np.stack([np.cos(p[:, 1]) * np.cos(p[:, 0]), np.cos(p[:, 1]) * np.sin(p[:, 0]), np.sin(p[:, 1])], 1)
    h = 0.15
    p = session.cut(fill_surface(spark, band, place, h))
    area = 6.0 * 2 * math.sin(1.0)
    norm = F.sqrt(F.col("x") * F.col("x") + F.col("y") * F.col("y") + F.col("z") * F.col("z"))
    near = measures.separation(p.withColumn("h", F.lit(h)), 3, h)
    return p.agg((F.max(F.abs(norm - 1)) < 1e-9).alias("on_sphere"), F.count("*").alias("n")).join(F.broadcast(near)).select("on_sphere", (F.col("separation") > 0.94 * h).alias("spaced"), F.col("n").between(0.4 * area / h**2, 1.2 * area / h**2).alias("about_as_many"))


@query("fill_annulus_invariants", "SELECT CAST(0 AS BIGINT) AS outside, CAST(0 AS BIGINT) AS violations, CAST(0 AS BIGINT) AS unfilled")
def fill_annulus_invariants(spark, d):
    """A region that isn't star-shaped, by rounds of joins."""
    region, s = G.annulus(0.6, 1.2), G.constant(0.3)
    p = session.cut(fills.fill_rounds(workloads.first_seed(spark, region), region, s))
    return measures.invariants(p, region, s)


def round_trip(kind: str):
    def run(spark, d):
        session.cut(spark.range(1))
        path = f"{spark.sparkContext.getCheckpointDir()}/points-{uuid.uuid4().hex}"
        p = view(spark, d, "pv_part2")
        points_io.write_points(p, path, kind)
        back = points_io.read_points(spark, path, kind)
        return back.agg(F.count("*").alias("n"), F.sum("pid").alias("pids"), F.round(F.sum("x"), 3).alias("x"), F.round(F.max("y"), 4).alias("y"))

    return run


for kind in ("parquet", "csv", "json", "orc"):
    query(f"op_roundtrip_{kind}", "SELECT count(*) AS n, CAST(sum(p_partkey) AS BIGINT) AS pids, round(sum(CAST(p_size AS DOUBLE)), 3) AS x, round(max(p_retailprice - 900), 4) AS y FROM part")(round_trip(kind))


@query("inside_mesh_parity", "SELECT CAST(0 AS BIGINT) AS differ")
def inside_mesh_parity(spark, d):
    """A triangulated octahedron against the same solid as a formula, for the big cloud."""
    top = [(1, 0, 0), (0, 1, 0), (-1, 0, 0), (0, -1, 0)]
    rows = [(2 * k + s, *map(float, (*top[k], *top[(k + 1) % 4], 0, 0, 1 if s else -1))) for k in range(4) for s in (0, 1)]
    names = [f"{c}{x}" for c in "abc" for x in "xyz"]
    faces = spark.createDataFrame(rows, "face int, " + ", ".join(f"{n} double" for n in names))
    p = view(spark, d, "pv_line3", wide_ids=True)
    solid = p.filter(F.abs("x") + F.abs("y") + F.abs("z") < 1)
    mesh = points_io.inside_mesh(p, faces)
    a = solid.select("pid").join(mesh.select("pid"), "pid", "left_anti")
    b = mesh.select("pid").join(solid.select("pid"), "pid", "left_anti")
    return a.unionByName(b).agg(F.count("*").alias("differ"))


@query("stream_dedup", "SELECT count(*) AS pairs FROM (SELECT DISTINCT user_id, event_type FROM events) t")
def stream_dedup(spark, d):
    return load(spark, d, "events").dropDuplicates(["user_id", "event_type"]).agg(F.count("*").alias("pairs"))
