"""Quality, cost and run measures over points and run logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.geometry import SLACK
from .grid import AXES, knn, place_pairs
from .spark_fill import directions, expand, prune_close


def normalized_distances(points: DataFrame, k: int, dim: int, side: float) -> DataFrame:
    """pid, rank, nbr, dist, ndist = dist / h(pid) of the k nearest."""
    near = knn(points, points, k, dim, side, same=True)
    return near.join(points.select("pid", "h"), "pid").select("pid", "rank", "nbr", "dist", (F.col("dist") / F.col("h")).alias("ndist"))


def distance_histogram(nd: DataFrame, width: float) -> DataFrame:
    return nd.groupBy(F.floor(F.col("ndist") / width).alias("bin")).agg(F.count("*").alias("n"))


def histogram_delta(a: DataFrame, b: DataFrame) -> DataFrame:
    """bin, n_a, n_b, delta: bins of either histogram."""
    out = a.withColumnRenamed("n", "na").join(b.withColumnRenamed("n", "nb"), "bin", "full")
    return out.select("bin", F.coalesce("na", F.lit(0)).alias("n_a"), F.coalesce("nb", F.lit(0)).alias("n_b"), (F.coalesce("na", F.lit(0)) - F.coalesce("nb", F.lit(0))).alias("delta"))


def local_regularity(nd: DataFrame) -> DataFrame:
    """Mean and deviation over points of their mean normalised distance, and the mean spread."""
    each = nd.groupBy("pid").agg(F.avg("ndist").alias("m"), (F.max("ndist") - F.min("ndist")).alias("s"))
    return each.agg(F.avg("m").alias("mean_dist"), F.stddev_pop("m").alias("std_dist"), F.avg("s").alias("mean_spread"), F.count("*").alias("n"))


def separation(points: DataFrame, dim: int, side: float) -> DataFrame:
    """Least nearest-neighbour distance, plain and over h."""
    return normalized_distances(points, 1, dim, side).agg(F.min("dist").alias("separation"), F.min("ndist").alias("separation_h"))


def lattice_places(points: DataFrame, region, step: float) -> DataFrame:
    """Lattice places inside a region that are the nearest of one of `points` at least, each once."""
    at = [(F.floor((F.col(k) - float(lo)) / step + 0.5) * step + float(lo)).alias(k) for k, lo in zip(AXES, region.low, strict=False)]
    return points.select(*at).distinct().filter(region.contains())


def probe_lattice(spark, region, step: float) -> DataFrame:
    """Lattice points inside a region: pid, x, y, z."""
    shape = [int((b - a) / step) + 1 for a, b in zip(region.low, region.high, strict=True)]
    total, stride, cols = 1, 1, []
    for n in shape:
        total *= n
    for k, (lo, n) in enumerate(zip(region.low, shape, strict=True)):
        cols.append((F.lit(float(lo)) + F.lit(float(step)) * F.pmod(F.floor(F.col("id") / stride), F.lit(n))).alias(AXES[k]))
        stride *= n
    lattice = spark.range(total).select(F.col("id").alias("pid"), *cols, *[F.lit(0.0).alias(k) for k in AXES[region.dim :]])
    return lattice.filter(region.contains())


def fill_distance(points: DataFrame, probes: DataFrame, dim: int, side: float) -> DataFrame:
    """Largest 2 d / h(p) over probes, p the nearest point: a lower bound of the largest empty ball's diameter that grows as probes get dense."""
    near = knn(points, probes, 1, dim, side)
    return near.join(points.select(F.col("pid").alias("nbr"), "h"), "nbr").agg(F.max(2 * F.col("dist")).alias("fill"), F.max(2 * F.col("dist") / F.col("h")).alias("fill_h"))


def node_set_ratio(points: DataFrame, probes: DataFrame, dim: int, side: float) -> DataFrame:
    s, f = separation(points, dim, side), fill_distance(points, probes, dim, side)
    return s.join(F.broadcast(f)).select("separation_h", "fill_h", (F.col("fill_h") / F.col("separation_h")).alias("ratio"))


def violations(points: DataFrame, dim: int, side: float) -> DataFrame:
    """Number of pairs nearer than the smaller of their acceptance radii."""
    pairs = place_pairs(points, side, dim, ["r"])
    least = F.least("a_r", "b_r")
    apart = pairs.filter(F.col("d2") < least * least * SLACK).select((F.col("a_n") * F.col("b_n")).alias("n"))
    alike = points.filter(F.col("r") * F.col("r") > 0).groupBy(*AXES[:dim], "r").agg(F.count("*").alias("n")).filter("n > 1").select(F.expr("n * (n - 1) div 2").alias("n"))
    return apart.unionByName(alike).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("violations"))


def unfilled(points: DataFrame, region, spacing, n_c: int = 12, rotate: bool = True) -> DataFrame:
    """Number of candidates that could still be placed: all points expanded again. `ord` isn't needed for that."""
    dirs = directions(points.sparkSession, region.dim, n_c, rotate)
    p = points.withColumn("h", spacing.column()).withColumn("ord", F.array(F.lit(0).cast("long")))
    cands = expand(p, dirs, region.dim).filter(region.contains())
    return prune_close(cands, p, spacing.most * 1.0001, region.dim).agg(F.count("*").alias("unfilled"))


def outside(points: DataFrame, region) -> DataFrame:
    return points.agg(F.count(F.when(~region.contains(), 1)).alias("outside"))


def invariants(points: DataFrame, region, spacing, n_c: int = 12) -> DataFrame:
    """One row: what must be zero."""
    side = spacing.most * 1.0001
    return outside(points, region).join(F.broadcast(violations(points, region.dim, side))).join(F.broadcast(unfilled(points, region, spacing, n_c)))


def fill_counters(points: DataFrame, region, spacing, n_c: int = 12) -> DataFrame:
    """Candidates by what became of them, for a finished fill: all candidates = outside + too close + placed."""
    dirs = directions(points.sparkSession, region.dim, n_c)
    p = points.withColumn("h", spacing.column()).withColumn("ord", F.array(F.lit(0).cast("long")))
    c = expand(p, dirs, region.dim)
    return c.agg(F.count("*").alias("candidates"), F.count_if(~region.contains()).alias("outside"), F.count_if(region.contains()).alias("neighbour_queries"))


def speedup(runs: DataFrame) -> DataFrame:
    """runs (method, size, workers, seconds, placed): time per placed point of method sequential over that of the others, and over workers."""
    per = runs.groupBy("method", "size", "workers").agg((F.sum("seconds") / F.sum("placed")).alias("per_point"))
    base = per.filter("method = 'sequential'").groupBy("size").agg(F.min("per_point").alias("base"))
    return per.join(base, "size").select("method", "size", "workers", (F.col("base") / F.col("per_point")).alias("speedup"), (F.col("base") / F.col("per_point") / F.col("workers")).alias("efficiency"))


def overhead(runs: DataFrame) -> DataFrame:
    """size, extra seconds per placed point of method parallel1 over sequential, means over repeats."""
    per = runs.groupBy("size").pivot("method", ["sequential", "parallel1"]).agg(F.avg(F.col("seconds") / F.col("placed")))
    return per.select("size", (F.col("parallel1") - F.col("sequential")).alias("overhead"))


def step_shares(steps: DataFrame) -> DataFrame:
    """run, step, share of the run's seconds."""
    total = F.sum("seconds").over(Window.partitionBy("run"))
    return steps.groupBy("run", "step").agg(F.sum("seconds").alias("seconds")).select("run", "step", "seconds", (F.col("seconds") / total).alias("share"))


def bootstrap_share(steps: DataFrame) -> DataFrame:
    """run, share of the run's seconds that went into its step `bootstrap`; 0 for a run without one."""
    return step_shares(steps).groupBy("run").agg(F.sum("seconds").alias("seconds"), F.coalesce(F.sum(F.when(F.col("step") == "bootstrap", F.col("share"))), F.lit(0.0)).alias("share"))


def single_vs_sum(runs: DataFrame) -> DataFrame:
    """Correlation over settings of the single worker's time with the sum of all workers' times."""
    return runs.groupBy("setting").agg(F.sum(F.when(F.col("workers") == 1, F.col("seconds"))).alias("single"), F.sum(F.when(F.col("workers") > 1, F.col("seconds"))).alias("summed")).agg(F.corr("single", "summed").alias("corr"), F.count("*").alias("n"))


def growth_rate(levels: DataFrame, x: str, y: str) -> DataFrame:
    """Slope of log y over log x."""
    return levels.agg(F.regr_slope(F.ln(y), F.ln(x)).alias("rate"), F.count("*").alias("n"))


def load_balance(work: DataFrame) -> DataFrame:
    """work (worker_id, placed): each worker's idle share against the busiest."""
    most = F.max("work").over(Window.partitionBy())
    return work.groupBy("worker_id").agg(F.sum("placed").alias("work")).select("worker_id", "work", ((most - F.col("work")) / F.col("work")).alias("idle_ratio"))


def cell_skew(points: DataFrame) -> DataFrame:
    per = points.groupBy("cell_id").agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("cells"), F.max("n").alias("largest"), (F.max("n") / F.avg("n")).alias("skew"))


def front_snapshots(points: DataFrame, ks, order) -> DataFrame:
    """The first k points of each worker for each k, counted: (k, worker_id, n, cells)."""
    at = points.withColumn("turn", F.row_number().over(Window.partitionBy("worker_id").orderBy(*order)))
    each = at.withColumn("k", F.explode(F.array(*[F.lit(k) for k in ks]))).filter(F.col("turn") <= F.col("k"))
    return each.groupBy("k", "worker_id").agg(F.count("*").alias("n"), F.countDistinct("cell_id").alias("cells"))


def front_collisions(points: DataFrame, r: float, dim: int) -> DataFrame:
    """Pairs of workers whose points come within r of each other."""
    pairs = place_pairs(points, r, dim, ["worker_id"]).filter("a_worker_id <> b_worker_id")
    one, other = F.least("a_worker_id", "b_worker_id"), F.greatest("a_worker_id", "b_worker_id")
    return pairs.groupBy(one.alias("a"), other.alias("b")).agg(F.sum(F.col("a_n") * F.col("b_n")).alias("pairs"))


def cost_model(n: Column, n_ct: Column, p: Column, n_s: Column) -> list[Column]:
    """Operation counts: sequential; parallel at worst; parallel expected; space."""
    log = lambda c: F.log2(F.greatest(c, F.lit(2.0)))
    return [
        (n_ct * n * log(n)).alias("t_sequential"),
        (n_ct * n * log(n) + n_ct * n_s * log(n_s)).alias("t_parallel_worst"),
        (n_ct * n * log(n) / p + n_ct * n_s * log(n_s)).alias("t_parallel_expected"),
        n.cast("double").alias("space"),
    ]
