"""The experiments, as functions of (spark, sizes): what is filled, counted, compared and solved."""

from __future__ import annotations

import math
import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..operators import front, measures, pde
from ..operators import spark_fill as fills
from ..sources.tables import view
from .session import cut

PACKING = {2: 0.78, 3: 0.85}  # points placed times h^dim over volume, measured on fills of constant h


def first_seed(spark: SparkSession, region) -> DataFrame:
    p = [*map(float, region.inside), 0.0][:3]
    return spark.createDataFrame([(1, *p)], "seed_id long, x double, y double, z double")


def integral(region, spacing, n: int = 200_000) -> float:
    """Integral of h^-dim over a region, by a fixed low-discrepancy sum."""
    k = np.arange(1, n + 1)[:, None]
    root = {2: 1.32471795724474602596, 3: 1.22074408460575947536}[region.dim]
    u = np.mod(0.5 + k * root ** -np.arange(1.0, region.dim + 1)[None], 1.0)
    low, high = np.array(region.low, float), np.array(region.high, float)
    p = low + u * (high - low)
    p = p[region.test(p)]
    return float((spacing.at(p) ** -region.dim).sum() / n * np.prod(high - low))


def spacing_of_size(name: str, n_target: int):
    """The region's own spacing, scaled to about n_target points."""
    region, make = G.REGIONS[name](), G.SPACINGS[name]
    unit = make(1.0)
    h = (PACKING[region.dim] * integral(region, unit) / n_target) ** (1 / region.dim)
    return region, make(h)


def spacing_for_target(spark, region, shape, targets, step: float, packing: float) -> DataFrame:
    """n, h: the scale of a spacing that gives about n points, by a sum over a lattice."""
    total = measures.probe_lattice(spark, region, step).agg(F.sum(F.lit(step**region.dim) / F.pow(F.expr(shape.sql), region.dim)).alias("s"))
    return total.select(F.explode(F.array(*[F.lit(n).cast("long") for n in targets])).alias("n"), "s").select("n", F.round(F.pow(packing * F.col("s") / F.col("n"), 1 / region.dim), 5).alias("h"))


def supplier_seed(spark, d: str, region) -> DataFrame:
    """One seed inside the region: the least supplier whose place, spread over the region's box, lies in it; else the region's own."""
    box = [(F.lit(float(lo)) + (F.col(c) + 9.0) / 18.0 * F.lit(float(hi - lo))).alias(c) if i < region.dim else F.lit(0.0).alias(c) for i, (c, lo, hi) in enumerate(zip("xyz", [*region.low, 0][:3], [*region.high, 0][:3], strict=True))]
    at = view(spark, d, "pv_supp2").withColumn("z", (F.col("x") + F.col("y")) / 2).select("seed_id", *box).filter(region.contains()).orderBy("seed_id").limit(1)
    own = first_seed(spark, region).withColumn("seed_id", F.lit(-1).cast("long"))
    return at.unionByName(own).orderBy(F.desc("seed_id")).limit(1)


def fill_invariants(spark, d: str, region, n_target: int, n_seeds: int = 32, parts: int = 16) -> DataFrame:
    """A fill side by side from bootstrapped seeds: what must be zero, and whether the count is near the one asked for."""
    region, s = spacing_of_size(region.name, n_target)
    seeds, _ = fills.bootstrap_iterative(supplier_seed(spark, d, region), region, s, n_target, n_seeds)
    p = cut(fills.fill_parallel(seeds, region, s, parts, "colour"))
    return measures.invariants(p, region, s).join(F.broadcast(p.agg((F.count("*").between(0.7 * n_target, 1.4 * n_target)).alias("on_target"))))


def bootstrap(spark, d: str, n_target: int, n_seeds: int, reuse: bool = False):
    region, s = spacing_of_size("clover2d", n_target)
    return fills.bootstrap_iterative(first_seed(spark, region), region, s, n_target, n_seeds, reuse=reuse)


def cells_invariants(spark, d: str, border: str, n_target: int = 700, n_seeds: int = 8) -> DataFrame:
    region, s = spacing_of_size("clover2d", n_target)
    seeds, _ = fills.bootstrap_iterative(first_seed(spark, region), region, s, n_target, n_seeds)
    p = cut(fills.fill_parallel(seeds, region, s, 8, border))
    return measures.invariants(p, region, s)


def components(spark) -> DataFrame:
    """Two discs apart: a seed in each fills both, a seed in one leaves the other empty."""
    both = G.ellipsoid((-2, 0), (1, 1)) | G.ellipsoid((2, 0), (1, 1))
    two = spark.createDataFrame([(1, -2.0, 0.0, 0.0), (2, 2.0, 0.0, 0.0)], "seed_id long, x double, y double, z double")
    a = fills.fill_sequential(two, both, G.constant(0.3))
    b = fills.fill_sequential(two.filter("seed_id = 1"), both, G.constant(0.3))
    left = a.agg((F.count_if(F.col("x") < 0) > 20).alias("left_filled"), (F.count_if(F.col("x") > 0) > 20).alias("right_filled"))
    return left.join(F.broadcast(b.agg((F.count_if(F.col("x") > 0) == 0).alias("one_seed_leaves_other_empty"))))


def quasi_uniformity(spark, levels: int, h: float = 0.2) -> DataFrame:
    """level, ratio, for h halved level by level."""
    region, out = G.clover2d(), None
    for k in range(levels):
        s = G.clover_spacing(h / 2**k, 5 * h / 2**k)
        p = cut(fills.fill_sequential(first_seed(spark, region), region, s))
        one = measures.node_set_ratio(p, measures.probe_lattice(spark, region, h / 2**k / 1.5), 2, s.most).withColumn("level", F.lit(k))
        out = one if out is None else out.unionByName(one)
    return out


def regularity(spark, h: float, k: int = 5) -> DataFrame:
    """Sequential and cell-parallel fills compared by mean, deviation and spread of normalised distances."""
    region, s = G.clover2d(), G.clover_spacing(h)
    one = cut(fills.fill_sequential(first_seed(spark, region), region, s))
    seeds, _ = fills.bootstrap_iterative(first_seed(spark, region), region, s, one.count(), 8)
    many = cut(fills.fill_parallel(seeds, region, s, 8, "flag"))
    a, b = (measures.local_regularity(measures.normalized_distances(p, k, 2, s.most)).first() for p in (one, many))
    near = [abs(a[c] - b[c]) < 0.1 * abs(a[c]) + 0.02 for c in ("mean_dist", "std_dist", "mean_spread")]
    return spark.createDataFrame([(*near, 1.0 < a["mean_dist"] < 1.4)], "mean_near boolean, std_near boolean, spread_near boolean, as_reported boolean")


def weight_moments(spark) -> DataFrame:
    """Weights of the Laplacian, the normal derivative and the value reproduce polynomials of degree two."""
    region = G.box((0, 0), (1, 1))
    p = cut(fills.fill_sequential(first_seed(spark, region), region, G.constant(0.12)))
    s = pde.stencils(p, 15, 2, 0.36)
    polys = [(F.lit(1.0), 0.0, 0.0), (F.col("x"), 0.0, 1.0), (F.col("y"), 0.0, 0.0), (F.col("x") * F.col("x"), 2.0, None), (F.col("x") * F.col("y"), 0.0, None), (F.col("y") * F.col("y"), 2.0, None)]
    lap = pde.rbf_weights(s, p, 2)
    normal = pde.rbf_weights(s, p, 2, "normal", p.select("pid", F.lit(1.0).alias("nx"), F.lit(0.0).alias("ny"), F.lit(0.0).alias("nz")))
    ok = F.lit(True)
    cols = [F.abs(F.sum(F.col("w") * f) - want).alias(f"l{i}") for i, (f, want, _) in enumerate(polys)]
    at = p.select(F.col("pid").alias("j"), "x", "y")
    a = lap.join(at, "j").groupBy("i").agg(*cols).agg(*[F.max(f"l{i}").alias(f"l{i}") for i in range(6)])
    b = normal.join(at, "j").groupBy("i").agg(*[F.abs(F.sum(F.col("w") * f) - want).alias(f"n{i}") for i, (f, _, want) in enumerate(polys) if want is not None]).agg(*[F.max(f"n{i}").alias(f"n{i}") for i in range(3)])
    for c in [f"l{i}" for i in range(6)] + [f"n{i}" for i in range(3)]:
        ok = ok & (F.col(c) < 1e-6)
    return a.join(F.broadcast(b)).select(ok.alias("exact_to_degree_two"))


def poisson_system(spark, n: int, n_st: int = 15):
    """Nodes, matrix, right side of the model problem on the square [0, 3]^2 with the solution sin(pi x / 3) sin(pi y / 3)."""
    region = G.box((0, 0), (3, 3))
    h = math.sqrt(PACKING[2] * 9 / n)
    m = max(4, round(3 / h))
    t = 3 * np.arange(m) / m
    ring = np.concatenate([np.stack([t, 0 * t], 1), np.stack([3 + 0 * t, t], 1), np.stack([3 - t, 3 + 0 * t], 1), np.stack([0 * t, 3 - t], 1)])
    inner = G.box((0.6 * h, 0.6 * h), (3 - 0.6 * h, 3 - 0.6 * h))

    def one(frame):
        out = front.fill(region, G.constant(h), ring, np.arange(len(ring)), allowed=inner.test)
        pos = np.r_[out["pos"]]
        return pd.DataFrame({"pid": np.arange(len(pos)), "x": pos[:, 0], "y": pos[:, 1], "z": 0.0, "kind": np.where(out["gen"] > 0, "interior", "dirichlet")})

    nodes = cut(spark.range(1).groupBy("id").applyInPandas(one, "pid long, x double, y double, z double, kind string"))
    s = pde.stencils(nodes, n_st, 2, 3 * h)
    u = F.sin(F.col("x") * math.pi / 3) * F.sin(F.col("y") * math.pi / 3)
    matrix = cut(pde.assemble(nodes, s, 2))
    rhs = nodes.select(F.col("pid").alias("i"), F.when(F.col("kind") == "interior", -2 * math.pi**2 / 9 * u).otherwise(u).alias("v"))
    return nodes, matrix, rhs, u, h


def poisson(spark, sizes=(500, 1000, 2000, 4000), method: str = "dense") -> DataFrame:
    """Errors fall and the condition number grows with n."""
    rows = poisson_table(spark, sizes, method)
    a, b = rows[0], rows[-1]
    return spark.createDataFrame([(b["e1"] < a["e1"] and b["e_inf"] < a["e_inf"], b["e1"] < 0.02, b["kappa"] > a["kappa"])], "errors_fall boolean, small boolean, condition_grows boolean")


def poisson_table(spark, sizes, method: str = "dense") -> list[dict]:
    out = []
    for n in sizes:
        nodes, matrix, rhs, u, h = poisson_system(spark, n)
        x = cut(pde.solve(matrix, rhs, method))
        grid = measures.probe_lattice(spark, G.box((0, 0), (3, 3)), h / 2)
        at = pde.evaluate(x, nodes, grid, 2, 3 * h).join(grid.select("pid", u.alias("u")), "pid")
        e = pde.errors(at).first()
        out.append({"n": nodes.count(), "e1": e["e1"], "e_inf": e["e_inf"], "kappa": pde.condest(matrix, rhs)})
    return out


def heatsink(spark, h: float = 0.25, u_b: float = 100.0, u_a: float = 20.0, alpha: float = 1.0) -> DataFrame:
    """Laplace's equation on a plate that is heated below and loses heat through the other sides, with ghost nodes."""
    m, k = round(3 / h), round(2 / h)
    tx, ty = 3 * np.arange(m + 1) / m, 2 * np.arange(1, k) / k
    low = np.stack([tx, 0 * tx], 1)
    sides = np.concatenate([np.stack([0 * ty, ty], 1), np.stack([3 + 0 * ty, ty], 1), np.stack([tx[1:-1], 2 + 0 * tx[1:-1]], 1)])
    normal = np.concatenate([np.tile([-1.0, 0.0], (len(ty), 1)), np.tile([1.0, 0.0], (len(ty), 1)), np.tile([0.0, 1.0], (m - 1, 1))])
    edge = np.concatenate([low, sides])
    out = front.fill(G.box((0, 0), (3, 2)), G.constant(h), edge, np.arange(len(edge)), allowed=G.box((0.6 * h, 0.6 * h), (3 - 0.6 * h, 2 - 0.6 * h)).test)
    pos, n = out["pos"], len(out["pos"])
    ghost = sides + h * normal
    kind = ["dirichlet"] * len(low) + ["robin"] * len(sides) + ["interior"] * (n - len(edge)) + ["ghost"] * len(ghost)
    every = np.concatenate([pos, ghost])
    nodes = cut(spark.createDataFrame(pd.DataFrame({"pid": np.arange(len(every)), "x": every[:, 0], "y": every[:, 1], "z": 0.0, "kind": kind})))
    flux = spark.createDataFrame(pd.DataFrame({"pid": np.arange(len(low), len(edge)), "nx": normal[:, 0], "ny": normal[:, 1], "nz": 0.0}))
    ghosts = spark.createDataFrame(pd.DataFrame({"pid": np.arange(n, n + len(ghost)), "of": np.arange(len(low), len(edge))}))
    s = pde.stencils(nodes, 15, 2, 3 * h)
    matrix = cut(pde.assemble(nodes, s, 2, flux=flux, ghosts=ghosts, alpha=alpha))
    rhs = nodes.select(F.col("pid").alias("i"), F.when(F.col("kind") == "dirichlet", u_b).when(F.col("kind") == "robin", u_a).otherwise(0.0).alias("v"))
    x = cut(pde.solve(matrix, rhs))
    residual = pde.combine((1, pde.spmv(matrix, x)), (-1, rhs)).agg((F.max(F.abs("v")) < 1e-6).alias("residual_small"))
    inside = x.join(nodes.filter("kind <> 'ghost'").select(F.col("pid").alias("i")), "i")
    return inside.agg((F.min("v").between(u_a - 0.5, u_b) & (F.max("v") <= u_b + 0.5)).alias("within_bounds")).join(F.broadcast(residual))


def timed(method: str, size: int, workers: int, run) -> tuple:
    t = time.perf_counter()
    n = run()
    return method, size, workers, time.perf_counter() - t, n


def scaling(spark, name: str, sizes, parts: int) -> DataFrame:
    """Runs (method, size, workers, seconds, placed) of the sequential and the cell-parallel fill; the latter with bootstrap, borders and refill."""
    rows = []
    for n in sizes:
        region, s = spacing_of_size(name, n)
        seed = first_seed(spark, region)
        rows.append(timed("sequential", n, 1, lambda: fills.fill_sequential(seed, region, s).count()))
        rows.append(timed("cells", n, parts, lambda: fills.fill_from_one_seed(seed, region, s, n, parts).count()))
    return spark.createDataFrame(rows, "method string, size long, workers long, seconds double, placed long")


def bootstrap_sweep(spark, multiples, n_target: int = 4000, base: int = 8) -> DataFrame:
    """requested, obtained, placed, largest cell over the mean, for growing numbers of seeds."""
    region, s = spacing_of_size("clover2d", n_target)
    rows = []
    for m in multiples:
        seeds, _ = fills.bootstrap_iterative(first_seed(spark, region), region, s, n_target, base * m)
        seeds = cut(seeds)
        p = cut(fills.fill_cells(seeds, region, s, 8, "none"))
        skew = measures.cell_skew(p).first()
        rows.append((base * m, seeds.count(), p.count(), float(skew["skew"])))
    return spark.createDataFrame(rows, "requested long, obtained long, placed long, skew double")


def direction_sweep(spark, counts=(6, 10, 12, 15, 20, 30), n_target: int = 1000) -> DataFrame:
    """n_c, placed, mean and deviation of normalised distances: more directions help little beyond ten."""
    region, s = spacing_of_size("clover2d", n_target)
    out = None
    for n_c in counts:
        p = cut(fills.fill_sequential(first_seed(spark, region), region, s, n_c))
        one = measures.local_regularity(measures.normalized_distances(p, 3, 2, s.most)).withColumn("n_c", F.lit(n_c))
        out = one if out is None else out.unionByName(one)
    return out


def sequential_trace(spark, iteration: int = 72, n_target: int = 400, n_c: int = 12) -> DataFrame:
    """Points placed from the iteration-th expanded point, with their direction."""
    region, s = spacing_of_size("clover2d", n_target)
    p = fills.fill_sequential(first_seed(spark, region), region, s, n_c)
    order = p.withColumn("turn", F.row_number().over(Window.orderBy("gen", "pid")))
    parent = order.filter(F.col("turn") == iteration).select(F.col("pid").alias("parent"))
    return p.join(F.broadcast(parent), "parent").select("pid", "parent", "cand", "x", "y")


def step_times(spark, n: int = 500) -> DataFrame:
    """run, step, seconds of the steps from points to solution."""
    rows, t = [], time.perf_counter()

    def done(step):
        nonlocal t
        now = time.perf_counter()
        rows.append((f"n={n}", step, now - t))
        t = now

    nodes, matrix, rhs, _, h = poisson_system(spark, n)
    done("placement, stencils, weights, assembly")
    cut(pde.stencils(nodes, 15, 2, 3 * h))
    done("stencils")
    pde.solve(matrix, rhs).count()
    done("solve")
    return spark.createDataFrame(rows, "run string, step string, seconds double")


def bootstrap_steps(spark, multiples, n: int = 800, n_parts: int = 4) -> DataFrame:
    """run (the number of seeds asked for), step, seconds of the steps of a parallel fill."""
    region, s = spacing_of_size("clover2d", n)
    seed, rows = first_seed(spark, region), []
    for k in multiples:
        t = time.perf_counter()
        seeds = cut(fills.bootstrap_iterative(seed, region, s, n, 8 * k)[0])
        booted = time.perf_counter()
        fills.fill_parallel(seeds, region, s, n_parts, "colour").count()
        rows += [(str(8 * k), "bootstrap", booted - t), (str(8 * k), "fill", time.perf_counter() - booted)]
    return spark.createDataFrame(rows, "run string, step string, seconds double")


def adapt(points: DataFrame, indicator: DataFrame, factor: float = 0.5, share: float = 0.2) -> DataFrame:
    """New spacing at each point: smaller by `factor` where the indicator is among the largest `share`."""
    limit = indicator.agg(F.percentile_approx("indicator", 1 - share, 10000).alias("limit"))
    return points.join(indicator, "pid", "left").join(F.broadcast(limit)).withColumn("h", F.when(F.col("indicator") >= F.col("limit"), F.col("h") * factor).otherwise(F.col("h"))).drop("indicator", "limit")
