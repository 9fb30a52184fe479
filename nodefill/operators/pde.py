"""From points to a solved boundary problem: stencils, weights, sparse system, solution, errors.

Weights are per-point dense solves, batched in numpy inside mapInPandas; the system is rows (i, j, w), so a product with a
vector is a join and a sum. The solver's vectors are checkpointed every few steps.
"""

from __future__ import annotations

import math
import sys

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.session import cut
from .grid import AXES, knn, radius_join

cloudpickle.register_pickle_by_value(sys.modules[__name__])


def stencils(points: DataFrame, n: int, dim: int, side: float) -> DataFrame:
    """pid, nbrs: the n nearest points, the point itself first, as (rank, nbr, dist), in order."""
    near = knn(points, points, n, dim, side)
    return near.groupBy("pid").agg(F.sort_array(F.collect_list(F.struct("rank", "nbr", "dist"))).alias("nbrs"))


def widening(points: DataFrame, side: float, choose, enough: int) -> DataFrame:
    """choose(pairs (pid, nbr, x, y, nx, ny, dist)) for each point over growing rings, until it has `enough` rows or the ring covers the cloud."""
    low = points.agg(*[f(c).alias(f"{n}{c}") for c in "xy" for n, f in (("l", F.min), ("h", F.max))]).first()
    if low[0] is None:
        return choose(points.select("pid", F.col("pid").alias("nbr"), "x", "y", F.col("x").alias("nx"), F.col("y").alias("ny"), F.lit(0.0).alias("dist")).limit(0))
    reach, done, live = math.hypot(low["hx"] - low["lx"], low["hy"] - low["ly"]) * 1.001 + 1e-9, None, points
    to = points.select(F.col("pid").alias("nbr"), F.col("x").alias("nx"), F.col("y").alias("ny"))
    while True:
        last = side >= reach
        pairs = radius_join(live, points, min(side, reach), 2).filter("pid <> nbr").withColumn("dist", F.sqrt("d2")).join(to, "nbr").join(live.select("pid", "x", "y"), "pid")
        found = cut(choose(pairs))
        settled = found if last else found.join(found.groupBy("pid").agg(F.count("*").alias("n")).filter(F.col("n") >= enough).select("pid"), "pid", "left_semi")
        done = settled if done is None else done.unionByName(settled)
        if last:
            return done
        live = cut(live.join(settled.select("pid").distinct(), "pid", "left_anti"))
        if not live.limit(1).count():
            return done
        side *= 2


def sector_stencils(points: DataFrame, sectors: int, dim: int, side: float) -> DataFrame:
    """The nearest point in each of equal sectors of the plane, however far: few, well-spread neighbours."""
    turn = F.pmod(F.atan2(F.col("ny") - F.col("y"), F.col("nx") - F.col("x")) + 2 * math.pi, F.lit(2 * math.pi))
    sector = F.least(F.floor(turn / (2 * math.pi / sectors)), F.lit(sectors - 1)).cast("int")
    choose = lambda pairs: pairs.groupBy("pid", sector.alias("sector")).agg(F.min(F.struct("dist", "nbr")).alias("m")).select("pid", "sector", "m.nbr", "m.dist")
    return widening(points, side, choose, sectors)


def visible_stencils(points: DataFrame, walls: DataFrame, k: int, side: float) -> DataFrame:
    """The k nearest among those whose straight line crosses no wall (x1, y1, x2, y2); walls are few and broadcast."""
    turn = lambda ax, ay, bx, by, cx, cy: (F.col(bx) - F.col(ax)) * (F.col(cy) - F.col(ay)) - (F.col(by) - F.col(ay)) * (F.col(cx) - F.col(ax))
    crosses = (turn("x", "y", "nx", "ny", "x1", "y1") * turn("x", "y", "nx", "ny", "x2", "y2") < 0) & (turn("x1", "y1", "x2", "y2", "x", "y") * turn("x1", "y1", "x2", "y2", "nx", "ny") < 0)
    rank = F.row_number().over(Window.partitionBy("pid").orderBy("dist", "nbr"))
    choose = lambda pairs: pairs.join(F.broadcast(walls), crosses, "left_anti").withColumn("rank", rank).filter(F.col("rank") <= k).select("pid", "rank", "nbr", "dist")
    return widening(points, side, choose, k)


def exponents(dim: int, degree: int) -> np.ndarray:
    grid = np.stack(np.meshgrid(*[np.arange(degree + 1)] * dim, indexing="ij"), -1).reshape(-1, dim)
    grid = grid[grid.sum(1) <= degree]
    return grid[np.lexsort((*grid.T[::-1], grid.sum(1)))]


def batch_weights(x: np.ndarray, op: str, normal: np.ndarray | None, order: int = 3, degree: int = 2) -> np.ndarray:
    """x [m, n, d]: stencil points relative to the centre. Weights of the Laplacian, the normal derivative or the value at 0."""
    m, n, d = x.shape
    scale = np.sqrt((x**2).sum(2)).max(1)
    s = x / scale[:, None, None]
    e = exponents(d, degree)
    r = np.sqrt(((s[:, :, None] - s[:, None]) ** 2).sum(3))
    p = np.prod(s[:, :, None, :] ** e[None, None], axis=3)
    a = np.zeros((m, n + len(e), n + len(e)))
    a[:, :n, :n], a[:, :n, n:], a[:, n:, :n] = r**order, p, p.transpose(0, 2, 1)
    b = np.zeros((m, n + len(e)))
    r0 = np.sqrt((s**2).sum(2))
    if op == "lap":
        b[:, :n] = order * (order + d - 2) * r0 ** (order - 2) / scale[:, None] ** 2
        b[:, n:] = np.where((e.sum(1) == 2) & (e.max(1) == 2), 2.0, 0.0)[None] / scale[:, None] ** 2
    elif op == "normal":
        b[:, :n] = -order * r0 ** (order - 2) * np.einsum("mnd,md->mn", s, normal) / scale[:, None]
        for k, powers in enumerate(e):
            if powers.sum() == 1:
                b[:, n + k] = normal[:, powers.argmax()] / scale
    else:
        b[:, :n] = r0**order
        b[:, n:] = (e.sum(1) == 0)[None]
    return np.linalg.solve(a, b[..., None])[:, :n, 0]


def with_places(sten: DataFrame, points: DataFrame, dim: int, centre: DataFrame | None = None) -> DataFrame:
    """One row a stencil with its members' ids and places, for the batch solver."""
    each = sten.select("pid", F.explode("nbrs").alias("n")).select("pid", F.col("n.rank").alias("rank"), F.col("n.nbr").alias("nbr"))
    at = each.join(points.select(F.col("pid").alias("nbr"), *[F.col(k).alias(f"n{k}") for k in AXES[:dim]]), "nbr")
    packed = at.groupBy("pid").agg(F.sort_array(F.collect_list(F.struct("rank", "nbr", *[f"n{k}" for k in AXES[:dim]]))).alias("s"))
    rows = packed.select("pid", F.transform("s", lambda x: x["nbr"]).alias("nbrs"), F.flatten(F.transform("s", lambda x: F.array(*[x[f"n{k}"] for k in AXES[:dim]]))).alias("at"))
    return rows.join((points if centre is None else centre).select("pid", F.array(*AXES[:dim]).alias("centre")), "pid")


def rbf_weights(sten: DataFrame, points: DataFrame, dim: int, op: str = "lap", normals: DataFrame | None = None, centre: DataFrame | None = None, order: int = 3, degree: int = 2) -> DataFrame:
    """(i, j, w): weights by which the values at a stencil's points give the operator at its centre."""
    rows = with_places(sten, points, dim, centre)
    if op == "normal":
        rows = rows.join(normals.select("pid", F.array("nx", "ny", "nz").alias("normal")), "pid")

    def solve(frames):
        for frame in frames:
            if not len(frame):
                continue
            out = []
            size = frame["nbrs"].map(len)
            for n in sorted(size.unique()):
                own = frame[size == n]
                x = np.stack(own["at"].to_list()).reshape(len(own), n, dim) - np.stack(own["centre"].to_list())[:, None, :]
                normal = np.stack(own["normal"].to_list())[:, :dim] if op == "normal" else None
                w = batch_weights(x, op, normal, order, degree)
                out.append(pd.DataFrame({"i": np.repeat(own["pid"].to_numpy(), n), "j": np.concatenate(own["nbrs"].to_list()), "w": w.ravel()}))
            yield pd.concat(out)

    return rows.mapInPandas(solve, "i long, j long, w double")


def spmv(coo: DataFrame, v: DataFrame) -> DataFrame:
    """(i, v) of the product: a join on the column and a sum over the row."""
    return coo.join(v.select(F.col("i").alias("j"), "v"), "j").groupBy("i").agg(F.sum(F.col("w") * F.col("v")).alias("v"))


def column_abs_sums(coo: DataFrame) -> DataFrame:
    return coo.groupBy("j").agg(F.sum(F.abs("w")).alias("abs_sum"))


def assemble(nodes: DataFrame, sten: DataFrame, dim: int, kappa: float = 0.0, flux: DataFrame | None = None, ghosts: DataFrame | None = None, alpha: float = 1.0) -> DataFrame:
    """(i, j, w). Interior rows: Laplacian + kappa; Dirichlet rows: 1; with `flux` (pid, normals) Robin rows u + alpha du/dn, and for
    each ghost (pid, of) the Laplacian of the Robin node it belongs to."""
    interior = sten.join(nodes.filter("kind = 'interior'").select("pid"), "pid", "left_semi")
    lap = rbf_weights(interior, nodes, dim)
    out = lap if not kappa else lap.withColumn("w", F.col("w") + F.when(F.col("i") == F.col("j"), kappa).otherwise(0.0))
    out = out.unionByName(nodes.filter("kind = 'dirichlet'").select(F.col("pid").alias("i"), F.col("pid").alias("j"), F.lit(1.0).alias("w")))
    if flux is not None:
        robin = sten.join(flux.select("pid"), "pid", "left_semi")
        d = rbf_weights(robin, nodes, dim, "normal", flux).withColumn("w", F.col("w") * alpha + F.when(F.col("i") == F.col("j"), 1.0).otherwise(0.0))
        out = out.unionByName(d)
    if ghosts is not None:
        own = rbf_weights(sten.join(ghosts.select(F.col("of").alias("pid")), "pid", "left_semi"), nodes, dim)
        out = out.unionByName(own.join(ghosts.select(F.col("of").alias("i"), F.col("pid").alias("g")), "i").select(F.col("g").alias("i"), "j", "w"))
    return out


def dense(coo: DataFrame, rhs: DataFrame, limit: int = 5000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, matrix and right side on the driver; refuses more than `limit` unknowns."""
    b = rhs.orderBy("i").limit(limit + 1).toPandas()
    if len(b) > limit:
        raise ValueError("too many unknowns for a dense solve")
    ids = b["i"].to_numpy()
    rows = coo.groupBy("i", "j").agg(F.sum("w").alias("w")).limit(limit * 100 + 1).toPandas()
    if len(rows) > limit * 100:
        raise ValueError("too many entries for a dense solve")
    a = np.zeros((len(ids), len(ids)))
    np.add.at(a, (np.searchsorted(ids, rows["i"]), np.searchsorted(ids, rows["j"])), rows["w"])
    return ids, a, b["v"].to_numpy()


def dot(a: DataFrame, b: DataFrame) -> float:
    return a.join(b.select("i", F.col("v").alias("w")), "i").agg(F.sum(F.col("v") * F.col("w"))).first()[0] or 0.0


def combine(*terms) -> DataFrame:
    """Sum of factor * vector."""
    out = None
    for factor, v in terms:
        part = v.select("i", (F.lit(float(factor)) * F.col("v")).alias("v"))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("i").agg(F.sum("v").alias("v"))


def solve(coo: DataFrame, rhs: DataFrame, method: str = "dense", tolerance: float = 1e-8, steps: int = 200) -> DataFrame:
    """(i, v). dense: numpy on the driver, small systems only; bicgstab: joins and sums, scaled by the diagonal, for any size."""
    if method == "dense":
        ids, a, b = dense(coo, rhs)
        return coo.sparkSession.createDataFrame(pd.DataFrame({"i": ids, "v": np.linalg.solve(a, b)}))
    diagonal = coo.filter("i = j").groupBy("i").agg(F.sum("w").alias("d"))
    a = cut(coo.join(diagonal, "i").select("i", "j", (F.col("w") / F.col("d")).alias("w")))
    b = cut(rhs.join(diagonal, "i").select("i", (F.col("v") / F.col("d")).alias("v")))
    x, r = b.select("i", F.lit(0.0).alias("v")), b
    shadow, p, rho = r, r, dot(r, r)
    size = math.sqrt(rho) or 1.0
    for _ in range(steps):
        ap = cut(spmv(a, p))
        alpha = rho / dot(shadow, ap)
        s = cut(combine((1, r), (-alpha, ap)))
        if math.sqrt(dot(s, s)) < tolerance * size:
            return combine((1, x), (alpha, p))
        at = cut(spmv(a, s))
        omega = dot(at, s) / dot(at, at)
        x = cut(combine((1, x), (alpha, p), (omega, s)))
        r = cut(combine((1, s), (-omega, at)))
        if math.sqrt(dot(r, r)) < tolerance * size:
            return x
        rho, old = dot(shadow, r), rho
        beta = rho / old * alpha / omega
        p = cut(combine((1, r), (beta, p), (-beta * omega, ap)))
    raise RuntimeError(f"bicgstab not converged after {steps} steps")


def condest(coo: DataFrame, rhs: DataFrame) -> float:
    """1-norm condition number: by power steps on the inverse's sign vectors (Hager's way); dense solves, small systems."""
    _, a, _ = dense(coo, rhs)
    n, x, best = len(a), np.full(len(a), 1 / len(a)), 0.0
    for _ in range(6):
        y = np.linalg.solve(a, x)
        best = max(best, float(np.abs(y).sum()))
        z = np.linalg.solve(a.T, np.where(y >= 0, 1.0, -1.0))
        k = int(np.abs(z).argmax())
        if np.abs(z[k]) <= z @ x:
            break
        x = np.zeros(n)
        x[k] = 1.0
    return best * float(np.abs(a).sum(0).max())


def errors(at: DataFrame) -> DataFrame:
    """at (u_h, u): relative mean and largest errors."""
    gap = F.abs(F.col("u_h") - F.col("u"))
    return at.agg((F.sum(gap) / F.sum(F.abs("u"))).alias("e1"), (F.max(gap) / F.max(F.abs("u"))).alias("e_inf"), F.count("*").alias("n"))


def evaluate(values: DataFrame, points: DataFrame, at: DataFrame, dim: int, side: float, n: int = 15) -> DataFrame:
    """(pid, u_h) at other places, through each place's local interpolant."""
    near = knn(points, at, n, dim, side).groupBy("pid").agg(F.sort_array(F.collect_list(F.struct("rank", "nbr", "dist"))).alias("nbrs"))
    w = rbf_weights(near, points, dim, "eval", centre=at)
    return w.join(values.select(F.col("i").alias("j"), "v"), "j").groupBy(F.col("i").alias("pid")).agg(F.sum(F.col("w") * F.col("v")).alias("u_h"))


def gradient_recovery(points: DataFrame, k: int, dim: int, side: float, value: str = "u") -> DataFrame:
    """pid, indicator: the spread of the slopes towards the k nearest, as an error indicator."""
    near = knn(points, points, k, dim, side, same=True).join(points.select(F.col("pid").alias("nbr"), F.col(value).alias("nu")), "nbr").join(points.select("pid", F.col(value).alias("u0")), "pid")
    slope = (F.col("nu") - F.col("u0")) / F.col("dist")
    return near.filter("dist > 0").groupBy("pid").agg((F.max(slope) - F.min(slope)).alias("indicator"))


def boundary_polygon(corners: DataFrame, h: float) -> DataFrame:
    """Points along edges (edge, x1, y1, x2, y2) about h apart, with outward normals of a ring that runs against the clock. An edge without length is one point without a normal."""
    length = F.sqrt((F.col("x2") - F.col("x1")) * (F.col("x2") - F.col("x1")) + (F.col("y2") - F.col("y1")) * (F.col("y2") - F.col("y1")))
    e = corners.withColumn("len", length).withColumn("n", F.greatest(F.lit(1), F.ceil(F.col("len") / h)).cast("int"))
    t = e.withColumn("k", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    s = F.col("k") / F.col("n")
    other = [c for c in corners.columns if c not in ("x1", "y1", "x2", "y2")]
    return t.select(*other, "k", (F.col("x1") + (F.col("x2") - F.col("x1")) * s).alias("x"), (F.col("y1") + (F.col("y2") - F.col("y1")) * s).alias("y"), F.try_divide(F.col("y2") - F.col("y1"), "len").alias("nx"), F.try_divide(F.col("x1") - F.col("x2"), "len").alias("ny"))


def boundary_curve(samples: DataFrame, spacing_sql: str) -> DataFrame:
    """Points of a finely sampled closed curve (k, x, y): where the summed length over h passes a whole number. Lengths are summed in whole billionths, the same in any order."""
    w = Window.orderBy("k")
    step = F.sqrt(F.pow(F.col("x") - F.lag("x").over(w), 2) + F.pow(F.col("y") - F.lag("y").over(w), 2))
    part = samples.withColumn("part", F.round(F.coalesce(step, F.lit(0.0)) / F.expr(spacing_sql) * 1e9).cast("long"))
    total = part.withColumn("t", F.sum("part").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return total.withColumn("mark", F.expr("t div 1000000000")).withColumn("first", F.coalesce(F.col("mark") > F.lag("mark").over(w), F.lit(True))).filter("first").select("k", "x", "y", "mark")
