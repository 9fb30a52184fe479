"""Fills as DataFrame programs: rounds of joins, bootstrapped seeds, levels, and cells filled side by side.

Points are rows (pid, seed_id, parent, cand, gen, level, x, y, z, h, r, ord). `ord` is the fifo order within a generation as
an array: the seed's number, then the direction taken at each step; arrays compare in exactly that order.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as G
from ..plans.session import cut
from . import front
from .grid import neighbour_cells

POINT = "pid long, seed_id long, parent long, cand int, gen int, level int, x double, y double, z double, h double, r double"


PLACED = POINT + ", cell_id long, is_border boolean, is_open boolean"  # is_open: a candidate in the region was refused only for another cell's sake


def square(a: str, b: str, dim: int = 3) -> Column:
    return sum((F.col(f"{a}.{c}") - F.col(f"{b}.{c}")) * (F.col(f"{a}.{c}") - F.col(f"{b}.{c}")) for c in "xyz"[:dim])


def directions(spark, dim: int, n_c: int, rotate: bool = True) -> DataFrame:
    """(bank, cand, ux, uy, uz): 16 banks of unit vectors; its size depends on dim and n_c only."""
    return spark.createDataFrame(G.direction_rows(dim, n_c, rotate), "bank int, cand int, ux double, uy double, uz double")


def directions_for(sizes: DataFrame, dim: int) -> DataFrame:
    """The unit vectors of every size that rows (n_c, ...) ask for, unrotated: its columns, cand, ux, uy, uz. Executors make them, a batch of sizes at a time."""
    names = list(sizes.columns)

    def each(frames):
        for f in frames:
            for row in f.itertuples(index=False):
                u = G.sphere(dim, int(row.n_c))
                out = pd.DataFrame({c: [getattr(row, c)] * len(u) for c in names}).assign(cand=np.arange(len(u), dtype="int32"))
                yield out.assign(**{"u" + k: u[:, i] if i < dim else 0.0 for i, k in enumerate("xyz")})

    kinds = ", ".join(f"`{c}` {t}" for c, t in sizes.dtypes)
    return sizes.mapInPandas(each, f"{kinds}, cand int, ux double, uy double, uz double")


def direction_counts(sizes: DataFrame, dims) -> DataFrame:
    """n_c, dim, n: how many directions a size has in each dimension, for rows with n_c."""

    def each(frames):
        for f in frames:
            yield pd.DataFrame([(c, k, len(G.sphere(k, c))) for c in f["n_c"].tolist() for k in dims], columns=["n_c", "dim", "n"])

    return sizes.select("n_c").mapInPandas(each, "n_c int, dim long, n long")


def expand(points: DataFrame, dirs: DataFrame, dim: int) -> DataFrame:
    """Candidates on the sphere of radius h around each point, under the point's own rotation."""
    p = points.withColumn("bank", F.pmod(F.xxhash64("pid"), F.lit(16)).cast("int"))  # the direction a point came by gives way to those it sends
    c = p.drop("cand").join(F.broadcast(dirs), "bank")
    at = [(F.col(k) + F.col("h") * F.col("u" + k)).alias(k) if i < dim else F.lit(0.0).alias(k) for i, k in enumerate("xyz")]
    child = F.xxhash64("pid", F.col("cand").cast("long"))
    return c.select(child.alias("pid"), "seed_id", F.col("pid").alias("parent"), F.col("cand"), (F.col("gen") + 1).alias("gen"), "level", *at, F.col("h").alias("r"), F.concat("ord", F.array(F.col("cand").cast("long"))).alias("ord"), F.col("x").alias("px"), F.col("y").alias("py"), F.col("z").alias("pz"))


def prune_close(cands: DataFrame, points: DataFrame, side: float, dim: int, exempt_parent: bool = False) -> DataFrame:
    """Candidates without a point within their radius r <= side. Points are copied to the cells around them, candidates stay in one.

    The copies are never broadcast: a file's size says little about them.
    """
    blockers = neighbour_cells(points.select(F.col("pid").alias("b_pid"), F.struct("x", "y", "z").alias("b"), "x", "y", "z"), side, dim).drop("x", "y", "z").hint("merge")
    here = cands.withColumn("cell", F.array(*[F.floor(F.col(k) / side) for k in "xyz"[:dim]]))
    d2 = sum((F.col(k) - F.col(f"b.{k}")) * (F.col(k) - F.col(f"b.{k}")) for k in "xyz"[:dim])
    on = (here["cell"] == blockers["cell"]) & (d2 < F.col("r") * F.col("r") * G.SLACK)
    if exempt_parent:
        on = on & (F.col("b_pid") != F.col("parent"))
    return here.join(blockers, on, "left_anti").drop("cell")


def independent(cands: DataFrame, side: float, dim: int) -> DataFrame:
    """The first maximal independent set in `ord`: an accepted earlier candidate blocks a later one within the later one's r.

    """
    slim = cands.select("pid", "ord", "x", "y", "z", "r")
    a = neighbour_cells(slim.select(F.col("pid").alias("a_pid"), F.col("ord").alias("a_ord"), F.struct("x", "y", "z").alias("a"), "x", "y", "z"), side, dim).drop("x", "y", "z")
    b = slim.select(F.col("pid").alias("b_pid"), F.col("ord").alias("b_ord"), F.struct("x", "y", "z").alias("b"), "r", F.array(*[F.floor(F.col(k) / side) for k in "xyz"[:dim]]).alias("cell"))
    edges = a.join(b, "cell").filter((F.col("a_ord") < F.col("b_ord")) & (square("a", "b", dim) < F.col("r") * F.col("r") * G.SLACK)).select("a_pid", "b_pid")
    return cands.join(settle(cands.select("pid"), edges), "pid", "left_semi")


def seed_points(seeds: DataFrame, region, spacing, level: int = 0) -> DataFrame:
    """Seeds as generation 0, those outside the region left out: seed_id, x, y, z."""
    s = seeds.filter(region.contains()).withColumn("h", spacing.column())
    first = F.row_number().over(Window.orderBy("seed_id"))
    return s.select(F.col("seed_id").alias("pid"), "seed_id", F.lit(-1).cast("long").alias("parent"), F.lit(-1).alias("cand"), F.lit(0).alias("gen"), F.lit(level).alias("level"), "x", "y", "z", "h", F.col("h").alias("r"), F.array(first.cast("long")).alias("ord"))


def fill_rounds(seeds: DataFrame, region, spacing, n_c: int = 12, exclusion: str = "parent", rotate: bool = True, max_rounds: int = 10_000, level: int = 0) -> DataFrame:
    """The sequential fill, a generation a round: expand, drop those outside, drop those close to older points, settle the rest, append.

    Bit-equal to the kernel in `front`: same directions, same order, same comparisons. Every round is cut from its lineage.
    """
    dirs = directions(seeds.sparkSession, region.dim, n_c, rotate)
    side = spacing.most * 1.0001
    points = cut(seed_points(seeds, region, spacing, level))
    edge = points
    for _ in range(max_rounds):
        cands = expand(edge, dirs, region.dim).filter(region.contains()).withColumn("h", spacing.column())
        if exclusion != "parent":
            cands = cands.withColumn("r", F.col("h"))
        cands = cut(prune_close(cands, points, side, region.dim, exclusion == "candidate").select(*points.columns))
        edge = cut(independent(cands, side, region.dim))
        if not edge.limit(1).count():
            return points.drop("ord")
        points = cut(points.unionByName(edge))
    raise RuntimeError(f"fill not finished after {max_rounds} rounds")


def columns_of(out: dict, level: int = 0) -> pd.DataFrame:
    pos = np.zeros((len(out["pid"]), 3))
    pos[:, : out["pos"].shape[1]] = out["pos"]
    return pd.DataFrame({"pid": out["pid"], "seed_id": out["seed_id"], "parent": out["parent"], "cand": out["cand"].astype("int32"), "gen": out["gen"].astype("int32"), "level": np.full(len(pos), level, "int32"), "x": pos[:, 0], "y": pos[:, 1], "z": pos[:, 2], "h": out["h"], "r": out["r"]})


def kernel_fill(frame: pd.DataFrame, region, spacing, level: int = 0, **options) -> pd.DataFrame:
    f = frame.sort_values("seed_id")
    p = f[list("xyz"[: region.dim])].to_numpy(float)
    ok = region.test(p) if len(p) else np.zeros(0, bool)
    return columns_of(front.fill(region, spacing, p[ok], f["seed_id"].to_numpy()[ok], **options), level)


def fill_sequential(seeds: DataFrame, region, spacing, n_c: int = 12, exclusion: str = "parent", rotate: bool = True, by: str | None = None) -> DataFrame:
    """The baseline: the whole fill in one task. by: a fill of its own, in a task, for the seeds of each value of that column."""
    one = seeds.select("seed_id", "x", "y", "z", (F.col(by) if by else F.lit(0)).alias("g"))
    return one.groupBy("g").applyInPandas(lambda f: kernel_fill(f, region, spacing, n_c=n_c, exclusion=exclusion, rotate=rotate), POINT)


def amplification(n_target: float, n_seeds: float, dim: int) -> float:
    return (n_target / n_seeds) ** (1 / dim)


def bootstrap_once(seeds: DataFrame, region, spacing, n_target: int, n_seeds: int, n_c: int = 12, by: str | None = None) -> DataFrame:
    """Seeds from one fill at inflated spacing, or one for each value of column `by`; their number may miss n_seeds. origin: the first seed that they grew from."""
    out = fill_sequential(seeds, region, spacing.scaled(amplification(n_target, n_seeds, region.dim)), n_c, by=by)
    return out.select(F.col("pid").alias("seed_id"), "x", "y", "z", F.col("seed_id").alias("origin"))


BOOTED = "seed_id long, x double, y double, z double, step long, factor double, n long"


def bootstrap_passes(region, spacing, first: float, n_seeds: int, n_c: int, shrink: float, reuse: bool):
    """From a frame of first seeds, the rows BOOTED: inflated fills until there are n_seeds points, and the log (step, factor, n)."""

    def passes(frame: pd.DataFrame) -> pd.DataFrame:
        factor, log, have = first, [], frame[["seed_id", "x", "y", "z"]]
        while True:
            out = kernel_fill(have, region, spacing.scaled(factor), n_c=n_c)[["pid", "x", "y", "z"]].rename(columns={"pid": "seed_id"})
            log.append((len(log), factor, len(out)))
            if len(out) >= n_seeds or not len(have):
                break
            factor *= shrink
            have = out if reuse and len(out) else have
        return pd.concat([out, pd.DataFrame(log, columns=["step", "factor", "n"])])

    return passes


def bootstrap_logs(seeds: DataFrame, region, spacing, n_target: int, n_seeds: int, by: str, n_c: int = 12, start: float = 10.0, shrink: float = 0.5) -> DataFrame:
    """seed_id, step, factor, n: the log of the iterative bootstrap from the seeds of each value of column `by`, with the least seed's id. A task for each value."""
    passes = bootstrap_passes(region, spacing, start * amplification(n_target, n_seeds, region.dim), n_seeds, n_c, shrink, False)

    def log(frame: pd.DataFrame) -> pd.DataFrame:
        return passes(frame).dropna(subset=["step"]).assign(seed_id=frame["seed_id"].min())[["seed_id", "step", "factor", "n"]]

    one = seeds.select("seed_id", "x", "y", "z", F.col(by).alias("g"))
    return one.groupBy("g").applyInPandas(log, "seed_id long, step long, factor double, n long")


def bootstrap_iterative(seeds: DataFrame, region, spacing, n_target: int, n_seeds: int, n_c: int = 12, start: float = 10.0, shrink: float = 0.5, reuse: bool = False) -> tuple[DataFrame, list]:
    """Inflated fills from start times the amplification, shrinking until at least n_seeds points; and a log of (factor, count).

    reuse: each pass starts from the points of the one before instead of the first seeds.
    """
    passes = bootstrap_passes(region, spacing, start * amplification(n_target, n_seeds, region.dim), n_seeds, n_c, shrink, reuse)
    # the passes are tiny and follow each other: one task does them all
    one = seeds.select("seed_id", "x", "y", "z", F.lit(0).alias("g")).groupBy("g").applyInPandas(passes, BOOTED)
    every = cut(one)
    log = [(int(r["step"]), r["factor"], int(r["n"])) for r in every.filter("step IS NOT NULL").orderBy("step").collect()]
    return every.filter("step IS NULL").select("seed_id", "x", "y", "z"), log


def reduce_seeds(seeds: DataFrame, n: int, how: str = "hash") -> DataFrame:
    """Exactly n seeds: by hash, or farthest-first from the smallest id, a pass over all seeds each (n is small). Ties: the smaller id. Fewer than n: all."""
    if how == "hash":
        return seeds.orderBy(F.xxhash64("seed_id"), "seed_id").limit(n)
    pool = cut(seeds.withColumn("_far", F.lit(math.inf)))
    chosen = []
    while len(chosen) < n:
        # each pass: the seed farthest from those chosen, which leaves the pool
        top = pool.orderBy(F.desc("_far"), "seed_id").limit(1).collect()
        if not top:
            break
        chosen += top
        d2 = sum((F.col(k) - F.lit(top[0][k])) * (F.col(k) - F.lit(top[0][k])) for k in "xyz")
        pool = cut(pool.filter(~F.col("seed_id").eqNullSafe(top[0]["seed_id"])).withColumn("_far", F.least("_far", d2)))
    return seeds.sparkSession.createDataFrame(chosen, pool.schema).drop("_far")


def assign_workers(seeds: DataFrame, n: int, how: str = "round_robin", weight: str | None = None) -> DataFrame:
    """Seeds dealt over workers: by turns, in contiguous shares, or by weight to and fro. The seed table is small (one row a cell)."""
    if how == "contiguous":
        return seeds.withColumn("worker_id", F.ntile(n).over(Window.orderBy("seed_id")) - 1)
    k = F.row_number().over(Window.orderBy(*([F.desc(weight)] if how == "weighted" else []), "seed_id")) - 1
    turn, place = F.floor(k / n), k % n
    worker = F.when(turn % 2 == 1, n - 1 - place).otherwise(place) if how == "weighted" else place
    return seeds.withColumn("worker_id", worker.cast("int"))


class NearestSeed:
    """Nearest of few seeds for many points, in blocks; ties to the smaller id, as the seeds come sorted."""

    def __init__(self, seeds: np.ndarray):
        self.seeds, self.norm = seeds, (seeds**2).sum(1)

    def nearest(self, p: np.ndarray) -> np.ndarray:
        own = np.zeros(len(p), np.int64)
        step = max(1, 1_000_000 // max(1, len(self.seeds)))
        for i in range(0, len(p), step):
            own[i : i + step] = (self.norm[None, :] - 2 * p[i : i + step] @ self.seeds.T).argmin(1)
        return own

    def two(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the nearest, and the distance to the border with the nearest other cell."""
        own, gap = np.zeros(len(p), np.int64), np.full(len(p), np.inf)
        step = max(1, 4_000_000 // max(1, len(self.seeds)))
        for i in range(0, len(p), step):
            q = p[i : i + step]
            d = self.norm[None, :] - 2 * q @ self.seeds.T
            own[i : i + step] = k = d.argmin(1)
            if len(self.seeds) > 1:
                here = d[np.arange(len(q)), k]
                apart = np.sqrt(np.maximum(1e-300, self.norm[None, :] - 2 * self.seeds[k] @ self.seeds.T + self.norm[k][:, None]))
                apart[np.arange(len(q)), k] = np.inf
                gap[i : i + step] = ((d - here[:, None]) / (2 * apart)).min(1, where=np.isfinite(apart), initial=np.inf)
        return own, gap


def fill_cells(seeds: DataFrame, region, spacing, n_parts: int = 8, border: str = "colour", n_c: int = 12, level: int = 0, radii: bool = False, max_seeds: int = 20_000) -> DataFrame:
    """Cells of the seeds filled side by side, a task for each group of cells; then the borders.

    none: cells ignore each other, so points on both sides of a border can be too close. flag: points nearer to a
    border than their radius are settled afterwards in a fixed order (`resolve_borders`), and the gaps refilled.
    colour: cells keep their radius away from borders; `refill` then grows over them in blocks of space whose colours
    keep them apart, with everything placed as blockers, so nothing has to be taken back.
    The seeds are shared with all tasks: at most max_seeds, checked; more call for another level of seeds.
    """
    spark = seeds.sparkSession
    rows = seeds.select("seed_id", "x", "y", "z", *(["r"] if radii else [])).filter(region.contains()).orderBy("seed_id").limit(max_seeds + 1).toPandas()
    if len(rows) > max_seeds:
        raise ValueError("more seeds than can be shared; fill level by level")
    dim = region.dim
    p = rows[list("xyz"[:dim])].to_numpy(float)
    ids = rows["seed_id"].to_numpy(np.int64)
    cells = NearestSeed(p)
    keep_off = border in ("colour", "flag")

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        own = np.sort(frame["k"].to_numpy())
        mine = np.zeros(len(ids), bool)
        mine[own] = True

        def allowed(c):
            if border != "colour":
                return mine[cells.nearest(c)]
            k, gap = cells.two(c)
            return mine[k] & (gap > spacing.at(c))

        out = front.fill(region, spacing, p[own], ids[own], n_c=n_c, allowed=allowed, salt=1)
        found = columns_of(out, level)
        k, gap = cells.two(out["pos"])
        found["cell_id"] = ids[k]
        found["is_border"] = gap < found["r"].to_numpy() if keep_off else False
        found["is_open"] = out["open"]
        return found

    n = max(1, min(n_parts, len(p)))
    deal = np.arange(len(p)) * n // max(1, len(p))
    order = space_order(p)
    work = spark.createDataFrame(pd.DataFrame({"k": order, "part": deal}) if len(p) else pd.DataFrame({"k": pd.Series([], dtype="int64"), "part": pd.Series([], dtype="int64")}), "k long, part long")
    return work.repartition(n, "part").groupBy("part").applyInPandas(one, PLACED)


def space_order(p: np.ndarray) -> np.ndarray:
    """Indices along a space-filling curve (bits of the coordinates by turns), so that a worker's cells are neighbours."""
    if not len(p):
        return np.zeros(0, np.int64)
    q = ((p - p.min(0)) / (np.ptp(p, 0).max() + 1e-12) * 1023).astype(np.int64)
    key = np.zeros(len(p), np.int64)
    for bit in range(10):
        for d in range(p.shape[1]):
            key |= ((q[:, d] >> bit) & 1) << (bit * p.shape[1] + d)
    return np.argsort(key, kind="stable")


def border_conflicts(points: DataFrame, side: float, dim: int) -> DataFrame:
    """Pairs of border points of different workers' cells that are too close: (earlier, later) by a hash order."""
    b = points.filter("is_border").withColumn("prio", F.xxhash64("pid"))
    left = neighbour_cells(b.select(F.col("pid").alias("a_pid"), F.col("prio").alias("a_prio"), F.col("cell_id").alias("a_cell"), F.col("r").alias("ra"), F.struct("x", "y", "z").alias("a"), "x", "y", "z"), side, dim).drop("x", "y", "z")
    right = b.select(F.col("pid").alias("b_pid"), F.col("prio").alias("b_prio"), F.col("cell_id").alias("b_cell"), "r", F.struct("x", "y", "z").alias("b"), F.array(*[F.floor(F.col(k) / side) for k in "xyz"[:dim]]).alias("cell"))
    near = square("a", "b", dim) < F.least("r", "ra") * F.least("r", "ra") * G.SLACK
    return left.join(right, "cell").filter((F.col("a_cell") != F.col("b_cell")) & (F.struct("a_prio", "a_pid") < F.struct("b_prio", "b_pid")) & near).select("a_pid", "b_pid")


ONE_TASK = 200_000


def settle_in_one_task(frame: pd.DataFrame) -> pd.DataFrame:
    ids, codes = np.unique(np.r_[frame["a_pid"].to_numpy(), frame["b_pid"].to_numpy()], return_inverse=True)
    n = len(frame)
    return pd.DataFrame({"pid": ids[~front.first_independent(len(ids), codes[:n], codes[n:])]})


def settle(ids: DataFrame, edges: DataFrame) -> DataFrame:
    """The kept ids: none blocked by a kept earlier one; edges (a_pid, b_pid) go from earlier to later.

    Each round keeps the open ids without an open earlier blocker and drops those that a kept one blocks. Once at most
    ONE_TASK edges are left, one task follows their chains to the end, however long.
    """
    live, open_ids, kept = cut(edges), ids, None
    while live.limit(ONE_TASK + 1).count() > ONE_TASK:
        new = open_ids.join(live.select(F.col("b_pid").alias("pid")), "pid", "left_anti")
        kept = cut(new if kept is None else kept.union(new))
        lost = live.join(new.select(F.col("pid").alias("a_pid")), "a_pid", "left_semi").select(F.col("b_pid").alias("pid")).distinct()
        open_ids = cut(open_ids.join(new, "pid", "left_anti").join(lost, "pid", "left_anti"))
        live = cut(live.join(open_ids.select(F.col("pid").alias("a_pid")), "a_pid", "left_semi").join(open_ids.select(F.col("pid").alias("b_pid")), "b_pid", "left_semi"))
    lost = live.withColumn("g", F.lit(0)).groupBy("g").applyInPandas(settle_in_one_task, "pid long")
    rest = open_ids.join(lost, "pid", "left_anti")
    return rest if kept is None else kept.union(rest)


def resolve_borders(points: DataFrame, spacing, dim: int) -> DataFrame:
    """Border points without conflicts: losers go."""
    points = cut(points)
    edges = border_conflicts(points, spacing.most * 1.0001, dim)
    losers = cut(points.join(points.filter("is_border").select("pid").join(settle(points.filter("is_border").select("pid"), edges), "pid", "left_anti"), "pid", "left_semi"))
    left = points.join(losers.select("pid"), "pid", "left_anti")
    # a point within two radii of one that went may place a candidate now
    side = 2.0002 * spacing.most
    near = neighbour_cells(losers.select("x", "y", "z"), side, dim).select("cell", F.lit(True).alias("freed")).distinct()
    here = left.withColumn("cell", F.array(*[F.floor(F.col(k) / side) for k in "xyz"[:dim]])).join(near, "cell", "left")
    return here.withColumn("is_open", F.col("is_open") | F.coalesce("freed", F.lit(False))).select(*points.columns)


ONE_TASK_POINTS, BLOCK_POINTS = 2_000_000, 200_000


def grow_from(frame: pd.DataFrame, region, spacing, n_c: int, allowed=None) -> pd.DataFrame:
    """New points from the open ones of a frame; all of the frame's points block."""
    f = frame.iloc[np.argsort(frame["pid"].to_numpy(), kind="stable")]
    at, opened, level = f[list("xyz"[: region.dim])].to_numpy(float), f["is_open"].to_numpy(bool), int(f["level"].max())
    sources = f[opened]
    out = front.fill(region, spacing, at[opened], sources["pid"].to_numpy(np.int64), n_c=n_c, allowed=allowed, around=at[~opened], salt=2 + level)
    found = columns_of(out, level)
    found["is_border"], found["is_open"] = True, out["open"]
    new = found[found["gen"] > 0].copy()
    new["cell_id"] = sources["cell_id"].to_numpy()[np.searchsorted(sources["pid"].to_numpy(), new["seed_id"].to_numpy())] if len(new) else new["pid"]
    new["seed_id"] = new["cell_id"]
    return new[[c.split()[0] for c in PLACED.split(", ")]]


def refill(points: DataFrame, region, spacing, n_parts: int = 8, n_c: int = 12, until_full: bool = True) -> DataFrame:
    """Grows from the open points (all, without a column is_open) into what gaps are left. Points stay; new ones are added.

    Up to ONE_TASK_POINTS points: one task, as only open points are expanded. More: blocks of space of about BLOCK_POINTS
    points, at least four radii wide, in 2^dim colours; blocks of one colour are a block apart, so they can't disturb each
    other. A block takes part only if an open point reaches it. Each sweep's sources are the open ones of the sweep before
    it and its own; sweeps end when there are none. What was placed before is never written again.
    """
    dim = region.dim
    base = points if "is_open" in points.columns else points.withColumn("is_open", F.lit(True))
    base = cut(base.select(*[c.split()[0] for c in PLACED.split(", ")]))
    total = base.count()
    if total <= ONE_TASK_POINTS:
        near = base.filter("is_open").limit(1).count()
        new = base.withColumn("g", F.lit(0)).groupBy("g").applyInPandas(lambda f: grow_from(f, region, spacing, n_c), PLACED)
        return base.unionByName(cut(new)) if near else base
    extent = max(b - a for a, b in zip(region.low, region.high, strict=True))
    side = max(4.001 * spacing.most, extent / max(2, math.ceil((total / BLOCK_POINTS) ** (1 / dim))))
    keys = [f"_{i}" for i in range(dim)]
    pieces, sweep, reach = [(base, -1)], 0, 2.001 * spacing.most
    while True:
        for colour in range(2**dim):
            p = None
            for piece, born in pieces:
                own = piece if born >= sweep - 1 else piece.withColumn("is_open", F.lit(False))
                p = own if p is None else p.unionByName(own)
            lo, hi = ([F.floor((F.col(k) + s * reach - region.low[i]) / side) for i, k in enumerate("xyz"[:dim])] for s in (-1, 1))
            near = p.select("*", *[F.sequence(a, b).alias(k) for k, a, b in zip(keys, lo, hi, strict=True)])
            for i, k in enumerate(keys):
                near = near.withColumn(k, F.explode(k)).filter(F.pmod(F.col(k), F.lit(2)) == (colour >> i) % 2)
            near = near.join(near.filter("is_open").select(*keys).distinct(), keys, "left_semi")

            def grow(frame: pd.DataFrame) -> pd.DataFrame:
                low = np.array([frame[k].iloc[0] * side + region.low[i] for i, k in enumerate(keys)])
                return grow_from(frame, region, spacing, n_c, lambda c: ((c >= low) & (c < low + side)).all(1))

            pieces.append((cut(near.groupBy(*keys).applyInPandas(grow, PLACED)), sweep))
        last = [piece for piece, born in pieces if born == sweep]
        if not until_full or not any(piece.filter("is_open").limit(1).count() for piece in last):
            out = pieces[0][0]
            for piece, _ in pieces[1:]:
                out = out.unionByName(piece)
            return out
        sweep += 1


def fill_parallel(seeds: DataFrame, region, spacing, n_parts: int = 8, border: str = "flag", n_c: int = 12) -> DataFrame:
    """Cells side by side, borders settled, gaps refilled: no pair too close, no candidate left to place."""
    points = fill_cells(seeds, region, spacing, n_parts, border, n_c)
    if border == "none":
        return points
    return refill(resolve_borders(points, spacing, region.dim) if border == "flag" else points, region, spacing, n_parts, n_c)


def fill_from_one_seed(seed: DataFrame, region, spacing, n_target: int, n_parts: int, n_c: int = 12) -> DataFrame:
    """The whole parallel method: bootstrapped seeds, cells side by side, gaps at borders filled."""
    seeds, _ = bootstrap_iterative(seed, region, spacing, n_target, 8 * n_parts, n_c)
    return fill_parallel(seeds, region, spacing, n_parts, "colour", n_c)


def fill_multilevel(seeds: DataFrame, region, spacing, levels: int, n_parts: int = 8, n_c: int = 12) -> DataFrame:
    """Spacing inflated 2^levels, halved level by level; every level's points are the next one's seeds and stay.

    Generations a level are few whatever the size, so rounds grow with the logarithm of the point count. The radius with
    which a point was accepted belongs to its own level.
    """
    dim = region.dim
    out = None
    have = seeds.select("seed_id", "x", "y", "z")
    for k in range(levels, -1, -1):
        s = spacing.scaled(2.0**k)
        if out is None:
            new = fill_sequential(have, region, s, n_c).withColumn("cell_id", F.col("seed_id")).withColumn("is_border", F.lit(True)).withColumn("is_open", F.lit(True))
            out = cut(new.withColumn("level", F.lit(k)))
        else:
            grown = refill(out.withColumn("is_open", F.lit(True)).withColumn("h", s.column()).withColumn("level", F.lit(k)), region, s, n_parts, n_c, until_full=k == 0)
            old = out.select("pid", F.col("level").alias("old"), F.col("gen").alias("old_gen"))
            out = cut(grown.join(old, "pid", "left").withColumn("gen", F.when(F.col("old").isNull(), F.col("gen")).otherwise(F.col("old_gen"))).withColumn("level", F.coalesce("old", "level")).drop("old", "old_gen"))
    return out.withColumn("h", spacing.column())
