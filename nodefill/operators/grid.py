"""Distance joins as equi-joins on grid cells: Catalyst sees a key, not a theta condition."""

from __future__ import annotations

import itertools
import sys

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from ..plans.session import cut

cloudpickle.register_pickle_by_value(sys.modules[__name__])

AXES = "xyz"


def cell(side: float, dim: int, axes=AXES) -> Column:
    return F.array(*[F.floor(F.col(k) / side) for k in axes[:dim]])


def neighbour_cells(df: DataFrame, side: float, dim: int) -> DataFrame:
    """A copy of each row for each of the 3^dim cells around it."""
    around = [F.array(*[F.floor(F.col(k) / side) + F.lit(o).cast("long") for k, o in zip(AXES, offset, strict=False)]) for offset in itertools.product((-1, 0, 1), repeat=dim)]
    return df.withColumn("cell", F.explode(F.array(*around)))


def distance2(a: str, b: str, dim: int) -> Column:
    return sum(((F.col(f"{a}{k}") - F.col(f"{b}{k}")) * (F.col(f"{a}{k}") - F.col(f"{b}{k}")) for k in AXES[:dim]), F.lit(0.0))


def prefixed(df: DataFrame, p: str, dim: int, extra=(), plain=()) -> DataFrame:
    return df.select(F.col("pid").alias(f"{p}pid"), *[F.col(k).alias(f"{p}{k}") for k in (*AXES[:dim], *extra)], *plain)


def radius_join(a: DataFrame, b: DataFrame, r: float, dim: int, extra=()) -> DataFrame:
    """(pid, nbr, d2) for all pairs closer than r: b copied to the cells around it, a in one cell."""
    left = prefixed(a, "a_", dim, extra).withColumn("cell", F.array(*[F.floor(F.col(f"a_{k}") / r) for k in AXES[:dim]]))
    right = neighbour_cells(b.select("pid", *AXES[:dim]), r, dim)
    right = right.select("cell", F.col("pid").alias("b_pid"), *[F.col(k).alias(f"b_{k}") for k in AXES[:dim]]).hint("merge")
    out = left.join(right, "cell").withColumn("d2", distance2("a_", "b_", dim)).filter(F.col("d2") < r * r)
    return out.select(F.col("a_pid").alias("pid"), F.col("b_pid").alias("nbr"), "d2", *[F.col(f"a_{k}").alias(k) for k in extra])


def place_pairs(points: DataFrame, r: float, dim: int, extra=()) -> DataFrame:
    """Pairs of places closer than r, each once: a_ and b_ with the least pid, the number n of rows there and the extra columns, which tell places apart too, and d2.

    Copies at one place are one row, so that n of them cost no n * n pairs.
    """
    at = points.groupBy(*AXES[:dim], *extra).agg(F.min("pid").alias("pid"), F.count("*").alias("n"))
    a = prefixed(at, "a_", dim, ["n", *extra]).withColumn("cell", F.array(*[F.floor(F.col(f"a_{k}") / r) for k in AXES[:dim]]))
    b = prefixed(neighbour_cells(at, r, dim), "b_", dim, ["n", *extra], ["cell"]).hint("merge")
    return a.join(b, "cell").withColumn("d2", distance2("a_", "b_", dim)).filter((F.col("a_pid") < F.col("b_pid")) & (F.col("d2") < r * r)).drop("cell")


def octave_of(r: Column, least: float) -> Column:
    return F.floor(F.log2(r / F.lit(least))).cast("int")


CROWD = 64


def start_side(at: DataFrame, k: int, dim: int, side: float, span: list[float], n: int) -> float:
    """A side of at most `side` at which a row has about k others in the cells around it, and at most CROWD * k in its own cell on average."""
    wide = [x for x in span if x > 0]
    if not wide or n < 2:
        return max(side, 1e-12)
    side = max(1e-12, min(side, float(np.exp((np.log(wide).sum() + np.log(2 * k / n)) / len(wide)))))
    least = max(wide) * 1e-12
    while side > least:
        crowd = at.groupBy(cell(side, dim)).agg(F.count("*").cast("double").alias("c")).agg(F.sum(F.col("c") * F.col("c"))).first()[0]
        if crowd <= CROWD * k * n:
            break
        side /= 2
    return max(side, 1e-12)


def knn(points: DataFrame, queries: DataFrame, k: int, dim: int, side: float, same: bool = False, cutoff=None) -> DataFrame:
    """(pid, rank, nbr, dist): the k nearest of `points` for each query, ties to the smaller id.

    Places are searched, not rows: queries at one place share one search, and of the points at one place only the first ids
    can count. A ring of cells, as wide as `side` or less where points are dense, settles every place whose k-th distance is
    at most the side; the others go on with twice the side until all are settled or the ring covers the cloud.
    """
    axes, want = list(AXES[:dim]), k + 1 if same else k
    first = F.row_number().over(Window.partitionBy(*axes).orderBy("pid"))
    few_each = cut(points.select("pid", *axes).withColumn("f", first).filter(F.col("f") <= want))
    p = few_each.drop("f")
    places = few_each.filter("f = 1")
    ends = [f(c).alias(n + c) for n, f in (("l", F.min), ("h", F.max)) for c in axes]
    low_high = edge = few_each.agg(*ends, F.count_if(F.col("f") == 1)).first()
    if queries is points:  # the places are the queries
        open_q = places.select("pid", *axes).dropna(subset=axes)
    else:
        open_q = cut(queries.dropna(subset=axes).groupBy(*axes).agg(F.min("pid").alias("pid")))
        edge = open_q.agg(*ends).first()
    if low_high[0] is None or edge[0] is None:
        return queries.sparkSession.createDataFrame([], "pid long, rank int, nbr long, dist double")
    reach = sum((max(low_high[dim + i], edge[dim + i]) - min(low_high[i], edge[i])) ** 2 for i in range(dim)) ** 0.5
    side = start_side(places, want, dim, side, [low_high[dim + i] - low_high[i] for i in range(dim)], low_high[2 * dim])
    rank, done = F.row_number().over(Window.partitionBy("pid").orderBy("d2", "nbr")), None
    while True:
        last = side > reach
        found = radius_join(open_q, p, side if not last else reach * 1.001 + 1e-9, dim)
        top = found.withColumn("rank", rank).filter(F.col("rank") <= want).groupBy("pid").agg(F.array_sort(F.collect_list(F.struct("d2", "nbr"))).alias("near"))
        settled = cut(top if last else top.filter(F.size("near") == want))
        done = settled if done is None else done.unionByName(settled)
        open_q = open_q if last else cut(open_q.join(settled, "pid", "left_anti"))
        if last or not open_q.limit(1).count():
            break
        side *= 2
    each = Window.partitionBy(*axes)
    q = queries.select("pid", *axes).dropna(subset=axes).select("pid", F.min("pid").over(each).alias("place")).join(done.withColumnRenamed("pid", "place"), "place")
    near = F.filter("near", lambda s: s["nbr"] != F.col("pid")) if same else F.col("near")
    return q.select("pid", F.posexplode(F.slice(near, 1, k)).alias("rank", "s")).select("pid", (F.col("rank") + 1).alias("rank"), F.col("s.nbr").alias("nbr"), F.sqrt("s.d2").alias("dist"))


MAX_SHARED_SEEDS = 20_000
SPREAD_BYTES = 16 << 20


def spread(points: DataFrame) -> DataFrame:
    """Points over all cores at least, by id: a small file is one task, however much work each of its rows is. Larger inputs get more parts, up to those of any exchange."""
    spark = points.sparkSession
    size = int(str(points._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    parts = min(int(spark.conf.get("spark.sql.shuffle.partitions")), size // SPREAD_BYTES)
    return points.repartition(max(spark.sparkContext.defaultParallelism, parts), "pid")


def few(seeds: DataFrame, limit: int) -> bool:
    """Whether seeds may be shared with every task: their number is checked, not assumed."""
    return seeds.limit(limit + 1).count() <= limit


def first_of_places(seeds: DataFrame, dim: int, n: int) -> DataFrame:
    """Seeds that can be among the n nearest of any point: of those at one place the n smallest ids; none without a place."""
    axes = list(AXES[:dim])
    first = F.row_number().over(Window.partitionBy(*axes).orderBy("seed_id"))
    return seeds.select("seed_id", *axes).dropna(subset=axes).withColumn("f", first).filter(F.col("f") <= n).drop("f")


def shared_nearest(seeds: DataFrame, dim: int, n: int, limit: int) -> Column | None:
    """The n nearest seeds as columns d0, i0, d1, ... of a struct: squared distance and seed_id, ties to the smaller id. None, if there are more than `limit` seeds.

    A batch of points against all seeds at a time, by the comparisons of the SQL to the last bit.
    """
    rows = seeds.limit(limit + 1).collect()
    if len(rows) > limit:
        return None
    rows.sort(key=lambda r: r["seed_id"])
    ids, at = np.array([r["seed_id"] for r in rows], np.int64), [np.array([r[c] for r in rows], float) for c in AXES[:dim]]
    kind = seeds.schema["seed_id"].dataType
    fields = [StructField(f"{c}{j}", DoubleType() if c == "d" else kind) for j in range(n) for c in "di"]

    @F.pandas_udf(StructType(fields))
    def nearest(x: pd.Series, y: pd.Series, z: pd.Series) -> pd.DataFrame:
        p = [np.asarray(c, float) for c in (x, y, z)[:dim]]
        d, i = np.full((n, len(x)), np.nan), np.full((n, len(x)), -1, np.int64)
        step = max(1, 100_000 // max(1, len(ids)))  # so that a block stays in the processor's cache
        for low in range(0, len(x) if len(ids) else 0, step):
            one = slice(low, low + step)
            d2 = None
            for a, b in zip(p, at, strict=True):
                gap = a[one, None] - b[None]
                gap *= gap
                d2 = gap if d2 is None else np.add(d2, gap, out=d2)
            order = np.where(np.isfinite(d2), d2, np.finfo(float).max)  # to a point without a place all seeds are alike
            turn = np.arange(len(d2))
            for j in range(min(n, len(ids))):
                best = order.argmin(1)
                d[j, one], i[j, one] = d2[turn, best], ids[best]
                order[turn, best] = np.inf
        out = {}
        for j in range(n):
            out[f"d{j}"], out[f"i{j}"] = pd.array(d[j], "Float64"), pd.array(i[j], "Int64")
            out[f"d{j}"][np.isnan(d[j])] = pd.NA
            if len(ids) <= j:
                out[f"i{j}"][:] = pd.NA
        return pd.DataFrame(out)

    # as if it could vary: else a join's test for null would be pushed below it, and all distances computed twice
    return nearest.asNondeterministic()("x", "y", "z" if dim > 2 else F.lit(0.0))


def nearest_by_grid(points: DataFrame, seeds: DataFrame, dim: int, n: int) -> DataFrame:
    """(pid, rank, nbr, dist) of the n nearest seeds by grid joins, for seeds of any number."""
    s = seeds.withColumnRenamed("seed_id", "pid")
    span = s.agg(F.count("*"), *[F.max(k) - F.min(k) for k in AXES[:dim]]).first()
    side = max([1e-9, *[x or 0.0 for x in span[1:]]]) / max(1.0, span[0] ** (1 / dim)) * 1.5
    return knn(s, points, n, dim, side)


def no_place(dim: int) -> Column:
    """Rows without a place: to them all seeds are alike, and the smallest ids come first."""
    return F.array_contains(F.array(*[F.col(k).isNull() for k in AXES[:dim]]), True)


def nearest_cells(points: DataFrame, seeds: DataFrame, dim: int, n: int = 2, limit: int = MAX_SHARED_SEEDS) -> DataFrame:
    """pid, cells: the n nearest seeds as (d2, seed_id), nearest first, ties to the smaller id. At most `limit` seeds are shared; more are met by grid joins."""
    first = cut(first_of_places(seeds, dim, n))
    at = first.select("seed_id", *[F.col(k).alias(f"s{k}") for k in AXES[:dim]])
    near = shared_nearest(first, dim, n, limit)
    if near is None:
        pairs = nearest_by_grid(points, first, dim, n).select("pid", F.col("nbr").alias("seed_id")).join(at, "seed_id").join(points.select("pid", *AXES[:dim]), "pid")
        pairs = pairs.withColumn("d2", sum(((F.col(k) - F.col(f"s{k}")) * (F.col(k) - F.col(f"s{k}")) for k in AXES[:dim]), F.lit(0.0)))
        item = F.struct("d2", "seed_id", *[f"s{k}" for k in AXES[:dim]])
        found = pairs.groupBy("pid", *AXES[:dim]).agg(F.array_sort(F.collect_list(item)).alias("cells"))
        least = at.orderBy("seed_id").limit(n).withColumn("d2", F.lit(None).cast("double")).agg(F.array_sort(F.collect_list(item)).alias("cells"))
        return found.unionByName(points.select("pid", *AXES[:dim]).filter(no_place(dim)).join(F.broadcast(least)))
    found = spread(points.select("pid", *AXES[:dim])).select("pid", *AXES[:dim], near.alias("near"))
    for j in range(n):
        one = at.select(F.col("seed_id").alias("at_id"), F.struct(*[f"s{k}" for k in AXES[:dim]]).alias(f"s{j}"))
        found = found.join(F.broadcast(one), F.col(f"near.i{j}") == F.col("at_id"), "left").drop("at_id")
    cells = F.array(*[F.when(F.col(f"near.i{j}").isNotNull(), F.struct(F.col(f"near.d{j}").alias("d2"), F.col(f"near.i{j}").alias("seed_id"), *[F.col(f"s{j}.s{k}").alias(f"s{k}") for k in AXES[:dim]])) for j in range(n)])
    return found.select("pid", *AXES[:dim], F.filter(cells, lambda c: c.isNotNull()).alias("cells"))


def assign_cells(points: DataFrame, seeds: DataFrame, dim: int, limit: int = MAX_SHARED_SEEDS) -> DataFrame:
    """points with cell_id and seed_dist: all seeds beside a batch of points, spread over the cores, so rows don't multiply. More than `limit` seeds: grid joins."""
    first = cut(first_of_places(seeds, dim, 1))
    best = shared_nearest(first, dim, 1, limit)
    if best is None:
        near = nearest_by_grid(points, first, dim, 1).select("pid", F.col("nbr").alias("cell_id"), F.col("dist").alias("seed_dist"))
        least = first.agg(F.min("seed_id").alias("least"))
        out = points.join(near, "pid", "left").join(F.broadcast(least))
        return out.withColumn("cell_id", F.when(no_place(dim), F.col("least")).otherwise(F.col("cell_id"))).drop("least")
    return spread(points).withColumn("best", best).withColumn("cell_id", F.col("best.i0")).withColumn("seed_dist", F.sqrt("best.d0")).drop("best")


def border_distance(points: DataFrame, seeds: DataFrame, dim: int) -> DataFrame:
    """pid, cell_id, near_cell, gap: distance to the bisector with the second nearest seed."""
    near = nearest_cells(points, seeds, dim, 2).filter(F.size("cells") > 1)
    a, b = F.col("cells")[0], F.col("cells")[1]
    apart = F.sqrt(sum(((a[f"s{k}"] - b[f"s{k}"]) * (a[f"s{k}"] - b[f"s{k}"]) for k in AXES[:dim]), F.lit(0.0)))
    return near.select("pid", a["seed_id"].alias("cell_id"), b["seed_id"].alias("near_cell"), F.try_divide(b["d2"] - a["d2"], 2 * apart).alias("gap"))


def nearest_by_grid_of(points: DataFrame, queries: DataFrame, seeds: DataFrame, k: int, dim: int, same: bool) -> DataFrame:
    """Too many seeds to share: the grid alone, with cells as wide as the seeds lie apart."""
    span = seeds.agg(F.count("*"), *[F.max(c) - F.min(c) for c in AXES[:dim]]).first()
    return knn(points, queries, k, dim, max(1e-9, *[x or 0.0 for x in span[1:]]) / span[0] ** (1 / dim), same)


def indexed_knn(points: DataFrame, queries: DataFrame, seeds: DataFrame, k: int, dim: int, same: bool = False) -> DataFrame:
    """k nearest by the two-level index: first the own cell; then only cells that the bisector bound leaves possible.

    A point of cell j is no nearer to q than q is to the bisector of its own seed and j's.
    """
    if not few(seeds, MAX_SHARED_SEEDS):
        return nearest_by_grid_of(points, queries, seeds, k, dim, same)
    p = assign_cells(points.select("pid", *AXES[:dim]), seeds, dim).select(F.col("cell_id").alias("cell"), F.col("pid").alias("nbr"), *[F.col(c).alias(f"b_{c}") for c in AXES[:dim]])
    q = assign_cells(queries.select("pid", *AXES[:dim]), seeds, dim)
    rank = F.row_number().over(Window.partitionBy("pid").orderBy("d2", "nbr"))
    keep = F.lit(True) if not same else F.col("pid") != F.col("nbr")

    def ranked(pairs):
        at = pairs.withColumnsRenamed({c: f"a_{c}" for c in AXES[:dim]}).withColumn("d2", distance2("a_", "b_", dim)).filter(keep)
        return at.withColumn("rank", rank).filter(F.col("rank") <= k).select("pid", "rank", "nbr", "d2")

    own = ranked(q.withColumnRenamed("cell_id", "cell").select("pid", "cell", *AXES[:dim]).join(p, "cell"))
    kth = own.groupBy("pid").agg(F.max(F.when(F.col("rank") == k, F.col("d2"))).alias("kth"))
    # the other cells within reach: a filter over the shared seeds beside each home, so that only those become rows
    top = seeds.agg(F.array_sort(F.collect_list(F.struct("seed_id", *AXES[:dim]))).alias("seeds"))
    home = seeds.select(F.col("seed_id").alias("cell_id"), F.struct(*AXES[:dim]).alias("home")).join(F.broadcast(top))
    far = lambda a, b: sum(((a(c) - b(c)) * (a(c) - b(c)) for c in AXES[:dim]), F.lit(0.0))

    def possible(s):
        apart = 2 * F.sqrt(far(lambda c: s[c], lambda c: F.col("home")[c]))
        gap = F.when(apart > 0, (far(F.col, lambda c: s[c]) - far(F.col, lambda c: F.col("home")[c])) / F.nullif(apart, F.lit(0.0))).otherwise(0.0)
        return (s["seed_id"] != F.col("cell_id")) & (F.col("kth").isNull() | (gap * gap <= F.col("kth") * (1 + 1e-9)))

    cells = q.join(kth, "pid", "left").join(F.broadcast(home), "cell_id").select("pid", *AXES[:dim], F.explode(F.transform(F.filter("seeds", possible), lambda s: s["seed_id"])).alias("cell"))
    more = cells.join(p, "cell").select("pid", "nbr", *AXES[:dim], *[f"b_{c}" for c in AXES[:dim]])
    # the own cell has been ranked already: only its best go on
    both = ranked(more).unionByName(own.select("pid", "rank", "nbr", "d2"))
    return both.withColumn("rank", rank).filter(F.col("rank") <= k).select("pid", "rank", "nbr", F.sqrt("d2").alias("dist"))
