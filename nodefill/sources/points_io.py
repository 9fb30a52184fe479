"""Reading and writing points: Parquet, CSV, JSON, ORC, coordinate text, meshes, streams, and a data source that fills."""

from __future__ import annotations

import sys
from functools import reduce
from operator import or_

from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions import geometry as G

cloudpickle.register_pickle_by_value(sys.modules[__name__])

SCHEMA = "pid long, x double, y double, z double"


def read_points(spark: SparkSession, path: str, kind: str = "parquet", schema: str = SCHEMA) -> DataFrame:
    """Points with an explicit schema. text: one point a line, white space between coordinates, lines of # left out; pid from the place in the file is not stable, so it is a hash of the line."""
    if kind == "text":
        line = F.trim("value")
        parts = F.split(line, r"\s+")
        rows = spark.read.text(path).filter((line != "") & ~line.startswith("#"))
        return rows.select(F.xxhash64(line).alias("pid"), *[F.coalesce(F.get(parts, i).cast("double"), F.lit(0.0)).alias(c) for i, c in enumerate("xyz")])
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else getattr(reader, kind)(path)


def write_points(points: DataFrame, path: str, kind: str = "parquet", by: str | None = None, mode: str = "error") -> None:
    """by: a column of few values that becomes the folder; rows are sorted by place within files so that scans prune."""
    out = points.repartition(by).sortWithinPartitions(by, "x", "y") if by else points
    if kind == "text":
        out.select(F.concat_ws(" ", *[F.col(c).cast("string") for c in ("x", "y", "z") if c in out.columns]).alias("value")).write.mode(mode).text(path)
        return
    writer = out.write.mode(mode).partitionBy(by) if by else out.write.mode(mode)
    writer.option("header", True).csv(path) if kind == "csv" else getattr(writer, kind)(path)


def fault(points: DataFrame, region=None):
    """Why a row can't take part in a fill: coordinate (null, NaN, infinite), spacing (so, or not positive), outside; null if it can."""
    broken = lambda c: F.col(c).isNull() | F.isnan(c) | (F.abs(c) == float("inf"))
    why = F.when(reduce(or_, [broken(c) for c in "xyz" if c in points.columns]), "coordinate")
    if "h" in points.columns:
        why = why.when(broken("h") | (F.col("h") <= 0), "spacing")
    return why if region is None else why.when(~region.contains(), "outside")


def require_valid(points: DataFrame, region=None) -> DataFrame:
    """The points as they are; the job fails if it meets a row with a fault."""
    why = fault(points, region)
    return points.filter(F.when(why.isNotNull(), F.raise_error(F.concat(F.lit("invalid point: "), why))).otherwise(F.lit(True)))


def write_sorted(rows: DataFrame, path: str, *by: str) -> None:
    """Parquet in one order: each file is sorted, and holds a range of its own."""
    rows.repartitionByRange(*by).sortWithinPartitions(*by).write.parquet(path)


def write_cells(points: DataFrame, table: str, buckets: int = 64) -> None:
    """Points bucketed and sorted by cell: joins by cell then need no exchange."""
    points.write.mode("overwrite").bucketBy(buckets, "cell_id").sortBy("cell_id").format("parquet").saveAsTable(table)


def read_mesh(spark: SparkSession, path: str) -> DataFrame:
    """Faces (face, ax..cz) from lines `v x y z` and `f i j k`, vertices counted from 1 in file order."""
    lines = spark.read.text(path, wholetext=True).select(F.posexplode(F.split("value", "\n")).alias("n", "line"))
    parts = F.split(F.trim("line"), r"\s+")
    v = lines.filter(F.trim("line").startswith("v ")).select("n", *[F.get(parts, i + 1).cast("double").alias(c) for i, c in enumerate("xyz")])
    from pyspark.sql import Window

    v = v.select(F.row_number().over(Window.orderBy("n")).alias("k"), "x", "y", "z")
    f = lines.filter(F.trim("line").startswith("f ")).select(F.col("n").alias("face"), *[F.split(F.get(parts, i + 1), "/")[0].cast("int").alias(c) for i, c in enumerate("abc")])
    for c in "abc":
        f = f.join(v.select(F.col("k").alias(c), *[F.col(k).alias(f"{c}{k}") for k in "xyz"]), c)
    return f.select("face", *[f"{c}{k}" for c in "abc" for k in "xyz"])


def inside_mesh(points: DataFrame, faces: DataFrame) -> DataFrame:
    """Points inside closed triangle meshes: parity of the faces above, found by the faces' boxes over x and y."""
    a, b, c = [[F.col(f"{k}{s}") for s in "xyz"] for k in "abc"]
    area = (b[0] - a[0]) * (c[1] - a[1]) - (b[1] - a[1]) * (c[0] - a[0])
    u = ((F.col("x") - a[0]) * (c[1] - a[1]) - (F.col("y") - a[1]) * (c[0] - a[0])) / area
    v = ((b[0] - a[0]) * (F.col("y") - a[1]) - (b[1] - a[1]) * (F.col("x") - a[0])) / area
    above = a[2] + u * (b[2] - a[2]) + v * (c[2] - a[2]) > F.col("z")
    boxed = faces.filter(area != 0).select("*", *[F.least(*[F.col(f"{k}{s}") for k in "abc"]).alias(f"lo{s}") for s in "xy"], *[F.greatest(*[F.col(f"{k}{s}") for k in "abc"]).alias(f"hi{s}") for s in "xy"])
    near = (F.col("x") >= F.col("lox")) & (F.col("x") <= F.col("hix")) & (F.col("y") >= F.col("loy")) & (F.col("y") <= F.col("hiy"))
    hits = points.join(F.broadcast(boxed), near).filter((u >= 0) & (v >= 0) & (u + v < 1) & above).groupBy("pid").agg((F.count("*") % 2).alias("odd"))
    return points.join(hits.filter("odd = 1"), "pid", "left_semi")


def stream_points(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


class FillPart(InputPartition):
    def __init__(self, k: int, low: list, high: list):
        super().__init__(k)
        self.k, self.low, self.high = k, low, high


class FillReader(DataSourceReader):
    """Lattice of a region, a slab of it for each partition."""

    def __init__(self, options):
        self.region, self.h, self.n = options.get("region", "clover2d"), float(options.get("h", "0.25")), int(options.get("parts", "4"))

    def partitions(self):
        r = G.REGIONS[self.region]()
        rows = int((r.high[0] - r.low[0]) / self.h) + 1
        n = min(self.n, rows)
        return [FillPart(k, [rows * k // n], [rows * (k + 1) // n]) for k in range(n)]

    def read(self, part):
        import numpy as np

        r = G.REGIONS[self.region]()
        sizes = [int((b - a) / self.h) + 1 for a, b in zip(r.low, r.high, strict=True)]
        for i in range(part.low[0], part.high[0]):
            grid = np.stack(np.meshgrid([r.low[0] + i * self.h], *[lo + self.h * np.arange(n) for lo, n in zip(r.low[1:], sizes[1:], strict=True)], indexing="ij"), -1).reshape(-1, r.dim)
            for j in np.flatnonzero(r.test(grid)):
                p = [*map(float, grid[j]), 0.0][:3]
                yield (int(i) * 10**9 + int(j), *p)


class NodefillSource(DataSource):
    """spark.read.format("nodefill").option("region", ...).option("h", ...).option("parts", ...)."""

    @classmethod
    def name(cls):
        return "nodefill"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return FillReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(NodefillSource)
