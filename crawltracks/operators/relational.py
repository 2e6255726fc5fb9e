"""Joins and samples that the methods need and Spark has no operator for."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from crawltracks.functions.geo import EARTH_RADIUS_M, step_m

#: Rows that a side sent to all tasks may have at most; beyond it the call fails instead of growing.
MAX_QUERIES = 100_000


def within(points: DataFrame, targets: DataFrame, metres: float, degrees: float) -> DataFrame:
    """Pairs of points and targets (lat, lon) at most ``metres`` apart, with ``metres``.

    Each target stands in every cell of ``degrees`` that its circle can touch: rows up to the
    circle's reach north and south, columns up to its reach east and west, which grows towards
    the poles and goes on across the date line. An equi-join on the cell then finds all pairs.
    Rows without a position have no pairs.
    """
    columns = math.ceil(360 / degrees)
    angle = min(metres / EARTH_RADIUS_M, math.pi) * (1 + 1e-9)
    north = math.degrees(angle)
    row = lambda lat: F.floor((lat + 90) / degrees)
    column = lambda lon: F.floor(F.pmod(lon + 180, F.lit(360.0)) / degrees)
    cos = F.cos(F.radians("lat"))
    pole = (F.abs("lat") + north >= 90) | (cos <= math.sin(min(angle, math.pi / 2)))
    east = F.when(pole, 180.0).otherwise(F.degrees(F.asin(F.least(math.sin(min(angle, math.pi / 2)) / cos, F.lit(1.0)))))
    first = F.floor((F.col("lon") + 180 - F.col("_east")) / degrees)
    last = F.floor((F.col("lon") + 180 + F.col("_east")) / degrees) + 1  # one more: the last column may be a narrow one
    t = targets.where("lat is not null and lon is not null").withColumn("_east", east)
    t = t.select("*", F.explode(F.sequence(row(F.col("lat") - north), row(F.col("lat") + north))).alias("_a"))
    t = t.select("*", F.explode(F.array_distinct(F.transform(F.sequence(first - 1, F.least(last, first + columns)), lambda c: F.pmod(c, F.lit(columns))))).alias("_b"))
    t = t.select(*[F.col(c).alias(f"_t_{c}" if c in ("lat", "lon") else c) for c in targets.columns], "_a", "_b")
    p = points.withColumns({"_a": row(F.col("lat")), "_b": column(F.col("lon"))})
    joined = p.join(t, ["_a", "_b"]).withColumn("metres", step_m(F.col("lat"), F.col("lon"), F.col("_t_lat"), F.col("_t_lon")))
    return joined.where(F.col("metres") <= metres).drop("_a", "_b", "_t_lat", "_t_lon")


def cosine_top(queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """q, vec_id and rank of the ``k`` most similar vectors of each query; queries are checked for size and sent out.

    Every task keeps the best k of a query among its rows, so the shuffle has k rows a query and task.
    """
    if queries.limit(MAX_QUERIES + 1).count() > MAX_QUERIES:
        raise ValueError(f"more than {MAX_QUERIES} queries; use blocks of them")
    unit = lambda v: F.transform(v, lambda x: x.cast("double"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    norm = lambda v: F.sqrt(dot(v, v))
    q = queries.select(F.col("vec_id").alias("q"), unit(F.col("embedding")).alias("a")).withColumn("na", norm(F.col("a")))
    v = vectors.select("vec_id", unit(F.col("embedding")).alias("b")).withColumn("nb", norm(F.col("b")))
    scored = v.join(F.broadcast(q), F.col("q") != F.col("vec_id")).select("q", "vec_id", F.round(dot(F.col("a"), F.col("b")) / (F.col("na") * F.col("nb")), 9).alias("s"))
    best = lambda by: F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("s"), "vec_id"))
    salted = scored.withColumn("salt", F.pmod(F.hash("vec_id"), F.lit(16)))
    part = salted.withColumn("rk", best(["q", "salt"])).where(F.col("rk") <= k)
    return part.withColumn("rk", best(["q"])).where(F.col("rk") <= k).select("q", "vec_id", F.col("rk").cast("long").alias("rk"))


def as_of(left: DataFrame, right: DataFrame, by: str, at: Column, take: list[str]) -> DataFrame:
    """For each left row the last right row of the same key at or before it: one sort over the union, no range join."""
    w = Window.partitionBy(by).orderBy("_at", "_side").rowsBetween(Window.unboundedPreceding, 0)
    r = right.select(F.col(by), at.alias("_at"), F.lit(0).alias("_side"), F.struct(*take).alias("_right"))
    names = [F.col(c) for c in left.columns]
    l = left.select(F.col(by), at.alias("_at"), F.lit(1).alias("_side"), F.struct(*names).alias("_left"))
    both = r.unionByName(l, allowMissingColumns=True).withColumn("_hit", F.last("_right", ignorenulls=True).over(w)).where("_side = 1")
    return both.select("_left.*", *[F.col(f"_hit.{c}").alias(f"prev_{c}") for c in take])


def hash_sample(rows: DataFrame, key: str, share: float) -> DataFrame:
    """A repeatable sample for looking at: the same keys at every run and size, by the start of the key's digest."""
    below = f"{min(int(share * (1 << 24)), (1 << 24) - 1):06x}"
    return rows.where(F.substring(F.md5(F.encode(F.col(key).cast("string"), "UTF-8")), 1, 6) < below)
