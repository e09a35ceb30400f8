"""Spatial joins as equi-joins on grid cells with exact refinement; nearest neighbours by growing rings."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from querygrade.sources.tables import written


def cell(x: Column, y: Column, size: float) -> tuple[Column, Column]:
    return F.floor(x / size).cast("long"), F.floor(y / size).cast("long")


def points_in_boxes(points: DataFrame, boxes: DataFrame, size: float) -> DataFrame:
    """Points (x, y) with the boxes (x1, y1, x2, y2; half open) that hold them.

    A box is copied into the cells that it meets; a point is in one cell, so no pair comes twice.
    """
    cx, cy = cell(F.col("x"), F.col("y"), size)
    placed = points.withColumns({"cx": cx, "cy": cy})
    (ax, ay), (bx, by) = cell(F.col("x1"), F.col("y1"), size), cell(F.col("x2"), F.col("y2"), size)
    spread = boxes.withColumn("cx", F.explode(F.sequence(ax, bx))).withColumn("cy", F.explode(F.sequence(ay, by)))
    inside = "x >= x1 AND x < x2 AND y >= y1 AND y < y2"
    return placed.join(spread, ["cx", "cy"]).where(inside).drop("cx", "cy")


def within_distance(left: DataFrame, right: DataFrame, d: float) -> DataFrame:
    """Pairs of points (x, y | x2, y2) at planar distance d or less; the right side is copied to nine cells."""
    cx, cy = cell(F.col("x"), F.col("y"), d)
    placed = left.withColumns({"cx": cx, "cy": cy})
    rx, ry = cell(F.col("x2"), F.col("y2"), d)
    around = right.withColumn("cx", F.explode(F.sequence(rx - 1, rx + 1))).withColumn("cy", F.explode(F.sequence(ry - 1, ry + 1)))
    dx, dy = F.col("x") - F.col("x2"), F.col("y") - F.col("y2")
    gap = dx * dx + dy * dy  # not by powers, whose last bit may differ
    return placed.join(around, ["cx", "cy"]).where(gap <= d * d).withColumn("distance", F.sqrt(gap)).drop("cx", "cy")


def _meeting_radius(left: DataFrame, right: DataFrame, spread: float, k: int, levels: int = 24) -> float:
    """The side of the widest cells (``spread`` halved some times) in which a left point meets 2 k right points or fewer on average."""
    sides = F.explode(F.transform(F.sequence(F.lit(0), F.lit(levels)), lambda n: F.lit(spread) / F.pow(F.lit(2.0), n))).alias("side")
    ones = lambda df, x, y, a, b: df.select(F.col(x).alias("x"), F.col(y).alias("y"), F.lit(a).alias("l"), F.lit(b).alias("r")).select("*", sides)
    both = ones(left, "x", "y", 1, 0).unionByName(ones(right, "x2", "y2", 0, 1))
    cx, cy = cell(F.col("x"), F.col("y"), F.col("side"))
    cells = both.groupBy("side", cx.alias("cx"), cy.alias("cy")).agg(F.sum("l").cast("double").alias("l"), F.sum("r").alias("r"))
    met = cells.groupBy("side").agg((F.sum(F.col("l") * F.col("r")) / F.sum("l")).alias("met")).where(F.col("met") <= 2 * k)
    return met.agg(F.max("side")).first()[0] or spread / 2**levels


def nearest(left: DataFrame, right: DataFrame, key: str, other: str, k: int, first_radius: float | None = None) -> DataFrame:
    """The k nearest right points of every left point (all, where there are fewer), ties by the right key.

    Rounds double the radius; a left point leaves when it has k points within its radius, so a round joins only those that
    are open, which are written between rounds.  The first radius follows the points' density unless it is given; of right points at one
    place the k least keys take part.  The last round's radius spans all points of both sides, so nothing stays open.
    """
    ends = [F.min("x"), F.max("x"), F.min("y"), F.max("y")]
    edges = [v for r in (left.agg(*ends).first(), right.agg(F.min("x2"), F.max("x2"), F.min("y2"), F.max("y2")).first()) for v in r]
    spread = 0.0 if None in edges else math.hypot(max(edges[1], edges[5]) - min(edges[0], edges[4]), max(edges[3], edges[7]) - min(edges[2], edges[6]))
    place = Window.partitionBy("x2", "y2").orderBy(other)
    right = written(right.select(other, "x2", "y2").withColumn("nth", F.row_number().over(place)).where(F.col("nth") <= k).drop("nth"), "nearest-places")
    radius = float(first_radius or (_meeting_radius(left, right, spread, k) if spread > 0 else 1.0))
    out, todo = None, left.select(key, "x", "y")
    while True:
        last = radius >= spread
        near = within_distance(todo, right, radius)
        w = Window.partitionBy(key).orderBy("distance", other)
        ranked = near.withColumns({"rank": F.row_number().over(w), "n": F.count(F.lit(1)).over(Window.partitionBy(key))}).where(F.lit(last) | (F.col("n") >= k)).where(F.col("rank") <= k)
        ranked = written(ranked.select(key, "rank", other, "distance"), "nearest")
        out = ranked if out is None else out.unionByName(ranked)
        if last:
            return out
        todo = written(todo.join(ranked.select(key).distinct(), key, "left_anti"), "nearest-open")
        if todo.isEmpty():
            return out
        radius *= 2
