"""Hull, extent and centroid of groups of geometries, from small mergeable parts.

Each task reduces its own rows first, so a group that holds most rows is never gathered in one task.  Null and
unreadable geometries take no part; a group without any other keeps a row with nulls (hull: an empty MULTIPOINT).
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from querygrade.functions import geometry as g
from querygrade.functions import geometry_udfs as u


def hulls(shapes: DataFrame, keys: list[str], geom: str, held_groups: int = 50_000, held_points: int = 4096) -> DataFrame:
    """keys, hull: convex hull of each group, from the hulls of its rows in each task."""
    rows = shapes.select(*keys, F.col(geom).alias("hull"))
    names = rows.schema.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}

        def flush(types):
            texts = [g.to_ewkt(g.Shape("MULTIPOINT", tuple(tuple(map(float, p)) for p in g.convex_hull(points)))) for points in held.values()]
            columns = [pa.array([k[i] for k in held], t) for i, t in enumerate(types)]
            held.clear()
            return pa.RecordBatch.from_arrays([*columns, pa.array(texts, pa.string())], names=names)

        types = None
        for batch in batches:
            types = [c.type for c in batch.columns[:-1]]
            columns = [c.to_pylist() for c in batch.columns]
            for *key, value in zip(*columns, strict=True):
                points = held.setdefault(tuple(key), [])
                shape = u._shape(value)
                if shape is not None:
                    points.extend(p[:2] for p in g.dump_points(shape))
                    if len(points) > held_points:
                        points[:] = g.convex_hull(points)
            if len(held) > held_groups:
                yield flush(types)
        if held:
            yield flush(types)

    kinds = rows.schema
    parts = rows.mapInArrow(run, kinds)
    return parts.groupBy(*keys).agg(u.convex_hull_agg("hull").alias("hull"))


def extents(shapes: DataFrame, keys: list[str], geom: str) -> DataFrame:
    """keys, x1, y1, x2, y2: least box around each group."""
    box = shapes.select(*keys, u.envelope_of(geom).alias("box"))
    return box.groupBy(*keys).agg(F.min("box.x1").alias("x1"), F.min("box.y1").alias("y1"), F.max("box.x2").alias("x2"), F.max("box.y2").alias("y2"))


def centroids(shapes: DataFrame, keys: list[str], geom: str) -> DataFrame:
    """keys, x, y: centroid of each group; areas weigh by size, then lines by length, then points alike, as the highest dimension has it."""
    m = shapes.select(*keys, u.moment_of(geom).alias("m"))
    top = F.max("m.dim")
    sums = [F.sum(F.when(F.col("m.dim") == d, F.col(f"m.{c}"))).alias(f"{c}{d}") for d in (0, 1, 2) for c in ("w", "wx", "wy")]
    got = m.groupBy(*keys).agg(top.alias("dim"), *sums)
    pick = lambda c: F.element_at(F.array(*[F.try_divide(f"{c}{d}", f"w{d}") for d in (0, 1, 2)]), F.col("dim") + 1)
    return got.select(*keys, pick("wx").alias("x"), pick("wy").alias("y"))
