"""Exact top-k by inner product: ball-tree branch and bound in shards that share the kth score.

Vectors become integers floor(256*x).  A hash of the id deals them into shards of a bounded number of rows;
each shard builds a ball tree.  A node with centre c and radius r bounds the products of its points with q
by q.c + |q|r; nodes are visited by falling bound and left out when the bound is under the kth score so far.
Pass 1 looks at each query's best leaf in every shard; the kth best over all shards is a valid floor for the
whole, and pass 2 starts every shard's search from this shared score.  Products are sums of integers far
below 2^53, so float64 products are exact; bounds get a margin for rounding.

Queries (a stated set) travel in packed blocks to every shard; a task reads one shard and streams the blocks
of one query group.  Each shard returns k rows at most for a query.

Defined cases: vectors that are null, empty or hold null, NaN or infinite components take no part, nor do rows without
id; repeated rows of an id are vectors of their own, as queries (each with its k rows) and as candidates (of each other too); only vectors of equal length are compared; fewer than k candidates give all;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import stored, table

K = 5
SCALE = 256.0
SHARD_ROWS = 16_384
BLOCK = 512
BLOCKS_PER_GROUP = 64
LEAF = 96
NO_ID = np.iinfo(np.int64).max


class BallTree:
    """Leaves of points with the levels of balls above them."""

    def __init__(self, points: np.ndarray, ids: np.ndarray, rows: np.ndarray, leaf: int = LEAF):
        self.points, self.ids, self.rows = points, ids, rows
        self.leaves: list[np.ndarray] = []
        self.centre: list[np.ndarray] = []
        self.radius: list[float] = []
        self.children: list[tuple[int, int] | None] = []
        self.leaf_of: list[int] = []
        self.root = self._build(np.arange(len(points)), leaf)
        self.centres, self.radii = np.array(self.centre), np.array(self.radius)

    def _build(self, rows: np.ndarray, leaf: int) -> int:
        node, own = len(self.centre), self.points[rows]
        centre = own.mean(axis=0)
        away = np.sqrt(((own - centre) ** 2).sum(axis=1))
        self.centre.append(centre)
        self.radius.append(float(away.max()) if len(rows) else 0.0)
        self.children.append(None)
        self.leaf_of.append(-1)
        if len(rows) <= leaf:
            self.leaf_of[node] = len(self.leaves)
            self.leaves.append(rows)
            return node
        a = own[away.argmax()]
        b = own[((own - a) ** 2).sum(axis=1).argmax()]
        order = np.argsort(own @ (b - a), kind="stable")
        half = len(rows) // 2
        left = self._build(rows[order[:half]], leaf)
        self.children[node] = (left, self._build(rows[order[half:]], leaf))
        return node

    def bounds(self, queries: np.ndarray, length: np.ndarray, nodes: list[int]) -> np.ndarray:
        return queries @ self.centres[nodes].T + length[:, None] * self.radii[nodes][None, :] + 1e-6 * (1 + length[:, None] ** 2)

    def search(self, queries: np.ndarray, own: np.ndarray, floor: np.ndarray, k: int, first_leaf_only: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """(scores, ids), k columns each, of every query but for its ``own`` row; scores under ``floor`` may be left out."""
        m = len(queries)
        scores, ids = np.full((m, k), -np.inf), np.full((m, k), NO_ID)
        length = np.sqrt((queries**2).sum(axis=1))
        alive: dict[int, np.ndarray] = {self.root: np.arange(m)}
        if first_leaf_only:  # down the better child to one leaf for each query
            todo, at = [self.root], {self.root: np.arange(m)}
            while todo:
                node = todo.pop()
                who = at.pop(node)
                if self.children[node] is None:
                    self._score_leaf(node, who, queries, own, floor, scores, ids, k)
                    continue
                pair = list(self.children[node])
                better = self.bounds(queries[who], length[who], pair).argmax(axis=1)
                for side in (0, 1):
                    if (better == side).any():
                        at[pair[side]] = who[better == side]
                        todo.append(pair[side])
            return scores, ids
        # depth first by bound: the child that promises more goes first; floors rise on the way
        stack = [(self.root, alive[self.root], np.full(m, np.inf))]
        while stack:
            node, who, bound = stack.pop()
            keep = bound >= np.maximum(floor[who], scores[who, k - 1])
            who = who[keep]
            if not len(who):
                continue
            if self.children[node] is None:
                self._score_leaf(node, who, queries, own, floor, scores, ids, k)
                continue
            pair = list(self.children[node])
            limits = self.bounds(queries[who], length[who], pair)
            first = int(limits[:, 1].sum() > limits[:, 0].sum())
            for side in (1 - first, first):
                stack.append((pair[side], who, limits[:, side]))
        return scores, ids

    def _score_leaf(self, node, who, queries, own, floor, scores, ids, k) -> None:
        rows = self.leaves[self.leaf_of[node]]
        got = queries[who] @ self.points[rows].T
        names = self.ids[rows]
        got[own[who][:, None] == self.rows[rows][None, :]] = -np.inf
        best = got >= np.maximum(floor[who], scores[who, k - 1])[:, None]
        best &= got > -np.inf
        for j in np.flatnonzero(best.any(axis=1)):
            q, new = who[j], np.flatnonzero(best[j])
            s, i = np.concatenate([scores[q], got[j, new]]), np.concatenate([ids[q], names[new]])
            order = np.lexsort((i, -s))[:k]
            scores[q], ids[q] = s[order], i[order]


def _scan(k: int, first_leaf_only: bool):
    """Streams rows (shard, part, kind, ...): kind 0 holds the shard's vectors, kind 1 blocks of queries."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, trees = None, {}
        for batch in batches:
            for row in batch.to_pylist():
                key = (row["shard"], row["part"])
                if key != at:
                    at, trees = key, {}
                dim = row["dim"]
                ids, rows, values = np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["rows"], "<i8"), np.frombuffer(row["data"], "<i4").reshape(-1, dim).astype(float)
                if row["kind"] == 0:
                    trees[dim] = BallTree(values, ids, rows)
                    continue
                if dim not in trees:
                    continue
                floor = np.frombuffer(row["floor"], "<f8") if row["floor"] else np.full(len(ids), -np.inf)
                scores, found = trees[dim].search(values, rows, floor, k, first_leaf_only)
                q, r = np.nonzero(scores > -np.inf)
                yield pa.RecordBatch.from_arrays([pa.array(rows[q]), pa.array(ids[q]), pa.array(found[q, r]), pa.array(scores[q, r].astype(np.int64))], names=["row", "query_id", "vec_id", "score"])

    return run


def _packed(df: DataFrame, keys: list[str]) -> DataFrame:
    """One row for each key and dim: ids and integers of its vectors as bytes; keys bound the number of rows."""

    def pack(group: pa.Table) -> pa.Table:
        data = np.array(group.column("v").to_pylist(), "<i4")
        cols = [group.column(c).slice(0, 1) for c in [*keys, "dim"]]
        floor = group.column("floor").to_numpy().astype("<f8").tobytes() if "floor" in group.column_names else None
        longs = [pa.array([group.column(c).to_numpy().astype("<i8").tobytes()]) for c in ("vec_id", "row")]
        return pa.table([*cols, *longs, pa.array([data.tobytes()]), pa.array([floor], pa.binary())], names=[*keys, "dim", "ids", "rows", "data", "floor"])

    return df.groupBy(*keys, "dim").applyInArrow(pack, ", ".join(f"{k} long" for k in keys) + ", dim int, ids binary, rows binary, data binary, floor binary")


def whole_numbers(vectors: DataFrame, scale: float = SCALE) -> DataFrame:
    """vec_id, row (unlike for all rows), v (array of floor(scale*x)), dim: the vectors that take part."""
    sound = F.col("vec_id").isNotNull() & (F.size("embedding") > 0) & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    one = vectors.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("embedding")).where(sound).withColumnRenamed("embedding", "e")
    return one.select("vec_id", F.monotonically_increasing_id().alias("row"), F.transform("e", lambda x: F.floor(x * F.lit(scale)).cast("int")).alias("v"), F.size("e").alias("dim"))


def top_k(vectors: DataFrame, is_query: Column, k: int = K, shard_rows: int = SHARD_ROWS, block: int = BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score: the k largest inner products of every query, ties to the smaller id."""
    numbers = stored(whole_numbers(vectors), "vectors")
    n, q = numbers.agg(F.count(F.lit(1)), F.count_if(is_query)).first()
    shards, blocks = max(1, -(-n // shard_rows)), max(1, -(-q // block))
    groups = -(-blocks // BLOCKS_PER_GROUP)
    dealt = numbers.withColumn("shard", F.pmod(F.xxhash64("row"), F.lit(shards)))
    held = stored(_packed(dealt.select("shard", "vec_id", "row", "v", "dim"), ["shard"]), "shards")
    asked = numbers.where(is_query).withColumn("block", F.pmod(F.xxhash64("row", F.lit(7)), F.lit(blocks)))

    def against_all(packed: DataFrame, first_leaf_only: bool) -> DataFrame:
        part = F.pmod("block", F.lit(groups))
        queries = packed.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shards - 1).cast("long"))).alias("shard"), part.alias("part"), F.lit(1).alias("kind"), "dim", "ids", "rows", "data", "floor")
        points = held.select("shard", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("part"), F.lit(0).alias("kind"), "dim", "ids", "rows", "data", "floor")
        rows = points.unionByName(queries).repartition("shard", "part").sortWithinPartitions("shard", "part", "kind")
        return rows.mapInArrow(_scan(k, first_leaf_only), "row long, query_id long, vec_id long, score long")

    def best(found: DataFrame) -> DataFrame:
        w = Window.partitionBy("row").orderBy(F.desc("score"), "vec_id")
        return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)

    first = best(against_all(_packed(asked, ["block"]), True))
    floors = stored(first.where(F.col("rank") == k).select("row", F.col("score").cast("double").alias("floor")), "floors")
    bounded = asked.join(floors, "row", "left").withColumn("floor", F.coalesce("floor", F.lit(float("-inf"))))
    return best(against_all(_packed(bounded, ["block"]), False)).select("query_id", "rank", "vec_id", "score")


def op2_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


SQL = """
WITH v AS (
  SELECT row_number() OVER () AS n, vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.n, q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score FROM v q JOIN v c ON c.n <> q.n WHERE q.vec_id % 50 = 0
), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY n ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
