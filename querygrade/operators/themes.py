"""Themes: vectors, distances, Ward linkage, silhouette and the best number of clusters."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from querygrade.sources.tables import spread, written


#: Bytes of the vectors in a block.
BLOCK_BYTES = 1 << 20


def _matrix(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(rows filled up with zeros, their lengths); vectors that are null or hold null have length -1."""
    if column.null_count == 0 and column.values.null_count == 0 and len(set(np.diff(column.offsets))) == 1:
        x = column.flatten().to_numpy().reshape(len(column), -1)
        return x, np.full(len(x), x.shape[1])
    rows = [() if v is None else v for v in column.to_pylist()]
    size = np.array([-1 if v is None or None in v else len(v) for v in column.to_pylist()], np.int64)
    x = np.zeros((len(rows), max(map(len, rows), default=0)))
    for k in np.flatnonzero(size > 0):
        x[k, : size[k]] = rows[k]
    return x, size


def _packed(vectors: DataFrame, label: str, block_bytes: int) -> DataFrame:
    """Rows of ``vectors(id, v, label)`` in blocks of about ``block_bytes``: key, ids, labels, sizes, x (rows of doubles as bytes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k = TaskContext.get().partitionId(), 0
        for batch in batches:
            x, size = _matrix(batch.column(1))
            step = max(1, block_bytes // (8 * max(1, x.shape[1])))
            for a in range(0, batch.num_rows, step):
                at = slice(a, a + step)
                key, rows = pa.array([part << 32 | k], pa.int64()), len(size[at])
                lists = [pa.ListArray.from_arrays(pa.array([0, rows], pa.int32()), c) for c in (batch.column(0).slice(a, rows), batch.column(2).slice(a, rows), pa.array(size[at], pa.int64()))]
                yield pa.RecordBatch.from_arrays([key, *lists, pa.array([np.ascontiguousarray(x[at]).tobytes()], pa.binary())], names=["key", "ids", "labels", "sizes", "x"])
                k += 1

    typed = vectors.where("id is not null").select(F.col("id").cast("long"), F.col("v").cast("array<double>"), F.col("label").cast(label))
    return written(typed.mapInArrow(run, f"key long, ids array<long>, labels array<{label}>, sizes array<long>, x binary"), "vector-blocks")


def _met(left: DataFrame, right: DataFrame, of: Callable, shape: str, once: bool) -> DataFrame:
    """What ``of`` yields for every pair of blocks (with ``once``, two different blocks meet once); tasks hold few blocks at once."""
    a, b = (side.select(*[F.col(c).alias(f"{n}_{c}") for c in side.columns]) for n, side in (("a", spread(left)), ("b", right)))
    # either order of two blocks, by the parity of their keys, so that all tasks have as much to do
    pairs = a.join(b, F.expr("a_key = b_key OR (a_key < b_key) = (pmod(a_key + b_key, 2) = 0)")) if once else a.crossJoin(b)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                sides = []
                for at in (0, 5):
                    ids, labels, size = (batch.column(at + c)[k].values for c in (1, 2, 3))
                    x = np.frombuffer(batch.column(at + 4)[k].as_buffer(), float).reshape(len(ids), -1)
                    sides.append((ids.to_numpy(), labels, size.to_numpy(), x))
                width = max(s[3].shape[1] for s in sides)
                sides = [(*s[:3], np.pad(s[3], ((0, 0), (0, width - s[3].shape[1])))) for s in sides]
                yield from of(*sides, batch.column(0)[k].as_py() == batch.column(5)[k].as_py())

    return pairs.mapInArrow(run, shape)


def _apart(left: tuple, right: tuple, same: bool, once: bool) -> Iterator[pa.RecordBatch]:
    """i, j, d of two blocks, summed in the order of the components."""
    (i, _, m, x), (j, _, n, y) = left, right
    columns = np.ascontiguousarray(y.T)
    step = max(1, (1 << 17) // max(1, len(j)))
    for a in range(0, len(i), step):
        part = slice(a, a + step)
        square = np.zeros((len(i[part]), len(j)))
        for k in range(len(columns)):
            gap = x[part, k, None] - columns[k]
            square += np.multiply(gap, gap, out=gap)
        p, q = np.nonzero(i[part, None] != j)
        if once and same:
            p, q = p[p + a < q], q[p + a < q]
        one, two = i[part][p], j[q]
        if once:
            one, two = np.minimum(one, two), np.maximum(one, two)
        known = (m[part][p] == n[q]) & (n[q] >= 0)
        yield pa.RecordBatch.from_arrays([pa.array(one), pa.array(two), pa.array(np.sqrt(square[p, q]), mask=~known)], names=["i", "j", "d"])


def pairwise_distance(vectors: DataFrame, queries: DataFrame | None = None, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """i, j, d (i < j) of ``vectors(id, v)``; with ``queries(id, v)``, of each query i and every row j of another id.

    Blocks of rows meet in pairs, so no task holds more than a few blocks.  Vectors that are null, hold null or
    differ in length have a null distance."""
    plain = lambda df: _packed(df.select("id", "v", F.lit(None).alias("label")), "int", block_bytes)
    rows, shape = plain(vectors), "i long, j long, d double"
    if queries is None:
        return _met(rows, rows, lambda a, b, same: _apart(a, b, same, True), shape, True)
    return _met(rows, plain(queries), lambda row, asked, same: _apart(asked, row, same, False), shape, False)


def silhouette(distances: DataFrame, labels: DataFrame) -> DataFrame:
    """id, label, s from distances (i, j, d) and labels (id, label); members of singletons score 0."""
    both = distances.select("i", "j", "d").unionByName(distances.select(F.col("j").alias("i"), F.col("i").alias("j"), "d"))
    of_i, of_j = labels.select(F.col("id").alias("i"), F.col("label").alias("own")), labels.select(F.col("id").alias("j"), "label")
    return _silhouette_of(both.join(of_i, "i").join(of_j, "j").groupBy("i", "own", "label").agg(F.avg("d").alias("m")))


def _silhouette_of(mean: DataFrame) -> DataFrame:
    """id, label, s from the mean distance m of i (labelled own) to the members of each label."""
    ab = mean.groupBy("i", "own").agg(F.min(F.when(F.col("label") == F.col("own"), F.col("m"))).alias("a"), F.min(F.when(F.col("label") != F.col("own"), F.col("m"))).alias("b"))
    s = F.when(F.col("a").isNull() | F.col("b").isNull(), 0.0).otherwise(F.try_divide(F.col("b") - F.col("a"), F.greatest("a", "b")))
    return ab.select(F.col("i").alias("id"), F.col("own").alias("label"), F.coalesce(s, F.lit(0.0)).alias("s"))


def _distance_matrix(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Distances by inner products; near pairs, whose digits these would cancel, by differences."""
    scale = (x * x).sum(1)[:, None] + (y * y).sum(1)
    square = scale - 2 * (x @ y.T)
    p, q = np.nonzero(~(square > 1e-4 * scale))
    for k in range(0, len(p), 1 << 14):
        at = p[k : k + (1 << 14)], q[k : k + (1 << 14)]
        square[at] = ((x[at[0]] - y[at[1]]) ** 2).sum(1)
    return np.sqrt(square, out=square)


def _label_sums(left: tuple, right: tuple, same: bool) -> Iterator[pa.RecordBatch]:
    """i, own, label, s, known, n: sums of distances of each row of a block to each label of the other, both ways unless they are one."""
    for (i, own, m, x), (j, label, n, y) in ((left, right), (right, left))[: 1 if same else 2]:
        coded = label.dictionary_encode()
        code = coded.indices.fill_null(len(coded.dictionary)).to_numpy()
        order = np.argsort(code, kind="stable")
        codes, starts = np.unique(code[order], return_index=True)
        names = label.take(pa.array(order[starts]))
        j, n, y = j[order], n[order], y[order]
        step = max(1, (1 << 18) // max(1, len(j)))
        for a in range(0, len(i), step):
            part = slice(a, a + step)
            other = i[part, None] != j
            known = other & (m[part, None] == n) & (n >= 0)
            d = np.where(known, _distance_matrix(x[part], y), 0.0)
            sums = [np.add.reduceat(v, starts, axis=1, dtype=t) for v, t in ((d, float), (known, np.int64), (other, np.int64))]
            p, q = np.nonzero(sums[2])
            yield pa.RecordBatch.from_arrays([pa.array(i[part][p]), own.slice(a, len(i[part])).take(pa.array(p)), names.take(pa.array(q)), *[pa.array(v[p, q]) for v in sums[:2]]], names=["i", "own", "label", "s", "known"])


def label_silhouette(vectors: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """id, label, s of ``vectors(id, v, label)``, as :func:`silhouette` of all their distances, which are summed by label as they arise.

    Blocks hold rows of few labels, so a row has about a sum for each label and block."""
    kind = vectors.schema["label"].dataType.simpleString()
    blocks = _packed(vectors.repartitionByRange("label", "id").sortWithinPartitions("label", "id"), kind, block_bytes)
    sums = _met(blocks, blocks, _label_sums, f"i long, own {kind}, label {kind}, s double, known long", True)
    return _silhouette_of(sums.groupBy("i", "own", "label").agg(F.try_divide(F.sum("s"), F.sum("known")).alias("m")))


def ward_merges(x: np.ndarray) -> list[tuple[int, int, float, int]]:
    """(a, b, height, size) of each merge; new clusters are numbered from n on.  Lance-Williams on squared distances."""
    n = len(x)
    d = ((x[:, None] - x[None]) ** 2).sum(-1).astype(float)
    np.fill_diagonal(d, np.inf)
    size, name, live, out = np.ones(n), np.arange(n), list(range(n)), []
    for step in range(n - 1):
        sub = d[np.ix_(live, live)]
        k = int(sub.argmin())
        i, j = live[k // len(live)], live[k % len(live)]
        height = float(np.sqrt(d[i, j]))
        for m in live:
            if m not in (i, j):
                t = size[i] + size[j] + size[m]
                d[i, m] = d[m, i] = ((size[i] + size[m]) * d[i, m] + (size[j] + size[m]) * d[j, m] - size[m] * d[i, j]) / t
        out.append((int(min(name[i], name[j])), int(max(name[i], name[j])), height, int(size[i] + size[j])))
        size[i] += size[j]
        name[i] = n + step
        live.remove(j)
    return out


def cut_tree(merges: list[tuple[int, int, float, int]], k: int) -> list[int]:
    """Labels 0..k-1 of the leaves after all but the last k-1 merges."""
    n = len(merges) + 1
    root = list(range(2 * n - 1))

    def find(a: int) -> int:
        while root[a] != a:
            a = root[a]
        return a

    for step, (a, b, _, _) in enumerate(merges[: n - k]):
        root[find(a)] = root[find(b)] = n + step
    names: dict[int, int] = {}
    return [names.setdefault(find(a), len(names)) for a in range(n)]


def _score(d: np.ndarray, labels: np.ndarray) -> float:
    s = []
    for i, own in enumerate(labels):
        same = labels == own
        if same.sum() < 2:
            s.append(0.0)
            continue
        a = d[i, same].sum() / (same.sum() - 1)
        b = min(d[i, labels == c].mean() for c in set(labels.tolist()) - {own})
        s.append((b - a) / max(a, b) if max(a, b) else 0.0)
    return float(np.mean(s))


def centroids(vectors: DataFrame, most: int) -> DataFrame:
    """id, v: at most ``most`` cluster centres of all rows, by bisecting k-means."""
    from pyspark.ml.clustering import BisectingKMeans
    from pyspark.ml.functions import array_to_vector

    model = BisectingKMeans(k=most, seed=1, maxIter=8).fit(vectors.select(array_to_vector("v").alias("features")))
    rows = [(k, [float(x) for x in c]) for k, c in enumerate(model.clusterCenters())]  # most rows
    return vectors.sparkSession.createDataFrame(rows, "id long, v array<double>")


def theme_clusters(vectors: DataFrame, low: int = 2, high: int = 16, most: int = 256) -> DataFrame:
    """k, silhouette, chosen for Ward cuts of all rows; beyond ``most`` rows, of the centres that bisecting k-means gives them."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        x = np.array(group.sort_values("id")["v"].tolist(), float)
        merges, d = ward_merges(x), np.sqrt(((x[:, None] - x[None]) ** 2).sum(-1))
        ks = [k for k in range(low, high + 1) if k < len(x)]
        scores = [_score(d, np.array(cut_tree(merges, k))) for k in ks]
        best = int(np.argmax(scores)) if scores else -1
        return pd.DataFrame({"k": ks, "silhouette": scores, "chosen": [int(i == best) for i in range(len(ks))]})

    few = vectors if vectors.limit(most + 1).count() <= most else centroids(vectors, most)
    return few.withColumn("one_group", F.lit(0)).groupBy("one_group").applyInPandas(run, "k int, silhouette double, chosen int")


def word_vectors(docs: DataFrame, size: int = 32, parts: int | None = None) -> DataFrame:
    """Mean word vectors of texts ``docs(id, text)`` by Word2Vec after stop words are dropped.

    All texts are learnt from in ``parts`` partitions at once (as many as the session has cores), whose vectors are averaged."""
    from pyspark.ml.feature import RegexTokenizer, StopWordsRemover, Word2Vec
    from pyspark.ml.functions import vector_to_array

    words = RegexTokenizer(inputCol="text", outputCol="words", pattern=r"\W+").transform(spread(docs))
    kept = written(StopWordsRemover(inputCol="words", outputCol="kept").transform(words).select("id", "kept"), "kept-words")
    model = Word2Vec(vectorSize=size, minCount=5, seed=1, inputCol="kept", outputCol="vector", numPartitions=parts or docs.sparkSession.sparkContext.defaultParallelism).fit(kept)
    return model.transform(kept).select("id", vector_to_array("vector").alias("v"))


def name_clusters(labels: DataFrame, names: DataFrame) -> DataFrame:
    """``labels(id, cluster)`` with the name that ``names(cluster, name)`` gives; unnamed clusters are called by number.

    A cluster named more than once takes its least name."""
    one = names.where("name is not null").groupBy("cluster").agg(F.min("name").alias("name"))
    return labels.join(one, "cluster", "left").withColumn("name", F.coalesce("name", F.concat(F.lit("cluster "), F.col("cluster").cast("string"))))
