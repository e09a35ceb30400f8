import random

import numpy as np
import xxhash

from querygrade.llm.bit_slices import bit_planes, forest, lanes_to_bool, near_lanes
from querygrade.llm.simhash import hex_print, op4_simhash_near_dedup, print_links, simhash_groups


def brute_print(text, width=3):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << k for k in range(64) if sum(h >> k & 1 for h in hashes) * 2 > len(hashes))


def brute(rows, radius=2, width=3):
    prints = {i: brute_print(t, width) for i, t in rows}
    ids, root = sorted(prints), {}
    arr = np.array([prints[i] for i in ids], np.uint64)
    for i in ids:
        if i in root:
            continue
        root[i], todo = i, [prints[i]]
        while todo:
            q = todo.pop()
            for k in np.flatnonzero(np.bitwise_count(arr ^ np.uint64(q)) <= radius):
                if ids[k] not in root:
                    root[ids[k]] = i
                    todo.append(prints[ids[k]])
    return sorted((i, f"{prints[i]:016x}", root[i]) for i in ids)


def test_bit_slices_equal_popcount():
    rng = np.random.default_rng(1)
    for n, radius in ((1, 0), (63, 2), (64, 3), (200, 7), (130, 16)):
        base = rng.integers(0, 1 << 63, 3, np.uint64)
        prints = base[rng.integers(0, 3, n)] ^ (np.uint64(1) << rng.integers(0, 64, n).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, n).astype(np.uint64))
        got = lanes_to_bool(near_lanes(bit_planes(prints), prints, radius), n)
        assert (got == (np.bitwise_count(prints[:, None] ^ prints[None, :]) <= radius)).all()
    child, parent = forest(prints, 3)
    assert (np.bitwise_count(prints[child] ^ prints[parent]) <= 3).all()


def test_links_connect_what_is_near(spark):
    rng = np.random.default_rng(2)
    centre = rng.integers(0, 1 << 63, 6, np.uint64)
    prints = np.unique(np.concatenate([centre[rng.integers(0, 6, 900)] ^ (np.uint64(1) << rng.integers(0, 64, 900).astype(np.uint64)), rng.integers(0, 1 << 63, 200, np.uint64)]))
    df = spark.createDataFrame([(int(x),) for x in prints.view(np.int64)], "item long")
    for max_bucket in (8192, 20):
        from querygrade.llm.common import components

        got = {r.node: r.root for r in components(print_links(df, 2, max_bucket)).collect()}
        want = {}
        for x in prints.tolist():
            if x in want:
                continue
            todo, seen = [x], {x}
            while todo:
                q = todo.pop()
                for y in prints[np.bitwise_count(prints ^ np.uint64(q)) <= 2].tolist():
                    if y not in seen:
                        seen.add(y)
                        todo.append(y)
            for y in seen:
                want[y] = frozenset(seen)
        groups = {}
        for x in prints.tolist():
            s = int(np.array([x], np.uint64).view(np.int64)[0])
            groups.setdefault(got.get(s, s), set()).add(x)
        assert {frozenset(g) for g in groups.values()} == set(want.values())


def test_edge_cases(spark):
    rows = [(1, None), (2, ""), (3, " \t"), (4, "A b"), (5, "a B"), (6, "a b c d"), (7, "x " * 3000), (8, "x " * 2000), (8, "x " * 2000)]
    df = spark.createDataFrame([(i, t, "k") for i, t in rows], "doc_id long, text string, print string")
    got = sorted(tuple(r) for r in simhash_groups(df).select("doc_id", hex_print().alias("f"), "component_id").collect())
    assert [g for k, g in enumerate(got) if k == 0 or g != got[k - 1]] == brute(rows)
    assert len(got) == 9
    assert simhash_groups(spark.createDataFrame([], df.schema)).count() == 0
    assert simhash_groups(spark.createDataFrame([(None, "a"), (5, "a")], "doc_id long, text string")).where("component_id = 5").count() == 2


def test_query_against_brute_force(spark):
    sf = "/root/testdata/sf0.001"
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    assert sorted(map(tuple, op4_simhash_near_dedup(spark, sf).collect())) == brute(rows)
