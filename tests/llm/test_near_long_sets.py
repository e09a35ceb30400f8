"""Long sets that meet but differ are left out before their shingles are read."""

import numpy as np

from querygrade.llm.near_documents import PARITY, may_be_similar, parity_sketch, wide_sketch


def test_long_sets_that_differ_are_left_out_and_similar_ones_are_kept():
    rng = np.random.default_rng(5)
    sets, want = [], []
    for size in (1500, 4000, 9000, 20000):
        for share in (0.0, 0.3, 0.6, 0.8, 0.83, 1.0):  # similarity of the two
            both = round(share * size)
            hashes = rng.integers(0, 1 << 63, 2 * size, dtype=np.int64).astype(np.uint64)
            own = (size - both) // 2
            left, right = hashes[: both + own], np.concatenate([hashes[:both], hashes[both + own : both + 2 * own]])
            sets += [np.unique(left), np.unique(right)]
            want.append(share >= 0.8)
    sizes = np.array([len(x) for x in sets])
    parity = np.array([np.frombuffer(parity_sketch(x), np.uint64) for x in sets])
    wide = np.array([*[wide_sketch(x) for x in sets], None], object)[:-1]
    a, b = np.arange(0, len(sets), 2), np.arange(1, len(sets), 2)
    assert may_be_similar(sizes, parity, a, b, 0.8).sum() > sum(want)  # the short sketch is full
    assert may_be_similar(sizes, parity, a, b, 0.8, wide).tolist() == want


def test_sketches_of_two_widths_are_folded():
    rng = np.random.default_rng(6)
    long = np.unique(rng.integers(0, 1 << 63, 4300, dtype=np.int64).astype(np.uint64))
    sets = [long, long[:4000], np.unique(rng.integers(0, 1 << 63, 4000, dtype=np.int64).astype(np.uint64)), long[:PARITY]]
    wide = np.array([wide_sketch(x) for x in sets], object)
    assert [len(x) * 8 if x else 0 for x in wide] == [8192, 4096, 4096, 0]
    parity = np.array([np.frombuffer(parity_sketch(x), np.uint64) for x in sets])
    got = may_be_similar(np.array([len(x) for x in sets]), parity, np.array([0, 0, 0]), np.array([1, 2, 3]), 0.8, wide)
    assert got.tolist() == [True, False, False]
