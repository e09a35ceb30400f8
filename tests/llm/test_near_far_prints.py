import random

from querygrade.llm.near_documents import RADIUS, near_groups
from querygrade.llm.simhash import majority_bits, shingle_hashes
from tests.llm.test_pipeline import brute, make_rows


def far(a, b):
    return bin(majority_bits(shingle_hashes(a.encode(), 5)) ^ majority_bits(shingle_hashes(b.encode(), 5))).count("1") > RADIUS


def test_similar_pairs_with_far_fingerprints_are_found(spark):
    rng = random.Random(3)
    word = lambda: "v" + str(rng.randrange(10**6))
    rows = []

    def add(a, b):
        rows.extend([(len(rows), a), (len(rows) + 1, b)])
        return far(a, b)

    beyond = 0
    for _ in range(40):  # repeats weigh in a fingerprint but not in a set
        body, line = " ".join(word() for _ in range(100)), " ".join(word() for _ in range(8))
        beyond += add(" ".join([body, *[line] * 2]), " ".join([body, *[line] * 40]))
    for _ in range(300):  # four of five shingles
        words = [word() for _ in range(9)]
        beyond += add(" ".join(words[:8]), " ".join(words))
    assert beyond > 5
    want = brute([r for r in rows])
    assert all(want[i] == i - i % 2 for i in want)
    got = {r.node: r.root for r in near_groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    assert got == want


def test_hot_buckets_in_chunks_give_the_same_groups(spark):
    rows = make_rows(160)
    rows += [(2000 + k, (t or "").upper()) for k, (_, t) in enumerate(rows[:12])]  # equal sets
    want = brute(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for hot in (8, 40):
        got = {r.node: r.root for r in near_groups(df, hot=hot).collect()}
        assert {i: got.get(i, i) for i in want} == want


def test_recall_over_thousands_of_pairs_and_short_texts(spark):
    rng = random.Random(11)
    rows, want = [], 0
    for _ in range(1500):
        words = [f"u{rng.randrange(10**7)}" for _ in range(rng.choice((6, 9, 14, 30, 60, 120, 300)))]
        other = list(words)
        for _ in range(max(1, len(words) // 90)):
            other[rng.choice((0, -1, rng.randrange(len(words))))] = "z"
        rows += [(len(rows), " ".join(words)), (len(rows) + 1, " ".join(other))]
    pairs = {i for i in range(0, len(rows), 2) if len(brute(rows[i : i + 2])) == 2 and brute(rows[i : i + 2])[i + 1] == i}
    got = {r.node: r.root for r in near_groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    found = {i for i in range(0, len(rows), 2) if got.get(i + 1) == i}
    assert len(pairs) > 400 and found <= pairs
    assert len(found) >= 0.99 * len(pairs)
