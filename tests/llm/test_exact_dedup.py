import hashlib
import random
import re
from collections import defaultdict

from querygrade.llm.exact_dedup import exact_dedup


def brute(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[re.sub(r"[\x20\x09-\x0D]", "", t or "")].append((i, len(t or "")))
    out = []
    for norm, members in groups.items():
        keep = sorted(members, key=lambda m: (-m[1], m[0]))[0][0]
        out += [(i, keep, len(members), i == keep, hashlib.sha256(norm.encode()).hexdigest()) for i, _ in members]
    return sorted(out)


def rows():
    rng = random.Random(5)
    base = ["".join(rng.choice("ab é\n") for _ in range(rng.randrange(0, 12))) for _ in range(60)]
    return [(i, rng.choice([x, x.replace(" ", "  "), x + "\x0b"])) for i, x in enumerate(rng.choices(base, k=300))] + [(900, None), (901, ""), (902, " \t\r")]


def tuples(df):
    return sorted((r.doc_id, r.keep_id, r.group_size, r.kept, bytes(r.digest).hex()) for r in df.collect())


def test_one_trigger_and_many(spark):
    data = rows()
    df = spark.createDataFrame([(i, t, "x", 7) for i, t in data], "doc_id long, text string, digest string, row int").repartition(6)
    assert tuples(exact_dedup(df)) == brute(data)
    assert tuples(exact_dedup(df, files_per_trigger=2)) == brute(data)


def test_digest_collisions_are_told_apart_by_bytes(spark):
    data = rows()
    got = tuples(exact_dedup(spark.createDataFrame(data, "doc_id long, text string").repartition(3), digest_bytes=1))
    assert [g[:4] for g in got] == [b[:4] for b in brute(data)]


def test_repeated_rows_null_ids_and_empty(spark):
    df = spark.createDataFrame([(1, "a b"), (1, "a b"), (None, "ab"), (None, "a"), (2, "zz")], "doc_id long, text string")
    out = exact_dedup(df)
    got = sorted(((r.doc_id, r.keep_id, r.group_size, r.kept) for r in out.collect()), key=str)
    assert sorted(g[3] for g in got) == [False, False, True, True, True]
    assert [g for g in got if g[0] == 1] == [(1, 1, 3, False), (1, 1, 3, True)]
    assert exact_dedup(spark.createDataFrame([], df.schema)).count() == 0
