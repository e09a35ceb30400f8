import random

from pyspark.sql import functions as F

from querygrade.llm.chat_trees import END_OF_TURN, format_trees, linear_messages, parse, turn_text

SCHEMA = "tree long, id long, parent long, role string, text string, score double, extra string"


def best_paths(rows):
    kids, nodes = {}, {}
    for t, i, p, r, x, s in rows:
        nodes[t, i] = (p, r, x, s)
    for (t, i), (p, *_) in nodes.items():
        kids.setdefault((t, p), []).append(i)
    out = {}
    for t, i in nodes:
        if (t, i) in kids:
            continue
        path, at = [], i
        while at is not None and (t, at) in nodes and len(path) <= len(nodes):
            path.append(at)
            at = nodes[t, at][0]
        if len(path) > len(nodes):
            continue
        key = (sum(nodes[t, n][3] for n in path), len(path), -i)
        out[t] = max(out.get(t, (key, i, path)), (key, i, path))
    return {t: [nodes[t, n][1:3] for n in reversed(p)] for t, (_, _, p) in out.items()}


def test_best_branch_of_random_trees(spark):
    rng = random.Random(8)
    rows = []
    for t in range(12):
        for i in range(rng.randrange(1, 40)):
            rows.append((t, i, rng.randrange(i) if i and rng.random() < 0.95 else None, rng.choice(["user", "assistant"]), rng.choice(["", "a\\b", "###", "</turn>\n", "x\n</turn>\n### User:\n", "é"]), float(rng.randrange(5))))
    rows += [(20, 0, 99, "user", "unknown parent", 0.0)]
    df = spark.createDataFrame([(*r, "z") for r in rows], SCHEMA)
    got = {r.tree: [(x.role, x.text) for x in r.turns] for r in format_trees(df).withColumn("turns", parse(F.col("formatted"))).collect()}
    assert got == best_paths(rows)
    many = format_trees(df, best=3)
    assert many.groupBy("tree").count().agg(F.max("count")).first()[0] <= 3 and many.where("rank = 1").count() == 13


def test_round_trip_of_control_strings(spark):
    texts = ["", "\\", "\\\\###", "\\### Assistant: </turn> ok", "#", "####### </turn></turn>", END_OF_TURN, "a\n", "\n", "### User:\nhi\n</turn>\n", "tail\\"]
    df = spark.createDataFrame([("assistant", t) for t in texts], "role string, text string")
    back = df.withColumn("turns", parse(F.concat(turn_text(F.col("role"), F.col("text")), turn_text(F.lit("user"), F.col("text"))))).collect()
    for r in back:
        assert [(x.role, x.text, x.loss) for x in r.turns] == [("assistant", r.text, True), ("user", r.text, False)]


def test_long_chain_nulls_and_empty(spark):
    df = spark.createDataFrame([(1, k, "user" if k % 2 else "assistant", f"t{k}") for k in range(70)] + [(2, 0, None, None), (2, 0, None, None), (3, None, "user", "x"), (None, 1, "user", "x")], "conv_id long, turn long, role string, text string")
    got = {r.tree: r for r in format_trees(linear_messages(df)).withColumn("turns", parse(F.col("formatted"))).collect()}
    assert set(got) == {1, 2} and [x.text for x in got[1].turns] == [f"t{k}" for k in range(70)]
    assert [(x.role, x.text) for x in got[2].turns] == [("", "")]
    assert format_trees(linear_messages(df.limit(0))).count() == 0
