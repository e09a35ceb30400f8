import random

from querygrade.llm.toxicity import LexiconAutomaton, Scanner, learn, op7_toxicity


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
    return row[-1]


def test_automaton_equals_edit_distance():
    rng = random.Random(2)
    words = {w: 1.0 for w in ("trash", "idiot", "scum", "worthless", "aaaaabbbbb")}
    machine = LexiconAutomaton(words, {"vequ": 2.0})
    allowed = {w: 0 if len(w) < 5 else 1 if len(w) < 9 else 2 for w in words}
    for _ in range(3000):
        w = list(rng.choice(list(words)))
        for _ in range(rng.randrange(0, 4)):
            k = rng.randrange(len(w) + 1)
            w[k : k + rng.randrange(2)] = rng.choice(["", "a", "t", "z"])
        w = "".join(w)
        want = min((edits(w, t) for t in words if edits(w, t) <= allowed[t]), default=None)
        got = machine.match(w)
        assert (None if got is None else got[1]) == want, w
    assert machine.match("vequxyz")[:2] == (2.0, 0)
    assert machine.match("vexu") is None


def test_quotation_counts_apart():
    s = Scanner({"idiot": 1.0}, {})
    assert s.features('he said "such an idiot he is" and left')[2] > 0
    plain = s.features("you are an idiot and a bore")
    assert plain[0] > 0 and plain[2] == 0 and plain[5] > 0
    assert s.features(None) == s.features("") == [0.0] * 6


def test_edge_cases(spark):
    docs = spark.createDataFrame([(i, f"word{i} scumbag you scumbag" if i % 3 == 0 else f"word{i} hello there") for i in range(60)] + [(100, None), (101, ""), (None, "scumbag"), (5, "dup")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0), 0) for i in range(50)] + [(3, 0, 0), (7, None, 0), (None, 1, 1)], "doc_id long, toxic int, score int")
    got = learn(docs, labels).score(docs).collect()
    assert len(got) == 64
    assert all((r.score >= 0.3) == (r.doc_id % 3 == 0) for r in got if r.doc_id is not None and r.doc_id < 60)
    assert all(r.score < 0.3 for r in got if r.doc_id in (100, 101))
    none = learn(docs, labels.where("toxic = 0")).score(docs)
    assert {r.score for r in none.collect()} == {0.0}
    assert learn(docs.limit(0), labels.limit(0)).score(docs.limit(0)).count() == 0


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    got = op7_toxicity(spark, sf).where("held_out").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").collect()
    hit = sum(r.predicted == r.toxic for r in got) / len(got)
    recall = sum(r.predicted for r in got if r.toxic) / sum(r.toxic for r in got)
    assert len(got) > 500 and hit > 0.97 and recall > 0.9, (hit, recall)
