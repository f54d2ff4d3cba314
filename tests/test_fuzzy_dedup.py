"""Near copies that share a bucket with a least id that is like neither of them."""

import hashlib
import random
from itertools import combinations

from webtext.operators import components as K
from webtext.operators import corpus as C


def test_links_between_members_that_are_not_near_the_least_id(spark, monkeypatch):
    monkeypatch.setattr(C, "LEADER_ROUNDS", 1, raising=False)
    rng = random.Random(4)
    say = lambda n: [f"w{rng.randrange(10**6)}" for _ in range(n)]
    shared, texts = say(40), {}
    for family in range(12):
        own = say(40)
        for copy in range(3):
            texts[3 * family + copy] = " ".join([*shared, *own, f"end{copy}"])
    grams = {i: {" ".join(w[k : k + 5]) for k in range(len(w) - 4)} for i, w in ((i, t.split()) for i, t in texts.items())}
    bucket = {i: min(int(hashlib.md5(f"0:{g}".encode()).hexdigest()[:15], 16) for g in s) for i, s in grams.items()}
    near = [(i, j) for i, j in combinations(texts, 2) if bucket[i] == bucket[j] and len(grams[i] & grams[j]) / len(grams[i] | grams[j]) >= 0.8]
    want = {i: i for i in texts}
    for i, j in near:
        want[j] = min(want[j], want[i])
    stars = {min(i for i in texts if bucket[i] == h) for h in bucket.values()}
    assert any(i not in stars and j not in stars for i, j in near)
    got = {r.doc_id: r.comp for r in C.fuzzy_dedup(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), 1, 1, 0.8, portable=True).collect()}
    assert got == want


def test_copies_are_sketched_once_and_joined_in_few_jobs(spark):
    """Copies are one node, null texts stay alone (as in the SQL), and small inputs need few jobs: the driver keeps figures of each."""
    texts = ["a b c d e f g h"] * 5 + [None, None, "", " ", "x y", "X  y"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sc = spark.sparkContext
    sc.setJobGroup("fuzzy", "fuzzy")
    got = {r.doc_id: r.comp for r in C.fuzzy_dedup(docs, 8, 4, 0.8, portable=True).collect()}
    jobs = len(sc.statusTracker().getJobIdsForGroup("fuzzy"))
    sc.setLocalProperty("spark.jobGroup.id", None)
    assert got == {0: 0, 1: 0, 2: 0, 3: 0, 4: 0, 5: 5, 6: 6, 7: 7, 8: 7, 9: 9, 10: 9}
    assert jobs < 30


def test_portable_minima_are_those_of_the_native_ones(spark):
    for text in ("", "one two", "a b c d e f a b c d e f g", "Ünï  cödé\twords in\na line of text"):
        row = C.minhash(spark.createDataFrame([(1, text)], "doc_id long, text string"), 4, portable=True).first()
        assert row.sig == C._md5_minima(text.lower().encode().split(), 4)


def test_components_by_rounds_and_in_one_task_agree(spark, monkeypatch):
    rng = random.Random(7)
    edges = [(rng.randrange(400), rng.randrange(400)) for _ in range(220)] + [(k, k + 1) for k in range(1000, 1060)]
    df = spark.createDataFrame(edges, "u long, v long")
    want = K.least_labels([e for e in edges if e[0] != e[1]])
    assert {r.node: r.comp for r in K.components(df).collect()} == want
    monkeypatch.setattr(K, "ONE_TASK_EDGES", 0)
    assert {r.node: r.comp for r in K.components(df).collect()} == want


def test_sets_differ_in_at_least_as_many_elements_as_parity_bits():
    rng = random.Random(9)
    for n in (5, 50, 500):
        a = [rng.randrange(2**64) for _ in range(n)]
        x, y = (C.np.array(sorted(set(v)), C.np.uint64) for v in (a, a[n // 4 :] + [rng.randrange(2**64)]))
        bits = sum(int(v).bit_count() for v in (C.parity(x) ^ C.parity(y)).view(C.np.uint64))
        assert 0 < bits <= len(set(x.tolist()) ^ set(y.tolist()))
