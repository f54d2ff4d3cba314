"""Pre-processing, propagation, measures and samples by hand-made pages and brute force."""

import os
import random
from collections import Counter

import duckdb
import pytest

from webtext.functions import measures as PM
from webtext.functions.blocks import Config, block_rows
from webtext.functions.scoring import lexicon
from webtext.operators import corpus as C
from webtext.operators import measures as M
from webtext.operators import templates as T
from webtext.plans import CATALOGUE
from webtext.plans import evaluation as E

SF = "/root/testdata/sf0.001"
PAGE = "<html><body><header><div class=top>Site of many words that stand above all</div></header><main><p>The text of the page, which is long enough to be kept as it is.</p></main><aside><p>An aside with a sentence of its own.</p></aside></body></html>"


def test_headers_and_asides_are_not_seen_by_the_model():
    listed, none = (block_rows(PAGE, Config(drop=d)) for d in ("listed", "none"))
    assert [r["simplified"] != "" for r in listed[2]] == [False, True, False] and all(r["simplified"] for r in none[2])
    assert [r["raw_html"] for r in listed[2]] == [r["raw_html"] for r in none[2]]  # the mapping view keeps them
    assert [m > o for o, m in lexicon(listed[1])] == [False, True, False]


def test_common_subsequence_by_table():
    rng = random.Random(4)
    for _ in range(200):
        a, b = ([rng.choice("abcd") for _ in range(rng.randint(0, 90))] for _ in range(2))
        row = [0] * (len(b) + 1)
        for x in a:
            before = 0
            for j, y in enumerate(b, 1):
                before, row[j] = row[j], before + 1 if x == y else max(row[j], row[j - 1])
        assert PM.common_subsequence(a, b) == row[-1]
    assert PM.rouge_l([], []) == 1.0 and PM.rouge_l(["a"], []) == 0.0


def test_uncovered_pages_are_labelled_in_a_second_round(spark):
    pages = spark.createDataFrame([(k, f"http://h.net/{k}", PAGE) for k in range(3)], "page_id long, url string, html string")
    idx = T.clusters(T.index(pages))
    rules = T.cluster_rules(pages, T.representatives(idx)).where("selector = 'none of them'")
    one = T.propagate(pages, idx, rules, second=None).collect()
    two = T.propagate(pages, idx, rules).collect()
    assert all(r.n_uncovered == r.n_blocks and r.main_text == "" and not r.relabelled for r in one)
    assert all(r.relabelled and "long enough to be kept" in r.main_text for r in two)


def test_mixed_tokens_split_texts_without_blanks(spark):
    x = spark.createDataFrame([(1, "中文abc字 Été, x1", "中文abd字 Été, x1"), (2, "", None), (3, "中" * 30, "中" * 30)], "page_id long, pred string, gold string")
    got = {r.page_id: r for r in x.select("page_id", M.tokens("pred", "mixed").alias("a")).collect()}
    assert got[1].a == ["中", "文", "abc", "字", "été", ",", "x1"] and len(got[3].a) == 30
    f1 = {r.page_id: r.f1 for r in M.rouge(x.where("gold is not null"), n=2).collect()}
    assert f1[3] == 1.0 and f1[1] == pytest.approx(4 / 6)


@pytest.mark.parametrize("name", ["hybrid_sample", "fn_variant", "xpath_wellformed", "win_running_tokens", "q_gram_repetition", "benchmark_overlap", "rouge5_rulebook", "block_confusion", "formula_scan", "media_units"])
def test_query_equals_sql(spark, name):
    q, con = CATALOGUE[name], duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    df, cur = q.run(spark, SF), con.execute(q.sql)
    names = [d[0] for d in cur.description]
    plain = lambda v: round(v, 5) if isinstance(v, float) else v
    assert sorted(names) == sorted(df.columns)
    assert sorted(repr([plain(float(r[n]) if isinstance(r[n], float) else r[n]) for n in names]) for r in df.collect()) == sorted(repr([plain(v) for v in r]) for r in cur.fetchall())


def test_ratio_against_the_density_corpus_by_hand(spark):
    got = {r.page_id: r for r in CATALOGUE["density_length_ratio"].run(spark, SF).collect()}
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    a, b = ({r.page_id: len(r.pred) for r in E.METHODS[m](pages).collect()} for m in ("labelled", "density"))
    assert set(got) == set(a)
    bins = Counter()
    for i, r in got.items():
        ratio = (a[i] - b[i]) / max(a[i], b[i], 1)
        assert (r.len_a, r.len_b) == (a[i], b[i]) and r.ratio == pytest.approx(ratio, abs=1e-6)
        bins[min(19, int((round(ratio, 6) + 1) * 10))] += 1
    assert {r.bin: r.n for r in CATALOGUE["density_ratio_histogram"].run(spark, SF).collect()} == dict(bins)


def test_characters_of_blocks_are_weighed(spark):
    r = CATALOGUE["char_confusion"].run(spark, SF).first()
    assert r.tp > 0 and r.tn > 0 and r.f1 == pytest.approx(2 * r.p * r.r / (r.p + r.r), abs=1e-5) and C.gram_shares(spark.createDataFrame([], "doc_id long, text string")).count() == 0


@pytest.mark.parametrize("rounds", [0, 1])
def test_template_clusters_lose_no_link(spark, monkeypatch, rounds):
    """Against all pairs: signatures that drift apart step by step, in one band of one host."""
    import random

    from webtext.operators import templates

    monkeypatch.setattr(templates, "LEADER_ROUNDS", rounds)
    rng, rows = random.Random(5), []
    for family in range(3):
        sig = [rng.randrange(1000) for _ in range(16)]
        for step in range(7):
            sig = sig[:2] + [rng.randrange(1000) if rng.random() < 0.15 else x for x in sig[2:]]
            rows.append((len(rows), "h" if family else "g", f"s{len(rows)}", list(sig)))
    idx = spark.createDataFrame(rows, "page_id long, host string, sig string, minhash array<long>")
    got = {r.page_id: r.cluster_id for r in templates.clusters(idx, "lsh").collect()}
    comp = {r[0]: r[0] for r in rows}
    for a in rows:
        for b in rows:
            same = [x == y for x, y in zip(a[3], b[3])]
            if a[1] == b[1] and sum(same) >= 0.8 * 16 and any(same[k] and same[k + 1] for k in range(0, 16, 2)):
                lo, hi = sorted((comp[a[0]], comp[b[0]]))
                comp = {k: lo if v == hi else v for k, v in comp.items()}
    assert len(set(comp.values())) > 3 and len(set(got.values())) == len(set(comp.values())) == len(set(zip(got.values(), (comp[k] for k in got))))


def test_rouge_of_rows_by_hand(spark):
    rng = random.Random(9)
    rows = [(k, *(" ".join(rng.choice("ab.") for _ in range(rng.randint(0, 30))) for _ in range(2))) for k in range(80)] + [(80, None, "a b"), (81, None, None), (82, "汉字", "汉字 x"), (80, "a", "a")]
    df = spark.createDataFrame(rows, "page_id long, pred string, gold string")
    got = Counter((r.page_id, r.p, r.r, r.f1) for r in M.rouge(df, n=3).collect())
    want = Counter((k, *(round(v, 6) for v in PM.rouge_n(PM.tokens(a), PM.tokens(b), 3))) for k, a, b in rows)
    assert got == want
    plan = M.rouge(df)._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert "Exchange" not in plan


def test_edit_distance_by_table():
    rng = random.Random(2)
    for _ in range(300):
        a, b = ("".join(rng.choice("abc") for _ in range(rng.randint(0, 12))) for _ in range(2))
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        assert PM.edit_distance(a, b) == row[-1]


def test_elements_meet_their_best_partner():
    assert PM.aligned([], []) == 1.0 and PM.aligned(["x"], []) == 0.0 and PM.aligned([], ["x"]) == 0.0
    assert PM.aligned(["b", "a"], ["a", "b"]) == 1.0  # order does not matter
    assert PM.aligned(["abcd"], ["abcd", "abcd"]) == 0.5  # a partner serves once
    assert PM.aligned(["abcx", "zz"], ["abcd", "zz", "q"]) == pytest.approx((0.75 + 1) / 3)


def test_a_win_by_place_is_a_tie():
    assert PM.judged("x", "y", lambda a, b: "first") == ("tie", False)
    longer = lambda a, b: "tie" if len(a) == len(b) else "first" if len(a) > len(b) else "second"
    assert [PM.judged(a, b, longer) for a, b in (("xx", "y"), ("x", "yy"), ("x", "y"))] == [("a", True), ("b", True), ("tie", True)]
    stop = frozenset(("the", "of"))
    assert PM.blind_score("The end of the long story\nHome About", stop) == 4 and PM.blind_score(None, stop) == 0


def test_ngram_model_by_counting(spark):
    import math

    rng = random.Random(5)
    train, held = ([" ".join(rng.choice("abcd") for _ in range(rng.randint(0, 12))) for _ in range(n)] for n in (30, 8))
    frames = [spark.createDataFrame([(x,) for x in xs] + [(None,)], "text string") for xs in (train, held)]
    words = [x.split() for x in train]
    uni = Counter(w for x in words for w in x)
    for order in (1, 2, 3):
        bits, n = 0.0, 0
        for x in held:
            x = x.split()
            for i, w in enumerate(x):
                p = (uni[w] + 0.5) / (uni.total() + 0.5 * (len(uni) + 1))
                for k in range(2, min(order, i + 1) + 1):
                    gram, history = x[i - k + 1 : i + 1], x[i - k + 1 : i]
                    c = sum(y[j : j + k] == gram for y in words for j in range(len(y) - k + 1))
                    h = sum(y[j : j + k - 1] == history for y in words for j in range(len(y) - k + 1))
                    p = (c + 2 * p) / (h + 2)
                bits, n = bits - math.log2(p), n + 1
        got = M.ngram_cross_entropy(*frames, order=order).first().bits
        assert got == pytest.approx(bits / n, abs=1e-4)
    assert M.ngram_cross_entropy(*frames, order=1).first().bits == M.cross_entropy(*frames).first().bits


def test_code_formulas_and_tables_are_content():
    from webtext.functions.content import units

    pages = {
        "code": "<p>Run this:</p><pre><code>x = 1</code></pre><p>Done.</p>",
        "display_formula": '<p>Then</p><script type="math/tex; mode=display">a + b</script><p>holds.</p>',
        "table": "<p>See.</p><table><tr><th>a</th></tr><tr><td>1</td></tr></table>",
    }
    for kind, body in pages.items():
        main = E.labelled_html(f'<html><body><ul class="nav"><li><a href="/">Home</a></li></ul>{body}<script>var a = 1</script><div class="footer"><pre>© 2024</pre></div></body></html>')
        types = [u["type"] for u in units(main)]
        assert kind in types and "paragraph" in types and "Home" not in main and "var a" not in main and "2024" not in main


def test_row_stages_are_the_attrition_before_fuzzy(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert C.row_stages(docs).count() == {r.name: r.docs_out for r in C.attrition(docs, k=8, bands=4)[1].collect()}["safety"]
