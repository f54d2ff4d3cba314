"""Findings of the third review."""

import random
from collections import Counter

from webtext.functions import decoding as D
from webtext.operators import corpus as C
from webtext.plans import CATALOGUE

SF = "/root/testdata/sf0.001"


def test_free_decoding_may_end_as_an_array():
    """Random logits write arrays now and then: they are invalid, not an error."""
    rng = random.Random(14119)
    rows = [[rng.gauss(0, 1) for _ in D.VOCAB] for _ in range(4)]
    wire = D.decode(4, lambda prefix, block: rows[len(prefix) % 4], "free")
    assert wire == "[8]" and not D.valid(wire, 4) and D.labels_of(wire, 4) == ([0] * 4, 4)
    assert not D.valid('[["1","main"]]', 1) and not D.valid("[" * 200_000, 1) and not D.valid("[]", 1)
    assert D.valid('{"1":"main"}', 1) and D.valid("{}", 0) and not D.valid('{"1":["main"]}', 1)


def test_decoding_is_tried_on_a_page_whose_free_output_is_an_array(spark, tmp_path):
    page = "<html><body>" + "".join(f"<p>One sentence of block {k}.</p>" for k in range(4)) + "</body></html>"
    spark.createDataFrame([(14119, "http://a.example.com/", page)], "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {r.mode: (r.n, r.is_valid, r.n_main) for r in CATALOGUE["decode_ablation"].run(spark, str(tmp_path)).collect()}
    assert got["free"] == (4, 0, 0) and got["fsm"] == got["fast"] == (4, 1, got["fsm"][2])


def _prose(seed: int, n: int = 120) -> str:
    rng = random.Random(seed)
    return " ".join(w if k % 3 else rng.choice(("the", "of", "with", "have")) for k, w in enumerate("".join(rng.choices("abcdefghijklmnopqrstuvw", k=6)) for _ in range(n)))


def test_stages_drop_hosts_on_the_list_and_repeated_grams(spark):
    """Safety looks at the page's host as well as at its words, and quality at repeated n-grams as well as at lines."""
    phrase = "the river of stones runs with seven quiet bridges"
    again = " ".join(f"{phrase} {_prose(k, 6)}" for k in range(12))
    rows = [(1, _prose(1), "https://www.example.com/a"), (2, _prose(2), "http://Spam-Farm.example.com/b"), (3, _prose(3) + " idiot", "http://x.example.com/"), (4, again, "http://y.example.com/"), (5, _prose(5), None)]
    left, stages = C.attrition(spark.createDataFrame(rows, "doc_id long, text string, url string"))
    assert sorted(r.doc_id for r in left.collect()) == [1, 5]
    assert {r.name: r.docs_out for r in stages.collect()} == {"input": 5, "exact": 5, "language": 5, "quality": 4, "safety": 2, "fuzzy": 2}
    assert sorted(r.doc_id for r in C.row_stages(spark.createDataFrame(rows, "doc_id long, text string, url string")).collect()) == [1, 5]


def test_language_is_that_of_a_trained_classifier(spark):
    """Texts without stop words have no vote; letters of no trained language are und."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = C.language_model(docs)
    assert model[0] == sorted({r.lang for r in docs.select("lang").distinct().collect()}) and model[1].shape == (len(model[0]), C.BUCKETS)
    texts = [(r.lang, " ".join(w for w in r.text.split() if w.lower().strip(".,") not in set().union(*C.STOP.values()))) for r in docs.where("n_chars > 500").collect()]
    assert sum(C.language_of(model, x) == lang for lang, x in texts) > 0.9 * len(texts)
    assert [C.language_of(model, x) for x in (None, "", "12 34", "\u10d0\u10d1")] == [None, "und", "und", "und"]
    rows = [(1, _prose(1), "xx"), (2, _prose(2), "en"), (3, _prose(3), None)]
    stages = C.attrition(spark.createDataFrame(rows, "doc_id long, text string, lang_pred string"))[1]
    assert {r.name: r.docs_out for r in stages.collect()}["language"] == 1
    assert C.language_model(docs.limit(0))[0] == []


def test_repeated_grams_are_those_of_a_full_count():
    rng = random.Random(7)
    for size in (0, 1, 5, 12, 40, 300):
        w = [rng.choice(("a", "bb", "ccc", "d")) for _ in range(size)] + ["x", "y", "z", "a", "bb"] * (size // 20)
        chars = len(" ".join(w))
        want = []
        for n in range(2, 11):
            counts = Counter(tuple(w[i : i + n]) for i in range(len(w) - n + 1))
            often = [(g, c) for g, c in counts.items() if c > 1]
            want.append(C._six(max((c * len(" ".join(g)) for g, c in often), default=0) / max(1, chars)) if n < 5 else C._six(sum(c - 1 for _, c in often) / max(1, counts.total())))
        assert C._repeated(w, chars) == want


def test_the_pair_of_corpora_knows_hosts_and_languages(spark, monkeypatch):
    from webtext.plans import evaluation as E

    seen = []
    monkeypatch.setattr(E, "attrition", lambda docs, p: seen.append(docs) or (docs, docs.limit(1)))
    CATALOGUE["corpus_pair"].run(spark, SF)
    urls = {(r.page_id, r.url) for r in spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "url").collect()}
    for docs in seen:
        rows = docs.collect()
        assert {(r.doc_id, r.url) for r in rows} == urls and {r.lang_pred for r in rows} <= {"en", "de", "fr", "es", "und"}
