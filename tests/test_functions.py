"""Parser, blocks, decoding, rules, content lists and measures on worked examples and random input."""

import itertools
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from webtext.functions import measures as M
from webtext.functions.baselines import density, rulebook, strip_all
from webtext.functions.blocks import Config, assemble, block_rows, chunk, is_layout_table, simplify
from webtext.functions.content import formulas_in, guess_language, markdown, plain_text, table_kind, units
from webtext.functions.decoding import VOCAB, Machine, block_logits, decode, labels_of, valid
from webtext.functions.dom import parse, shape, visible_text
from webtext.functions.rules import Compiled, synthesise

PAGE = (
    '<!DOCTYPE html><html><head><title>T</title><script>var t="</p>";</script></head><body><nav><ul><li><a href="/">Home</a></ul></nav>'
    '<!-- x --><div class="ad"><p>Buy now, it is cheap.</p></div><article><h1>T</h1><p><b>One line<br><p>Two &amp; three lines.</article><footer>&copy; host</footer>'
)


def test_traps():
    root, blocks, _ = block_rows(PAGE)
    assert [b.tag for b in blocks] == ["ul", "p", "h1", "p", "p", "footer"]
    assert [b.text for b in blocks][2:] == ["T", "One line", "Two & three lines.", "© host"]
    kept = assemble(root, blocks[2:5])
    assert plain_text(kept) == "T\nOne line\nTwo & three lines."


@given(st.lists(st.sampled_from(["<p>", "</p>", "<div class='a b'>", "</div>", "<table>", "<td>", "<tr>", "</table>", "<script>", "</script>", "<li>", "<ul>", "</ul>", "text ", "<", "&amp;", "<!--", "-->", "<br/>", '<a href="x>y">', "</a>", "<b>", "é"]), max_size=40))
@settings(max_examples=150, deadline=None)
def test_parser_never_raises_and_output_is_cut_from_the_page(parts):
    page = "".join(parts)
    root, blocks, rows = block_rows(page)
    assert [b.block_id for b in blocks] == list(range(1, len(blocks) + 1)) == [r["block_id"] for r in rows]
    for mask in (0, 1, 2):
        kept = [b for b in blocks if b.block_id % 3 == mask]
        text = "".join("".join(b.text.split()) for b in kept)
        got = iter("".join(visible_text(root).split()) + "".join("".join(b.text.split()) for b in blocks))
        assert all(c in got for c in text)
        assemble(root, kept)
    assert assemble(root, []) == ""


def test_deep_page_is_parsed():
    assert visible_text(parse("<div>" * 5000 + "x")) == "x"


def test_truncation_and_attributes():
    b = chunk(parse('<p class="c" style="s">' + "x" * 300 + "</p>"))[0]
    text, cut = simplify(b)
    assert cut and text == '<p class="c">' + "x" * 200 + "</p>"
    assert simplify(b, Config(para_chars=0)) == ('<p class="c">' + "x" * 300 + "</p>", False)
    rows = "<table>" + "<tr><td>a</td></tr>" * 9 + "</table>"
    assert simplify(chunk(parse(rows))[0])[0].count("<tr>") == 3


def test_layout_table():
    layout = '<table role="presentation"><tr><td><div>menu</div></td><td><div><p>text</p></div></td></tr></table>'
    data = "<table><tr><th>a</th><th>b</th></tr><tr><td>1</td><td>2</td></tr></table>"
    one = lambda h: next(parse(h).elements("table"))
    assert is_layout_table(one(layout)) and not is_layout_table(one(data))
    assert len(chunk(parse(layout))) == 2 and len(chunk(parse(data))) == 1


@pytest.mark.parametrize("n", [0, 1, 9, 10, 11, 99, 100])
def test_decoding(n):
    rng = random.Random(n)
    scores = [(rng.gauss(0, 1), rng.gauss(0, 1)) for _ in range(n)]
    wire = decode(n, block_logits(scores))
    assert valid(wire, n) and wire == decode(n, block_logits(scores), "fast")
    assert labels_of(wire, n) == ([int(m > o) for o, m in scores], 0)
    noise = [[rng.gauss(0, 1) for _ in VOCAB] for _ in range(5)]
    assert not valid(decode(n, lambda p, b: noise[len(p) % 5], "free"), max(1, n))


def test_decoding_edge_values():
    nan = float("nan")
    assert labels_of(decode(3, block_logits([(nan, nan), (0.0, 0.0), (nan, 1.0)])), 3)[0] == [0, 0, 1]
    assert labels_of("{broken", 2) == ([0, 0], 2)
    with pytest.raises(ValueError):
        Machine(1).step("}")


def test_rules_reproduce_labels_and_carry_over():
    root, blocks, _ = block_rows(PAGE)
    labels = [0, 0, 1, 1, 1, 0]
    rules = synthesise(root, blocks, labels)
    compiled = Compiled([(r.selector, r.action) for r in rules])
    assert compiled.decide(root, blocks) == (labels, 0)
    assert {(r.selector, r.action) for r in rules} >= {("//article", "retain"), ("//nav", "prune")}
    other = parse(PAGE.replace("One line", "Another, longer line"))
    assert compiled.decide(other, chunk(other))[0] == labels


def test_content_units():
    us = units("<h2>H</h2><pre><code>SELECT a\n</code></pre><pre>FROM b WHERE c</pre><p>see <code>x`y</code> and \\(a+b\\)</p><ul><li>one<ol><li>two</li></ol></li></ul><img src='i.png' alt='p'>")
    assert [u["type"] for u in us] == ["title", "code", "paragraph", "inline_code", "inline_formula", "list", "image"]
    assert us[1]["lang"] == "sql" and us[1]["text"] == "SELECT a\nFROM b WHERE c"
    md = markdown(us)
    assert "``x`y``" in md and "- one\n  1. two" in md and "![p](i.png)" in md
    assert markdown(us, drop=("image",)).endswith("1. two")


def test_tables():
    one = lambda h: next(parse(h).elements("table"))
    assert table_kind(one("<table><tr><td colspan=2>a</td></tr></table>")) == "complex"
    assert table_kind(one("<table><tr><td><table><tr><td>a</td></tr></table></td></tr></table>")) == "nested"
    assert markdown(units("<table><tr><th>a|b</th><th>c</th></tr><tr><td>1</td></tr></table>")) == "| a\\|b | c |\n| --- | --- |\n| 1 |  |"


RICH = r"""<p>First $$a+b$$ second <code>x</code>.</p><ul><li>use <code>f(x)</code> and \(a^2\)<ul><li>in $$y=1$$</li></ul></li></ul>
<table><tr><td><code>k</code></td><td>a<br>b</td></tr><tr><td>1</td><td>$x_1$<img src="i.png"></td></tr></table>
<p>so <math><msup><mi>x</mi><mn>2</mn></msup><mo>=</mo><mfrac><mrow><mi>a</mi><mo>+</mo><mn>1</mn></mrow><msqrt><mi>π</mi></msqrt></mfrac></math></p>
<math display="block"><munderover><mo>∑</mo><mrow><mi>i</mi><mo>=</mo><mn>1</mn></mrow><mi>n</mi></munderover><msup><mrow><mo>(</mo><mi>a</mi><mo>)</mo></mrow><mn>2</mn></msup></math>"""


def test_spans_within_units():
    md = markdown(units(RICH))
    assert md.startswith("First\n\n$$\na+b\n$$\n\nsecond `x`.\n\n- use `f(x)` and $a^2$\n  - in $$y=1$$\n\n| `k` | a b |\n| --- | --- |\n| 1 | $x_1$ |\n\n![](i.png)")
    assert md.endswith("so $x^{2}=\\frac{a+1}{\\sqrt{\\pi}}$\n\n$$\n\\sum_{i=1}^{n}{(a)}^{2}\n$$")
    assert [u["text"] for u in units(RICH) if u["type"] == "display_formula" and u["alt"] == "embedded"] == ["y=1"]
    assert plain_text(RICH).count("y=1") == 1


def test_native_renderer_has_no_span_twice(spark):
    from webtext.operators.formatting import render
    from webtext.plans import extraction as E

    page = spark.createDataFrame([(1, RICH)], "page_id long, html string")
    c = E.M.content_list(page, "page_id", "html").select(render("units").alias("md"), render("units", "text").alias("text"), render("units", "html").alias("html")).first()
    assert c.md == markdown(units(RICH)) and c.text.count("y=1") == c.html.count("y=1") == 1


def test_formulas():
    assert formulas_in("it costs $5 and $6, or $$$ junk $$$") == []
    assert [(x[2], x[3]) for x in formulas_in("$x^2$ and $$y=1$$ and \\[z\\]")] == [("x^2", False), ("y=1", True), ("z", True)]
    assert guess_language('{"a": 1}') == "json" and guess_language("hello world") is None


def test_baselines():
    assert rulebook(PAGE) == "T" or "Buy" not in rulebook(PAGE)
    assert "Home" in strip_all(PAGE) and "var t" not in strip_all(PAGE)
    assert "three lines" in density(PAGE + "") or density(PAGE)


def _brute(a, b):
    """Forest edit distance by plain recursion."""
    if not a and not b:
        return 0.0
    best = []
    if a:
        best.append(_brute(a[:-1] + a[-1][2], b) + 1)
    if b:
        best.append(_brute(a, b[:-1] + b[-1][2]) + 1)
    if a and b:
        x, y = a[-1], b[-1]
        cost = 1.0 if x[0] != y[0] else (0.0 if x[1] == y[1] else 1 - M.edit_similarity(x[1], y[1]))
        best.append(_brute(x[2], y[2]) + _brute(a[:-1], b[:-1]) + cost)
    return min(best)


def test_tree_distance_against_brute_force():
    rng = random.Random(3)

    def tree(n):
        nodes = [(rng.choice("ab"), rng.choice(["", "x", "xy"]), []) for _ in range(n)]
        for k in range(1, n):
            nodes[rng.randrange(k)][2].append(nodes[k])
        return nodes[0]

    for _ in range(60):
        a, b = tree(rng.randint(1, 6)), tree(rng.randint(1, 6))
        assert M.tree_distance(a, b) == pytest.approx(_brute([a], [b]))
        assert M.tree_distance(a, b) == pytest.approx(M.tree_distance(b, a)) and M.tree_distance(a, a) == 0


def test_rouge_and_edit():
    a, b = "a b c d e f".split(), "a b c d e g".split()
    assert M.rouge_n(a, b) == (0.5, 0.5, 0.5) and M.rouge_n([], []) == (1, 1, 1) and M.rouge_n(a, [])[2] == 0
    assert M.rouge_n(a[:2], a[:2])[2] == 1 and M.rouge_l(a, b) == pytest.approx(10 / 12)
    assert M.edit_similarity("", "") == 1 and M.edit_similarity("abc", "abd") == pytest.approx(2 / 3)
    assert M.tokens("Ab 中文 c") == ["ab", "中", "文", "c"]


def test_shape():
    s = shape(parse("<div id=a><p>x</p><p>y</p></div>"))
    assert s == {"n_tags": 3, "n_attr_names": 1, "n_distinct_tags": 2, "depth": 2, "width": 2}
    assert list(itertools.islice(parse("").walk(), 2))[0].tag == "#root"
