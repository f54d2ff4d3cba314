"""Rendered pages for what the given ones lack, and gold texts: pure functions of the tables (FIXTURES.md)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def gold(t) -> DataFrame:
    """page_id, gold_text: heading and the lines of the least document of equal text. For evaluation only."""
    art = F.regexp_extract("html", r"(?s)<article>(.*?)</article>", 1)
    clean = lambda c: F.replace(F.replace(F.regexp_replace(c, r"<[^>]*>", ""), F.lit("&quot;"), F.lit('"')), F.lit("&amp;"), F.lit("&"))
    p = t("pages").select("page_id", clean(F.regexp_extract(art, r"(?s)<h1>(.*?)</h1>", 1)).alias("h1"), F.regexp_replace(clean(F.regexp_extract(art, r"(?s)</h1>(.*)", 1)), r"\s", "").alias("k"))
    d = t("documents").select(F.regexp_replace("text", r"\s", "").alias("k"), "doc_id", "text").groupBy("k").agg(F.min_by("text", "doc_id").alias("text"))
    lines = F.filter(F.transform(F.split("text", "\n"), lambda x: F.trim(F.regexp_replace(x, r"\s+", " "))), lambda x: x != "")
    return p.join(d, "k").select("page_id", F.concat(F.trim(F.regexp_replace("h1", r"\s+", " ")), F.lit("\n"), F.array_join(lines, "\n")).alias("gold_text"))


def _page(body) -> object:
    return F.concat(F.lit("<html><head><title>t</title></head><body>"), body, F.lit("</body></html>"))


def code(t) -> DataFrame:
    """fx_id, html, gold_code, gold_lang: JSON of events split over adjacent tags, SQL and Python snippets."""
    k = F.col("event_id") % 3
    js, sql = F.concat(F.lit('{\n  "event": '), F.col("event_id").cast("string"), F.lit(',\n  "props": '), "props", F.lit("\n}")), F.concat(F.lit("SELECT value\nFROM events\nWHERE event_id = "), F.col("event_id").cast("string"))
    py = F.concat(F.lit("def f(x):\n    print(x + "), F.col("event_id").cast("string"), F.lit(")"))
    gold_code = F.when(k == 0, js).when(k == 1, sql).otherwise(py)
    esc = F.replace(F.replace(gold_code, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;"))
    parts = F.concat(F.lit("<p>Before.</p><pre><code>"), F.substring_index(esc, "\n", 1), F.lit("</code></pre>\n<pre><code>"), F.substr(esc, F.length(F.substring_index(esc, "\n", 1)) + 2), F.lit("</code></pre><p>After.</p>"))
    return t("events").select(F.col("event_id").alias("fx_id"), _page(parts).alias("html"), gold_code.alias("gold_code"), F.when(k == 0, "json").when(k == 1, "sql").otherwise("python").alias("gold_lang"))


CODE_SQL = """SELECT {out} FROM (SELECT event_id AS fx_id, CASE event_id % 3
  WHEN 0 THEN '{{' || chr(10) || '  "event": ' || event_id || ',' || chr(10) || '  "props": ' || props || chr(10) || '}}'
  WHEN 1 THEN 'SELECT value' || chr(10) || 'FROM events' || chr(10) || 'WHERE event_id = ' || event_id
  ELSE 'def f(x):' || chr(10) || '    print(x + ' || event_id || ')' END AS code,
  CASE event_id % 3 WHEN 0 THEN 'json' WHEN 1 THEN 'sql' ELSE 'python' END AS lang FROM events)"""


def table_simple(t) -> DataFrame:
    n = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    rows = n.groupBy("r_regionkey").agg(F.array_sort(F.collect_list(F.struct("n_nationkey", "n_name", "r_name"))).alias("x"))
    row = F.transform("x", lambda r: F.concat(F.lit("<tr><td>"), r["n_nationkey"].cast("string"), F.lit("</td><td>"), r["n_name"], F.lit("</td><td>"), r["r_name"], F.lit("</td></tr>")))
    return rows.select(F.col("r_regionkey").cast("long").alias("fx_id"), _page(F.concat(F.lit("<table><thead><tr><th>key</th><th>nation</th><th>region</th></tr></thead><tbody>"), F.array_join(row, ""), F.lit("</tbody></table>"))).alias("html"))


TABLE_SQL = """SELECT r_regionkey::BIGINT AS fx_id, '| key | nation | region |' || chr(10) || '| --- | --- | --- |' || chr(10) ||
  string_agg('| ' || n_nationkey || ' | ' || n_name || ' | ' || r_name || ' |', chr(10) ORDER BY n_nationkey) AS md FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1"""


def table_complex(t) -> DataFrame:
    li = t("lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_partkey"))).alias("x")).where(F.size("x") > 1)
    row = F.transform("x", lambda r, k: F.concat(F.lit("<tr>"), F.when(k == 0, F.concat(F.lit('<td rowspan="'), F.size("x").cast("string"), F.lit('" style="color:red">'), F.col("l_orderkey").cast("string"), F.lit("</td>"))).otherwise(""), F.lit("<td>"), r["l_linenumber"].cast("string"), F.lit("</td><td>"), r["l_partkey"].cast("string"), F.lit("</td></tr>")))
    return li.select(F.col("l_orderkey").alias("fx_id"), _page(F.concat(F.lit("<table><tr><th>order</th><th>line</th><th>part</th></tr>"), F.array_join(row, ""), F.lit("</table>"))).alias("html"))


def table_nested(t) -> DataFrame:
    n = t("region").join(t("nation"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_regionkey", "r_name").agg(F.array_sort(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("x"))
    inner = F.array_join(F.transform("x", lambda r: F.concat(F.lit("<tr><td>"), r["n_nationkey"].cast("string"), F.lit("</td><td>"), r["n_name"], F.lit("</td></tr>"))), "")
    return n.select(F.col("r_regionkey").cast("long").alias("fx_id"), _page(F.concat(F.lit("<table><tr><td>"), "r_name", F.lit("<table>"), inner, F.lit("</table></td></tr></table>"))).alias("html"))


KIND_SQL = """SELECT 'simple' AS kind, (SELECT count(DISTINCT n_regionkey) FROM nation)::BIGINT AS n
  UNION ALL SELECT 'complex', count(*)::BIGINT FROM (SELECT 1 FROM lineitem GROUP BY l_orderkey HAVING count(*) > 1)
  UNION ALL SELECT 'nested', (SELECT count(*) FROM nation)::BIGINT + (SELECT count(DISTINCT n_regionkey) FROM nation)::BIGINT"""


def table_layout(t) -> DataFrame:
    body = F.concat(F.lit("<p>"), F.array_join(F.split(F.replace(F.replace("text", F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), "\n"), "</p><p>"), F.lit("</p>"))
    return t("documents").select(F.col("doc_id").alias("fx_id"), _page(F.concat(F.lit('<table role="presentation"><tr><td><div class="menu"><a href="/a">a</a></div></td><td><div>'), body, F.lit("</div></td></tr></table>"))).alias("html"), F.col("text").alias("gold_text"))


def lists(t) -> DataFrame:
    p = t("part").groupBy("p_brand", "p_type").agg(F.array_sort(F.collect_list("p_partkey")).alias("ps")).groupBy("p_brand").agg(F.array_sort(F.collect_list(F.struct("p_type", "ps"))).alias("x"))
    inner = lambda r: F.array_join(F.transform(r["ps"], lambda k: F.concat(F.lit("<li>part "), k.cast("string"), F.lit("</li>"))), "")
    items = F.array_join(F.transform("x", lambda r: F.concat(F.lit("<li>"), r["p_type"], F.lit("<ol>"), inner(r), F.lit("</ol></li>"))), "")
    return p.select(F.col("p_brand").alias("fx_id"), _page(F.concat(F.lit("<ul>"), items, F.lit("</ul>"))).alias("html"))


LIST_SQL = """SELECT p_brand AS fx_id, string_agg('- ' || p_type || chr(10) || inner_, chr(10) ORDER BY p_type) AS md FROM (
  SELECT p_brand, p_type, string_agg('  1. part ' || p_partkey, chr(10) ORDER BY p_partkey) AS inner_ FROM part GROUP BY 1, 2) GROUP BY 1"""


def media(t) -> DataFrame:
    first = F.replace(F.replace(F.substring_index("text", "\n", 1), F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;"))
    i = F.col("doc_id").cast("string")
    body = F.concat(F.lit("<p>"), first, F.lit('</p><img src="/i'), i, F.lit('.png" alt="picture"><video src="/v'), i, F.lit('.mp4"></video><div><audio><source src="/a'), i, F.lit('.mp3"></audio></div>'))
    return t("documents").select(F.col("doc_id").alias("fx_id"), _page(body).alias("html"))


def formula(t) -> DataFrame:
    """fx_id, html, gold_tex, display, renderer: a price expression in four spellings."""
    x = t("lineitem").select((F.col("l_orderkey") * 10 + F.col("l_linenumber")).alias("fx_id"), F.concat(F.lit("p_{"), F.col("l_linenumber").cast("string"), F.lit("} = "), F.col("l_quantity").cast("int").cast("string"), F.lit(" \\cdot x")).alias("gold_tex"))
    k, tex = F.col("fx_id") % 4, F.col("gold_tex")
    body = (
        F.when(k == 0, F.concat(F.lit("<p>Let \\("), tex, F.lit("\\) hold for $5 and $6.</p>")))
        .when(k == 1, F.concat(F.lit('<p>Then</p><script type="math/tex; mode=display">'), tex, F.lit("</script><p>holds.</p>")))
        .when(k == 2, F.concat(F.lit('<p>Let <span class="katex"><span class="katex-mathml"><math><semantics><mrow><mi>p</mi></mrow><annotation encoding="application/x-tex">'), tex, F.lit("</annotation></semantics></math></span></span> hold.</p>")))
        .otherwise(F.concat(F.lit("<p>$$"), tex, F.lit("$$</p>")))
    )
    return x.select("fx_id", _page(body).alias("html"), "gold_tex", k.isin(1, 3).alias("display"), F.element_at(F.array(*map(F.lit, ("delimiters", "script", "span", "dollars"))), (k + 1).cast("int")).alias("renderer"))


FORMULA_SQL = "SELECT l_orderkey * 10 + l_linenumber AS fx_id, 'p_{' || l_linenumber || '} = ' || l_quantity::INT || ' \\cdot x' AS tex, (l_orderkey * 10 + l_linenumber) % 4 IN (1, 3) AS display FROM lineitem"

RICH_SQL = """SELECT 'code' AS fixture, count(*)::BIGINT AS n_code, 0::BIGINT AS n_formula, 0::BIGINT AS n_table FROM events
  UNION ALL SELECT 'formula', 0::BIGINT, count(*)::BIGINT, 0::BIGINT FROM lineitem
  UNION ALL SELECT 'table', 0::BIGINT, 0::BIGINT, count(DISTINCT n_regionkey)::BIGINT FROM nation"""


def threads(t) -> DataFrame:
    """fx_id, html: a thread with counters and time stamps as noise."""
    x = t("conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("x"))
    esc = lambda c: F.replace(F.replace(F.replace(c, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit("\n"), F.lit(" "))
    post = F.transform("x", lambda r: F.concat(F.lit('<div class="post"><p class="share">12 likes</p><p>'), esc(r["text"]), F.lit('</p><p class="footer">2024-01-01 10:00</p></div>')))
    return x.select(F.col("conv_id").alias("fx_id"), _page(F.concat(F.lit('<ul class="nav"><li><a href="/">Home</a></li></ul><main>'), F.array_join(post, ""), F.lit("</main>"))).alias("html"))


def shuffled(t) -> DataFrame:
    """page_id, html: article, nav and footer renamed to div with one of four class schemes by hash, and a wrapper more or less."""
    k = F.pmod(F.xxhash64("page_id"), F.lit(4)).cast("string")
    h = F.col("html")
    for tag, name in (("article", "s"), ("nav", "menu-top"), ("footer", "copyright-line")):
        h = F.replace(h, F.lit(f"<{tag}>"), F.concat(F.lit('<div class="'), F.element_at(F.array(*[F.lit(f"{x}-{name}") for x in ("aa", "bb", "cc", "dd")]), (k.cast("int") + 1)), F.lit('">')))
        h = F.replace(h, F.lit(f"</{tag}>"), F.lit("</div>"))
    h = F.when(k.isin("1", "3"), F.regexp_replace(h, "<body>", '<body><div class="wrap"><div>')).otherwise(h)
    return t("pages").select("page_id", "url", h.alias("html"))
