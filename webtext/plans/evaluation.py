"""Measures, experiment workloads and reports."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from webtext.functions import baselines as B
from webtext.functions.blocks import assemble, block_rows
from webtext.functions.content import plain_text, units
from webtext.functions.dom import parse
from webtext.functions.measures import aligned, blind_score, judged, teds
from webtext.functions.measures import edit_similarity as py_edit
from webtext.functions.scoring import _ALL_STOP, lexicon
from webtext.operators import extract as X
from webtext.operators import labeller as L
from webtext.operators import measures as M
from webtext.operators.components import cut
from webtext.operators.corpus import POLICIES, attrition, exact_dedup, language_model, language_of, overlap, row_stages
from webtext.operators.passes import distinct_rows, row_pass
from webtext.plans import fixtures as FX
from webtext.plans.extraction import GOLD
from webtext.plans.registry import query

def _plain(extract):
    """A method that makes a text of the page alone."""
    return lambda pages, keep=(): row_pass(pages.select("page_id", "html", *keep), lambda k, h, *kept: (k, extract(h), *kept), ", ".join(["page_id long, pred string", *(f"{c} {pages.schema[c].dataType.simpleString()}" for c in keep)]))


#: page_id, pred (and columns of pages to keep) by each method.
METHODS = {
    "labelled": lambda pages, keep=(): X.core(pages, keep=keep).select("page_id", F.col("main_text").alias("pred"), *keep),
    "density": _plain(lambda h: plain_text(B.density(h))),
    "rulebook": _plain(B.rulebook),
    "strip_all": _plain(B.strip_all),
}


def _scored(pages, gold, methods=METHODS, n=5):
    parts = [M.rouge(run(pages).join(gold, "page_id").withColumnRenamed("gold_text", "gold"), n=n).withColumn("method", F.lit(name)) for name, run in methods.items()]
    return reduce(lambda a, b: a.unionByName(b), parts)


_RULE_GRAMS = rf"""WITH {GOLD}, l AS (SELECT page_id, unnest(string_split(main_text, chr(10))) AS line, generate_subscripts(string_split(main_text, chr(10)), 1) AS i FROM gold),
pr AS (SELECT page_id, string_agg(line, ' ' ORDER BY i) AS pred FROM l WHERE i = 1 OR length(line) >= 25 GROUP BY 1),
wt AS (SELECT page_id, regexp_extract_all(lower(pred), '{M.MIXED}') AS a, regexp_extract_all(lower(main_text), '{M.MIXED}') AS b FROM pr JOIN gold USING (page_id)),
nn AS (SELECT page_id, a, b, greatest(1, least(5, len(a), len(b))) AS n FROM wt),
gr AS (SELECT page_id, unnest(list_transform(range(1, len(a) - n + 2), lambda i: array_to_string(a[i:i + n - 1], ' '))) AS g, 1 AS x FROM nn
  UNION ALL SELECT page_id, unnest(list_transform(range(1, len(b) - n + 2), lambda i: array_to_string(b[i:i + n - 1], ' '))), 0 FROM nn),
ct AS (SELECT page_id, g, sum(x) AS ca, sum(1 - x) AS cb FROM gr GROUP BY 1, 2),
sm AS (SELECT page_id, sum(ca) AS a, sum(cb) AS b, sum(least(ca, cb)) AS hit FROM ct GROUP BY 1)
SELECT page_id, round(hit / a, 6) AS p, round(hit / b, 6) AS r, round(2 * hit / (a + b), 6) AS f1 FROM sm"""


@query("rouge5_rulebook", _RULE_GRAMS)
def _(t):
    return M.rouge(METHODS["rulebook"](t("pages")).join(FX.gold(t), "page_id").withColumnRenamed("gold_text", "gold"))


@query("rouge5_pages", f"WITH {GOLD} SELECT page_id, 1.0::DOUBLE AS p, 1.0::DOUBLE AS r, 1.0::DOUBLE AS f1 FROM gold")
def _(t):
    return M.rouge(METHODS["labelled"](t("pages")).join(FX.gold(t), "page_id").withColumnRenamed("gold_text", "gold"))


@query("rouge_sweep")
def _(t):
    gold = FX.gold(t)
    parts = [_scored(t("pages"), gold, {k: METHODS[k] for k in ("labelled", "density", "rulebook")}, n).withColumn("n", F.lit(n)) for n in (1, 2, 3, 4, 5)]
    return reduce(lambda a, b: a.unionByName(b), parts).groupBy("method", "n").agg(F.round(F.avg("f1"), 4).alias("mean_f1"))


@query("rouge_l_small")
def _(t):
    """The rejected measure: its cost is the product of the lengths (G12); here 64 places of one text at a time."""
    pairs = METHODS["rulebook"](t("pages")).join(FX.gold(t), "page_id").withColumnRenamed("gold_text", "gold")
    return M.rouge_l(pairs).select("page_id", F.round("f1", 6).alias("f1"))


@query("token_counts", r"SELECT doc_id, len(list_filter(string_split_regex(lower(text), '\s+'), lambda x: x <> ''))::BIGINT AS n FROM documents")
def _(t):
    return t("documents").select("doc_id", F.size(M.tokens("text")).cast("long").alias("n"))


def _levels(t):
    """Difficulty by complexity tertiles (depth, width, variety, links)."""
    links = t("pages").select("page_id", F.regexp_count("html", F.lit("<a ")).alias("links"))
    c = X.shapes(t("pages")).join(links, "page_id").select("page_id", (F.col("depth") / 10 + F.log10(1 + F.col("width")) + F.col("n_distinct_tags") / 20 + F.col("links") / 50).alias("c"))
    cuts = c.agg(F.percentile_approx("c", [1 / 3, 2 / 3], 10000).alias("q"))
    return c.crossJoin(F.broadcast(cuts)).select("page_id", F.when(F.col("c") <= F.col("q")[0], "simple").when(F.col("c") <= F.col("q")[1], "mid").otherwise("hard").alias("level"))


@query("levels")
def _(t):
    return _levels(t).groupBy("level").agg(F.count("*").alias("n_pages"))


def _fixture_pages(t):
    """track, page_id, html, gold_text of the content tracks."""
    text = lambda df, track, gold: df.select(F.lit(track).alias("track"), F.xxhash64(F.lit(track), F.col("fx_id").cast("string")).alias("page_id"), "html", gold.alias("gold_text"))
    first = lambda x: F.concat(F.lit("Before.\n"), x, F.lit("\nAfter."))
    thread = t("conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "text"))).alias("x")).select(F.col("conv_id").alias("fx_id"), F.array_join(F.transform("x", lambda r: r["text"]), "\n").alias("g"))
    table = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_regionkey").agg(F.array_sort(F.collect_list(F.struct("n_nationkey", "n_name", "r_name"))).alias("x"))
    table = table.select(F.col("r_regionkey").cast("long").alias("fx_id"), F.concat(F.lit("key nation region\n"), F.array_join(F.transform("x", lambda r: F.concat_ws(" ", r["n_nationkey"].cast("string"), r["n_name"], r["r_name"])), "\n")).alias("g"))
    formula = FX.formula(t).where("display = false")
    g = F.when(F.col("renderer") == "delimiters", F.concat(F.lit("Let $"), "gold_tex", F.lit("$ hold for $5 and $6."))).otherwise(F.concat(F.lit("Let $"), "gold_tex", F.lit("$ hold.")))
    return (
        text(FX.code(t), "code", first(F.col("gold_code")))
        .unionByName(text(FX.table_simple(t).join(table, "fx_id"), "table", F.col("g")))
        .unionByName(text(formula, "equation", g))
        .unionByName(text(FX.threads(t).join(thread, "fx_id"), "conversational", F.col("g")))
    )


@query("track_report")
def _(t):
    """Mean F1 by track and method (L181-L193); tracks overlap."""
    three = {k: METHODS[k] for k in ("labelled", "density", "rulebook")}
    s = _scored(t("pages"), FX.gold(t), three).join(_levels(t), "page_id").withColumn("tracks", F.array(F.lit("all"), "level"))
    # equal fixture pages are extracted and scored once
    fx = cut(distinct_rows(_fixture_pages(t).drop("page_id")).withColumn("page_id", F.xxhash64("track", "html", "gold_text")))
    f = _scored(fx, fx.select("page_id", "gold_text"), three).join(fx.select("page_id", "track", "copies"), "page_id").withColumn("tracks", F.array("track"))
    x = s.withColumn("copies", F.lit(1).cast("long")).select("method", "f1", "tracks", "copies").unionByName(f.select("method", "f1", "tracks", "copies"))
    mean = F.sum(F.col("f1") * F.col("copies")) / F.sum(F.when(F.col("f1").isNotNull(), F.col("copies")))
    return x.select("method", "f1", "copies", F.explode("tracks").alias("track")).groupBy("track", "method").agg(F.sum("copies").alias("n_pages"), F.round(mean, 4).alias("mean_f1"))


@query("shuffled_report")
def _(t):
    """The tracks' pages without semantic tags (fx_shuffled): no method can rely on article."""
    return _scored(FX.shuffled(t), FX.gold(t)).groupBy("method").agg(F.count("*").alias("n_pages"), F.round(F.avg("f1"), 4).alias("mean_f1"))


@query("external_report")
def _(t):
    """Plain-text gold (W5): documents' own text, without the heading."""
    gold = t("documents").groupBy(F.regexp_replace("text", r"\s", "").alias("k")).agg(F.min_by("text", "doc_id").alias("text"))
    g = FX.gold(t).select("page_id", F.regexp_replace(F.substr("gold_text", F.length(F.substring_index("gold_text", "\n", 1)) + 2), r"\s", "").alias("k")).join(gold, "k").select("page_id", F.col("text").alias("gold_text"))
    return _scored(t("pages"), g).groupBy("method").agg(F.count("*").alias("n_pages"), F.round(F.avg("f1"), 4).alias("mean_f1"))


@query("lang_report")
def _(t):
    lang = t("pages").select("page_id", F.regexp_extract("html", r'<html lang="?([a-z]+)', 1).alias("lang"))
    return _scored(t("pages"), FX.gold(t), {"labelled": METHODS["labelled"], "density": METHODS["density"]}).join(lang, "page_id").groupBy("lang", "method").agg(F.count("*").alias("n_pages"), F.round(F.avg("f1"), 4).alias("mean_f1"))


@query("system_deltas")
def _(t):
    """Absolute and relative distance to the labelled extractor."""
    m = _scored(t("pages"), FX.gold(t)).groupBy("method").agg(F.avg("f1").alias("f1"))
    top = m.where("method = 'labelled'").select(F.col("f1").alias("top"))
    return m.crossJoin(F.broadcast(top)).select("method", F.round(100 * (F.col("top") - F.col("f1")), 2).alias("delta_pp"), F.round(F.col("top") / F.col("f1"), 3).alias("factor"))


# -- structured elements
@query("code_edit_sim", FX.CODE_SQL.format(out="fx_id, 1.0::DOUBLE AS sim"))
def _(t):
    got = row_pass(FX.code(t).select("fx_id", "html"), lambda k, h: (k, "\n".join(u["text"] for u in units(h) if u["type"] == "code")), "fx_id long, pred string")
    return got.join(FX.code(t).select("fx_id", "gold_code"), "fx_id").select("fx_id", M.edit_similarity("pred", "gold_code").alias("sim"))


@query("edit_similarity_names", "SELECT a.p_partkey AS a, b.p_partkey AS b, round(1 - levenshtein(a.p_name, b.p_name) / greatest(length(a.p_name), length(b.p_name)), 6) AS sim FROM part a JOIN part b ON a.p_partkey + 1 = b.p_partkey")
def _(t):
    p = t("part").select("p_partkey", "p_name")
    return p.alias("a").join(p.alias("b"), F.expr("a.p_partkey + 1 = b.p_partkey")).select(F.col("a.p_partkey").alias("a"), F.col("b.p_partkey").alias("b"), F.round(M.edit_similarity(F.col("a.p_name"), F.col("b.p_name")), 6).alias("sim"))


@query("teds_tables", "SELECT fx_id, round(CASE kind WHEN 'same' THEN 1.0 ELSE 1 - (1 + 3) / (1 + (1 + n) * (1 + 3)) END, 6) AS teds, kind FROM (SELECT n_regionkey::BIGINT AS fx_id, count(*) AS n FROM nation GROUP BY 1), (VALUES ('same'), ('row_dropped')) v(kind)")
def _(t):
    """Identity is 1, and a dropped row of three cells costs four of 1 + 4 (n + 1) nodes."""

    def run(k, h):
        rows = h[: h.rindex("<tr>")] + "</tbody></table>"
        return [(k, "same", round(teds(h, h), 6)), (k, "row_dropped", round(teds(rows, h), 6))]

    return row_pass(FX.table_simple(t).select("fx_id", "html"), run, "fx_id long, kind string, teds double", many=True)


def labelled_html(page):
    """The main HTML of one page by the lexicon, as `extract.core` keeps it."""
    root, own, rows = block_rows(page)
    return assemble(root, [b for b, (o, m), r in zip(own, lexicon(own), rows, strict=True) if m > o and r["simplified"].strip()])


def _structured(t, align: bool):
    """kind, method, n, score over all fixtures. align: element by element; else code and formulas in order as one text, tables by the best."""

    def score(kind, h, gold, copies):
        out = []
        for name, main in {"labelled": labelled_html(h), "density": B.density(h), "rulebook": "<p>" + B.rulebook(h).replace("\n", "</p><p>") + "</p>"}.items():
            if kind == "table":
                found = [n.markup for n in parse(main).elements("table")]
                s = aligned(found, [gold], teds) if align else max([teds(m, gold) for m in found], default=0.0)
            else:
                found = [u["text"] for u in units(main) if u["type"] == kind or u["type"].endswith(f"_{kind}")]
                s = aligned(found, [gold]) if align else py_edit("\n".join(found), gold)
            out.append((kind, name, s, copies))
        return out

    x = FX.code(t).select(F.lit("code").alias("kind"), "html", F.col("gold_code").alias("gold"))
    x = x.unionByName(FX.formula(t).select(F.lit("formula").alias("kind"), "html", F.col("gold_tex").alias("gold")))
    x = x.unionByName(FX.table_complex(t).select(F.lit("table").alias("kind"), "html", F.col("html").alias("gold"))).unionByName(FX.table_simple(t).select(F.lit("table").alias("kind"), "html", F.col("html").alias("gold")))
    s = row_pass(distinct_rows(x), score, "kind string, method string, score double, copies long", many=True)
    return s.groupBy("kind", "method").agg(F.sum("copies").alias("n"), F.round(F.sum(F.col("score") * F.col("copies")) / F.sum("copies"), 4).alias("score"))


@query("structured_report")
def _(t):
    """Code and formula edit similarity, table TEDS, by method (W4): density and rule book lose structure."""
    return _structured(t, align=False)


@query("structured_report_aligned")
def _(t):
    """The same with each gold element against its best partner; a missing one scores 0."""
    return _structured(t, align=True)


@query("element_distribution", "SELECT 'code' AS kind, (SELECT count(*) FROM events)::BIGINT AS n UNION ALL SELECT 'formula', count(*)::BIGINT FROM lineitem UNION ALL SELECT 'table', (SELECT count(DISTINCT n_regionkey) FROM nation)::BIGINT")
def _(t):
    one = lambda df, kind: df.agg(F.lit(kind).alias("kind"), F.count("*").alias("n"))
    return one(FX.code(t), "code").unionByName(one(FX.formula(t), "formula")).unionByName(one(FX.table_simple(t), "table"))


# -- corpus-level comparison
def _pairs(t):
    a, b = METHODS["labelled"](t("pages")).withColumnRenamed("pred", "text_a"), METHODS["rulebook"](t("pages")).withColumnRenamed("pred", "text_b")
    x = a.join(b, "page_id").withColumns({"len_a": F.length("text_a").cast("long"), "len_b": F.length("text_b").cast("long")})
    # the SQL rounds the binary product, not its decimal spelling: 41 / 640 is 0.064062
    x = x.withColumn("ratio", F.round(M.length_ratio(F.col("len_a"), F.col("len_b")) * 1e6) / 1e6)
    return x.withColumn("bin", M.ratio_bin(F.col("ratio")))


_PAIRS = f"""WITH {GOLD}, l AS (SELECT page_id, unnest(string_split(main_text, chr(10))) AS line, generate_subscripts(string_split(main_text, chr(10)), 1) AS i FROM gold),
rb AS (SELECT page_id, string_agg(line, chr(10) ORDER BY i) AS b FROM l WHERE i = 1 OR length(line) >= 25 GROUP BY 1),
pa AS (SELECT page_id, length(main_text)::BIGINT AS len_a, length(b)::BIGINT AS len_b, round((length(main_text) - length(b)) / greatest(length(main_text), length(b)), 6) AS ratio FROM gold JOIN rb USING (page_id)),
pb AS (SELECT *, least(19, floor((ratio + 1) * 10))::INT AS bin FROM pa)"""


@query("length_ratio", f"{_PAIRS} SELECT page_id, len_a, len_b, ratio FROM pb")
def _(t):
    return _pairs(t).select("page_id", "len_a", "len_b", "ratio")


@query("length_summary", f"{_PAIRS} SELECT round(avg(len_a / len_b), 6) AS mean_ratio, round(sum(len_a) / sum(len_b), 6) AS ratio_of_sums, round(avg(ratio), 6) AS mean_signed FROM pb")
def _(t):
    """Three readings of "longer on average" (I7)."""
    return _pairs(t).agg(F.round(F.avg(F.col("len_a") / F.col("len_b")), 6).alias("mean_ratio"), F.round(F.sum("len_a") / F.sum("len_b"), 6).alias("ratio_of_sums"), F.round(F.avg("ratio"), 6).alias("mean_signed"))


@query("ratio_histogram", f"{_PAIRS} SELECT bin, count(*)::BIGINT AS n FROM pb GROUP BY 1")
def _(t):
    return _pairs(t).groupBy("bin").agg(F.count("*").alias("n"))


@query("stratified_pairs", f"{_PAIRS} SELECT bin, page_id FROM (SELECT bin, page_id, row_number() OVER (PARTITION BY bin ORDER BY md5('0:' || page_id)) AS r FROM pb) WHERE r <= 5")
def _(t):
    return M.stratified(_pairs(t).select("bin", "page_id"), "bin", "page_id", 5)


def _density_pairs(t):
    """Labelled (a) against density (b) with the gold judge: the higher F1 wins (stand-in for the LLM judge)."""
    gold = FX.gold(t)

    def one(name, f1, chars):
        pairs = METHODS[name](t("pages")).join(gold, "page_id").withColumnRenamed("gold_text", "gold")
        return M.rouge(pairs, lengths=True).select("page_id", F.col("f1").alias(f1), F.coalesce("n_chars", F.lit(0)).alias(chars))

    x = one("labelled", "labelled", "la").join(one("density", "density", "lb"), "page_id")
    d = F.col("labelled") - F.col("density")
    x = x.withColumn("bin", M.ratio_bin(M.length_ratio(F.col("la"), F.col("lb"))))
    # thin rows, which reports read more than once
    return cut(x.withColumn("winner", F.when(F.abs(d) < 0.001, "tie").when(d > 0, "a").otherwise("b")))


@query("pair_winner")
def _(t):
    return _density_pairs(t).select("page_id", "bin", "winner")


def _blind(first, second):
    a, b = blind_score(first, _ALL_STOP), blind_score(second, _ALL_STOP)
    return "tie" if abs(a - b) < 1 else "first" if a > b else "second"


def _blind_pairs(t):
    """Both extractions of a page and their judgement in one row: nothing is joined or shuffled."""

    def run(page_id, page):
        a, b = plain_text(labelled_html(page)), plain_text(B.density(page))
        return (page_id, len(a), len(b), *judged(a, b, _blind))

    x = row_pass(t("pages").select("page_id", "html"), run, "page_id long, la long, lb long, winner string, agreed boolean")
    return x.select("page_id", M.ratio_bin(M.length_ratio(F.col("la"), F.col("lb"))).alias("bin"), "winner", "agreed")


@query("pair_winner_blind")
def _(t):
    """A judge without gold that is asked in both orders (D11): stop words and sentences stand in for a language model."""
    return _blind_pairs(t)


@query("weighted_win_rate_blind")
def _(t):
    p = cut(_blind_pairs(t))
    return M.weighted_win_rate(p, M.win_rates(M.stratified(p, "bin", "page_id", PER_BIN))).withColumn("standin", F.lit(True))


@query("win_rate_by_bin")
def _(t):
    return M.win_rates(M.stratified(_density_pairs(t), "bin", "page_id", PER_BIN))


@query("weighted_win_rate")
def _(t):
    p = _density_pairs(t)
    return M.weighted_win_rate(p, M.win_rates(M.stratified(p, "bin", "page_id", PER_BIN))).withColumn("standin", F.lit(True))


@query("win_crossover")
def _(t):
    """First bin won by a, and how often the rate falls from bin to bin."""
    r = M.win_rates(_density_pairs(t)).withColumn("rate", (F.col("wins") + F.col("ties") / 2) / (F.col("wins") + F.col("losses") + F.col("ties")))
    r = r.withColumn("before", F.lag("rate").over(Window.orderBy("bin")))
    return r.agg(F.min(F.when(F.col("rate") > 0.5, F.col("bin"))).alias("first_won"), F.count(F.when(F.col("rate") < F.col("before"), 1)).alias("falls"))


@query("failure_cases")
def _(t):
    """The pages of the outer and middle bins with the widest gap."""
    x = _density_pairs(t).where("bin in (0, 9, 10, 19)").withColumn("gap", F.abs(F.col("labelled") - F.col("density")))
    return x.withColumn("r", F.row_number().over(Window.partitionBy("bin").orderBy(F.desc("gap"), "page_id"))).where("r <= 3").select("bin", "page_id", "gap")


_U = "('0x' || substr(md5('{salt}' || page_id), 1, 7))::BIGINT / 268435456.0"


@query("hybrid_sample", f"""WITH h AS (SELECT lower(regexp_extract(url, '^[A-Za-z]+://([^/?#:]+)', 1)) AS host, page_id, {_U.format(salt="r:")} AS u, {_U.format(salt="p:")} AS v FROM pages),
  n AS (SELECT host FROM h GROUP BY 1 ORDER BY count(*) DESC, host LIMIT 3), x AS (SELECT h.*, host IN (SELECT host FROM n) AS top FROM h),
  z AS (SELECT count(*) AS n, count(*) FILTER (top AND u >= 0.45) AS rest FROM x)
  SELECT page_id, CASE WHEN u < 0.45 THEN 'random' ELSE 'popular' END AS part FROM x, z WHERE u < 0.45 OR (top AND v < 0.05 * n / rest)""")
def _(t):
    """Half of the pages: nine tenths of the sample at random, one tenth from the most popular hosts (W2, L140)."""
    u = lambda salt: F.conv(F.substring(F.md5(F.concat(F.lit(salt), F.col("page_id").cast("string")).cast("binary")), 1, 7), 16, 10).cast("long") / 268435456.0
    h = t("pages").select("page_id", F.lower(F.regexp_extract("url", r"^[A-Za-z]+://([^/?#:]+)", 1)).alias("host"), u("r:").alias("u"), u("p:").alias("v"))
    top = h.groupBy("host").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "host").limit(3).select("host", F.lit(True).alias("top"))
    x = h.join(F.broadcast(top), "host", "left").withColumn("top", F.coalesce("top", F.lit(False)))
    sizes = x.agg(F.count("*").alias("n"), F.count(F.when(F.col("top") & (F.col("u") >= 0.45), 1)).alias("rest"))
    x = x.crossJoin(F.broadcast(sizes))  # one row
    popular = F.col("top") & (F.col("v") < 0.05 * F.col("n") / F.col("rest"))
    return x.where((F.col("u") < 0.45) | popular).select("page_id", F.when(F.col("u") < 0.45, "random").otherwise("popular").alias("part"))


# -- labelled against density, as published (L261): the other partner of the ratio
def _density_lengths(t):
    a, b = METHODS["labelled"](t("pages")).withColumnRenamed("pred", "text_a"), METHODS["density"](t("pages")).withColumnRenamed("pred", "text_b")
    x = a.join(b, "page_id").select("page_id", F.length("text_a").cast("long").alias("len_a"), F.length("text_b").cast("long").alias("len_b"))
    # the SQL rounds the binary product, not its decimal spelling: 41 / 640 is 0.064062
    x = x.withColumn("ratio", F.round(M.length_ratio(F.col("len_a"), F.col("len_b")) * 1e6) / 1e6)
    return x.withColumn("bin", M.ratio_bin(F.col("ratio")))


@query("density_length_ratio")
def _(t):
    return _density_lengths(t).select("page_id", "len_a", "len_b", "ratio")


@query("density_length_summary")
def _(t):
    return _density_lengths(t).agg(F.round(F.avg(F.try_divide("len_a", "len_b")), 6).alias("mean_ratio"), F.round(F.sum("len_a") / F.sum("len_b"), 6).alias("ratio_of_sums"), F.round(F.avg("ratio"), 6).alias("mean_signed"))


@query("density_ratio_histogram")
def _(t):
    return _density_lengths(t).groupBy("bin").agg(F.count("*").alias("n"))


#: Pairs that are judged in each of the 20 bins (L274).
PER_BIN = 500


@query("density_stratified_pairs")
def _(t):
    return M.stratified(_density_lengths(t).select("bin", "page_id"), "bin", "page_id", PER_BIN)


# -- labeller
@query("labeller_cv")
def _(t):
    """Trained on some hosts, judged on others, on pages without semantic tags; with and without neighbours."""
    gold = L.examples(t("pages")).select("page_id", "block_id", "gold")
    x = L.examples(FX.shuffled(t)).drop("gold").join(gold, ["page_id", "block_id"])
    even = F.xxhash64(F.regexp_extract("url", r"://([^/]+)", 1)) % 2 == 0
    parts = [L.block_f1(L.predict(L.fit(x.where(even), c), x.where(~even), c)).withColumn("context", F.lit(c)) for c in (True, False)]
    return parts[0].unionByName(parts[1])


@query("scorer_scaling_curve")
def _(t):
    """Block F1 on other hosts as the training share grows."""
    gold = L.examples(t("pages")).select("page_id", "block_id", "gold")
    # pages are parsed and joined once, not for each of the four fits and judgements
    x = cut(L.examples(FX.shuffled(t)).drop("gold").join(gold, ["page_id", "block_id"]))
    even = F.xxhash64(F.regexp_extract("url", r"://([^/]+)", 1)) % 2 == 0
    part = F.pmod(F.xxhash64("page_id", F.lit("share")), F.lit(100))
    out = [L.block_f1(L.predict(L.fit(x.where(even & (part < s))), x.where(~even))).withColumn("share", F.lit(s)) for s in (10, 25, 50, 100)]
    return reduce(lambda a, b: a.unionByName(b), out)


@query("improvement_loop")
def _(t):
    """Block F1 on other hosts over three rounds, each of which adds the pages that the model fails on to its training set."""
    gold = L.examples(t("pages")).select("page_id", "block_id", "gold")
    x = cut(L.examples(FX.shuffled(t)).drop("gold").join(gold, ["page_id", "block_id"]))
    even = F.xxhash64(F.regexp_extract("url", r"://([^/]+)", 1)) % 2 == 0
    return L.improve(x.where(even), x.where(~even), start=1, rounds=3)


# -- downstream stand-in
def _entropy_sql(train: str) -> str:
    tok = r"list_filter(string_split_regex(lower(text), '\s+'), lambda x: x <> '')"
    return f"""c AS (SELECT w, count(*) AS c FROM (SELECT unnest({tok}) AS w FROM {train}) GROUP BY 1), h AS (SELECT w, count(*) AS h FROM (SELECT unnest({tok}) AS w FROM benchmark) GROUP BY 1),
z AS (SELECT sum(c) AS n, count(*) AS v FROM c)
SELECT round(-sum(h * log2((coalesce(c, 0) + 0.5) / (n + 0.5 * (v + 1)))) / sum(h), 4) AS bits, true AS standin FROM h LEFT JOIN c USING (w), z"""


@query("lm_cross_entropy", f"WITH {_entropy_sql('documents')}")
def _(t):
    return M.cross_entropy(t("documents"), t("benchmark")).withColumn("standin", F.lit(True))


_BUDGET_SQL = rf"""w AS (SELECT ('0x' || substr(md5(doc_id::VARCHAR), 1, 7))::BIGINT / 268435456.0 AS u, unnest(list_filter(string_split_regex(lower(text), '\s+'), lambda x: x <> '')) AS w FROM documents),
b AS (SELECT unnest({list(M.BUDGETS)}::DOUBLE[]) AS share), v AS (SELECT count(DISTINCT w) AS v FROM w),
h AS (SELECT w, count(*) AS h FROM (SELECT unnest(list_filter(string_split_regex(lower(text), '\s+'), lambda x: x <> '')) AS w FROM benchmark) GROUP BY 1),
c AS (SELECT share, w, count(*) AS c FROM w JOIN b ON u < share GROUP BY 1, 2), n AS (SELECT share, coalesce(sum(c), 0) AS n FROM b LEFT JOIN c USING (share) GROUP BY 1)
SELECT share, round(-sum(h * log2((coalesce(c, 0) + 0.5) / (n + 0.5 * (v + 1)))) / sum(h), 4) AS bits, true AS standin FROM n CROSS JOIN h CROSS JOIN v LEFT JOIN c USING (share, w) GROUP BY share"""


@query("budget_curve", f"WITH {_BUDGET_SQL}")
def _(t):
    """Cross-entropy over 15 nested hash-ordered token budgets."""
    return M.budget_curve(t("documents"), t("benchmark")).withColumn("standin", F.lit(True))


@query("lm_order_curve")
def _(t):
    """Bits per token of the benchmark under models of order 1, 2 and 3 of `documents`, with and without documents that hold its passages."""
    docs = t("documents")
    clean = docs.join(cut(overlap(docs, t("benchmark")).select("doc_id").distinct()), "doc_id", "left_anti")
    parts = [M.ngram_cross_entropy(d, t("benchmark"), order=k).select(F.lit(name).alias("corpus"), F.lit(k).alias("order"), "bits") for name, d in (("all", docs), ("decontaminated", clean)) for k in (1, 2, 3)]
    return reduce(lambda a, b: a.unionByName(b), parts).withColumn("standin", F.lit(True))


def _corpus(t, name, model):
    """doc_id, text, url and lang_pred of the pages by one method: the input of the stages. Written out, as these read it several times."""
    kind = t("pages").schema["url"].dataType.simpleString()
    x = METHODS[name](t("pages"), keep=("url",))
    return cut(row_pass(x, lambda k, text, url: (k, text, url, language_of(model, text)), f"doc_id long, text string, url {kind}, lang_pred string"))


@query("corpus_downstream")
def _(t):
    """Four corpora that differ in their extractor only, after exact dedup and the row-wise stages, scored on the benchmark by orders 1 and 3."""
    out, model = [], language_model(t("documents"))
    for name in METHODS:
        kept = cut(row_stages(_corpus(t, name, model), POLICIES["default"]).select("text"))
        out += [M.ngram_cross_entropy(kept, t("benchmark"), order=k).select(F.lit(name).alias("extractor"), F.lit(k).alias("order"), "bits") for k in (1, 3)]
    return reduce(lambda a, b: a.unionByName(b), out).withColumn("standin", F.lit(True))


@query("corpus_pair")
def _(t):
    """Two corpora that differ in their extractor only, through the same stages (E13); the language classifier is trained on `documents`."""
    model = language_model(t("documents"))
    out = [attrition(_corpus(t, name, model), POLICIES["default"])[1].withColumn("extractor", F.lit(name)) for name in ("labelled", "density")]
    return out[0].unionByName(out[1])


@query("density_corpus_attrition")
def _(t):
    """The density corpus through the same stages."""
    return attrition(_corpus(t, "density", language_model(t("documents"))), POLICIES["default"])[1]


@query("snapshot_build")
def _(t):
    """Each snapshot (hash half of the sources) built by itself, then both with equal texts across them kept once."""
    d = t("documents")
    half = F.pmod(F.crc32(F.coalesce("source", F.lit("")).cast("binary")), F.lit(2))
    kept, rows = [], []
    for s in (0, 1):
        left, stages = attrition(d.where(half == s), POLICIES["default"])
        kept.append(left.select("doc_id", "text"))
        rows.append(stages.withColumn("snapshot", F.lit(str(s))))
    both = kept[0].unionByName(kept[1])
    once = exact_dedup(both).select("doc_id")
    merged = both.join(once, "doc_id", "left_semi").agg(F.lit(6).alias("stage"), F.lit("merged").alias("name"), F.count("*").alias("docs_out"), F.coalesce(F.sum(F.size(M.tokens("text"))), F.lit(0)).cast("long").alias("tokens_out"), F.lit("both").alias("snapshot"))
    return rows[0].unionByName(rows[1]).unionByName(merged)


@query("quality_model_auc")
def _(t):
    """A quality classifier on rule measures, fitted on even ids and judged on odd ones: the extension the paper leaves out."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.evaluation import BinaryClassificationEvaluator
    from pyspark.ml.functions import array_to_vector

    from webtext.operators.corpus import measures

    names = ("n_words", "mean_word_len", "hash_ratio", "alpha_share", "n_stop", "dup_line_share", "dup_line_chars")
    x = measures(t("documents")).join(t("labels"), "doc_id").select("doc_id", F.col("quality").cast("double").alias("y"), array_to_vector(F.array(*[F.log1p(F.col(n)).cast("double") for n in names])).alias("v"))
    model = LogisticRegression(featuresCol="v", labelCol="y", maxIter=30).fit(x.where("doc_id % 2 = 0"))
    auc = BinaryClassificationEvaluator(labelCol="y").evaluate(model.transform(x.where("doc_id % 2 = 1")))
    return t.spark.range(1).select(F.lit(round(auc, 4)).alias("auc"))
