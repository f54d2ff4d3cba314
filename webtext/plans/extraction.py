"""Queries on pages: the extractor, templates, formatting and baselines."""

from __future__ import annotations

from pyspark.sql import functions as F

from webtext.functions import baselines as B
from webtext.functions.blocks import Config, block_rows, is_layout_table
from webtext.functions.content import formulas_in, guess_language
from webtext.functions.decoding import VOCAB, decode, labels_of, valid
from webtext.functions.dom import parse
from webtext.operators import extract as X
from webtext.operators import formatting as M
from webtext.operators import templates as T
from webtext.operators.passes import row_pass
from webtext.plans import fixtures as FX
from webtext.plans.registry import query

#: Article, heading and key of a page's text; joined to the least document of equal text.
GOLD = r"""
a AS (SELECT page_id, html, regexp_extract(html, '(?s)<article>(.*?)</article>', 1) AS art FROM pages),
b AS (SELECT page_id, html, replace(replace(regexp_replace(regexp_extract(art, '(?s)<h1>(.*?)</h1>', 1), '<[^>]*>', '', 'g'), '&quot;', '"'), '&amp;', '&') AS h1,
  regexp_replace(replace(replace(regexp_replace(regexp_extract(art, '(?s)</h1>(.*)', 1), '<[^>]*>', '', 'g'), '&quot;', '"'), '&amp;', '&'), '\s', '', 'g') AS k FROM a),
d AS (SELECT regexp_replace(text, '\s', '', 'g') AS k, min(doc_id) AS doc_id FROM documents GROUP BY 1),
g AS (SELECT page_id, html, trim(regexp_replace(h1, '\s+', ' ', 'g')) AS h1, text FROM b JOIN d USING (k) JOIN documents USING (doc_id)),
gold AS (SELECT page_id, h1 || chr(10) || array_to_string(list_filter(list_transform(string_split(text, chr(10)), lambda x: trim(regexp_replace(x, '\s+', ' ', 'g'))), lambda x: x <> ''), chr(10)) AS main_text FROM g)
"""
MAIN = f"WITH {GOLD} SELECT page_id, main_text FROM gold"
PARAGRAPHS = "(len(string_split(html, '<p>')) - 1)"


@query("extract_core", MAIN)
def _(t):
    return X.core(t("pages")).select("page_id", "main_text")


@query("main_text", MAIN)
def _(t):
    return X.core(t("pages"), mode="fsm").select("page_id", "main_text")


@query("oracle_scorer_bound", MAIN)
def _(t):
    """The gold scorer (B4) instead of a real one: what post-processing can reach at best."""

    def gold(blocks):
        return [(-1.0, 1.0) if "/article" in f"/{b.node.path()}" else (1.0, -1.0) for b in blocks]

    return X.core(t("pages"), gold).select("page_id", "main_text")


@query("main_html", f"WITH {GOLD} SELECT page_id, (len(string_split(main_text, chr(10))))::BIGINT AS n_kept, sha256(regexp_replace(main_text, '\\s', '', 'g')) AS text_sha FROM gold")
def _(t):
    x = X.core(t("pages"))
    return x.select("page_id", F.aggregate("labels", F.lit(0).cast("long"), lambda a, y: a + y).alias("n_kept"), F.sha2(F.regexp_replace("main_text", r"\s", ""), 256).alias("text_sha"))


@query("page_blocks", f"SELECT page_id, ({PARAGRAPHS} + 4)::BIGINT AS n_blocks FROM pages")
def _(t):
    return X.blocks(t("pages")).groupBy("page_id").agg(F.count("*").alias("n_blocks"))


@query("view_alignment", f"SELECT page_id, ({PARAGRAPHS} + 4)::BIGINT AS n_simplified, ({PARAGRAPHS} + 4)::BIGINT AS n_mapping FROM pages")
def _(t):
    return X.blocks(t("pages")).groupBy("page_id").agg(F.count("simplified").alias("n_simplified"), F.count("raw_html").alias("n_mapping"))


_LABELS = f"SELECT page_id, ({PARAGRAPHS} + 1)::BIGINT AS n_main, 3::BIGINT AS n_other FROM pages"


def _counted(df, name):
    return df.groupBy("page_id").agg(F.sum(F.col(name).cast("long")).alias("n_main"), F.sum(1 - F.col(name).cast("long")).alias("n_other"))


@query("gold_blocks", _LABELS)
def _(t):
    return _counted(X.gold_labels(t("pages")), "gold")


@query("lexicon_labels", _LABELS)
def _(t):
    return _counted(X.lexicon_labels(t("pages")), "label")


@query("block_labels", _LABELS)
def _(t):
    """Labels parsed natively from the wire form."""
    x = X.core(t("pages"), mode="fsm").select("page_id", "n_blocks", F.from_json("wire", "map<string,string>").alias("m"))
    y = F.transform(F.sequence(F.lit(1), F.col("n_blocks")), lambda k: (F.coalesce(F.try_element_at("m", k.cast("string")), F.lit("other")) == "main").cast("long"))
    main = F.aggregate(y, F.lit(0).cast("long"), lambda a, v: a + v)
    return x.select("page_id", main.alias("n_main"), (F.col("n_blocks") - main).alias("n_other"))


@query("block_confusion", f"SELECT sum({PARAGRAPHS} + 1)::BIGINT AS tp, 0::BIGINT AS fp, 0::BIGINT AS fn, (3 * count(*))::BIGINT AS tn FROM pages")
def _(t):
    x = X.gold_labels(t("pages")).join(X.lexicon_labels(t("pages")), ["page_id", "block_id"])
    cell = lambda g, y: F.count(F.when((F.col("gold") == g) & (F.col("label") == y), 1))
    return x.agg(cell(1, 1).alias("tp"), cell(0, 1).alias("fp"), cell(1, 0).alias("fn"), cell(0, 0).alias("tn"))


@query("char_confusion")
def _(t):
    """The same weighted by the characters of each block, with precision, recall and F1 (D3)."""
    size = X.blocks(t("pages")).select("page_id", "block_id", F.col("n_chars").cast("long").alias("n"))
    x = X.gold_labels(t("pages")).join(X.lexicon_labels(t("pages")), ["page_id", "block_id"]).join(size, ["page_id", "block_id"])
    cell = lambda g, y: F.coalesce(F.sum(F.when((F.col("gold") == g) & (F.col("label") == y), F.col("n"))), F.lit(0))
    c = x.agg(cell(1, 1).alias("tp"), cell(0, 1).alias("fp"), cell(1, 0).alias("fn"), cell(0, 0).alias("tn"))
    p, r = F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), F.try_divide(F.col("tp"), F.col("tp") + F.col("fn"))
    return c.withColumns({"p": F.round(p, 6), "r": F.round(r, 6), "f1": F.round(2 * p * r / (p + r), 6)})


@query("fsm_output_valid", f"SELECT page_id, ({PARAGRAPHS} + 4)::BIGINT AS n_keys, 0::BIGINT AS n_bad FROM pages")
def _(t):
    m = F.from_json("wire", "map<string,string>")
    keys = F.transform(F.sequence(F.lit(1), F.col("n_blocks")), lambda k: k.cast("string"))
    bad = F.size(F.array_except(F.map_keys(m), keys)) + F.size(F.array_except(keys, F.map_keys(m))) + F.size(F.filter(F.map_values(m), lambda v: ~v.isin("main", "other")))
    return X.core(t("pages"), mode="fsm").select("page_id", F.size(F.map_keys(m)).cast("long").alias("n_keys"), bad.cast("long").alias("n_bad"))


@query("label_roundtrip", f"SELECT page_id, ({PARAGRAPHS} + 4)::BIGINT AS n_same FROM pages")
def _(t):
    fast, fsm = X.core(t("pages"), mode="fast"), X.core(t("pages"), mode="fsm").select("page_id", F.col("labels").alias("other"))
    same = F.size(F.filter(F.zip_with("labels", "other", lambda a, b: a == b), lambda x: x))
    return fast.join(fsm, "page_id").select("page_id", same.cast("long").alias("n_same"))


@query("decode_ablation")
def _(t):
    """Malformed outputs under random logits, for the blocks of each page: free, fsm and fast decoding."""
    import random

    def run(page_id, page):
        out, n = [], len(block_rows(page)[1])
        for mode in ("free", "fsm", "fast"):
            rng = random.Random(page_id)
            rows = [[rng.gauss(0, 1) for _ in VOCAB] for _ in range(max(1, n))]
            logits = (lambda prefix, block: rows[len(prefix) % len(rows)]) if mode == "free" else (lambda prefix, block: rows[block - 1])
            wire = decode(n, logits, mode)
            out.append((page_id, n, mode, int(valid(wire, n)), sum(labels_of(wire, n)[0])))
        return out

    return row_pass(t("pages").select("page_id", "html"), run, "page_id long, n int, mode string, is_valid int, n_main int", many=True)


@query("tag_inventory", r"""SELECT lower(tag) AS tag, count(DISTINCT page_id)::BIGINT AS n_pages, count(*)::BIGINT AS n_tags FROM (
  SELECT page_id, unnest(regexp_extract_all(regexp_replace(html, '(?s)<script>.*?</script>', '<script></script>', 'g'), '<([a-zA-Z][a-zA-Z0-9]*)', 1)) AS tag FROM pages) GROUP BY 1""")
def _(t):
    return X.nodes(t("pages")).groupBy("tag").agg(F.countDistinct("page_id").alias("n_pages"), F.count("*").alias("n_tags"))


@query("dom_nodes", r"""SELECT page_id, len(regexp_extract_all(regexp_replace(html, '(?s)<script>.*?</script>', '<script></script>', 'g'), '<[a-zA-Z]'))::BIGINT AS n_nodes FROM pages""")
def _(t):
    return X.nodes(t("pages")).groupBy("page_id").agg(F.count("*").alias("n_nodes"))


@query("attr_inventory", r"""SELECT attr, count(*)::BIGINT AS n FROM (SELECT unnest(regexp_extract_all(tag, '\s([a-z]+)=', 1)) AS attr FROM (
  SELECT unnest(regexp_extract_all(regexp_replace(html, '(?s)<script>.*?</script>|<!--.*?-->', '', 'g'), '<[a-zA-Z][^>]*>')) AS tag FROM pages)) GROUP BY 1""")
def _(t):
    return X.attributes(t("pages")).groupBy("attr").agg(F.count("*").alias("n"))


@query("removed_tag_counts", "SELECT 'script' AS tag, sum(len(string_split(html, '<script')) - 1)::BIGINT AS n FROM pages UNION ALL SELECT 'style', sum(len(string_split(html, '<style')) - 1)::BIGINT FROM pages")
def _(t):
    return X.nodes(t("pages")).where(F.col("tag").isin("style", "script", "header", "aside")).groupBy("tag").agg(F.count("*").alias("n"))


@query("truncated_blocks", f"""WITH {GOLD}, l AS (SELECT page_id, unnest(string_split(main_text, chr(10))) AS line FROM gold)
  SELECT page_id, count(*) FILTER (length(line) > 200)::BIGINT AS n_truncated FROM l GROUP BY 1""")
def _(t):
    x = X.blocks(t("pages"))
    below = F.concat(F.lit("/"), "path", F.lit("/")).contains("/article/")
    return x.groupBy("page_id").agg(F.count(F.when(below & F.col("truncated"), 1)).alias("n_truncated"))


@query("truncation_ablation")
def _(t):
    """Simplified characters and label agreement with truncation on and off."""
    on = X.core(t("pages")).select("page_id", "labels", "simplified_chars", "raw_chars")
    off = X.core(t("pages"), cfg=Config(para_chars=0, rows=0, cells=0, items=0)).select("page_id", F.col("labels").alias("l2"), F.col("simplified_chars").alias("c2"))
    return on.join(off, "page_id").agg(
        F.count(F.when(F.col("labels") == F.col("l2"), 1)).alias("n_agree"), F.count("*").alias("n_pages"), F.round(F.sum("simplified_chars") / F.sum("raw_chars"), 4).alias("share_cut"), F.round(F.sum("c2") / F.sum("raw_chars"), 4).alias("share_uncut")
    )


def _variants(t):
    """Tag presets, kept attributes and br splitting side by side (A3-A5)."""
    out = None
    for name, cfg in (("default", Config()), ("extended", Config(drop="extended")), ("no_tags_dropped", Config(drop="none")), ("no_attributes", Config(keep=())), ("all_attributes", Config(keep=None)), ("split_br", Config(split_br=True))):
        own = X.core(t("pages"), cfg=cfg).agg(F.lit(name).alias("variant"), F.sum("n_blocks").alias("n_blocks"), F.sum("simplified_chars").alias("simplified_chars"))
        out = own if out is None else out.unionByName(own)
    return out


query("simplify_variants")(_variants)


@query("token_reduction", f"""WITH {GOLD} SELECT
  (SELECT sum(len(list_filter(string_split_regex(html, '\\s+'), lambda x: x <> '')))::BIGINT FROM pages) AS raw_tokens,
  (SELECT sum({PARAGRAPHS} + 4)::BIGINT FROM pages) AS output_tokens,
  (SELECT sum(len(list_filter(string_split_regex(main_text, '\\s+'), lambda x: x <> '')))::BIGINT FROM gold) AS generated_tokens""")
def _(t):
    """White-space tokens: raw page, one label per block, and the text a generative extractor would write."""
    ws = lambda c: F.size(F.filter(F.split(c, r"\s+"), lambda x: x != "")).cast("long")
    x = X.core(t("pages")).select("page_id", "n_blocks", "main_text").join(t("pages").select("page_id", ws("html").alias("raw")), "page_id")
    return x.agg(F.sum("raw").alias("raw_tokens"), F.sum("n_blocks").cast("long").alias("output_tokens"), F.sum(ws("main_text")).alias("generated_tokens"))


@query("token_load")
def _(t):
    """Characters per four as tokens: raw, simplified, labels, text (compare L200)."""
    x = X.core(t("pages"))
    return x.agg(F.avg(F.col("raw_chars") / 4).alias("raw"), F.avg(F.col("simplified_chars") / 4).alias("simplified"), F.avg("n_blocks").alias("labels"), F.avg(F.length("main_text") / 4).alias("text"), F.lit(True).alias("standin"))


@query("generative_cost", f"""WITH {GOLD} SELECT sum(len(list_filter(string_split_regex(html, '\\s+'), lambda x: x <> '')))::BIGINT AS in_tokens,
  sum(len(list_filter(string_split_regex(main_text, '\\s+'), lambda x: x <> '')))::BIGINT AS out_tokens FROM gold JOIN pages USING (page_id)""")
def _(t):
    ws = lambda c: F.size(F.filter(F.split(c, r"\s+"), lambda x: x != "")).cast("long")
    return t("pages").join(FX.gold(t), "page_id").agg(F.sum(ws("html")).alias("in_tokens"), F.sum(ws("gold_text")).alias("out_tokens"))


# -- templates
HOST = r"lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]+)', 1))"


@query("pages_per_host", f"SELECT {HOST} AS host, count(*)::BIGINT AS n_pages FROM pages GROUP BY 1")
def _(t):
    return t("pages").groupBy(T.host("url").alias("host")).agg(F.count("*").alias("n_pages"))


@query("canonical_url", r"""SELECT page_id, regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(url, '#.*$', ''),
  '([?&])(utm_[a-z]+|ref)=[^&]*', '\1', 'g'), '&+', '&', 'g'), '\?&', '?', 'g'), '[?&]+$', ''), '^https?://', ''), '^(www|m)\.', ''), '/$', ''), '\.html$', '') AS canon FROM pages""")
def _(t):
    return t("pages").select("page_id", T.canonical("url").alias("canon"))


_ONE_TEMPLATE = f"SELECT {HOST} AS host, count(*)::BIGINT AS n_pages FROM pages GROUP BY 1"


@query("template_exact")
def _(t):
    return T.index(t("pages")).groupBy("host", "sig").agg(F.count("*").alias("n_pages"))


@query("template_clusters", None)
def _(t):
    return T.clusters(T.index(t("pages"))).groupBy("host", "cluster_id").agg(F.count("*").alias("n_pages"))


@query("template_lsh", _ONE_TEMPLATE)
def _(t):
    """Near-equal signatures of a host are one cluster."""
    c = T.clusters(T.index(t("pages")), "lsh")
    return c.groupBy("host", "cluster_id").agg(F.count("*").alias("n_pages")).drop("cluster_id")


@query("dom_shape", r"""WITH s AS (SELECT page_id, regexp_replace(html, '(?s)<script>.*?</script>', '<script></script>', 'g') AS h FROM pages)
  SELECT page_id, len(regexp_extract_all(h, '<[a-zA-Z]'))::BIGINT AS n_tags, len(list_distinct(list_transform(regexp_extract_all(h, '<([a-zA-Z][a-zA-Z0-9]*)', 1), lambda x: lower(x))))::BIGINT AS n_distinct_tags FROM s""")
def _(t):
    return X.shapes(t("pages")).select("page_id", F.col("n_tags").cast("long").alias("n_tags"), F.col("n_distinct_tags").cast("long").alias("n_distinct_tags"))


@query("representatives")
def _(t):
    return T.representatives(T.clusters(T.index(t("pages")), "lsh")).select("host", "n_pages", "rep_page_id")


@query("representative_ablation")
def _(t):
    """Pages whose propagated text equals their own extraction, by how the representative is chosen."""
    idx = T.clusters(T.index(t("pages")), "lsh")
    own = X.core(t("pages")).select("page_id", F.col("main_text").alias("own"))
    out = None
    for strategy in ("coverage", "random", "longest", "worst"):
        got = T.propagate(t("pages"), idx, T.cluster_rules(t("pages"), T.representatives(idx, strategy)))
        row = got.join(own, "page_id").agg(F.lit(strategy).alias("strategy"), F.count("*").alias("n_pages"), F.count(F.when(F.col("main_text") == F.col("own"), 1)).alias("n_equal"))
        out = row if out is None else out.unionByName(row)
    return out


@query("rep_extract")
def _(t):
    reps = T.representatives(T.clusters(T.index(t("pages")), "lsh"))
    return X.core(t("pages").join(reps.select(F.col("rep_page_id").alias("page_id")), "page_id", "left_semi")).select("page_id", "main_text")


@query("cluster_rules")
def _(t):
    reps = T.representatives(T.clusters(T.index(t("pages")), "lsh"))
    return T.cluster_rules(t("pages"), reps).groupBy("selector", "xpath", "css", "action").agg(F.count("*").alias("n_clusters"), F.min("purity").alias("least_purity"))


def _propagated(t, mode="lsh", level="subdomain", broadcast=None):
    idx = T.clusters(T.index(t("pages"), level), mode)
    return T.propagate(t("pages"), idx, T.cluster_rules(t("pages"), T.representatives(idx)), broadcast=broadcast)


@query("propagated_main", MAIN)
def _(t):
    return _propagated(t).select("page_id", "main_text")


@query("propagated_main_shuffled", MAIN)
def _(t):
    """The same by a join on the cluster instead of broadcast rules."""
    return _propagated(t, broadcast=False).select("page_id", "main_text")


@query("propagation_agreement", "SELECT count(*)::BIGINT AS n_pages, count(*)::BIGINT AS n_equal FROM pages")
def _(t):
    own = X.core(t("pages")).select("page_id", F.col("main_text").alias("own"))
    return _propagated(t).join(own, "page_id").agg(F.count("*").alias("n_pages"), F.count(F.when(F.col("main_text") == F.col("own"), 1)).alias("n_equal"))


@query("fallback_pages", "SELECT page_id FROM pages WHERE false")
def _(t):
    return T.fallback(_propagated(t))


@query("inference_share", f"SELECT count(*)::BIGINT AS n_pages, count(DISTINCT {HOST})::BIGINT AS n_clusters, round(count(DISTINCT {HOST}) / count(*), 6) AS share FROM pages")
def _(t):
    return T.inference_share(T.clusters(T.index(t("pages")), "lsh"))


@query("cluster_ablation")
def _(t):
    """Share of pages to label and share of equal results, by cluster scope and mode (C14)."""
    own = X.core(t("pages")).select("page_id", F.col("main_text").alias("own"))
    out = None
    for level in ("subdomain", "registered", "global"):
        for mode in ("exact", "lsh"):
            idx = T.clusters(T.index(t("pages"), level), mode)
            got = T.propagate(t("pages"), idx, T.cluster_rules(t("pages"), T.representatives(idx)))
            equal = got.join(own, "page_id").agg(F.count(F.when(F.col("main_text") == F.col("own"), 1)).alias("n_equal"))
            row = T.inference_share(idx).crossJoin(equal).select(F.lit(level).alias("level"), F.lit(mode).alias("mode"), "n_pages", "n_clusters", "share", "n_equal")
            out = row if out is None else out.unionByName(row)
    return out


# -- formatting
_UNITS = f"WITH {GOLD} SELECT page_id, 1::BIGINT AS n_title, (len(string_split(main_text, chr(10))) - 1)::BIGINT AS n_paragraph FROM gold"


@query("content_list", _UNITS)
def _(t):
    c = M.content_list(X.core(t("pages")))
    return c.select("page_id", M.count_type("units", "title").cast("long").alias("n_title"), M.count_type("units", "paragraph").cast("long").alias("n_paragraph"))


@query("content_list_violations", "SELECT 0::BIGINT AS n_violations")
def _(t):
    return M.violations(M.content_list(X.core(t("pages")))).agg(F.count("*").alias("n_violations"))


_MD = f"""WITH {GOLD} SELECT page_id, sha256(m) AS md_sha, length(m)::BIGINT AS md_chars FROM (SELECT page_id, '# ' || replace(main_text, chr(10), chr(10) || chr(10)) AS m FROM gold)"""


@query("markdown", _MD)
def _(t):
    c = M.content_list(X.core(t("pages"))).select("page_id", M.render("units").alias("md"))
    return c.select("page_id", F.sha2("md", 256).alias("md_sha"), F.length("md").cast("long").alias("md_chars"))


@query("plain_render", MAIN)
def _(t):
    return M.content_list(X.core(t("pages"))).select("page_id", M.render("units", "text").alias("main_text"))


@query("html_render", f"WITH {GOLD} SELECT page_id, regexp_replace(main_text, '\\s', '', 'g') AS squeezed FROM gold")
def _(t):
    """Minimal HTML, read again by the parser: the same text."""
    c = M.content_list(X.core(t("pages"))).select("page_id", M.render("units", "html").alias("main_html"))
    again = M.content_list(c).select("page_id", M.render("units", "text").alias("x"))
    return again.select("page_id", F.regexp_replace("x", r"\s", "").alias("squeezed"))


@query("jsonl_render", _UNITS)
def _(t):
    """JSON lines, parsed again."""
    c = M.content_list(X.core(t("pages"))).select("page_id", F.split(M.render("units", "jsonl"), "\n").alias("l"))
    kind = F.transform("l", lambda x: F.get_json_object(x, "$.type"))
    return c.select("page_id", F.size(F.filter(kind, lambda k: k == "title")).cast("long").alias("n_title"), F.size(F.filter(kind, lambda k: k == "paragraph")).cast("long").alias("n_paragraph"))


@query("turns_to_content_list", "SELECT conv_id, string_agg(role || ': ' || text, chr(10) || chr(10) ORDER BY turn) AS md FROM conversations GROUP BY 1")
def _(t):
    return M.from_turns(t("conversations")).select("conv_id", M.render("units").alias("md"))


@query("code_blocks", FX.CODE_SQL.format(out="fx_id, code"))
def _(t):
    c = M.content_list(FX.code(t), "fx_id", "html").select("fx_id", F.explode("units").alias("u")).where("u.type = 'code'")
    return c.select("fx_id", F.col("u.text").alias("code"))


@query("code_language", FX.CODE_SQL.format(out="lang, count(*)::BIGINT AS n") + " GROUP BY lang")
def _(t):
    found = row_pass(FX.code(t).select("fx_id", "gold_code"), lambda k, c: (k, guess_language(c)), "fx_id long, lang string")
    return found.groupBy("lang").agg(F.count("*").alias("n"))


@query("table_markdown", FX.TABLE_SQL)
def _(t):
    c = M.content_list(FX.table_simple(t), "fx_id", "html")
    return c.select("fx_id", M.render("units").alias("md"))


@query("table_complexity", FX.KIND_SQL)
def _(t):
    """Which table fixtures stay HTML, become pipes, or are linearised."""
    parts = FX.table_simple(t).select("html").unionByName(FX.table_complex(t).select("html")).unionByName(FX.table_nested(t).select("html"))
    c = M.content_list(parts.withColumn("fx_id", F.monotonically_increasing_id()), "fx_id", "html").select(F.explode("units").alias("u"))
    kind = F.when(F.col("u.rows").isNotNull(), "simple").when(F.col("u.html").isNotNull(), "complex").otherwise("nested")
    return c.groupBy(kind.alias("kind")).agg(F.count("*").alias("n"))


@query("table_html_kept", "SELECT l_orderkey AS fx_id, count(*)::BIGINT + 1 AS n_rows, 1::BIGINT AS n_spans FROM lineitem GROUP BY 1 HAVING count(*) > 1")
def _(t):
    c = M.content_list(FX.table_complex(t), "fx_id", "html").select("fx_id", F.col("units")[0]["html"].alias("h"))
    return c.select("fx_id", F.regexp_count("h", F.lit("<tr>")).cast("long").alias("n_rows"), F.regexp_count("h", F.lit("rowspan=")).cast("long").alias("n_spans"))


@query("table_linearized", "SELECT r_regionkey::BIGINT AS fx_id, string_agg(x, chr(10) ORDER BY k, n) AS text FROM (SELECT r_regionkey, r_name AS x, 0 AS k, 0 AS n FROM region UNION ALL SELECT n_regionkey, n_nationkey || ' ' || n_name, 1, n_nationkey FROM nation) GROUP BY 1")
def _(t):
    c = M.content_list(FX.table_nested(t), "fx_id", "html")
    return c.select("fx_id", F.array_join(F.transform("units", lambda u: u["text"]), "\n").alias("text"))


@query("list_markdown", FX.LIST_SQL)
def _(t):
    return M.content_list(FX.lists(t), "fx_id", "html").select("fx_id", M.render("units").alias("md"))


@query("media_units", "SELECT doc_id AS fx_id, 1::BIGINT AS n_image, 1::BIGINT AS n_video, 1::BIGINT AS n_audio FROM documents")
def _(t):
    c = M.content_list(FX.media(t), "fx_id", "html")
    return c.select("fx_id", *[M.count_type("units", k).cast("long").alias(f"n_{k}") for k in ("image", "video", "audio")])


@query("pruned_units", "SELECT count(*)::BIGINT AS n_pages, 0::BIGINT AS n_media FROM documents")
def _(t):
    """Media dropped for a language-model target."""
    media = ("image", "video", "audio")
    c = M.content_list(FX.media(t), "fx_id", "html").withColumn("units", M.select_types("units", drop=media))
    return c.agg(F.count("*").alias("n_pages"), F.coalesce(F.sum(M.count_type("units", *media)), F.lit(0)).cast("long").alias("n_media"))


@query("formula_modes", FX.FORMULA_SQL)
def _(t):
    c = M.content_list(FX.formula(t), "fx_id", "html").select("fx_id", F.explode("units").alias("u")).where("u.type in ('inline_formula', 'display_formula')")
    return c.select("fx_id", F.col("u.text").alias("tex"), F.col("u.display").alias("display"))


@query("formula_scan", "SELECT 0::BIGINT AS n_docs, 0::BIGINT AS n_formulas")
def _(t):
    """Documents hold junk runs of dollars and no formula; every match would be false."""
    x = row_pass(t("documents").where(F.col("text").contains("$")).select("doc_id", "text"), lambda k, s: (k, len(formulas_in(s))), "doc_id long, n int")
    return x.where("n > 0").agg(F.count("*").alias("n_docs"), F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n_formulas"))


@query("rich_pages", FX.RICH_SQL)
def _(t):
    """Fixtures rich in code, formulas or tables, found by type counts (L126)."""
    parts = [FX.code(t).select(F.lit("code").alias("fixture"), "html"), FX.formula(t).select(F.lit("formula").alias("fixture"), "html"), FX.table_simple(t).select(F.lit("table").alias("fixture"), "html")]
    x = parts[0].unionByName(parts[1]).unionByName(parts[2]).withColumn("fx_id", F.monotonically_increasing_id())
    c = M.content_list(x, "fx_id", "html").join(x.select("fx_id", "fixture"), "fx_id")
    has = lambda *k: F.count(F.when(F.exists("units", lambda u: u["type"].isin(*k)), 1))
    return c.groupBy("fixture").agg(has("code").alias("n_code"), has("inline_formula", "display_formula").alias("n_formula"), has("table").alias("n_table"))


@query("layout_table_detect", "SELECT 'data' AS fixture, 5::BIGINT AS n, 0::BIGINT AS n_layout UNION ALL SELECT 'layout', count(*)::BIGINT, count(*)::BIGINT FROM documents")
def _(t):
    x = FX.table_simple(t).select(F.lit("data").alias("fixture"), "html").unionByName(FX.table_layout(t).select(F.lit("layout").alias("fixture"), "html"))
    y = row_pass(x, lambda k, h: (k, int(is_layout_table(next(parse(h).elements("table"))))), "fixture string, layout int")
    return y.groupBy("fixture").agg(F.count("*").alias("n"), F.sum("layout").cast("long").alias("n_layout"))


@query("atomic_block_check", "SELECT 'table' AS fixture, 5::BIGINT AS n_blocks UNION ALL SELECT 'list', count(DISTINCT p_brand)::BIGINT FROM part")
def _(t):
    """Tables and lists stay one block each."""
    x = FX.table_simple(t).select(F.lit("table").alias("fixture"), "html").unionByName(FX.lists(t).select(F.lit("list").alias("fixture"), "html"))
    y = row_pass(x, lambda k, h: (k, len(block_rows(h)[1])), "fixture string, n int")
    return y.groupBy("fixture").agg(F.sum("n").cast("long").alias("n_blocks"))


# -- baselines
@query("density_main")
def _(t):
    return row_pass(t("pages").select("page_id", "html"), lambda k, h: (k, B.density(h)), "page_id long, main_html string").select("page_id", F.length("main_html").alias("n_chars"), F.sha2("main_html", 256).alias("html_sha"))


@query("density_text")
def _(t):
    return row_pass(t("pages").select("page_id", "html"), lambda k, h: (k, B.density_text(h)), "page_id long, text string").select("page_id", F.length("text").alias("n_chars"), F.sha2("text", 256).alias("text_sha"))


_RULEBOOK = f"""WITH {GOLD}, l AS (SELECT page_id, generate_subscripts(string_split(main_text, chr(10)), 1) AS i, unnest(string_split(main_text, chr(10))) AS line FROM gold),
 r AS (SELECT page_id, string_agg(line, chr(10) ORDER BY i) AS x FROM l WHERE i = 1 OR length(line) >= 25 GROUP BY 1)
 SELECT page_id, length(x)::BIGINT AS n_chars, sha256(x) AS text_sha FROM r"""


@query("rulebook_main", _RULEBOOK)
def _(t):
    x = row_pass(t("pages").select("page_id", "html"), lambda k, h: (k, B.rulebook(h)), "page_id long, text string")
    return x.select("page_id", F.length("text").cast("long").alias("n_chars"), F.sha2("text", 256).alias("text_sha"))


@query("strip_all_text", r"""SELECT page_id, length(x)::BIGINT AS n_chars, sha256(x) AS text_sha FROM (SELECT page_id,
  trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script\b.*?</script>|<style\b.*?</style>|<!--.*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g'), '\s+', ' ', 'g')) AS x FROM pages)""")
def _(t):
    x = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " "), r"<[^>]*>", " ")
    return t("pages").select("page_id", F.trim(F.regexp_replace(x, r"\s+", " ")).alias("x")).select("page_id", F.length("x").cast("long").alias("n_chars"), F.sha2("x", 256).alias("text_sha"))


@query("thread_extract", "SELECT conv_id AS fx_id, string_agg(trim(regexp_replace(text, '\\s+', ' ', 'g')), chr(10) ORDER BY turn) AS main_text FROM conversations GROUP BY 1")
def _(t):
    """Conversational pages: turns are kept, counters and time stamps are not (L152)."""
    x = FX.threads(t).select(F.col("fx_id").alias("page_id"), "html")
    return X.core(x).select(F.col("page_id").alias("fx_id"), "main_text")


