"""Template-aware scaling (L87-L105): cluster pages within a host, label one page of each cluster, replay its rules on the rest."""

from __future__ import annotations

import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webtext.functions.blocks import Config, assemble, block_rows
from webtext.functions.content import plain_text
from webtext.functions.decoding import block_logits, decode, labels_of
from webtext.functions.dom import parse, shape, step
from webtext.functions.rules import apply_rules, synthesise
from webtext.functions.scoring import lexicon
from webtext.operators.components import components, cut
from webtext.operators.extract import Scorer
from webtext.operators.passes import row_pass

#: Rules of all clusters are broadcast up to this many bytes, else pages and rules meet by cluster.
BROADCAST_BYTES = 64 << 20


def host(url: Column | str, level: str = "subdomain") -> Column:
    """Lower-case host without port; level 'registered' keeps its last two labels, 'global' is one for all."""
    url = F.col(url) if isinstance(url, str) else url
    name = F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1))
    return {"subdomain": name, "registered": F.substring_index(name, ".", -2), "global": F.lit("*")}[level]


def canonical(url: Column | str) -> Column:
    """Without scheme, www./m., tracking parameters, fragment, .html and last slash."""
    url = F.col(url) if isinstance(url, str) else url
    x = F.regexp_replace(url, r"#.*$", "")
    x = F.regexp_replace(x, r"([?&])(utm_[a-z]+|ref)=[^&]*", "$1")
    x = F.regexp_replace(F.regexp_replace(F.regexp_replace(x, r"&+", "&"), r"\?&", "?"), r"[?&]+$", "")
    x = F.regexp_replace(F.regexp_replace(x, r"^https?://", ""), r"^(www|m)\.", "")
    return F.regexp_replace(F.regexp_replace(x, r"/$", ""), r"\.html$", "")


def index(pages: DataFrame, level: str = "subdomain", k: int = 32) -> DataFrame:
    """The thin table all clustering works on: page_id, host, sig (hash of the path set), minhash (k values), shape features."""

    def run(page_id, url, page):
        root = parse(page)
        items, stack = set(), [(c, "") for c in root.children]
        while stack:
            n, above = stack.pop()
            if n.tag:
                own = step(n)
                items.add(f"{above}>{own}")
                stack.extend((c, own) for c in n.children)
        raw = [x.encode() for x in sorted(items)]
        s = shape(root)
        signed = lambda h: h - (1 << 64) if h >= 1 << 63 else h
        mins = [min((signed(xxhash.xxh3_64_intdigest(x, seed)) for x in raw), default=0) for seed in range(k)]
        return page_id, url, xxhash.xxh3_128_hexdigest(b"\n".join(raw)), mins, s["n_tags"], s["n_attr_names"], s["n_distinct_tags"], s["depth"], s["width"]

    thin = row_pass(pages.select("page_id", "url", "html"), run, "page_id long, url string, sig string, minhash array<long>, n_tags int, n_attr_names int, n_distinct_tags int, depth int, width int")
    return thin.withColumn("host", host("url", level)).drop("url")


#: Rounds in which a band's signatures are compared with one leader each, before all pairs that are still apart are.
LEADER_ROUNDS = 3


def linked(sigs: DataFrame, spread: DataFrame, least: float) -> DataFrame:
    """node, comp of distinct signatures (node, minhash): components of all pairs that share a band (node, host, band) and agree enough.

    Leaders join most of a band at a cost linear in its size; only pairs of one band that still lie in different components
    after that are compared one by one, so no link is lost.
    """
    key = ["host", "band"]
    shared = spread.join(spread.groupBy(key).agg(F.count("*").alias("n")).where("n > 1").drop("n"), key)
    shared = cut(shared.select("node", *key))
    labels = cut(shared.select("node").distinct().withColumn("comp", F.col("node")))
    agree = F.size(F.filter(F.zip_with("x", "y", lambda p, q: p == q), lambda same: same)) / F.size("x")

    def merge(labels: DataFrame, pairs: DataFrame) -> DataFrame:
        near = pairs.join(sigs.select(F.col("node").alias("a"), F.col("minhash").alias("x")), "a").join(sigs.select(F.col("node").alias("b"), F.col("minhash").alias("y")), "b").where(agree >= least)
        ends = [labels.select(F.col("node").alias(n), F.col("comp").alias(c)) for n, c in (("a", "u"), ("b", "v"))]
        joined = components(near.select("a", "b").join(ends[0], "a").join(ends[1], "b").select("u", "v"))
        to = joined.select(F.col("node").alias("comp"), F.col("comp").alias("next"))
        return cut(labels.join(to, "comp", "left").select("node", F.coalesce("next", "comp").alias("comp")))

    for turn in range(LEADER_ROUNDS):
        placed = shared.join(labels, "node")
        order = F.struct(F.xxhash64("node", F.lit(turn)), F.col("node"))
        lead = placed.groupBy(key).agg(F.min_by("node", order).alias("a"), F.min_by("comp", order).alias("lead_comp"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi")
        pairs = cut(placed.join(lead, key).where("comp <> lead_comp").select("a", F.col("node").alias("b")).distinct())
        if pairs.isEmpty():
            return labels
        labels = merge(labels, pairs)
    placed = shared.join(labels, "node")
    other = placed.select(*key, F.col("node").alias("b"), F.col("comp").alias("other"))
    return merge(labels, cut(placed.withColumnRenamed("node", "a").join(other, key).where("comp < other").select("a", "b").distinct()))


def clusters(idx: DataFrame, mode: str = "exact", bands: int = 8, least: float = 0.8) -> DataFrame:
    """idx with cluster_id. exact: equal signatures; lsh: distinct signatures of a host that share a band and agree enough are linked."""
    named = lambda key: F.conv(F.substring(F.md5(F.concat_ws("|", "host", key).cast("binary")), 1, 15), 16, 10).cast("long")
    if mode == "exact":
        return idx.withColumn("cluster_id", named("sig"))
    sigs = cut(idx.groupBy("host", "sig").agg(F.any_value("minhash").alias("minhash")).withColumn("node", named("sig")))
    rows = F.size("minhash") / bands
    band = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.xxhash64(b, F.array_join(F.slice("minhash", (b * rows + 1).cast("int"), rows.cast("int")).cast("array<string>"), ",")))
    to = sigs.join(linked(sigs, sigs.select("host", "node", F.explode(band).alias("band")), least), "node", "left")
    return idx.join(to.select("host", "sig", F.coalesce("comp", "node").alias("cluster_id")), ["host", "sig"])


FEATURES = ("n_distinct_tags", "n_attr_names", "depth", "width")


def representatives(clustered: DataFrame, strategy: str = "coverage", weights: tuple[float, ...] = (1.0, 1.0, 1.0, 1.0)) -> DataFrame:
    """cluster_id, host, n_pages, rep_page_id. coverage: the scaled sum of FEATURES (L96); random, longest, worst: ablations."""
    ends = clustered.groupBy("cluster_id").agg(*[f(n).alias(f"{p}_{n}") for n in FEATURES for p, f in (("lo", F.min), ("hi", F.max))])
    x = clustered.join(ends, "cluster_id")
    score = sum((w * F.coalesce(F.try_divide(F.col(n) - F.col(f"lo_{n}"), F.col(f"hi_{n}") - F.col(f"lo_{n}")), F.lit(0.0)) for n, w in zip(FEATURES, weights, strict=True)), F.lit(0.0))
    score = {"coverage": score, "worst": -score, "longest": F.col("n_tags").cast("double"), "random": F.xxhash64("page_id").cast("double")}[strategy]
    x = x.withColumn("score", F.round(score, 9))
    return x.groupBy("cluster_id", "host").agg(F.count("*").alias("n_pages"), F.max_by("page_id", F.struct("score", -F.col("page_id"))).alias("rep_page_id"))


def cluster_rules(pages: DataFrame, reps: DataFrame, scorer: Scorer = lexicon, cfg: Config = Config()) -> DataFrame:
    """Rules of each cluster from its representative; the only step that runs the scorer."""
    wanted = pages.select("page_id", "html").join(reps.select("cluster_id", F.col("rep_page_id").alias("page_id")), "page_id").select("cluster_id", "html")

    def run(cluster_id, page):
        root, own, _ = block_rows(page, cfg)
        labels, _ = labels_of(decode(len(own), block_logits(scorer(own)), "fast"), len(own))
        return [(cluster_id, r.selector, r.xpath, r.css, r.action, r.specificity, r.support, r.purity) for r in synthesise(root, own, labels)]

    return row_pass(wanted, run, "cluster_id long, selector string, xpath string, css string, action string, specificity int, support int, purity double", many=True)


def propagate(pages: DataFrame, clustered: DataFrame, rules: DataFrame, cfg: Config = Config(), broadcast: bool | None = None, second: Scorer | None = lexicon, most_uncovered: float = 0.3) -> DataFrame:
    """page_id, main_html, main_text, n_blocks, n_uncovered, relabelled of every page, by DOM traversal.

    A page whose rules leave more than most_uncovered of its blocks undecided is labelled itself in a second round, in the same pass
    and with the scorer `second` (none: it keeps what the rules say). Rules are written out first, so that the scorer runs once for them.

    A page gets its cluster's rules: broadcast while their bytes are within bounds, else by a join on the cluster.
    """
    rules = cut(rules)
    own = rules.groupBy("cluster_id").agg(F.collect_list(F.struct("selector", "action")).alias("rules"))
    if broadcast is None:
        size = rules.agg(F.coalesce(F.sum(F.length("selector") + 40), F.lit(0))).first()[0]
        broadcast = size <= BROADCAST_BYTES
    x = pages.select("page_id", "html").join(clustered.select("page_id", "cluster_id"), "page_id").join(F.broadcast(own) if broadcast else own, "cluster_id", "left")

    def run(page_id, page, rules):
        root, blocks, labels, uncovered = apply_rules(page, [(r["selector"], r["action"]) for r in rules or ()], cfg)
        again = second is not None and uncovered > most_uncovered * len(blocks)
        if again:
            root, blocks, _ = block_rows(page, cfg)
            labels, _ = labels_of(decode(len(blocks), block_logits(second(blocks)), "fast"), len(blocks))
        main = assemble(root, [b for b, y in zip(blocks, labels, strict=True) if y])
        return page_id, main, plain_text(main), len(blocks), uncovered, again

    return row_pass(x.select("page_id", "html", "rules"), run, "page_id long, main_html string, main_text string, n_blocks int, n_uncovered int, relabelled boolean")


def fallback(propagated: DataFrame, most_uncovered: float = 0.3) -> DataFrame:
    """page_id of pages whose rules left too many blocks undecided; `propagate` labels them themselves in its second round."""
    return propagated.where((F.col("n_blocks") > 0) & (F.col("n_uncovered") > most_uncovered * F.col("n_blocks"))).select("page_id")


def inference_share(clustered: DataFrame) -> DataFrame:
    """n_pages, n_clusters, share: how many pages need the model (L105)."""
    return clustered.agg(F.count("*").alias("n_pages"), F.countDistinct("cluster_id").alias("n_clusters")).withColumn("share", F.round(F.col("n_clusters") / F.col("n_pages"), 6))
