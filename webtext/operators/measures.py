"""Measures over whole tables (L156-L172, L261-L278), native unless noted."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from webtext.functions.measures import rouge_l as _rouge_l
from webtext.functions.measures import rouge_n as _rouge_n
from webtext.functions.measures import teds as _teds
from webtext.functions.measures import tokens as _tokens
from webtext.operators.corpus import BROADCAST_GRAMS
from webtext.operators.components import cut
from webtext.operators.passes import row_pass


_CJK = "\u3400-\u9fff\uf900-\ufaff"
#: One CJK character, a run of other letters and digits, or one mark; the same in Java's and RE2's spelling.
MIXED = rf"[{_CJK}]|[^\s\p{{P}}\p{{S}}\p{{Z}}\p{{C}}{_CJK}]+|[\p{{P}}\p{{S}}]"


def tokens(text: Column | str, mode: str = "ws") -> Column:
    """Lower-cased tokens. ws: runs of anything but white space; mixed: for texts that write no blanks between words."""
    if mode == "mixed":
        return F.regexp_extract_all(F.lower(text), F.lit(MIXED), F.lit(0))
    return F.filter(F.split(F.lower(text), r"\s+"), lambda x: x != "")


def rouge(pairs: DataFrame, key: str = "page_id", n: int = 5, mode: str = "mixed", lengths: bool = False) -> DataFrame:
    """key, p, r, f1 (and n_chars of pred, if lengths) of each row of pairs (key, pred, gold): clipped n-gram counts.

    Tokens are native; the n-grams of a pair are counted within its row, so neither texts nor n-grams are shuffled.
    Shorter texts are compared by their own length; null counts as empty, two empty texts score 1.
    """
    kind = pairs.schema[key].dataType.simpleString()
    words = lambda x: [w for w in (x or "").split(" ") if w]
    listed = lambda c: F.array_join(tokens(c, mode), " ")
    base = pairs.select(key, listed("pred").alias("a"), listed("gold").alias("b"), F.length("pred").cast("long").alias("n"))
    x = row_pass(base, lambda k, a, b, chars: (k, *_rouge_n(words(a), words(b), n), chars), f"{key} {kind}, p double, r double, f1 double, n_chars long")
    return x.select(key, *[F.round(c, 6).alias(c) for c in ("p", "r", "f1")], *(["n_chars"] if lengths else []))


def rouge_l(pairs: DataFrame, key: str = "page_id") -> DataFrame:
    kind = pairs.schema[key].dataType.simpleString()
    return row_pass(pairs.select(key, "pred", "gold"), lambda k, a, b: (k, _rouge_l(_tokens(a, "ws"), _tokens(b, "ws"))), f"{key} {kind}, f1 double")


def edit_similarity(a: Column | str, b: Column | str) -> Column:
    """1 - distance / longer length; both empty: 1."""
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longer)


def teds(pairs: DataFrame, key: str = "fx_id", structure_only: bool = False) -> DataFrame:
    kind = pairs.schema[key].dataType.simpleString()
    return row_pass(pairs.select(key, "pred", "gold"), lambda k, a, b: (k, _teds(a, b, structure_only)), f"{key} {kind}, teds double")


def length_ratio(a: Column, b: Column) -> Column:
    """(a - b) / the longer, in [-1, 1]; both 0: 0."""
    return F.when(F.greatest(a, b) == 0, 0.0).otherwise((a - b) / F.greatest(a, b))


def ratio_bin(ratio: Column, bins: int = 20) -> Column:
    return F.least(F.lit(bins - 1), F.floor((ratio + 1) * bins / 2)).cast("int")


def stratified(df: DataFrame, by: str, key: str, k: int, seed: int = 0) -> DataFrame:
    """k rows of each stratum in the order of a hash of seed and key; each stratum is ranked by one window, of which Spark keeps k rows a task before the shuffle."""
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string")).cast("binary"))
    x = df.withColumn("h", h)
    rank = F.row_number().over(Window.partitionBy(by).orderBy("h"))
    return x.withColumn("rank", rank).where(F.col("rank") <= k).drop("h", "rank")


def win_rates(judged: DataFrame) -> DataFrame:
    """bin, wins, losses, ties of judged pairs (bin, winner in a, b, tie)."""
    n = lambda w: F.count(F.when(F.col("winner") == w, 1))
    return judged.groupBy("bin").agg(n("a").alias("wins"), n("b").alias("losses"), n("tie").alias("ties"))


def weighted_win_rate(population: DataFrame, rates: DataFrame, split_ties: bool = True) -> DataFrame:
    """Rate per bin weighted by the bin's share of all pairs; bins without a sample are left out and the rest scaled up."""
    half = 0.5 if split_ties else 0.0
    all_ = F.col("wins") + F.col("losses") + (F.col("ties") if split_ties else 0)
    rate = rates.where(all_ > 0).select("bin", ((F.col("wins") + half * F.col("ties")) / all_).alias("rate"))
    share = population.groupBy("bin").agg(F.count("*").alias("n"))
    return rate.join(share, "bin").agg(F.round(F.sum(F.col("n") * F.col("rate")) / F.sum("n"), 6).alias("win_rate"))


def cross_entropy(train: DataFrame, held: DataFrame, alpha: float = 0.5, vocabulary: DataFrame | None = None) -> DataFrame:
    """bits per token of held (text) under an additively smoothed unigram model of train (text): a stand-in for training models (L299).

    Models of different budgets are comparable only over one vocabulary; give the texts that span it.
    """
    count = lambda df, name: df.select(F.explode(tokens("text")).alias("w")).groupBy("w").agg(F.count("*").alias(name))
    c, h = count(train, "c"), count(held, "h")
    total = c.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    if vocabulary is not None:
        total = total.drop("v").crossJoin(count(vocabulary, "c").agg(F.count("*").alias("v")))
    x = h.join(c, "w", "left").crossJoin(F.broadcast(total))
    p = (F.coalesce("c", F.lit(0)) + alpha) / (F.col("n") + alpha * (F.col("v") + 1))
    return x.agg(F.round(-F.sum(F.col("h") * F.log2(p)) / F.sum("h"), 4).alias("bits"))


#: The nested token budgets of the learning curve (W12): 15 shares from 1 % to all, in equal ratios.
BUDGETS = tuple(round(0.01 ** (1 - j / 14), 6) for j in range(15))


def budget_curve(docs: DataFrame, held: DataFrame, alpha: float = 0.5, budgets: tuple[float, ...] = BUDGETS) -> DataFrame:
    """share, bits: `cross_entropy` after each of the nested shares of docs (in md5 order of doc_id), over the vocabulary of all.

    One scan and one shuffle of partial word counts for all budgets: a word's row holds its count in each.
    """
    h = F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 7), 16, 10).cast("double") / 16**7
    w = docs.select(h.alias("u"), tokens("text").alias("w")).select("u", F.explode_outer("w").alias("w")).where("w is not null")
    c = w.groupBy("w").agg(*[F.count(F.when(F.col("u") < s, 1)).alias(f"c{j}") for j, s in enumerate(budgets)])
    asked = held.select(F.explode_outer(tokens("text")).alias("w")).where("w is not null").groupBy("w").agg(F.count("*").alias("h"))
    c = cut(c.join(asked, "w", "full"))  # read twice
    names = [f"c{j}" for j in range(len(budgets))]
    total = c.agg(F.count("c0").alias("v"), *[F.coalesce(F.sum(n), F.lit(0)).alias(f"n{n}") for n in names])
    x = c.where("h is not null").crossJoin(F.broadcast(total))  # one row
    p = lambda n: (F.coalesce(n, F.lit(0)) + alpha) / (F.col(f"n{n}") + alpha * (F.col("v") + 1))
    bits = x.agg(*[(-F.sum(F.col("h") * F.log2(p(n))) / F.sum("h")).alias(n) for n in names])
    return bits.select(F.explode(F.array(*[F.struct(F.lit(s).alias("share"), F.round(n, 4).alias("bits")) for s, n in zip(budgets, names, strict=True)])).alias("x")).select("x.*")


def ngram_cross_entropy(train: DataFrame, held: DataFrame, order: int = 3, alpha: float = 0.5, mass: float = 2.0) -> DataFrame:
    """bits per token of held (text) under an interpolated word model of train (text), of order 1 to 3.

    The unigram is that of `cross_entropy`; each longer history h moves the estimate by its own counts:
    p(w | h) = (c(h w) + mass * p(w | shorter h)) / (c(h .) + mass). Of train only the n-grams that held asks for are
    shuffled: their hashes are broadcast up to BROADCAST_GRAMS, beyond which both sides meet by key.
    """
    if not 1 <= order <= 3:
        raise ValueError(f"order {order} is not 1 to 3")
    back = lambda i, k: F.concat_ws(" ", *[F.get("w", i - j) for j in range(k, -1, -1)])

    def slots(i) -> list:
        """(name, key) of the n-grams that end at token i and of their histories."""
        out = [("g1", F.xxhash64(F.lit("g"), F.get("w", i)))]
        for k in range(1, order):
            history = F.concat_ws(" ", *[F.get("w", i - j) for j in range(k, 0, -1)])
            out += [(f"g{k + 1}", F.when(i >= k, F.xxhash64(F.lit("g"), back(i, k)))), (f"h{k + 1}", F.when(i >= k, F.xxhash64(F.lit("h"), history)))]
        return out

    words = lambda df: df.select(tokens("text").alias("w")).where(F.size("w") > 0)
    places = F.sequence(F.lit(0), F.size("w") - 1)
    events = words(held).select(F.explode_outer(F.transform(places, lambda i: F.struct(*[key.alias(name) for name, key in slots(i)]))).alias("e")).groupBy("e").agg(F.count("*").alias("h"))
    events = cut(events.select("e.*", "h").withColumn("id", F.monotonically_increasing_id()))
    names = [c for c in events.columns if c not in ("h", "id")]
    long = events.select("id", F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.col(n).alias("key")) for n in names])).alias("s")).select("id", "s.*").where("key is not null")
    asked = cut(long.select("key").distinct())
    if asked.count() <= BROADCAST_GRAMS:
        asked = F.broadcast(asked)
    grams = words(train).select(F.explode_outer(F.flatten(F.transform(places, lambda i: F.array(*[key for _, key in slots(i)])))).alias("key"))
    counts = grams.where("key is not null").join(asked, "key", "left_semi").groupBy("key").agg(F.count("*").alias("c"))
    every = words(train).select(F.explode_outer("w").alias("w")).groupBy("w").agg(F.count("*").alias("c"))
    total = every.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    row = long.join(counts, "key", "left").groupBy("id").agg(*[F.coalesce(F.max(F.when(F.col("name") == n, F.col("c"))), F.lit(0)).alias(f"c_{n}") for n in names])
    x = row.join(events.select("id", "h"), "id").crossJoin(F.broadcast(total))  # one row
    p = (F.col("c_g1") + alpha) / (F.coalesce("n", F.lit(0)) + alpha * (F.col("v") + 1))
    for k in range(2, order + 1):
        p = (F.col(f"c_g{k}") + mass * p) / (F.col(f"c_h{k}") + mass)
    return x.agg(F.round(-F.sum(F.col("h") * F.log2(p)) / F.sum("h"), 4).alias("bits"))
