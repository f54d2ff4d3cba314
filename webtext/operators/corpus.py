"""Corpus construction (L256-L297): exact dedup, language, quality rules, safety lists, fuzzy dedup. Native expressions but for `gram_shares`, `trigrams`, the classifier and fuzzy dedup's passes."""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from operator import add, or_

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webtext.functions.scoring import STOP
from webtext.operators.components import components, cut
from webtext.operators.passes import row_pass
from webtext.operators.templates import host
from webtext.session import ship

try:
    from _md5 import md5  # without the cost of a context for each short text
except ImportError:
    from hashlib import md5

# -- exact dedup


def exact_key(how: str = "raw") -> Column:
    return F.sha2("text" if how == "raw" else F.trim(F.regexp_replace("text", r"\s+", " ")), 256)


def exact_dedup(docs: DataFrame, how: str = "raw") -> DataFrame:
    """The least id of each group of equal texts; only hashes and ids are shuffled."""
    return docs.select(exact_key(how).alias("h"), "doc_id").groupBy("h").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("n")).select("doc_id", "n")


# -- language


def words(text: Column | str = "text") -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}]+"), lambda w: w != "")


def lang_vote(text: Column | str = "text") -> Column:
    """The language whose stop words are most; ties and none are `und`."""
    w = words(text)
    among = lambda v: F.size(F.filter(w, lambda x: x.isin(*sorted(v))))
    hits = {k: among(v) for k, v in STOP.items()}
    best = F.greatest(*hits.values())
    n_best = sum((F.when(h == best, 1).otherwise(0) for h in hits.values()), F.lit(0))
    out = F.lit("und")
    for k, h in hits.items():
        out = F.when((h == best) & (best > 0) & (n_best == 1), F.lit(k)).otherwise(out)
    return out


def trigram_model(docs: DataFrame) -> DataFrame:
    """lang, gram, logp of a naive Bayes model with add-half smoothing."""
    g = trigrams(docs, "lang").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    total = g.groupBy("lang").agg(F.sum("n").alias("total"))
    vocabulary = g.agg(F.countDistinct("gram").alias("v"))
    return g.join(F.broadcast(total), "lang").crossJoin(F.broadcast(vocabulary)).select("lang", "gram", (F.log((F.col("n") + 0.5) / (F.col("total") + 0.5 * F.col("v"))) - F.log(0.5 / (F.col("total") + 0.5 * F.col("v")))).alias("gain"))


def trigrams(docs: DataFrame, key: str) -> DataFrame:
    """key, gram, n: how often each character trigram of letters and blanks stands in each text.

    Counted text by text: a substring by place is searched from the start of a text, which takes time with the square of its length.
    """
    kind = docs.schema[key].dataType.simpleString()
    x = docs.select(key, F.concat(F.lit(" "), F.regexp_replace(F.lower("text"), r"[^\p{L}]+", " "), F.lit(" ")).alias("p"))

    def run(k, p):
        return [(k, gram, n) for gram, n in Counter(map("".join, zip(p, p[1:], p[2:]))).items()] if p else []

    return row_pass(x, run, f"{key} {kind}, gram string, n long", many=True, batch_bytes=1 << 20)


def lang_bayes(docs: DataFrame, model: DataFrame) -> DataFrame:
    """doc_id, lang_pred: grams meet the model by key; unseen grams cost a language the same as any other rare gram."""
    ll = trigrams(docs, "doc_id").join(model, "gram").groupBy("doc_id", "lang").agg(F.sum(F.col("n") * F.col("gain")).alias("ll"))
    return ll.groupBy("doc_id").agg(F.max_by("lang", "ll").alias("lang_pred"))


#: Buckets that trigrams are hashed to, so that a model has a size of its own, whatever the texts hold; and what a language's probability must reach.
BUCKETS = 1 << 15
MIN_CONFIDENCE = 0.65
_NO_LETTERS = re.compile(r"[\W\d_]+")


def _gram_buckets(text: str) -> np.ndarray:
    """The bucket of each character trigram of letters and blanks."""
    c = np.frombuffer(f" {_NO_LETTERS.sub(' ', text.lower())} ".encode("utf-32-le", "surrogatepass"), np.uint32).astype(_U)
    return (_mix(c[:-2] + _mix(c[1:-1] + _mix(c[2:] + _STEP))) % _U(BUCKETS)).astype(np.int64)


def language_model(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """The languages of docs (lang, text) and the log probability of each bucket in each: a linear classifier on hashed trigrams.

    One pass; what is collected is a number per language and bucket.
    """
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[str, np.ndarray] = {}
        for batch in batches:
            for lang, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                of = counts.setdefault(lang, np.zeros(BUCKETS, np.int64))
                of += np.bincount(_gram_buckets(text), minlength=BUCKETS)
        for lang, of in counts.items():
            at = np.flatnonzero(of)
            yield pa.record_batch([pa.array([lang] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(of[at], pa.int64())], ["lang", "bucket", "n"])

    got = docs.where("lang is not null and text is not null").select("lang", "text").mapInArrow(run, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    langs = sorted(set(got["lang"].to_pylist()))
    counts = np.full((len(langs), BUCKETS), 0.5)
    counts[np.searchsorted(np.array(langs, object), np.array(got["lang"].to_pylist(), object)) if langs else [], got["bucket"].to_numpy()] += got["n"].to_numpy()
    return langs, np.log(counts / counts.sum(axis=1, keepdims=True)).astype(np.float32)


def language_of(model: tuple[list[str], np.ndarray], text: str | None) -> str | None:
    """The most probable language of a text, all being as likely at first; `und` without letters or below MIN_CONFIDENCE."""
    langs, weights = model
    if text is None:
        return None
    at = _gram_buckets(text)
    if not len(at) or not langs:
        return "und"
    z = weights @ np.bincount(at, minlength=BUCKETS)
    best = int(z.argmax())
    return langs[best] if 1 / np.exp(z - z[best]).sum() >= MIN_CONFIDENCE else "und"


# -- quality rules


@dataclass(frozen=True)
class Policy:
    """Thresholds of one corpus; the defaults are the publicly documented rule set."""

    min_words: int = 50
    max_words: int = 100_000
    min_word_len: float = 3.0
    max_word_len: float = 10.0
    max_symbols: float = 0.1
    max_bullets: float = 0.9
    max_ellipsis: float = 0.3
    min_alpha: float = 0.8
    min_stop: int = 2
    max_dup_lines: float = 0.3
    max_dup_line_chars: float = 0.2
    top_grams: tuple[float, ...] = (0.20, 0.18, 0.16)
    dup_grams: tuple[float, ...] = (0.15, 0.14, 0.13, 0.12, 0.11, 0.10)
    fuzzy: float = 0.8
    languages: tuple[str, ...] = ("en", "de", "fr", "es")


POLICIES = {
    "default": Policy(),
    "balanced": Policy(min_words=30, max_dup_lines=0.4, min_stop=1),
    "strict": Policy(min_words=100, max_symbols=0.05, max_dup_lines=0.2, min_alpha=0.85, fuzzy=0.7),
}


def _words(text: Column | str = "text") -> Column:
    return F.filter(F.split(text, r"\s+"), lambda w: w != "")


def _share(hits: Column, all_: Column) -> Column:
    return F.when(all_ > 0, hits / all_).otherwise(0.0)


def measures(docs: DataFrame) -> DataFrame:
    """docs with what the rules look at, in one scan."""
    x = docs.withColumns({"w": _words(), "lines": F.filter(F.split("text", "\n"), lambda s: F.trim(s) != "")})
    n, m = F.size("w"), F.size("lines")
    stops = F.array(*[F.lit(s) for s in sorted(frozenset().union(*STOP.values()))])
    distinct = F.array_distinct("lines")
    length = lambda a: F.aggregate(a, F.lit(0), lambda acc, s: acc + F.length(s))
    return x.select(
        *docs.columns,
        n.cast("long").alias("n_words"),
        F.round(_share(length("w"), n), 6).alias("mean_word_len"),
        F.round(_share(F.length("text") - F.length(F.replace("text", F.lit("#"))), n), 6).alias("hash_ratio"),
        F.round(_share(F.size(F.split("text", r"\.\.\.|…", -1)) - 1, n), 6).alias("ellipsis_ratio"),
        F.round(_share(F.size(F.filter("lines", lambda s: F.trim(s).rlike(r"^[•\-*‣]"))), m), 6).alias("bullet_share"),
        F.round(_share(F.size(F.filter("lines", lambda s: F.rtrim(s).rlike(r"(\.\.\.|…)$"))), m), 6).alias("ellipsis_lines"),
        F.round(_share(F.size(F.filter("w", lambda s: s.rlike(r"\p{L}"))), n), 6).alias("alpha_share"),
        F.size(F.array_intersect(F.transform("w", lambda s: F.lower(s)), stops)).cast("long").alias("n_stop"),
        F.round(_share(m - F.size(distinct), m), 6).alias("dup_line_share"),
        F.round(_share(length("lines") - length(distinct), length("lines")), 6).alias("dup_line_chars"),
    )


def _six(x: float) -> float:
    """x to six places, halves upwards, as SQL rounds (Python's round() sends an exact half to the even neighbour)."""
    v = x * 1e6
    low = math.floor(v)
    return (low + (v - low >= 0.5)) / 1e6


def _repeated(w: list[str], chars: int) -> list[float]:
    """The shares of `gram_shares` of one text's words.

    An n-gram can only repeat where both (n-1)-grams in it do, so longer ones are looked for at few places; each is known by those two.
    """
    ends, total, out = [0], 0, []
    for x in w:
        total += len(x)
        ends.append(total)
    grams: dict[int, object] = dict(enumerate(w))  # by place
    counts = Counter(w)
    for n in range(1, 11):
        if n > 1:
            names: dict[tuple, int] = {}
            grams = {i: names.setdefault((g, grams[i + 1]), len(names)) for i, g in grams.items() if i + 1 in grams}
            counts = Counter(grams.values())
        grams = {i: g for i, g in grams.items() if counts[g] > 1}
        if 1 < n < 5:
            out.append(_six(max((counts[g] * (ends[i + n] - ends[i] + n - 1) for i, g in grams.items()), default=0) / max(1, chars)))
        elif n > 4:
            out.append(_six((len(grams) - len(set(grams.values()))) / max(1, len(w) - n + 1)))
    return out


def gram_shares(docs: DataFrame, keep: tuple[str, ...] = (), asked: Column | None = None) -> DataFrame:
    """doc_id, the columns in keep, top2..top4 (character share of the commonest n-gram) and dup5..dup10 (share of words in repeated
    n-grams); of all texts, or of those for which asked holds (0 for others).

    N-grams are counted document by document in one Arrow pass: nothing is shuffled.
    """
    own = ("doc_id", *keep)
    names = [f"top{n}" for n in (2, 3, 4)] + [f"dup{n}" for n in range(5, 11)]
    w = F.transform(_words(), lambda w: F.lower(w))
    words = docs.select(*own, (w if asked is None else F.when(asked, w)).alias("w"), F.length("text").alias("chars"))
    kinds = [f"{c} {docs.schema[c].dataType.simpleString()}" for c in own] + [f"{n} double" for n in names]
    return row_pass(words, lambda *x: (*x[:-2], *_repeated(x[-2] or [], x[-1] or 0)), ", ".join(kinds))


def reasons(p: Policy = Policy()) -> Column:
    """Names of the rules that a measured document fails."""
    rules = {
        "words": ~F.col("n_words").between(p.min_words, p.max_words), "word_length": ~F.col("mean_word_len").between(p.min_word_len, p.max_word_len),
        "hash": F.col("hash_ratio") > p.max_symbols, "ellipsis": F.col("ellipsis_ratio") > p.max_symbols, "bullets": F.col("bullet_share") > p.max_bullets, "ellipsis_lines": F.col("ellipsis_lines") > p.max_ellipsis,
        "alpha": F.col("alpha_share") < p.min_alpha, "stop": F.col("n_stop") < p.min_stop, "dup_lines": F.col("dup_line_share") > p.max_dup_lines, "dup_line_chars": F.col("dup_line_chars") > p.max_dup_line_chars,
    }
    return F.array_compact(F.array(*[F.when(c, F.lit(k)) for k, c in rules.items()]))


def gram_reasons(p: Policy = Policy()) -> Column:
    """Names of the limits on repeated n-grams that a document with its `gram_shares` is beyond."""
    limits = {f"top{n}": v for n, v in enumerate(p.top_grams, 2)} | {f"dup{n}": v for n, v in enumerate(p.dup_grams, 5)}
    return F.array_compact(F.array(*[F.when(F.col(k) > v, F.lit(k)) for k, v in limits.items()]))


# -- safety

#: Host prefixes and indicator words; parameters with these defaults [D].
BAD_HOSTS = ("www.cheap-pills", "www.casino-win", "spam-farm", "ads-track", "m.free-bets", "m.adult-x")
BAD_WORDS = ("trash", "idiot", "scum", "clown", "worthless", "moron")
PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}", "ipv4": r"\b[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\b", "secret": r'token = "[0-9a-f]+"', "license": r"(?i)licen[sc]e|copyright",
}


def unsafe_host(host: Column) -> Column:
    return F.array_size(F.filter(F.array(*map(F.lit, BAD_HOSTS)), lambda b: F.startswith(host, b))) > 0


def unsafe_words(text: Column | str = "text") -> Column:
    return F.arrays_overlap(words(text), F.array(*map(F.lit, BAD_WORDS)))


# -- fuzzy dedup


def shingles(docs: DataFrame, key: str = "doc_id", n: int = 5) -> DataFrame:
    """key, s: word n-grams; texts of fewer words are one. Words are a column of their own, so they are split once a row.

    They are not made distinct as strings (which Spark does by comparing all pairs), but where needed as hashes.
    """
    w = docs.select(key, F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "").alias("w"))
    # element by element: slice() would copy the whole array for each gram
    grams = F.transform(F.sequence(F.lit(0), F.size("w") - n), lambda i: F.concat_ws(" ", *[F.get("w", i + k) for k in range(n)]))
    return w.select(key, F.when(F.size("w") >= n, grams).otherwise(F.array(F.array_join("w", " "))).alias("s"))


def hashed_shingles(docs: DataFrame, key: str = "doc_id", n: int = 5) -> DataFrame:
    """key, s: distinct 64-bit hashes of the n-grams."""
    return shingles(docs, key, n).select(key, F.array_distinct(F.transform("s", lambda x: F.xxhash64(x))).alias("s"))


def minhash(docs: DataFrame, k: int, portable: bool = False, n: int = 5) -> DataFrame:
    """doc_id, sig: k minima over the shingles. portable hashes agree with md5 in any engine; fast ones are seeded xxhash.

    The minima are taken before anything is shuffled, and documents are not split over tasks, so a row per document moves.
    """
    # outer: for a plain explode Spark infers a filter on the array and evaluates it again below, words and all, for each gram
    s = shingles(docs, n=n).select("doc_id", F.explode_outer("s").alias("x"))
    if portable:
        one = lambda i: F.conv(F.substring(F.md5(F.concat(F.lit(f"{i}:"), "x").cast("binary")), 1, 15), 16, 10).cast("long")
    else:
        one = lambda i: F.xxhash64("x", F.lit(i))
    return s.groupBy("doc_id").agg(*[F.min(one(i)).alias(f"h{i}") for i in range(k)]).select("doc_id", F.array(*[f"h{i}" for i in range(k)]).alias("sig"))


def buckets(sig: DataFrame, bands: int, rows: int, scope: Column | None = None) -> DataFrame:
    """doc_id, scope, b, key: the bucket of each document in each band."""
    scope = scope if scope is not None else F.lit(0)
    key = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.struct(b.alias("b"), F.array_join(F.transform(F.slice("sig", b * rows + 1, rows), lambda v: v.cast("string")), ",").alias("key")))
    return sig.select("doc_id", scope.alias("scope"), F.explode(key).alias("k")).select("doc_id", "scope", "k.b", "k.key")


def candidates(sig: DataFrame, bands: int, rows: int, scope: Column | None = None) -> DataFrame:
    """Distinct pairs a < b of a bucket's least id with each other member: a star per bucket. They join what shares a bucket, but
    near copies in a bucket need not be near its least id: `verified_components` has those links too."""
    e = buckets(sig, bands, rows, scope)
    least = e.groupBy("scope", "b", "key").agg(F.min("doc_id").alias("a"), F.count("*").alias("n")).where("n > 1")
    return e.join(least, ["scope", "b", "key"]).where("doc_id <> a").select("a", F.col("doc_id").alias("b")).distinct()


LEADER_ROUNDS = 4
#: Buckets go through leader rounds only while they hold more than so many pairs per member.
FEW_PAIRS = 4
#: Ids (8 bytes each) that are broadcast at most.
BROADCAST_IDS = 250_000
_U = np.uint64
_STEP = _U(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class _WordHashes(dict):
    """word -> 64-bit hash; forgets all beyond a number of words."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= 300_000:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def gram_keys(own: list[bytes], hashes: _WordHashes, n: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the n-grams of words; fewer words are one."""
    w = np.fromiter(map(hashes.__getitem__, own), _U, len(own))
    size = min(n, len(w))
    key = np.full(len(w) - size + 1, size, _U)
    for k in range(size):
        key = _mix(key + w[k : len(w) - size + 1 + k] + _STEP)
    return np.unique(key)


def _md5_minima(own: list[bytes], k: int, n: int = 5) -> list[int]:
    """The k minima of `minhash(portable=True)`."""
    grams = {b" ".join(own[i : i + n]) for i in range(max(1, len(own) - n + 1))}
    return [int.from_bytes(min([md5(p + g).digest() for g in grams])[:8]) >> 4 for p in (b"%d:" % i for i in range(k))]


def _seeded_minima(sets: list[np.ndarray], k: int) -> np.ndarray:
    keys, at = np.concatenate(sets), np.cumsum([0, *map(len, sets[:-1])])
    return np.stack([np.minimum.reduceat(_mix(keys ^ _mix(np.full(1, i + 1, _U) * _STEP)), at) for i in range(k)], axis=1)


def sketches(docs: DataFrame, k: int, bands: int, portable: bool = False) -> DataFrame:
    """doc_id, node (hash of the set of n-grams), size (of the set) and bands (hashes of k / bands minima each); null for a null text.

    One Arrow pass; the n-grams themselves are not moved. Documents of equal sets are one node.
    """
    ship(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = k // bands

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for batch in batches:
            texts, at = batch.column("text").cast(pa.large_binary()).to_pylist(), 0
            while at < len(texts):
                start, sets, minima, size = at, [], [], 0
                while at < len(texts) and size < 300_000:
                    if texts[at] is not None:
                        own = texts[at].split()
                        sets.append(gram_keys(own, hashes))
                        size += len(sets[-1])
                        if portable:
                            minima.append(_md5_minima(own, k))
                    at += 1
                there = [t is not None for t in texts[start:at]]
                sig = (np.array(minima, _U) if portable else _seeded_minima(sets, k)) if sets else np.zeros((0, k), _U)
                key = np.broadcast_to(np.arange(bands, dtype=_U), (len(sets), bands)).copy()
                for r in range(rows):
                    key = _mix(key * _STEP + sig[:, r : bands * rows : rows])
                node, number, band = iter([xxhash.xxh3_64_intdigest(x.tobytes()) for x in sets]), iter(map(len, sets)), iter(key.view(np.int64).tolist())
                of = lambda values, put=lambda v: v: [put(next(values)) if t else None for t in there]
                signed = lambda v: v - (1 << 64) if v >= 1 << 63 else v
                yield pa.record_batch(
                    [batch.column("doc_id").slice(start, at - start), pa.array(of(node, signed), pa.int64()), pa.array(of(number), pa.int64()), pa.array(of(band), pa.list_(pa.int64()))],
                    ["doc_id", "node", "size", "bands"],
                )

    return docs.select("doc_id", F.lower("text").alias("text")).mapInArrow(run, f"doc_id {kind}, node long, size long, bands array<long>")


def scoped(rows: DataFrame, scope: Column) -> DataFrame:
    """Sketches of which those of different scopes share neither node nor bucket."""
    of = scope.cast("string")
    return rows.select("doc_id", F.when(F.col("node").isNotNull(), F.xxhash64("node", of)).alias("node"), "size", F.transform("bands", lambda b: F.xxhash64(b, of)).alias("bands"))


PARITY_WORDS = 16


def parity(keys: np.ndarray) -> np.ndarray:
    """Longs whose bit k tells whether an odd number of the set's elements falls on k: two sets differ in at least as many elements as bits."""
    odd = np.bincount((keys % _U(64 * PARITY_WORDS)).astype(np.int64), minlength=64 * PARITY_WORDS) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def gram_sets(docs: DataFrame) -> DataFrame:
    """doc_id, s: the sorted distinct 64-bit hashes of a text's n-grams as bytes; odd: their parity bits (see `parity`)."""
    ship(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                sets = [gram_keys(t.split(), hashes) for t in part.column("text").cast(pa.large_binary()).to_pylist()]
                yield pa.record_batch([part.column("doc_id"), pa.array([x.tobytes() for x in sets], pa.binary()), pa.array([parity(x) for x in sets], pa.list_(pa.int64()))], ["doc_id", "s", "odd"])

    return docs.where("text is not null").select("doc_id", F.lower("text").alias("text")).mapInArrow(run, f"doc_id {kind}, s binary, odd array<long>")


def set_similarity(a: bytes, b: bytes) -> float:
    """Jaccard similarity of two sets as `gram_sets` stores them."""
    x, y = sorted((np.frombuffer(a, _U), np.frombuffer(b, _U)), key=len)
    at = np.minimum(np.searchsorted(y, x), len(y) - 1)
    both = int((y[at] == x).sum())
    return both / (len(x) + len(y) - both)


def near(pairs: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """The pairs a, b whose sets (doc_id, s) have a Jaccard similarity of at least `least`, exactly."""

    @F.arrow_udf("double")
    def compare(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array([set_similarity(x.as_py(), y.as_py()) for x, y in zip(a, b, strict=True)], pa.float64())

    x = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("doc_id").alias("b"), F.col("s").alias("sb")), "b")
    return x.where(compare("sa", "sb") >= least).select("a", "b")


def verified_components(docs: DataFrame, members: DataFrame, least: float) -> DataFrame:
    """doc_id, comp of the documents in members (key, doc_id, size) that share a bucket: components of all near pairs in a bucket.

    While buckets hold many pairs, members are compared with a leader of their bucket, which then leaves it: all its links are known.
    After that every pair of a bucket that still spans components is compared. What a round has joined is not compared again.
    """
    labels = cut(members.select("doc_id").distinct().withColumn("comp", F.col("doc_id")))
    n = labels.count()
    if not n:
        return labels
    wanted = labels.select("doc_id")
    sets = cut(gram_sets(docs.join(F.broadcast(wanted) if n <= BROADCAST_IDS else wanted, "doc_id", "left_semi")))
    alike = lambda x, y: F.least(x, y) >= F.greatest(x, y) * least - 1e-9
    ordered = lambda x, y: (F.least(x, y).alias("a"), F.greatest(x, y).alias("b"))

    def merge(labels: DataFrame, pairs: DataFrame) -> DataFrame:
        a, b = (labels.select(F.col("doc_id").alias(n), F.col("comp").alias(c)) for n, c in (("a", "u"), ("b", "v")))
        joined = components(near(pairs, sets, least).join(a, "a").join(b, "b").select("u", "v"))
        to = joined.select(F.col("node").alias("comp"), F.col("comp").alias("next"))
        return cut(labels.join(to, "comp", "left").select("doc_id", F.coalesce("next", "comp").alias("comp")))

    for turn in range(LEADER_ROUNDS):
        n = members.groupBy("key").agg(F.count("*").alias("n")).agg(F.sum("n").alias("members"), F.sum(F.col("n") * (F.col("n") - 1.0) / 2).alias("pairs")).first()
        if (n.pairs or 0) <= FEW_PAIRS * (n.members or 0):
            break
        placed = members.join(labels, "doc_id")
        order = F.col("doc_id") if turn == 0 else F.xxhash64("doc_id", F.lit(turn))
        lead = placed.groupBy("key").agg(F.min(F.struct(order.alias("o"), "doc_id", "comp", "size")).alias("l"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi")
        lead = lead.select("key", F.col("l.doc_id").alias("lead"), F.col("l.comp").alias("lead_comp"), F.col("l.size").alias("lead_size"))
        placed = cut(placed.join(lead, "key").where("doc_id <> lead"))
        labels = merge(labels, placed.where(F.col("comp") != F.col("lead_comp")).where(alike("size", "lead_size")).select(*ordered("lead", "doc_id")).distinct())
        members = placed.select("key", "doc_id", "size")
    # what is still apart first passes an exact bound on its overlap, so that few sets have to meet
    rest = members.join(labels, "doc_id").join(sets.select("doc_id", *[F.col("odd")[w].alias(f"o{w}") for w in range(PARITY_WORDS)]), "doc_id")
    other = rest.select("key", F.col("doc_id").alias("other"), F.col("comp").alias("other_comp"), F.col("size").alias("other_size"), *[F.col(f"o{w}").alias(f"x{w}") for w in range(PARITY_WORDS)])
    total = F.col("size") + F.col("other_size")
    most = (total - reduce(add, [F.bit_count(F.col(f"o{w}").bitwiseXOR(F.col(f"x{w}"))) for w in range(PARITY_WORDS)])) / 2
    return merge(labels, rest.join(other, "key").where(F.col("comp") < F.col("other_comp")).where(alike("size", "other_size")).where(most >= (total - most) * least - 1e-9).select(*ordered("doc_id", "other")).distinct())


def fuzzy_dedup(docs: DataFrame, k: int = 112, bands: int = 14, verify: float | None = 0.8, portable: bool = False) -> DataFrame:
    """doc_id, comp: components of the (verified) candidate pairs; documents without any, and those without a text, are their own."""
    return fuzzy_classes(docs, cut(sketches(docs, k, bands, portable)), verify)


def fuzzy_classes(docs: DataFrame, rows: DataFrame, verify: float | None) -> DataFrame:
    """The classes of `fuzzy_dedup` of the documents in rows, which are their sketches."""
    nodes = cut(rows.where("node is not null").groupBy("node").agg(F.min("doc_id").alias("one"), F.any_value("size").alias("size"), F.any_value("bands").alias("bands")))
    spread = nodes.select(F.col("one").alias("doc_id"), "size", F.explode("bands").alias("key"))
    members = cut(spread.join(spread.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "key"))
    if verify is None:  # all that share a bucket are joined, which its star does
        star = members.groupBy("key").agg(F.min("doc_id").alias("u"))
        comp = components(members.join(star, "key").select("u", F.col("doc_id").alias("v"))).select(F.col("node").alias("one"), "comp")
    else:
        comp = verified_components(docs, members, verify).select(F.col("doc_id").alias("one"), "comp")
    known = nodes.select("node", "one").join(comp, "one", "left").select("node", F.coalesce("comp", "one").alias("comp"))
    return rows.select("doc_id", "node").join(known, "node", "left").select("doc_id", F.coalesce("comp", "doc_id").alias("comp"))


# -- the whole pipeline


def row_flags(docs: DataFrame, policies: list[Policy], grams: bool = True) -> DataFrame:
    """doc_id, tokens, safe and, for each policy n, lang{n} and quality{n}: all row-wise stages from one scan.

    docs may hold more than doc_id and text: url, whose host must not be on the list, and lang_pred, the language by a classifier (else by vote).
    grams: whether quality has the limits on repeated n-grams, too.
    """
    language = F.col("lang_pred") if "lang_pred" in docs.columns else lang_vote()
    safe = ~unsafe_words() & ~unsafe_host(host("url")) if "url" in docs.columns else ~unsafe_words()
    flags = [c for n, p in enumerate(policies) for c in (language.isin(*p.languages).alias(f"lang{n}"), (F.size(reasons(p)) == 0).alias(f"quality{n}"))]
    x = measures(docs).select("doc_id", "text", F.size(_words()).cast("long").alias("tokens"), safe.alias("safe"), *flags)
    if not grams:
        return x.drop("text")
    # n-grams are counted where the other rules leave anything to decide
    asked = reduce(or_, [F.col(f"lang{n}") & F.col(f"quality{n}") for n in range(len(policies))])
    x = gram_shares(x, tuple(c for c in x.columns if c not in ("doc_id", "text")), asked)
    own = [c for n, p in enumerate(policies) for c in (f"lang{n}", (F.col(f"quality{n}") & (F.size(gram_reasons(p)) == 0)).alias(f"quality{n}"))]
    return x.select("doc_id", "tokens", "safe", *own)


def row_stages(docs: DataFrame, p: Policy = Policy()) -> DataFrame:
    """The documents that exact dedup, language, quality and safety keep: `attrition` up to fuzzy dedup, without its counts."""
    kept = row_flags(docs, [p]).where("lang0 and quality0 and safe").select("doc_id")
    return docs.join(kept.join(exact_dedup(docs), "doc_id", "left_semi"), "doc_id", "left_semi")


def attrition(docs: DataFrame, p: Policy = Policy(), k: int = 64, bands: int = 16, portable: bool = False, grams: bool = True) -> tuple[DataFrame, DataFrame]:
    """(survivors, one row per stage with docs and tokens left). Flags of all row-wise stages come from one scan (see `row_flags`)."""
    return attritions(docs, {"": p}, k, bands, portable, grams)[""]


def attritions(docs: DataFrame, policies: dict[str, Policy], k: int = 64, bands: int = 16, portable: bool = False, grams: bool = True) -> dict[str, tuple[DataFrame, DataFrame]]:
    """`attrition` of docs under each policy; texts are measured and sketched once for all of them."""
    first = exact_dedup(docs).select("doc_id")
    flagged = row_flags(docs, list(policies.values()), grams)
    flagged = cut(flagged.join(first.withColumn("exact_ok", F.lit(True)), "doc_id", "left").withColumn("exact_ok", F.coalesce("exact_ok", F.lit(False))))
    left = lambda n: F.expr(f"exact_ok and lang{n} and quality{n} and safe")
    some = flagged.where(reduce(or_, map(left, range(len(policies)))))
    rows = cut(sketches(docs.join(some.select("doc_id"), "doc_id", "left_semi"), k, bands, portable))
    got = {}
    for n, (name, p) in enumerate(policies.items()):
        own = rows.join(flagged.where(left(n)).select("doc_id"), "doc_id", "left_semi") if len(policies) > 1 else rows
        kept = cut(fuzzy_classes(docs, own, p.fuzzy).where("doc_id = comp").select("doc_id"))
        x = flagged.join(kept.withColumn("fuzzy_ok", F.lit(True)), "doc_id", "left").withColumn("fuzzy_ok", F.coalesce("fuzzy_ok", F.lit(False)))
        stages = {"input": F.lit(True), "exact": F.col("exact_ok"), "language": F.col(f"lang{n}"), "quality": F.col(f"quality{n}"), "safety": F.col("safe"), "fuzzy": F.col("fuzzy_ok")}
        sofar, counts = F.lit(True), []
        for stage, (label, flag) in enumerate(stages.items()):
            sofar = sofar & flag
            counts.append(F.struct(F.lit(stage).alias("stage"), F.lit(label).alias("name"), F.count(F.when(sofar, 1)).alias("docs_out"), F.coalesce(F.sum(F.when(sofar, F.col("tokens"))), F.lit(0)).alias("tokens_out")))
        got[name] = docs.join(kept, "doc_id", "left_semi"), x.agg(F.array(*counts).alias("all")).select(F.inline("all"))
    return got


# -- contamination and sampling


#: N-grams of test items that are broadcast at most (16 bytes each); beyond that they meet the documents' by key.
BROADCAST_GRAMS = 2_000_000


def overlap(docs: DataFrame, items: DataFrame, n: int = 8) -> DataFrame:
    """doc_id, item_id, n_grams of documents that share n-grams with test items."""
    grams = lambda df, key: hashed_shingles(df, key, n).select(key, F.explode_outer("s").alias("g")).where("g is not null")
    asked = cut(grams(items, "item_id"))
    if asked.count() <= BROADCAST_GRAMS:
        asked = F.broadcast(asked)
    return grams(docs, "doc_id").join(asked, "g").groupBy("doc_id", "item_id").agg(F.count("*").alias("n_grams"))


def token_budget(docs: DataFrame, budget: int, bits: int = 8) -> DataFrame:
    """doc_id of documents in md5 order until the budget is reached; sums of hash ranges first, so no global sort.

    Only the range in which the budget ends is ordered.
    """
    h = F.md5(F.col("doc_id").cast("string").cast("binary"))
    x = docs.select("doc_id", h.alias("h"), F.size(_words()).cast("long").alias("tokens")).withColumn("r", F.substring("h", 1, bits // 4))
    ranges = x.groupBy("r").agg(F.sum("tokens").alias("s"))
    from pyspark.sql.window import Window

    before = ranges.withColumn("before", F.coalesce(F.sum("s").over(Window.orderBy("r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    x = x.join(before, "r").where(F.col("before") < budget)
    inside = F.sum("tokens").over(Window.partitionBy("r").orderBy("h"))
    return x.withColumn("upto", F.col("before") + inside).where(F.col("upto") <= budget).select("doc_id", "upto")
