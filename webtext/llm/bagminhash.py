"""Near-duplicate classes by weighted minwise hashing of word 5-gram multisets.

Each shingle s with weight (count) c owns a Poisson process on [0, c): the axis of weights is cut into the unit interval and
dyadic blocks [1, 2), [2, 4), ...; each block has a process of its own whose rate is its length, and a point carries its place in
the block, so that a shingle of a smaller weight sees exactly the points below it. Points are dealt to the m registers
by hash, a register keeps its earliest time, and a process stops at the first point later than all registers of its document.
Two documents agree in a register with a probability that is their weighted Jaccard similarity.

Documents with the same multiset become one node first. Registers are banded; buckets of equal bands propose pairs, which are
verified on the whole multisets. A bucket's members are compared with its most connected member first, and only what is still in
different components afterwards is paired further, so large groups cost a pair per member rather than per pair. Those further
pairs must first pass two exact bounds on their overlap: elements no other open node holds, and parity bitmaps. Classes are the
connected components of the verified links.

Edge cases: null text counts as empty; all texts without words are one class; texts of one to four words are one shingle and
match only equal ones (as do all texts too short to reach the threshold otherwise); repeated rows, and rows with null ids,
are placed by their text; a class takes its smallest id (null if it has none); an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webtext.llm.common import WordHashes, blobs, cut, freed, row_key
from webtext.llm.graph import components
from webtext.session import ship

_U = np.uint64
_STEP = _U(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class Settings:
    words: int = 5
    threshold: float = 0.8
    bands: int = 25
    rows: int = 5
    leader_rounds: int = 4
    parity_words: int = 16

    @property
    def registers(self) -> int:
        return self.bands * self.rows

    @property
    def least_weight(self) -> int:
        """Documents of fewer shingles reach the threshold only with an equal multiset."""
        return math.ceil(self.threshold / (1 - self.threshold) - 1e-9)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def shingles(text: bytes, hashes: WordHashes, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes, sorted, and their counts."""
    own = text.lower().split()
    w = np.fromiter(map(hashes.__getitem__, own), _U, len(own))
    size = min(words, len(w))
    if not size:
        return np.zeros(0, _U), np.zeros(0, np.int64)
    key = np.full(len(w) - size + 1, size, _U)
    for k in range(size):
        key = _mix(key + w[k : len(w) - size + 1 + k] + _STEP)
    return np.unique(key, return_counts=True)


def numbered(keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The multiset as a sorted set: the k-th copy of a shingle is an element of its own."""
    if len(keys) and counts.max() > 1:
        first = np.repeat(np.cumsum(counts) - counts, counts)
        nth = (np.arange(len(first)) - first).astype(_U)
        again = np.repeat(keys, counts)
        return np.sort(np.where(nth > 0, _mix(again + nth * _STEP), again))
    return keys


def node_of(keys: np.ndarray, counts: np.ndarray) -> int:
    h = xxhash.xxh3_64_intdigest(keys.tobytes() + counts.astype(np.int64).tobytes())
    return h - (1 << 64) if h >= 1 << 63 else h


def signatures(docs: list[tuple[np.ndarray, np.ndarray]], m: int) -> np.ndarray:
    """(len(docs), m) earliest times; documents need at least one shingle."""
    sizes = [len(k) for k, _ in docs]
    keys, counts = np.concatenate([k for k, _ in docs]), np.concatenate([c for _, c in docs])
    doc = np.repeat(np.arange(len(docs)), sizes)
    parts, low = [(keys, doc, counts, np.zeros(len(keys), np.int64))], 1
    while (over := counts > low).any():
        parts.append((keys[over], doc[over], counts[over], np.full(int(over.sum()), low)))
        low *= 2
    key, doc, count, base = (np.concatenate(x) for x in zip(*parts, strict=True))
    seed = _mix(key ^ _mix(base.astype(_U) + _STEP))
    rate = np.maximum(base, 1).astype(np.float64)
    time = np.zeros(len(seed))
    out = np.full(len(docs) * m, np.inf)
    while len(seed):
        seed = seed + _STEP
        r = _mix(seed)
        time = time - np.log1p(-(r >> _U(11)).astype(np.float64) * 2.0**-53) / rate
        alive = time < out.reshape(-1, m).max(axis=1)[doc]
        seed, doc, count, base, rate, time, r = (x[alive] for x in (seed, doc, count, base, rate, time, r))
        place = _mix(r ^ _STEP)
        below = base + ((place >> _U(32)).astype(np.float64) * 2.0**-32 * base).astype(np.int64) < count
        register = ((place & _U(0xFFFFFFFF)) % _U(m)).astype(np.int64)
        np.minimum.at(out, (doc * m + register)[below], time[below])
    return out.reshape(-1, m)


def band_keys(signature: np.ndarray, s: Settings) -> np.ndarray:
    """(documents, bands) hashes of each band's registers, the band's number included."""
    bits = np.ascontiguousarray(signature).view(_U).reshape(len(signature), s.bands, s.rows)
    key = np.broadcast_to(np.arange(s.bands, dtype=_U), bits.shape[:2]).copy()
    for k in range(s.rows):
        key = _mix(key * _STEP + bits[:, :, k])
    return key.view(np.int64)


def sketch(docs: DataFrame, s: Settings) -> DataFrame:
    """_id, _th, node, weight, bands of docs (_id, _th, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            texts, at = blobs(batch.column("text")), 0
            while at < len(texts):
                held, size, start = [], 0, at
                while at < len(texts) and size < 600_000:
                    held.append(shingles(texts[at] or b"", hashes, s.words))
                    size += len(held[-1][0])
                    at += 1
                weight = np.array([int(c.sum()) for _, c in held])
                long = np.flatnonzero(weight >= s.least_weight)
                bands = band_keys(signatures([held[k] for k in long], s.registers), s).ravel() if len(long) else np.zeros(0, np.int64)
                offsets = np.concatenate([[0], np.cumsum(np.where(weight >= s.least_weight, s.bands, 0))]).astype(np.int32)
                part = batch.slice(start, at - start)
                yield pa.record_batch(
                    [part.column("_id"), part.column("_th"), pa.array([node_of(*x) for x in held], pa.int64()), pa.array(weight), pa.ListArray.from_arrays(pa.array(offsets), pa.array(bands))],
                    ["_id", "_th", "node", "weight", "bands"],
                )

    return docs.mapInArrow(run, "_id long, _th long, node long, weight long, bands array<long>")


def multisets(docs: DataFrame, s: Settings) -> DataFrame:
    """node, grams (sorted 8-byte elements) of docs (text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            nodes, grams = [], []
            for text in blobs(batch.column("text")):
                x = shingles(text or b"", hashes, s.words)
                nodes.append(node_of(*x))
                grams.append(numbered(*x).tobytes())
            yield pa.record_batch([pa.array(nodes, pa.int64()), pa.array(grams, pa.binary())], ["node", "grams"])

    return docs.mapInArrow(run, "node long, grams binary")


def similarity(a: bytes, b: bytes) -> float:
    """Weighted Jaccard similarity of two multisets as `numbered` stores them."""
    x, y = np.frombuffer(a, _U), np.frombuffer(b, _U)
    if len(x) > len(y):
        x, y = y, x
    if not len(y):
        return 1.0
    at = np.searchsorted(y, x)
    shared = int((y[np.minimum(at, len(y) - 1)] == x).sum())
    return shared / (len(x) + len(y) - shared)


def parity(grams: bytes, words: int) -> np.ndarray:
    """64 * words bits as longs: bit k tells whether an odd number of the set's elements falls on k.

    Elements that two sets share cancel out, so the bits in which two sets differ are at most the elements in which they do.
    """
    at = np.frombuffer(grams, _U) % _U(64 * words)
    odd = np.bincount(at.astype(np.int64), minlength=64 * words) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def verified(pairs: DataFrame, grams: DataFrame, s: Settings) -> DataFrame:
    """The pairs (u, v) whose multisets reach the threshold."""

    @F.arrow_udf("double")
    def compare(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array([similarity(x.as_py(), y.as_py()) for x, y in zip(a, b, strict=True)], pa.float64())

    left, right = (grams.select(F.col("node").alias(n), F.col("grams").alias(f"g{n}")) for n in "uv")
    both = pairs.join(left, "u").join(right, "v")
    short, long = (f(F.length("gu"), F.length("gv")) for f in (F.least, F.greatest))
    return both.where(short >= long * s.threshold).where(compare("gu", "gv") >= s.threshold - 1e-12).select("u", "v")


def _merge(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (node, comp) after links (u, v) have joined components."""
    u, v = (labels.select(F.col("node").alias(n), F.col("comp").alias(f"c{n}")) for n in "uv")
    joined = components(links.join(u, "u").join(v, "v").select(F.col("cu").alias("u"), F.col("cv").alias("v")))
    to = joined.select(F.col("node").alias("comp"), F.col("comp").alias("next"))
    return cut(labels.join(to, "comp", "left").select("node", F.coalesce("next", "comp").alias("comp")))


def classes_of_nodes(nodes: DataFrame, docs: DataFrame, s: Settings) -> DataFrame:
    """node, comp of the nodes that share a bucket with another; nodes has node, _id, _th (of one document) and bands."""
    spread = nodes.select("node", F.explode("bands").alias("key"))
    shared = spread.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    members = cut(spread.join(shared, "key"))
    # a node's weight in choosing leaders: how many share its buckets
    popular = members.groupBy("node").agg(F.sum("n").alias("pop"))
    members = cut(members.join(popular, "node").select("key", "node", "pop"))
    labels = cut(popular.select("node", F.col("node").alias("comp")))
    n = labels.count()
    if not n:
        return labels
    wanted = nodes.join(labels.select("node"), "node", "left_semi").select("_id", "_th")
    if n <= 1_000_000:  # 16 bytes each
        wanted = F.broadcast(wanted)
    own = docs.join(wanted.withColumnsRenamed({"_id": "w_id", "_th": "w_th"}), F.col("_id").eqNullSafe(F.col("w_id")) & (F.col("_th") == F.col("w_th")), "left_semi")
    grams = cut(multisets(own.select("text"), s).dropDuplicates(["node"]))
    for turn in range(s.leader_rounds):
        freed(docs.sparkSession)
        placed = members.join(labels, "node")
        order = F.struct(F.col("pop") if turn == 0 else F.xxhash64("node", F.lit(turn)), F.xxhash64("node"))
        lead = placed.groupBy("key").agg(F.max_by("node", order).alias("u"), F.max_by("comp", order).alias("lead_comp"), F.min("comp").alias("a"), F.max("comp").alias("b")).where("a <> b").select("key", "u", "lead_comp")
        pairs = cut(placed.join(lead, "key").where("comp <> lead_comp").select("u", F.col("node").alias("v")).distinct())
        freed(docs.sparkSession)
        if pairs.isEmpty():
            return labels
        labels = _merge(labels, verified(pairs, grams, s))
    freed(docs.sparkSession)
    # whatever buckets still span components: every pair across them that can reach the threshold at all
    placed = members.join(labels, "node")
    open_keys = placed.groupBy("key").agg(F.min("comp").alias("a"), F.max("comp").alias("b")).where("a <> b").select("key")
    rest = linkable(cut(placed.join(open_keys, "key").select("key", "node", "comp")), grams, s)
    bits = [f"b{k}" for k in range(s.parity_words)]
    other = rest.select("key", F.col("node").alias("v"), F.col("comp").alias("cv"), F.col("weight").alias("wv"), F.col("common").alias("kv"), *(F.col(b).alias(f"o{b}") for b in bits))
    both = F.col("weight") + F.col("wv")
    differ = reduce(add, (F.bit_count(F.col(b).bitwiseXOR(F.col(f"o{b}"))) for b in bits))
    shared = F.least(F.col("common"), F.col("kv"), (both - differ) / 2)
    within = (F.col("comp") < F.col("cv")) & (shared >= (both - shared) * s.threshold - 1e-9)
    pairs = cut(rest.withColumnRenamed("key", "k").join(other, (F.col("k") == F.col("key")) & within).select(F.col("node").alias("u"), "v").distinct())
    freed(docs.sparkSession)
    return labels if pairs.isEmpty() else _merge(labels, verified(pairs, grams, s))


def linkable(rest: DataFrame, grams: DataFrame, s: Settings) -> DataFrame:
    """rest (key, node, comp) with weight, common and parity bits b0, b1, ..., without nodes that can match no member of their bucket.

    Elements that no other node of rest holds are shared with none. If u of a node's n are such, its overlap with a partner of
    weight w is at most n - u and their union at least w + u. Counting them is linear in the nodes' sizes.
    """

    @F.arrow_udf("array<long>")
    def unpacked(column: pa.Array) -> pa.Array:
        return pa.array([np.frombuffer(x.as_py(), np.int64) for x in column], pa.list_(pa.int64()))

    @F.arrow_udf("array<long>")
    def odd(column: pa.Array) -> pa.Array:
        return pa.array([parity(x.as_py(), s.parity_words) for x in column], pa.list_(pa.int64()))

    own = grams.join(rest.select("node").distinct(), "node", "left_semi").select("node", (F.length("grams") / 8).cast("long").alias("weight"), unpacked("grams").alias("g"), odd("grams").alias("odd"))
    own = cut(own)
    freed(own.sparkSession)
    alone = own.select("node", F.explode("g").alias("x")).groupBy("x").agg(F.count("*").alias("n"), F.any_value("node").alias("node")).where("n = 1").groupBy("node").agg(F.count("*").alias("u"))
    bits = [F.col("odd")[k].alias(f"b{k}") for k in range(s.parity_words)]
    known = own.select("node", "weight", *bits).join(alone, "node", "left").withColumn("common", F.col("weight") - F.coalesce("u", F.lit(0))).drop("u")
    x = rest.join(known, "node")
    least = x.groupBy("key").agg(F.min("weight").alias("least"))
    able = F.col("common") >= (F.col("weight") - F.col("common") + F.col("least")) * s.threshold - 1e-9
    return cut(x.join(least, "key").where(able).drop("least"))


def placed_nodes(own: DataFrame, s: Settings = Settings()) -> tuple[DataFrame, DataFrame]:
    """(_id, _th, node, ... of each row of own (_id, _th, text); node, least, comp: the least id of a node and its class)."""
    rows = cut(sketch(own, s))
    nodes = cut(rows.groupBy("node").agg(F.min("_id").alias("least"), F.min(F.struct(F.col("_id").isNull(), "_id", "_th")).alias("one"), F.any_value("bands").alias("bands")))
    labels = classes_of_nodes(nodes.select("node", "one._id", "one._th", "bands"), own, s)
    freed(own.sparkSession)
    return rows, nodes.select("node", "least").join(labels, "node", "left").withColumn("comp", F.coalesce("comp", "node"))


def near_duplicates(docs: DataFrame, s: Settings = Settings(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """_id, _th (see row_key) and class_id, the smallest id of its class, of each row of docs."""
    ship(docs.sparkSession)
    key = row_key(id_col, text_col)
    own = docs.select(key[0].cast("long").alias("_id"), key[1], F.col(text_col).cast("string").alias("text"))
    rows, placed = placed_nodes(own, s)
    least = placed.groupBy("comp").agg(F.min("least").alias("class_id"))
    return rows.select("_id", "_th", "node").join(placed.join(least, "comp").select("node", "class_id"), "node").select("_id", "_th", "class_id", "node")


def plain_classes(texts: dict[int, str | None], words: int = 5, threshold: float = 0.8) -> dict[int, int]:
    """The classes again by comparing all pairs; for tests."""
    from collections import Counter

    def bag(text: str | None) -> Counter:
        w = (text or "").encode().lower().split()
        return Counter(tuple(w[i : i + min(words, len(w))]) for i in range(len(w) - min(words, len(w)) + 1) if w)

    ids = sorted(texts)
    bags, top = {i: bag(texts[i]) for i in ids}, {i: i for i in ids}

    def find(i: int) -> int:
        while top[i] != i:
            i = top[i]
        return i

    for k, i in enumerate(ids):
        for j in ids[:k]:
            union = (bags[i] | bags[j]).total()
            if not union or (bags[i] & bags[j]).total() / union >= threshold - 1e-12:
                a, b = sorted((find(i), find(j)))
                top[b] = a
    return {i: find(i) for i in ids}
