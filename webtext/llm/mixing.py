"""Mixing sources to target weights, in DataFrame operations only.

Each source's documents, in hash order, form one stream of words that is cut into blocks of `block` words; the last is shorter. Targets
fill up by weight until they meet twice the source's size. A source then owns as many slots as its target has blocks, the last of
them cut to the rest. Every slot draws its output shard by itself and uniformly, so a source's counts over the shards are a
multinomial draw of its total, and a shard's size is about `shard_slots`. The totals themselves are not drawn: a source whose
target is twice its size would go beyond it half of the time. A slot's number within
its source, through a permutation of the source's block numbers that differs from pass to pass, names the block, and blocks
meet slots by that number.

Permutations are keyed Feistel networks over a rectangle of numbers just above n; numbers that leave 0 .. n - 1 are permuted on
until they are back. They hold for any n that a long holds, and a rerun gives the same mix. Word positions are prefix sums in two
levels (chunks of the hash within a source, as many as a chunk has rows; then chunks), so no task holds a source. Only ids, sizes and
numbers are shuffled until texts are wanted, and none of them is broadcast but one row per source.

Edge cases: null text has no words and is never taken; a null source is the last source; documents and sources without words
have target or share 0; repeated rows are documents of their own (ties keep equal sizes); an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from webtext.llm.common import WORD, cut

WEIGHTS = (5, 2, 1)
#: Slots that one row unfolds into, and of which a task takes several.
PIECE = 1 << 16
_ROUNDS, _WALK = 3, 16


def _once(i: Column, high: Column, low: Column, key: Column) -> Column:
    """One pass of the network as a single expression."""
    right = F.pmod(i, low)
    left = F.floor((i - right) / low)
    for turn in range(_ROUNDS):
        left = F.pmod(left + F.pmod(F.xxhash64(key, F.lit(2 * turn), right), high), high)
        right = F.pmod(right + F.pmod(F.xxhash64(key, F.lit(2 * turn + 1), left), low), low)
    return left * low + right


def permuted(rows: DataFrame, to: str, i: Column, n: Column, *salt: Column) -> DataFrame:
    """rows with column `to`: the place of i under a pseudorandom permutation of 0 .. n - 1 chosen by salt.

    The rectangle high x low holds fewer than high numbers beyond n - 1. For low of 16 or less those are at most 16, so as many
    further passes always suffice; beyond that they fail with a probability under 17 ** -16, and then raise an error.
    """
    high, low, key, left, right = (f"__{x}" for x in ("high", "low", "key", "left", "right"))
    x = rows.withColumns({"__i": i.cast("long"), "__n": n.cast("long"), key: F.xxhash64(*salt)})
    x = x.withColumn(high, F.greatest(F.ceil(F.sqrt("__n")), F.lit(1)).cast("long"))
    x = x.withColumn(low, F.greatest(F.expr("(__n + __high - 1) div __high"), F.lit(1)))
    x = x.withColumns({left: F.expr("__i div __low"), right: F.pmod("__i", low)})
    for turn in range(_ROUNDS):
        x = x.withColumn(left, F.pmod(F.col(left) + F.pmod(F.xxhash64(key, F.lit(2 * turn), right), high), high))
        x = x.withColumn(right, F.pmod(F.col(right) + F.pmod(F.xxhash64(key, F.lit(2 * turn + 1), left), low), low))
    x = x.withColumn(to, F.col(left) * F.col(low) + F.col(right))
    inside = lambda c: c < F.col("__n")
    again = F.aggregate(F.sequence(F.lit(1), F.lit(_WALK)), F.col(to), lambda c, _: F.when(inside(c), c).otherwise(_once(c, F.col(high), F.col(low), F.col(key))))
    x = x.withColumn(to, F.when(inside(F.col(to)), F.col(to)).otherwise(again))
    x = x.withColumn(to, F.when(inside(F.col(to)), F.col(to)).otherwise(F.raise_error(F.lit("a permutation did not come back")).cast("long")))
    return x.drop("__i", "__n", high, low, key, left, right)


def sized(docs: DataFrame) -> DataFrame:
    """doc_id, source, size, h of docs (doc_id, source, text)."""
    size = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    return docs.select("doc_id", F.col("source").cast("string").alias("source"), size.alias("size"), F.xxhash64("doc_id", F.lit("order")).alias("h"))


def targets(sources: DataFrame, share: float = 1.5, most: float = 2.0, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """source, k, source_size, target of sources (source, source_size): one row per source, so one window over all of them.

    Sources are taken in the order of the ratio at which they would be full; the first that does not fill sets the level for
    the rest, which is where handing on the excess again and again ends.
    """
    order = W.Window.orderBy(F.col("source").asc_nulls_last())
    s = sources.withColumn("k", F.row_number().over(order))
    s = s.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("k") - 1) % len(weights) + 1))
    s = s.withColumns({"cap": most * F.col("source_size"), "full": most * F.col("source_size") / F.col("weight")})
    by, everything = W.Window.orderBy("full", "k"), W.Window.partitionBy(F.lit(1))
    before, rest = by.rowsBetween(W.Window.unboundedPreceding, -1), by.rowsBetween(0, W.Window.unboundedFollowing)
    level = (share * F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(rest)
    s = s.withColumn("level", level)
    s = s.withColumn("level", F.min(F.when(F.col("level") <= F.col("full"), F.struct("full", "k", "level"))).over(everything)["level"])
    target = F.when(F.col("source_size") == 0, F.lit(0.0)).otherwise(F.least("cap", F.coalesce(F.col("weight") * F.col("level"), F.col("cap"))))
    return s.select("source", "k", "source_size", target.alias("target"))


def streams(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """rows (doc_id, source, size, h) with k, begin (its first word's place in its source), source_size, target; and the sources."""
    bits = max(8, math.ceil(math.log2(rows.count() + 1) / 2))
    rows = rows.withColumn("chunk", F.shiftrightunsigned("h", 64 - bits))
    sums = cut(rows.groupBy("source", "chunk").agg(F.sum("size").alias("sum")))
    sources = cut(targets(sums.groupBy("source").agg(F.sum("sum").alias("source_size"))))
    ahead = W.Window.partitionBy("source").orderBy("chunk").rowsBetween(W.Window.unboundedPreceding, -1)
    offsets = sums.select("source", F.col("chunk").alias("oc"), F.coalesce(F.sum("sum").over(ahead), F.lit(0)).alias("off"))
    offsets = offsets.join(sources.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s").withColumnRenamed("source", "os")
    inner = W.Window.partitionBy("source", "chunk").orderBy("h", "size", "doc_id").rowsBetween(W.Window.unboundedPreceding, 0)
    rows = rows.withColumn("begin", F.sum("size").over(inner) - F.col("size"))
    rows = rows.join(offsets.hint("merge"), F.col("source").eqNullSafe(F.col("os")) & (F.col("chunk") == F.col("oc")))
    return rows.withColumn("begin", F.col("begin") + F.col("off")).drop("os", "oc", "off", "chunk", "h"), sources


def slots(sources: DataFrame, block: int, shard_slots: int) -> DataFrame:
    """shard, k, number, block_no, words of every slot of the mix."""
    size, target = F.col("source_size"), F.col("target")
    passes = F.floor(target / size).cast("long")
    rest = F.round(target - passes * size).cast("long")
    blocks = F.ceil(size / block).cast("long")
    n = passes * blocks + F.ceil(rest / block).cast("long")
    s = sources.where("source_size > 0 and target > 0").select("k", blocks.alias("blocks"), rest.alias("rest"), n.alias("n")).where("n > 0")
    everything = s.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    shards = max(1, -(-everything // shard_slots))
    pieces = s.withColumn("first", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1, F.lit(PIECE).cast("long"))))
    pieces = pieces.repartition(max(1, everything // (4 * PIECE)), "k", "first")
    x = pieces.withColumn("number", F.explode(F.sequence(F.col("first"), F.least(F.col("first") + PIECE, F.col("n")) - 1)))
    x = permuted(x.withColumn("turn", F.expr("number div blocks")), "block_no", F.col("number") % F.col("blocks"), F.col("blocks"), F.lit("block"), F.col("k"), F.col("turn"))
    cut_to = F.when((F.col("number") == F.col("n") - 1) & (F.col("rest") % block > 0), F.col("rest") % block).otherwise(F.lit(block))
    return x.select(F.pmod(F.xxhash64(F.lit("shard"), "k", "number"), F.lit(shards)).alias("shard"), "k", "number", "block_no", cut_to.cast("long").alias("words"))


def shard_counts(drawn: DataFrame) -> DataFrame:
    """shard, k, n: how many blocks of each source an output shard holds."""
    return drawn.groupBy("shard", "k").agg(F.count("*").alias("n"))


def fragments(rows: DataFrame, block: int) -> DataFrame:
    """k, block_no, and the part of each block that is a document's: doc_id, begin, from and to in the block, skip in the document."""
    first, last = F.floor(F.col("begin") / block), F.floor((F.col("begin") + F.col("size") - 1) / block)
    x = rows.where("size > 0").select("k", "doc_id", "size", "begin", F.explode(F.sequence(first, last)).alias("block_no"))
    at = F.col("block_no") * block
    return x.select("k", "block_no", "doc_id", "size", "begin", F.greatest(F.col("begin") - at, F.lit(0)).alias("from"), F.least(F.col("begin") + F.col("size") - at, F.lit(block)).alias("to"), F.greatest(at - F.col("begin"), F.lit(0)).alias("skip"))


def mix(docs: DataFrame, block: int = 64, shard_slots: int = 8192) -> tuple[DataFrame, DataFrame]:
    """(every document with size, source_size, target and taken; the slots of the mix)."""
    rows, sources = streams(cut(sized(docs)))
    rows = cut(rows)
    drawn = slots(sources, block, shard_slots)
    # the sizes of what is unfolded here are not known to the optimiser, which would broadcast it
    asked = drawn.groupBy("k", "block_no", "words").agg(F.count("*").alias("n"))
    hit = fragments(rows, block).hint("merge").join(asked, ["k", "block_no"])
    took = F.greatest(F.least("to", "words") - F.col("from"), F.lit(0)) * F.col("n")
    taken = hit.groupBy("k", "begin", "doc_id", "size").agg(F.sum(took).alias("taken")).withColumnsRenamed({"k": "tk", "begin": "tb", "doc_id": "td", "size": "ts"})
    same = (F.col("k") == F.col("tk")) & (F.col("begin") == F.col("tb")) & F.col("doc_id").eqNullSafe(F.col("td")) & (F.col("size") == F.col("ts"))
    out = rows.join(taken.hint("merge"), same, "left").select("doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))
    return out, drawn


def mixed_blocks(docs: DataFrame, block: int = 64, shard_slots: int = 8192) -> DataFrame:
    """shard, place, k, words: the texts of the mix, block by block (words separated by blanks), in a drawn order within the shard."""
    rows, sources = streams(cut(sized(docs)))
    parts = fragments(cut(rows), block).join(docs.select(F.col("doc_id").alias("d"), F.col("source").alias("src"), "text"), F.col("doc_id").eqNullSafe(F.col("d")))
    words = F.regexp_extract_all("text", F.lit(f"({WORD})"), F.lit(1))
    parts = parts.where(F.size(words) == F.col("size")).dropDuplicates(["k", "begin", "block_no"])
    parts = parts.select("k", "block_no", "from", F.slice(words, (F.col("skip") + 1).cast("int"), (F.col("to") - F.col("from")).cast("int")).alias("part"))
    full = parts.groupBy("k", "block_no").agg(F.array_sort(F.collect_list(F.struct("from", "part"))).alias("parts")).select("k", "block_no", F.flatten(F.transform("parts", lambda p: p["part"])).alias("all"))
    place = F.row_number().over(W.Window.partitionBy("shard").orderBy(F.xxhash64("k", "number"), "k", "number")) - 1
    drawn = slots(sources, block, shard_slots).withColumn("place", place.cast("long"))
    return drawn.hint("merge").join(full, ["k", "block_no"]).select("shard", "place", "k", F.array_join(F.slice("all", F.lit(1), F.col("words").cast("int")), " ").alias("words"))


def repeats(size: Column, taken: Column, *salt: Column) -> Column:
    """Whole copies of a document that stand for its taken words: taken / size, rounded up or down by hash."""
    u = F.pmod(F.xxhash64(*salt, F.lit("copies")), F.lit(1 << 20)) / (1 << 20)
    return F.when(size > 0, F.floor(taken / size + u)).otherwise(0).cast("int")
