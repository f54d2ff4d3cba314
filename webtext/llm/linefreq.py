"""Quality rules: measures of each document and cross-document line frequency.

A line is normalised (lower case, digits to 0, white space to single blanks) and hashed. For each host the distinct
documents that hold a line are counted. Copies are not distinct: documents with the same set of normalised lines count once, whatever
else they share counts as often as it is held. A line is boilerplate if more than `max_docs` distinct documents hold it, and more than
`max_share` of the host's documents: the first limit alone would take common short lines of very large hosts for boilerplate, the second alone
any line of a small one.
Boilerplate lines are removed; a document is rejected that lost lines and is left with less than `min_left` of its
words. Base rules reject very short and very repetitive documents.

Edge cases: null text has no words; a null host is a host of its own; repeated rows are copies; rows with
null or repeated ids are told apart by their text and each keeps its own row; ties do not arise as every limit is a strict
comparison; an empty table gives no rows; other columns are left as they are, but those named as a result are replaced.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webtext.llm.common import WordHashes, blobs, cut, row_key, same_key
from webtext.session import ship

WINDOW = 8
_SPACE = b" \t\n\r\x0b\x0c"
_SYMBOLS = b"#*$%&|<>"
_DIGITS = bytes.maketrans(b"123456789", b"0" * 9)


@dataclass(frozen=True)
class Limits:
    min_words: int = 20
    max_repeat_percent: int = 30
    max_docs: int = 50
    max_share: float = 0.01
    min_left: float = 0.3


def line_hash(line: bytes) -> int:
    """Signed 64-bit hash of the normalised line."""
    h = xxhash.xxh3_64_intdigest(b" ".join(line.lower().translate(_DIGITS).split()))
    return h - (1 << 64) if h >= 1 << 63 else h


def line_set(lines: list[tuple[int, int]]) -> int:
    """One hash for all documents of the same normalised lines."""
    return xxhash.xxh3_64_intdigest(np.unique(np.array([h for h, _ in lines], np.int64)).tobytes()) - (1 << 63)


def repeat_words(words: list[bytes], hashes: WordHashes, window: int = WINDOW) -> int:
    """Words in windows of `window` words that occur twice or more."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    w = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    key = np.zeros(n, np.uint64)
    for k in range(window):
        key = (key ^ w[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    order = np.argsort(key, kind="stable")
    ordered = key[order]
    same = ordered[1:] == ordered[:-1]
    if not same.any():
        return 0
    hit = np.zeros(n, bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    edge = np.zeros(len(words) + 1, np.int32)
    at = np.flatnonzero(hit)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def measures(text: bytes, hashes: WordHashes) -> tuple[int, int, int, int, int, list[tuple[int, int]]]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, and (hash, words) of each line with a word."""
    words = text.split()
    kept = text.translate(None, _SPACE)
    seen: set[bytes] = set()
    dup, lines = 0, []
    for line in text.split(b"\n"):
        if n := len(line.split()):
            dup += line in seen
            seen.add(line)
            lines.append((line_hash(line), n))
    return len(words), len(kept.decode("utf-8", "replace")), len(kept) - len(kept.translate(None, _SYMBOLS)), dup, repeat_words(words, hashes), lines


_MEASURED = "_id long, _th long, host string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, line_set long, lines array<struct<h: long, w: int>>"


def measure(docs: DataFrame) -> DataFrame:
    """One thin row per document (_id, _th, host, text)."""
    kind = pa.list_(pa.struct([("h", pa.int64()), ("w", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for batch in batches:
            rows = [measures(t or b"", hashes) for t in blobs(batch.column("text"))]
            flat = [x for r in rows for x in r[5]]
            offsets = np.concatenate([[0], np.cumsum([len(r[5]) for r in rows], dtype=np.int64)]).astype(np.int32)
            h, w = (pa.array([x[k] for x in flat], t) for k, t in ((0, pa.int64()), (1, pa.int32())))
            lines = pa.ListArray.from_arrays(pa.array(offsets), pa.StructArray.from_arrays([h, w], fields=list(kind.value_type)))
            out = [batch.column(n) for n in ("_id", "_th", "host")] + [pa.array([r[k] for r in rows], pa.int64()) for k in range(5)]
            sets = pa.array([line_set(r[5]) for r in rows], pa.int64())
            yield pa.record_batch([*out, sets, lines], ["_id", "_th", "host", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "line_set", "lines"])

    return docs.mapInArrow(run, _MEASURED)


def frequent_lines(measured: DataFrame, limits: Limits) -> DataFrame:
    """host, h, n_docs of the boilerplate lines of each host."""
    own = F.array_distinct(F.transform("lines", lambda x: x["h"]))
    each = measured.select("host", "line_set", F.explode(own).alias("h")).distinct()
    lines = each.groupBy("host", "h").agg(F.count("*").alias("n_docs")).where(F.col("n_docs") > limits.max_docs)
    hosts = measured.groupBy(F.col("host").alias("host_name")).agg(F.count("*").alias("host_docs"))
    return lines.join(hosts, F.col("host").eqNullSafe(F.col("host_name"))).where(F.col("n_docs") > limits.max_share * F.col("host_docs")).select("host", "h", "n_docs")


def judge(docs: DataFrame, limits: Limits = Limits(), host: str = "source", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with the measures, base_failed, removed (hashes of its boilerplate lines), words_left and kept.

    Text is measured once; only hashes and counts are shuffled. Documents meet their verdict by key.
    """
    return _with_verdict(docs, measured_once(docs, host, id_col, text_col), limits, id_col, text_col)


def measured_once(docs: DataFrame, host: str = "source", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Measures of each row, kept in the shared folder as two passes follow."""
    ship(docs.sparkSession)
    key = row_key(id_col, text_col)
    return cut(measure(docs.select(key[0].cast("long").alias("_id"), key[1], F.col(host).cast("string").alias("host"), F.col(text_col).cast("string").alias("text"))))


def verdicts(measured: DataFrame, limits: Limits) -> DataFrame:
    """measured without its lines, with base_failed, removed, words_left and kept."""
    frequent = cut(frequent_lines(measured, limits).select(F.col("host").alias("f_host"), F.col("h").alias("f_h")))
    lines = measured.select("_id", "_th", "host", F.explode("lines").alias("line")).select("_id", "_th", "host", "line.h", "line.w")
    hits = lines.join(frequent, F.col("host").eqNullSafe(F.col("f_host")) & (F.col("h") == F.col("f_h"))).select("_id", "_th", "host", "h", "w")
    # repeated rows are summed together here, and shared out again by their number
    gone = hits.groupBy("_id", "_th", "host").agg(F.collect_set("h").alias("removed"), F.sum("w").alias("words_removed"))
    same = measured.groupBy("_id", "_th", "host").agg(F.count("*").alias("times"))
    gone = gone.join(same, same_key(gone, same) & gone["host"].eqNullSafe(same["host"])).select(gone["_id"].alias("g_id"), gone["_th"].alias("g_th"), gone["host"].alias("g_host"), "removed", (F.col("words_removed") / F.col("times")).cast("long").alias("words_removed"))
    out = measured.drop("lines", "line_set").join(gone, F.col("_id").eqNullSafe(F.col("g_id")) & (F.col("_th") == F.col("g_th")) & F.col("host").eqNullSafe(F.col("g_host")), "left")
    out = out.withColumn("base_failed", (F.col("n_words") < limits.min_words) | (100 * F.col("n_repeat_words") > limits.max_repeat_percent * F.col("n_words")))
    out = out.withColumn("words_left", F.col("n_words") - F.coalesce("words_removed", F.lit(0)))
    depleted = F.col("removed").isNotNull() & (F.col("words_left") < limits.min_left * F.col("n_words"))
    return out.withColumn("kept", ~F.col("base_failed") & ~depleted).drop("g_id", "g_th", "g_host", "words_removed")


def _with_verdict(docs: DataFrame, measured: DataFrame, limits: Limits, id_col: str, text_col: str) -> DataFrame:
    found = verdicts(measured, limits).drop("host").dropDuplicates(["_id", "_th"]).withColumnsRenamed({"_id": "v_id", "_th": "v_th"})
    key = row_key(id_col, text_col)
    own = docs.withColumns({"__k0": key[0].cast("long"), "__k1": key[1]})
    return own.join(found, F.col("__k0").eqNullSafe(F.col("v_id")) & (F.col("__k1") == F.col("v_th")), "left").drop("__k0", "__k1", "v_id", "v_th")


def clean_text(text_col: str, removed_col: str):
    """The text without the lines whose hashes are in removed."""

    @F.arrow_udf("string")
    def cleaned(text: pa.Array, removed: pa.Array) -> pa.Array:
        out = []
        for t, gone in zip(text, removed, strict=True):
            t, gone = t.as_py(), gone.as_py()
            if t is not None and gone:
                hashes = set(gone)
                t = "\n".join(x for x in t.split("\n") if not x.encode().split() or line_hash(x.encode()) not in hashes)
            out.append(t)
        return pa.array(out, pa.string())

    return cleaned(text_col, removed_col)


def plain_measures(text: str | None) -> dict[str, int]:
    """The base measures again, straight from their definitions; for tests."""
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    grams = [tuple(words[i : i + WINDOW]) for i in range(len(words) - WINDOW + 1)]
    often = {g for g in grams if grams.count(g) > 1}
    covered = {i + k for i, g in enumerate(grams) if g in often for k in range(WINDOW)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return {
        "n_words": len(words),
        "word_chars": sum(map(len, words)),
        "n_symbols": sum(c in "#*$%&|<>" for c in text),
        "n_dup_lines": sum(x in lines[:i] for i, x in enumerate(lines)),
        "n_repeat_words": len(covered),
    }
