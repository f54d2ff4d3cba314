"""LM scoring with a weighted backoff automaton of order 3.

The model: counts of all tokens, pairs and triples of the training texts (lower-cased words and one end per document; two starts
stand before each text), none left out. A context is a state. In state s with count c(s) the word w has

    p(w | s) = (c(sw) + prior * p(w | s')) / (c(s) + prior)

where s' is s without its first token and the root has (c(w) + 1) / (N + V + 1): Dirichlet smoothing, whose
probabilities sum to 1 in each state over the vocabulary and one class of unknown words. As an automaton: an arc where c(sw) > 0, and a
failure arc of weight prior / (c(s) + prior) to s', which is followed until a state has the arc; the root has all. The next state is the
longest suffix of what was read that is a state. One pass from left to right carries the state and adds up log10 weights.

The model grows with the corpus, and so no task, worker or driver holds it. Texts are taken in batches of some megabytes. Each
batch asks for the counts of its distinct n-grams and tells its own: sorted 64-bit hashes go, compressed, to the part of the hash
range that they fall in. A part adds up what the batches told and answers each with the sums. A batch that has its answers holds
just the states and arcs that its texts can reach, builds that part of the automaton and runs its texts through. Shuffled
are hashes and counts, some six bytes for each distinct n-gram of a batch, and texts once, compressed. A frequent word
or pair costs one entry per batch, so there are no hot keys. `batch_bytes` bounds what a task holds when asking and scoring, `part_grams` what it
holds when adding up.

Rows are read twice and must come in the same order and split both times, as those of a file scan do; a digest in each answer tells
if they did not, and the run ends with an error.

Edge cases: null text counts as empty and scores its end token; null ids count as the empty string in the split into
training and held-out rows; repeated rows are counted and scored each; empty training data give every token the weight of
the unknown class; a text longer than a batch is a batch; an empty table gives no rows; other columns, whatever their names (but those
of the result), are left as they are.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from webtext.llm.common import WordHashes, blobs, cut
from webtext.session import ship

#: Hashes of the end token and of the start.
END, START = 0x51ED270B7A2C4F11, 0x2545F4914F6CDD1D
ORDER = 3
#: Weight of the shorter context in states of one and of two tokens; of seven settings tried on held-out rows the best at the larger size (3.38 against 4.19 a token at the root).
PRIOR = (1000.0, 10.0)
#: Bytes of text that a batch reaches, and n-grams of all batches that a part gets on average.
BATCH_BYTES, PART_GRAMS = 12_000_000, 4_000_000
_U = np.uint64
_BLOCK = 1 << 20


def held_out(id_col: Column | str) -> Column:
    """The rows that are kept from training: crc32 of the id as text, modulo 7, is 2."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % 7 == 2


def tokens_of(text: bytes, hashes: WordHashes) -> np.ndarray:
    words = text.lower().split()
    out = np.empty(len(words) + 1, _U)
    out[:-1] = np.fromiter(map(hashes.__getitem__, words), _U, len(words))
    out[-1] = END
    return out


def longer(state: np.ndarray, token: np.ndarray) -> np.ndarray:
    """The key of a state and the token behind it."""
    key = (state * _U(0x9E3779B97F4A7C15)) ^ (token + _U(0x632BE59BD9B4E019) + (state >> _U(7)))
    key = (key ^ (key >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return key ^ (key >> _U(32))


def begun(x: np.ndarray, starts: np.ndarray, first) -> np.ndarray:
    """x one place later in each text; a text begins with `first`."""
    out = np.empty_like(x)
    out[1:] = x[:-1]
    out[starts] = first
    return out


def grams(tokens: np.ndarray, starts: np.ndarray) -> list[np.ndarray]:
    """The keys of the n-grams that end at each token, order by order; before a text stands START, of which there are as many as needed."""
    out = [tokens]
    for _ in range(ORDER - 1):
        out.append(longer(begun(out[-1], starts, START), tokens))
    return out


def placed(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys, sorted, and the place of each key among them: one sort, where looking each up would cost several."""
    sequence = np.argsort(keys)
    keys = keys[sequence]
    first = np.append(True, keys[1:] != keys[:-1])[: len(keys)]
    places = np.empty(len(keys), np.int32)
    places[sequence] = np.cumsum(first, dtype=np.int32) - 1
    return keys[first], places


def pack(arrays: list[np.ndarray], steps: bool) -> bytes:
    """64-bit numbers as eight planes of bytes, each compressed by itself: high ones are nearly all zero; steps: as differences, for sorted ones."""
    flat = np.concatenate([np.diff(x, prepend=_U(0)) if steps else x.astype(_U) for x in arrays])
    codec = pa.Codec("zstd", compression_level=1)
    planes = [codec.compress(plane.tobytes(), asbytes=True) for plane in flat.view(np.uint8).reshape(-1, 8).T]
    return np.array([len(x) for x in planes], np.int64).tobytes() + b"".join(planes)


def unpack(data: bytes, sizes: list[int], steps: bool) -> list[np.ndarray]:
    codec, n, at = pa.Codec("zstd"), sum(sizes), 64
    flat = np.empty((n, 8), np.uint8)
    for k, size in enumerate(np.frombuffer(data, np.int64, 8).tolist()):
        flat[:, k] = np.frombuffer(codec.decompress(data[at : at + size], n, asbytes=True), np.uint8)
        at += size
    parts = np.split(flat.view(_U).reshape(n), np.cumsum(sizes)[:-1])
    return [np.cumsum(x, dtype=_U) for x in parts] if steps else parts


def stretches(batches: Iterator[pa.RecordBatch], limit: int) -> Iterator[tuple[int, pa.Table]]:
    """(number, rows) of consecutive rows whose texts reach limit bytes; the same however the rows are batched."""
    number, held, size = TaskContext.get().partitionId() << 32, [], 0
    for batch in batches:
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at, done = 0, 0
        while at < batch.num_rows:
            to = min(batch.num_rows, int(np.searchsorted(ends, done + limit - size)) + 1)
            held.append(batch.slice(at, to - at))
            size += int(ends[to - 1]) - done
            at, done = to, int(ends[to - 1])
            if size >= limit:
                yield number, pa.Table.from_batches(held)
                number, held, size = number + 1, [], 0
    if held:
        yield number, pa.Table.from_batches(held)


def tokenised(texts: pa.ChunkedArray, hashes: WordHashes) -> tuple[np.ndarray, np.ndarray]:
    """All tokens, and where each text begins."""
    each = [tokens_of(t or b"", hashes) for chunk in texts.chunks for t in blobs(chunk)]
    return np.concatenate(each), np.concatenate([[0], np.cumsum([len(t) for t in each[:-1]], dtype=np.int64)])


def digest(keys: list[np.ndarray]) -> int:
    return xxhash.xxh3_64_intdigest(b"".join(k.tobytes() for k in keys)) >> 1


def bounds(keys: np.ndarray, bits: int) -> np.ndarray:
    """Where in the sorted keys each of the 2 ** bits parts of the range begins (and the last ends)."""
    edges = np.arange(1 << bits, dtype=_U) << _U(64 - bits) if bits else np.zeros(1, _U)
    return np.append(np.searchsorted(keys, edges), len(keys))


_ASKED = "part long, batch long, digest long, sizes array<long>, keys binary, counts binary"


def asked(docs: DataFrame, learn: str, bits: int, batch_bytes: int) -> DataFrame:
    """What each batch of docs (learn, text) asks of each part: its distinct n-grams, and how often it holds them in rows to learn from."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes(200_000)
        for number, rows in stretches(batches, batch_bytes):
            tokens, starts = tokenised(rows.column("text"), hashes)
            told = np.repeat(pc.fill_null(rows.column(learn), False).to_numpy().astype(bool), np.diff(np.append(starts, len(tokens))))
            keys, counts = [], []
            for k in grams(tokens, starts):
                sequence = np.argsort(k)
                k = k[sequence]
                first = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
                keys.append(k[first])
                counts.append(np.add.reduceat(told[sequence].astype(np.int64), first))
            check, at = digest(keys), [bounds(k, bits) for k in keys]
            out: dict[str, list] = {name: [] for name in ("part", "batch", "digest", "sizes", "keys", "counts")}
            for part in range(1 << bits):
                cuts = [slice(a[part], a[part + 1]) for a in at]
                sizes = [c.stop - c.start for c in cuts]
                if any(sizes):
                    for name, value in zip(out, (part, number, check, sizes, pack([k[c] for k, c in zip(keys, cuts, strict=True)], True), pack([n[c] for n, c in zip(counts, cuts, strict=True)], False)), strict=True):
                        out[name].append(value)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary(), pa.binary())
            yield pa.record_batch([pa.array(v, kind) for v, kind in zip(out.values(), kinds, strict=True)], list(out))

    return docs.select(learn, "text").mapInArrow(run, _ASKED)


_ANSWERED = "batch long, part long, digest long, sizes array<long>, counts binary, tokens long, distinct long"


def answer(rows: pa.Table) -> pa.Table:
    """One part: the sums of what was told, back to each batch that asked; tokens and distinct of the part are in its first row."""
    sizes = rows.column("sizes").to_pylist()
    keys = [unpack(k, s, True) for k, s in zip(rows.column("keys").to_pylist(), sizes, strict=True)]
    told = [unpack(n, s, False) for n, s in zip(rows.column("counts").to_pylist(), sizes, strict=True)]
    sums, tokens, distinct = [], 0, 0
    for order in range(ORDER):
        k = np.concatenate([x[order] for x in keys])
        sequence = np.argsort(k, kind="stable")
        k = k[sequence]
        first = np.ones(len(k), bool)
        first[1:] = k[1:] != k[:-1]
        n = np.concatenate([x[order] for x in told]).astype(np.int64)
        total = np.add.reduceat(n[sequence], np.flatnonzero(first)) if len(k) else n
        if not order:
            tokens, distinct = int(total.sum()), int((total > 0).sum())
        back = np.empty_like(n)
        back[sequence] = total[np.cumsum(first) - 1]
        sums.append(np.split(back, np.cumsum([s[order] for s in sizes])[:-1]))
    counts = pa.array([pack(list(x), False) for x in zip(*sums, strict=True)], pa.binary())
    rest = np.zeros(len(sizes) - 1, np.int64)
    return pa.table([rows.column("batch"), rows.column("part"), rows.column("digest"), rows.column("sizes"), counts, np.append(tokens, rest), np.append(distinct, rest)], ["batch", "part", "digest", "sizes", "counts", "tokens", "distinct"])


class Automaton:
    """The states and arcs that the n-grams of some texts can reach.

    Arcs and states are numbered by the places of the n-grams among the distinct ones of their order, and known by their counts.
    """

    def __init__(self, keys: list[np.ndarray], counts: list[np.ndarray], tokens: int, distinct: int, prior: tuple[float, ...] = PRIOR):
        self.keys, self.counts, self.prior = keys, counts, prior
        self.classes = tokens + distinct + 1
        at = np.searchsorted(keys[0], _U(END))
        #: Texts learned from, each of which begins in the state of starts and has one end.
        self.texts = int(counts[0][at]) if at < len(keys[0]) and keys[0][at] == END else 0

    def run(self, tokens: np.ndarray, starts: np.ndarray, places: list[np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Count of each token, log10 of its weight at the root, and the weight of the way from the state before it.

        places: of the n-grams that end at each token among the keys, order by order; they are looked up if not given.
        """
        if places is None:
            places = [np.searchsorted(k, g) for k, g in zip(self.keys, grams(tokens, starts), strict=True)]
        seen = [n[at] for n, at in zip(self.counts, places, strict=True)]
        root = np.log10((seen[0] + 1) / self.classes)
        way, todo = np.zeros(len(root)), np.ones(len(root), bool)
        smooth, fails = [10**root], []
        for order in range(1, ORDER):
            state = begun(seen[order - 1], starts, self.texts)
            prior = self.prior[order - 1]
            smooth.append((seen[order] + prior * smooth[-1]) / (state + prior))
            fails.append(np.log10(prior / (state + prior)))
        for order in range(ORDER - 1, 0, -1):  # from the longest state down its failure arcs; a context never seen is no state and costs nothing
            arc = todo & (seen[order] > 0)
            way[arc] += np.log10(smooth[order][arc])
            todo &= ~arc
            way[todo] += fails[order - 1][todo]
        way[todo] += root[todo]
        return seen[0], root, way


RESULT = "n_tokens long, n_known long, base_score double, score double"


def score(docs: DataFrame, learn: str, prior: tuple[float, ...] = PRIOR, batch_bytes: int = BATCH_BYTES, part_grams: int = PART_GRAMS) -> tuple[DataFrame, int]:
    """docs (..., learn, text) without text, with n_tokens, n_known, base_score and score; and the tokens learned from.

    Rows whose `learn` is true are learned from, all are scored.
    """
    ship(docs.sparkSession)
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    bits = max(0, math.ceil(math.log2(max(1, size / 4 / part_grams))))  # an n-gram for some four bytes of text, of all orders
    answers = asked(docs, learn, bits, batch_bytes).groupBy("part").applyInArrow(answer, _ANSWERED)
    answers = cut(answers)
    tokens, distinct = answers.agg(F.coalesce(F.sum("tokens"), F.lit(0)), F.coalesce(F.sum("distinct"), F.lit(0))).first()

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = pa.Codec("zstd", compression_level=4)
        for number, rows in stretches(batches, batch_bytes):
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rows.schema) as out:
                out.write_table(rows)
            body = sink.getvalue()
            yield pa.record_batch([pa.array([number], pa.int64()), pa.array([body.size], pa.int64()), pa.array([codec.compress(body, asbytes=True)], pa.binary())], ["batch", "size", "body"])

    kept = StructType([f for f in docs.schema.fields if f.name != "text"])
    names = [*kept.names, "n_tokens", "n_known", "base_score", "score"]

    def scored(batch: pa.Table, answered: pa.Table) -> pa.Table:
        codec = pa.Codec("zstd")
        raw = codec.decompress(batch.column("body")[0].as_py(), batch.column("size")[0].as_py())
        rows = pa.ipc.open_stream(raw).read_all()
        words, starts = tokenised(rows.column("text"), WordHashes(200_000))
        keys, places = zip(*map(placed, grams(words, starts)), strict=True)
        answered = answered.sort_by("part")
        if set(answered.column("digest").to_pylist()) != {digest(keys)}:
            raise ValueError("the rows of a batch were not the same when read again")
        parts = [unpack(n, s, False) for n, s in zip(answered.column("counts").to_pylist(), answered.column("sizes").to_pylist(), strict=True)]
        counts = [np.concatenate([p[order] for p in parts]).astype(np.int64) for order in range(ORDER)]
        automaton, sums, n = Automaton(keys, counts, tokens, distinct, prior), [], np.diff(np.append(starts, len(words)))
        edge = 0
        while edge < len(n):  # a block of texts at a time
            to = max(edge + 1, int(np.searchsorted(starts, starts[edge] + _BLOCK)))
            own = starts[edge:to] - starts[edge]
            block = slice(starts[edge], starts[edge] + own[-1] + n[to - 1])
            seen, root, way = automaton.run(words[block], own, [at[block] for at in places])
            sums.append([np.add.reduceat(x, own) for x in ((seen > 0).astype(np.int64), root, way)])
            edge = to
        known, base, total = (np.concatenate(x) for x in zip(*sums, strict=True))
        return pa.table([*(rows.column(c) for c in kept.names), n, known, base, total], names)

    bodies = docs.select(*kept.names, "text").mapInArrow(packed, "batch long, size long, body binary")
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.fields)
    out = bodies.groupBy("batch").cogroup(answers.groupBy("batch")).applyInArrow(scored, f"{fields}, {RESULT}")
    return out, tokens


def plain_scores(texts: list[str | None], learn: list[bool], prior: tuple[float, ...] = PRIOR) -> list[float]:
    """The scores again from counters of tuples; for tests."""
    from collections import Counter

    def tokens(text: str | None) -> list[str]:
        return ["<s>", "<s>", *(w.decode("utf-8", "replace") for w in (text or "").encode().lower().split()), "</s>"]

    grams, contexts = Counter(), Counter()
    for text, use in zip(texts, learn, strict=True):
        t = tokens(text)
        for i in range(2, len(t)) if use else ():
            for n in range(3):
                grams[tuple(t[i - n : i + 1])] += 1
                contexts[tuple(t[i - n : i])] += 1
    single = [g for g in grams if len(g) == 1]
    classes = contexts[()] + len(single) + 1

    def p(word: str, state: tuple[str, ...]) -> float:
        if not state:
            return (grams[(word,)] + 1) / classes
        k = prior[len(state) - 1]
        return (grams[(*state, word)] + k * p(word, state[1:])) / (contexts[state] + k)

    return [sum(math.log10(p(t[i], tuple(t[i - 2 : i]))) for i in range(2, len(t))) for t in map(tokens, texts)]
