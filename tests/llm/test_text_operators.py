"""BPE, audio, language model, quality rules and near-duplicates against brute force."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from webtext.llm import audio, bagminhash, bpe, linefreq, ngram
from webtext.llm.queries import QUERIES
from webtext.llm.q09 import tokenised, tokenizer_path

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer_path())


def test_bpe_equals_the_library(library):
    rng = random.Random(1)
    bits = ["a", "aa", "'s", " ", "  ", "\n", "\t", "é", "\x85", "\x1c", "<|endoftext|>", "中", "🙂", "1", "#", " the", "　", "\xa0", "'", "½", "​", "ʯ", "ß"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 60))) for _ in range(800)] + ["a" * 3000, " " * 3000, "ab" * 900, "=" * 999, ""]
    e = bpe.encoder(tokenizer_path())
    want = [x.ids for x in library.encode_batch(texts, add_special_tokens=False)]
    assert [x.tolist() for x in e.encode_all(texts)] == want
    assert [e.decode(x) for x in want] == [library.decode(x, skip_special_tokens=False) for x in want]


def test_bpe_query(spark, odd_docs, no_docs, library):
    got = Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in tokenised(odd_docs).collect())

    def want(i, t):
        ids = library.encode(t or "", add_special_tokens=False).ids
        sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
        return i, len(ids), sha(",".join(map(str, ids))), sha(library.decode(ids, skip_special_tokens=False))

    assert got == Counter(want(r.doc_id, r.text) for r in odd_docs.collect())
    assert tokenised(no_docs).count() == 0


def test_audio_round_trip(spark, odd_docs, no_docs):
    x = odd_docs.select("doc_id", "text", audio.to_wav("text").alias("media")).withColumn("f", audio.audio_features("media")).collect()
    for r in x:
        raw = (r.text or "").encode()
        assert bytes(r.f.payload) == raw + bytes(-len(raw) % 64 if raw else 64)
        blocks, spans = audio.read_tensors(bytes(r.f.tensors))
        assert blocks.shape[1:] == (audio.BLOCK, audio.BANDS) and sum(s["n_frames"] for s in spans) == r.f.n_frames
    assert len({bytes(r.f.tensors) for r in x if r.doc_id == 4}) == 1
    assert no_docs.select(audio.to_wav("text")).count() == 0
    assert spark.createDataFrame([(b"junk",), (None,)], "m binary").select(audio.audio_features("m").alias("f")).where("f is null").count() == 2


def test_audio_parts():
    import numpy as np

    t = np.arange(12000) / 12000
    y = audio.resample(np.sin(2 * np.pi * 500 * t).astype(np.float32), 2, 3)
    spectrum = np.abs(np.fft.rfft(y[:8000]))
    assert len(y) == 8000 and abs(int(spectrum.argmax()) - 500) <= 1
    slow = np.convolve(np.repeat(np.sin(2 * np.pi * 500 * t), 2) * np.tile([1, 0], 12000), np.ravel(audio._filter(2, 3)[:, ::-1].T))[::3][:8000]
    assert np.allclose(y, slow, atol=1e-4)
    assert audio.segments(np.array([0, 3, 1.5, 1.5, 0, 3.0]), 2, 1) == [(1, 4), (5, 6)]


def test_language_model(spark):
    """The query against counters of tuples, on a whole table; and the same scores however the texts are cut into batches and parts."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", ngram.held_out("doc_id").alias("held_out"), (~ngram.held_out("doc_id")).alias("learn"), "text")
    one = {r.doc_id: r for r in QUERIES["op5_lm_score"](spark, SF).collect()}
    two = {r.doc_id: r for r in ngram.score(docs, "learn", batch_bytes=20_000, part_grams=5_000)[0].collect()}
    words = lambda s: re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), s or "")) + [None]
    rows = docs.collect()
    counts = Counter(w for r in rows if zlib.crc32(str(r.doc_id).encode()) % 7 != 2 for w in words(r.text))
    n, v = counts.total(), len(counts)
    want = ngram.plain_scores([r.text for r in rows], [r.learn for r in rows])
    for r, score in zip(rows, want, strict=True):
        ws, got = words(r.text), one[r.doc_id]
        assert got.train_tokens == n and got.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2)
        assert (got.n_tokens, got.n_known) == (len(ws), sum(counts[w] > 0 for w in ws)) == (two[r.doc_id].n_tokens, two[r.doc_id].n_known)
        base = sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in ws)
        assert got.base_score == pytest.approx(base) == two[r.doc_id].base_score
        assert got.score == pytest.approx(score) == two[r.doc_id].score
    held = [i for i, r in one.items() if r.held_out]
    assert len(one) == len(rows) and sum(one[i].score for i in held) > sum(one[i].base_score for i in held)


def test_language_model_is_a_distribution():
    """From each state the probabilities of all words and the unknown class sum to 1, singletons included."""
    import numpy as np

    hashes = ngram.WordHashes()
    flat = lambda texts: ngram.tokenised(pa.chunked_array([pa.array(texts)]), hashes)
    told = ngram.grams(*flat(["a b a b a c", "a b c", "b a"]))
    counted = [np.unique(k, return_counts=True) for k in told]
    vocabulary = [*(hashes[w] for w in (b"a", b"b", b"c", b"unknown")), ngram.END]
    for before in ([], [b"a"], [b"a", b"b"], [b"b", b"a"], [b"c", b"x"], [b"x", b"a"]):
        p = 0.0
        for w in vocabulary:
            asks = np.array([*(hashes[x] for x in before), w], np.uint64)
            start = np.zeros(1, np.int64)
            keys = [np.unique(np.concatenate([k, g])) for k, g in zip(told, ngram.grams(asks, start), strict=True)]
            counts = []
            for k, (own, n) in zip(keys, counted, strict=True):
                counts.append(np.zeros(len(k), np.int64))
                counts[-1][np.searchsorted(k, own)] = n
            way = ngram.Automaton(keys, counts, int(counted[0][1].sum()), len(counted[0][0]), (3.0, 2.0)).run(asks, start)[2]
            p += 10 ** way[-1]
        assert p == pytest.approx(1)


def test_language_model_edges(spark, odd_docs, no_docs):
    docs = odd_docs.withColumns({"learn": F.lit(True), "batch": F.lit("x"), "part": F.lit(1)})
    got = ngram.score(docs, "learn")[0]
    assert got.count() == odd_docs.count() and set(docs.columns) - {"text"} <= set(got.columns)
    same = {(r.n_tokens, r.score) for r in got.where("doc_id = 4").collect()}
    assert len(same) == 1 and {r.n_tokens for r in got.where("doc_id in (1, 2, 9)").collect()} == {1}
    assert ngram.score(docs.withColumn("learn", F.lit(None).cast("boolean")), "learn")[0].agg(F.sum("n_known")).first()[0] == 0
    assert ngram.score(no_docs.withColumn("learn", F.lit(True)), "learn")[0].count() == 0


def test_quality_measures(spark, odd_docs, no_docs):
    rows = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source")
    got = {r._id: r for r in linefreq.verdicts(linefreq.measured_once(rows), linefreq.Limits()).collect()}
    for r in rows.where("length(text) < 6000").collect():
        want = linefreq.plain_measures(r.text)
        assert {k: got[r.doc_id][k] for k in want} == want
    judged = linefreq.judge(odd_docs)
    assert judged.count() == odd_docs.count() and set(odd_docs.columns) <= set(judged.columns)
    assert judged.where("doc_id is null and n_words = 60").count() == 1 and linefreq.judge(no_docs).count() == 0


def test_frequent_lines_go_and_depleted_documents_are_rejected(spark):
    rng = random.Random(2)
    say = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    notice = "all rights reserved by the owner of this very page of ours 2024 " * 2
    rows = [(i, f"{say(30)}\n{notice.replace('2024', str(2000 + i))}\n{say(30)}", "h1") for i in range(80)]
    rows += [(100, notice + "\n" + notice + "\nshort rest", "h1"), (101, notice + "\n" + say(5) + "\n" + notice, "h2")]
    long = f"{say(40)}\n{say(40)}"
    rows += [(200 + i, long, "h1") for i in range(90)]  # copies do not make their lines frequent
    got = {r.doc_id: r for r in linefreq.judge(spark.createDataFrame(rows, "doc_id long, text string, source string"), linefreq.Limits(max_repeat_percent=100)).collect()}
    assert not got[100].kept and got[101].kept and all(got[i].kept and got[i].words_left == 60 for i in range(80)) and all(got[200 + i].kept for i in range(90))
    assert linefreq.line_hash(b" A  1 b") == linefreq.line_hash(b"a 2 B")


def test_many_shared_lines_are_boilerplate(spark):
    """Twenty navigation lines of a host go however many they are; copies and a host of its own for null do not count them up."""
    rng = random.Random(3)
    say = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    shared, notice, copy = [say(4) for _ in range(20)], say(10), "\n".join(say(30) for _ in range(4))
    rows = [(i, "\n".join([*shared, say(60), say(60)]), "h1") for i in range(120)]  # 80 of 200 words are shared
    rows += [(200 + i, f"{notice}\n{say(40)}", None) for i in range(70)] + [(300 + i, f"{notice}\n{say(40)}", "h2") for i in range(40)]
    rows += [(400 + i, copy, "h2") for i in range(90)] + [(500, "\n".join([*shared, say(25)]), "h1"), (501, "\n".join([*shared, say(25)]), "h2")]
    got = {r.doc_id: r for r in linefreq.judge(spark.createDataFrame(rows, "doc_id long, text string, source string"), linefreq.Limits(max_repeat_percent=100)).collect()}
    assert all(got[i].kept and got[i].words_left == 120 and len(got[i].removed) == 20 for i in range(120))
    assert all(got[200 + i].words_left == 40 for i in range(70)) and all(got[300 + i].words_left == 50 for i in range(40))
    assert all(got[400 + i].kept and got[400 + i].words_left == 120 for i in range(90))
    assert not got[500].kept and got[500].words_left == 25 and not got[500].base_failed and got[501].kept


def test_quality_query_by_brute_force(spark):
    """Every verdict on a whole table, with limits low enough that lines are removed and documents rejected."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source").union(spark.createDataFrame([(9000 + k, f"shared line of this host\none more {chr(97 + k)}", "src1") for k in range(9)] + [(9100, "shared line of this host\nyes", "src1")], "doc_id long, text string, source string"))
    limits = linefreq.Limits(min_words=1, max_docs=3, max_share=0.02, min_left=0.4, max_repeat_percent=100)
    normal = lambda line: " ".join(re.sub("[0-9]", "0", re.sub("[A-Z]", lambda m: m[0].lower(), line)).split(" "))
    words = lambda x: re.findall(r"[^\x20\x09-\x0D]+", x or "")
    rows = [(r.doc_id, r.source, [(" ".join(words(normal(x))), len(words(x))) for x in (r.text or "").split("\n") if words(x)], len(words(r.text))) for r in docs.collect()]
    hosts, holders = Counter(r[1] for r in rows), {}
    for _, host, lines, _ in rows:
        for x in {x for x, _ in lines}:
            holders.setdefault((host, x), set()).add(frozenset(y for y, _ in lines))
    gone = {k for k, sets in holders.items() if len(sets) > 3 and len(sets) > 0.02 * hosts[k[0]]}
    want = {}
    for i, host, lines, n in rows:
        lost = sum(w for x, w in lines if (host, x) in gone)
        want[i] = (n - lost, n >= 1 and not (lost and n - lost < 0.4 * n))
    got = {r._id: (r.words_left, r.kept) for r in linefreq.verdicts(linefreq.measured_once(docs), limits).collect()}
    assert got == want and not want[9100][1] and sum(not k for _, k in want.values()) > 5


def test_weighted_similarity_is_unbiased():
    import numpy as np

    rng = np.random.default_rng(0)
    keys = np.sort(rng.integers(1, 2**63, 200).astype(np.uint64))
    a = rng.integers(1, 12, 200)
    b = np.maximum(1, a + rng.integers(-3, 4, 200))
    true = np.minimum(a, b).sum() / np.maximum(a, b).sum()
    s = bagminhash.signatures([(keys, a), (keys, b)], 8192)
    assert abs((s[0] == s[1]).mean() - true) < 4 * math.sqrt(true * (1 - true) / 8192)
    assert bagminhash.similarity(bagminhash.numbered(keys, a).tobytes(), bagminhash.numbered(keys, b).tobytes()) == pytest.approx(true)


@pytest.mark.parametrize("leader_rounds", [0, 4])
def test_near_duplicates_against_all_pairs(spark, leader_rounds):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(300)]
    base, texts = [rng.choice(words) for _ in range(120)], {}
    for i in range(50):
        w = list(base)
        for _ in range(rng.choice([0, 1, 2, 3, 4, 6])):
            w[rng.randrange(len(w))] = rng.choice(words)
        texts[i] = " ".join(w)
    texts |= {100: None, 101: "", 102: "a b", 103: "A  b", 104: "x " * 50, 105: "x " * 60, 106: "x " * 300, 107: texts[3]}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r._id: r.class_id for r in bagminhash.near_duplicates(docs, bagminhash.Settings(leader_rounds=leader_rounds)).collect()}
    assert got == bagminhash.plain_classes(texts)


def test_near_duplicates_edges(spark, odd_docs, no_docs):
    got = bagminhash.near_duplicates(odd_docs).collect()
    by = {r._id: r.class_id for r in got}
    assert len(got) == odd_docs.count() and by[2] == by[9] == by[1] == 1 and by[3] == by[4] == 3 and by[7] == by[8] == 7
    assert bagminhash.near_duplicates(no_docs).count() == 0


def test_parity_bits_bound_the_difference():
    rng = np.random.default_rng(5)
    universe = rng.integers(0, 1 << 63, 400).astype(np.uint64)
    for _ in range(50):
        a, b = (np.sort(universe[rng.random(400) < share]) for share in rng.random(2))
        x, y = (bagminhash.parity(s.tobytes(), 16) for s in (a, b))
        differ = sum(int(v).bit_count() for v in (x ^ y).view(np.uint64))
        apart = len(np.setxor1d(a, b))
        assert differ <= apart and (differ - apart) % 2 == 0
    assert not bagminhash.parity(b"", 16).any()


def test_places_of_ngrams_come_from_their_sort():
    """No n-gram is looked up once more after it was sorted."""
    rng = np.random.default_rng(3)
    for n in (0, 1, 2000):
        tokens = rng.integers(0, 90, n).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        keys, places = ngram.placed(tokens)
        assert (keys == np.unique(tokens)).all() and (keys[places] == tokens).all()
