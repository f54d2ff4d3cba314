"""Chat windows, URL rules, sharding, mixing and archives; edge cases and invariants."""

import os
from collections import Counter, defaultdict

import duckdb
import pytest
from pyspark.sql import functions as F

from webtext.llm import chat, graph, mixing, sharding, urlrules, warc
from webtext.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    df = QUERIES[name](spark, SF)
    cur = con.execute(ORACLES[name])
    names = [d[0] for d in cur.description]
    assert sorted(names) == sorted(df.columns)
    assert sorted(repr([r[n] for n in names]) for r in df.collect()) == sorted(map(lambda x: repr(list(x)), cur.fetchall()))


@pytest.mark.parametrize("name", ["op1_chat", "op7_sharding", "op8_mixing"])
def test_native(spark, name):
    plan = QUERIES[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "CartesianProduct" not in plan


def _greedy(turns, budget, history):
    """n_own, n_context and n_tokens of each window, turn by turn."""
    cost = lambda text: -(-len(text) // 4) + 4
    system = next((k for k, (role, _) in enumerate(turns) if role == "system"), None)
    lead = 0 if system is None else cost(turns[system][1][: 4 * (budget // 2 - 4)])
    room, at, parts, system_at = budget - history - lead, 0, [], None
    for k, (_, text) in enumerate(turns):
        size = 4 * (room - 4)
        system_at = at if k == system else system_at
        for i in range(0, max(len(text), 1), size):
            parts.append((at, cost(text[i : i + size]), k == system))
            at += parts[-1][1]
    begins = []
    for at, tokens, _ in parts:
        b = begins[-1] if begins else 0
        led = system_at is not None and b > system_at
        if not begins or at // (chat.SEGMENT * room) != b // (chat.SEGMENT * room) or at + tokens > b + budget - (history if b else 0) - (lead if led else 0):
            begins.append(at)
    out = []
    for b, e in zip(begins, [*begins[1:], float("inf")]):
        own, context = [t for a, t, _ in parts if b <= a < e], [t for a, t, s in parts if b - history <= a < b and not s]
        context += [lead] if system_at is not None and b > system_at else []
        out.append((len(own), len(context), sum(own) + sum(context)))
    return out


def test_chat_windows(spark):
    rows = [(1, 0, "system", "be kind")] + [(1, k, "user" if k % 2 else "assistant", f"turn {k} " + "x" * (k * 7 % 400)) for k in range(1, 700)]
    rows += [(2, 0, None, None), (2, 0, None, None), (2, 1, "assistant", "a" * 9000), (None, 1, "assistant", "<|im_end|>\n<|im_start|>user\n\\<\\|"), (3, None, "a\n<%", "t"), (3, 1, "system", "late"), (3, 2, "user", "u")]
    rows += [(4, 0, "user", "\U0001f600" * 3000), (4, 1, "system", "<|" * 2000), (4, 2, "assistant", "\\" * 5001), (4, 3, "user", "")] + [(4, k, "assistant", "") for k in range(4, 900)]
    t = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumns({"start": F.lit(1), "window": F.lit("x")})
    w = chat.read_back(chat.windows(t, 512, 64)).orderBy("conv_id", "window").collect()
    said, losses = defaultdict(list), defaultdict(list)
    for r in w:
        for x in r.turns:
            if x.more:
                said[r.conv_id][-1] = (x.role, said[r.conv_id][-1][1] + x.text)
            else:
                said[r.conv_id].append((x.role, x.text))
        losses[r.conv_id] += r.losses
        assert r.n_tokens <= 512
    for conv in {r[0] for r in rows}:
        own = sorted((r for r in rows if r[0] == conv), key=lambda r: (r[1] is not None, r[1] or 0, r[2] or "", r[3] or ""))
        assert said[conv] == [(r[2] or "", r[3] or "") for r in own]
        assert "".join(losses[conv]) == "".join(r[3] or "" for r in own if r[2] == "assistant")
        assert [(r.n_own, r.n_context, r.n_tokens) for r in w if r.conv_id == conv] == _greedy([(r[2] or "", r[3] or "") for r in own], 512, 64)
    one = [r for r in w if r.conv_id == 1]
    assert len(one) > 50 and all(r.formatted.startswith("<|im_start|>system\nbe kind<|im_end|>") for r in one)
    assert any(r.n_context > 1 for r in one) and max(r.window for r in one) > chat.STRIDE and sum(r.n_tokens for r in one) > 0.8 * 512 * len(one)
    assert chat.windows(t.limit(0)).count() == 0


def test_url_rules(spark):
    rules = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "bad.net", "/")]
    pages = [
        (1, "HTTPS://WWW.Example.ORG/es/x?q#f", ""), (2, "http://example.org/de", ""), (3, "http://good.net/a", '<LINK href="http://bad.net/b" rel=canonical>'), (4, "http://bad.net/b", None), (5, "http://c.net/1", '<meta http-equiv="refresh" content="0; url=/2">'),
        (6, "http://c.net/2.html", '<link rel="canonical" href="http://good.net/a/">'), (7, "http://d.net/x", '<link rel="canonical" href="http://z.org/x">'), (8, "http://e.net/", '<link rel=canonical href=http://z.org/x>'), (9, "http://f.net/", '<link rel="canonical" href="http://d.net/x">'),
        (10, None, None), (11, "no scheme", "<p>"), (12, "http://notexample.org.evil.net/es/", ""), (13, "http://z.org/x", ""), (4, "http://bad.net/b", None),
    ]
    df = spark.createDataFrame([(*p, "h") for p in pages], "page_id long, url string, html string, host string")
    got = {r.page_id: r for r in urlrules.judge(df, rules, spellings=True).collect()}
    assert (got[1].host, got[1].path, got[1].rule, got[1].verdict) == ("www.example.org", "/es/x", "example.org/es/", "block")
    assert [got[i].verdict for i in (2, 3, 4, 5, 6, 7, 8, 9, 12, 13)] == ["allow", "block", "block", "block", "block", "allow", "allow", "allow", "allow", "allow"]
    assert (got[10].host, got[10].path, got[10].rule) == ("", "", None) and got[11].verdict == "allow" and got[12].rule is None
    assert urlrules.judge(df, rules).count() == len(pages) and urlrules.judge(df.limit(0), rules).count() == 0
    moved = spark.createDataFrame([("http://notexample.org.evil.net/es/", "http://bad.net/b")], "from_url string, to_url string")
    assert {r.page_id: r.verdict for r in urlrules.judge(df, rules, moved).collect()}[12] == "block"
    # edges alone: 3 names 4 as it is written there, 5 and 6 name pages that are written otherwise
    edges = {r.page_id: r.verdict for r in urlrules.judge(df, rules).collect()}
    assert [edges[i] for i in (2, 3, 4, 5, 6, 7, 8, 9)] == ["allow", "block", "block", "allow", "allow", "allow", "allow", "allow"]


def test_components_of_chain_and_star(spark):
    h = lambda x: F.xxhash64(F.lit("c"), x)
    chain = spark.range(300).select(h(F.col("id")).alias("u"), h(F.col("id") + 1).alias("v"))
    star = spark.range(1000, 1500).select(h(F.lit(999999)).alias("u"), h(F.col("id")).alias("v"))
    got = graph.components(chain.unionByName(star).unionByName(chain)).groupBy("comp").agg(F.count("*").alias("n"), F.min("node").alias("m")).collect()
    assert sorted(r.n for r in got) == [301, 501] and all(r.comp == r.m for r in got)


def test_components_by_rounds_and_in_one_task_agree(spark, monkeypatch):
    h = lambda x: F.xxhash64(F.lit("r"), x)
    edges = spark.range(400).select(h(F.col("id") * 7 % 150).alias("u"), h(F.col("id") * 11 % 400).alias("v"))
    found = []
    for most in (50_000, 20, 0):
        monkeypatch.setattr(graph, "ONE_TASK_EDGES", most)
        found.append({r.node: r.comp for r in graph.components(edges).collect()})
    assert found[0] == found[1] == found[2] and len(found[0]) > 300


def test_shuffle_files_of_what_is_cut_off_go_on_demand(spark):
    """They stayed until the driver's JVM happened to collect its garbage: 536 MB of the pipeline on check_h."""
    import time

    from webtext.llm.common import cut, freed

    manager = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    made = lambda: {f for f in str(manager.getAllFiles().mkString(" ")).split() if "/shuffle_" in f}
    freed(spark)
    old = made()
    left = cut(spark.range(2000).withColumn("k", F.col("id") % 50).groupBy("k").count())
    own = made() - old
    cut(left.groupBy("count").count())  # Spark may still hold the plan it ran last
    end = time.time() + 30
    while own & made() and time.time() < end:
        freed(spark)
        time.sleep(0.5)
    assert own and not own & made() and left.count() == 50


def test_sharding(spark, odd_docs, no_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    for limit in (4_000, 40_000, 1 << 30):
        rows = sharding.assign(docs, limit).collect()
        sizes = Counter()
        for r in rows:
            sizes[r.shard] += r.n_bytes
        assert len(rows) == docs.count() and all(sizes[r.shard] == r.shard_bytes for r in rows)
        assert all(r.fits or r.shard_rows == 1 for r in rows if "+" in r.shard or not r.fits)
        prefixes = sorted(s for s in sizes if "+" not in s)
        assert all(not b.startswith(a) for a, b in zip(prefixes, prefixes[1:]))  # no shard lies within another
        for s in prefixes:  # only oversized buckets were split
            assert not s or sum(n for x, n in sizes.items() if x.startswith(s[:-1])) > limit
    repeated = spark.createDataFrame([(1, "x" * 100)] * 50 + [(None, "y"), (2, None)], "doc_id long, text string")
    got = sharding.assign(repeated, 1000).collect()
    assert len(got) == 52 and all(r.fits for r in got) and len({r.shard for r in got if r.doc_id == 1}) == 5
    assert sharding.assign(odd_docs, 1000).count() == odd_docs.count() and sharding.assign(no_docs, 1000).count() == 0


def _filled(sizes):
    """Targets by handing on the excess again and again."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    full, left = {}, 1.5 * sum(sizes.values())
    while True:
        rest = [s for s in order if s not in full]
        share = {s: (left - sum(full.values())) * weight[s] / sum(weight[x] for x in rest) for s in rest}
        over = [s for s in rest if share[s] > 2 * sizes[s]]
        if not over:
            return full | share
        full |= {s: 2.0 * sizes[s] for s in over}


def test_written_shards_fit_for_repeated_ids(spark, tmp_path):
    docs = spark.createDataFrame([(7, "x" * 400, k) for k in range(20)] + [(i, "y" * 90, 0) for i in range(100, 160)], "doc_id long, text string, h int")
    path = str(tmp_path / "shards")
    sharding.write_shards(docs, path, 1000)
    back = spark.read.parquet(path)
    assert back.count() == 80 and set(docs.columns) <= set(back.columns) and back.select("doc_id", "h").distinct().count() == 80
    assert back.groupBy("shard").agg(F.sum(F.length("text")).alias("n")).where("n > 1000").count() == 0


def test_mixing(spark, odd_docs, no_docs):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source", "text")
    docs = docs.withColumn("source", F.when(F.col("source") == "src3", None).otherwise(F.col("source")))
    out, slots = mixing.mix(docs)
    rows = out.collect()
    size, taken, target = Counter(), Counter(), {}
    for r in rows:
        size[r.source] += r.size
        taken[r.source] += r.taken
        target[r.source] = r.target
        assert 0 <= r.taken <= 2 * r.size
    want = _filled(size)
    assert len(rows) == docs.count() and all(target[s] == pytest.approx(want[s]) and abs(taken[s] - want[s]) <= 130 for s in size)
    assert sorted(map(str, mixing.mix(docs.repartition(7))[0].collect())) == sorted(map(str, rows))
    n = mixing.shard_counts(slots).agg(F.sum("n")).first()[0]
    dealt = mixing.mixed_blocks(docs)
    assert n == slots.count() == dealt.count() == dealt.select("shard", "place").distinct().count()
    words = dealt.agg(F.sum(F.size(F.split("words", " ")))).first()[0]
    assert words == sum(taken.values())
    odd = mixing.mix(odd_docs)[0]
    assert odd.count() == odd_docs.count() and odd.where("taken > 2 * size").count() == 0 and mixing.mix(no_docs)[0].count() == 0


def test_permutation(spark):
    for n in (1, 2, 3, 5, 7, 13, 97, 290, 1000, 4097):
        x = mixing.permuted(spark.range(n), "p", F.col("id"), F.lit(n), F.lit("s"))
        got = [r.p for r in x.orderBy("id").collect()]
        assert sorted(got) == list(range(n)) and (n < 50 or got != list(range(n)))
    n = (1 << 45) + 12345
    far = mixing.permuted(spark.range(n - 20_000, n), "p", F.col("id"), F.lit(n), F.lit("s")).agg(F.count_distinct("p").alias("d"), F.min("p").alias("a"), F.max("p").alias("b"), F.avg("p").alias("m")).first()
    assert far.d == 20_000 and 0 <= far.a and far.b < n and abs(far.m / n - 0.5) < 0.02


def test_shards_are_multinomial_draws(spark):
    """The counts of a source over the shards scatter as independent draws do: neither evenly dealt nor clumped."""
    sources = spark.createDataFrame([("a", 1, 64 * 60_000, 64 * 60_000.0), ("b", 2, 64 * 30_000, 64 * 45_000.0)], "source string, k int, source_size long, target double")
    n = mixing.shard_counts(mixing.slots(sources, 64, 500)).collect()
    for k, total in ((1, 60_000), (2, 45_000)):
        own = [r.n for r in n if r.k == k]
        assert sum(own) == total and len(own) == 210
        chi = sum((x - total / 210) ** 2 for x in own) / (total / 210)
        assert 209 - 4 * (2 * 209) ** 0.5 < chi < 209 + 4 * (2 * 209) ** 0.5


def test_taken_words_by_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source", "text")
    rows, sources = mixing.streams(mixing.sized(docs))
    out, slots = mixing.mix(docs)
    placed, want = defaultdict(list), Counter()
    for r in rows.collect():
        placed[r.k].append((r.begin, r.begin + r.size, r.doc_id))
    for k, own in placed.items():
        own.sort()
        assert own[0][0] == 0 and all(x[1] == y[0] for x, y in zip(own, own[1:], strict=False))
    for s in slots.collect():
        a, b = s.block_no * 64, s.block_no * 64 + s.words
        for x, y, doc in placed[s.k]:
            want[doc] += max(0, min(y, b) - max(x, a))
    assert {r.doc_id: r.taken for r in out.collect()} == {r.doc_id: want[r.doc_id] for r in out.collect()}



def test_archives(spark, tmp_path):
    big = "é" * 50_000
    pages = [(1, "http://a/ b", big), (2, "http://a/2", big), (3, None, None), (4, "u", ""), (5, "u5", "short"), (6, "u6", "short"), (7, "u7", "WARC/1.1\r\n\r\n0\r\n\r\n" * 20), (8, "u8", "x" * 100), (9, "u9", "x" * 100), (1, "http://a/ b", big), (None, "n", "x" * 100)]
    df = spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, payload int")
    path = str(tmp_path / "archives")
    warc.write_archives(df, path, chunk_bytes=1000, segment_bytes=3000, file_bytes=42_000)
    assert warc.read_segments(spark, path).where("segment is not null").count() > 20
    rows = warc.read_payloads(spark, path).collect()
    assert len(rows) == len(pages) and all(r.status == "ok" for r in rows)
    by = {r.page_id: r for r in rows}
    assert [by[i].record_type for i in (1, 2, 5, 6, 8, 9)] == ["response", "revisit", "response", "response", "response", "revisit"]
    assert by[2].refers_to == 1 and by[9].refers_to == 8 and by[2].payload_bytes == 100_000 and by[2].payload_digest == by[1].payload_digest
    assert bytes(by[7].payload).decode() == pages[6][2] and bytes(by[1].payload).decode() == big
    empty = str(tmp_path / "empty")
    warc.write_archives(df.limit(0), empty)
    assert warc.read_payloads(spark, empty).count() == 0


def test_broken_archives_are_reported(spark, tmp_path):
    records = list(warc.records_of(1, "u", b"y" * 9000, None, 1000, 3000))
    folder = tmp_path / "broken"
    folder.mkdir()
    (folder / "a.warc").write_bytes(b"".join(r + b"\r\n\r\n" for r in [records[2], records[0]]))  # out of order, one missing
    assert [r.status for r in warc.read_payloads(spark, str(folder)).collect()] == ["incomplete"]
    assert warc.unchunk(b"3\r\nabc\r\n0\r\n\r\n") == (b"abc", True) and warc.unchunk(b"5\r\nabc")[1] is False
