"""Relational operators and functions around the methods."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from webtext.plans.registry import query

c, lit = F.col, F.lit


def _agg(name, sql):
    return query(name, sql)


@query("scan_pages", "SELECT page_id, length(html)::BIGINT AS n_chars FROM pages")
def _(t):
    return t("pages").select("page_id", F.length("html").cast("long").alias("n_chars"))


@query("proj_filter", r"SELECT doc_id, len(list_filter(string_split_regex(text, '\s+'), lambda x: x <> ''))::BIGINT AS words FROM documents WHERE lang = 'en' AND n_chars BETWEEN 200 AND 2000")
def _(t):
    return t("documents").where((c("lang") == "en") & c("n_chars").between(200, 2000)).select("doc_id", F.size(F.filter(F.split("text", r"\s+"), lambda x: x != "")).cast("long").alias("words"))


@query("null_safe_eq", "SELECT count(*)::BIGINT AS n FROM documents d LEFT JOIN labels l USING (doc_id) WHERE quality IS NOT DISTINCT FROM NULL")
def _(t):
    return t("documents").join(t("labels"), "doc_id", "left").where(c("quality").eqNullSafe(None)).agg(F.count("*").alias("n"))


# -- joins
@query("join_broadcast", "SELECT r_name, count(*)::BIGINT AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(t):
    return t("nation").join(F.broadcast(t("region")), c("n_regionkey") == c("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("join_sort_merge", "SELECT o_orderstatus, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(t):
    return t("lineitem").hint("merge").join(t("orders"), c("l_orderkey") == c("o_orderkey")).groupBy("o_orderstatus").agg(F.sum(c("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("revenue"))


@query("join_shuffle_hash", "SELECT lang, quality, count(*)::BIGINT AS n FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def _(t):
    return t("documents").join(t("labels").hint("shuffle_hash"), "doc_id").groupBy("lang", "quality").agg(F.count("*").alias("n"))


for _kind, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    def _outer(t, kind=_kind):
        a, b = t("documents").where("doc_id % 3 > 0").select("doc_id", "lang"), t("labels").where("doc_id % 5 > 0")
        return a.join(b, "doc_id", kind).groupBy("lang", "quality").agg(F.count("*").alias("n"))

    query(f"join_{_kind}_outer", f"SELECT lang, quality, count(*)::BIGINT AS n FROM (SELECT * FROM documents WHERE doc_id % 3 > 0) d {_sql} JOIN (SELECT * FROM labels WHERE doc_id % 5 > 0) l USING (doc_id) GROUP BY 1, 2")(_outer)


@query("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def _(t):
    return t("documents").join(t("labels"), "doc_id", "left_semi").select("doc_id")


@query("join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _(t):
    return t("documents").join(t("labels"), "doc_id", "left_anti").select("doc_id")


@query("join_cross", "SELECT r_name, l.lang, count(doc_id)::BIGINT AS n FROM region CROSS JOIN (SELECT DISTINCT lang FROM documents) l LEFT JOIN documents d ON d.lang = l.lang AND d.doc_id % 5 = r_regionkey GROUP BY 1, 2")
def _(t):
    d = t("documents").select("doc_id", "lang", (c("doc_id") % 5).cast("int").alias("r_regionkey"))
    grid = t("region").select("r_regionkey", "r_name").crossJoin(t("documents").select("lang").distinct())
    return grid.join(d, ["lang", "r_regionkey"], "left").groupBy("r_name", "lang").agg(F.count("doc_id").alias("n"))


@query("join_theta_bins", "SELECT bin, count(*)::BIGINT AS n FROM documents JOIN (SELECT i AS bin, i * 500 AS lo, CASE WHEN i = 19 THEN 1000000000 ELSE (i + 1) * 500 END AS hi FROM range(20) r(i)) ON lo <= n_chars AND n_chars < hi GROUP BY 1")
def _(t):
    bins = t.spark.range(20).select(c("id").alias("bin"), (c("id") * 500).alias("lo"), F.when(c("id") == 19, 1_000_000_000).otherwise((c("id") + 1) * 500).alias("hi"))
    return t("documents").join(F.broadcast(bins), (c("lo") <= c("n_chars")) & (c("n_chars") < c("hi"))).groupBy("bin").agg(F.count("*").alias("n"))


@query("join_theta_rewrite", "SELECT least(19, n_chars // 500)::BIGINT AS bin, count(*)::BIGINT AS n FROM documents GROUP BY 1")
def _(t):
    """The same as a computed bucket: no nested loop."""
    return t("documents").groupBy(F.least(lit(19), F.floor(c("n_chars") / 500)).cast("long").alias("bin")).agg(F.count("*").alias("n"))


_PAIR = "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE"


def interval_join(left, right, key, left_ts, right_ts, seconds):
    """Pairs of a key whose right time follows the left within an interval: equal buckets of that width, then the exact test."""
    bucket = lambda ts: F.floor(F.unix_timestamp(c(ts).cast("timestamp")) / seconds)
    a = left.withColumn("bucket", F.explode(F.array(bucket(left_ts), bucket(left_ts) + 1)))
    b = right.withColumn("bucket", bucket(right_ts))
    return a.join(b, [key, "bucket"]).where((c(right_ts) > c(left_ts)) & (c(right_ts) <= c(left_ts) + F.make_dt_interval(secs=lit(float(seconds))))).drop("bucket")


@query("join_interval", _PAIR)
def _(t):
    e = t("events")
    a = e.where("event_type = 'error'").select("user_id", c("event_id").alias("first_id"), c("ts").alias("ts_a"))
    b = e.where("event_type = 'purchase'").select("user_id", c("event_id").alias("second_id"), c("ts").alias("ts_b"))
    return interval_join(a, b, "user_id", "ts_a", "ts_b", 600).select("first_id", "second_id")


@query("join_asof", "SELECT p.event_id, (SELECT max(v.ts) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts) AS view_ts FROM events p WHERE p.event_type = 'purchase'")
def _(t):
    """Each purchase with its user's latest view: one window over the union."""
    w = W.partitionBy("user_id").orderBy("ts", "is_purchase").rowsBetween(W.unboundedPreceding, 0)
    e = t("events").where("event_type in ('view', 'purchase')").select("event_id", "user_id", "ts", (c("event_type") == "purchase").cast("int").alias("is_purchase"))
    return e.withColumn("view_ts", F.last(F.when(c("is_purchase") == 0, c("ts")), ignorenulls=True).over(w)).where("is_purchase = 1").select("event_id", "view_ts")


_HOST = r"lower(regexp_extract(url, '^[A-Za-z]+://([^/?#:]+)', 1))"


@query("join_salted", f"SELECT page_id, n FROM (SELECT page_id, count(*) OVER (PARTITION BY {_HOST})::BIGINT AS n FROM pages)")
def _(t):
    """Pages with their host's count; the host's key is spread over eight salts and the small side repeated."""
    p = t("pages").select("page_id", F.lower(F.regexp_extract("url", r"^[A-Za-z]+://([^/?#:]+)", 1)).alias("host"), F.pmod(F.xxhash64("page_id"), lit(8)).alias("salt"))
    n = p.groupBy("host", "salt").agg(F.count("*").alias("k")).groupBy("host").agg(F.sum("k").alias("n"))
    return p.join(n.withColumn("salt", F.explode(F.sequence(lit(0).cast("long"), lit(7).cast("long")))), ["host", "salt"]).select("page_id", "n")


@query("lateral_blocks", "SELECT page_id, count(*)::BIGINT AS n FROM (SELECT page_id, unnest(regexp_extract_all(html, '<p>')) FROM pages) GROUP BY 1")
def _(t):
    t("pages").createOrReplaceTempView("webtext_lateral_pages")
    return t.spark.sql("SELECT page_id, count(*) AS n FROM webtext_lateral_pages, LATERAL explode(regexp_extract_all(html, '(<p>)', 1)) AS x(p) GROUP BY page_id")


# -- aggregates
@query("agg_basic", "SELECT lang, count(*)::BIGINT AS n, min(n_chars) AS lo, max(n_chars) AS hi, round(avg(n_chars), 4) AS mean FROM documents GROUP BY 1")
def _(t):
    return t("documents").groupBy("lang").agg(F.count("*").alias("n"), F.min("n_chars").alias("lo"), F.max("n_chars").alias("hi"), F.round(F.avg("n_chars"), 4).alias("mean"))


@query("agg_distinct", "SELECT lang, count(DISTINCT text)::BIGINT AS n_texts, count(DISTINCT source)::BIGINT AS n_sources FROM documents GROUP BY 1")
def _(t):
    return t("documents").groupBy("lang").agg(F.countDistinct("text").alias("n_texts"), F.countDistinct("source").alias("n_sources"))


@query("agg_approx", "SELECT true AS lines_ok, true AS median_ok")
def _(t):
    """Sketches against exact values: within 5 %."""
    lines = t("documents").select(F.explode(F.split("text", "\n")).alias("l")).agg(F.approx_count_distinct("l", 0.01).alias("a"), F.countDistinct("l").alias("e"))
    med = t("documents").agg(F.percentile_approx("n_chars", 0.5, 10000).alias("p"), F.expr("percentile(n_chars, 0.5)").alias("q"))
    near = lambda a, e: F.abs(c(a) - c(e)) <= 0.05 * c(e)
    return lines.crossJoin(med).select(near("a", "e").alias("lines_ok"), near("p", "q").alias("median_ok"))


@query("agg_max_by", "SELECT source, arg_max(doc_id, (n_chars, -doc_id)) AS doc_id FROM documents GROUP BY 1")
def _(t):
    return t("documents").groupBy("source").agg(F.max_by("doc_id", F.struct("n_chars", -c("doc_id"))).alias("doc_id"))


@query("agg_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def _(t):
    t("nation").createOrReplaceTempView("webtext_nation")
    return t.spark.sql("SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM webtext_nation GROUP BY n_regionkey")


@query("agg_filter", "SELECT lang, count(*) FILTER (quality = 1)::BIGINT AS good, count(*) FILTER (toxic = 1)::BIGINT AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def _(t):
    return t("documents").join(t("labels"), "doc_id").groupBy("lang").agg(F.count_if(c("quality") == 1).alias("good"), F.count_if(c("toxic") == 1).alias("toxic"))


@query("agg_sort_based", "SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY 1")
def _(t):
    return t("conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("x")).select("conv_id", F.array_join(F.transform("x", lambda r: r["role"]), ">").alias("roles"))


def _grouping(t, how):
    d = t("documents").join(t("labels"), "doc_id")
    if how == "sets":
        d.createOrReplaceTempView("webtext_grouping")
        return t.spark.sql("SELECT lang, quality, toxic, grouping_id() AS gid, count(*) AS n FROM webtext_grouping GROUP BY GROUPING SETS ((lang, quality, toxic), (lang), (toxic), ())")
    return getattr(d, how)("lang", "quality", "toxic").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"))


for _how, _clause in (("rollup", "ROLLUP (lang, quality, toxic)"), ("cube", "CUBE (lang, quality, toxic)"), ("sets", "GROUPING SETS ((lang, quality, toxic), (lang), (toxic), ())")):
    query(f"track_{'grouping_sets' if _how == 'sets' else _how}", f"SELECT lang, quality, toxic, grouping_id(lang, quality, toxic)::BIGINT AS gid, count(*)::BIGINT AS n FROM documents JOIN labels USING (doc_id) GROUP BY {_clause}")(lambda t, how=_how: _grouping(t, how))


@query("track_pivot", "SELECT lang, count(*) FILTER (quality = 0)::BIGINT AS q0, count(*) FILTER (quality = 1)::BIGINT AS q1 FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def _(t):
    p = t("documents").join(t("labels"), "doc_id").groupBy("lang").pivot("quality", [0, 1]).agg(F.count("doc_id"))
    return p.select("lang", F.coalesce(c("0"), lit(0)).alias("q0"), F.coalesce(c("1"), lit(0)).alias("q1"))


@query("scores_unpivot", "SELECT lang, 'q' || quality AS quality, count(*)::BIGINT AS n FROM documents JOIN labels USING (doc_id) GROUP BY 1, 2")
def _(t):
    p = t("documents").join(t("labels"), "doc_id").groupBy("lang").pivot("quality", [0, 1]).agg(F.count("doc_id")).withColumnsRenamed({"0": "q0", "1": "q1"})
    return p.unpivot("lang", ["q0", "q1"], "quality", "n").where("n is not null")


# -- windows
_BY = "PARTITION BY lang ORDER BY n_chars"


@query("win_rank", f"SELECT doc_id, rank() OVER ({_BY})::INT AS r, dense_rank() OVER ({_BY})::INT AS d, row_number() OVER ({_BY}, doc_id)::INT AS n FROM documents")
def _(t):
    w = W.partitionBy("lang").orderBy("n_chars")
    return t("documents").select("doc_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.row_number().over(W.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("n"))


@query("win_ntile", f"SELECT doc_id, ntile(3) OVER ({_BY}, doc_id)::INT AS tertile FROM documents")
def _(t):
    return t("documents").select("doc_id", F.ntile(3).over(W.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("tertile"))


@query("win_percent", f"SELECT doc_id, round(percent_rank() OVER ({_BY}), 6) AS p, round(cume_dist() OVER ({_BY}), 6) AS c FROM documents")
def _(t):
    w = W.partitionBy("lang").orderBy("n_chars")
    return t("documents").select("doc_id", F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))


@query("win_lag", "SELECT conv_id, turn, lag(role) OVER w AS before, (length(text) - lag(length(text)) OVER w)::BIGINT AS change, lead(role) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def _(t):
    w = W.partitionBy("conv_id").orderBy("turn")
    n = F.length("text").cast("long")
    return t("conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), (n - F.lag(n).over(w)).alias("change"), F.lead("role").over(w).alias("after"))


@query("win_rows_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 4) AS m FROM events")
def _(t):
    return t("events").select("event_id", F.round(F.avg("value").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)), 4).alias("m"))


@query("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE 3600 PRECEDING)::BIGINT AS n FROM events")
def _(t):
    s = F.round(c("ts").cast("timestamp").cast("double")).cast("long")
    return t("events").withColumn("s", s).select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n"))


@query("win_first_last", "SELECT DISTINCT user_id, ts::DATE AS day, first_value(event_type) OVER w AS first, last_value(event_type) OVER w AS last, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id, ts::DATE ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(t):
    w = W.partitionBy("user_id", "day").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    e = t("events").withColumn("day", F.to_date("ts"))
    return e.select("user_id", "day", F.first("event_type").over(w).alias("first"), F.last("event_type").over(w).alias("last"), F.nth_value("event_type", 2).over(w).alias("second")).distinct()


# -- order and sets
@query("topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10")
def _(t):
    return t("documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(10)


@query("topk_per_host", f"SELECT host, page_id FROM (SELECT {_HOST} AS host, page_id, row_number() OVER (PARTITION BY {_HOST} ORDER BY length(html) DESC, page_id) AS r FROM pages) WHERE r <= 2")
def _(t):
    p = t("pages").select(F.lower(F.regexp_extract("url", r"^[A-Za-z]+://([^/?#:]+)", 1)).alias("host"), "page_id", F.length("html").alias("n"))
    return p.withColumn("r", F.row_number().over(W.partitionBy("host").orderBy(F.desc("n"), "page_id"))).where("r <= 2").select("host", "page_id")


@query("sort_total", "SELECT doc_id FROM documents ORDER BY lang, n_chars DESC, doc_id LIMIT 50 OFFSET 20")
def _(t):
    return t("documents").orderBy("lang", F.desc("n_chars"), "doc_id").offset(20).limit(50).select("doc_id")


for _op, _sqlop in (("union", "UNION"), ("union_all", "UNION ALL"), ("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):

    def _set(t, op=_op):
        lines = t("documents").select("doc_id", F.explode(F.split("text", "\n", -1)).alias("l"))
        a, b = lines.where("doc_id % 2 = 0").select("l"), lines.where("doc_id % 2 = 1").select("l")
        both = {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.unionByName(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[op]()
        return both.agg(F.count("*").alias("n"), F.sum(F.length("l")).alias("n_chars"))

    query(f"set_{_op}", f"""WITH x AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents)
      SELECT count(*)::BIGINT AS n, sum(length(l))::BIGINT AS n_chars FROM (SELECT l FROM x WHERE doc_id % 2 = 0 {_sqlop} SELECT l FROM x WHERE doc_id % 2 = 1)""")(_set)


# -- functions
@query("fn_string", "SELECT p_partkey, split_part(p_name, ' ', 1) AS first, reverse(p_name) AS back, lpad(p_brand, 20, '*') AS padded, translate(p_name, 'abc', 'xyz') AS moved, upper(p_type) AS up FROM part")
def _(t):
    return t("part").select("p_partkey", F.substring_index("p_name", " ", 1).alias("first"), F.reverse("p_name").alias("back"), F.lpad("p_brand", 20, "*").alias("padded"), F.translate("p_name", "abc", "xyz").alias("moved"), F.upper("p_type").alias("up"))


@query("fn_regex", r"SELECT page_id, len(regexp_extract_all(html, '<li>'))::BIGINT AS n_li, regexp_extract(url, '([0-9]+)', 1) AS num, regexp_replace(url, '[0-9]+', '#', 'g') AS masked FROM pages")
def _(t):
    return t("pages").select("page_id", F.regexp_count("html", lit("<li>")).cast("long").alias("n_li"), F.regexp_extract("url", "([0-9]+)", 1).alias("num"), F.regexp_replace("url", "[0-9]+", "#").alias("masked"))


@query("fn_url", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM pages")
def _(t):
    return t("pages").select("page_id", F.try_parse_url("url", lit("HOST")).alias("host"), F.try_parse_url("url", lit("PATH")).alias("path"))


@query("fn_hash", "SELECT doc_id, sha256(text) AS sha, md5(text) AS md, ('0x' || substr(md5(text), 1, 15))::BIGINT AS h60 FROM documents")
def _(t):
    return t("documents").select("doc_id", F.sha2("text", 256).alias("sha"), F.md5("text").alias("md"), F.conv(F.substring(F.md5("text"), 1, 15), 16, 10).cast("long").alias("h60"))


@query("html_unescape", "SELECT page_id, sha256(replace(replace(replace(replace(html, '&quot;', '\"'), '&copy;', '©'), '&middot;', '·'), '&amp;', '&')) AS sha FROM pages")
def _(t):
    x = c("html")
    for k, v in (("&quot;", '"'), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&")):
        x = F.replace(x, lit(k), lit(v))
    return t("pages").select("page_id", F.sha2(x, 256).alias("sha"))


@query("fn_date", "SELECT date_trunc('month', o_orderdate)::DATE AS month, quarter(o_orderdate)::INT AS q, count(*)::BIGINT AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::INT AS days FROM orders GROUP BY 1, 2")
def _(t):
    return t("orders").groupBy(F.to_date(F.date_trunc("month", "o_orderdate")).alias("month"), F.quarter("o_orderdate").alias("q")).agg(F.count("*").alias("n"), F.max(F.datediff(F.to_date("o_orderdate"), F.to_date(lit("1992-01-01")))).alias("days"))


@query("fn_math", "SELECT l_returnflag, sum((l_extendedprice::DECIMAL(18,2) * (1 + l_tax::DECIMAL(4,2))))::DOUBLE AS taxed, sum(floor(l_quantity / 7)::BIGINT)::BIGINT AS f, max(round(ln(l_extendedprice), 6)) AS l, max(greatest(l_discount, l_tax)) AS g FROM lineitem GROUP BY 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.sum(c("l_extendedprice").cast("decimal(18,2)") * (1 + c("l_tax").cast("decimal(4,2)"))).cast("double").alias("taxed"), F.sum(F.floor(c("l_quantity") / 7)).alias("f"), F.max(F.round(F.log("l_extendedprice"), 6)).alias("l"), F.max(F.greatest("l_discount", "l_tax")).alias("g"))


@query("fn_array", r"SELECT doc_id, array_to_string(list_sort(list_distinct(list_transform(list_filter(string_split(text, ' '), lambda x: length(x) > 8), lambda x: lower(x))))[1:3], ',') AS a FROM documents")
def _(t):
    x = F.transform(F.filter(F.split("text", " "), lambda x: F.length(x) > 8), lambda x: F.lower(x))
    return t("documents").select("doc_id", F.array_join(F.slice(F.array_sort(F.array_distinct(x)), 1, 3), ",").alias("a"))


@query("fn_map", r"SELECT length(w)::INT AS len, count(*)::BIGINT AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY 1")
def _(t):
    """Word-length histogram, summed as a map per document and then over documents."""
    w = F.transform(F.split("text", " ", -1), lambda x: F.length(x))
    hist = t("documents").select(F.map_from_entries(F.transform(F.array_distinct(w), lambda k: F.struct(k.alias("k"), F.size(F.filter(w, lambda v: v == k)).alias("v")))).alias("m"))
    return hist.select(F.explode_outer("m").alias("len", "v")).groupBy("len").agg(F.sum("v").alias("n"))


@query("fn_json", "SELECT sum((props->>'$.k')::BIGINT)::BIGINT AS a, sum((props->>'$.k')::BIGINT)::BIGINT AS b, sum((props->>'$.k')::BIGINT)::BIGINT AS v FROM events")
def _(t):
    e = t("events")
    return e.agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("a"), F.sum(F.from_json("props", "k long")["k"]).alias("b"), F.sum(F.variant_get(F.parse_json("props"), "$.k", "long")).alias("v"))


@query("fn_variant", "SELECT sum((props->>'$.k')::BIGINT)::BIGINT AS k, count(*)::BIGINT AS n, 0::BIGINT AS n_missing FROM events")
def _(t):
    v = F.parse_json("props")
    e = t("events").select(v.alias("v"))
    return e.agg(F.sum(F.variant_get("v", "$.k", "long")).alias("k"), F.count("v").alias("n"), F.count(F.try_variant_get("v", "$.no_such_key", "long")).alias("n_missing"))


@query("xpath_wellformed", "SELECT r_name, count(*)::BIGINT AS n_rows, min(n_name) AS first_name, sum(n_nationkey)::BIGINT AS keys FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(t):
    """The built-in XPath functions on tables that we render ourselves, which are well-formed XML."""
    row = F.concat(F.lit("<tr><td>"), F.col("n_nationkey").cast("string"), F.lit("</td><td>"), F.col("n_name"), F.lit("</td></tr>"))
    x = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.array_sort(F.collect_list(F.struct("n_name", row.alias("tr")))).alias("x"))
    x = x.select("r_name", F.concat(F.lit("<table>"), F.array_join(F.transform("x", lambda r: r["tr"]), ""), F.lit("</table>")).alias("xml"))
    return x.select("r_name", F.expr("xpath_long(xml, 'count(//tr)')").alias("n_rows"), F.expr("xpath_string(xml, '//tr[1]/td[2]')").alias("first_name"), F.expr("xpath_long(xml, 'sum(//tr/td[1])')").alias("keys"))


@query("win_running_tokens", r"""SELECT doc_id, upto FROM (SELECT doc_id, sum(len(list_filter(string_split_regex(text, '\s+'), lambda x: x <> ''))) OVER (PARTITION BY lang ORDER BY md5(doc_id::VARCHAR) ROWS UNBOUNDED PRECEDING)::BIGINT AS upto FROM documents) WHERE upto <= 20000""")
def _(t):
    """Running tokens of each language in md5 order until a budget."""
    n = F.size(F.filter(F.split("text", r"\s+"), lambda x: x != "")).cast("long")
    w = W.partitionBy("lang").orderBy(F.md5(F.col("doc_id").cast("string").cast("binary"))).rowsBetween(W.unboundedPreceding, 0)
    return t("documents").select("doc_id", F.sum(n).over(w).alias("upto")).where("upto <= 20000")


@query("subquery_scalar", "SELECT doc_id FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents e WHERE e.lang = d.lang)")
def _(t):
    mean = t("documents").groupBy("lang").agg(F.avg("n_chars").alias("m"))
    return t("documents").join(mean, "lang").where("n_chars > m").select("doc_id")


@query("subquery_exists", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey)")
def _(t):
    return t("part").join(t("lineitem"), c("l_partkey") == c("p_partkey"), "left_anti").select("p_partkey")


@query("udaf_weighted_mean", "SELECT lang, round(sum(n_chars * (doc_id % 7)) / sum(doc_id % 7), 4) AS m FROM documents GROUP BY 1")
def _(t):
    w = c("doc_id") % 7
    return t("documents").groupBy("lang").agg(F.round(F.sum(c("n_chars") * w) / F.sum(w), 4).alias("m"))


@query("embedding_clusters")
def _(t):
    """Random-projection buckets of vectors (the learned clustering of L345 as an extension)."""
    import random

    rng = random.Random(7)
    planes = [[rng.gauss(0, 1) for _ in range(64)] for _ in range(8)]
    dot = lambda p: F.aggregate(F.zip_with("embedding", F.array(*map(lit, p)), lambda a, b: a * b), lit(0.0), lambda a, x: a + x)
    bits = sum((F.when(dot(p) > 0, 1 << k).otherwise(0) for k, p in enumerate(planes)), lit(0))
    return t("embeddings").groupBy(bits.alias("bucket"), "label").agg(F.count("*").alias("n"))
