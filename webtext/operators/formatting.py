"""Content lists and their renderings over tables of pages (L107-L129)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from webtext.functions.content import UNIT, units
from webtext.operators.passes import row_pass

UNITS = (
    "array<struct<seq:int,type:string,level:int,text:string,lang:string,rows:array<array<string>>,html:string,"
    "items:array<struct<depth:int,ordered:boolean,text:string>>,url:string,alt:string,display:boolean>>"
)


def content_list(df: DataFrame, id_col: str = "page_id", html_col: str = "main_html") -> DataFrame:
    """id and units of each content subtree."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(key, main):
        return key, [{n: u[n] for n in UNIT} for u in units(main)]

    return row_pass(df.select(id_col, html_col), run, f"{id_col} {kind}, units {UNITS}")


#: Fields each type needs (L115).
REQUIRED = {
    "title": ("level", "text"), "paragraph": ("text",), "inline_formula": ("text",), "display_formula": ("text",), "inline_code": ("text",), "code": ("text",), "list": ("items",), "image": ("url",), "video": ("url",), "audio": ("url",),
}


def violations(df: DataFrame, id_col: str = "page_id") -> DataFrame:
    """Units that lack a field their type needs, or whose type is unknown."""
    u = F.col("u")
    bad = ~u["type"].isin(*REQUIRED, "table")
    for t, fields in REQUIRED.items():
        for f in fields:
            bad = bad | ((u["type"] == t) & u[f].isNull())
    bad = bad | ((u["type"] == "table") & u["rows"].isNull() & u["html"].isNull())
    return df.select(id_col, F.explode("units").alias("u")).where(bad).select(id_col, "u.seq", "u.type")


def select_types(units: Column | str, keep: tuple[str, ...] | None = None, drop: tuple[str, ...] = ()) -> Column:
    """Units of the kept types, without the dropped ones (L126)."""
    return F.filter(units, lambda u: (u["type"].isin(*keep) if keep else F.lit(True)) & (~u["type"].isin(*drop) if drop else F.lit(True)))


def count_type(units: Column | str, *types: str) -> Column:
    return F.size(F.filter(units, lambda u: u["type"].isin(*types)))


def _fence(text: Column, least: int) -> Column:
    runs = F.transform(F.regexp_extract_all(text, F.lit("(`+)"), F.lit(1)), lambda r: F.length(r))
    return F.repeat(F.lit("`"), F.greatest(F.lit(least), F.coalesce(F.array_max(runs), F.lit(0)) + 1))


def _cell(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("|"), F.lit("\\|")), F.lit("\n"), F.lit(" "))


def _embedded(u: Column) -> Column:
    """Whether a formula stands within a list item or table cell, whose text has it already."""
    return F.coalesce(u["alt"] == "embedded", F.lit(False))


def unit_markdown(u: Column) -> Column:
    """Markdown of one unit in Catalyst expressions; null for spans that are embedded in another unit."""
    wide = F.array_max(F.transform(u["rows"], lambda r: F.size(r)))
    line = lambda r: F.concat(F.lit("| "), F.array_join(F.concat(F.transform(r, _cell), F.array_repeat(F.lit(""), wide - F.size(r))), " | "), F.lit(" |"))
    rule = F.concat(F.lit("|"), F.repeat(F.lit(" --- |"), wide))
    table = F.array_join(F.concat(F.array(line(u["rows"][0]), rule), F.transform(F.slice(u["rows"], 2, 1 << 30), line)), "\n")
    item = lambda i: F.concat(F.repeat(F.lit("  "), i["depth"]), F.when(i["ordered"], F.lit("1. ")).otherwise(F.lit("- ")), i["text"])
    fence = _fence(u["text"], 3)
    return (
        F.when(u["type"] == "title", F.concat(F.repeat(F.lit("#"), u["level"]), F.lit(" "), u["text"]))
        .when(u["type"] == "paragraph", u["text"])
        .when((u["type"] == "display_formula") & ~_embedded(u), F.concat(F.lit("$$\n"), u["text"], F.lit("\n$$")))
        .when(u["type"] == "code", F.concat(fence, F.coalesce(u["lang"], F.lit("")), F.lit("\n"), u["text"], F.lit("\n"), fence))
        .when(u["type"] == "table", F.when(u["rows"].isNotNull(), table).otherwise(u["html"]))
        .when(u["type"] == "list", F.array_join(F.transform(u["items"], item), "\n"))
        .when(u["type"] == "image", F.concat(F.lit("!["), F.coalesce(u["alt"], F.lit("")), F.lit("]("), F.coalesce(u["url"], F.lit("")), F.lit(")")))
        .when(u["type"].isin("video", "audio"), F.concat(F.lit("["), F.when(F.coalesce(u["alt"], F.lit("")) != "", u["alt"]).otherwise(u["type"]), F.lit("]("), F.coalesce(u["url"], F.lit("")), F.lit(")")))
    )


def render(units: Column | str, target: str = "md") -> Column:
    """md, text, html or jsonl of a content list, as a native expression."""
    units = F.col(units) if isinstance(units, str) else units
    if target == "md":
        return F.array_join(F.transform(units, unit_markdown), "\n\n")
    if target == "jsonl":
        return F.array_join(F.transform(units, lambda u: F.to_json(u)), "\n")
    shown = F.filter(units, lambda u: ~u["type"].isin("inline_formula", "inline_code") & ~((u["type"] == "display_formula") & _embedded(u)))
    if target == "text":
        return F.array_join(F.transform(shown, lambda u: F.coalesce(u["text"], F.array_join(F.transform(u["items"], lambda i: i["text"]), "\n"), F.array_join(F.transform(u["rows"], lambda r: F.array_join(r, " ")), "\n"), F.regexp_replace(u["html"], "<[^>]*>", " "))), "\n")
    esc = lambda c: F.replace(F.replace(F.replace(c, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))
    one = lambda u: (
        F.when(u["type"] == "title", F.concat(F.lit("<h"), u["level"].cast("string"), F.lit(">"), esc(u["text"]), F.lit("</h"), u["level"].cast("string"), F.lit(">")))
        .when(u["type"] == "code", F.concat(F.lit("<pre><code>"), esc(u["text"]), F.lit("</code></pre>")))
        .when(u["type"] == "list", F.concat(F.lit("<ul>"), F.array_join(F.transform(u["items"], lambda i: F.concat(F.lit("<li>"), esc(i["text"]), F.lit("</li>"))), ""), F.lit("</ul>")))
        .when((u["type"] == "table") & u["rows"].isNotNull(), F.concat(F.lit("<table>"), F.array_join(F.transform(u["rows"], lambda r: F.concat(F.lit("<tr><td>"), F.array_join(F.transform(r, esc), "</td><td>"), F.lit("</td></tr>"))), ""), F.lit("</table>")))
        .when(u["type"] == "table", u["html"])
        .when(u["text"].isNotNull(), F.concat(F.lit("<p>"), esc(u["text"]), F.lit("</p>")))
    )
    return F.array_join(F.transform(shown, one), "")


def _blank(**given: Column) -> Column:
    kinds = {"seq": "int", "type": "string", "level": "int", "text": "string", "lang": "string", "rows": "array<array<string>>", "html": "string", "items": "array<struct<depth:int,ordered:boolean,text:string>>", "url": "string", "alt": "string", "display": "boolean"}
    return F.struct(*[(given[n] if n in given else F.lit(None)).cast(k).alias(n) for n, k in kinds.items()])


def from_turns(turns: DataFrame) -> DataFrame:
    """Conversations as content lists: conv_id, units (one paragraph a turn)."""
    x = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("t"))
    return x.select("conv_id", F.transform("t", lambda t, k: _blank(seq=k, type=F.lit("paragraph"), text=F.concat(t["role"], F.lit(": "), t["text"]))).alias("units"))


def from_table(df: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """A relational table as content lists: key, units (one simple table for each key, a header row first)."""
    row = F.array(*[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in columns])
    x = df.groupBy(key).agg(F.array_sort(F.collect_list(row)).alias("body"))
    return x.select(key, F.array(_blank(seq=F.lit(0), type=F.lit("table"), rows=F.concat(F.array(F.array(*map(F.lit, columns))), "body"))).alias("units"))
