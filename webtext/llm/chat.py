"""Chat formatting in budgeted windows, in DataFrame operations only.

Every turn gets a length in tokens; prefix sums give its start within the conversation. A window takes the longest span of
whole turns that fits: the next one begins at the first turn whose end exceeds the window's begin plus its room, which is the
budget less `history` (none in the first window) and less the repeated system turn (none until that turn has been). Only a
turn above budget - system - history, which would fit no window, is split, into parts of just that many tokens; a part that
goes on is marked by `<more` behind its role. So no window exceeds the budget. Whole turns that lie in the last `history` tokens
before a window are repeated at its head. The first system turn leads every later window, with its first budget / 2 tokens if it
is longer (the turn itself stays whole, in parts). Both are context: the loss mask covers assistant texts of a window's own
turns, so each is learned once.

No conversation has to meet in one task: turns are summed in chunks of 256 turn numbers, chunks over a conversation, and the
spans are chosen in segments of SEGMENT times the room, at whose ends a window also ends. A segment holds a bounded number of
tokens, hence of turns (at least four tokens each) and of characters. Windows are numbered in order, with gaps between segments.

The text is `<|im_start|>role\\ntext<|im_end|>\\n` per turn; inside texts a backslash is doubled and `<|` becomes
`<\\|`, so control strings cannot be forged and everything can be read back.

Edge cases: null text or role counts as empty; null conv_id is a conversation; null turns come first; rows with equal turns are
ordered by role and text; repeated rows are turns of their own; an empty table gives no windows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

CHUNK = 256
#: Windows are chosen within spans of so many rooms; two successive windows hold more than one room, so a span has at most 2 * SEGMENT + 3.
SEGMENT = 16
STRIDE = 64
OPEN, CLOSE, MORE = "<|im_start|>", "<|im_end|>\n", "<more"


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def escape_role(role: Column) -> Column:
    for c, code in (("%", "%25"), ("\n", "%0A"), ("<", "%3C")):
        role = F.replace(role, F.lit(c), F.lit(code))
    return role


def unescape_role(role: Column) -> Column:
    for code, c in (("%0A", "\n"), ("%3C", "<"), ("%25", "%")):
        role = F.replace(role, F.lit(code), F.lit(c))
    return role


def turn_tokens(text: Column) -> Column:
    """About four characters a token, and four tokens of framing."""
    return (F.ceil(F.length(text) / 4) + 4).cast("long")


def _placed(turns: DataFrame, budget: int, history: int) -> DataFrame:
    """Parts of turns with their start, the room of their conversation, its leading system text and where that turn starts."""
    # One struct as key: equal also where its fields are null, so that joins and windows share one shuffle of the texts.
    key = F.struct("conv_id", F.floor(F.col("turn") / CHUNK).alias("chunk")).alias("key")
    t = turns.select(key, "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    before = W.Window.partitionBy("key.conv_id").orderBy("key.chunk")
    ahead, whole = before.rowsBetween(W.Window.unboundedPreceding, -1), W.Window.partitionBy("key.conv_id")
    system = t.groupBy("key").agg(F.min(F.when(F.col("role") == "system", F.struct("turn", "text"))).alias("system"))
    system = system.withColumn("system", F.min("system").over(whole)).withColumn("lead_text", F.left("system.text", F.lit(4 * (budget // 2 - 4))))
    t = t.join(system, "key")
    lead = F.coalesce(turn_tokens(F.col("lead_text")), F.lit(0).cast("long"))
    t = t.withColumns({"lead": lead, "room": F.lit(budget - history) - lead})
    is_system = F.col("system").isNotNull() & (F.col("role") == "system") & F.col("turn").eqNullSafe(F.col("system.turn")) & (F.col("text") == F.col("system.text"))
    part = 4 * (F.col("room") - 4)
    n_parts = F.greatest(F.lit(1), F.ceil(F.length("text") / part))
    t = t.withColumns({"is_system": is_system, "part": part, "n_parts": n_parts, "tokens": F.ceil(F.length("text") / 4) + 4 * n_parts}).drop("system")

    inner = W.Window.partitionBy("key").orderBy("turn", "role", "text").rowsBetween(W.Window.unboundedPreceding, 0)
    t = t.withColumn("start", F.sum("tokens").over(inner) - F.col("tokens"))
    chunks = t.groupBy("key").agg(F.sum("tokens").alias("sum"), F.min(F.when(F.col("is_system"), F.col("start"))).alias("system_at"))
    chunks = chunks.withColumn("off", F.coalesce(F.sum("sum").over(ahead), F.lit(0)))
    chunks = chunks.withColumn("system_at", F.min(F.col("system_at") + F.col("off")).over(whole))
    t = t.join(chunks.select("key", "off", "system_at"), "key")

    pieces = F.when(F.col("n_parts") == 1, F.array("text")).otherwise(F.regexp_extract_all("text", F.concat(F.lit("(?s).{1,"), F.col("part"), F.lit("}")), F.lit(0)))
    t = t.select("key.conv_id", "role", "is_system", "lead", "lead_text", "room", "system_at", (F.col("start") + F.col("off")).alias("turn_at"), F.posexplode_outer(pieces).alias("k", "text"))
    return t.withColumns({"start": F.col("turn_at") + F.col("k") * F.col("room"), "tokens": turn_tokens(F.col("text"))})


_SPANS = """aggregate(items, named_struct('at', 0, 'spans', cast(array() as array<struct<start:int,length:int>>)),
  (a, x) -> named_struct('at', a.at + length(x.head) + length(x.body) + {close},
    'spans', if(x.own and x.role = 'assistant', concat(a.spans, array(named_struct('start', a.at + length(x.head), 'length', length(x.body)))), a.spans)))"""


def windows(turns: DataFrame, budget: int = 1024, history: int = 96) -> DataFrame:
    """conv_id, window, n_context, n_own, n_tokens, formatted, mask (code-point spans of formatted) of turns (conv_id, turn, role, text)."""
    if not 0 <= 4 * history <= budget or budget < 64:
        raise ValueError("a budget has at least 64 tokens, and the history at most a quarter of them")
    t = _placed(turns, budget, history)
    span = SEGMENT * F.col("room")
    t = t.withColumn("segment", F.floor(F.col("start") / span))
    # What may be history of the next segment goes there too; its first begin decides.
    late = (F.col("start") >= (F.col("segment") + 1) * span - history) & (F.col("tokens") <= history) & ~F.col("is_system")
    here, next_ = F.struct("segment", F.lit(True).alias("own")), F.struct((F.col("segment") + 1).alias("segment"), F.lit(False).alias("own"))
    t = t.withColumn("in", F.explode(F.when(late, F.array(here, next_)).otherwise(F.array(here))))
    head = F.concat(F.lit(OPEN), escape_role(F.col("role")), F.when(F.col("k") > 0, F.lit(MORE)).otherwise(F.lit("")), F.lit("\n"))
    item = F.struct("start", F.col("in.own").alias("own"), "role", head.alias("head"), escape(F.col("text")).alias("body"), "tokens", "is_system")
    s = t.groupBy("conv_id", F.col("in.segment").alias("segment")).agg(F.array_sort(F.collect_list(item)).alias("items"), *(F.first(c).alias(c) for c in ("lead", "lead_text", "system_at")))
    s = s.withColumn("own", F.filter("items", lambda x: x["own"])).where(F.size("own") > 0)

    def led(at: Column) -> Column:
        return F.coalesce(at > F.col("system_at"), F.lit(False))

    def end(at: Column) -> Column:
        return at + budget - F.when(at > 0, F.lit(history)).otherwise(F.lit(0)) - F.when(led(at), F.col("lead")).otherwise(F.lit(0).cast("long"))

    def place(begins: Column, x: Column) -> Column:
        last = F.element_at(begins, -1)
        return F.when(x["start"] + x["tokens"] <= end(last), begins).otherwise(F.concat(begins, F.array(x["start"])))

    s = s.withColumn("begins", F.aggregate("own", F.array(F.element_at("own", 1)["start"]), place))
    w = s.select("conv_id", "segment", "items", "own", "lead", "lead_text", "system_at", "begins", F.posexplode_outer("begins").alias("k", "at"))
    until = F.try_element_at("begins", F.col("k") + 2)
    leading = F.struct(
        F.lit(-1).cast("long").alias("start"), F.lit(False).alias("own"), F.lit("system").alias("role"), F.lit(f"{OPEN}system\n").alias("head"), escape(F.col("lead_text")).alias("body"), F.col("lead").alias("tokens"), F.lit(True).alias("is_system")
    )
    context = F.transform(F.filter("items", lambda x: (x["start"] >= F.col("at") - history) & (x["start"] < F.col("at")) & ~x["is_system"]), lambda x: x.withField("own", F.lit(False)))
    chosen = F.filter("own", lambda x: (x["start"] >= F.col("at")) & F.coalesce(x["start"] < until, F.lit(True)))
    w = w.withColumn("items", F.concat(F.when(led(F.col("at")), F.array(leading)).otherwise(F.array().cast(w.schema["items"].dataType)), context, chosen))
    return w.select(
        "conv_id",
        (F.col("segment") * STRIDE + F.col("k")).alias("window"),
        F.size(F.filter("items", lambda x: ~x["own"])).alias("n_context"),
        F.size(F.filter("items", lambda x: x["own"])).alias("n_own"),
        F.aggregate("items", F.lit(0).cast("long"), lambda a, x: a + x["tokens"]).alias("n_tokens"),
        F.array_join(F.transform("items", lambda x: F.concat(x["head"], x["body"], F.lit(CLOSE))), "").alias("formatted"),
        F.expr(_SPANS.format(close=len(CLOSE)))["spans"].alias("mask"),
    )


def read_back(w: DataFrame) -> DataFrame:
    """Windows with their own turns (role, text, whether they go on with the turn before) and the texts under the mask, parsed from `formatted` alone."""
    pieces = F.split("formatted", r"<\|im_end\|>\n", -1)
    own = F.slice(pieces, F.col("n_context") + 1, F.size(pieces) - 1 - F.col("n_context"))

    def parse(piece: Column) -> Column:
        said = F.substring(piece, len(OPEN) + 1, 2**31 - 1)
        role = F.substring_index(said, "\n", 1)
        more = F.endswith(role, F.lit(MORE))
        return F.struct(unescape_role(F.when(more, F.substring_index(role, MORE, 1)).otherwise(role)).alias("role"), more.alias("more"), unescape(F.substr(said, F.length(role) + 2)).alias("text"))

    return w.withColumns({"turns": F.transform(own, parse), "losses": F.transform("mask", lambda m: unescape(F.substr("formatted", m["start"] + 1, m["length"])))})
