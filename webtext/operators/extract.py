"""Single-page extraction as one Arrow pass (L36-L40): parse, chunk, simplify, score, decode, assemble."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from webtext.functions.blocks import Block, Config, assemble, block_rows
from webtext.functions.content import plain_text
from webtext.functions.decoding import block_logits, decode, labels_of
from webtext.functions.dom import parse, shape
from webtext.functions.scoring import lexicon
from webtext.operators.passes import row_pass

Scorer = Callable[[list[Block]], list[tuple[float, float]]]
BLOCK = "block_id int, tag string, path string, cls string, eid string, simplified string, raw_html string, n_chars int, truncated boolean"


def blocks(pages: DataFrame, cfg: Config = Config()) -> DataFrame:
    """page_id and both views of each block: the same ids in the simplified and the mapping view."""
    names = [x.split()[0] for x in BLOCK.split(", ")]

    def run(page_id, page):
        return [(page_id, *(r[n] for n in names)) for r in block_rows(page, cfg)[2]]

    return row_pass(pages.select("page_id", "html"), run, f"page_id long, {BLOCK}", many=True)


def core(pages: DataFrame, scorer: Scorer = lexicon, cfg: Config = Config(), mode: str = "fast", keep: tuple[str, ...] = ()) -> DataFrame:
    """page_id, n_blocks, wire, labels, n_missing, main_html, main_text, status, raw_chars, simplified_chars of each page, and its columns in keep.

    status is ok or empty (null or no block); pages of any length are parsed.
    """

    def run(page_id, page, *kept):
        root, own, rows = block_rows(page, cfg)
        wire = decode(len(own), block_logits(scorer(own)), mode)
        labels, missing = labels_of(wire, len(own))
        # what simplification leaves nothing of is boilerplate
        labels = [y and bool(r["simplified"].strip()) for y, r in zip(labels, rows, strict=True)]
        main = assemble(root, [b for b, y in zip(own, labels, strict=True) if y])
        return page_id, len(own), wire, [int(y) for y in labels], missing, main, plain_text(main), "ok" if own else "empty", len(page or ""), sum(len(r["simplified"]) for r in rows), *kept

    return row_pass(
        pages.select("page_id", "html", *keep),
        run,
        ", ".join(["page_id long, n_blocks int, wire string, labels array<tinyint>, n_missing int, main_html string, main_text string, status string, raw_chars long, simplified_chars long", *(f"{c} {pages.schema[c].dataType.simpleString()}" for c in keep)]),
    )


def nodes(pages: DataFrame) -> DataFrame:
    """The node table: page_id, nid (pre-order), parent, ord, depth, tag, path, text of each element."""

    def run(page_id, page):
        out, stack = [], [(c, -1, k, 1) for k, c in reversed(list(enumerate(parse(page).children)))]
        while stack:
            n, parent, ord_, depth = stack.pop()
            if not n.tag:
                continue
            nid = len(out)
            out.append((page_id, nid, parent, ord_, depth, n.tag, n.path(), "".join(c.text for c in n.children if not c.tag)))
            stack.extend((c, nid, k, depth + 1) for k, c in reversed(list(enumerate(n.children))))
        return out

    return row_pass(pages.select("page_id", "html"), run, "page_id long, nid int, parent int, ord int, depth int, tag string, path string, text string", many=True)


def attributes(pages: DataFrame) -> DataFrame:
    """page_id, tag, attr of each attribute."""

    def run(page_id, page):
        return [(page_id, n.tag, a) for n in parse(page).walk() if n.tag and n.raw_attrs for a in n.attrs]

    return row_pass(pages.select("page_id", "html"), run, "page_id long, tag string, attr string", many=True)


def shapes(pages: DataFrame) -> DataFrame:
    """page_id and the features that representatives are chosen by."""
    names = ("n_tags", "n_attr_names", "n_distinct_tags", "depth", "width")

    def run(page_id, page):
        s = shape(parse(page))
        return (page_id, *(s[n] for n in names))

    return row_pass(pages.select("page_id", "html"), run, "page_id long, " + ", ".join(f"{n} int" for n in names))


def gold_labels(pages: DataFrame) -> DataFrame:
    """page_id, block_id, gold: content iff the block lies below the article; for evaluation only."""
    return blocks(pages).select("page_id", "block_id", (F.concat(F.lit("/"), "path", F.lit("/")).rlike(r"/article(\.[^/]*)?/")).cast("int").alias("gold"))


def lexicon_labels(pages: DataFrame) -> DataFrame:
    """page_id, block_id, label of the lexicon scorer."""
    return core(pages).select("page_id", F.posexplode("labels").alias("k", "label")).select("page_id", (F.col("k") + 1).alias("block_id"), F.col("label").cast("int").alias("label"))
