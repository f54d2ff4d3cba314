"""Blocks of a page: chunking, the simplified and the mapping view, and reassembly."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from webtext.functions.dom import Node, body_of, parse, visible_text

BREAK = frozenset(
    "address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr legend li main nav ol option p pre section summary table tbody td tfoot th thead tr ul".split()
)
ATOM = frozenset(("table", "ul", "ol", "dl", "pre", "figure", "math"))
DROP = {
    "listed": frozenset(("style", "script", "header", "aside")),
    "extended": frozenset(("style", "script", "header", "aside", "noscript", "template", "svg", "iframe", "link", "meta")),
    "none": frozenset(),
}


@dataclass(frozen=True)
class Config:
    """drop: preset of removed tags; keep: attributes kept (None: all); para_chars, rows, cells, items: truncation (0: off)."""

    drop: str = "listed"
    keep: tuple[str, ...] | None = ("class", "id")
    para_chars: int = 200
    rows: int = 3
    cells: int = 6
    items: int = 5
    split_br: bool = False
    layout_cut: int = 3


@dataclass
class Block:
    block_id: int
    nodes: list[Node]
    tag: str
    node: Node = field(repr=False)  # the element itself, or the parent of a run
    dropped: bool = False  # stands in a removed element: the model sees nothing of it

    @property
    def raw_html(self) -> str:
        return self.nodes[0].source[self.nodes[0].start : self.nodes[-1].end]

    @property
    def text(self) -> str:
        return " ".join("".join(visible_text(n) + (" " if n.tag else "") for n in self.nodes).split()) if len(self.nodes) > 1 else visible_text(self.nodes[0])


def is_layout_table(table: Node, cut: int = 3) -> bool:
    """Evidence that a table arranges a page rather than data."""
    cells = list(table.elements("td", "th"))
    rows = list(table.elements("tr"))
    if not cells:
        return False
    lengths = [len(visible_text(c)) for c in cells]
    mean = sum(lengths) / len(lengths)
    evidence = (
        (not any(True for _ in table.elements("th", "caption", "thead")))
        + 2 * (table.attrs.get("role") == "presentation")
        + any(t is not table for t in table.elements("table"))
        + (len(rows) <= 1 or len(cells) <= 2 * len(rows))
        + any(c.tag in ("div", "p", "article", "section", "nav", "h1", "h2", "h3") for x in cells for c in x.children)
        + (max(lengths) > 20 * (mean / 4 + 1))
        - 2 * any(True for _ in table.elements("th"))
    )
    return evidence > cut


def is_tex(node: Node) -> bool:
    """A formula that is written as a script (type math/tex), which is content."""
    return node.tag == "script" and node.attrs.get("type", "").startswith("math/")


def _shows(node: Node) -> bool:
    return node.tag in ("img", "video", "audio", "math") or is_tex(node)


def _breaks_below(node: Node) -> bool:
    return any(n.tag in BREAK for c in node.children for n in c.walk())


def chunk(root: Node, cfg: Config = Config()) -> list[Block]:
    """Blocks in document order, ids 1..n."""
    out: list[Block] = []

    def add(nodes: list[Node], tag: str, node: Node) -> None:
        out.append(Block(len(out) + 1, nodes, tag, node))

    def descend(parent: Node) -> None:
        work = [iter(parent.children)]
        owners, runs = [parent], [[]]

        def flush() -> None:
            run = runs[-1]
            while run and run[0].tag == "" and not run[0].text.strip():
                run.pop(0)
            while run and run[-1].tag == "" and not run[-1].text.strip():
                run.pop()
            if run and any(_shows(n) or (n.tag == "" and n.text.strip()) for r in run for n in r.walk()):
                add(list(run), "#run", owners[-1])
            runs[-1] = []

        while work:
            child = next(work[-1], None)
            if child is None:
                flush()
                work.pop(), owners.pop(), runs.pop()
                continue
            if child.tag in ("head", "script", "style") and not is_tex(child):
                continue
            if child.tag in ATOM and not (child.tag == "table" and is_layout_table(child, cfg.layout_cut)):
                flush()
                add([child], child.tag, child)
            elif child.tag in BREAK and not _breaks_below(child):
                flush()
                if child.tag == "hr" or visible_text(child) or any(_shows(n) for n in child.walk()):
                    add([child], child.tag, child)
            elif child.tag in BREAK or (child.tag and _breaks_below(child)):
                flush()
                work.append(iter(child.children)), owners.append(child), runs.append([])
            elif cfg.split_br and child.tag == "br":
                flush()
            else:
                runs[-1].append(child)

    descend(body_of(root))
    return out


def _open(node: Node, keep: tuple[str, ...] | None) -> str:
    if keep is None:
        return node.open_tag
    return f"<{node.tag}" + "".join(f' {k}="{node.attrs[k]}"' for k in keep if k in node.attrs) + ">"


def is_dropped(block: Block, drop: frozenset[str]) -> bool:
    """Whether all of the block lies in removed elements."""
    return bool(drop) and (any(a.tag in drop for a in block.nodes[0].ancestors()) or all(n.tag in drop and not is_tex(n) for n in block.nodes))


def simplify(block: Block, cfg: Config = Config()) -> tuple[str, bool]:
    """The block as the model sees it, and whether something was cut off; '' within a removed element."""
    drop, cut = DROP[cfg.drop], False
    if is_dropped(block, drop):
        return "", False
    budget = cfg.para_chars or 1 << 60
    out: list[str] = []

    def write(node: Node) -> None:
        nonlocal budget, cut
        if node.tag == "":
            text = re.sub(r"\s+", " ", node.text)
            if len(text) > budget:
                text, cut = text[:budget], True
            budget -= len(text)
            out.append(text)
            return
        if node.tag in drop and not is_tex(node):
            return
        children = node.children
        limit = {"table": cfg.rows, "tbody": cfg.rows, "tr": cfg.cells, "ul": cfg.items, "ol": cfg.items, "dl": cfg.items}.get(node.tag, 0)
        if limit:
            items = [c for c in children if c.tag]
            if len(items) > limit:
                children, cut = items[:limit], True
        out.append(_open(node, cfg.keep))
        for c in children:
            if c.tag in ("td", "th", "li", "dt", "dd") and cfg.para_chars:
                budget = cfg.para_chars
            write(c)
        if node.end > node.inner or node.children:
            out.append(f"</{node.tag}>")

    for n in block.nodes:
        write(n)
    return "".join(out), cut


def assemble(root: Node, kept: list[Block]) -> str:
    """The kept blocks with all their ancestors, cut from the unmodified page; '' if none is kept."""
    if not kept:
        return ""
    whole = {id(n) for b in kept for n in b.nodes}
    above = {id(a) for b in kept for n in b.nodes for a in n.ancestors()}
    out: list[str] = []

    def write(node: Node) -> None:
        work = [(node, iter(node.children))]
        while work:
            owner, children = work[-1]
            child = next(children, None)
            if child is None:
                work.pop()
                if owner.end > owner.inner_end:
                    out.append(owner.source[owner.inner_end : owner.end])
                elif owner.tag not in ("#root",) and owner.tag:
                    out.append(f"</{owner.tag}>")
                continue
            if id(child) in whole:
                out.append(child.markup if child.end > child.inner_end or not child.children else child.markup + f"</{child.tag}>")
            elif id(child) in above:
                out.append(child.open_tag)
                work.append((child, iter(child.children)))

    write(root)
    return "".join(out)


def block_rows(page: str | None, cfg: Config = Config()) -> tuple[Node, list[Block], list[dict]]:
    """Tree, blocks and the rows of both views of a page."""
    root = parse(page)
    blocks = chunk(root, cfg)
    rows = []
    for b in blocks:
        b.dropped = is_dropped(b, DROP[cfg.drop])
        simplified, cut = simplify(b, cfg)
        rows.append({
            "block_id": b.block_id, "tag": b.tag, "path": b.node.path(), "cls": b.node.attrs.get("class", ""), "eid": b.node.attrs.get("id", ""),
            "simplified": simplified, "raw_html": b.raw_html, "n_chars": len(b.text), "truncated": cut,
        })
    return root, blocks, rows
