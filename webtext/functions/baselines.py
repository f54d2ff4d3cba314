"""Baselines: density extraction, a rule book, and stripping all tags (L9, L172). Own designs after published ideas."""

from __future__ import annotations

import re

from webtext.functions.blocks import chunk
from webtext.functions.dom import Node, body_of, parse, visible_text
from webtext.functions.scoring import _BAD, _GOOD

_BOXES = frozenset("p div article section main td blockquote pre".split())


def link_density(node: Node) -> float:
    return sum(len(visible_text(a)) for a in node.elements("a")) / max(1, len(visible_text(node)))


def density(page: str | None, keep_share: float = 0.2) -> str:
    """Markup of the subtree where paragraph text is densest, with siblings that score near it."""
    root = parse(page)
    score: dict[int, float] = {}
    nodes: dict[int, Node] = {}
    for n in body_of(root).walk():
        if n.tag not in _BOXES:
            continue
        text = " ".join(c.text for c in n.children if c.tag == "") + " ".join(visible_text(c) for c in n.children if c.tag in ("b", "i", "em", "strong", "span", "a", "code"))
        own = (len(text.strip()) + 25 * text.count(",")) * (1 - link_density(n))
        if own <= 0:
            continue
        share = 1.0
        for a in list(n.ancestors())[:2]:
            if a.tag in ("#root", "html"):
                break
            name = f"{a.attrs.get('class', '')} {a.attrs.get('id', '')}"
            score[id(a)] = score.get(id(a), 0.0) + own * share * (0.3 if _BAD.search(name) else 1.2 if _GOOD.search(name) else 1.0)
            nodes[id(a)] = a
            share /= 2
    if not score:
        return ""
    best = max(score, key=score.get)
    parent = nodes[best].parent
    if parent is None or nodes[best].tag == "body":
        return nodes[best].markup
    kept = []
    for c in parent.children:
        text = visible_text(c) if c.tag else ""
        if c is nodes[best] or score.get(id(c), 0) >= keep_share * score[best] or (c.tag == "p" and len(text) > 80 and link_density(c) < 0.25):
            kept.append(c.markup)
    return "".join(kept)


def density_text(page: str | None) -> str:
    """The plain-text mode: structure is lost."""
    return "\n".join(b.text for b in chunk(parse(density(page))))


_OUT = frozenset("nav footer header aside form script style noscript".split())


def rulebook(page: str | None, least_chars: int = 25, most_links: float = 0.5) -> str:
    """Paragraphs and headings outside denied regions; nothing is scored."""
    lines, stack = [], [body_of(parse(page))]
    while stack:
        n = stack.pop()
        if n.tag in _OUT or (n.tag and n.raw_attrs and _BAD.search(f"{n.attrs.get('class', '')} {n.attrs.get('id', '')}")):
            continue
        if n.tag in ("p", "h1", "h2", "h3", "h4", "blockquote"):
            text = visible_text(n)
            if text and (n.tag[0] == "h" or (len(text) >= least_chars and link_density(n) < most_links)):
                lines.append(text)
        else:
            stack.extend(reversed(n.children))
    return "\n".join(lines)


def strip_all(page: str | None) -> str:
    """All text outside scripts and styles."""
    page = re.sub(r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " ", page or "")
    return " ".join(re.sub(r"<[^>]*>", " ", page).split())
