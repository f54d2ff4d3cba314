"""Block scorers: anything that gives a pair of logits per block.

The published labeller is a 0.6B language model that is not available offline. `lexicon` is a deterministic stand-in, the trained
linear scorer of operators/labeller.py another; neither's scores may be presented as the model's.
"""

from __future__ import annotations

import math
import re

from webtext.functions.blocks import Block, is_tex
from webtext.functions.dom import visible_text

_BAD = re.compile(r"\b(ads?|advert\w*|nav\w*|menu|footer|header|share|social|related|cookie|promo\w*|sidebar|banner|comment-form|breadcrumb|copyright|login|subscribe|popup)\b", re.I)
_GOOD = re.compile(r"\b(article|content|entry|main|post|story|text|body)\b", re.I)
_TEX = re.compile(r"\$\$|\\\(|\\\[")
STOP = {
    "en": frozenset("the of and to in a is that it was for on are with as be this by an or from at not have".split()),
    "de": frozenset("der die das und in zu den mit von ist im auf für des sich eine ein nicht auch als".split()),
    "fr": frozenset("le la les de des et en un une du dans est que pour qui sur par pas au il".split()),
    "es": frozenset("el la los las de y en un una que es por con para del se no al lo su".split()),
}
_ALL_STOP = frozenset().union(*STOP.values())
FEATURES = ("bias", "log_chars", "link_density", "stop_share", "sentence_end", "heading", "list", "in_article", "in_boiler", "bad_name", "good_name", "copyright", "short", "position", "rich", "formal")


def features(blocks: list[Block]) -> list[list[float]]:
    """One row of FEATURES for each block."""
    out, n = [], len(blocks)
    for k, b in enumerate(blocks):
        text = b.text
        linked = sum(len(visible_text(a)) for x in b.nodes for a in x.elements("a"))
        words = re.findall(r"\w+", text.lower())
        names = " ".join(f"{x.attrs.get('class', '')} {x.attrs.get('id', '')}" for x in (b.node, *b.node.ancestors()))
        above = {b.node.tag, *(a.tag for a in b.node.ancestors())}
        out.append([
            1.0, math.log1p(len(text)) / 6, linked / max(1, len(text)), sum(w in _ALL_STOP for w in words) / max(1, len(words)), float(bool(re.search(r"[.!?…][\"')\]]*$", text))),
            float(b.tag in ("h1", "h2", "h3", "h4", "h5", "h6")), float(b.tag in ("ul", "ol", "dl")), float(bool(above & {"article", "main"})), float(bool(above & {"nav", "footer", "aside", "header", "form"})),
            float(bool(_BAD.search(names))), float(bool(_GOOD.search(names))), float("©" in text or "(c)" in text), float(len(text) < 25), k / max(1, n - 1),
            float(any(True for x in b.nodes for _ in x.elements("pre", "code", "table", "math", "img", "video", "audio"))),
            float(bool(_TEX.search(text)) or b.tag == "table" or any(n.tag in ("pre", "code", "math") or is_tex(n) for x in b.nodes for n in x.walk())),
        ])
    return out


#: Weights of the lexicon scorer, in the order of FEATURES; [D]
LEXICON = (-1.6, 1.6, -5.0, 2.0, 0.8, 1.6, -0.3, 2.0, -3.0, -3.0, 0.5, -3.0, -0.8, 0.0, 1.2, 2.5)


def linear(weights: tuple[float, ...], blocks: list[Block]) -> list[tuple[float, float]]:
    """(other, main) logits of each block; a lone short block between two others follows them, and what the model does not see is other.

    Unlinked text in plain surroundings beside a main block of code or formulas introduces or follows it, so it is main as well. So is a
    short one in an article beside a main block of the same parent, or with only short ones between: it is a paragraph that happens to be short.
    """
    rows = features(blocks)
    z = [sum(w * f for w, f in zip(weights, row, strict=True)) for row in rows]
    out = list(z)
    plain = [blocks[k].tag in ("p", "#run") and not any(row[FEATURES.index(c)] for c in ("link_density", "in_boiler", "bad_name", "copyright")) for k, row in enumerate(rows)]
    small = [p and bool(row[FEATURES.index("short")] and row[FEATURES.index("in_article")]) for p, row in zip(plain, rows, strict=True)]
    main: list[list[float]] = [[] for _ in z]  # of each block: the nearest main ones of its parent, past small ones
    for step, order in ((-1, range(1, len(z))), (1, range(len(z) - 2, -1, -1))):
        last = None
        for k in order:
            j = k + step
            if blocks[j].node.parent is not blocks[k].node.parent:
                last = None
            elif z[j] > 0:
                last = z[j]
            elif not small[j]:
                last = None
            if last is not None:
                main[k].append(last)
    for k in range(len(z)):
        near = [z[j] for j in (k - 1, k + 1) if 0 <= j < len(z) and rows[j][-1] and z[j] > 0] + (main[k] if small[k] else [])
        if plain[k] and z[k] <= 0 and near:
            out[k] = min(near)
    grown = list(out)
    for k in range(1, len(z) - 1):
        if out[k] == z[k] and not rows[k][-1] and abs(z[k]) < 1 and len(blocks[k].text) < 25 and blocks[k].tag[:1] != "h" and (z[k] > 0) != (grown[k - 1] > 0) and (z[k] > 0) != (grown[k + 1] > 0):
            out[k] = (grown[k - 1] + grown[k + 1]) / 2
    out = [-20.0 if b.dropped else x for x, b in zip(out, blocks, strict=True)]
    return [(-x / 2, x / 2) for x in out]


def lexicon(blocks: list[Block]) -> list[tuple[float, float]]:
    return linear(LEXICON, blocks)
