"""Selector rules: distilled from a labelled page, applied to others of its template (L100-L102).

A selector is a chain of steps `tag`, `tag.class`, `tag#id`, optionally `tag[k]` (k-th of its name among siblings), joined by `/`
(child); a leading `//` leaves out what is above. The most specific rule that selects a node decides for it and what is below.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from webtext.functions.blocks import Block, Config, chunk
from webtext.functions.dom import Node, parse

Step = tuple[str, str, str, int]  # tag, classes, id, position (0: any)


@dataclass(frozen=True)
class Rule:
    steps: tuple[Step, ...]
    anywhere: bool
    action: str
    support: int
    purity: float

    @property
    def specificity(self) -> int:
        return sum(1000 * bool(i) + 100 * (c.count(".") + 1 if c else 0) + 10 + (p > 0) for _, c, i, p in self.steps)

    @property
    def selector(self) -> str:
        return ("//" if self.anywhere else "/") + "/".join(t + (f".{c}" if c else "") + (f"#{i}" if i else "") + (f"[{p}]" if p else "") for t, c, i, p in self.steps)

    @property
    def xpath(self) -> str:
        def one(s: Step) -> str:
            t, c, i, p = s
            tests = [f'contains(concat(" ",normalize-space(@class)," ")," {x} ")' for x in c.split(".") if x] + ([f'@id="{i}"'] if i else [])
            return t + (f"[{' and '.join(tests)}]" if tests else "") + (f"[{p}]" if p and not tests else "")

        return ("//" if self.anywhere else "/") + "/".join(map(one, self.steps))

    @property
    def css(self) -> str:
        return " > ".join(t + "".join(f".{x}" for x in c.split(".") if x) + (f"#{i}" if i else "") + (f":nth-of-type({p})" if p else "") for t, c, i, p in self.steps)


_PARSE = re.compile(r"([^.#\[/]+)(?:\.([^#\[]+))?(?:#([^\[]+))?(?:\[(\d+)\])?")


def parse_selector(text: str) -> tuple[tuple[Step, ...], bool]:
    anywhere = text.startswith("//")
    steps = []
    for part in text.lstrip("/").split("/"):
        m = _PARSE.fullmatch(part)
        steps.append((m[1], m[2] or "", m[3] or "", int(m[4] or 0)))
    return tuple(steps), anywhere


def step_of(node: Node) -> Step:
    same = [c for c in node.parent.children if c.tag == node.tag] if node.parent else [node]
    classes = ".".join(sorted(x for x in node.attrs.get("class", "").split() if not re.search(r"\d|[.#/\[\]]", x)))
    eid = node.attrs.get("id", "")
    return node.tag, classes, eid if eid and not re.search(r"[\d.#/\[\]\s]", eid) else "", same.index(node) + 1 if len(same) > 1 else 0


def _chain(node: Node) -> list[Node]:
    out = [node]
    while out[-1].parent is not None and out[-1].parent.tag != "#root":
        out.append(out[-1].parent)
    return out[::-1]


def _fits(node: Node, steps: tuple[Step, ...], anywhere: bool) -> bool:
    k = len(steps) - 1
    while k >= 0:
        if node is None or node.tag == "#root":
            return False
        tag, classes, eid, position = steps[k]
        own = step_of(node)
        if own[0] != tag or (classes and not set(classes.split(".")) <= set(own[1].split("."))) or (eid and own[2] != eid) or (position and (own[3] or 1) != position):
            return False
        node, k = node.parent, k - 1
    return anywhere or node is None or node.tag == "#root"


def _verdicts(blocks: list[Block], labels: list[int]) -> dict[int, int]:
    """1 where all blocks at or below a node are kept, 0 where none is, -1 where they differ."""
    out: dict[int, int] = {}
    for b, y in zip(blocks, labels, strict=True):
        for n in [*(b.nodes if b.tag != "#run" else []), *b.nodes[0].ancestors()]:
            out[id(n)] = y if out.get(id(n), y) == y else -1
    return out


def synthesise(root: Node, blocks: list[Block], labels: list[int], least_purity: float = 0.95) -> list[Rule]:
    """Rules that reproduce the labels on this page: one for each highest node whose blocks agree, as general as purity allows."""
    verdict = _verdicts(blocks, labels)
    counts: dict[int, list[int]] = {}
    for b, y in zip(blocks, labels, strict=True):
        for n in [*(b.nodes if b.tag != "#run" else []), *b.nodes[0].ancestors()]:
            counts.setdefault(id(n), [0, 0])[y] += 1
    elements = [n for n in root.walk() if n.tag and n.tag != "#root" and id(n) in verdict]
    by_tag: dict[str, list[Node]] = {}
    for n in elements:
        by_tag.setdefault(n.tag, []).append(n)
    rules: dict[str, Rule] = {}
    for b, y in zip(blocks, labels, strict=True):
        top = b.nodes[0] if b.tag != "#run" else b.node
        for a in ([top] if b.tag == "#run" else []) + list(top.ancestors()):
            if a.tag == "#root" or verdict.get(id(a)) != y:
                break
            top = a
        if verdict.get(id(top)) != y and b.tag == "#run":
            continue  # a run between differing siblings: its parent's rule decides
        steps = tuple(step_of(n) for n in _chain(top))
        last = steps[-1]
        tries = [((last[0], "", "", 0),), ((last[0], last[1], "", 0),), ((last[0], last[1], last[2], 0),)]
        tries += [tuple((t, c, i, 0) for t, c, i, _ in steps[k:]) for k in range(len(steps) - 2, -1, -1)] + [(*((t, c, i, 0) for t, c, i, _ in steps[:-1]), last), steps]
        for k, cand in enumerate(dict.fromkeys(tries)):
            whole = k >= len(dict.fromkeys(tries)) - 2
            hits = [n for n in by_tag[top.tag] if _fits(n, cand, not whole)]
            n_all = sum(sum(counts[id(n)]) for n in hits)
            n_same = sum(counts[id(n)][y] for n in hits)
            if hits and n_same >= least_purity * n_all or cand == steps:
                r = Rule(cand, not whole, "retain" if y else "prune", n_all, n_same / max(1, n_all))
                rules.setdefault(r.selector, r)
                break
    return list(rules.values())


class Compiled:
    """Rules of one cluster, grouped by the tag of their last step."""

    def __init__(self, rules: list[tuple[str, str]]):
        self.by_tag: dict[str, list[Rule]] = {}
        for selector, action in rules:
            steps, anywhere = parse_selector(selector)
            self.by_tag.setdefault(steps[-1][0], []).append(Rule(steps, anywhere, action, 0, 1.0))
        for own in self.by_tag.values():  # most specific first; of equals retain comes first
            own.sort(key=lambda r: (-r.specificity, r.action != "retain"))

    def decide(self, root: Node, blocks: list[Block]) -> tuple[list[int], int]:
        """Labels of blocks, and how many no rule covered (they count as boilerplate)."""
        known: dict[int, int | None] = {}

        def of(node: Node | None) -> int | None:
            trail = []
            while node is not None and id(node) not in known:
                trail.append(node)
                node = node.parent
            value = known[id(node)] if node is not None else None
            for n in reversed(trail):
                found = next((r for r in self.by_tag.get(n.tag, ()) if _fits(n, r.steps, r.anywhere)), None)
                if found is not None:
                    value = int(found.action == "retain")
                known[id(n)] = value
            return value

        got = [of(b.node) if b.tag == "#run" else of(b.nodes[0]) for b in blocks]
        return [int(bool(g)) for g in got], sum(g is None for g in got)


def apply_rules(page: str | None, rules: list[tuple[str, str]], cfg: Config = Config()) -> tuple[Node, list[Block], list[int], int]:
    root = parse(page)
    blocks = chunk(root, cfg)
    return root, blocks, *Compiled(rules).decide(root, blocks)
