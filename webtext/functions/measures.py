"""Measures on one pair of texts or tables, in Python: n-gram overlap, edit and tree-edit similarity (L156-L169)."""

from __future__ import annotations

import re
from collections import Counter

from webtext.functions.content import own_rows
from webtext.functions.dom import parse, visible_text

_WORD = re.compile(r"[㐀-鿿豈-﫿]|[^\W㐀-鿿豈-﫿]+|[^\w\s]")


def tokens(text: str | None, mode: str = "mixed") -> list[str]:
    """ws: white-space runs; mixed: words of alphabetic scripts, single CJK characters, marks."""
    text = (text or "").lower()
    return text.split() if mode == "ws" else _WORD.findall(text)


def rouge_n(pred: list[str], gold: list[str], n: int = 5, strict: bool = False) -> tuple[float, float, float]:
    """Precision, recall and F1 of clipped n-gram counts. Shorter texts are compared by their own length."""
    if not strict:
        n = max(1, min(n, len(pred) or n, len(gold) or n))
    a, b = (Counter(tuple(x[i : i + n]) for i in range(len(x) - n + 1)) for x in (pred, gold))
    if not a and not b:
        return (1.0, 1.0, 1.0) if not strict or pred == gold else (0.0, 0.0, 0.0)
    hit = (a & b).total()
    if not hit:
        return 0.0, 0.0, 0.0
    p, r = hit / a.total(), hit / b.total()
    return p, r, 2 * p * r / (p + r)


def common_subsequence(a: list[str], b: list[str]) -> int:
    """Length of the longest common subsequence: a row of the table is one long integer, whose zero bits are the steps reached."""
    where: dict[str, int] = {}
    for j, y in enumerate(b):
        where[y] = where.get(y, 0) | 1 << j
    full = (1 << len(b)) - 1
    row = full
    for x in a:
        met = row & where.get(x, 0)
        row = ((row + met) | (row - met)) & full
    return len(b) - row.bit_count()


def rouge_l(pred: list[str], gold: list[str]) -> float:
    """F1 of the longest common subsequence; its cost is the product of the lengths, 64 places at a time."""
    if not pred and not gold:
        return 1.0
    return 2 * common_subsequence(pred, gold) / (len(pred) + len(gold))


def edit_distance(a: str, b: str) -> int:
    """Levenshtein distance; what both begin and end with costs nothing and is left out first."""
    if len(a) < len(b):
        a, b = b, a
    at = 0
    while at < len(b) and a[at] == b[at]:
        at += 1
    to = 0
    while to < len(b) - at and a[-1 - to] == b[-1 - to]:
        to += 1
    a, b = a[at : len(a) - to], b[at : len(b) - to]
    if not b:
        return len(a)
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        before, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            before, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, before + (x != y))
    return row[-1]


def edit_similarity(a: str, b: str) -> float:
    longer = max(len(a), len(b))
    return 1.0 if not longer else 1 - edit_distance(a, b) / longer


Tree = tuple[str, str, list]  # label, text, children


def table_tree(markup: str | None) -> Tree | None:
    """table > tr > td; td and th are one label, spans are part of it."""
    table = next(parse(markup).elements("table"), None)
    if table is None:
        return None
    rows = []
    for row in own_rows(table):
        cells = [(f"td {c.attrs.get('rowspan', '1')} {c.attrs.get('colspan', '1')}", visible_text(c), []) for c in row]
        rows.append(("tr", "", cells))
    return "table", "", rows


def tree_distance(a: Tree, b: Tree, structure_only: bool = False) -> float:
    """Ordered tree edit distance by the keyroots of both trees; inserting and deleting cost 1, renaming up to 1."""

    def laid_out(tree: Tree) -> tuple[list, list[int], list[int]]:
        nodes, left = [], []

        def visit(t: Tree) -> int:
            first = None
            for c in t[2]:
                leaf = visit(c)
                first = leaf if first is None else first
            nodes.append(t)
            left.append(len(nodes) - 1 if first is None else first)
            return left[-1]

        visit(tree)
        return nodes, left, sorted({x: i for i, x in enumerate(left)}.values())

    def rename(x: Tree, y: Tree) -> float:
        if x[0] != y[0]:
            return 1.0
        return 0.0 if structure_only or x[1] == y[1] else 1 - edit_similarity(x[1], y[1])

    (an, al, ak), (bn, bl, bk) = laid_out(a), laid_out(b)
    tree = [[0.0] * len(bn) for _ in an]
    for i in ak:
        for j in bk:
            li, lj = al[i], bl[j]
            f = [[0.0] * (j - lj + 2) for _ in range(i - li + 2)]
            for x in range(1, len(f)):
                f[x][0] = f[x - 1][0] + 1
            for y in range(1, len(f[0])):
                f[0][y] = f[0][y - 1] + 1
            for x in range(1, len(f)):
                for y in range(1, len(f[0])):
                    u, v = li + x - 1, lj + y - 1
                    edge = min(f[x - 1][y] + 1, f[x][y - 1] + 1)
                    if al[u] == li and bl[v] == lj:
                        f[x][y] = min(edge, f[x - 1][y - 1] + rename(an[u], bn[v]))
                        tree[u][v] = f[x][y]
                    else:
                        f[x][y] = min(edge, f[al[u] - li][bl[v] - lj] + tree[u][v])
    return tree[-1][-1]


def tree_size(t: Tree | None) -> int:
    return 0 if t is None else 1 + sum(map(tree_size, t[2]))


def teds(a: str | None, b: str | None, structure_only: bool = False, most: int = 1500) -> float:
    """Tree-edit similarity of two tables; beyond the guard rows are aligned by place."""
    x, y = table_tree(a), table_tree(b)
    if x is None and y is None:
        return 1.0
    if x is None or y is None:
        return 0.0
    if x == y:
        return 1.0
    n = max(tree_size(x), tree_size(y))
    if n > most:
        paired = sum(tree_distance(r, s, structure_only) for r, s in zip(x[2], y[2]))
        rest = sum(map(tree_size, (x[2] if len(x[2]) > len(y[2]) else y[2])[min(len(x[2]), len(y[2])) :]))
        return 1 - (paired + rest) / n
    return 1 - tree_distance(x, y, structure_only) / n


def aligned(pred: list[str], gold: list[str], similarity=edit_similarity) -> float:
    """Mean over gold of the similarity of each element with its predicted partner: equal ones first, then the best pair left; without one 0."""
    if not gold:
        return 1.0 if not pred else 0.0
    left = Counter(pred)
    rest, score = [], 0.0
    for g in gold:
        if left[g]:
            left[g] -= 1
            score += 1
        else:
            rest.append(g)
    pairs = sorted(((similarity(p, g), -i, -j) for i, p in enumerate(left.elements()) for j, g in enumerate(rest)), reverse=True)
    used, met = set(), set()
    for s, i, j in pairs:
        if i not in used and j not in met:
            used.add(i)
            met.add(j)
            score += s
    return score / len(gold)


def blind_score(text: str | None, stop: frozenset[str]) -> float:
    """What a text holds that reads like sentences, less what does not: words of lines with two stop words and five words, less all others."""
    score = 0
    for line in (text or "").split("\n"):
        words = _WORD.findall(line.lower())
        good = len(words) >= 5 and sum(w in stop for w in words) >= 2
        score += len(words) if good else -len(words)
    return float(score)


def judged(a: str | None, b: str | None, judge) -> tuple[str, bool]:
    """(winner: a, b or tie; whether both orders agree) of a judge that is asked in both orders and says first, second or tie: a win by place is a tie."""
    names = {"first": "a", "second": "b", "tie": "tie"}, {"first": "b", "second": "a", "tie": "tie"}
    one, two = names[0][judge(a, b)], names[1][judge(b, a)]
    return (one, True) if one == two else ("tie", False)
