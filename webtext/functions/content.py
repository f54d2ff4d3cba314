"""Content lists: typed units of a page's content, and their Markdown (L107-L129)."""

from __future__ import annotations

import html
import re

from webtext.functions.blocks import BREAK
from webtext.functions.dom import Node, parse, visible_text

UNIT = ("seq", "type", "level", "text", "lang", "rows", "html", "items", "url", "alt", "display")
TYPES = ("title", "paragraph", "inline_formula", "display_formula", "inline_code", "code", "table", "list", "image", "video", "audio")
_CODE = frozenset(("pre", "code", "samp", "kbd", "tt"))
_HEAD = ("h1", "h2", "h3", "h4", "h5", "h6")

#: Patterns whose hits speak for a language; [D]
LANGUAGES = {
    "json": (r'^\s*[\[{]', r'"\w+"\s*:', r"[}\]]\s*$"),
    "python": (r"\bdef \w+\(.*\):", r"^\s*(from \w+ )?import \w+", r"\bprint\(", r":\s*$", r"\bNone\b|\bself\b"),
    "sql": (r"(?is)\bselect\b.+\bfrom\b", r"(?i)\bwhere\b|\bgroup by\b|\border by\b", r"(?i)\b(insert into|create table|join)\b"),
    "java": (r"\bpublic (static |final )*(class|void|int)\b", r"\bSystem\.out\b", r"\bnew \w+\("),
    "js": (r"\b(const|let|var) \w+ =", r"=>", r"\bfunction\b|\bconsole\.log\("),
    "c": (r"#include\s*<", r"\bint main\(", r"\bprintf\("),
    "shell": (r"^#!.*sh\b", r"^\s*(sudo|cd|echo|export|ls|grep)\b", r"\$\{?\w+"),
    "html": (r"<!DOCTYPE|<html", r"</\w+>", r"<\w+ [^>]*=\""),
    "css": (r"[.#]?\w+\s*\{[^}]*:[^}]*;", r"\b(color|margin|padding|font-size)\s*:"),
}


def guess_language(code: str) -> str | None:
    """The language most of whose patterns hit; None if none has two."""
    best = max(LANGUAGES, key=lambda x: (sum(bool(re.search(p, code, re.M)) for p in LANGUAGES[x]) / len(LANGUAGES[x]), -list(LANGUAGES).index(x)))
    return best if sum(bool(re.search(p, code, re.M)) for p in LANGUAGES[best]) >= 2 else None


def code_text(node: Node) -> str:
    """Text with its white space; br is a line break."""
    if node.tag == "":
        return node.text
    return "\n" if node.tag == "br" else "".join(map(code_text, node.children))


# -- formulas
_DELIMITED = re.compile(
    r"\\\[(?P<d1>.+?)\\\]|\\\((?P<i1>.+?)\\\)|\\begin\{(?P<env>equation|align|gather|displaymath)\*?\}(?P<d2>.+?)\\end\{(?P=env)\*?\}|(?<![\\$])\$\$(?P<d3>(?:[^$]|\\\$)+?)\$\$(?!\$)|(?<![\\$\w])\$(?P<i2>[^\s$](?:[^$\n]*?[^\s$\\])?)\$(?![\d$\w])",
    re.S,
)


def formulas_in(text: str) -> list[tuple[int, int, str, bool]]:
    """start, end, TeX, display of each delimited formula; prices and runs of dollars are none."""
    out = []
    for m in _DELIMITED.finditer(text):
        display = next((m[g] for g in ("d1", "d2", "d3") if m[g] is not None), None)
        tex = display if display is not None else m["i1"] if m["i1"] is not None else m["i2"]
        if m["i2"] is not None and (re.fullmatch(r"[\d.,]+.*\s.*", tex) or not re.search(r"[\\^_=+*/<>{}]|^[A-Za-z]$", tex)):
            continue
        if m["d3"] is not None and not re.search(r"[A-Za-z0-9\\]", tex):
            continue
        out.append((m.start(), m.end(), tex.strip(), display is not None))
    return out


#: TeX of operators and letters that MathML spells as characters; others stay as they are. Fixed values.
_SYMBOLS = {
    "∑": r"\sum", "∏": r"\prod", "∫": r"\int", "∞": r"\infty", "≤": r"\le", "≥": r"\ge", "≠": r"\ne", "≈": r"\approx", "×": r"\times", "·": r"\cdot", "±": r"\pm", "→": r"\to", "∂": r"\partial", "∈": r"\in",
    "α": r"\alpha", "β": r"\beta", "γ": r"\gamma", "δ": r"\delta", "ε": r"\epsilon", "θ": r"\theta", "λ": r"\lambda", "μ": r"\mu", "π": r"\pi", "σ": r"\sigma", "φ": r"\phi", "ω": r"\omega", "−": "-", "\u2061": "", "\u2062": "",
}


def mathml_tex(node: Node) -> str:
    """TeX of presentation MathML."""
    parts = [c for c in node.children if c.tag and not c.tag.startswith("annotation")]
    tex = [mathml_tex(c) for c in parts]
    match node.tag:
        case "mi" | "mn" | "mo" | "ms":
            text = code_text(node).strip()
            if text in _SYMBOLS:
                return _SYMBOLS[text] + (" " if _SYMBOLS[text].startswith("\\") else "")
            return rf"\mathrm{{{text}}}" if node.tag == "mi" and len(text) > 1 else text
        case "mtext":
            return rf"\text{{{code_text(node).strip()}}}"
        case "msqrt":
            return rf"\sqrt{{{''.join(tex).strip()}}}"
        case "mfenced":
            return node.attrs.get("open", "(") + ",".join(tex) + node.attrs.get("close", ")")
        case "mtable":
            return r"\begin{matrix}" + r" \\ ".join(tex) + r"\end{matrix}"
        case "mtr":
            return " & ".join(tex)
    a, b, c = ([x.strip() for x in tex] + [""] * 3)[:3]
    match node.tag, len(tex):
        case "mfrac", 2:
            return rf"\frac{{{a}}}{{{b}}}"
        case "mroot", 2:
            return rf"\sqrt[{b}]{{{a}}}"
        case ("msup" | "mover"), 2:
            return f"{_base(a)}^{{{b}}}"
        case ("msub" | "munder"), 2:
            return f"{_base(a)}_{{{b}}}"
        case ("msubsup" | "munderover"), 3:
            return f"{_base(a)}_{{{b}}}^{{{c}}}"
    return "".join(tex)


def _base(tex: str) -> str:
    """tex as the base of a script: in braces if it is more than one symbol."""
    return tex if re.fullmatch(r"\\?\w+|\W", tex) and (tex[:1] == "\\" or len(tex) == 1 or tex.isdigit()) else f"{{{tex}}}"


def formula_of(node: Node) -> tuple[str, bool] | None:
    """TeX and mode of an element that some renderer has left."""
    a = node.attrs if node.raw_attrs else {}
    if node.tag == "script" and a.get("type", "").startswith("math/tex"):
        return html.unescape(code_text(node)).strip(), "mode=display" in a["type"]
    if node.tag == "math" or (node.tag == "span" and re.search(r"\bkatex\b|\bkatex-display\b", a.get("class", ""))):
        for x in node.elements("annotation"):
            if "tex" in x.attrs.get("encoding", ""):
                display = "katex-display" in a.get("class", "") or any(m.attrs.get("display") == "block" for m in node.elements("math"))
                return code_text(x).strip(), display
        if node.tag == "math" and "alttext" in a:
            return a["alttext"].strip(), a.get("display") == "block"
        if node.tag == "math" and (tex := mathml_tex(node).strip()):
            return tex, a.get("display") == "block"
    if node.tag == "img" and re.search(r"\b(tex|math|latex|formula)\b", a.get("class", "")) and a.get("alt"):
        return a["alt"].strip("$ "), "display" in a.get("class", "")
    return None


# -- tables
def own_rows(table: Node) -> list[list[Node]]:
    """Cells by row, without those of inner tables."""
    rows: list[list[Node]] = []
    stack = list(reversed(table.children))
    while stack:
        n = stack.pop()
        if n.tag == "tr":
            rows.append([c for c in n.children if c.tag in ("td", "th")])
        elif n.tag in ("thead", "tbody", "tfoot"):
            stack.extend(reversed(n.children))
    return rows


def table_kind(table: Node) -> str:
    """nested, complex (spans) or simple (L121)."""
    cells = [c for r in own_rows(table) for c in r]
    if any(n is not table for n in table.elements("table")):
        return "nested"
    if any(c.attrs.get(k, "1").strip() not in ("", "1") for c in cells for k in ("rowspan", "colspan")) or any(True for c in cells for _ in c.elements("ul", "ol", "pre")):
        return "complex"
    return "simple"


def table_html(table: Node) -> str:
    """The table with its spans as only attributes."""
    out = ["<table>"]
    for row in own_rows(table):
        out.append("<tr>")
        for c in row:
            spans = "".join(f' {k}="{c.attrs[k]}"' for k in ("rowspan", "colspan") if c.attrs.get(k, "1") != "1")
            out.append(f"<{c.tag}{spans}>{html.escape(visible_text(c), quote=False)}</{c.tag}>")
        out.append("</tr>")
    return "".join([*out, "</table>"])


def linearised(table: Node) -> list[str]:
    """Texts of a nested table in reading order, inner tables row by row."""
    out = []
    for row in own_rows(table):
        for c in row:
            inner = [n for n in c.walk() if n.tag == "table" and next((a for a in n.ancestors() if a.tag in ("td", "th")), None) is c]
            below = {id(n) for t in inner for n in t.walk()}
            text = " ".join("".join(n.text for n in c.walk() if n.tag == "" and id(n) not in below).split())
            if text:
                out.append(text)
            for t in inner:
                if table_kind(t) == "nested":
                    out.extend(linearised(t))
                else:
                    out.extend(" ".join(x for x in map(visible_text, r) if x) for r in own_rows(t) if r)
    return out


# -- lists
def list_items(node: Node, found: list[dict], depth: int = 0) -> list[dict]:
    """Items with code and formulas as spans; these and media also go to found."""
    out = []
    for li in node.children:
        if li.tag not in ("li", "dt", "dd"):
            continue
        inner = [c for c in li.walk() if c.tag in ("ul", "ol", "dl") and next((a for a in c.ancestors() if a.tag in ("li", "dd", "dt")), None) is li]
        out.append({"depth": depth, "ordered": node.tag == "ol", "text": spanned(li, found, {id(x) for x in inner})})
        for x in inner:
            out.extend(list_items(x, found, depth + 1))
    return out


def _unit(type_: str, **more) -> dict:
    return dict.fromkeys(UNIT) | {"type": type_} | more


def inline_parts(nodes: list[Node], found: list[dict], skip: frozenset | set = frozenset()) -> list[str | dict]:
    """Texts of inline nodes with code and formulas as spans, and their display formulas in between; media and the spans go to found."""
    parts: list[str | dict] = []
    out: list[str] = []

    def formula(tex: str, display: bool) -> None:
        if display:
            parts.extend([" ".join("".join(out).split()), _unit("display_formula", text=tex, display=True)])
            out.clear()
        else:
            out.append(f"${tex}$")
            found.append(_unit("inline_formula", text=tex, display=False))

    def walk(n: Node) -> None:
        if id(n) in skip:
            return
        if n.tag == "":
            text, at = n.text, 0
            for start, end, tex, display in formulas_in(text):
                out.append(text[at:start])
                at = end
                formula(tex, display)
            out.append(text[at:])
            return
        if (written := formula_of(n)) is not None:
            formula(*written)
        elif n.tag in ("script", "style", "noscript", "template"):
            return
        elif n.tag == "br":
            out.append(" ")
        elif n.tag in ("img", "video", "audio"):
            media = {"img": "image"}.get(n.tag, n.tag)
            src = n.attrs.get("src") or next((s.attrs.get("src", "") for s in n.elements("source")), "")
            found.append(_unit(media, url=src, alt=n.attrs.get("alt") or n.attrs.get("title") or ""))
        elif n.tag in _CODE:
            code = " ".join(code_text(n).split())
            tick = "`" * (1 + max(map(len, re.findall(r"`+", code)), default=0))
            out.append(f"{tick}{code}{tick}")
            found.append(_unit("inline_code", text=code))
        else:
            for c in n.children:
                walk(c)

    for n in nodes:
        walk(n)
    return [p for p in [*parts, " ".join("".join(out).split())] if p]


def spanned(node: Node, found: list[dict], skip: frozenset | set = frozenset()) -> str:
    """One line of a list item or table cell, its display formulas between double dollars."""
    parts = inline_parts(node.children, found, skip)
    found.extend(p | {"alt": "embedded"} for p in parts if isinstance(p, dict))
    return " ".join(p if isinstance(p, str) else f"$${p['text']}$$" for p in parts)


def units(main: str | None) -> list[dict]:
    """The content list of a content subtree; each node is claimed by one detector."""
    root = parse(main)
    title = next((visible_text(t) for t in root.elements("title")), None)
    out: list[dict] = []
    run: list[Node] = []

    def close(found: list[dict]) -> None:
        out.extend(f for f in found if f["type"] in ("image", "video", "audio"))
        out.extend(f | {"alt": "embedded"} for f in found if f["type"] not in ("image", "video", "audio"))

    def flush() -> None:
        found: list[dict] = []
        out.extend(_unit("paragraph", text=p) if isinstance(p, str) else p for p in inline_parts(run, found))
        run.clear()
        close(found)

    def code_block(nodes: list[Node]) -> None:
        text = "\n".join(x.strip("\n") for x in map(code_text, nodes) if x.strip())
        if text:
            out.append(_unit("code", text=text, lang=guess_language(text)))

    def is_block_code(n: Node) -> bool:
        return n.tag == "pre" or (n.tag in _CODE and "\n" in code_text(n).strip()) or (n.tag in ("div", "figure") and n.children and all(is_block_code(c) or (c.tag == "" and not c.text.strip()) for c in n.children) and any(c.tag for c in n.children))

    def walk(parent: Node) -> None:
        children, k = parent.children, 0
        while k < len(children):
            n = children[k]
            k += 1
            if n.tag in ("head",):
                continue
            if n.tag and is_block_code(n):
                flush()
                near = [n]
                while k < len(children) and (is_block_code(children[k]) or (children[k].tag == "" and not children[k].text.strip()) or children[k].tag == "br"):
                    near.append(children[k])
                    k += 1
                code_block([x for x in near if x.tag not in ("", "br")])
            elif n.tag == "table":
                flush()
                kind = table_kind(n)
                if kind == "nested":
                    out.extend(_unit("paragraph", text=t) for t in linearised(n))
                elif own_rows(n):
                    found: list[dict] = []
                    rows = [[spanned(c, found) for c in r] for r in own_rows(n)] if kind == "simple" else None
                    out.append(_unit("table", rows=rows, html=table_html(n) if kind == "complex" else None))
                    close(found)
            elif n.tag in ("ul", "ol", "dl"):
                flush()
                found = []
                items = [i for i in list_items(n, found) if i["text"]]
                if items:
                    out.append(_unit("list", items=items))
                close(found)
            elif n.tag in _HEAD:
                flush()
                text = visible_text(n)
                if text:
                    out.append(_unit("title", level=1 if text == title else int(n.tag[1]), text=text))
            elif n.tag in BREAK or (n.tag and n.tag not in _CODE and formula_of(n) is None and any(c.tag in BREAK for x in n.children for c in x.walk())):
                flush()
                walk(n)
                flush()
            else:
                run.append(n)

    walk(root)
    flush()
    for k, u in enumerate(out):
        u["seq"] = k
    return out


def escape_cell(text: str) -> str:
    return text.replace("|", "\\|").replace("\n", " ")


def unit_markdown(u: dict) -> str:
    """Markdown of one unit; '' for spans embedded in a paragraph."""
    match u["type"]:
        case "title":
            return f"{'#' * u['level']} {u['text']}"
        case "paragraph":
            return u["text"]
        case "display_formula" if u["alt"] != "embedded":
            return f"$$\n{u['text']}\n$$"
        case "code":
            fence = "`" * max(3, 1 + max(map(len, re.findall(r"`+", u["text"])), default=0))
            return f"{fence}{u['lang'] or ''}\n{u['text']}\n{fence}"
        case "table":
            if u["rows"] is None:
                return u["html"]
            wide = max(map(len, u["rows"]))
            lines = ["| " + " | ".join([*map(escape_cell, r), *[""] * (wide - len(r))]) + " |" for r in u["rows"]]
            return "\n".join([lines[0], "|" + " --- |" * wide, *lines[1:]])
        case "list":
            return "\n".join(f"{'  ' * i['depth']}{'1.' if i['ordered'] else '-'} {i['text']}" for i in u["items"])
        case "image":
            return f"![{u['alt'] or ''}]({u['url'] or ''})"
        case "video" | "audio":
            return f"[{u['alt'] or u['type']}]({u['url'] or ''})"
    return ""


def markdown(us: list[dict], drop: tuple[str, ...] = ()) -> str:
    return "\n\n".join(x for x in (unit_markdown(u) for u in us if u["type"] not in drop) if x)


def plain_text(main: str | None) -> str:
    """One line per unit that has text."""
    lines = []
    for u in units(main):
        if u["type"] in ("title", "paragraph", "code") or (u["type"] == "display_formula" and u["alt"] != "embedded"):
            lines.append(u["text"])
        elif u["type"] == "list":
            lines.extend(i["text"] for i in u["items"])
        elif u["type"] == "table":
            lines.extend(" ".join(r) for r in u["rows"]) if u["rows"] else lines.append(visible_text(parse(u["html"])))
    return "\n".join(lines)
