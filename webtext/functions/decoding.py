"""Constrained decoding of block labels (L70-L76): an automaton whose only freedom is one of two words a block."""

from __future__ import annotations

import json
import math
from collections.abc import Callable, Sequence

MAIN, OTHER = "main", "other"
#: The toy vocabulary: structural symbols, digits, the two words, and some words that must never come out.
VOCAB = ("{", "}", '"', ":", ",", " ", *"0123456789", MAIN, OTHER, "<end>", "the", "content", "null", "[", "]")
ID = {t: i for i, t in enumerate(VOCAB)}


class Machine:
    """States are (block, phase); a phase is a place in the text that one label takes up."""

    def __init__(self, n: int):
        self.n, self.block, self.phase, self.digit = n, 0, "open", 0

    def allowed(self) -> tuple[str, ...]:
        match self.phase:
            case "open":
                return ("{",)
            case "key":
                return (str(self.block)[self.digit],)
            case "choice":
                return (MAIN, OTHER)
            case "key quote" | "key end" | "value quote" | "value end":
                return ('"',)
            case "colon":
                return (":",)
            case "next":
                return (",",) if self.block < self.n else ("}",)
            case "end":
                return ("<end>",)
        return ()

    def step(self, token: str) -> None:
        if token not in self.allowed():
            raise ValueError(f"{token!r} cannot follow here")
        match self.phase:
            case "open":
                self.block, self.phase = (1, "key quote") if self.n else (0, "next")
            case "key quote":
                self.phase, self.digit = "key", 0
            case "key":
                self.digit += 1
                if self.digit == len(str(self.block)):
                    self.phase = "key end"
            case "key end":
                self.phase = "colon"
            case "colon":
                self.phase = "value quote"
            case "value quote":
                self.phase = "choice"
            case "choice":
                self.phase = "value end"
            case "value end":
                self.phase = "next"
            case "next":
                if token == "}":
                    self.phase = "end"
                else:
                    self.block, self.phase = self.block + 1, "key quote"
            case "end":
                self.phase = "done"


def _better(main: float, other: float) -> str:
    """main if its logit is greater; ties and values that are no numbers give other."""
    return MAIN if not math.isnan(main) and (main > other or math.isnan(other)) else OTHER


Logits = Callable[[list[str], int], Sequence[float]]


def decode(n: int, logits: Logits, mode: str = "fsm", most: int | None = None) -> str:
    """The text of n labels. fsm: masked; fast: forced tokens are skipped; free: no mask (may be malformed)."""
    if mode == "fast":
        labels = []
        for k in range(1, n + 1):
            z = logits([], k)
            labels.append(_better(z[ID[MAIN]], z[ID[OTHER]]))
        return "{" + ",".join(f'"{k}":"{x}"' for k, x in enumerate(labels, 1)) + "}"
    out: list[str] = []
    if mode == "free":
        while len(out) < (most or 12 * n + 8):
            z = logits(out, 0)
            best = max(range(len(VOCAB)), key=lambda i: (-math.inf if math.isnan(z[i]) else z[i], -i))
            if VOCAB[best] == "<end>":
                break
            out.append(VOCAB[best])
        return "".join(out)
    machine = Machine(n)
    while (allowed := machine.allowed()) and allowed != ("<end>",):
        if len(allowed) == 1:
            token = allowed[0]
        else:
            z = logits(out, machine.block)
            token = _better(z[ID[MAIN]], z[ID[OTHER]])
        machine.step(token)
        out.append(token)
    return "".join(out)


def block_logits(scores: list[tuple[float, float]]) -> Logits:
    """Logits over VOCAB that depend on the block only."""
    rows = []
    for other, main in scores:
        row = [-math.inf] * len(VOCAB)
        row[ID[OTHER]], row[ID[MAIN]] = other, main
        rows.append(row)
    return lambda prefix, block: rows[block - 1]


def labels_of(wire: str, n: int) -> tuple[list[int], int]:
    """0 or 1 for each of n blocks, and how many labels were missing (they count as other)."""
    try:
        got = json.loads(wire)
    except (ValueError, RecursionError):
        got = {}
    got = got if isinstance(got, dict) else {}
    return [int(got.get(str(k)) == MAIN) for k in range(1, n + 1)], sum(str(k) not in got for k in range(1, n + 1))


class _Pairs(list):
    """The pairs of an object; arrays are plain lists, whatever they hold."""


def valid(wire: str, n: int) -> bool:
    """Keys 1..n once each, in order, and values of the two words."""
    try:
        pairs = json.loads(wire, object_pairs_hook=_Pairs)
    except (ValueError, RecursionError):
        return False
    return isinstance(pairs, _Pairs) and [k for k, _ in pairs] == [str(k) for k in range(1, n + 1)] and all(v in (MAIN, OTHER) for _, v in pairs) if n else wire == "{}"
