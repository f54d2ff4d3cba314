"""BPE encoding and decoding by dynamic programming over prefixes.

For every prefix of a piece exactly one token can be the last one of its encoding. A suffix automaton of the vocabulary
(states are prefixes of tokens, failure links lead to the longest proper suffix that is a state) is read byte by byte; its
state yields all tokens that end at a position, longest first. A token is the last one iff it spans the whole
prefix or fits behind the (already known) last token of the prefix before it. Whether two tokens fit
is decided on the merge trees alone. Back-pointers then give the ids. Time is linear in the text,
whatever its pieces look like; no merge queue is kept.

Pieces not seen lately go through the automaton together, one byte of each at a time, as arrays; pieces beyond `TOGETHER`
bytes take the same steps one by one. What is remembered is bounded: `room` pieces, and a table of fixed size for pairs.

Edge cases: null text counts as empty; an empty text has no ids and decodes to the empty text; ids
that the vocabulary lacks decode to nothing; bytes that are not UTF-8 decode to U+FFFD. Equal rows
give equal results; other columns, whatever their names, are left as they are.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column
from pyspark.sql import functions as F

_NEVER = 1 << 60
#: Pieces of at most so many bytes are taken together.
TOGETHER = 64
#: Remembered pairs are a power of two.
_PAIR_BITS = 19
_ODD = np.uint64(0x9E3779B97F4A7C15)
# White space of the tokenizer's splitting rule, and the rule itself. Letters come first, which
# changes no match as no other branch can start with a letter, or with a space and a letter.
_WS = r"\t-\r \x85\xa0  -     　"
_RULE = " ?[{letter}]+|'s|'t|'re|'ve|'m|'ll|'d| ?[{digit}]+| ?[^{ws}{letter}{digit}]+|[{ws}]+(?![^{ws}])|[{ws}]+"
#: Letters of the Latin blocks; texts that hold nothing else beyond ASCII take the faster of two equal patterns.
_LATIN = "À-ÖØ-öø-ʯ"


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = (b for b in range(256) if b not in set(plain))
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


class Automaton:
    """The suffix automaton of the tokens and the test whether two tokens may stand side by side, as arrays."""

    def __init__(self, bytes_of: dict[int, bytes], made: dict[int, tuple[int, int, int]], rank: dict[int, int]):
        tokens = max(bytes_of) + 1
        pairs = sorted(rank.items())
        self.merge, self.merge_rank = np.array([k for k, _ in pairs] or [-1], np.int64), np.array([r for _, r in pairs] or [0], np.int64)
        order = sorted(bytes_of, key=lambda t: made.get(t, (0, 0, -1))[2])
        self.right, self.left = self._spines(order, made, tokens, 1), self._spines(order, made, tokens, 0)
        self.seen, self.seen_fits = np.full(1 << _PAIR_BITS, -1, np.int64), np.zeros(1 << _PAIR_BITS, bool)
        built = np.array([t for t in order if t in made], np.int64)
        a, b, r = (np.array([made[t][k] for t in built.tolist()], np.int64) for k in range(3))
        whole = set(order) - set(built[~self.fits(a, b, r)].tolist()) if len(built) else set(order)
        self._states(bytes_of, whole, tokens)

    @staticmethod
    def _spines(order: list[int], made: dict, tokens: int, side: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start per token, nodes and ranks: the nodes on one edge of its merge tree, leaf first, each with the rank at which it is merged away."""
        start, nodes, gone = np.zeros(tokens, np.int64), [], []
        for token in order:
            own, ranks = [token], [_NEVER]
            while own[-1] in made:
                ranks.append(made[own[-1]][2])
                own.append(made[own[-1]][side])
            start[token] = len(nodes)
            nodes += own[::-1]
            gone += ranks[::-1]
        return start, np.array(nodes, np.int64), np.array(gone, np.int64)

    def _states(self, bytes_of: dict[int, bytes], whole: set[int], tokens: int) -> None:
        """goto by (state << 8 | byte), failure links, the longest token that ends in each state, and the next shorter one of each token."""
        goto: dict[int, int] = {}
        end, parents = {}, [(0, 0)]
        for token in whole:
            state = 0
            for byte in bytes_of[token]:
                key = state << 8 | byte
                if key not in goto:
                    goto[key] = len(parents)
                    parents.append((state, byte))
                state = goto[key]
            end.setdefault(state, token)
        depth = [0] * len(parents)
        for state in range(1, len(parents)):
            depth[state] = depth[parents[state][0]] + 1
        fail, out = [0] * len(parents), [-1] * len(parents)
        link = np.full(tokens, -1, np.int64)
        for state in sorted(range(1, len(parents)), key=depth.__getitem__):
            above, byte = parents[state]
            if above:
                at = fail[above]
                while at and at << 8 | byte not in goto:
                    at = fail[at]
                fail[state] = goto.get(at << 8 | byte, 0)
            out[state] = out[fail[state]]
            if state in end:
                link[end[state]] = out[state]
                out[state] = end[state]
        edges = sorted(goto.items())
        self.goto, self.edge, self.child = goto, np.array([k for k, _ in edges], np.int64), np.array([c for _, c in edges], np.int64)
        self.fail, self.out, self.link = np.array(fail, np.int64), np.array(out, np.int64), link
        self.size = np.zeros(tokens, np.int64)
        for token, text in bytes_of.items():
            self.size[token] = len(text)

    def step(self, state: np.ndarray, byte: np.ndarray) -> np.ndarray:
        """The states after one byte each."""
        state, todo = state.copy(), np.arange(len(state))
        while len(todo):
            key = state[todo] << 8 | byte[todo]
            at = np.minimum(np.searchsorted(self.edge, key), len(self.edge) - 1)
            hit = self.edge[at] == key
            lost = ~hit & (state[todo] == 0)
            state[todo[hit]] = self.child[at[hit]]
            todo = todo[~hit & ~lost]
            state[todo] = self.fail[state[todo]]
        return state

    def fits(self, a: np.ndarray, b: np.ndarray, before: np.ndarray | None = None) -> np.ndarray:
        """No merge across the border of a and b happens (before the given rank) while both of its parts exist.

        Of equal merges the left one goes first, so a part of a that is merged at the same rank is gone,
        and a part of b is not.
        """
        (r_start, r_node, r_gone), (l_start, l_node, l_gone) = self.right, self.left
        i, j = r_start[a], l_start[b]
        out, todo = np.ones(len(i), bool), np.arange(len(i))
        limit = np.full(len(i), _NEVER) if before is None else before
        while len(todo):
            key = r_node[i] << 20 | l_node[j]
            at = np.minimum(np.searchsorted(self.merge, key), len(self.merge) - 1)
            r = np.where(self.merge[at] == key, self.merge_rank[at], _NEVER)
            x, y = r_gone[i], l_gone[j]
            bad = (r < limit) & (r < x) & (r <= y)
            out[todo[bad]] = False
            go = ~bad & ((x > y) | (x < _NEVER))
            up = x <= y
            i, j, todo, limit = (i + up)[go], (j + ~up)[go], todo[go], limit[go]
        return out

    def pair(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """fits, remembered in a table whose slots newer pairs take over."""
        key = a << 20 | b
        slot = (key.astype(np.uint64) * _ODD >> np.uint64(64 - _PAIR_BITS)).astype(np.int64)
        out = self.seen_fits[slot]
        new = np.flatnonzero(self.seen[slot] != key)
        if len(new):
            unique, back = np.unique(key[new], return_inverse=True)
            found = self.fits(unique >> 20, unique & 0xFFFFF)
            out[new] = found[back]
            slots = (unique.astype(np.uint64) * _ODD >> np.uint64(64 - _PAIR_BITS)).astype(np.int64)
            last = np.unique(slots[::-1], return_index=True)[1]
            keep = len(slots) - 1 - last
            self.seen[slots[keep]], self.seen_fits[slots[keep]] = unique[keep], found[keep]
        return out

    def walk(self, raw: bytes) -> np.ndarray:
        """The ids of one piece, byte by byte."""
        token_at, state = [], 0
        goto, fail, known = self.goto, self.fail, {}
        for e, byte in enumerate(raw):
            while (to := goto.get(state << 8 | byte)) is None and state:
                state = int(fail[state])
            state = to or 0
            token = int(self.out[state])
            while (size := int(self.size[token])) <= e:
                key = token_at[e - size] << 20 | token
                if key not in known:
                    if len(known) > 100_000:
                        known.clear()
                    known[key] = bool(self.fits(np.array([key >> 20]), np.array([token]))[0])
                if known[key]:
                    break
                token = int(self.link[token])
            token_at.append(token)
        ids, end = [], len(raw) - 1
        while end >= 0:
            ids.append(token_at[end])
            end -= int(self.size[token_at[end]])
        return np.array(ids[::-1], np.int32)

    def walk_all(self, raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids right-aligned in rows, their number) of pieces sorted from long to short."""
        sizes = np.fromiter(map(len, raws), np.int64, len(raws))
        wide = int(sizes[0])
        text = np.zeros((len(raws), wide), np.uint8)
        text[np.arange(wide) < sizes[:, None]] = np.frombuffer(b"".join(raws), np.uint8)
        text = np.ascontiguousarray(text.T).astype(np.int64)
        token_at, state = np.zeros((wide, len(raws)), np.int64), np.zeros(len(raws), np.int64)
        for e in range(wide):
            n = int(np.searchsorted(-sizes, -e))  # the pieces longer than e
            state = self.step(state[:n], text[e, :n])
            row, token = np.arange(n), self.out[state]
            while True:
                inner = np.flatnonzero(self.size[token] <= e)
                if not len(inner):
                    break
                before = token_at[e - self.size[token[inner]], row[inner]]
                no = ~self.pair(before, token[inner])
                done = np.ones(len(row), bool)
                done[inner[no]] = False
                token_at[e, row[done]] = token[done]
                row, token = row[~done], self.link[token[~done]]
            token_at[e, row] = token
        ids, end, number, each = np.zeros((len(raws), wide), np.int32), sizes - 1, np.zeros(len(raws), np.int64), np.flatnonzero(sizes)
        while len(each):
            number[each] += 1
            token = token_at[end[each], each]
            ids[each, wide - number[each]] = token
            end[each] -= self.size[token]
            each = each[end[each] >= 0]
        return ids, number


class Encoder(dict):
    """piece -> ids as the bytes of an int32 array, remembering at most `room` pieces (and those of the texts in hand)."""

    def __init__(self, path: str, room: int = 250_000):
        super().__init__()
        self.room = room
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet = byte_alphabet()
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        bytes_of = {i: bytes(alphabet[c] for c in t) for t, i in vocab.items()}
        rank: dict[int, int] = {}
        made: dict[int, tuple[int, int, int]] = {}
        for r, pair in enumerate(merges):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            x, y = vocab[a], vocab[b]
            rank.setdefault(x << 20 | y, r)
            made.setdefault(vocab[a + b], (x, y, r))
        self.automaton = Automaton(bytes_of, made, rank)
        self.specials = {}
        for t in spec.get("added_tokens") or []:
            self.specials[t["content"]] = t["id"]
            bytes_of[t["id"]] = t["content"].encode()
        self.cut_specials = re.compile("|".join(map(re.escape, sorted(self.specials, key=len, reverse=True))) or r"(?!)")
        self.pieces = regex.compile(_RULE.format(letter=r"\p{L}", digit=r"\p{N}", ws=_WS))
        self.latin_pieces = re.compile(_RULE.format(letter=f"A-Za-z{_LATIN}", digit="0-9", ws=_WS))
        self.beyond_latin = re.compile(f"[^\x00-\x7f{_LATIN}]")
        every = [bytes_of.get(i, b"") for i in range(max(bytes_of) + 1)]
        self.token_bytes = np.frombuffer(b"".join(every), np.uint8)
        self.token_size = np.array([len(x) for x in every] + [0], np.int64)
        self.token_start = np.concatenate([[0], np.cumsum(self.token_size[:-1])])

    def forget(self) -> None:
        self.clear()
        for token in self.specials.values():
            ids = np.int32(token).tobytes()
            self[ids] = ids

    def learn(self, pieces: list[str]) -> None:
        """Encodes pieces, equal lengths side by side."""
        raws = sorted((p.encode() for p in pieces), key=len, reverse=True)
        while raws and len(raws[0]) > TOGETHER:
            raw = raws.pop(0)
            self[raw.decode()] = self.automaton.walk(raw).tobytes()
        if raws:
            ids, number = self.automaton.walk_all(raws)
            flat, row = ids.tobytes(), 4 * ids.shape[1]
            for k, (raw, n) in enumerate(zip(raws, number.tolist(), strict=True)):
                self[raw.decode()] = flat[(k + 1) * row - 4 * n : (k + 1) * row]

    def split(self, text: str) -> list[str | bytes]:
        """Pieces of the text; special tokens as their ids."""
        rule = self.pieces if self.beyond_latin.search(text) else self.latin_pieces
        out, at = [], 0
        for hit in self.cut_specials.finditer(text):
            out += rule.findall(text[at : hit.start()])
            out.append(np.int32(self.specials[hit[0]]).tobytes())
            at = hit.end()
        out += rule.findall(text[at:] if at else text)
        return out

    def encode_all(self, texts: list[str]) -> list[np.ndarray]:
        """The ids of each text; texts are taken together up to about a million characters."""
        out, held, size = [], [], 0
        for k, text in enumerate(texts):
            held.append(self.split(text))
            size += len(text)
            if size > 1_000_000 or k == len(texts) - 1:
                if not self or len(self) > self.room:
                    self.forget()
                if new := set().union(*held).difference(self):
                    self.learn(list(new))
                out += [np.frombuffer(b"".join(map(self.__getitem__, pieces)), np.int32) for pieces in held]
                held, size = [], 0
        return out

    def encode(self, text: str) -> np.ndarray:
        return self.encode_all([text])[0]

    def spelled(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes of the ids, one after the other, and where those of each begin (with the end of all)."""
        known = np.where((ids >= 0) & (ids < len(self.token_start) - 1), ids, len(self.token_start) - 1)
        size = self.token_size[known]
        at = np.concatenate([[0], np.cumsum(size)])
        return self.token_bytes[np.arange(at[-1]) + np.repeat(self.token_start[known] - at[:-1], size)], at

    def decode(self, ids: list[int]) -> str:
        return self.spelled(np.array(ids, np.int64))[0].tobytes().decode("utf-8", "replace")


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One encoder for each worker process."""
    return Encoder(path)


def bpe_encode(text: Column | str, path: str) -> Column:
    """array<int> of the ids of each text."""

    @F.arrow_udf("array<int>")
    def ids(column: pa.Array) -> pa.Array:
        e, found, held, size = encoder(path), [], [], 0
        for k, value in enumerate(column):  # a stretch of texts at a time is a Python string
            held.append(value.as_py() or "")
            size += len(held[-1])
            if size > 4_000_000 or k == len(column) - 1:
                found += e.encode_all(held)
                held, size = [], 0
        offsets = np.concatenate([[0], np.cumsum([len(x) for x in found])]).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(found) if found else np.zeros(0, np.int32)))

    return ids(text)


def bpe_decode(ids: Column | str, path: str) -> Column:
    """The text of each array of ids; null for null."""

    def spelled(e: Encoder, column: pa.ListArray) -> pa.Array:
        values = column.flatten().to_numpy(zero_copy_only=False)
        sizes = np.nan_to_num(column.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
        raw, at = e.spelled(values)
        starts = at[np.concatenate([[0], np.cumsum(sizes)])]
        data = raw.tobytes()
        try:
            data.decode()
        except UnicodeDecodeError:
            whole = False
        else:
            inner = starts[(starts > 0) & (starts < len(raw))]
            whole = not ((raw[inner] & 0xC0) == 0x80).any()  # no text begins within a character
        if whole:
            mask = None if not column.null_count else column.is_valid().cast(pa.uint8()).to_numpy(zero_copy_only=False)
            valid = None if mask is None else pa.py_buffer(np.packbits(mask, bitorder="little").tobytes())
            return pa.Array.from_buffers(pa.string(), len(column), [valid, pa.py_buffer(starts.astype(np.int32).tobytes()), pa.py_buffer(data)], null_count=column.null_count)
        texts = (data[a:b].decode("utf-8", "replace") for a, b in zip(starts[:-1].tolist(), starts[1:].tolist(), strict=True))
        return pa.array([t if v.is_valid else None for t, v in zip(texts, column, strict=True)], pa.string())

    @F.arrow_udf("string")
    def text(column: pa.Array) -> pa.Array:
        e, step = encoder(path), 500
        parts = [spelled(e, column.slice(k, step)) for k in range(0, len(column), step)]
        return pa.concat_arrays(parts) if parts else pa.array([], pa.string())

    return text(ids)
