"""Byte-level pair encoding: an exact backtracking encoder and an offset-table decoder.

A vocabulary file of the ``tokenizers`` JSON format gives tokens, merges, added
tokens and the pre-tokenising rule. Encoding a piece never replays merges. An
Aho-Corasick automaton over all tokens gives the longest token that starts at each
byte; the encoder walks these greedily and asks the pair-compatibility table whether
two neighbours could stand side by side in a merged text. If not, it tries the next
shorter token that is a prefix, and goes back one token when none is left. A byte
position that proved unreachable is never tried again, so each position is left at
most once and the work is linear in the piece.

Pieces repeat, so their ids are remembered in a table of bounded size per worker.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache
from itertools import chain

import ahocorasick
import numpy as np
import regex

#: Pre-tokenising pattern of byte-level vocabularies: a fixed value, as published with them.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: The same rule where only these characters occur, which the standard engine runs faster.
_PLAIN = r"A-Za-z\u00C0-\u00D6\u00D8-\u00F6\u00F8-\u017F"
_PLAIN_SPLIT = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[{_PLAIN}]+| ?[0-9]+| ?[^\s0-9{_PLAIN}]+|\s+(?!\S)|\s+").findall
_OTHER = re.compile(rf"[^\t-\r -~{_PLAIN}]").search
_SPLIT = regex.compile(SPLIT).findall
_PIECES_KEPT = 1 << 17
_PAIRS_KEPT = 1 << 17


def _printable_bytes() -> dict[str, int]:
    """Byte-level vocabularies write each byte as one visible character: visible Latin-1
    bytes stand for themselves, the rest are numbered on from U+0100."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


class _Remembered(dict):
    """A table of at most ``2 * most`` entries: when it is full it becomes the older half,
    from which what is asked for again moves back."""

    def __init__(self, make, most: int):
        self.make, self.most, self.older = make, most, {}

    def __missing__(self, key):
        value = self.older.get(key)
        if value is None:
            value = self.make(key)
        if len(self) >= self.most:
            self.older = dict(self)
            self.clear()
        self[key] = value
        return value


def split(text: str) -> list[str]:
    """Pieces of a text; merges never cross their borders."""
    return (_SPLIT if _OTHER(text) else _PLAIN_SPLIT)(text)


class BytePairCoder:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, before = spec["model"], spec.get("pre_tokenizer") or {}
        if model["type"] != "BPE" or before.get("type") != "ByteLevel" or before.get("add_prefix_space") or spec.get("normalizer"):
            raise ValueError(f"not a plain byte-level BPE vocabulary: {path}")
        code = _printable_bytes()
        self.added = {a["content"]: a["id"] for a in spec.get("added_tokens", [])}
        spelled = {t: bytes(code[c] for c in t) for t in model["vocab"]}
        size = 1 + max([*model["vocab"].values(), *self.added.values()])
        self.tokens: list[bytes] = [b""] * size
        for t, i in model["vocab"].items():
            self.tokens[i] = spelled[t]
        for t, i in self.added.items():
            self.tokens[i] = t.encode()
        ids = {b: model["vocab"][t] for t, b in spelled.items()}
        self.ids = ids
        self.added_split = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self.merges = model["merges"]
        self.pieces = _Remembered(self._piece, _PIECES_KEPT)
        self.pairs = _Remembered(self._compatible, _PAIRS_KEPT)
        self.matcher = None  # made with the first text that is encoded: decoding needs the tokens alone
        # Decoding table: all tokens one after another, and where each begins.
        self.blob = np.frombuffer(b"".join(self.tokens), np.uint8)
        self.begins = np.zeros(size + 1, np.int64)
        np.cumsum([len(t) for t in self.tokens], out=self.begins[1:])

    def _prepare(self) -> None:
        code, ids = _printable_bytes(), self.ids
        # Of each token the two halves of its merge; of each adjacent pair the rank at which it merges.
        self.halves: dict[int, tuple[int, int]] = {}
        self.joins: dict[tuple[int, int], int] = {}
        self.rank = [-1] * len(self.tokens)
        for rank, pair in enumerate(self.merges):
            left, right = (ids.get(bytes(code[c] for c in x), -1) for x in (pair.split(" ") if isinstance(pair, str) else pair))
            whole = ids.get(self.tokens[left] + self.tokens[right], -1)
            if min(left, right, whole) < 0:
                continue
            self.joins.setdefault((left, right), rank)
            if whole not in self.halves:
                self.halves[whole], self.rank[whole] = (left, right), rank
        matcher = ahocorasick.Automaton()
        for b, i in ids.items():
            matcher.add_word(b.decode("latin-1"), (len(b), i))
        matcher.make_automaton()
        self.matcher = matcher
        self.merges = None

    def _compatible(self, pair: tuple[int, int]) -> bool:
        """Whether neighbours (a, b) stay apart: walking back through the merges that
        made them, latest first, no pair that ever touched at their border merges before
        one of the two sides was completed."""
        a, b = pair
        last = len(self.joins)
        while True:
            met = self.joins.get((a, b))
            if met is not None and met < last:
                return False
            ra, rb = self.rank[a], self.rank[b]
            if ra < 0 and rb < 0:
                return True
            if ra > rb:  # a was made later: before that, its right half touched b
                last, a = ra, self.halves[a][1]
            else:  # at b's own rank a merge further left comes first, so that rank counts too
                last, b = rb + 1, self.halves[b][0]

    def _piece(self, piece: str) -> tuple[int, ...]:
        if self.matcher is None:
            self._prepare()
        raw = piece.encode("utf-8", "surrogatepass")
        whole = self.ids.get(raw)
        if whole is not None and (len(raw) == 1 or self.rank[whole] >= 0):
            return (whole,)
        return tuple(self.backtrack(raw))

    def backtrack(self, raw: bytes) -> list[int]:
        n = len(raw)
        starting: list[list[tuple[int, int]]] = [[] for _ in range(n)]
        for end, match in self.matcher.iter(raw.decode("latin-1")):
            starting[end - match[0] + 1].append(match)  # of one start, shorter ones come first
        dead = bytearray(n + 1)
        ids: list[int] = []
        ends = [0]
        left = [len(starting[0]) if n else 0]  # candidates of the current start that are not yet tried
        pairs = self.pairs
        while ends[-1] < n:
            at, tried = ends[-1], left[-1]
            here = starting[at]
            while tried:
                tried -= 1
                size, token = here[tried]
                if not dead[at + size] and (not ids or pairs[ids[-1], token]):
                    left[-1] = tried
                    ids.append(token)
                    ends.append(at + size)
                    left.append(len(starting[at + size]) if at + size < n else 0)
                    break
            else:
                if not ids:
                    raise ValueError("the vocabulary lacks a byte of the text")
                dead[at] = 1
                ids.pop(), ends.pop(), left.pop()
        return ids

    def encode(self, text: str) -> list[int]:
        if self.added_split is not None and any(t in text for t in self.added):
            out: list[int] = []
            for k, part in enumerate(self.added_split.split(text)):
                out += [self.added[part]] if k % 2 else self._plain(part)
            return out
        return self._plain(text)

    def _plain(self, text: str) -> list[int]:
        return list(chain.from_iterable(map(self.pieces.__getitem__, split(text))))

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        """Bytes of all tokens, gathered by their places in the offset table."""
        if not len(ids):
            return b""
        begins = self.begins[ids]
        sizes = self.begins[ids + 1] - begins
        total = np.cumsum(sizes)
        at = np.arange(total[-1])
        at += np.repeat(begins - (total - sizes), sizes)
        return self.blob[at].tobytes()

    def decode(self, ids) -> str:
        return self.decode_bytes(np.asarray(ids, np.int64)).decode("utf-8", "replace")

    def spans(self, text: str, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First character and end (exclusive) of each token; a token that begins inside a
        character counts from that character, one that ends inside it reaches its end."""
        sizes = self.begins[ids + 1] - self.begins[ids]
        end = np.cumsum(sizes)
        raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
        leads = np.zeros(len(raw) + 1, np.int64)
        np.cumsum((raw & 0xC0) != 0x80, out=leads[1:])
        start = end - sizes
        first = leads[np.minimum(start + 1, len(raw))] - 1
        return np.maximum(first, 0), leads[end]


@lru_cache(maxsize=4)
def coder(path: str) -> BytePairCoder:
    """One coder per vocabulary and worker process."""
    return BytePairCoder(path)


class FastIds:
    """The same ids through a native library where only ids are needed, not the method.

    Where no two blanks are neighbours, the rule needs no look-ahead and a pattern without
    one splits alike and faster. Very long runs of blanks, on which the native library's
    engine gives up, take the exact encoder.
    """

    _LONG_BLANK = re.compile(r"\s{5000}").search
    _BLANKS = re.compile(r"\s\s").search

    def __init__(self, path: str):
        import tiktoken

        self.exact = coder(path)
        ranks = dict(self.exact.ids)
        self.native = tiktoken.Encoding("runs", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})
        self.single = tiktoken.Encoding("single", pat_str=SPLIT.replace(r"\s+(?!\S)|\s+", r"\s"), mergeable_ranks=ranks, special_tokens={})
        self.special = tuple(self.exact.added)

    def listed(self, text: str) -> list[int]:
        if any(t in text for t in self.special):
            return self.exact.encode(text)
        if not self._BLANKS(text):
            return self.single.encode_ordinary(text)
        if len(text) > 5000 and self._LONG_BLANK(text):
            return self.exact.encode(text)
        return self.native.encode_ordinary(text)

    def __call__(self, text: str) -> np.ndarray:
        return np.array(self.listed(text), np.uint32)

    def count(self, text: str) -> int:
        return len(self.listed(text))


@lru_cache(maxsize=4)
def fast_ids(path: str) -> FastIds:
    return FastIds(path)
