"""Vectorised pre-tokenisation for byte-level BPE, and a bounded cache of encoded pre-tokens.

The split is that of ``public_tokenizers.PATTERN``: contractions, letter runs, digit runs and other runs
(each with one blank before it), and white space, of which the last character before a word stands apart.
It is computed on code points with run boundaries instead of a regex engine; tests compare it with the regex.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import regex

from mixagg.llm.textkit import Texts, differ, mix, prefix_hash, runs, span_hash

_OTHER, _LETTER, _NUMBER, _SPACE = range(4)

# The endings that an apostrophe takes with it.
CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")

_classes: np.ndarray | None = None


def char_classes() -> np.ndarray:
    global _classes
    if _classes is None:
        points = np.r_[np.arange(0xD800), np.arange(0xE000, 0x110000)].astype("<u4")
        every = points.tobytes().decode("utf-32-le")
        table = np.zeros(0x110000, np.uint8)
        for pattern, kind in ((r"\p{L}+", _LETTER), (r"\p{N}+", _NUMBER), (r"\s+", _SPACE)):
            for m in regex.finditer(pattern, every):
                table[points[m.start() : m.end()]] = kind
        _classes = table
    return _classes


def code_points(texts: Texts) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts and the texts' offsets in them."""
    lead = (texts.data & 0xC0) != 0x80
    count = np.zeros(len(texts.data) + 1, np.int64)
    np.cumsum(lead, out=count[1:])
    points = np.frombuffer(texts.data.tobytes().decode("utf-8").encode("utf-32-le"), np.uint32)
    return points, count[texts.off]


def split_points(cp: np.ndarray, off: np.ndarray) -> np.ndarray:
    """The start of each pre-token in ``cp``; ``off`` are the texts' offsets."""
    n = len(cp)
    if not n:
        return np.zeros(0, np.int64)
    kind = char_classes()[cp]
    edge = np.zeros(n + 1, bool)
    edge[off] = True
    run = np.empty(n, bool)
    run[0], run[1:] = True, kind[1:] != kind[:-1]
    run |= edge[:-1]
    flag = run.copy()
    # white space followed by something else in the same text
    b = np.flatnonzero(run & (kind != _SPACE) & ~edge[:-1])
    b = b[b > 0]
    b = b[kind[b - 1] == _SPACE]
    flag[b - 1] = True
    flag[b[cp[b - 1] == 0x20]] = False
    # an apostrophe that stands alone and starts a token, with letters after it
    p = np.flatnonzero((cp == 0x27) & flag)
    p = p[p + 1 < n]
    p = p[run[p + 1] & (kind[p + 1] == _LETTER) & ~edge[p + 1]]
    if len(p):
        pad = np.r_[cp, np.zeros(3, np.uint32)]
        same = np.r_[~run[1:], False, False, False]  # the next char continues the run
        c1, c2 = pad[p + 1], pad[p + 2]
        two = same[p + 1]
        length = np.zeros(len(p), np.int64)
        for ending in CONTRACTIONS:
            hit = c1 == ord(ending[0])
            if len(ending) == 2:
                hit &= two & (c2 == ord(ending[1]))
            length[hit & (length == 0)] = 1 + len(ending)
        p, length = p[length > 0], length[length > 0]
        flag[p + 1] = False
        after = p + length
        inside = after < n
        after = after[inside]
        flag[after] = True
    return np.flatnonzero(flag)


class Pretokens:
    """The pre-tokens of a batch: byte and code-point starts, content hashes, texts' ranges."""

    def __init__(self, texts: Texts) -> None:
        cp, off = code_points(texts)
        self.cp = cp
        self.start = split_points(cp, off)
        self.end = np.r_[self.start[1:], len(cp)] if len(self.start) else self.start
        # Code points hash as they are, spread over 64 bits first.
        self.hash = span_hash(prefix_hash(mix(cp.astype(np.uint64) + np.uint64(0x51ED270B))), self.start, self.end) if len(cp) else np.zeros(0, np.uint64)
        self.first = np.searchsorted(self.start, off)

    def string(self, i: int) -> str:
        return self.cp[self.start[i] : self.end[i]].tobytes().decode("utf-32-le")


class PretokenCache:
    """Direct-mapped memory from a pre-token to an index into lists the caller keeps.

    A pre-token is looked up by its hash, and its code points are compared with the entry's on every hit, so pre-tokens
    whose hashes collide are told apart.  ``encode(strings)`` makes the entries of pre-tokens not found.  Size is
    bounded: a slot keeps the last pre-token that fell on it, and after ``limit`` entries or ``room`` code points
    everything starts afresh.
    """

    def __init__(self, encode: Callable[[list[str]], list], bits: int = 19, limit: int = 400_000, room: int = 1 << 22) -> None:
        self.encode, self.mask, self.limit, self.room = encode, np.uint64((1 << bits) - 1), limit, room
        self.reset()

    def reset(self) -> None:
        size = int(self.mask) + 1
        self.key = np.zeros(size, np.uint64)
        self.at = np.full(size, -1, np.int64)
        self.entries: list = []
        self.points, self.used = np.zeros(1 << 16, np.uint32), 0  # the entries' code points, one after the other
        self.begin = np.zeros(1 << 12, np.int64)  # of each entry; the next entry's is its end

    def _keep(self, points: np.ndarray, sizes: np.ndarray) -> None:
        """Appends the code points of new entries."""
        base = len(self.entries)
        if self.used + len(points) > len(self.points):
            self.points = np.r_[self.points[: self.used], np.zeros(self.used + len(points), np.uint32)]
        if base + len(sizes) + 1 > len(self.begin):
            self.begin = np.r_[self.begin[: base + 1], np.zeros(base + len(sizes) + 1, np.int64)]
        self.points[self.used : self.used + len(points)] = points
        self.begin[base + 1 : base + 1 + len(sizes)] = self.used + np.cumsum(sizes)
        self.used += len(points)

    def lookup(self, tokens: Pretokens) -> np.ndarray:
        """For each pre-token the index of its entry in ``entries``."""
        if len(self.entries) > self.limit or self.used > self.room:
            self.reset()
        size = tokens.end - tokens.start
        slot = (tokens.hash & self.mask).astype(np.int64)
        out = np.where(self.key[slot] == tokens.hash, self.at[slot], -1)
        hit = np.flatnonzero(out >= 0)
        out[hit[differ(tokens.cp, tokens.start[hit], size[hit], self.points, self.begin[out[hit]], self.begin[out[hit] + 1] - self.begin[out[hit]])]] = -1
        missing = np.flatnonzero(out < 0)
        while len(missing):
            hashes, first, back = np.unique(tokens.hash[missing], return_index=True, return_inverse=True)
            lead = missing[first]
            base = len(self.entries)
            self._keep(tokens.cp[runs(tokens.start[lead], size[lead])], size[lead])
            self.entries.extend(self.encode([tokens.string(i) for i in lead]))
            out[missing] = base + back
            slot = (hashes & self.mask).astype(np.int64)
            self.key[slot], self.at[slot] = hashes, base + np.arange(len(hashes))
            # of several new hashes on one slot numpy keeps the last for both arrays alike
            like = lead[back]
            missing = missing[differ(tokens.cp, tokens.start[missing], size[missing], tokens.cp, tokens.start[like], size[like])]
        return out
