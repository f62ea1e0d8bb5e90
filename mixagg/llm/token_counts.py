"""Token counts that follow edits.

A document is kept as a segment tree whose leaves are blocks of pre-tokens and whose nodes hold (characters, tokens).
An edit walks down to the pre-tokens it touches, re-splits from a little before them (the pattern looks at most a few
characters ahead) until a new boundary falls on an old one beyond the edit, re-encodes only that stretch and updates
the sums on the paths to the root.

Defined cases: a null text is empty; null or empty edit lists leave the count; positions beyond the text's end are
clipped to it, negative ones to its start; edits apply in order, each to the text the former ones left; extra columns
are ignored; repeated rows are counted as often as they occur; an empty table gives no rows.
"""

from __future__ import annotations

from bisect import bisect_right
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
import regex
import tiktoken
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm.byte_bpe import read_ranks
from mixagg.llm.pretokens import PretokenCache, Pretokens
from mixagg.llm.textkit import over_texts

BLOCK, LOOKAHEAD = 64, 4
EDITS = "array<struct<pos:int,n_del:int,ins:string>>"


class Counter:
    """Counts tokens of pre-tokens; the cache's entries are the counts."""

    def __init__(self, path: str, pattern: str) -> None:
        self.pattern = regex.compile(pattern)
        encode = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=read_ranks(path), special_tokens={}).encode_ordinary
        self.cache = PretokenCache(lambda tokens: [len(encode(t)) for t in tokens])
        self.count = lru_cache(maxsize=100_000)(lambda token: len(encode(token)))


@lru_cache(maxsize=2)
def counter(path: str, pattern: str) -> Counter:
    return Counter(path, pattern)


class TokenTree:
    """Sums of characters and tokens over blocks of a document's pre-tokens."""

    def __init__(self, text: str, lengths: np.ndarray, counts: np.ndarray, counter: Counter) -> None:
        self.text, self.counter, self.reencoded = text, counter, 0
        self.blocks = [(lengths[i : i + BLOCK].tolist(), counts[i : i + BLOCK].tolist()) for i in range(0, len(lengths), BLOCK)] or [([], [])]
        self._build()

    def _build(self) -> None:
        self.size = 1 << max(0, (len(self.blocks) - 1).bit_length())
        self.chars, self.tokens = [0] * (2 * self.size), [0] * (2 * self.size)
        for i, (a, b) in enumerate(self.blocks):
            self.chars[self.size + i], self.tokens[self.size + i] = sum(a), sum(b)
        for i in range(self.size - 1, 0, -1):
            self._sum(i)

    def _sum(self, i: int) -> None:
        self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
        self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    def prefix(self, chars: int) -> int:
        """Tokens of the pre-tokens that end at or before a character position."""
        block, start, tokens = self._find(chars)
        for n, t in zip(*self.blocks[block]):
            if start + n > chars:
                break
            start, tokens = start + n, tokens + t
        return tokens

    def _find(self, at: int) -> tuple[int, int, int]:
        """The last block that starts at or before a position: its index, its start and the tokens before it."""
        i, start, tokens = 1, 0, 0
        while i < self.size:
            left = 2 * i
            if start + self.chars[left] <= at and self.chars[left + 1]:
                start, tokens, i = start + self.chars[left], tokens + self.tokens[left], left + 1
            else:
                i = left
        return i - self.size, start, tokens

    def edit(self, pos: int, n_del: int, ins: str) -> None:
        old = self.text
        pos = min(max(pos, 0), len(old))
        stop = min(pos + max(n_del, 0), len(old))
        self.text = new = old[:pos] + ins + old[stop:]
        shift = len(new) - len(old)
        block, start, _ = self._find(max(pos - LOOKAHEAD - 1, 0))
        ends = list(accumulate(self.blocks[block][0], initial=start))
        first = min(max(bisect_right(ends, pos - LOOKAHEAD - 1) - 1, 0), max(len(ends) - 2, 0))  # its end reaches pos - LOOKAHEAD
        begin = ends[first]
        # old boundaries from the first touched pre-token on, walked as the new ones come
        b, i, at = block, first, begin
        lengths, counts = [], []
        resync = False
        for m in self.counter.pattern.finditer(new, begin):
            p = m.start()
            if p >= pos + len(ins):
                while at < p - shift and b < len(self.blocks):
                    if i < len(self.blocks[b][0]):
                        at += self.blocks[b][0][i]
                        i += 1
                    else:
                        b, i = b + 1, 0
                if at == p - shift and at >= stop:
                    resync = True
                    break
            lengths.append(m.end() - p)
            counts.append(self.counter.count(m.group()))
        self.reencoded += sum(lengths)
        if not resync:
            b, i = len(self.blocks) - 1, len(self.blocks[-1][0])
        if b == block:
            rest = tuple(x[i:] for x in self.blocks[b])
            touched = [block]
        else:
            if b < len(self.blocks):
                self.blocks[b] = tuple(x[i:] for x in self.blocks[b])
            for j in range(block + 1, min(b, len(self.blocks))):
                self.blocks[j] = ([], [])
            rest, touched = ([], []), list(range(block, min(b + 1, len(self.blocks))))
        head = tuple(x[:first] for x in self.blocks[block])
        self.blocks[block] = (head[0] + lengths + rest[0], head[1] + counts + rest[1])
        if len(self.blocks[block][0]) > 4 * BLOCK:
            flat = [sum((x[k] for x in self.blocks), []) for k in (0, 1)]
            self.blocks = [(flat[0][j : j + BLOCK], flat[1][j : j + BLOCK]) for j in range(0, len(flat[0]), BLOCK)]
            self._build()
            return
        for j in touched:
            k = self.size + j
            self.chars[k], self.tokens[k] = sum(self.blocks[j][0]), sum(self.blocks[j][1])
        parents = {(self.size + j) // 2 for j in touched}
        while parents and parents != {0}:
            for k in sorted(parents, reverse=True):
                self._sum(k)
            parents = {k // 2 for k in parents}


def count_with_edits(docs: DataFrame, tokenizer: str, pattern: str, id_col: str = "doc_id", text: str = "text", edits: str = "edits") -> DataFrame:
    """Per document: tokens before and after its edits, how many edits, the text's characters and those re-encoded.

    ``edits`` is an array of structs (pos, n_del, ins) in characters; see ``with_edits`` for edits in a table.
    """
    kind = docs.schema[id_col].dataType.simpleString()

    def run(part, texts):
        tool = counter(tokenizer, pattern)
        tokens = Pretokens(texts)
        entries = tool.cache.entries
        at = tool.cache.lookup(tokens)
        entries = tool.cache.entries
        counts = np.fromiter((entries[i] for i in at.tolist()), np.int64, len(at))
        lengths = tokens.end - tokens.start
        rows = []
        bounds = tokens.first.tolist()
        for k, (doc, body, changes) in enumerate(zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(2).to_pylist())):
            a, b = bounds[k], bounds[k + 1]
            tree = TokenTree(body or "", lengths[a:b], counts[a:b], tool)
            before = tree.total
            for e in changes or []:
                tree.edit(e["pos"] or 0, e["n_del"] or 0, e["ins"] or "")
            rows.append((doc, before, len(changes or []), tree.total, b - a, len(tree.text), tree.reencoded))
        columns = list(zip(*rows))
        return pa.record_batch([pa.array(columns[0], part.schema.field(0).type), *(pa.array(c, pa.int64()) for c in columns[1:])], ["id", "n_tokens", "n_edits", "n_tokens_after", "n_pretokens", "n_chars_after", "n_reencoded"])

    out = docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"), F.col(edits).cast(EDITS).alias("edits")).mapInArrow(
        over_texts(run), f"id {kind}, n_tokens long, n_edits long, n_tokens_after long, n_pretokens long, n_chars_after long, n_reencoded long")
    return out.withColumnRenamed("id", id_col)


def with_edits(docs: DataFrame, edits: DataFrame, id_col: str = "doc_id", order: str = "seq") -> DataFrame:
    """``docs`` with each document's rows of ``edits`` (id, order, pos, n_del, ins) as an array column ``edits``."""
    lists = edits.groupBy(id_col).agg(F.transform(F.sort_array(F.collect_list(F.struct(order, "pos", "n_del", "ins"))), lambda e: F.struct(e["pos"].alias("pos"), e["n_del"].alias("n_del"), e["ins"].alias("ins"))).alias("edits"))
    return docs.join(lists, id_col, "left")


def revision_edits(text="text", id_col="doc_id"):
    """A revision of each document as edits: a word put in near its middle, a stretch removed, an ending added."""
    n = F.length(F.coalesce(F.col(text), F.lit("")))
    h = F.pmod(F.xxhash64(F.col(id_col)), F.greatest(n, F.lit(1))).cast("int")
    edit = lambda p, d, s: F.struct(p.cast("int").alias("pos"), F.lit(d).alias("n_del"), F.lit(s).alias("ins"))
    return F.array(edit(F.floor(n / 2), 0, " revised"), edit(h, 17, ""), edit(F.floor(h / 3), 3, "it's 42\n"), edit(n, 0, "\nEnd of revision."))
