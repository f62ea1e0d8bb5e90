"""Bounded-space online packing of token pieces into fixed windows.

Each partition keeps ``open_windows`` windows open: a piece goes to the open window that it fills best; if none has
room and all places are taken, the fullest window is emitted.  Documents longer than a window are cut into whole
windows and a rest.  What is still open at the end of the partitions is packed once more, best fit by falling length,
in groups of ``merge_partitions`` partitions (a bounded number of pieces), so padding does not grow with partitions.

The tokens are those of the named tokenizer file; equal pre-tokens are encoded once per worker.  Assignments are
written to the shared checkpoint before leftovers are read, so a lost executor can't change them half-way.
Defined cases: a null or empty text is the end token alone; extra columns are ignored; an empty table gives no rows;
repeated rows are packed as often as they occur.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm.byte_bpe import read_ranks
from mixagg.llm.pretokens import PretokenCache, Pretokens
from mixagg.llm.session import saved
from mixagg.llm.textkit import grouped, slices

OPEN_WINDOWS, MERGE_PARTITIONS = 64, 64
PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


@lru_cache(maxsize=2)
def id_cache(path: str, pattern: str) -> PretokenCache:
    """Entries are a pre-token's ids as little-endian unsigned 32-bit bytes."""
    encode = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=read_ranks(path), special_tokens={}).encode_ordinary
    return PretokenCache(lambda tokens: [np.array(encode(t), "<u4").tobytes() for t in tokens])


class Windows:
    """The open windows of a partition; ``closed`` holds finished pieces until they are taken."""

    def __init__(self, width: int, limit: int, first_id: int) -> None:
        self.width, self.limit, self.next = width, limit, first_id
        self.room = np.full(limit, -1, np.int64)  # -1: no window in this place
        self.held: list[list[tuple]] = [[] for _ in range(limit)]
        self.closed: list[tuple] = []

    def _emit(self, pieces: list[tuple]) -> None:
        at = 0
        for p in pieces:
            self.closed.append((*p, self.next, at))
            at += p[2]
        self.next += 1

    def add(self, piece: tuple) -> None:
        n = piece[2]
        if n == self.width:
            self._emit([piece])
            return
        fits = np.where(self.room >= n, self.room, self.width + 1)
        best = int(fits.argmin())
        if fits[best] > self.width:
            free = np.flatnonzero(self.room < 0)
            if len(free):
                best = int(free[0])
            else:
                best = int(self.room.argmin())
                self._emit(self.held[best])
            self.room[best], self.held[best] = self.width, []
        self.held[best].append(piece)
        self.room[best] -= n
        if not self.room[best]:
            self._emit(self.held[best])
            self.room[best], self.held[best] = -1, []


def best_fit_falling(lengths: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each piece: longest first, each into the fullest bin with room for it."""
    bins, offsets = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    by_room: list[list[int]] = [[] for _ in range(width + 1)]
    rooms, made = 0, 0  # rooms: bit r is set if some bin has room r
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        above = rooms >> n
        if above:
            r = n + (above & -above).bit_length() - 1
            b = by_room[r].pop()
            if not by_room[r]:
                rooms &= ~(1 << r)
        else:
            r, b, made = width, made, made + 1
        bins[i], offsets[i] = b, width - r
        if r > n:
            by_room[r - n].append(b)
            rooms |= 1 << (r - n)
    return bins, offsets


def _pieces_batch(rows: list[tuple], part: int, is_open: bool) -> pa.RecordBatch:
    columns = list(zip(*rows))
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    return pa.record_batch([*(pa.array(c, pa.int64()) for c in columns), pa.array([part] * len(rows), pa.int64()), pa.array([is_open] * len(rows))], [*names, "part", "open"])


def pack_documents(
    docs: DataFrame, tokenizer: str, pattern: str, width: int = 1024, end_id: int = 0, id_col: str = "doc_id", text: str = "text",
    open_windows: int = OPEN_WINDOWS, merge_partitions: int = MERGE_PARTITIONS,
) -> DataFrame:
    """One row per piece: which ids of which document lie where in which sequence."""

    def run(batches):
        cache, part = id_cache(tokenizer, pattern), TaskContext.get().partitionId()
        windows = Windows(width, open_windows, part << 32)
        for batch in batches:
            for rows, texts in slices(batch, "text"):
                tokens = Pretokens(texts)
                at, ids_of = cache.lookup(tokens).tolist(), rows.column(0).to_pylist()
                for doc, a, b in zip(ids_of, tokens.first[:-1].tolist(), tokens.first[1:].tolist()):
                    blob = b"".join([cache.entries[i] for i in at[a:b]]) + end_id.to_bytes(4, "little")
                    n = len(blob) // 4
                    for start in range(0, n, width):
                        cut = blob[4 * start : 4 * (start + width)]
                        windows.add((doc, start, len(cut) // 4, zlib.crc32(cut), n))
                if windows.closed:
                    yield _pieces_batch(windows.closed, part, False)
                    windows.closed = []
        for held in windows.held:
            if held:
                windows._emit(held)
        if windows.closed:
            yield _pieces_batch(windows.closed, part, True)

    def merge(cols, starts):
        out = []
        for a, b in zip(starts, np.r_[starts[1:], len(cols["group"])]):
            bins, offsets = best_fit_falling(cols["length"][a:b], width)
            out.append((bins + ((1 << 62) + (int(cols["group"][a]) << 32)), offsets))
        seq, off = (np.concatenate(x) for x in zip(*out))
        return pa.record_batch([*(pa.array(cols[c]) for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")), pa.array(seq), pa.array(off)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text"))
    placed = saved(rows.mapInArrow(run, PIECE + ", part long, open boolean"))
    left = placed.where("open").withColumn("group", F.floor(F.col("part") / merge_partitions).cast("long"))
    merged = left.repartition("group").sortWithinPartitions("group", F.desc("length"), "doc_id", "start").drop("part", "open").mapInArrow(grouped("group", merge), PIECE)
    return placed.where("not open").drop("part", "open").unionByName(merged)


def padding(pieces: DataFrame, width: int = 1024) -> DataFrame:
    """Sequences, tokens and padded tokens of a packing (a length that is a power of two is not padded)."""
    each = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.bit_count(F.col("n")) == 1, 0).otherwise(width - F.col("n"))
    return each.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padding"))
