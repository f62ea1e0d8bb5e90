"""Vectorised text primitives over Arrow batches.

Everything here works on the raw UTF-8 buffer of a whole batch with numpy: words, lines and shingles of
thousands of documents are hashed in a few array passes, never token by token.  Sub-batches are cut by
bytes, so memory follows ``MAX_BYTES`` (or one document, if that is longer), not the batch's row count.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash

MAX_BYTES = 1 << 18  # array passes stay in the cache
_BASE = 0x9E3779B97F4A7C15 | 1
_M64 = (1 << 64) - 1

# The six ASCII whitespace bytes that separate words.
WHITESPACE = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)

IS_SPACE = np.zeros(256, bool)
IS_SPACE[list(WHITESPACE)] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply rounds)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x = x * np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


BYTE_CODE = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))
LOWER_CODE = BYTE_CODE[_LOWER]


class _Powers:
    """Powers of the hash base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def __call__(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, MAX_BYTES + 64)
            inverse = pow(_BASE, -1, 1 << 64)
            grown = []
            for b in (_BASE, inverse):
                out, have, step = np.ones(size, np.uint64), 1, b
                while have < size:  # doubling: out[have:2*have] = out[:have] * b**have
                    take = min(have, size - have)
                    out[have : have + take] = out[:take] * np.uint64(step)
                    have, step = have + take, step * step & _M64
                grown.append(out)
            self.up, self.down = grown
        return self.up, self.down


powers = _Powers()


LONG = 256  # codes; polynomials modulo 2**64 keep apart what is shorter, but not all regular strings of 1024


class Prefix:
    """Codes and their prefix sums as a polynomial modulo 2**64; pieces hash by ``span_hash``."""

    def __init__(self, codes: np.ndarray) -> None:
        up, _ = powers(len(codes) + 1)
        self.codes, self.sums = codes, np.zeros(len(codes) + 1, np.uint64)
        np.cumsum(codes * up[: len(codes)], out=self.sums[1:])


def prefix_hash(codes: np.ndarray) -> Prefix:
    return Prefix(codes)


def span_hash(prefix: Prefix, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit content hashes of the pieces [start, end), equal for equal contents wherever they stand.

    Pieces of more than ``LONG`` codes are hashed one by one by XXH3, which regular strings don't make collide.
    """
    _, down = powers(len(prefix.sums))
    size = end - start
    out = mix((prefix.sums[end] - prefix.sums[start]) * down[start] ^ size.astype(np.uint64))
    for i in np.flatnonzero(size > LONG).tolist():
        out[i] = xxhash.xxh3_64_intdigest(prefix.codes[start[i] : end[i]])
    return out


class Texts:
    """Some documents' bytes in one buffer: ``data`` and ``off`` (n + 1 offsets into it)."""

    def __init__(self, data: np.ndarray, off: np.ndarray) -> None:
        self.data, self.off = data, off

    def __len__(self) -> int:
        return len(self.off) - 1

    def doc_of(self, positions: np.ndarray) -> np.ndarray:
        """The document index of each byte position (empty documents own none)."""
        return np.searchsorted(self.off, positions, side="right") - 1

    def words(self) -> tuple[np.ndarray, np.ndarray]:
        """Byte starts and ends of the words, in order; words never span documents."""
        return spans_of(~IS_SPACE[self.data], self.off)

    def word_hashes(self, lower: bool) -> tuple[np.ndarray, np.ndarray]:
        """(hash, document index) of every word."""
        s, e = self.words()
        if not len(s):
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        p = prefix_hash((LOWER_CODE if lower else BYTE_CODE)[self.data])
        return span_hash(p, s, e), self.doc_of(s)


def spans_of(inside: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of True, cut at the offsets ``off``."""
    n = len(inside)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    edge = np.zeros(n + 1, bool)
    edge[off[(off >= 0) & (off <= n)]] = True
    before = np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    starts = np.flatnonzero(inside & (~before | edge[:-1]))
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, inside[1:]
    ends = np.flatnonzero(inside & (~after | edge[1:])) + 1
    return starts, ends


def window_hash(h: np.ndarray, group: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each run of ``width`` neighbours within a group, and the index each starts at.

    A group with fewer than ``width`` members gives one hash over all of them.
    """
    n = len(h)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    mult = mix(np.arange(7, 7 + width, dtype=np.uint64)) | np.uint64(1)
    m = n - width + 1
    full = np.flatnonzero(group[: max(m, 0)] == group[width - 1 :]) if m > 0 else np.zeros(0, np.int64)
    acc = np.zeros(len(full), np.uint64)
    for k in range(width):
        acc += h[full + k] * mult[k]
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.diff(np.r_[first, n])
    few = size < width
    fs, fn = first[few], size[few]
    short = np.zeros(len(fs), np.uint64)
    for k in range(width - 1):
        has = fn > k
        short[has] += h[fs[has] + k] * mult[k]
    short += fn.astype(np.uint64) * np.uint64(0xA24BAED4963EE407)
    at = np.r_[full, fs]
    out = mix(np.r_[acc, short])
    order = np.argsort(at, kind="stable")
    return out[order], at[order]


def texts_of(column: pa.Array) -> Texts:
    """Whole texts of an Arrow string or binary array; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    n = len(column)
    buffers = column.buffers()
    if not n:
        return Texts(np.zeros(0, np.uint8), np.zeros(1, np.int64))
    off = np.frombuffer(buffers[1], np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], np.uint8)[off[0] : off[-1]] if buffers[2] is not None and off[-1] > off[0] else np.zeros(0, np.uint8)
    return Texts(data, off - off[0])


def slices(batch: pa.RecordBatch, text: str, max_bytes: int = MAX_BYTES) -> Iterator[tuple[pa.RecordBatch, Texts]]:
    """Consecutive parts of a batch with at most ``max_bytes`` of text each, one row at least."""
    column = batch.column(batch.schema.get_field_index(text))
    whole = texts_of(column)
    n, at = len(whole), 0
    while at < n:
        to = int(np.searchsorted(whole.off, whole.off[at] + max_bytes, side="right")) - 1
        to = min(max(to, at + 1), n)
        lo, hi = whole.off[at], whole.off[to]
        yield batch.slice(at, to - at), Texts(whole.data[lo:hi], whole.off[at : to + 1] - lo)
        at = to


def over_texts(fn: Callable[[pa.RecordBatch, Texts], pa.RecordBatch | None], text: str = "text", max_bytes: int = MAX_BYTES):
    """A mapInArrow function that applies ``fn`` to byte-bounded slices of the input."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, texts in slices(batch, text, max_bytes):
                out = fn(part, texts)
                if out is not None and out.num_rows:
                    yield out

    return run


class Frequent:
    """The values that a task has seen most often, from a bounded number of counters."""

    def __init__(self, limit: int) -> None:
        self.limit, self.values, self.counts = limit, np.zeros(0, np.uint64), np.zeros(0, np.int64)

    def add(self, values: np.ndarray) -> None:
        values = np.sort(values)
        at = np.flatnonzero(np.r_[True, values[1:] != values[:-1]]) if len(values) else np.zeros(0, np.int64)
        n = np.diff(np.r_[at, len(values)])
        many = n > 1
        kept, back = np.unique(np.r_[self.values, values[at][many]], return_inverse=True)
        total = np.bincount(back, np.r_[self.counts, n[many]], len(kept)).astype(np.int64)
        best = np.argsort(-total, kind="stable")[: 8 * self.limit]
        self.values, self.counts = kept[best], total[best]

    def batch(self) -> pa.RecordBatch:
        return pa.record_batch([pa.array(self.values[: self.limit].view(np.int64)), pa.array(self.counts[: self.limit])], ["h", "n"])


def segments(values: np.ndarray, doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """[start, end) of each document's run in arrays that are ordered by document."""
    edges = np.searchsorted(doc, np.arange(n + 1))
    return edges[:-1], edges[1:]


def shingles(texts: Texts, width: int = 5, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document index) of every word shingle, in order, repeats included."""
    h, d = texts.word_hashes(lower)
    s, at = window_hash(h, d, width)
    return s, d[at]


def runs(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The indices start, start + 1, ... of each piece, one piece after the other."""
    return np.repeat(start - np.cumsum(size) + size, size) + np.arange(int(size.sum()))


def differ(x: np.ndarray, xs: np.ndarray, xn: np.ndarray, y: np.ndarray, ys: np.ndarray, yn: np.ndarray) -> np.ndarray:
    """Which pieces of ``x`` differ from their pieces of ``y`` in size or content."""
    out = xn != yn
    same = np.flatnonzero(~out & (xn > 0))
    n = xn[same]
    apart = x[runs(xs[same], n)] != y[runs(ys[same], n)]
    if apart.any():
        out[same[np.repeat(np.arange(len(same)), n)[apart]]] = True
    return np.flatnonzero(out)


def list_array(values: np.ndarray, sizes: np.ndarray) -> pa.ListArray:
    off = np.zeros(len(sizes) + 1, np.int32)
    np.cumsum(sizes, out=off[1:])
    return pa.ListArray.from_arrays(pa.array(off), pa.array(values))


def binary_array(blob: bytes, sizes: np.ndarray) -> pa.BinaryArray:
    off = np.zeros(len(sizes) + 1, np.int32)
    np.cumsum(sizes, out=off[1:])
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(off.tobytes()), pa.py_buffer(blob)])


def grouped(key: str, fn: Callable[[dict[str, np.ndarray], np.ndarray], pa.RecordBatch | None]):
    """A mapInArrow function over partitions sorted by ``key``: calls ``fn(columns, starts)`` on whole groups.

    ``columns`` are numpy arrays of as many complete groups as a batch brings; ``starts`` are the groups'
    first rows.  Only the last, unfinished group is carried over to the next batch.
    """

    def to_numpy(t: pa.Table) -> dict[str, np.ndarray]:
        return {c: t.column(c).combine_chunks() if pa.types.is_binary(t.schema.field(c).type) else t.column(c).to_numpy() for c in t.column_names}

    def call(t: pa.Table):
        cols = to_numpy(t)
        k = cols[key]
        starts = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
        return fn(cols, starts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            k = batch.column(batch.schema.get_field_index(key)).to_numpy()
            change = np.flatnonzero(k[1:] != k[:-1])
            if held and (held_last := held[-1].column(batch.schema.get_field_index(key))[-1].as_py()) != k[0]:
                if len(change) == 0:
                    out = call(pa.Table.from_batches(held))
                    held = [batch]
                    if out is not None and out.num_rows:
                        yield out
                    continue
            if len(change) == 0:
                held.append(batch)
                continue
            cut = int(change[-1]) + 1
            out = call(pa.Table.from_batches([*held, batch.slice(0, cut)]))
            held = [batch.slice(cut)]
            if out is not None and out.num_rows:
                yield out
        if held:
            out = call(pa.Table.from_batches(held))
            if out is not None and out.num_rows:
                yield out

    return run
