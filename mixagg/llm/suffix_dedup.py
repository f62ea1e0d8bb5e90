"""Removal of long repeated strings by suffix sorting, one bucket of suffixes at a time.

Only suffixes that may repeat need to meet.  Every window of ``length`` bytes names an anchor: the leftmost smallest
hash among the ``GRAM``-byte strings inside it.  Equal windows name equal anchors, so anchors that one document alone has
are left out: their documents are counted first, and a Bloom filter of the others (of bounded size; a fuller one only
lets more through) picks what travels.  Suffixes are dealt out by anchor hash; a bucket is the anchors of one residue,
and buckets are sorted one after another, which bounds disk.  Before the shuffle each batch settles what it can: of equal
contexts only those of the smallest document travel, and neighbours with equal contexts (runs of one byte) are one row.
Anchors of thousands of documents are dealt out twice: first by document, to settle equal contexts, then those left.

Within a bucket the window starts are sorted as suffixes by difference-cover sampling: suffixes that start at cover
positions get ranks by prefix doubling; all others compare by their first bytes up to the next cover position and then
by that position's rank, so long ties cost no more than short ones.  Contexts are laid out with their anchors at one
residue, so suffixes that are compared share the cover position.  Neighbours in that order with a common prefix of
``length`` bytes form a class; members in documents after the class's smallest are removed.  The buckets are anchors
instead of suffix prefixes, and ranks are computed for the contexts of a task, not for the whole text: sorting every
suffix of the corpus would move each byte many times over.

Defined cases: a null or empty text has no bytes; texts shorter than ``length`` lose nothing; longer ones than ``PIECE``
are read in pieces that overlap by a window; copies within a document are no repeats; rows with a null id take no part and
lose nothing; extra columns are ignored; an empty table gives no rows.  Ids are taken as unique.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm import bloom
from mixagg.llm.session import discard, release, saved
from mixagg.llm.textkit import BYTE_CODE, Texts, binary_array, differ, grouped, list_array, mix, over_texts, powers, prefix_hash, runs, slices, span_hash

GRAM, BUCKETS, COVER = 20, 2, 16
PIECE = 1 << 20  # bytes of a long text that are read at once
STRETCH = 1 << 16  # windows with one smallest hash that are looked at together
HOT, HOT_LISTED, HOT_PARTS = 4096, 1 << 15, 64  # documents of an anchor that is dealt out twice; how many are listed; into how many parts


def difference_cover(v: int) -> np.ndarray:
    """A set of residues such that every difference modulo ``v`` occurs between two of them (grown greedily)."""
    cover, have = [0], {0}
    while len(have) < v:
        gain = lambda x: len(have | {(x - c) % v for c in cover} | {(c - x) % v for c in cover})
        best = max(range(1, v), key=lambda x: (x not in cover, gain(x), -x))
        cover.append(best)
        have = {(a - b) % v for a in cover for b in cover}
    return np.array(sorted(cover))


def _slide(x: np.ndarray, width: int, op) -> np.ndarray:
    """op over each run of ``width`` neighbours (by doubling)."""
    out, have = x, 1
    while have < width:
        step = min(have, width - have)
        out = op(out[:-step], out[step:])
        have += step
    return out


def anchors(texts: Texts, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """For each anchor: its position, hash, the first and last window start that name it; and the prefix hashes."""
    data, n = texts.data, len(texts.data)
    prefix = prefix_hash(BYTE_CODE[data])
    none = np.zeros(0, np.int64)
    grams, span = n - GRAM + 1, length - GRAM + 1
    if grams < span:
        return none, none.view(np.uint64), none, none, prefix
    _, down = powers(n + 1)
    h = mix((prefix.sums[GRAM:] - prefix.sums[:-GRAM]) * down[:grams])
    low = _slide(h, span, np.minimum)  # by window start
    doc = np.repeat(np.arange(len(texts)), np.diff(texts.off))
    valid = doc[: len(low)] == doc[length - 1 :]
    # runs of windows with one minimum; a run whose anchor drops out while an equal one follows is cut there
    edge = np.r_[True, (low[1:] != low[:-1]) | (valid[1:] != valid[:-1])]
    first = np.flatnonzero(edge)
    last = np.r_[first[1:], len(low)] - 1
    first, last = first[valid[first]], last[valid[first]]
    cut = (last - first) // STRETCH + 1
    run = np.repeat(np.arange(len(first)), cut)
    first, stop = np.repeat(first, cut) + STRETCH * (np.arange(len(run)) - np.repeat(np.cumsum(cut) - cut, cut)), last[run]
    last = np.minimum(stop, first + STRETCH - 1)
    size = last - first + span
    total, done, lo = np.cumsum(size), [], 0
    while lo < len(first):
        hi = max(int(np.searchsorted(total, total[lo] - size[lo] + (1 << 20), side="right")), lo + 1)
        at = runs(first[lo:hi], size[lo:hi])
        equal = h[at] == np.repeat(low[first[lo:hi]], size[lo:hi])
        pos, of = at[equal], np.repeat(np.arange(lo, hi), size[lo:hi])[equal]
        begin = np.r_[0, pos[:-1] + 1][: len(pos)]  # the first window that the place before has left
        fresh = np.r_[True, of[1:] != of[:-1]][: len(pos)]
        begin[fresh] = first[of[fresh]]
        named = begin <= last[of]
        pos, begin, of = pos[named], begin[named], of[named]
        done.append((pos, begin, np.minimum(last[of], pos)))
        lo = hi
    if not done:
        return none, none.view(np.uint64), none, none, prefix
    pos, first, last = (np.concatenate(x) for x in zip(*done))
    return pos, h[pos], first, last, prefix


def in_pieces(fn, length: int):
    """A mapInArrow function: ``fn(part, texts, base)`` on slices of the input; of a text longer than PIECE on parts of it,
    from byte ``base`` on, that hold each window of ``length`` bytes once."""

    def run(batches):
        for batch in batches:
            for part, texts in slices(batch, "text"):
                bytes_here = len(texts.data)
                for base in range(0, max(bytes_here, 1), PIECE) if len(texts) == 1 else (0,):
                    data = texts.data[base : base + PIECE + length - 1] if len(texts) == 1 else texts.data
                    out = fn(part, Texts(data, np.array([0, len(data)])) if len(texts) == 1 else texts, base)
                    if out is not None and out.num_rows:
                        yield out

    return run


def shared_anchors(docs: DataFrame, length: int) -> DataFrame:
    """h1, h2 (equal), docs: the anchors that several documents have, and about how many do (repeats within one count)."""

    def emit(part, texts, base):
        pos, h, _, _, _ = anchors(texts, length)
        if not len(pos):
            return None
        doc = texts.doc_of(pos)
        new = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])])  # a run of one byte is one row
        return pa.record_batch([pa.array(h[new].view(np.int64)), part.column(0).take(pa.array(doc[new]))], ["h", "doc_id"])

    def merge(batches):
        held = None

        def fold(new):
            h, lo, hi, n = (np.concatenate(x) for x in zip(*new))
            order = np.argsort(h, kind="stable")
            h, lo, hi, n = h[order], lo[order], hi[order], n[order]
            at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            return h[at], np.minimum.reduceat(lo, at), np.maximum.reduceat(hi, at), np.add.reduceat(n, at)

        new, rows = [], 0
        for t in batches:
            if t.num_rows:
                h, d = t.column(0).to_numpy(), t.column(1).to_numpy()
                new.append((h, d, d, np.ones(len(h), np.int64)))
                rows += len(h)
            if rows > 1 << 20:
                held = fold([held, *new] if held else new)
                new, rows = [], 0
        if new or held:
            h, lo, hi, n = fold([held, *new] if held else new)
            many = lo != hi
            yield pa.record_batch([pa.array(h[many]), pa.array(h[many]), pa.array(n[many])], ["h1", "h2", "docs"])

    return docs.mapInArrow(in_pieces(emit, length), "h long, doc_id long").repartition("h").mapInArrow(merge, "h1 long, h2 long, docs long")


SETTLED, NORMAL, SALTED = 0, 1, 2
CONTEXT = "anchor long, deal long, doc_id long, start long, before long, size long, repeat long, state long, content long, context binary"


def contexts(docs: DataFrame, length: int, bucket: int, buckets: int, known: bloom.Bloom, hot: np.ndarray) -> DataFrame:
    """Anchored contexts of one bucket, in columns CONTEXT.  ``state``: settled in its batch (without context), normal or salted."""
    shared = docs.sparkSession.sparkContext.broadcast((known, hot))

    def run(part, texts, base):
        pos, h, first, last, prefix = anchors(texts, length)
        filter_, often = shared.value
        mine = np.flatnonzero((h >> np.uint64(8)) % np.uint64(buckets) == np.uint64(bucket))
        mine = mine[filter_.test(h[mine], h[mine])]
        if not len(mine):
            return None
        mine = mine[np.argsort(first[mine], kind="stable")]
        pos, h, first, last = pos[mine], h[mine], first[mine], last[mine]
        doc, size = texts.doc_of(pos), last + length - first
        content = span_hash(prefix, first, first + size) ^ mix((pos - first).astype(np.uint64))
        alike = (first[1:] == first[:-1] + 1) & (content[1:] == content[:-1]) & (h[1:] == h[:-1]) & (doc[1:] == doc[:-1]) & (size[1:] == size[:-1])
        j = np.flatnonzero(alike) + 1
        alike[j[differ(texts.data, first[j], size[j], texts.data, first[j - 1], size[j - 1])] - 1] = False
        lead = np.flatnonzero(np.r_[True, ~alike])
        repeat = np.diff(np.r_[lead, len(pos)])
        pos, h, first, doc, size, content = (x[lead] for x in (pos, h, first, doc, size, content))
        ids = part.column(0).to_numpy()[doc]
        order = np.lexsort((ids, content))
        c, d = content[order], ids[order]
        new = np.r_[True, c[1:] != c[:-1]]
        least = order[np.flatnonzero(new)][np.cumsum(new) - 1]  # by order: the row of the smallest document
        later = d > ids[least]
        i, k = order[later], least[later]
        same = np.ones(len(i), bool)
        same[differ(texts.data, first[i], size[i], texts.data, first[k], size[k])] = False
        state = np.full(len(pos), NORMAL)
        state[h_in(h, often)] = SALTED
        state[i[same]] = SETTLED
        start = first - texts.off[doc] + base
        salt = mix(ids.astype(np.uint64)) % np.uint64(HOT_PARTS) + np.uint64(1)
        deal = np.where(state == NORMAL, h, np.where(state == SALTED, mix(h + salt), mix(mix(ids.astype(np.uint64)) + start.astype(np.uint64))))
        sent = np.where(state == SETTLED, 0, size)
        columns = [h.view(np.int64), deal.view(np.int64), ids, start, pos - first, size, repeat, state, content.view(np.int64)]
        return pa.record_batch([*(pa.array(x) for x in columns), binary_array(texts.data[runs(first, sent)].tobytes(), sent)], [x.split()[0] for x in CONTEXT.split(", ")])

    return docs.mapInArrow(in_pieces(run, length), CONTEXT)


def h_in(h: np.ndarray, listed: np.ndarray) -> np.ndarray:
    """Which of ``h`` are in the sorted ``listed``."""
    return listed[np.minimum(np.searchsorted(listed, h), len(listed) - 1)] == h if len(listed) else np.zeros(len(h), bool)


def _dense(*keys: np.ndarray) -> np.ndarray:
    """Dense ranks from 1 of rows compared key by key, first key first."""
    order = np.lexsort(keys[::-1])
    change = np.zeros(len(order), bool)
    for k in keys:
        s = k[order]
        change[1:] |= s[1:] != s[:-1]
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(change) + 1
    return out


def _word(grid: np.ndarray, row: np.ndarray, col: np.ndarray) -> np.ndarray:
    """Eight bytes from each place as one big-endian number."""
    flat = grid.reshape(-1)
    at = row * grid.shape[1] + col
    out = np.zeros(len(at), np.uint64)
    for k in range(8):
        out = out << np.uint64(8) | flat[at + k]
    return out


def sort_block(grid: np.ndarray, group: np.ndarray, row: np.ndarray, col: np.ndarray, length: int, cover: np.ndarray) -> np.ndarray:
    """Class of each suffix start (row, col): equal for equal group, column and first ``length`` bytes.

    ``grid`` has a context per row, padded with zeros to a multiple of the period and ``COVER`` bytes more.
    """
    v, width = COVER, grid.shape[1] - COVER
    cols = np.flatnonzero(np.isin(np.arange(width) % v, cover))
    table = np.zeros((len(grid), width + 4 * v), np.int64)  # rank of each cover suffix; beyond the end: 0
    r, c = np.repeat(np.arange(len(grid)), len(cols)), np.tile(cols, len(grid))
    table[r, c] = _dense(_word(grid, r, c), _word(grid, r, c + 8))
    depth = v
    while depth < length:  # ranks by 2 * depth bytes from ranks by depth
        table[r, c] = _dense(table[r, c], table[r, np.minimum(c + depth, width)])
        depth *= 2
    ahead = (cols[np.minimum(np.searchsorted(cols, np.arange(width)), len(cols) - 1)] - np.arange(width)) % v
    step = ahead[col]  # bytes before the next cover position
    head = [_word(grid, row, col), _word(grid, row, col + 8)]
    for k in (0, 1):  # keep only the bytes before that position
        bits = np.clip(step - 8 * k, 0, 8) * 8
        head[k] = np.where(bits == 64, head[k], np.where(bits == 0, np.uint64(0), head[k] >> (np.uint64(64) - bits.astype(np.uint64)) % np.uint64(64)))
    keys = [group, col, head[0], head[1], table[row, np.minimum(col + step, width)]]
    order = np.lexsort(keys[::-1])
    apart = np.ones(len(order), bool)
    g, k, a = group[order], col[order], row[order]
    apart[1:] = (g[1:] != g[:-1]) | (k[1:] != k[:-1])
    tied = np.flatnonzero(~apart)
    for i in range(0, len(tied), 1 << 16):
        t = tied[i : i + (1 << 16)]
        at = k[t][:, None] + np.arange(length)[None]
        apart[t] = (grid[a[t][:, None], at] != grid[a[t - 1][:, None], at]).any(1)  # common prefix shorter than length
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(apart) - 1
    return out


def find_spans(cols, starts, length: int, cover: np.ndarray):
    """(doc_id, start, stop) arrays of removed stretches, from whole groups of contexts that are no longer salted."""
    ahead = -(-(length - GRAM) // COVER) * COVER  # the anchor's column
    width = -(-(ahead + length) // COVER) * COVER
    ids, size, repeat = cols["doc_id"], cols["size"], cols["repeat"]
    n = len(ids)
    group = np.repeat(np.arange(len(starts)), np.diff(np.r_[starts, n]))
    several = (np.maximum.reduceat(ids, starts) > np.minimum.reduceat(ids, starts))[group]
    at = np.flatnonzero(several)
    if not len(at):
        return (np.zeros(0, np.int64),) * 3
    # equal contexts are sorted once, for their smallest document
    group, ids, size, repeat, before, start = group[at], ids[at], size[at], repeat[at], cols["before"][at], cols["start"][at]
    rep = same_context(cols, at, group, ids)
    lead = ahead - before
    reps = np.flatnonzero(rep == np.arange(len(at)))
    distinct = np.bincount(group[reps], minlength=len(starts))
    reps = reps[distinct[group[reps]] > 1]  # the others have nothing to be compared with
    gone = np.zeros((len(reps), width), bool)
    if len(reps):
        data, off = blobs(cols["context"])
        grid = np.zeros((len(reps), width + COVER), np.uint8)
        r = np.repeat(np.arange(len(reps)), size[reps])
        grid[r, runs(lead[reps], size[reps])] = data[runs(off[at[reps]], size[reps])]
        windows = (size - length + 1)[reps]
        row, col = np.repeat(np.arange(len(reps)), windows), runs(lead[reps], windows)
        cls = sort_block(grid, group[reps][row], row, col, length, cover)
        least = np.full(cls.max() + 1, np.iinfo(np.int64).max)
        np.minimum.at(least, cls, ids[reps][row])
        gone[row, col] = ids[reps][row] > least[cls]
    back = np.full(len(at), -1)
    back[reps] = np.arange(len(reps))
    out = []
    for part in range(0, len(at), 1 << 15):
        some = np.arange(part, min(part + (1 << 15), len(at)))
        mine = np.zeros((len(some), width), bool)
        has = back[rep[some]] >= 0
        mine[has] = gone[back[rep[some][has]]]
        span = np.arange(width)[None]
        mine |= (ids[some] > ids[rep[some]])[:, None] & (span >= lead[some][:, None]) & (span <= (lead + size - length)[some][:, None])
        edge = np.diff(np.pad(mine, ((0, 0), (1, 1))).astype(np.int8), axis=1)
        (a, s), (_, e) = np.nonzero(edge == 1), np.nonzero(edge == -1)
        a = some[a]
        out.append((ids[a], start[a] + s - lead[a], start[a] + e - 1 - lead[a] + length + repeat[a] - 1))
    return tuple(np.concatenate(x) for x in zip(*out))


def blobs(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of binary values and where each begins in them."""
    off = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8), off


def same_context(cols, at: np.ndarray, group: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """For each of the rows ``at`` the place in ``at`` of the smallest document's row with its group and context."""
    content, size = cols["content"][at], cols["size"][at]
    order = np.lexsort((ids, content, group))
    new = np.r_[True, (group[order][1:] != group[order][:-1]) | (content[order][1:] != content[order][:-1])]
    rep = np.empty(len(at), np.int64)
    rep[order] = order[np.flatnonzero(new)][np.cumsum(new) - 1]
    data, off = blobs(cols["context"])
    other = np.flatnonzero(rep != np.arange(len(at)))
    alone = other[differ(data, off[at[other]], size[other], data, off[at[rep[other]]], size[rep[other]])]
    rep[alone] = alone
    return rep


def taken(cols, chosen: np.ndarray):
    """Some rows of a group function's columns."""
    return {k: v.take(pa.array(chosen)) if isinstance(v, pa.Array) else v[chosen] for k, v in cols.items()}


FOUND = "anchor long, doc_id long, start long, stop long, before long, size long, repeat long, content long, context binary"


def first_deal(length: int, cover: np.ndarray):
    """A group function: removed stretches, and of salted anchors the contexts that their part leaves (with their context)."""

    def one(cols, starts):
        state = cols["state"]
        keys = np.repeat(np.arange(len(starts)), np.diff(np.r_[starts, len(state)]))
        settled, normal, salted = (np.flatnonzero(state == x) for x in (SETTLED, NORMAL, SALTED))
        spans = [(cols["doc_id"][settled], cols["start"][settled], (cols["start"] + cols["size"] + cols["repeat"] - 1)[settled])]
        if len(normal):
            spans.append(find_spans(taken(cols, normal), np.flatnonzero(np.r_[True, keys[normal][1:] != keys[normal][:-1]]), length, cover))
        rest = salted
        if len(salted):
            ids = cols["doc_id"][salted]
            rep = same_context(cols, salted, keys[salted], ids)
            later = ids > ids[rep]
            gone, rest = salted[later], salted[~later]
            spans.append((cols["doc_id"][gone], cols["start"][gone], (cols["start"] + cols["size"] + cols["repeat"] - 1)[gone]))
        doc, start, stop = (np.concatenate(x).astype(np.int64) for x in zip(*spans))
        zero = np.zeros(len(doc), np.int64)
        left = taken(cols, rest)
        both = lambda a, b: pa.array(np.r_[a, b].astype(np.int64))
        columns = [both(zero, left["anchor"]), both(doc, left["doc_id"]), both(start, left["start"]), both(stop, zero[:0] if not len(rest) else np.zeros(len(rest), np.int64))]
        columns += [both(zero, left[c]) for c in ("before", "size", "repeat", "content")]
        columns.append(pa.concat_arrays([pa.nulls(len(doc), pa.binary()), left["context"].cast(pa.binary())]))
        return pa.record_batch(columns, [x.split()[0] for x in FOUND.split(", ")])

    return one


def repeated_spans(rows: DataFrame, length: int) -> DataFrame:
    """(doc_id, start, stop) of removed stretches, from the contexts of a bucket; reads a saved table."""
    cover = difference_cover(COVER)
    found = saved(rows.repartition("deal").sortWithinPartitions("deal").mapInArrow(grouped("deal", first_deal(length, cover)), FOUND))

    def find(cols, starts):
        return pa.record_batch([pa.array(x) for x in find_spans(cols, starts, length, cover)], ["doc_id", "start", "stop"])

    spans = found.where("context is null").select("doc_id", "start", "stop")
    left = found.where("context is not null")
    if left.isEmpty():
        return spans
    return spans.unionByName(left.drop("stop").repartition("anchor").sortWithinPartitions("anchor").mapInArrow(grouped("anchor", find), "doc_id long, start long, stop long"))


def removed_spans(docs: DataFrame, length: int = 50, buckets: int = BUCKETS, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, start, stop): byte stretches to remove; they may overlap."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text")).where(F.col("doc_id").isNotNull())
    shared = saved(shared_anchors(rows, length))
    known = bloom.blocked(shared, shared.count())
    often = shared.where(F.col("docs") >= HOT).orderBy(F.desc("docs"), "h1").limit(HOT_LISTED).select("h1").toArrow().column("h1").to_numpy()
    hot = np.sort(often.view(np.uint64))
    discard(shared)
    out = None
    for bucket in range(buckets):
        spans = saved(joined_spans(repeated_spans(contexts(rows, length, bucket, buckets, known, hot), length)))
        release(docs.sparkSession)  # nothing refers to the bucket's shuffle any more
        out = spans if out is None else out.unionByName(spans)
    return out.select("doc_id", F.inline(F.arrays_zip("starts", "stops"))).select("doc_id", F.col("starts").alias("start"), F.col("stops").alias("stop"))


def joined_spans(spans: DataFrame) -> DataFrame:
    """doc_id, starts, stops: each document's stretches, those that touch made one."""

    def run(batches):
        for t in batches:
            starts, stops = t.column(1), t.column(2)
            a, b = starts.flatten().to_numpy(), stops.flatten().to_numpy()
            off = starts.offsets.to_numpy() - starts.offsets[0].as_py()
            got = [union_spans(a[i:j], b[i:j]) for i, j in zip(off[:-1], off[1:])]
            if got:
                sizes = np.array([len(x) for x, _ in got])
                yield pa.record_batch([t.column(0), list_array(np.concatenate([x for x, _ in got]), sizes), list_array(np.concatenate([y for _, y in got]), sizes)], ["doc_id", "starts", "stops"])

    lists = spans.groupBy("doc_id").agg(F.collect_list("start").alias("starts"), F.collect_list("stop").alias("stops"))
    return lists.mapInArrow(run, "doc_id long, starts array<long>, stops array<long>")


def union_spans(start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal disjoint stretches; those that touch become one."""
    order = np.argsort(start, kind="stable")
    s, e = start[order], np.maximum.accumulate(stop[order]) if len(stop) else stop
    new = np.r_[True, s[1:] > e[:-1]] if len(s) else np.zeros(0, bool)
    first = np.flatnonzero(new)
    return s[first], e[np.r_[first[1:] - 1, len(s) - 1]] if len(s) else e


def strip_documents(docs: DataFrame, spans: DataFrame, id_col: str = "doc_id", text: str = "text", keep_text: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and the remaining bytes) of every row."""
    lists = joined_spans(spans).withColumnRenamed("doc_id", "id")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text"))
    joined = rows.join(lists, rows["doc_id"] == lists["id"], "left").select("doc_id", "text", "starts", "stops")

    def run(part, texts):
        out = []
        for i in range(len(texts)):
            data = texts.data[texts.off[i] : texts.off[i + 1]]
            a, b = np.zeros(0, np.int64), np.zeros(0, np.int64)
            if part.column(2)[i].is_valid:
                a, b = union_spans(*(np.array(part.column(k)[i].as_py(), np.int64) for k in (2, 3)))
            kept = [data[x:y] for x, y in zip(np.r_[0, b].tolist(), np.r_[a, len(data)].tolist())]
            digest = hashlib.sha256()
            for x in kept:
                digest.update(x)
            out.append((len(data), int((b - a).sum()), len(a), digest.hexdigest(), b"".join(x.tobytes() for x in kept) if keep_text else None))
        c = list(zip(*out))
        columns = [part.column(0), *(pa.array(x, pa.int64()) for x in c[:3]), pa.array(c[3])] + ([pa.array(c[4], pa.binary())] if keep_text else [])
        return pa.record_batch(columns, ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + (["kept"] if keep_text else []))

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if keep_text else "")
    return joined.mapInArrow(over_texts(run), schema)


def dedup_substrings(docs: DataFrame, length: int = 50, buckets: int = BUCKETS, id_col: str = "doc_id", text: str = "text", keep_text: bool = False) -> DataFrame:
    """Every document without the bytes that a ``length``-byte string of an earlier document covers."""
    return strip_documents(docs, removed_spans(docs, length, buckets, id_col, text), id_col, text, keep_text)
