"""Repeated passages: stretches of ``length`` words or more that documents share, wherever lines begin and end.

Every run of ``length`` words is a window.  A window names an anchor, the smallest hash among its ``GRAM``-word strings,
so equal windows name equal anchors.  Anchors that one document alone has are left out early, by a Bloom filter of the
others; the windows of the rest are grouped by anchor and compared by 64-bit hashes of all their words.  Of a window that
several documents have, the place in the smallest document stays and those in other documents go.  Windows that follow
each other in both documents are joined to one stretch.  Nothing is sampled: every shared run of ``length`` words is found.

Defined cases: words are compared without ASCII case and whatever whitespace parts them; copies within a document are
no repeats; rows with a null id take no part; texts of fewer words have no windows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm import bloom
from mixagg.llm.session import discard, saved
from mixagg.llm.suffix_dedup import _slide
from mixagg.llm.textkit import LOWER_CODE, Texts, binary_array, grouped, mix, over_texts, prefix_hash, span_hash

LENGTH, GRAM = 51, 8
WINDOW = np.dtype([("hash", "<i8"), ("start", "<i4"), ("stop", "<i4"), ("line", "<i4")])
PLACE = "doc_id long, first long, last long, start long, stop long, line long, kept_doc_id long, kept_first long, kept_line long, places long"


class Windows:
    """The windows of a batch, by the word they start at, and their anchors; ``run`` numbers neighbours of one anchor."""

    def __init__(self, texts: Texts, length: int) -> None:
        self.ws, self.we = texts.words()
        self.doc, n, gram = texts.doc_of(self.ws), len(self.ws), min(GRAM, length)
        self.prefix = prefix_hash(span_hash(prefix_hash(LOWER_CODE[texts.data]), self.ws, self.we))
        self.length = length
        if n < length:
            self.at, self.anchor = np.zeros(0, np.int64), np.zeros(0, np.int64)
        else:
            i = np.arange(n - gram + 1)
            low = _slide(span_hash(self.prefix, i, i + gram), length - gram + 1, np.minimum)
            self.at = np.flatnonzero(self.doc[: n - length + 1] == self.doc[length - 1 :])
            self.anchor = mix(low[self.at]).view(np.int64)
        self.edge = np.r_[True, (self.anchor[1:] != self.anchor[:-1]) | (np.diff(self.at) != 1)][: len(self.at)]

    def table(self, chosen: np.ndarray, texts: Texts) -> tuple[np.ndarray, np.ndarray]:
        """WINDOW entries of the chosen windows, and the first's place among its document's words."""
        at = self.at[chosen]
        doc = self.doc[at]
        out = np.zeros(len(at), WINDOW)
        out["hash"] = span_hash(self.prefix, at, at + self.length).view(np.int64)
        out["start"], out["stop"] = self.ws[at] - texts.off[doc], self.we[at + self.length - 1] - texts.off[doc]
        newlines = np.flatnonzero(texts.data == 10)
        out["line"] = np.searchsorted(newlines, self.ws[at]) - np.searchsorted(newlines, texts.off[doc])
        return out, at - np.searchsorted(self.doc, doc)


def shared_anchors(docs: DataFrame, length: int) -> DataFrame:
    """h1, h2 of the anchors that several documents have."""

    def run(part, texts):
        w = Windows(texts, length)
        if not len(w.at):
            return None
        pair = np.unique(np.stack([w.anchor[w.edge], w.doc[w.at[w.edge]]]), axis=1)
        return pa.record_batch([pa.array(pair[0]), part.column(0).take(pa.array(pair[1]))], ["h1", "doc_id"])

    found = docs.mapInArrow(over_texts(run), "h1 long, doc_id long")
    return found.groupBy("h1").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo != hi").select("h1", F.col("h1").alias("h2"))


def anchored_windows(docs: DataFrame, length: int, known: bloom.Bloom) -> DataFrame:
    """anchor, doc_id, first (word), windows: a row for each run of windows whose anchor may be shared."""
    shared = docs.sparkSession.sparkContext.broadcast(known)

    def run(part, texts):
        w = Windows(texts, length)
        if not len(w.at):
            return None
        first = np.flatnonzero(w.edge)
        key = w.anchor[first].view(np.uint64)
        ok = shared.value.test(key, key)
        size = np.diff(np.r_[first, len(w.at)])
        chosen = np.repeat(ok, size)
        if not ok.any():
            return None
        out, at = w.table(chosen, texts)
        begin = np.r_[0, np.cumsum(size[ok])[:-1]]
        return pa.record_batch(
            [pa.array(w.anchor[first[ok]]), part.column(0).take(pa.array(w.doc[w.at[first[ok]]])), pa.array(at[begin]), binary_array(out.tobytes(), size[ok] * WINDOW.itemsize)],
            ["anchor", "doc_id", "first", "windows"])

    return docs.mapInArrow(over_texts(run), "anchor long, doc_id long, first long, windows binary")


def stretches(c: dict[str, np.ndarray]) -> pa.RecordBatch:
    """Pieces (columns of PLACE) that follow each other in both documents, joined; the first's kept place holds."""
    lag = c["kept_first"] - c["first"]
    order = np.lexsort((c["first"], lag, c["kept_doc_id"], c["doc_id"]))
    c = {k: v[order] for k, v in c.items()}
    new = np.ones(len(order), bool)
    new[1:] = c["first"][1:] != c["last"][:-1] + 1
    for v in (c["doc_id"], c["kept_doc_id"], lag[order]):
        new[1:] |= v[1:] != v[:-1]
    begin = np.flatnonzero(new)
    end = np.r_[begin[1:], len(order)] - 1
    names = [x.split()[0] for x in PLACE.split(", ")]
    return pa.record_batch([pa.array(c[k][end if k in ("last", "stop") else begin].astype(np.int64)) for k in names], names)


def compare(cols, starts):
    """From whole groups of an anchor: the windows that several documents have, as stretches."""
    blobs = cols["windows"]
    off = np.frombuffer(blobs.buffers()[1], np.int32)[blobs.offset : blobs.offset + len(blobs) + 1].astype(np.int64)
    win = np.frombuffer(blobs.buffers()[2], np.uint8)[off[0] : off[-1]].view(WINDOW)
    size = np.diff(off) // WINDOW.itemsize
    row = np.repeat(np.arange(len(size)), size)
    doc = cols["doc_id"][row]
    at = cols["first"][row] + np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
    h = win["hash"].copy()
    order = np.lexsort((at, doc, h))
    h, d = h[order], doc[order]
    new = np.r_[True, h[1:] != h[:-1]]
    first = np.flatnonzero(new)
    group = np.cumsum(new) - 1
    places = np.add.reduceat((new | np.r_[True, d[1:] != d[:-1]]).astype(np.int64), first)
    chosen = (places[group] > 1) & ((d > d[first][group]) | new)
    if not chosen.any():
        return None
    i, kept = order[chosen], order[first][group[chosen]]
    return stretches({"doc_id": doc[i], "first": at[i], "last": at[i], "start": win["start"][i], "stop": win["stop"][i], "line": win["line"][i], "kept_doc_id": doc[kept], "kept_first": at[kept], "kept_line": win["line"][kept], "places": places[group[chosen]]})


def repeated_passages(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """Stretches of ``docs`` (doc_id, text) that an earlier document has, and the stretches that stay (kept_doc_id is their own)."""
    docs = docs.where(F.col("doc_id").isNotNull())
    anchors = saved(shared_anchors(docs, length))
    rows = anchored_windows(docs, length, bloom.blocked(anchors, anchors.count()))
    discard(anchors)
    found = saved(rows.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(grouped("anchor", compare), PLACE))
    return found.repartition("doc_id").sortWithinPartitions("doc_id").mapInArrow(grouped("doc_id", lambda cols, starts: stretches(cols)), PLACE)
