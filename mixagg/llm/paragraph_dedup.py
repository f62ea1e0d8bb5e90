"""Substring dedup by paragraphs: MinHash bands, exact Jaccard, components, removal of all but the first.

Passages of ``passage_words`` words that documents share inside longer lines or over lines cut elsewhere are found
exactly and go too (see ``passages``).  A passage's first place may lie in a line that goes as a near copy of another:
then the near copy is what stays.

Paragraphs are the lines of a text with at least ``min_words`` words, and runs of neighbouring shorter lines (wrapped text)
that together have as many.  By default that is 20: single sentences and headings are shared by documents that are no
copies of each other, and stay.  Band keys are hashes of ``rows`` MinHash values; 12 bands of 3 rows find a pair of
similarity 0.75 with probability 0.9986.
Equal sets are one set whatever their bands, and sets too small to be similar to any other have none.  Candidates are
verified exactly (see ``links``); of each component the paragraph with the smallest (doc_id, position) stays.

Defined cases: a null or empty text has no paragraphs; runs of lines with fewer words than ``min_words`` are none; repeated
paragraphs of one document count like others; very long texts and lines are read whole; extra columns are ignored
(``remove_paragraphs`` passes them on, whatever they are called); an empty table gives no rows.  Ids are taken as unique;
rows with the same id share their paragraphs' fate by position.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm.links import HASH_BITS, bitmap_columns, classed, keys_column, link_sets, mixed_keys, places
from mixagg.llm.ngram_join import set_id
from mixagg.llm.passages import LENGTH, repeated_passages
from mixagg.llm.session import discard, saved
from mixagg.llm.textkit import LOWER_CODE, Texts, list_array, runs, mix, over_texts, prefix_hash, span_hash, spans_of, window_hash

MIN_WORDS, BANDS, ROWS = 20, 12, 3


class Paragraphs:
    """The paragraphs of a batch: document, first line's number, lines, byte span, words and distinct sorted shingle keys."""

    def __init__(self, texts: Texts, width: int, min_words: int) -> None:
        newline = texts.data == 10
        s, e = spans_of(~newline, texts.off)
        ws, we = texts.words()
        in_line = np.searchsorted(s, ws, side="right") - 1
        words = np.bincount(in_line, minlength=len(s)) if len(s) else np.zeros(0, np.int64)
        count = np.zeros(len(texts.data) + 1, np.int64)
        np.cumsum(newline, out=count[1:])
        doc = texts.doc_of(s)
        number = count[s] - count[texts.off[doc]]
        short = (words > 0) & (words < min_words)
        joined = np.zeros(len(s), bool)  # to the line before
        joined[1:] = short[1:] & short[:-1] & (doc[1:] == doc[:-1]) & (number[1:] == number[:-1] + 1)
        first = np.flatnonzero(~joined)
        last = np.r_[first[1:], len(s)][: len(first)] - 1
        many = np.add.reduceat(words, first) if len(first) else words
        keep = many >= min_words
        line = (np.cumsum(~joined) - 1)[in_line]  # of each word: its paragraph
        self.start, self.end, self.words = s[first[keep]], e[last[keep]], many[keep]
        self.doc, self.line = doc[first[keep]], number[first[keep]]
        self.lines = number[last[keep]] - self.line + 1
        self.start_in_doc = self.start - texts.off[self.doc]
        self.end_in_doc = self.end - texts.off[self.doc]
        if len(self.start):
            chosen = keep[line]
            index = np.cumsum(keep) - 1
            owner = index[line[chosen]]
            h = span_hash(prefix_hash(LOWER_CODE[texts.data]), ws[chosen], we[chosen])
            sh, at = window_hash(h, owner, width)
            sh, of = sh >> np.uint64(6), owner[at]
        else:
            sh, of = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        order = np.lexsort((sh, of))
        sh, of = sh[order], of[order]
        new = np.r_[True, (sh[1:] != sh[:-1]) | (of[1:] != of[:-1])] if len(sh) else np.zeros(0, bool)
        self.keys, self.owner = sh[new], of[new]
        edges = np.searchsorted(self.owner, np.arange(len(self.start) + 1))
        self.first, self.n = edges[:-1], np.diff(edges)

    def __len__(self) -> int:
        return len(self.start)

    def set_keys(self, i: int) -> np.ndarray:
        return self.keys[self.first[i] : self.first[i] + self.n[i]]

    def set_ids(self) -> np.ndarray:
        if not len(self):
            return np.zeros(0, np.int64)
        total = np.add.reduceat(mix(self.keys), self.first)
        return mix(total + self.n.astype(np.uint64)).view(np.int64)

    def bands(self, bands: int, rows: int) -> np.ndarray:
        """A key for each paragraph and band, below the frequency bits."""
        out = np.zeros((len(self), bands), np.uint64)
        if len(self):
            for b in range(bands):
                acc = np.full(len(self), np.uint64(b + 1))
                for r in range(rows):
                    odd = mix(np.array([b * rows + r + 11], np.uint64))[0] | np.uint64(1)
                    turned = self.keys * odd
                    turned ^= turned >> np.uint64(32)
                    turned *= odd
                    acc = mix(acc * np.uint64(0x9E3779B97F4A7C15) + np.minimum.reduceat(turned, self.first))
                out[:, b] = acc >> np.uint64(64 - HASH_BITS)
        return out


def paragraph_table(docs: DataFrame, width: int, min_words: int, with_keys: bool, percent: int = 75, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, line, lines, start, stop (bytes), n_words, setid of each paragraph; with keys: n, bands and bitmap too."""

    def run(part, texts):
        p = Paragraphs(texts, width, min_words)
        if not len(p):
            return None
        columns = [part.column(0).take(pa.array(p.doc)), pa.array(p.line), pa.array(p.lines), pa.array(p.start_in_doc), pa.array(p.end_in_doc), pa.array(p.words), pa.array(p.set_ids())]
        names = ["doc_id", "line", "lines", "start", "stop", "n_words", "setid"]
        if with_keys:
            _, one = np.unique(p.set_ids(), return_index=True)  # copies in a batch are one set: the first
            linkable = 100 * p.n[one] >= percent * (p.n[one] + 1)  # a different set can reach the similarity
            bitmap, wide = bitmap_columns(places(mixed_keys(p.keys[runs(p.first[one], p.n[one])])), p.n[one])
            columns = [c.take(pa.array(one)) for c in columns] + [pa.array(p.n[one]), list_array(p.bands(bands, rows)[one[linkable]].ravel().view(np.int64), np.where(linkable, bands, 0)), bitmap, wide]
            names += ["n", "bands", "bitmap", "wide"]
        return pa.record_batch(columns, names)

    schema = "doc_id long, line long, lines long, start long, stop long, n_words long, setid long" + (", n long, bands array<long>, bitmap binary, wide binary" if with_keys else "")
    return docs.mapInArrow(over_texts(run), schema)


def fetch_paragraphs(docs: DataFrame, width: int, min_words: int):
    hashed = docs.select("doc_id", "text", F.xxhash64("doc_id").alias("h1"), F.xxhash64("doc_id", F.lit(1)).alias("h2"))

    def fetch(reps) -> DataFrame:
        shared = docs.sparkSession.sparkContext.broadcast(reps)

        def run(part, texts):
            p = Paragraphs(texts, width, min_words)
            key = np.stack([p.doc, p.set_ids()]) if len(p) else np.zeros((2, 0), np.int64)
            _, one = np.unique(key, axis=1, return_index=True)
            return pa.record_batch([part.column(0).take(pa.array(p.doc[one])), pa.array(p.set_ids()[one]), keys_column([p.set_keys(i) for i in one])], ["rep", "setid", "keys"])

        def only(batches):
            for t in batches:
                ok = shared.value.test(*(t.column(i).to_numpy().view(np.uint64) for i in (2, 3)))
                yield t.select([0, 1]).filter(pa.array(ok))

        return hashed.mapInArrow(lambda batches: over_texts(run)(only(batches)), "rep long, setid long, keys binary")

    return fetch


def duplicate_paragraphs(docs: DataFrame, width: int = 5, percent: int = 75, min_words: int = MIN_WORDS, passage_words: int = LENGTH, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Each paragraph of a component of several: its place, the place of the one that stays, and ``removed``.

    Rows of the unit ``passage`` are stretches of at least ``passage_words`` words, inside a line or over several, that
    an earlier document has (``removed``) or later ones have, unless a paragraph's row says so already; ``line`` is where
    they begin, ``component_size`` how many documents have their first ``passage_words`` words.
    """
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text"))
    found = paragraph_table(docs, width, min_words, with_keys=True, percent=percent)
    sets = saved(found.groupBy("setid", "n").agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands"), F.first("bitmap").alias("bitmap"), F.first("wide").alias("wide")))
    keyed = sets.withColumnRenamed("bands", "keys")
    index = classed(sets.select("setid", "n", F.posexplode("bands").alias("pos", "key")), keyed)
    comps = link_sets(index, keyed, fetch_paragraphs(docs, width, min_words), percent, ordered=False)
    places = paragraph_table(docs, width, min_words, with_keys=False).join(comps.withColumnRenamed("node", "setid"), "setid", "left").withColumn("comp", F.coalesce("comp", "setid"))
    places = saved(places)
    discard(sets, comps)
    first = places.groupBy("comp").agg(F.min(F.struct("doc_id", "line")).alias("first"), F.count("*").alias("size")).where("size > 1")
    lines = saved(places.join(first, "comp").select(
        "doc_id", "line", "lines", "start", "stop", "n_words", F.col("first.doc_id").alias("kept_doc_id"), F.col("first.line").alias("kept_line"), F.col("size").alias("component_size"),
        ((F.col("doc_id") != F.col("first.doc_id")) | (F.col("line") != F.col("first.line"))).alias("removed"), F.lit("line").alias("unit")))
    discard(places)
    passages = repeated_passages(docs, passage_words).select(
        "doc_id", "line", F.lit(None).cast("long").alias("lines"), "start", "stop", (F.col("last") - F.col("first") + passage_words).alias("n_words"), "kept_doc_id", "kept_line", F.col("places").alias("component_size"),
        (F.col("doc_id") != F.col("kept_doc_id")).alias("removed"), F.lit("passage").alias("unit"))
    said = lines.select("doc_id", F.explode(F.sequence("line", F.col("line") + F.col("lines") - 1)).alias("line"), F.col("start").alias("s"), F.col("stop").alias("e"), F.col("removed").alias("r"))
    within = (F.col("start") >= F.col("s")) & (F.col("stop") <= F.col("e")) & (F.col("r") | ~F.col("removed"))
    more = passages.join(said, ["doc_id", "line"], "left").where(~F.coalesce(within, F.lit(False))).select(*lines.columns)
    return lines.unionByName(more)


def without(raw: bytes, lines: set[int], spans: list[tuple[int, int]]) -> bytes:
    """A text without whole lines and without stretches of bytes; a line that these leave blank goes too."""
    keep = np.ones(len(raw), bool)
    for a, b in spans:
        keep[a:b] = False
    out, at = [], 0
    for i, line in enumerate(raw.split(b"\n")):
        mask = keep[at : at + len(line)]
        at += len(line) + 1
        if i not in lines:
            left = line if mask.all() else np.frombuffer(line, np.uint8)[mask].tobytes()
            if left == line or left.strip():
                out.append(left)
    return b"\n".join(out)


def remove_paragraphs(docs: DataFrame, id_col: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """``docs`` without its removed paragraphs and passages; all else stays; a text left blank leaves no row."""
    gone = duplicate_paragraphs(docs, id_col=id_col, text=text, **options).where("removed")
    span = F.when(F.col("unit") == "passage", F.struct("start", "stop"))
    lists = gone.groupBy(F.col("doc_id").alias("__id")).agg(F.flatten(F.collect_list(F.when(F.col("unit") == "line", F.sequence("line", F.col("line") + F.col("lines") - 1)))).alias("__lines"), F.collect_list(span["start"]).alias("__starts"), F.collect_list(span["stop"]).alias("__stops"))
    own = docs.toDF(*(f"c{k}" for k in range(len(docs.columns))))  # whatever the columns are called
    joined = own.join(lists, F.col(f"c{docs.columns.index(id_col)}") == F.col("__id"), "left").select(*own.columns, "__lines", "__starts", "__stops")
    place, width = docs.columns.index(text), len(docs.columns)

    def cut(batches):
        for t in batches:
            hit = t.column(width).is_valid().to_numpy(zero_copy_only=False)
            values = t.column(place)
            if hit.any():
                new = values.to_pylist()
                for i in np.flatnonzero(hit).tolist():
                    lines, starts, stops = (t.column(width + k)[i].as_py() for k in range(3))
                    left = without(new[i].encode(), set(lines), list(zip(starts, stops)))
                    new[i] = left.decode() if left.strip() else None
                values = pa.array(new, values.type)
            keep = ~hit | values.is_valid().to_numpy(zero_copy_only=False)
            columns = [values if k == place else t.column(k) for k in range(width)]
            yield pa.record_batch(columns, docs_columns).filter(pa.array(keep))

    docs_columns = docs.columns
    return joined.mapInArrow(cut, docs.schema)
