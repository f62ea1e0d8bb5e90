"""N-gram Jaccard self-join: linked documents by exact similarity of their shingle sets.

Index rows come from prefixes: with members ordered by one global order (frequent shingles last), two sets that reach
the similarity share a member of their prefixes of n - ceil(t n) + 1.  The frequent shingles are those that single
tasks see most often, merged; the order only steers work, so which are listed can't change the result.  Candidates are
then cut by sizes (tiles of size-ordered blocks), positions and bitmap bounds before exact intersections; see ``links``.

Shingles are 58-bit content hashes.  Defined cases: a null or blank text has no shingles, is linked with nothing and is
its own component; a text with fewer words than a shingle is one shingle; copies are linked with each other; extra
columns are ignored; an empty table gives no rows; repeated rows (same id) are rows of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm.links import HASH_BITS, bitmap_columns, keys_column, link_sets, mixed_keys, places
from mixagg.llm.session import discard, saved
from mixagg.llm.textkit import Frequent, Texts, list_array, mix, over_texts, segments, shingles

TOP_PER_TASK, TOP_SHINGLES = 2048, 1 << 15
RARE = 64  # a pair is tested in the first round if more than a 64th of its members name it
_MASK = np.uint64((1 << HASH_BITS) - 1)


def frequent_shingles(docs: DataFrame, width: int, top: int = TOP_SHINGLES, per_task: int = TOP_PER_TASK) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes and frequency classes (binary logarithms) of shingles that many documents have."""

    def count(batches):
        seen = Frequent(per_task)
        for _ in over_texts(lambda part, texts: seen.add(shingles(texts, width)[0] >> np.uint64(6)), max_bytes=1 << 21)(batches):
            pass
        yield seen.batch()

    merged = docs.select("text").mapInArrow(count, "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))
    got = merged.orderBy(F.desc("n"), "h").limit(top).toArrow()
    h, n = got.column("h").to_numpy().view(np.uint64), got.column("n").to_numpy()
    order = np.argsort(h)
    return h[order], np.log2(np.maximum(n[order], 1)).astype(np.uint64)


def set_keys(texts: Texts, width: int, frequent) -> list[np.ndarray]:
    """Each document's distinct shingle keys, sorted: frequency class in the high bits, hash below."""
    h, d = shingles(texts, width)
    h >>= np.uint64(6)
    if frequent is not None and len(frequent[0]):
        i = np.minimum(np.searchsorted(frequent[0], h), len(frequent[0]) - 1)
        h |= np.where(frequent[0][i] == h, frequent[1][i], np.uint64(0)) << np.uint64(HASH_BITS)
    a, b = segments(h, d, len(texts))
    return [distinct(h[i:j]) for i, j in zip(a.tolist(), b.tolist())]


def distinct(keys: np.ndarray) -> np.ndarray:
    """The different keys, sorted."""
    keys = np.sort(keys)
    return keys[np.r_[True, keys[1:] != keys[:-1]]] if len(keys) else keys


def set_id(keys: np.ndarray) -> int:
    """A content id: a sum of mixed members, mixed with their number."""
    return int(mix((mix(keys & _MASK).sum(dtype=np.uint64) + np.uint64(len(keys))).reshape(1)).view(np.int64)[0])


def set_ids(mixed: np.ndarray, n: np.ndarray) -> np.ndarray:
    """``set_id`` of neighbouring sets with ``n`` members each, from all their mixed members."""
    total = np.r_[np.uint64(0), np.cumsum(mixed, dtype=np.uint64)]
    end = np.cumsum(n)
    return mix(total[end] - total[end - n] + n.astype(np.uint64)).view(np.int64)


def set_table(docs: DataFrame, width: int, percent: int, frequent) -> DataFrame:
    """doc_id, n, setid, prefix, bitmap, wide per document."""
    shared = docs.sparkSession.sparkContext.broadcast(frequent)

    def run(part, texts):
        keys = set_keys(texts, width, shared.value)
        n = np.array([len(k) for k in keys], np.int64)
        prefix = [k[: len(k) + (-percent * len(k) // 100) + 1] if len(k) else k for k in keys]
        mixed = mixed_keys(np.concatenate(keys) if len(keys) else np.zeros(0, np.uint64))
        bitmap, wide = bitmap_columns(places(mixed), n)
        prefixes = list_array(np.concatenate(prefix).view(np.int64), np.array([len(p) for p in prefix]))
        return pa.record_batch([part.column(0), pa.array(n), pa.array(set_ids(mixed, n)), prefixes, bitmap, wide], ["doc_id", "n", "setid", "prefix", "bitmap", "wide"])

    return docs.mapInArrow(over_texts(run), "doc_id long, n long, setid long, prefix array<long>, bitmap binary, wide binary")


def fetch_sets(docs: DataFrame, width: int, frequent):
    """A fetch function for ``links``: the sets of documents in a Bloom filter."""
    hashed = docs.select("doc_id", "text", F.xxhash64("doc_id").alias("h1"), F.xxhash64("doc_id", F.lit(1)).alias("h2"))

    def fetch(reps) -> DataFrame:
        shared = docs.sparkSession.sparkContext.broadcast((reps, frequent))

        def run(part, texts):
            keys = set_keys(texts, width, shared.value[1])
            return pa.record_batch([part.column(0), pa.array(set_ids(mixed_keys(np.concatenate(keys)), np.array([len(k) for k in keys]))), keys_column(keys)], ["rep", "setid", "keys"])

        def only(batches):
            for t in batches:
                ok = shared.value[0].test(*(t.column(i).to_numpy().view(np.uint64) for i in (2, 3)))
                yield t.select([0, 1]).filter(pa.array(ok))

        return hashed.mapInArrow(lambda batches: over_texts(run)(only(batches)), "rep long, setid long, keys binary")

    return fetch


def linked_documents(docs: DataFrame, width: int = 5, percent: int = 75, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id (the smallest id that links reach) of every row."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text"))
    frequent = frequent_shingles(docs, width)
    table = saved(set_table(docs, width, percent, frequent))
    places_of = saved(table.select("doc_id", "n", "setid"))
    some = table.where("n > 0").groupBy("setid", "n").agg(F.min("doc_id").alias("rep"), F.first("prefix").alias("prefix"), F.first("bitmap").alias("bitmap"), F.first("wide").alias("wide"))
    sets = saved(some)
    discard(table)
    index = sets.select("setid", "n", F.posexplode("prefix").alias("pos", "key"))
    comps = link_sets(index, sets.withColumnRenamed("prefix", "keys"), fetch_sets(docs, width, frequent), percent, RARE)
    label = sets.select("setid", "rep").join(comps.withColumnRenamed("node", "setid"), "setid", "left").withColumn("comp", F.coalesce("comp", "setid"))
    least = label.groupBy("comp").agg(F.min("rep").alias("component_id"))
    of_set = saved(label.join(least, "comp").select("setid", "component_id"))
    discard(sets, comps)
    linked = places_of.where("n > 0").join(of_set, "setid").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return linked.unionByName(places_of.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def keep_first(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of ``docs`` whose document is its component's smallest; rows without shingles stay."""
    gone = linked_documents(docs, id_col=id_col, **options).where("doc_id != component_id").select(F.col("doc_id").alias("__gone"))
    return docs.join(gone, docs[id_col] == gone["__gone"], "left_anti")
