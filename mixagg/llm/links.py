"""Sets, candidate links, exact links and connected components, shared by the similarity operators.

A *set* is a distinct set of shingle hashes with an id made from its content, so copies are one set.  Candidates come
from index rows (key, set): sets that share a key.  Two rounds find every link that any key proposes without ever
listing all pairs of a group:

1. in each key's group, ordered by size, a set is paired with the smallest set that its size allows and with its
   predecessor; pairs that many keys name are intersected exactly and give components.  This only steers the work;
2. index rows are dealt to size-banded tiles: a tile is a key and a band of sizes, each band ``100 / percent`` times as
   wide as the one below.  A set is at home in its own band's tile and a guest in the next band's, if its position
   still allows a link there; so each pair of sizes that may link meets in the larger one's tile.  Tiles with several
   components get their sets' hashed bitmaps, and only pairs from different components whose sizes, positions and bit
   counts allow a link leave the task, to be intersected exactly.  Tiles with far more such pairs than rows first name
   each row's likeliest partner; links found so merge components, and those tiles are searched again, until such a
   turn finds nothing and all pairs that are left are tested.

Pairs within a component need no test: they can't change the result.  Tiles of more than ``TILE_ROWS`` rows are cut
into blocks that meet pairwise, but for rows of a tile's largest component, which only meet the other rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm import bloom
from mixagg.llm.session import discard, saved
from mixagg.llm.textkit import Frequent, grouped, mix

LEAST_BITS, MOST_BITS = 512, 4096  # of a bitmap in a tile
TILE_ROWS = 4096
BYTES_AT_ONCE = 1 << 24  # of bitmaps that a task compares together
PAIRS_PER_ROW = 4  # beyond which a tile first names likely partners only
BACK = 6  # keys before its own that a tile's row knows
NEIGHBOURS = 8  # in a small group, tested one by one
FOREST_EDGES = 200_000  # of a task that joins edges to trees
HASH_BITS = 58  # of a shingle key; the bits above hold its frequency class
HOT_CLASS = 12  # binary logarithm of the rows from which a key's group is salted


def places(mixed: np.ndarray) -> np.ndarray:
    """Where mixed keys stand in bitmaps, before the width is taken off."""
    return (mixed >> np.uint64(20)).astype(np.int64)


def mixed_keys(keys: np.ndarray) -> np.ndarray:
    return mix(keys & np.uint64((1 << HASH_BITS) - 1))


def widths(n: np.ndarray) -> np.ndarray:
    """The bits of each set's bitmap: at least two a member, a power of two."""
    return np.maximum(LEAST_BITS, 1 << np.ceil(np.log2(np.maximum(2 * n, 2))).astype(np.int64))


def bitmap_columns(at: np.ndarray, n: np.ndarray) -> tuple[pa.Array, pa.Array]:
    """(bitmap of at most MOST_BITS, whole bitmap where that is wider) of neighbouring sets with members' places ``at``."""
    wide = widths(n)
    capped = np.minimum(wide, MOST_BITS)

    def build(width: np.ndarray, at: np.ndarray, n: np.ndarray) -> pa.Array:
        off = np.r_[0, np.cumsum(width)]
        row = np.zeros(off[-1], np.uint8)
        row[np.repeat(off[:-1], n) + (at & np.repeat(width - 1, n))] = 1
        offsets = pa.py_buffer((off // 8).astype(np.int32).tobytes())
        return pa.Array.from_buffers(pa.binary(), len(width), [None, offsets, pa.py_buffer(np.packbits(row, bitorder="little").tobytes())])

    whole = pa.nulls(len(n), pa.binary())
    large = wide > capped
    if large.any():
        index = np.where(large, np.cumsum(large) - 1, -1)
        whole = build(wide[large], at[np.repeat(large, n)], n[large]).take(pa.array(index, mask=~large))
    return build(capped, at, n), whole


def wide_bound(x: bytes, y: bytes, n1: int, n2: int) -> int:
    """The overlap bound of two sets from bitmaps that may differ in width: the wider one is folded."""
    a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
    while len(a) > len(b):
        a = a[: len(a) // 2] | a[len(a) // 2 :]
    while len(b) > len(a):
        b = b[: len(b) // 2] | b[len(b) // 2 :]
    return min(n1 - int(np.bitwise_count(a & ~b).sum()), n2 - int(np.bitwise_count(b & ~a).sum()))


def needed(n1: np.ndarray, n2: np.ndarray, percent: int) -> np.ndarray:
    """The smallest overlap at which sets of these sizes reach the similarity."""
    return -(-percent * (n1 + n2) // (100 + percent))


def overlap_bound(w1: np.ndarray, w2: np.ndarray, n1: np.ndarray, n2: np.ndarray) -> np.ndarray:
    """An upper bound on the overlap from rows of bitmap words: a bit that only one side sets stands for a member that the other lacks."""
    return np.minimum(n1 - np.bitwise_count(w1 & ~w2).sum(1).astype(np.int64), n2 - np.bitwise_count(w2 & ~w1).sum(1).astype(np.int64))


def folded(column: pa.Array, rows: np.ndarray, width: int) -> np.ndarray:
    """The bitmaps of ``rows`` as words, folded to ``width`` bits."""
    off = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8)
    size = off[rows + 1] - off[rows]
    out = np.zeros((len(rows), width // 8), np.uint8)
    for part in range(int(size.max()) // (width // 8)):
        has = np.flatnonzero(size > part * (width // 8))
        out[has] |= data[(off[rows[has]] + part * (width // 8))[:, None] + np.arange(width // 8)]
    return out.view(np.uint64)


def classed(index: DataFrame, sets: DataFrame, per_task: int = 2048, top: int = 1 << 15) -> DataFrame:
    """``index`` with the frequency classes of its hottest keys in their high bits: those of which single tasks see most.

    At most ``top`` keys are broadcast.  A class only splits work, so which keys are listed can't change the result.
    """

    def count(batches):
        seen = Frequent(per_task)
        for t in batches:
            seen.add(t.column(0).flatten().to_numpy().view(np.uint64))
        yield seen.batch()

    counts = sets.select("keys").mapInArrow(count, "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where(F.col("n") >= 1 << HOT_CLASS)
    hot = counts.orderBy(F.desc("n"), "h").limit(top).select(F.col("h").alias("key"), F.floor(F.log2("n")).cast("long").alias("class"))
    high = F.coalesce(F.shiftleft("class", HASH_BITS), F.lit(0).cast("long"))
    return index.join(F.broadcast(hot), "key", "left").withColumn("key", F.col("key").bitwiseOR(high)).drop("class")


def shared_rows(index: DataFrame, percent: int, ordered: bool) -> DataFrame:
    """Index rows of keys that several sets have and whose sizes and positions let some of those sets link; with each row
    its group's leader (the smallest set that its size allows) and its predecessor.

    Keys whose frequency class says that thousands of sets share them are salted by set, and all their rows are kept.
    """
    high = F.shiftrightunsigned("key", HASH_BITS)
    hot = high >= HOT_CLASS
    salt = F.when(hot, F.pmod(F.xxhash64("setid"), F.pow(F.lit(2.0), high - HOT_CLASS + 1).cast("long"))).otherwise(F.lit(0).cast("long"))
    rows = index.select("key", "setid", "n", "pos").withColumn("group", F.xxhash64("key", salt)).withColumn("hot", hot)

    def lead(cols, starts):
        g, n, pos, size = cols["group"], cols["n"].astype(np.int64), cols["pos"].astype(np.int64), len(cols["group"])
        left = n - pos if ordered else n
        many = np.diff(np.r_[starts, size])
        idx = np.repeat(np.arange(len(starts)), many)
        order = idx * (1 << 32) + n  # rising: groups, then sizes
        leader = np.searchsorted(order, idx * (1 << 32) - (-percent * n // 100))
        before = np.maximum(np.arange(size) - 1, starts[idx])
        keep = cols["hot"].astype(bool)
        for d in range(1, min(NEIGHBOURS, size)):  # all pairs of small groups; in large ones neighbours by size only
            i = np.flatnonzero((idx[d:] == idx[:-d]) & (percent * n[d:] <= 100 * n[:-d]) & ((many[idx[d:]] <= NEIGHBOURS) | (d == 1)))
            ok = (np.minimum(left[i], left[i + d]) >= needed(n[i], n[i + d], percent)) | (many[idx[i]] > NEIGHBOURS)
            keep[i[ok]] = keep[i[ok] + d] = True
        at = np.flatnonzero(keep)
        if not len(at):
            return None
        s = cols["setid"]
        return pa.record_batch([pa.array(x) for x in (cols["key"][at], s[at], n[at], pos[at], s[leader[at]], n[leader[at]], s[before[at]], n[before[at]], cols["hot"][at].astype(bool))], ["key", "setid", "n", "pos", "leader", "leader_n", "prev", "prev_n", "hot"])

    schema = "key long, setid long, n long, pos long, leader long, leader_n long, prev long, prev_n long, hot boolean"
    return rows.repartition("group").sortWithinPartitions("group", "n", "setid").mapInArrow(grouped("group", lead), schema)


def first_pairs(shared: DataFrame, percent: int, rare: int) -> DataFrame:
    """Round 1: pairs a < b that at least one key in ``rare`` of the smaller set's members names.

    Salted groups' leaders are joined by one more pair each.
    """
    leaders = shared.where("hot").select("key", "leader", "leader_n").distinct()
    heads = leaders.groupBy("key").agg(F.min(F.struct("leader_n", "leader")).alias("head"))
    across = leaders.join(heads, "key").select(F.col("leader").alias("x"), F.col("leader_n").alias("xn"), F.col("head.leader").alias("y"), F.col("head.leader_n").alias("yn"))
    pairs = shared.select(F.col("setid").alias("x"), F.col("n").alias("xn"), F.inline(F.array(F.struct(F.col("leader").alias("y"), F.col("leader_n").alias("yn")), F.struct(F.col("prev").alias("y"), F.col("prev_n").alias("yn")))))
    pairs = pairs.unionByName(across).where((F.col("x") != F.col("y")) & (100 * F.least("xn", "yn") >= percent * F.greatest("xn", "yn")))
    named = pairs.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count("*").alias("keys"), F.min(F.least("xn", "yn")).alias("n"))
    return named.where(F.col("keys") * rare > F.col("n")).select("a", "b")


def among(sets: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of ``sets`` that ``ids`` (column setid) names, and a few percent of the others: joined with it, only these move."""
    ids = ids.distinct()
    known = sets.sparkSession.sparkContext.broadcast(bloom.blocked(ids.select(F.xxhash64("setid").alias("h1"), F.xxhash64("setid", F.lit(1)).alias("h2")), ids.count()))
    columns = sets.columns

    def only(batches):
        for t in batches:
            ok = known.value.test(*(t.column(len(columns) + i).to_numpy().view(np.uint64) for i in (0, 1)))
            yield t.select(columns).filter(pa.array(ok))

    return sets.select(*columns, F.xxhash64("setid").alias("h1"), F.xxhash64("setid", F.lit(1)).alias("h2")).mapInArrow(only, sets.schema)


def bounded(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a saved table) whose whole bitmaps (a few percent of the sets' bytes) allow a link."""
    sets = among(sets.select("setid", "n", "bitmap", "wide"), pairs.select(F.explode(F.array("a", "b")).alias("setid")))
    side = lambda c: sets.select(F.col("setid").alias(c), F.col("n").alias(f"n{c}"), F.coalesce("wide", "bitmap").alias(f"m{c}"))
    joined = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "na", "nb", "ma", "mb")

    def keep(batches):
        for t in batches:
            if t.num_rows:
                na, nb = t.column(2).to_numpy().astype(np.int64), t.column(3).to_numpy().astype(np.int64)
                most = [wide_bound(x.as_py(), y.as_py(), i, j) for x, y, i, j in zip(t.column(4), t.column(5), na.tolist(), nb.tolist())]
                yield t.select([0, 1]).filter(pa.array(np.array(most) >= needed(na, nb, percent)))

    return joined.mapInArrow(keep, "a long, b long")


def linked(pairs: DataFrame, sets: DataFrame, fetch, percent: int) -> DataFrame:
    """The pairs that are links, by exact intersection of sorted arrays; a saved table.

    ``fetch(reps)`` gives (rep, setid, keys) for at least the sets of the documents in the Bloom filter ``reps``; the
    filter's size follows the number of sets asked for, beyond its limit it only prunes less.
    """
    asked = saved(pairs.select(F.inline(F.array(F.struct(F.col("a").alias("setid")), F.struct(F.col("b").alias("setid"))))).distinct().join(sets.select("setid", "rep"), "setid"))
    reps = bloom.blocked(asked.select(F.xxhash64("rep").alias("h1"), F.xxhash64("rep", F.lit(1)).alias("h2")), asked.count())
    arrays = saved(fetch(reps).join(asked, ["setid", "rep"]).select("setid", "keys"))
    side = lambda c: arrays.select(F.col("setid").alias(c), F.col("keys").alias(f"k{c}"))
    joined = pairs.join(side("b"), "b").join(side("a"), "a").select("a", "b", "ka", "kb")

    def test(batches):
        for t in batches:
            ok = np.zeros(t.num_rows, bool)
            for i, (x, y) in enumerate(zip(t.column(2), t.column(3))):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                if len(p) > len(q):
                    p, q = q, p
                both = int((q[np.minimum(np.searchsorted(q, p), len(q) - 1)] == p).sum())
                ok[i] = 100 * both >= percent * (len(p) + len(q) - both)
            yield t.select([0, 1]).filter(pa.array(ok))

    out = saved(joined.mapInArrow(test, "a long, b long"))
    discard(asked, arrays)
    return out


def _forest(batches):
    """Star edges (node, root) of the trees that a partition's edges join."""
    root: dict[int, int] = {}

    def find(x: int) -> int:
        while (p := root.setdefault(x, x)) != x:
            root[x] = root[p]
            x = root[x]
        return x

    for t in batches:
        for a, b in zip(t.column(0).to_pylist(), t.column(1).to_pylist()):
            a, b = find(a), find(b)
            if a != b:
                root[max(a, b)] = min(a, b)
    nodes = [x for x in root if find(x) != x]
    yield pa.record_batch([pa.array(nodes, pa.int64()), pa.array([find(x) for x in nodes], pa.int64())], ["u", "v"])


def components(edges: DataFrame, at_once: int = FOREST_EDGES) -> DataFrame:
    """(node, comp): the smallest node that each node of the undirected ``edges`` (a, b) reaches; a saved table.

    Tasks of about ``at_once`` edges first reduce them to forests; where one task is not all, nodes and their smallest
    neighbours are contracted in turns (large and small stars) until all edges are stars.  Only aggregates and joins: no
    list of a node's edges.
    """
    given = saved(edges.select(F.least("a", "b").alias("v"), F.greatest("a", "b").alias("u")).where("u != v").select("u", "v"))
    tasks = -(-given.count() // at_once)
    cur = saved(given.coalesce(max(tasks, 1)).mapInArrow(_forest, "u long, v long").distinct())
    discard(given)
    mark = None
    while tasks > 1:
        now = cur.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark or not now[0]:
            break
        mark = now
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(small, "u")
        after = saved(joined.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v"))).where("u != v").distinct())
        discard(cur)
        cur = after
    out = saved(cur.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(cur.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct()))
    discard(cur)
    return out


def likely(i: np.ndarray, j: np.ndarray, score: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of these pairs those that are some row's pair of the highest score (the first of ties)."""
    row, at = np.r_[i, j], np.tile(np.arange(len(i)), 2)
    order = np.lexsort((at, -score[at], row))
    best = np.unique(at[order[np.r_[True, row[order][1:] != row[order][:-1]]]]) if len(i) else at
    return i[best], j[best], score[best]


def tiles(shared: DataFrame, comps: DataFrame, percent: int, ordered: bool) -> DataFrame:
    """Round 2's rows: tile, key, setid, n, pos, comp, guest, block, inner, of tiles in which several components meet."""
    base = 100 / percent + 1e-4 if percent < 100 else 2.0
    rows = shared.select("key", "setid", "n", "pos").join(comps.select(F.col("node").alias("setid"), "comp"), "setid", "left").withColumn("comp", F.coalesce("comp", "setid"))
    band = F.floor(F.log("n") / math.log(base)).cast("int")
    above = F.pow(F.lit(base), F.col("band") + 1) - 1e-6  # no set of the next band is smaller
    visits = (F.col("n") - (F.col("pos") if ordered else 0)) * (100 + percent) >= percent * (F.col("n") + above) - 1e-6
    dealt = rows.withColumn("band", band).withColumn("two", F.when(visits, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0))))
    dealt = dealt.withColumn("up", F.explode("two")).withColumn("band", F.col("band") + F.col("up")).withColumn("guest", F.col("up") == 1).drop("two", "up")
    mixed = saved(dealt.groupBy("key", "band").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("c"), F.bool_and("guest").alias("empty")).where("lo != hi and not empty").select("key", "band", "c"))
    large = mixed.where(F.col("c") > TILE_ROWS)
    whole = dealt.join(mixed.where(F.col("c") <= TILE_ROWS).select("key", "band"), ["key", "band"]).withColumn("lo", F.lit(0).cast("long")).withColumn("hi", F.lit(0).cast("long")).withColumn("block", F.lit(0).cast("long"))
    if not large.isEmpty():
        counts = dealt.join(large.select("key", "band"), ["key", "band"]).groupBy("key", "band", "comp").agg(F.count("*").alias("k"))
        top = counts.groupBy("key", "band").agg(F.max(F.struct("k", "comp")).alias("top"), F.sum("k").alias("c"))
        plan = saved(top.select("key", "band", F.col("top.comp").alias("main"), F.ceil(F.col("top.k") / TILE_ROWS).alias("mains"), F.ceil((F.col("c") - F.col("top.k")) / TILE_ROWS).alias("others")))
        cut = dealt.join(plan, ["key", "band"]).withColumn("is_main", F.col("comp") == F.col("main"))
        cut = cut.withColumn("block", F.pmod(F.xxhash64("setid"), F.when(F.col("is_main"), F.col("mains")).otherwise(F.col("others"))) + F.when(F.col("is_main"), F.col("others")).otherwise(0))
        cut = cut.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.when(F.col("is_main"), F.col("others")).otherwise(F.col("others") + F.col("mains")) - 1)))
        cut = cut.withColumn("lo", F.least("block", "other")).withColumn("hi", F.greatest("block", "other"))
        whole = whole.unionByName(cut.select(*whole.columns))
    return whole.select(F.xxhash64("key", "band", "lo", "hi").alias("tile"), "key", "setid", "n", "pos", "comp", "guest", "block", (F.col("lo") == F.col("hi")).alias("inner"))


def mixed_pairs(shared: DataFrame, sets: DataFrame, comps: DataFrame, percent: int, whole: bool, ordered: bool) -> DataFrame:
    """Round 2: pairs (a, b) of different components that share a key and may be links.

    A row knows the ``BACK`` keys before its own: pairs that share one of those are left to its tile.  Unless ``whole``, tasks whose tiles have many pairs give each row's likeliest only, and the keys of those tiles as
    rows (key, null).
    """
    earlier = [F.coalesce(F.get("keys", (F.col("pos") - k).cast("int")), F.lit(0).cast("long")).alias(f"k{k}") for k in range(1, BACK + 1)]
    full = tiles(shared, comps, percent, ordered).join(sets.select("setid", "bitmap", "keys"), "setid").select("*", *earlier).drop("keys")
    per_row = PAIRS_PER_ROW

    def search(cols, starts):
        n, pos, comp, blk, s, inner, guest = (cols[c] for c in ("n", "pos", "comp", "block", "setid", "inner", "guest"))
        size = len(n)
        left, past = n - pos if ordered else n, np.stack([cols[f"k{k}"] for k in range(1, BACK + 1)], axis=1)
        tile = np.repeat(np.arange(len(starts)), np.diff(np.r_[starts, size]))
        group = tile << 32
        to = np.searchsorted(group + n, group + 100 * n // percent, side="right")  # first row that is too large
        turn = np.flatnonzero(np.r_[comp[1:] != comp[:-1], True])
        other = turn[np.searchsorted(turn, np.arange(size))] + 1  # next row of another component
        wide = np.minimum(widths(n[starts]), MOST_BITS)[tile]  # the smallest set's, for a tile
        got, partial, held = [], False, 0
        for width in np.unique(wide).tolist():
            mine = np.flatnonzero(wide == width)
            local = np.zeros(size, np.int64)
            local[mine] = np.arange(len(mine))
            words = folded(cols["bitmap"], mine, width)
            spans = np.maximum(to[mine] - other[mine], 0)
            total = np.cumsum(spans)
            at_once, lo = max(BYTES_AT_ONCE // (width // 8), 1), 0
            while lo < len(mine):
                base = total[lo - 1] if lo else 0
                hi = max(int(np.searchsorted(total, base + at_once, side="right")), lo + 1)
                row = np.repeat(np.arange(lo, hi), spans[lo:hi])
                i = mine[row]
                j = other[i] + np.arange(len(i)) - (total[row] - spans[row] - base)
                lo = hi
                ok = (comp[i] != comp[j]) & (inner[i] | (blk[i] != blk[j])) & ~(guest[i] & guest[j])
                i, j = i[ok], j[ok]
                ok = np.minimum(left[i], left[j]) >= needed(n[i], n[j], percent)
                i, j = i[ok], j[ok]
                if len(i):
                    most = overlap_bound(words[local[i]], words[local[j]], n[i], n[j])
                    ok = most >= needed(n[i], n[j], percent)
                    i, j, most = i[ok], j[ok], most[ok]
                    again = np.zeros(len(i), bool)
                    for k in range(BACK):
                        again |= ((past[i, k][:, None] == past[j]) & (past[j] != 0)).any(1)
                    i, j, most = i[~again], j[~again], most[~again]
                    got.append((i, j, most / (n[i] + n[j])))
                    held += len(i)
                    if not whole and held > per_row * size:
                        partial, got = True, [likely(*(np.concatenate(v) for v in zip(*got)))]
                        held = len(got[0][0])
        if not got:
            return None
        i, j, score = (np.concatenate(v) for v in zip(*got))
        again = np.zeros(0, np.int64)
        if partial:
            again = np.unique(cols["key"][i])
            i, j, _ = likely(i, j, score)
        x, y = np.minimum(s[i], s[j]), np.maximum(s[i], s[j])
        order = np.lexsort((y, x))
        x, y = x[order], y[order]
        new = np.flatnonzero(np.r_[True, (x[1:] != x[:-1]) | (y[1:] != y[:-1])][: len(x)])
        return pa.record_batch([pa.array(np.r_[x[new], again]), pa.array(np.r_[y[new], again], mask=np.r_[np.zeros(len(new), bool), np.ones(len(again), bool)])], ["a", "b"])

    return full.repartition("tile").sortWithinPartitions("tile", "n", "setid").mapInArrow(grouped("tile", search), "a long, b long").distinct()


def link_sets(index: DataFrame, sets: DataFrame, fetch, percent: int = 75, rare: int = 1 << 40, ordered: bool = True) -> DataFrame:
    """(node, comp) of all sets that have a link; ``sets``: setid, n, rep, keys, bitmap, wide; ``index``: key, setid, n, pos.

    ``keys`` are a set's index keys by ``pos``.  ``ordered`` says that they are its members in one global order, so that
    sets whose first common key stands at some position have no more common members than stand from there on.
    """
    shared = saved(shared_rows(index, percent, ordered))
    named = saved(first_pairs(shared, percent, rare))
    tested = saved(bounded(named, sets, percent))
    discard(named)
    links = linked(tested, sets, fetch, percent)
    comps = components(links)
    discard(links)
    search, some, whole = shared, sets, False
    while True:
        found = saved(mixed_pairs(search, some, comps, percent, whole, ordered))
        fresh = saved(found.where("b is not null").join(tested, ["a", "b"], "left_anti"))
        more = saved(bounded(fresh, sets, percent))
        discard(fresh)
        tested = tested.unionByName(more)
        new = None if more.isEmpty() else linked(more, sets, fetch, percent)
        whole = new is None or new.isEmpty()
        if not whole:  # the new links join whole components
            side = lambda c: comps.select(F.col("node").alias(c), F.col("comp").alias(f"{c}_comp"))
            of = lambda c: F.coalesce(f"{c}_comp", c).alias(c)
            joint = components(new.join(side("a"), "a", "left").join(side("b"), "b", "left").select(of("a"), of("b")))
            ends = new.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(comps, "node", "left_anti").select("node", F.col("node").alias("comp"))
            merged = comps.unionByName(ends).join(joint.select(F.col("node").alias("comp"), F.col("comp").alias("now")), "comp", "left").select("node", F.coalesce("now", "comp").alias("comp"))
            comps = saved(merged)
        again = found.where("b is null").select(F.col("a").alias("key"))
        if again.isEmpty():
            discard(shared)
            return comps
        search = saved(shared.join(again, "key", "left_semi"))
        some = among(sets, search.select("setid"))


def keys_column(values: list[np.ndarray]) -> pa.Array:
    """Sorted key arrays as large binary, 8 bytes a key."""
    off = np.r_[0, np.cumsum([8 * len(v) for v in values])].astype(np.int64)
    data = pa.py_buffer(b"".join([v.tobytes() for v in values]))
    return pa.Array.from_buffers(pa.large_binary(), len(values), [None, pa.py_buffer(off.tobytes()), data]).cast(pa.binary())
