"""Nearest neighbours by randomly rotated one-bit codes.

Index: centroids are fitted on a bounded sample; every vector is stored in its nearest centroid's cell as the signs
of its rotated unit residual (one bit a dimension) with two scalars, the residual's length and its inner product with
its own code.  Search: a query visits the cells nearest to it; the code and the scalars give an unbiased estimate of
each inner product and a bound on its error, and only vectors whose lower bound on the distance beats the current
k-th exact distance are measured exactly.

Equal vectors are one index entry that keeps the k + 1 smallest ids (more can't appear in any answer), so copies cost
nothing; cells are split into parts of ``part_rows`` and queries into blocks of ``query_rows``, so tasks are bounded.
How many cells a query visits is calibrated on the sample for ``target`` recall; queries that find fewer than k there
visit all cells, so each has k neighbours, or all candidates.
Defined cases: repeated ids are rows of their own (as candidates, each may be listed); vectors that are null, zero, of another length than most, or hold null or non-finite components take no
part, as queries or candidates; ties go to the smaller id; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from mixagg.llm.session import saved
from mixagg.llm.textkit import binary_array, grouped

SAMPLE_ROWS, CALIBRATION_QUERIES = 20_000, 200


def clean_vectors(df: DataFrame, id_col: str, vector: str, dim: int | None) -> tuple[DataFrame, int]:
    v = F.col("v")
    finite = F.forall(v, lambda x: F.coalesce(F.abs(x) < float("inf"), F.lit(False))) & F.exists(v, lambda x: x != 0)
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v")).where(v.isNotNull() & (F.size(v) > 0) & finite)
    if dim is None:
        top = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
        dim = top["d"] if top else 1
    return rows.where(F.size("v") == dim), dim


def rotation(dim: int, seed: int = 7) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def k_means(x: np.ndarray, k: int, rounds: int = 8, seed: int = 7) -> np.ndarray:
    c = x[np.random.default_rng(seed).choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = nearest(x, c)
        size = np.bincount(near, minlength=k)
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        c[size > 0] = total[size > 0] / size[size > 0, None]
    return c


def squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None], 0)


def nearest(x: np.ndarray, c: np.ndarray, block: int = 4096) -> np.ndarray:
    return np.concatenate([squared(x[i : i + block], c).argmin(1) for i in range(0, len(x), block)]) if len(x) else np.zeros(0, np.int64)


def calibrate(x: np.ndarray, c: np.ndarray, k: int, target: float) -> int:
    """The fewest cells that hold ``target`` of the sample's true neighbours, over some sample queries, and a margin."""
    q = x[np.linspace(0, len(x) - 1, min(len(x), CALIBRATION_QUERIES)).astype(int)]
    cell, order = nearest(x, c), squared(q, c).argsort(1)
    rank = np.empty_like(order)
    np.put_along_axis(rank, order, np.arange(len(c))[None], 1)
    near = np.argpartition(squared(q, x), min(k, len(x) - 1), axis=1)[:, : k + 1]
    needed = np.sort(np.take_along_axis(rank, cell[near], 1).ravel())
    return min(len(c), int(needed[min(len(needed) - 1, math.ceil(target * len(needed)))]) + 2)


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return np.asarray(column.flatten()).astype(np.float64).reshape(-1, dim)


class Model:
    def __init__(self, centroids: np.ndarray, turn: np.ndarray, visits: int) -> None:
        self.centroids, self.turn, self.visits = centroids, turn, visits

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Cell, residual length, code bits and <unit residual, code> of each vector."""
        cell = nearest(x, self.centroids)
        r = x - self.centroids[cell]
        length = np.sqrt((r * r).sum(1))
        turned = (r / np.where(length > 0, length, 1)[:, None]) @ self.turn.T
        sign = turned >= 0
        own = np.abs(turned).sum(1) / math.sqrt(x.shape[1])
        return cell, length, np.packbits(sign, axis=1), np.where(length > 0, own, 1)


def exact_distance(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    d = x - q
    return np.sqrt((d * d).sum(1))


def search_block(model: Model, cell: int, q: np.ndarray, x: np.ndarray, length, code, own, k: int, width: float) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each query the k best rows of a block (indices, exact distances), measured only where the bound allows."""
    dim = x.shape[1]
    base = q - model.centroids[cell]
    q_len = np.sqrt((base * base).sum(1))
    turned = (base / np.where(q_len > 0, q_len, 1)[:, None]) @ model.turn.T
    signs = np.unpackbits(code, axis=1)[:, :dim].astype(np.float32) * 2 - 1
    inner = (signs @ turned.T.astype(np.float32)).T / math.sqrt(dim) / own[None]
    slack = width * np.sqrt(np.maximum(1 - own * own, 0)) / own / math.sqrt(max(dim - 1, 1)) + 1e-4
    spread = 2 * length[None] * q_len[:, None]
    estimate = length[None] ** 2 + q_len[:, None] ** 2 - spread * inner
    lower = estimate - spread * slack[None]
    out = []
    for i in range(len(q)):
        first = np.argpartition(estimate[i], k - 1)[:k] if len(x) > k else np.arange(len(x))
        worst = np.sort(exact_distance(q[i], x[first]))[-1] if len(x) > k else np.inf
        chosen = np.flatnonzero(lower[i] <= worst * worst)
        chosen = np.union1d(chosen, first)
        d = exact_distance(q[i], x[chosen])
        best = np.argsort(d, kind="stable")
        if len(best) > k:
            best = best[d[best] <= d[best[k - 1]]]
        out.append((chosen[best], d[best]))
    return out


def fit(vectors: DataFrame, dim: int, k: int, target: float, sample_rows: int = SAMPLE_ROWS) -> tuple[Model, int]:
    """Centroids from a bounded sample: the ``sample_rows`` distinct vectors with the smallest id hashes."""
    n = vectors.count()
    some = vectors.orderBy(F.xxhash64("id"), "id").limit(sample_rows).select("v").toArrow().column("v").combine_chunks()
    x = _matrix(some, dim)
    cells = max(1, min(len(x) // 8, round(math.sqrt(n) / 2), 4096)) if len(x) else 1
    c = k_means(x, cells) if len(x) else np.zeros((1, dim))
    return Model(c, rotation(dim), calibrate(x, c, k, target) if len(x) else 1), n


def nearest_neighbours(
    base: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vector: str = "embedding", dim: int | None = None,
    target: float = 0.97, bound: float = 1.9, part_rows: int = 8192, query_rows: int = 1024, sample_rows: int = SAMPLE_ROWS,
) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k nearest rows of ``base`` other than the row of its own id."""
    spark = base.sparkSession
    rows, dim = clean_vectors(base, id_col, vector, dim)
    asked, _ = clean_vectors(queries, id_col, vector, dim)
    # Equal vectors are one entry: its k + 1 smallest ids; the rank limit is applied before the shuffle too.
    ranked = rows.withColumn("r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).where(F.col("r") <= k + 1)
    index = saved(ranked.groupBy("v").agg(F.min("id").alias("id"), F.sort_array(F.collect_list("id")).alias("ids")))
    model, n = fit(index, dim, k, target, sample_rows)
    shared = spark.sparkContext.broadcast(model)
    distinct = asked.groupBy("v").agg(F.min("id").alias("id"))

    def encode(batches):
        m = shared.value
        for batch in batches:
            if batch.num_rows:
                x = _matrix(batch.column(1), dim)
                cell, length, code, own = m.encode(x)
                yield pa.record_batch([batch.column(0), pa.array(cell), pa.array(length), pa.array(own), binary_array(code.tobytes(), np.full(len(x), code.shape[1])), binary_array(x.tobytes(), np.full(len(x), 8 * dim)), batch.column(2)], ["id", "cell", "length", "own", "code", "vector", "ids"])

    coded = saved(index.select("id", "v", "ids").mapInArrow(encode, "id long, cell long, length double, own double, code binary, vector binary, ids array<long>"))

    def look(some: DataFrame, cells_each: int) -> DataFrame:
        """id, best: the k + 1 nearest found for each query of ``some`` in the cells nearest to it."""

        def visit(batches):
            m = shared.value
            for batch in batches:
                if batch.num_rows:
                    x = _matrix(batch.column(1), dim)
                    cells = np.sort(np.argpartition(squared(x, m.centroids), cells_each - 1, axis=1)[:, : cells_each], axis=1) if cells_each < len(m.centroids) else np.tile(np.arange(len(m.centroids)), (len(x), 1))
                    ids = np.repeat(batch.column(0).to_numpy(), cells.shape[1])
                    vec = np.repeat(np.frombuffer(x.tobytes(), f"V{8 * dim}"), cells.shape[1])
                    yield pa.record_batch([pa.array(ids), pa.array(cells.ravel()), binary_array(vec.tobytes(), np.full(len(ids), 8 * dim))], ["id", "cell", "vector"])

        # Block sizes: at most as many rows as there are cells, a bound that the model sets.
        cell_rows = coded.groupBy("cell").agg(F.ceil(F.count("*") / part_rows).alias("parts"))
        visits = some.select("id", "v").mapInArrow(visit, "id long, cell long, vector binary")
        visit_rows = saved(visits)
        cell_visits = visit_rows.groupBy("cell").agg(F.ceil(F.count("*") / query_rows).alias("blocks"))
        plan = F.broadcast(cell_rows.join(cell_visits, "cell"))  # one row a cell; cells are at most 4096
        key = F.xxhash64("cell", "part", "block").alias("key")
        left = coded.join(plan, "cell").select("*", F.pmod(F.xxhash64("id"), "parts").alias("part"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"))
        right = visit_rows.join(plan, "cell").select("*", F.pmod(F.xxhash64("id"), "blocks").alias("block"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"))
        null = lambda t: F.lit(None).cast(t)
        both = left.select(key, F.lit(1).alias("kind"), "id", "cell", "length", "own", "code", "vector", "ids").unionByName(
            right.select(key, F.lit(0).alias("kind"), "id", "cell", null("double").alias("length"), null("double").alias("own"), null("binary").alias("code"), "vector", null("array<long>").alias("ids")))

        def find(cols, starts):
            m, got = shared.value, []
            ends = np.r_[starts[1:], len(cols["key"])]
            for a, b in zip(starts, ends):
                cut = a + int((cols["kind"][a:b] == 0).sum())
                if cut == a or cut == b:
                    continue
                read = lambda c, i, j, t, w: np.frombuffer(b"".join(cols[c].slice(i, j - i).to_pylist()), t).reshape(-1, w)  # noqa: E731, B023
                q, x = read("vector", a, cut, np.float64, dim), read("vector", cut, b, np.float64, dim)
                code = read("code", cut, b, np.uint8, (dim + 7) // 8)
                found = search_block(m, int(cols["cell"][a]), q, x, cols["length"][cut:b], code, cols["own"][cut:b], k + 1, bound)
                for i, (rows_, d) in enumerate(found):
                    got.append((int(cols["id"][a + i]), d, cut + rows_))
            if not got:
                return None
            q_ids = np.concatenate([np.full(len(d), q, np.int64) for q, d, _ in got])
            ids = [cols["ids"][i] for _, _, rows_ in got for i in rows_]
            return pa.record_batch([pa.array(q_ids), pa.array(np.concatenate([d for _, d, _ in got])), pa.array(ids, pa.list_(pa.int64()))], ["id", "score", "ids"])

        hits = both.repartition("key").sortWithinPartitions("key", "kind").mapInArrow(grouped("key", find), "id long, score double, ids array<long>")
        each = hits.select("id", "score", F.explode("ids").alias("vec_id"))
        top = each.withColumn("r", F.row_number().over(Window.partitionBy("id").orderBy("score", "vec_id"))).where(F.col("r") <= k + 1)
        return saved(top.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("score", "vec_id"))).alias("best")))

    best = look(distinct, model.visits)
    members = asked.select(F.col("id").alias("query_id"), "v").join(distinct, "v").select("query_id", "id")
    others = F.filter("best", lambda b: b["vec_id"] != F.col("query_id"))
    if model.visits < len(model.centroids):  # cells that hold too few rows: those queries visit all
        few = saved(members.join(best, "id", "left").where(F.coalesce(F.size(others), F.lit(0)) < k).select("id").distinct())
        if not few.isEmpty():
            best = best.join(few, "id", "left_anti").unionByName(look(distinct.join(few, "id"), len(model.centroids)))
    own_out = members.join(best, "id").select("query_id", F.slice(others, 1, k).alias("best"))
    return own_out.select("query_id", F.posexplode("best").alias("p", "b")).select(
        "query_id", (F.col("p") + 1).cast("int").alias("rank"), F.col("b.vec_id").alias("vec_id"), F.col("b.score").alias("score"))
