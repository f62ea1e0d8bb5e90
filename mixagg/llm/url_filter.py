"""URL rules through cascades of Bloom filters.

A rule is a host and a path prefix; it fits its host and all subdomains, and the longest fitting rule wins.
Each url has a few candidate keys: host suffixes with as many labels as some rule's host, joined to path
prefixes as long as some rule's path.  Two cascades (keys to allow, keys to block) are built over all candidate
keys of the corpus: level 0 encodes the listed keys, level 1 the candidates that level 0 wrongly lets through,
level 2 the listed keys that level 1 lets through, and so on until no key errs.  Over that universe membership is
exact, and judging a url needs no join.

Sizes: level 0 takes a false-positive rate such that about as many candidates pass as are listed, so all levels
together hold O(listed * log(universe / listed)) bits; that, not the corpus, bounds the broadcast.
Defined cases: repeated rows are judged alike, urls of any length whole; a null url or one without ``://`` has an empty host and path and fits no rule; extra columns are
ignored; an empty table gives no rows; no rules means that every url gets the default verdict.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mixagg.llm import bloom
from mixagg.llm.session import saved

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def key(self) -> str:
        return self.host + self.path


def host_and_path(url: Column) -> tuple[Column, Column]:
    url = F.coalesce(url, F.lit(""))
    host = F.translate(F.regexp_extract(url, r"://([^/?#]*)", 1), _UPPER, _LOWER)
    return host, F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1)


def candidates(host: Column, path: Column, labels: list[int], lengths: list[int]) -> Column:
    """A url's possible rule keys, longest host first, then longest path."""
    parts = F.split(host, r"\.", -1)
    keys = [
        F.when((F.size(parts) >= k) & (F.length(path) >= n), F.concat(F.array_join(F.slice(parts, -k, k), "."), F.substring(path, 1, n)))
        for k in sorted(labels, reverse=True) for n in sorted(lengths, reverse=True)
    ]
    return F.filter(F.array(*keys), lambda x: x.isNotNull()) if keys else F.array().cast("array<string>")


def _hashed(keys: DataFrame) -> DataFrame:
    return keys.select("key", F.xxhash64("key").alias("h1"), F.xxhash64(F.concat(F.lit("\0"), "key")).alias("h2"))


@dataclass(frozen=True)
class Cascade:
    levels: tuple[bloom.Bloom, ...]

    def test(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        """Exact over the universe: a key is listed if the first level that refuses it has an odd number."""
        verdict = np.zeros(len(h1), bool)
        live = np.arange(len(h1))
        for i, level in enumerate(self.levels):
            ok = level.test(h1[live], h2[live])
            verdict[live[~ok]] = i % 2 == 1
            live = live[ok]
        verdict[live] = len(self.levels) % 2 == 1
        return verdict


def _passing(keys: DataFrame, level: bloom.Bloom) -> DataFrame:
    shared = keys.sparkSession.sparkContext.broadcast(level)

    def keep(batches):
        for batch in batches:
            h1, h2 = (batch.column(i).to_numpy(zero_copy_only=False).view(np.uint64) for i in (1, 2))
            if batch.num_rows:
                yield batch.filter(pa.array(shared.value.test(h1, h2)))

    return keys.mapInArrow(keep, "key string, h1 long, h2 long")


def build_cascade(listed: DataFrame, universe: DataFrame, max_levels: int = 64) -> Cascade:
    """``listed`` and ``universe``: DataFrames with a string column ``key``; listed keys need not be in the universe."""
    listed = _hashed(listed.select("key").where(F.col("key").isNotNull()).distinct())
    universe = _hashed(universe.select("key").where(F.col("key").isNotNull()))
    r = listed.count()
    if not r:
        return Cascade(())
    s = universe.agg(F.approx_count_distinct("key")).first()[0]
    levels = []
    wanted, others = listed, universe
    rate = min(0.5, max(r * math.sqrt(0.5) / max(s, 1), 1e-9))
    count = r
    for i in range(max_levels):
        levels.append(level := bloom.build(wanted, *bloom.size_for(count, rate), salt=i))
        wrong = _passing(others, level).distinct()
        wrong = saved(wrong if i else wrong.join(listed.select("key"), "key", "left_anti"))
        count = wrong.count()
        if not count:
            return Cascade(tuple(levels))
        wanted, others, rate = wrong, wanted, 0.5
    raise ValueError("keys with equal 128-bit hashes: the cascade can't tell them apart")


def judge_urls(
    df: DataFrame, rules: list[Rule], id_col: str = "page_id", url: str = "url", default: str = "allow",
) -> DataFrame:
    """id, host, path, the winning rule's key (or null) and the verdict of every row.

    The rules are a list of the caller's; candidate keys of all rows make the cascades' universe.
    """
    spark = df.sparkSession
    host, path = host_and_path(F.col(url))
    labels = sorted({r.host.count(".") + 1 for r in rules})
    lengths = sorted({len(r.path) for r in rules})
    rows = df.select(F.col(id_col), host.alias("host"), path.alias("path")).withColumn("keys", candidates(F.col("host"), F.col("path"), labels, lengths))
    universe = rows.select(F.explode("keys").alias("key"))
    cascades = {v: build_cascade(_list(spark, rules, v), universe) for v in sorted({r.verdict for r in rules})}
    shared = spark.sparkContext.broadcast(cascades)
    id_type = df.schema[id_col].dataType.simpleString()

    def judge(batches):
        for batch in batches:
            keys = batch.column(3)
            flat, off = keys.flatten(), keys.offsets.to_numpy() - keys.offsets[0].as_py()
            h1, h2 = (batch.column(i).flatten().to_numpy(zero_copy_only=False).view(np.uint64) for i in (4, 5))
            n = batch.num_rows
            best = np.full(n, len(flat), np.int64)
            verdict = np.full(n, default, object)
            owner = np.repeat(np.arange(n), np.diff(off))
            for name, cascade in shared.value.items():
                hit = np.flatnonzero(cascade.test(h1, h2))[::-1] if cascade.levels else np.zeros(0, np.int64)
                first = np.full(n, len(flat), np.int64)
                first[owner[hit]] = hit  # reversed: the first candidate's write is the last
                better = first < best
                best[better], verdict[better] = first[better], name
            rule = flat.take(pa.array(np.where(best < len(flat), best, -1), mask=best >= len(flat))) if len(flat) else pa.nulls(n, pa.string())
            yield pa.record_batch([batch.column(0), batch.column(1), batch.column(2), rule, pa.array(verdict, pa.string())], ["id", "host", "path", "rule", "verdict"])

    hashed = rows.select(
        F.col(id_col).alias("id"), "host", "path", "keys",
        F.transform("keys", lambda k: F.xxhash64(k)).alias("h1"), F.transform("keys", lambda k: F.xxhash64(F.concat(F.lit("\0"), k))).alias("h2"),
    )
    out = hashed.mapInArrow(judge, f"id {id_type}, host string, path string, rule string, verdict string")
    return out.withColumnRenamed("id", id_col)


def _list(spark: SparkSession, rules: list[Rule], verdict: str) -> DataFrame:
    return spark.createDataFrame([(r.key,) for r in rules if r.verdict == verdict], "key string")
