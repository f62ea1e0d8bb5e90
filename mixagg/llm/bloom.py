"""Bloom filters whose bits are set by a Spark aggregation and tested with numpy.

The filter's size is fixed by the caller before any row is read, so what is collected and broadcast is bounded.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.llm.textkit import mix


def positions(h1: np.ndarray, h2: np.ndarray, bits: int, hashes: int, salt: int) -> list[np.ndarray]:
    """The bits of each key: double hashing of two 64-bit hashes, remixed with the filter's salt."""
    s = mix(np.array([salt + 1], np.uint64) * np.uint64(0x9E3779B97F4A7C15))[0]
    a, b = mix(h1 ^ s), mix(h2 + s) | np.uint64(1)
    return [(a + np.uint64(i) * b) % np.uint64(bits) for i in range(hashes)]


def word_masks(h1: np.ndarray, h2: np.ndarray, bits: int, hashes: int, salt: int) -> tuple[np.ndarray, np.ndarray]:
    """Each key's word and its bits there: six bits of a hash name one."""
    s = mix(np.array([salt + 1], np.uint64) * np.uint64(0x9E3779B97F4A7C15))[0]
    word, turned, mask = mix(h1 ^ s) % np.uint64(bits // 64), mix(h2 + s), np.zeros(len(h1), np.uint64)
    for i in range(hashes):
        mask |= np.uint64(1) << (turned >> np.uint64(6 * i) & np.uint64(63))
    return word, mask


@dataclass(frozen=True)
class Bloom:
    words: np.ndarray
    bits: int
    hashes: int
    salt: int
    blocked: bool = False  # all bits of a key lie in one word

    def test(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        if self.blocked:
            word, mask = word_masks(h1.view(np.uint64), h2.view(np.uint64), self.bits, self.hashes, self.salt)
            return self.words[word.astype(np.int64)] & mask == mask
        ok = np.ones(len(h1), bool)
        for p in positions(h1.view(np.uint64), h2.view(np.uint64), self.bits, self.hashes, self.salt):
            ok &= (self.words[(p >> np.uint64(6)).astype(np.int64)] >> (p & np.uint64(63))) & np.uint64(1) == 1
        return ok


def size_for(n: int, rate: float) -> tuple[int, int]:
    """Bits and hash functions for ``n`` keys at a false-positive rate."""
    rate = min(max(rate, 1e-9), 0.5)
    bits = max(64, math.ceil(-n * math.log(rate) / math.log(2) ** 2))
    return -(-bits // 64) * 64, max(1, round(bits / max(n, 1) * math.log(2)))


def blocked(keys: DataFrame, count: int) -> Bloom:
    """A filter over about ``count`` keys that passes a few percent of others, of 75 MB at most: beyond 50 million keys
    it only passes more."""
    return build(keys, -(-max(min(count, 50_000_000), 64) * 12 // 64) * 64, 4, one_word=True)


def build(keys: DataFrame, bits: int, hashes: int, salt: int = 0, one_word: bool = False) -> Bloom:
    """The filter over ``keys`` (columns h1, h2: 64-bit hashes): bits are combined by ``bit_or`` per 64-bit word."""
    import pyarrow as pa

    def spread(batches):
        for batch in batches:
            h1, h2 = (batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False).view(np.uint64) for c in ("h1", "h2"))
            if one_word:
                at, bit = word_masks(h1, h2, bits, hashes, salt)
            else:
                p = np.concatenate(positions(h1, h2, bits, hashes, salt)) if len(h1) else np.zeros(0, np.uint64)
                at, bit = p >> np.uint64(6), np.uint64(1) << (p & np.uint64(63))
            word, inverse = np.unique(at, return_inverse=True)
            mask = np.zeros(len(word), np.uint64)
            np.bitwise_or.at(mask, inverse, bit)
            yield pa.record_batch([pa.array(word.astype(np.int64)), pa.array(mask.view(np.int64))], ["word", "mask"])

    set_bits = keys.select("h1", "h2").mapInArrow(spread, "word long, mask long").groupBy("word").agg(F.bit_or("mask").alias("mask"))
    words = np.zeros(bits // 64, np.uint64)
    got = set_bits.toArrow()
    words[got.column("word").to_numpy()] = got.column("mask").to_numpy().view(np.uint64)
    return Bloom(words, bits, hashes, salt, one_word)
