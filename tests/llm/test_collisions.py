"""Long regular strings whose polynomials modulo 2**64 agree: each operator has to tell them apart."""

import hashlib

import numpy as np
import pyarrow as pa
import public_tokenizers
import pytest
import tiktoken

from mixagg.llm import byte_bpe, ngram_join, packing, paragraph_dedup, quality, token_counts
from mixagg.llm.pretokens import PretokenCache, Pretokens
from mixagg.llm.textkit import texts_of

PATH = public_tokenizers.path("byte_bpe_50k.json")


def pair(n, a="a", b="b"):
    """A string that counts set bits modulo 2, and its complement."""
    bits = [bin(i).count("1") % 2 for i in range(n)]
    return "".join((a, b)[x] for x in bits), "".join((b, a)[x] for x in bits)


def texts(*values):
    return texts_of(pa.array(values))


@pytest.mark.parametrize("n", [1024, 2048, 4096])
def test_words_lines_and_pretokens_differ(n):
    s, t = pair(n)
    h, _ = texts(s, t).word_hashes(lower=True)
    assert h[0] != h[1]
    assert quality.base_counts(texts(f"{s}\n{t}\n{s}"))["n_dup_lines"].tolist() == [1]
    p = paragraph_dedup.Paragraphs(texts(f"v w x y {s}\nv w x y {t}"), 5, 5)
    assert p.set_ids()[0] != p.set_ids()[1]
    for order in ((s, t), (t, s)):
        cache = PretokenCache(lambda tokens: list(tokens))
        for batch in (order, order[::-1]):
            at = cache.lookup(Pretokens(texts(*batch)))
            assert [cache.entries[i] for i in at] == list(batch)


def test_cache_tells_equal_hashes_apart():
    cache = PretokenCache(lambda tokens: list(tokens))
    words = ["alpha", "beta", "gamma", "beta"]
    for batch in (words, words[::-1]):
        tokens = Pretokens(texts(*batch))
        tokens.hash = np.full(len(tokens.hash), 7, np.uint64)
        assert [cache.entries[i] for i in cache.lookup(tokens)] == batch


@pytest.mark.parametrize("n", [1024, 4096])
def test_queries_tell_them_apart(spark, n):
    s, t = pair(n)
    docs = spark.createDataFrame([(0, f"x {s}"), (1, f"x {t}"), (2, s), (3, t)], "doc_id long, text string").coalesce(1)
    assert all(r.component_id == r.doc_id and r.n_shingles == 1 for r in ngram_join.linked_documents(docs).collect())
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(PATH), special_tokens={})
    want = [len(enc.encode_ordinary(r.text)) for r in docs.orderBy("doc_id").collect()]
    packed = packing.pack_documents(docs, PATH, public_tokenizers.PATTERN).select("doc_id", "doc_tokens").distinct().orderBy("doc_id")
    assert [r.doc_tokens - 1 for r in packed.collect()] == want
    counted = token_counts.count_with_edits(docs.withColumn("edits", token_counts.revision_edits()), PATH, public_tokenizers.PATTERN)
    assert counted.count() == 4
    multi = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    got = {r.doc_id: r.decoded_sha256 for r in byte_bpe.encode_digests(docs, multi).collect()}
    assert got == {r.doc_id: hashlib.sha256(r.text.encode()).hexdigest() for r in docs.collect()}
