import hashlib
import random

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import regex
import tiktoken
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from mixagg.llm import byte_bpe, chat_format, one_bit_search, packing, pretokens, textkit, token_counts, url_filter

BPE_JSON, BPE_MULTI = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
ODD = "ab st're l'd \n\t  'm'vé1２٣.,!?<| 　x'll 's日本"
TEXTS = ["", None, "don't", "'s", "  ", "\n", "a\n's  b", "''s", "<|endoftext|> x", "x" * 5000, " ".join(["word"] * 3000), "日本語 テキスト " * 50]


def some_texts(n=300, seed=3):
    r = random.Random(seed)
    return TEXTS + ["".join(r.choice(ODD) for _ in range(r.randrange(60))) for _ in range(n)]


def docs(spark, texts):
    rows = [(i, t, "noise", i) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, id string, length long")


def test_pretokens_follow_the_pattern():
    texts = [t or "" for t in some_texts(3000)]
    tokens = pretokens.Pretokens(textkit.texts_of(pa.array(texts)))
    for k, t in enumerate(texts):
        assert [tokens.string(i) for i in range(tokens.first[k], tokens.first[k + 1])] == regex.findall(public_tokenizers.PATTERN, t)


def test_words_and_shingles_match_plain_python():
    texts = ["", "a", "a b c d", "A b  c\td e f", "x y z w v", "é ü \x0b q\x0cr s t u"]
    t = textkit.texts_of(pa.array(texts))
    h, d = textkit.shingles(t)
    words = [regex.findall(r"[^\x20\x09-\x0D]+", x) for x in texts]
    assert [int((d == k).sum()) for k in range(len(texts))] == [max(len(w) - 4, 1 if w else 0) for w in words]
    same = textkit.shingles(textkit.texts_of(pa.array(["zz", "a B c d", "A b c d"])))[0]
    assert same[1] == same[2] and same[1] == h[d == 2][0]


def test_byte_bpe_equals_tiktoken_and_round_trips(spark):
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(BPE_MULTI), special_tokens={})
    texts = some_texts()
    got = {r.doc_id: r for r in byte_bpe.encode_digests(docs(spark, texts), BPE_MULTI).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        ids = enc.encode_ordinary(t or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    back = byte_bpe.decode_ids(byte_bpe.encode_ids(docs(spark, texts), BPE_MULTI), BPE_MULTI)
    assert {r.doc_id: bytes(r.text).decode() for r in back.collect()} == {i: t or "" for i, t in enumerate(texts)}


def test_packing_covers_every_id_once(spark):
    tok = Tokenizer.from_file(BPE_JSON)
    tok.encode_special_tokens = True
    texts = some_texts(200)
    pieces = packing.pack_documents(docs(spark, texts).repartition(3), BPE_JSON, public_tokenizers.PATTERN, open_windows=4, merge_partitions=2).collect()
    import zlib

    by_doc, by_seq = {}, {}
    for p in pieces:
        by_doc.setdefault(p.doc_id, []).append(p)
        by_seq.setdefault(p.sequence_id, []).append(p)
    assert set(by_doc) == set(range(len(texts)))
    for i, t in enumerate(texts):
        ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
        at = 0
        for p in sorted(by_doc[i], key=lambda p: p.start):
            assert p.start == at and p.doc_tokens == len(ids)
            assert p.ids_crc32 == zlib.crc32(np.array(ids[at : at + p.length], "<u4").tobytes())
            at += p.length
        assert at == len(ids)
    for ps in by_seq.values():
        at = 0
        for p in sorted(ps, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= 1024
    assert packing.padding(spark.createDataFrame(pieces)).first().padding < 0.05 * sum(p.length for p in pieces) + 1024


def test_best_fit_falling():
    lengths = np.array([5, 7, 5, 2, 4, 3, 10, 1])
    bins, offsets = packing.best_fit_falling(lengths, 10)
    for b in set(bins):
        m = np.argsort(offsets[bins == b])
        n = lengths[bins == b][m]
        assert n.sum() <= 10 and (offsets[bins == b][m] == np.r_[0, np.cumsum(n)[:-1]]).all()
    assert len(set(bins)) == 4


def test_counts_follow_edits():
    tool = token_counts.counter(BPE_JSON, public_tokenizers.PATTERN)
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(BPE_JSON), special_tokens={})
    r = random.Random(5)
    for k in range(60):
        text = "".join(r.choice(ODD) for _ in range(r.choice([0, 5, 400, 3000])))
        tokens = pretokens.Pretokens(textkit.texts_of(pa.array([text])))
        counts = np.array([tool.count(tokens.string(i)) for i in range(len(tokens.start))], np.int64)
        tree = token_counts.TokenTree(text, tokens.end - tokens.start, counts, tool)
        for _ in range(25):
            tree.edit(r.randrange(-2, len(tree.text) + 3), r.choice([0, 1, 5, 300]), "".join(r.choice(ODD) for _ in range(r.choice([0, 1, 4, 200, 900 if k < 5 else 0]))))
            assert tree.total == len(enc.encode_ordinary(tree.text))
            assert [n for b in tree.blocks for n in b[0]] == [len(t) for t in regex.findall(public_tokenizers.PATTERN, tree.text)]
        assert tree.prefix(len(tree.text)) == tree.total


def test_edit_query_on_nulls_and_tables(spark):
    d = docs(spark, TEXTS)
    edits = spark.createDataFrame([(2, 1, 1, 2, "zz"), (2, 0, 0, 0, "q "), (99, 0, 0, 0, "x")], "doc_id long, seq int, pos int, n_del int, ins string")
    rows = {r.doc_id: r for r in token_counts.count_with_edits(token_counts.with_edits(d, edits), BPE_JSON, public_tokenizers.PATTERN).collect()}
    assert len(rows) == len(TEXTS) and rows[1].n_tokens == 0 and rows[2].n_edits == 2 and rows[0].n_edits == 0
    revised = token_counts.count_with_edits(d.withColumn("edits", token_counts.revision_edits()), BPE_JSON, public_tokenizers.PATTERN)
    assert revised.count() == len(TEXTS) and revised.where("n_tokens_after <= 0").count() == 0


def test_chat_format_reads_back(spark):
    rows = [(1, 0, "user", "hi <|im_end|>"), (1, 1, "user", None), (1, 2, "assistant", "<\\|im_start|> \\ <|"), (1, 3, "assistant", "more\n"), (2, 5, None, ""),
            (3, 0, "sys\ntem\\n", "x"), (3, 0, "assistant", "tie"), (3, 0, "assistant", "tie"), (None, None, "assistant", "日本")]
    df = spark.createDataFrame([(*r, 0) for r in rows], "conv_id long, turn long, role string, text string, segments int")
    out = chat_format.format_conversations(df, block=2)
    got = {r.conv_id: r for r in out.select("conv_id", "formatted", chat_format.parse_formatted(F.col("formatted")).alias("turns"), chat_format.masked_text(F.col("segments")).alias("loss")).collect()}
    assert [(t.role, t.text) for t in got[1].turns] == [(r[2], r[3] or "") for r in rows[:4]]
    assert got[1].formatted.count("<|im_start|>") == 2 and got[1].loss == rows[2][3] + rows[3][3]
    assert [(t.role, t.text) for t in got[2].turns] == [("", "")]
    assert [(t.role, t.text) for t in got[3].turns] == [("assistant", "tie"), ("assistant", "tie"), ("sys\ntem\\n", "x")]
    assert got[None].loss == "日本"
    assert chat_format.digests(chat_format.format_conversations(df.limit(0))).count() == 0


def test_url_rules_are_exact(spark):
    r = random.Random(2)
    parts = ["www", "example", "com", "net", "a", "b", "EXAMPLE"]
    urls = [None, "", "no scheme", "http://", "http://example.com", "https://x.net/es/?a=://b.com/en/", "http://Example.com/en/1", "http://www.example.com/en/#q", "http://notexample.com/en/"]
    urls += ["http://" + ".".join(r.choice(parts) for _ in range(r.randrange(1, 5))) + r.choice(["/", "/en/", "/es/x", "/fr", "/fr/?q", ""]) for _ in range(400)]
    from mixagg.llm.queries import URL_RULES

    def plain(u):
        if not u or "://" not in u:
            return "", "", None, "allow"
        rest = u.split("://", 1)[1]
        host = regex.match(r"[^/?#]*", rest)[0]
        path = regex.match(r"[^?#]*", rest[len(host) :])[0]
        host = host.lower()
        fit = [x for x in URL_RULES if (host == x.host or host.endswith("." + x.host)) and path.startswith(x.path)]
        best = max(fit, key=lambda x: (len(x.host), len(x.path)), default=None)
        return host, path, best and best.key, best.verdict if best else "allow"

    df = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {x.page_id: (x.host, x.path, x.rule, x.verdict) for x in url_filter.judge_urls(df, URL_RULES).collect()}
    assert got == {i: plain(u) for i, u in enumerate(urls)}
    assert url_filter.judge_urls(df.limit(0), URL_RULES).count() == 0
    assert {x.verdict for x in url_filter.judge_urls(df, []).collect()} == {"allow"}


def test_cascade_with_many_keys(spark):
    universe = spark.range(20000).select(F.concat(F.lit("k"), "id").alias("key"))
    listed = universe.where("hash(key) % 50 = 0")
    cascade = url_filter.build_cascade(listed, universe)
    assert len(cascade.levels) > 1
    rows = url_filter._hashed(universe).toPandas()
    ok = cascade.test(rows.h1.to_numpy().view(np.uint64), rows.h2.to_numpy().view(np.uint64))
    assert set(rows.key[ok]) == {r.key for r in listed.collect()}


@pytest.mark.parametrize("n", [0, 5, 900])
def test_one_bit_search_recall_and_scores(spark, n):
    r = np.random.default_rng(1)
    x = r.standard_normal((n, 16)).astype(np.float32)
    rows = [(i, [float(v) for v in x[i]], i) for i in range(n)]
    rows += [(1000 + i, [1.0] * 16, 0) for i in range(60)]  # many copies
    rows += [(2000, None, 0), (2100, [0.0] * 16, 0), (2200, [float("nan")] + [1.0] * 15, 0), (2300, [1.0] * 3, 0), (2400, [None] + [1.0] * 15, 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, ids int")
    got = one_bit_search.nearest_neighbours(df, df.where("vec_id % 20 = 0"), part_rows=100, query_rows=8).collect()
    valid = {i: np.array(v, np.float64) for i, v, _ in rows[: n + 60]}
    found = total = 0
    for q in [i for i in valid if i % 20 == 0]:
        truth = sorted((float(np.sqrt(((valid[q] - v) ** 2).sum())), i) for i, v in valid.items() if i != q)[:10]
        mine = sorted(((g.rank, g.vec_id, g.score) for g in got if g.query_id == q))
        assert [m[0] for m in mine] == list(range(1, len(truth) + 1))
        for _, v, s in mine:
            assert abs(s - np.sqrt(((valid[q] - valid[v]) ** 2).sum())) < 1e-9
        assert [(m[2], m[1]) for m in mine] == sorted((m[2], m[1]) for m in mine)
        found, total = found + len({m[1] for m in mine} & {t[1] for t in truth}), total + len(truth)
    assert found >= 0.9 * total
    assert {g.query_id for g in got} <= set(valid)


def test_queries_in_small_cells_still_find_k(spark, monkeypatch):
    monkeypatch.setattr(one_bit_search, "calibrate", lambda *a, **k: 1)
    r = np.random.default_rng(8)
    rows = [(i, (np.eye(8)[i % 8] * 50 + r.normal(size=8) * (0.01 if i % 8 else 3)).tolist()) for i in range(64)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = one_bit_search.nearest_neighbours(df, df, k=10).collect()
    assert {q: sum(x.query_id == q for x in got) for q in range(64)} == dict.fromkeys(range(64), 10)
    assert all(len({x.vec_id for x in got if x.query_id == q} | {q}) == 11 for q in range(64))


def test_empty_and_repeated_rows(spark):
    none = spark.createDataFrame([], "doc_id long, text string, comp string")
    path, multi = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    assert packing.pack_documents(none, path, public_tokenizers.PATTERN).count() == 0
    assert byte_bpe.encode_digests(none, multi).count() == 0
    assert token_counts.count_with_edits(none.withColumn("edits", token_counts.revision_edits()), path, public_tokenizers.PATTERN).count() == 0
    vectors = spark.createDataFrame([], "vec_id long, embedding array<double>")
    assert one_bit_search.nearest_neighbours(vectors, vectors).count() == 0
    text = "some words, repeated 123 times. " * 12_000  # longer than a slice
    twice = spark.createDataFrame([(1, text, "c"), (1, text, "c"), (2, None, "c")], "doc_id long, text string, comp string")
    out = byte_bpe.encode_digests(twice, multi).collect()
    assert sorted(r.doc_id for r in out) == [1, 1, 2] and len({(r.n_tokens, r.ids_sha256) for r in out}) == 2
    pieces = packing.pack_documents(twice, path, public_tokenizers.PATTERN).collect()
    ids = {r.doc_tokens for r in pieces if r.doc_id == 1}
    assert len(ids) == 1 and sum(r.length for r in pieces if r.doc_id == 1) == 2 * ids.pop()
    counted = token_counts.count_with_edits(twice.withColumn("edits", token_counts.revision_edits()), path, public_tokenizers.PATTERN).collect()
    assert sorted(r.doc_id for r in counted) == [1, 1, 2]
