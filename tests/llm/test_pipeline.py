"""The pipeline's stages alone and together, on odd inputs and on the smallest tables."""

import public_tokenizers
import pytest
import tiktoken

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from mixagg.llm import byte_bpe  # noqa: E402

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, __gone long, __id long, comp string"
PASSAGE = " ".join(f"common{i}" for i in range(60))


def odd(spark):
    """Nulls, blanks, repeated rows, a near copy, a shared passage inside lines, a long text, clashing column names."""
    words = [f"w{i}" for i in range(200)]
    near = [*words[:150], "other", *words[151:]]
    texts = [None, "", " \n ", " ".join(words), " ".join(near), " ".join(words), "one two", " ".join(f"a{i} {PASSAGE if i == 40 else ''}" for i in range(90)),
             " ".join(f"b{i} {PASSAGE if i == 20 else ''}" for i in range(90)), " ".join(f"long{i}" for i in range(60_000))]
    rows = [(i, t, "en" if i % 2 else None, "s", 1, i, None, "c") for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[-2]], SCHEMA)


def test_stages_on_odd_rows(spark):
    docs = odd(spark)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        rows = out.collect()
        if name == "n-gram Jaccard join":  # the near copy and the copy go, blanks stay
            assert sorted(r.doc_id for r in rows) == [0, 1, 2, 3, 6, 7, 8, 8, 9]
        if name == "substring dedup":
            texts = {r.doc_id: r.text or "" for r in rows}
            assert texts[7].count("common0 ") == 1 and "common30" not in texts[8] and "b89" in texts[8] and len(texts[9].split()) == 60_000
        assert stage(spark, docs.limit(0), SF).count() == 0
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect()
    assert {r.doc_id for r in pieces} == set(range(10)) and max(r.offset + r.length for r in pieces) <= 1024


def test_run_equals_its_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, kept = docs.columns, {r.doc_id for r in docs.select("doc_id").collect()}
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        stage(spark, docs, SF).write.parquet(path := str(tmp_path / str(i)))
        docs = spark.read.parquet(path)
        left = {r.doc_id for r in docs.select("doc_id").collect()}
        assert docs.columns == columns and left and left <= kept
        kept = left
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.json")), special_tokens={})
    want = {r.doc_id: len(enc.encode_ordinary(r.text)) + 1 for r in docs.collect()}
    got: dict[int, int] = {}
    for r in corpus_pipeline.run(spark, SF).collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + r.length
        assert r.doc_tokens == want[r.doc_id]
    assert got == want
