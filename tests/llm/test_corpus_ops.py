"""The corpus-scale operators against brute force on small fixtures with copies, near copies, ties and odd texts."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from mixagg.llm import links, ngram_join, paragraph_dedup, passages, quality, suffix_dedup
from mixagg.llm.textkit import texts_of

ODD = [None, "", "   \n", "one two", "One TWO", "日本 " * 70, "x" * 3000, "a b c d e " * 80, "é\n" * 60]


def fixture(seed=1, n=60):
    r = random.Random(seed)
    words = ["w%d" % i for i in range(400)]
    passage = " ".join(r.choice(words) for _ in range(60))
    texts = list(ODD)
    for _ in range(n):
        t = [r.choice(words) for _ in range(r.randrange(5, 160))]
        texts.append(" ".join(t))
        if r.random() < 0.5:
            for _ in range(r.randrange(3)):
                u = list(t)
                for _ in range(r.randrange(4)):
                    u[r.randrange(len(u))] = r.choice(words)
                texts.append(" ".join(u))
        if r.random() < 0.3:
            texts.append(" ".join(t) + "\n" + passage + "\n" + r.choice(words))
    r.shuffle(texts)
    return texts


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en" if i % 3 else None, "s", 1, 2) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long, comp long").repartition(3)


def shingle_set(t, width=5):
    w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
    return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])


def roots(n, edges):
    up = list(range(n))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return [find(x) for x in range(n)]


@pytest.mark.parametrize("per_row, tile, rare", [(links.PAIRS_PER_ROW, links.TILE_ROWS, ngram_join.RARE), (0, 3, 1)])  # 0: likely partners first; 3: tiles cut into blocks
def test_ngram_join_is_exact(spark, monkeypatch, per_row, tile, rare):
    monkeypatch.setattr(links, "PAIRS_PER_ROW", per_row)
    monkeypatch.setattr(links, "TILE_ROWS", tile)
    monkeypatch.setattr(ngram_join, "RARE", rare)
    texts = fixture()
    sets = [shingle_set(t) for t in texts]
    edges = [(i, j) for i in range(len(texts)) for j in range(i) if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j])]
    want = {i: (len(sets[i]), c) for i, c in enumerate(roots(len(texts), edges))}
    df = frame(spark, texts)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.linked_documents(df).collect()} == want
    kept = ngram_join.keep_first(df)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} == {i for i, (_, c) in want.items() if i == c}
    assert ngram_join.linked_documents(df.limit(0)).count() == 0


def test_components_of_long_chains(spark):
    r = random.Random(2)
    n = 200
    edges = [(i, i + 1) for i in range(90)] + [(r.randrange(100, n), r.randrange(100, n)) for _ in range(60)]
    want = roots(n, edges)
    for at_once in (links.FOREST_EDGES, 20):
        got = {x.node: x.comp for x in links.components(spark.createDataFrame(edges, "a long, b long").repartition(5), at_once).collect()}
        assert all(want[k] == v for k, v in got.items()) and set(got) == {x for a, b in edges if a != b for x in (a, b)}


def test_likely_partners_cover_every_row():
    r = np.random.default_rng(3)
    i = r.integers(0, 20, 200)
    j, score = i + r.integers(1, 20, 200), r.integers(0, 5, 200) / 5
    a, b, s = links.likely(i, j, score)
    for row in {*i.tolist(), *j.tolist()}:
        assert s[(a == row) | (b == row)].max() == score[(i == row) | (j == row)].max()
    assert len(a) <= len({*i.tolist(), *j.tolist()})


def test_overlap_bounds_hold():
    r = np.random.default_rng(0)
    sets = [np.unique(r.integers(0, 9000, r.integers(1, size)).astype(np.uint64)) for size in (900, 5000) for _ in range(30)]
    n = np.array([len(x) for x in sets])
    capped, whole = links.bitmap_columns(links.places(links.mixed_keys(np.concatenate(sets))), n)
    full = [(w if w.is_valid else c).as_py() for c, w in zip(capped, whole)]
    assert any(w.is_valid for w in whole) and all(8 * len(x) >= 2 * k for x, k in zip(full, n))
    for i in range(0, 60, 2):
        j, both = i + 1, len(np.intersect1d(sets[i], sets[i + 1]))
        assert links.wide_bound(full[i], full[j], n[i], n[j]) >= both
        width = min(8 * len(capped[i].as_py()), 8 * len(capped[j].as_py()))
        w = links.folded(capped, np.array([i, j]), width)
        assert links.overlap_bound(w[:1], w[1:], n[i : i + 1], n[j : j + 1])[0] >= both


def brute_removed(texts, length):
    first = {}
    for i, t in enumerate(texts):
        b = (t or "").encode()
        for k in range(len(b) - length + 1):
            first.setdefault(b[k : k + length], i)
    out = {}
    for i, t in enumerate(texts):
        b = (t or "").encode()
        m = bytearray(len(b))
        for k in range(len(b) - length + 1):
            if first[b[k : k + length]] < i:
                m[k : k + length] = b"\1" * length
        out[i] = (len(b), sum(m), sum(1 for k in range(len(m)) if m[k] and not (k and m[k - 1])), hashlib.sha256(bytes(x for x, y in zip(b, m) if not y)).hexdigest())
    return out


@pytest.mark.parametrize("length, hot", [(50, suffix_dedup.HOT), (50, 2), (30, suffix_dedup.HOT)])  # 2: most shared anchors are dealt out twice
def test_suffix_dedup_is_exact(spark, monkeypatch, length, hot):
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    texts = fixture(4, 30) + ["ab" * 200, "ba" * 150 + "c", "z" * 49, "z" * 50, "z" * 51, "-" * 3000, "x" + "-" * 2500, "a b c d e " * 80]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.dedup_substrings(frame(spark, texts), length, buckets=2).collect()}
    assert got == brute_removed(texts, length)
    assert suffix_dedup.dedup_substrings(frame(spark, texts).limit(0), length, buckets=1).count() == 0


def test_suffix_dedup_reads_long_texts_in_pieces(spark):
    r = np.random.default_rng(5)
    long = r.choice(list("abcd"), suffix_dedup.PIECE + 300_000)
    texts = ["".join(long), "".join(long[suffix_dedup.PIECE - 500 : suffix_dedup.PIECE + 700]), "".join(long[100:300]), "-" * 1_200_000, "-" * 400_000]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.dedup_substrings(frame(spark, texts)).collect()}
    assert got == brute_removed(texts, 50)


def test_difference_cover():
    for v in (8, 16, 32):
        d = suffix_dedup.difference_cover(v)
        assert {(a - b) % v for a in d for b in d} == set(range(v)) and len(d) < v


def test_paragraphs_keep_their_first_place(spark):
    r = random.Random(6)
    line = lambda n: " ".join("v%d" % r.randrange(500) for _ in range(n))
    shared = line(60)
    near = " ".join(shared.split()[:-2] + ["other", "end"])
    texts = [line(30), line(25) + "\n" + shared, shared + "\n" + line(40), line(8) + "\n" + near + "\nshort", None, "", "short\nshort", shared + "\n" + shared]
    df = frame(spark, texts)
    out = {(x.doc_id, x.line): (x.kept_doc_id, x.kept_line, x.removed) for x in paragraph_dedup.duplicate_paragraphs(df).collect()}
    assert out == {(1, 1): (1, 1, False), (2, 0): (1, 1, True), (3, 1): (1, 1, True), (7, 0): (1, 1, True), (7, 1): (1, 1, True)}
    left = {x.doc_id: x.text for x in paragraph_dedup.remove_paragraphs(df).collect()}
    assert left[1] == texts[1] and left[2] == texts[2].split("\n")[1] and left[3] == texts[3].split("\n")[0] + "\nshort" and 7 not in left
    assert left[6] == texts[6] and left[4] is None and left[5] == ""
    assert paragraph_dedup.duplicate_paragraphs(df.limit(0)).count() == 0


def test_short_lines_are_paragraphs(spark):
    r = random.Random(16)
    line = lambda n: " ".join("s%d" % r.randrange(5000) for _ in range(n))
    wrapped = [line(r.randrange(10, 16)) for _ in range(6)]
    five, seven = line(5), line(7)
    near = wrapped[5].split() + ["tail"]  # differs in one shingle of several
    texts = ["\n".join(wrapped + [five]), line(30) + "\n" + "\n".join(wrapped), five.upper() + "\n" + seven + "\na b c d", "a b c d\n" + seven + " " + "x\n" + seven, " ".join(near)]
    df = frame(spark, texts)
    out = {(x.doc_id, x.line): (x.kept_doc_id, x.kept_line, x.removed) for x in paragraph_dedup.duplicate_paragraphs(df, min_words=5).collect()}
    want = {(0, i): (0, i, False) for i in range(7)} | {(1, i + 1): (0, i, True) for i in range(6)}
    want |= {(2, 0): (0, 6, True), (4, 0): (0, 5, True), (2, 1): (2, 1, False), (3, 1): (2, 1, True), (3, 2): (2, 1, True)}
    assert out == want
    left = {x.doc_id: x.text for x in paragraph_dedup.remove_paragraphs(df, min_words=5).collect()}
    assert left == {0: texts[0], 1: texts[1].split("\n")[0], 2: seven + "\na b c d", 3: "a b c d"}


def test_wrapped_lines_are_one_paragraph(spark):
    r = random.Random(17)
    line = lambda n: " ".join("t%d" % r.randrange(5000) for _ in range(n))
    wrapped, heading = [line(r.randrange(6, 16)) for _ in range(4)], line(9)
    words = " ".join(wrapped).split()
    texts = [heading + "\n\n" + "\n".join(wrapped), line(30) + "\n" + "\n".join(" ".join(words[i : i + 7]) for i in range(0, len(words), 7)) + "\n\nend", heading + "\n" + line(50), " ".join(words)]
    df = frame(spark, texts)
    out = {(x.doc_id, x.line, x.lines): (x.kept_doc_id, x.kept_line, x.removed) for x in paragraph_dedup.duplicate_paragraphs(df).collect()}
    assert out == {(0, 2, 4): (0, 2, False), (1, 1, -(-len(words) // 7)): (0, 2, True), (3, 0, 1): (0, 2, True)}
    left = {x.doc_id: x.text for x in paragraph_dedup.remove_paragraphs(df).collect()}
    assert left == {0: texts[0], 1: texts[1].split("\n")[0] + "\n\nend", 2: texts[2]}


def test_paragraphs_meet_brute_force(spark):
    """Paragraphs by plain Python, linked by exact Jaccard of all pairs: every link is found, and none too many."""
    texts = [t for t in fixture(41, 40)]
    paragraphs = []
    for i, t in enumerate(texts):
        run = []
        for k, x in enumerate([*(t or "").split("\n"), ""]):
            n = len(re.findall(r"[^\x20\x09-\x0D]+", x))
            if 0 < n < 20:
                run.append((k, x))
                continue
            if run and len(" ".join(y for _, y in run).split()) >= 20:
                paragraphs.append((i, run[0][0], "\n".join(y for _, y in run)))
            run = []
            if n >= 20:
                paragraphs.append((i, k, x))
    sets = [shingle_set(x) for _, _, x in paragraphs]
    edges = [(i, j) for i in range(len(sets)) for j in range(i) if 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j])]
    root = roots(len(sets), edges)
    size = {c: root.count(c) for c in root}
    want = {paragraphs[i][:2]: (*paragraphs[c][:2], i != c) for i, c in enumerate(root) if size[c] > 1}
    got = {(x.doc_id, x.line): (x.kept_doc_id, x.kept_line, x.removed) for x in paragraph_dedup.duplicate_paragraphs(frame(spark, texts)).where("unit = 'line'").collect()}
    assert len(want) > 30 and got == want


def test_passages_inside_and_over_lines_are_found(spark):
    r = random.Random(26)
    words = lambda n: ["p%d" % r.randrange(9000) for _ in range(n)]
    passage, short = words(51), words(50)
    wrap = lambda w, k: "\n".join(" ".join(w[i : i + k]) for i in range(0, len(w), k))
    lead, tail = words(60), words(70)
    texts = [" ".join(words(80) + passage + words(40)), " ".join(lead + [x.upper() for x in passage] + tail), wrap(passage, 4), wrap(words(30) + passage + words(30), 7),
             " ".join(words(70) + short + words(80)), " ".join(words(70) + short + words(80)), " ".join(words(20) * 9)]
    df = frame(spark, texts)
    out = [x for x in paragraph_dedup.duplicate_paragraphs(df).collect()]
    cover = {}  # removed words of each document
    for x in out:
        if x.removed:
            assert x.unit == "passage" and x.kept_doc_id == 0 and x.n_words == 51
            cover.setdefault(x.doc_id, []).extend(texts[x.doc_id].encode()[x.start : x.stop].decode().lower().split())
    assert cover == {i: passage for i in (1, 2, 3)}
    assert [(x.doc_id, x.component_size) for x in out if x.unit == "passage" and not x.removed] == [(0, 4)]
    left = {x.doc_id: x.text for x in paragraph_dedup.remove_paragraphs(df).collect()}
    assert left.keys() == {0, 1, 3, 4, 5, 6} and left[1].split() == lead + tail and len(left[3].split()) == 60
    assert all(left[i] == texts[i] for i in (0, 4, 5, 6))


def test_windows_meet_brute_force(spark):
    texts = fixture(31, 40)
    got = {}
    for x in passages.repeated_passages(frame(spark, texts).select("doc_id", "text"), 12).collect():
        if x.kept_doc_id != x.doc_id:
            got.setdefault(x.doc_id, set()).update(range(x.first, x.last + 1))
    seen, want = {}, {}
    for i, t in enumerate(texts):
        w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
        for k in range(len(w) - 11):
            if seen.setdefault(tuple(w[k : k + 12]), i) < i:
                want.setdefault(i, set()).add(k)
    assert want and got == want


def base(t):
    t = t or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", t)
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    cover = {i + k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(3)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(cover)


def test_quality_counts_and_verdicts(spark):
    texts = fixture(3, 40) + ["a | b # c\n" * 30, "good words\ngood words\n\n \n<x>"]
    df = frame(spark, texts)
    got = {r.doc_id: r for r in quality.judge_documents(df).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == base(t), t
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
        assert not (r.kept and r.base_failed)
    assert quality.filter_documents(df).columns == df.columns
    assert quality.judge_documents(df.limit(0)).count() == 0


def test_bands_reject_planted_junk_and_keep_clean_text(spark):
    r = random.Random(41)
    parts = {"en": "the er ing an tion ou st re", "de": "ung sch ein ber ü ß keit en", "es": "ción ado ñ que os ll ar í", "fr": "eau ment é ç tion oi le è"}
    rows, labels, junk = [], [], set()
    for name, p in parts.items():
        text = lambda n: ["".join(r.choices(p.split(), k=3)) for _ in range(n)]  # noqa: B023, E731
        spoil = [lambda: " ".join(w + r.choice(["%%%", "***", "$$$", "&&&"]) for w in text(90)), lambda: " | ".join(text(90)), lambda: " ".join(w.upper() + "!!" for w in text(90))]  # noqa: B023
        for k in range(120):
            bad = k % 4 == 3
            i = len(rows)
            rows.append((i, spoil[k // 4 % 3]() if bad else " ".join(text(90)) + ".", name))
            if bad:
                junk.add(i)
            if k < 80:
                labels.append((i, 0 if bad else 1))
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    told = spark.createDataFrame(labels, "doc_id long, quality int")
    verdict = {x.doc_id: x for x in quality.judge_documents(df, labels=told).collect()}
    assert not any(x.base_failed for x in verdict.values())
    assert {i for i, x in verdict.items() if not x.kept} & junk == junk
    for name in parts:
        clean = [i for i, _, n in rows if n == name and i not in junk]
        assert sum(verdict[i].kept for i in clean) >= 0.95 * len(clean)


def test_model_probabilities_sum_to_one():
    r = np.random.default_rng(5)
    code, n = np.unique(r.integers(0, 1 << 13, 4000).astype(np.uint32), return_counts=True)
    m = quality.kneser_ney(code, n)
    for ctx in [*(code[:40] >> 6), 99999]:
        p = np.exp(m.score((np.uint32(ctx) << np.uint32(6)) | np.arange(64, dtype=np.uint32)))
        assert abs(p.sum() - 1) < 1e-4 and (p > 0).all()


def grams(text):
    return np.unique(quality.gram_codes(texts_of(pa.array([text])))[0], return_counts=True)


def model_of(some, discount=None):
    total = Counter()
    for t in some:
        total.update(dict(zip(*(x.tolist() for x in grams(t)))))
    code = np.array(sorted(total), np.uint32)
    return quality.kneser_ney(code, np.array([total[c] for c in code.tolist()]), discount)


def test_counts_taken_off_leave_the_model_of_the_others():
    """Also where the document alone holds n-grams of each length, or is the only one."""
    some = [t for t in fixture(5, 30) if t] + ["zzq", "Zq zq 99", "the the the", "é%é%"]
    for docs in (some, some[:1]):
        whole = model_of(docs)
        parts = [grams(t) for t in docs]
        doc = np.repeat(np.arange(len(docs)), [len(c) for c, _ in parts])
        code, own = np.concatenate([c for c, _ in parts]), np.concatenate([n for _, n in parts])
        got = whole.score_without(doc, code, whole.count(code), own)
        for i in range(len(docs)):
            rest = model_of(docs[:i] + docs[i + 1 :], [o.discount for o in whole.orders])
            assert np.allclose(got[doc == i], rest.score(code[doc == i]), atol=1e-4), docs[i]


def test_models_learn_from_all_good_documents_and_bands_are_fit_on_all(spark):
    r = random.Random(8)
    good = [" ".join("".join(r.choices("abcdefgh" if i % 5 else "stuvwxyz", k=4)) for _ in range(60)) for i in range(40)]
    junk = [" ".join("".join(r.choices("abc%$#", k=4)) for _ in range(60)) for _ in range(10)]
    rows = [(i, t, "xx") for i, t in enumerate(good + good + junk)]  # the second copies have no labels
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    labels = spark.createDataFrame([(i, 1) for i in range(40)] + [(i, 0) for i in range(80, 90)], "doc_id int, quality int")
    got = {x.doc_id: x for x in quality.judge_documents(docs, labels=labels).collect()}
    assert len(got) == len(rows) and not any(x.base_failed for x in got.values())
    assert all(got[i].perplexity > got[40 + i].perplexity for i in range(40))  # each text is in the model that scores its copy, not in its own
    whole = model_of(good)
    mean = lambda m, t: -float(m.score(grams(t)[0]) @ grams(t)[1]) / len(t)
    apart = [mean(model_of(good[:i] + good[i + 1 :], [o.discount for o in whole.orders]), t) for i, t in enumerate(good)]
    told = [mean(whole, t) for t in good]
    spoilt = sorted(mean(whole, t) for t in junk)
    assert np.allclose([np.log(got[i].perplexity) for i in range(40)], apart, atol=1e-4)
    assert np.allclose([np.log(got[40 + i].perplexity) for i in range(40)], told, atol=1e-4)
    ranked = sorted(apart)
    q = lambda x, p: x[int(np.ceil(p * len(x))) - 1]
    assert np.isclose(np.log(got[0].band_high), (q(ranked, 0.99) + q([x for x in spoilt if x > q(ranked, 0.99)], 0.05)) / 2, atol=1e-4)
    assert all(got[i].kept for i in range(40)) and not any(got[i].kept for i in range(80, 90))


def test_teachers_are_the_same_either_way(spark, monkeypatch):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    every = [sorted(tuple(r) for r in quality.judge_documents(docs, labels=labels).collect())]
    monkeypatch.setattr(quality, "BROADCAST_IDS", 0)
    every.append(sorted(tuple(r) for r in quality.judge_documents(docs, labels=labels).collect()))
    assert every[0] == every[1]


def test_languages_past_the_first_have_models_of_their_own(spark):
    rng = random.Random(9)
    words = {lang: ["".join(rng.choice(letters) for _ in range(5)) for _ in range(40)] for lang, letters in zip(["aa", "bb", "cc", "dd", None], ("abcde", "fghij", "klmno", "pqrst", "uvwxyz"))}
    rows = [(i, lang, " ".join(rng.choices(words[lang], k=60))) for i, lang in enumerate([*words] * 12)] + [(1000, "rare", "one two three"), (1001, "", None)]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    got = quality.score_documents(docs, max_languages=2, least_documents=3).orderBy("doc_id").collect()
    want = quality.score_documents(docs, max_languages=5).orderBy("doc_id").collect()  # all but the rare one at once
    assert [tuple(r) for r in got] == [tuple(r) for r in want] and len(got) == len(rows)
    assert {r["model"] for r in got} == {"aa", "bb", "cc", "dd", "", quality.OTHER}
    shared = quality.score_documents(docs, max_languages=2, least_documents=1000)  # too rare for models of their own
    assert {r[0] for r in shared.select("model").distinct().collect()} == {"aa", "", quality.OTHER}


def test_bounds_move_only_the_sets_that_pairs_name(spark):
    """Without broadcasts: the bitmaps of sets that no pair names are not shuffled, and all named pairs are tested."""
    keys = [np.arange(100, dtype=np.uint64) + np.uint64(50 * (i // 2)) for i in range(4000)]
    at = links.places(links.mixed_keys(np.concatenate(keys)))
    bitmap, _ = links.bitmap_columns(at, np.full(len(keys), 100))
    sets = spark.createDataFrame([(i, 100, bytearray(b.as_py()), None) for i, b in enumerate(bitmap)], "setid long, n long, bitmap binary, wide binary")
    pairs = spark.createDataFrame([(2 * i, 2 * i + 1 + 20 * (i % 2)) for i in range(20)], "a long, b long")
    written = lambda: (lambda e: sum(e.apply(i).totalShuffleWrite() for i in range(e.size())))(spark.sparkContext._jsc.sc().statusStore().executorList(True))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        before = written()
        got = sorted(tuple(r) for r in links.bounded(pairs, sets, 75).collect())
        assert got == [(2 * i, 2 * i + 1) for i in range(0, 20, 2)]
        assert written() - before < 100_000
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
