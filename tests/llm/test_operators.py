"""Corpus operators against brute force, libraries and fixtures with awkward rows."""

import hashlib
import random

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from probsum.llm import (
    common,
    edits,
    hamming,
    licenses,
    line_dedup,
    packing,
    passage_dedup,
    piece_bpe,
    quality_rules,
    queries,
    simhash_dedup,
    site_quality,
    toxicity,
    vector_join,
)

DOC = "doc_id long, text string, lang string, source string, n_chars long, score string"


def words(rnd, n, letters="abcdefghij"):
    return [" ".join("".join(rnd.choice(letters) for _ in range(rnd.randint(3, 8))) for _ in range(1)) for _ in range(n)]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and blank texts, repeated rows, a very long text and clashing extra columns."""
    rnd = random.Random(1)
    long = " ".join(words(rnd, 60_000))
    rows = [
        (1, None, None, None, None, "x"), (2, "", "en", "s", 0, "x"), (3, " \t\n", "en", "s", 3, None), (4, "one", "en", None, 3, "y"),
        (4, "one", "en", None, 3, "y"), (5, long, "en", "s", len(long), "z"), (6, long, None, "s", len(long), "z"), (None, "two words", "en", "s", 9, "q"),
        (7, "naïve \U0001f600 ▁ café\n\nnaïve", "fr", "t", 20, "q"),
    ]
    return spark.createDataFrame(rows, DOC)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


LABELS = "doc_id long, quality int, toxic int"


def labels(spark, rows=((2, 1, 0), (5, 0, 1), (None, 1, 1), (7, None, None), (7, 1, 0))):
    return spark.createDataFrame(list(rows), LABELS)


def same_rows(spark, sql_name, sf):
    import os

    import duckdb

    got = queries.QUERIES[sql_name](spark, sf).toPandas()
    con = duckdb.connect()
    for f in os.listdir(sf):
        con.sql(f"create view {f.removesuffix('.parquet')} as select * from '{sf}/{f}'")
    want = con.sql(queries.ORACLES[sql_name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    a, b = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    pd.testing.assert_frame_equal(a, b, check_dtype=False)


@pytest.mark.parametrize("name", ["op1_quality_rules", "op5_license_scan", "op10_vector_join"])
def test_sql_oracles(spark, sf, name):
    same_rows(spark, name, sf)


# -- components and fingerprints ------------------------------------------------------


@pytest.mark.parametrize("bound", [10**6, 0])
def test_components(spark, bound):
    rnd = random.Random(2)
    edges = [(rnd.randrange(200), rnd.randrange(200)) for _ in range(120)] + [(500 + i, 501 + i) for i in range(40)] + [(900, 900 + i) for i in range(50)]
    got = dict(common.components(spark.createDataFrame(edges, "a long, b long"), in_one_task=bound).collect())
    parent = {}

    def root(x):
        while parent.get(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        ra, rb = root(a), root(b)
        parent[max(ra, rb)] = min(ra, rb)
    want = {x: root(x) for e in edges if e[0] != e[1] for x in e}
    assert got == want


def test_components_of_nothing(spark):
    assert common.components(spark.createDataFrame([], "a long, b long")).count() == 0


def _closure(fps, bits):
    x = np.array(fps, dtype=np.uint64)
    near = np.bitwise_count(x[:, None] ^ x[None, :]) <= bits
    lab = np.arange(len(x))
    while True:
        new = np.array([lab[r].min() for r in near])
        if (new == lab).all():
            return lab
        lab = new


@pytest.mark.parametrize("tile", [2048, 5])
@pytest.mark.parametrize("masks,bits", [(None, 4), (hamming.block_masks(5, 2), 3)])
def test_hamming_links(spark, tile, masks, bits):
    rnd = random.Random(3)
    fps = set()
    for _ in range(60):
        base = rnd.getrandbits(64)
        fps.add(base)
        for _ in range(rnd.randint(0, 6)):
            x = base
            for _ in range(rnd.randint(1, 6)):
                x ^= 1 << rnd.randrange(64)
            fps.add(x)
    hot = rnd.getrandbits(64)
    fps |= {hot ^ (1 << i) for i in range(64)} | {0, 1, (1 << 64) - 1}
    fps = sorted(fps)
    signed = [int(np.uint64(f).view(np.int64)) for f in map(np.uint64, fps)]
    df = spark.createDataFrame([(s,) for s in signed], "fp long")
    got = dict(common.components(hamming.links(df, "fp", bits, tile, masks)).collect())
    lab = _closure(fps, bits)
    mine = [got.get(s, s) for s in signed]
    assert len(set(mine)) == len(set(lab))
    for i in range(len(fps)):
        for j in (lab[i],):
            assert mine[i] == mine[j]


def test_covering():
    from itertools import combinations

    for shared, size in ((4, 3), (5, 3), (4, 2)):
        family = hamming.covering_positions(shared, size)
        assert all(any(set(c) <= set(t) for c in family) for t in combinations(range(8), shared))


def test_fingerprint_by_definition():
    import xxhash

    for text in ("", None, "a", "A b C", "x " * 700, "É one two three four é", "a b c d e f\ta b\x0bc"):
        w = (text or "").encode().lower().split()
        shingles = [b" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))] if w else []
        h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
        want = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
        assert int(simhash_dedup.fingerprint_batch([text])[0]) == want


def test_simhash_odd_rows(spark, odd, none):
    rows = simhash_dedup.near_duplicates(odd).collect()
    assert len(rows) == odd.count()
    comp = {r["id"]: r["component"] for r in rows}
    assert comp[1] == comp[2] == comp[3] == 1 and comp[5] == comp[6] == 5
    assert sorted(r["doc_id"] for r in simhash_dedup.keep_first(odd).collect() if r["doc_id"]) == [1, 4, 4, 5, 7]
    assert simhash_dedup.near_duplicates(none).count() == 0 and simhash_dedup.keep_first(none).columns == none.columns


def test_near_copies_of_the_pipeline_equal_jaccard(spark, sf):
    import corpus_pipeline

    rnd = random.Random(22)
    rows = []
    for n in (60, 150, 400) * 5:
        base = words(rnd, n)
        for changed in (0, n // 100 + 1, n // 60 + 1, n // 15):
            copy = list(base)
            for i in rnd.sample(range(n), changed):
                copy[i] = words(rnd, 1)[0]
            rows.append(" ".join(copy))
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in map(str.split, rows)]
    near = [(a, b) for b in range(len(rows)) for a in range(b) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    low = dict(zip(*common.joined_nodes(*np.array(near).T)))
    docs = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    kept = {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, docs, sf).collect()}
    assert kept == {i for i in range(len(rows)) if low.get(i, i) == i}
    assert len(kept) < simhash_dedup.keep_first(docs).count()


# -- quality rules -----------------------------------------------------------------------


def test_binomial_tail(spark):
    from math import comb

    for n, k, p in ((50, 0, 0.05), (200, 3, 0.05), (1000, 12, 0.02)):
        want = sum(comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1))
        got = spark.sql(f"select {quality_rules.binomial_tail(f'{n}L', f'{k}L', p)} as x").first()["x"]
        assert np.isclose(got, want, rtol=1e-9)
    assert spark.sql(f"select {quality_rules.binomial_tail('10L', '5L', 0.05)} as x").first()["x"] == 1.0


def test_cutoffs_limit_false_rejections(spark):
    """Good documents fail the chosen cutoffs at most about as often as allowed; junk is caught where it differs."""
    rows = [("en", i % 2 == 0, 100, 500, 0 if i % 2 == 0 else 60, 0, 0) for i in range(4000)]
    df = spark.createDataFrame(rows, "stratum string, good boolean, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long")
    cut = {r["rule"]: r for r in quality_rules.certified_cutoffs(df, "stratum", "good").collect()}
    assert cut["symbols"]["n_lost"] == 0 and cut["symbols"]["n_bad"] == 2000
    few = quality_rules.certified_cutoffs(df.limit(20), "stratum", "good")
    assert few.count() == 0


def test_counts(spark):
    df = spark.createDataFrame([(1, "a b c a b c x\n\nq\nq\n a#b"), (2, None), (3, "x x x x")], "doc_id long, text string")
    r = {x["doc_id"]: x for x in quality_rules.counted(df).collect()}
    assert (r[1]["n_words"], r[1]["word_chars"], r[1]["n_symbols"], r[1]["n_dup_lines"], r[1]["n_repeat_words"]) == (10, 12, 1, 1, 6)
    assert (r[2]["n_words"], r[2]["n_repeat_words"]) == (0, 0) and r[3]["n_repeat_words"] == 4


def test_quality_odd_rows(spark, odd, none):
    assert quality_rules.judged(odd, labels(spark)).count() == odd.count()
    assert quality_rules.judged(none, labels(spark, [])).count() == 0


# -- lines ---------------------------------------------------------------------------------


def test_edit_distance():
    rnd = random.Random(4)

    def plain(a, b):
        p = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            q = [i]
            for j, y in enumerate(b, 1):
                q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
            p = q
        return p[-1]

    for _ in range(500):
        a, b = ("".join(rnd.choice("abc") for _ in range(rnd.randint(0, 12))) for _ in range(2))
        assert edits.edit_distance(a, b) == plain(a, b)
        assert edits.edit_distance(list(a), list(b)) == plain(a, b)


def test_line_hashes_follow_normal_forms():
    rnd = random.Random(5)
    texts = ["Ab, cd  EF!\nab cd ef\n\nünï Code_x", "ab cd ef", "a b\r\nc", *[" ".join(words(rnd, 30)) for _ in range(5)]]
    t, line, h, *_ = line_dedup.hashed_lines(texts)
    got = {(a, b): c for a, b, c in zip(t.tolist(), line.tolist(), h.tolist())}
    form = {(i, j): line_dedup.normalised(x) for i, z in enumerate(texts) for j, x in enumerate(z.split("\n"))}
    assert set(got) == {k for k, v in form.items() if v}
    for x in got:
        for y in got:
            assert (got[x] == got[y]) == (form[x] == form[y])
    assert [p for _, p in line_dedup._pieces("ab\ncd\nef", 2)] == ["ab", "cd", "ef"]


def test_lines_are_kept_once(spark):
    rnd = random.Random(6)
    base = [" ".join(words(rnd, 40)) for _ in range(6)]
    near = base[0].replace(base[0].split()[5], "altered")
    docs = spark.createDataFrame(
        [(1, f"{base[0]}\n{base[1]}\nshort line"), (2, f"{base[1].upper()}!\n{base[2]}\nshort line"), (3, f"{near}\n{base[3]}"), (4, f"{base[4]}\n{base[4]}")],
        "doc_id long, text string",
    )
    out = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(docs).collect()}
    assert out[1] == f"{base[0]}\n{base[1]}\nshort line"
    assert out[2] == f"{base[2]}\nshort line"
    assert out[4] == base[4]
    sims = line_dedup.hashed_lines([base[0], near])[4]
    linked = int(np.bitwise_count(sims[0] ^ sims[1])) <= 3
    assert (out[3] == base[3]) == linked
    report = {r["id"]: r for r in line_dedup.reported(docs).collect()}
    assert report[2]["n_lines"] == 3 and report[2]["n_dropped"] == 1
    assert report[4]["text_sha256"] == hashlib.sha256(base[4].encode()).hexdigest()


def test_line_groups_equal_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {(r["id"], r["line"]): (r["first_id"], r["first_line"]) for r in line_dedup.repeated_lines(docs).collect()}
    rows = [(r["doc_id"], i, n) for r in docs.collect() for i, x in enumerate(r["text"].split("\n")) if (n := line_dedup.normalised(x)).count(" ") >= 4]
    rows.sort()
    t, _, _, _, sim = line_dedup.hashed_lines([n for *_, n in rows])
    first = {}
    lab = list(range(len(rows)))

    def root(x):
        while lab[x] != x:
            x = lab[x]
        return x

    for i in range(len(rows)):
        near = np.flatnonzero(np.bitwise_count(sim[:i] ^ sim[i]) <= 3)
        for j in near.tolist():
            if root(i) != root(j) and line_dedup.similar(rows[i][2], rows[j][2], 0.8):
                a, b = sorted((root(i), root(j)))
                lab[b] = a
    want = {rows[i][:2]: rows[root(i)][:2] for i in range(len(rows)) if root(i) != i}
    assert got == want and not first


def test_wide_line_groups_equal_edit_similarity(spark):
    rnd = random.Random(21)
    rows = []
    for n in (8, 15, 30, 45, 60) * 6:
        base = words(rnd, n)
        for _ in range(3):
            copy = list(base)
            for i in rnd.sample(range(n), n // 10 + 1):
                copy[i] = words(rnd, 1)[0]
            rows.append(" ".join(copy))
    docs = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    near = [(a, b) for b in range(len(rows)) for a in range(b) if line_dedup.similar(rows[a], rows[b], 0.8)]
    low = dict(zip(*common.joined_nodes(*np.array(near).T)))
    want = {int(a) for a, b in low.items() if a != b}
    got = {r["id"] for r in line_dedup.repeated_lines(docs, **line_dedup.WIDE).collect()}
    assert len(want) > 40 and got <= want and len(got) >= 0.9 * len(want)
    assert len(line_dedup.repeated_lines(docs).collect()) < 0.5 * len(want)


def test_short_lines_repeat_exactly(spark):
    docs = spark.createDataFrame([(1, "All rights reserved.\nOne\n\n"), (2, "all rights reserved\nAll rights removed\n\none")], "doc_id long, text string")
    out = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(docs, **line_dedup.WIDE).collect()}
    assert out == {1: "All rights reserved.\nOne\n\n", 2: "All rights removed\n"}


def test_lines_odd_rows(spark, odd, none):
    out = line_dedup.without_repeats(odd)
    assert out.columns == odd.columns and out.count() == odd.count()
    assert line_dedup.without_repeats(none).count() == 0 and line_dedup.reported(none).count() == 0
    assert {r["doc_id"]: r["text"] for r in out.collect()}[6] == ""


# -- passages --------------------------------------------------------------------------------


def test_chain_is_optimal():
    rnd = np.random.default_rng(7)
    for _ in range(40):
        n = 9
        p, q = np.sort(rnd.choice(60, n, replace=False)), rnd.integers(0, 60, n)
        got = passage_dedup.chain(p, q, 5)
        score = lambda c: 5 * len(c) - passage_dedup.GAP / 2 * sum((p[b] - p[a]) + (q[b] - q[a]) for a, b in zip(c, c[1:]))
        best = 0.0
        for bits in range(1, 1 << n):
            c = [i for i in range(n) if bits >> i & 1]
            if all(q[a] < q[b] for a, b in zip(c, c[1:])):
                best = max(best, score(c))
        assert np.isclose(max(score(c.tolist()) for c in got), best)
        assert sorted(np.concatenate(got).tolist()) == list(range(n))


def test_exact_and_fuzzy_passages(spark):
    rnd = random.Random(8)
    shared, other = words(rnd, 80), words(rnd, 60)
    fuzzy = list(shared)
    for i in (11, 35, 58):
        fuzzy[i] = "changed"
    docs = [
        (1, [*words(rnd, 50), *shared, *words(rnd, 30)]), (2, [*words(rnd, 20), *shared]), (3, [*fuzzy, *words(rnd, 40)]),
        (4, words(rnd, 200)), (5, [*other[:30], *words(rnd, 9)]), (6, [*words(rnd, 5), *other]), (7, [*other, *words(rnd, 7)]),
    ]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in docs], "doc_id long, text string")
    got = {r["id"]: r for r in passage_dedup.passages(df).collect()}
    assert set(got) == {2, 3, 7}
    assert (got[2]["start"], got[2]["end"]) == (20, 100) and got[2]["others"] == [1]
    assert got[3]["start"] <= 2 and got[3]["end"] >= 78 and got[3]["edits"] == 3
    assert (got[7]["start"], got[7]["end"]) == (0, 60)
    left = {r["doc_id"]: r["text"].split() for r in passage_dedup.without_passages(df).collect()}
    assert left[2] == docs[1][1][:20] and left[1] == docs[0][1] and left[4] == docs[3][1]


def test_exact_passages_beside_revised_text(spark):
    rnd = random.Random(23)
    base, same = words(rnd, 50), [words(rnd, 12) for _ in range(4)]
    a, b = list(base), list(base)
    for part in same:
        a += words(rnd, 8) + part
        b += words(rnd, 8) + part
    assert len(a) == len(b) == 130
    p = [*range(0, 46, 5), *(50 + 20 * n + 8 + m for n in range(4) for m in (0, 7))]
    found = passage_dedup.align(a, b, 0, p, p, 5, 0.8)
    assert any(s == 0 and e >= 50 for s, e, *_ in found)
    assert all(n <= 0.2 * max(e - s, u - t) for s, e, t, u, n in found)
    docs = spark.createDataFrame([(1, " ".join(a)), (2, " ".join(b))], "doc_id long, text string")
    got = passage_dedup.passages(docs).collect()
    assert [r["id"] for r in got] == [2] and got[0]["start"] == 0 and got[0]["end"] >= 50


def test_every_exact_repeat_is_found(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r["doc_id"]: passage_dedup.words_of(r["text"]) for r in docs.collect()}
    flagged = {}
    for r in passage_dedup.passages(docs).collect():
        flagged.setdefault(r["id"], set()).update(range(r["start"], r["end"]))
    first = {}
    for k in sorted(texts):
        w = texts[k]
        grams = [" ".join(w[i : i + 50]) for i in range(len(w) - 49)]
        for i, g in enumerate(grams):
            if first.get(g, k) != k:
                assert set(range(i, i + 50)) <= flagged.get(k, set())
        for g in grams:
            first.setdefault(g, k)


def test_passages_odd_rows(spark, odd, none):
    assert [r["id"] for r in passage_dedup.passages(odd).collect()] == [6]
    out = passage_dedup.without_passages(odd)
    assert out.columns == odd.columns and out.count() == odd.count()
    assert passage_dedup.without_passages(none).count() == 0


# -- toxicity --------------------------------------------------------------------------------


def _toxic_rows(n=400, seed=9):
    rnd = random.Random(seed)
    vocab = words(rnd, 300)
    rows = []
    for i in range(n):
        sents = [" ".join(rnd.choice(vocab) for _ in range(8)) for _ in range(6)]
        bad = i % 3 == 0
        if bad:
            sents[rnd.randrange(6)] += " vile brute"
        elif i % 7 == 0:
            sents[0] += " vile"
        rows.append((i, ". ".join(sents) + ".", int(bad)))
    return rows


def test_sentences_explain_labels(spark):
    rows = _toxic_rows()
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string")
    lab = spark.createDataFrame([(i, 1, y) for i, _, y in rows], LABELS)
    model = toxicity.trained(docs, lab)
    got = {r["id"]: r for r in toxicity.scored(docs, model).collect()}
    held = [i for i, _, _ in rows if spark is not None and __import__("zlib").crc32(str(i).encode()) % 5 == 0]
    right = sum(got[i]["predicted"] == rows[i][2] for i in held)
    assert right >= 0.95 * len(held)
    found = toxicity.offending(docs, model).collect()
    assert found and all("brute" in r["text"] for r in found if rows[r["id"]][2])
    kept = toxicity.without_toxic(docs, model).count()
    assert abs(kept - sum(1 for *_, y in rows if not y)) <= 8


def test_toxicity_odd_rows(spark, odd, none):
    model = toxicity.trained(odd, labels(spark))
    r = {x["id"]: x for x in toxicity.scored(odd, model).collect()}
    assert r[1]["score"] == r[2]["score"] == 0.0 and r[1]["worst_sentence"] == -1
    assert toxicity.trained(none, labels(spark, [])).weights == {}
    assert toxicity.scored(none, model).count() == 0 and toxicity.without_toxic(odd, model).columns == odd.columns


# -- tokens ------------------------------------------------------------------------------------


def test_pieces_equal_library(spark, sf):
    import public_tokenizers
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    model = piece_bpe.PieceModel(open(path, "rb").read())
    rnd = random.Random(10)
    alphabet = ["a", "b", "aa", "the", "  ", "   ", "\n", "\t", "\r\n", "é", "😀", "\x00", "▁", "<s>", "ing", "tion", "0", "12", ";", "}", "́", "中"]
    texts = ["".join(rnd.choice(alphabet) for _ in range(rnd.randint(0, 40))) for _ in range(3000)]
    texts += [" " * n for n in range(40)] + ["a" * n for n in range(40)] + ["ab" * 3000, " " * 2000 + "x", "=-" * 300]
    for text, ids in zip(texts, model.encode(texts), strict=True):
        want = sp.encode(text, add_bos=True, add_eos=True)
        assert ids.tolist() == want
        assert model.decode(ids) == sp.decode(want)
    for _ in range(800):
        ids = [rnd.randrange(32000) if rnd.random() < 0.5 else rnd.randrange(260) for _ in range(rnd.randint(0, 8))]
        assert model.decode(np.array(ids, dtype=np.int64)) == sp.decode(ids)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r["id"]: r for r in piece_bpe.encoded(docs, path, chars=20_000).collect()}
    for r in docs.limit(60).collect():
        want = sp.encode(r["text"], add_bos=True, add_eos=True)
        assert got[r["doc_id"]]["ids"] == want
        assert got[r["doc_id"]]["decoded_sha256"] == hashlib.sha256(sp.decode(want).encode()).hexdigest()


def test_pieces_odd_rows(spark, odd, none):
    import public_tokenizers

    path = public_tokenizers.path("piece_bpe_32k.model")
    rows = piece_bpe.encoded(odd, path, ids=False).collect()
    assert len(rows) == odd.count() and {r["id"]: r["n_tokens"] for r in rows}[1] == 2
    assert piece_bpe.encoded(none, path).count() == 0


# -- licences, quality, packing, vectors -----------------------------------------------------------


def test_licenses(spark, odd, none):
    mit = licenses.TEMPLATES["MIT"][2]
    changed = mit.replace("sublicense", "relicense").replace(". ", ".\n")
    rows = [(1, "text\nReleased under the MIT License."), (2, changed), (3, "nothing here"), (4, "all rights reserved"), (5, "All rights")]
    got = {(r["id"], r["license"]) for r in licenses.scanned(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {(1, "MIT"), (2, "MIT"), (4, "proprietary")}
    assert licenses.scanned(odd).count() == 0 and licenses.scanned(none).count() == 0


def test_licenses_spread_over_lines(spark):
    """Licences in paragraphs, comments and longer lines are found; the rows are those of the SQL."""
    mit, bsd, isc = licenses.TEMPLATES["MIT"][2], licenses.TEMPLATES["BSD"][1], licenses.TEMPLATES["ISC"][1]
    rnd = random.Random(23)
    other = [" ".join(words(rnd, 40)) for _ in range(12)]
    cut = mit.index("The above"), mit.index("THE SOFTWARE")
    paragraphs = "\n\n".join([mit[: cut[0]], mit[cut[0] : cut[1]], mit[cut[1] :]])
    wrapped = mit.split()
    comment = "\n".join(" * " + " ".join(wrapped[i : i + 11]) for i in range(0, len(wrapped), 11))
    clauses = bsd.replace(" 1. ", "\n\n1. ").replace(" 2. ", "\n2. ").replace(" THIS ", "\n\nTHIS ")
    texts = [
        "\n".join(["MIT License\n", paragraphs, "", *other]),
        "\n".join(["/*", comment, " */", *other[:3], comment]),
        "\n".join([*other, clauses, other[0]]),
        " ".join([other[0], isc, other[1]]),
        " ".join(wrapped[: len(wrapped) // 2]) + "\n" + other[0],
        "\n".join(other),
        " ".join(x for x in wrapped[3:] if rnd.random() > 0.03) + " " + other[4],
        None,
        "",
    ]
    docs = spark.createDataFrame([*enumerate(texts), (0, texts[1])], "doc_id long, text string")
    got = licenses.scanned(docs).withColumnRenamed("id", "doc_id").toPandas().sort_values(["doc_id", "license"])
    assert {*zip(got["doc_id"], got["license"])} == {(0, "MIT"), (1, "MIT"), (2, "BSD"), (3, "ISC"), (6, "MIT")}
    base = duckdb.connect()
    base.register("given", docs.toPandas())
    base.execute("create view documents as select doc_id::bigint as doc_id, text::varchar as text from given")
    want = base.execute(licenses.oracle()).df().sort_values(["doc_id", "license"])
    pd.testing.assert_frame_equal(got.reset_index(drop=True), want[got.columns].reset_index(drop=True), check_dtype=False)
    only = licenses.scanned(docs, window_from=10**6)
    assert {r["id"] for r in only.collect()} < set(got["doc_id"])


def test_site_quality(spark, odd, none):
    """Sparse sites stay near the global rate, full ones move; held-out labels are not evidence."""
    rnd = random.Random(11)
    good = [(i, " ".join(words(rnd, 120)), "en", "good" if i % 10 else "tiny", 1, "x") for i in range(200)]
    bad = [(1000 + i, "#$% " * 70 + " ".join(words(rnd, 30)), "en", "bad", 1, "x") for i in range(100)]
    docs = spark.createDataFrame(good + bad, DOC)
    lab = spark.createDataFrame([(r[0], int(r[0] < 1000), 0) for r in good + bad], LABELS)
    got = site_quality.scored(docs, lab, F.col("source"), F.col("lang")).toPandas()
    held = got[got.held_out]
    assert ((held["id"] < 1000).astype(int) == held["predicted"]).mean() > 0.98
    site = got.groupby(got["id"] < 1000).host_score.mean()
    assert site[True] > site[False]
    assert site_quality.scored(odd, labels(spark), F.col("source"), F.col("lang")).count() == odd.count()
    empty = site_quality.scored(none, labels(spark, []), F.col("source"), F.col("lang"))
    assert empty.count() == 0
    assert set(site_quality.scored(odd, labels(spark, []), F.col("source"), F.col("lang")).toPandas().score.round(6)) == {0.5}


def test_packing(spark, odd, none):
    rnd = random.Random(12)
    sizes = sorted((rnd.randint(1, 3000) if rnd.random() < 0.8 else rnd.randint(1, 8192) for _ in range(500)), reverse=True)
    where, caps, used = packing.pack(sizes)
    load = np.bincount(where, sizes, minlength=len(caps))
    assert (load == used).all() and all(u <= c for u, c in zip(used, caps)) and set(caps) <= set(packing.CAPACITIES)
    cost = sum(map(packing.bin_cost, caps))
    for c in packing.CAPACITIES[-1:]:
        w, single = packing._best_fit(sizes, [c] * (max(packing.CAPACITIES) + 1), packing.CAPACITIES)
        assert cost <= len(single) * packing.bin_cost(c)
    docs = spark.createDataFrame([(i, "w " * n) for i, n in enumerate(sizes[:60] + [20_000])], "doc_id long, text string")
    p = packing.packed(docs, shard_rows=20).toPandas()
    assert p.groupby("id").n_tokens.sum().tolist() == sizes[:60] + [20_000]
    bins = p.groupby("bin_id").agg(t=("n_tokens", "sum"), c=("bin_capacity", "first"), u=("bin_used", "first"))
    assert (bins.t == bins.u).all() and (bins.t <= bins.c).all()
    for _, g in p.sort_values("bin_offset").groupby("bin_id"):
        assert g.bin_offset.tolist() == [0, *np.cumsum(g.n_tokens)[:-1].tolist()]
    q = packing.packed(odd).toPandas()
    assert q[q["id"] == 1].bin_id.isna().all() and len(q[q["id"] == 4]) == 2
    assert packing.packed(none).count() == 0


def test_vectors(spark):
    rng = np.random.default_rng(13)
    centres = rng.normal(size=(25, 16))
    rows = []
    for i in range(400):
        c = centres[i % 25] + rng.normal(size=16) * (0.05 if i % 3 else 0.5)
        rows.append((i, [float(np.float32(x)) for x in c * rng.uniform(0.1, 9)]))
    rows += [(1000 + i, rows[0][1]) for i in range(30)]
    odd_rows = [(2000, None), (2001, []), (2002, [0.0] * 16), (2003, [float("nan")] * 16), (2004, [float("inf")] * 16), (2005, [None] * 16), (2006, [1.0, 2.0]), (2007, [2.0, 4.0])]
    df = spark.createDataFrame(rows + odd_rows, "vec_id long, embedding array<float>")
    for block in (2048, 40):
        got = {r["id"]: r for r in vector_join.near_duplicates(df, block=block).collect()}
        x = np.array([v for _, v in rows])
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        near = x @ x.T >= 0.9
        ids = np.array([i for i, _ in rows])
        lab = ids.copy()
        while True:
            new = np.array([lab[r].min() for r in near])
            if (new == lab).all():
                break
            lab = new
        for k, i in enumerate(ids.tolist()):
            assert got[i]["n_links"] == near[k].sum() - 1 and got[i]["component"] == lab[k] and got[i]["kept"] == (lab[k] == i)
        for i in range(2000, 2006):
            assert got[i]["n_links"] == 0 and got[i]["component"] == i and got[i]["kept"]
        assert got[2006]["n_links"] == 1 and got[2007]["component"] == 2006
    assert vector_join.near_duplicates(df.limit(0)).count() == 0


# -- the pipeline -------------------------------------------------------------------------------------


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n = docs.count()
    for name, stage in corpus_pipeline.STAGES:
        out = common.written(stage(spark, docs, sf), name)
        if name != "packing":
            assert out.columns == docs.columns and out.count() <= docs.count()
        docs = out
    assert 0 < docs.select("doc_id").distinct().count() <= n
    assert docs.where("bin_used > bin_capacity").count() == 0


def test_pipeline_stages_take_odd_rows(spark, odd, none, sf):
    import corpus_pipeline

    for df in (odd, none):
        docs = df
        for _, stage in corpus_pipeline.STAGES:
            docs = common.written(stage(spark, docs, sf), "odd-stage")
        assert docs.count() >= 0
