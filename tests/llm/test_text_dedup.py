"""Lines, passages and near copies: recall by edits, rows that share an id, clashing columns, edit distances."""

import random

import numpy as np
import pytest

from probsum.llm import common, edits, line_dedup, passage_dedup, simhash_dedup

DOC = "doc_id long, text string"
VOCABULARY = [f"{a}{b}{c}" for a in ("ba", "ko", "mi", "ter", "lu", "san") for b in ("dor", "vi", "ne", "gal", "po", "rus") for c in ("t", "la", "min", "ek", "ost", "u", "ar")]


def prose(rnd, n):
    return [rnd.choice(VOCABULARY) + rnd.choice("abcdefgh") + rnd.choice(VOCABULARY)[:3] for _ in range(n)]


def test_edit_distances_side_by_side():
    rnd = random.Random(1)
    for _ in range(12):
        left, right = [], []
        for _ in range(200):
            letters = rnd.choice(["ab", "abcdefghij klm", "aé漢😀z "])
            a = [rnd.choice(letters) for _ in range(rnd.choice([0, 1, 30, 63, 64, 65, 128, 300, 1200]))]
            b = list(a)
            for _ in range(rnd.randrange(0, len(a) // 3 + 2)):
                i = rnd.randrange(len(b) + 1)
                b[i : i + rnd.randrange(2)] = [rnd.choice(letters)] * rnd.randrange(2)
            left.append("".join(a)), right.append("".join(b))
        most = [int(0.2 * max(len(a), len(b))) for a, b in zip(left, right)]
        exact = [edits.edit_distance(a, b) for a, b in zip(left, right)]
        want = [d <= m for d, m in zip(exact, most)]
        assert edits.within(left, right, most, memory=rnd.choice([1 << 24, 1 << 15])).tolist() == want
        assert all(w for a, b, m, w in zip(left, right, most, want) if edits.surely_within(a, b, m))


@pytest.mark.parametrize("n", [6, 8, 12, 20, 40])
def test_lines_found_by_edit_similarity_alone(spark, n):
    """Brute force knows edit similarity only; at least nine tenths of the pairs are joined."""
    rnd = random.Random(n)
    rows = []
    for _ in range(120):
        base = prose(rnd, n)
        copy = list(base)
        for i in rnd.sample(range(n), max(1, n // 10)):
            copy[i] = prose(rnd, 1)[0]
        rows += [base, copy]
    lines = [" ".join(r) for r in rows]
    docs = spark.createDataFrame(list(enumerate(lines)), DOC)
    want = {i for i in range(1, len(lines), 2) if line_dedup.similar(lines[i - 1], lines[i], 0.8)}
    got = {r["id"]: r["first_id"] for r in line_dedup.repeated_lines(docs, **line_dedup.WIDE).collect()}
    assert len(want) > 60 and sum(got.get(i) == i - 1 for i in want) >= 0.9 * len(want)
    assert all(line_dedup.similar(lines[a], lines[b], 0.8) for a, b in got.items())


@pytest.mark.parametrize("chunk", [512, 6])
def test_large_line_groups(spark, chunk):
    """Groups over the chunk are joined as small ones are, whether one part or several."""
    rnd = random.Random(3)
    rows = []
    for _ in range(3):
        base = prose(rnd, 25)
        other = base[:20] + prose(rnd, 5)  # shares words, too far in edits
        for stem in (base, other):
            for _ in range(20):
                copy = list(stem)
                copy[rnd.randrange(20)] = prose(rnd, 1)[0]
                rows.append(" ".join(copy))
    docs = spark.createDataFrame(list(enumerate(rows)), DOC)
    near = [(a, b) for b in range(len(rows)) for a in range(b) if line_dedup.similar(rows[a], rows[b], 0.8)]
    low = dict(zip(*common.joined_nodes(*np.array(near).T)))
    got = {r["id"]: r["first_id"] for r in line_dedup.repeated_lines(docs, bands=8, max_bits=40, chunk=chunk).collect()}
    assert got == {int(a): int(b) for a, b in low.items() if a != b}


def test_lines_of_rows_that_share_an_id(spark):
    rnd = random.Random(4)
    line, *more = (" ".join(prose(rnd, 9)) for _ in range(5))
    rows = [(1, line), (2, "\n".join(more[:3])), (2, f"{line}\n{more[3]}")]
    docs = spark.createDataFrame(rows, DOC)
    for options in ({}, line_dedup.WIDE):
        out = sorted(r["text"] for r in line_dedup.without_repeats(docs, **options).collect())
        assert out == sorted([line, "\n".join(more[:3]), more[3]])
    report = sorted((r["id"], r["n_lines"], r["n_dropped"]) for r in line_dedup.reported(docs, **line_dedup.WIDE).collect())
    assert report == [(1, 1, 0), (2, 2, 1), (2, 3, 0)]


def test_lines_counted_whatever_is_left(spark):
    docs = spark.createDataFrame([(1, "one two\nsix"), (2, "one two"), (3, "six\n"), (4, "\n\nsix"), (5, ""), (6, None), (7, "six\n\none two\nnew")], DOC)
    got = {r["id"]: (r["n_lines"], r["n_dropped"], r["kept_chars"]) for r in line_dedup.reported(docs, **line_dedup.WIDE).collect()}
    assert got == {1: (2, 0, 11), 2: (1, 1, 0), 3: (2, 1, 0), 4: (3, 1, 1), 5: (1, 0, 0), 6: (1, 0, 0), 7: (4, 2, 4)}


def test_passages_of_rows_that_share_an_id(spark):
    rnd = random.Random(5)
    shared, alone = prose(rnd, 60), prose(rnd, 100)
    docs = spark.createDataFrame([(1, " ".join(shared)), (2, " ".join(alone)), (2, " ".join(shared))], DOC)
    out = sorted(len((r["text"] or "").split()) for r in passage_dedup.without_passages(docs).collect())
    assert out == [0, 60, 100]


def test_near_copies_of_rows_that_share_an_id(spark):
    rnd = random.Random(6)
    shared, alone = " ".join(prose(rnd, 90)), " ".join(prose(rnd, 90))
    docs = spark.createDataFrame([(1, shared), (2, alone), (2, shared), (3, alone), (None, shared)], DOC)
    for stage in (simhash_dedup.without_similar, simhash_dedup.keep_first):
        out = sorted((r["doc_id"] or 0, r["text"]) for r in stage(docs).collect())
        assert out == sorted([(0, shared), (1, shared), (2, alone)])


def test_passages_among_decoys(spark):
    """Nine-word fragments of a passage stand in other documents before each of its two copies."""
    rnd = random.Random(7)
    rows, n = [], 20
    shared = [prose(rnd, 60) for _ in range(n)]
    for i, s in enumerate(shared):
        for side in (0, 500):
            rows += [(side + i, " ".join([*prose(rnd, 20), *s[j : j + 9], *prose(rnd, 20)])) for j in range(0, 52, 3)]
        rows += [(400 + i, " ".join([*prose(rnd, 30), *s, *prose(rnd, 30)])), (900 + i, " ".join([*prose(rnd, 10), *s, *prose(rnd, 40)]))]
    rows = [(key * 10_000 + at, text) for at, (key, text) in enumerate(rows)]
    docs = spark.createDataFrame(rows, DOC).repartition(3)
    got = {r["id"] // 10_000: r for r in passage_dedup.passages(docs).collect()}
    assert all(900 + i in got and got[900 + i]["start"] <= 10 and got[900 + i]["end"] >= 70 for i in range(n))


@pytest.mark.parametrize("decoys", [1, 20])
def test_passages_whose_seeds_all_have_other_holders(spark, decoys):
    """Before and between the two copies of a passage stand documents that hold thirty words of it each, every stretch in so many of them."""
    rnd = random.Random(31 + decoys)
    n, rows = 5, []
    shared = [prose(rnd, 60) for _ in range(n)]
    for i in range(n):
        for base in (0, 50_000):
            for at in range(0, 31, 3):
                for j in range(decoys):
                    rows.append((base + 1000 * i + 20 * at + j, " ".join(prose(rnd, 20) + shared[i][at : at + 30] + prose(rnd, 20))))
        rows.append((40_000 + i, " ".join(prose(rnd, 30) + shared[i] + prose(rnd, 30))))
        rows.append((90_000 + i, " ".join(prose(rnd, 10) + shared[i] + prose(rnd, 30))))
    got = {r["id"]: r for r in passage_dedup.passages(spark.createDataFrame(rows, DOC).repartition(8)).collect()}
    assert all(40_000 + i in got[90_000 + i]["others"] for i in range(n))
    assert all(got[90_000 + i]["start"] <= 10 and got[90_000 + i]["end"] >= 70 for i in range(n))


def test_passages_list_every_earlier_text_and_copies_the_first(spark):
    rnd = random.Random(33)
    shared = prose(rnd, 60)
    texts = [" ".join(prose(rnd, 20) + shared + prose(rnd, 20)) for _ in range(5)]
    rows = [(i, t) for i, t in enumerate(texts)] + [(9, texts[2])]
    got = {r["id"]: (r["others"], r["start"], r["end"]) for r in passage_dedup.passages(spark.createDataFrame(rows, DOC)).collect()}
    assert {i: got[i][0] for i in got} == {1: [0], 2: [0, 1], 3: [0, 1, 2], 4: [0, 1, 2, 3], 9: [2]}
    assert got[9][1:] == (0, 100)


@pytest.mark.parametrize("changed,share", [(0, 1.0), (4, 0.99), (7, 0.95), (10, 0.9)])
def test_fuzzy_passages_found(spark, changed, share):
    """Of 70-word passages with so many words replaced (similarity 1 to 0.857) the stated share is found."""
    rnd, n = random.Random(8 + changed), 120
    rows = []
    for i in range(n):
        base = prose(rnd, 70)
        copy = list(base)
        for j in rnd.sample(range(70), changed):
            copy[j] = prose(rnd, 1)[0]
        rows += [(i, " ".join([*prose(rnd, 30), *base, *prose(rnd, 30)])), (1000 + i, " ".join([*prose(rnd, 30), *copy, *prose(rnd, 30)]))]
    got = passage_dedup.passages(spark.createDataFrame(rows, DOC)).collect()
    found = {r["id"] - 1000 for r in got if r["others"] == [r["id"] - 1000]}
    assert len(found) == len(got) and len(found) >= share * n
    assert all(r["start"] >= 20 and r["end"] <= 110 for r in got)


def test_dealt_rows_come_back_whole_and_few():
    """Rows meet again by bucket; the couples of a repeated passage give each pair of first words once, with the farthest shared end."""
    rng = np.random.default_rng(11)
    d, e = rng.integers(-50, 50, 5000), rng.integers(-(1 << 62), 1 << 62, 5000)
    deal = passage_dedup._Dealer(4, most=1000)
    h = passage_dedup._pair_hash(d, e)
    frames = [f for s in range(0, 5000, 700) for f in deal.add(0, h[s : s + 700], d[s : s + 700], e[s : s + 700])] + list(deal.rest())
    assert sum(map(len, frames)) <= 16 * 5
    import pandas as pd

    back = [np.column_stack(x[1:]) for x in passage_dedup._buckets([pd.concat(frames).sort_values("bucket")], "i8", "i8")]
    assert len(back) == 16 and sorted(map(tuple, np.concatenate(back).tolist())) == sorted(zip(d.tolist(), e.tolist()))
    once = passage_dedup._once(*(np.array(x) for x in ([2, 2, 2, 3], [1, 1, 1, 1], [64 * 7 + 16, 64 * 7 + 31, 64 * 7 + 33, 64 * 7 + 15], [64 * 9 + 16, 64 * 9 + 31, 64 * 9 + 32, 64 * 9 + 15])))
    assert sorted(zip(*(x.tolist() for x in once))) == [(2, 1, 64 * 7 + 31, 64 * 9 + 31), (3, 1, 64 * 7 + 15, 64 * 9 + 15)]


def test_anchors_of_whole_buckets_are_chained_pair_by_pair():
    """Chains of a bucket equal those of each pair alone, whatever the order of the anchors."""
    rng = np.random.default_rng(12)
    rows = [(d, e, 64 * p + r, 64 * q + r) for d in range(6) for e in range(d) for p, q, r in rng.integers(0, [400, 400, 30], (rng.integers(1, 40), 3)).tolist()]
    rows += [(9, 8, 64 * i, 64 * (i + 5)) for i in range(0, 60, 6)]
    rng.shuffle(rows)
    assert not list(passage_dedup.chained_anchors(*np.array([[2], [1], [64], [64]]), 5))
    key = lambda c: (c[0], c[1], c[2].tolist(), c[3].tolist())
    got = sorted(key(c) for c in passage_dedup.chained_anchors(*np.array(rows).T, 5))
    assert got == sorted(key(c) for c in passage_dedup.chained_anchors(*np.array(rows).T, 5, at_once=10))
    alone = [key(c) for x in sorted({r[:2] for r in map(tuple, rows)}) for c in passage_dedup.chained_anchors(*np.array([r for r in rows if tuple(r[:2]) == x]).T, 5)]
    assert got == sorted(alone) and (9, 8, [*range(0, 60, 6)], [*range(5, 65, 6)]) in got


def test_packed_seeds_are_read_back():
    key, doc, place = np.arange(5, dtype=np.uint64) << np.uint64(50), np.arange(5) - 2, np.arange(5, dtype=np.int32)
    low = np.ascontiguousarray(key.view(np.uint8).reshape(-1, 8)[:, :6])
    a, b, c = passage_dedup._columns(passage_dedup._blob(low, doc, place), "V6", "i8", "i4")
    assert a.tobytes() == low.tobytes() and b.tolist() == doc.tolist() and c.tolist() == place.tolist()


def test_clashing_columns(spark):
    rnd = random.Random(9)
    text = " ".join(prose(rnd, 80))
    names = ["_id", "_lost", "_cuts", "id", "key", "row", "at", "cut", "h", "z", "n", "line", "c", "d", "first"]
    rows = [(1, text, *"a" * len(names)), (2, f"{text} more", *"b" * len(names)), (3, None, *"c" * len(names))]
    docs = spark.createDataFrame(rows, DOC + "".join(f", {c} string" for c in names))
    for stage in (line_dedup.without_repeats, passage_dedup.without_passages, simhash_dedup.without_similar, simhash_dedup.keep_first):
        out = stage(docs)
        assert out.columns == docs.columns
        kept = {r["doc_id"]: r for r in out.collect()}
        assert kept[1]["text"] == text and kept[1]["_id"] == "a" and kept[3]["text"] is None and kept[3]["row"] == "c"


def test_tally_goes_before_the_bit_check():
    from probsum.llm import hamming

    rng = np.random.default_rng(10)
    base = rng.integers(0, 1 << 63, 300, dtype=np.uint64)
    fps = np.unique(np.r_[base, base ^ np.uint64(3), base ^ np.uint64(0x0101010101), base ^ np.uint64(0xFFFF), base ^ np.uint64(0x1111111111111111)])
    pairs, left, links = hamming.tallied(fps, 4)
    x = fps[:, None] ^ fps[None, :]
    upper = np.triu(np.ones(x.shape, bool), 1)
    shared = (x[..., None].view(np.uint8).reshape(*x.shape, 8) == 0).sum(axis=-1)
    assert pairs == upper.sum() and left == (upper & (shared >= 4)).sum()
    assert links == (upper & (np.bitwise_count(x) <= 4)).sum() and links < left < pairs


def test_pairs_are_compared_side_by_side_and_long_ones_between_anchors(monkeypatch):
    """Sixty pairs take no walk of their own; a long pair with a block of other words is settled without a walk over the whole."""
    rnd = random.Random(8)
    left = [" ".join(prose(rnd, 40)) for _ in range(60)]
    right = [" ".join(x.split()[10:] + prose(rnd, 12)) for x in left]
    base = [f"{w}{i}" for i, w in enumerate(prose(rnd, 900))]
    long, other = " ".join(base), " ".join(prose(rnd, 1) + base[1:300] + prose(rnd, 40) + base[335:-1] + prose(rnd, 1))
    most = [int(0.2 * max(len(a), len(b))) for a, b in zip([*left, long], [*right, other])]
    want = [edits.edit_distance(a, b) <= m for a, b, m in zip([*left, long], [*right, other], most)]
    walked, walk = [], edits.edit_distance
    monkeypatch.setattr(edits, "edit_distance", lambda a, b, *m: walked.append(max(len(a), len(b))) or walk(a, b, *m))
    assert edits.within([*left, long], [*right, other], most).tolist() == want
    assert want[-1] and max(walked, default=0) < 500


@pytest.mark.parametrize("tile, at_once", [(2048, 4_000_000), (16, 50)])
def test_bands_go_packed_and_hot_keys_are_let_go(spark, tile, at_once):
    """Lines of one key come out as one group, whether a task holds all entries or lets go of keys over the tile; few rows are shuffled."""
    rnd = random.Random(9)
    rows = [(i, 7, 7, rnd.getrandbits(31) << 32 | (5 if i < 300 else 1000 + i // 2)) for i in range(500)]
    kinds = spark.createDataFrame(rows, "h long, sim long, fine long, b0 long").repartition(3)
    groups: dict = {}
    for root, h in line_dedup.banded(kinds, 3, tile=tile, at_once=at_once).collect():
        groups.setdefault(root, set()).add(h)
    assert sorted(map(sorted, groups.values())) == [list(range(300)), *([i, i + 1] for i in range(300, 500, 2))]


def test_places_are_longs_where_ids_and_lines_fit(spark):
    for ids, kind in (([-5, 3, 10**9], "bigint"), ([-(2**63), 2**63 - 1], "decimal")):
        table = spark.createDataFrame([(i, n) for i in ids for n in (0, 3, 70_000)], "id long, line int")
        place, id_of, line_of = line_dedup._places(table)
        got = table.withColumn("place", place)
        assert dict(got.dtypes)["place"].startswith(kind)
        back = got.orderBy("place").select("id", "line", id_of.alias("i"), line_of.alias("n")).collect()
        assert [(r["id"], r["line"]) for r in back] == sorted((r["i"], r["n"]) for r in back) == [(r["i"], r["n"]) for r in back]


def test_distances_in_a_band():
    rnd = random.Random(10)
    for _ in range(300):
        a = [rnd.choice("abcdef") for _ in range(rnd.choice([1, 40, 700, 1500]))]
        b = list(a)
        for _ in range(rnd.randrange(0, len(a) // 2 + 2)):
            i = rnd.randrange(len(b) + 1)
            b[i : i + rnd.randrange(2)] = [rnd.choice("abcdef")] * rnd.randrange(2)
        a, b, exact = "".join(a), "".join(b), edits.edit_distance("".join(a), "".join(b))
        for most in (0, exact - 1, exact, exact + 1, exact // 2, 2 * exact):
            found = edits.edit_distance(a, b, max(0, most))
            assert found == exact if exact <= most else found > most
