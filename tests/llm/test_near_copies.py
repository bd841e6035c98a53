"""Near copies of the pipeline: the SimHash index gives candidates that band keys miss."""

import random

import numpy as np

from probsum.llm import line_dedup, simhash_dedup

DOC = "doc_id long, text string"


def test_simhash_index_gives_candidates(spark):
    rnd = random.Random(3)
    word = lambda: "".join(rnd.choices("abcdefghijklmnop", k=6))
    rows = []
    for i in range(600):
        base = [word() for _ in range(200)]
        copy = list(base)
        for at in rnd.sample(range(200), 2):
            copy[at] = word()
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(copy))]
    docs = spark.createDataFrame(rows, DOC).repartition(4)
    got = {r["id"]: r for r in simhash_dedup.shingle_sketches(docs, "doc_id", "text", 5, 2).collect()}
    sim = {k: np.uint64(r["sim"] & (2**64 - 1)) for k, r in got.items()}
    sets = {k: set(simhash_dedup.shingle_set(t, 5).tolist()) for k, t in rows}
    close = [i for i in range(0, 1200, 2) if int(np.bitwise_count(sim[i] ^ sim[i + 1])) <= 4 and len(sets[i] & sets[i + 1]) >= 0.8 * len(sets[i] | sets[i + 1])]
    apart = [i for i in close if all((got[i]["b0"] ^ got[i + 1]["b0"]) >> s & 0xFFFFFFFF for s in (0, 32))]
    assert apart  # some share no band key
    kept = {r["doc_id"] for r in simhash_dedup.without_similar(docs, bands=2).collect()}
    assert not kept & {i + 1 for i in close}


def test_groups_inside_others_are_not_compared_again(spark):
    frame = lambda rows: spark.createDataFrame(rows, "root long, h long")
    groups = frame([(1, 10), (1, 11), (2, 11), (2, 20), (3, 30), (3, 31)])
    by = frame([(7, 10), (7, 11), (7, 12), (8, 20), (9, 30)])
    assert sorted(map(tuple, line_dedup.uncovered(groups, by).collect())) == [(2, 11), (2, 20), (3, 30), (3, 31)]


def test_groups_that_share_members_are_joined_up_to_a_size(spark):
    rows = [(1, 10), (1, 11), (2, 11), (2, 20), (3, 30), (3, 31), (4, 40), (4, 41), (4, 42), (5, 42), (5, 43), (5, 44)]
    got: dict = {}
    for root, h in line_dedup.joined_groups(spark.createDataFrame(rows, "root long, h long"), 4).collect():
        got.setdefault(root, []).append(h)
    assert sorted(map(sorted, got.values())) == [[10, 11, 20], [30, 31], [40, 41, 42], [42, 43, 44]]
