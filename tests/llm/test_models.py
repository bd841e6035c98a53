"""Learned operators and packing against plain re-computations."""

import random
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from probsum.llm import packing, site_quality

DOC = "doc_id long, text string, source string, lang string"


def test_site_posteriors_equal_grouped_arithmetic(spark):
    """Global rate, strengths of hosts and of paths inside hosts, and every posterior, from the evidence row by row."""
    rnd = random.Random(1)
    rows, labels = [], []
    for i in range(900):
        host = rnd.randrange(12)
        path = rnd.randrange(3)
        good = rnd.random() < 0.15 + 0.06 * host + 0.1 * (path - 1)
        words = ["w" + rnd.choice("abcdefghijkl") * rnd.randint(1, 6) for _ in range(rnd.randint(40, 90) if good else rnd.randint(10, 70))]
        rows.append((i, " ".join(words + ([] if good else ["#"] * rnd.randrange(9))), f"h{host}" if host else None, f"p{path}"))
        if rnd.random() < 0.6:
            labels.append((i, int(good), 0))
    docs = spark.createDataFrame(rows, DOC)
    lab = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = site_quality.scored(docs, lab, F.col("source"), F.col("lang")).toPandas().set_index("id").sort_index()
    d = pd.DataFrame(rows, columns=["id", "t", "host", "path"]).set_index("id")
    known = {i: y for i, y, _ in labels if zlib.crc32(str(i).encode()) % 5}
    d["e"] = [float(known[i]) if i in known else got.doc_score[i] for i in d.index]
    d["host"] = d.host.fillna("none")

    def moments(n, s, rate, share=None):
        between, chance = (s * s / n).sum() - n.sum() * rate * rate, (len(n) - 1) * rate * (1 - rate)
        return between, chance, n.sum() - (n * n).sum() / n.sum()

    hosts = d.groupby("host").e.agg(["count", "sum"])
    rate = d.e.mean()
    between, chance, weight = moments(hosts["count"], hosts["sum"], rate)
    k_host = min(max(rate * (1 - rate) / ((between - chance) / weight) - 1, 1), 1e6)
    paths = d.groupby(["host", "path"]).e.agg(["count", "sum"])
    total = np.zeros(3)
    spread = 0.0
    for h, g in paths.groupby(level=0):
        r = hosts["sum"][h] / hosts["count"][h]
        total += moments(g["count"], g["sum"], r)
        spread += hosts["count"][h] * r * (1 - r) / len(d)
    tau2 = (total[0] - total[1]) / total[2]
    k_path = min(max(spread / tau2 - 1, 1), 1e6) if tau2 > 0 else 1e6
    host_score = {h: (hosts["sum"][h] + k_host * rate) / (hosts["count"][h] + k_host) for h in hosts.index}
    for i, r in d.iterrows():
        n, s = paths.loc[(r.host, r.path)]
        want = (s - r.e + k_path * host_score[r.host]) / (n - 1 + k_path)
        assert abs(got.host_score[i] - host_score[r.host]) < 1e-9 and abs(got.path_score[i] - want) < 1e-9
        odds = got.doc_score[i] / (1 - got.doc_score[i]) * want / (1 - want) * (1 - rate) / rate
        assert abs(got.score[i] - odds / (1 + odds)) < 1e-6


def test_best_fit_equals_a_scan_of_all_bins():
    """A piece goes to the fullest open bin that holds it, found here by looking at every bin."""
    rnd = random.Random(2)
    for _ in range(30):
        sizes = sorted((rnd.randint(1, 60) for _ in range(80)), reverse=True)
        caps = [64, 100]
        opening = [caps[1]] * (max(caps) + 1)
        where, opened = packing._best_fit(sizes, opening, tuple(caps))
        room, want = [], []
        for n in sizes:
            fits = [(r, i) for i, r in enumerate(room) if r >= n]
            if fits:
                least = min(fits)[0]
                chosen = {i for r, i in fits if r == least}
            else:
                room.append(caps[1])
                chosen = {len(room) - 1}
            at = where[len(want)]
            assert at in chosen
            want.append(at)
            room[at] -= n
        assert len(opened) == len(room)
