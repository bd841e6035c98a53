"""Links between 64-bit fingerprints through a byte-position inverted index.

Two fingerprints at d or fewer differing bits differ in at most d of their eight bytes, so they share
at least 8 - d positional bytes. The index lists every fingerprint under combinations of positional
bytes chosen so that any set of 8 - d shared positions contains one of them; inside a
posting the shared positional bytes are tallied, pairs under the guaranteed minimum are
discarded and the rest are verified bit by bit.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm.common import settled, written

BYTES = 8


def covering_positions(shared: int, size: int) -> list[tuple[int, ...]]:
    """A greedy family of `size`-subsets of the byte positions that hits inside every `shared`-subset."""
    todo = {frozenset(c) for c in combinations(range(BYTES), shared)}
    family = [tuple(c) for c in combinations(range(BYTES), size)]
    chosen = []
    while todo:
        best = max(family, key=lambda c: (sum(1 for t in todo if t >= set(c)), tuple(-x for x in c)))
        chosen.append(best)
        todo = {t for t in todo if not t >= set(best)}
    return sorted(chosen)


def _tally(x: np.ndarray) -> np.ndarray:
    """Positional bytes shared by each pair, from the exclusive or of the fingerprints."""
    return (x.view(np.uint8).reshape(*x.shape, BYTES) == 0).sum(axis=-1)


def near(a: np.ndarray, b: np.ndarray, max_bits: int) -> np.ndarray:
    """Which pairs, side by side, share enough positional bytes and then pass the bit check."""
    x = np.ascontiguousarray(a ^ b)
    left = np.flatnonzero(_tally(x) >= BYTES - max_bits)
    out = np.zeros(len(x), dtype=bool)
    out[left] = np.bitwise_count(x[left]) <= max_bits
    return out


def tallied(fps: np.ndarray, max_bits: int) -> tuple[int, int, int]:
    """Of all pairs of one posting: how many there are, how many the tally leaves, and how many of those are links."""
    i, j = np.triu_indices(len(fps), 1)
    x = np.ascontiguousarray(fps[i] ^ fps[j])
    left = _tally(x) >= BYTES - max_bits
    return len(x), int(left.sum()), int((np.bitwise_count(x[left]) <= max_bits).sum())


def forest(fps: np.ndarray, max_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that connect exactly what all links within `max_bits` connect, at most len - 1 of them."""
    left, right = [], []
    rest = np.arange(len(fps))
    while len(rest) > 1:
        stack, rest = [rest[0]], rest[1:]
        while stack and len(rest):
            i = stack.pop()
            hit = near(fps[rest], fps[i], max_bits)
            if hit.any():
                found = rest[hit]
                left += [i] * len(found)
                right += found.tolist()
                stack += found.tolist()
                rest = rest[~hit]
    return np.array(left, dtype=np.int64), np.array(right, dtype=np.int64)


def _run_links(key: np.ndarray, fps: np.ndarray, max_bits: int, small: int = 24):
    """Links inside runs of equal key; short runs by offsets for all runs at once, long ones by forest()."""
    start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    size = np.diff(np.r_[start, len(key)])
    out = []
    is_short = np.repeat(size <= small, size)
    for d in range(1, min(small, int(size.max(initial=1)))):
        ok = (key[d:] == key[:-d]) & is_short[d:]
        at = np.flatnonzero(ok)
        if not len(at):
            break
        hit = near(fps[at], fps[at + d], max_bits)
        out.append((fps[at[hit]], fps[at[hit] + d]))
    for s, n in zip(start[size > small], size[size > small], strict=True):
        run = fps[s : s + n]
        i, j = forest(run, max_bits)
        out.append((run[i], run[j]))
    return out


def byte_masks(max_bits: int, subset: int = 3) -> list[int]:
    """Masks of the positional bytes an index key takes."""
    shared = BYTES - max_bits
    return [sum(0xFF << (8 * p) for p in c) for c in covering_positions(shared, min(subset, shared))]


def block_masks(blocks: int, intact: int) -> list[int]:
    """Masks of every `intact` of `blocks` bit blocks: complete for up to blocks - intact differing bits."""
    edges = [64 * i // blocks for i in range(blocks + 1)]
    each = [((1 << (b - a)) - 1) << a for a, b in zip(edges, edges[1:])]
    return [sum(c) for c in combinations(each, intact)]


def links(fps: DataFrame, col: str, max_bits: int = 4, tile: int = 2048, masks: list[int] | None = None) -> DataFrame:
    """Pairs (a, b) of distinct values of `col` that connect what all links within `max_bits` connect.

    `masks` say which bits the index keys take, byte combinations by default. `fps` holds distinct non-null longs. Postings over `tile` members are cut into tiles that
    pair every two chunks of members, so no task holds more than two chunks of a posting; a tile
    yields a forest of its links, never all its pairs.
    """
    chosen = masks or byte_masks(max_bits)
    fp = F.col(col).cast("long")

    def key(mask: int, n: int):
        signed = mask - (1 << 64) if mask >> 63 else mask
        return F.struct(F.lit(n).cast("tinyint").alias("c"), fp.bitwiseAND(F.lit(signed).cast("long")).alias("v"))

    post = fps.select(
        fp.alias("fp"), F.explode(F.array(*[key(c, n) for n, c in enumerate(chosen)])).alias("k")
    ).select("fp", F.xxhash64("k.c", "k.v").alias("k"))
    # two keys that share a hash only add candidates, which are verified

    def pair_up(batches):
        """Links of the runs of a sorted stream; members of runs over `tile` come out as (key, fingerprint) rows."""
        held, size, key, over = [], 0, None, False
        for pdf in batches:
            k, v = pdf["k"].to_numpy(), pdf["fp"].to_numpy()
            start = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
            if key is not None and k[0] == key and len(start) == 1:  # still the same run
                last = 0
            else:
                last = int(start[-1])
            if last or k[0] != key:
                # all runs before the last are whole now; the one carried over ends inside this batch or did before
                end = int(start[1]) if key is not None and k[0] == key else 0
                if key is not None:
                    if over:
                        if end:
                            yield _rows(k[:end], v[:end], True)
                    else:
                        held.append((k[:end], v[:end]))
                        yield from whole(held)
                elif end == 0:
                    pass
                inner = slice(end, last)
                if last > end:
                    yield from whole([(k[inner], v[inner])])
                held, size, key, over = [], 0, int(k[-1]), False
                k, v = k[last:], v[last:]
            size += len(k)
            if over or size > tile:
                for a, b in [*held, (k, v)]:
                    yield _rows(a, b, True)
                held, over = [], True
            else:
                held.append((k, v))
        if held:
            yield from whole(held)

    def whole(parts):
        k, v = (np.concatenate(x) for x in zip(*parts, strict=True))
        if len(k) < 2:
            return
        start = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
        run = np.diff(np.r_[start, len(k)])
        large = np.repeat(run > tile, run)
        if large.any():
            yield _rows(k[large], v[large], True)
            k, v = k[~large], v[~large]
        yield from (_rows(a.view(np.int64), b.view(np.int64), False) for a, b in _run_links(k, v.view(np.uint64), max_bits) if len(a))

    first = written(
        post.repartition("k").sortWithinPartitions("k").mapInPandas(settled(pair_up), "a long, b long, over boolean"), "postings"
    )
    close = first.where("not over").select("a", "b")
    large = first.where("over").select(F.col("a").alias("k"), F.col("b").alias("fp"))
    sizes = large.groupBy("k").agg(F.ceil(F.count(F.lit(1)) / tile).cast("int").alias("c"))
    tiled = (
        large.join(sizes, "k")
        .withColumn("i", F.pmod(F.xxhash64("fp", F.lit(7)), F.col("c")).cast("int"))
        .withColumn("j", F.explode(F.expr("sequence(0, c - 1)")))
        .select(F.xxhash64("k", F.least("i", "j"), F.greatest("i", "j")).alias("k"), "fp")
    )

    def tile_links(batches):
        hold: list = []
        for pdf in batches:
            hold.append((pdf["k"].to_numpy(), pdf["fp"].to_numpy().view(np.uint64)))
            k, v = (np.concatenate(x) for x in zip(*hold, strict=True))
            cut = int(np.searchsorted(k, k[-1]))
            if cut:
                yield from (_rows(a.view(np.int64), b.view(np.int64)) for a, b in _run_links(k[:cut], v[:cut], max_bits) if len(a))
            hold = [(k[cut:], v[cut:])]
        for k, v in hold:
            if len(k) > 1:
                yield from (_rows(a.view(np.int64), b.view(np.int64)) for a, b in _run_links(k, v, max_bits) if len(a))

    within = tiled.repartition("k").sortWithinPartitions("k").mapInPandas(settled(tile_links), "a long, b long")
    return close.union(within)


def _rows(a, b, over: bool | None = None) -> pd.DataFrame:
    out = {"a": a, "b": b}
    return pd.DataFrame(out if over is None else out | {"over": over})
