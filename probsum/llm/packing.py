"""Best-fit packing of documents into sequences of several permitted lengths."""

from __future__ import annotations

from bisect import bisect_left

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm.common import BLANKS, written

CAPACITIES = (512, 1024, 2048, 4096, 8192)


def bin_cost(capacity: int, fixed: int = 64, quadratic: int = 65_536) -> float:
    """Cost of a sequence: a fixed part, its tokens, and the quadratic share of attention."""
    return fixed + capacity + capacity * capacity / quadratic


def _best_fit(sizes: list[int], open_at: list[int], capacities: tuple[int, ...]):
    """Bin of each item and contents of each bin; open_at[s] is the capacity of a bin opened for size s."""
    free: dict[int, list[int]] = {}
    mask = 0  # bit r is set if a bin with r tokens left exists
    where, left, full = [], [], []
    for s in sizes:
        above = mask >> s
        if above:
            r = s + (above & -above).bit_length() - 1
            b = free[r].pop()
            if not free[r]:
                mask ^= 1 << r
        else:
            b, r = len(left), open_at[s]
            left.append(r)
            full.append(r)
        r -= s
        left[b] = r
        where.append(b)
        if r:
            free.setdefault(r, []).append(b)
            mask |= 1 << r
    return where, [c - r for c, r in zip(full, left, strict=True)]


def pack(sizes, capacities: tuple[int, ...] = CAPACITIES):
    """(bin of each item, capacity of each bin, contents of each bin) for sizes in 1..max(capacities).

    Items are taken as given (give them in falling order). A new bin opens at the permitted length that
    admits the item at the least cost; which lengths are worth opening is decided by packing once for every
    smallest length to open and once by cost per token, each bin being cut down at the end to the
    smallest permitted length that holds its contents, and keeping the packing of least total cost.
    """
    caps = tuple(sorted(capacities))
    top = caps[-1]
    policies = []
    for floor in caps:
        policies.append([caps[bisect_left(caps, max(s, floor))] for s in range(top + 1)])
    rate = {c: bin_cost(c) / c for c in caps}
    policies.append([min((c for c in caps if c >= s), key=lambda c: (rate[c], c)) for s in range(top + 1)])
    best = None
    for open_at in policies:
        where, used = _best_fit(list(sizes), open_at, caps)
        final = [caps[bisect_left(caps, u)] for u in used]
        cost = sum(map(bin_cost, final))
        if best is None or cost < best[0]:
            best = cost, where, final, used
    return best[1:]


def packed(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokens=None,
    capacities: tuple[int, ...] = CAPACITIES, shard_rows: int = 50_000,
) -> DataFrame:
    """One row per piece of a document: id, piece, start, n_tokens, bin_id, bin_capacity, bin_used, bin_offset.

    The length of a document is `tokens` (a column), by default its number of words. A document longer than
    the largest capacity is cut into pieces of that capacity and a rest. Pieces are dealt by hash to shards of about
    `shard_rows` pieces, so a task's work has a bound and the number of tasks grows with the input. A
    document of length 0 (null and empty texts) gives a row without a bin. Repeated rows are packed
    as often as they occur.
    """
    top = max(capacities)
    length = tokens if tokens is not None else F.size(F.array_remove(F.split(F.coalesce(F.col(text_col), F.lit("")), BLANKS), ""))
    sized = written(
        docs.select(F.col(id_col).alias("id"), length.cast("long").alias("n")), "lengths"
    )
    pieces = sized.select(
        "id",
        "n",
        F.explode(F.expr(f"sequence(0L, greatest(cast(ceil(n / {top}) as bigint) - 1, 0L))")).alias("piece"),
    ).select(
        "id",
        "piece",
        (F.col("piece") * top).alias("start"),
        F.least(F.col("n") - F.col("piece") * top, F.lit(top)).cast("long").alias("n_tokens"),
    )
    total = sized.agg(F.sum(F.greatest(F.ceil(F.col("n") / top), F.lit(1)))).first()[0] or 0
    shards = max(1, -(-int(total) // shard_rows))
    kind = docs.schema[id_col].dataType.simpleString()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["n_tokens", "id", "piece"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
        real = pdf["n_tokens"].to_numpy() > 0
        where, caps, used = pack(pdf["n_tokens"][real].tolist(), capacities)
        where, base = np.array(where, dtype=np.int64), int(pdf["shard"].iloc[0]) << 32 if len(pdf) else 0
        caps, used = np.array(caps, dtype=np.int64), np.array(used, dtype=np.int64)
        out = pdf[["id", "piece", "start", "n_tokens"]].copy()
        for name, value in (("bin_id", base + where), ("bin_capacity", caps[where]), ("bin_used", used[where])):
            out[name] = pd.Series(value, index=out.index[real], dtype="Int64").reindex(out.index)
        sizes = out["n_tokens"][real]
        out["bin_offset"] = (sizes.groupby(where).cumsum() - sizes).astype("Int64").reindex(out.index)
        return out

    return (
        pieces.withColumn("shard", F.pmod(F.xxhash64("id", "piece"), F.lit(shards)))
        .groupBy("shard")
        .applyInPandas(
            run,
            f"id {kind}, piece long, start long, n_tokens long, bin_id long, bin_capacity long, bin_used long,"
            " bin_offset long",
        )
    )
