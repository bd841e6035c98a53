"""Near-duplicate documents by SimHash fingerprints of word shingles."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm import hamming, line_dedup
from probsum.llm.words import mixed
from probsum.llm.common import answered, components, forget, give_back, joined_hot, packed, settled, unpacked, written

_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64)


def shingle_hashes(text: str | None, words: int, lo: int = 0, most: int | None = None):
    """XXH64 (seed 42) of the word shingles of a text, in blocks of at most 65,536."""
    import xxhash

    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    n = max(1, len(w) - words + 1) if w else 0
    h = xxhash.xxh64_intdigest
    for at in range(0, n, 65_536):
        to = min(n, at + 65_536)
        yield np.fromiter((h(b" ".join(w[i : i + words]), 42) for i in range(at, to)), np.uint64, to - at)


def fingerprint_batch(texts, words: int = 4) -> np.ndarray:
    """Majority fingerprints of texts; texts without a word have fingerprint zero."""
    out = np.zeros(len(texts), dtype=np.uint64)
    ids, hashes, held = [], [], 0

    counts = np.zeros((len(texts), 8, 256), dtype=np.int64) if len(texts) <= 256 else None
    if counts is None:
        return np.concatenate([fingerprint_batch(texts[i : i + 256], words) for i in range(0, len(texts), 256)])
    total = np.zeros(len(texts), dtype=np.int64)

    def flush():
        nonlocal held
        if not held:
            return
        row = np.repeat(np.array(ids), [len(x) for x in hashes])
        octet = np.concatenate(hashes).view(np.uint8).reshape(-1, 8)
        for p in range(8):
            counts[:, p, :] += np.bincount(row * 256 + octet[:, p], minlength=len(texts) * 256).reshape(-1, 256)
        ids.clear(), hashes.clear()
        held = 0

    for i, text in enumerate(texts):
        for block in shingle_hashes(text, words):
            ids.append(i)
            hashes.append(block)
            total[i] += len(block)
            held += len(block)
            if held >= 200_000:
                flush()
    flush()
    ones = counts @ _BITS  # texts x byte x bit
    bits = 2 * ones > total[:, None, None]
    octets = np.packbits(bits.astype(np.uint8), axis=2, bitorder="little").reshape(len(texts), 8)
    out[:] = np.ascontiguousarray(octets).view(np.uint64).ravel()
    return out


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 4) -> DataFrame:
    """(id, fp): fp is the 64-bit fingerprint as a signed long; null texts count as empty."""

    def run(batches):
        for pdf in batches:
            fp = fingerprint_batch(pdf["text"].tolist(), words)
            yield pd.DataFrame({"id": pdf["id"], "fp": fp.view(np.int64)})

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInPandas(
        settled(run), "id long, fp long"
    )


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 4, max_bits: int = 4
) -> DataFrame:
    """Groups of near duplicates: one row (id, fp, component) per input row.

    A fingerprint link joins rows at `max_bits` or fewer differing bits; component is the smallest
    id reachable. Rows with equal fingerprints are one node; texts that are null or hold no
    word have fingerprint zero and are linked like any other. Repeated ids give repeated rows. Rows whose id is
    null take part in no minimum: their component is null unless the group has an id.
    """
    rows = written(fingerprints(docs, id_col, text_col, words), "fingerprints")
    nodes = written(rows.groupBy("fp").agg(F.min("id").alias("least"), F.count(F.lit(1)).alias("n")), "fp-nodes")
    found = components(hamming.links(nodes.select("fp"), "fp", max_bits))
    found = written(found, "fp-components")
    root = nodes.join(found, nodes.fp == found.node, "left").select("fp", "least", "n", F.coalesce("component", "fp").alias("root"))
    root = written(root, "fp-roots")
    named = written(root.groupBy("root").agg(F.min("least").alias("component"), F.count(F.lit(1)).alias("fps")), "fp-names")
    of = written(joined_hot(root, named, "root", "fps").select("fp", "n", "component"), "fp-groups")
    return joined_hot(rows, of, "fp", "n").select("id", "fp", "component")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of `docs` without near duplicates: of each group the row with the least id stays.

    All columns are kept as they are. Rows that share an id stay or go by their own text, and all rows of the least id
    of a group stay; a row with a null id stays.
    """
    words = options.get("words", 4)
    lost = near_duplicates(docs, id_col, text_col, **options).where("id > component").select("id", "fp").distinct()
    gone = lost.groupBy("id").agg(F.collect_set("fp").alias("h"))
    return _left(docs, id_col, text_col, gone, lambda text: int(fingerprint_batch([text], words).view(np.int64)[0]))


def shingle_set(text: str | None, words: int) -> np.ndarray:
    return np.unique(np.concatenate([np.zeros(0, np.uint64), *shingle_hashes(text, words)]))


def _set_name(u: np.ndarray) -> int:
    return int(mixed(u).sum(dtype=np.uint64).view(np.int64))


def shingle_sketches(docs: DataFrame, id_col: str, text_col: str, words: int, bands: int) -> DataFrame:
    """(id, h, sim, fine, b0, b1, ...): h names the set of word shingles of a text, sim and fine are sketches of it, a b is two band keys.

    Texts without a word have the empty set, h zero and nulls beside it. Rows with a null id are left out.
    """
    halves = [f"b{i}" for i in range(bands // 2)]

    def some(ids, sets):
        full = [i for i, u in enumerate(sets) if len(u)]
        out = pd.DataFrame({"id": ids, "h": [_set_name(u) for u in sets]})
        more = np.zeros((len(sets), 2 + len(halves)), dtype=np.int64)
        if full:
            word, n = np.concatenate([sets[i] for i in full]), np.array([len(sets[i]) for i in full])
            first = np.cumsum(n) - n
            keys, fine = line_dedup._band_keys(mixed(word), None, first, bands)
            bits = np.unpackbits(word.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            ones = np.add.reduceat(bits, first, axis=0, dtype=np.int64)
            sim = np.packbits(2 * ones > n[:, None], axis=1, bitorder="little").view(np.int64).ravel()
            more[full] = np.column_stack([sim, fine.view(np.int64), np.ascontiguousarray(keys).view(np.int64)])
        none = np.ones(len(sets), dtype=bool)
        none[full] = False
        for i, c in enumerate(["sim", "fine", *halves]):
            out[c] = pd.Series(more[:, i], dtype="Int64").mask(none)
        return out

    def run(batches):
        for pdf in batches:
            ids, sets, held = [], [], 0
            for key, text in zip(pdf["id"].tolist(), pdf["text"].tolist(), strict=True):
                ids.append(key), sets.append(shingle_set(text, words))
                held += len(sets[-1])
                if held > 100_000:
                    yield some(ids, sets)
                    ids, sets, held = [], [], 0
            if ids:
                yield some(ids, sets)

    return (
        docs.where(F.col(id_col).isNotNull())
        .select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
        .mapInPandas(settled(run), "id long, h long, sim long, fine long" + "".join(f", {c} long" for c in halves))
    )


def without_similar(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, least: float = 0.8, bands: int = 16,
    max_bits: int = 34, chunk: int = 128, sim_bits: int = 4,
) -> DataFrame:
    """The rows of `docs` without near duplicates: of documents that Jaccard similarities of `least` connect the least id stays.

    Similarity is exact, on sets of `words`-word shingles. Candidates are texts whose SimHashes differ in at most `sim_bits` bits, found
    by the index of near_duplicates(), and texts that share one of `bands` hashes of three minima of their sets; both differ in at most
    `max_bits` bits of SimHash and minima together. Ids are taken as longs; rows that share an id stay or go by
    their own text, and all rows of the least id of a group stay. Rows with a null id stay.
    """
    rows = written(shingle_sketches(docs, id_col, text_col, words, bands), "shingles")
    sketch = [c for c in rows.columns if c not in ("id", "h")]
    kinds = rows.groupBy("h").agg(F.min("id").alias("least"), F.count(F.lit(1)).alias("n"), *[F.min(c).alias(c) for c in sketch])
    kinds = written(kinds, "shingle-kinds")
    full = kinds.where("sim is not null")
    wide = written(line_dedup.banded(full, max_bits), "shingle-bands")
    close = written(line_dedup.simhashed(full, sim_bits), "shingle-sims")
    roots = written(wide.union(line_dedup.uncovered(close, wide)), "shingle-groups")
    forget(wide), forget(close)
    asks = kinds.join(roots.select("h").distinct(), "h").select(F.col("least").alias("id"), "h", "sim", "fine")

    def sets(text, wanted):
        h = _set_name(shingle_set(text, words))
        return [(h, a["sim"], a["fine"], text) for a in wanted if a["h"] == h]

    held = answered(docs, id_col, text_col, asks, sets, "h long, sim long, fine long, t string").dropDuplicates(["h"])
    members = written(roots.join(held.withColumn("t", packed("t")), "h"), "shingle-members")

    def alike(left, right):
        cache: dict = {}

        def of(z):
            if id(z) not in cache:
                cache[id(z)] = shingle_set(unpacked(z), words)
            return cache[id(z)]

        out = np.zeros(len(left), dtype=bool)
        for i, (a, b) in enumerate(zip(left, right, strict=True)):
            a, b = of(a), of(b)
            both = len(np.intersect1d(a, b, assume_unique=True))
            out[i] = both >= least * (len(a) + len(b) - both) - 1e-9
        return out

    found = written(components(line_dedup.linked(members, max_bits, chunk, alike)), "shingle-components")
    forget(members), forget(roots)
    root = written(
        kinds.join(found, F.col("h") == F.col("node"), "left").select("h", "least", "n", F.coalesce("component", "h").alias("root")), "shingle-roots"
    )
    named = root.groupBy("root").agg(F.min("least").alias("first"), F.count(F.lit(1)).alias("kinds"))
    first = written(joined_hot(root, written(named, "shingle-names"), "root", "kinds").select("h", "n", "first"), "shingle-firsts")
    lost = joined_hot(rows.select("id", "h"), first, "h", "n").where("id > first").select("id", "h").distinct()
    gone = lost.groupBy("id").agg(F.collect_set("h").alias("h"))
    return _left(docs, id_col, text_col, gone, lambda text: _set_name(shingle_set(text, words)))


def _left(docs: DataFrame, id_col: str, text_col: str, gone: DataFrame, name) -> DataFrame:
    """The rows of `docs` but those whose id and name(text) are in `gone` (id, h array)."""
    row = docs.select(F.struct("*").alias("row"), F.col(id_col).cast("long").alias("key"))
    row = row.withColumn("row", F.col("row").withField(text_col, packed(F.col(f"row.`{text_col}`"))))
    lost = gone.select(F.col("id").alias("at"), F.col("h").alias("names"))

    def back(z: pd.Series, names: pd.Series) -> pd.DataFrame:
        out = []
        for x, h in zip(z, names, strict=True):
            text = None if x is None else unpacked(x)
            out.append((text, h is None or name(text) not in np.asarray(h).tolist()))
        give_back()
        return pd.DataFrame(out, columns=["text", "stays"])

    back = F.pandas_udf(back, "text string, stays boolean")
    return (
        row.join(lost, F.col("key") == F.col("at"), "left")
        .select("row", back(F.col(f"row.`{text_col}`"), F.col("names")).alias("now"))
        .where("now.stays")
        .select(*[F.col("now.text").alias(c) if c == text_col else F.col(f"row.`{c}`") for c in docs.columns])
    )
