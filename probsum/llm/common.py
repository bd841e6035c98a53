"""Shared plumbing of the corpus operators: table access, scratch tables, components."""

from __future__ import annotations

import tempfile
import uuid

from collections.abc import Callable, Iterable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs of characters other than the blank and U+0009..U+000D.
BLANKS = "[\\x20\\x09-\\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch_root(spark: SparkSession) -> str:
    """The shared folder the cluster names; where none is set, a folder of our own in local mode and an error elsewhere."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            return found.get()
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="probsum-")
        spark.sparkContext.setCheckpointDir(root)
    return root


def written(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage: write `df` to the shared scratch folder and read it back."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/probsum/{label}-{uuid.uuid4().hex}"
    schema = df.schema
    df.write.parquet(path)
    out = spark.read.schema(schema).parquet(path)
    out._scratch_path = path
    return out


def forget(df: DataFrame) -> None:
    """Delete a scratch table that nothing needs any more."""
    path = getattr(df, "_scratch_path", None)
    if path:
        spark = df.sparkSession
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def give_back() -> None:
    """Hand memory that a batch needed back to the system: workers are kept, and others run beside them."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # where the C library has it
    if trim:
        trim(0)


def settled(run: Callable) -> Callable:
    """`run` over batches, giving memory back at the end."""

    def whole(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return whole


def in_slices(batches, rows: int = 500):
    """Frames of a few rows at a time from Arrow batches, so that only so many texts are strings of Python at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows).to_pandas()


def _pack(text: str | None) -> bytes | None:
    import zstandard

    return None if text is None else zstandard.ZstdCompressor(level=3).compress(text.encode("utf-8", "surrogatepass"))


def unpacked(z: bytes) -> str:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(z).decode("utf-8", "surrogatepass")


def packed(text: str | Column) -> Column:
    """The texts compressed, for shuffles: some two fifths of what Spark's own compression of rows leaves."""

    def run(t: pd.Series) -> pd.Series:
        out = pd.Series([_pack(x) for x in t], dtype=object)
        give_back()
        return out

    return F.pandas_udf(run, "binary")(text)


_ARROW = {"long": "int64", "int": "int32", "string": "string"}


def answered(docs: DataFrame, id_col: str, text_col: str, asks: DataFrame, answer: Callable[[str, list[dict]], Iterable[tuple]], schema: str, check: Callable[[list[tuple]], list[tuple]] | None = None, pack: bool = False) -> DataFrame:
    """Rows answer(text, asks) for every text of `docs` and the rows of `asks` (id and others) about its id, as `check` leaves them.

    Texts, compressed if `pack`, meet the asks of their id in one sorted stream: the asks of one id are held, its
    texts pass one by one. `schema` has columns of type long, int or string.
    """
    names = [c for c in asks.columns if c != "id"]
    kinds = dict(asks.dtypes)
    texts = docs.where(F.col(id_col).isNotNull() & F.col(text_col).isNotNull()).select(
        F.col(id_col).cast("long").alias("id"), (packed(F.col(text_col)) if pack else F.col(text_col)).alias("z"),
        *[F.lit(None).cast(kinds[c]).alias(c) for c in names],
    )
    rows = asks.select("id", F.lit(None).cast("binary" if pack else "string").alias("z"), *names).unionByName(texts)
    fields = [x.split() for x in schema.split(", ")]

    def run(batches):
        import pyarrow as pa

        made = pa.schema([(name, getattr(pa, _ARROW[kind])()) for name, kind in fields])

        def frame(out):
            out = out if check is None else check(out)
            if not out:
                return pa.RecordBatch.from_pylist([], schema=made)
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), made)], schema=made)

        held, key, out = [], None, []
        for batch in batches:
            ids, zs = batch.column("id").to_pylist(), batch.column("z")
            empty = zs.is_null().to_pylist()
            rest = batch.select(names)
            asked = iter(rest.filter(zs.is_null()).to_pylist())
            for i, (this, ask) in enumerate(zip(ids, empty, strict=True)):
                if this != key:
                    held, key = [], this
                if ask:
                    held.append(next(asked))
                elif held:
                    out += answer(unpacked(zs[i].as_py()) if pack else zs[i].as_py(), held)
                    if len(out) > 5000:
                        yield frame(out)
                        out = []
        if out:
            yield frame(out)

    return rows.repartition("id").sortWithinPartitions("id", F.col("z").isNotNull()).mapInArrow(settled(run), schema)


def with_text(docs: DataFrame, id_col: str, text_col: str, cuts: DataFrame, change: Callable, pack: bool = False) -> DataFrame:
    """`docs` with texts changed by change(texts, *lists) where their id has a row (id, lists) in `cuts`; other texts stay.

    If `pack`, texts are compressed on their way. Every column keeps its name, whatever it is, and its place; an id
    without a cut costs no Python.
    """
    lists = [c for c in cuts.columns if c != "id"]
    cut = cuts.select(F.col("id").alias("at"), F.struct(*lists).alias("cut"))
    rows = docs.withColumn(text_col, packed(F.col(text_col))) if pack else docs
    row = rows.select(F.struct("*").alias("row"), F.col(id_col).cast("long").alias("key"))

    def run(z: pd.Series, *held: pd.Series) -> pd.Series:
        out = [x if x is None or not pack else unpacked(x) for x in z]
        at = [i for i, (x, given) in enumerate(zip(out, held[0], strict=True)) if x is not None and given is not None]
        for i, x in zip(at, change([out[i] for i in at], *[[h.iloc[i] for i in at] for h in held]), strict=True):
            out[i] = x
        give_back()
        return pd.Series(out, dtype=object)

    text = F.col(f"row.`{text_col}`")
    changed = F.pandas_udf(run, "string")(text if pack else F.when(F.col("cut").isNotNull(), text), *[F.col(f"cut.{c}") for c in lists])
    if not pack:
        changed = F.coalesce(changed, text)
    return row.join(cut, F.col("key") == F.col("at"), "left").select(
        *[changed.alias(c) if c == text_col else F.col(f"row.`{c}`") for c in docs.columns]
    )


#: Keys with more than one in so many of all rows are joined by broadcast: there are at most so many of them.
HOT_SHARE = 1000


def joined_hot(left: DataFrame, right: DataFrame, key: str, n: str) -> DataFrame:
    """`left` joined with `right` on `key`, which is unique in `right`; column `n` there counts the rows of `left`.

    Keys that hold over a thousandth of the rows (a thousand keys at most) meet their rows by broadcast, so no
    task gets a hot key whole; the others are shuffled. `right` should be a written table: it is read twice.
    """
    total = right.agg(F.sum(n)).first()[0] or 0
    is_hot = F.col(n) * HOT_SHARE > F.lit(total)
    hot, cold = F.broadcast(right.where(is_hot)), right.where(~is_hot)
    rest = left.join(F.broadcast(right.where(is_hot).select(key)), key, "left_anti")
    return left.join(hot, key).unionByName(rest.join(cold, key))


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(
        F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))
    ).first()
    return tuple(row)


def joined_nodes(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, least node reachable) of links given as arrays, by label halving."""
    nodes, at = np.unique(np.r_[a, b], return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[x], root[y])
        new = root.copy()
        for side in (root[x], root[y], x, y):
            np.minimum.at(new, side, low)
        while True:
            jump = new[new]
            if (jump == new).all():
                break
            new = jump
        if (new == root).all():
            return nodes, nodes[root]
        root = new


#: Up to so many links one task joins the nodes, in some 50 MB; more take distributed rounds.
LINKS_PER_TASK = 1_000_000


def components(
    edges: DataFrame, src: str = "a", dst: str = "b", max_rounds: int = 60, in_one_task: int = LINKS_PER_TASK
) -> DataFrame:
    """Connected components of an undirected graph given as pairs of longs.

    Returns (node, component), component being the smallest node reachable; a node without
    a link to another node is not listed. The links are counted first: up to `in_one_task` are joined by one executor
    task, whose memory that bounds. More go through rounds that alternate two star contractions (every node hangs
    its larger neighbours, then itself and its smaller ones, on its least neighbour) until the
    edge set stops changing: O(log n) rounds in practice. Each round is two aggregates and two joins on the
    edge table; rows are never gathered per node, so hubs cost no memory. Self links and
    repeats are ignored; an empty input gives an empty result.
    """
    x, y = F.col(src).cast("long"), F.col(dst).cast("long")
    e = written(
        edges.where(x != y)
        .select(F.greatest(x, y).alias("a"), F.least(x, y).alias("b"))
        .distinct(),
        "edges",
    )
    seen = _signature(e)
    if not seen[0]:
        return e.select(F.col("a").alias("node"), F.col("b").alias("component"))
    if seen[0] <= in_one_task:

        def join_up(batches):
            got = [(p["a"].to_numpy(), p["b"].to_numpy()) for p in batches]
            if got:
                nodes, low = joined_nodes(*(np.concatenate(x) for x in zip(*got, strict=True)))
                yield pd.DataFrame({"node": nodes, "component": low})

        return e.repartition(1).mapInPandas(settled(join_up), "node long, component long")
    for _ in range(max_rounds):
        both = e.select(F.col("a").alias("u"), F.col("b").alias("v")).union(
            e.select(F.col("b").alias("u"), F.col("a").alias("v"))
        )
        least = both.groupBy("u").agg(F.min("v").alias("m")).select(
            "u", F.least("u", "m").alias("m")
        )
        large = (
            both.where("v > u")
            .join(least, "u")
            .select(F.col("v").alias("a"), F.col("m").alias("b"))
            .where("a <> b")
            .distinct()
        )
        large = written(large, "large")
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = (
            large.join(low, "a")
            .where("b <> m")
            .select(F.greatest("b", "m").alias("a"), F.least("b", "m").alias("b"))
            .union(low.select("a", F.col("m").alias("b")))
            .distinct()
        )
        small = written(small, "small")
        forget(e)
        forget(large)
        e, now = small, _signature(small)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    roots = e.select("b").distinct()
    return e.select(F.col("a").alias("node"), F.col("b").alias("component")).union(
        roots.select(F.col("b").alias("node"), F.col("b").alias("component"))
    )
