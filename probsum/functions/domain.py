"""Attributes, their ordered active domains, and the integer codes of a relation."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Dictionaries of more values than this are joined by shuffle instead of broadcast.
MOST_BROADCAST = 100_000


def equi_width(x: Column | str, width: float, lo: float = 0.0, bins: int | None = None) -> Column:
    """Code of the bucket of `width` from `lo` on; with `bins`, what lies outside falls into the end buckets."""
    x = F.col(x) if isinstance(x, str) else x
    code = F.floor((x - F.lit(lo)) / F.lit(width))
    if bins is not None:
        code = F.greatest(F.least(code, F.lit(bins - 1)), F.lit(0))
    return code.cast("int")


def fitted_width(df: DataFrame, col: str, bins: int) -> tuple[float, float]:
    """(lo, width) of `bins` equal buckets over the observed range: one aggregate."""
    lo, hi = df.agg(F.min(col).cast("double"), F.max(col).cast("double")).first()
    if lo is None:
        return 0.0, 1.0
    return lo, (hi - lo) / bins if hi > lo else 1.0


def date_code(col: str, unit: str, origin: str) -> Column:
    """Days, weeks, months, years or three-year eras since `origin` (a date)."""
    d, o = F.to_date(F.col(col)), F.to_date(F.lit(origin))
    if unit == "day":
        return F.datediff(d, o).cast("int")
    if unit == "week":
        return F.floor(F.datediff(d, o) / 7).cast("int")
    months = (F.year(d) - F.year(o)) * 12 + F.month(d) - F.month(o)
    size = {"month": 1, "year": 12, "era": 36}[unit]
    return F.floor(months / size).cast("int")


def fold_rare(df: DataFrame, parent: str, child: str, k: int = 2, other: str = "Other", name: str | None = None) -> DataFrame:
    """`df` with the child values of each parent beyond the `k` most frequent (ties by value) made `other`."""
    counts = df.groupBy(parent, child).agg(F.count(F.lit(1)).alias("_n"))
    rank = F.row_number().over(W.partitionBy(parent).orderBy(F.desc("_n"), child))
    top = counts.withColumn("_r", rank).where(F.col("_r") <= k).select(
        F.col(parent).alias("_p"), F.col(child).alias("_c")
    )
    joined = df.join(top, (F.col(parent).eqNullSafe(F.col("_p"))) & (F.col(child).eqNullSafe(F.col("_c"))), "left")
    folded = F.when(F.col("_p").isNotNull() | F.col("_c").isNotNull(), F.col(child).cast("string")).otherwise(F.lit(other))
    return joined.withColumn(name or child, folded).drop("_p", "_c")


def drop_nulls(df: DataFrame, attrs: list[str]) -> DataFrame:
    return df.dropna(subset=attrs)


@dataclass(frozen=True)
class Attr:
    """An attribute: a dictionary of its values, or buckets of `width` from `lo`; `size` pins the number of codes."""

    name: str
    width: float | None = None
    lo: float = 0.0
    size: int | None = None

    @property
    def arithmetic(self) -> bool:
        return self.width is not None


def _dictionary(counts: DataFrame, name: str) -> DataFrame:
    code = F.row_number().over(W.orderBy(name)) - 1
    return counts.select(
        F.lit(name).alias("attr"), code.cast("int").alias("code"), F.col(name).cast("string").alias("label"),
        F.lit(None).cast("double").alias("lo"), F.lit(None).cast("double").alias("hi"), "n",
    )


def _bucketed(counts: DataFrame, a: Attr) -> DataFrame:
    rows = counts.select(F.col(a.name).alias("code"), "n")
    if a.size is not None:
        grid = counts.sparkSession.range(a.size).select(F.col("id").cast("int").alias("code"))
        rows = grid.join(rows, "code", "left").select("code", F.coalesce("n", F.lit(0)).alias("n"))
    lo = F.lit(a.lo) + F.col("code") * a.width
    return rows.select(
        F.lit(a.name).alias("attr"), "code", F.col("code").cast("string").alias("label"),
        lo.alias("lo"), (lo + a.width).alias("hi"), "n",
    )


def build_domain(df: DataFrame, attrs: list[Attr]) -> DataFrame:
    """domain(attr, code, label, lo, hi, n): codes ascend with the value; pinned buckets may have n = 0.

    The values of all attributes are counted in one pass by grouping sets; what follows works on that small table.
    """
    names = [a.name for a in attrs]
    keyed = df.select(*[equi_width(a.name, a.width, a.lo, a.size).alias(a.name) if a.arithmetic else F.col(a.name) for a in attrs])
    counts = keyed.groupingSets([[c] for c in names], *names).agg(
        F.count(F.lit(1)).alias("n"), F.grouping_id(*[F.col(c) for c in names]).alias("_g")
    ).persist()
    full = (1 << len(names)) - 1
    parts = []
    for i, a in enumerate(attrs):
        own = counts.where((F.col("_g") == full - (1 << (len(names) - 1 - i))) & F.col(a.name).isNotNull())
        parts.append(_bucketed(own, a) if a.arithmetic else _dictionary(own, a.name))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def encode(
    df: DataFrame, attrs: list[Attr], domain: DataFrame | None = None, nulls: str = "drop", unknown: str = "drop"
) -> tuple[DataFrame, DataFrame]:
    """(codes, domain): one int column per attribute.

    A given `domain` pins the codes, so that several relations or a stream agree. Values outside it are
    dropped, or make code -1 with unknown="mark" (the overflow bucket of updates). Rows with a null in any attribute
    are dropped, or kept with a null code.
    """
    names = [a.name for a in attrs]
    kept = df.select(*names)
    if nulls == "drop":
        kept = drop_nulls(kept, names)
    domain = build_domain(kept, attrs) if domain is None else domain
    out = kept
    listed = [a.name for a in attrs if not a.arithmetic]
    values = domain.where(F.col("attr").isin(listed)).groupBy("attr").agg(F.count(F.lit(1))).collect() if listed else []
    many = {r[0] for r in values if r[1] > MOST_BROADCAST}
    for a in attrs:
        if a.arithmetic:
            code = equi_width(a.name, a.width, a.lo, a.size)
            out = out.withColumn(a.name, code)
            continue
        book = domain.where(F.col("attr") == a.name).select(
            F.col("label").alias("_label"), F.col("code").alias("_code")
        )
        if a.name not in many:
            book = F.broadcast(book)
        out = out.join(book, F.col(a.name).cast("string") == F.col("_label"), "left")
        missing = F.when(F.col(a.name).isNotNull(), F.lit(-1)) if unknown == "mark" else F.lit(None)
        out = out.withColumn(a.name, F.coalesce("_code", missing.cast("int"))).drop("_label", "_code")
    out = out.select(*names)
    if unknown == "drop" and nulls == "drop":
        out = drop_nulls(out, names)
    return out, domain


def domain_report(domain: DataFrame) -> DataFrame:
    """(attr, size, log10_d): domain sizes, and log10 of the number of possible tuples on every row."""
    sizes = domain.groupBy("attr").agg(F.count(F.lit(1)).alias("size"))
    total = sizes.agg(F.sum(F.log10("size")).alias("log10_d"))
    return sizes.join(F.broadcast(total), F.lit(True))


def codes_matching(domain: DataFrame, attr: str, predicate: str) -> list[int]:
    """Codes whose value meets a SQL predicate over the attribute's name; Spark parses it.

    The name is the bucket number for a bucketed attribute, else the value as text (compared as a
    number where the text is one); `lo` and `hi` give the edges of a bucket.
    """
    own = domain.where(F.col("attr") == attr)
    number = F.expr("try_cast(label as double)")
    numeric = own.agg(F.count_if(number.isNull())).first()[0] == 0
    named = own.withColumn(attr, number if numeric else F.col("label"))
    return sorted(r["code"] for r in named.where(predicate).select("code").collect())


def bucket_weights(domain: DataFrame, attr: str, lo: float, hi: float) -> dict[int, float]:
    """Share of each bucket that lies in [lo, hi): a linear query for ranges that cut buckets."""
    share = F.greatest(F.lit(0.0), F.least(F.col("hi"), F.lit(float(hi))) - F.greatest(F.col("lo"), F.lit(float(lo)))) / (
        F.col("hi") - F.col("lo")
    )
    rows = domain.where(F.col("attr") == attr).select("code", share.alias("w")).where("w > 0").collect()
    return {r["code"]: r["w"] for r in rows}
