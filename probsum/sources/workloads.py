"""The experiment relations on the given tables, and their query sets. SQL forms are for DuckDB."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probsum.functions.domain import Attr, date_code, equi_width, fold_rare
from probsum.sources.tables import table

COARSE = ["ship_month", "p_brand", "p_size", "p_type", "net", "gross"]
FINE = ["ship_month", "brand_name", "size_type", "net", "gross"]
PARTICLES = ["density", "mass", "x", "y", "z", "grp", "type", "snap"]
#: Pairs 1 to 4 of the evaluation, and the summaries compared: none, 1&2, 3&4, 1&2&3.
PAIRS = {1: ("p_brand", "p_type"), 2: ("p_size", "p_type"), 3: ("net", "gross"), 4: ("p_brand", "p_size")}
SUMMARIES = {"none": [], "1&2": [1, 2], "3&4": [3, 4], "1&2&3": [1, 2, 3]}


def coarse_attrs() -> list[Attr]:
    return [
        Attr("ship_month", 1, 0, 83), Attr("p_brand"), Attr("p_size"), Attr("p_type"), Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81),
    ]


def fine_attrs() -> list[Attr]:
    return [Attr("ship_month", 1, 0, 83), Attr("brand_name"), Attr("size_type"), Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81)]


def particle_attrs() -> list[Attr]:
    return [
        Attr("density", 1, 0, 58), Attr("mass", 1, 0, 52), Attr("x", 1, 0, 21), Attr("y", 1, 0, 11), Attr("z", 1, 0, 9),
        Attr("grp"), Attr("type"), Attr("snap", 1, 0, 3),
    ]


def _priced(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem")
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return line.select(
        "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey",
        date_code("l_shipdate", "month", "1995-01-01").alias("ship_month"),
        equi_width(net, 1700, 0, 62).alias("net"),
        equi_width("l_extendedprice", 1300, 0, 81).alias("gross"),
    )


def shop_coarse(spark: SparkSession, sf_dir: str, keys: bool = False) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_size", "p_type")
    out = _priced(spark, sf_dir).join(part, F.col("l_partkey") == F.col("p_partkey"))
    extra = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"] if keys else []
    return out.select(*COARSE, *extra)


def shop_fine(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_name", "p_size", "p_type")
    rows = _priced(spark, sf_dir).join(part, F.col("l_partkey") == F.col("p_partkey"))
    named = fold_rare(rows, "p_brand", "p_name", 2, name="_name")
    typed = fold_rare(named, "p_size", "p_type", 2, name="_type")
    return typed.select(
        "ship_month", F.concat_ws("|", "p_brand", "_name").alias("brand_name"),
        F.concat_ws("|", F.col("p_size").cast("string"), "_type").alias("size_type"), "net", "gross",
    )


def shop_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_size", "p_type")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    rows = _priced(spark, sf_dir).join(part, F.col("l_partkey") == F.col("p_partkey"))
    rows = rows.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return rows.select("ship_month", "p_brand", "p_size", "p_type", "c_nationkey", "c_mktsegment")


def shop_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _priced(spark, sf_dir).select("ship_month", "net", "gross")


def particles_like(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem")
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    year = F.year("l_shipdate")
    return line.select(
        equi_width("l_extendedprice", 1810.4, 0, 58).alias("density"),
        equi_width(net, 2020, 0, 52).alias("mass"),
        F.least(F.floor((F.col("l_quantity") - 1) * 21 / 50), F.lit(20)).cast("int").alias("x"),
        F.round(F.col("l_discount") * 100).cast("int").alias("y"),
        F.round(F.col("l_tax") * 100).cast("int").alias("z"),
        F.col("l_linestatus").alias("grp"),
        F.col("l_returnflag").alias("type"),
        F.when(year <= 1996, 0).when(year <= 1998, 1).otherwise(2).alias("snap"),
    )


def event_rel(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events")
    return e.select(
        F.hour("ts").alias("hour"), "event_type", equi_width("value", 5).alias("bucket"),
        F.get_json_object("props", "$.k").cast("int").alias("k"), "event_id", "ts", "user_id",
    )


def talk_rel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "conversations").select(
        "role", F.col("turn").cast("int").alias("turn"),
        F.floor(F.log2(F.greatest(F.char_length("text"), F.lit(1)).cast("double"))).cast("int").alias("loglen"),
    )


def doc_rel(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return docs.join(labels, "doc_id", "left").select(
        "lang", "source", F.floor(F.log2(F.greatest("n_chars", F.lit(1)).cast("double"))).cast("int").alias("logchars"), "quality",
    )


def point_rel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings: the label and three components in buckets of 1/21."""
    e = table(spark, sf_dir, "embeddings")
    return e.select("label", *[F.floor((F.col("embedding")[i].cast("double") + 1) * 21).cast("int").alias(f"e{i}") for i in range(3)])


def page_rel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select(
        F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("html_lang"),
        F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"),
        F.regexp_extract("url", "\\.([a-z]+)/", 1).alias("suffix"),
    )


COARSE_SQL = """(select 12 * (year(l_shipdate) - 1995) + month(l_shipdate) - 1 as ship_month, p_brand, p_size, p_type,
  greatest(least(floor(l_extendedprice * (1 - l_discount) / 1700), 61), 0)::int as net,
  greatest(least(floor(l_extendedprice / 1300), 80), 0)::int as gross, l_orderkey, l_linenumber, l_partkey, l_suppkey
  from lineitem join part on l_partkey = p_partkey)"""

PARTICLES_SQL = """(select greatest(least(floor(l_extendedprice / 1810.4), 57), 0)::int as density,
  greatest(least(floor(l_extendedprice * (1 - l_discount) / 2020), 51), 0)::int as mass,
  least(floor((l_quantity - 1) * 21 / 50), 20)::int as x, round(l_discount * 100)::int as y, round(l_tax * 100)::int as z,
  l_linestatus as grp, l_returnflag as type,
  case when year(l_shipdate) <= 1996 then 0 when year(l_shipdate) <= 1998 then 1 else 2 end as snap from lineitem)"""


def templates(attrs: list[str], sizes=(2, 3), count: int | None = None) -> list[tuple[str, ...]]:
    """Query templates: subsets of the attributes in a fixed order."""
    out = [c for k in sizes for c in combinations(attrs, k)]
    return out if count is None else out[:count]


#: Fifteen two- and three-attribute templates of the coarse relation.
FIFTEEN = [*combinations(("p_brand", "p_size", "p_type", "net", "gross"), 2), *list(combinations(("p_brand", "p_size", "p_type", "net"), 3)), ("p_size", "net", "gross")]


def group_counts(rel: DataFrame, attrs) -> DataFrame:
    return rel.groupBy(*attrs).agg(F.count(F.lit(1)).alias("n"))


def mix(attrs, salt: int = 0) -> str:
    """An integer mix of code columns that Spark and DuckDB compute alike."""
    primes = (7919, 104729, 1299709, 15485863)
    return "(" + " + ".join(f"{a} * {p}" for a, p in zip(attrs, primes)) + f" + {salt}) % 1000003"


def hitters(codes: DataFrame, attrs, domain_codes: dict[str, int], heavy: int = 100, light: int = 100, absent: int = 200) -> DataFrame:
    """(kind, attrs.., n): the largest and smallest groups, ties by codes, and cells without rows in mixed order."""
    counts = group_counts(codes, attrs)
    h = counts.orderBy(F.desc("n"), *attrs).limit(heavy).withColumn("kind", F.lit("heavy"))
    l = counts.orderBy("n", *attrs).limit(light).withColumn("kind", F.lit("light"))
    grid = None
    for a in attrs:  # the product of a few small domains
        own = codes.sparkSession.range(domain_codes[a]).select(F.col("id").cast("int").alias(a))
        grid = own if grid is None else grid.crossJoin(own)
    none = grid.join(counts, list(attrs), "left_anti").orderBy(F.expr(mix(attrs)), *attrs).limit(absent)
    z = none.withColumn("n", F.lit(0).cast("long")).withColumn("kind", F.lit("absent"))
    return h.unionByName(l).unionByName(z).select("kind", *attrs, "n")


def hitters_of(counts, attrs, heavy: int = 100, light: int = 100, absent: int = 200) -> list[tuple]:
    """hitters() as (kind, codes, n) rows from the array of all groups' counts, one axis per attribute."""
    import numpy as np

    points = np.argwhere(counts > 0)
    n = counts[tuple(points.T)]
    down, up = np.argsort(-n, kind="stable")[:heavy], np.argsort(n, kind="stable")[:light]  # points ascend by codes
    none = np.argwhere(counts == 0)
    mixed = sum(none[:, i] * p for i, p in zip(range(len(attrs)), (7919, 104729, 1299709, 15485863))) % 1000003
    none = none[np.argsort(mixed, kind="stable")[:absent]]
    out = [(kind, tuple(points[i].tolist()), int(n[i])) for kind, at in (("heavy", down), ("light", up)) for i in at.tolist()]
    return out + [("absent", tuple(x), 0) for x in none.tolist()]


def block_matrix(size: int = 12):
    """A 12 x 12 matrix of blocks that twelve leaves describe without error; values up to 4,000,000."""
    import numpy as np

    out = np.zeros((size, size), dtype=np.int64)
    level = 0
    for i in range(3):
        for j in range(4):
            out[i * size // 3 : (i + 1) * size // 3, j * size // 4 : (j + 1) * size // 4] = (level * 4_000_000) // 11
            level += 1
    return out
