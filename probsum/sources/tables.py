"""Sources and sinks: the given tables, file formats, and summaries as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThanOrEqual, InputPartition, LessThanOrEqual


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, label: str) -> str:
    """A path for files of our own in the shared folder the cluster names; where none is, temporary in local mode and an error elsewhere."""
    import tempfile
    import uuid

    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = found.get() if found.isDefined() else None
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="probsum-")
        spark.sparkContext.setCheckpointDir(root)
    return f"{root}/probsum/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """`df` written to the shared folder and read back: what comes after neither repeats its joins nor keeps their broadcasts."""
    return round_trip(df, "parquet", label)


def round_trip(df: DataFrame, fmt: str, label: str) -> DataFrame:
    """Write in a file format and read back under the same schema."""
    path = scratch(df.sparkSession, label)
    writer = df.write.format(fmt)
    reader = df.sparkSession.read.format(fmt)
    if fmt == "csv":
        writer, reader = writer.option("header", True), reader.option("header", True)
    if fmt == "text":
        df.selectExpr("to_json(struct(*)) as value").write.text(path)
        from pyspark.sql import functions as F

        return df.sparkSession.read.text(path).select(F.from_json("value", df.schema).alias("v")).select("v.*")
    writer.save(path)
    return reader.schema(df.schema).load(path)


def partitioned(df: DataFrame, by: str, label: str) -> str:
    """Write one folder per value of `by`, rows of a value together; returns the path."""
    path = scratch(df.sparkSession, label)
    df.repartition(by).write.partitionBy(by).parquet(path)
    return path


class SummarySource(DataSource):
    """spark.read.format("maxent_summary").option("path", ..).option("by", "a,b"): groups of a stored summary.

    Filters on the group columns that Spark pushes down become masks, so that excluded groups are never
    estimated. Columns are codes; est is the expected count.
    """

    @classmethod
    def name(cls) -> str:
        return "maxent_summary"

    def schema(self) -> str:
        by = self.options["by"].split(",")
        return ", ".join(f"{a} int" for a in by) + ", est double"

    def reader(self, schema):
        return SummaryReader(self.options)


class SummaryReader(DataSourceReader):
    def __init__(self, options):
        self.by = options["by"].split(",")
        self.model = options["model"]
        self.bounds: dict[str, list[int]] = {}

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, (EqualTo, GreaterThanOrEqual, LessThanOrEqual)) and len(f.attribute) == 1 and f.attribute[0] in self.by:
                lo, hi = self.bounds.setdefault(f.attribute[0], [0, 1 << 30])
                if not isinstance(f, LessThanOrEqual):
                    lo = max(lo, int(f.value))
                if not isinstance(f, GreaterThanOrEqual):
                    hi = min(hi, int(f.value))
                self.bounds[f.attribute[0]] = [lo, hi]
            else:
                yield f

    def partitions(self):
        return [InputPartition(0)]

    def read(self, partition):
        import base64
        import pickle

        import numpy as np

        from probsum.plans import infer

        model = pickle.loads(base64.b64decode(self.model))
        weights = {}
        for a, (lo, hi) in self.bounds.items():
            at = np.arange(model.sizes[a])
            weights[a] = ((at >= lo) & (at <= hi)).astype(float)
        est = infer.estimate_groups(model, self.by, weights)
        for point in np.argwhere(est > 0):
            yield (*[int(x) for x in point], float(est[tuple(point)]))


def model_option(model) -> str:
    """A model as an option of the source; models are small."""
    import base64
    import pickle

    return base64.b64encode(pickle.dumps(model)).decode()


def register_udtf(spark: SparkSession, summaries: dict) -> None:
    """SQL table function maxent_estimate(name, 'gross >= 10; p_type = ...'): estimates of registered summaries.

    Clauses are separated by semicolons, one attribute each, over codes: attr op number.
    """
    import re

    from pyspark.sql.functions import udtf

    models = {k: s.model for k, s in summaries.items()}

    class MaxentEstimate:
        def eval(self, name: str, where: str):
            import numpy as np

            from probsum.plans import infer

            model, weights = models[name], {}
            ops = {"=": np.equal, ">=": np.greater_equal, "<=": np.less_equal, ">": np.greater, "<": np.less}
            for clause in filter(None, (c.strip() for c in where.split(";"))):
                attr, op, value = re.fullmatch(r"(\w+)\s*(>=|<=|=|>|<)\s*(-?\d+)", clause).groups()
                hit = ops[op](np.arange(model.sizes[attr]), int(value)).astype(float)
                weights[attr] = weights.get(attr, 1.0) * hit
            est = infer.estimate(model, weights)
            yield float(est), int(infer.rounded(est))

    spark.udtf.register("maxent_estimate", udtf(MaxentEstimate, returnType="est double, est_rounded bigint"))
