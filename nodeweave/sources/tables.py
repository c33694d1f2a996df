"""Scans and sinks: declared columns of the tables, signal files, the generator as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

SIGNALS = "sample_id BIGINT, x ARRAY<DOUBLE>"
SIGNALS_LONG = "sample_id BIGINT, var_id INT, value DOUBLE"


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table of the folder, with only the columns named (all by default)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_signals(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Signals from parquet, orc or json (sample_id, x), or from csv of sample_id and one column a variable; text: numbers split by white space, numbered by line offset."""
    if fmt == "csv":
        wide = spark.read.options(header="true", inferSchema="true", **options).csv(path)
        rest = [c for c in wide.columns if c != "sample_id"]
        return wide.select(F.col("sample_id").cast("long").alias("sample_id"), F.array(*[F.col(f"`{c}`").cast("double") for c in rest]).alias("x"))
    if fmt == "text":
        lines = spark.read.text(path)
        numbers = F.transform(F.split(F.trim("value"), r"\s+"), lambda s: s.cast("double"))
        return lines.filter(F.trim("value") != "").select(F.monotonically_increasing_id().alias("sample_id"), numbers.alias("x"))
    reader = spark.read.options(**options)
    return reader.schema(schema or SIGNALS).format(fmt).load(path)


def write_signals(df: DataFrame, path: str, layout: str = "wide", partition: str | None = None, fmt: str = "parquet") -> None:
    """``wide`` (sample_id, x) or ``long`` rows, sorted by sample within files, optionally one folder for each unit."""
    if layout == "long" and "x" in df.columns:
        keep = [c for c in (partition,) if c]
        df = df.select("sample_id", *keep, F.posexplode("x").alias("var_id", "value"))
    df = df.repartition(partition) if partition else df
    writer = df.sortWithinPartitions("sample_id").write.mode("overwrite").format(fmt)
    (writer.partitionBy(partition) if partition else writer).save(path)


def register_planted_source(spark: SparkSession) -> None:
    """spark.read.format("planted").option("n", ...) with m, k, p, sigma and seed: planted samples by id ranges."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Range(InputPartition):
        def __init__(self, lo, hi):
            self.lo, self.hi = lo, hi

    class Reader(DataSourceReader):
        def __init__(self, options):
            self.o = {k: float(options.get(k, d)) for k, d in (("n", 1000), ("m", 2), ("k", 5), ("p", 70), ("sigma", 0), ("seed", 0), ("parts", 8))}

        def partitions(self):
            n, parts = int(self.o["n"]), int(self.o["parts"])
            return [Range(n * i // parts, n * (i + 1) // parts) for i in range(parts)]

        def read(self, partition):
            import numpy as np

            from nodeweave.sources.planted import draw, plant_truth

            truth = plant_truth(int(self.o["m"]), int(self.o["k"]), int(self.o["p"]), int(self.o["seed"]))
            for lo in range(partition.lo, partition.hi, 1000):
                ids = np.arange(lo, min(lo + 1000, partition.hi))
                x, state = draw(truth, ids, self.o["sigma"], int(self.o["seed"]))
                for i, v, s in zip(ids.tolist(), x.tolist(), state.tolist(), strict=True):
                    yield (i, v, s)

    class Planted(DataSource):
        @classmethod
        def name(cls):
            return "planted"

        def schema(self):
            return "sample_id BIGINT, x ARRAY<DOUBLE>, state INT"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(Planted)
