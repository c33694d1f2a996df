"""Tables that all executors share, in the folder that ``spark.checkpoint.dir`` names."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; where it is unset, a local one in local mode, and an error on a cluster."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        where = "/tmp/checkpoints"
    return where.rstrip("/")


def write_table(df: DataFrame, name: str, **options) -> str:
    """Write ``df`` as Parquet in the shared folder and return its path."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    return path


def materialize(df: DataFrame, name: str, **options) -> DataFrame:
    """Cut lineage: the written table, read again; lost executors cost no recomputation."""
    spark = df.sparkSession
    schema = df.schema
    return spark.read.schema(schema).parquet(write_table(df, name, **options))


#: Rows of one key beyond which it is hot, and hot keys that are broadcast at most (a few bytes each).
HOT_ROWS, HOT_KEYS = 1000, 100_000


def join_one(rows: DataFrame, single: DataFrame, key: str, count: str = "n") -> DataFrame:
    """Inner join of ``rows`` with ``single`` (one written row a key, ``count``: how many of ``rows`` have it), without ``count``.

    Hot keys are broadcast (there are fewer than rows / HOT_ROWS of them, and at most HOT_KEYS), so no task gets all rows of one; the
    others are shuffled.
    """
    hot = single.filter(F.col(count) > HOT_ROWS)
    n = hot.limit(HOT_KEYS + 1).count()
    if not 0 < n <= HOT_KEYS:
        return rows.join(single.drop(count), key)
    spread = rows.join(F.broadcast(hot.drop(count)), key)
    cold = rows.join(F.broadcast(hot.select(key)), key, "left_anti").join(single.filter(F.col(count) <= HOT_ROWS).drop(count), key)
    return spread.unionByName(cold)


def fresh(columns: list[str], name: str) -> str:
    """``name``, longer until no column has it (in any case)."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def remove(df: DataFrame) -> None:
    """Delete the files under a table made by :func:`materialize`, once nothing reads it any more."""
    spark = df.sparkSession
    jvm, conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(conf).delete(path, True)


def texts(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id and text (null: empty) with the named columns, and no others."""
    return docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text"), *more)


def small_batches(spark: SparkSession, rows: int = 2000) -> None:
    """Arrow batches of few rows, as texts can be long; a runtime setting, for this session."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))
