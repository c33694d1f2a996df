"""Signal builders: tables to samples over variables, in long form and as dense vectors.

Long form is (sample_id, var_id, value); ``densify`` makes (sample_id, x) with absent cells zero.
Builders return (long form, number of variables).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import load

# The letters whose shares make a text's signal.
LETTERS = "abcdefghijklmnopqrstuvwxyzàâäáçéèêëñöóüúß"
EPOCH = "1992-01-01"


def densify(long: DataFrame, p: int, *keys: str) -> DataFrame:
    """(sample_id, keys..., x): absent cells are zero, repeated cells add up. One shuffle on the sample."""
    cells = F.map_from_entries(F.collect_list(F.struct("var_id", "value")))
    summed = long.groupBy("sample_id", *keys, "var_id").agg(F.sum("value").alias("value"))
    grouped = summed.groupBy("sample_id", *keys).agg(cells.alias("__cells"))
    x = F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda i: F.coalesce(F.element_at("__cells", i.cast("int")), F.lit(0.0)))
    return grouped.select("sample_id", *keys, x.alias("x"))


def to_long(signals: DataFrame) -> DataFrame:
    return signals.select("sample_id", F.posexplode("x").alias("var_id", "value"))


def week_of(ts: Column) -> Column:
    """Weeks since the Monday of the epoch's week."""
    return F.floor(F.datediff(F.to_date(F.date_trunc("week", ts)), F.lit("1991-12-30").cast("date")) / 7)


def month_of(ts: Column) -> Column:
    return (F.year(ts) - 1992) * 12 + F.month(ts) - 1


def embedding_long(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    v = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    rows = v.select(F.col("vec_id").alias("sample_id"), F.posexplode("embedding").alias("var_id", "v"))
    return rows.select("sample_id", "var_id", F.col("v").cast("double").alias("value")), 64


def embedding_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = load(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    return v.select(F.col("vec_id").alias("sample_id"), F.transform("embedding", lambda e: e.cast("double")).alias("x"), "label")


def count_letters(texts: DataFrame, letters: str = LETTERS, column: str = "letters") -> DataFrame:
    """All columns but ``text``, and an array of how often each letter stands in the lower-cased text (null: empty).

    One pass over a text's bytes, however many letters are counted; map-only. Letters are of Latin-1.
    """
    import numpy as np

    kept = [c for c in texts.columns if c.lower() != "text"]
    codes = np.frombuffer(letters.encode("latin-1"), np.uint8)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            counts = np.empty((batch.num_rows, len(codes)))
            for i, t in enumerate(batch.column(len(kept))):
                low = (t.as_py() or "").lower().encode("latin-1", "replace")
                counts[i] = np.bincount(np.frombuffer(low, np.uint8), minlength=256)[codes]
            ends = pa.array(np.arange(batch.num_rows + 1, dtype=np.int32) * len(codes))
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(kept))), pa.ListArray.from_arrays(ends, pa.array(counts.reshape(-1)))], names=[*kept, column])

    schema = ", ".join(f"`{n}` {t}" for n, t in texts.select(*kept).dtypes)
    return texts.select(*kept, "text").mapInArrow(run, f"{schema}, {column} array<double>")


def letter_signals(texts: DataFrame, id_column: str, *keep: str, least: int = 50) -> DataFrame:
    """sample_id, kept columns and x: shares of letters, for texts of more than ``least`` letters; map-only."""
    counted = count_letters(texts.select(F.col(id_column).cast("long").alias("sample_id"), *keep, "text"))
    counted = counted.withColumn("total", F.aggregate("letters", F.lit(0.0), lambda a, b: a + b)).filter(F.col("total") > least)
    return counted.select("sample_id", *keep, F.transform("letters", lambda v: v / F.col("total")).alias("x"))


def document_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return letter_signals(load(spark, sf_dir, "documents", "doc_id", "text", "lang"), "doc_id", "lang")


def page_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load(spark, sf_dir, "pages", "page_id", "html").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    return letter_signals(pages, "page_id")


def conversation_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = load(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    return letter_signals(turns.withColumn("id", F.col("conv_id").cast("long") * F.lit(1 << 20) + F.col("turn")), "id", "role")


def benchmark_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return letter_signals(load(spark, sf_dir, "benchmark", "item_id", "text"), "item_id")


def nation_week_long(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """Revenue of each customer nation by week of shipping."""
    li = load(spark, sf_dir, "lineitem", "l_orderkey", "l_shipdate", "l_extendedprice", "l_discount")
    orders, customer = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), load(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    rows = li.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    value = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return rows.groupBy(week_of(F.col("l_shipdate")).alias("sample_id"), F.col("c_nationkey").alias("var_id")).agg(F.sum(value).alias("value")), 25


def brand_month_long(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    li = load(spark, sf_dir, "lineitem", "l_partkey", "l_shipdate", "l_extendedprice", "l_discount")
    part = load(spark, sf_dir, "part", "p_partkey", "p_brand")
    brand = F.regexp_extract("p_brand", r"(\d+)$", 1).cast("int") - 1
    rows = li.join(part, F.col("l_partkey") == F.col("p_partkey"))
    return rows.groupBy(month_of(F.col("l_shipdate")).alias("sample_id"), brand.alias("var_id")).agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("value")), 25


def part_grid_long(spark: SparkSession, sf_dir: str, size_step: int = 5, slice_: str | None = None) -> tuple[DataFrame, DataFrame]:
    """Cells brand x size bucket of one part type by month and return flag; with the dictionary of cells (D3)."""
    part = load(spark, sf_dir, "part", "p_partkey", "p_brand", "p_size", "p_type")
    if slice_ is None:
        slice_ = part.agg(F.min("p_type")).first()[0]
    b = F.regexp_extract("p_brand", r"(\d+)$", 1).cast("int") - 1
    s = F.floor((F.col("p_size") - 1) / size_step).cast("int")
    buckets = -(-50 // size_step)
    cells = part.filter(F.col("p_type") == slice_).select("p_partkey", (b * buckets + s).cast("int").alias("var_id"))
    li = load(spark, sf_dir, "lineitem", "l_partkey", "l_shipdate", "l_returnflag", "l_extendedprice", "l_discount")
    rows = li.join(cells, F.col("l_partkey") == F.col("p_partkey"))
    flag = F.ascii("l_returnflag") - 65
    long = rows.groupBy((month_of(F.col("l_shipdate")) * 26 + flag).alias("sample_id"), "var_id").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("value"))
    names = spark.range(25 * buckets).select(F.col("id").cast("int").alias("var_id"), F.format_string("brand%d-size%d", F.floor(F.col("id") / buckets), F.col("id") % buckets).alias("name"), F.struct(F.floor(F.col("id") / buckets).cast("int").alias("a"), (F.col("id") % buckets).cast("int").alias("b"), F.lit(0).alias("c")).alias("coord"))
    return long, names


def event_bin_long(spark: SparkSession, sf_dir: str, unit: str = "hour") -> tuple[DataFrame, int]:
    """Sum of event values by type, per hour or day since 2024-01-01."""
    ev = load(spark, sf_dir, "events", "ts", "event_type", "value")
    return event_bins(ev, unit), 5


def event_bins(events: DataFrame, unit: str = "hour") -> DataFrame:
    seconds = {"hour": 3600, "day": 86400}[unit]
    # seconds between timestamps without zone, exact and independent of the session's zone
    since = F.timestamp_diff("SECOND", F.lit("2024-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts").cast("timestamp_ntz"))
    kind = F.pmod(F.crc32(F.col("event_type").cast("binary")), F.lit(1000)).cast("int")
    return events.groupBy(F.floor(since / seconds).alias("sample_id"), "event_type", kind.alias("type_code")).agg(F.sum("value").alias("value"))


def event_bin_signals(spark: SparkSession, sf_dir: str, unit: str = "hour") -> tuple[DataFrame, list[str]]:
    """Dense signals over event types in name order."""
    long, _ = event_bin_long(spark, sf_dir, unit)
    kinds = [r[0] for r in long.select("event_type").distinct().orderBy("event_type").collect()]  # event types: a small domain
    var = F.array_position(F.array(*[F.lit(k) for k in kinds]), F.col("event_type")).cast("int") - 1
    return densify(long.select("sample_id", var.alias("var_id"), "value"), len(kinds)), kinds


def user_day_long(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """Users over days: fewer samples than variables."""
    ev = load(spark, sf_dir, "events", "ts", "user_id", "value")
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))
    return ev.groupBy(day.cast("long").alias("sample_id"), (F.col("user_id") % 150).cast("int").alias("var_id")).agg(F.sum("value").alias("value")), 150


def supplier_nation_long(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    li, sup = load(spark, sf_dir, "lineitem", "l_suppkey", "l_shipdate", "l_quantity"), load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    rows = li.join(sup, F.col("l_suppkey") == F.col("s_suppkey"))
    return rows.groupBy(month_of(F.col("l_shipdate")).alias("sample_id"), F.col("s_nationkey").alias("var_id")).agg(F.sum("l_quantity").alias("value")), 25


def variable_stats(long: DataFrame) -> DataFrame:
    """var_id, n, mean, variance (population) over the cells present."""
    return long.groupBy("var_id").agg(F.count("*").alias("n"), F.avg("value").alias("mean"), F.var_pop("value").alias("variance"))


def variance_mask(signals: DataFrame, eps: float = 1e-12) -> list[int]:
    """Variables that vary over the dense signals; one aggregate row per variable reaches the driver."""
    stats = to_long(signals).groupBy("var_id").agg(F.var_pop("value").alias("v"), F.max(F.abs("value")).alias("top"))
    return [r["var_id"] for r in stats.filter(F.col("v") > eps * F.greatest(F.lit(1e-300), F.col("top") * F.col("top"))).orderBy("var_id").collect()]


def keep_variables(signals: DataFrame, kept: list[int]) -> DataFrame:
    at = F.array(*[F.lit(int(i)) for i in kept])
    return signals.withColumn("x", F.transform(at, lambda i: F.element_at("x", i + 1)))


def standardize(signals: DataFrame, center: bool = True, scale: bool = True) -> DataFrame:
    """Each variable less its mean and over its population deviation (constant ones stay at zero)."""
    stats = to_long(signals).groupBy("var_id").agg(F.avg("value").alias("m"), F.stddev_pop("value").alias("s")).orderBy("var_id").collect()
    mean = F.array(*[F.lit(float(r["m"]) if center else 0.0) for r in stats])
    dev = F.array(*[F.lit(float(r["s"]) if scale and r["s"] > 0 else 1.0) for r in stats])
    return signals.withColumn("x", F.zip_with(F.zip_with("x", mean, lambda a, b: a - b), dev, lambda a, b: a / b))


def add_noise(signals: DataFrame, sigma: float, seed: int = 0) -> DataFrame:
    """Gaussian noise that depends on (seed, sample, variable) only: Box-Muller over hashed uniforms."""
    u = lambda i, salt: (F.pmod(F.xxhash64("sample_id", i, F.lit(seed * 2 + salt)), F.lit(1 << 40)) + 0.5) / F.lit(float(1 << 40))
    noise = lambda v, i: v + sigma * F.sqrt(-2.0 * F.ln(u(i, 0))) * F.cos(2.0 * 3.141592653589793 * u(i, 1))
    return signals.withColumn("x", F.transform("x", noise))


def with_units(long: DataFrame, unit: Column) -> DataFrame:
    """Number the samples of all units one after the other (subjects concatenated in time), keeping unit and step."""
    from pyspark.sql import Window as W

    keys = long.select(unit.alias("unit"), F.col("sample_id").alias("step")).distinct()
    sizes = keys.groupBy("unit").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(W.orderBy("unit").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))  # one row a unit
    numbered = keys.withColumn("i", F.row_number().over(W.partitionBy("unit").orderBy("step")) - 1)
    numbered = numbered.join(sizes.select("unit", before.alias("base")), "unit").select("unit", "step", (F.col("base") + F.col("i")).alias("new_id"))
    named = long.withColumn("unit", unit).withColumnRenamed("sample_id", "step").join(numbered, ["unit", "step"])
    return named.withColumnRenamed("new_id", "sample_id")
