"""Relational operators around states over time: spells, as-of and interval joins, smoothing, reports."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def state_spells(states: DataFrame, unit: str = "unit", step: str = "step", state: str = "state") -> DataFrame:
    """(unit, state, begin, end, steps): maximal runs of one state in a unit's steps."""
    order = W.partitionBy(unit).orderBy(step)
    marked = states.withColumn("__new", F.coalesce((F.lag(state).over(order) != F.col(state)).cast("int"), F.lit(1)))
    numbered = marked.withColumn("__spell", F.sum("__new").over(order.rowsBetween(W.unboundedPreceding, 0)))
    return numbered.groupBy(F.col(unit).alias("unit"), F.col("__spell"), F.col(state).alias("state")).agg(F.min(step).alias("begin"), F.max(step).alias("end"), F.count("*").alias("steps")).drop("__spell")


def state_switches(states: DataFrame, unit: str = "unit", step: str = "step", state: str = "state") -> DataFrame:
    """(unit, switches): how often the state changes between neighbouring steps."""
    order = W.partitionBy(unit).orderBy(step)
    return states.withColumn("__was", F.lag(state).over(order)).groupBy(F.col(unit).alias("unit")).agg(F.count_if(F.col("__was") != F.col(state)).alias("switches"))


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, name: str) -> DataFrame:
    """Left rows with the right side's last value at or before their time, per key.

    One union and one window: no row pairs are made. Among right rows of one time the greatest value counts.
    """
    columns = left.columns
    a = left.select(*columns, F.lit(1).alias("__side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("__v"))
    b = right.select(F.col(key), F.col(at), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = a.unionByName(b, allowMissingColumns=True)
    order = W.partitionBy(key).orderBy(at, "__side", F.col("__v").asc_nulls_first()).rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(name, F.last("__v", ignorenulls=True).over(order)).filter("__side = 1").select(*columns, name)


def interval_join(events: DataFrame, spells: DataFrame, key: str, at: str, begin: str, end: str, width: int) -> DataFrame:
    """Events inside [begin, end] of their key's spells: an equi-join on time buckets, then the range test.

    A spell is copied to each bucket it touches, so ``width`` should be near a spell's usual length.
    """
    bucket = lambda c: F.floor(F.col(c) / F.lit(width))
    e = events.withColumn("__b", bucket(at))
    s = spells.withColumn("__b", F.explode(F.sequence(bucket(begin), bucket(end))))
    return e.join(s, [key, "__b"]).filter((F.col(at) >= F.col(begin)) & (F.col(at) <= F.col(end))).drop("__b")


def range_join(rows: DataFrame, bins: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Rows with the bins [lo, hi) that hold their value, by buckets."""
    e = rows.withColumn("__b", F.floor(F.col(at) / F.lit(width)))
    s = bins.withColumn("__b", F.explode(F.sequence(F.floor(F.col(lo) / F.lit(width)), F.floor((F.col(hi) - 1) / F.lit(width)))))
    return e.join(s, "__b").filter((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("__b")


def smooth(scores: DataFrame, unit: str, step: str, value: str, reach: int) -> DataFrame:
    """Moving average of a state probability over the steps within ``reach``."""
    near = W.partitionBy(unit).orderBy(step).rangeBetween(-reach, reach)
    return scores.withColumn("smoothed", F.avg(value).over(near))


def top_edges(edges: DataFrame, k: int) -> DataFrame:
    """The k links of largest absolute weight in each state; ties to the smaller pair."""
    order = W.partitionBy("state").orderBy(F.abs("weight").desc(), "a", "b")
    return edges.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def top_variables(membership: DataFrame, k: int) -> DataFrame:
    """The k variables of largest weight in each node of each state."""
    rows = membership.select("state", "node", "var_id", F.element_at("weights", F.col("node") + 1).alias("weight"))
    return rows.withColumn("rank", F.row_number().over(W.partitionBy("state", "node").orderBy(F.desc("weight"), "var_id"))).filter(F.col("rank") <= k)


def cube_report(rows: DataFrame, *dims: str) -> DataFrame:
    """Counts over all combinations of the dimensions, with totals."""
    return rows.cube(*dims).agg(F.count("*").alias("n"))


def neighbours(variables: DataFrame) -> DataFrame:
    """Pairs (i, j) of grid cells that differ by one in one coordinate: three equi-joins, not a cross join."""
    cells = variables.select("var_id", "coord.*")
    out = None
    for axis in ("a", "b", "c"):
        rest = [x for x in ("a", "b", "c") if x != axis]
        moved = cells.select(F.col("var_id").alias("j"), (F.col(axis) - 1).alias(axis), *rest)
        pairs = cells.join(moved, ["a", "b", "c"]).select(F.col("var_id").alias("i"), "j")
        out = pairs if out is None else out.unionByName(pairs)
    return out


def quantile_buckets(rows: DataFrame, parts: int, by: str, *within: str) -> DataFrame:
    """Rows with ``bucket``: equal parts of each group in the order of ``by``."""
    return rows.withColumn("bucket", F.ntile(parts).over(W.partitionBy(*within).orderBy(by)))


def rollup_report(rows: DataFrame, *dims: str) -> DataFrame:
    """Counts by leading dimensions, with subtotals and the total."""
    return rows.rollup(*dims).agg(F.count("*").alias("n"))


def pair_statistics(rows: DataFrame, x: str, y: str, *by: str) -> DataFrame:
    """Built-in statistics of two columns: covariance, correlation and the regression of y on x."""
    a, b = F.col(x), F.col(y)
    return rows.groupBy(*by).agg(F.covar_pop(a, b).alias("covariance"), F.corr(a, b).alias("correlation"), F.regr_slope(b, a).alias("slope"), F.regr_intercept(b, a).alias("intercept"), F.regr_r2(b, a).alias("r2"))


def approximate_profile(rows: DataFrame, column: str, *by: str, bins: int = 10) -> DataFrame:
    """Approximate distinct values, quartiles and a histogram of a column, each one aggregate pass."""
    c = F.col(column)
    return rows.groupBy(*by).agg(F.approx_count_distinct(c).alias("distinct"), F.percentile_approx(c, [0.25, 0.5, 0.75]).alias("quartiles"), F.histogram_numeric(c, F.lit(bins)).alias("histogram"))
