"""Accuracy measures as DataFrame expressions; label alignment is the only step on the driver."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.numeric import assignment


def edge_scores(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Per state: n_found, n_true, n_hit, accuracy = n_hit / n_true (a recall), f1 = 2 n_hit / (n_found + n_true).

    Edges are rows (state, a, b); either order of a and b. Zero where a ratio has no meaning.
    """
    pair = lambda df: df.select("state", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    f, t = pair(found).withColumn("f", F.lit(1)), pair(truth).withColumn("t", F.lit(1))
    both = f.join(t, ["state", "a", "b"], "full")
    counts = both.groupBy("state").agg(F.count("f").alias("n_found"), F.count("t").alias("n_true"), F.count(F.col("f") + F.col("t")).alias("n_hit"))
    return counts.select("state", "n_found", "n_true", "n_hit", F.when(F.col("n_true") > 0, F.col("n_hit") / F.col("n_true")).otherwise(0.0).alias("accuracy"), (2.0 * F.col("n_hit") / F.greatest(F.col("n_found") + F.col("n_true"), F.lit(1))).alias("f1"))


def edge_accuracy(found: DataFrame, truth: DataFrame) -> DataFrame:
    return edge_scores(found, truth).select("state", "accuracy")


def edge_f1(found: DataFrame, truth: DataFrame) -> DataFrame:
    return edge_scores(found, truth).select("state", "f1")


def edge_sets(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Every edge of either side with its kind: hit, missed or spurious."""
    f, t = found.select("state", "a", "b").distinct(), truth.select("state", "a", "b").distinct()
    hit = f.intersect(t).withColumn("kind", F.lit("hit"))
    missed = t.exceptAll(f).withColumn("kind", F.lit("missed"))
    return hit.unionByName(missed).unionByName(f.exceptAll(t).withColumn("kind", F.lit("spurious")))


def contingency(pairs: DataFrame, cluster: str = "cluster", label: str = "label") -> DataFrame:
    return pairs.groupBy(F.col(cluster).alias("cluster"), F.col(label).alias("label")).agg(F.count("*").alias("n"))


def purity(pairs: DataFrame, cluster: str = "cluster", label: str = "label") -> DataFrame:
    """One row: purity, the share of rows that carry their cluster's most frequent label."""
    best = contingency(pairs, cluster, label).groupBy("cluster").agg(F.max("n").alias("top"), F.sum("n").alias("size"))
    return best.agg((F.sum("top") / F.sum("size")).alias("purity"))


def nmi(pairs: DataFrame, norm: str = "sqrt", cluster: str = "cluster", label: str = "label") -> DataFrame:
    """One row: nmi. Normalised by sqrt, mean, max or min of the entropies; 0 where both are 0."""
    c = contingency(pairs, cluster, label)
    c = c.select("*", F.sum("n").over(W.partitionBy("cluster")).alias("nc"), F.sum("n").over(W.partitionBy("label")).alias("nl"))
    total = c.agg(F.sum("n").alias("t"))  # one row
    c = c.crossJoin(F.broadcast(total))
    n, nc, nl, t = (F.col(x).cast("double") for x in ("n", "nc", "nl", "t"))
    parts = c.agg(F.sum(n / t * F.ln(n * t / (nc * nl))).alias("mi"), F.sum(-(n / t) * F.ln(nc / t)).alias("hc"), F.sum(-(n / t) * F.ln(nl / t)).alias("hl"))
    by = {"sqrt": F.sqrt(F.col("hc") * F.col("hl")), "mean": (F.col("hc") + F.col("hl")) / 2, "max": F.greatest("hc", "hl"), "min": F.least("hc", "hl")}[norm]
    return parts.select(F.when(by > 0, F.col("mi") / by).otherwise(0.0).alias("nmi"))


def align(pairs: DataFrame, m: int) -> np.ndarray:
    """For each cluster the true label it overlaps most, one to one (both 0 .. m-1)."""
    table = np.zeros((m, m))
    for r in contingency(pairs).collect():  # at most m x m rows
        if r["cluster"] is not None and r["label"] is not None:
            table[r["cluster"], r["label"]] = r["n"]
    return assignment(table)


def summarize_runs(metrics: DataFrame) -> DataFrame:
    """Mean and spread over repetitions of rows (scenario, setting, method, rep, metric, value), and by generator where rows have one."""
    by = [c for c in ("generator",) if c in metrics.columns]
    return metrics.groupBy(*by, "scenario", "setting", "method", "metric").agg(F.count("*").alias("runs"), F.avg("value").alias("mean"), F.stddev_samp("value").alias("spread"))


def compare_edges(edges: DataFrame, first: int, second: int) -> DataFrame:
    """Links of two states side by side: a, b, in_first, in_second."""
    side = lambda s, name: edges.filter(F.col("state") == s).select("a", "b", F.lit(True).alias(name)).distinct()
    both = side(first, "in_first").join(side(second, "in_second"), ["a", "b"], "full")
    return both.select("a", "b", F.coalesce("in_first", F.lit(False)).alias("in_first"), F.coalesce("in_second", F.lit(False)).alias("in_second"))


def compare_nodes(nodes: DataFrame, first: int, second: int) -> DataFrame:
    """Variables by their node in two states: first_node, second_node, n."""
    side = lambda s, name: nodes.filter(F.col("state") == s).select("var_id", F.col("node").alias(name))
    return side(first, "first_node").join(side(second, "second_node"), "var_id", "full").groupBy("first_node", "second_node").agg(F.count("*").alias("n"))


def align_states(first, second) -> list[int]:
    """For each state of one model the state of another whose nodes overlap most (lists of memberships, one to one).

    Two states' overlap: variables in matched nodes, nodes matched one to one by shared variables.
    """

    def shared(a, b) -> float:
        table = np.zeros((a.shape[1], b.shape[1]))
        np.add.at(table, (a.argmax(axis=1), b.argmax(axis=1)), 1.0)
        return float(sum(table[i, j] for i, j in enumerate(assignment(table)) if j >= 0))

    return [int(j) for j in assignment(np.array([[shared(a, b) for b in second] for a in first]))]


# the same measures on small arrays, for fits that run inside a task


def local_purity(cluster, label) -> float:
    cluster, label = np.asarray(cluster), np.asarray(label)
    return float(sum(np.bincount(label[cluster == c]).max() for c in np.unique(cluster)) / max(len(cluster), 1))


def local_nmi(cluster, label) -> float:
    cluster, label = np.unique(cluster, return_inverse=True)[1], np.unique(label, return_inverse=True)[1]
    t = np.zeros((cluster.max() + 1, label.max() + 1))
    np.add.at(t, (cluster, label), 1.0)
    t /= t.sum()
    a, b = t.sum(axis=1), t.sum(axis=0)
    on = t > 0
    mi = float((t[on] * np.log(t[on] / np.outer(a, b)[on])).sum())
    h = float(np.sqrt((a * np.log(a)).sum() * (b * np.log(b)).sum()))
    return mi / h if h > 0 else 0.0


def local_edge_scores(found: set, truth: set) -> tuple[float, float]:
    hit = len(found & truth)
    return (hit / len(truth) if truth else 0.0), 2 * hit / max(len(found) + len(truth), 1)


def frame_of_metrics(spark: SparkSession, rows) -> DataFrame:
    return spark.createDataFrame(rows, "scenario string, setting double, method string, rep int, metric string, value double")
