"""Count models that the state mixture is likened to: a mixture of topics, and naive Bayes counts."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .signals import count_letters


def letter_bag(docs: DataFrame, letters: str = "abcdefghijklmnopqrstuvwxyz") -> DataFrame:
    """(doc_id, term, n) of the letters of each text, absent ones left out; one pass over a text, whatever the number of letters."""
    counted = count_letters(docs.select("doc_id", "text"), letters)
    return counted.select("doc_id", F.posexplode("letters").alias("term", "n")).select("doc_id", "term", F.col("n").cast("long").alias("n")).filter("n > 0")


def naive_bayes_counts(bag: DataFrame, labels: DataFrame, label: str) -> DataFrame:
    """(label, term, n, total): term counts by class, the sufficient statistics of multinomial naive Bayes."""
    joined = bag.join(labels.select("doc_id", label), "doc_id")
    counts = joined.groupBy(F.col(label).alias("label"), "term").agg(F.sum("n").alias("n"))
    totals = counts.groupBy("label").agg(F.sum("n").alias("total"))
    return counts.join(totals, "label").select("label", "term", "n", "total")


def topic_mixture(bag: DataFrame, m: int, terms: int, max_iter: int = 15, seed: int = 0, smooth: float = 0.5, theta=None) -> tuple[np.ndarray, np.ndarray, DataFrame]:
    """EM of a mixture of multinomials: shares, term probabilities and (doc_id, state). One aggregate per iteration."""
    if theta is None:
        overall = np.zeros(terms)
        for r in bag.groupBy("term").agg(F.sum("n").alias("n")).collect():  # one row a term
            overall[r["term"]] = r["n"]
        theta = (overall + smooth) / (overall + smooth).sum() * np.random.default_rng(seed).uniform(0.7, 1.3, (m, terms))
        theta /= theta.sum(axis=1, keepdims=True)
    shares = np.full(m, 1 / m)
    docs = bag.groupBy("doc_id").agg(F.collect_list(F.struct("term", "n")).alias("e")).persist()
    names = [f"z{j}" for j in range(m)]

    def adding(weights):
        return lambda total, e: total + e["n"] * F.element_at(weights, e["term"] + 1)

    def scored():
        out = docs
        for j in range(m):
            weights = F.array(*[F.lit(float(v)) for v in np.log(theta[j])])
            out = out.withColumn(names[j], F.aggregate("e", F.lit(float(np.log(shares[j]))), adding(weights)))
        top = F.greatest(*names) if m > 1 else F.col(names[0])
        total = sum((F.exp(F.col(z) - top) for z in names), F.lit(0.0))
        return out.withColumn("r", F.array(*[F.exp(F.col(z) - top) / total for z in names]))

    for _ in range(max_iter):
        # a document's mass travels as one more term, so one pass gives both sums
        entries = F.concat(F.array(F.struct(F.lit(-1).alias("term"), F.lit(1).cast("long").alias("n"))), "e")
        flat = scored().select("r", F.explode(entries).alias("x"))
        sums = flat.groupBy("x.term").agg(*[F.sum(F.col("x.n") * F.col("r")[j]).alias(names[j]) for j in range(m)]).collect()
        theta = np.full((m, terms), smooth)
        for r in sums:
            if r["term"] < 0:
                shares = np.array([r[z] for z in names])
            else:
                theta[:, r["term"]] += [r[z] for z in names]
        theta /= theta.sum(axis=1, keepdims=True)
        shares = np.maximum(shares / shares.sum(), 1e-9)
    states = scored().select("doc_id", (F.array_position("r", F.array_max("r")) - 1).cast("int").alias("state"))
    return shares, theta, states
