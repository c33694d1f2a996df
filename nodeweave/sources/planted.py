"""Planted data: states with their own nodes and links, and samples drawn from their mixture.

``invariant`` (default) builds a state's precision as H P H' + (I - H H') / tau with H the unit
indicator columns of its nodes and P a sparse node precision: then the projected precision H'TH and the
inverse of the projected covariance are both P, so there is one truth about links. ``random``
fills diagonal blocks densely and off-diagonal blocks sparsely, made positive definite by diagonal
dominance; its truth is H'TH as published (``projected_precision``) or the inverse of the
projected covariance. Pairs of nodes planted without a link get zero blocks.

Samples come from a counter-based generator keyed by (seed, sample id), so the rows do not depend
on partitioning.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass
class Truth:
    """Per state: node of each variable, p x p precision, its inverse's factor, k x k node precision, links."""

    node: np.ndarray  # m x p
    theta: np.ndarray  # m x p x p
    factor: np.ndarray  # m x p x p, lower factor of the covariance
    links: list  # per state, set of (a, b) with a < b
    node_precision: np.ndarray  # m x k x k
    shares: np.ndarray

    @property
    def m(self):
        return len(self.theta)

    @property
    def k(self):
        return self.node_precision.shape[1]

    @property
    def p(self):
        return self.theta.shape[1]

    def frames(self, spark: SparkSession) -> tuple[DataFrame, DataFrame]:
        """truth_membership (state, var_id, node) and truth_edges (state, a, b)."""
        members = [(j, v, int(self.node[j, v])) for j in range(self.m) for v in range(self.p)]
        edges = [(j, a, b) for j in range(self.m) for a, b in sorted(self.links[j])]
        return spark.createDataFrame(members, "state int, var_id int, node int"), spark.createDataFrame(edges, "state int, a int, b int")


def _sizes(rng, p, k):
    """Node sizes of at least two where possible, different between states."""
    share = rng.dirichlet(np.full(k, 8.0))
    size = np.maximum(1 + (p >= 2 * k), np.floor(share * p).astype(int))
    while size.sum() > p:
        size[size.argmax()] -= 1
    while size.sum() < p:
        size[size.argmin()] += 1
    return size


def _link_graph(rng, k, density):
    pairs = [(a, b) for a in range(k) for b in range(a + 1, k)]
    want = max(1, round(density * len(pairs))) if pairs else 0
    some = rng.permutation(len(pairs))[:want]
    return {pairs[i] for i in some}


def plant_truth(m=2, k=5, p=70, seed=0, within_density=0.8, between_density=0.05, link_density=0.4, construction="invariant", tau=1.0, truth_links="projected_precision") -> Truth:
    rng = np.random.default_rng(np.random.SeedSequence([seed, m, k, p]))
    node, theta, factor, links, node_precision = [], [], [], [], []
    for _ in range(m):
        own = np.repeat(np.arange(k), _sizes(rng, p, k))
        own = own[rng.permutation(p)]
        h = np.zeros((p, k))
        h[np.arange(p), own] = 1.0
        h /= np.maximum(np.sqrt(h.sum(axis=0)), 1e-12)
        graph = _link_graph(rng, k, link_density)
        if construction == "invariant":
            pattern = np.zeros((k, k))
            for a, b in graph:
                pattern[a, b] = pattern[b, a] = rng.uniform(0.5, 1.0) * rng.choice([-1, 1])
            omega = pattern + np.diag(np.abs(pattern).sum(axis=1) * 1.1 + 0.5)
            omega *= 0.3 * k / (p * tau)  # a variable then owes its node about as much at any p
            t = h @ omega @ h.T + (np.eye(p) - h @ h.T) / tau
        elif construction == "random":
            t = np.zeros((p, p))
            for a in range(k):
                for b in range(a, k):
                    linked = a == b or (a, b) in graph
                    if not linked:
                        continue
                    rows, cols = np.flatnonzero(own == a), np.flatnonzero(own == b)
                    dense = within_density if a == b else max(between_density, 1.0 / max(len(rows) * len(cols), 1))
                    on = rng.random((len(rows), len(cols))) < dense
                    value = -rng.uniform(0.4, 1.0, on.shape) if a == b else rng.uniform(0.2, 0.6, on.shape) * rng.choice([-1, 1], on.shape)
                    t[np.ix_(rows, cols)] += np.where(on, value, 0.0)
            t = np.triu(t, 1)
            t = t + t.T
            t += np.diag(np.abs(t).sum(axis=1) + 0.2)
            t /= np.median(np.diag(t))
            omega = h.T @ t @ h
            if truth_links == "inverse_projected_covariance":
                omega = np.linalg.inv(h.T @ np.linalg.inv(t) @ h)
            off = np.abs(omega) / np.sqrt(np.outer(np.diag(omega), np.diag(omega)))
            graph = {(a, b) for a in range(k) for b in range(a + 1, k) if off[a, b] > 1e-3}
        else:
            raise ValueError(f"unknown construction {construction!r}")
        node.append(own)
        theta.append(t)
        factor.append(np.linalg.cholesky(np.linalg.inv(t)))
        links.append(graph)
        node_precision.append(omega)
    return Truth(np.array(node), np.array(theta), np.array(factor), links, np.array(node_precision), np.full(m, 1 / m))


def draw(truth: Truth, ids, sigma=0.0, seed=0):
    """Samples (n x p) and states of these ids."""
    n, p = len(ids), truth.p
    white, noise, pick = np.empty((n, p)), np.empty((n, p)) if sigma else None, np.empty(n)
    for row, i in enumerate(np.asarray(ids, dtype=np.int64).tolist()):
        rng = np.random.Generator(np.random.Philox(key=seed + 1, counter=[0, 0, 0, i % (1 << 63)]))
        pick[row] = rng.random()
        white[row] = rng.standard_normal(p)
        if sigma:
            noise[row] = rng.standard_normal(p)
    state = np.searchsorted(np.cumsum(truth.shares), pick, side="right").clip(0, truth.m - 1)
    x = np.empty((n, p))
    for j in range(truth.m):
        own = state == j
        x[own] = white[own] @ truth.factor[j].T
    return (x + sigma * noise if sigma else x), state


def plant_signals(ids: DataFrame, truth: Truth, sigma: float = 0.0, seed: int = 0, id_column: str = "sample_id") -> DataFrame:
    """sample_id, x, state: one sample for each row of a key table; map-only."""
    shared = ids.sparkSession.sparkContext.broadcast(truth)  # m p x p matrices, whatever the number of rows

    def run(batches) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            own = batch.column(0).to_numpy()
            x, state = draw(shared.value, own, sigma, seed)
            flat = pa.array(x.reshape(-1))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(own) + 1, dtype=np.int32) * truth.p), flat)
            yield pa.RecordBatch.from_arrays([batch.column(0), lists, pa.array(state.astype(np.int32))], names=["sample_id", "x", "state"])

    return ids.select(F.col(id_column).cast("long").alias("sample_id")).mapInArrow(run, "sample_id long, x array<double>, state int")
