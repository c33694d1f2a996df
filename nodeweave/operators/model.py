"""A fitted network model: tables of memberships, precisions, links and states; scoring; saving."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.states import Params, log_joint, responsibilities
from .moments import batch_matrix


@dataclass
class NetworkModel:
    params: Params
    mass: np.ndarray
    loss: float
    trace: list = field(default_factory=list)
    settings: dict = field(default_factory=dict)

    @property
    def m(self) -> int:
        return len(self.params.w)

    @property
    def k(self) -> int:
        return self.params.w[0].shape[1]

    def node_labels(self) -> np.ndarray:
        return np.array([w.argmax(axis=1) for w in self.params.w])

    def link_sets(self, eps: float = 1e-8) -> list[set]:
        out = []
        for o in self.params.omega:
            size = np.sqrt(np.outer(np.diag(o), np.diag(o)))
            out.append({(a, b) for a in range(len(o)) for b in range(a + 1, len(o)) if abs(o[a, b]) > eps * size[a, b]})
        return out

    def membership(self, spark: SparkSession) -> DataFrame:
        """state, var_id, weights, node."""
        rows = [(j, v, [float(t) for t in w[v]], int(w[v].argmax())) for j, w in enumerate(self.params.w) for v in range(len(w))]
        return spark.createDataFrame(rows, "state int, var_id int, weights array<double>, node int")

    def precision(self, spark: SparkSession) -> DataFrame:
        rows = [(j, a, b, float(o[a, b])) for j, o in enumerate(self.params.omega) for a in range(len(o)) for b in range(len(o))]
        return spark.createDataFrame(rows, "state int, a int, b int, value double")

    def edges(self, spark: SparkSession, eps: float = 1e-8) -> DataFrame:
        """state, a, b, weight, partial_corr for a < b: a link is a nonzero off-diagonal precision."""
        return edges_from_precision(self.precision(spark), eps)

    def states(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(j, float(s), float(n)) for j, (s, n) in enumerate(zip(self.params.shares, self.mass, strict=True))], "state int, share double, mass double")

    def fit_trace(self, spark: SparkSession) -> DataFrame:
        rows = [(int(t), str(ph), float(v), float(c), float(o)) for t, ph, v, c, o in self.trace]
        return spark.createDataFrame(rows, "iter int, phase string, objective double, rel_change double, max_overlap double")

    def transform(self, signals: DataFrame) -> DataFrame:
        """All columns with r (array of state probabilities), loglik and state; map-only."""
        shared = signals.sparkSession.sparkContext.broadcast(self.params)
        names = [c for c in signals.columns if c not in ("r", "loglik", "state_hat")]
        source = signals.select(*names)
        at = names.index("x")

        def run(batches) -> Iterator:
            import pyarrow as pa

            for batch in batches:
                x = batch_matrix(batch.column(at))
                z = log_joint(x, shared.value)
                top = z.max(axis=1)
                total = top + np.log(np.exp(z - top[:, None]).sum(axis=1))
                r = np.exp(z - total[:, None])
                cols = [batch.column(i) for i in range(batch.num_columns)]
                cols += [pa.array(list(r), pa.list_(pa.float64())), pa.array(total), pa.array(r.argmax(axis=1).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(cols, names=[*names, "r", "loglik", "state_hat"])

        schema = ", ".join(f"`{n}` {t}" for n, t in source.dtypes) + ", r array<double>, loglik double, state_hat int"
        return source.mapInArrow(run, schema)

    def project(self, signals: DataFrame) -> DataFrame:
        """sample_id and y: the node-space sample under each state (array of arrays)."""
        shared = signals.sparkSession.sparkContext.broadcast(self.params.w)

        def run(batches) -> Iterator:
            import pyarrow as pa

            for batch in batches:
                x = batch_matrix(batch.column(1))
                y = np.stack([x @ w for w in shared.value], axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(y.tolist(), pa.list_(pa.list_(pa.float64())))], names=["sample_id", "y"])

        return signals.select("sample_id", "x").mapInArrow(run, "sample_id long, y array<array<double>>")

    def assign_states(self, signals: DataFrame) -> DataFrame:
        return self.transform(signals).select("sample_id", F.col("state_hat").alias("state"))

    def assign_nodes(self, spark: SparkSession) -> DataFrame:
        return self.membership(spark).select("state", "var_id", "node")

    def score_udf(self):
        """Pandas UDF x -> array of state probabilities, for SQL."""
        from pyspark.sql.functions import pandas_udf

        params = self.params

        @pandas_udf("array<double>")
        def score_states(x: pd.Series) -> pd.Series:
            return pd.Series(list(responsibilities(np.stack(x.to_numpy()), params)))

        return score_states

    def save(self, spark: SparkSession, path: str) -> None:
        """Parquet tables and one JSON row of settings, under ``path``."""
        self.membership(spark).write.mode("overwrite").parquet(f"{path}/membership")
        self.precision(spark).write.mode("overwrite").parquet(f"{path}/precision")
        self.states(spark).write.mode("overwrite").parquet(f"{path}/states")
        meta = {"density": self.params.density, "tau": [float(t) for t in self.params.tau], "loss": float(self.loss), "settings": self.settings}
        spark.createDataFrame([(json.dumps(meta),)], "value string").write.mode("overwrite").text(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> NetworkModel:
        meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
        states = spark.read.parquet(f"{path}/states").orderBy("state").collect()
        m = len(states)
        w: list[list] = [[] for _ in range(m)]
        for r in spark.read.parquet(f"{path}/membership").orderBy("state", "var_id").collect():
            w[r["state"]].append(r["weights"])
        k = len(w[0][0])
        omega = [np.zeros((k, k)) for _ in range(m)]
        for r in spark.read.parquet(f"{path}/precision").collect():
            omega[r["state"]][r["a"], r["b"]] = r["value"]
        params = Params(np.array([r["share"] for r in states]), [np.array(x) for x in w], omega, np.array(meta["tau"]), meta["density"])
        return NetworkModel(params, np.array([r["mass"] for r in states]), meta["loss"], [], meta["settings"])


def edges_from_precision(precision: DataFrame, eps: float = 1e-8) -> DataFrame:
    """Links (state, a, b, weight, partial_corr) of a precision table (state, a, b, value)."""
    d = precision.filter("a = b").select("state", F.col("a").alias("v"), F.col("value").alias("d"))
    off = precision.filter("a < b")
    # one row a node and state: small by construction
    da, db = F.broadcast(d.withColumnsRenamed({"v": "a", "d": "da"})), F.broadcast(d.withColumnsRenamed({"v": "b", "d": "db"}))
    both = off.join(da, ["state", "a"]).join(db, ["state", "b"])
    corr = -F.col("value") / F.sqrt(F.col("da") * F.col("db"))
    return both.select("state", "a", "b", F.col("value").alias("weight"), corr.alias("partial_corr")).filter(F.abs("partial_corr") > eps)
