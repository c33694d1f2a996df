"""SQL surface: views of a model and its signals, registered functions and a table function."""

from __future__ import annotations

from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from ..operators.model import NetworkModel


def register(spark: SparkSession, model: NetworkModel, signals: DataFrame | None = None) -> None:
    """Temp views membership, precision, edges, states (and signals); functions score_states(x), node_of(state, var_id), edge_rows(...)."""
    from pyspark.sql.functions import udtf

    model.membership(spark).createOrReplaceTempView("membership")
    model.precision(spark).createOrReplaceTempView("precision")
    model.edges(spark).createOrReplaceTempView("edges")
    model.states(spark).createOrReplaceTempView("states")
    if signals is not None:
        signals.createOrReplaceTempView("signals")
    spark.udf.register("score_states", model.score_udf())
    # a SQL function over the membership view, so no Python runs for it
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION node_of(s INT, v INT) RETURNS INT RETURN SELECT max(node) FROM membership WHERE state = s AND var_id = v")

    @udtf(returnType="a int, b int, weight double")
    class EdgeRows:
        """Links of one precision matrix given as a flat array of k * k numbers."""

        def eval(self, values: list, k: int):
            for a in range(k):
                for b in range(a + 1, k):
                    if values[a * k + b]:
                        yield a, b, float(values[a * k + b])

    spark.udtf.register("edge_rows", EdgeRows)
    register_moments(spark)


def register_moments(spark: SparkSession) -> None:
    """moment_udaf(x): flat second moment (1/n) X'X of a group's vectors, for few variables; pairs(x): rows (a, b, value) of the products x_a x_b, a <= b."""
    from pyspark.sql.functions import udtf

    spark.udf.register("moment_udaf", moment_udaf())

    @udtf(returnType="a int, b int, value double")
    class Pairs:
        """Products of one vector's components."""

        def eval(self, x: list):
            for a, u in enumerate(x):
                for b in range(a, len(x)):
                    yield a, b, float(u * x[b])

    spark.udtf.register("pairs", Pairs)


def moment_udaf():
    """Grouped-aggregate pandas UDF of the flat second moment; a group is one task's, so for small groups."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("array<double>")
    def moment(x: pd.Series) -> Any:
        rows = np.stack(x.to_numpy())
        return (rows.T @ rows / len(rows)).reshape(-1).tolist()

    return moment


def scored(spark: SparkSession, least: float = 0.5) -> DataFrame:
    """Samples of the view ``signals`` whose best state has at least this probability."""
    return spark.sql("SELECT sample_id, r, array_position(r, array_max(r)) - 1 AS state FROM (SELECT sample_id, score_states(x) AS r FROM signals) WHERE array_max(r) >= :least", args={"least": least})
