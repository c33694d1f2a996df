"""Planted experiments and table workloads.

The proposal runs in two forms: ``mixture-printed`` is the estimator as published (projected density, multiplicative
membership, no restart of a state's membership), ``mixture`` this package's own (residual density, disjoint
membership, refresh). Both generators serve every scenario: ``random`` is the published construction, ``invariant`` this package's own.

Every (scenario, setting, repetition) is a key; one ``applyInPandas`` group draws its samples and fits
all methods, so the sweep is as parallel as it has keys. One cell can also be run over the
distributed path (:func:`distributed_cell`), and both agree.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import partition as part
from ..functions.numeric import assignment
from ..functions.states import Options, fit_local, responsibilities
from ..sources.planted import Truth, draw, plant_signals, plant_truth
from ..sources.staging import stage
from . import measures, signals
from .estimators import CoupledNetwork, OrthoTriFactor, StateNetworkMixture, two_stage_moments
from .model import NetworkModel

METHODS = ("mixture", "mixture-printed", "coupled", "trifactor", "kmeans+coupled", "kmeans+trifactor", "kmeans+joint")
#: Published settings: samples, noise, variables and nodes, the others held at n=2000, p=70, sigma=0, k=5.
SCENARIOS = {
    "samples": [dict(n=n, p=70, k=5, sigma=0.0, setting=n) for n in (200, 500, 1000, 1500, 2000)],
    "noise": [dict(n=2000, p=70, k=5, sigma=float(s), setting=s) for s in (2, 3, 4, 5)],
    "variables": [dict(n=2000, p=p, k=5, sigma=0.0, setting=p) for p in (70, 140, 210, 280, 350)],
    "nodes": [dict(n=2000, p=70, k=k, sigma=0.0, setting=k) for k in (3, 5, 7, 9, 11)],
}
#: l1 of the experiments, in units of the mean node variance; unpublished, so chosen here: of the scenario "penalty" the weight that serves both generators.
L1 = 0.05
MIXTURE = dict(density="residual", membership_update="disjoint", max_iter=25, n_restarts=2, l1=L1, l1_relative=True)
#: The published estimator; what is unpublished (restarts, l1, moments' signs) as for MIXTURE.
PRINTED = dict(density="projected", membership_update="multiplicative", refresh=(), max_iter=25, n_restarts=2, l1=L1, l1_relative=True)
GENERATORS = ("random", "invariant")


def fit_methods(x, ids, m: int, k: int, seed: int, methods=METHODS, l1: float = L1) -> dict[str, tuple[NetworkModel, np.ndarray]]:
    """Model and state of each sample for every method on one sample set."""
    out: dict[str, tuple[NetworkModel, np.ndarray]] = {}
    n = len(x)
    whole = x.T @ x / n
    label = part.kmeans(x, m, seed)[0] if any("kmeans" in s for s in methods) else None
    groups = [((x[label == j].T @ x[label == j]) / max((label == j).sum(), 1), int((label == j).sum())) for j in range(m)] if label is not None else []
    one = dict(seed=seed, membership_update="disjoint", max_iter=20, l1_relative=True)
    for name in methods:
        if name.startswith("mixture"):
            fit = fit_local(x, Options(m=m, k=k, seed=seed, **((PRINTED if name == "mixture-printed" else MIXTURE) | {"l1": l1})), ids)
            out[name] = NetworkModel(fit.params, fit.mass, fit.loss, fit.trace), responsibilities(x, fit.params).argmax(axis=1)
        elif name == "coupled":
            out[name] = CoupledNetwork(k, l1, **one).fit_moment(whole, n), np.zeros(n, dtype=int)
        elif name == "trifactor":
            out[name] = OrthoTriFactor(k, seed).fit_moment(whole, n), np.zeros(n, dtype=int)
        elif name == "kmeans+joint":
            out[name] = two_stage_moments("joint", groups, k, l1, 0.05, seed, l1_relative=True), label
        else:
            kind = name.partition("+")[2]
            more = {key: v for key, v in one.items() if key != "seed"} if kind == "coupled" else {}
            out[name] = two_stage_moments(kind, groups, k, l1, seed=seed, **more), label
    return out


def score_model(model: NetworkModel, states, truth: Truth, true_states) -> dict[str, float]:
    """Measures against planted truth, states and nodes matched by largest overlap, averaged over true states."""
    m, k = truth.m, truth.k
    if model.m == 1:  # one network stands for every state
        chosen = [0] * m
    else:
        table = np.zeros((m, model.m))
        np.add.at(table, (true_states, states), 1.0)
        chosen = assignment(table)  # each true state's own found one; with more found states the rest stay unmatched
    got = {"edge_accuracy": [], "edge_f1": [], "node_purity": [], "node_nmi": []}
    for j in range(m):
        label, own = model.params.w[chosen[j]].argmax(axis=1), truth.node[j]
        table = np.zeros((k, k))
        np.add.at(table, (label, own), 1.0)
        name = assignment(table)
        found = {tuple(sorted((int(name[a]), int(name[b])))) for a, b in model.link_sets()[chosen[j]]}
        accuracy, f1 = measures.local_edge_scores(found, truth.links[j])
        for key, v in (("edge_accuracy", accuracy), ("edge_f1", f1), ("node_purity", measures.local_purity(label, own)), ("node_nmi", measures.local_nmi(label, own))):
            got[key].append(v)
    out = {key: float(np.mean(v)) for key, v in got.items()}
    out["state_purity"] = measures.local_purity(states, true_states)
    out["state_nmi"] = measures.local_nmi(states, true_states)
    return out


#: Weights of the penalty, in units of the mean node variance, for the study of hyper-parameters; p, n, k as in the base setting.
WEIGHTS = (0.02, 0.05, 0.15, 0.3, 0.6)
SCENARIOS["penalty"] = [dict(n=2000, p=70, k=5, sigma=0.0, setting=v, l1=v) for v in WEIGHTS]
#: Numbers of states that are assumed, where two are planted.
SCENARIOS["states"] = [dict(n=2000, p=70, k=5, sigma=0.0, setting=m, m=m) for m in (1, 2, 3, 4)]


def run_cell(cell: dict, rep: int, ids, methods=METHODS, m: int = 2, seed: int = 0, generator: str = "invariant") -> list[tuple]:
    """Metric rows (generator, scenario, setting, method, rep, metric, value) of one setting and repetition."""
    truth = plant_truth(m, cell["k"], cell["p"], seed + rep, construction=generator)
    x, true_states = draw(truth, ids[: cell["n"]], cell["sigma"], seed + rep)
    rows = []
    for name, (model, states) in fit_methods(x, np.asarray(ids[: cell["n"]]), cell.get("m", m), cell["k"], seed + rep, methods, cell.get("l1", L1)).items():
        rows += [(generator, cell["scenario"], float(cell["setting"]), name, rep, metric, v) for metric, v in score_model(model, states, truth, true_states).items()]
    return rows


METRICS = "generator string, scenario string, setting double, method string, rep int, metric string, value double"


def run_methods(spark: SparkSession, keys: DataFrame, id_column: str, scenarios=None, reps: int = 10, methods=METHODS, settings=None, generators=GENERATORS) -> DataFrame:
    """Metric rows of whole sweeps. Sample ids are the least of a key table's (as many as a setting has samples). ``scenarios``: all by default."""
    scenarios = tuple(SCENARIOS) if scenarios is None else scenarios
    cells = [(g, s, i, r) for g in generators for s in scenarios for i in range(len(SCENARIOS[s])) if settings is None or SCENARIOS[s][i]["setting"] in settings for r in range(reps)]
    most = max(SCENARIOS[s][i]["n"] for _, s, i, _ in cells)
    ids = np.array([r[0] for r in keys.select(F.col(id_column).cast("long")).orderBy(id_column).limit(most).collect()], dtype=np.int64)  # at most 2,000
    shared = spark.sparkContext.broadcast(ids)
    frame = spark.createDataFrame([(n, *c) for n, c in enumerate(cells)], "cell int, generator string, scenario string, i int, rep int").repartition(len(cells), "cell")

    def fit(key, pdf):
        import pandas as pd

        rows = []
        for g, s, i, rep in zip(pdf["generator"], pdf["scenario"], pdf["i"], pdf["rep"], strict=True):
            rows += run_cell(SCENARIOS[s][i] | {"scenario": s}, int(rep), shared.value, methods, generator=g)
        return pd.DataFrame(rows, columns=["generator", "scenario", "setting", "method", "rep", "metric", "value"])

    return frame.groupBy("cell").applyInPandas(fit, METRICS)


def distributed_cell(spark: SparkSession, keys: DataFrame, id_column: str, cell: dict, rep: int = 0, seed: int = 0, generator: str = "invariant", form: dict = MIXTURE) -> tuple[NetworkModel, DataFrame, Truth]:
    """The mixture on planted signals over the distributed path: model, scored samples, truth. ``form``: MIXTURE or PRINTED."""
    truth = plant_truth(2, cell["k"], cell["p"], seed + rep, construction=generator)
    ids = keys.select(F.col(id_column).cast("long").alias("sample_id")).orderBy("sample_id").limit(cell["n"])
    rows = plant_signals(ids, truth, cell["sigma"], seed + rep)
    rows = stage(rows)
    model = StateNetworkMixture(m=2, k=cell["k"], seed=seed + rep, **form).fit(rows)
    return model, model.transform(rows), truth


def language_workload(spark: SparkSession, sf_dir: str, m: int = 4, k: int = 5, **settings) -> tuple[NetworkModel, DataFrame]:
    """States of documents from standardised letter shares; the languages are the truth (positive control)."""
    rows = stage(signals.document_signals(spark, sf_dir))
    rows = signals.keep_variables(rows, signals.variance_mask(rows))
    rows = signals.standardize(rows)
    options = dict(density="residual", membership_update="disjoint", max_iter=15, n_restarts=3, seed=1, l1=0.02) | settings
    model = StateNetworkMixture(m=m, k=k, **options).fit(rows)
    return model, model.transform(rows)


def embedding_workload(spark: SparkSession, sf_dir: str, m: int = 10, k: int = 5, **settings) -> tuple[NetworkModel, DataFrame]:
    """States of embeddings against their labels, which second moments don't show (negative control)."""
    rows = signals.embedding_signals(spark, sf_dir)
    options = dict(density="residual", membership_update="disjoint", max_iter=6, seed=1, l1=0.02, l1_relative=True) | settings
    model = StateNetworkMixture(m=m, k=k, **options).fit(rows)
    return model, model.transform(rows)


def nation_workload(spark: SparkSession, sf_dir: str) -> tuple[NetworkModel, DataFrame]:
    """Nodes of nations from weekly revenue, against regions: independent by construction, so near chance."""
    long, p = signals.nation_week_long(spark, sf_dir)
    rows = signals.standardize(signals.densify(long, p))
    model = CoupledNetwork(5, 0.1, membership_update="disjoint", l1_relative=True).fit(rows)
    nation = spark.read.parquet(f"{sf_dir}/nation.parquet").select(F.col("n_nationkey").alias("var_id"), F.col("n_regionkey").alias("label"))
    pairs = model.assign_nodes(spark).join(nation, "var_id").select(F.col("node").alias("cluster"), "label", "var_id")
    return model, pairs


def grid_workload(spark: SparkSession, sf_dir: str, m: int = 2, k: int = 6, **settings):
    """Masked slice of a grid of variables over time, m = 2 and k = 6: model, links, nodes with variable lists."""
    from .estimators import report

    long, names = signals.part_grid_long(spark, sf_dir)
    rows = stage(signals.densify(long, names.count()))
    kept = signals.variance_mask(rows)
    rows = stage(signals.standardize(signals.keep_variables(rows, kept)))
    options = dict(density="residual", membership_update="disjoint", max_iter=10, seed=1, l1=0.1, l1_relative=True) | settings
    model = StateNetworkMixture(m=m, k=k, **options).fit(rows)
    where = spark.createDataFrame([(i, v) for i, v in enumerate(kept)], "new_id int, var_id int")
    variables = names.join(F.broadcast(where), "var_id").select(F.col("new_id").alias("var_id"), "name", "coord")  # one row a variable
    return (model, *report(spark, model, variables), variables)


def cohort_workload(spark: SparkSession, sf_dir: str, m: int = 2, k: int = 6, **settings) -> dict[int, NetworkModel]:
    """Two cohorts of documents (quality 1 and 0) fitted separately on letter shares of the same variables."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").join(labels, "doc_id")
    rows = stage(signals.letter_signals(docs, "doc_id", "quality"))
    rows = signals.standardize(signals.keep_variables(rows, signals.variance_mask(rows)))
    options = dict(density="residual", membership_update="disjoint", max_iter=10, seed=1, l1=0.1, l1_relative=True) | settings
    return {q: StateNetworkMixture(m=m, k=k, **options).fit(rows.filter(F.col("quality") == q)) for q in (1, 0)}


def cohort_nodes(spark: SparkSession, models: dict[int, NetworkModel]) -> DataFrame:
    """Variables by node in each cohort's state and in the other cohort's matched state: how nodes differ between cohorts.

    Rows (state, match, first_node, second_node, n); states are matched by their nodes' overlap, the first cohort is the greater key.
    """
    high, low = (models[q] for q in sorted(models, reverse=True))
    parts = []
    for j, other in enumerate(measures.align_states(high.params.w, low.params.w)):
        nodes = [(s, v, int(n)) for s, w in ((0, high.params.w[j]), (1, low.params.w[other])) for v, n in enumerate(w.argmax(axis=1))]
        table = measures.compare_nodes(spark.createDataFrame(nodes, "state int, var_id int, node int"), 0, 1)
        parts.append(table.select(F.lit(j).alias("state"), F.lit(other).alias("match"), "first_node", "second_node", "n"))
    out = parts[0]
    for more in parts[1:]:
        out = out.unionByName(more)
    return out


def node_maps(spark: SparkSession, model: NetworkModel, variables: DataFrame) -> DataFrame:
    """Where the nodes lie on the grid: (state, node, a, b, c, weight) of every variable, and how near its node's middle it is.

    ``variables``: var_id, name, coord. ``from_middle`` is the distance to the mean place of the node's variables.
    """
    from pyspark.sql import Window as W

    rows = model.membership(spark).join(F.broadcast(variables.select("var_id", "coord.*")), "var_id")  # one row a variable
    rows = rows.select("state", "node", "var_id", "a", "b", "c", F.element_at("weights", F.col("node") + 1).alias("weight"))
    own = W.partitionBy("state", "node")
    away = sum(((F.col(x) - F.avg(x).over(own)) * (F.col(x) - F.avg(x).over(own)) for x in ("a", "b", "c")), F.lit(0.0))
    return rows.withColumn("from_middle", F.sqrt(away))
