"""The estimators: the state mixture, its single-state and known-node forms, and the baselines."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import partition as part
from ..functions.numeric import symmetric, unit_columns
from ..functions.precision import joint_precision, sparse_precision
from ..functions.states import Fit, Options, Params, Stats, coupled_fit, fit_loop
from ..plans.planner import choose_strategy, moment_mode_for
from ..sources.staging import stage, unstage
from . import moments
from .model import NetworkModel


class StateNetworkMixture:
    """EM over hidden states, each with its own nodes (membership) and links (sparse node precision).

    One distributed pass per iteration, shared by all restarts; matrix algebra is local. See
    :class:`Options` for the settings. ``fit`` takes signals (sample_id, x array<double>).
    """

    def __init__(self, m: int = 2, k: int = 5, l1: float = 0.02, **settings):
        self.options = Options(m=m, k=k, l1=l1, **settings)
        self.w0 = None

    def fit(self, signals: DataFrame, n: int | None = None) -> NetworkModel:
        """The model of least loss over the restarts. Signals that are neither cached nor a plain scan are staged first.

        ``n``: number of samples, if known, for the choice of a strategy.
        """
        opt = self.options
        if opt.init == "kmeans" and opt.m > 1:
            signals = kmeans_groups(signals.select("sample_id", "x"), opt.m, opt.seed).withColumnRenamed("state", "start_state")
        given = signals
        signals = stage(signals.select("sample_id", "x", *[c for c in signals.columns if c == "start_state"])) if opt.stage else signals
        p = moments.assert_uniform_length(signals)
        strategy = opt.strategy if opt.strategy != "auto" else choose_strategy(n, p, opt.k, opt.m, opt.moment_mode)
        mode = moment_mode_for(strategy, opt.moment_mode)
        opts = [Options(**{**opt.__dict__, "seed": opt.seed + i, "strategy": strategy, "moment_mode": mode}) for i in range(max(1, opt.n_restarts))]
        rows = moments.few_tasks(signals, p if strategy == "gram" else 0)
        w0 = self.w0
        if strategy == "product" and w0 is None:
            label = part.kmeans(moments.sketch(rows, p, seed=opt.seed), opt.k, opt.seed)[0]
            w0 = unit_columns(part.indicators(label, opt.k) + opt.offset)
        fits = _stacked(rows, opts, w0)
        if signals is not given and not given.is_cached and opt.stage:
            unstage(signals)
        best = min(fits, key=lambda f: f.loss)
        return NetworkModel(best.params, best.mass, best.loss, best.trace, {k: (list(v) if isinstance(v, tuple) else v) for k, v in opt.__dict__.items()} | {"p": p, "strategy": strategy, "moment_mode": mode})


def _stacked(signals: DataFrame, opts: list[Options], w0) -> list[Fit]:
    """Run the loops of all restarts in step, one Spark pass serving all that wait for one."""
    import threading

    n = len(opts)
    lock = threading.Condition()
    waiting: dict[int, tuple] = {}
    answers: dict[int, Stats | Exception] = {}
    active = set(range(n))

    def ask(i):
        def run(params, gram, begin):
            with lock:
                waiting[i] = (params, gram, begin)
                lock.notify_all()
                while i not in answers:
                    lock.wait()
                got = answers.pop(i)
            if isinstance(got, Exception):
                raise got
            return got

        return run

    def loop(i):
        try:
            return fit_loop(ask(i), opts[i], w0)
        finally:
            with lock:
                active.discard(i)
                lock.notify_all()

    with ThreadPoolExecutor(n) as pool:
        futures = [pool.submit(loop, i) for i in range(n)]
        while True:
            with lock:
                while active and set(waiting) != active:
                    lock.wait()
                if not active:
                    break
                due = dict(waiting)
                waiting.clear()
            try:
                got: dict[int, Stats | Exception] = {}
                for gram, begin in {x[1:] for x in due.values()}:
                    own = [i for i, x in due.items() if x[1:] == (gram, begin)]
                    for i, s in zip(own, moments.state_passes(signals, [due[i][0] for i in own], [opts[i] for i in own], gram, begin, False), strict=True):
                        got[i] = s
            except Exception as e:  # handed to the loops, which raise it
                got = dict.fromkeys(due, e)
            with lock:
                answers.update(got)
                lock.notify_all()
        return [f.result() for f in futures]


class KnownNodeMixture(StateNetworkMixture):
    """Mixture graphical lasso on given nodes: the membership W (p x k) stays as it is."""

    def __init__(self, w, m: int = 2, l1: float = 0.02, **settings):
        w = unit_columns(np.asarray(w, dtype=float))
        super().__init__(m=m, k=w.shape[1], l1=l1, membership_update="frozen", **settings)
        self.w0 = w


class ZeroMeanMixture(KnownNodeMixture):
    """Gaussian mixture with means fixed at zero: identity membership, no penalty."""

    def __init__(self, m: int, p: int, **settings):
        super().__init__(np.eye(p), m=m, l1=settings.pop("l1", 0.0), density="projected", **settings)


def gaussian_mixture(signals: DataFrame, m: int, seed: int = 0, max_iter: int = 50):
    """Spark's free-mean Gaussian mixture, for comparison; its model and the samples' states."""
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.functions import array_to_vector

    vectors = signals.select("sample_id", array_to_vector("x").alias("features"))
    model = GaussianMixture(k=m, seed=seed, maxIter=max_iter).fit(vectors)
    return model, model.transform(vectors).select("sample_id", F.col("prediction").alias("state"))


class CoupledNetwork:
    """Single-state estimator: one moment pass, then membership and precision together."""

    def __init__(self, k: int = 5, l1: float = 0.02, **settings):
        self.options = Options(m=1, k=k, l1=l1, **settings)

    def fit(self, signals: DataFrame) -> NetworkModel:
        a, n = moments.gram(signals)
        return self.fit_moment(a, n)

    def fit_moment(self, a, n: int = 1) -> NetworkModel:
        w, omega, tau, trace = coupled_fit(a, self.options)
        return NetworkModel(Params(np.ones(1), [w], [omega], np.array([tau]), self.options.density), np.array([float(n)]), trace[-1][2], [(t, ph, v, 0.0, o) for t, ph, v, o in trace], {"method": "coupled"})


class OrthoTriFactor:
    """Orthogonal tri-factorisation of the absolute moment; links by a threshold on its scaled middle factor."""

    def __init__(self, k: int = 5, seed: int = 0, threshold: float = 0.1):
        self.k, self.seed, self.threshold = k, seed, threshold

    def fit(self, signals: DataFrame) -> NetworkModel:
        a, n = moments.gram(signals)
        return self.fit_moment(a, n)

    def fit_moment(self, a, n: int = 1) -> NetworkModel:
        w, s, errors = part.tri_factor(a, self.k, self.seed)
        d = np.sqrt(np.maximum(np.diag(s), 1e-300))
        c = s / np.outer(d, d)
        linked = np.where((c > self.threshold) | np.eye(self.k, dtype=bool), c, 0.0)
        # -c off the diagonal, so that "nonzero off-diagonal" reads as a link and partial_corr as c
        omega = 2 * np.eye(self.k) * np.diag(linked) - linked
        return NetworkModel(Params(np.ones(1), [w], [omega], np.ones(1), "projected"), np.array([float(n)]), errors[-1], [(t, "trifactor", e, 0.0, 0.0) for t, e in enumerate(errors)], {"method": "trifactor"})


class SparsePrecision:
    """Graphical lasso on the variables themselves; solved apart on the components of |S_ab| > l1."""

    def __init__(self, l1: float = 0.1, penalize_diagonal: bool = True):
        self.l1, self.penalize_diagonal = l1, penalize_diagonal

    def fit(self, signals: DataFrame, block: int = 512) -> DataFrame:
        """Rows (state, a, b, value) of the nonzero precision; one task per component.

        The moment stays in tiles on the executors. The driver streams the pairs above l1 and keeps one number a variable (the
        components); a task holds its component's block.
        """
        tiles = stage(moments.tiled_gram(signals, block), "moment-tiles")
        spark, l1, diag = signals.sparkSession, self.l1, self.penalize_diagonal

        def cells(keep):
            """Cells (i, j, v), i <= j, that ``keep(i, j, v)`` marks."""

            def run(batches):
                import pyarrow as pa

                for batch in batches:
                    for bi, bj, rows, cols, v in zip(*(batch.column(n).to_pylist() for n in range(4)), batch.column(4), strict=True):
                        v = v.values.to_numpy().reshape(rows, cols)
                        i, j = np.broadcast_arrays(bi * block + np.arange(rows)[:, None], bj * block + np.arange(cols)[None, :])
                        on = keep(i, j, v) & (i <= j)
                        yield pa.RecordBatch.from_arrays([pa.array(i[on].astype(np.int32)), pa.array(j[on].astype(np.int32)), pa.array(v[on])], names=["i", "j", "v"])

            return tiles.mapInArrow(run, "i int, j int, v double")

        root: dict[int, int] = {}

        def find(a: int) -> int:
            while root.setdefault(a, a) != a:
                root[a] = root[root[a]]
                a = root[a]
            return a

        for r in cells(lambda i, j, v: (np.abs(v) > l1) | (i == j)).select("i", "j").toLocalIterator():
            a, b = find(r["i"]), find(r["j"])
            root[max(a, b)] = min(a, b)
        component = np.array([find(a) for a in range(len(root))], dtype=np.int32)
        shared = spark.sparkContext.broadcast(component)  # one number a variable
        inside = cells(lambda i, j, v: shared.value[i] == shared.value[j])
        labels = F.pandas_udf(lambda i: pd.Series(shared.value[i.to_numpy()]), "int")

        def solve(key, pdf):
            own = np.unique(pdf["i"].to_numpy())
            at = np.searchsorted(own, pdf["i"].to_numpy()), np.searchsorted(own, pdf["j"].to_numpy())
            s = np.zeros((len(own), len(own)))
            s[at] = pdf["v"].to_numpy()
            s[at[::-1]] = pdf["v"].to_numpy()
            p = sparse_precision(s, l1, diag)
            i, j = np.nonzero(p)
            return pd.DataFrame({"state": np.zeros(len(i), dtype=np.int32), "a": own[i].astype(np.int32), "b": own[j].astype(np.int32), "value": p[i, j]})

        return inside.withColumn("component", labels("i")).groupBy("component").applyInPandas(solve, "state int, a int, b int, value double")


def kmeans_groups(signals: DataFrame, m: int, seed: int = 0) -> DataFrame:
    """Signals with state: the nearest of m centres (Spark's k-means)."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    vectors = signals.drop("state").withColumn("features", array_to_vector("x"))
    model = KMeans(k=m, seed=seed).fit(vectors.select("features"))
    return model.transform(vectors).withColumnRenamed("prediction", "state").drop("features")


def nearest(x: str, centres) -> Column:
    """Number of the centre nearest to the array column; ties to the first."""
    far = lambda c: F.aggregate(F.zip_with(x, F.array(*[F.lit(float(v)) for v in c]), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    dist = F.array(*[far(c) for c in centres])
    return (F.array_position(dist, F.array_min(dist)) - 1).cast("int")


def lloyd(signals: DataFrame, centres, steps: int) -> tuple[DataFrame, np.ndarray]:
    """k-means from given centres: signals with ``state`` after so many steps, and the centres then (an empty one stays).

    One aggregate a step; the driver gets one row for each centre and variable.
    """
    centres = np.array(centres, dtype=float)
    for _ in range(steps):
        sums = signals.select(nearest("x", centres).alias("state"), F.posexplode("x").alias("v", "value")).groupBy("state", "v").agg(F.avg("value").alias("mean"))
        for row in sums.collect():
            centres[row["state"], row["v"]] = row["mean"]
    return signals.withColumn("state", nearest("x", centres)), centres


def two_stage(kind: str, signals: DataFrame, m: int, k: int, l1: float = 0.02, l2: float = 0.05, seed: int = 0, penalty: str = "group", **settings) -> tuple[NetworkModel, DataFrame]:
    """k-means of samples into states, then ``coupled``, ``trifactor`` or ``joint`` per state; (model, sample states)."""
    grouped = kmeans_groups(signals, m, seed)
    return two_stage_moments(kind, moments.grouped_moments(grouped, m), k, l1, l2, seed, penalty, **settings), grouped.select("sample_id", "state")


def two_stage_moments(kind, found, k, l1=0.02, l2=0.05, seed=0, penalty="group", **settings) -> NetworkModel:
    """Second stage from the groups' moments [(A_j, n_j)]."""
    mass = np.array([float(n) for _, n in found])
    shares = mass / max(mass.sum(), 1.0)
    if kind == "joint":
        total = sum(a * n for a, n in found) / max(mass.sum(), 1.0)
        w = unit_columns(part.indicators(part.kmeans_variables(total, k, seed), k))
        s = [symmetric(w.T @ a @ w) for a, _ in found]
        scale = float(np.mean([np.trace(x) / k for x in s])) if settings.get("l1_relative") else 1.0
        omega = joint_precision([x / scale for x in s], l1, l2, penalty) / scale
        return NetworkModel(Params(shares, [w] * len(found), list(omega), np.ones(len(found)), "projected"), mass, float("nan"), [], {"method": "kmeans+joint"})
    make = (lambda a, n: CoupledNetwork(k, l1, seed=seed, **settings).fit_moment(a, n)) if kind == "coupled" else (lambda a, n: OrthoTriFactor(k, seed).fit_moment(a, n))
    fits = [make(a, n) for a, n in found]
    params = Params(shares, [f.params.w[0] for f in fits], [f.params.omega[0] for f in fits], np.array([f.params.tau[0] for f in fits]), fits[0].params.density)
    return NetworkModel(params, mass, float(sum(f.loss for f in fits)), [], {"method": f"kmeans+{kind}"})


def alternating_two_objective(a, k: int, l1: float, seed: int = 0, rounds: int = 20, w=None, tol: float = 1e-6):
    """Node and link objectives in turn, each on its own loss: sparse precision on the present nodes, then a factorisation
    step of |A| whose middle factor is the covariance that the links imply. Returns W and the precision on it."""
    w = part.init_membership(a, k, seed=seed) if w is None else w
    size = np.abs(a)
    for _ in range(rounds):
        omega = sparse_precision(symmetric(w.T @ a @ w), l1, jitter=1e-10)
        aws = size @ w @ np.abs(np.linalg.inv(omega))
        new = unit_columns(w * np.sqrt(aws / np.maximum(w @ (w.T @ aws), 1e-12)))
        moved, w = np.abs(new - w).max(), new
        if moved < tol:
            break
    return w, sparse_precision(symmetric(w.T @ a @ w), l1, jitter=1e-10)


def contiguous_trifactor(a, k: int, neighbours, weight: float = 0.5, seed: int = 0, max_iter: int = 100, start=None):
    """Tri-factor nodes with a penalty on membership differing between grid neighbours [(i, j), ...]; ``start``: W and S."""
    near = np.zeros_like(a)
    for i, j in neighbours:
        near[i, j] = near[j, i] = 1.0
    near /= np.maximum(near.sum(axis=1, keepdims=True), 1.0)
    w, s = start if start is not None else part.tri_factor(a, k, seed)[:2]
    pull = weight * np.abs(a).mean()
    for _ in range(max_iter):
        aws = np.abs(a) @ w @ s
        # neighbours' weights enter the numerator, the variable's own the denominator
        w = unit_columns(w * np.sqrt((aws + pull * near @ w) / np.maximum(w @ (w.T @ aws) + pull * w, 1e-12)))
        s = np.maximum(w.T @ np.abs(a) @ w, 0.0)
    return w, s


def atlas_membership(mapping: DataFrame, p: int, k: int) -> np.ndarray:
    """Unit-column indicators of a fixed map (var_id, node)."""
    label = np.zeros(p, dtype=int)
    for r in mapping.select("var_id", "node").collect():  # one row a variable
        label[r["var_id"]] = r["node"]
    return unit_columns(part.indicators(label, k))


def select_model(signals: DataFrame, ms, ks, criterion: str = "bic", l1: float = 0.02, held_out: int = 5, **settings) -> DataFrame:
    """Rows (m, k, loss, parameters, score) over a grid: ``bic`` or ``heldout`` loss per sample (every ``held_out``-th id)."""
    spark = signals.sparkSession
    inside, outside = signals, signals
    if criterion == "heldout":
        inside, outside = signals.filter(F.pmod(F.xxhash64("sample_id"), F.lit(held_out)) != 0), signals.filter(F.pmod(F.xxhash64("sample_id"), F.lit(held_out)) == 0)
    rows = []
    for m in ms:
        for k in ks:
            model = StateNetworkMixture(m=m, k=k, l1=l1, **settings).fit(inside)
            size = m - 1 + sum(int((w > 1e-6).sum()) for w in model.params.w) + sum(int((np.triu(np.abs(o)) > 1e-10).sum()) for o in model.params.omega) + m
            n = float(model.mass.sum())
            if criterion == "heldout":
                r = model.transform(outside).agg(F.avg("loglik")).first()[0]
                score = -float(r)
            else:
                score = 2 * model.loss + size * float(np.log(max(n, 1.0)))
            rows.append((m, k, float(model.loss), size, score))
    return spark.createDataFrame(rows, "m int, k int, loss double, parameters int, score double")


def negative_log_likelihood(signals: DataFrame, model: NetworkModel) -> float:
    return -float(model.transform(signals).agg(F.sum("loglik")).first()[0])


def report(spark: SparkSession, model: NetworkModel, variables: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Links, and per state and node the list of its variables (names, if a dictionary is given)."""
    nodes = model.assign_nodes(spark)
    if variables is not None:
        nodes = nodes.join(variables.select("var_id", "name"), "var_id")
    else:
        nodes = nodes.withColumn("name", F.col("var_id").cast("string"))
    return model.edges(spark), nodes.groupBy("state", "node").agg(F.count("*").alias("size"), F.array_sort(F.collect_list("name")).alias("variables"))
