"""Registered queries that take the iterative estimators through a few steps from a stated start, beside the same steps in SQL.

All use every sample and every variable of the hourly event signals.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from .functions import membership as mem
from .functions import partition as part
from .functions.precision import joint_precision, sparse_precision
from .functions.states import Options, Params, m_step, solve_state
from .operators import estimators as est
from .operators import moments, topics
from .operators.model import NetworkModel
from .plans.unrolled import Steps
from .queries import BINS, bins_dense, query, r
from .sources.tables import load

# Starts of the unrolled estimators, for five variables, two states and two nodes.
W_START = np.array([[0.6, 0.1], [0.5, 0.2], [0.2, 0.7], [0.3, 0.4], [0.1, 0.5]])
W_OTHER = np.array([[0.2, 0.5], [0.6, 0.1], [0.1, 0.6], [0.5, 0.3], [0.4, 0.2]])
OMEGA = np.array([[1.5, -0.4], [-0.4, 2.0]])
CENTRES = np.array([[-1.5, 0.0, 0.5, 0.0, 0.0], [0.5, 1.5, 0.0, 0.0, -0.5], [0.5, -0.5, 0.0, 1.5, 0.5]])
FACTOR_F = np.array([[0.5, 0.4], [0.3, 0.6], [0.7, 0.2], [0.4, 0.4], [0.2, 0.8]])
FACTOR_G = np.array([[0.2, 0.7], [0.6, 0.3], [0.5, 0.5], [0.3, 0.6], [0.8, 0.1]])
L1 = 0.05
P = 5

#: Two zero-mean states over all variables.
FULL = Params(np.array([0.4, 0.6]), [np.eye(P)] * 2, [0.25 * np.eye(P) + 0.05, 0.8 * np.eye(P) - 0.05], np.ones(2), "projected")


def start(density: str) -> Params:
    return Params(np.array([0.45, 0.55]), [mem.unit_columns(W_START), mem.unit_columns(W_OTHER)], [np.linalg.inv(OMEGA), np.eye(2)], np.array([0.8, 1.2]), density)


def rows_of(spark, kinds, digits=3):
    """Rows (kind, state, i, j, value) of named lists of matrices, one a state."""
    out = [(kind, int(g), int(i), int(j), round(float(v), digits) + 0.0) for kind, ms in kinds.items() for g, m in enumerate(ms) for (i, j), v in np.ndenumerate(np.atleast_2d(m))]
    return spark.createDataFrame(out, "kind string, state int, i int, j int, value double")


def last(kinds: dict[str, str], digits=3) -> str:
    """The same rows from tables (g, i, j, v)."""
    return " UNION ALL ".join(f"SELECT '{kind}' AS kind, CAST(g AS INTEGER) AS state, CAST(i AS INTEGER) AS i, CAST(j AS INTEGER) AS j, round(v, {digits}) + 0.0 AS value FROM {t}" for kind, t in kinds.items())


def scalars(steps: Steps, t: str) -> str:
    return steps.add(f"SELECT g, 0 AS i, 0 AS j, v FROM {t}")


def moment(steps: Steps) -> str:
    return steps.add("SELECT 0 AS g, i, j, value AS v FROM ea")


# ---- the state mixture ------------------------------------------------------------------------------


def full_sql(steps: int):
    s = Steps(BINS)
    shares = s.add("SELECT * FROM (VALUES " + ", ".join(f"({j}, CAST({v} AS DOUBLE))" for j, v in enumerate(FULL.shares)) + ") t(g, v)")
    omega = s.constant(FULL.omega)
    z = None
    for t in range(steps + 1):
        logdet = s.inverse(omega, P)[1]
        z = s.full_density("ec", shares, omega, logdet, P)
        if t < steps:
            rr = s.posterior(z)
            shares = s.shares(rr)
            omega = s.inverse(s.weighted_moments("ec", rr), P)[0]
    return s, shares, omega, z


def full_fit(spark, d, steps):
    rows = bins_dense(spark, d)
    opt = Options(m=2, k=P, l1=0.0, density="projected", membership_update="frozen", refresh=(), guard=False)
    p, stats = FULL, moments.state_passes(rows, [FULL], [opt], True)[0]
    for _ in range(steps):
        p = m_step(stats, p, opt)
        stats = moments.state_passes(rows, [p], [opt], True)[0]
    return rows, p, stats


def full_params_sql(steps):
    s, shares, omega, _ = full_sql(steps)
    return s.text(last({"share": scalars(s, shares), "precision": omega}))


def step_e_sql():
    s, _, _, z = full_sql(0)
    return s.text(f"SELECT sample_id, round(r, 5) AS r0 FROM {s.posterior(z)} WHERE g = 0")


def nll_sql():
    s, _, _, z = full_sql(0)
    return s.text(f"SELECT round(-sum(t), 3) AS nll FROM (SELECT max(z) + ln(sum(exp(z - m))) AS t FROM (SELECT *, max(z) OVER (PARTITION BY sample_id) AS m FROM {z}) GROUP BY sample_id)")


@query(step_e_sql())
def mixture_step_e(spark, d):
    rows, p, s = full_fit(spark, d, 0)
    return NetworkModel(p, s.mass, s.nll).transform(rows).select("sample_id", r(F.col("r")[0], 5).alias("r0"))


@query(nll_sql())
def mixture_nll(spark, d):
    rows, p, s = full_fit(spark, d, 0)
    return spark.createDataFrame([(round(est.negative_log_likelihood(rows, NetworkModel(p, s.mass, s.nll)), 3),)], "nll double")


@query(full_params_sql(1))
def mixture_step_m(spark, d):
    _, p, _ = full_fit(spark, d, 1)
    return rows_of(spark, {"share": p.shares, "precision": p.omega})


@query(full_params_sql(3))
def mixture_unrolled_3(spark, d):
    _, p, _ = full_fit(spark, d, 3)
    return rows_of(spark, {"share": p.shares, "precision": p.omega})


@query(full_params_sql(1))
def stream_online_mixture(spark, d):
    """The model that follows a stream, after one micro-batch of all samples: one EM step from the stated start."""
    import uuid

    from .sources.staging import shared_dir
    from .streaming.streams import OnlineMixture

    folder = f"{shared_dir(spark)}/online-{uuid.uuid4().hex}"
    rows = bins_dense(spark, d)
    rows.coalesce(1).write.parquet(f"{folder}/in")
    online = OnlineMixture(Options(m=2, k=P, l1=0.0, density="projected", membership_update="frozen", refresh=(), guard=False), start_from=FULL)
    online.start(spark.readStream.schema(rows.schema).parquet(f"{folder}/in"), f"{folder}/log").awaitTermination()
    again = OnlineMixture(online.options, path=online.path)  # as after a restart: the state comes from its files
    again._resume(spark)
    return rows_of(spark, {"share": again.params.shares, "precision": again.params.omega})


def network_sql(steps, density, update, product=False):
    s = Steps(BINS)
    shares, w, omega, tau = s.mixture("ec", P, start(density), L1, steps, density, update, product)
    return s.text(last({"share": scalars(s, shares), "membership": w, "precision": s.unpair(omega), "tau": scalars(s, tau)}))


def network_fit(spark, d, steps, density, update, product=False):
    rows = bins_dense(spark, d)
    opt = Options(m=2, k=2, l1=L1, density=density, membership_update=update, moment_mode="signed" if product else "sign_split", inner_max_iter=1, max_overlap=1.1, refresh=(), strategy="product" if product else "gram")
    p = start(density)
    for _ in range(steps):
        p = m_step(moments.state_passes(rows, [p], [opt], not product)[0], p, opt)
    return rows_of(spark, {"share": p.shares, "membership": p.w, "precision": p.omega, "tau": p.tau})


@query(network_sql(2, "projected", "multiplicative"))
def printed_unrolled_2(spark, d):
    """The estimator as printed: projected density, multiplicative membership; two full iterations."""
    return network_fit(spark, d, 2, "projected", "multiplicative")


@query(network_sql(2, "residual", "multiplicative"))
def residual_unrolled_2(spark, d):
    return network_fit(spark, d, 2, "residual", "multiplicative")


@query(network_sql(3, "projected", "frozen"))
def known_nodes_unrolled_3(spark, d):
    return network_fit(spark, d, 3, "projected", "frozen")


@query(network_sql(2, "residual", "multiplicative", True))
def product_unrolled_2(spark, d):
    return network_fit(spark, d, 2, "residual", "multiplicative", True)


def density_parts():
    """Steps up to the log joint densities under the start of the residual density."""
    s = Steps(BINS)
    p = start("residual")
    shares = s.add(f"SELECT * FROM (VALUES (0, CAST({p.shares[0]} AS DOUBLE)), (1, CAST({p.shares[1]} AS DOUBLE))) t(g, v)")
    tau = s.add(f"SELECT * FROM (VALUES (0, CAST({p.tau[0]} AS DOUBLE)), (1, CAST({p.tau[1]} AS DOUBLE))) t(g, v)")
    return s, s.node_density("ec", shares, s.constant(p.w), s.pair(s.constant(p.omega)), tau, P)


def density_sql():
    s, z = density_parts()
    return s.text(f"SELECT sample_id, round(r, 5) AS r0 FROM {s.posterior(z)} WHERE g = 0")


@query(density_sql())
def residual_density_step(spark, d):
    return NetworkModel(start("residual"), np.ones(2), 0.0).transform(bins_dense(spark, d)).select("sample_id", r(F.col("r")[0], 5).alias("r0"))


def model_round_trip(spark, d):
    """A model saved in the shared folder and loaded again scores the samples alike."""
    import uuid

    from .sources.staging import shared_dir

    path = f"{shared_dir(spark)}/model-{uuid.uuid4().hex}"
    NetworkModel(start("residual"), np.ones(2), 0.0).save(spark, path)
    return NetworkModel.load(spark, path).transform(bins_dense(spark, d)).select("sample_id", r(F.col("r")[0], 5).alias("r0"))


query(density_sql())(model_round_trip)


# ---- single-state estimators and pipelines ----------------------------------------------------------


def coupled_rounds(a, w, rounds):
    opt = Options(m=1, k=2, l1=L1, density="projected", inner_max_iter=rounds, inner_tol=0.0, max_overlap=1.1)
    w, omega, _ = solve_state(a, w, np.eye(2), opt, L1)
    return w, omega


def coupled_sql():
    s = Steps(BINS)
    w, omega = s.coupled(moment(s), s.constant([mem.unit_columns(W_START)]), L1, 3)
    return s.text(last({"membership": w, "precision": s.unpair(omega)}))


@query(coupled_sql())
def coupled_unrolled_3(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    w, omega = coupled_rounds(a, mem.unit_columns(W_START), 3)
    return rows_of(spark, {"membership": [w], "precision": [omega]})


def tri_sql():
    s = Steps(BINS)
    w, mid = s.tri_factor(moment(s), s.constant([mem.unit_columns(W_START)]), 3)
    return s.text(last({"membership": w, "middle": mid}))


@query(tri_sql())
def trifactor_unrolled_3(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    w, mid, _ = part.tri_factor(a, 2, max_iter=3, tol=-np.inf, w=mem.unit_columns(W_START))
    return rows_of(spark, {"membership": [w], "middle": [mid]})


def factor_sql(symmetric):
    s = Steps(BINS)
    a = moment(s)
    if symmetric:
        return s.text(last({"factor": s.symmetric_factor(a, s.constant([FACTOR_F]), 3)}))
    f, g = s.factors(a, s.constant([FACTOR_F]), s.constant([FACTOR_G]), 3)
    return s.text(last({"first": f, "second": g}))


@query(factor_sql(False))
def nmf_unrolled_3(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    f, g, _ = part.nmf(a, 2, max_iter=3, tol=-np.inf, start=(FACTOR_F, FACTOR_G))
    return rows_of(spark, {"first": [f], "second": [g]})


@query(factor_sql(True))
def symmetric_nmf_unrolled_3(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    f, _ = part.symmetric_nmf(a, 2, max_iter=3, tol=-1.0, start=FACTOR_F)
    return rows_of(spark, {"factor": [f]})


def groups_sql():
    s = Steps(BINS)
    near, _ = s.lloyd("ec", CENTRES, 3)
    return s, near


def groups_found(spark, d):
    """Moments of the groups that three Lloyd steps from the stated centres give."""
    rows = bins_dense(spark, d)
    grouped, _ = est.lloyd(rows, CENTRES, 3)
    return [a for a, _ in moments.grouped_moments(grouped, len(CENTRES))]


def lloyd_sql():
    s = Steps(BINS)
    _, c = s.lloyd("ec", CENTRES, 2)
    return s.text(f"SELECT CAST(i AS INTEGER) AS state, CAST(j AS INTEGER) AS var_id, round(v, 5) AS value FROM {c}")


@query(lloyd_sql())
def kmeans_lloyd_3(spark, d):
    _, centres = est.lloyd(bins_dense(spark, d), CENTRES, 3)
    return spark.createDataFrame([(int(i), int(j), round(float(v), 5) + 0.0) for (i, j), v in np.ndenumerate(centres)], "state int, var_id int, value double")


def kmeans_coupled_sql():
    s, near = groups_sql()
    a = s.grouped_moments("ec", near)
    w, omega = s.coupled(a, s.constant([mem.unit_columns(W_START)] * len(CENTRES)), L1, 2)
    return s.text(last({"membership": w, "precision": s.unpair(omega)}))


@query(kmeans_coupled_sql())
def kmeans_coupled_unrolled(spark, d):
    fits = [coupled_rounds(a, mem.unit_columns(W_START), 2) for a in groups_found(spark, d)]
    return rows_of(spark, {"membership": [w for w, _ in fits], "precision": [o for _, o in fits]})


def kmeans_tri_sql():
    s, near = groups_sql()
    w, mid = s.tri_factor(s.grouped_moments("ec", near), s.constant([mem.unit_columns(W_START)] * len(CENTRES)), 2)
    return s.text(last({"membership": w, "middle": mid}))


@query(kmeans_tri_sql())
def kmeans_trifactor_unrolled(spark, d):
    fits = [part.tri_factor(a, 2, max_iter=2, tol=-np.inf, w=mem.unit_columns(W_START)) for a in groups_found(spark, d)]
    return rows_of(spark, {"membership": [f[0] for f in fits], "middle": [f[1] for f in fits]})


def node_groups(spark, d):
    w = mem.unit_columns(W_START)
    return [w.T @ a @ w for a in groups_found(spark, d)]


def joint_sql(coupled):
    s, near = groups_sql()
    m = s.node_moment(s.constant([mem.unit_columns(W_START)] * len(CENTRES)), s.grouped_moments("ec", near))
    if not coupled:
        return s.text(last({"precision": s.unpair(s.node_precision(m, L1))}))
    single = s.add(f"SELECT g, i, j, CASE WHEN i = j THEN 1 / (v + CAST({L1} AS DOUBLE)) ELSE 0 END AS v FROM {m}")
    return s.text(last({"precision": single}))


@query(joint_sql(False))
def joint_precision_apart(spark, d):
    """Joint precision of the k-means groups without a coupling penalty: each group's own closed form."""
    return rows_of(spark, {"precision": joint_precision(node_groups(spark, d), L1, 0.0, "group", tol=1e-10, max_iter=20_000)})


@query(joint_sql(True))
def joint_precision_shared_zeros(spark, d):
    """With a group penalty at the norm over groups of an entry's excess, the entry is zero in all groups."""
    s = node_groups(spark, d)
    excess = float(np.sqrt(sum(max(abs(x[0, 1]) - L1, 0.0) ** 2 for x in s)))
    return rows_of(spark, {"precision": joint_precision(s, L1, excess * 1.001 + 1e-6, "group", tol=1e-10, max_iter=20_000)})


@query(joint_sql(False))
def joint_precision_fused_apart(spark, d):
    return rows_of(spark, {"precision": joint_precision(node_groups(spark, d), L1, 0.0, "fused", tol=1e-10, max_iter=20_000)})


# ---- sparse precision of many variables: the conditions of an optimum, one column by SQL -----------------


def precision_sql():
    s = Steps(BINS)
    a = moment(s)
    top = s.add(f"SELECT max(abs(v)) AS v FROM {a} WHERE i < j")
    # the single strongest pair is linked at a weight just under its moment; all else stays apart
    second = s.add(f"SELECT max(abs(v)) AS v FROM {a} WHERE i < j AND abs(v) < (SELECT v FROM {top})")
    l1 = s.add(f"SELECT (t.v + q.v) / 2 AS v FROM {top} t, {second} q")
    held = s.add(f"SELECT x.g, x.i, x.j, CASE WHEN x.i = x.j THEN x.v + l.v ELSE sign(x.v) * greatest(abs(x.v) - l.v, 0) END AS v FROM {a} x, {l1} l")
    return s.text(last({"precision": s.inverse(held, P)[0]}, 4))


@query(precision_sql())
def glasso_one_link(spark, d):
    """Between the two strongest moments only one pair is linked: its block has the closed form, all else is diagonal."""
    a, _ = moments.gram(bins_dense(spark, d))
    off = np.sort(np.unique(np.abs(a[np.triu_indices(P, 1)])))
    return rows_of(spark, {"precision": [sparse_precision(a, float(off[-1] + off[-2]) / 2, tol=1e-12, max_iter=5000)]}, 4)


# ---- mixture of topics ------------------------------------------------------------------------------


def topic_start(m=4, terms=26):
    """Term probabilities of each topic: one letter in m is three times as likely."""
    theta = np.array([[3.0 if t % m == j else 1.0 for t in range(terms)] for j in range(m)])
    return theta / theta.sum(axis=1, keepdims=True)


def topic_sql(steps=2, m=4, terms=26, smooth=0.5):
    s = Steps("""l AS (SELECT unnest(string_split('abcdefghijklmnopqrstuvwxyz', '')) AS c, generate_subscripts(string_split('abcdefghijklmnopqrstuvwxyz', ''), 1) - 1 AS term),
bag AS MATERIALIZED (SELECT doc_id, lang, CAST(term AS INTEGER) AS term, length(lower(text)) - length(replace(lower(text), c, '')) AS n FROM documents CROSS JOIN l)""")
    bag = s.add("SELECT * FROM bag WHERE n > 0")
    theta = s.constant([topic_start(m, terms)])  # i: topic, j: term
    shares = s.add(f"SELECT CAST(range AS INTEGER) AS g, CAST({1 / m} AS DOUBLE) AS v FROM range({m})")
    for t in range(steps + 1):
        z = s.add(f"SELECT b.doc_id AS sample_id, t.i AS g, max(ln(s.v)) + sum(b.n * ln(t.v)) AS z FROM {bag} b JOIN {theta} t ON t.j = b.term JOIN {shares} s ON s.g = t.i GROUP BY 1, 2")
        rr = s.posterior(z)
        if t < steps:
            shares = s.shares(rr)
            sums = s.add(f"SELECT r.g AS i, x.range AS j, sum(CASE WHEN b.term = x.range THEN b.n * r.r ELSE 0 END) + CAST({smooth} AS DOUBLE) AS v FROM {bag} b JOIN {rr} r ON r.sample_id = b.doc_id CROSS JOIN range({terms}) x GROUP BY 1, 2")
            theta = s.add(f"SELECT 0 AS g, i, j, v / sum(v) OVER (PARTITION BY i) AS v FROM {sums}")
    best = s.add(f"SELECT sample_id, arg_max(g, z) AS g FROM {rr} GROUP BY 1")
    return s.text(f"SELECT CAST(b.g AS INTEGER) AS state, d.lang AS lang, count(*) AS n FROM {best} b JOIN documents d ON d.doc_id = b.sample_id GROUP BY 1, 2")


@query(topic_sql())
def topic_unrolled_2(spark, d):
    docs = load(spark, d, "documents", "doc_id", "text", "lang")
    _, _, states = topics.topic_mixture(topics.letter_bag(docs), 4, 26, max_iter=2, theta=topic_start())
    return states.join(docs.select("doc_id", "lang"), "doc_id").groupBy("state", "lang").agg(F.count("*").alias("n"))
