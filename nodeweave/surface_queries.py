"""Registered queries of measures, recovery on planted data, reports, files, SQL functions and the wider relational surface."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from .functions import membership as mem
from .functions import partition as part
from .functions.precision import two_node_precision
from .functions.states import Options
from .operators import estimators as est
from .operators import experiments as exp
from .operators import measures, moments, relops
from .operators import signals as sig
from .operators.model import NetworkModel
from .plans.unrolled import Steps
from .queries import BINS, NATION_WEEK, SOFT, bins_dense, nation_dense, planted_rows, query, r
from .sources.planted import plant_signals, plant_truth
from .sources.staging import shared_dir, stage
from .sources.tables import load, read_signals, write_signals
from .unrolled_queries import L1, P, W_START, last, moment, rows_of, start

# ---- planted truth, recovered ------------------------------------------------------------------------


def matched(model: NetworkModel, truth, scored):
    """For each true state the found one, and for each found node the true one."""
    table = np.zeros((truth.m, model.m))
    for row in scored.groupBy("state", "state_hat").count().collect():  # states x states rows
        table[row["state"], row["state_hat"]] = row["count"]
    states = measures.assignment(table)
    names = []
    for j, found in enumerate(states):
        overlap = np.zeros((truth.k, truth.k))
        np.add.at(overlap, (model.params.w[found].argmax(axis=1), truth.node[j]), 1.0)
        names.append(measures.assignment(overlap))
    return states, names


def values(rows) -> str:
    return ", ".join("(" + ", ".join(map(str, row)) + ")" for row in rows)


def truth_nodes_sql(m):
    t = plant_truth(m, 5, 70, 0)
    return f"SELECT CAST(s AS INTEGER) AS state, CAST(v AS INTEGER) AS var_id, CAST(n AS INTEGER) AS node FROM (VALUES {values((j, v, int(n)) for j in range(m) for v, n in enumerate(t.node[j]))}) t(s, v, n)"


def truth_edges_sql(m):
    t = plant_truth(m, 5, 70, 0)
    return f"SELECT CAST(s AS INTEGER) AS state, CAST(a AS INTEGER) AS a, CAST(b AS INTEGER) AS b FROM (VALUES {values((j, a, b) for j in range(m) for a, b in sorted(t.links[j]))}) t(s, a, b)"


def recovered(spark, d):
    truth = plant_truth(2, 5, 70, 0)
    rows = stage(planted_rows(spark, d))
    model = est.StateNetworkMixture(2, 5, **exp.MIXTURE).fit(rows)
    return truth, model, *matched(model, truth, model.transform(rows))


@query(truth_nodes_sql(2))
def planted_nodes_recovered(spark, d):
    """The nodes of every state that the mixture finds are those that were planted (variable by variable)."""
    truth, model, states, names = recovered(spark, d)
    return spark.createDataFrame([(j, v, int(names[j][n])) for j, found in enumerate(states) for v, n in enumerate(model.params.w[found].argmax(axis=1))], "state int, var_id int, node int")


def single_rows(spark, d):
    truth = plant_truth(1, 5, 70, 0)
    ids = load(spark, d, "events", "event_id").select(F.col("event_id").alias("sample_id"))
    return truth, moments.gram(plant_signals(ids, truth))[0]


def grouped_nodes(spark, truth, label):
    overlap = np.zeros((truth.k, truth.k))
    np.add.at(overlap, (label, truth.node[0]), 1.0)
    name = measures.assignment(overlap)
    return spark.createDataFrame([(0, v, int(name[n])) for v, n in enumerate(label)], "state int, var_id int, node int")


@query(truth_nodes_sql(1))
def nodes_by_kmeans(spark, d):
    """k-means of variables finds the nodes of data with one state."""
    truth, a = single_rows(spark, d)
    return grouped_nodes(spark, truth, part.kmeans_variables(a, 5))


@query(truth_nodes_sql(1))
def nodes_by_spectral_clustering(spark, d):
    truth, a = single_rows(spark, d)
    return grouped_nodes(spark, truth, part.spectral_nodes(a, 5))


@query(truth_nodes_sql(1))
def nodes_by_trifactor(spark, d):
    truth, a = single_rows(spark, d)
    return grouped_nodes(spark, truth, part.tri_factor(a, 5)[0].argmax(axis=1))


@query(truth_nodes_sql(1))
def nodes_by_coupled_estimator(spark, d):
    truth, a = single_rows(spark, d)
    return grouped_nodes(spark, truth, est.CoupledNetwork(5, exp.L1, membership_update="disjoint", l1_relative=True).fit_moment(a).params.w[0].argmax(axis=1))


# ---- loss, choice of a model, start ------------------------------------------------------------------


@query("SELECT CAST(range AS INTEGER) AS iter, false AS rose FROM range(12)")
def loss_never_rises(spark, d):
    """With nodes given and a penalty of fixed weight, the penalised loss falls in every iteration."""
    rows = bins_dense(spark, d)
    model = est.KnownNodeMixture(W_START, 2, 0.05, penalty_scale="global", density="projected", refresh=(), max_iter=12, tol=-1.0, stage=True).fit(rows)
    return model.fit_trace(spark).select("iter", F.coalesce(F.col("rel_change") < -1e-9, F.lit(False)).alias("rose"))


@query("SELECT CAST(m AS INTEGER) AS m, CAST(k AS INTEGER) AS k, true AS holds FROM (VALUES (1, 2), (1, 3), (2, 2), (2, 3)) t(m, k)")
def model_choice(spark, d):
    """The grid's scores are twice the loss and the logarithm of the samples for each parameter."""
    rows = stage(bins_dense(spark, d))
    n = rows.count()
    grid = est.select_model(rows, (1, 2), (2, 3), l1=0.05, max_iter=4)
    return grid.select("m", "k", (F.abs(F.col("score") - 2 * F.col("loss") - F.col("parameters") * float(np.log(n))) < 1e-6).alias("holds"))


@query(f"""WITH w AS (SELECT n_nationkey AS var_id, k.range AS node, CASE WHEN n_regionkey = k.range THEN 1 ELSE 0 END + 2e-1 AS v FROM nation CROSS JOIN range(5) k)
SELECT CAST(var_id AS INTEGER) AS var_id, CAST(node AS INTEGER) AS node, round(v / sqrt(sum(v * v) OVER (PARTITION BY node)), 6) AS weight FROM w""")
def membership_start(spark, d):
    """Indicators of a grouping plus the offset, in unit columns."""
    rows = load(spark, d, "nation", "n_nationkey", "n_regionkey").orderBy("n_nationkey").collect()  # 25 rows
    w = part.offset_membership(np.array([x["n_regionkey"] for x in rows]), 5)
    return spark.createDataFrame([(i, j, round(float(v), 6)) for (i, j), v in np.ndenumerate(w)], "var_id int, node int, weight double")


@query("""WITH c AS (SELECT event_type, count(*) AS n, CAST(count(DISTINCT user_id) AS INTEGER) AS p, 5 AS k, 2 AS m, 8 AS tasks FROM events GROUP BY 1),
s AS (SELECT *, CAST(n AS DOUBLE) AS dn, CAST(p AS DOUBLE) AS dp FROM c)
SELECT event_type, CAST(n AS BIGINT) AS n, p, 'gram' AS strategy, 2 * dn * dp * dp * m + 2 * dn * m * (dp * k + k * k) AS flops, 4 * greatest(m - 1, 1) * dp * (dp + 1) AS task_bytes, 4 * tasks * greatest(m - 1, 1) * dp * (dp + 1) AS shuffle_bytes, p <= 5000 AS chosen FROM s
UNION ALL SELECT event_type, CAST(n AS BIGINT), p, 'product', 4 * dn * dp * k * m, 8 * m * dp * k, 8 * tasks * m * dp * k, p > 5000 FROM s""")
def pass_costs(spark, d):
    """Work, memory and shuffle of one pass over each type's events as samples of its users, under each strategy, and which one the planner takes."""
    from .plans.planner import choose_strategy, pass_cost

    k, m, tasks, rows = 5, 2, 8, []
    sizes = load(spark, d, "events", "event_type", "user_id").groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("p"))
    for kind, n, p in sizes.collect():  # a row a type
        for strategy in ("gram", "product"):
            c = pass_cost(n, p, k, m, tasks, strategy)
            rows.append((kind, n, p, strategy, float(c["flops"]), float(c["task_bytes"]), float(c["shuffle_bytes"]), choose_strategy(n, p, k, m) == strategy))
    return spark.createDataFrame(rows, "event_type string, n long, p int, strategy string, flops double, task_bytes double, shuffle_bytes double, chosen boolean")


# ---- described baselines, unrolled -------------------------------------------------------------------

CHAIN = [(i, i + 1) for i in range(P - 1)]


def alternating_sql(rounds=3):
    s = Steps(BINS)
    a = moment(s)
    size, w = s.map(a, "abs(v)"), s.constant([mem.unit_columns(W_START)])
    for _ in range(rounds):
        implied = s.map(s.unpair(s.inverse_pair(s.node_precision(s.node_moment(w, a), L1))), "abs(v)")
        aws = s.product(s.product(size, w), implied)
        w = s.unit_columns(s.cells(w, s.cells(aws, s.product(w, s.product(w, aws, first=True)), "sqrt(x.v / greatest(y.v, 1e-12))"), "x.v * y.v"))
    return s.text(last({"membership": w, "precision": s.unpair(s.node_precision(s.node_moment(w, a), L1))}))


@query(alternating_sql())
def alternating_unrolled_3(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    w, omega = est.alternating_two_objective(a, 2, L1, rounds=3, w=mem.unit_columns(W_START), tol=-1.0)
    return rows_of(spark, {"membership": [w], "precision": [omega]})


def contiguous_sql(rounds=3, weight=0.5):
    s = Steps(BINS)
    a = s.map(moment(s), "abs(v)")
    near = np.zeros((P, P))
    for i, j in CHAIN:
        near[i, j] = near[j, i] = 1.0
    near = s.constant([near / near.sum(axis=1, keepdims=True)])
    pull = s.add(f"SELECT CAST({weight} AS DOUBLE) * avg(v) AS v FROM {a}")
    w, mid = s.constant([mem.unit_columns(W_START)]), s.constant([np.array([[1.0, 0.2], [0.2, 1.0]])])
    for _ in range(rounds):
        aws = s.product(s.product(a, w), mid)
        over = s.cells(aws, s.product(near, w), f"x.v + (SELECT v FROM {pull}) * y.v")
        under = s.cells(s.product(w, s.product(w, aws, first=True)), w, f"x.v + (SELECT v FROM {pull}) * y.v")
        w = s.unit_columns(s.cells(w, s.cells(over, under, "sqrt(x.v / greatest(y.v, 1e-12))"), "x.v * y.v"))
        mid = s.map(s.node_moment(w, a), "greatest(v, 0)")
    return s.text(last({"membership": w, "middle": mid}))


@query(contiguous_sql())
def contiguous_unrolled_3(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    w, mid = est.contiguous_trifactor(a, 2, CHAIN, max_iter=3, start=(mem.unit_columns(W_START), np.array([[1.0, 0.2], [0.2, 1.0]])))
    return rows_of(spark, {"membership": [w], "middle": [mid]})


# ---- measures and contrasts --------------------------------------------------------------------------


def orders_of_four() -> str:
    from itertools import permutations

    return ", ".join("(" + ", ".join(map(str, p)) + ")" for p in permutations(range(4)))


@query(f"""WITH p AS (SELECT event_id % 4 AS cluster, (event_id // 4 + CASE WHEN value > 60 THEN 1 ELSE 0 END + event_id % 4) % 4 AS label FROM events),
c AS (SELECT cluster, label, count(*) AS n FROM p GROUP BY 1, 2), o AS (SELECT row_number() OVER () AS i, * FROM (VALUES {orders_of_four()}) t(a, b, c, d)),
m AS (SELECT i, 0 AS cluster, a AS label FROM o UNION ALL SELECT i, 1, b FROM o UNION ALL SELECT i, 2, c FROM o UNION ALL SELECT i, 3, d FROM o),
g AS (SELECT i, sum(coalesce(n, 0)) AS gain FROM m LEFT JOIN c USING (cluster, label) GROUP BY 1)
SELECT CAST(max(gain) AS BIGINT) AS gain FROM g""")
def align_labels(spark, d):
    """The one-to-one matching of clusters and labels has the greatest overlap of all orders."""
    ev = load(spark, d, "events", "event_id", "value")
    cluster = F.col("event_id") % 4
    label = (F.floor(F.col("event_id") / 4) + F.when(F.col("value") > 60, 1).otherwise(0) + cluster) % 4
    pairs = ev.select(cluster.cast("int").alias("cluster"), label.cast("int").alias("label"))
    best = measures.align(pairs, 4)
    n = {(x["cluster"], x["label"]): x["n"] for x in measures.contingency(pairs).collect()}  # at most 16 rows
    return spark.createDataFrame([(int(sum(n.get((i, int(j)), 0) for i, j in enumerate(best))),)], "gain long")


@query("SELECT CAST(n_regionkey AS INTEGER) AS first_node, CAST(n_nationkey % 4 AS INTEGER) AS second_node, count(*) AS n FROM nation GROUP BY 1, 2")
def node_contrast(spark, d):
    n = load(spark, d, "nation", "n_nationkey", "n_regionkey").withColumn("var_id", F.col("n_nationkey"))
    rows = n.select(F.lit(0).alias("state"), "var_id", F.col("n_regionkey").cast("int").alias("node")).unionByName(n.select(F.lit(1).alias("state"), "var_id", (F.col("n_nationkey") % 4).cast("int").alias("node")))
    return measures.compare_nodes(rows, 0, 1)


def top_sql():
    s = Steps(BINS)
    soft = s.add(f"SELECT sample_id, g.range AS g, CASE WHEN {SOFT.format(id='sample_id', seed=3, m=2)} = g.range THEN CAST(0.9 AS DOUBLE) ELSE CAST(0.1 AS DOUBLE) END AS r FROM (SELECT DISTINCT sample_id FROM ec) CROSS JOIN range(2) g")
    w, a = s.constant(start("projected").w), s.weighted_moments("ec", soft)
    w = s.membership(w, a, s.unpair(s.node_precision(s.node_moment(w, a), L1)))
    node = s.add(f"SELECT g, i, j, v FROM {w} QUALIFY row_number() OVER (PARTITION BY g, i ORDER BY v DESC, j) = 1")
    return s.text(f"SELECT CAST(g AS INTEGER) AS state, CAST(j AS INTEGER) AS node, CAST(i AS INTEGER) AS var_id, round(v, 6) AS weight, CAST(row_number() OVER (PARTITION BY g, j ORDER BY v DESC, i) AS INTEGER) AS rank FROM {node} QUALIFY rank <= 2")


@query(top_sql())
def top_variables(spark, d):
    """The event types of largest weight in each node of each state, after one step from the stated start on the moments of the soft states."""
    s = moments.state_passes(bins_dense(spark, d), [None], [Options(m=2, k=2, seed=3)], True)[0]
    model = NetworkModel(start("projected"), s.mass, 0.0)
    p = model.params
    for j, w in enumerate(p.w):
        a = s.gram[j] / s.mass[j]
        p.omega[j] = two_node_precision(w.T @ a @ w, L1)
        p.w[j] = mem.update_membership(w, a, p.omega[j])
    return relops.top_variables(model.membership(spark), 2).select("state", "node", "var_id", r("weight").alias("weight"), "rank")


@query()
def cohort_nodes(spark, d):
    """How the nodes of two cohorts differ, state by matched state."""
    return exp.cohort_nodes(spark, exp.cohort_workload(spark, d))


@query()
def grid_maps(spark, d):
    """Place on the grid of every variable of every node and state."""
    model, _, _, variables = exp.grid_workload(spark, d)
    return exp.node_maps(spark, model, variables)


# ---- relational surface ------------------------------------------------------------------------------


@query("""WITH c AS (SELECT range AS v, range // 10 AS a, range % 10 AS b FROM range(250))
SELECT CAST(x.v AS INTEGER) AS i, CAST(y.v AS INTEGER) AS j FROM c x JOIN c y ON (y.a = x.a + 1 AND y.b = x.b) OR (y.a = x.a AND y.b = x.b + 1)""")
def grid_neighbours(spark, d):
    return relops.neighbours(sig.part_grid_long(spark, d)[1])


@query("SELECT o_orderkey, o_orderstatus, CAST(ntile(4) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey) AS INTEGER) AS bucket FROM orders")
def quantile_buckets(spark, d):
    return relops.quantile_buckets(load(spark, d, "orders", "o_orderkey", "o_orderstatus"), 4, "o_orderkey", "o_orderstatus")


@query("SELECT source, lang, count(*) AS n FROM documents GROUP BY ROLLUP (source, lang)")
def contingency_rollup(spark, d):
    return relops.rollup_report(load(spark, d, "documents", "source", "lang"), "source", "lang")


@query("""SELECT l_returnflag, round(covar_pop(l_quantity, l_extendedprice), 2) AS covariance, round(corr(l_quantity, l_extendedprice), 6) AS correlation, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope,
round(regr_intercept(l_extendedprice, l_quantity), 2) AS intercept, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2 FROM lineitem GROUP BY 1""")
def pair_statistics(spark, d):
    rows = relops.pair_statistics(load(spark, d, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice"), "l_quantity", "l_extendedprice", "l_returnflag")
    return rows.withColumns({c: r(c, n) for c, n in (("covariance", 2), ("correlation", 6), ("slope", 4), ("intercept", 2), ("r2", 6))})


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def approximate_profile(spark, d):
    """Approximate aggregates stay near the exact ones: distinct users within 15 %, the median within a twentieth of the range."""
    ev = load(spark, d, "events", "event_type", "user_id", "value")
    users = relops.approximate_profile(ev, "user_id", "event_type")
    exact = ev.groupBy("event_type").agg(F.countDistinct("user_id").alias("u"), F.median("value").alias("m"), (F.max("value") - F.min("value")).alias("w"))
    value = relops.approximate_profile(ev, "value", "event_type").select("event_type", F.col("quartiles")[1].alias("q"), F.size("histogram").alias("bins"))
    near = (F.abs(F.col("distinct") - F.col("u")) <= 0.15 * F.col("u")) & (F.abs(F.col("q") - F.col("m")) <= 0.05 * F.col("w")) & (F.col("bins") > 0)
    return users.join(exact, "event_type").join(value, "event_type").select("event_type", near.alias("near"))


@query(f"""WITH {NATION_WEEK}, u AS (SELECT var_id % 3 AS unit, sample_id AS step, var_id, value FROM nw), k AS (SELECT DISTINCT unit, step FROM u),
n AS (SELECT unit, step, row_number() OVER (ORDER BY unit, step) - 1 AS sample_id FROM k)
SELECT unit, step, CAST(n.sample_id AS BIGINT) AS sample_id, var_id, round(value, 4) AS value FROM u JOIN n USING (unit, step)""")
def units_in_a_row(spark, d):
    """Samples of several units numbered one after the other."""
    rows = sig.with_units(sig.nation_week_long(spark, d)[0], F.col("var_id") % 3)
    return rows.select("unit", "step", F.col("sample_id").cast("long").alias("sample_id"), "var_id", r("value", 4).alias("value"))


# ---- files, SQL functions ----------------------------------------------------------------------------


@query(f"WITH {BINS} SELECT f.fmt, sample_id, var_id, round(value, 5) AS value FROM ec CROSS JOIN (VALUES ('parquet'), ('orc'), ('json')) f(fmt)")
def signal_files(spark, d):
    """Signals written to and read from each format."""
    import uuid

    rows, folder, out = stage(bins_dense(spark, d)), f"{shared_dir(spark)}/files-{uuid.uuid4().hex}", None
    for fmt in ("parquet", "orc", "json"):
        write_signals(rows, f"{folder}/{fmt}", fmt=fmt)
        got = sig.to_long(read_signals(spark, f"{folder}/{fmt}", fmt)).select(F.lit(fmt).alias("fmt"), "sample_id", "var_id", r("value", 5).alias("value"))
        out = got if out is None else out.unionByName(got)
    return out


def scored_sql():
    from .unrolled_queries import density_parts

    s, z = density_parts()
    best = s.add(f"SELECT sample_id, max(r) AS top, arg_max(g, r) AS g FROM {s.posterior(z)} GROUP BY 1")
    return s.text(f"SELECT sample_id, CAST(g AS INTEGER) AS state FROM {best} WHERE top >= CAST(0.6 AS DOUBLE)")


@query(scored_sql())
def sql_scores(spark, d):
    """The registered function score_states in SQL, over the view of signals."""
    from .plans import sql

    sql.register(spark, NetworkModel(start("residual"), np.ones(2), 0.0), bins_dense(spark, d))
    return sql.scored(spark, 0.6).select("sample_id", F.col("state").cast("int").alias("state"))


@query(f"""WITH {BINS}, h AS (SELECT sample_id % 3 AS part, * FROM ec)
SELECT CAST(a.part AS BIGINT) AS part, CAST(a.var_id * {P} + b.var_id AS INTEGER) AS cell, round(sum(a.value * b.value) / count(*), 6) AS value FROM h a JOIN h b USING (sample_id) GROUP BY 1, 2""")
def sql_moments(spark, d):
    """The registered aggregate moment_udaf in SQL, by group."""
    from .plans import sql

    sql.register_moments(spark)
    bins_dense(spark, d).createOrReplaceTempView("moment_signals")
    rows = spark.sql("SELECT sample_id % 3 AS part, moment_udaf(x) AS m FROM moment_signals GROUP BY 1")
    return rows.select("part", F.posexplode("m").alias("cell", "value")).select("part", "cell", r("value").alias("value"))


@query(f"WITH {BINS} SELECT i AS a, j AS b, round(value, 6) AS value FROM ea WHERE i <= j")
def sql_pairs(spark, d):
    """The registered table function pairs in SQL, averaged."""
    from .plans import sql

    sql.register_moments(spark)
    bins_dense(spark, d).createOrReplaceTempView("pair_signals")
    rows = spark.sql("SELECT p.a, p.b, avg(p.value) AS value FROM pair_signals s, LATERAL pairs(s.x) p GROUP BY 1, 2")
    return rows.select("a", "b", r("value").alias("value"))
