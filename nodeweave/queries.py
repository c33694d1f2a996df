"""Registered queries of the network estimators and, where SQL can express them, their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import membership as mem
from .functions.precision import optimality_residual, sparse_precision
from .functions.states import Params
from .operators import estimators as est
from .operators import experiments as exp
from .operators import measures, moments, relops, topics
from .operators import signals as sig
from .operators.model import NetworkModel, edges_from_precision
from .sources.tables import load
from .streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Register the function under its name, with its SQL if there is one."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def r(column, digits=6):
    return F.round(column, digits) + F.lit(0.0)  # no negative zero


# ---- shared SQL -------------------------------------------------------------------------------

NATION_WEEK = """nw AS (
  SELECT CAST(date_diff('day', DATE '1991-12-30', CAST(date_trunc('week', l_shipdate) AS DATE)) // 7 AS BIGINT) AS sample_id,
         c_nationkey AS var_id, sum(l_extendedprice * (1 - l_discount)) AS value
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2
), nwd AS (
  SELECT s.sample_id, CAST(v.range AS INTEGER) AS var_id, coalesce(nw.value, CAST(0 AS DOUBLE)) AS value
  FROM (SELECT DISTINCT sample_id FROM nw) s CROSS JOIN range(25) v
  LEFT JOIN nw ON nw.sample_id = s.sample_id AND nw.var_id = v.range
), nst AS (
  SELECT var_id, avg(value) AS m, stddev_pop(value) AS s FROM nwd GROUP BY 1
), nz AS (
  SELECT sample_id, var_id, (value - m) / s AS value FROM nwd JOIN nst USING (var_id)
)"""
# hourly sums of event values: clicks etc. as variables in name order, scaled to hundreds
BINS = """ev AS (
  SELECT CAST(date_diff('second', TIMESTAMP '2024-01-01 00:00:00', ts) // 3600 AS BIGINT) AS sample_id, event_type, sum(value) AS value
  FROM events GROUP BY 1, 2
), kinds AS (SELECT event_type, CAST(row_number() OVER (ORDER BY event_type) - 1 AS INTEGER) AS var_id FROM (SELECT DISTINCT event_type FROM events)
), eb AS (
  SELECT s.sample_id, k.var_id, coalesce(ev.value, CAST(0 AS DOUBLE)) / 100 AS value
  FROM (SELECT DISTINCT sample_id FROM ev) s CROSS JOIN kinds k
  LEFT JOIN ev ON ev.sample_id = s.sample_id AND ev.event_type = k.event_type
), em AS (SELECT var_id, avg(value) AS m FROM eb GROUP BY 1
), ec AS (SELECT sample_id, var_id, value - m AS value FROM eb JOIN em USING (var_id)
), ea AS (SELECT a.var_id AS i, b.var_id AS j, sum(a.value * b.value) / count(*) AS value FROM ec a JOIN ec b USING (sample_id) GROUP BY 1, 2
)"""
SOFT = "((({id} % 2147483648) * 2654435761 + {seed} * 40503) % 4294967296) // 65536 % {m}"


def nation_dense(spark, d):
    long, p = sig.nation_week_long(spark, d)
    return sig.densify(long, p)


def bins_dense(spark, d, variables=None):
    """Centred hourly event sums in hundreds; optionally the first variables only."""
    rows, _ = sig.event_bin_signals(spark, d)
    rows = rows.withColumn("x", F.transform("x", lambda v: v / 100))
    rows = sig.standardize(rows, scale=False)
    return rows if variables is None else rows.withColumn("x", F.slice("x", 1, variables))


def matrix_frame(spark, a, names=("i", "j"), digits=6):
    a = np.asarray(a)
    rows = [(int(i), int(j), round(float(a[i, j]), digits) + 0.0) for i in range(a.shape[0]) for j in range(a.shape[1])]
    return spark.createDataFrame(rows, f"{names[0]} int, {names[1]} int, value double")


# ---- signals ----------------------------------------------------------------------------------


@query(f"WITH {NATION_WEEK} SELECT sample_id, var_id, round(value, 5) AS value FROM nw")
def signals_nation_week(spark, d):
    return sig.nation_week_long(spark, d)[0].select("sample_id", "var_id", r("value", 5).alias("value"))


@query(f"WITH {BINS} SELECT sample_id, event_type, round(value, 4) AS value FROM ev")
def signals_event_bins(spark, d):
    return sig.event_bin_long(spark, d)[0].select("sample_id", "event_type", r("value", 4).alias("value"))


@query(f"""WITH l AS (SELECT unnest(string_split('{sig.LETTERS}', '')) AS c, generate_subscripts(string_split('{sig.LETTERS}', ''), 1) - 1 AS v),
t AS (SELECT doc_id, lower(text) AS low FROM documents),
n AS (SELECT doc_id, CAST(v AS INTEGER) AS var_id, length(low) - length(replace(low, c, '')) AS n FROM t CROSS JOIN l),
s AS (SELECT doc_id, sum(n) AS total FROM n GROUP BY 1)
SELECT doc_id AS sample_id, var_id, round(CAST(n AS DOUBLE) / CAST(total AS DOUBLE), 6) AS value FROM n JOIN s USING (doc_id) WHERE total > 50""")
def signals_letters(spark, d):
    return sig.to_long(sig.document_signals(spark, d)).select("sample_id", "var_id", r("value").alias("value"))


def letters_sql(table: str, sample: str, text: str, extra: str = "") -> str:
    """Shares of letters of a table's texts, long."""
    return f"""WITH l AS (SELECT unnest(string_split('{sig.LETTERS}', '')) AS c, generate_subscripts(string_split('{sig.LETTERS}', ''), 1) - 1 AS v),
t AS (SELECT {sample} AS id, lower({text}) AS low{extra} FROM {table}),
n AS (SELECT t.*, CAST(v AS INTEGER) AS var_id, length(low) - length(replace(low, c, '')) AS n FROM t CROSS JOIN l),
s AS (SELECT *, sum(n) OVER (PARTITION BY id) AS total FROM n)
SELECT CAST(id AS BIGINT) AS sample_id, var_id, round(CAST(n AS DOUBLE) / CAST(total AS DOUBLE), 6) AS value{', role' if extra else ''} FROM s WHERE total > 50"""


@query(letters_sql("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')"))
def signals_letters_pages(spark, d):
    return sig.to_long(sig.page_signals(spark, d)).select("sample_id", "var_id", r("value").alias("value"))


@query(letters_sql("conversations", "conv_id * 1048576 + turn", "text", ", role"))
def signals_letters_conversations(spark, d):
    return sig.conversation_signals(spark, d).select("sample_id", "role", F.posexplode("x").alias("var_id", "value")).select("sample_id", "var_id", r("value").alias("value"), "role")


@query(letters_sql("benchmark", "item_id", "text"))
def signals_letters_benchmark(spark, d):
    return sig.to_long(sig.benchmark_signals(spark, d)).select("sample_id", "var_id", r("value").alias("value"))


@query("""SELECT vec_id AS sample_id, CAST(generate_subscripts(embedding, 1) - 1 AS INTEGER) AS var_id, CAST(unnest(embedding) AS DOUBLE) AS value FROM embeddings""")
def signals_embedding_long(spark, d):
    return sig.embedding_long(spark, d)[0]


@query("""WITH t AS (SELECT min(p_type) AS t FROM part), c AS (
  SELECT p_partkey, (CAST(regexp_extract(p_brand, '(\\d+)$', 1) AS INTEGER) - 1) * 10 + (p_size - 1) // 5 AS var_id FROM part, t WHERE p_type = t.t)
SELECT CAST(((year(l_shipdate) - 1992) * 12 + month(l_shipdate) - 1) * 26 + ascii(l_returnflag) - 65 AS BIGINT) AS sample_id,
  CAST(var_id AS INTEGER) AS var_id, round(sum(l_extendedprice * (1 - l_discount)), 5) AS value
FROM lineitem JOIN c ON l_partkey = p_partkey GROUP BY 1, 2""")
def signals_part_grid(spark, d):
    return sig.part_grid_long(spark, d)[0].select(F.col("sample_id").cast("long").alias("sample_id"), "var_id", r("value", 5).alias("value"))


@query("""SELECT CAST((year(l_shipdate) - 1992) * 12 + month(l_shipdate) - 1 AS BIGINT) AS sample_id, CAST(regexp_extract(p_brand, '(\\d+)$', 1) AS INTEGER) - 1 AS var_id,
  round(sum(l_extendedprice * (1 - l_discount)), 5) AS value FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2""")
def signals_brand_month(spark, d):
    return sig.brand_month_long(spark, d)[0].select(F.col("sample_id").cast("long").alias("sample_id"), "var_id", r("value", 5).alias("value"))


@query("""SELECT CAST((year(l_shipdate) - 1992) * 12 + month(l_shipdate) - 1 AS BIGINT) AS sample_id, s_nationkey AS var_id, round(sum(l_quantity), 5) AS value
FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2""")
def signals_supplier_nation(spark, d):
    return sig.supplier_nation_long(spark, d)[0].select(F.col("sample_id").cast("long").alias("sample_id"), "var_id", r("value", 5).alias("value"))


@query("""SELECT CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS BIGINT) AS sample_id, CAST(user_id % 150 AS INTEGER) AS var_id, round(sum(value), 4) AS value FROM events GROUP BY 1, 2""")
def signals_user_day(spark, d):
    return sig.user_day_long(spark, d)[0].select("sample_id", "var_id", r("value", 4).alias("value"))


@query(f"WITH {NATION_WEEK} SELECT var_id, count(*) AS n, round(avg(value), 2) AS mean, round(var_pop(value) / 1e6, 2) AS variance FROM nw GROUP BY 1")
def variable_stats(spark, d):
    return sig.variable_stats(sig.nation_week_long(spark, d)[0]).select("var_id", "n", r("mean", 2).alias("mean"), r(F.col("variance") / 1e6, 2).alias("variance"))


@query(f"""WITH l AS (SELECT unnest(string_split('{sig.LETTERS}', '')) AS c, generate_subscripts(string_split('{sig.LETTERS}', ''), 1) - 1 AS v),
t AS (SELECT doc_id, lower(text) AS low FROM documents),
n AS (SELECT doc_id, CAST(v AS INTEGER) AS var_id, length(low) - length(replace(low, c, '')) AS n FROM t CROSS JOIN l),
s AS (SELECT doc_id, sum(n) AS total FROM n GROUP BY 1)
SELECT var_id FROM n JOIN s USING (doc_id) WHERE total > 50 GROUP BY 1 HAVING max(n) > 0""")
def variance_mask(spark, d):
    return spark.createDataFrame([(int(v),) for v in sig.variance_mask(sig.document_signals(spark, d))], "var_id int")


@query(f"WITH {NATION_WEEK} SELECT sample_id, var_id, round(value, 5) AS value FROM nz")
def standardize(spark, d):
    return sig.to_long(sig.standardize(nation_dense(spark, d))).select("sample_id", "var_id", r("value", 5).alias("value"))


# ---- moments ----------------------------------------------------------------------------------


@query("""WITH e AS (SELECT vec_id, generate_subscripts(embedding, 1) - 1 AS v, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings),
n AS (SELECT count(*) AS n FROM embeddings)
SELECT CAST(a.v AS INTEGER) AS i, CAST(b.v AS INTEGER) AS j, round(sum(a.x * b.x) / max(n.n), 6) AS value FROM e a JOIN e b USING (vec_id), n GROUP BY 1, 2""")
def second_moment_embedding(spark, d):
    return matrix_frame(spark, moments.gram(sig.embedding_signals(spark, d))[0])


@query(f"WITH {BINS} SELECT i, j, round(value, 6) AS value FROM ea WHERE i <= j")
def second_moment_sql(spark, d):
    return moments.sql_gram(moments.long_form(bins_dense(spark, d))).select("i", "j", r("value").alias("value"))


@query(f"WITH {BINS} SELECT i, j, round(value, 6) AS value FROM ea")
def second_moment_tiled(spark, d):
    tiles = moments.tiled_gram(bins_dense(spark, d), 2)
    full = tiles.select("bi", "bj", "cols", F.posexplode("v").alias("at", "value"))
    i, j = (F.col("bi") * 2 + F.floor(F.col("at") / F.col("cols"))).cast("int"), (F.col("bj") * 2 + F.col("at") % F.col("cols")).cast("int")
    upper = full.select(i.alias("i"), j.alias("j"), "value", "bi", "bj")
    both = upper.select("i", "j", "value").unionByName(upper.filter("bi <> bj").select(F.col("j").alias("i"), F.col("i").alias("j"), "value"))
    return both.select("i", "j", r("value").alias("value"))


@query(f"WITH {NATION_WEEK} SELECT a.var_id AS i, b.var_id AS j, round(corr(a.value, b.value), 6) AS value FROM nwd a JOIN nwd b ON a.sample_id = b.sample_id AND a.var_id < b.var_id GROUP BY 1, 2")
def correlation_nations(spark, d):
    a, _ = moments.gram(sig.standardize(nation_dense(spark, d)))
    return matrix_frame(spark, a).filter("i < j")


@query(f"WITH {BINS} SELECT i, j, round(abs(value), 6) AS value FROM ea")
def absolute_moment(spark, d):
    return matrix_frame(spark, moments.gram(bins_dense(spark, d), "absolute")[0])


@query(f"WITH {BINS} SELECT i, j, round(greatest(value, 0), 6) AS plus, round(greatest(-value, 0), 6) AS minus FROM ea")
def sign_split_moment(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    rows = matrix_frame(spark, a, digits=12)
    return rows.select("i", "j", r(F.greatest("value", F.lit(0.0))).alias("plus"), r(F.greatest(-F.col("value"), F.lit(0.0))).alias("minus"))


@query(f"SELECT event_id AS sample_id, CAST({SOFT.format(id='event_id', seed=7, m=3)} AS INTEGER) AS state FROM events")
def init_soft_states(spark, d):
    mix = F.pmod(F.pmod(F.col("event_id"), F.lit(2147483648)) * 2654435761 + 7 * 40503, F.lit(4294967296))
    return load(spark, d, "events", "event_id").select(F.col("event_id").alias("sample_id"), F.pmod(F.floor(mix / 65536), F.lit(3)).cast("int").alias("state"))


@query(f"""WITH s AS (SELECT CAST({SOFT.format(id='event_id', seed=7, m=3)} AS INTEGER) AS c FROM events)
SELECT CAST(j.range AS INTEGER) AS state, round(avg(CASE WHEN c = j.range THEN CAST(0.9 AS DOUBLE) ELSE CAST(0.05 AS DOUBLE) END), 6) AS share FROM s CROSS JOIN range(3) j GROUP BY 1""")
def state_shares(spark, d):
    soft = init_soft_states(spark, d)
    each = F.explode(F.transform(F.sequence(F.lit(0), F.lit(2)), lambda j: F.struct(j.alias("state"), F.when(F.col("state") == j, 0.9).otherwise(0.05).alias("v"))))
    return soft.select(each.alias("e")).groupBy("e.state").agg(r(F.avg("e.v")).alias("share"))


@query(f"""WITH {BINS}, w AS (SELECT sample_id, CASE WHEN {SOFT.format(id='sample_id', seed=3, m=2)} = 0 THEN CAST(0.9 AS DOUBLE) ELSE CAST(0.1 AS DOUBLE) END AS r0 FROM (SELECT DISTINCT sample_id FROM ec)),
ws AS (SELECT sample_id, CAST(j.range AS INTEGER) AS state, CASE WHEN j.range = 0 THEN r0 ELSE 1 - r0 END AS r FROM w CROSS JOIN range(2) j)
SELECT state, a.var_id AS i, b.var_id AS j, round(sum(r * a.value * b.value) / sum(r), 6) AS value FROM ws JOIN ec a USING (sample_id) JOIN ec b USING (sample_id) GROUP BY 1, 2, 3""")
def weighted_moment(spark, d):
    from .functions.states import Options

    s = moments.state_passes(bins_dense(spark, d), [None], [Options(m=2, k=2, seed=3)], True)[0]
    out = [matrix_frame(spark, s.gram[j] / s.mass[j]).withColumn("state", F.lit(j)) for j in range(2)]
    return out[0].unionByName(out[1]).select("state", "i", "j", "value")


def atlas(spark, d):
    mapping = load(spark, d, "nation", "n_nationkey", "n_regionkey").select(F.col("n_nationkey").alias("var_id"), F.col("n_regionkey").alias("node"))
    return est.atlas_membership(mapping, 25, 5)


@query(f"WITH {NATION_WEEK} SELECT sample_id, n_regionkey AS node, round(sum(value) / sqrt(5e0), 4) AS y FROM nz JOIN nation ON n_nationkey = var_id GROUP BY 1, 2")
def project_nodes_atlas(spark, d):
    model = NetworkModel(Params(np.ones(1), [atlas(spark, d)], [np.eye(5)], np.ones(1)), np.ones(1), 0.0)
    y = model.project(sig.standardize(nation_dense(spark, d)))
    return y.select("sample_id", F.posexplode(F.col("y")[0]).alias("node", "y")).select("sample_id", "node", r("y", 4).alias("y"))


NODE_SQL = f"""WITH {NATION_WEEK}, y AS (SELECT sample_id, n_regionkey AS node, sum(value) / sqrt(5e0) AS y FROM nz JOIN nation ON n_nationkey = var_id GROUP BY 1, 2)
SELECT a.node AS i, b.node AS j, round(sum(a.y * b.y) / count(*), 6) AS value FROM y a JOIN y b USING (sample_id) GROUP BY 1, 2"""


@query(NODE_SQL)
def node_covariance(spark, d):
    a, _ = moments.gram(sig.standardize(nation_dense(spark, d)))
    w = atlas(spark, d)
    return matrix_frame(spark, w.T @ a @ w)


@query(f"""WITH {NATION_WEEK}, a AS (SELECT a.var_id AS i, b.var_id AS j, abs(sum(a.value * b.value) / count(*)) AS v FROM nz a JOIN nz b USING (sample_id) GROUP BY 1, 2)
SELECT p.n_regionkey AS i, q.n_regionkey AS j, round(sum(v) / 5, 6) AS value FROM a JOIN nation p ON p.n_nationkey = i JOIN nation q ON q.n_nationkey = j GROUP BY 1, 2""")
def trifactor_middle(spark, d):
    a, _ = moments.gram(sig.standardize(nation_dense(spark, d)), "absolute")
    w = atlas(spark, d)
    return matrix_frame(spark, w.T @ a @ w)


# ---- precision --------------------------------------------------------------------------------

PAIR = f"""WITH {BINS}, s AS (SELECT max(CASE WHEN i = 0 AND j = 0 THEN value END) AS s00, max(CASE WHEN i = 1 AND j = 1 THEN value END) AS s11, max(CASE WHEN i = 0 AND j = 1 THEN value END) AS s01 FROM ea)"""


@query(f"""{PAIR}, w AS (SELECT s00 + 1e-2 AS a, s11 + 1e-2 AS b, sign(s01) * greatest(abs(s01) - 1e-2, 0) AS c FROM s)
SELECT 0 AS i, 0 AS j, round(b / (a * b - c * c), 5) AS value FROM w UNION ALL SELECT 1, 1, round(a / (a * b - c * c), 5) FROM w
UNION ALL SELECT 0, 1, round(-c / (a * b - c * c), 5) + 0.0 FROM w UNION ALL SELECT 1, 0, round(-c / (a * b - c * c), 5) + 0.0 FROM w""")
def glasso_two_nodes(spark, d):
    a, _ = moments.gram(bins_dense(spark, d, 2))
    return matrix_frame(spark, sparse_precision(a, 0.01, tol=1e-12, max_iter=5000), digits=5)


@query(f"""WITH {BINS}, l AS (SELECT max(abs(value)) AS l FROM ea WHERE i <> j)
SELECT i, round(1 / (value + l), 6) AS value FROM ea, l WHERE i = j""")
def glasso_diagonal_regime(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    top = float(np.abs(a - np.diag(np.diag(a))).max())
    return matrix_frame(spark, sparse_precision(a, top)).filter("i = j").select("i", "value")


@query("SELECT CAST(l.v AS DOUBLE) AS l1, CAST(0 AS DOUBLE) AS violation FROM (VALUES (0.01), (0.05), (0.2)) l(v)")
def glasso_optimality_residual(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    return spark.createDataFrame([(l1, round(optimality_residual(sparse_precision(a, l1), a, l1), 5) + 0.0) for l1 in (0.01, 0.05, 0.2)], "l1 double, violation double")


def sparse_precision_variables(spark, d):
    return est.SparsePrecision(0.1).fit(sig.standardize(nation_dense(spark, d)))


QUERIES["sparse_precision_variables"] = sparse_precision_variables


# ---- membership rule, on all variables ------------------------------------------------------------

W5 = np.array([[0.6, 0.1], [0.5, 0.2], [0.2, 0.7], [0.3, 0.4], [0.1, 0.5]])
O2 = np.array([[1.5, -0.4], [-0.4, 2.0]])
RULE = f"""WITH {BINS}, w(i, k, v) AS (VALUES {', '.join(f'({i}, {k}, {W5[i, k]}e0)' for i in range(5) for k in range(2))}),
o(k, l, v) AS (VALUES {', '.join(f'({k}, {l}, {O2[k, l]}e0)' for k in range(2) for l in range(2))}),
a AS (SELECT i, j, value AS v FROM ea),
waw AS (SELECT p.k, q.k AS l, sum(p.v * a.v * q.v) AS v FROM w p JOIN a ON a.i = p.i JOIN w q ON q.i = a.j GROUP BY 1, 2),
lam AS (SELECT waw.k, o.l, -sum(waw.v * o.v) AS v FROM waw JOIN o ON o.k = waw.l GROUP BY 1, 2)"""


@query(f"{RULE} SELECT CAST(k AS INTEGER) AS i, CAST(l AS INTEGER) AS j, round(v, 5) AS value, round(greatest(v, 0), 5) AS plus, round(greatest(-v, 0), 5) AS minus FROM lam")
def ortho_multiplier(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    rows = matrix_frame(spark, mem.ortho_multiplier(W5, a, O2), digits=12)
    return rows.select("i", "j", r("value", 5).alias("value"), r(F.greatest("value", F.lit(0.0)), 5).alias("plus"), r(F.greatest(-F.col("value"), F.lit(0.0)), 5).alias("minus"))


@query(f"""{RULE}, ap AS (SELECT a.i, w.k, sum(greatest(a.v, 0) * w.v) AS p, sum(greatest(-a.v, 0) * w.v) AS n FROM a JOIN w ON w.i = a.j GROUP BY 1, 2),
t AS (SELECT ap.i, o.l AS k, sum(p * greatest(-o.v, 0) + n * greatest(o.v, 0)) AS num, sum(p * greatest(o.v, 0) + n * greatest(-o.v, 0)) AS den FROM ap JOIN o ON o.k = ap.k GROUP BY 1, 2),
u AS (SELECT w.i, lam.l AS k, sum(w.v * greatest(-lam.v, 0)) AS num, sum(w.v * greatest(lam.v, 0)) AS den FROM w JOIN lam ON lam.k = w.k GROUP BY 1, 2),
n AS (SELECT w.i, w.k, w.v * greatest(t.num + u.num, 1e-10) / greatest(t.den + u.den, 1e-10) AS v FROM w JOIN t USING (i, k) JOIN u USING (i, k))
SELECT CAST(i AS INTEGER) AS var_id, CAST(k AS INTEGER) AS node, round(v / sqrt(sum(v * v) OVER (PARTITION BY k)), 5) AS weight FROM n""")
def membership_update_once(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    return matrix_frame(spark, mem.update_membership(W5, a, O2, "sign_split"), ("var_id", "node"), 5).withColumnRenamed("value", "weight")


def plain_rule_sql(moment: str) -> str:
    """The rule with one moment for both sides of the fraction, signed or absolute."""
    rule = RULE.replace("value AS v FROM ea", f"{moment} AS v FROM ea")
    return f"""{rule}, aw AS (SELECT a.i, w.k, sum(a.v * w.v) AS v FROM a JOIN w ON w.i = a.j GROUP BY 1, 2),
t AS (SELECT aw.i, o.l AS k, sum(aw.v * greatest(-o.v, 0)) AS num, sum(aw.v * greatest(o.v, 0)) AS den FROM aw JOIN o ON o.k = aw.k GROUP BY 1, 2),
u AS (SELECT w.i, lam.l AS k, sum(w.v * greatest(-lam.v, 0)) AS num, sum(w.v * greatest(lam.v, 0)) AS den FROM w JOIN lam ON lam.k = w.k GROUP BY 1, 2),
n AS (SELECT w.i, w.k, w.v * greatest(t.num + u.num, 1e-10) / greatest(t.den + u.den, 1e-10) AS v FROM w JOIN t USING (i, k) JOIN u USING (i, k))
SELECT CAST(i AS INTEGER) AS var_id, CAST(k AS INTEGER) AS node, round(v / sqrt(sum(v * v) OVER (PARTITION BY k)), 5) AS weight FROM n"""


@query(plain_rule_sql("abs(value)"))
def membership_update_absolute(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    return matrix_frame(spark, mem.update_membership(W5, a, O2, "absolute"), ("var_id", "node"), 5).withColumnRenamed("value", "weight")


@query(plain_rule_sql("value"))
def membership_update_signed(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    return matrix_frame(spark, mem.update_membership(W5, a, O2, "signed"), ("var_id", "node"), 5).withColumnRenamed("value", "weight")


# ---- k-means and the second stage -----------------------------------------------------------------


@query("""WITH e AS (SELECT vec_id, generate_subscripts(embedding, 1) AS v, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings),
c AS (SELECT vec_id AS c, v, x FROM e WHERE vec_id < 4),
s AS (SELECT e.vec_id, c.c, sum((e.x - c.x) * (e.x - c.x)) AS dist FROM e JOIN c USING (v) GROUP BY 1, 2)
SELECT vec_id AS sample_id, CAST(arg_min(c, dist) AS INTEGER) AS state FROM s GROUP BY 1""")
def kmeans_assign(spark, d):
    rows = sig.embedding_signals(spark, d).select("sample_id", "x")
    centres = [r["x"] for r in rows.filter("sample_id < 4").orderBy("sample_id").collect()]  # four centres
    return rows.select("sample_id", est.nearest("x", centres).alias("state"))


@query("""WITH e AS (SELECT label, vec_id, generate_subscripts(embedding, 1) - 1 AS v, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings WHERE label IS NOT NULL)
SELECT CAST(a.label AS INTEGER) AS state, CAST(a.v AS INTEGER) AS i, CAST(b.v AS INTEGER) AS j, round(sum(a.x * b.x) / count(*), 6) AS value FROM e a JOIN e b USING (vec_id) GROUP BY 1, 2, 3""")
def two_stage_group_moments(spark, d):
    """All components of every row, and every label of the table."""
    rows = sig.embedding_signals(spark, d).withColumn("state", F.col("label").cast("int")).filter("state is not null")
    labels = [x["state"] for x in rows.select("state").distinct().orderBy("state").collect()]  # one row a label
    places = F.create_map(*[F.lit(v) for pair in ((g, i) for i, g in enumerate(labels)) for v in pair])
    found = moments.grouped_moments(rows.withColumn("state", places[F.col("state")]), len(labels))
    return spark.createDataFrame([(g, i, j, round(float(x), 6) + 0.0) for g, (a, _) in zip(labels, found, strict=True) for (i, j), x in np.ndenumerate(a)], "state int, i int, j int, value double")


# ---- edges and measures ---------------------------------------------------------------------------


@query(f"""WITH {BINS} SELECT 0 AS state, p.i AS a, p.j AS b, round(p.value, 5) AS weight, round(-p.value / sqrt(x.value * y.value), 5) AS partial_corr
FROM ea p JOIN ea x ON x.i = p.i AND x.j = p.i JOIN ea y ON y.i = p.j AND y.j = p.j WHERE p.i < p.j AND abs(p.value / sqrt(x.value * y.value)) > 1e-2""")
def edges_from_precision_table(spark, d):
    a, _ = moments.gram(bins_dense(spark, d))
    table = matrix_frame(spark, a, ("a", "b"), 12).withColumn("state", F.lit(0))
    return edges_from_precision(table, 1e-2).select("state", "a", "b", r("weight", 5).alias("weight"), r("partial_corr", 5).alias("partial_corr"))


FOUND = f"""WITH {NATION_WEEK}, f AS (SELECT DISTINCT a.var_id AS a, b.var_id AS b FROM (SELECT x.var_id AS va, y.var_id AS vb, corr(x.value, y.value) AS c FROM nwd x JOIN nwd y ON x.sample_id = y.sample_id AND x.var_id < y.var_id GROUP BY 1, 2) q JOIN (SELECT range AS var_id FROM range(25)) a ON a.var_id = va JOIN (SELECT range AS var_id FROM range(25)) b ON b.var_id = vb WHERE abs(c) > 5e-2),
t AS (SELECT p.n_nationkey AS a, q.n_nationkey AS b FROM nation p JOIN nation q ON p.n_regionkey = q.n_regionkey AND p.n_nationkey < q.n_nationkey)"""


def found_and_true(spark, d):
    found = correlation_nations(spark, d).filter(F.abs("value") > 0.05).select(F.lit(0).alias("state"), F.col("i").alias("a"), F.col("j").alias("b"))
    n = load(spark, d, "nation", "n_nationkey", "n_regionkey")
    m = n.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("region"))
    truth = n.join(m, F.col("n_regionkey") == F.col("region")).filter("n_nationkey < b").select(F.lit(0).alias("state"), F.col("n_nationkey").alias("a"), "b")
    return found, truth


@query(f"""{FOUND} SELECT 0 AS state, (SELECT count(*) FROM f) AS n_found, (SELECT count(*) FROM t) AS n_true, count(*) AS n_hit,
round(count(*) / CAST((SELECT count(*) FROM t) AS DOUBLE), 6) AS accuracy, round(2 * count(*) / CAST((SELECT count(*) FROM t) + (SELECT count(*) FROM f) AS DOUBLE), 6) AS f1 FROM f JOIN t USING (a, b)""")
def edge_accuracy_f1(spark, d):
    return measures.edge_scores(*found_and_true(spark, d)).withColumns({"accuracy": r("accuracy"), "f1": r("f1")})


@query(f"""{FOUND} SELECT 0 AS state, CAST(coalesce(f.a, t.a) AS INTEGER) AS a, CAST(coalesce(f.b, t.b) AS INTEGER) AS b, CASE WHEN f.a IS NULL THEN 'missed' WHEN t.a IS NULL THEN 'spurious' ELSE 'hit' END AS kind
FROM f FULL JOIN t ON f.a = t.a AND f.b = t.b""")
def edge_sets(spark, d):
    return measures.edge_sets(*found_and_true(spark, d))


@query("""WITH c AS (SELECT source, lang, count(*) AS n FROM documents GROUP BY 1, 2) SELECT round(CAST(sum(t) AS DOUBLE) / CAST(sum(s) AS DOUBLE), 6) AS purity FROM (SELECT source, max(n) AS t, sum(n) AS s FROM c GROUP BY 1)""")
def purity_language(spark, d):
    return measures.purity(load(spark, d, "documents", "source", "lang"), "source", "lang").select(r("purity").alias("purity"))


NMI = """WITH c AS (SELECT source, lang, CAST(count(*) AS DOUBLE) AS n FROM documents GROUP BY 1, 2), m AS (SELECT n, sum(n) OVER (PARTITION BY source) AS a, sum(n) OVER (PARTITION BY lang) AS b, sum(n) OVER () AS t FROM c),
h AS (SELECT sum(n / t * ln(n * t / (a * b))) AS mi, sum(-(n / t) * ln(a / t)) AS ha, sum(-(n / t) * ln(b / t)) AS hb FROM m)
SELECT 'sqrt' AS norm, round(mi / sqrt(ha * hb), 6) AS nmi FROM h UNION ALL SELECT 'mean', round(mi / ((ha + hb) / 2), 6) FROM h UNION ALL SELECT 'max', round(mi / greatest(ha, hb), 6) FROM h UNION ALL SELECT 'min', round(mi / least(ha, hb), 6) FROM h"""


@query(NMI)
def nmi_language(spark, d):
    docs = load(spark, d, "documents", "source", "lang")
    parts = [measures.nmi(docs, n, "source", "lang").select(F.lit(n).alias("norm"), r("nmi").alias("nmi")) for n in ("sqrt", "mean", "max", "min")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


@query("SELECT source, lang, count(*) AS n FROM documents GROUP BY CUBE (source, lang)")
def contingency_cube(spark, d):
    return relops.cube_report(load(spark, d, "documents", "source", "lang"), "source", "lang")


@query("""SELECT o_orderstatus AS scenario, CAST(year(o_orderdate) AS DOUBLE) AS setting, o_orderpriority AS method, 'price' AS metric, count(*) AS runs, round(avg(o_totalprice), 3) AS mean, round(stddev_samp(o_totalprice), 3) AS spread FROM orders GROUP BY 1, 2, 3""")
def run_summary(spark, d):
    rows = load(spark, d, "orders", "o_orderstatus", "o_orderdate", "o_orderpriority", "o_totalprice")
    rows = rows.select(F.col("o_orderstatus").alias("scenario"), F.year("o_orderdate").cast("double").alias("setting"), F.col("o_orderpriority").alias("method"), F.lit("price").alias("metric"), F.col("o_totalprice").alias("value"))
    return measures.summarize_runs(rows).withColumns({"mean": r("mean", 3), "spread": r("spread", 3)})


CONTRAST = f"""{FOUND}, e AS (SELECT 0 AS state, a, b FROM f UNION ALL SELECT 1, a, b FROM t)
SELECT CAST(coalesce(x.a, y.a) AS INTEGER) AS a, CAST(coalesce(x.b, y.b) AS INTEGER) AS b, x.a IS NOT NULL AS in_first, y.a IS NOT NULL AS in_second
FROM (SELECT * FROM e WHERE state = 0) x FULL JOIN (SELECT * FROM e WHERE state = 1) y ON x.a = y.a AND x.b = y.b"""


@query(CONTRAST)
def state_contrast(spark, d):
    found, truth = found_and_true(spark, d)
    return measures.compare_edges(found.unionByName(truth.withColumn("state", F.lit(1))), 0, 1)


@query(f"""WITH {NATION_WEEK}, c AS (SELECT a.var_id % 3 AS state, a.var_id AS a, b.var_id AS b, corr(a.value, b.value) AS w FROM nwd a JOIN nwd b ON a.sample_id = b.sample_id AND a.var_id < b.var_id GROUP BY 1, 2, 3),
k AS (SELECT *, row_number() OVER (PARTITION BY state ORDER BY abs(w) DESC, a, b) AS rank FROM c)
SELECT CAST(state AS INTEGER) AS state, a, b, round(w, 6) AS weight, CAST(rank AS INTEGER) AS rank FROM k WHERE rank <= 5""")
def top_edges(spark, d):
    a, _ = moments.gram(sig.standardize(nation_dense(spark, d)))
    rows = matrix_frame(spark, a, ("a", "b"), 12).filter("a < b").select((F.col("a") % 3).cast("int").alias("state"), "a", "b", F.col("value").alias("weight"))
    return relops.top_edges(rows, 5).withColumn("weight", r("weight"))


# ---- states over time -----------------------------------------------------------------------------

STEPS = "s AS (SELECT user_id AS unit, event_type AS state, event_id AS step FROM events)"
SPELLS = f"""{STEPS}, n AS (SELECT *, CASE WHEN lag(state) OVER w = state THEN 0 ELSE 1 END AS new FROM s WINDOW w AS (PARTITION BY unit ORDER BY step)),
g AS (SELECT *, sum(new) OVER (PARTITION BY unit ORDER BY step ROWS UNBOUNDED PRECEDING) AS k FROM n),
sp AS (SELECT unit, state, min(step) AS begin, max(step) AS "end", count(*) AS steps FROM g GROUP BY unit, k, state)"""


def event_steps(spark, d):
    return load(spark, d, "events", "user_id", "event_type", "event_id").select(F.col("user_id").alias("unit"), F.col("event_type").alias("state"), F.col("event_id").alias("step"))


@query(f"WITH {SPELLS} SELECT * FROM sp")
def state_spells(spark, d):
    return relops.state_spells(event_steps(spark, d))


@query(f"WITH {SPELLS} SELECT unit, CAST(sum(new) - 1 AS BIGINT) AS switches FROM n GROUP BY 1")
def state_switches(spark, d):
    return relops.state_switches(event_steps(spark, d))


@query("""SELECT p.event_id, p.user_id, c.value AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') p
ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.event_id >= c.event_id""")
def asof_state(spark, d):
    ev = load(spark, d, "events", "event_id", "user_id", "event_type", "value")
    left = ev.filter("event_type = 'purchase'").select("event_id", "user_id")
    right = ev.filter("event_type = 'click'").select("event_id", "user_id", "value")
    return relops.asof_join(left, right, "user_id", "event_id", "value", "last_click")


@query(f"WITH {SPELLS} SELECT e.event_id, e.user_id, sp.steps FROM events e JOIN sp ON sp.unit = e.user_id AND e.event_id BETWEEN sp.begin AND sp.\"end\" WHERE sp.steps >= 3")
def interval_join_spells(spark, d):
    spells = relops.state_spells(event_steps(spark, d)).filter("steps >= 3").select(F.col("unit").alias("user_id"), "begin", "end", "steps")
    ev = load(spark, d, "events", "event_id", "user_id")
    return relops.interval_join(ev, spells, "user_id", "event_id", "begin", "end", 2000).select("event_id", "user_id", "steps")


@query("""WITH b(lo, hi, name) AS (VALUES (0, 24, 'first day'), (24, 168, 'first week'), (100, 300, 'middle')), e AS (SELECT event_id, date_diff('second', TIMESTAMP '2024-01-01 00:00:00', ts) // 3600 AS h FROM events)
SELECT name, count(*) AS n FROM e JOIN b ON h >= lo AND h < hi GROUP BY 1""")
def range_join_bins(spark, d):
    hour = F.floor(F.timestamp_diff("SECOND", F.lit("2024-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts").cast("timestamp_ntz")) / 3600)
    rows = load(spark, d, "events", "event_id", "ts").select("event_id", hour.alias("h"))
    bins = spark.createDataFrame([(0, 24, "first day"), (24, 168, "first week"), (100, 300, "middle")], "lo long, hi long, name string")
    return relops.range_join(rows, bins, "h", "lo", "hi", 48).groupBy("name").agg(F.count("*").alias("n"))


@query(f"WITH {BINS} SELECT sample_id, var_id, round(avg(value) OVER (PARTITION BY var_id ORDER BY sample_id RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING), 5) AS smoothed FROM ec")
def smooth_states(spark, d):
    rows = sig.to_long(bins_dense(spark, d))
    return relops.smooth(rows, "var_id", "sample_id", "value", 2).select("sample_id", "var_id", r("smoothed", 5).alias("smoothed"))


@query("""WITH l AS (SELECT unnest(string_split('abcdefghijklmnopqrstuvwxyz', '')) AS c, generate_subscripts(string_split('abcdefghijklmnopqrstuvwxyz', ''), 1) - 1 AS term),
n AS (SELECT lang AS label, CAST(term AS INTEGER) AS term, sum(length(lower(text)) - length(replace(lower(text), c, ''))) AS n FROM documents CROSS JOIN l GROUP BY 1, 2)
SELECT label, term, CAST(n AS BIGINT) AS n, CAST(sum(n) OVER (PARTITION BY label) AS BIGINT) AS total FROM n WHERE n > 0""")
def naive_bayes_counts(spark, d):
    docs = load(spark, d, "documents", "doc_id", "text", "lang")
    return topics.naive_bayes_counts(topics.letter_bag(docs), docs, "lang")


# ---- fits (rows only; numeric checks are in the tests) ----------------------------------------------


@query()
def topic_mixture(spark, d):
    docs = load(spark, d, "documents", "doc_id", "text", "lang")
    _, _, states = topics.topic_mixture(topics.letter_bag(docs), 4, 26)
    return states.join(docs.select("doc_id", "lang"), "doc_id").groupBy("state", "lang").agg(F.count("*").alias("n"))


@query()
def flagship_planted(spark, d):
    model, scored, _ = exp.distributed_cell(spark, load(spark, d, "events", "event_id"), "event_id", exp.SCENARIOS["samples"][-1])
    return model.edges(spark)


@query()
def planted_states(spark, d):
    _, scored, _ = exp.distributed_cell(spark, load(spark, d, "events", "event_id"), "event_id", exp.SCENARIOS["samples"][-1])
    return measures.contingency(scored, "state_hat", "state")


@query()
def fit_language(spark, d):
    _, scored = exp.language_workload(spark, d)
    return measures.purity(scored, "state_hat", "lang").crossJoin(measures.nmi(scored, "sqrt", "state_hat", "lang"))  # one row each


@query()
def fit_embedding(spark, d):
    _, scored = exp.embedding_workload(spark, d)
    return measures.purity(scored, "state_hat", "label").crossJoin(measures.nmi(scored, "sqrt", "state_hat", "label"))  # one row each


@query()
def nation_nodes(spark, d):
    _, pairs = exp.nation_workload(spark, d)
    return measures.purity(pairs).crossJoin(measures.nmi(pairs))  # one row each


@query()
def grid_report(spark, d):
    return exp.grid_workload(spark, d)[2]


@query()
def cohort_contrast(spark, d):
    models = exp.cohort_workload(spark, d)
    parts = [measures.compare_edges(m.edges(spark), 0, 1).withColumn("quality", F.lit(q)) for q, m in models.items()]
    return parts[0].unionByName(parts[1])


def planted_rows(spark, d):
    from .sources.planted import plant_signals, plant_truth

    ids = load(spark, d, "events", "event_id").select(F.col("event_id").alias("sample_id"))
    return plant_signals(ids, plant_truth(2, 5, 70, 0))


@query()
def baseline_coupled(spark, d):
    return est.CoupledNetwork(5, exp.L1, membership_update="disjoint", l1_relative=True).fit(planted_rows(spark, d)).edges(spark)


@query()
def baseline_trifactor(spark, d):
    return est.OrthoTriFactor(5).fit(planted_rows(spark, d)).edges(spark)


@query()
def baseline_kmeans_coupled(spark, d):
    return est.two_stage("coupled", planted_rows(spark, d), 2, 5, exp.L1, membership_update="disjoint", l1_relative=True)[0].edges(spark)


@query()
def baseline_kmeans_trifactor(spark, d):
    return est.two_stage("trifactor", planted_rows(spark, d), 2, 5)[0].edges(spark)


@query()
def baseline_kmeans_joint(spark, d):
    return est.two_stage("joint", planted_rows(spark, d), 2, 5, exp.L1, l1_relative=True)[0].edges(spark)


@query()
def baseline_known_nodes(spark, d):
    from .functions.partition import indicators
    from .sources.planted import plant_truth

    w = indicators(plant_truth(2, 5, 70, 0).node[0], 5)
    return est.KnownNodeMixture(w, 2, exp.L1, l1_relative=True, max_iter=10).fit(planted_rows(spark, d)).states(spark)


@query()
def baseline_gaussian_mixture(spark, d):
    _, states = est.gaussian_mixture(bins_dense(spark, d), 2)
    return states.groupBy("state").agg(F.count("*").alias("n"))


@query()
def zero_mean_mixture(spark, d):
    return est.ZeroMeanMixture(2, 5, max_iter=10).fit(bins_dense(spark, d)).states(spark)


@query()
def product_strategy(spark, d):
    return est.StateNetworkMixture(2, 5, 0.02, strategy="product", moment_mode="signed", max_iter=5).fit(planted_rows(spark, d)).states(spark)


@query()
def alternating_objectives(spark, d):
    a, _ = moments.gram(planted_rows(spark, d))
    w, omega = est.alternating_two_objective(a, 5, 1.0)
    return matrix_frame(spark, omega, ("a", "b"))


@query()
def contiguous_nodes(spark, d):
    long, names = sig.part_grid_long(spark, d)
    a, _ = moments.gram(sig.standardize(sig.densify(long, names.count())))
    pairs = [(x["i"], x["j"]) for x in relops.neighbours(names).collect()]  # a few pairs a variable
    w, _ = est.contiguous_trifactor(a, 6, pairs)
    return spark.createDataFrame([(v, int(n)) for v, n in enumerate(w.argmax(axis=1))], "var_id int, node int")


@query()
def model_selection(spark, d):
    return est.select_model(planted_rows(spark, d), (1, 2), (3, 5), l1=exp.L1, l1_relative=True, membership_update="disjoint", max_iter=8)


def _scenario(name, settings=None):
    def run(spark, d):
        rows = exp.run_methods(spark, load(spark, d, "events", "event_id"), "event_id", (name,), reps=10, settings=settings)
        return measures.summarize_runs(rows)

    return run


for _name in exp.SCENARIOS:
    QUERIES[f"scenario_{_name}"] = _scenario(_name)


def _keys_sql() -> str:
    """Every (generator, scenario, setting, method, metric), and how many repetitions it has."""
    cells = ", ".join(f"('{s}', CAST({x['setting']} AS DOUBLE))" for s, xs in exp.SCENARIOS.items() for x in xs)
    names = lambda xs: ", ".join(f"('{x}')" for x in xs)
    metrics = ("edge_accuracy", "edge_f1", "node_purity", "node_nmi", "state_purity", "state_nmi")
    return f"""SELECT generator, scenario, setting, method, metric, CAST(1 AS BIGINT) AS runs, true AS within
FROM (VALUES {cells}) c(scenario, setting) CROSS JOIN (VALUES {names(exp.GENERATORS)}) g(generator) CROSS JOIN (VALUES {names(exp.METHODS)}) m(method) CROSS JOIN (VALUES {names(metrics)}) t(metric)"""


@query(_keys_sql())
def scenario_coverage(spark, d):
    """One repetition of every cell of all sweeps: each has every measure, all of them between zero and one."""
    rows = exp.run_methods(spark, load(spark, d, "events", "event_id"), "event_id", reps=1)
    return rows.groupBy("generator", "scenario", "setting", "method", "metric").agg(F.count("*").alias("runs"), F.min(F.col("value").between(-1e-9, 1 + 1e-9)).alias("within"))


@query()
def fit_printed(spark, d):
    """The published estimator on the published generator: measures of one data set, over the distributed path."""
    cell = exp.SCENARIOS["samples"][-1]
    model, scored, truth = exp.distributed_cell(spark, load(spark, d, "events", "event_id"), "event_id", cell, generator="random", form=exp.PRINTED)
    rows = scored.select("state_hat", "state").toPandas()  # at most 2,000 samples
    got = exp.score_model(model, rows["state_hat"].to_numpy(), truth, rows["state"].to_numpy())
    return spark.createDataFrame([(k, float(v)) for k, v in got.items()], "metric string, value double")


# ---- streaming --------------------------------------------------------------------------------------


#: Keeps the state of streams outside the heap, as there can be a row for every event.
STATE_STORE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def _run_stream(spark, d, build, name, mode="complete"):
    """Run a stream over the events file to its end; the result is a table that executors write to the shared folder.

    ``append`` rows go to one table; of ``complete`` results each batch writes its own, and the last is read.
    """
    import uuid

    from .sources.staging import delete, shared_dir

    folder = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    source = spark.readStream.schema(spark.read.parquet(f"{d}/events.parquet").schema).option("pathGlobFilter", "events.parquet").parquet(d)
    rows, written = build(source), []
    writer = rows.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True)
    if mode == "append":
        written.append(f"{folder}/rows")
        writer = writer.format("parquet").option("path", written[0])
    else:

        def keep(batch, batch_id):
            batch.write.mode("overwrite").parquet(f"{folder}/rows-{batch_id}")
            written.append(f"{folder}/rows-{batch_id}")

        writer = writer.foreachBatch(keep)
    before = {k: spark.conf.get(k, None) for k in STATE_STORE}
    for k, v in STATE_STORE.items():
        spark.conf.set(k, v)
    try:
        q = writer.start()  # takes the settings as they are now
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    delete(spark, f"{folder}/log")
    for path in written[:-1]:
        delete(spark, path)
    return spark.read.schema(rows.schema).parquet(written[-1]) if written else spark.createDataFrame([], rows.schema)


@query(f"WITH {BINS} SELECT sample_id, event_type, round(value, 4) AS value FROM ev")
def stream_bins(spark, d):
    rows = _run_stream(spark, d, streams.windowed_bins, "bins")
    hour = F.floor((F.unix_timestamp("w.start") - F.unix_timestamp(F.lit("2024-01-01 00:00:00").cast("timestamp"))) / 3600)
    return rows.select(hour.alias("sample_id"), "event_type", r("value", 4).alias("value"))


@query("""WITH e AS (SELECT user_id, ts, value, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, count(DISTINCT k) AS sessions, round(sum(value), 3) AS value FROM g GROUP BY 1""")
def stream_sessions(spark, d):
    rows = _run_stream(spark, d, streams.session_bins, "sessions", "complete")
    return rows.groupBy("user_id").agg(F.count("*").alias("sessions"), r(F.sum("value"), 3).alias("value"))


@query("""WITH e AS (SELECT date_diff('second', TIMESTAMP '2024-01-01 00:00:00', ts) // 3600 AS h, event_type, value FROM events),
w AS (SELECT h AS first_hour, event_type, value FROM e UNION ALL SELECT h - 1, event_type, value FROM e)
SELECT CAST(first_hour AS BIGINT) AS first_hour, event_type, count(*) AS n, round(sum(value), 4) AS value FROM w GROUP BY 1, 2""")
def stream_sliding(spark, d):
    """Windows of two hours that begin every hour."""
    rows = _run_stream(spark, d, lambda source: streams.windowed_bins(source, width="2 hours", slide="1 hour"), "sliding")
    hour = F.floor((F.unix_timestamp("w.start") - F.unix_timestamp(F.lit("2024-01-01 00:00:00").cast("timestamp"))) / 3600)
    return rows.select(hour.alias("first_hour"), "event_type", "n", r("value", 4).alias("value"))


@query(f"""WITH {SPELLS}, k AS (SELECT event_type, CAST(row_number() OVER (ORDER BY event_type) - 1 AS INTEGER) AS code FROM (SELECT DISTINCT event_type FROM events)),
o AS (SELECT *, row_number() OVER (PARTITION BY unit ORDER BY begin DESC) AS back FROM sp)
SELECT unit, code AS state, steps, back > 1 AS closed, count(*) AS n FROM o JOIN k ON k.event_type = o.state GROUP BY 1, 2, 3, 4""")
def stream_dwell(spark, d):
    """Spells of every user's states as the stream closes them; the last one is open. A state is its name's place in order."""
    kinds = [x[0] for x in load(spark, d, "events", "event_type").distinct().orderBy("event_type").collect()]  # a small domain

    def build(source):
        code = F.array_position(F.array(*[F.lit(k) for k in kinds]), F.col("event_type")).cast("int") - 1
        return streams.dwell_stream(source.select(F.col("user_id").alias("unit"), code.alias("state"), F.col("event_id").alias("step")))

    return _run_stream(spark, d, build, "dwell", "append").groupBy("unit", "state", "steps", "closed").agg(F.count("*").alias("n"))


@query("""SELECT p.event_id AS event_id, c.event_id AS click_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p
JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 6 HOUR""")
def stream_spell_join(spark, d):
    """Purchases in the six hours after a click of the same user, both sides streamed."""

    def build(source):
        ev = source.withColumn("ts", F.col("ts").cast("timestamp"))
        bought = ev.filter("event_type = 'purchase'").select("event_id", F.col("user_id").alias("unit"), "ts")
        clicked = ev.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("unit"), F.col("ts").alias("begin"), (F.col("ts") + F.expr("INTERVAL 6 HOUR")).alias("end"))
        return streams.spell_join(bought, clicked, "40 days").select("event_id", "click_id")

    return _run_stream(spark, d, build, "spelljoin", "append")


@query("""WITH e AS (SELECT *, date_diff('second', TIMESTAMP '2024-01-01 00:00:00', ts) // 3600 AS h FROM events WHERE event_id % 2 = 0)
SELECT CAST(h AS BIGINT) AS sample_id, event_type, count(*) AS n, round(sum(value), 4) AS value FROM e GROUP BY 1, 2""")
def stream_late_rows(spark, d):
    """Half of the events arrive when the watermark has passed them, and are dropped.

    Rows are late by the watermark before the last batch, so the even events come in two batches and the odd ones in a third.
    """
    import time
    import uuid

    from .sources.staging import shared_dir

    folder, table = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}", f"late_{uuid.uuid4().hex[:8]}"
    ev = load(spark, d, "events")
    even = ev.filter("event_id % 2 = 0")
    last = even.agg(F.max_by("event_id", "ts").alias("id"), F.max("ts").alias("ts")).first()
    late = ev.filter("event_id % 2 = 1").filter(F.col("ts") < F.lit(last["ts"]) - F.expr("INTERVAL 5 HOUR"))
    for name, rows in (("a", even.filter(F.col("event_id") != last["id"])), ("b", even.filter(F.col("event_id") == last["id"])), ("c", late)):
        rows.coalesce(1).write.parquet(f"{folder}/{name}")
        time.sleep(1.2)  # files are read in the order of their times
    source = spark.readStream.schema(ev.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder)
    q = streams.windowed_bins(source).writeStream.format("memory").queryName(table).outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    hour = F.floor((F.unix_timestamp("w.start") - F.unix_timestamp(F.lit("2024-01-01 00:00:00").cast("timestamp"))) / 3600)
    newest = spark.table(table).groupBy("w", "event_type").agg(F.max("n").alias("n"), F.max_by("value", "n").alias("value"))
    return newest.select(hour.alias("sample_id"), "event_type", "n", r("value", 4).alias("value"))


@query()
def stream_scores(spark, d):
    model = est.StateNetworkMixture(2, 2, 0.02, density="residual", max_iter=5).fit(bins_dense(spark, d))
    kinds = sig.event_bin_signals(spark, d)[1]

    def build(source):
        # one signal per event: its value on its own type's axis, scored by the fixed model
        x = F.array(*[F.when(F.col("event_type") == k, F.col("value") / 100).otherwise(0.0) for k in kinds])
        return streams.score_stream(source.select(F.col("event_id").alias("sample_id"), x.alias("x")), model).select("sample_id", "state_hat")

    return _run_stream(spark, d, build, "scores", "append").groupBy("state_hat").agg(F.count("*").alias("n"))


from . import surface_queries, unrolled_queries  # noqa: E402, F401  (both register their own)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
