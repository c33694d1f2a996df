"""Measures on hand-made frames."""

import numpy as np

from nodeweave.operators import measures, relops

EDGE = "state int, a int, b int"


def test_edge_scores(spark):
    truth = spark.createDataFrame([(0, 0, 1), (0, 1, 2), (1, 0, 2)], EDGE)
    found = spark.createDataFrame([(0, 1, 0), (0, 0, 2), (2, 0, 1)], EDGE)
    got = {r["state"]: r for r in measures.edge_scores(found, truth).collect()}
    assert (got[0]["n_hit"], got[0]["accuracy"], got[0]["f1"]) == (1, 0.5, 0.5)
    assert got[1]["accuracy"] == 0 and got[1]["f1"] == 0 and got[2]["n_true"] == 0 and got[2]["accuracy"] == 0
    none = spark.createDataFrame([], EDGE)
    assert measures.edge_scores(none, none).count() == 0


def test_f1_identity():
    for a, b in ((set(), set()), ({(0, 1)}, set()), ({(0, 1), (1, 2)}, {(0, 1)})):
        acc, f1 = measures.local_edge_scores(a, b)
        hit = len(a & b)
        assert f1 == (2 * hit / (len(a) + len(b)) if a or b else 0) and acc == (hit / len(b) if b else 0)


def test_purity_and_nmi(spark):
    same = spark.createDataFrame([(i % 3, i % 3) for i in range(30)], "cluster int, label int")
    assert measures.purity(same).first()[0] == 1 and np.isclose(measures.nmi(same).first()[0], 1)
    one = spark.createDataFrame([(0, i % 2) for i in range(10)], "cluster int, label int")
    assert measures.purity(one).first()[0] == 0.5 and measures.nmi(one).first()[0] == 0
    alone = spark.createDataFrame([(i, i % 2) for i in range(10)], "cluster int, label int")
    assert measures.purity(alone).first()[0] == 1
    assert np.isclose(measures.nmi(alone, "min").first()[0], 1) and measures.nmi(alone, "max").first()[0] < 1
    assert np.isclose(measures.local_nmi([0, 0, 1, 1], [0, 0, 1, 1]), 1) and measures.local_purity([0, 0, 1], [0, 1, 1]) == 2 / 3


def test_alignment(spark):
    pairs = spark.createDataFrame([(0, 2), (0, 2), (1, 0), (2, 1), (2, 1), (2, 0)], "cluster int, label int")
    assert measures.align(pairs, 3).tolist() == [2, 0, 1]


def test_edge_sets_and_contrast(spark):
    f, t = spark.createDataFrame([(0, 0, 1), (0, 1, 2)], EDGE), spark.createDataFrame([(0, 1, 2), (0, 2, 3)], EDGE)
    assert sorted(r["kind"] for r in measures.edge_sets(f, t).collect()) == ["hit", "missed", "spurious"]
    both = f.unionByName(t.selectExpr("1 as state", "a", "b"))
    assert sorted((r["in_first"], r["in_second"]) for r in measures.compare_edges(both, 0, 1).collect()) == [(False, True), (True, False), (True, True)]


def test_asof_against_brute_force(spark):
    rng = np.random.default_rng(0)
    left = [(int(k), int(t)) for k, t in zip(rng.integers(0, 3, 60), rng.integers(0, 50, 60), strict=True)]
    right = [(int(k), int(t), int(v)) for k, t, v in zip(rng.integers(0, 3, 40), rng.permutation(50)[:40], rng.integers(0, 9, 40), strict=True)]
    got = relops.asof_join(spark.createDataFrame(left, "k int, t int"), spark.createDataFrame(right, "k int, t int, v int"), "k", "t", "v", "last")
    want = []
    for k, t in left:
        before = [(rt, v) for rk, rt, v in right if rk == k and rt <= t]
        want.append((k, t, max(before)[1] if before else None))
    key = lambda r: tuple(-1 if x is None else x for x in r)
    assert sorted(map(tuple, got.collect()), key=key) == sorted(want, key=key)


def test_spells(spark):
    rows = spark.createDataFrame([(1, i, s) for i, s in enumerate("aabba")] + [(2, 0, "a")], "unit int, step int, state string")
    got = sorted(tuple(r) for r in relops.state_spells(rows).select("unit", "state", "begin", "end", "steps").collect())
    assert got == [(1, "a", 0, 1, 2), (1, "a", 4, 4, 1), (1, "b", 2, 3, 2), (2, "a", 0, 0, 1)]
    assert {r["unit"]: r["switches"] for r in relops.state_switches(rows).collect()} == {1: 2, 2: 0}


def test_neighbours(spark):
    grid = spark.createDataFrame([(a * 2 + b, (a, b, 0)) for a in range(2) for b in range(2)], "var_id int, coord struct<a int, b int, c int>")
    assert sorted(map(tuple, relops.neighbours(grid).collect())) == [(0, 1), (0, 2), (1, 3), (2, 3)]


def test_pass_costs_follow_the_table(spark, sf):
    """Sizes of the passes are those of the events."""
    from nodeweave.queries import QUERIES

    rows = QUERIES["pass_costs"](spark, sf).filter("strategy = 'gram'").collect()
    assert sum(r["n"] for r in rows) == spark.read.parquet(f"{sf}/events.parquet").count()


def test_top_variables_follow_the_table(spark, sf, duck, tmp_path):
    """Other events, other weights; still as by the SQL."""
    from conftest import same_rows
    from pyspark.sql import functions as F

    from nodeweave.queries import ORACLES, QUERIES

    events = spark.read.parquet(f"{sf}/events.parquet").withColumn("value", F.col("value") * F.length("event_type"))
    events.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    with duck.cursor() as other:
        other.execute(f"CREATE TEMP VIEW events AS SELECT * FROM read_parquet('{tmp_path}/events.parquet/*.parquet')")
        assert same_rows(QUERIES["top_variables"](spark, str(tmp_path)), other, ORACLES["top_variables"]) > 0
    assert set(QUERIES["top_variables"](spark, str(tmp_path)).collect()) != set(QUERIES["top_variables"](spark, sf).collect())
