"""Group moments over whole vectors and all labels, against numpy."""

import numpy as np

from nodeweave import queries as q


def test_all_components_and_labels(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    rows = e.withColumn("label", e.label + (e.vec_id % 2) * 37 - 3)  # labels below zero and above nine
    rows.write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {(r["state"], r["i"], r["j"]): r["value"] for r in q.QUERIES["two_stage_group_moments"](spark, str(tmp_path)).collect()}
    data = rows.select("label", "embedding").collect()
    x, g = np.array([r["embedding"] for r in data], dtype=float), np.array([r["label"] for r in data])
    assert x.shape[1] == 64 and len(got) == len(set(g.tolist())) * 64 * 64 and min(g) < 0 and max(g) > 9
    for s in set(g.tolist()):
        want = x[g == s].T @ x[g == s] / (g == s).sum()
        assert max(abs(got[s, i, j] - want[i, j]) for i in range(64) for j in range(64)) < 2e-6
