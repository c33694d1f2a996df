"""Near-dedup judges rows, not doc_ids."""

import random

import pytest

WORDS = [f"w{i}" for i in range(3000)]


@pytest.mark.parametrize("order", [1, 2])
def test_repeated_doc_ids(spark, order):
    import corpus_pipeline

    rng = random.Random(order)
    a, b, c, d = (" ".join(rng.choice(WORDS) for _ in range(120)) for _ in range(4))
    docs = [(1, a), (5, a + " more"), (5, b), (7, c), (7, c), (7, c), (8, c), (9, d), (9, d + " more"), (3, b + " x"), (None, d), (10, None)]
    rng.shuffle(docs)
    frame = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(docs)], "doc_id long, text string, mark int").repartition(3)
    got = corpus_pipeline.drop_copies(spark, frame, "")
    assert got.columns == frame.columns
    rows = sorted((r["doc_id"], r["text"] or "") for r in got.collect())
    assert [i for i, _ in rows] == [1, 3, 7, 9, 10]
    assert rows[0][1] == a and rows[1][1] == b + " x" and rows[2][1] == c and rows[3][1] in (d, d + " more")


def test_unlike_text_under_a_copy_s_doc_id_stays(spark):
    import corpus_pipeline

    rng = random.Random(3)
    a, b = (" ".join(rng.choice(WORDS) for _ in range(120)) for _ in range(2))
    frame = spark.createDataFrame([(1, a), (5, a), (5, b)], "doc_id long, text string")
    assert sorted(map(tuple, corpus_pipeline.drop_copies(spark, frame, "").collect())) == [(1, a), (5, b)]
