"""Near copies that windows and leaders alone miss, against brute force over all pairs."""

import itertools
import random

from nodeweave.llm import neardup

WORDS = [f"w{i}" for i in range(5000)]


def prose(rng, n):
    return [rng.choice(WORDS) for _ in range(n)]


def brute_groups(texts, least=0.8):
    sets = {i: frozenset(neardup.shingle_hashes(t.lower().encode().split()).tolist()) for i, t in texts.items()}
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in itertools.combinations(sorted(texts), 2):
        if len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return {i: find(i) for i in texts}


def found(spark, texts):
    rows = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    return {r["doc_id"]: r["component_id"] for r in neardup.near_groups(rows).collect()}


def test_pairs_in_a_bucket_of_hundreds(spark):
    """Near pairs whose common windows all lie in two passages that 400 texts hold."""
    rng = random.Random(11)
    passages = [prose(rng, 60) for _ in range(2)]
    ids, texts = list(range(400)), {}
    rng.shuffle(ids)
    for i in range(200):
        own = prose(rng, 30)
        changed = list(own)
        changed[rng.randrange(5, 25)] = "edit"
        for k, part in enumerate((own, changed)):
            texts[ids[2 * i + k]] = " ".join(passages[0] + part + passages[1])
    want = brute_groups(texts)
    assert len(set(want.values())) == 200
    assert found(spark, texts) == want


def test_pairs_of_short_texts(spark):
    """A word added before and after, or one changed, at 9 to 30 words; and similarities just above and below 0.8."""
    rng = random.Random(12)
    texts = {}
    for n in (9, 12, 14, 16, 18, 20, 24, 30):
        for _ in range(30):
            base = prose(rng, n)
            texts[len(texts)] = " ".join(base)
            texts[len(texts)] = " ".join(["before", *base, "after"])
    for n in (9, 19, 30):
        for _ in range(10):
            base = prose(rng, n)
            texts[len(texts)] = " ".join(base)
            texts[len(texts)] = " ".join([*base, "after"])
    want = brute_groups(texts)
    pairs = sum(i != r for i, r in want.items())
    assert pairs >= 220
    assert found(spark, texts) == want
