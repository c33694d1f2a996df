"""Operator 7, toxicity: a factorization machine over hashed terms.

Terms are a document's distinct lower-cased words and their prefixes of 3 to 7 letters, hashed into
``SPACE`` buckets. The machine has a weight and a factor vector for every bucket; none is left out for
having no effect alone, so two terms that mean little apart can mean much together. It is learned
from a bounded sample of labelled rows in small batches, ``ROUNDS`` times through, by one task on an executor (changes
of tasks side by side, added or averaged, gave worse machines). Weights and factors follow a proximal rule
that holds them at zero until the evidence of many rows outgrows a threshold (for a factor vector by
its norm), so the machine that is broadcast for scoring is small. Scores are map-only over whole texts.

Null and empty texts get the score of a document without terms. Without usable labels of both classes there
is no machine and every row scores 0.0. Labels, lang, source and doc_id are no inputs. Repeated rows score alike
(for learning, rows of one doc_id in the sample each count); other columns are ignored; an empty
table gives no rows. Texts of any length are read whole.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .encode import forget, slices
from .store import materialize, remove, small_batches, texts

#: Bound on the labelled sample (rows of least hash), and parts of the hashes that are taken whole.
TRAIN_ROWS, HASH_PARTS = 20_000, 4096
SPACE = 1 << 18
PREFIXES = (3, 4, 5, 6, 7)
FACTORS = 4
THRESHOLD = 0.3
#: Times through the sample.
ROUNDS = 4
_WORD = re.compile(r"\w+")
MEMO = 400_000


def terms(unit: str) -> set[int]:
    """Hashed terms of the words in a lower-cased unit."""
    out: set[int] = set()
    for word in _WORD.findall(unit):
        out.add(zlib.crc32(b"=" + word.encode("utf-8", "replace")) % SPACE)
        out.update(zlib.crc32(word[:n].encode("utf-8", "replace")) % SPACE for n in PREFIXES if len(word) >= n)
    return out


@dataclass(frozen=True)
class Learning:
    """Thresholds and rates of the weights (l1, rate) and of the factors (l1_factors, rate_factors).

    A threshold grows with the root of the number of rows (``spread``), as sums of gradients that tell nothing do, but is
    not below its value here: a few rows are no evidence.
    """

    l1: float = 5.0
    rate: float = 0.3
    l1_factors: float = 15.0
    spread: float = 0.018
    rate_factors: float = 0.1
    batch: int = 32
    start: float = 0.02

    def grown(self, rows: int) -> float:
        return max(1.0, self.spread * rows**0.5)


class Machine:
    """Sums of the proximal rule per bucket, from which weights and factors follow.

    ``z`` and ``n`` are the sums of gradients (less the rule's own correction) and of their squares. Factors begin at a
    fixed pattern of plus and minus ``start``, as all-zero factors have no gradient.
    """

    def __init__(self, prior: float, rows: int, learning: Learning = Learning(), factors: int = FACTORS):
        import numpy as np

        self.learning = learning
        self.l1, self.l1_factors = (np.float32(x * learning.grown(rows)) for x in (learning.l1, learning.l1_factors))
        self.bias = np.array([np.log(prior / (1 - prior)), 0.0])
        self.z, self.n = np.zeros(SPACE, np.float32), np.zeros(SPACE, np.float32)
        self.zv, self.nv = np.zeros((SPACE, factors), np.float32), np.zeros(SPACE, np.float32)
        self.begin = np.random.default_rng(7).choice(np.array([-learning.start, learning.start], np.float32), (SPACE, factors))

    def weights(self, at):
        import numpy as np

        o, z = self.learning, self.z[at]
        return np.where(np.abs(z) <= self.l1, 0, -(z - np.sign(z) * self.l1) * np.float32(o.rate) / (1 + np.sqrt(self.n[at])))

    def factors(self, at):
        """Learned factors, without their beginning."""
        import numpy as np

        o, z = self.learning, self.zv[at]
        norm = np.sqrt((z * z).sum(axis=1))
        keep = np.maximum(1 - self.l1_factors / np.maximum(norm, np.float32(1e-9)), 0)
        return -z * (keep * np.float32(o.rate_factors) / (1 + np.sqrt(self.nv[at])))[:, None]

    def learn(self, rows: list, labels, order) -> None:
        """One way through the rows (arrays of buckets) in this order."""
        import numpy as np

        o = self.learning
        for i in range(0, len(order), o.batch):
            some = [j for j in order[i : i + o.batch] if len(rows[j])]
            if not some:
                continue
            sizes = np.array([len(rows[j]) for j in some])
            starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
            every = np.concatenate([rows[j] for j in some])
            order_of = np.argsort(every, kind="stable")  # merges rows, which are sorted
            cut = np.flatnonzero(np.diff(every[order_of], prepend=-1))
            at = every[order_of[cut]]
            inside = np.empty(len(every), dtype=np.int32)
            inside[order_of] = np.repeat(np.arange(len(at), dtype=np.int32), np.diff(cut, append=len(every)))
            w, learned = self.weights(at), self.factors(at)
            v = self.begin[at] + learned
            own = np.concatenate([w[:, None], v, (v * v).sum(axis=1, keepdims=True)], axis=1)[inside]
            total = np.add.reduceat(own, starts, axis=0).astype(float)
            s = total[:, 1:-1]
            logit = self.bias[0] + total[:, 0] + 0.5 * ((s * s).sum(axis=1) - total[:, -1])
            g = 1 / (1 + np.exp(-np.clip(logit, -30, 30))) - labels[some]
            self.bias[1] += g.sum() ** 2
            self.bias[0] -= 0.1 * g.sum() / np.sqrt(self.bias[1] + 1)
            of = np.repeat(np.arange(len(some), dtype=np.int32), sizes)[order_of]
            grad = np.add.reduceat(np.concatenate([g[:, None], g[:, None] * s], axis=1).astype(np.float32)[of], cut, axis=0)
            gw = grad[:, 0]
            gv = grad[:, 1:] - v * gw[:, None]
            n = self.n[at]
            more = n + gw * gw
            self.z[at] += gw - (np.sqrt(more) - np.sqrt(n)) / o.rate * w
            self.n[at] = more
            n = self.nv[at]
            more = n + (gv * gv).sum(axis=1)
            self.zv[at] += gv - ((np.sqrt(more) - np.sqrt(n)) / o.rate_factors)[:, None] * learned
            self.nv[at] = more

    def kept(self):
        """(buckets in use, bias, weights, factors): all that scoring needs."""
        import numpy as np

        every = np.arange(SPACE)
        w, v = self.weights(every), self.factors(every)
        on = (v != 0).any(axis=1)
        used = np.flatnonzero((w != 0) | on)
        return used.tolist(), float(self.bias[0]), w[used].astype(float), np.where(on[used, None], self.begin[used] + v[used], 0).astype(float)


def train(docs: DataFrame, labels: DataFrame, train_rows: int = TRAIN_ROWS, held_out: bool = True, rounds: int = ROUNDS, learning: Learning = Learning()):
    """Learn from labelled rows outside the held-out quarter; returns (buckets in use, bias, weights, factors) or None."""
    import numpy as np

    spark = docs.sparkSession
    small_batches(spark)
    known = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).filter("toxic in (0, 1) and doc_id is not null")
    if held_out:
        known = known.filter(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 != 2)
    # Rows of least hash part by part, train_rows at most, so they may be broadcast; only the parts' sizes reach the driver.
    part = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(HASH_PARTS))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).withColumn("part", part)
    total, parts = 0, HASH_PARTS
    for row in known.groupBy("part").agg(F.count("*").alias("n")).orderBy("part").collect():
        total += row["n"]
        if total > train_rows:
            parts = row["part"]
            break
    known = known.filter(F.col("part") < parts).drop("part")

    def indexed(batches) -> Iterator:
        import pyarrow as pa

        forget()
        memo: dict[str, tuple[int, ...]] = {}
        for batch in batches:
            out = []
            for text in batch.column(1).to_pylist():
                got: set[int] = set()
                for u in set(text.lower().split()):
                    if u not in memo:
                        memo[u] = tuple(terms(u))
                    got.update(memo[u])
                if len(memo) > 50_000:
                    memo.clear()
                out.append(np.array(sorted(got), dtype="<i4").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["toxic", "at"])

    sample = texts(docs).join(F.broadcast(known), "doc_id").select("toxic", "text").mapInArrow(indexed, "toxic int, at binary")
    sample = materialize(sample, "toxic-sample")
    counts = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n0, n1 = counts.get(0, 0), counts.get(1, 0)
    if not n0 or not n1:
        remove(sample)
        return None

    def seen(batches) -> Iterator:
        import pyarrow as pa

        tally = np.zeros(SPACE, dtype=np.int64)
        for batch in batches:
            for at in batch.column(0).to_pylist():
                tally[np.frombuffer(at, "<i4")] += 1
        on = np.flatnonzero(tally)
        yield pa.RecordBatch.from_arrays([pa.array(on), pa.array(tally[on])], names=["bucket", "n"])

    # a bucket's sum grows by less than one a row and round: below the threshold for good, it can be passed over
    least = int(learning.l1 * learning.grown(n0 + n1) // rounds) + 1
    often = sample.select("at").mapInArrow(seen, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).filter(F.col("n") >= least)
    on = np.zeros(SPACE, dtype=bool)
    on[often.select("bucket").toArrow().column(0).to_numpy()] = True  # at most SPACE numbers
    prior = min(max(n1 / (n0 + n1), 1e-4), 1 - 1e-4)
    shared = spark.sparkContext.broadcast(np.packbits(on))

    def learn(batches) -> Iterator:
        import pyarrow as pa

        forget()
        mask = np.unpackbits(shared.value).astype(bool)
        rows, y = [], []
        for batch in batches:
            y += batch.column(0).to_pylist()
            for at in batch.column(1).to_pylist():
                at = np.frombuffer(at, "<i4")
                rows.append(at[mask[at]])
        machine = Machine(prior, len(rows), learning)
        for turn in range(rounds):  # an order of its own in every round, and the same on any machine
            machine.learn(rows, np.array(y, dtype=float), sorted(range(len(rows)), key=lambda j: (zlib.crc32(rows[j].tobytes(), turn), y[j])))
        used, bias, w, v = machine.kept()
        yield pa.RecordBatch.from_arrays([pa.array([bias]), pa.array([used], pa.list_(pa.int64())), pa.array([w], pa.list_(pa.float64())), pa.array([v.reshape(-1)], pa.list_(pa.float64()))], names=["bias", "used", "w", "v"])

    got = sample.coalesce(1).mapInArrow(learn, "bias double, used array<long>, w array<double>, v array<double>").first()
    remove(sample)
    return list(got["used"]), got["bias"], np.array(got["w"]), np.array(got["v"]).reshape(-1, FACTORS)


def score(docs: DataFrame, model, threshold: float = THRESHOLD) -> DataFrame:
    """All columns of ``docs`` with score (0 to 1) and predicted; ``text`` is scored whole."""
    small_batches(docs.sparkSession)
    if model is None:
        return docs.withColumn("score", F.lit(0.0)).withColumn("predicted", F.lit(0))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kept_columns = [c for c in docs.columns if c not in ("score", "predicted")]
    source = docs.select(*kept_columns)
    text_at = kept_columns.index("text")

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        forget()
        kept, b, w, v = shared.value
        number = {t: i for i, t in enumerate(kept)}
        clean: set[str] = set()
        hits: dict[str, tuple[int, ...]] = {}
        for batch in batches:
            text = batch.column(text_at).to_pylist()
            out = []
            for lo, hi in slices([t or "" for t in text]):
                for t in text[lo:hi]:
                    got: set[int] = set()
                    for u in set((t or "").lower().split()).difference(clean):
                        f = hits.get(u)
                        if f is None:
                            f = tuple({number[x] for x in terms(u) if x in number})
                            if not f:
                                clean.add(u)
                                continue
                            hits[u] = f
                        got.update(f)
                    at = np.array(sorted(got), dtype=np.int64)
                    own = v[at]
                    z = b + w[at].sum() + 0.5 * (own.sum(axis=0) ** 2 - (own**2).sum(axis=0)).sum()
                    out.append(1 / (1 + float(np.exp(-np.clip(z, -30, 30)))))
                if len(clean) + len(hits) > MEMO:
                    clean, hits = set(), {}
            s = pa.array(out, pa.float64())
            cols = [batch.column(i) for i in range(batch.num_columns)]
            yield pa.RecordBatch.from_arrays([*cols, s, pa.array([int(x >= threshold) for x in out], pa.int32())], names=[*kept_columns, "score", "predicted"])

    schema = ", ".join(f"`{n}` {k}" for n, k in source.dtypes) + ", score double, predicted int"
    return source.mapInArrow(run, schema)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: every document scored, labels of the held-out quarter unused."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    rows = score(texts(docs), model)
    out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    return rows.select("doc_id", out.alias("held_out"), "score", "predicted")
