"""Operator 8, exact top-k by inner product over an impact-ordered index, score at a time.

Vectors become integers, floor(256 x). The base is dealt into blocks; each block is an inverted
index: per dimension, postings grouped into segments of one quantised level. For a query, a
segment's impact is what its level adds to the score above the dimension's worst level, so impacts
are never negative. Queries go in small batches, each segment adding to all of a batch in one
stroke; segments are processed by descending impact (the greatest in the batch) into one
accumulator per vector and query. A vector's score lies within its accumulator, plus the largest impacts not yet processed, plus or minus
the product of the norms of the query and of what rounding left of the vector, plus or minus a bound on what the
accumulator's own arithmetic loses, which grows with the impacts. Processing stops only when that proves all but a
few vectors out; those few are scored exactly. If no proof comes, all that may belong are scored.

Rows are dealt to blocks evenly, whatever their ids. First every query meets one block; the k-th best score found there
is a floor under its final one, with which the other blocks prove more rows out, sooner. Queries then meet the
other blocks block by block: per pair of blocks each query keeps k rows at most, so what is shuffled is queries x blocks x k rows,
and a block of the base is fetched once for every ``QUERY_ROWS`` queries.

Vectors that are null or empty, hold null or non-finite components
or differ in length from the query take no part (lengths are compared within a block pair). Ties go to the smaller
vec_id. Repeated vec_ids: a query's own vec_id is never its candidate; the scores of all rows
of a repeated query are ranked together. Integers beyond
2**52 either way are held there; a score beyond a long is shown as the nearest long, but ranked by its exact value. Other
columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .store import materialize

#: A segment spans 2**LEVEL_BITS integers of a component, or more where a block's components reach far.
LEVEL_BITS, LEVELS = 3, 128
#: Candidates that may be left for exact scores when processing stops early.
RESCORE = 64
#: Parts of the segments after which a proof is tried.
PROOFS = (0.6, 0.8, 1.0)
BASE_ROWS, QUERY_ROWS, BATCH = 8192, 8192, 128
#: Blocks of queries that are aimed at where there are few queries, so that all tasks have work.
QUERY_BLOCKS = 4
#: Largest integer of a component, and the bits of a score's lower part.
LARGEST, LOW_BITS = 1 << 52, 62


class ImpactIndex:
    """One block of integer vectors as postings by dimension and level."""

    def __init__(self, ids, vectors):
        import numpy as np

        self.ids, self.vectors = ids, vectors
        reach = int(vectors.max()) - int(vectors.min()) if vectors.size else 0
        self.bits = max(LEVEL_BITS, reach.bit_length() - LEVELS.bit_length() + 1)
        level = vectors >> self.bits
        step = 1 << self.bits
        self.low, self.high = level.min(axis=0), level.max(axis=0)
        middle = level * step + (step - 1) / 2
        self.left_over = np.sqrt(((vectors - middle) ** 2).sum(axis=1)) * (1 + 1e-9)
        self.most = int(max(abs(int(vectors.min())), abs(int(vectors.max())))) if vectors.size else 0
        dim, lev, rows = [], [], []
        for d in range(vectors.shape[1]):
            by = np.argsort(level[:, d], kind="stable")
            cut = np.flatnonzero(np.diff(level[by, d])) + 1
            for part in np.split(by, cut):
                dim.append(d)
                lev.append(int(level[part[0], d]))
                rows.append(part)
        self.dim, self.level, self.rows = np.array(dim), np.array(lev), rows

    def exact(self, rows, query) -> list[int]:
        """Exact inner products; Python's integers where a long may not do."""
        import numpy as np

        if self.most * int(np.abs(query).max(initial=0)) * len(query) < 1 << 62:
            return (self.vectors[rows] @ query).tolist()
        return (self.vectors[rows].astype(object) @ query.astype(object)).tolist()

    def top(self, queries, own_ids, k: int, floors=None):
        """For each query of a batch, ids and exact scores of the k best, in order.

        ``floors``: scores (None: none) below which no row can be among a query's k best; such rows may be left out.
        """
        import numpy as np

        n, dims = self.vectors.shape
        step = float(1 << self.bits)
        q = queries.astype(np.float64)  # batch x dims; exact, as integers stay within 2**52
        up = q.T >= 0
        gain = np.where(up[self.dim], (self.level - self.low[self.dim])[:, None], (self.high[self.dim] - self.level)[:, None])
        impact = (np.abs(q.T)[self.dim] * gain * step).astype(np.float32)  # segments x batch
        order = np.argsort(-impact.max(axis=1), kind="stable")
        impact = np.ascontiguousarray(impact[order])
        worst = (q.T * (np.where(up, self.low[:, None], self.high[:, None]) * step + (step - 1) / 2)).sum(axis=0)
        norm = np.sqrt((q * q).sum(axis=1)) * (1 + 1e-9)
        acc = np.zeros((n, len(q)), dtype=np.float32)
        rows, by_dim = self.rows, self.dim[order]
        largest = np.abs(q.T) * ((self.high - self.low) * step)[:, None]
        # a vector's sum has one addend per dimension, each with two roundings of 2**-24 of at most all of it
        rounding = (dims + 4) * 2.0**-22 * largest.sum(axis=0) + 2.0**-40 * np.abs(worst) + 1
        segments, out, waiting, done = order.tolist(), {}, list(range(len(q))), 0
        for part in PROOFS:
            upto = int(len(segments) * part) if part < 1 else len(segments)
            for i in range(done, upto):
                acc[rows[segments[i]]] += impact[i]
            done = upto
            # the largest impact of each dimension from here on
            ahead = np.zeros(len(q))
            if done < len(segments):
                by = np.argsort(by_dim[done:], kind="stable")
                cut = np.flatnonzero(np.diff(by_dim[done:][by], prepend=-1))
                ahead = np.maximum.reduceat(impact[done:][by], cut, axis=0).sum(axis=0, dtype=np.float64)
            for j in list(waiting):
                mine = self.ids == own_ids[j]
                wanted = min(k, n - int(mine.sum()))
                if wanted <= 0:
                    out[j] = [], []
                    waiting.remove(j)
                    continue
                slack = self.left_over * norm[j] + rounding[j]
                sums = acc[:, j] + worst[j]
                least = np.where(mine, -np.inf, sums - slack)
                # the k-th best score is at least the k-th best lower bound
                kth = np.partition(least, n - wanted)[n - wanted]
                if floors is not None and floors[j] is not None:
                    kth = max(kth, floors[j] - 1e-9 * abs(floors[j]) - 1)
                possible = np.flatnonzero((sums + slack + ahead[j] >= kth) & ~mine)
                if len(possible) <= max(RESCORE, 2 * k) or done == len(segments):
                    score = self.exact(possible, queries[j])
                    ids = self.ids[possible].tolist()
                    best = sorted(range(len(ids)), key=lambda i: (-score[i], ids[i]))[:k]  # noqa: B023
                    out[j] = [ids[i] for i in best], [score[i] for i in best]
                    waiting.remove(j)
            if not waiting:
                break
        return [out[j] for j in range(len(q))]


def quantised(vectors: DataFrame) -> DataFrame:
    """vec_id and v array<long> = floor(256 * x) with x as double; rows that take no part are left out."""
    x = F.transform("embedding", lambda e: e.cast("double"))
    bad = F.exists(x, lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == F.lit(float("inf"))))
    ok = F.col("embedding").isNotNull() & F.col("vec_id").isNotNull() & (F.size("embedding") > 0) & ~F.coalesce(bad, F.lit(True))
    held = lambda e: F.least(F.greatest(F.floor(e * 256), F.lit(-LARGEST)), F.lit(LARGEST))
    return vectors.filter(ok).select("vec_id", F.transform(x, held).alias("v"))


def _blocks(rows: DataFrame, name: str, size: int, n: int, *more: str) -> DataFrame:
    """Rows dealt evenly into blocks of about ``size``, each one row of its number and an array of rows; written, as it is read again."""
    count = max(1, -(-n // size))
    spread = F.pmod(F.monotonically_increasing_id(), F.lit(count)).cast("int")
    packed = rows.withColumn(name, spread).groupBy(name).agg(F.collect_list(F.struct("vec_id", "v", *more)).alias(f"{name}_rows"))
    return materialize(packed, f"{name}-blocks")


def _halves(score: Column) -> Column:
    """A score's two parts as one long, the nearest where it does not fit."""
    fits = score["hi"].between(-2, 1)
    whole = score["hi"] * F.lit(1 << (LOW_BITS - 1)) * 2 + score["lo"]
    return F.when(fits, whole).when(score["hi"] > 0, F.lit((1 << 63) - 1)).otherwise(F.lit(-(1 << 63)))


def _search(pairs: DataFrame, k: int) -> DataFrame:
    """query_row, query_id, vec_id and score (hi, lo) of the k best of every block pair (asked_rows, base_rows)."""

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        def arrays(cell):
            """Ids, vectors and other fields of a block's rows by vector length."""
            rows = cell.values
            ids, v = rows.field("vec_id").to_numpy(), rows.field("v")
            more = [rows.field(n).to_pylist() for n in ("query_row", "floor") if rows.type.get_field_index(n) >= 0]
            sizes = np.diff(v.offsets.to_numpy())
            flat, ends = v.values.to_numpy(), v.offsets.to_numpy()
            out = {}
            for n in np.unique(sizes).tolist():
                own = np.flatnonzero(sizes == n)
                out[n] = (ids[own], flat[ends[own][:, None] + np.arange(n)], *[[m[i] for i in own.tolist()] for m in more])
            return out

        last_rows, index = None, {}
        for batch in batches:
            for ask, rows in zip(batch.column(0), batch.column(1), strict=True):
                if last_rows is None or not rows.equals(last_rows):
                    last_rows, index = rows, {n: ImpactIndex(*x[:2]) for n, x in arrays(rows).items()}
                out = [[], [], [], [], []]
                for n, (ids, vs, row, *floor) in arrays(ask).items():
                    if n not in index:
                        continue
                    for i in range(0, len(ids), BATCH):
                        own = ids[i : i + BATCH].tolist()
                        under = floor[0][i : i + BATCH] if floor else None
                        for at, o, (got, score) in zip(row[i : i + BATCH], own, index[n].top(vs[i : i + BATCH], own, k, under), strict=True):
                            out[0] += [at] * len(got)
                            out[1] += [o] * len(got)
                            out[2] += got
                            out[3] += [s >> LOW_BITS for s in score]
                            out[4] += [s & ((1 << LOW_BITS) - 1) for s in score]
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], names=["query_row", "query_id", "vec_id", "hi", "lo"])

    return pairs.mapInArrow(run, "query_row long, query_id long, vec_id long, hi long, lo long")


def _best(found: DataFrame, k: int, by: str = "query_row") -> DataFrame:
    order = W.partitionBy(by).orderBy(F.desc("hi"), F.desc("lo"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score: the k best base rows of every query (quantised frames)."""
    n, m = vectors.count(), queries.count()
    base = _blocks(vectors, "base", BASE_ROWS, n)
    asked = materialize(queries.withColumn("query_row", F.monotonically_increasing_id()), "asked-rows")
    size = min(QUERY_ROWS, max(256, -(-m // QUERY_BLOCKS)))
    first = _blocks(asked, "asked", size, m, "query_row")
    # block pairs (blocks, not rows, are crossed); the first block of the base gives every query a floor. The number of
    # partitions is given, as little data is much work here and would be merged into few tasks
    parts = min(20_000, 4 * max(1, -(-n // BASE_ROWS)))

    def crossed(blocks: DataFrame, part: DataFrame) -> DataFrame:
        every = blocks.crossJoin(part.select("base")).repartition(parts, "base")
        return every.join(part.repartition(parts, "base"), "base").select("asked_rows", "base_rows")

    begun = materialize(_best(_search(first.crossJoin(base.filter("base = 0")).repartition(4 * QUERY_BLOCKS, "asked").select("asked_rows", "base_rows"), k), k).drop("rank"), "begun")
    found = begun
    if n > BASE_ROWS:
        kth = begun.groupBy("query_row").agg(F.count("*").alias("n"), F.min(F.struct("hi", "lo")).alias("s")).filter(F.col("n") == k)
        floors = kth.select("query_row", (F.col("s.hi") * F.lit(2.0**LOW_BITS) + F.col("s.lo")).alias("floor"))
        again = _blocks(asked.join(floors, "query_row", "left"), "asked", size, m, "query_row", "floor")
        found = begun.unionByName(_search(crossed(again, base.filter("base > 0")), k))
    ranked = _best(found, k, "query_id")
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", _halves(F.struct("hi", "lo")).alias("score"))


def op8_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query: every row whose vec_id is divisible by 50 against all rows."""
    rows = quantised(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    return top_k(rows, rows.filter(F.col("vec_id") % 50 == 0), 5)


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s
)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5
"""
