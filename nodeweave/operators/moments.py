"""Distributed passes over signals (sample_id, x array<double>): moments and fused EM steps.

A pass is one ``mapInArrow`` over the samples, so that each task emits its sums as a few rows of
tiles, and one shuffle on the tile key that adds them. Driver and shuffle see tasks x tiles, never samples.
Sums are added in partition order, so results repeat.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.states import Options, Params, Stats, em_pass, soft_start, sums, weighted_start

#: Numbers in one tile of a flattened sum; bounds the rows that the merge handles.
TILE = 1 << 16


def batch_matrix(column) -> np.ndarray:
    """An Arrow list column as a matrix; ragged, null or non-finite input is an error."""
    p = {len(v) if v.is_valid else -1 for v in column.slice(0, 1)}.pop() if len(column) else 0
    sizes = column.value_lengths().to_numpy(zero_copy_only=False)
    if len(column) and (column.null_count or (sizes != p).any()):
        raise ValueError("signals must be arrays of one length, without nulls")
    flat = column.flatten()
    if flat.null_count:
        raise ValueError("signals hold null components")
    x = flat.to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(len(column), p)
    if not np.isfinite(x).all():
        raise ValueError("signals hold non-finite components")
    return x


def assert_uniform_length(signals: DataFrame) -> int:
    """The number of variables; raises where arrays differ, or hold nulls or non-finite numbers."""
    bad = F.exists("x", lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf")))
    r = signals.agg(F.min(F.size("x")).alias("lo"), F.max(F.size("x")).alias("hi"), F.count_if(F.col("x").isNull() | bad).alias("bad")).first()
    if r["lo"] is None or r["lo"] != r["hi"] or r["bad"]:
        raise ValueError(f"signals need arrays of one length of finite numbers, found lengths {r['lo']} to {r['hi']}, {r['bad']} bad rows")
    return int(r["lo"])


#: Variables beyond which a task's sums are large, so that few, long tasks are better than many.
WIDE = 512


def few_tasks(signals: DataFrame, variables: int) -> DataFrame:
    """The samples in at most a few tasks a core where every task's sums are large: what is shuffled is tasks x sums."""
    if variables <= WIDE:
        return signals
    return signals.coalesce(4 * signals.sparkSession.sparkContext.defaultParallelism)


def _summed(rows: DataFrame) -> dict[int, np.ndarray]:
    """Rows (slot, tile, part, v array<double>) added over parts; arrays by slot on the driver."""

    def merge(batches) -> Iterator:
        total: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            for slot, tile, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                v = v.values.to_numpy()
                total[slot, tile] = total[slot, tile] + v if (slot, tile) in total else v
        if total:
            keys = sorted(total)
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys], pa.int32()), pa.array([total[k] for k in keys], pa.list_(pa.float64()))], names=["slot", "tile", "v"])

    merged = rows.repartition("slot", "tile").sortWithinPartitions("slot", "tile", "part").select("slot", "tile", "v").mapInArrow(merge, "slot int, tile int, v array<double>")
    got = merged.toArrow()  # sums only, as Arrow buffers
    slots, tiles, values = got.column(0).to_pylist(), got.column(1).to_pylist(), got.column(2)
    out: dict[int, list] = {}
    for i in sorted(range(len(slots)), key=lambda i: (slots[i], tiles[i])):
        out.setdefault(slots[i], []).append(values[i].values.to_numpy())
    return {k: np.concatenate(v) for k, v in out.items()}


def run_sums(signals: DataFrame, make, columns: list[str]) -> dict[int, np.ndarray]:
    """Sum over batches of ``make(batch columns) -> {slot: flat array}``, in one pass."""

    def part(batches) -> Iterator:
        import os

        os.environ.setdefault("OMP_NUM_THREADS", "1")
        from pyspark import TaskContext

        total: dict[int, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            for slot, v in make(batch).items():
                total[slot] = total[slot] + v if slot in total else v
        own = TaskContext.get().partitionId()
        for slot, v in total.items():
            for tile in range(-(-len(v) // TILE)):
                yield pa.RecordBatch.from_arrays([pa.array([slot], pa.int32()), pa.array([tile], pa.int32()), pa.array([own], pa.int32()), pa.array([v[tile * TILE : (tile + 1) * TILE]], pa.list_(pa.float64()))], names=["slot", "tile", "part", "v"])

    return _summed(signals.select(*columns).mapInArrow(part, "slot int, tile int, part int, v array<double>"))


def _square(flat: np.ndarray) -> np.ndarray:
    """The symmetric matrix of an upper triangle."""
    p = int(round((np.sqrt(8 * len(flat) + 1) - 1) / 2))
    upper = np.triu_indices(p)
    out = np.zeros((p, p))
    out[upper] = flat
    out.T[upper] = flat
    return out


def gram(signals: DataFrame, mode: str = "signed") -> tuple[np.ndarray, int]:
    """Second moment (1/n) X'X and n."""

    def make(batch):
        x = batch_matrix(batch.column(0))
        return {0: np.concatenate([[len(x)], (x.T @ x)[np.triu_indices(x.shape[1])]])}

    got = run_sums(signals, make, ["x"])
    if not got:
        raise ValueError("no samples")
    a = _square(got[0][1:]) / got[0][0]
    return (np.abs(a) if mode == "absolute" else a), int(got[0][0])


def grouped_moments(signals: DataFrame, groups: int, column: str = "state") -> list[tuple[np.ndarray, int]]:
    """Second moment and size of each group 0 .. groups-1, in one pass."""

    def make(batch):
        x, g = batch_matrix(batch.column(0)), batch.column(1).to_numpy(zero_copy_only=False)
        out = {}
        for j in np.unique(g).tolist():
            own = x[g == j]
            out[int(j)] = np.concatenate([[len(own)], (own.T @ own)[np.triu_indices(x.shape[1])]])
        return out

    got = run_sums(signals, make, ["x", column])
    p = len(_square(next(iter(got.values()))[1:]))
    return [(_square(got[j][1:]) / got[j][0], int(got[j][0])) if j in got else (np.eye(p), 0) for j in range(groups)]


def sketch(signals: DataFrame, p: int, width: int = 64, seed: int = 0) -> np.ndarray:
    """Rows of the correlation matrix times a fixed random p x width matrix, in two passes; no p x p matrix anywhere.

    Distances between its rows are close to those between the rows of the correlation matrix.
    """
    squares = run_sums(signals, lambda batch: {0: (batch_matrix(batch.column(0)) ** 2).sum(axis=0)}, ["x"])[0]
    scale = 1 / np.sqrt(np.maximum(squares, 1e-300))
    mix = scale[:, None] * np.random.default_rng(seed).choice([-1.0, 1.0], (p, width)) / np.sqrt(width)
    shared = signals.sparkSession.sparkContext.broadcast(mix)  # p x width numbers

    def make(batch):
        x = batch_matrix(batch.column(0))
        return {0: (x.T @ (x @ shared.value)).reshape(-1)}

    out = run_sums(signals, make, ["x"])[0].reshape(p, width) * scale[:, None]
    shared.unpersist()
    return out


def state_passes(signals: DataFrame, params: list[Params | None], opts: list[Options], use_gram: bool, begin: bool = False, all_states: bool = True) -> list[Stats]:
    """Sums of one pass for several restarts at once.

    With ``begin`` (or None for parameters) samples have the start's states: soft random ones, or the column start_state if the signals
    have it. Without ``all_states`` the last state's gram is left out, as it follows from that of all samples.
    """
    spark = signals.sparkSession
    grouped = "start_state" in signals.columns
    shared = spark.sparkContext.broadcast((params, opts))  # states x p x k numbers, whatever the samples

    def make(batch):
        ps, os_ = shared.value
        ids, x = batch.column(0).to_numpy(), batch_matrix(batch.column(1))
        out = {}
        for slot, (p, o) in enumerate(zip(ps, os_, strict=True)):
            if begin or p is None:
                r = weighted_start(batch.column(2).to_numpy(), o.m, o.hi) if grouped and o.m > 1 else soft_start(ids, o.m, o.seed, o.hi)
                out[slot] = sums(x, r, 0.0, p, use_gram or p is None).flat()
            else:
                out[slot] = em_pass(x, p, use_gram, all_states).flat()
        return out

    got = run_sums(signals, make, ["sample_id", "x", *(["start_state"] if grouped else [])])
    shared.unpersist()
    grams = lambda p, o: (o.m if begin or p is None or all_states or o.m == 1 else o.m - 1) if use_gram or p is None else 0
    return [Stats.of(got[slot], o.m, o.k, grams(p, o)) for slot, (p, o) in enumerate(zip(params, opts, strict=True))]


def long_form(signals: DataFrame) -> DataFrame:
    """sample_id, var_id, value."""
    return signals.select("sample_id", F.posexplode("x").alias("var_id", "value"))


def sql_gram(long: DataFrame, upper: bool = True) -> DataFrame:
    """Second moment as rows (i, j, value) from the long form, by a self-join on the sample: a teaching path for few variables."""
    a, b = long.alias("a"), long.alias("b")
    on = (F.col("a.sample_id") == F.col("b.sample_id")) & ((F.col("a.var_id") <= F.col("b.var_id")) if upper else F.lit(True))
    n = long.agg(F.countDistinct("sample_id").alias("n"))
    pairs = a.join(b, on).groupBy(F.col("a.var_id").alias("i"), F.col("b.var_id").alias("j")).agg(F.sum(F.col("a.value") * F.col("b.value")).alias("s"))
    return pairs.crossJoin(F.broadcast(n)).select("i", "j", (F.col("s") / F.col("n")).alias("value"))  # n is one row


def tiled_gram(signals: DataFrame, block: int = 512) -> DataFrame:
    """Second moment as blocks (bi, bj, rows, cols, values) for many variables; the driver never holds it all."""

    def part(batches) -> Iterator:
        total: dict[tuple[int, int], np.ndarray] = {}
        n = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch_matrix(batch.column(0))
            n += len(x)
            cuts = range(0, x.shape[1], block)
            for i in cuts:
                for j in cuts:
                    if j >= i:
                        v = x[:, i : i + block].T @ x[:, j : j + block]
                        key = (i // block, j // block)
                        total[key] = total[key] + v if key in total else v
        for (bi, bj), v in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([bi], pa.int32()), pa.array([bj], pa.int32()), pa.array([v.shape[0]], pa.int32()), pa.array([v.shape[1]], pa.int32()), pa.array([n], pa.int64()), pa.array([v.reshape(-1)], pa.list_(pa.float64()))], names=["bi", "bj", "rows", "cols", "n", "v"])

    parts = signals.select("x").mapInArrow(part, "bi int, bj int, rows int, cols int, n long, v array<double>")

    def merge(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total, shape = 0, None, None
        for batch in batches:
            for r, c, m, v in zip(batch.column("rows").to_pylist(), batch.column("cols").to_pylist(), batch.column("n").to_pylist(), batch.column("v"), strict=True):
                v, shape = v.values.to_numpy(), (r, c)
                total = v if total is None else total + v
                n += m
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([key[1].as_py()], pa.int32()), pa.array([shape[0]], pa.int32()), pa.array([shape[1]], pa.int32()), pa.array([total / n], pa.list_(pa.float64()))], names=["bi", "bj", "rows", "cols", "v"])

    return parts.groupBy("bi", "bj").applyInArrow(merge, "bi int, bj int, rows int, cols int, v array<double>")
