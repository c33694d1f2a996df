"""Streams of events to binned signals, state scores, dwell times and a model that follows the data."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.states import Options, Params, Stats, m_step
from ..operators.model import NetworkModel

EVENTS = "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Events from Parquet files as they arrive."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def windowed_bins(events: DataFrame, late: str = "1 hour", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Sums per type and window; rows later than the watermark are dropped."""
    win = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy(win.alias("w"), "event_type").agg(F.sum("value").alias("value"), F.count("*").alias("n"))


def session_bins(events: DataFrame, late: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    """Sums per user and session."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.sum("value").alias("value"), F.count("*").alias("n"))


def score_stream(signals: DataFrame, model: NetworkModel) -> DataFrame:
    """State probabilities of streamed signals under a fixed model; stateless."""
    return model.transform(signals)


def dwell_stream(states: DataFrame) -> DataFrame:
    """(unit, state, steps, closed): steps of each unit's current spell, one row whenever a spell ends or a batch does."""

    def update(key, frames: Iterator, held):
        import pandas as pd

        state, steps = held.get if held.exists else (None, 0)
        out = []
        for s in pd.concat(list(frames)).sort_values("step")["state"]:  # a unit's steps of one micro-batch
            if state is not None and s != state:
                out.append((key[0], int(state), int(steps), True))
                steps = 0
            state, steps = int(s), steps + 1
        held.update((int(state), int(steps)))
        out.append((key[0], int(state), int(steps), False))
        yield pd.DataFrame(out, columns=["unit", "state", "steps", "closed"])

    return states.groupBy("unit").applyInPandasWithState(update, "unit long, state int, steps long, closed boolean", "state int, steps long", "append", "NoTimeout")


def spell_join(events: DataFrame, spells: DataFrame, late: str = "1 hour") -> DataFrame:
    """Stream-stream join: events (unit, ts) inside spells (unit, begin, end) of at most a day."""
    e = events.withWatermark("ts", late)
    s = spells.withWatermark("begin", late).withColumnRenamed("unit", "s_unit")
    return e.join(s, F.expr("unit = s_unit AND ts >= begin AND ts <= end AND ts <= begin + INTERVAL 1 DAY"))


class OnlineMixture:
    """State mixture over micro-batches: sums decay by ``decay`` and the M step follows each batch.

    ``update`` is what foreachBatch calls; a batch id that was seen is ignored, so retries change nothing. With ``path`` the
    parameters, sums and last batch id are written there after every batch, and an object made with the same path
    goes on from the last one: a restarted stream loses nothing. ``start_from``: parameters before the first batch
    (by default from the first batch itself).
    """

    def __init__(self, options: Options, decay: float = 0.9, path: str | None = None, start_from: Params | None = None):
        self.options, self.decay, self.path = options, decay, path
        self.params: Params | None = start_from
        self.stats: Stats | None = None
        self.seen = -1
        self._read = path is None

    def _resume(self, spark: SparkSession) -> None:
        """Take up the state of the greatest batch id, if there is any."""
        if self._read:
            return
        self._read = True
        jvm, conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        folder = jvm.org.apache.hadoop.fs.Path(self.path)
        if not folder.getFileSystem(conf).exists(folder):
            return
        row = spark.read.schema("batch long, state binary").parquet(self.path).orderBy(F.desc("batch")).first()
        if row is not None:
            self.seen = row["batch"]
            self.options, self.params, self.stats = pickle.loads(bytes(row["state"]))

    def _keep(self, spark: SparkSession) -> None:
        if self.path is not None:
            state = pickle.dumps((self.options, self.params, self.stats))
            spark.createDataFrame([(self.seen, bytearray(state))], "batch long, state binary").coalesce(1).write.mode("append").parquet(self.path)

    def update(self, batch: DataFrame, batch_id: int) -> None:
        from ..functions.states import absolute_penalty, start_params
        from ..operators import moments

        self._resume(batch.sparkSession)
        if batch_id <= self.seen or batch.limit(1).count() == 0:
            return
        if self.params is None:
            total = moments.state_passes(batch, [None], [self.options], True)[0]
            self.options = absolute_penalty(total.gram.sum(axis=0) / max(float(total.mass.sum()), 1e-12), self.options)
            self.params = m_step(total, start_params(total, self.options), self.options)
        new = moments.state_passes(batch, [self.params], [self.options], True)[0]
        old = self.stats
        self.stats = new if old is None else Stats(new.mass + self.decay * old.mass, new.square + self.decay * old.square, new.nll, new.n, new.gram + self.decay * old.gram)
        self.params = m_step(self.stats, self.params, self.options)
        self.seen = batch_id
        self._keep(batch.sparkSession)

    def model(self) -> NetworkModel:
        return NetworkModel(self.params, self.stats.mass, self.stats.nll)

    def start(self, stream: DataFrame, checkpoint: str):
        """The running query; its state goes to ``path``, or beside the checkpoint where none was given."""
        if self.path is None:
            self.path, self._read = f"{checkpoint.rstrip('/')}-model", False
        return stream.writeStream.foreachBatch(self.update).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
