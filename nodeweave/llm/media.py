"""Operator 10, media columns: texts as sampled sound, its spectrum and peak-pair fingerprints.

A text's UTF-8 bytes, padded with zeros to a positive multiple of 64, become the 8-bit samples of
a one-channel WAV file in a binary column of a table in the shared folder. The table is read again, its files by the wave module, and
everything is computed from what was read: short-time Fourier transforms, the strongest bin of
each band and frame, and pairs of peaks close in time. A pair is one long: the earlier peak's
frame, both bins and the frames between them, so an array of pairs is a time-coded landmark list.

Frames overlap by half, so what a window's edge hides is in the middle of the next. Peaks are paired with those of the
same frame and of the next ones, so a text of a single frame has pairs too.

Null texts are empty (64 zero bytes). Equal texts give equal values. Other columns are ignored;
an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from .encode import slices
from .store import materialize, small_batches, texts

WINDOW, HOP, RATE = 512, 256, 8000
#: First bins of the bands, and the last band's end; bin 0 is left out.
BANDS = (1, 16, 48, 112, 257)
#: A peak is paired with those of so many following frames.
FAN_OUT = 2
SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def payload(data: bytes) -> bytes:
    """Zero-padded to a positive multiple of 64."""
    return data + bytes(-len(data) % 64 if data else 64)


def to_wav(samples: bytes, rate: int = RATE) -> bytes:
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(rate)
        w.writeframes(samples)
    return out.getvalue()


def from_wav(stored: bytes) -> bytes:
    with wave.open(io.BytesIO(stored), "rb") as w:
        if w.getnchannels() != 1 or w.getsampwidth() != 1:
            raise ValueError("one channel of 8-bit samples is expected")
        return w.readframes(w.getnframes())


def spectrum(samples: bytes):
    """Magnitudes, frames by bins, of the windowed short-time Fourier transform."""
    import numpy as np

    x = np.frombuffer(samples, np.uint8).astype(np.float32) - 128
    frames = max(1, -(-(len(x) - WINDOW) // HOP) + 1)
    x = np.concatenate([x, np.zeros((frames - 1) * HOP + WINDOW - len(x), np.float32)])
    rows = np.lib.stride_tricks.sliding_window_view(x, WINDOW)[::HOP]
    return np.abs(np.fft.rfft(rows * np.hanning(WINDOW).astype(np.float32), axis=1))


def landmarks(samples: bytes):
    """Peak pairs as int64: frame << 32 | bin << 20 | later bin << 8 | frames between."""
    import numpy as np

    mag = np.round(spectrum(samples), 2)  # equal samples give equal peaks on any machine
    peaks = np.stack([a + mag[:, a:b].argmax(axis=1) for a, b in zip(BANDS, BANDS[1:], strict=False)], axis=1).astype(np.int64)
    t = np.arange(len(peaks), dtype=np.int64)
    low, high = np.triu_indices(peaks.shape[1], 1)
    out = [((t[:, None] << 32) | (peaks[:, low] << 20) | (peaks[:, high] << 8)).reshape(-1)]
    for gap in range(1, FAN_OUT + 1):
        if len(peaks) > gap:
            a, b = peaks[:-gap, :, None], peaks[gap:, None, :]
            out.append(((t[:-gap, None, None] << 32) | (a << 20) | (b << 8) | gap).reshape(-1))
    return np.sort(np.concatenate(out))


def media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media (a WAV file): what a media table stores; map-only."""
    small_batches(docs.sparkSession)

    def run(batches) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            doc, text = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lo, hi in slices(text):
                raw = [t.encode("utf-8", "replace") for t in text[lo:hi]]
                yield pa.RecordBatch.from_arrays([pa.array(doc[lo:hi], pa.int64()), pa.array([len(x) for x in raw], pa.int64()), pa.array([to_wav(payload(x)) for x in raw], pa.binary())], names=["doc_id", "n_bytes", "media"])

    return texts(docs).mapInArrow(run, "doc_id long, n_bytes long, media binary")


def features(table: DataFrame, keep: bool = False) -> DataFrame:
    """SCHEMA's columns from a media table's files and, with ``keep``, the file and its landmarks (array); map-only."""
    small_batches(table.sparkSession)

    def run(batches) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            rows = []
            for d, n, stored in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                stored = stored.as_py()
                back = from_wav(stored)
                marks = landmarks(back)
                feature = f"{len(marks)}:{hashlib.sha256(marks.astype('<i8').tobytes()).hexdigest()}"
                row = (d, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), feature)
                rows.append((*row, stored, marks) if keep else row)
            if rows:
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary(), pa.list_(pa.int64())]
                names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media", "landmarks"]
                cols = [pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=False)]
                yield pa.RecordBatch.from_arrays(cols, names=names[: len(cols)])

    return table.select("doc_id", "n_bytes", "media").mapInArrow(run, SCHEMA + (", media binary, landmarks array<long>" if keep else ""))


def store(docs: DataFrame) -> DataFrame:
    """The media table of all documents, written to the shared folder and read from there."""
    return materialize(media(docs), "media", compression="zstd")


def op10_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all documents."""
    return features(store(spark.read.parquet(f"{sf_dir}/documents.parquet")))
