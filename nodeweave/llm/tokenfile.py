"""Operator 2, token ids as binary: patched frame-of-reference blocks with an index of block starts.

A segment holds the ids of consecutive documents (ascending doc_id) in blocks of 128 ids. A block
is its minimum, a bit width, the ids less the minimum packed at that width, and an exception list
(position, value) for those that do not fit. The width is that of the block's ``percentile``-th
smallest id, or wider where exceptions would cost more than they save. The index of block starts makes
any id range readable without decoding what lies before it.

Segments are the binary column of a Parquet table, so any store that Spark writes to holds them,
commits are atomic, and lost executors only repeat their tasks.

Layout of a segment, all little-endian: magic "PFR1"; u32 documents, blocks, ids; u64 doc_id and
u32 ids of every document; u32 block starts (blocks + 1, from the payload's first byte); payload.
A block: u32 minimum, u8 width, u8 exceptions, packed bits (most significant first), u8 positions,
u32 values less the minimum.

Null texts are empty; an empty document is its end id alone. Rows with one doc_id stay apart, in
order of their texts. Other columns are ignored. An empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .encode import encoder, slices
from .store import small_batches, texts, write_table

BLOCK = 128
MAGIC = b"PFR1"
SEGMENT_IDS = 1 << 20
SEGMENTS = "shard int, segment int, n_ids long, bytes binary"


def _pack(delta, width: int):
    """Rows of 128 numbers below 2**width as bytes."""
    import numpy as np

    if width == 0:
        return np.zeros((len(delta), 0), dtype=np.uint8)
    top = 8 if width <= 8 else 16 if width <= 16 else 32
    big = delta.astype({8: ">u1", 16: ">u2", 32: ">u4"}[top])
    if width == top:  # whole bytes
        return big.view(np.uint8)
    bits = np.unpackbits(big.view(np.uint8).reshape(len(delta), BLOCK, top // 8), axis=2)
    return np.packbits(bits[:, :, top - width :].reshape(len(delta), -1), axis=1)


def _unpack(packed, width: int):
    import numpy as np

    if width == 0:
        return np.zeros((len(packed), BLOCK), dtype=np.uint32)
    top = 8 if width <= 8 else 16 if width <= 16 else 32
    if width == top:
        return np.ascontiguousarray(packed).view({8: ">u1", 16: ">u2", 32: ">u4"}[top]).astype(np.uint32)
    bits = np.unpackbits(packed, axis=1)[:, : BLOCK * width].reshape(len(packed), BLOCK, width)
    wide = np.zeros((len(packed), BLOCK, top), dtype=np.uint8)
    wide[:, :, top - width :] = bits
    return np.packbits(wide, axis=2).reshape(len(packed), BLOCK * top // 8).view({8: ">u1", 16: ">u2", 32: ">u4"}[top]).astype(np.uint32)


def encode_segment(doc_ids: list[int], lengths: list[int], ids, percentile: float = 0.9) -> bytes:
    """One segment's bytes; ``ids`` is a uint32 array of all documents' ids in order."""
    import numpy as np

    n = len(ids)
    blocks = -(-n // BLOCK)
    full = np.concatenate([ids, np.full(blocks * BLOCK - n, ids[-1] if n else 0, dtype=np.uint32)]).reshape(blocks, BLOCK)
    low = full.min(axis=1, initial=np.iinfo(np.uint32).max)
    delta = full - low[:, None]
    need = np.frexp(delta.astype(np.float64))[1]  # bits of each number
    usual = np.sort(need, axis=1)[:, int(percentile * (BLOCK - 1))] if blocks else np.zeros(0, dtype=np.int64)
    # an exception costs 40 bits: keep the percentile's width unless the widest number's is cheaper
    widest = need.max(axis=1, initial=0)
    over = (need > usual[:, None]).sum(axis=1)
    width = np.where(over * 40 < (widest - usual) * BLOCK, usual, widest)
    parts: list[bytes] = [b""] * blocks
    for w in np.unique(width):
        rows = np.flatnonzero(width == w)
        packed = _pack(delta[rows] & np.uint32((1 << int(w)) - 1), int(w))
        for r, p in zip(rows.tolist(), packed, strict=True):
            parts[r] = p.tobytes()
    late = need > width[:, None]
    for r in np.flatnonzero(late.any(axis=1)).tolist():
        at = np.flatnonzero(late[r])
        parts[r] += at.astype(np.uint8).tobytes() + delta[r, at].astype("<u4").tobytes()
    count = late.sum(axis=1)
    head = [int(a).to_bytes(4, "little") + bytes((int(b), int(c))) for a, b, c in zip(low, width, count, strict=True)]
    starts = np.zeros(blocks + 1, dtype="<u4")
    starts[1:] = np.cumsum([len(p) + 6 for p in parts])
    table = np.array(doc_ids, dtype="<i8").tobytes() + np.array(lengths, dtype="<u4").tobytes()
    sizes = np.array([len(doc_ids), blocks, n], dtype="<u4").tobytes()
    return b"".join([MAGIC, sizes, table, starts.tobytes(), *(x for pair in zip(head, parts, strict=True) for x in pair)])


def segment_table(data: bytes):
    """doc_ids, lengths, number of ids, block starts and where the payload begins."""
    import numpy as np

    if data[:4] != MAGIC:
        raise ValueError("not a token segment")
    docs, blocks, n = np.frombuffer(data, "<u4", 3, 4).tolist()
    at = 16
    doc_ids = np.frombuffer(data, "<i8", docs, at)
    lengths = np.frombuffer(data, "<u4", docs, at + 8 * docs)
    at += 12 * docs
    return doc_ids, lengths, n, np.frombuffer(data, "<u4", blocks + 1, at), at + 4 * (blocks + 1)


def decode_segment(data: bytes, first: int = 0, last: int | None = None):
    """Ids ``first`` to ``last`` (all by default) as uint32; reads only the blocks that hold them."""
    import numpy as np

    _, _, n, starts, base = segment_table(data)
    last = n if last is None else min(last, n)
    if first >= last:
        return np.zeros(0, dtype=np.uint32)
    b0, b1 = first // BLOCK, -(-last // BLOCK)
    raw = np.frombuffer(data, np.uint8)
    at = base + starts[b0:b1].astype(np.int64)
    low = raw[at[:, None] + np.arange(4)].reshape(-1).view("<u4").astype(np.uint32)
    width, count = raw[at + 4].astype(np.int64), raw[at + 5].astype(np.int64)
    out = np.zeros((b1 - b0, BLOCK), dtype=np.uint32)
    for w in np.unique(width).tolist():
        rows = np.flatnonzero(width == w)
        out[rows] = _unpack(raw[(at[rows] + 6)[:, None] + np.arange(BLOCK * w // 8)], w)
    for r in np.flatnonzero(count).tolist():
        p = int(at[r]) + 6 + BLOCK * int(width[r]) // 8
        c = int(count[r])
        out[r, raw[p : p + c]] = raw[p + c : p + 5 * c].view("<u4") if (p + c) % 4 == 0 else np.frombuffer(data, "<u4", c, p + c)
    out += low[:, None]
    return out.reshape(-1)[first - b0 * BLOCK : last - b0 * BLOCK]


def write_tokens(docs: DataFrame, tokenizer: str, end_id: int = 2, segment_ids: int = SEGMENT_IDS, percentile: float = 0.9) -> str:
    """Encode whole texts and write segments in ascending doc_id order; returns the table's path.

    One range shuffle of the texts by doc_id; a segment is cut before a document that would
    overfill it, so memory is bounded by a segment and one document.
    """
    small_batches(docs.sparkSession)
    end = end_id.to_bytes(4, "little")

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        enc, shard = encoder(tokenizer, False), TaskContext.get().partitionId()
        ids_of: list[bytes] = []
        docs_of: list[int] = []
        held = segment = 0

        def flush():
            nonlocal held, segment
            lengths = [len(x) // 4 for x in ids_of]
            data = encode_segment(docs_of, lengths, np.frombuffer(b"".join(ids_of), "<u4"), percentile)
            row = pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([segment], pa.int32()), pa.array([held], pa.int64()), pa.array([data], pa.binary())], names=["shard", "segment", "n_ids", "bytes"])
            ids_of.clear()
            docs_of.clear()
            held, segment = 0, segment + 1
            return row

        for batch in batches:
            doc, text = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lo, hi in slices(text):
                for d, ids in zip(doc[lo:hi], enc.encode(text[lo:hi]), strict=True):
                    if held and held + len(ids) // 4 + 1 > segment_ids:
                        yield flush()
                    ids_of.append(ids + end)
                    docs_of.append(d)
                    held += len(ids) // 4 + 1
        if docs_of:
            yield flush()

    ordered = texts(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return write_table(ordered.mapInArrow(run, SEGMENTS), "token-segments")


def read_tokens(spark: SparkSession, path: str, keep_ids: bool = False) -> DataFrame:
    """Per document from the files: doc_id, start, n_tokens, ids_crc32 and, with ``keep_ids``, ids.

    ``start`` counts the ids of all documents before it: sums over shards, then over a shard's
    segments, then inside the segment.
    """
    files = spark.read.parquet(path)
    shards = files.groupBy("shard").agg(F.sum("n_ids").alias("n"))  # one row for each range partition
    earlier = shards.select("shard", F.coalesce(F.sum("n").over(W.orderBy("shard").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    within = W.partitionBy("shard").orderBy("segment").rowsBetween(W.unboundedPreceding, -1)
    index = files.select("shard", "segment", F.coalesce(F.sum("n_ids").over(within), F.lit(0)).alias("inside"))
    index = index.join(earlier, "shard").select("shard", "segment", (F.col("base") + F.col("inside")).alias("base"))
    # the index meets the documents' rows, not the segments' bytes

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for shard, segment, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                data = data.as_py()
                doc_ids, lengths, *_ = segment_table(data)
                flat = decode_segment(data).astype("<u4").tobytes()
                ends = np.cumsum(lengths, dtype=np.int64)
                parts = [flat[4 * (e - n) : 4 * e] for e, n in zip(ends.tolist(), lengths.tolist(), strict=True)]
                same = [pa.array(np.full(len(doc_ids), x, dtype=np.int32)) for x in (shard, segment)]
                cols = [*same, pa.array(doc_ids), pa.array(ends - lengths), pa.array(lengths.astype(np.int64)), pa.array([zlib.crc32(p) for p in parts], pa.int64())]
                names = ["shard", "segment", "doc_id", "inside", "n_tokens", "ids_crc32"]
                if keep_ids:
                    cols.append(pa.array(np.split(np.frombuffer(flat, "<u4").astype(np.int32), ends[:-1]), pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names=names)

    more = ["ids"] if keep_ids else []
    rows = files.select("shard", "segment", "bytes").mapInArrow(run, "shard int, segment int, doc_id long, inside long, n_tokens long, ids_crc32 long" + (", ids array<int>" if keep_ids else ""))
    return rows.join(index, ["shard", "segment"]).select("doc_id", (F.col("base") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32", *more)


def op2_tokenfile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all documents."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return read_tokens(spark, write_tokens(docs, public_tokenizers.path("word_bpe_49k.json")))
