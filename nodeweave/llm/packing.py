"""Operator 1, packing: shortest-pack-first over the histogram of piece lengths.

Documents are cut into whole sequences and one rest each. Only the histogram of lengths (at most
``capacity`` numbers, whatever the input) reaches the driver. It is packed there, longest length
first, each time into the packs that are least full, by counts of packing patterns and never by
single pieces. Pieces then find their place by rank: the n-th piece of a length takes the n-th
slot that the patterns hold for that length.

Null texts are empty; an empty document is its end id alone. Repeated doc_id rows are pieces of
their own. Other columns are ignored. An empty table gives no rows.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right
from collections import defaultdict
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .encode import encoder, slices
from .store import fresh, materialize, small_batches, texts

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def pieces(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 1, keep_ids: bool = False, memo: float = 1.0) -> DataFrame:
    """Cut every document's ids into pieces of at most ``capacity``; map-only.

    Returns doc_id, start, length, ids_crc32, doc_tokens and, with ``keep_ids``, the ids as
    little-endian unsigned 32-bit integers. ``memo``: part of the encoder's memos that a worker may fill.
    """
    end = end_id.to_bytes(4, "little")

    def run(batches) -> Iterator:
        import pyarrow as pa

        enc = encoder(tokenizer, True)
        enc.share = memo
        for batch in batches:
            doc, text = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lo, hi in slices(text):
                rows = []
                for d, ids in zip(doc[lo:hi], enc.encode(text[lo:hi]), strict=True):
                    ids += end
                    n = len(ids) // 4
                    for start in range(0, n, capacity):
                        part = ids[4 * start : 4 * (start + capacity)]
                        rows.append((d, start, len(part) // 4, zlib.crc32(part), n, part))
                cols = [list(c) for c in zip(*rows, strict=True)]
                kinds = [pa.int64()] * 5 + [pa.binary()]
                k = 6 if keep_ids else 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols[:k], kinds[:k], strict=True)], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "ids"][:k])

    return texts(docs).mapInArrow(run, PIECES + (", ids binary" if keep_ids else ""))


def pack_histogram(histogram: dict[int, int], capacity: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Packing patterns for the counts of lengths: (how often, [(length, times in the pack), ...]).

    Lengths are placed from longest to shortest; each goes to the open packs with most room. A
    pattern stands for all packs alike, so the work depends on the number of lengths alone.
    """
    by_room: dict[int, list[list]] = defaultdict(list)
    rooms: list[int] = []  # sorted rooms in use

    def add(room: int, count: int, parts: tuple) -> None:
        if room not in by_room or not by_room[room]:
            at = bisect_right(rooms, room)
            if at == 0 or rooms[at - 1] != room:
                rooms.insert(at, room)
        by_room[room].append([count, parts])

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        if not 0 < length <= capacity:
            raise ValueError(f"a piece of {length} ids does not fit {capacity}")
        while left:
            if rooms and rooms[-1] >= length:
                room = rooms[-1]
                count, parts = by_room[room].pop()
                if not by_room[room]:
                    rooms.pop()
                # several of this length go in at once while the pack stays the one with most room
                below = rooms[-1] if rooms else 0
                times = max(1, min((room - below) // length, left // count)) if left >= count else 1
                used = min(count, left // times)
                if used < count:
                    add(room, count - used, parts)
            else:
                room, parts = capacity, ()
                times = 1
                used = left
            left -= used * times
            add(room - times * length, used, (*parts, (length, times)))
    return [(count, list(parts)) for room in sorted(by_room) for count, parts in by_room[room]]


def slots(patterns: list[tuple[int, list[tuple[int, int]]]]) -> dict[int, list[tuple[int, int, int, int, int]]]:
    """By length: (first rank, packs, first sequence id, offset, times). Offsets are gapless from 0."""
    out: dict[int, list[tuple[int, int, int, int, int]]] = defaultdict(list)
    taken: dict[int, int] = defaultdict(int)
    sequence = 0
    for count, parts in patterns:
        offset = 0
        for length, times in parts:
            out[length].append((taken[length], count, sequence, offset, times))
            taken[length] += count * times
            offset += length * times
        sequence += count
    return out


def padding(histogram: dict[int, int], capacity: int) -> dict[str, int]:
    """Sequences, ids and padding of the packing; a fill of a power of two needs none."""
    total = pad = ids = 0
    for count, parts in pack_histogram(histogram, capacity):
        fill = sum(length * times for length, times in parts)
        total += count
        ids += fill * count
        pad += 0 if fill & (fill - 1) == 0 else (capacity - fill) * count
    return {"sequences": total, "ids": ids, "padding": pad}


def place(cut: DataFrame, capacity: int = 2048, rows_per_bucket: int = 50_000) -> DataFrame:
    """Add sequence_id and offset to pieces (a written table with doc_id, start, length).

    Ranks within a length come from counts per (length, bucket) and a row number inside each
    bucket, so that a length with a third of all pieces is spread over many tasks. Columns sequence_id and
    offset are replaced, others pass. Equal pieces take their slots in any order.
    """
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}
    table = slots(pack_histogram(histogram, capacity))
    buckets = max(16, sum(histogram.values()) // rows_per_bucket)
    bucket, number, earlier, rank = (fresh(cut.columns, x) for x in ("__bucket", "__n", "__before", "__rank"))
    key = F.pmod(F.xxhash64("doc_id", "start"), F.lit(buckets)).cast("int")
    keyed = cut.drop("sequence_id", "offset").withColumn(bucket, key)
    before = W.partitionBy("length").orderBy(bucket).rowsBetween(W.unboundedPreceding, -1)
    counts = keyed.groupBy("length", bucket).agg(F.count("*").alias(number))
    counts = counts.select("length", bucket, F.coalesce(F.sum(number).over(before), F.lit(0)).alias(earlier))
    order = [c for c in ("doc_id", "start", "ids_crc32", "doc_tokens") if c in cut.columns]
    inside = W.partitionBy("length", bucket).orderBy(*order)
    ranked = keyed.withColumn(rank, F.row_number().over(inside) - 1).join(counts, ["length", bucket])
    ranked = ranked.withColumn(rank, F.col(rank) + F.col(earlier)).drop(earlier, bucket)
    #: Bounded by the number of lengths (2,048), not by the input.
    flat = [(length, *row) for length, rows in table.items() for row in rows]
    shared = cut.sparkSession.sparkContext.broadcast(flat)
    names, rank_name = ranked.columns, rank

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        t = np.array(shared.value, dtype=np.int64).reshape(-1, 6)
        keys = (t[:, 0] << 48) + t[:, 1]
        by = np.argsort(keys, kind="stable")
        keys, t = keys[by], t[by]
        for batch in batches:
            length = batch.column(names.index("length")).to_numpy()
            nth = batch.column(names.index(rank_name)).to_numpy()
            row = t[np.searchsorted(keys, (length << 48) + nth, side="right") - 1]
            at = nth - row[:, 1]
            turn, pack = at // row[:, 2], at % row[:, 2]
            kept = [batch.column(i) for i, n in enumerate(names) if n != rank_name]
            kept += [pa.array(row[:, 3] + pack), pa.array(row[:, 4] + turn * length)]
            yield pa.RecordBatch.from_arrays(kept, names=[n for n in names if n != rank_name] + ["sequence_id", "offset"])

    schema = ", ".join(f"`{n}` {k}" for n, k in ranked.dtypes if n != rank_name) + ", sequence_id bigint, offset bigint"
    return ranked.mapInArrow(run, schema)


def pack(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 1, memo: float = 1.0) -> DataFrame:
    """Pieces of every document with sequence_id and offset (columns of PIECES and these two)."""
    small_batches(docs.sparkSession)
    cut = materialize(pieces(docs, tokenizer, capacity, end_id, memo=memo), "pieces")
    return place(cut, capacity).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def sequences(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 1, pad_id: int = 0) -> DataFrame:
    """The packed sequences themselves: sequence_id, tokens (padded), doc_ids and starts of its pieces."""
    small_batches(docs.sparkSession)
    cut = materialize(pieces(docs, tokenizer, capacity, end_id, keep_ids=True), "pieces")
    placed = place(cut, capacity)
    parts = F.array_sort(F.collect_list(F.struct("offset", "doc_id", "start", "ids")))  # at most ``capacity`` pieces

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            seqs, docs_in, starts = [], [], []
            for parts in batch.column(1).to_pylist():
                ids = np.frombuffer(b"".join(p["ids"] for p in parts), dtype="<u4")
                full = len(ids) if len(ids) & (len(ids) - 1) == 0 else capacity
                seqs.append(np.concatenate([ids, np.full(full - len(ids), pad_id)]).astype(np.int32))
                docs_in.append([p["doc_id"] for p in parts])
                starts.append([p["offset"] for p in parts])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(seqs, pa.list_(pa.int32())), pa.array(docs_in, pa.list_(pa.int64())), pa.array(starts, pa.list_(pa.int64()))], names=["sequence_id", "tokens", "doc_ids", "offsets"])

    return placed.groupBy("sequence_id").agg(parts.alias("parts")).mapInArrow(run, "sequence_id long, tokens array<int>, doc_ids array<long>, offsets array<long>")


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all documents."""
    import public_tokenizers

    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
