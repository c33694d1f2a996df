"""Near copies by word-shingle similarity, with candidates from SimHash.

A pair is near if the sets of its five-word shingles (lower-cased A-Z; a shorter text is one
shingle) have a Jaccard similarity of 0.8 or more. Fingerprints of whole texts at a small radius
miss many such pairs (at 0.8 about ten of 64 bits differ), so candidates come from two searches:

* whole texts whose fingerprints link (ball hashing, :mod:`simhash`), and
* texts that share the fingerprint of a window: around each of a text's ``ANCHORS`` least shingle
  hashes, the words on either side of the anchor. A pair at 0.8 keeps an anchor and
  its window with a probability of over a half, so that eight of them miss few pairs of longer texts.

Both miss many pairs of short texts, where one edit near an end is in every window. Texts of up to ``SHORT`` distinct
shingles are therefore joined exactly as well: no pair of them is missed, nor one whose lesser has up to 0.8 ``SHORT``.

Every candidate pair is verified on the full shingle sets. In a bucket of texts with one key each
is compared with a leader, not with all others: the work is linear in the bucket. Those that are
not near their leader meet again under other leaders, for ``ROUNDS`` rounds; as near copies
share many buckets, groups come together over several paths. Texts of buckets that still hold several groups then
go to an exact join over their rarest shingles (:func:`prefix_pairs`), so no pair that shares a bucket is left out.

Exact copies (equal word sequences) are collapsed first. Null texts are empty; texts without words are exact
copies of each other. Other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .encode import forget
from .simhash import BROADCAST_KEYS, components, links
from .store import join_one, materialize, remove, small_batches, texts

SHINGLE, SIMILARITY = 5, 0.8
ANCHORS, REACH = 8, 6
ROUNDS = 3
#: Texts of up to so many distinct shingles are joined exactly, whatever their windows.
SHORT = 80
#: Hash buckets of the shingle counts, and rows of a block of a common prefix shingle.
BUCKETS, BLOCK = 1 << 18, 256


def shingle_hashes(words: list[bytes], n: int = SHINGLE):
    """Sorted distinct 64-bit hashes of the word shingles."""
    import numpy as np
    from xxhash import xxh64_digest

    got = [xxh64_digest(b" ".join(words[i : i + n])) for i in range(max(1, len(words) - n + 1))] if words else []
    return np.unique(np.frombuffer(b"".join(got), ">u8").astype(np.uint64)) if got else np.zeros(0, np.uint64)


def window_keys(words: list[bytes], anchors: int = ANCHORS, reach: int = REACH) -> tuple[bytes, list[int], int]:
    """The whole text's SimHash, the SimHashes of the windows around its least shingle hashes, and its number of shingles."""
    import numpy as np
    from xxhash import xxh64_digest

    if not words:
        return bytes(8), [], 0
    n = max(1, len(words) - SHINGLE + 1)
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = [0, *ends[: n - 1].tolist()]
    stops = (ends[min(SHINGLE, len(words)) - 1 :] - 1).tolist()
    raw = np.frombuffer(b"".join([xxh64_digest(joined[i:j]) for i, j in zip(starts, stops, strict=True)]), np.uint8).reshape(-1, 8)
    votes = np.zeros(64, dtype=np.int64)
    for i in range(0, n, 4096):
        votes += np.unpackbits(raw[i : i + 4096], axis=1).sum(axis=0, dtype=np.int64)
    whole = np.packbits(votes * 2 > n).tobytes()
    value = raw.view(">u8").reshape(-1).astype(np.uint64)
    _, first = np.unique(value, return_index=True)  # least hashes, each at its first place
    keys = set()
    for p in first[:anchors].tolist():
        # the shingles that lie within the anchor's window, as a SimHash of their hashes
        some = raw[max(0, p - reach) : p + reach + 1]
        bits = np.packbits(np.unpackbits(some, axis=1).sum(axis=0, dtype=np.int64) * 2 > len(some)).tobytes()
        keys.add(int.from_bytes(bits, "big", signed=True))
    return whole, sorted(keys), len(first)


def similarity(a: str, b: str) -> float:
    """Jaccard similarity of two texts' shingle sets."""
    import numpy as np

    x, y = (shingle_hashes(t.encode("utf-8", "replace").lower().split()) for t in (a, b))
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both / (len(x) + len(y) - both) if len(x) + len(y) else 1.0


def sketches(docs: DataFrame) -> DataFrame:
    """doc_id, same (hash of the word sequence), fp (whole SimHash), keys (window SimHashes), size (distinct shingles)."""
    small_batches(docs.sparkSession)

    def run(batches) -> Iterator:
        import pyarrow as pa
        from xxhash import xxh3_128_digest

        forget()
        for batch in batches:
            same, fp, keys, size = [], [], [], []
            for t in batch.column(1):
                words = t.as_py().encode("utf-8", "replace").lower().split()
                whole, some, n = window_keys(words)
                same.append(xxh3_128_digest(b" ".join(words)))
                fp.append(int.from_bytes(whole, "big", signed=True))
                keys.append(some)
                size.append(n)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(same, pa.binary()), pa.array(fp, pa.int64()), pa.array(keys, pa.list_(pa.int64())), pa.array(size, pa.int32())], names=["doc_id", "same", "fp", "keys", "size"])

    return texts(docs).mapInArrow(run, "doc_id long, same binary, fp long, keys array<long>, size int")


def _verified(pairs: DataFrame, some: DataFrame, least: float) -> DataFrame:
    """Pairs (a, b) with ``near``: whether their texts (rows of ``some``) are similar.

    Few ids are broadcast to pick their texts before any shuffle; beyond BROADCAST_KEYS all texts of ``some`` are shuffled.
    """
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    if wanted.count() <= BROADCAST_KEYS:
        some = some.join(F.broadcast(wanted), "doc_id", "left_semi")
    left = pairs.join(some.select(F.col("doc_id").alias("a"), F.col("text").alias("ta")), "a")
    both = left.join(some.select(F.col("doc_id").alias("b"), F.col("text").alias("tb")), "b").select("a", "b", "ta", "tb")

    def run(batches) -> Iterator:
        import pyarrow as pa

        forget()
        for batch in batches:
            near = [similarity(x.as_py(), y.as_py()) >= least for x, y in zip(batch.column(2), batch.column(3), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(near, pa.bool_())], names=["a", "b", "near"])

    return both.mapInArrow(run, "a long, b long, near boolean")


def _tally(some: DataFrame) -> bytes:
    """Counts of shingles by hash bucket, as int32; those seen once in a task are left out, as only an order is wanted."""
    import numpy as np

    def run(batches) -> Iterator:
        import pyarrow as pa

        forget()
        tally = np.zeros(BUCKETS, dtype=np.int64)
        for batch in batches:
            for t in batch.column(1):
                at = shingle_hashes(t.as_py().encode("utf-8", "replace").lower().split()) % np.uint64(BUCKETS)
                np.add.at(tally, at.astype(np.int64), 1)
        seen = np.flatnonzero(tally > 1)
        yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(tally[seen])], names=["bucket", "n"])

    sums = some.select("doc_id", "text").mapInArrow(run, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(BUCKETS, dtype=np.int32)  # BUCKETS rows at most reach the driver
    out[sums.column(0).to_numpy()] = np.minimum(sums.column(1).to_numpy(), 2**31 - 1)
    return out.tobytes()


def prefix_pairs(some: DataFrame, group: DataFrame, least: float = SIMILARITY) -> DataFrame:
    """Candidate pairs (a, b) of ``some`` (doc_id, text): every pair of similarity ``least`` or more whose
    members have not the same ``root`` in ``group`` (doc_id, root) is among them.

    In any one order of all shingles, two such texts have one in common among the first n - least n + 1 of their n.
    Here the rare go first, so passages that many texts share are in few of these prefixes. Pairs whose
    lengths, or the shingles left after the common one, can't reach ``least`` are dropped. A shingle in many prefixes is
    dealt to pairs of blocks of ``BLOCK`` rows.
    """
    shared = some.sparkSession.sparkContext.broadcast(_tally(some))

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        forget()
        count = np.frombuffer(shared.value, np.int32)
        for batch in batches:
            size, first = [], []
            for t in batch.column(1):
                h = shingle_hashes(t.as_py().encode("utf-8", "replace").lower().split())
                n = len(h)
                take = n - math.ceil(least * n - 1e-9) + 1 if n else 0
                first.append(h[np.lexsort((h, count[(h % np.uint64(BUCKETS)).astype(np.int64)]))[:take]].view(np.int64))
                size.append(n)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int32()), pa.array(first, pa.list_(pa.int64()))], names=["d", "n", "first"])

    heads = some.select("doc_id", "text").mapInArrow(run, "d long, n int, first array<long>")
    heads = heads.join(group.select(F.col("doc_id").alias("d"), "root"), "d", "left").withColumn("root", F.coalesce("root", "d"))
    rows = materialize(heads.select("d", "n", "root", F.posexplode("first").alias("i", "h")), "prefixes")
    mixed = rows.groupBy("h").agg(F.count("*").alias("m"), F.min("root").alias("r0"), F.max("root").alias("r1")).filter("r0 <> r1")
    blocks = mixed.select("h", F.ceil(F.col("m") / BLOCK).cast("int").alias("blocks"))
    dealt = rows.join(blocks, "h").withColumn("own", F.pmod(F.xxhash64("d"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("h", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "own", "d", "n", "i", "root")
    x, y = (dealt.select("h", "lo", "hi", *[F.col(c).alias(f"{c}_{s}") for c in ("own", "d", "n", "i", "root")]) for s in "xy")
    met = x.join(y, ["h", "lo", "hi"]).filter("d_x < d_y and root_x <> root_y and (lo = hi or own_x <> own_y)")
    fits = F.least("n_x", "n_y") >= F.lit(least) * F.greatest("n_x", "n_y") - 1e-9
    left = F.least(F.col("n_x") - F.col("i_x"), F.col("n_y") - F.col("i_y"))
    reach = left >= F.lit(least / (1 + least)) * (F.col("n_x") + F.col("n_y")) - 1e-9
    pairs = materialize(met.filter(fits & reach).select(F.col("d_x").alias("a"), F.col("d_y").alias("b")).distinct(), "prefix-pairs")
    remove(rows)
    return pairs


def near_groups(docs: DataFrame, least: float = SIMILARITY, radius: int = 4, rounds: int = ROUNDS) -> DataFrame:
    """doc_id and component_id (least doc_id of the group) of every document.

    doc_id has to tell rows apart: rows that share one are taken for one text (``corpus_pipeline`` numbers rows first where ids repeat).
    Two written tables stay, as the result reads them.
    """
    made = materialize(sketches(docs), "sketches")
    copies = made.groupBy("same").agg(F.min("doc_id").alias("rep"), F.first("fp").alias("fp"), F.first("keys").alias("keys"), F.first("size").alias("size"), F.count("*").alias("n"))
    copies = materialize(copies, "copies")
    windows = copies.select(F.col("rep").alias("d"), F.explode("keys").alias("key"))
    prints = copies.select("fp", F.col("rep").alias("d"))
    temps: list[DataFrame] = []
    met = links(prints.select("fp").distinct(), radius, temps).select(F.col("a").alias("lo"), F.col("b").alias("hi"))
    firsts = prints.groupBy("fp").agg(F.min("d").alias("d"))
    ball_pairs = met.join(firsts.select(F.col("fp").alias("lo"), F.col("d").alias("x")), "lo").join(firsts.select(F.col("fp").alias("hi"), F.col("d").alias("y")), "hi").select("x", "y")
    same_print = prints.join(firsts.select("fp", F.col("d").alias("m")), "fp").filter("d <> m").select(F.col("m").alias("x"), F.col("d").alias("y"))
    direct = ball_pairs.unionByName(same_print).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    crowded = materialize(windows.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1"), "crowded")
    shared = materialize(join_one(windows, crowded, "key").select("d", "key"), "windows")
    remove(crowded)
    open_ = shared
    direct = materialize(direct.distinct(), "direct")
    for used in temps:
        remove(used)
    done: list[DataFrame] = []
    # texts are shuffled once, for those that may have a near copy; every round works on these
    short = copies.filter(F.col("size").between(1, SHORT)).select(F.col("rep").alias("doc_id"))
    wanted = open_.select(F.col("d").alias("doc_id")).unionByName(direct.select(F.explode(F.array("a", "b")).alias("doc_id"))).unionByName(short).distinct()
    some = materialize(texts(docs).join(wanted, "doc_id", "left_semi"), "candidates")
    edges, tried = None, None
    for turn in range(rounds):
        # a bucket's leader: its least text in an order that changes with the round
        order = F.col("d") if turn == 0 else F.xxhash64("d", F.lit(turn))
        lead = materialize(open_.groupBy("key").agg(F.min_by("d", order).alias("leader"), F.count("*").alias("n")).filter("n > 1"), "lead")
        led = materialize(join_one(open_, lead, "key").filter("d <> leader").select("key", "d", "leader"), "led")
        remove(lead)
        pairs = led.select(F.least("d", "leader").alias("a"), F.greatest("d", "leader").alias("b")).distinct()
        if turn == 0:
            pairs = pairs.unionByName(direct).distinct()
        if tried is not None:
            pairs = pairs.join(tried.select("a", "b"), ["a", "b"], "left_anti")
        pairs = materialize(pairs, "pairs")
        checked = materialize(_verified(pairs, some, least).groupBy("a", "b").agg(F.max("near").alias("near")), "checked")
        remove(pairs)
        done.append(checked)
        tried = checked if tried is None else tried.unionByName(checked)
        good = checked.filter("near").select("a", "b")
        edges = good if edges is None else edges.unionByName(good)
        # who is near the leader is settled in this bucket; the others meet again
        pair_of = led.withColumn("a", F.least("d", "leader")).withColumn("b", F.greatest("d", "leader"))
        rest = pair_of.join(tried.filter("near").select("a", "b"), ["a", "b"], "left_anti").select("d", "key")
        rest = materialize(rest, "rest")
        remove(led)
        if turn:
            remove(open_)
        open_ = rest
        if not rest.limit(1).count():
            break
    roots = materialize(components(edges), "roots")
    # a bucket whose members are not all in one group by now may hold pairs that no leader has shown
    placed = shared.join(roots.withColumnRenamed("node", "d"), "d", "left").select("key", "d", F.coalesce("root", "d").alias("root"))
    placed = materialize(placed, "placed")
    unlike = placed.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.count("*").alias("n")).filter("r0 <> r1").select("key", "n")
    unlike = materialize(unlike, "unlike")
    unsettled = join_one(placed, unlike, "key").select(F.col("d").alias("doc_id")).unionByName(short).distinct()
    found = prefix_pairs(some.join(unsettled, "doc_id", "left_semi"), roots.withColumnRenamed("node", "doc_id"), least)
    pairs = found.join(tried.select("a", "b"), ["a", "b"], "left_anti")
    more = materialize(_verified(pairs, some, least).filter("near").select("a", "b"), "more")
    if more.limit(1).count():
        done.append(roots)
        roots = materialize(components(edges.unionByName(more).distinct()), "roots")
    classes = copies.join(roots.withColumnRenamed("node", "rep"), "rep", "left").select("same", F.coalesce("root", "rep").alias("component_id"), "n")
    classes = materialize(classes, "classes")
    for used in (*done, open_, some, placed, unlike, shared, direct, found, more, roots, copies):
        remove(used)
    return join_one(made.select("doc_id", "same"), classes, "same").select("doc_id", "component_id")
