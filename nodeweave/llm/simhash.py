"""Operator 6, SimHash near-duplicates by meet-in-the-middle ball hashing.

A fingerprint bit is one if it is set in over half of the hashes of a text's word shingles, repeats
included. Two fingerprints link at ``radius`` or fewer differing bits. Then some value lies within
half the radius of both, so if every fingerprint emits all values of its ball of half the radius,
linked fingerprints meet on one.

Whole-width balls are large (2,081 values for radius 4), so the first search is per half: a pair
within 4 bits has 2 or fewer in one of its 32-bit halves, where balls of one bit (33 values)
meet. Fingerprints that meet are verified. A meeting of two or three is resolved by built-in
aggregates (count, least, greatest, exclusive or), without lists. Where more meet, as in large
groups of near copies, their members emit the whole-width ball instead: there a meeting proves a
link, so each member links to the least one, and the work is linear in the group. A whole-width
value has at most 2,081 members, as they are distinct. No link is lost on either way.

Exact copies share one fingerprint and are collapsed first. Null texts are empty; texts without
words have fingerprint zero and link like any other. Repeated doc_ids are rows of their own in one component. Other
columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .store import join_one, materialize, remove, small_batches, texts

#: A table of keys is broadcast up to so many rows (8 bytes each), and joined by shuffle beyond.
BROADCAST_KEYS = 100_000


def fingerprint(text: bytes, words: int = 4, seed: int = 42) -> bytes:
    """Eight bytes, most significant bit first."""
    import numpy as np
    from xxhash import xxh64_digest

    found = text.lower().split()
    if not found:
        return bytes(8)
    n = max(1, len(found) - words + 1)
    joined = b" ".join(found)
    ends = np.cumsum([len(w) + 1 for w in found])
    a = [0, *ends[: n - 1].tolist()]
    b = (ends[min(words, len(found)) - 1 :] - 1).tolist()
    hashes = b"".join([xxh64_digest(joined[i:j], seed) for i, j in zip(a, b, strict=True)])
    votes = np.zeros(64, dtype=np.int64)
    flat = np.frombuffer(hashes, np.uint8).reshape(-1, 8)
    for i in range(0, n, 4096):
        votes += np.unpackbits(flat[i : i + 4096], axis=1).sum(axis=0, dtype=np.int64)
    return np.packbits(votes * 2 > n).tobytes()


def fingerprints(docs: DataFrame, words: int = 4, seed: int = 42) -> DataFrame:
    """doc_id and fp (the fingerprint as a signed long); map-only over whole texts."""
    small_batches(docs.sparkSession)

    def run(batches) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            fp = [int.from_bytes(fingerprint(t.as_py().encode("utf-8", "replace"), words, seed), "big", signed=True) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp, pa.int64())], names=["doc_id", "fp"])

    return texts(docs).mapInArrow(run, "doc_id long, fp long")


def masks(width: int, bits: int) -> list[int]:
    """Every signed 64-bit pattern of up to ``bits`` ones among the lowest ``width`` places."""
    out = [sum(1 << b for b in some) for k in range(bits + 1) for some in combinations(range(width), k)]
    return [m - (1 << 64) if m >= 1 << 63 else m for m in out]


def _ball(value: Column, patterns: list[int]) -> Column:
    return F.transform(F.array(*[F.lit(m).cast("long") for m in patterns]) if len(patterns) < 100 else _literal(patterns), lambda m: value.bitwiseXOR(m))


def _literal(patterns: list[int]) -> Column:
    """A long constant array from one string, as thousands of literals would bloat the plan."""
    return F.transform(F.split(F.lit(",".join(map(str, patterns))), ","), lambda x: x.cast("long"))


def half_keys(distinct: DataFrame, radius: int) -> DataFrame:
    """fp and each key of the balls of its two 32-bit halves."""
    patterns = masks(32, -(-(radius // 2) // 2))
    high, low = F.shiftrightunsigned("fp", 32), F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF))
    low_keys = F.transform(_ball(low, patterns), lambda k: k.bitwiseOR(F.lit(1 << 32)))
    return distinct.select("fp", F.explode(F.concat(_ball(high, patterns), low_keys)).alias("key"))


def links(distinct: DataFrame, radius: int = 4, temps: list | None = None) -> DataFrame:
    """Edges (a, b) between distinct fingerprints that connect all that lie within ``radius`` bits.

    Not every linked pair is an edge, but each is joined by a path of edges, and every edge is a link. Written
    tables that the result reads are added to ``temps``, for the caller to remove.
    """
    temps = [] if temps is None else temps
    keys = half_keys(distinct, radius)
    met = keys.groupBy("key").agg(F.count("*").alias("n"), F.min("fp").alias("lo"), F.max("fp").alias("hi"), F.bit_xor("fp").alias("x")).filter("n > 1")
    met = materialize(met, "met")
    temps.append(met)
    third = F.col("x").bitwiseXOR(F.col("lo")).bitwiseXOR(F.col("hi"))
    pair = lambda a, b: F.struct(F.least(a, b).alias("a"), F.greatest(a, b).alias("b"))
    lo, hi = F.col("lo"), F.col("hi")
    some = F.when(F.col("n") == 2, F.array(pair(lo, hi))).otherwise(F.array(pair(lo, hi), pair(lo, third), pair(third, hi)))
    few = met.filter("n <= 3").select(F.explode(some).alias("e")).select("e.*").filter(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius)
    crowded = met.filter("n > 3").select("key")
    if crowded.limit(1).count():
        hot = F.broadcast(crowded) if crowded.count() <= BROADCAST_KEYS else crowded
        members = materialize(keys.join(hot, "key", "left_semi").select("fp").distinct(), "crowded")
        temps.append(members)
        values = members.select("fp", F.explode(_ball(F.col("fp"), masks(64, radius // 2))).alias("value"))
        least = values.withColumn("a", F.min("fp").over(W.partitionBy("value")))  # at most 2,081 rows a value
        few = few.unionByName(least.filter("a <> fp").select("a", F.col("fp").alias("b")))
    return few.distinct()


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.pmod(F.xxhash64("b", "a"), F.lit(1 << 30)))).first())


def components(edges: DataFrame) -> DataFrame:
    """node and root (least node reachable) for every node of the edges (a, b).

    Alternates two steps until nothing changes: each node's larger neighbours move to its least
    neighbour, then its smaller neighbours do. Rounds grow with the logarithm of the longest path;
    each is written to the shared folder.
    """
    at = materialize(edges.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    mark = _mark(at)
    while True:
        both = at.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(at.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("m").alias("a"), F.col("v").alias("b")).filter("a <> b").distinct()
        # now every edge goes from a larger node b to a smaller a
        least = large.groupBy(F.col("b").alias("u")).agg(F.min("a").alias("m"))
        small = large.withColumnRenamed("b", "u").join(least, "u")
        small = small.select(F.explode(F.array(F.struct("m", F.col("a").alias("v")), F.struct("m", F.col("u").alias("v")))).alias("e")).select(F.col("e.m").alias("a"), F.col("e.v").alias("b")).filter("a <> b").distinct()
        after = materialize(small, "edges")
        now = _mark(after)
        remove(at)
        at = after
        if now == mark:
            break
        mark = now
    roots = at.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("root"))
    return roots.unionByName(at.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct().join(roots.select("node"), "node", "left_anti"))


def groups(docs: DataFrame, words: int = 4, radius: int = 4, seed: int = 42) -> DataFrame:
    """doc_id, fp and component_id (least doc_id reachable over links) of every document."""
    prints = materialize(fingerprints(docs, words, seed), "prints")
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")), "distinct")
    temps: list[DataFrame] = []
    roots = materialize(components(links(distinct.select("fp"), radius, temps)), "roots")
    linked = roots.join(distinct, roots.node == distinct.fp).select("fp", "root", "rep")
    least = linked.groupBy("root").agg(F.min("rep").alias("component_id"))
    moved = linked.join(least, "root").select("fp", "component_id")
    classes = distinct.join(moved, "fp", "left").select("fp", F.coalesce("component_id", "rep").alias("component_id"), "n")
    classes = materialize(classes, "classes")
    for used in (*temps, distinct, roots):
        remove(used)
    return join_one(prints, classes, "fp").select("doc_id", "fp", "component_id")


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all documents."""
    found = groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
