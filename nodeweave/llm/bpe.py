"""Operator 3, byte-level BPE by merge replay.

The texts of a batch are one corpus. Their distinct pre-tokens lie end to end in one array of
symbols, with links to the neighbours. An inverted index maps each symbol pair that has a rank to
the positions where it stands. Merges are applied in rank order, each to all its positions at once;
only the pairs of touched neighbours enter the index anew. Ids of a text are then looked up by its
pre-tokens. The result does not depend on which texts share a batch, so the operator is map-only
and its memory is bounded by a batch.

Equal symbols in a row merge from the left. Where a merge makes a pair of lower rank than itself,
the pre-token is done again alone, always taking its lowest pair first; and a pre-token that is in
the vocabulary is that id, as the reference library has it.

Null texts are empty and give no ids. Repeated rows are rows of their own; other columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from heapq import heappop, heappush
from itertools import chain

from pyspark.sql import DataFrame, SparkSession

from .encode import slices
from .store import small_batches, texts

MEMO_UNITS = 1_000_000
MEMO_WORDS = 1_000_000
MEMO_CHARS = 40
_REPLAYS: dict = {}


def read_ranks(path: str) -> dict[bytes, int]:
    """Token bytes to rank, from a file of base64 tokens and ranks."""
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in f if line.strip())}


class MergeReplay:
    """Encoder and decoder for one table of ranks and one pre-token pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.tokens = {r: t for t, r in ranks.items()}
        self.find = regex.compile(pattern).findall
        self.pairs: dict[int, int] = {}  # left * 2**32 + right -> rank, as pairs turn up; -1: none
        self.words: dict[str, bytes] = {}
        self.units: dict[str, bytes | None] = {}

    def _rank(self, pair: int) -> int:
        got = self.pairs.get(pair)
        if got is None:
            got = self.ranks.get(self.tokens[pair >> 32] + self.tokens[pair & 0xFFFFFFFF], -1)
            self.pairs[pair] = got
        return got

    def alone(self, word: bytes) -> list[int]:
        """Lowest-ranked pair first, leftmost among equals, over one pre-token."""
        if word in self.ranks:
            return [self.ranks[word]]
        n = len(word)
        symbol = [self.ranks[word[i : i + 1]] for i in range(n)]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[int, int, int]] = []

        def offer(i: int) -> None:
            if i >= 0 and after[i] < n and (r := self._rank(symbol[i] << 32 | symbol[after[i]])) >= 0:
                heappush(heap, (r, i, symbol[i] << 32 | symbol[after[i]]))

        for i in range(n - 1):
            offer(i)
        while heap:
            r, i, pair = heappop(heap)
            j = after[i]
            if symbol[i] < 0 or j >= n or symbol[i] << 32 | symbol[j] != pair:
                continue
            symbol[i], symbol[j] = r, -1
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            offer(i)
            offer(before[i])
        return [s for s in symbol if s >= 0]

    def replay(self, words: list[bytes]) -> list[bytes]:
        """Ids of distinct pre-tokens as little-endian unsigned 32-bit bytes."""
        import numpy as np

        out: list[bytes | None] = [None] * len(words)
        rest: list[int] = []
        for k, w in enumerate(words):
            if w in self.ranks:
                out[k] = self.ranks[w].to_bytes(4, "little")
            else:
                rest.append(k)
        if not rest:
            return out  # type: ignore[return-value]
        single = np.array([self.ranks[bytes([b])] for b in range(256)], dtype=np.int64)
        flat = single[np.frombuffer(b"".join(words[k] for k in rest), np.uint8)]
        size = np.array([len(words[k]) for k in rest])
        ends = np.cumsum(size)
        n = len(flat)
        owner = np.repeat(np.arange(len(rest)), size)
        after = np.arange(1, n + 1)
        after[ends - 1] = -1
        before = np.arange(-1, n - 1)
        before[ends - size] = -1
        index: dict[int, list] = {}  # rank -> arrays of left positions
        queue: list[int] = []
        redo: set[int] = set()

        def enter(left, floor: int) -> None:
            """Index the pairs that begin at these positions, if they have a rank."""
            left = left[after[left] >= 0]
            if not len(left):
                return
            pair = flat[left] << 32 | flat[after[left]]
            by = np.argsort(pair, kind="stable")
            pair, left = pair[by], left[by]
            cut = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]]))
            for p, a, b in zip(pair[cut].tolist(), cut.tolist(), [*cut[1:].tolist(), len(pair)], strict=True):
                r = self._rank(p)
                if r < 0:
                    continue
                if r <= floor:  # lower than what has been applied: these pre-tokens go alone
                    redo.update(owner[left[a:b]].tolist())
                elif r in index:
                    index[r].append((p, left[a:b]))
                else:
                    index[r] = [(p, left[a:b])]
                    heappush(queue, r)

        enter(np.arange(n), -1)
        while queue:
            r = heappop(queue)
            for p in {p for p, _ in index[r]}:
                at = [x for q, x in index[r] if q == p]
                left = np.unique(np.concatenate(at)) if len(at) > 1 else np.sort(at[0])
                a, b = p >> 32, p & 0xFFFFFFFF
                left = left[(flat[left] == a) & (after[left] >= 0)]
                left = left[flat[after[left]] == b]
                if a == b and len(left) > 1:  # runs: from the left, each symbol once
                    keep, last = [], -1
                    for i, j in zip(left.tolist(), after[left].tolist(), strict=True):
                        if i != last:
                            keep.append(i)
                            last = j
                    left = np.array(keep)
                if not len(left):
                    continue
                right = after[left]
                beyond = after[right]
                flat[left], flat[right] = r, -1
                after[left], after[right] = beyond, -1
                before[beyond[beyond >= 0]] = left[beyond >= 0]
                prior = before[left]
                enter(np.unique(np.concatenate([left, prior[prior >= 0]])), r)
            del index[r]
        kept = flat >= 0
        ids, of = flat[kept].astype("<u4").tobytes(), np.bincount(owner[kept], minlength=len(rest))
        at = 0
        for k, c in zip(rest, of.tolist(), strict=True):
            out[k] = ids[at : at + 4 * c]
            at += 4 * c
        for i in redo:
            out[rest[i]] = b"".join(x.to_bytes(4, "little") for x in self.alone(words[rest[i]]))
        return out  # type: ignore[return-value]

    def _learn(self, fresh: list[str]) -> dict[str, bytes | None]:
        """Ids of units (a space and what follows up to the next); None if white space meets there."""
        out: dict[str, bytes | None] = {}
        split: list[tuple[str, list[str]]] = []
        for u in fresh:
            if not u or u[0].isspace() or u[-1].isspace():
                out[u] = None
            else:
                split.append((u, self.find(" " + u)))
        known = self.words
        new = list(set().union(*(w for _, w in split)).difference(known)) if split else []
        if len(known) + len(new) > MEMO_WORDS:
            self.words = known = {w: known[w] for _, ws in split for w in ws if w in known}
        known.update(zip(new, self.replay([w.encode("utf-8", "replace") for w in new]), strict=True))
        out.update((u, b"".join([known[w] for w in ws])) for u, ws in split)
        for w in new:
            if len(w) > MEMO_CHARS:
                del known[w]
        if len(known) > MEMO_WORDS:
            self.words = {}
        return out

    def encode(self, batch: list[str]) -> list[bytes]:
        """Ids of whole texts as little-endian unsigned 32-bit bytes."""
        memo = self.units
        split = [t.split(" ") for t in batch]
        heads = [parts.pop(0) for parts in split]
        fresh = list(set().union(*split).difference(memo)) if split else []
        if len(memo) + len(fresh) > MEMO_UNITS:
            self.units = memo = {u: memo[u] for u in set().union(*split) if u in memo}
        memo.update(self._learn(fresh))
        get, out, whole = memo.__getitem__, [b""] * len(batch), []
        for i, parts in enumerate(split):
            if heads[i] and heads[i][-1].isspace() and parts:
                whole.append((i, batch[i]))
                continue
            try:
                out[i] = b"".join(map(get, parts))
            except TypeError:
                whole.append((i, batch[i]))
                continue
            if heads[i]:
                whole.append((i, heads[i]))
        found = [(i, self.find(t)) for i, t in whole]
        words = list(set(chain.from_iterable(w for _, w in found)))
        ids = dict(zip(words, self.replay([w.encode("utf-8", "replace") for w in words]), strict=True))
        for i, ws in found:
            out[i] = b"".join([ids[w] for w in ws]) + out[i]
        if len(memo) > MEMO_UNITS:
            self.units = {}
        else:
            for u in fresh:
                if len(u) > MEMO_CHARS:
                    del memo[u]
        return out

    def decode(self, ids) -> bytes:
        """The bytes of an id array."""
        return b"".join(map(self.tokens.__getitem__, ids.tolist()))


def replayer(path: str, pattern: str) -> MergeReplay:
    if (path, pattern) not in _REPLAYS:
        _REPLAYS[path, pattern] = MergeReplay(read_ranks(path), pattern)
    return _REPLAYS[path, pattern]


def encode_decode(docs: DataFrame, ranks_path: str, pattern: str, keep_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, with ``keep_ids``, ids and decoded text."""
    small_batches(docs.sparkSession)
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded binary" if keep_ids else "")

    def run(batches) -> Iterator:
        import numpy as np
        import pyarrow as pa

        bpe = replayer(ranks_path, pattern)
        for batch in batches:
            doc, text = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lo, hi in slices(text):
                rows = []
                for d, ids in zip(doc[lo:hi], bpe.encode(text[lo:hi]), strict=True):
                    back = bpe.decode(np.frombuffer(ids, "<u4"))
                    row = (d, len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(back).hexdigest())
                    rows.append((*row, np.frombuffer(ids, "<u4").astype(np.int32), back) if keep_ids else row)
                kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.int32()), pa.binary()]
                cols = [pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=False)]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"][: len(cols)])

    return texts(docs).mapInArrow(run, schema)


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all documents."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return encode_decode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
