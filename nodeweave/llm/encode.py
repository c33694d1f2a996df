"""Library tokenizers over whole texts, each distinct word encoded once per worker's memory.

Both public tokenizers split a text before every space that stands alone between other
characters, so the ids of a text are the ids of its space-separated units in order. The strings of special tokens in
a text are ordinary text, as the tokenizer files' own instructions have it (``encode_special_tokens``); with ``specials``
they become the special ids instead, and a text that holds one goes to the library whole. Units and the
words in them recur; bounded memos in each Python worker keep the ids of those seen, and words not
seen go to the library many at a time. A text where a space meets other white space, and whatever
else does not follow these rules, goes to the library as it is.
"""

from __future__ import annotations

import os
from itertools import chain

#: Units and words kept in a worker's memos before those start anew; bounds memory, not results.
MEMO_UNITS = 1_500_000
MEMO_WORDS = 1_200_000
#: Longer units are encoded each time.
MEMO_CHARS = 40
#: Punctuation that is a piece of its own after a word, under either tokenizer.
_TAIL = ".,!?;:"

_ENCODERS: dict = {}


class UnitEncoder:
    """Ids as little-endian unsigned 32-bit bytes. ``spaced``: words carry their leading space."""

    def __init__(self, path: str, spaced: bool, specials: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import numpy as np
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.encode_special_tokens = not specials
        self.specials = [t.content for t in self.library.get_added_tokens_decoder().values()] if specials else []
        self.spaced = spaced
        #: Part of the bounds that the memos of this encoder may fill; changes memory and time, not results.
        self.share = 1.0
        self.units: dict[str, bytes | None] = {}
        self.words: dict[str, bytes] = {}
        self.tails: dict[str, bytes] = {}
        vocab = self.library.get_vocab()
        #: Ids that start (spaced) or end (otherwise) a word.
        self.edge = np.zeros(max(vocab.values()) + 1, dtype=bool)
        for token, i in vocab.items():
            self.edge[i] = token.startswith("Ġ") if spaced else token.endswith("</w>")

    def _library(self, texts: list[str]) -> list[bytes]:
        import numpy as np

        out: list[bytes] = []
        for i in range(0, len(texts), 1000):
            ids = [e.ids for e in self.library.encode_batch_fast(texts[i : i + 1000], add_special_tokens=False)]
            flat = np.fromiter(chain.from_iterable(ids), dtype="<u4").tobytes()
            at = 0
            for x in ids:
                out.append(flat[at : at + 4 * len(x)])
                at += 4 * len(x)
        return out

    def _words(self, words: list[str]) -> dict[str, bytes]:
        """Ids of words of letters alone, many to a call."""
        import numpy as np

        out: dict[str, bytes] = {}
        groups = [words[i : i + 400] for i in range(0, len(words), 400)]
        lead = " " if self.spaced else ""
        for i in range(0, len(groups), 25):
            some = groups[i : i + 25]
            for group, got in zip(some, self.library.encode_batch_fast([lead + " ".join(g) for g in some], add_special_tokens=False), strict=True):
                ids = np.array(got.ids, dtype="<u4")
                edges = np.flatnonzero(self.edge[ids])
                if len(edges) != len(group):
                    out.update(zip(group, self._library([lead + w for w in group]), strict=True))
                    continue
                flat = ids.tobytes()
                cuts = (4 * edges).tolist() + [len(flat)] if self.spaced else [0] + (4 * edges + 4).tolist()
                out.update((w, flat[a:b]) for w, a, b in zip(group, cuts[:-1], cuts[1:], strict=True))
        return out

    def _learn(self, fresh: list[str]) -> dict[str, bytes | None]:
        """Ids of units; None for one that starts or ends in white space or is empty, if that matters."""
        out: dict[str, bytes | None] = {}
        plain: list[tuple[str, str, str]] = []
        other: list[str] = []
        for u in fresh:
            core = u.rstrip(_TAIL)
            if core.isalpha() and (core.isascii() or core.lower().isalpha()):
                plain.append((u, core, u[len(core) :]))
            elif self.spaced and (not u or u[0].isspace() or u[-1].isspace()):
                out[u] = None
            else:
                other.append(u)
        lead = " " if self.spaced else ""
        out.update(zip(other, self._library([lead + u for u in other]), strict=True))
        known = self.words
        new = list({c for _, c, _ in plain}.difference(known))
        most = int(MEMO_WORDS * self.share)
        if len(known) + len(new) > most:
            self.words = known = {c: known[c] for _, c, _ in plain if c in known}
        known.update(self._words(new))
        tails = self.tails
        for t in {t for _, _, t in plain if t}.difference(tails):
            tails[t] = self._library([t])[0]
        out.update((u, known[c] + tails[t] if t else known[c]) for u, c, t in plain)
        if len(known) > most:
            self.words = {}
        if len(tails) > 10_000:
            self.tails = {}
        return out

    def _units(self, text: str) -> list[str]:
        if self.spaced:
            return text.split(" ")
        # here white space only separates, and the library lowers the case, so forms of one word are one unit;
        # in Latin-1 lowering commutes with the library's other normalisation
        try:
            if not text.isascii():
                text.encode("latin-1")
            return text.lower().replace("\n", " ").split(" ")
        except UnicodeEncodeError:
            return text.replace("\n", " ").split(" ")

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of every text, whole."""
        if self.specials and (held := [i for i, t in enumerate(texts) if any(x in t for x in self.specials)]):
            whole = dict(zip(held, self._library([texts[i] for i in held]), strict=True))
            rest = iter(self.encode([t for i, t in enumerate(texts) if i not in whole]))
            return [whole[i] if i in whole else next(rest) for i in range(len(texts))]
        memo = self.units
        split = [self._units(t) for t in texts]
        heads = [""] * len(texts)
        if self.spaced:
            heads = [parts.pop(0) for parts in split]
        fresh = list(set().union(*split).difference(memo)) if split else []
        most = int(MEMO_UNITS * self.share)
        if len(memo) + len(fresh) > most:
            wanted = set().union(*split)
            self.units = memo = {u: memo[u] for u in wanted if u in memo}
        memo.update(self._learn(fresh))
        get, out = memo.__getitem__, [b""] * len(texts)
        odd: list[int] = []
        first = dict(zip(pick := [h for h in heads if h], self._library(pick), strict=True))
        for i, parts in enumerate(split):
            head = heads[i]
            if self.spaced and head and head[-1].isspace() and parts:
                odd.append(i)
                continue
            try:
                out[i] = first.get(head, b"") + b"".join(map(get, parts))
            except TypeError:
                odd.append(i)
        for i, ids in zip(odd, self._library([texts[i] for i in odd]), strict=True):
            out[i] = ids
        if len(memo) > most:
            self.units = {}
        else:
            for u in fresh:
                if len(u) > MEMO_CHARS:
                    del memo[u]
        return out


def encoder(path: str, spaced: bool, specials: bool = False) -> UnitEncoder:
    """The worker's encoder for this vocabulary file; kept between tasks, as workers are reused."""
    key = path, spaced, specials
    if key not in _ENCODERS:
        _ENCODERS[key] = UnitEncoder(*key)
    return _ENCODERS[key]


def forget() -> None:
    """Free this worker's memos; for operators that need the memory and no tokenizer."""
    for e in _ENCODERS.values():
        e.units, e.words = {}, {}


def slices(values: list[str], chars: int = 4_000_000):
    """Index ranges of about so many characters, so that a batch of long texts stays small."""
    start = total = 0
    for i, v in enumerate(values):
        total += len(v)
        if total >= chars:
            yield start, i + 1
            start, total = i + 1, 0
    if start < len(values):
        yield start, len(values)
