"""Packing, token files, BPE and media against their libraries, with the odd cases of texts."""

import hashlib
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from nodeweave.llm import bpe, encode, media, packing, tokenfile

TEXTS = ["", " ", "  a b", "a  b", "a b ", "a \n b", "a\n\nb c", "xİ yİz á éa", "don't can't 's", "<|endoftext|> a<|endoftext|>b", "ΣΑΣ Σ.", "a\u00a0b\u0085 c", "12 a1 1a, a., b!? .", "\x1c a\x1c b", "Å ﬁ ẞ É", "日本 語 ไทย", "aaaaaaaaaa aaaa", "x" * 30_000, "word, " * 20_000, "🙂🙂 🙂", None, "same", "same"]
KINDS = "doc_id long, text string, lang string, source string, n_chars long, length int, start int, fp long, score double, ids string, sequence_id int"


def frame(spark, texts=TEXTS):
    rows = [(i, t, "en", "s", 0, 7, 7, 7, 0.5, "x", 1) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, KINDS).repartition(3)


def library(name):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path(name))
    t.encode_special_tokens = True
    return lambda x: t.encode(x or "", add_special_tokens=False).ids


def crc(ids):
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


@pytest.mark.parametrize("name,spaced", [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_unit_encoder_equals_the_library(name, spaced, monkeypatch):
    one = library(name)
    texts = [t or "" for t in TEXTS]
    enc = encode.UnitEncoder(P.path(name), spaced)
    for _ in range(2):
        assert [np.frombuffer(x, "<u4").tolist() for x in enc.encode(texts)] == [one(t) for t in texts]
    monkeypatch.setattr(encode, "MEMO_UNITS", 3)
    monkeypatch.setattr(encode, "MEMO_WORDS", 3)
    small = encode.UnitEncoder(P.path(name), spaced)
    for t in texts:
        assert np.frombuffer(small.encode([t])[0], "<u4").tolist() == one(t)


@pytest.mark.parametrize("name,spaced", [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_share_bounds_the_memos(name, spaced, monkeypatch):
    """An encoder with a share of the memos holds no more than that between calls, and gives the library's ids."""
    monkeypatch.setattr(encode, "MEMO_UNITS", 400)
    monkeypatch.setattr(encode, "MEMO_WORDS", 400)
    one, enc = library(name), encode.UnitEncoder(P.path(name), spaced)
    enc.share = 0.25
    for i in range(12):
        text = " ".join(f"w{chr(97 + j % 26)}{chr(97 + j // 26)}{chr(97 + i)} {i}x{j}" for j in range(40))
        assert np.frombuffer(enc.encode([text])[0], "<u4").tolist() == one(text)
        assert len(enc.units) <= 100 and len(enc.words) <= 100


@pytest.mark.parametrize("name,spaced", [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_special_strings_on_demand(name, spaced):
    """By default they are ordinary text; with ``specials`` ids are those of a library as it comes."""
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(P.path(name))
    texts = ["hello <|endoftext|> world", "<|startoftext|>a b", "a <|endoftext|>", "nothing here", "", "<|endoftext|>"]
    got = encode.encoder(P.path(name), spaced, True).encode(texts)
    assert [np.frombuffer(x, "<u4").tolist() for x in got] == [plain.encode(t, add_special_tokens=False).ids for t in texts]


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet=st.sampled_from("aAbBzZéÉßſİǅ .,'!\n\t\u00a0\u030112"), max_size=30))
def test_unit_encoder_on_any_text(text):
    for name, spaced in (("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)):
        got = encode.encoder(P.path(name), spaced).encode([text])[0]
        assert np.frombuffer(got, "<u4").tolist() == library_memo(name)(text)


_LIB = {}


def library_memo(name):
    return _LIB.setdefault(name, library(name))


def test_packing(spark):
    rows = packing.pack(frame(spark), P.path("byte_bpe_50k.json")).collect()
    one = library("byte_bpe_50k.json")
    ids = {i: [*one(t), 1] for i, t in enumerate(TEXTS)}
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append(r)
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] and crc(part) == r["ids_crc32"] and r["doc_tokens"] == len(ids[r["doc_id"]])
    for d, own in by_doc.items():
        assert sorted((r["start"], r["length"]) for r in own)[0][0] == 0 and sum(r["length"] for r in own) == len(ids[d])
    assert set(by_doc) == set(ids)
    for own in by_seq.values():
        at = 0
        for r in sorted(own, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
    full = packing.sequences(frame(spark), P.path("byte_bpe_50k.json")).collect()
    assert len(full) == len(by_seq) and all(len(r["tokens"]) == 2048 or len(r["tokens"]).bit_count() == 1 for r in full)


@settings(max_examples=100, deadline=None)
@given(st.dictionaries(st.integers(1, 64), st.integers(1, 200), max_size=30))
def test_histogram_packing_places_all(histogram):
    patterns = packing.pack_histogram(histogram, 64)
    placed = {}
    for count, parts in patterns:
        assert sum(n * t for n, t in parts) <= 64
        for n, t in parts:
            placed[n] = placed.get(n, 0) + count * t
    assert placed == histogram
    for length, rows in packing.slots(patterns).items():
        assert sorted(r[0] for r in rows)[0] == 0 and sum(r[1] * r[4] for r in rows) == histogram[length]


def test_padding_is_small():
    rng = np.random.default_rng(0)
    histogram = dict(zip(*[x.tolist() for x in np.unique(rng.integers(1, 2049, 50_000), return_counts=True)], strict=True))
    p = packing.padding(histogram, 2048)
    assert p["padding"] < 0.01 * p["ids"]


def test_token_files(spark):
    path = tokenfile.write_tokens(frame(spark), P.path("word_bpe_49k.json"), segment_ids=5000)
    rows = sorted(tokenfile.read_tokens(spark, path, keep_ids=True).collect(), key=lambda r: r["doc_id"])
    one, at = library("word_bpe_49k.json"), 0
    assert [r["doc_id"] for r in rows] == list(range(len(TEXTS)))
    for r, t in zip(rows, TEXTS, strict=True):
        ids = [*one(t), 2]
        assert (r["start"], r["n_tokens"], r["ids_crc32"], r["ids"]) == (at, len(ids), crc(ids), ids)
        at += len(ids)
    again = spark.createDataFrame([(1, "b"), (1, "a"), (1, "a")], "doc_id long, text string")
    starts = sorted(r["start"] for r in tokenfile.read_tokens(spark, tokenfile.write_tokens(again, P.path("word_bpe_49k.json"))).collect())
    assert len(set(starts)) == 3


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.integers(0, 60), st.integers(0, 2**32 - 1)), max_size=400), st.integers(0, 400), st.integers(0, 400))
def test_segment_round_trip(values, first, last):
    ids = np.array(values, dtype=np.uint32)
    data = tokenfile.encode_segment([1], [len(ids)], ids)
    assert (tokenfile.decode_segment(data) == ids).all()
    assert (tokenfile.decode_segment(data, first, last) == ids[first:last]).all()


def test_segment_uses_exceptions():
    ids = np.arange(128, dtype=np.uint32) % 8
    plain = len(tokenfile.encode_segment([1], [128], ids))
    ids[5] = 2**31
    assert len(tokenfile.encode_segment([1], [128], ids)) < plain + 10


def reference():
    import tiktoken

    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_query_equals_the_library(spark):
    ref = reference()
    rows = bpe.encode_decode(frame(spark), P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN, keep_ids=True).collect()
    assert len(rows) == len(TEXTS)
    for r in rows:
        t = TEXTS[r["doc_id"]] or ""
        ids = ref.encode_ordinary(t)
        assert r["ids"] == ids and r["n_tokens"] == len(ids) and bytes(r["decoded"]) == t.encode()
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(t.encode()).hexdigest()


_REF = []


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet=st.sampled_from("abc de=-!\n\t '日é1🙂"), max_size=40), min_size=1, max_size=4))
def test_replay_on_any_text(texts):
    if not _REF:
        _REF.extend([reference(), bpe.MergeReplay(bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken")), P.PATTERN)])
    ref, own = _REF
    assert [np.frombuffer(x, "<u4").tolist() for x in own.encode(texts)] == [ref.encode_ordinary(t) for t in texts]


@settings(max_examples=100, deadline=None)
@given(st.lists(st.text(alphabet="abc", min_size=1, max_size=12), min_size=1, max_size=5), st.randoms())
def test_replay_with_ranks_out_of_order(words, rnd):
    """Tables where a merge opens a pair of lower rank: those pre-tokens go alone, and equal the reference."""
    import tiktoken

    tokens = [x.encode() for x in ("ab", "bc", "abc", "ca", "aa", "cab", "bb", "aab", "abab")]
    rnd.shuffle(tokens)
    ranks = {bytes([b]): b for b in range(256)} | {t: 256 + i for i, t in enumerate(tokens)}
    ref = tiktoken.Encoding("odd", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = bpe.MergeReplay(ranks, P.PATTERN).replay([w.encode() for w in dict.fromkeys(words)])
    assert [np.frombuffer(x, "<u4").tolist() for x in got] == [ref.encode_ordinary(w) for w in dict.fromkeys(words)]


def test_media(spark):
    import io
    import wave

    rows = {r["doc_id"]: r for r in media.features(media.store(frame(spark)), keep=True).collect()}
    assert len(rows) == len(TEXTS) and rows[21]["feature"] == rows[22]["feature"] and rows[0]["feature"] == rows[20]["feature"]
    for i, t in enumerate(TEXTS):
        raw, r = (t or "").encode(), rows[i]
        want = raw + bytes(-len(raw) % 64 if raw else 64)
        with wave.open(io.BytesIO(bytes(r["media"]))) as w:
            assert w.readframes(w.getnframes()) == want and w.getsampwidth() == 1
        assert (r["n_bytes"], r["payload_bytes"], r["tail_crc32"]) == (len(raw), len(want), zlib.crc32(want[-64:]))
        assert r["payload_sha256"] == hashlib.sha256(want).hexdigest() and r["media_sha256"] == hashlib.sha256(bytes(r["media"])).hexdigest() and r["media_bytes"] == len(r["media"])
        assert r["feature"] == f"{len(r['landmarks'])}:{hashlib.sha256(np.array(r['landmarks'], '<i8').tobytes()).hexdigest()}" and len(r["landmarks"]) >= 6
        assert len(want) > 20_000 or r["landmarks"] == brute_landmarks(want)


def brute_landmarks(samples):
    """Peak pairs with a plain discrete Fourier transform, frame by frame."""
    w = media.WINDOW
    x = [b - 128.0 for b in samples]
    frames = max(1, -(-(len(x) - w) // media.HOP) + 1)
    x += [0.0] * ((frames - 1) * media.HOP + w - len(x))
    wave = np.exp(-2j * np.pi * np.outer(np.arange(w // 2 + 1), np.arange(w)) / w)
    hann = [0.5 - 0.5 * np.cos(2 * np.pi * n / (w - 1)) for n in range(w)]
    peaks = []
    for f in range(frames):
        size = np.round(np.abs(wave @ np.array([np.float32(a) * np.float32(h) for a, h in zip(x[f * media.HOP : f * media.HOP + w], hann, strict=True)])), 2)
        peaks.append([max(range(a, b), key=lambda k: (size[k], -k)) for a, b in zip(media.BANDS, media.BANDS[1:], strict=False)])
    out = [(f << 32) | (a << 20) | (b << 8) for f, p in enumerate(peaks) for i, a in enumerate(p) for b in p[i + 1 :]]
    out += [(f << 32) | (a << 20) | (b << 8) | gap for f, p in enumerate(peaks) for gap in range(1, media.FAN_OUT + 1) if f + gap < frames for a in p for b in peaks[f + gap]]
    return sorted(out)


def test_media_spectrum_is_a_short_time_fourier_transform():
    samples = bytes((128 + 100 * np.sin(2 * np.pi * 20 * np.arange(1024) / media.WINDOW)).astype(np.uint8))
    mag = media.spectrum(samples)
    assert mag.shape == (3, 257) and (mag[:, 1:].argmax(axis=1) + 1 == 20).all()


def test_empty_tables(spark):
    none = frame(spark).limit(0)
    assert packing.pack(none, P.path("byte_bpe_50k.json")).count() == 0
    assert tokenfile.read_tokens(spark, tokenfile.write_tokens(none, P.path("word_bpe_49k.json"))).count() == 0
    assert bpe.encode_decode(none, P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN).count() == 0
    assert media.features(media.store(none)).count() == 0
