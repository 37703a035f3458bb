"""Properties of the small kernels."""

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from geoprobe.llm import bpe, decontamination, media, substring_dedup, words

BYTES = st.binary(max_size=2000)


@given(st.lists(st.tuples(st.integers(0, 50), st.integers(0, 6))))
def test_merged_covers_the_same(spans):
    closed = [(a, a + n) for a, n in spans]
    out = decontamination.merged(closed)
    cover = lambda rows: {p for a, b in rows for p in range(a, b + 1)}
    assert cover(out) == cover(closed) and all(b + 1 < c for (_, b), (c, _) in zip(out, out[1:], strict=False))


@given(st.lists(st.integers(0, 2**63), min_size=1, max_size=80), st.integers(1, 80))
def test_sliding_minimum(values, width):
    x, width = np.array(values, np.uint64), min(width, len(values))
    assert words.sliding_minimum(x, width).tolist() == [min(values[i : i + width]) for i in range(len(values) - width + 1)]


@settings(deadline=None)
@given(BYTES, st.integers(0, 4))
def test_png_round_trip(data, kind):
    payload = media.padded(data)
    assert len(payload) % 576 == 0 and payload.startswith(data)
    assert media.decode_png(media.encode_png(payload, kind=kind)).tobytes() == payload


@settings(deadline=None)
@given(st.lists(st.sampled_from(["a", "b", "c"]), max_size=140), st.integers(0, 4))
def test_super_kmers_cover_every_window_once(tokens, order):
    flat, ends = words.hashed([[t.encode() for t in tokens], [b"x"] * 55, []])
    doc, start, count, low, sequence = substring_dedup.super_kmers(flat, ends, 50, order)
    got = sorted((d, s + i) for d, s, n in zip(doc.tolist(), start.tolist(), count.tolist(), strict=True) for i in range(n))
    assert got == [(0, i) for i in range(max(0, len(tokens) - 49))] + [(1, i) for i in range(6)]


@given(st.lists(st.tuples(st.integers(0, 5), st.lists(st.integers(0, 1), min_size=1, max_size=24)), min_size=1, max_size=8), st.integers(1, 9))
def test_repeats_by_sorting(rows, window):
    """Sorted windows against a dictionary of them."""
    given_ = [(doc, n, 100 * n, np.array(words, np.int32)) for n, (doc, words) in enumerate(rows)]
    least = {}
    for doc, words in rows:
        for i in range(len(words) - window + 1):
            w = tuple(words[i : i + window])
            least[w] = min(least.get(w, doc), doc)
    want = {(n, i) for n, (doc, words) in enumerate(rows) for i in range(len(words) - window + 1) if least[tuple(words[i : i + window])] < doc}
    got = substring_dedup.repeats_in_buckets(given_, window).tolist()
    cover = [(n, start - 100 * n + i) for doc, n, start, count in got for i in range(count)]
    assert len(cover) == len(set(cover)) and set(cover) == want and all(rows[n][0] == doc for doc, n, _, _ in got)


@given(st.lists(st.sampled_from("abcde"), min_size=2, max_size=40), st.integers(1, 20))
def test_stretch_hash_is_of_content(tokens, size):
    flat, _ = words.hashed([[t.encode() for t in tokens]])
    size = min(size, len(tokens))
    first = np.arange(len(tokens) - size + 1)
    got = substring_dedup._SEQUENCE.stretches(flat, first, first + size).tolist()
    text = ["".join(tokens[i : i + size]) for i in first.tolist()]
    assert all((a == b) == (x == y) for a, x in zip(got, text, strict=True) for b, y in zip(got, text, strict=True))


_ENCODER: list[bpe.Encoder] = []


def repeated_scans(own, data):
    """Merging by the rule itself: the leftmost pair of the lowest rank, until none is left."""
    live = [*(own.inner[b] for b in data[:-1]), own.last[data[-1]]]
    while True:
        ranks = [own.ranks.get(a << 20 | b, bpe.NEVER) for a, b in zip(live, live[1:], strict=False)]
        if not ranks or min(ranks) == bpe.NEVER:
            return live
        i = ranks.index(min(ranks))
        live[i : i + 2] = [own.products[ranks[i]]]


@settings(deadline=None, max_examples=60)
@given(st.lists(st.text(alphabet="abcdeinorst'é漢", min_size=1, max_size=70), min_size=1, max_size=60))
def test_trees_merge_as_repeated_scans(words):
    """One tree for a word and many side by side, at every length."""
    if not _ENCODER:
        _ENCODER.append(bpe.Encoder(bpe.default_path()))
    own, data = _ENCODER[0], [w.encode() for w in words]
    wanted = [repeated_scans(own, d) for d in data]
    assert own.merged_words(data) == wanted
    for d, ids in zip(data, wanted, strict=True):
        size = 1 << max(0, len(d) - 2).bit_length()
        assert own.forest([d], size) == [ids] == [own.merge([*(own.inner[b] for b in d[:-1]), own.last[d[-1]]])]


def test_generations_keep_what_comes_again(monkeypatch):
    monkeypatch.setattr(bpe, "REMEMBERED", 20)
    own = bpe.Encoder(bpe.default_path())
    texts = [f"alpha beta{i} gamma, delta{i % 7}!" for i in range(60)]
    once = [own.summary(t) for t in texts]
    assert own.summaries(texts) == once == bpe.Encoder(bpe.default_path()).summaries(texts)
