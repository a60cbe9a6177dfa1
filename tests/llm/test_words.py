import re

import numpy as np
import pyarrow as pa
from hypothesis import given, settings
from hypothesis import strategies as st

from axisgrove.llm import anchors
from axisgrove.llm.anchors import runs, runs_of_texts
from axisgrove.llm.suffix_dedup import _trimmed, repeated_windows
from axisgrove.llm.words import ALNUM, SPACED, Words, shingle_hashes, slices

texts = st.lists(st.one_of(st.none(), st.text(alphabet="ab C\t\n1é😀-", max_size=30)), max_size=6)


@settings(max_examples=80, deadline=None)
@given(texts)
def test_words_like_regex(values):
    for kind, pattern, lower in ((SPACED, r"[^\x20\x09-\x0D]+", False), (ALNUM, r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", True)):
        words = Words(pa.array(values, pa.string()), kind, lower)
        got = [x.decode() for x in words.packed().to_pylist()]
        low = [(v or "").replace("C", "c") if lower else v or "" for v in values]
        expected = [re.findall(pattern, v) for v in low]
        assert got == [w for e in expected for w in e] and words.counts().tolist() == [len(e) for e in expected]
        h = words.hashes()
        assert len(set(h.tolist())) == len(set(got))


def test_shingles():
    words = Words(pa.array(["a b c d e", "A B C D E", "x y", None, ""]), SPACED, True)
    found, owner = shingle_hashes(words, 4)
    assert np.bincount(owner, minlength=5).tolist() == [2, 2, 1, 0, 0]
    assert sorted(found[owner == 0]) == sorted(found[owner == 1])


def test_slices_lose_nothing():
    batch = pa.RecordBatch.from_arrays([pa.array(["x" * n for n in (5, 0, 300, 2, 2)])], names=["t"])
    assert [r for part in slices(batch, "t", 10) for r in part.column(0).to_pylist()] == batch.column(0).to_pylist()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.sampled_from([b"abcdefgh" * 9, b"the quick brown fox jumps over the lazy dog and runs. ", bytes(range(60, 120)), b"z" * 50]), min_size=1, max_size=12), st.integers(30, 60))
def test_equal_windows_share_anchor_and_offset(parts, length):
    data = np.frombuffer(b"".join(parts), np.uint8)
    start, count, anchor, _ = runs(data, length)
    if len(data) < length:
        assert len(start) == 0
        return
    assert count.sum() == len(data) - length + 1 and start[0] == 0
    seen = {}
    for s, n, a in zip(start.tolist(), count.tolist(), anchor.tolist(), strict=True):
        for i in range(s, s + n):
            assert seen.setdefault(data[i : i + length].tobytes(), a) == a


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 3), min_size=20, max_size=400), st.integers(8, 20), st.integers(1, 50))
def test_suffix_classes_like_brute_force(values, length, bucket):
    text = bytes(v + 97 for v in values) * 2
    data = np.frombuffer(text + bytes(36), np.uint8)
    places = np.arange(len(text) - length + 1)
    got = []
    for rows, number in repeated_windows(data, places, length, bucket):
        got += [tuple(sorted(places[rows[number == n]].tolist())) for n in np.unique(number)]
    expected: dict = {}
    for i in places.tolist():
        expected.setdefault(text[i : i + length], []).append(i)
    assert sorted(got) == sorted(tuple(v) for v in expected.values() if len(v) > 1)


def test_runs_of_many_texts_like_one_by_one(monkeypatch):
    rng = np.random.default_rng(4)
    texts = [bytes(rng.integers(97, 101, n).astype(np.uint8)) for n in (0, 150, 99, 100, 101, 700, 5, 0, 3000, 100)]
    expected = [(i, *row) for i, t in enumerate(texts) for row in zip(*(v.tolist() for v in runs(np.frombuffer(t, np.uint8), 100)), strict=True)]
    offsets = np.cumsum([0, *map(len, texts)])
    for chunk in 1, 400, 1 << 16:
        monkeypatch.setattr(anchors, "CHUNK", chunk)
        got = runs_of_texts(np.frombuffer(b"".join(texts), np.uint8), offsets, 100)
        assert list(zip(*(v.tolist() for v in got[:5]), strict=True)) == expected


def test_segments_without_a_half_in_common_are_not_sorted():
    rng = np.random.default_rng(6)
    for length in 30, 100:
        texts = [bytes(rng.integers(97, 123, 150).astype(np.uint8)) for _ in range(4)]
        texts += [texts[0][:90] + texts[1][90:], texts[2][:40] + texts[0][40:110] + texts[3][110:], texts[1][20:60] + texts[3]]
        data = np.frombuffer(b"".join(texts) + bytes(64 + length), np.uint8)
        offsets = np.cumsum([0, *map(len, texts)])
        owner, start, n, anchor, _, place = runs_of_texts(data[: offsets[-1]], offsets, length)
        base = offsets[owner] + start
        first, stop = _trimmed(data, base, n, place, anchor.view(np.int64), length)
        windows = lambda a, b: [bytes(data[s + i : s + i + length]) for s, x, y in zip(base, a, b, strict=True) for i in range(x, y)]
        everything, left = windows(0 * n, n), windows(first, stop)
        assert {w for w in everything if everything.count(w) > 1} <= set(left)
        assert all(everything.count(w) == left.count(w) for w in set(left) if everything.count(w) > 1)
        if length == 100:
            assert 0 < len(left) < len(everything) // 2
