"""Words are what Python parts, each different word of a batch is hashed once, and the n-grams' lists need no sort by two keys."""

import numpy as np
import pyarrow as pa
import xxhash

from relmine.llm import quality


def plain(text):
    words = (text or "").split()
    h = [xxhash.xxh3_64_intdigest(w.encode()) | 8 for w in words]
    return [x ^ int(quality.AGAIN) if i and words[i - 1] == words[i] else x for i, x in enumerate(h)]


TEXTS = ["a b  b b\tc", None, "", "  ", "　c c d\x1ce\x85f  ", "c", "x" * 70, "c c", "é é ß 𝒳 a​b", None]


def test_words_are_those_of_split():
    for texts in (TEXTS, TEXTS[1:4], ["b", "b", "b b"], []):
        got = quality.word_hashes(pa.array(texts, pa.string()))
        assert [t.tolist() for t in got] == [plain(t) for t in texts]
    sliced = pa.array(TEXTS, pa.string()).slice(3, 4)
    assert [t.tolist() for t in quality.word_hashes(sliced)] == [plain(t) for t in TEXTS[3:7]]
    every = [f"a{chr(c)}b" for c in range(0x110000) if not 0xD800 <= c <= 0xDFFF]
    assert [len(t) for t in quality.word_hashes(pa.array(every))] == [len(t.split()) for t in every]


def test_each_word_of_a_batch_is_hashed_once(monkeypatch):
    asked, digest = [], xxhash.xxh3_64_intdigest
    monkeypatch.setattr(quality.xxhash, "xxh3_64_intdigest", lambda w: asked.append(w) or digest(w))
    quality.word_hashes(pa.array(["b a b a"] * 40 + ["c a"] * 40))
    assert len(asked) == 3


def test_lists_are_the_same_however_they_are_sorted():
    class Frame:
        def select(self, *names):
            return self

        def mapInArrow(self, run, schema):
            return run

    rows = pa.RecordBatch.from_arrays([pa.array(range(10), pa.int64()), pa.array([3] * 10, pa.int64()), pa.array(TEXTS, pa.string())], names=["key", "l", "text"])
    lists = [[r for b in quality.packed_documents(Frame(), 2, 1, bits)([rows]) for r in b.to_pylist()] for bits in (60, 64)]
    keys = [np.cumsum(quality._spread(r[0]["keys"], np.uint64), dtype=np.uint64) for r in lists]
    assert (keys[0] == keys[1] >> np.uint64(4)).all()
    assert all(lists[0][0][c] == lists[1][0][c] for c in ("a", "b", "c", "tokens"))
