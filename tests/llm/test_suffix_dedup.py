from __future__ import annotations

import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from gleaner.llm import suffix_dedup as S

SCHEMA = "doc_id long, text string, _cut string, h long"


def brute(texts: dict, window: int, keep_first: bool = False) -> dict:
    """Marks byte by byte."""
    seen, first = Counter(), {}
    data = {k: (t or "").encode() for k, t in texts.items()}
    for k in sorted(data):
        for i in range(len(data[k]) - window + 1):
            w = data[k][i : i + window]
            seen[w] += 1
            first.setdefault(w, (k, i))
    out = {}
    for k, t in data.items():
        gone = np.zeros(len(t) + 1, dtype=bool)
        for i in range(len(t) - window + 1):
            w = t[i : i + window]
            if seen[w] > 1 and not (keep_first and first[w] == (k, i)):
                gone[i : i + window] = True
        kept = bytes(b for b, g in zip(t, gone, strict=False) if not g)
        out[k] = (len(t), int(gone.sum()), int((np.diff(gone.astype(int), prepend=0) == 1).sum()), hashlib.sha256(kept).hexdigest())
    return out


def corpus() -> dict:
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randint(2, 6)))
    prose = lambda n: " ".join(word() for _ in range(n))
    shared = [prose(60) for _ in range(3)]
    texts = {1: None, 2: "", 3: "short", 4: "x" * 900, 5: "ab" * 300, 6: "x" * 450}
    for i in range(7, 60):
        parts = [prose(rng.randint(5, 60)) for _ in range(3)]
        if i % 3 == 0:
            parts.insert(rng.randint(0, 3), shared[i % 2])
        if i % 5 == 0:
            parts.insert(rng.randint(0, 3), shared[2][: 190 + i])
        texts[i] = " ".join(parts)
    texts[60] = texts[9]
    texts[61] = texts[12] + shared[0] + shared[0]
    return texts


@pytest.mark.parametrize("keep_first", [False, True])
@pytest.mark.parametrize("crowd", [4000, 3])
def test_equals_brute_force(spark, monkeypatch, keep_first, crowd):
    if crowd == 3:
        monkeypatch.setattr(S, "SPREAD", 2)  # nearly all hashes go the way of heavy ones
        monkeypatch.setattr(S, "HEAVY", 0)
    texts = corpus()
    docs = spark.createDataFrame([(k, t, "clash", 5) for k, t in texts.items()], SCHEMA)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in S.suffix_dedup(docs, keep_first=keep_first, crowd=crowd).collect()}
    assert got == brute(texts, S.WINDOW, keep_first)


def test_long_texts_in_parts(monkeypatch):
    rng = random.Random(3)
    text = bytes(rng.randrange(97, 123) for _ in range(5000))
    whole = {(int(x), int(f) + i) for x, _, f, n in zip(*S.anchors(text, np.array([5000])), strict=True) for i in range(n)}
    monkeypatch.setattr(S, "CHUNK", 700)
    parts = set()
    for data, ends, _, shift in S._portions([text], S.WINDOW):
        parts |= {(int(x), int(f) + i + int(shift[0])) for x, _, f, n in zip(*S.anchors(data, ends), strict=True) for i in range(n)}
    assert parts == whole


def test_longest_previous_factors():
    data = b"abaababaabab"
    order, _ = S.suffix_order(np.frombuffer(data, dtype=np.uint8), 16)
    assert order.tolist() == sorted(range(len(data)), key=lambda i: data[i:])
    common = lambda i, j: next((k for k in range(99) if max(i, j) + k >= len(data) or data[i + k] != data[j + k]), 99)
    lcp = np.array([0, *(common(order[i - 1], order[i]) for i in range(1, len(data)))])
    assert S.longest_previous_factors(order, lcp).tolist() == [max((common(i, j) for j in range(i)), default=0) for i in range(len(data))]


def test_empty_nulls_and_cut(spark):
    assert S.suffix_dedup(spark.createDataFrame([], SCHEMA)).count() == 0
    same = "lorem ipsum dolor " * 20
    docs = spark.createDataFrame([(None, same, "a", 1), (2, same, "b", 2), (2, same, "b", 2), (3, None, "c", 3)], SCHEMA)
    rows = S.suffix_dedup(docs).collect()
    assert len(rows) == 4 and sum(r.n_removed for r in rows) == 3 * len(same)
    kept = {(r.doc_id, r._cut): r.text for r in S.cut_repeats(docs).collect()}
    assert kept[None, "a"] == "" and kept[3, "c"] is None and kept[2, "b"] != ""
