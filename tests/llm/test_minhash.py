"""Fingerprints, likeness and the next document, compared with brute force."""

from __future__ import annotations

import hashlib
import random
import re
import struct

import pytest
import xxhash

from gleaner.llm import minhash


def signed(h: int) -> int:
    return h - (1 << 64) if h >> 63 else h


def chain(values: list[int], form: str = "q") -> int:
    """One hash of several numbers, each seeded by that of those before."""
    seed = 42
    for i, v in enumerate(values):
        seed = xxhash.xxh64_intdigest(struct.pack("<" + (form[i] if len(form) > 1 else form), v), seed=seed)
    return signed(seed)


def brute_bins(text: str) -> list[int]:
    words = [signed(xxhash.xxh64_intdigest(w.encode(), seed=42)) for w in re.findall(r"[a-z0-9]+", text.lower())]
    hashes = [chain(words[i : i + 5]) for i in range(max(1, len(words) - 4))] if words else []
    full = {}
    for h in hashes:
        full[h >> 56] = min(h, full.get(h >> 56, h))
    if not full:
        return [255 - 128] * minhash.BINS
    looks, out = minhash._probes(minhash.PROBES), []
    for j in range(minhash.BINS):
        places = [j, *(p[j] for p in looks)]
        found = next((full[p - 128] for p in places if p - 128 in full), None)
        if found is None:
            found = min((chain([j, b], "iq"), v) for b, v in full.items())[1]
        out.append((found & 255) - 128)
    return out


def brute_like(a: list[int], b: list[int]) -> float:
    return 1.0 if a == b else max(0.0, (sum(x == y for x, y in zip(a, b)) / minhash.BINS - 1 / 256) / (1 - 1 / 256))


@pytest.mark.parametrize("bucket_rows", [1, 4096])
@pytest.mark.parametrize("ids", ["even", "uneven"])
def test_fingerprints_are_brute_force(spark, bucket_rows, ids, monkeypatch):
    dice = random.Random(5)
    # Few quantiles, so that equal widths within them make the buckets.
    monkeypatch.setattr(minhash, "QUANTILES", 3)
    keys = range(60) if ids == "even" else sorted({dice.randrange(10**dice.randrange(1, 18)) * dice.choice((1, -1)) for _ in range(60)})
    vocabulary = [f"w{i}" for i in range(40)]
    docs = [(k, " ".join(dice.choices(vocabulary, k=dice.choice((0, 1, 4, 5, 9, 60, 400))))) for k in keys]
    docs += [(None, "the last one has no number at all")]
    frame = spark.createDataFrame(docs, "doc_id long, text string").repartition(5)
    got = {r.doc_id: r for r in minhash.fingerprints(frame, bucket_rows).collect()}
    assert len(got) == len(docs)
    order = [docs[-1 - 1 - i] for i in range(len(docs) - 1)] + [docs[-1]]  # descending, the null one last
    for i, (k, text) in enumerate(order):
        following = order[(i + 1) % len(order)][1]
        half = len(text) // 2
        edited = text[: len(text) - half] + following[:half]
        mine, changed, behind = brute_bins(text), brute_bins(edited), brute_bins(following)
        row = got[k]
        assert row.n_chars == len(text) and row.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert row.fingerprint == "".join(f"{b + 128:02x}" for b in mine) and row.edited_fingerprint == "".join(f"{b + 128:02x}" for b in changed)
        assert row.near_edited == pytest.approx(brute_like(mine, changed)) and row.near_next == pytest.approx(brute_like(mine, behind))


def test_likeness_is_near_jaccard(spark):
    """Without bias: over pairs of known overlap the mean error is small."""
    dice = random.Random(7)
    texts = []
    for share in (0.2, 0.5, 0.8):
        for _ in range(12):
            words = [f"x{dice.randrange(10**9)}" for _ in range(400)]
            texts.append((share, " ".join(words), " ".join(words[: int(400 * share)] + [f"y{dice.randrange(10**9)}" for _ in range(400 - int(400 * share))])))
    a = minhash.with_bins(spark.createDataFrame([(i, s, x, y) for i, (s, x, y) in enumerate(texts)], "i int, share double, x string, y string"), "x", "p")
    rows = minhash.with_bins(a, "y", "q").select("share", minhash.likeness(minhash.F.col("p"), minhash.F.col("q")).alias("like")).collect()
    for share in (0.2, 0.5, 0.8):
        common = 400 * share - 4
        exact = common / (2 * 396 - common)
        likes = [r.like for r in rows if r.share == share]
        assert abs(sum(likes) / len(likes) - exact) < 0.03
