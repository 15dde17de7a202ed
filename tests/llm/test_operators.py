"""Small fixtures, compared with brute force."""

from __future__ import annotations

import hashlib
import re
import zlib

import numpy as np
import pytest
import xxhash

from gleaner.llm import exact_dedup, html_text, langid, licenses, merge_dropout, minhash, packing, simhash, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keep_id string, fp string, length string"
TEXTS = {
    1: "The MIT License and the apache  license.\nSPDX-License-Identifier: (MIT OR Apache-2.0) AND BSD-3-Clause WITH x", 2: None, 3: "", 4: "the mit license and the Apache license.",
    5: "lorem ipsum dolor " * 3000, 6: "lorem ipsum dolor " * 3000 + "sit", 7: "été ▁ 漢字 😀\t\n x", 8: "a b", 9: "a\t b", 10: "<|endoftext|> it's 42",
}


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(k, t, None if k == 4 else "en", None, len(t or ""), "clash", "clash", "clash") for k, t in TEXTS.items()]
    return spark.createDataFrame([*rows, rows[7], (None, "a b", "en", None, 3, "", "", "")], SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_licenses(docs, empty):
    rows = {r.doc_id: r for r in licenses.license_scan(docs).collect()}
    for k, t in TEXTS.items():
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        at = [i for p in licenses.BASE for i in range(len(words)) if words[i : i + len(p.split())] == p.split()]
        assert (rows[k].n_words, rows[k].n_base, rows[k].first_word, rows[k].last_word) == (len(words), len(at), min(at, default=None), max(at, default=None))
    assert rows[1].base_labels == "apache,mit" and "bsd-3-clause with x" in rows[1].labels
    assert licenses.license_scan(empty).count() == 0
    assert set(licenses.alternatives("MIT OR Apache-2.0 AND BSD")) == {frozenset(["mit"]), frozenset(["apache-2.0", "bsd"])}


def test_exact_dedup(docs, empty):
    rows = exact_dedup.exact_dedup(docs).collect()
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    assert len(rows) == 12 and exact_dedup.exact_dedup(empty).count() == 0
    for r in rows:
        group = [k for k, t in TEXTS.items() if norm(t) == norm(TEXTS.get(r.doc_id, "a b"))]
        assert r.keep_id == min(group) and r.kept == (r.doc_id == min(group)) and r.text_sha256 == hashlib.sha256(norm(TEXTS.get(r.doc_id, "a b")).encode()).hexdigest()
    weak = exact_dedup.exact_dedup(docs, digest=lambda c: c.substr(1, 1))  # digests that clash
    assert sorted(map(str, weak.collect())) == sorted(map(str, rows))
    assert sorted(r.doc_id for r in exact_dedup.drop_exact(docs).collect()) == [1, 2, 4, 5, 6, 7, 8, 10]


def test_simhash(docs, empty):
    def brute(t):
        w = re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", w) if x]
        h = [xxhash.xxh64_intdigest(" ".join(s), 42) for s in ([w[i : i + 3] for i in range(len(w) - 2)] or [w])] if w else []
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    fps = {k: brute(t) for k, t in TEXTS.items()}
    got = {r.doc_id: r for r in simhash.simhash_components(docs).collect()}
    assert all(int(got[k].fingerprint, 16) == v for k, v in fps.items()) and got[3].component_id == 2 and got[6].component_id == 5
    assert simhash.simhash_components(empty).count() == 0


@pytest.mark.parametrize("tile", [8192, 20])
def test_links_are_complete(spark, tile):
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 12, dtype=np.int64)
    fps = sorted({int(b) ^ (1 << int(i)) ^ (1 << int(j)) for b in base for i, j in rng.integers(0, 62, (12, 2))})
    links = simhash.near_links(spark.createDataFrame([(x,) for x in fps], "fp long"), tile=tile)
    up = {x: x for x in fps}
    root = lambda x: x if up[x] == x else root(up[x])
    for r in links.collect():
        assert (r.a ^ r.b).bit_count() <= 2
        up[root(r.a)] = root(r.b)
    want = {x: x for x in fps}
    find = lambda x: x if want[x] == x else find(want[x])
    for i, x in enumerate(fps):
        for y in fps[:i]:
            if (x ^ y).bit_count() <= 2:
                want[find(x)] = find(y)
    assert all((root(x) == root(y)) == (find(x) == find(y)) for x in fps for y in fps)


def test_packing(docs, empty):
    from tokenizers import Tokenizer

    encode = Tokenizer.from_file(packing.vocabulary()).encode
    rows = packing.pack(docs).collect()
    assert packing.pack(empty).count() == 0
    for r in rows:
        ids = [*encode(TEXTS.get(r.doc_id, "a b") or "", add_special_tokens=False).ids, 1]
        assert r.start == 4096 * r.piece and r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], dtype="<u4").tobytes())
    for s in {r.sequence_id for r in rows}:
        at = 0
        for r in sorted((r for r in rows if r.sequence_id == s), key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 4096
    counts = {60: 5, 40: 5, 30: 4, 70: 3, 50: 2, 20: 5, 100: 2}
    done = packing.plan(counts, 100)
    assert all(sum(p) <= 100 for p, _ in done) and {k: sum(p.count(k) * n for p, n in done) for k in counts} == counts


def test_merge_dropout(docs, empty):
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=merge_dropout.model_path())
    for r in merge_dropout.encode(docs).collect():
        text = TEXTS.get(r.doc_id, "a b") or ""
        assert "▁" in text or r.ids == model.encode(text)
    rows = merge_dropout.round_trip(docs).collect()
    assert len(rows) == 12 and all(r.lossless for r in rows) and merge_dropout.round_trip(empty).count() == 0
    assert any(r.n_varied != r.n_pieces for r in rows)


def test_minhash(docs, empty):
    rows = {r.doc_id: r for r in minhash.fingerprints(docs, bucket_rows=1).collect()}
    order = sorted(TEXTS, reverse=True)
    for k in order[:-1]:
        text, after = TEXTS[k] or "", TEXTS[order[order.index(k) + 1]] or ""
        n = len(text)
        edited = text[: n - n // 2] + after[: n // 2]
        if k != 8:  # stands twice
            assert rows[k].n_chars == n and rows[k].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
    assert rows[2].fingerprint == rows[3].fingerprint and rows[6].near_next > 0.5 and minhash.fingerprints(empty).count() == 0


def test_html():
    page = "<html><head><title>t</title><style>p{}</style></head><body><nav><a href=x>Menu</a></nav><div class=\"ad\">Buy</div><article><h1>Head &amp; line</h1><p><b>First\n one<br>two<p>Last.</p></article><div class='comments'><p>Nice</p></div><footer>&copy;</footer></body></html>"
    assert html_text.main_text(page) == "Head & line First one two Last." and html_text.main_text("") == ""


def test_language_and_toxicity(spark, docs, empty):
    said = {"aa": "wim wam wom ", "bb": "kri kra kro "}
    rows = [(i, said["aa" if i % 2 else "bb"] * 5 + ("scumm " if i % 3 == 0 else ""), "aa" if i % 2 else "bb") for i in range(200)]
    train = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert all(r.lang_pred == ("aa" if r.doc_id % 2 else "bb") for r in langid.identify(train).collect())
    assert {r.lang_pred for r in langid.identify(docs).where("doc_id in (2, 3)").collect()} == {"und"} and langid.identify(empty).count() == 0
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(200)], "doc_id long, toxic int")
    assert all(r.predicted == (r.doc_id % 3 == 0) for r in toxicity.toxicity(train, labels).collect())
    assert toxicity.toxicity(docs, labels.limit(0)).count() == 12 and toxicity.toxicity(empty, labels).count() == 0
    assert toxicity.drop_toxic(train, labels).count() == 133


def test_viterbi_reads_whole_tokens():
    from itertools import product

    rng = np.random.default_rng(3)
    lm = np.log(rng.dirichlet(np.ones(toxicity.A), (toxicity.A, toxicity.A)))

    def score(path):
        letters = [toxicity._INDEX[c] for x, _ in path for c in x]
        padded = [0, 0, *letters, 0]
        return sum(lm[tuple(padded[i : i + 3])] for i in range(len(padded) - 2)) - sum(cost for _, cost in path)

    for token in ("1d10t", "h44te", "b@$$", "l0ve.", "xx5%"):
        best = max(product(*toxicity.lattice(token)), key=score)
        assert toxicity.decode(token, lm) == "".join(x for x, _ in best)
    whole = toxicity.decode("ab0" * 500, lm)  # a look-alike may be dropped, a letter not
    assert (whole.count("a"), whole.count("b")) == (500, 500)
