"""The corpus pipeline against brute force, stage by stage, on a small corpus with planted cases."""

from __future__ import annotations

import random
import re

import pytest

from gleaner.llm import packing, toxicity
from tests.llm.test_near_dedup import _brute

WINDOW = 200


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    dice = random.Random(12)
    known = ["".join(dice.choice("abcdefghijklmno") for _ in range(dice.randrange(3, 9))) for _ in range(700)]
    prose = lambda n: " ".join(dice.choice(known) for _ in range(n))
    texts: list[str | None] = [prose(dice.randrange(30, 160)) for _ in range(120)]
    passage = prose(70)
    texts += [f"{prose(40)} {passage} {prose(30)}" for _ in range(8)]
    texts += [t.replace(" ", dice.choice(["  ", "\n", " \t"]), 3) for t in texts[:15]]  # exact copies
    for t in texts[20:35]:  # near copies
        words = t.split()
        texts.append(" ".join([*words[:-1], "changed"]) if len(words) > 60 else t)
    clean = len(texts)
    texts += [f"{prose(25)} scummface {prose(20)}" for _ in range(60)] + [f"{prose(25)} scummf@c3 {prose(20)}" for _ in range(3)] + [None, "", " "]
    rows = [(i + 1, t, "en", "s", None if t is None else len(t)) for i, t in enumerate(texts)]
    dice.shuffle(rows)
    rows += rows[:3]  # repeated rows
    path = tmp_path_factory.mktemp("corpus")
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(i + 1, int(clean <= i < clean + 60)) for i in range(clean + 60)], "doc_id long, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path), clean


def _cut(rows):
    """Later copies of windows go, rows in the order of doc_id."""
    first, out = {}, {}
    for k, text in rows:
        data = (text or "").encode()
        gone = [False] * len(data)
        for i in range(len(data) - WINDOW + 1):
            if first.setdefault(data[i : i + WINDOW], (k, i)) != (k, i):
                gone[i : i + WINDOW] = [True] * WINDOW
        out[k] = bytes(b for b, g in zip(data, gone, strict=True) if not g).decode("utf-8", "ignore")
    return out


def test_run_is_brute_force(spark, folder):
    import corpus_pipeline

    path, clean = folder
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "exact dedup", "near dedup", "suffix dedup", "packing"]
    docs = spark.read.parquet(f"{path}/documents.parquet")
    bad = {r.doc_id for r in toxicity.toxicity(docs, spark.read.parquet(f"{path}/labels.parquet")).where("predicted = 1").collect()}
    assert bad == set(range(clean + 1, clean + 64))
    left = {r.doc_id: r.text for r in docs.collect() if r.doc_id not in bad}
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    once: dict = {}
    for k in sorted(left):
        once.setdefault(norm(left[k]), k)
    rows = sorted((k, left[k]) for k in once.values())
    groups = _brute(rows)
    rows = [r for i, r in enumerate(rows) if groups.index(groups[i]) == i]
    assert len(left) > len(once) > len(rows)
    whole = sum(len((t or "").encode()) for _, t in rows)
    kept = _cut(rows)
    assert sum(len(t.encode()) for t in kept.values()) < whole - 1000
    tokens = packing.chunk_ids(packing.vocabulary())
    want = {k: len(tokens([packing.separated(t)])[0]) // 4 + 1 for k, t in kept.items()}
    done = corpus_pipeline.run(spark, path).collect()
    got: dict = {}
    for r in done:
        got[r.doc_id] = got.get(r.doc_id, 0) + r.length
    assert got == want
    ends: dict = {}
    for r in sorted(done, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == ends.get(r.sequence_id, 0)
        ends[r.sequence_id] = r.offset + r.length
    assert max(ends.values()) <= packing.SIZE and len(ends) == -(-sum(want.values()) // packing.SIZE)


def test_run_on_empty_tables(spark, folder, tmp_path):
    import corpus_pipeline

    for name in ("documents", "labels"):
        spark.read.parquet(f"{folder[0]}/{name}.parquet").limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
