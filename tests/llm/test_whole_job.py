"""Cases where the text operators once did less than the whole job."""

from __future__ import annotations

import random
from itertools import combinations

import numpy as np
import xxhash

from gleaner.llm import exact_dedup, html_text, langid, licenses, merge_dropout, near_dedup, packing, simhash, suffix_dedup, toxicity


def test_dropout_is_drawn_for_each_occurrence(spark):
    rows = [(i, " international internationally" * 10) for i in range(60)]
    got = {r.doc_id: list(r.varied) for r in merge_dropout.encode(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    encoder = merge_dropout.Encoder(merge_dropout.pieces(merge_dropout.model_path()), merge_dropout.SEED, merge_dropout.RATE)
    varied = lambda t, i: encoder([t], [i])[2].tolist()
    assert all(got[i] == varied(t, i) for i, t in rows)  # the same on its own as among others
    words = {tuple(varied(" international", i)) for i in range(300)}
    plain = tuple(encoder([" international"], [0])[0].tolist())
    assert len(words) > 6 and plain in words and len({tuple(x) for x in got.values()}) == 60


def test_dropout_is_the_agenda_of_each_chunk():
    """Against one heap-free agenda in plain Python: the best pair that is not skipped, again and again."""
    pieces, seed, rate = merge_dropout.pieces(merge_dropout.model_path()), 5, 0.3
    table = dict(zip(pieces.table.key[:-1].tolist(), zip(pieces.table.rank.tolist(), pieces.table.made.tolist(), strict=True), strict=False))
    wide = (1 << 64) - 1

    def mixed(x):
        for by in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F):
            x = ((x ^ (x >> 32)) * by) & wide
        return x

    def brute(text, doc):
        out = []
        for n, chunk in enumerate(merge_dropout.chunks(text)):
            key = mixed((xxhash.xxh64_intdigest(str(doc), seed) + n * int(merge_dropout.GOLDEN)) & wide)
            now = [(i, int(pieces.codes[ord(c)])) for i, c in enumerate(chunk)]
            while True:
                can = []
                for k, ((at, a), (_, b)) in enumerate(zip(now, now[1:], strict=False)):
                    pair = a << 32 | b
                    if pair in table and mixed(mixed((key + at * int(merge_dropout.GOLDEN)) & wide) ^ pair) >> 11 >= int(rate * 2**53):
                        can.append((table[pair][0], k, table[pair][1]))
                if not can:
                    break
                _, k, made = min(can)
                now[k : k + 2] = [(now[k][0], made)]
            out += [x for _, c in now for x in ([c] if c < pieces.n else [pieces.bytes[b] for b in chr(c - pieces.n).encode()])]
        return out

    texts = ["The internationalisation of unbelievable words, naïvely 漢字 😀 said.\n  Two  blanks", "x" * 200 + " " + "abcdefghij" * 12, "", " a", "été " * 30]
    encoder = merge_dropout.Encoder(pieces, seed, rate)
    ids, ends, varied, stops = encoder(texts, [11, 12, 13, 14, 15])
    for i, (text, a, b) in enumerate(zip(texts, [0, *stops.tolist()], stops.tolist(), strict=False)):
        assert varied[a:b].tolist() == brute(text, 11 + i), text
        assert pieces.decode(varied[a:b]) == text


def test_best_fit_is_that_of_pieces_one_by_one():
    """The residual phase, against the fullest sequence that still fits, piece by piece; and complements against all sums."""
    rng = np.random.default_rng(7)
    for _ in range(60):
        lengths = sorted(rng.integers(1, 41, rng.integers(1, 60)).tolist(), reverse=True)
        left = np.bincount(lengths, minlength=41).tolist()
        bins: list[list[int]] = []
        for x in lengths:
            fits = [b for b in bins if sum(b) + x <= 40]
            if fits:
                max(fits, key=sum).append(x)
            else:
                bins.append([x])
        done = list(packing.best_fit(left, 40))
        assert sum(n for _, n in done) == len(bins)
        assert sorted(sum(p) for p, n in done for _ in range(n)) == sorted(map(sum, bins))
        exact = list(packing.complements(left, 40))
        assert all(sum(p) == 40 and len(p) <= 4 for p, _ in exact)
        rest = [x for x in range(1, 41) for _ in range(left[x])]
        assert not any(sum(c) == 40 and max(c) == c[-1] for k in (1, 2, 3, 4) for c in combinations(rest, k) if len(rest) < 25)


def test_lengths_above_a_window_are_ranked_in_buckets(spark):
    docs = spark.createDataFrame([(i, "a b c" if i % 3 else "word " * 90) for i in range(600)], "doc_id long, text string")
    rows = packing.pack(docs, size=64, least=20).collect()
    assert len({(r.sequence_id, r.offset) for r in rows}) == len(rows) == 400 + 200 * len({r.piece for r in rows if r.doc_id == 0})
    assert packing.buckets(400, 20) == 3 and packing.buckets(20, 20) == 1 and packing.buckets(10**9) == 3953
    ends: dict = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == ends.get(r.sequence_id, 0)
        ends[r.sequence_id] = r.offset + r.length
    assert max(ends.values()) <= 64


def test_disguises_reach_the_lattice(spark):
    said = "you are an idiot and an ass and a bass player said what the duck did to the ducks in the lake today ; "
    lm = toxicity.language_model(spark.createDataFrame([(said * 50,)], "text string"))
    for token, word in {"duuck": "duck", "iddiioott": "idiot", "a$$": "ass", "b@$$": "bass", "@$$": "ass", "4$$": "ass", "idiot!": "idiot", "duck,": "duck", "...": ""}.items():
        assert toxicity.restored(token, lm) == word, token
    for text, words in {"a s s": {"ass"}, "i d i o t": {"idiot"}, "i d ! o t": {"idiot"}, "an i-d-i-o-t.": {"idiot"}, "y o u  a r e  i d i o t": {"you", "are", "idiot"}, "id i ot": {"idiot"}}.items():
        assert words <= toxicity.words_of(text, lm, {}), (text, toxicity.words_of(text, lm, {}))


def test_no_licence_of_an_expression_is_lost():
    tag = "SPDX-License-Identifier: "
    labels = lambda said: set(licenses.scan((tag + said).encode(), licenses.automaton())["labels"].split(","))
    assert labels(" OR ".join(f"l{i}" for i in range(200))) == {f"l{i}" for i in range(200)}
    assert labels(" AND ".join(f"(a{i} OR b{i})" for i in range(40))) == {f"{c}{i}" for i in range(40) for c in "ab"}
    for said in ("a or b and c with d", "(a or b) with c and d", "a and", "(a or (b and c)) or d"):
        assert labels(said) == {x for s in licenses.alternatives(said) for x in s}


def test_short_sections_of_a_page_stay():
    long, short = "long words of the first part " * 40, "A short part that closes the text, in a line of more than eighty characters all told."
    links = "<div><a href=x>Go there</a></div>" * 5
    one = html_text.main_text(f"<body><p>{long}</p>{links}<p>{short}</p>{links}</body>")
    two = html_text.main_text(f"<body><article><p>{long}</p><p>{long}</p></article>{links}<article><p>Brief.</p></article></body>")
    assert one == f"{long}{short}" and two == f"{long}{long}Brief."


def test_pages_of_known_parts(spark):
    """Pages put together of known parts, with an article element or without, against the parts that belong to the text."""
    dice = random.Random(8)
    said = lambda n: " ".join("".join(dice.choice("abcdefgh") for _ in range(dice.randrange(3, 9))) for _ in range(n))
    noise = [
        lambda: "<nav><ul>" + "".join(f"<li><a href=/{i}>{said(1)}</a></li>" for i in range(6)) + "</ul></nav>", lambda: f'<div class="ad">{said(30)}</div>', lambda: f"<script>var x = '<p>{said(20)}</p>';</script>",
        lambda: f'<div id="cookie-notice"><p>{said(25)}</p><button>ok</button></div>', lambda: f"<aside><p>{said(40)}</p></aside>", lambda: f"<form><label>{said(3)}</label><input name=q></form>", lambda: f"<!-- {said(30)} -->",
        lambda: "".join(f"<div><a href=/{i}>{said(3)}</a></div>" for i in range(5)), lambda: f'<ul class="related">{"".join(f"<li>{said(6)}</li>" for _ in range(4))}</ul>',
    ]
    after = [lambda: f'<section class="comments"><p>{said(40)}</p><p>{said(30)}</p></section>', lambda: f"<footer>&copy; {said(12)}</footer>"]
    rows, want = [], {}
    for page in range(200):
        article = page % 2 == 0
        body = []
        for _ in range(dice.randrange(2, 7)):
            text = said(dice.randrange(20, 60))
            tag = dice.choice(["p", "div", "blockquote", 'p class="related-work"', 'p id="notice"', 'div class="side"']) if article else dice.choice(["p", "div", "blockquote"])
            body.append((f"<{tag}>{text.replace(' ', dice.choice([' ', '  ', chr(10)]), 1)} &amp; <b>so</b></{tag.split()[0]}>", f"{text} & so"))
            if article and dice.random() < 0.3:
                body.append((f"<h2>{said(2)}</h2>", None))
                body[-1] = (body[-1][0], body[-1][0][4:-5])
            if article and dice.random() < 0.3:
                body.append((f'<div class="ad">{said(30)}</div>', None))
        inner = "".join(h for h, _ in body)
        before, behind = "".join(n() for n in dice.sample(noise, 4)), "".join(n() for n in dice.sample(noise, 2)) + "".join(n() for n in after)
        rows.append((page, f"http://x/{page}", f"<html><head><title>t</title></head><body>{before}{'<article>' if article else '<div>'}{inner}{'</article>' if article else '</div>'}{behind}</body></html>", "clash"))
        want[page] = " ".join(t for _, t in body if t)
    rows += [(1000, None, None, ""), (None, "u", "", ""), (1001, "u", "<p>One.</p><p>Two more.</p><p>Three.</p>", ""), (1001, "u", "<p>One.</p><p>Two more.</p><p>Three.</p>", ""), (1002, "u", "<div><a href=x>Home</div><p>" + "main text " * 20 + "</p>", "")]
    rows.append((1003, "u", "<p>" + "very long " * 200_000 + "</p>", ""))
    want |= {1000: "", None: "", 1001: "One. Two more. Three.", 1003: ("very long " * 200_000).strip()}
    got = html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string, text string")).collect()
    assert len(got) == len(rows) and all(r.n_chars == len(r.text) for r in got)
    for r in got:
        if r.page_id in want:
            assert r.text == want[r.page_id], r.page_id
    assert next(r.text for r in got if r.page_id == 1002).endswith(("main text " * 20).strip())
    assert html_text.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_words_are_letters_with_their_marks(spark):
    assert langid.words_in("Été ½ ² naïve x1y हिन्दी 42 A") == ["été", "naïve", "x", "y", "हिन्दी", "a"]
    docs = spark.createDataFrame([(i, "wim wam wom", "aa") for i in range(40)] + [(100, "½ ² 42", "aa"), (101, None, "aa"), (None, "wim", None), (100, "wim wam", "bb")], "doc_id long, text string, lang string")
    got = [(r.doc_id, r.lang_pred) for r in langid.identify(docs).collect()]
    assert (100, "und") in got and (101, "und") in got and (None, "aa") in got and len(got) == 44


def test_rows_with_any_columns(spark):
    """Maps, dotted names, shared and null ids: stages keep what they should."""
    long = lambda k: " ".join(f"w{k}x{i}" for i in range(60))
    rows = [(1, long(1), {"a": 1}, 5), (1, long(1), {"a": 1}, 5), (2, long(1), {"b": 2}, 6), (None, long(3), None, 7), (None, long(4), {}, 8), (2, long(5), {}, 9), (3, None, {}, 1), (4, "", {}, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, m map<string,int>, `a.b` int")
    want = sorted([(1, long(1)), (None, long(3)), (None, long(4)), (2, long(5)), (3, None)], key=str)
    for stage in (exact_dedup.drop_exact, near_dedup.drop_near):
        out = stage(docs)
        assert out.columns == docs.columns and sorted(((r.doc_id, r.text) for r in out.collect()), key=str) == want
        assert stage(docs.limit(0)).count() == 0
    cut = suffix_dedup.cut_repeats(docs)
    assert cut.columns == docs.columns and cut.count() == 8 and suffix_dedup.cut_repeats(docs.limit(0)).count() == 0
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.drop_toxic(docs, labels).count() == 8


def test_small_languages_keep_their_words(spark):
    big = [(f"big{chr(97 + i % 26)}{chr(97 + i // 26)} " * 5, "aa") for i in range(400)]
    small = [("wim wam wom", "bb"), ("kri kra", "cc")]
    counts = langid.word_counts(spark.createDataFrame(big + small, "text string, lang string"), most=100)
    assert len(counts) == 100 and {r.word for r in counts if r.lang != "aa"} == {"wim", "wam", "wom", "kri", "kra"}
    docs = spark.createDataFrame([(i, *(big * 10)[i]) for i in range(4000)] + [(4000 + i, *small[i % 2]) for i in range(40)], "doc_id long, text string, lang string")
    taken = {r["lang"]: r["count"] for r in langid.train_rows(docs, 200).groupBy("lang").count().collect()}
    may = docs.where(~langid.held_out(docs.doc_id)).groupBy("lang").count().collect()
    assert all(taken[r["lang"]] == r["count"] for r in may if r["lang"] != "aa") and 100 < taken["aa"] < 250
    assert langid.shares({"aa": 1000, "bb": 10}, 110) == {"bb": 1.0, "aa": 0.1}


def test_tiles_of_short_blocks():
    """Links within blocks of every size, and sides, as by brute force."""
    dice = np.random.default_rng(3)
    block = np.sort(dice.integers(-40, 40, 900))
    block[:70] = block[0]
    centre = dice.integers(0, 1 << 63, 6, dtype=np.uint64)
    flips = np.uint64(1) << dice.integers(0, 64, (900, 2), dtype=np.uint64)
    fp = centre[dice.integers(0, 6, 900)] ^ flips[:, 0] ^ np.where(dice.random(900) < 0.5, flips[:, 1], np.uint64(0))
    side = np.where(block % 3 == 0, dice.integers(0, 2, 900), 2)
    got = [tuple(sorted(p)) for x, y in simhash._short_links(block, fp, side, 2, at_once=7) for p in zip(x.tolist(), y.tolist(), strict=True)]
    brute = {
        (i, j) for i in range(900) for j in range(i + 1, 900)
        if block[i] == block[j] and int(fp[i] ^ fp[j]).bit_count() <= 2 and (side[i] != side[j] or side[i] == 2)
    }
    assert brute and len(got) == len(set(got)) and set(got) == brute
    assert list(simhash._short_links(block[:0], fp[:0], side[:0], 2)) == []
