"""Worked examples, exact laws and agreement of methods."""

from __future__ import annotations

import math
import random
from collections import Counter
from fractions import Fraction
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from gleaner.functions.chance import uniform, uniform_value
from gleaner.operators import components, encode, jump, kg, matrix, mining, model, sampler
from gleaner.operators.lengths import MEAN, SUM, LengthUtility, PascalCache, coefficient, log_factorials, pascal_cells

W = [44, 12, 75, 34]


@pytest.mark.parametrize(
    ("price", "f", "expected"),
    [
        (1, SUM, [1320, 44, 12, 218]), (3, SUM, [1864, 44, 12, 354]), (1, LengthUtility("const", 1, 2), [660, 44, 12, 218]),
        (1, MEAN, [Fraction(2475, 4), 44, 12, Fraction(327, 2)]), (3, LengthUtility("mean", 1, 2), [Fraction(1165, 2), 44, 12, Fraction(531, 2)]),
    ],
)
def test_toy_weights(spark, price, f, expected):
    got = {r.tid: r.w for r in model.weights(encode.toy(spark, price), f).collect()}
    assert [got[t] for t in (1, 2, 3, 4)] == pytest.approx([float(x) for x in expected])


def test_toy_utilities_and_triangle(spark):
    found = {tuple(r.pattern): r.utility for r in mining.enumerate_patterns(encode.toy(spark), 1, 4).collect()}
    assert found[(2, 4)] == 46 and found[(3, 4)] == 218 and sum(found.values()) == 1594
    assert {tuple(r.pattern): r.utility for r in mining.enumerate_patterns(encode.toy(spark, 3), 1, 4).collect()}[(2, 4)] == 114
    packed = model.pack(encode.toy(spark).where("tid = 1"))
    table = {(r.l, r.i): r.t for r in model.triangle(packed).collect()}
    assert [table[1, i] for i in (1, 2, 3, 4)] == [44, 56, 131, 165] and table[2, 3] == 262 and table[3, 4] == 495 and table[4, 4] == 165
    assert {(r.l, r.i): r.t for r in model.triangle_by_recursion(packed).collect()} == table


def test_matrix_columns_and_path():
    assert matrix.columns(W, 4) == [([44], [0]), ([12, 56], [44, 0]), ([75, 206, 131], [56, 56, 0]), ([34, 233, 364, 165], [131, 262, 131, 0])]
    assert jump.path_probability([1, 2, 3, 4], W, [1, 3], 495 / 1320) == pytest.approx(119 / 1320)


def _law(step, length, n=4):
    """Expands every draw of ``length`` items: chances of patterns, where ``step(left, j, u)`` lists (place, chance, next j)."""
    law: Counter = Counter()

    def grow(left, j, u, p, pick):
        if not left:
            law[tuple(sorted(pick))] += p
            return
        for i, q, after in step(left, j, u):
            grow(left - 1, after, u + W[i - 1], p * q, [*pick, i])

    grow(length, n, 0, Fraction(1), [])
    return law


def test_jump_law_is_exact():
    mass = jump.whole_mass([0, 44, 56, 131, 165])
    for length in (1, 2, 3, 4):
        law = _law(lambda left, j, u: [(i, Fraction(mass(left, i, u) - mass(left, i - 1, u), mass(left, j, u)), i - 1) for i in range(left, j + 1)], length)
        total = math.comb(3, length - 1) * 165
        assert law == {c: Fraction(sum(W[i - 1] for i in c), total) for c in combinations(range(1, 5), length)}
    # The exact draw follows it: over evenly spaced uniforms of the first pick, each place comes as often as it should.
    n = 1320
    first = Counter(jump.draw_exact([1, 2, 3, 4], W, 2, lambda step, k=k: (k + 0.5) / n if step == 1 else 0.5)[-1] for k in range(n))
    assert all(abs(first[i] - n * (mass(2, i, 0) - mass(2, i - 1, 0)) / 495) < 1 for i in (2, 3, 4))


@pytest.mark.parametrize("wrong", ["range end", "upper bounds", "next place"])
def test_misprints_are_not_followed(wrong):
    """A range that ends too early, intervals that leave gaps, or a next pick that may repeat the last: none gives the law."""
    s = [0, 44, 56, 131, 165]
    mass = jump.whole_mass(s)
    gap = 0.0
    for length in (2, 3):

        def step(left, j, u):
            end = mass(left, j, u)
            if wrong == "range end":
                end = math.comb(j - 1, left - 1) * (s[j] + u)
            out, low = [], 0
            for i in range(left, j + 1):
                high = math.comb(i - 1, left - 1) * (s[i] + u) if wrong == "upper bounds" else mass(left, i, u)
                low = mass(left, i - 1, u)
                take = max(0, min(high, end) - min(low, end))
                out.append((i, Fraction(take, end), i if wrong == "next place" else i - 1))
            return out

        law, total = _law(step, length), math.comb(3, length - 1) * 165
        want = {c: Fraction(sum(W[i - 1] for i in c), total) for c in combinations(range(1, 5), length)}
        gap += sum(abs(law.get(c, 0) - want.get(c, 0)) for c in {*law, *want})
    assert gap > 0.1


@pytest.mark.parametrize("n", [100, 2500])
def test_long_transactions(spark, n):
    """The same uniforms give the exact draw's patterns; items beyond the 63rd are drawn; nested expressions refuse such rows."""
    dice = random.Random(n)
    w = [dice.randrange(10, 1001) for _ in range(n)]
    qdb = spark.createDataFrame([(7, i, w[i]) for i in range(n)], "tid long, item long, w long").persist()
    f = LengthUtility("mean", 1, 6)
    drawn = sampler.sample(qdb, 400, f, 3, pick="prefix")
    for r in drawn.collect():
        assert r.pattern == jump.draw_exact(list(range(n)), w, r.length, lambda step, k=r.draw_id: uniform_value(3, k, step))
    other = sampler.sample(qdb, 400, f, 3, "sequential", pick="prefix").collect()
    for rows in (drawn.collect(), other):
        low = sum(x < n // 2 for r in rows for x in r.pattern) / sum(r.length for r in rows)
        assert len(rows) == 400 and 0.4 < low < 0.6
    with pytest.raises(Exception, match="more than 60 items"):
        sampler.sample(qdb, 3, f, 3, pick="prefix", engine="sql").collect()


@pytest.mark.parametrize("method", ["jump", "sequential"])
def test_singles_and_pairs_of_a_hundred_items(spark, method):
    w = [1 + (7 * i) % 13 for i in range(100)]
    qdb = spark.createDataFrame([(1, i, w[i]) for i in range(100)], "tid long, item long, w long")
    drawn = sampler.sample(qdb, 6000, LengthUtility("const", 2, 2), 11, method, pick="prefix").collect()
    times = Counter(x for r in drawn for x in r.pattern)
    total = 99 * sum(w)
    expected = [6000 * (98 * x + sum(w)) / total for x in w]  # pairs that hold an item: its own weight 99 times, each other once
    assert sum(expected) == pytest.approx(12000)
    assert sum((times[i] - e) ** 2 / e for i, e in enumerate(expected)) < 160  # 99 degrees of freedom, p about 0.0001


def test_large_transactions_do_not_overflow(spark):
    qdb = spark.createDataFrame([(1, i, 2) for i in range(1500)] + [(2, 1, 5)], "tid long, item long, w long")
    p = {r.item: r.p for r in model.item_marginals(qdb).collect()}
    assert len(p) == 1500 and p[7] == pytest.approx(0.5, abs=1e-3)
    logs = {r.tid: (r.w, r.logw) for r in sampler.support_weights(qdb).collect()}
    assert logs[1][0] is None and logs[1][1] == pytest.approx(1500 * math.log(2)) and logs[2][0] == 1.0


def test_new_prices_replace_the_old_ones(spark):
    qdb = spark.createDataFrame([(1, 1, 3, 30.0, "a"), (1, 2, 2, 20.0, "b")], "tid long, item long, qty long, w double, pred string")
    one = sampler.Sampler(qdb)
    again = one.reweight(spark.createDataFrame([(1, 5)], "item long, price long"))
    assert {r.item: r.w for r in again.qdb.collect()} == {1: 15, 2: 2}
    by_pred = again.reweight(spark.createDataFrame([("b", 4)], "pred string, price long"), key="pred")
    assert {r.item: r.w for r in by_pred.qdb.collect()} == {1: 3, 2: 8}
    assert one.reweight(f=MEAN)._sizes is one._sizes
    with pytest.raises(ValueError, match="quantities"):
        sampler.Sampler(encode.toy(spark)).reweight(spark.createDataFrame([(1, 5)], "item long, price long"))


def test_text_ids_and_many_buckets(spark):
    qdb = spark.createDataFrame([(f"t{t}", i, t + i) for t in range(1, 40) for i in range(1, 4)], "tid string, item long, w long")
    w = model.weights(qdb)
    for buckets in (1, 7, 500):
        times = Counter(r.tid for r in jump.pick_by_prefix(w, 4000, 5, buckets).collect())
        z = {r.tid: r.w for r in w.collect()}
        assert sum((times[t] - 4000 * x / sum(z.values())) ** 2 / (4000 * x / sum(z.values())) for t, x in z.items()) < 80  # 38 degrees of freedom
    a = sorted(r.tid for r in jump.pick_by_reservoir(w, 50, 3).collect())
    assert a == sorted(r.tid for r in jump.pick_by_reservoir(w.repartition(3), 50, 3).collect()) and len(a) == 50


def test_length_factor_has_no_longest_length(spark):
    for f in (LengthUtility("power", 1, None, 0.5), LengthUtility("decay", 2, None, 0.01), MEAN, LengthUtility("mean", 1, 90)):
        got = spark.range(1, 200).select("id", model.length_factor(F.col("id"), f).alias("v")).collect()
        assert all(r.v == pytest.approx(float(f(r.id))) for r in got)


def test_matrix_is_refused_and_stored_once(spark):
    long = model.pack(spark.createDataFrame([(1, i, 1) for i in range(8000)], "tid long, item long, w long"))
    with pytest.raises(MemoryError):
        matrix.stored(long)
    with pytest.raises(MemoryError):
        matrix.matrix_weights(long, 1, 8000)
    packed = model.pack(encode.toy(spark))
    row = matrix.stored(packed).where("tid = 1").first()
    assert row.own == [44, 12, 56, 75, 206, 131, 34, 233, 364, 165] and len(row.rest) == 10


def test_walk_follows_the_law(spark):
    toy = encode.toy(spark).withColumn("w", F.col("w").cast("double"))
    times = Counter(tuple(r.pattern) for r in mining.mcmc(toy, 1500, 60).collect())
    law = {tuple(r.pattern): r.p for r in mining.target(toy, LengthUtility("const", 1, 4)).collect()}
    assert sum((times[p] - 1500 * q) ** 2 / (1500 * q) for p, q in law.items()) < 40


def test_mining_of_every_length(spark):
    dice = random.Random(4)
    rows = [(t, i, dice.randrange(1, 30)) for t in range(40) for i in dice.sample(range(12), dice.randrange(1, 8))]
    qdb = spark.createDataFrame(rows, "tid long, item long, w long")
    all_ = {tuple(r.pattern): (r.utility, r.support) for r in mining.enumerate_patterns(qdb, 1, 8).collect()}
    got = {tuple(r.pattern): (r.utility, r.support) for r in mining.mine_threshold(qdb, 150).collect()}
    assert got == {p: v for p, v in all_.items() if v[0] >= 150} and max(map(len, got)) > 2
    for f in (SUM, MEAN):
        value = (lambda p, v: v / len(p)) if f.kind == "mean" else (lambda p, v: v)
        top = [(tuple(r.pattern), r.value) for r in mining.mine_topk(qdb, 15, f).collect()]
        assert top == sorted(((p, value(p, v[0])) for p, v in all_.items()), key=lambda x: (-x[1], x[0]))[:15]


def test_hubs_are_spread(spark, monkeypatch):
    monkeypatch.setattr(components, "SMALL", 10)
    edges = [(0, i) for i in range(1, 400)] + [(1000 + i, 1001 + i) for i in range(20)] + [(2000, 399)]
    got = {r.node: r.component for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(400)}, 2000: 0, **{1000 + i: 1000 for i in range(21)}}


def test_path_probability_of_long_patterns():
    w = [1.0 + i % 5 for i in range(300)]
    pattern = list(range(0, 300, 30))
    share = 1.0  # given the length
    law = sum(w[i] for i in pattern) / (math.comb(299, len(pattern) - 1) * sum(w))
    assert jump.path_probability(list(range(300)), w, pattern, share) == pytest.approx(law)


def test_lengths():
    for n in range(40):
        assert PascalCache(n).cells() == pascal_cells(n)
    assert PascalCache(12)(12, 5) == math.comb(12, 5) and log_factorials(5)[5] == pytest.approx(math.log(120))
    for n in range(1, 20):
        for m, top in ((1, None), (1, 3), (2, n), (3, None)):
            for kind in ("const", "mean"):
                f = LengthUtility(kind, m, top)
                assert coefficient(n, f) == sum(math.comb(n - 1, x - 1) * f(x) for x in range(1, n + 1))


def test_uniforms_agree(spark):
    got = [r.u for r in spark.range(5).select(uniform(3, F.col("id"), "a").alias("u")).collect()]
    assert got == [uniform_value(3, i, "a") for i in range(5)]


@pytest.mark.parametrize("method", ["jump", "sequential", "seed", "matrix"])
def test_draws_follow_the_law(spark, method):
    toy = encode.toy(spark).persist()
    drawn = sampler.sample(toy, 4000, seed=5, method=method, pick="prefix")
    times = Counter(tuple(r.pattern) for r in drawn.collect())
    law = {tuple(r.pattern): r.p for r in mining.target(toy, LengthUtility("const", 1, 4)).collect()}
    assert sum(times.values()) == 4000 and set(times) <= set(law)
    assert sum((times[p] - 4000 * q) ** 2 / (4000 * q) for p, q in law.items()) < 36  # 14 degrees of freedom, p about 0.001


def test_storage_and_engine_do_not_matter(spark):
    toy = encode.toy(spark)
    a = sorted(map(tuple, sampler.sample(toy, 50, seed=2, pick="prefix", engine="sql").collect()))
    assert a == sorted(map(tuple, sampler.sample(toy, 50, seed=2, pick="prefix", engine="arrow").collect())) == sorted(map(tuple, sampler.two_pass(toy.repartition(3), 50, seed=2).collect()))


def test_edges(spark):
    empty = spark.createDataFrame([], "tid long, item long, w long")
    assert sampler.sample(empty, 5, pick="prefix").count() == 0
    assert model.weights(encode.toy(spark), LengthUtility("const", 5)).count() == 0
    rows = spark.createDataFrame([(1, 1, 2), (1, 1, 3), (1, 2, 0), (None, 1, 4)], "tid long, item long, w long")
    assert [tuple(r) for r in model.validate(rows).collect()] == [(1, 1, 5)]


def test_toy_graph(spark):
    got = {}
    for r in kg.to_qdb(kg.toy_profile(spark)).collect():
        got.setdefault(r.tid.split("|")[0], Counter())[(r.item, r.qty)] += 1
    assert sum(got["out"].values()) == 4 and sum(got["in"].values()) == 4
    sizes = Counter(r.tid for r in kg.to_qdb(kg.toy_profile(spark)).collect())
    assert sorted(sizes.values()) == [1, 1, 2, 4]
    drawn = spark.createDataFrame([(0, [2, 4])], "draw_id long, pattern array<long>")
    nodes, edges = kg.sub_profile(drawn, kg.toy_profile(spark))
    assert sorted(tuple(r.labels) for r in nodes.collect()) == [("C1", "C3"), ("C4",), ("e1", "e2")]
    assert sorted((r.pred, r.weight) for r in edges.collect()) == [("P2", 12), ("P3", 34)] and kg.isolated(nodes, edges).count() == 0


def test_walks_side_by_side_are_those_in_memory(spark, monkeypatch):
    dice = random.Random(8)
    rows = [(t, i, dice.randrange(1, 30)) for t in range(60) for i in dice.sample("abcdef", dice.randrange(1, 5))]
    qdb = spark.createDataFrame(rows, "tid long, item string, w long")
    f = LengthUtility("const", 1, 3)
    memory = sorted(map(tuple, mining.mcmc(qdb, 5, 8, f, 2).collect()))
    monkeypatch.setattr(mining, "WALK_ROWS", 10)  # a database that was refused before
    assert sorted(map(tuple, mining.mcmc(qdb, 5, 8, f, 2).collect())) == memory and len(memory) == 5
    assert mining.mcmc(qdb.limit(0), 5, 8).count() == 0


def test_many_small_matrices_are_not_refused(spark, monkeypatch):
    monkeypatch.setattr(matrix, "CELL_BUDGET", 40)
    qdb = spark.createDataFrame([(t, i, t + i) for t in range(30) for i in range(5)], "tid long, item long, w long")
    got = {r.tid: (r.w, r.cells) for r in matrix.matrix_weights(model.pack(qdb), 1, 5).collect()}
    assert got == {t: (16.0 * sum(t + i for i in range(5)), 30) for t in range(30)}
    assert matrix.stored(model.pack(qdb)).count() == 30
    assert tuple(matrix.cells(model.sizes(qdb), 5).first()) == (900, True)
    assert tuple(matrix.cells(model.sizes(qdb), 5, whole=False).first()) == (900, False)


def test_picks_do_not_depend_on_the_number_of_rows_a_stretch_has(spark, monkeypatch):
    w = model.weights(spark.createDataFrame([(t * t, i, 1 + t * i % 7) for t in range(1, 900) for i in range(1, 4)], "tid long, item long, w long")).persist()
    want = sorted(map(tuple, jump.pick_by_prefix(w, 500, 3).collect()))
    z = {r.tid: r.w for r in w.collect()}
    by_bucket = {b: [t for t in sorted(z) if t % 256 == b] for b in range(256)}
    ends, run = [], 0.0
    for b in range(256):
        run += sum(z[t] for t in by_bucket[b])
        ends.append(run)
    for k, tid, _ in want:  # the 256 buckets of the SQL, whatever the number of rows
        b = next(i for i, e in enumerate(ends) if e >= uniform_value(3, k, "bucket") * run)
        y, at = uniform_value(3, k, "tx") * sum(z[t] for t in by_bucket[b]), 0.0
        for t in by_bucket[b]:
            at += z[t]
            if y <= at:
                break
        assert t == tid
    monkeypatch.setattr(jump, "PER_BUCKET", 1)
    assert sorted(map(tuple, jump.pick_by_prefix(w, 500, 3).collect())) == want


NO_TABLE = ("binom_table", "coefficients", "math_log_binom", "math_prefix_mass", "pascal_cells", "scan_triples_text", "synthetic_stats", "toy_graph", "toy_patterns", "toy_weights")


@pytest.mark.parametrize("name", NO_TABLE)
def test_query_reads_a_given_table(spark, name, tmp_path):
    """Without the given tables the query has nothing to answer from."""
    from gleaner import catalogue

    assert catalogue.queries()[name](spark, "/root/testdata/sf0.001").count() > 0
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        catalogue.queries()[name](spark, str(tmp_path)).collect()
