"""Enumeration, threshold and top-k mining, condensed output, mining on samples, and a Markov-chain sampler."""

from __future__ import annotations

import bisect
import random
from collections.abc import Callable, Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gleaner.functions.chance import uniform
from gleaner.operators.lengths import SUM, LengthUtility
from gleaner.operators.model import length_factor, sizes
from gleaner.sources.shared import written


def occurrences(qdb: DataFrame, m: int = 1, M: int = 3, deny: DataFrame | None = None) -> DataFrame:  # noqa: N803
    """(tid, pattern, u) of every sub-list with m to M items, grown level by level to the right of its last item."""
    level = qdb.select("tid", F.array("item").alias("pattern"), F.col("item").alias("last"), F.col("w").alias("u"))
    out = level if m <= 1 else None
    for size in range(2, M + 1):
        step = qdb.select("tid", F.col("item").alias("next"), F.col("w").alias("v"))
        level = level.join(step, "tid").where("next > last").select("tid", F.concat("pattern", F.array("next")).alias("pattern"), F.col("next").alias("last"), (F.col("u") + F.col("v")).alias("u"))
        if size >= m:
            out = level if out is None else out.unionByName(level)
    return out.select("tid", "pattern", "u")


def enumerate_patterns(qdb: DataFrame, m: int = 1, M: int = 3, max_n: int = 25) -> DataFrame:  # noqa: N803
    """(pattern, utility, support) of all patterns; refuses transactions longer than ``max_n`` if M is not small."""
    top = sizes(qdb).agg(F.max("n")).first()[0] or 0
    if top > max_n and M > 3:
        raise ValueError(f"{top} items in a transaction: enumeration to length {M} is refused")
    return occurrences(qdb, m, M).groupBy("pattern").agg(F.sum("u").alias("utility"), F.count("*").alias("support"))


def target(qdb: DataFrame, f: LengthUtility) -> DataFrame:
    """(pattern, p): the law that samplers must follow, by enumeration."""
    found = enumerate_patterns(qdb, f.m, f.M or 25)
    mass = found.select("pattern", (F.col("utility").cast("double") * length_factor(F.size("pattern"), f)).alias("mass"))
    return mass.crossJoin(F.broadcast(mass.agg(F.sum("mass").alias("z")))).select("pattern", (F.col("mass") / F.col("z")).alias("p"))  # z: one row


def _levels(qdb: DataFrame, M: int | None, least: Callable[[DataFrame], float], mean: bool = False) -> Iterator[DataFrame]:  # noqa: N803
    """(pattern, utility, support, value, bound) of each length in turn, of all patterns that can still matter.

    A pattern grows to the right of its last item. In a transaction it can gain no more than what stands to its right, so
    ``bound``, utility and rest together (for mean utility over one item more), is as much as any longer pattern that
    begins with it can have. ``least``, asked after each length, is the value below which none is wanted.
    """
    right = F.sum("w").over(Window.partitionBy("tid").orderBy(F.desc("item")).rowsBetween(Window.unboundedPreceding, -1))
    items = written(qdb.select("tid", "item", "w", F.coalesce(right, F.lit(0)).alias("rest")), "items")
    step = items.select("tid", F.col("item").alias("next"), F.col("w").alias("v"), F.col("rest").alias("next_rest"))
    level = items.select("tid", F.array("item").alias("pattern"), F.col("item").alias("last"), F.col("w").alias("u"), "rest")
    size = 1
    while True:
        level = written(level, "level")
        divisor, more = (size, size + 1) if mean else (1, 1)
        found = level.groupBy("pattern").agg(F.sum("u").alias("utility"), F.count("*").alias("support"), F.sum(F.when(F.col("rest") > 0, F.col("u") + F.col("rest"))).alias("reach"))
        found = written(found.select("pattern", "utility", "support", (F.col("utility") / divisor if mean else F.col("utility")).alias("value"), (F.col("reach") / more if mean else F.col("reach")).alias("bound")), "patterns")
        yield found
        grow = found.where(F.col("bound") >= F.lit(least(found))).select("pattern")
        if size == M or grow.isEmpty():
            return
        kept = level.where("rest > 0").join(grow, "pattern", "left_semi").join(step, "tid").where("next > last")
        level = kept.select("tid", F.concat("pattern", F.array("next")).alias("pattern"), F.col("next").alias("last"), (F.col("u") + F.col("v")).alias("u"), F.col("next_rest").alias("rest"))
        size += 1


def mine_threshold(qdb: DataFrame, least: float, M: int | None = None) -> DataFrame:  # noqa: N803
    """(pattern, utility, support) of all patterns, of any length up to M, with utility of ``least`` or more."""
    return reduce(DataFrame.unionByName, [found.where(F.col("utility") >= least) for found in _levels(qdb, M, lambda _: least)]).select("pattern", "utility", "support")


def mine_topk(qdb: DataFrame, k: int, f: LengthUtility = SUM, M: int | None = None) -> DataFrame:  # noqa: N803
    """The k patterns, of any length up to M, of most (mean) utility; ties in pattern order. What can't reach the k-th best so far isn't grown."""
    best: list = []

    def least(found: DataFrame) -> float:
        best.extend(r.value for r in found.orderBy(F.desc("value")).limit(k).select("value").collect())  # k numbers
        best.sort(reverse=True)
        del best[k:]
        return best[-1] if len(best) == k else 0

    tops = [found.orderBy(F.desc("value"), "pattern").limit(k) for found in _levels(qdb, M, least, f.kind == "mean")]
    return reduce(DataFrame.unionByName, tops).orderBy(F.desc("value"), "pattern").limit(k).select("pattern", "utility", "support", "value")


def condense(patterns: DataFrame, how: str = "maximal") -> DataFrame:
    """Patterns without a superset among them (``maximal``), or without one of equal support (``closed``)."""
    big = patterns.select(F.col("pattern").alias("q"), F.col("support").alias("qs"), F.explode("pattern").alias("item"))
    small = patterns.select("pattern", "support", F.element_at("pattern", 1).alias("item"))
    over = (F.size("q") > F.size("pattern")) & (F.size(F.array_except("pattern", "q")) == 0)
    met = small.join(big, "item").where(over if how == "maximal" else over & (F.col("qs") == F.col("support"))).select("pattern").distinct()
    return patterns.join(met, "pattern", "left_anti")


def mine_on_sample(qdb: DataFrame, share: float, least: float, M: int | None = None, seed: int = 0) -> DataFrame:  # noqa: N803
    """Threshold mining on a hash sample of transactions; the threshold shrinks with the share."""
    kept = qdb.where(uniform(seed, F.col("tid"), "sample") < share)
    return mine_threshold(kept, least * share, M).withColumn("utility", F.col("utility") / share)


#: Rows of item sets that a walk keeps in memory; beyond, each step is a query over them.
WALK_ROWS = 200_000


def _item_sets(qdb: DataFrame) -> DataFrame:
    """(items, item, w): weights summed over transactions of the same items, which give each pattern the same utility."""
    packed = qdb.groupBy("tid").agg(F.array_sort(F.collect_list(F.struct("item", F.col("w").cast("double").alias("w")))).alias("r"))
    rows = packed.select(F.expr("transform(r, x -> x.item)").alias("items"), F.explode("r").alias("x"))
    return rows.groupBy("items", F.col("x.item").alias("item")).agg(F.sum("x.w").alias("w"))


class _Walk:
    """One chain: ``propose`` gives the next pattern to be weighed, ``settle`` takes it or not."""

    def __init__(self, chain: int, items: list, seed: int) -> None:
        self.dice, self.items, self.now, self.u = random.Random(seed * 1_000_003 + chain), items, frozenset(), 0.0

    def start(self) -> frozenset:
        self.new = frozenset([self.dice.choice(self.items)])
        return self.new

    def propose(self) -> frozenset:
        dice, items, now = self.dice, self.items, self.now
        if dice.random() < 0.3 and len(now) < len(items):
            gone = dice.choice(sorted(now))
            at = dice.randrange(len(items) - len(now))
            for i in sorted(bisect.bisect_left(items, x) for x in now):  # the place among items that are not in the pattern
                at += i <= at
            self.new = now - {gone} | {items[at]}
        else:
            self.new = now ^ {dice.choice(items)}
        return self.new

    def settle(self, v: float) -> None:
        if not self.now or v and self.dice.random() * self.u < v:
            self.now, self.u = self.new, v


def _utilities(sets: DataFrame, patterns: list[frozenset]) -> dict[frozenset, float]:
    """The utility of each pattern over item sets, by one query."""
    spark, kind = sets.sparkSession, dict(sets.dtypes)["item"]
    asked = spark.createDataFrame([(k, sorted(p), x) for k, p in enumerate(patterns) for x in p], f"k int, p array<{kind}>, item {kind}")
    met = sets.join(F.broadcast(asked), "item").where("forall(p, x -> array_contains(items, x))")  # asked: the patterns' items
    got = {r.k: r.u for r in met.groupBy("k").agg(F.sum("w").alias("u")).collect()}
    return {p: got.get(k, 0.0) for k, p in enumerate(patterns)}


def _walk_in_steps(sets: DataFrame, items: list, chains: int, steps: int, f: LengthUtility, seed: int) -> list[tuple]:
    """(chain, pattern) of all chains side by side: the patterns they propose in a step are weighed together, and those met are remembered."""
    walks, known = [_Walk(c, items, seed) for c in range(chains)], {frozenset(): 0.0}
    for step in range(steps + 1):
        asked = [w.propose() if step else w.start() for w in walks]
        if fresh := [p for p in dict.fromkeys(asked) if p not in known]:
            known |= _utilities(sets, fresh)
        for w, p in zip(walks, asked, strict=True):
            w.settle(float(f(len(p))) * known[p])
    return [(c, sorted(w.now)) for c, w in enumerate(walks)]


def mcmc(qdb: DataFrame, chains: int, steps: int, f: LengthUtility = SUM, seed: int = 0) -> DataFrame:
    """(chain, pattern): Metropolis walks over patterns, by toggling an item or by swapping a member for another one.

    Both proposals are symmetric, so the walk's law is in proportion to utility. Transactions of the same items count as one;
    up to ``WALK_ROWS`` rows of such sets each task walks in memory, beyond that all chains walk side by side, each step being a query.
    """
    sets = written(_item_sets(qdb), "sets")
    items = sorted(r.item for r in sets.select("item").distinct().collect())  # one value an item
    spark, kind = qdb.sparkSession, dict(qdb.dtypes)["item"]
    if not items:
        return spark.createDataFrame([], f"chain long, pattern array<{kind}>")
    if sets.count() > WALK_ROWS:
        return spark.createDataFrame(_walk_in_steps(sets, items, chains, steps, f, seed), f"chain long, pattern array<{kind}>")
    tx: dict = {}
    for r in sets.orderBy("items", "item").collect():  # bounded above
        tx.setdefault(tuple(r["items"]), {})[r["item"]] = r["w"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[frozenset, float] = {}

        def utility(p: frozenset) -> float:
            if p not in held:
                held[p] = float(f(len(p))) * sum(sum(t[i] for i in p) for t in tx.values() if p <= t.keys()) if p else 0.0
            return held[p]

        for batch in batches:
            ids, pats = batch.column("chain").to_pylist(), []
            for c in ids:
                walk = _Walk(c, items, seed)
                walk.start()
                walk.settle(utility(walk.new))
                for _ in range(steps):
                    walk.settle(utility(walk.propose()))
                pats.append(sorted(walk.now))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(pats, pa.list_(pa.from_numpy_dtype("int64") if isinstance(items[0], int) else pa.string()))], ["chain", "pattern"])

    return spark.range(chains).withColumnRenamed("id", "chain").mapInArrow(run, f"chain long, pattern array<{kind}>")
