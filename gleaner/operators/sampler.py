"""Samples of patterns, end to end."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gleaner.functions.chance import uniform
from gleaner.operators import jump
from gleaner.operators.lengths import SUM, LengthUtility
from gleaner.operators.model import known_sizes, pack, sizes, weights
from gleaner.plans.choose import Choice, choose
from gleaner.sources.shared import written
from gleaner.sources.tables import bucket_of, buckets_in


def _packed(picks: DataFrame, qdb: DataFrame) -> DataFrame:
    """The transactions that were picked, each packed once however often it was drawn."""
    return pack(qdb.join(picks.select("tid").distinct(), "tid", "left_semi"))


def draw(picks: DataFrame, qdb: DataFrame, method: str, engine: str, seed: int) -> DataFrame:
    """(draw_id, tid, pattern, length) for picks that have their lengths. ``engine``: sql up to ``SQL_MOST`` items, arrow, or long for
    transactions that no array holds."""
    if method == "seed" or engine == "long":
        return jump.seed_split(picks, qdb, seed)
    packed = _packed(picks, qdb)
    if engine == "sql" and method != "matrix":
        rows = picks.drop("n").join(packed, "tid")
        return jump.jump_in_sql(rows, seed) if method == "jump" else jump.sequential_in_sql(rows, seed).drop("visited")
    if method == "matrix":
        from gleaner.operators.matrix import matrix_draw, stored

        return matrix_draw(picks, stored(packed), seed).drop("visited")
    rows = jump.grouped(picks, packed, "items", "w", "s")
    return (jump.jump_in_arrow if method == "jump" else jump.sequential_in_arrow)(rows, seed).drop("visited")


@dataclass
class Sampler:
    """Draws from one database, with its sizes and weights made once. ``reweight`` changes prices or lengths and draws again.

    ``qdb``: (tid, item, w), and the quantity ``qty`` (and any key of prices, such as a predicate) where prices may change.
    """

    qdb: DataFrame
    f: LengthUtility = SUM
    seed: int = 0
    storage: str = "memory"
    _sizes: DataFrame | None = field(default=None, repr=False)
    _weights: DataFrame | None = field(default=None, repr=False)

    def _kept(self, df: DataFrame, tag: str) -> DataFrame:
        return df.persist() if self.storage == "memory" else written(df, tag)

    @property
    def sizes(self) -> DataFrame:
        """(tid, n, s): the only scan of the whole database."""
        if self._sizes is None:
            self._sizes = self._kept(sizes(self.qdb), "sizes")
        return self._sizes

    @property
    def weights(self) -> DataFrame:
        if self._weights is None:
            self._weights = self._kept(weights(self.qdb, self.f, self.sizes), "weights")
        return self._weights

    @property
    def normaliser(self) -> float:
        return self.weights.agg(F.sum("w")).first()[0] or 0.0

    def choice(self, k: int) -> Choice:
        row = self.weights.agg(F.max("n"), F.count("*")).first()
        return choose(k, row[0] or 0, row[1], self.f)

    def explain(self, k: int = 1000) -> str:
        return self.choice(k).text()

    def picks(self, k: int, pick: str = "auto") -> DataFrame:
        """(draw_id, tid, n, l): k transactions and the lengths of their patterns."""
        ways = {"prefix": jump.pick_by_prefix, "race": jump.pick_by_race, "reservoir": jump.pick_by_reservoir}
        way = ways[self.choice(k).pick if pick == "auto" else pick]
        return written(jump.draw_length(way(self.weights, k, self.seed), self.f, self.seed), "picks")

    def sample(self, k: int, method: str = "jump", pick: str = "auto", engine: str = "auto") -> DataFrame:
        """(draw_id, tid, pattern, length): k independent patterns, P in proportion to utility times f(length)."""
        plan = self.choice(k)
        return draw(self.picks(k, plan.pick if pick == "auto" else pick), self.qdb, method, plan.engine if engine == "auto" else engine, self.seed)

    def reweight(self, prices: DataFrame | None = None, f: LengthUtility | None = None, seed: int | None = None, key: str = "item") -> Sampler:
        """Another law on the same quantities. ``prices``: (key, price) replace all prices, 1 where there is none.

        Another length function leaves sizes and sums as they are, so nothing is scanned again; so does another seed alone.
        """
        seed = self.seed if seed is None else seed
        if prices is None:
            return Sampler(self.qdb, f or self.f, seed, self.storage, self._sizes, self._weights if f in (None, self.f) else None)
        if "qty" not in self.qdb.columns:
            raise ValueError("new prices need the quantities: a column qty beside w")
        named = prices.select(F.col(prices.columns[0]).alias(key), F.col(prices.columns[1]).alias("_price"))
        qdb = self.qdb.join(named, key, "left").withColumn("w", F.col("qty") * F.coalesce("_price", F.lit(1))).drop("_price")
        return Sampler(qdb, f or self.f, seed, self.storage)


def sample(qdb: DataFrame, k: int, f: LengthUtility = SUM, seed: int = 0, method: str = "jump", storage: str = "memory", pick: str = "auto", engine: str = "auto") -> DataFrame:
    return Sampler(qdb, f, seed, storage).sample(k, method, pick, engine)


def two_pass(source: DataFrame, k: int, f: LengthUtility = SUM, seed: int = 0) -> DataFrame:
    """For data larger than memory: one scan keeps weights alone, a second one draws for the ids that were chosen.

    An id chosen c times yields c independent patterns. Draws equal those of the in-memory sampler for the same seed.
    """
    return Sampler(source, f, seed, "disk").sample(k, pick="prefix")


def two_pass_stored(store: str, spark: SparkSession, k: int, f: LengthUtility = SUM, seed: int = 0) -> DataFrame:
    """The same over ``tables.write_qdb``: the second pass reads only the buckets that hold a chosen id."""
    qdb = spark.read.parquet(store)
    sampler = Sampler(qdb.select("tid", "item", "w"), f, seed, "disk")
    picks = sampler.picks(k, "prefix")
    hit = [r[0] for r in picks.select(bucket_of("tid", buckets_in(store, spark))).distinct().collect()]  # at most one number a bucket
    near = qdb.where(F.col("bucket").isin(hit)).select("tid", "item", "w")  # a filter on partitions
    return draw(picks, near, "jump", sampler.choice(k).engine, seed)


def uniform_patterns(qdb: DataFrame, k: int, m: int = 1, M: int = 5, mode: str = "length_first", seed: int = 0) -> DataFrame:  # noqa: N803
    """The bootstrap baseline: a uniform transaction, then a legal length (uniform, or by its number of subsets), then a uniform subset."""
    per = sizes(qdb).where(F.col("n") >= m)
    even = per.withColumn("w", F.lit(1.0)).withColumn("logw", F.lit(0.0))
    return _even_subsets(qdb, jump.pick_by_prefix(even, k, seed), lambda n, x: 1 if mode == "length_first" else math.comb(n, x), m, M, seed)


def _even_subsets(qdb: DataFrame, picks: DataFrame, share: Callable[[int, int], int], m: int, M: int | None, seed: int) -> DataFrame:  # noqa: N803
    """Of each pick a length with the given share, then as many of its items, all alike."""
    picks, rows = written(picks, "picks"), []
    for n in known_sizes(picks):
        shares = [(x, share(n, x)) for x in range(max(m, 1), min(M or n, n) + 1)]
        total, run = sum(v for _, v in shares), 0
        for x, v in shares:
            rows.append((n, x, float(Fraction(run, total)), float(Fraction(run + v, total))))
            run += v
    law = qdb.sparkSession.createDataFrame(rows, "n int, l int, lo double, hi double")
    picks = picks.withColumn("x", uniform(seed, F.col("draw_id"), "length")).join(F.broadcast(law), "n").where("x > lo and x <= hi").drop("x", "lo", "hi")
    rank = F.row_number().over(Window.partitionBy("draw_id").orderBy(uniform(seed, F.col("draw_id"), F.col("item"), "subset"), "item"))
    kept = picks.join(qdb, "tid").withColumn("rank", rank).where("rank <= l")
    return kept.groupBy("draw_id", "tid").agg(F.array_sort(F.collect_list("item")).alias("pattern")).withColumn("length", F.size("pattern"))


def support_weights(qdb: DataFrame, m: int = 1, M: int | None = None) -> DataFrame:  # noqa: N803
    """(tid, n, w, logw): frequency-only sampling; every legal subset of a transaction counts one. ``w`` is null where a double can't hold it."""
    per = written(sizes(qdb), "sizes")
    counts = [(n, c) for n in known_sizes(per) if (c := sum(math.comb(n, x) for x in range(max(m, 1), min(M or n, n) + 1)))]
    rows = [(n, float(c) if math.log(c) < 700 else None, math.log(c)) for n, c in counts]
    return per.join(F.broadcast(qdb.sparkSession.createDataFrame(rows, "n int, w double, logw double")), "n").select("tid", "n", "w", "logw")


def support_sample(qdb: DataFrame, k: int, m: int = 1, M: int | None = None, seed: int = 0) -> DataFrame:  # noqa: N803
    """(draw_id, tid, pattern, length): patterns in proportion to their support, which the utility has no part in."""
    return _even_subsets(qdb, jump.pick_by_prefix(support_weights(qdb, m, M), k, seed), lambda n, x: math.comb(n, x), m, M, seed)


def distinct_patterns(drawn: DataFrame) -> DataFrame:
    """(pattern, times)."""
    return drawn.groupBy("pattern").agg(F.count("*").alias("times"))
