"""Measures of cost and of accuracy."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gleaner.functions.chance import uniform
from gleaner.operators.lengths import MEAN, LengthUtility
from gleaner.operators.model import length_factor, pattern_utility, sizes


def timed(action: Callable[[], DataFrame], repeats: int = 10) -> tuple[float, float]:
    """Mean and standard deviation of seconds, writing to nothing."""
    took = []
    for _ in range(repeats):
        t = time.time()
        action().write.format("noop").mode("overwrite").save()
        took.append(time.time() - t)
    return statistics.mean(took), statistics.stdev(took) if repeats > 1 else 0.0


def qdb_stats(qdb: DataFrame) -> DataFrame:
    """(transactions, items, rows, n_min, n_max, n_avg)."""
    per = sizes(qdb).agg(F.count("*").alias("transactions"), F.sum("n").alias("rows"), F.min("n").cast("long").alias("n_min"), F.max("n").cast("long").alias("n_max"))
    return per.crossJoin(F.broadcast(qdb.agg(F.countDistinct("item").alias("items")))).withColumn("n_avg", F.round(F.col("rows") / F.col("transactions"), 6))  # one row each


def storage_model(qdb: DataFrame) -> DataFrame:
    """(weights, cells, factors, matrix): numbers kept beside the data by the samplers' forms, and by the matrix baseline."""
    n = F.col("n").cast("long")
    row = sizes(qdb).agg(F.count("*").alias("weights"), F.max(n).alias("top"), F.sum(n * (n + 1)).alias("matrix"))
    cells = F.when(F.col("top") % 2 == 0, (F.col("top") / 2 + 1) * (F.col("top") / 2 + 1)).otherwise((F.col("top") + 1) * (F.col("top") + 3) / 4)
    return row.select("weights", cells.cast("long").alias("cells"), (F.col("top") + 1).alias("factors"), "matrix")


def representativeness(qdb: DataFrame, samples: dict[str, DataFrame], f: LengthUtility = MEAN) -> DataFrame:
    """(method, pattern, times, value): distinct patterns of each sample, how often each came, its (mean) utility."""
    drawn = None
    for name, s in samples.items():
        one = s.groupBy("pattern").agg(F.count("*").alias("times")).withColumn("method", F.lit(name))
        drawn = one if drawn is None else drawn.unionByName(one)
    util = pattern_utility(qdb, drawn.select("pattern").distinct())
    return drawn.join(util, "pattern").select("method", "pattern", "times", (F.col("utility").cast("double") * length_factor(F.size("pattern"), f)).alias("value"))


def normalised(rep: DataFrame) -> DataFrame:
    """Adds ``share``: value over the sum of values of all different patterns of the samples together."""
    whole = rep.select("pattern", "value").distinct().agg(F.sum("value").alias("whole"))
    return rep.crossJoin(F.broadcast(whole)).withColumn("share", F.col("value") / F.col("whole"))  # one row


def spread(norm: DataFrame, rounds: int = 200, seed: int = 0) -> DataFrame:
    """(method, k, mean, median, variance, sd, lo, hi, boot_lo, boot_hi) over draws: the normal 95 % interval of the mean, and
    the bootstrap's, where each round counts each distinct pattern as often as a Poisson draw of its times says."""
    each = norm.select("method", F.explode(F.sequence(F.lit(1).cast("long"), F.col("times"))).alias("_"), "share")
    row = each.groupBy("method").agg(F.count("*").alias("k"), F.avg("share").alias("mean"), F.percentile("share", 0.5).alias("median"), F.var_samp("share").alias("variance"), F.stddev_samp("share").alias("sd"))
    half = 1.96 * F.col("sd") / F.sqrt("k")
    # A Poisson number with mean t is close to the normal with that mean and variance, cut off at zero.
    u, v = (uniform(seed, F.col("method"), F.array_join(F.col("pattern").cast("array<string>"), ","), F.col("round"), part) for part in ("u", "v"))
    normal = F.sqrt(-2 * F.ln(u)) * F.cos(2 * math.pi * v)
    rows = norm.select("method", "pattern", "times", "share", F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    again = rows.withColumn("c", F.greatest(F.lit(0.0), F.col("times") + F.sqrt("times") * normal))
    means = again.groupBy("method", "round").agg((F.sum(F.col("c") * F.col("share")) / F.sum("c")).alias("m"))
    boot = means.groupBy("method").agg(F.percentile("m", 0.025).alias("boot_lo"), F.percentile("m", 0.975).alias("boot_hi"))
    return row.withColumn("lo", F.col("mean") - half).withColumn("hi", F.col("mean") + half).join(F.broadcast(boot), "method")  # one row a method


def violin(norm: DataFrame, bins: int = 40) -> DataFrame:
    """(method, bin, lo, hi, density): a histogram of shares over draws, all methods on the same bins."""
    ends = norm.agg(F.min("share").alias("least"), ((F.max("share") - F.min("share")) / bins).alias("step"))
    row = norm.crossJoin(F.broadcast(ends))  # one row
    at = F.when(F.col("step") > 0, F.least(F.floor((F.col("share") - F.col("least")) / F.col("step")), F.lit(bins - 1))).otherwise(0)
    counted = row.groupBy("method", at.cast("int").alias("bin"), "least", "step").agg(F.sum("times").alias("times"))
    whole = norm.groupBy("method").agg(F.sum("times").alias("k"))
    out = counted.join(F.broadcast(whole), "method")  # one row a method
    lo = F.col("least") + F.col("bin") * F.col("step")
    return out.select("method", "bin", lo.alias("lo"), (lo + F.col("step")).alias("hi"), (F.col("times") / F.col("k") / F.nullif(F.col("step"), F.lit(0.0))).alias("density"))


def fit(drawn: DataFrame, law: DataFrame) -> DataFrame:
    """(k, patterns, tv, max_error, kl, chi2) of a sample against the law (pattern, p)."""
    count = drawn.groupBy("pattern").agg(F.count("*").alias("times"))
    both = law.join(count, "pattern", "full").select(F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("times", F.lit(0)).alias("times"))
    both = both.crossJoin(F.broadcast(drawn.agg(F.count("*").alias("k")))).withColumn("q", F.col("times") / F.col("k"))  # one row
    gap = F.abs(F.col("q") - F.col("p"))
    return both.groupBy("k").agg(
        F.count("*").alias("patterns"), (F.sum(gap) / 2).alias("tv"), F.max(gap).alias("max_error"),
        F.sum(F.when(F.col("q") > 0, F.col("q") * F.ln(F.col("q") / F.col("p")))).alias("kl"), (F.first("k") * F.sum(F.when(F.col("p") > 0, gap * gap / F.col("p")))).alias("chi2"),
    )


def marginals(drawn: DataFrame, expected: DataFrame) -> DataFrame:
    """(item, p, q, z): expected and met shares of each item, and the difference in standard deviations."""
    met = drawn.select(F.explode("pattern").alias("item")).groupBy("item").agg(F.count("*").alias("times"))
    row = expected.join(met, "item", "left").crossJoin(F.broadcast(drawn.agg(F.count("*").alias("k"))))  # one row
    q = F.coalesce(F.col("times"), F.lit(0)) / F.col("k")
    return row.select("item", "p", q.alias("q"), ((q - F.col("p")) / F.sqrt(F.col("p") * (1 - F.col("p")) / F.col("k"))).alias("z"))


def diversity(drawn: DataFrame) -> DataFrame:
    """(k, distinct, items, entropy) of a sample."""
    count = drawn.groupBy("pattern").agg(F.count("*").alias("times"))
    row = count.agg(F.sum("times").alias("k"), F.count("*").alias("distinct"), F.sum(F.col("times") * F.ln("times")).alias("t"))
    items = drawn.select(F.explode("pattern").alias("i")).agg(F.countDistinct("i").alias("items"))
    return row.crossJoin(F.broadcast(items)).select("k", "distinct", "items", (F.ln("k") - F.col("t") / F.col("k")).alias("entropy"))  # one row


def mean_jaccard(drawn: DataFrame) -> DataFrame:
    """(pairs, jaccard): likeness of consecutive draws, which are independent."""
    a = drawn.select("draw_id", "pattern")
    b = drawn.select((F.col("draw_id") - 1).alias("draw_id"), F.col("pattern").alias("other"))
    like = F.size(F.array_intersect("pattern", "other")) / F.size(F.array_union("pattern", "other"))
    return a.join(b, "draw_id").agg(F.count("*").alias("pairs"), F.avg(like).alias("jaccard"))
