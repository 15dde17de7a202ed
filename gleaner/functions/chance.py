"""Replayable uniforms, and functions for SQL."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def uniform(*parts: Column | str | int) -> Column:
    """A number in (0, 1) that depends on ``parts`` alone: a retried task draws the same, and other engines can too."""
    text = F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts))
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") + 0.5) / F.lit(2.0**52)


def uniform_value(*parts: object) -> float:
    """The same on the driver."""
    return (int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) + 0.5) / 2.0**52


def duck_uniform(*parts: str) -> str:
    """The same in DuckDB's SQL; ``parts`` are SQL expressions."""
    return f"((('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"


def register(spark: SparkSession) -> None:
    """SQL functions, inlined by the analyser, and table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION log_binom(n INT, k INT) RETURNS DOUBLE RETURN CASE WHEN k < 0 OR k > n THEN NULL ELSE aggregate(sequence(0, least(k, n - k)), cast(0 AS DOUBLE), (a, i) -> a + CASE WHEN i = 0 THEN 0D ELSE ln(n - i + 1) - ln(i) END) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION prefix_mass(l INT, i INT, s DOUBLE, u DOUBLE) RETURNS DOUBLE RETURN coalesce(exp(log_binom(i, l)) * (l * s / i + u), 0D)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tx_log_weight(n INT, s DOUBLE) RETURNS DOUBLE RETURN ln(s) + (n - 1) * ln(2)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pattern_key(p ARRAY<BIGINT>) RETURNS STRING RETURN array_join(array_sort(p), ',')")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash_uniform(t STRING) RETURNS DOUBLE RETURN (cast(conv(substr(md5(t), 1, 13), 16, 10) AS DOUBLE) + 0.5D) / 4503599627370496D")
    spark.udtf.register("subsets", subsets())
    spark.udtf.register("draws", draws())


def weighted_pick():
    """Two grouped aggregates: (key, log weight) -> one key in proportion to weight, the same for the same rows in any order;
    and log weight -> log of the total."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    def pick(key: pd.Series, logw: pd.Series) -> int:
        order = np.argsort(key.to_numpy(), kind="stable")
        run = np.cumsum(np.exp(logw.to_numpy()[order] - logw.max()))
        x = uniform_value("pick", key.iloc[order[0]], len(key)) * run[-1]
        return int(key.iloc[order[min(int(np.searchsorted(run, x)), len(run) - 1)]])

    pick.__annotations__ = {"key": pd.Series, "logw": pd.Series, "return": int}

    def total(logw: pd.Series) -> float:
        return float(np.logaddexp.reduce(np.sort(logw.to_numpy())))

    total.__annotations__ = {"logw": pd.Series, "return": float}
    return pandas_udf(pick, "long"), pandas_udf(total, "double")


def subsets():
    from itertools import combinations

    from pyspark.sql.functions import udtf

    @udtf(returnType="pattern array<bigint>, length int")
    class Subsets:
        """All sub-lists of ``items`` with m to M members."""

        def eval(self, items: list, m: int, M: int):  # noqa: N803
            for size in range(m, min(M, len(items)) + 1):
                for pick in combinations(sorted(items), size):
                    yield list(pick), size

    return Subsets


def draws():
    from pyspark.sql.functions import udtf

    from gleaner.operators.jump import draw_exact

    @udtf(returnType="draw int, pattern array<bigint>")
    class Draws:
        """``count`` patterns of one transaction, in proportion to their summed weight."""

        def eval(self, tid: int, items: list, w: list, count: int):
            for k in range(count):
                yield k, draw_exact(items, w, None, lambda step, k=k: uniform_value(tid, k, step))

    return Draws
