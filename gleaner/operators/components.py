"""Connected components of an edge table, without collecting edges.

Rounds of two relational steps, each a map-side combined ``min`` and one join: every node hands the smallest
label that it knows to its larger neighbours, then to its smaller ones, so that each component shrinks to a star
around its smallest node. A round's edges are written to the shared folder, so lineage stays short.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gleaner.sources.shared import dropped, written

#: Edges below which hubs are not looked for.
SMALL = 20_000

#: Edges that one task makes a forest of.
FOREST = 500_000

#: A key is heavy if it has more than this share of all rows, so there are fewer heavy keys than its inverse.
HEAVY = 1 / 1000


def spread_join(rows: DataFrame, side: DataFrame, key: list[str], heavy: Column) -> DataFrame:
    """``rows`` joined to ``side`` (one row a key). Heavy keys of ``side``, at most 1 / HEAVY by the way they are chosen, are
    broadcast, so that no task gets all rows of such a key; the others are joined by shuffle. The rows are the same either way."""
    if side.where(heavy).isEmpty():
        return rows.join(side, key)
    hot = F.broadcast(side.where(heavy))
    rest = rows.join(F.broadcast(side.where(heavy).select(*key)), key, "left_anti")
    return rows.join(hot, key).unionByName(rest.join(side.where(~heavy), key))


def _hand_over(pairs: DataFrame, larger: bool, many: int) -> DataFrame:
    """Edges (u, v), u > v. Links each node's larger (or not larger) neighbours to the least of its neighbourhood."""
    both = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))) if larger else pairs
    least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("degree")).select("u", F.least("u", "m").alias("m"), "degree")
    moved = spread_join(both, least, ["u"], F.col("degree") > many) if many else both.join(least, "u")
    if larger:
        moved = moved.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        moved = moved.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return moved.where("u <> v").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """(node, component) for every node on an edge; ``component`` is the smallest node that it reaches.

    Nodes must be comparable and not null; loops and repeated edges are allowed; an empty table gives an empty one. Hubs,
    nodes with more than ``HEAVY`` of all edge ends, are spread over tasks. Edges of earlier rounds are deleted.
    """
    pairs = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    pairs = written(pairs, "edges")
    count, state = pairs.count(), None
    if not count:
        return pairs.select(F.col("u").alias("node"), F.col("v").alias("component"))
    for _ in range(rounds):
        # A small table has no task that is too large, and needs no second way.
        old, many = pairs, int(2 * count * HEAVY) if count > SMALL else 0
        pairs = written(_hand_over(_hand_over(pairs, True, many), False, many), "edges")
        seen = pairs.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        dropped(old)
        if tuple(seen) == state:
            break
        state, count = tuple(seen), seen[0]
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    stars = pairs.groupBy("u").agg(F.min("v").alias("component")).select(F.col("u").alias("node"), "component")
    return stars.unionByName(pairs.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, component) for every node of a task's edges (u, v) but the smallest of each component."""
    held = [[batch.column(c).to_numpy() for c in ("u", "v")] for batch in batches if batch.num_rows]
    if not held:
        return
    name, ends = np.unique(np.concatenate([np.concatenate(x) for x in zip(*held, strict=True)]), return_inverse=True)
    up, (a, b) = np.arange(len(name)), ends.reshape(2, -1)
    while len(a):
        np.minimum.at(up, np.maximum(a, b), np.minimum(a, b))
        while (up != up[up]).any():
            up = up[up]
        a, b = up[a], up[b]
        a, b = a[a != b], b[a != b]
    below = up != np.arange(len(up))
    yield pa.RecordBatch.from_arrays([pa.array(name[below]), pa.array(name[up[below]])], ["node", "component"])


def forest_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """As ``components``, over long nodes and without a row for the smallest node of each component. Tasks first make forests of
    ``FOREST`` edges each; rounds follow only if there was more than one task."""
    pairs = written(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct(), "edges")
    tasks = -(-pairs.count() // FOREST)
    trees = pairs.repartition(max(1, tasks)).mapInArrow(_forest, "node long, component long")
    return trees if tasks < 2 else components(trees, "node", "component").where("node <> component")
