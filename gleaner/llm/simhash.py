"""SimHash fingerprints and their near-duplicate components, by tiled exact comparison.

Fingerprints are made in Arrow batches. Distinct ones meet in blocks that any two within the radius must share
(pigeonhole on bit bands); inside a block numpy compares tiles by exclusive-or and bit counts, skipping tile pairs
whose population counts differ by more than the radius. A block above ``TILE`` members is dealt out to many tasks
as tile pairs. Each task returns a spanning forest of its links, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gleaner.llm.common import binary_column
from gleaner.operators.components import components, spread_join
from gleaner.sources.shared import written

#: Fixed values of the contract.
SEED, WIDTH, RADIUS = 42, 3, 2
BANDS = 4
TILE = 8192
#: Blocks of at most so many rows are compared together, in small tiles.
SHORT = 64


def fingerprint(text: bytes) -> int:
    """Majority bits of the XXH64 of each 3-word shingle; words are cut at ASCII white space, A-Z lowered. 0: no word."""
    words = text.lower().split()
    if not words:
        return 0
    line, ends = b" ".join(words), list(accumulate(len(w) + 1 for w in words))
    starts = [0, *ends]
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(line[s : e - 1], SEED) for s, e in zip(starts, ends[WIDTH - 1 :], strict=False)] or [digest(line, SEED)], dtype="<u8")
    set_bits = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 16):
        set_bits += np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * set_bits > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp): fp is the 64 bits as a signed BIGINT."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t) for t in binary_column(batch, "text")], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fps)], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, fp long")


def masks(bands: int = BANDS, radius: int = RADIUS) -> list[int]:
    """Signed 64-bit masks of every choice of bands - radius bands: two fingerprints within the radius agree under one."""
    edges = [round(64 * i / bands) for i in range(bands + 1)]
    band = [((1 << hi) - 1) ^ ((1 << lo) - 1) for lo, hi in zip(edges, edges[1:], strict=False)]
    return [m - (1 << 64) if (m := sum(pick)) >= 1 << 63 else m for pick in combinations(band, bands - radius)]


def _links(fp: np.ndarray, side: np.ndarray, radius: int, tile: int = 2048) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within the radius. Members of side 1 are compared with side 0 alone; side 2 with everything."""
    ones = np.bitwise_count(fp)
    order = np.argsort(ones, kind="stable")
    fp, ones, side = fp[order], ones[order].astype(np.int64), side[order]
    for i in range(0, len(fp), tile):
        a, top = fp[i : i + tile], ones[min(i + tile, len(fp)) - 1]
        for j in range(i, len(fp), tile):
            if ones[j] > top + radius:  # sorted by population count: no later tile can be near
                break
            near = np.bitwise_count(a[:, None] ^ fp[None, j : j + tile]) <= radius
            near &= (side[i : i + tile, None] != side[None, j : j + tile]) | (side[i : i + tile, None] == 2)
            x, y = np.nonzero(near)
            x, y = x + i, y + j
            keep = x < y
            yield order[x[keep]], order[y[keep]]


def _short_links(block: np.ndarray, fp: np.ndarray, side: np.ndarray, radius: int, tile: int = 8, at_once: int = 1 << 14) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """As ``_links`` within each of many short blocks, whose tiles are small; tile pairs of all blocks are compared together."""
    ones = np.bitwise_count(fp).astype(np.int64)
    order = np.lexsort((ones, block))
    block, fp, side, ones = block[order], fp[order], side[order], ones[order]
    cut = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
    size = np.diff(np.r_[cut, len(block)])
    count = -(-size // tile)  # tiles a block
    owner = np.repeat(np.arange(len(cut)), count)
    first = np.cumsum(count) - count
    start = cut[owner] + (np.arange(len(owner)) - first[owner]) * tile
    end = np.minimum(start + tile, (cut + size)[owner])
    low, high, lane = ones[start], ones[end - 1], np.arange(tile)
    for step in range(int(count.max(initial=0))):
        i = np.arange(len(owner) - step)
        j = i + step
        # Tiles of a block stand in order of population count: those too far apart are not compared.
        live = np.flatnonzero((owner[i] == owner[j]) & (low[j] <= high[i] + radius))
        for k in range(0, len(live), at_once):
            p, q = i[live[k : k + at_once]], j[live[k : k + at_once]]
            x, y = start[p][:, None] + lane, start[q][:, None] + lane
            full_x, full_y = x < end[p][:, None], y < end[q][:, None]
            x, y = np.minimum(x, len(fp) - 1), np.minimum(y, len(fp) - 1)
            near = np.bitwise_count(fp[x][:, :, None] ^ fp[y][:, None, :]) <= radius
            near &= full_x[:, :, None] & full_y[:, None, :] & (x[:, :, None] < y[:, None, :])
            near &= (side[x][:, :, None] != side[y][:, None, :]) | (side[x][:, :, None] == 2)
            pair, u, v = np.nonzero(near)
            yield order[x[pair, u]], order[y[pair, v]]


def forest(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> list[tuple[int, int]]:
    """Spanning forest of the pairs on 0..n-1 (union by halving paths)."""
    up, out = list(range(n)), []

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for xs, ys in pairs:
        for x, y in zip(xs.tolist(), ys.tolist(), strict=True):
            if up[x] == up[y]:
                continue
            a, b = root(x), root(y)
            if a != b:
                up[max(a, b)] = min(a, b)
                out.append((x, y))
    return out


def _compare(radius: int):
    """Rows sorted by (block, fp) come in; blocks may span batches. Links (a, b) go out."""

    def solve(block: np.ndarray, fp: np.ndarray, side: np.ndarray) -> tuple[list[int], list[int]]:
        cut = np.flatnonzero(np.diff(block, prepend=block[:1] - 1))
        size = np.diff(np.append(cut, len(block)))
        signed = fp.view(np.int64)
        long = size > SHORT
        at = np.flatnonzero(np.repeat(~long, size))
        found = [at[list(x)] for x in forest(len(at), _short_links(block[at], fp[at], side[at], radius))]
        for s, n in zip(cut[long].tolist(), size[long].tolist(), strict=True):
            own = slice(s, s + n)
            found += [np.array(x) + s for x in forest(n, _links(fp[own], side[own], radius))]
        pairs = np.array(found, dtype=np.int64).reshape(-1, 2)
        a, b = signed[pairs[:, 0]].tolist(), signed[pairs[:, 1]].tolist()
        return a, b

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        out = lambda a, b: pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(np.vstack([batch.column(c).to_numpy(zero_copy_only=False) for c in ("block", "fp", "side")]))
            if sum(x.shape[1] for x in held) < 200_000:
                continue
            rows = np.hstack(held)
            last = int(np.searchsorted(-(rows[0] != rows[0, -1]).astype(np.int8), 0))
            if last:
                yield out(*solve(rows[0, :last], rows[1, :last].view(np.uint64), rows[2, :last]))
            held = [rows[:, last:]]
        if held:
            rows = np.ascontiguousarray(np.hstack(held))
            yield out(*solve(rows[0], rows[1].view(np.uint64), rows[2]))

    return run


def near_links(fps: DataFrame, radius: int = RADIUS, bands: int = BANDS, tile: int = TILE) -> DataFrame:
    """Links (a, b) whose components are those of all pairs of the distinct values ``fp`` within ``radius`` bits."""
    picked = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(m).alias("m")) for i, m in enumerate(masks(bands, radius))])).alias("p")
    keyed = fps.select("fp", picked).select("fp", F.xxhash64("p.i", F.col("fp").bitwiseAND(F.col("p.m"))).alias("block"), F.bit_count("fp").alias("ones"))
    crowd = keyed.groupBy("block").agg(F.count("*").alias("n")).where("n > 1")
    keyed = spread_join(keyed, crowd, ["block"], F.col("n") > tile)  # at most rows / tile blocks, of a few numbers each
    plain = keyed.where(F.col("n") <= tile).select("block", "fp", F.lit(2).alias("side"))
    # A crowded block: tiles are (population count, part); each pair of tiles within the radius is a block of its own.
    parts = F.ceil(F.col("n") / tile / 4)
    own = keyed.where(F.col("n") > tile).select("block", "fp", F.col("ones").cast("long"), parts.alias("parts"), F.pmod(F.xxhash64("fp"), parts).alias("part"))
    others = own.select("*", F.explode(F.sequence(F.col("ones") - radius, F.col("ones") + radius)).alias("ones2"))
    others = others.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part2"))
    me, you = F.struct("ones", "part"), F.struct(F.col("ones2").alias("ones"), F.col("part2").alias("part"))
    dealt = others.select(F.xxhash64("block", F.least(me, you), F.greatest(me, you)).alias("block"), "fp", F.when(me == you, 2).when(me < you, 0).otherwise(1).alias("side"))
    rows = plain.unionByName(dealt).select("block", "fp", F.col("side").cast("long").alias("side"))
    return rows.repartition("block").sortWithinPartitions("block", "fp").mapInArrow(_compare(radius), "a long, b long")


def simhash_components(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of ``docs`` (doc_id, text).

    component_id: the smallest doc_id reachable over links of ``radius`` or fewer differing bits, itself included; rows
    with equal fingerprints are linked. Null or blank text has fingerprint zero and links like any other. A null
    doc_id is larger than any other; repeated rows each get their row; other columns are not read; empty stays empty.
    """
    fps = written(fingerprints(docs), "fingerprints")
    nodes = fps.groupBy("fp").agg(F.min("doc_id").alias("least"))
    member = components(near_links(nodes.select("fp"), radius))
    placed = nodes.join(member, nodes.fp == member.node, "left").select("fp", "least", F.coalesce("component", "fp").alias("component"))
    label = placed.groupBy("component").agg(F.min("least").alias("component_id"))
    named = placed.join(label, "component").select("fp", "component_id")
    return fps.join(named, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
