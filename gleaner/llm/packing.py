"""Best-fit packing of token sequences by exact-complement hashing.

Tokens are counted in Arrow batches. The plan depends on the histogram of piece lengths alone (at most ``size``
numbers, however many documents there are): single, pair and triple sums that exactly fill the gap of the longest
open piece are consumed as often as the counts allow, then what is left goes by best fit. Runs of the plan are
joined to ranks within a length; of lengths with many pieces, each bucket has a window of its own.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gleaner.llm.merges import WordEnds
from gleaner.sources.shared import written

SIZE, END_ID = 4096, 1
#: Rows of one length that are always ranked in one window; chunks whose ids are kept.
LEAST_ROWS, CACHE = 1000, 1_000_000
#: The white space of Unicode, at which the tokenizer separates; marks that always end a piece.
SPACES = re.compile(r"[\t\n\x0b\x0c\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+")
CONTROLS = re.compile("[\x1c-\x1f]")
MARKS = ".,!?;:*#$%&"


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class ChunkIds:
    """Ids (little-endian uint32 bytes) of white-space separated chunks; unseen ones are made many at a time."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.encode, self.words = Tokenizer.from_file(path).encode_batch, WordEnds(path)
        self.known: dict[str, bytes] = {}

    def learn(self, new: set[str]) -> None:
        """Makes the ids of chunks that aren't known."""
        known = self.known
        cut = {c: core for c in new if c[-1] in MARKS and (core := c.rstrip(MARKS)) and core[-1].isalpha()}
        todo = {x for x in new if x not in cut} | {x for c, core in cut.items() for x in (core, c[len(core) :]) if x not in known}
        plain = list(filter(self.words.takes, todo))
        if plain:
            known.update(zip(plain, self.words.ids(plain), strict=True))
        other = list(todo.difference(plain))
        known.update((c, np.array(e.ids, dtype="<u4").tobytes()) for c, e in zip(other, self.encode(other, add_special_tokens=False), strict=True))
        known.update((c, known[core] + known[c[len(core) :]]) for c, core in cut.items())

    def __call__(self, split: list[list[str]]) -> list[bytes]:
        """The ids of each list of chunks."""
        if len(self.known) > CACHE:
            self.known.clear()
        found = [list(map(self.known.get, chunks)) for chunks in split]
        unseen = [i for i, got in enumerate(found) if None in got]
        if unseen:
            self.learn({c for i in unseen for c, x in zip(split[i], found[i], strict=True) if x is None})
            for i in unseen:
                found[i] = map(self.known.__getitem__, split[i])
        return [b"".join(got) for got in found]


@lru_cache(maxsize=1)
def chunk_ids(path: str) -> ChunkIds:
    """One for all tasks of a worker process."""
    return ChunkIds(path)


def separated(text: str | None) -> list[str]:
    """Chunks between white space. str.split also cuts at four control characters that are no white space."""
    if not text:
        return []
    return [c for c in SPACES.split(text) if c] if CONTROLS.search(text) else text.split()


def pieces(docs: DataFrame, tokenizer: str, size: int = SIZE, end_id: int = END_ID) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): each document's ids and ``end_id``, cut only if longer than ``size``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        known, last = chunk_ids(tokenizer), np.array([end_id], dtype="<u4").tobytes()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                rows: list[tuple] = []
                for doc_id, ids in zip(part.column("doc_id").to_pylist(), known([separated(t) for t in part.column("text").to_pylist()]), strict=True):
                    ids += last
                    rows += ((doc_id, k, s // 4, min(len(ids) - s, 4 * size) // 4, zlib.crc32(ids[s : s + 4 * size])) for k, s in enumerate(range(0, len(ids), 4 * size)))
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def complements(left: list[int], size: int) -> Iterator[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, times) that exactly fill a sequence: the longest piece, and one, two or three whose sum is its gap.

    ``left``, the number of pieces of each length, is counted down. The lengths there are stand as bits of a number, and
    once more in reverse, so that one shift and one conjunction finds every pair with a given sum.
    """
    there = sum(1 << x for x in range(1, size + 1) if left[x])
    back = sum(1 << (size - x) for x in range(1, size + 1) if left[x])

    def pair(total: int, there: int, back: int, without: int = 0) -> tuple[int, int] | None:
        """The pair with the largest first member that sums to ``total``; of length ``without`` one piece is taken already."""
        both = there & (back >> (size - total))
        half, odd = divmod(total, 2)
        if not odd and left[half] - (half == without) < 2:
            both &= ~(1 << half)
        first = both.bit_length() - 1
        return (first, total - first) if first > 0 else None

    def fill(gap: int) -> tuple[int, ...] | None:
        if left[gap]:
            return (gap,)
        if found := pair(gap, there, back):
            return found
        rest = there & ((1 << (gap - 1)) - 1)
        while (a := rest.bit_length() - 1) >= -(-gap // 3):  # the largest of three
            rest ^= 1 << a
            last = left[a] == 1
            if found := pair(gap - a, there ^ (last << a), back ^ (last << (size - a)), a):
                return (a, *found)
        return None

    for top in range(size, 0, -1):
        while left[top]:
            more: tuple[int, ...] | None = ()
            if top < size:
                left[top] -= 1
                if not left[top]:
                    there, back = there ^ (1 << top), back ^ (1 << (size - top))
                more = fill(size - top)
                left[top] += 1
                if left[top] == 1:
                    there, back = there | 1 << top, back | 1 << (size - top)
            if more is None:
                break
            need = Counter((top, *more))
            times = min(left[x] // n for x, n in need.items())
            for x, n in need.items():
                left[x] -= times * n
                if not left[x]:
                    there, back = there & ~(1 << x), back & ~(1 << (size - x))
            yield (top, *more), times


def best_fit(left: list[int], size: int) -> Iterator[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, times) for what is left: the longest piece first, each into the fullest sequence that still holds it.

    Sequences with the same gap and all pieces of a length are dealt with together.
    """
    held: dict[int, list[tuple[tuple[int, ...], int]]] = {}  # by gap
    gaps = 0

    def put(pattern: tuple[int, ...], times: int, gap: int) -> None:
        nonlocal gaps
        held.setdefault(gap, []).append((pattern, times))
        gaps |= 1 << gap

    for length in range(size, 0, -1):
        n = left[length]
        while n:
            fits = gaps >> length
            gap = length + (fits & -fits).bit_length() - 1 if fits else size
            pattern, times = held[gap].pop() if fits else ((), n)
            if fits and not held[gap]:
                gaps ^= 1 << gap
            each = gap // length
            whole = min(times, n // each)
            if whole:
                put((*pattern, *[length] * each), whole, gap - each * length)
                n -= whole * each
            if n and whole < times:  # the last sequence takes fewer
                put((*pattern, *[length] * n), 1, gap - n * length)
                whole, n = whole + 1, 0
            if fits and whole < times:
                put(pattern, times - whole, gap)
    for some in held.values():
        yield from some


def plan(counts: dict[int, int], size: int = SIZE) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, times) that use every piece once: exact complements while there are any, then best fit."""
    left = [0] * (size + 1)
    for length, n in counts.items():
        left[length] = n
    return [*complements(left, size), *best_fit(left, size)]


def buckets(n: int, least: int = LEAST_ROWS) -> int:
    """In how many windows n pieces of one length are ranked: windows and their number both grow as the square root."""
    return 1 if n <= least else -(-math.isqrt(n) // 8)


def pack(docs: DataFrame, tokenizer: str | None = None, size: int = SIZE, end_id: int = END_ID, least: int = LEAST_ROWS) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row per piece.

    Null text is empty: such a document is its end id alone. Repeated rows are packed each; a null doc_id stays null;
    other columns are not read; an empty table gives an empty one. More than ``least`` pieces of a length are ranked in
    buckets, each in a window of its own.
    """
    spark = docs.sparkSession
    cut = written(pieces(docs, tokenizer or vocabulary(), size, end_id), "pieces")
    counts = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `size` rows
    split = {length: b for length, n in counts.items() if (b := buckets(n, least)) > 1}
    bucket = F.lit(0)
    if split:
        wide = F.broadcast(spark.createDataFrame(list(split.items()), "length long, buckets int"))  # at most `size` rows
        cut, bucket = cut.join(wide, "length", "left"), F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.coalesce("buckets", F.lit(1))).cast("int")
    cut = cut.withColumn("bucket", bucket)
    # Rows before each bucket of a split length: at most sqrt(size * pieces) / 8 rows.
    tally = cut.where(F.col("buckets").isNotNull()).groupBy("length", "bucket").agg(F.count("*").alias("n")).collect() if split else []
    before, seen = [(length, 0, 0) for length in counts if length not in split], dict.fromkeys(split, 0)
    for r in sorted(tally, key=lambda r: (r.length, r.bucket)):
        before.append((r.length, r.bucket, seen[r.length]))
        seen[r.length] += r.n
    runs: dict[int, list[tuple[int, int, int]]] = {}
    used: dict[int, int] = dict.fromkeys(counts, 0)
    base = 0
    for lengths, times in plan(counts, size):
        offset = 0
        for length in lengths:
            runs.setdefault(length, []).append((used[length], base, offset))
            used[length] += times
            offset += length
        base += times
    first = spark.createDataFrame(before, "length long, bucket int, before long")
    slots = spark.createDataFrame([(k, *map(list, zip(*v, strict=True))) for k, v in runs.items()], "length long, froms array<long>, bases array<long>, offsets array<long>")
    rank = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")) - 1
    # Both tables are bounded by the sequence size and the number of windows.
    ranked = cut.withColumn("nth", rank).join(F.broadcast(first), ["length", "bucket"]).withColumn("nth", F.col("nth") + F.col("before"))
    placed = ranked.join(F.broadcast(slots), "length").withColumn("run", F.expr("size(filter(froms, f -> f <= nth)) - 1"))
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        F.expr("bases[run] + nth - froms[run]").alias("sequence_id"), F.expr("offsets[run]").alias("offset"),
    )
