"""Merge-type segmentation of many words at once, in numpy, and caches that stay bounded."""

from __future__ import annotations

import heapq
import json
import unicodedata
from collections.abc import Callable

import numpy as np

#: No merge (ranks are below 2**24); words up to the widest of these advance together, so many symbols at a time.
LATE = np.int32((1 << 31) - 1)
WIDTHS, TOGETHER = (1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 12, 16, 24, 40, 63), 300_000
#: Odd multipliers, one for each table of pairs.
_ODD = [np.uint64(0x9E3779B97F4A7C15 * (2 * i + 1) % (1 << 64)) for i in range(64)]


class MergeTable:
    """Which pairs of symbols merge, in what order (least rank first, leftmost of equals), and into what.

    Pairs are found by open hashing: one table for nearly all, and another for those whose place there was taken.
    """

    def __init__(self, left: np.ndarray, right: np.ndarray, rank: np.ndarray, made: np.ndarray) -> None:
        self.key = np.append((left.astype(np.uint64) << np.uint64(32)) | right.astype(np.uint64), ~np.uint64(0))  # the last stands for none
        self.rank, self.made = np.append(rank, 0).astype(np.int64), np.append(made, 0).astype(np.int64)
        none = len(self.key) - 1
        todo, self.tables = np.arange(none), []
        while len(todo):
            bits = max(8, len(todo).bit_length() + 3)
            table = np.full(1 << bits, none, dtype=np.int32)
            shift = np.uint64(64 - bits)
            slot = self._slot(todo, len(self.tables), shift)
            table[slot] = todo  # of several, one stays
            self.tables.append((table, shift))
            todo = todo[table[slot] != todo]

    def _slot(self, at: np.ndarray, level: int, shift: np.uint64) -> np.ndarray:
        return (self.key[at] * _ODD[level]) >> shift

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The place of each pair in the table, or the number of pairs if it never merges."""
        key = (left.astype(np.uint64) << np.uint64(32)) | right.astype(np.uint64)
        none = len(self.key) - 1
        table, shift = self.tables[0]
        out = table[(key * _ODD[0]) >> shift].astype(np.int64)
        for level in range(1, len(self.tables) + 1):
            other = np.flatnonzero((out != none) & (self.key[out] != key))
            if not len(other):
                break
            if level == len(self.tables):
                out[other] = none
                break
            table, shift = self.tables[level]
            out[other] = table[(key[other] * _ODD[level]) >> shift]
        return out

    def segment(self, symbols: np.ndarray, word: np.ndarray, skip: Callable | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(symbols, word) after all merges; ``word``: ascending word number of each symbol.

        ``skip(word, place, left, right)`` tells which candidate merges are left out; ``place`` is the left symbol's
        first character in its word. It must depend on nothing else, so a candidate is skipped for good.
        """
        first = np.flatnonzero(np.diff(word, prepend=word[:1] - 1))
        size, name = np.diff(np.append(first, len(word))), word[first]
        count = np.zeros(len(first), dtype=np.int64)
        group = np.searchsorted(WIDTHS, size)
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        for g, width in enumerate(WIDTHS):
            own = np.flatnonzero(group == g)
            step = TOGETHER // width
            for some in (own[i : i + step] for i in range(0, len(own), step)):
                got, count[some] = self._together(symbols, first[some], size[some], width, name[some], skip)
                parts.append((some, got))
        for i in np.flatnonzero(group == len(WIDTHS)).tolist():
            got = self._agenda(symbols[first[i] : first[i] + size[i]], int(name[i]), skip)
            count[i] = len(got)
            parts.append((np.array([i]), got))
        out, start = np.zeros(int(count.sum()), dtype=np.int64), np.cumsum(count) - count
        for some, got in parts:
            n = count[some]
            out[np.arange(len(got)) + np.repeat(start[some] - np.cumsum(n) + n, n)] = got
        return out, np.repeat(name, count)

    def _together(self, symbols: np.ndarray, first: np.ndarray, size: np.ndarray, width: int, name: np.ndarray, skip: Callable | None) -> tuple[np.ndarray, np.ndarray]:
        """(symbols left, how many of each word). Words are columns; in each round every word that can makes its best merge."""
        n, none = len(first), len(self.key) - 1
        at = np.arange(width)[:, None]
        alive = at < size
        cell = symbols[np.where(alive, first + at, 0)].astype(np.int64)
        order, pair = np.full((width, n), LATE, dtype=np.int32), np.zeros((width, n), dtype=np.int32)
        after, before = (np.repeat((at + k) * n, n, axis=1) for k in (1, -1))
        after[size - 1, np.arange(n)] = none_after = width * n
        # From here on a symbol is known by row * n + column.
        alive_, cell_, order_, pair_, after_, before_ = (x.reshape(-1) for x in (alive, cell, order, pair, after, before))
        row_of, column_of = np.repeat(np.arange(width, dtype=np.int32), n), np.tile(np.arange(n), width)

        def enter(i: np.ndarray, left: np.ndarray, right: np.ndarray) -> None:
            """What the pairs that begin at ``i`` merge into, and when."""
            found = self.find(left, right)
            hit = np.flatnonzero(found < none)
            order_[i] = LATE
            i, found = i[hit], found[hit]
            if skip is not None:
                stay = np.flatnonzero(~skip(name[column_of[i]], row_of[i], left[hit], right[hit]))
                i, found = i[stay], found[stay]
            order_[i] = self.rank[found] << 6 | row_of[i]
            pair_[i] = found

        i = np.flatnonzero(alive_[n:])
        enter(i, cell_[i], cell_[i + n])
        while True:
            best = order.min(axis=0)
            live = np.flatnonzero(best < LATE)
            if not len(live):
                return cell.T[alive.T], alive.sum(axis=0)
            p = (best[live] & 63) * n + live
            q = after_[p] + live
            r = after_[q]
            made = self.made[pair_[p]]
            cell_[p], alive_[q], order_[q], order_[p], after_[p] = made, False, LATE, LATE, r
            o = before_[p]
            right, left = np.flatnonzero(r < none_after), np.flatnonzero(o >= 0)
            next_, last = r[right] + live[right], o[left] + live[left]
            before_[next_] = p[right] - live[right]
            enter(np.concatenate([p[right], last]), np.concatenate([made[right], cell_[last]]), np.concatenate([cell_[next_], made[left]]))

    def _agenda(self, symbols: np.ndarray, name: int, skip: Callable | None) -> np.ndarray:
        """The same for one long word, with a heap."""
        ids, none = symbols.astype(np.int64).tolist(), len(self.key) - 1
        after, before = [*range(1, len(ids)), -1], list(range(-1, len(ids) - 1))
        agenda: list[tuple[int, int, int, int, int]] = []

        def enter(places: list[int]) -> None:
            left, right = np.array([ids[i] for i in places]), np.array([ids[after[i]] for i in places])
            found = self.find(left, right)
            good = found < none
            if skip is not None and good.any():
                hit = np.flatnonzero(good)
                good[hit] = ~skip(np.full(len(hit), name), np.array(places)[hit], left[hit], right[hit])
            for k in np.flatnonzero(good).tolist():
                heapq.heappush(agenda, (int(self.rank[found[k]]), places[k], int(left[k]), int(right[k]), int(self.made[found[k]])))

        enter(list(range(len(ids) - 1)))
        while agenda:
            _, p, left, right, made = heapq.heappop(agenda)
            if ids[p] != left or after[p] < 0 or ids[after[p]] != right:
                continue  # one of the two has merged meanwhile
            q = after[p]
            ids[p], ids[q], after[p] = made, -1, after[q]
            if after[p] >= 0:
                before[after[p]] = p
            near = [i for i in (before[p], p) if i >= 0 and after[i] >= 0]
            if near:
                enter(near)
        return np.array([x for x in ids if x >= 0], dtype=np.int64)


class TwoAges(dict):
    """A bounded cache: when the young half is full, it becomes the old half."""

    def __init__(self, bound: int) -> None:
        self.bound, self.old = bound // 2, {}

    def missing(self, keys: set) -> list:
        """Those of ``keys`` to be made; the others are in the young half after this."""
        if len(self) > self.bound:
            self.old = dict(self)
            self.clear()
        out = []
        for k in keys:  # a set less a dictionary's keys would walk the whole dictionary
            if k in self:
                continue
            known = self.old.get(k)
            if known is None:
                out.append(k)
            else:
                self[k] = known
        return out


def byte_characters() -> dict[int, str]:
    """The printable stand-ins of bytes in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class WordEnds:
    """Byte-level merges with word ends, for words of Latin letters; everything else is left to the tokenizer itself."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab = model["vocab"]
        end = model["end_of_word_suffix"]
        split = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.table = MergeTable(*(np.array(x) for x in ([vocab[a] for a, _ in split], [vocab[b] for _, b in split], range(len(split)), [vocab[a + b] for a, b in split])))
        looks = byte_characters()
        self.inner = np.array([vocab[looks[b]] for b in range(256)])
        self.last = np.array([vocab[looks[b] + end] for b in range(256)])

    @staticmethod
    def takes(word: str) -> bool:
        return word.isascii() and word.isalpha() or len(word) < 200 and word.isalpha() and max(word) < "ƀ" and "İ" not in word and "ŉ" not in word and unicodedata.is_normalized("NFC", word)

    def ids(self, words: list[str]) -> list[bytes]:
        """Little-endian uint32 ids of each word."""
        raw = [w.lower().encode() for w in words]
        size = np.array([len(r) for r in raw])
        data = np.frombuffer(b"".join(raw), dtype=np.uint8)
        symbols = self.inner[data]
        stop = np.cumsum(size)
        symbols[stop - 1] = self.last[data[stop - 1]]
        ids, word = self.table.segment(symbols, np.repeat(np.arange(len(raw)), size))
        flat = ids.astype("<u4").tobytes()
        cut = [0, *(4 * np.cumsum(np.bincount(word, minlength=len(raw)))).tolist()]
        return [flat[a:b] for a, b in zip(cut, cut[1:], strict=False)]
