"""Inversion of a transform that a task holds packed: 2 bits a symbol, a bit for each string's begin, and counts each 64 places.

Each task reads all pieces of the transform and walks back from the ends of its
own strings together, a symbol a step. So the walk writes and shuffles nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .packedkmers import each_range

#: Places of a transform that a task holds, half a byte each; a larger one is for joins.
PLACES = 1_500_000_000
#: Strings that a task walks together, and those that its steps take at once.
STRINGS, STEP = 1_000_000, 1 << 16
_GROUP = 1024
_ODD = np.uint64(0x5555555555555555)


class Transform:
    """Symbols and counts of a transform of `total` places, put together of pieces in any order."""

    def __init__(self, alphabet: tuple[str, ...], total: int):
        self.alphabet, self.total = alphabet, total
        groups = total // 64 + 2
        self.words, self.begins = np.zeros(2 * groups, np.uint64), np.zeros(groups, np.uint64)
        self.codes = np.zeros(256, np.uint8)
        for i, c in enumerate(alphabet):
            self.codes[ord(c)] = i

    def put(self, first: int, text: bytes) -> None:
        group, before = first // 64, first % 64
        size = -(-(before + len(text)) // 64)
        own = np.frombuffer(text, np.uint8)
        codes, begin = np.zeros(64 * size, np.uint8), np.zeros(64 * size, bool)
        codes[before : before + len(own)] = self.codes[own]
        begin[before : before + len(own)] = own == ord("$")
        packed = codes[0::4] | codes[1::4] << 2 | codes[2::4] << 4 | codes[3::4] << 6
        self.words[2 * group : 2 * (group + size)] |= packed.view(np.uint64)
        self.begins[group : group + size] |= np.packbits(begin, bitorder="little").view(np.uint64)

    @staticmethod
    def _same(words: np.ndarray, code) -> np.ndarray:
        """A bit at each symbol that is `code`."""
        x = ~(words ^ _ODD * code)
        return x & x >> np.uint64(1) & _ODD

    def settle(self) -> None:
        """Counts of each symbol before each 64 places: of groups of them, and within a group."""
        n, k = len(self.begins), len(self.alphabet)
        self.before, self.inside, totals = np.zeros((-(-n // _GROUP), k), np.int64), np.zeros((n, k), np.uint16), []
        for c in range(k):
            own = np.zeros(n, np.int64)
            for i in range(0, n, 1 << 20):
                words = self.words[2 * i : 2 * (i + (1 << 20))]
                own[i : i + (1 << 20)] = np.bitwise_count(self._same(words, np.uint64(c))).reshape(-1, 2).sum(axis=1)
            if c == 0:  # begins of strings and places past the end look like the first symbol
                own -= np.bitwise_count(self.begins)
                g = self.total // 64
                own[g:] = 0
                own[g] = self._first_of(g, self.total - 64 * g)
            totals.append(int(own.sum()))
            up = np.cumsum(own) - own
            self.before[:, c] = up[::_GROUP]
            self.inside[:, c] = (up - np.repeat(up[::_GROUP], _GROUP)[:n]).astype(np.uint16)
        n_strings = int(np.bitwise_count(self.begins).sum())
        self.starts = n_strings + np.cumsum([0, *totals])[:-1]

    def _first_of(self, g: int, places: int) -> int:
        bits = int(self._same(self.words[2 * g : 2 * g + 1], np.uint64(0))[0]) | int(self._same(self.words[2 * g + 1 : 2 * g + 2], np.uint64(0))[0]) << 64
        begins = int(self.begins[g])
        return sum(bits >> 2 * i & 1 and not begins >> i & 1 for i in range(places))

    def back(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(symbols, places of the suffixes that are one longer) of places p; the symbol is 4 where a string begins."""
        group, within = p >> 6, (p & 63).astype(np.uint64)
        a, b, begins = self.words[2 * group], self.words[2 * group + 1], self.begins[group]
        code = np.where(within < 32, a, b) >> ((within & np.uint64(31)) << np.uint64(1)) & np.uint64(3)
        one = np.uint64(1)
        # bits of the places before: up to 32 in the first word, the rest in the second
        low = np.where(within >= 32, ~np.uint64(0), (one << (np.minimum(within, np.uint64(31)) << one)) - one)
        high = np.where(within > 32, (one << ((np.maximum(within, np.uint64(32)) - np.uint64(32)) << one)) - one, np.uint64(0))
        count = np.bitwise_count(self._same(a, code) & low).astype(np.int64) + np.bitwise_count(self._same(b, code) & high)
        count -= np.where(code == 0, np.bitwise_count(begins & ((one << within) - one)), 0)
        at = code.astype(np.int64)
        there = self.starts[np.minimum(at, len(self.starts) - 1)] + self.before[group // _GROUP, at] + self.inside[group, at] + count
        return np.where(begins >> within & one, 4, at).astype(np.uint8), there


def _walker(alphabet: tuple[str, ...], total: int, longest: int, low: int, high: int):
    """The strings whose ends are the places from low on and below high."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, ids = Transform(alphabet, total), np.zeros(high - low, np.int64)
        for batch in batches:
            for i in range(batch.num_rows):
                first, text, own = (batch.column(c)[i].as_py() for c in ("first", "text", "ids"))
                held.put(first, text)
                own = np.frombuffer(own, np.int64)
                a, b = max(low, first), min(high, first + len(own))
                if a < b:
                    ids[a - low : b - low] = own[a - first : b - first]
        held.settle()
        letters = np.frombuffer("".join(alphabet).encode(), np.uint8)
        for start in range(low, high, STEP):
            p = np.arange(start, min(high, start + STEP))
            said, size, live = np.zeros((len(p), longest), np.uint8), np.zeros(len(p), np.int64), np.arange(len(p))
            for step in range(longest + 1):
                code, p = held.back(p)
                on = code < 4
                p, live, code = p[on], live[on], code[on]
                if not len(live):
                    break
                said[live, longest - 1 - step] = letters[code]
                size[live] += 1
            text = said[np.arange(longest) >= longest - size[:, None]]
            at = np.concatenate([[0], np.cumsum(size)]).astype(np.int32)
            s = pa.StringArray.from_buffers(len(size), pa.py_buffer(at), pa.py_buffer(np.ascontiguousarray(text)))
            yield pa.RecordBatch.from_arrays([pa.array(ids[start - low : start - low + len(size)]), s], ["sid", "s"])

    return run


def invert_pieces(pieces: DataFrame, alphabet: tuple[str, ...], longest: int, strings: int = STRINGS) -> DataFrame | None:
    """(sid, s) back from the written pieces of a transform; nothing of one of more places than a task holds."""
    row = pieces.agg(F.sum(F.octet_length("text")).alias("total"), F.sum(F.expr("octet_length(ids) div 8")).alias("n")).first()
    total, n = row.total or 0, row.n or 0
    if total > PLACES:
        return None
    each = max(1, min(strings, -(-n // pieces.sparkSession.sparkContext.defaultParallelism)))
    return each_range(pieces, [_walker(alphabet, total, longest, low, min(n, low + each)) for low in range(0, n, each)], "sid long, s string")
