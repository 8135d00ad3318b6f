"""Size tables of packed strings: each task counts the first symbols of its suffixes as integers, so no row is made for a suffix."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .collection import END, StringCollection
from .packedsort import STEP, _flat, _packer, packable, packed_blocks

#: Symbols of a bucket that an integer holds.
DEEPEST = 32
#: Buckets, 8 bytes each, that every task may hold to split them; more are joined.
WANTED = 4_000_000
#: Different buckets, 16 bytes each, that a task counts before it goes on with those seen from then on.
HELD = 2_000_000
#: Symbols by which most suffixes of other buckets are told apart; symbols up to which counts are an array, of 64 MB at most.
_LEAD, _ARRAY = 10, 12
_COUNTS = "len int, value long, n long"


def takes(coll: StringCollection, depth: int) -> bool:
    return depth <= DEEPEST and packable(coll)


class _Tally:
    """Numbers and how often each was seen."""

    def __init__(self):
        self.values, self.counts, self.held = [], [], 0

    def add(self, values: np.ndarray, counts: np.ndarray) -> bool:
        """Whether it's full."""
        self.values.append(values)
        self.counts.append(counts)
        self.held += len(values)
        if self.held > 2 * HELD:
            self._join()
        return self.held > HELD

    def _join(self) -> None:
        values, counts = np.concatenate(self.values), np.concatenate(self.counts)
        order = np.argsort(values, kind="stable")
        values, counts = values[order], counts[order]
        at = np.flatnonzero(np.append(True, values[1:] != values[:-1])) if len(values) else np.zeros(0, np.int64)
        self.values, self.counts = [values[at]], [np.add.reduceat(counts, at) if len(at) else counts]
        self.held = len(at)

    def taken(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.values:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self._join()
        out = self.values[0], self.counts[0]
        self.values, self.counts, self.held = [], [], 0
        return out


def _runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(values):
        return values, np.zeros(0, np.int64)
    values = np.sort(values)
    at = np.flatnonzero(np.append(True, values[1:] != values[:-1]))
    return values[at], np.diff(np.append(at, len(values)))


def _words(strings: np.ndarray, wide: int) -> Iterator[tuple[int, np.ndarray]]:
    """For each place of a byte's four the 32 symbols from there on, for all bytes of padded strings and one more."""
    n, each = strings.shape
    eights = np.lib.stride_tricks.as_strided(strings, (n, wide + 1, 8), (each, 1, 1))
    eights = np.ascontiguousarray(eights).view(">u8")[:, :, 0].astype(np.uint64)
    yield 0, eights
    after = strings[:, 8 : 8 + wide + 1].astype(np.uint64)
    for s in range(1, 4):
        yield s, eights << np.uint64(2 * s) | after >> np.uint64(8 - 2 * s)


class _Counter:
    """Counts the buckets of `depth` symbols of the suffixes whose first `short` symbols are one of the sorted `wanted`."""

    def __init__(self, wide: int, depth: int, short: int, wanted: np.ndarray | None):
        self.wide, self.depth, self.short, self.wanted = wide, depth, short, wanted
        self.dense, self.added = np.zeros(4**depth, np.uint32) if depth <= _ARRAY else None, 0
        self.full, self.ended, self.seen = _Tally(), _Tally(), None
        if wanted is not None:
            self.lead = min(short, _LEAD)
            self.seen = np.zeros(4**self.lead, bool)
            self.seen[(wanted >> np.uint64(2 * (short - self.lead))).astype(np.int64)] = True

    def _inside(self, first: np.ndarray) -> np.ndarray:
        """Which are wanted; first: the first `short` symbols."""
        at = np.minimum(np.searchsorted(self.wanted, first), len(self.wanted) - 1)
        return self.wanted[at] == first

    def add(self, codes: np.ndarray, lens: np.ndarray) -> bool:
        """Whether what's held has to be sent."""
        n, wide = len(lens), self.wide
        strings = np.zeros((n, wide + 9), np.uint8)
        strings[:, :wide] = codes
        whole, ended = [], []
        for s, words in _words(strings, wide):
            left = lens.astype(np.int32)[:, None] - (4 * np.arange(wide + 1, dtype=np.int32) + s)
            some = words[left >= self.depth]
            if self.seen is not None:
                some = some[self.seen[(some >> np.uint64(64 - 2 * self.lead)).astype(np.int64)]]
            whole.append(some >> np.uint64(64 - 2 * self.depth))
            less = (left >= self.short) & (left < self.depth)
            ended.append((left[less], words[less]))
        whole = np.concatenate(whole)
        if self.dense is not None and self.depth <= 8:
            self.dense += np.bincount(whole.astype(np.int64), minlength=len(self.dense)).astype(np.uint32)
        elif self.dense is not None:
            values, counts = _runs(whole)
            self.dense[values.astype(np.int64)] += counts.astype(np.uint32)
        else:
            values, counts = _runs(whole)
            if self.wanted is not None:
                inside = self._inside(values >> np.uint64(2 * (self.depth - self.short)))
                values, counts = values[inside], counts[inside]
        if self.dense is not None:
            self.added += len(whole)
            filled = self.added >= 1 << 31
        else:
            filled = self.full.add(values, counts)
        left, words = (np.concatenate(x) for x in zip(*ended))
        if self.wanted is not None:
            inside = self._inside(words >> np.uint64(64 - 2 * self.short))
            left, words = left[inside], words[inside]
        # a one before the symbols tells their number
        bits = (2 * left).astype(np.uint64)
        values = np.where(left > 0, words >> (np.uint64(64) - np.maximum(bits, np.uint64(1))), np.uint64(0)) | np.uint64(1) << bits
        return self.ended.add(*_runs(values)) or filled

    def taken(self) -> Iterator[pa.RecordBatch]:
        if self.dense is not None:
            values = np.flatnonzero(self.dense).astype(np.uint64)
            counts = self.dense[values.astype(np.int64)]
            self.dense[:], self.added = 0, 0
            if self.wanted is not None and len(values):
                inside = self._inside(values >> np.uint64(2 * (self.depth - self.short)))
                values, counts = values[inside], counts[inside]
        else:
            values, counts = self.full.taken()
        yield from self._sent(np.full(len(values), self.depth), values, counts)
        values, counts = self.ended.taken()
        lens = np.zeros(len(values), np.int64)
        for k in range(1, self.depth):
            lens[values >= np.uint64(1) << np.uint64(2 * k)] = k
        yield from self._sent(lens, values ^ np.uint64(1) << (2 * lens).astype(np.uint64), counts)

    @staticmethod
    def _sent(lens: np.ndarray, values: np.ndarray, counts: np.ndarray) -> Iterator[pa.RecordBatch]:
        for i in range(0, len(values), 1 << 17):
            part = slice(i, i + (1 << 17))
            yield pa.RecordBatch.from_arrays([pa.array(lens[part].astype(np.int32)), pa.array(values[part].view(np.int64)), pa.array(counts[part].astype(np.int64))], names=["len", "value", "n"])


def _counted(wide: int, depth: int, short: int = 0, wanted=None, before=None):
    """wanted: a broadcast array. before: what is done to the batches first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _Counter(wide, depth, short, None if wanted is None else wanted.value)
        for batch in before(batches) if before else batches:
            codes, lens = _flat(batch.column("codes"), np.uint8).reshape(-1, wide), _flat(batch.column("lens"), np.uint16)
            for i in range(0, len(lens), STEP):
                if counter.add(codes[i : i + STEP], lens[i : i + STEP]):
                    yield from counter.taken()
        yield from counter.taken()

    return run


def _named(counts: DataFrame, alphabet: tuple[str, ...], depth: int) -> DataFrame:
    """(bucket, n): numbers of symbols as the symbols, padded."""
    half = lambda x: F.lpad(F.conv(x.cast("string"), 10, 4), 16, "0")
    value = F.col("value")
    digits = F.concat(half(F.shiftrightunsigned(value, 32)), half(value.bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))))
    text = F.translate(F.substring(digits, 33 - F.col("len"), F.col("len")), "0123"[: len(alphabet)], "".join(alphabet))
    return counts.groupBy("len", "value").agg(F.sum("n").alias("n")).select(F.rpad(text, depth, END).alias("bucket"), "n")


def _number(bucket: Column, alphabet: tuple[str, ...]) -> Column:
    digits = F.lpad(F.translate(bucket, "".join(alphabet), "0123"[: len(alphabet)]), DEEPEST, "0")
    half = lambda at: F.conv(F.substring(digits, at, 16), 4, 10).cast("long")
    return F.shiftleft(half(1), 32).bitwiseOR(half(17))


def _wide(coll: StringCollection) -> int:
    return max(1, -(-coll.longest() // 4))


def prefix_counts(coll: StringCollection, depth: int) -> DataFrame:
    """(bucket, n) of all suffixes, in one scan."""
    run = _counted(_wide(coll), depth, before=_packer(coll.symbols(), coll.longest()))
    return _named(coll.df.where("s is not null").select("sid", "s").mapInArrow(run, _COUNTS), coll.symbols(), depth)


class Splitter:
    """Counts the longer prefixes of some buckets' suffixes, from strings that are packed once."""

    def __init__(self, coll: StringCollection):
        self.coll, self.packed = coll, None

    def counts(self, large: DataFrame, buckets: int, short: int, depth: int) -> DataFrame | None:
        """(bucket, n) of `depth` symbols, of the suffixes in the `large` buckets (wanted) of `short`; None where that takes a join."""
        if buckets > WANTED or not takes(self.coll, depth):
            return None
        if self.packed is None:
            # a task for each core: the fewer they are, the fewer times a bucket is sent
            session = self.coll.df.sparkSession
            self.packed = packed_blocks(self.coll).select("codes", "lens").coalesce(max(1, session.sparkContext.defaultParallelism))
        numbers = large.select(_number(F.col("wanted"), self.coll.symbols()).alias("value")).toArrow()["value"].to_numpy()
        wanted = self.coll.df.sparkSession.sparkContext.broadcast(np.sort(numbers.astype(np.int64).view(np.uint64)))
        return _named(self.packed.mapInArrow(_counted(_wide(self.coll), depth, short, wanted), _COUNTS), self.coll.symbols(), depth)
