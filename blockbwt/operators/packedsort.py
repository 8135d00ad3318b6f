"""Block sort over packed strings: no suffix crosses a shuffle.

Strings of at most four symbols are written once, packed to 2 bits a symbol. The
task of each range reads all of them, keeps the places of its own suffixes and
the packed strings that they are in, and fetches words from those while it
sorts. So disk holds a quarter of a byte a symbol, and time grows with the
strings times the ranges; collections of more than SCANS ranges are listed row
by row as before.

A suffix's key is a row of digits of 16 bits: its symbols by eights, padded with
zeros, then its length, then its string's id. A bound of a range is a few of the
first digits. Buckets of more suffixes than a task sorts are split by the next
digit, down to the ids, so equal suffixes of any number of strings are split too.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockbwt.plans.planner import Budget, greedy
from blockbwt.storage import materialise

from .collection import StringCollection
from .sorters import order_index, order_lsd, order_merge

#: Suffixes that a task sorts at most, some 100 bytes each with what a sort takes.
CAPACITY = 4_000_000
#: Ranges, each of which scans all strings, beyond which suffixes are listed as rows.
SCANS = 512
#: Symbols of the longest string that is packed.
LONGEST = 4096
BLOCKS = "codes binary, lens binary, sids binary"
#: Strings in a row of a packed table, and in one step of a scan.
ROWS, STEP = 64, 8192
#: Symbols in a word of each encoding; the last two are made of table look-ups of eights.
SYMBOLS = {"bits": 31, "radix": 16, "digits": 24}


def packable(coll: StringCollection) -> bool:
    return coll.alphabet is not None and len(coll.alphabet) <= 4 and all(len(c.encode()) == 1 for c in coll.alphabet) and coll.longest() <= LONGEST


def _packer(alphabet: tuple[str, ...], longest: int):
    codes = np.full(256, 255, np.uint8)
    for i, c in enumerate(alphabet):
        codes[ord(c)] = i
    wide = max(1, -(-longest // 4))

    def cut(data: np.ndarray, n: int, each: int) -> pa.Array:
        offsets = np.minimum(np.arange(0, n + ROWS, ROWS), n).astype(np.int32) * np.int32(each)
        return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(data))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, s = batch.num_rows, batch.column("s").cast(pa.string())
            if not n:
                continue
            at = np.frombuffer(s.buffers()[1], np.int32)[s.offset : s.offset + n + 1]
            lens = np.diff(at)
            text = np.frombuffer(s.buffers()[2], np.uint8)[at[0] : at[-1]] if at[-1] > at[0] else np.zeros(0, np.uint8)
            each = np.zeros((n, 4 * wide), np.uint8)
            found = codes[text]
            if (found == 255).any() or lens.max() > longest:
                raise ValueError("a string holds a symbol outside the alphabet, or is longer than the longest")
            each[np.arange(4 * wide) < lens[:, None]] = found
            packed = each[:, 0::4] << 6 | each[:, 1::4] << 4 | each[:, 2::4] << 2 | each[:, 3::4]
            sids = batch.column("sid").cast(pa.int64()).to_numpy()
            yield pa.RecordBatch.from_arrays([cut(packed, n, wide), cut(lens.astype(np.uint16), n, 2), cut(sids, n, 8)], ["codes", "lens", "sids"])

    return run


def packed_blocks(coll: StringCollection) -> DataFrame:
    """The packed strings as a written table."""
    some = coll.df.where("s is not null").select("sid", "s")
    return materialise(some.mapInArrow(_packer(coll.symbols(), coll.longest()), BLOCKS), "packed")


def _flat(column: pa.Array, kind) -> np.ndarray:
    if not len(column):
        return np.zeros(0, kind)
    at = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2], np.uint8)[at[0] : at[-1]].view(kind)


@dataclass
class Held:
    """Packed strings, padded by PAD bytes of zeros each, and places in them: the string's number, the code of the symbol before (4 for none) and the position in one integer."""

    flat: np.ndarray
    wide: int
    lens: np.ndarray
    sids: np.ndarray
    place: np.ndarray

    PAD = 9
    #: Places that are looked up at once.
    AT_ONCE = 1 << 17

    @classmethod
    def of(cls, strings: np.ndarray, wide: int, lens: np.ndarray, sids: np.ndarray, ref: np.ndarray, pos: np.ndarray) -> Held:
        flat, before = strings.ravel(), np.maximum(pos - 1, 0)
        code = flat[ref * (wide + cls.PAD) + (before >> 2)] >> (6 - ((before & 3) << 1)).astype(np.uint8) & 3
        return cls(flat, wide, lens, sids, ref << 16 | np.where(pos > 0, code, 4).astype(np.int64) << 13 | pos)

    def some(self, which) -> Held:
        return replace(self, place=self.place[which])

    @property
    def ref(self) -> np.ndarray:
        return self.place >> 16

    @property
    def pos(self) -> np.ndarray:
        return self.place & 8191

    def before(self) -> np.ndarray:
        return (self.place >> 13 & 7).astype(np.uint8)

    def _looked_up(self, f, kind) -> np.ndarray:
        out = np.empty(len(self.place), kind)
        for i in range(0, len(out), self.AT_ONCE):
            out[i : i + self.AT_ONCE] = f(self.some(slice(i, i + self.AT_ONCE)))
        return out

    def _at(self, symbols: int) -> tuple[np.ndarray, np.ndarray]:
        """The byte that holds the symbol so far on in each suffix, and its bit there. Past a string all is padding."""
        on = self.pos + symbols
        return self.ref * (self.wide + self.PAD) + np.minimum(on >> 2, self.wide), (on & 3) << 1

    def word(self, j: int) -> np.ndarray:
        """31 symbols from the 31 j-th on, as in `Packing`."""
        eights = np.lib.stride_tricks.as_strided(self.flat, (len(self.flat) - 7, 8), (1, 1))

        def look_up(some: Held) -> np.ndarray:
            at, bit = some._at(31 * j)
            bit = bit.astype(np.uint64)
            x = eights[at].view(">u8").ravel().astype(np.uint64)
            return (x << bit | self.flat[at + 8].astype(np.uint64) >> (np.uint64(8) - bit)) >> np.uint64(2)

        return self._looked_up(look_up, np.int64)

    def eight(self, k: int) -> np.ndarray:
        """8 symbols from the 8 k-th on, as 16 bits."""

        def look_up(some: Held) -> np.ndarray:
            at, bit = some._at(8 * k)
            x = self.flat[at].astype(np.uint32) << 16 | self.flat[at + 1].astype(np.uint32) << 8 | self.flat[at + 2]
            return (x >> (8 - bit).astype(np.uint32)).astype(np.uint16)

        return self._looked_up(look_up, np.uint16)

    def left(self) -> np.ndarray:
        return self._looked_up(lambda some: self.lens[some.ref] - some.pos, np.int64)

    def sid(self) -> np.ndarray:
        return self._looked_up(lambda some: self.sids[some.ref], np.int64)

    def digit(self, k: int, eights: int) -> np.ndarray:
        if k < eights:
            return self.eight(k)
        if k == eights:
            return self.left().astype(np.uint16)
        raised = self.sid().view(np.uint64) ^ np.uint64(1 << 63)
        return (raised >> np.uint64(16 * (3 - (k - eights - 1)))).astype(np.uint16)


def eights_of(longest: int) -> int:
    return max(1, -(-longest // 8))


def _reached(held: Held, first: np.ndarray, bound: Sequence[int], eights: int) -> np.ndarray:
    """Which suffixes aren't below the bound; first: their first digit."""
    out = first > bound[0]
    same = np.flatnonzero(first == bound[0])
    for k in range(1, len(bound)):
        if not len(same):
            break
        digit = held.some(same).digit(k, eights)
        out[same[digit > bound[k]]] = True
        same = same[digit == bound[k]]
    out[same] = True
    return out


def _chunks(batches: Iterator[pa.RecordBatch], wide: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    for batch in batches:
        codes, lens, sids = (_flat(batch.column(c), k) for c, k in (("codes", np.uint8), ("lens", np.uint16), ("sids", np.int64)))
        codes = codes.reshape(-1, wide)
        for i in range(0, len(lens), STEP):
            yield codes[i : i + STEP], lens[i : i + STEP], sids[i : i + STEP]


def _listed(batches, wide: int, eights: int, low: Sequence[int], high: Sequence[int] | None) -> Iterator[Held]:
    """The suffixes from the bound low on and below high, chunk by chunk, with the strings that hold them. Four symbols, a byte each, tell nearly all others apart."""
    least = low[0] >> 8
    most = 255 if high is None else (high[0] if len(high) > 1 else high[0] - 1) >> 8
    for codes, lens, sids in _chunks(batches, wide):
        n = len(lens)
        padded = np.zeros((n, wide + 1), np.uint8)
        padded[:, :wide] = codes
        a = padded.ravel()
        b = np.append(a[1:], np.uint8(0))
        refs, places = [], []
        for s in range(4):
            four = a << 2 * s | b >> 8 - 2 * s if s else a
            at = np.flatnonzero((four - np.uint8(least)) <= np.uint8(most - least))
            ref = at // (wide + 1)
            refs.append(ref)
            places.append((at - ref * (wide + 1)) * 4 + s)
        ref, pos = np.concatenate(refs), np.concatenate(places)
        fits = pos <= lens[ref]
        ref, pos = ref[fits], pos[fits]
        strings = np.zeros((n, wide + Held.PAD), np.uint8)
        strings[:, :wide] = codes
        held = Held.of(strings, wide, lens, sids, ref, pos)
        first = held.eight(0)
        inside = _reached(held, first, low, eights)
        if high is not None:
            inside &= ~_reached(held, first, high, eights)
        held = held.some(inside)
        if len(held.place):
            used = np.zeros(n, bool)
            used[held.ref] = True
            number = np.cumsum(used) - 1
            yield Held(strings[used].ravel(), wide, lens[used], sids[used], number[held.ref] << 16 | held.place & 65535)


def _together(parts: Iterator[Held], wide: int, most: int) -> Held:
    """All of `most` suffixes. There are no more strings than these; pages that nothing is written to take no memory."""
    each = wide + Held.PAD
    flat, lens, sids, place = (np.empty(most * k, kind) for k, kind in ((each, np.uint8), (1, np.uint16), (1, np.int64), (1, np.int64)))
    strings = n = 0
    for p in parts:
        s, m = len(p.lens), len(p.place)
        if n + m > most:
            raise ValueError(f"more suffixes than the {most} of a range")
        flat[strings * each : (strings + s) * each], lens[strings : strings + s], sids[strings : strings + s] = p.flat, p.lens, p.sids
        place[n : n + m] = p.place + (strings << 16)
        strings, n = strings + s, n + m
    if n != most:
        raise ValueError(f"{n} suffixes in a range of {most}")
    return Held(flat[: strings * each], wide, lens[:strings], sids[:strings], place)


class _Words(Sequence):
    """A suffix's words from the first on and its length, where padding looks like a symbol. Each is made when it is asked for."""

    def __init__(self, held: Held, longest: int, encoding: str):
        self.held, self.encoding, self.n = held, encoding, max(1, -(-longest // SYMBOLS[encoding]))

    def __len__(self) -> int:
        return self.n + (self.encoding == "bits")

    def __getitem__(self, j: int) -> np.ndarray:
        if not 0 <= j < len(self):
            raise IndexError(j)
        if j == self.n:
            return self.held.left()
        if self.encoding == "bits":
            return self.held.word(j)
        table, each, left = _table(self.encoding), SYMBOLS[self.encoding] // 8, self.held.left()
        out = np.zeros(len(left), np.int64)
        for k in range(j * each, (j + 1) * each):
            digit = table[np.clip(left - 8 * k, 0, 8), self.held.eight(k)]
            out = out * _BASE[self.encoding] ** 8 + digit
        return out


_BASE = {"radix": 8, "digits": 5}


def _table(encoding: str) -> np.ndarray:
    """Of eight symbols, of which the first m are there: the number of their codes from 1, and zeros, in the encoding's base."""
    base = _BASE[encoding]
    x = np.arange(1 << 16)
    out = np.zeros((9, 1 << 16), np.int64)
    for m in range(9):
        for i in range(m):
            out[m] += ((x >> (14 - 2 * i) & 3) + 1) * base ** (7 - i)
    return out


def order_ties(held: Held, longest: int, doubled: bool = False) -> np.ndarray:
    """One sort by the first word; further words are fetched for tied suffixes alone, then lengths and ids. doubled: each time as many words as are ranked already, so a rank of 2h symbols comes of two of h."""
    words = max(1, -(-longest // SYMBOLS["bits"]))
    key = held.word(0)
    order = np.argsort(key)
    key = key[order]
    new = np.ones(len(order), bool)
    new[1:] = key[1:] != key[:-1]
    del key
    done = 1
    while True:
        tied = ~new
        tied[:-1] |= ~new[1:]
        at = np.flatnonzero(tied)
        if not len(at):
            break
        group, rows = np.cumsum(new[at]), order[at]
        some = held.some(rows)
        keys = [some.word(j) for j in range(done, min(2 * done if doubled else done + 1, words))] or [some.left(), some.sid()]
        inner = np.lexsort((*reversed(keys), group))
        order[at] = rows[inner]
        if done >= words:
            break
        for key in keys:
            key = key[inner]
            new[at[1:]] |= key[1:] != key[:-1]
        done += len(keys)
    return order


def _order(held: Held, longest: int, engine: str, encoding: str, bits: int) -> np.ndarray:
    if engine in ("catalyst", "doubling") and encoding == "bits":
        return order_ties(held, longest, engine == "doubling")
    words = _Words(held, longest, encoding)
    if engine == "lsd":
        return order_lsd(words, held.sid(), bits)
    return (order_merge if engine == "merge" else order_index)(list(words), held.sid())


@dataclass(frozen=True)
class Range:
    """The suffixes from the bound low on and below high; start: the number of those below."""

    low: tuple[int, ...]
    high: tuple[int, ...] | None
    start: int
    n: int
    round: int = 0


def _counter(wide: int, eights: int, prefixes: list[tuple[int, ...]]):
    """Counts of the digit after each prefix; all have the same length."""
    k = len(prefixes[0])

    def all_first(batches) -> Iterator[tuple[int, np.ndarray]]:
        counts = np.zeros(1 << 16, np.int64)
        for codes, lens, _ in _chunks(batches, wide):
            n = len(lens)
            strings = np.zeros((n, wide + 3), np.uint8)
            strings[:, :wide] = codes
            a = strings.ravel().astype(np.uint32)
            for s in range(4):
                here = (a[:-2] << 16 | a[1:-1] << 8 | a[2:]) >> 8 - 2 * s
                here = np.append(here, np.zeros(2, np.uint32)).astype(np.uint16).reshape(n, wide + 3)
                fits = np.arange(wide + 3) * 4 + s <= lens[:, None]
                counts += np.bincount(here[fits], minlength=1 << 16)
        yield 0, counts

    def deeper(batches) -> Iterator[tuple[int, np.ndarray]]:
        counts = np.zeros((len(prefixes), 1 << 16), np.int64)
        for batch in batches:
            for i, p in enumerate(prefixes):
                high = (*p[:-1], p[-1] + 1) if p[-1] < 65535 else None
                for held in _listed(iter([batch]), wide, eights, p, high):
                    first = np.ones(len(held.place), bool)
                    for j, x in enumerate(p):  # above the last value of a digit nothing bounds the prefix
                        first &= held.digit(j, eights) == x
                    counts[i] += np.bincount(held.some(first).digit(k, eights), minlength=1 << 16)
        yield from enumerate(counts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i, counts in (deeper if k else all_first)(batches):
            at = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), i)), pa.array(at), pa.array(counts[at])], ["p", "digit", "n"])

    return run


def buckets(blocks: DataFrame, longest: int, most: int) -> list[tuple[tuple[int, ...], int]]:
    """(first digits, suffixes) in order, each of at most `most` suffixes: the driver gets a row for each different digit, 65,536 of them at most for each split bucket."""
    wide, eights = max(1, -(-longest // 4)), eights_of(longest)
    done, open_ = [], [()]
    while open_:
        found = blocks.mapInArrow(_counter(wide, eights, open_), "p long, digit long, n long").groupBy("p", "digit").agg(F.sum("n").alias("n")).collect()
        each = [((*open_[x.p], x.digit), x.n) for x in found]
        # no two suffixes share all digits, where ids are unique; repeated ones stay together
        split = {p for p, n in each if n > most and len(p) < eights + 5}
        done += [(p, n) for p, n in each if p not in split]
        open_ = sorted(split)
    return sorted(done)


def ranges(found: list[tuple[tuple[int, ...], int]], most: int, round_rows: int | None = None) -> list[Range]:
    """Consecutive buckets packed for a task's capacity, within rounds."""
    total = sum(n for _, n in found)
    rounds = greedy([n for _, n in found], round_rows or max(1, total))
    out, at, start = [], 0, 0
    while at < len(found):
        end = at
        while end < len(found) and rounds[end] == rounds[at]:
            end += 1
        inner = greedy([n for _, n in found[at:end]], most)
        for r in range(inner[-1] + 1):
            mine = [x for x, k in zip(found[at:end], inner) if k == r]
            n = sum(x[1] for x in mine)
            out.append((mine[0][0], start, n, rounds[at]))
            start += n
        at = end
    return [Range(low, out[i + 1][0] if i + 1 < len(out) else None, start, n, r) for i, (low, start, n, r) in enumerate(out)]


def _sorter(part: Range, wide: int, longest: int, alphabet: tuple[str, ...], budget: Budget, block: int | None, ids: bool = False):
    encoding = "bits" if budget.encoding == "auto" else budget.encoding

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = _together(_listed(batches, wide, eights_of(longest), part.low, part.high), wide, part.n)
        order = _order(held, longest, budget.engine, encoding, budget.digit_bits)
        if block:
            text = np.frombuffer(("".join(alphabet).ljust(4) + "$").encode(), np.uint8)[held.before()[order]]
            if ids:
                left, sid = held.left()[order], held.sid()[order]
            cuts = [part.start, *range((part.start // block + 1) * block, part.start + part.n, block), part.start + part.n]
            for a, b in zip(cuts, cuts[1:]):
                if ids:
                    i, j = a - part.start, b - part.start
                    yield pa.RecordBatch.from_arrays([pa.array([a]), pa.array([text[i:j].tobytes()], pa.binary()), pa.array([sid[i:j][left[i:j] == 0].tobytes()], pa.binary())], ["first", "text", "ids"])
                    continue
                yield pa.RecordBatch.from_arrays([pa.array([a // block]), pa.array([a]), pa.array([text[a - part.start : b - part.start].tobytes().decode()])], ["block_id", "first", "text"])
            return
        names = pa.array([*alphabet])
        for i in range(0, len(order), 1 << 16):
            some = held.some(order[i : i + (1 << 16)])
            code = some.before()
            sym = pa.DictionaryArray.from_arrays(pa.array(code.astype(np.int8), mask=code == 4), names).cast(pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(part.start + i + np.arange(len(code))), pa.array(some.sid()), pa.array(some.pos.astype(np.int32)), sym], ["bwt_pos", "sid", "pos", "sym"])

    return run


def _union(parts: list[DataFrame]) -> DataFrame:
    """Pairs of pairs, so that a plan of many parts isn't a deep one."""
    while len(parts) > 1:
        parts = [parts[i].union(parts[i + 1]) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
    return parts[0]


def planned(coll: StringCollection, budget: Budget) -> tuple[DataFrame, list[Range]] | None:
    """The packed strings and the ranges of their suffixes; nothing where they aren't packable, one has no id, or they would be scanned too often."""
    if not packable(coll) or budget.encoding == "utf8" or not coll.df.where("sid is null").isEmpty():
        return None
    most = min(budget.sort_rows, CAPACITY)
    blocks = packed_blocks(coll)
    plan = ranges(buckets(blocks, coll.longest(), most), most, budget.round_rows)
    return (blocks, plan) if len(plan) <= SCANS else None


def bound_of(splitter: str, alphabet: tuple[str, ...], longest: int, cut: int = 256) -> tuple[int, ...]:
    """The digits of a suffix: its symbols by eights and its length; of one that is cut there the symbols alone."""
    eights = eights_of(longest)
    codes = [alphabet.index(c) for c in splitter] + [0] * (8 * eights)
    digits = tuple(sum(c << 14 - 2 * i for i, c in enumerate(codes[8 * k : 8 * k + 8])) for k in range(eights))
    return (*digits, len(splitter)) if len(splitter) < cut else digits[: cut // 8]


def counted(blocks: DataFrame, bounds: list[tuple[int, ...]], longest: int) -> list[Range]:
    """The ranges between bounds, counted after the fact by a scan for each; the first bound is the least."""
    wide, eights = max(1, -(-longest // 4)), eights_of(longest)
    spans = list(zip(bounds, [*bounds[1:], None]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = np.zeros(len(spans), np.int64)
        for batch in batches:
            for i, (low, high) in enumerate(spans):
                own[i] += sum(len(h.place) for h in _listed(iter([batch]), wide, eights, low, high))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(spans))), pa.array(own)], ["i", "n"])

    sizes = {x.i: x.n for x in blocks.mapInArrow(run, "i long, n long").groupBy("i").agg(F.sum("n").alias("n")).collect()}
    out, start = [], 0
    for i, (low, high) in enumerate(spans):
        out.append(Range(low, high, start, sizes.get(i, 0)))
        start += sizes.get(i, 0)
    return [r for r in out if r.n]


def planned_sampled(coll: StringCollection, budget: Budget, splitters: list[str]) -> tuple[DataFrame, list[Range]] | None:
    """Ranges between sampled splitters; one of more suffixes than a task sorts is cut again at counted buckets."""
    if (found := planned(coll, budget)) is None:
        return None
    blocks, plan = found
    bounds = {bound_of(x, coll.symbols(), coll.longest()) for x in splitters} | {r.low for r in plan} | {(0,)}
    return blocks, counted(blocks, sorted(bounds), coll.longest()) if plan else []


def _sorted(coll: StringCollection, blocks: DataFrame, plan: list[Range], budget: Budget, kinds: str, block: int | None, ids: bool = False) -> DataFrame:
    if not plan:
        return coll.df.sparkSession.createDataFrame([], kinds)
    wide, longest = max(1, -(-coll.longest() // 4)), coll.longest()
    # each range is one task's, which reads all packed strings; a union of single partitions alone would be one task
    none = coll.df.sparkSession.range(0, 2, 1, 2).where("id > 1").select(*[F.lit(None).cast(k).alias(c) for c, k in (x.split() for x in kinds.split(", "))])
    return _union([none, *(blocks.coalesce(1).mapInArrow(_sorter(p, wide, longest, coll.symbols(), budget, block, ids), kinds) for p in plan)])


def bwt_packed(coll: StringCollection, budget: Budget) -> DataFrame:
    """The transform, a row for each suffix."""
    if (found := planned(coll, budget)) is None:
        from .construct import bwt_build

        return bwt_build(coll.staged(), budget)
    return _sorted(coll, *found, budget, "bwt_pos long, sid long, pos int, sym string", None)


def bwt_packed_blocks(coll: StringCollection, budget: Budget, block: int = 65536, plan=None) -> DataFrame:
    """(block_id, text) as `bwt_blocks` gives it: a task writes its symbols as pieces of blocks, of which only those pieces move."""
    if (found := plan or planned(coll, budget)) is None:
        from .construct import bwt_blocks, bwt_build

        return bwt_blocks(bwt_build(coll.staged(), budget), block)
    pieces = _sorted(coll, *found, budget, "block_id long, first long, text string", block)
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("first", "text"))), lambda x: x["text"]), "")
    return pieces.groupBy("block_id").agg(text.alias("text"))


PIECES = "first long, text binary, ids binary"


def bwt_packed_pieces(coll: StringCollection, budget: Budget, block: int = 65536) -> DataFrame | None:
    """The transform as pieces of up to `block` symbols from the place `first` on, `$` before whole strings, with the ids of the strings' ends that are in it; nothing where `planned` finds nothing."""
    found = planned(coll, budget)
    return _sorted(coll, *found, budget, PIECES, block, True) if found else None
