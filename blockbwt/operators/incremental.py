"""Merging two transforms by counting ranks."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockbwt.storage import fresh_path, materialise

from .collection import END, StringCollection, ordered_ranks

#: Suffixes of a transform that a task may hold, at about 3 bytes each; larger ones are walked by joins.
LIMIT = 20_000_000
_BLOCK = 1 << 16


class CapacityError(ValueError):
    """The input is larger than a method limited by its memory takes."""


def _points(texts) -> np.ndarray:
    return np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)


@dataclass
class Counts:
    """A transform as its symbols' codes (0: a string's start) in rows of a fixed length, and each code's number before each row."""

    ids: np.ndarray
    symbols: np.ndarray
    text: np.ndarray
    before: np.ndarray
    starts: np.ndarray

    @classmethod
    def of(cls, symbols: np.ndarray, blocks, n: int, ids: np.ndarray) -> Counts:
        """symbols: code points in order. blocks: the n symbols in order, in texts of any length."""
        sigma = len(symbols) + 1
        step = max(64, 4 * sigma)
        text = np.zeros((n // step + 1) * step, np.uint8 if sigma <= 256 else np.uint16 if sigma <= 1 << 16 else np.uint32)
        at = 0
        for block in blocks:
            points = _points([block])
            text[at : at + len(points)] = np.where(points == ord(END), 0, np.searchsorted(symbols, points) + 1)
            at += len(points)
        text = text.reshape(-1, step)
        own = np.empty((len(text), sigma), np.int32)
        for i in range(0, len(text), 4096):
            some = text[i : i + 4096]
            own[i : i + 4096] = np.bincount((np.arange(len(some))[:, None] * sigma + some).ravel(), minlength=len(some) * sigma).reshape(-1, sigma)
        own[-1, 0] -= text.size - n  # the last row's filling
        before = np.zeros((len(text) + 1, sigma), np.int64 if n >= 1 << 31 else np.int32)
        np.cumsum(own, axis=0, out=before[1:])
        starts = np.concatenate([[len(ids)], len(ids) + np.cumsum(before[-1, 1:], dtype=np.int64)])
        return cls(ids, symbols, text, before[:-1], starts)

    def walk(self, sids: np.ndarray, strings: list[str]) -> list[np.ndarray]:
        """For each string the number of suffixes here below each of its own, all strings a step at a time."""
        lens = np.array([len(s) for s in strings], np.int64)
        points = _points(strings)
        codes = np.searchsorted(self.symbols, points).astype(np.int64)
        known = codes < len(self.symbols)
        known[known] = self.symbols[codes[known]] == points[known]
        first = np.concatenate([[0], np.cumsum(lens)])
        out = np.zeros(len(points) + len(lens), np.int64)
        ends = first[1:] + np.arange(len(lens))  # of a string's places, one more than its symbols
        live = np.arange(len(lens))
        at = np.searchsorted(self.ids, sids).astype(np.int64)
        out[ends] = at
        step, within = self.text.shape[1], np.arange(self.text.shape[1])
        for j in range(1, int(lens.max(initial=0)) + 1):
            keep = lens[live] >= j
            live, at = live[keep], at[keep]
            where = first[live + 1] - j
            code, has = codes[where], known[where]
            row, inside = at[has] // step, at[has] % step
            here = ((self.text[row] == (code[has] + 1)[:, None]) & (within < inside[:, None])).sum(1)
            at = self.starts[code]  # before the first suffix of a symbol that isn't below it
            at[has] += self.before[row, code[has] + 1] + here
            out[ends[live] - j] = at
        return np.split(out, (ends + 1)[:-1]) if len(lens) else []


def smaller_in(coll: StringCollection, other: StringCollection, other_bwt: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(sid, pos, before): for each suffix of coll the number of suffixes of `other` below it, by a walk on the other's counts.

    Tasks read the symbols of a transform of up to `limit` suffixes from where they
    are written, and hold them packed, with a count for about each fourth of them;
    the driver sees sizes alone. Larger ones are walked by joins with their blocks,
    a step for each symbol.
    """
    n = other_bwt.count()
    if n > limit:
        return smaller_by_joins(coll, other, other_bwt)
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("bwt_pos", F.coalesce("sym", F.lit(END)).alias("c")))), lambda x: x["c"]), "")
    blocks = other_bwt.groupBy(F.floor(F.col("bwt_pos") / _BLOCK).alias("key")).agg(text.alias("s")).select(F.lit(_TEXT).alias("kind"), "key", "s")
    ids = other.df.select(F.lit(_ID).alias("kind"), F.col("sid").alias("key"), F.lit(None).cast("string").alias("s"))
    index = materialise(blocks.unionByName(ids), "index")
    strings = materialise(coll.df.select(F.lit(_STRING).alias("kind"), F.col("sid").alias("key"), "s"), "strings")
    suffixes = strings.agg(F.sum(F.length("s").cast("long") + 1)).first()[0] or 0
    tasks = max(1, min(coll.df.sparkSession.sparkContext.defaultParallelism, suffixes // _LEAST), -(-suffixes // _WALKED))
    own = F.pmod(F.xxhash64("key"), F.lit(tasks))
    none = strings.sparkSession.range(0, 2, 1, 2).where("id > 1").select(F.lit(0).alias("kind"), F.col("id").alias("key"), F.lit("").alias("s"))
    parts = [index.unionByName(strings.where(own == r)).coalesce(1).mapInPandas(_walker(n), WALKED) for r in range(tasks)]
    return _union([none.mapInPandas(_walker(0), WALKED), *parts])


#: Suffixes of the strings that a task walks, all held, at most; below the lesser number another task isn't worth its own copy of the counts.
_WALKED, _LEAST = 4_000_000, 200_000
_TEXT, _ID, _STRING = 0, 1, 2
WALKED = "sid long, pos int, before long"


def _walker(n: int):
    """Rows (kind, key, s) in any order, the n symbols in blocks, the ids of their strings, and the strings to walk, as the latter's places."""

    def walk(batches):
        blocks, ids, sids, strings = {}, [], [], []
        for batch in batches:
            kind, key = batch["kind"].to_numpy(), batch["key"].to_numpy()
            blocks.update(zip(key[kind == _TEXT].tolist(), batch["s"][kind == _TEXT]))
            ids.append(key[kind == _ID])
            sids.append(key[kind == _STRING])
            strings += batch["s"][kind == _STRING].tolist()
        if not strings:
            return
        symbols = np.unique(np.concatenate([np.zeros(0, np.uint32), *(np.unique(_points([x])) for x in blocks.values())]))
        counts = Counts.of(symbols[symbols != ord(END)], (blocks.pop(k) for k in sorted(blocks)), n, np.sort(np.concatenate(ids)))
        sids = np.concatenate(sids)
        for i in range(0, len(sids), 2000):
            found = counts.walk(sids[i : i + 2000], strings[i : i + 2000])
            sizes = [len(x) for x in found]
            pos = np.concatenate([np.arange(x, dtype=np.int32) for x in sizes])
            yield pd.DataFrame({"sid": np.repeat(sids[i : i + 2000], sizes), "pos": pos, "before": np.concatenate(found)})

    return walk


def _union(parts: list[DataFrame]) -> DataFrame:
    """Pairs of pairs, so that a plan of many parts isn't a deep one."""
    while len(parts) > 1:
        parts = [parts[i].unionByName(parts[i + 1]) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
    return parts[0]


def smaller_by_joins(coll: StringCollection, other: StringCollection, other_bwt: DataFrame) -> DataFrame:
    """The same for transforms of any size: each step joins the strings' places with the blocks of the other's index, and is written."""
    from .fmindex import build_index

    index, spark = build_index(other_bwt), coll.df.sparkSession
    total, strings = index.bwt.count(), other.df.count()
    # an id's own rank among both collections' ids less that among its own is the number of the other's below it
    both = ordered_ranks(coll.df.select("sid", F.lit(0).alias("z")).unionByName(other.df.select("sid", F.lit(1).alias("z"))), ["sid", "z"], "r").where("z = 0")
    own = ordered_ranks(coll.df.select("sid"), ["sid"], "q")
    state = both.join(own, "sid").select("sid", (F.col("r") - F.col("q")).alias("before")).join(coll.df.select("sid", F.length("s").alias("pos")), "sid").select("sid", "pos", "before")
    starts = sorted(((k, v) for k, v in index.starts.items()), key=lambda x: x[0].encode())
    # where the suffixes of a symbol begin, or would: after those of all smaller ones
    begin = sum((F.when(F.col("c") > k, n).otherwise(0) for k, (_, n) in starts), F.lit(strings).cast("long"))
    path, longest = fresh_path(spark, "walk"), coll.longest()
    for i in range(longest + 1):
        state.write.option("compression", "zstd").parquet(f"{path}/step={i}")
        state = spark.read.schema(state.schema).parquet(f"{path}/step={i}")
        if i == longest:
            break
        asked = state.where("pos > 0").join(coll.df, "sid").select("sid", (F.col("pos") - 1).alias("pos"), "before", F.substring("s", F.col("pos"), F.lit(1)).alias("c"))
        asked = asked.withColumn("block", F.floor((F.col("before") - F.when(F.col("before") == total, 1).otherwise(0)) / index.step))
        head = F.substring("text", F.lit(1), (F.col("before") - F.col("block") * index.step).cast("int"))
        count = F.length(head) - F.length(F.replace(head, F.col("c"), F.lit("")))
        placed = asked.join(index.blocks, "block", "left")
        state = placed.select("sid", "pos", (begin + F.coalesce(F.element_at("counts", F.col("c")), F.lit(0)) + F.coalesce(count, F.lit(0))).cast("long").alias("before"))
    return spark.read.schema("sid long, pos int, before long").parquet(path).select("sid", "pos", "before")


def merge(a: StringCollection, a_bwt: DataFrame, b: StringCollection, b_bwt: DataFrame, limit: int = LIMIT) -> DataFrame:
    """The transform of both collections together."""
    out = None
    for coll, own, other, bwt in ((a, a_bwt, b, b_bwt), (b, b_bwt, a, a_bwt)):
        moved = own.join(smaller_in(coll, other, bwt, limit), ["sid", "pos"]).select((F.col("bwt_pos") + F.col("before")).alias("bwt_pos"), "sid", "pos", "sym")
        out = moved if out is None else out.unionByName(moved)
    return out
