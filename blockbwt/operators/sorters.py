"""Engines that order the suffixes of small ranges.

Each takes listed rows (small_range, start, sid, pos, sym, w.., wl?) of which a
small range fits its capacity, and adds `rank`: the range's first place plus the
row's place in it. Ties of equal suffixes are broken by the string's id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ENGINES = ("catalyst", "lsd", "index", "merge")
OUT = "rank long, sid long, pos int, sym string"


def word_columns(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c in ("wr", "wl") or c[0] == "w" and c[1:].isdigit()]


def by_catalyst(listed: DataFrame) -> DataFrame:
    """One composite sort, which spills and needs no Python: the default."""
    order = Window.partitionBy("small_range").orderBy(*word_columns(listed), "sid")
    return listed.select((F.col("start") + F.row_number().over(order) - 1).alias("rank"), "sid", "pos", "sym")


def by_partition(dealt: DataFrame) -> DataFrame:
    """The same where every partition is one small range, dealt by its number: a local sort that begins with the first word, so rows compare by it alone for the most part, and a row's place is its number in the partition."""
    ordered = dealt.sortWithinPartitions(*word_columns(dealt), "sid")
    place = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    return ordered.select((F.col("start") + place).alias("rank"), "sid", "pos", "sym")


def _words(table: pa.Table) -> list[np.ndarray]:
    """Keys from the most significant on."""
    out = [table[c].to_numpy() for c in table.column_names if c[0] == "w" and c[1:].isdigit()]
    if "wr" in table.column_names:
        rest = table["wr"].combine_chunks()
        flat = rest.flatten().to_numpy()
        out += list(flat.reshape(len(rest), -1).T) if len(rest) else []
    if "wl" in table.column_names:
        out.append(table["wl"].to_numpy())
    return out


def order_lsd(words: list[np.ndarray], sid: np.ndarray, bits: int = 62) -> np.ndarray:
    """Word by word from the last, stable, moving the index alone; rows begin in the order of their strings."""
    index = np.argsort(sid, kind="stable")
    for word in reversed(words):
        if bits >= 62:
            index = index[np.argsort(word[index], kind="stable")]
            continue
        for shift in range(0, 62, bits):  # narrower digits: more passes, each a radix sort for 16 bits
            digit = (word[index] >> shift) & ((1 << bits) - 1)
            index = index[np.argsort(digit.astype(np.uint16 if bits <= 16 else np.int64), kind="stable")]
    return index


def order_index(words: list[np.ndarray], sid: np.ndarray) -> np.ndarray:
    """One sort of indices over whole keys."""
    return np.lexsort((sid, *reversed(words)))


def order_merge(words: list[np.ndarray], sid: np.ndarray) -> np.ndarray:
    """A comparison sort of whole keys as records."""
    key = np.ascontiguousarray(np.stack([w.astype(np.int64) for w in [*words, sid]], axis=1))
    return np.argsort(key.view([("", np.int64)] * key.shape[1]).ravel(), kind="stable")


def by_arrow(listed: DataFrame, engine: str = "lsd", bits: int = 62) -> DataFrame:
    """A small range as one Arrow table: its capacity bounds the worker."""
    how = {"lsd": lambda w, s: order_lsd(w, s, bits), "index": order_index, "merge": order_merge}[engine]

    def run(table: pa.Table) -> pa.Table:
        order = how(_words(table), table["sid"].to_numpy())
        start = table["start"][0].as_py()
        some = table.take(pa.array(order))
        return pa.table({"rank": pa.array(start + np.arange(len(order))), "sid": some["sid"], "pos": some["pos"], "sym": some["sym"]})

    return listed.groupBy("small_range").applyInArrow(run, OUT)


def lsd_distributed(listed: DataFrame) -> DataFrame:
    """Word passes over the cluster: each sorts (word, rank so far) and moves all rows. An ablation: it moves them once a word."""
    from .collection import ordered_ranks

    ranked = ordered_ranks(listed, ["sid", "pos"], "rank")
    for c in reversed(word_columns(listed)):
        ranked = ordered_ranks(ranked.withColumnRenamed("rank", "before"), [c, "before"], "rank").drop("before")
    return ranked.select("rank", "sid", "pos", "sym")


def sort_ranges(listed: DataFrame, engine: str = "catalyst", bits: int = 62) -> DataFrame:
    if engine == "catalyst":
        return by_catalyst(listed)
    if engine in ("lsd", "index", "merge"):
        return by_arrow(listed, engine, bits)
    raise ValueError(engine)
