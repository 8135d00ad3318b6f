"""String collections and their suffixes.

A collection is (sid, s) with unique ids whose order breaks ties: every string
ends with an end marker of its own, below all symbols, and those of smaller ids
are smaller. Markers are never stored; a text may hold any character but U+0000.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blockbwt.storage import materialise

DNA = tuple("ACGT")
END = "\u0000"
EXPLICIT_LIMIT = 8 << 30


@dataclass
class StringCollection:
    """df: (sid long, s string). alphabet: its symbols in order, or None to be found by a scan."""

    df: DataFrame
    alphabet: tuple[str, ...] | None = None
    _longest: int | None = field(default=None, repr=False)

    @classmethod
    def of(cls, df: DataFrame, sid: str = "sid", s: str = "s", alphabet=None, nulls: str = "drop") -> StringCollection:
        if nulls not in ("drop", "empty", "reject"):
            raise ValueError(nulls)
        rows = df.select(F.col(sid).cast("long").alias("sid"), F.col(s).alias("s"))
        if nulls == "drop":
            rows = rows.where("sid is not null and s is not null")
        elif nulls == "empty":
            rows = rows.where("sid is not null").select("sid", F.coalesce("s", F.lit("")).alias("s"))
        elif not rows.where("sid is null or s is null").isEmpty():
            raise ValueError("null id or string")
        return cls(rows, tuple(alphabet) if alphabet else None)

    def symbols(self) -> tuple[str, ...]:
        """The alphabet, by code point; one scan where it isn't given, a row for each symbol to the driver."""
        if self.alphabet is None:
            each = self.df.select(F.explode(F.array_distinct(F.split("s", ""))).alias("c")).distinct()
            self.alphabet = tuple(sorted((x.c for x in each.where("c <> ''").collect()), key=lambda c: c.encode()))
            if END in self.alphabet:
                raise ValueError("a string holds U+0000")
        return self.alphabet

    def staged(self) -> StringCollection:
        """The same strings as a written table: what is scanned several times is derived once."""
        return StringCollection(materialise(self.df, "strings"), self.alphabet, self._longest)

    def longest(self) -> int:
        if self._longest is None:
            self._longest = self.df.agg(F.max(F.length("s"))).first()[0] or 0
        return self._longest

    def check(self) -> dict[str, int]:
        """Counts of what the definition forbids; all zero in a sound collection."""
        bad = ~F.col("s").rlike("^[" + "".join("\\" + c if c in r"\]^-[" else c for c in self.symbols()) + "]*$") if self.alphabet else F.lit(False)
        row = self.df.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("sid").alias("ids"), F.count_if(F.contains("s", F.lit(END))).alias("markers"), F.count_if(bad).alias("foreign")).first()
        return {"repeated_ids": row.n - row.ids, "markers": row.markers, "foreign": row.foreign}

    def restrict(self, policy: str) -> StringCollection:
        """Strings with symbols outside the alphabet: `reject`, `drop` them, or `extend` the alphabet."""
        foreign = F.length(F.translate("s", "".join(self.symbols()), "")) > 0
        if policy == "drop":
            return StringCollection(self.df.where(~foreign), self.alphabet)
        if policy == "extend":
            return StringCollection(self.df)
        if not self.df.where(foreign).isEmpty():
            raise ValueError("a string holds a symbol outside the alphabet")
        return self


def ordered_ranks(df: DataFrame, order: list, name: str = "rank") -> DataFrame:
    """df with its place from 0 in a total order: ranges are sorted apart, and their sizes say where each begins.

    The ranged rows are written once, since the sample behind the ranges mustn't
    be drawn twice; the driver gets a row for each range.
    """
    ranged = materialise(df.repartitionByRange(*order).withColumn("_range", F.spark_partition_id()), "ranged")
    sizes = sorted(tuple(x) for x in ranged.groupBy("_range").count().collect())
    starts, at = [], 0
    for r, n in sizes:
        starts.append((r, at))
        at += n
    begins = df.sparkSession.createDataFrame(starts, "_range int, _start long")
    place = F.row_number().over(Window.partitionBy("_range").orderBy(*order)) - 1
    return ranged.join(F.broadcast(begins), "_range").withColumn(name, place + F.col("_start")).drop("_range", "_start")


def assign_ids(df: DataFrame, order: list, s: str) -> DataFrame:
    """(sid, s): dense ids in the given order."""
    return ordered_ranks(df, order, "sid").select("sid", F.col(s).alias("s"))


def positions(low: Column | int = 0) -> Column:
    """The places of a string's suffixes, the empty one included."""
    low = F.lit(low) if isinstance(low, int) else low
    return F.sequence(low, F.length("s"))


def suffixes(coll: StringCollection) -> DataFrame:
    """(sid, s, pos): a row for each suffix; nothing moves."""
    return coll.df.select("sid", "s", F.explode(positions()).alias("pos"))


def previous(s: Column | str = "s", pos: Column | str = "pos", end: str | None = None) -> Column:
    """The symbol before a suffix; `end` (null by default) before a whole string."""
    s, pos = (F.col(x) if isinstance(x, str) else x for x in (s, pos))
    return F.when(pos > 0, F.substring(s, pos, F.lit(1))).otherwise(F.lit(end))


def explicit_suffixes(coll: StringCollection, limit: int = EXPLICIT_LIMIT) -> DataFrame:
    """(sid, pos, suffix), refused where their texts would take more than `limit` bytes at a byte a symbol."""
    size = coll.df.agg(F.sum(F.length("s").cast("double") * (F.length("s") + 1) / 2)).first()[0] or 0
    if size > limit:
        raise ValueError(f"explicit suffixes of {size:.3g} symbols; the limit is {limit}")
    return suffixes(coll).select("sid", "pos", F.expr("substring(s, pos + 1)").alias("suffix"))


def concat_offsets(coll: StringCollection) -> DataFrame:
    """(sid, start, len): where each string begins in the concatenation, its end marker counted."""
    lens = coll.df.select("sid", (F.length("s") + 1).cast("long").alias("len"))
    ranged = materialise(lens.repartitionByRange("sid").withColumn("_range", F.spark_partition_id()), "lengths")
    starts, at = [], 0
    for r, n in sorted(tuple(x) for x in ranged.groupBy("_range").agg(F.sum("len")).collect()):
        starts.append((r, at))
        at += n
    begins = coll.df.sparkSession.createDataFrame(starts, "_range int, _start long")
    run = F.sum("len").over(Window.partitionBy("_range").orderBy("sid").rowsBetween(Window.unboundedPreceding, -1))
    return ranged.join(F.broadcast(begins), "_range").select("sid", (F.coalesce(run, F.lit(0)) + F.col("_start")).alias("start"), "len")


def locate_offset(offsets: DataFrame, places: DataFrame, bin_bits: int = 12) -> DataFrame:
    """places (goff) -> (goff, sid, pos): an equi-join on bins of offsets, and a residual filter."""
    size = 1 << bin_bits
    spans = offsets.select("sid", "start", "len", F.explode(F.sequence(F.floor(F.col("start") / size), F.floor((F.col("start") + F.col("len") - 1) / size))).alias("bin"))
    asked = places.select("goff", F.floor(F.col("goff") / size).alias("bin"))
    return asked.join(spans, "bin").where("goff >= start and goff < start + len").select("goff", "sid", (F.col("goff") - F.col("start")).cast("int").alias("pos"))
