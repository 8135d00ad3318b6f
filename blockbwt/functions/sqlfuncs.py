"""The engine's functions for SQL and DataFrames, each with its native twin."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def reverse_complement(s):
    return F.translate(F.reverse(s), "ACGT", "TGCA")


@F.pandas_udf(T.StringType())
def revcomp(s: pd.Series) -> pd.Series:
    return s.str[::-1].str.translate(str.maketrans("ACGT", "TGCA"))


@F.pandas_udf(T.StringType())
def bwt_prefix(s: pd.Series, pos: pd.Series, depth: pd.Series) -> pd.Series:
    return pd.Series([x[p : p + d].ljust(d, "\0") for x, p, d in zip(s, pos, depth)])


@F.pandas_udf(T.StringType())
def bwt_prev(s: pd.Series, pos: pd.Series) -> pd.Series:
    return pd.Series([x[p - 1] if p else None for x, p in zip(s, pos)])


@F.pandas_udf(T.StringType())
def bwt_of_group(sid: pd.Series, s: pd.Series) -> str:
    """The transform of a small group's strings; an aggregate."""
    rows = sorted((x[p:].encode(), i, x[p - 1] if p else "$") for i, x in zip(sid, s) for p in range(len(x) + 1))
    return "".join(c for _, _, c in rows)


@F.pandas_udf(T.LongType())
def run_count(s: pd.Series) -> pd.Series:
    return s.map(lambda x: sum(a != b for a, b in zip(x, x[1:])) + bool(x))


@F.udtf(returnType=T.StructType([T.StructField(n, t) for n, t in [("pos", T.IntegerType()), ("suffix", T.StringType())]]))
class SuffixesOf:
    def eval(self, s: str):
        for p in range(len(s) + 1):
            yield p, s[p:]


@F.udtf(returnType=T.StructType([T.StructField(n, t) for n, t in [("pos", T.IntegerType()), ("kmer", T.StringType())]]))
class KmersOf:
    def eval(self, s: str, k: int):
        for p in range(len(s) - k + 1):
            yield p, s[p : p + k]


@F.udtf(returnType=T.StructType([T.StructField(n, t) for n, t in [("header", T.StringType()), ("s", T.StringType())]]))
class FastaRecords:
    def eval(self, text: str):
        for record in (text or "").split(">")[1:]:
            head, _, body = record.partition("\n")
            yield head.strip(), "".join(body.split())


def run_count_native(s):
    chars = F.split(s, "")
    pairs = F.arrays_zip(F.slice(chars, F.lit(1), F.greatest(F.length(s) - 1, F.lit(0))).alias("a"), F.slice(chars, F.lit(2), F.length(s)).alias("b"))
    return (F.size(F.filter(pairs, lambda x: x["a"] != x["b"])) + (F.length(s) > 0).cast("int")).cast("long")


def register(spark: SparkSession) -> None:
    for name, f in (("revcomp", revcomp), ("bwt_prefix", bwt_prefix), ("bwt_prev", bwt_prev), ("bwt_of_group", bwt_of_group), ("run_count", run_count)):
        spark.udf.register(name, f)
    for name, t in (("suffixes_of", SuffixesOf), ("kmers_of", KmersOf), ("fasta_records", FastaRecords)):
        spark.udtf.register(name, t)


__all__ = ["FastaRecords", "KmersOf", "SuffixesOf", "bwt_of_group", "bwt_prefix", "bwt_prev", "register", "revcomp", "reverse_complement", "run_count", "run_count_native"]
