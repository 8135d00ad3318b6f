"""The experiments: what the block-sort method costs against the others, and how that moves with each parameter.

Every function times whole builds whose rows go nowhere and returns plain
numbers; `shapes` says which of the published behaviours they show.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockbwt import tables as T
from blockbwt.functions import measures
from blockbwt.operators import baselines, construct
from blockbwt.operators.collection import StringCollection
from blockbwt.sources import fasta
from blockbwt.storage import fresh_path

from .planner import Budget, plan_summary

#: Lengths at equal bases; neighbours of the shortest reads make the longer ones.
LENGTHS = (5, 10, 20)


def _seconds(build) -> float:
    began = time.perf_counter()
    measures.run_to_noop(build())
    return round(time.perf_counter() - began, 3)


def _rows(coll: StringCollection) -> int:
    return coll.df.agg(F.sum(F.length("s") + 1)).first()[0] or 1


def _budget(rows: int, **options) -> Budget:
    return Budget(**({"sort_rows": max(1000, rows // 12), "ell": 4} | options))


def staged_reads(spark: SparkSession, sf_dir: str, lengths=LENGTHS) -> dict[int, StringCollection]:
    return {n: T.reads(spark, sf_dir, lengths[0], join=n // lengths[0]).staged() if n > lengths[0] else _whole_groups(T.reads(spark, sf_dir, lengths[0])).staged() for n in lengths}


def _whole_groups(coll: StringCollection) -> StringCollection:
    """The shortest reads without the incomplete group of four that the longer ones leave out, so that bases are equal."""
    counts = coll.df.groupBy(F.floor(F.col("sid") / T.READ_IDS).alias("doc")).agg((F.floor(F.count(F.lit(1)) / 4) * 4).alias("n"))
    keyed = coll.df.withColumn("doc", F.floor(F.col("sid") / T.READ_IDS)).join(counts, "doc").where(F.col("sid") % T.READ_IDS < F.col("n"))
    return StringCollection(keyed.select("sid", "s"), coll.alphabet, coll._longest)


def methods(coll: StringCollection, which=("block sort", "column insertion", "column insertion, delta", "partition and merge", "rank doubling")) -> dict[str, float]:
    """Seconds of each method on the same strings."""
    b = _budget(_rows(coll))
    builds = {
        "block sort": lambda: construct.bwt_build(coll, b),
        "column insertion": lambda: baselines.bwt_column_insertion(coll),
        "column insertion, delta": lambda: baselines.bwt_column_insertion(coll, "delta"),
        "partition and merge": lambda: baselines.bwt_partition_merge(coll),
        "rank doubling": lambda: baselines.bwt_rank_doubling(coll),
    }
    return {k: _seconds(builds[k]) for k in which}


def round_sweep(coll: StringCollection, parts=(1, 2, 4, 8)) -> dict[str, dict[str, float]]:
    """m2 as M, M/2, M/4, ...: rounds, scans and seconds."""
    out, rows = {}, _rows(coll)
    for k in parts:
        b = _budget(rows, sort_rows=max(1, rows // 32), round_rows=None if k == 1 else rows // k + 1)
        plan = construct.make_plan(coll, b)
        summary = plan_summary(plan, b.sort_rows).first()
        out[f"M/{k}"] = {"rounds": summary.rounds, "scans": summary.scans, "seconds": _seconds(lambda b=b: construct.bwt_build(coll, b))}
    return out


def node_sweep(spark: SparkSession, sf_dir: str, coll: StringCollection, nodes=(1, 2, 3, 4)) -> dict[str, dict[str, float]]:
    """Each node's range as a job of its own: nodes would run at once, so the longest counts. `loading` is the same for any number of them."""
    loading = _seconds(lambda: T.reads(spark, sf_dir).df)
    out, rows = {}, _rows(coll)
    for n in nodes:
        b = _budget(rows, nodes=n, sort_rows=max(1, rows // 24))
        plan = construct.make_plan(coll, b)
        each = [_seconds(lambda r=r, b=b, plan=plan: construct.listed_rounds(coll, plan, b, F.col("node") == r)) for r in range(n)]
        out[str(n)] = {"longest": max(each), "with_loading": round(max(each) + loading, 3), "sum": round(sum(each), 3)}
    out["loading"] = {"seconds": loading}
    return out


def length_series(colls: dict[int, StringCollection], which=("block sort", "column insertion")) -> dict[str, dict[str, float]]:
    """Seconds by method and length at equal bases, and the growth over the shortest."""
    out: dict[str, dict[str, float]] = {k: {} for k in which}
    for n, coll in colls.items():
        for k, t in methods(coll, which).items():
            out[k][str(n)] = t
    return out


def growth_in_bases(coll: StringCollection, parts=(4, 2, 1)) -> dict[str, dict[str, float]]:
    """A quarter, half and all of the reads."""
    out = {}
    for k in parts:
        some = StringCollection(coll.df.where(F.pmod(F.xxhash64("sid"), F.lit(k)) == 0), coll.alphabet, coll._longest).staged()
        rows = _rows(some)
        out[f"1/{k}"] = {"suffixes": rows, "seconds": _seconds(lambda some=some, rows=rows: construct.bwt_build(some, _budget(rows)))}
    return out


def loading(spark: SparkSession, sf_dir: str) -> dict[str, float]:
    """Seconds to read the same strings as Parquet, FASTA, and FASTA in gzip."""
    rows = T.reads(spark, sf_dir).df
    plain, packed, split, parquet = (fresh_path(spark, x) for x in ("fasta", "fasta-gz", "fasta-bz2", "strings"))
    fasta.write_fasta(rows, plain, "sid", "s")
    fasta.write_fasta(rows, packed, "sid", "s", compression="gzip")
    fasta.write_fasta(rows, split, "sid", "s", compression="bzip2")
    rows.write.parquet(parquet)
    return {
        "parquet": _seconds(lambda: spark.read.parquet(parquet)),
        "fasta": _seconds(lambda: fasta.read_fasta_any(spark, plain)),
        "fasta, gzip": _seconds(lambda: fasta.read_fasta_any(spark, packed)),
        "fasta, bzip2": _seconds(lambda: fasta.read_fasta_any(spark, split)),
    }


def prefix_and_capacity(coll: StringCollection) -> dict[str, float]:
    """Seconds by the first prefix's length and a task's capacity."""
    rows = _rows(coll)
    out = {f"l={ell}": _seconds(lambda ell=ell: construct.bwt_build(coll, _budget(rows, ell=ell))) for ell in (2, 4, 8)}
    return out | {f"m1=M/{k}": _seconds(lambda k=k: construct.bwt_build(coll, _budget(rows, sort_rows=max(1, rows // k)))) for k in (6, 24, 96)}


def engines(coll: StringCollection) -> dict[str, float]:
    """Seconds by engine, encoding and digits of a pass."""
    rows = _rows(coll)
    kinds = {"catalyst, bits": {}, "catalyst, radix": {"encoding": "radix"}, "catalyst, digits": {"encoding": "digits"}, "catalyst, bytes": {"encoding": "utf8"}, "words listed later": {"listing": "position"}, "index": {"engine": "index"}, "merge": {"engine": "merge"}, "word passes": {"engine": "lsd"}, "16-bit passes": {"engine": "lsd", "digit_bits": 16}, "8-bit passes": {"engine": "lsd", "digit_bits": 8}}
    return {k: _seconds(lambda o=o: construct.bwt_build(coll, _budget(rows, **o))) for k, o in kinds.items()}


def phases(spark: SparkSession, sf_dir: str) -> dict[str, float]:
    """Seconds of loading, sizes and plan, and listing, sorting and writing together, and the bytes each wrote or shuffled."""
    times: dict[str, float] = {}
    before = measures.io_bytes(spark)
    with measures.timed(times, "loading"):
        coll = T.reads(spark, sf_dir).staged()
    with measures.timed(times, "sizes and plan"):
        b = _budget(_rows(coll))
        plan = construct.make_plan(coll, b)
    with measures.timed(times, "listing, sorting, writing"):
        construct.bwt_build(coll, b, plan).write.parquet(fresh_path(spark, "out"))
    after = measures.io_bytes(spark)
    return {k: round(v, 3) for k, v in times.items()} | {f"{k}_mb": round((after[k] - before[k]) / 1e6, 1) for k in after}


def shapes(found: dict) -> dict[str, bool]:
    """Which published behaviours the figures show."""
    length, rounds, nodes, bases = found["lengths"], found["rounds"], found["nodes"], found["bases"]
    keys = list(length["block sort"])
    gap = [length["column insertion"][k] / length["block sort"][k] for k in keys]
    spread = [int(n) * x["longest"] for n, x in nodes.items() if n != "loading"]
    small, large = bases["1/4"], bases["1/1"]
    most = max(x["rounds"] for x in rounds.values())
    slow = max(x["seconds"] for x in rounds.values()) / rounds["M/1"]["seconds"]
    return {
        "block sort beats column insertion": min(gap) > 1,
        "the gap widens with length": gap == sorted(gap),
        "smaller rounds cost less than their number": most > 1 and slow < most,
        "a node's share falls with nodes": nodes["4"]["longest"] < nodes["1"]["longest"] and max(spread) / min(spread) < 4,
        "time grows no faster than bases, but for a fifth": large["seconds"] / small["seconds"] < 1.2 * large["suffixes"] / small["suffixes"],
    }


def run(spark: SparkSession, small: str, limit: float = 300.0) -> dict:
    """All of them on the reads of one folder of tables, in this order as far as `limit` seconds go; the names of those left out are under `left out`."""
    began, found, left = time.perf_counter(), {}, []
    lengths = staged_reads(spark, small)
    coll = T.reads(spark, small).staged()
    _seconds(lambda: construct.bwt_build(coll, _budget(_rows(coll))))  # compiles
    others = ("column insertion, delta", "partition and merge", "rank doubling")
    each = {
        "bases": lambda: growth_in_bases(coll),
        "rounds": lambda: round_sweep(coll),
        "nodes": lambda: node_sweep(spark, small, coll),
        "lengths": lambda: length_series(lengths),
        "phases": lambda: phases(spark, small),
        "loading": lambda: loading(spark, small),
        "methods": lambda: {"length": LENGTHS[0], **{k: x[str(LENGTHS[0])] for k, x in found["lengths"].items()}, **methods(lengths[LENGTHS[0]], others)},
        "prefix and capacity": lambda: prefix_and_capacity(coll),
        "engines": lambda: engines(coll),
    }
    for name, f in each.items():
        if time.perf_counter() - began > limit:
            left.append(name)
        else:
            found[name] = f()
    if "lengths" in found:
        block, insertion = found["lengths"]["block sort"], found["lengths"]["column insertion"]
        found["ratio to the baseline"] = {k: round(insertion[k] / block[k], 2) for k in block} | {"published at 100": round(measures.PUBLISHED_BASELINE[0][1] / measures.PUBLISHED_NODES["included", 1][0], 2)}
    if {"lengths", "rounds", "nodes", "bases"} <= found.keys():
        found["shapes"] = shapes(found)
        found["speed-up by nodes"] = {n: round(found["nodes"]["1"]["longest"] / x["longest"], 2) for n, x in found["nodes"].items() if n != "loading"}
    return found | {"left out": left}
