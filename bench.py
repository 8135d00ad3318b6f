"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one line of JSON.

Seconds of each query, its rows going nowhere; then the experiments of
blockbwt/plans/experiments.py on the reads of $BENCH_SHAPES_DIR (the smallest
tables), begun as long as $BENCH_SHAPES_SECONDS (120) aren't over; BENCH_SHAPES=0
leaves them out.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).parent))

from blockbwt import tables as T  # noqa: E402
from blockbwt.functions.measures import peak_memory, run_to_noop  # noqa: E402
from blockbwt.plans import catalogue, experiments  # noqa: E402
from blockbwt.session import local_session  # noqa: E402

HEADLINE = ("read_collection_dna", "size_table_reads_l8", "bwt_reads_blocksort", "bwt_page_urls", "bwt_part_names", "kmer_counts_k8", "contained_reads")


def cores(sf_dir: str, counts=(1, 2, 4, 8)) -> dict[str, float]:
    """Seconds of the flagship by number of cores, each in a process of its own."""
    code = "import sys, time; sys.path.insert(0, sys.argv[1])\nfrom blockbwt.session import local_session\nfrom blockbwt.functions.measures import run_to_noop\nfrom blockbwt.plans import catalogue\nspark = local_session(sys.argv[2], 16, '4g'); spark.sparkContext.setLogLevel('ERROR')\nf = catalogue.QUERIES['bwt_reads_blocksort']\nrun_to_noop(f(spark, sys.argv[3])); t = time.perf_counter(); run_to_noop(f(spark, sys.argv[3])); print(round(time.perf_counter() - t, 3))"
    out = {}
    for n in counts:
        done = subprocess.run([sys.executable, "-c", code, str(Path(__file__).parent), str(n), sf_dir], capture_output=True, text=True)
        out[str(n)] = float(done.stdout.split()[-1]) if done.returncode == 0 else None
    return out


def throughput(times: dict[str, float], sf_dir: str, spark) -> dict[str, float]:
    """Million bases a second of the flagship, and the published figures beside it."""
    bases = T.reads(spark, sf_dir).df.count() * 100
    return {"mbase_s": round(bases / 1e6 / times["bwt_reads_blocksort"], 3), "published_block_sort_mbase_s": 14.5, "published_baseline_mbase_s": 2.13}


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(os.environ.get("BENCH_CPUS", "8"), 16, os.environ.get("BENCH_MEMORY", "16g"))
    spark.sparkContext.setLogLevel("ERROR")
    run_to_noop(catalogue.QUERIES["bwt_worked_example"](spark, sf_dir))  # starts and compiles
    times = {}
    for name in HEADLINE:
        began = time.perf_counter()
        run_to_noop(catalogue.QUERIES[name](spark, sf_dir))
        times[name] = round(time.perf_counter() - began, 3)
    small = os.environ.get("BENCH_SHAPES_DIR", "/root/testdata/sf0.001")
    memory = peak_memory(spark)
    found = {}
    if os.environ.get("BENCH_SHAPES", "1") != "0":
        found = experiments.run(spark, small, float(os.environ.get("BENCH_SHAPES_SECONDS", "120")))
        if not found["left out"]:
            found["cores"] = cores(small)
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf_dir.rsplit("sf", 1)[-1], "throughput": throughput(times, sf_dir, spark), "shapes": found.pop("shapes", {}), "experiments": found, "memory": memory}))


if __name__ == "__main__":
    main()
