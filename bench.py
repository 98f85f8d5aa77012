"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

--sweep also measures the experiment workloads (length, count and threshold sweeps) and the join
methods' ratios, one line each, on stderr.
"""

from __future__ import annotations

import json
import os
import sys
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")

JOINS = ("a", "b", "c", "d")


def session():
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "6g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def run(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def timed(make, repeats: int = 1) -> float:
    """Seconds of a run after a first one that warms up."""
    run(make())
    began = time.time()
    for _ in range(repeats):
        run(make())
    return (time.time() - began) / repeats


def headline(spark) -> dict[str, float]:
    from cadenza.functions import transforms as T
    from cadenza.operators import joins, range_search
    from cadenza.plans.workloads import index_of, raw

    began = time.time()
    index = index_of(spark, SF_DIR, "supplier_walk")
    seconds = {"index_build": time.time() - began}
    t, eps, q = T.moving_average(index.n, 20), 1.6, raw(spark, SF_DIR, "supplier_walk", 3)
    methods = {
        "join_a_full_scan": lambda: joins.scan_join(index, t, eps, False),
        "join_b_stopping_scan": lambda: joins.scan_join(index, t, eps, True),
        "join_c_index_no_transform": lambda: joins.index_nested_loop(index, None, eps),
        "join_d_index_transform": lambda: joins.index_nested_loop(index, t, eps),
        "join_tree": lambda: joins.self_join(index, t, eps),
        "join_grid": lambda: joins.grid_join(index, index, t, t, eps, True),
        "range_index": lambda: range_search.search(index, q, t, 4.0, True),
        "range_index_identity": lambda: range_search.search(index, q, T.identity(index.n), 4.0),
        "range_index_plain": lambda: range_search.search(index, q, None, 4.0),
        "range_stopping_scan": lambda: range_search.scan_abandon(index, q, t, 4.0, True),
    }
    return seconds | {k: timed(f) for k, f in methods.items()} | many_walks(spark)


def many_walks(spark) -> dict[str, float]:
    """A saved index over all walks there are (20,000 at sf0.1) against scans of the same records: few answers."""
    import shutil
    import tempfile

    from cadenza.functions import transforms as T
    from cadenza.operators import kindex, range_search
    from cadenza.sources.series import random_walk

    folder = tempfile.mkdtemp(prefix="cadenza-bench-")
    try:
        began = time.time()
        kindex.build(random_walk(spark, SF_DIR, 128, 1 << 30)).save(f"{folder}/index")
        seconds = {"walks_build_and_save": time.time() - began}
        index = kindex.open_index(spark, f"{folder}/index")
        q, t = random_walk(spark, SF_DIR, 128, 1).one(0), T.moving_average(128, 20)
        ways = {
            "walks_range_index": lambda: range_search.search(index, q, t, 3.0, True),
            "walks_range_index_identity": lambda: range_search.search(index, q, T.identity(128), 6.0),
            "walks_range_index_plain": lambda: range_search.search(index, q, None, 6.0),
            "walks_range_stopping_scan": lambda: range_search.scan_abandon(index, q, t, 3.0, True),
            "walks_range_full_scan": lambda: range_search.scan_naive(index, q, t, 3.0, True),
        }
        return seconds | {k: timed(f, 3) for k, f in ways.items()}
    finally:
        shutil.rmtree(folder, ignore_errors=True)


def sweep(spark) -> None:
    from cadenza.functions import transforms as T
    from cadenza.operators import kindex, measures, range_search
    from cadenza.plans.workloads import index_of, raw
    from cadenza.sources.series import random_walk

    def tell(**x) -> None:
        print(json.dumps(x), file=sys.stderr, flush=True)

    for n, count in [(n, 1000) for n in (64, 128, 256, 512, 1024)] + [(128, c) for c in (500, 2000, 4000, 8000, 12_000)]:
        index = kindex.build(random_walk(spark, SF_DIR, n, count))
        q, eps = random_walk(spark, SF_DIR, n, 1).one(0), 0.3 * n**0.5
        mavg = T.moving_average(n, 20)
        ways = {"plain": lambda: range_search.search(index, q, None, eps), "identity": lambda: range_search.search(index, q, T.identity(n), eps), "mavg20": lambda: range_search.search(index, q, mavg, eps, True), "stopping scan": lambda: range_search.scan_abandon(index, q, mavg, eps, True)}
        reached = {k: sum(r.reached for r in measures.nodes_reached(index, q, t, eps).collect()) for k, t in (("plain", None), ("identity", T.identity(n)))}
        tell(length=n, count=count, seconds={k: round(timed(f), 3) for k, f in ways.items()}, nodes=reached, answers=ways["mavg20"]().count())
    index = index_of(spark, SF_DIR, "supplier_walk")
    q, t = raw(spark, SF_DIR, "supplier_walk", 3), T.moving_average(index.n, 20)
    for wanted in (1, 10, 50, 100, 200, 300, 500, 800):
        eps = measures.eps_for_answers(index, q, t, wanted, True)
        ways = {"index": lambda: range_search.search(index, q, t, eps, True), "stopping scan": lambda: range_search.scan_abandon(index, q, t, eps, True)}
        counted = measures.candidate_counts(index, q, t, eps, True).first()
        tell(answers=wanted, eps=round(eps, 3), candidates=counted.candidates, seconds={k: round(timed(f), 3) for k, f in ways.items()})


def main() -> None:
    spark = session()
    seconds = headline(spark)
    if "--sweep" in sys.argv:
        sweep(spark)
    from cadenza.operators import joins

    ratios = joins.speedups({k[5]: v for k, v in seconds.items() if k[:5] == "join_" and k[6:7] == "_"})
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": {k: round(v, 3) for k, v in seconds.items()}, "ratios": {k: round(v, 2) for k, v in ratios.items()}, "sf": os.path.basename(SF_DIR.rstrip("/"))}))


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
