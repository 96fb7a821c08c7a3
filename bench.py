"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line.

Every variant starts from rows spread over the lanes: mean of BENCH_REPEATS runs (4 by default) after one warm-up,
each a whole sort (sample, route, merge) written to the no-op sink.
"""

from __future__ import annotations

import json
import os
import time
from collections.abc import Callable
from pathlib import Path
from statistics import mean

from pyspark.sql import SparkSession, Window
from pyspark.sql import functions as F

from evenlane.functions.spec import SortSpec
from evenlane.operators import baselines, measure
from evenlane.operators.layout import Lanes
from evenlane.operators.sorts import classic_random_sort, local_sort, presorted_random_sort, regular_sort
from evenlane.plans import calibrate
from evenlane.plans.catalogue_relational import QUERIES as RELATIONAL
from evenlane.staging import stage

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 8))
REPEATS = int(os.environ.get("BENCH_REPEATS", "4"))
P = 8


def session() -> SparkSession:
    os.environ.setdefault("PYTHONPATH", str(Path(__file__).resolve().parent))
    s = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", str(CPUS)).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def sink(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def timed(f: Callable[[], None]) -> float:
    f()
    out = []
    for _ in range(REPEATS):
        t = time.perf_counter()
        f()
        out.append(time.perf_counter() - t)
    return mean(out)


def main() -> None:
    spark = session()
    # the input lies evenly spread over the lanes, in memory, before the clock starts, as the sorts assume; keys are 32-bit integers
    cents = F.round(F.col("l_extendedprice") * 100).cast("int").alias("cents")
    lineitem = stage(spark.read.parquet(f"{SF}/lineitem.parquet").select("l_orderkey", "l_partkey", "l_extendedprice", "l_returnflag", cents).repartition(P), "bench").persist()
    n = lineitem.count()
    one = lineitem.coalesce(1)
    spec, lanes = SortSpec.of("cents"), Lanes(P, layout="inplace")

    def local(how: str, f: Callable[[], None]) -> Callable[[], None]:
        def run() -> None:
            with local_sort(spark, how):
                f()

        return run

    def sorts(sort, how: str, key: SortSpec = spec, **options) -> Callable[[], None]:
        return local(how, lambda: sink(sort(lineitem, key, lanes, local=how, **options).by_keys))

    flag = SortSpec.of("l_returnflag")
    runs: dict[str, Callable[[], None]] = {
        "regular_radix": sorts(regular_sort, "radix"), "regular_cmp": sorts(regular_sort, "cmp"),
        "random_radix": sorts(presorted_random_sort, "radix"), "random_cmp": sorts(presorted_random_sort, "cmp"),
        "classic_random": lambda: sink(classic_random_sort(lineitem, spec, lanes).by_keys),
        "regular_stable": lambda: sink(regular_sort(lineitem, spec, lanes).df),
        "regular_duplicates": sorts(regular_sort, "radix", flag), "regular_duplicates_off": sorts(regular_sort, "radix", flag, dup=False),
        "plain_regular": lambda: sink(baselines.plain_regular(lineitem, spec, lanes).by_keys),
        "tag_all": lambda: sink(baselines.tag_all(lineitem, spec, lanes).by_keys),
        "two_round_regular": lambda: sink(baselines.two_round_regular(lineitem, spec, lanes).by_keys),
        "two_round_random": lambda: sink(baselines.two_round_random(lineitem, spec, lanes).by_keys),
        "range_exchange": lambda: sink(lineitem.orderBy("cents")),
        "sequential_radix": local("radix", lambda: sink(one.sortWithinPartitions("cents"))), "sequential_cmp": local("cmp", lambda: sink(one.sortWithinPartitions("cents"))),
        "builtin_dedup": lambda: sink(spark.read.parquet(f"{SF}/lineitem.parquet").dropDuplicates(["l_partkey"])),
        "builtin_rank": lambda: sink(spark.read.parquet(f"{SF}/lineitem.parquet").withColumn("rank", F.rank().over(Window.orderBy("l_shipdate")))),
    }
    for name in ("fenced_merge_join", "global_rank", "exact_median", "dedup_first_by_key"):
        runs[name] = lambda q=RELATIONAL[name]: sink(q(spark, SF))
    queries = {name: round(timed(f), 4) for name, f in runs.items()}
    balance = {}
    for label, key in (("price", "l_extendedprice"), ("returnflag", "l_returnflag"), ("constant", "1")):
        for method, sort in (("regular", regular_sort), ("random", presorted_random_sort)):
            balance[f"{method}_{label}"] = round(measure.imbalance(sort(lineitem, SortSpec.of(key), lanes).bucket_sizes()), 4)
    shares = {}
    for method in ("regular", "presorted_random", "two_round_regular"):
        _, phases = calibrate.profile(method, lineitem, spec, P)
        total = sum(phases.values())
        shares[method] = {k: round(100 * v / total, 1) for k, v in phases.items()}
    print(json.dumps({
        "metric": "total seconds of the headline queries, each a mean of its runs", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": SF, "rows": n, "lanes": P, "cpus": CPUS, "repeats": REPEATS,
        "imbalance": balance, "phase_pct": shares, "rows_per_s": {k: round(n / queries[k]) for k in ("regular_radix", "random_radix", "range_exchange", "sequential_radix")},
    }))
    spark.stop()


if __name__ == "__main__":
    main()
