"""Headline timings: one JSON line. BENCH_SF_DIR names the tables, BENCH_CPUS the local threads."""

from __future__ import annotations

import json
import os
import sys
import time

import numpy as np
from pyspark.sql import SparkSession, functions as F

from rankfit import catalog
from rankfit.config import AcsConfig
from rankfit.operators import kernel
from rankfit.operators.baselines import BASELINES
from rankfit.plans import answers, build, exact
from rankfit.sources import workloads
from rankfit.sources.io import table

FOLDER = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def ranks_100k(spark: SparkSession, folder: str):
    lineitem = table(spark, folder, "lineitem")
    xs = spark.range(100_000).select((F.col("id") * 1.05).alias("x"))
    return answers.query_ranks(build.build_summary(lineitem, "l_extendedprice"), xs).agg(F.sum("est_rank"))


def merged_chunks(spark: SparkSession, folder: str):
    parts = build.partials(table(spark, folder, "lineitem").repartition(64), "l_extendedprice")
    return build.finish_summaries(build.merge_summaries(parts, fanout=8, levels=2)).drop("summary")


HEADLINE = {
    "build_price": lambda s, d: build.build_summary(table(s, d, "lineitem"), "l_extendedprice").drop("summary"),
    "build_price_no_filter": lambda s, d: build.build_summary(table(s, d, "lineitem"), "l_extendedprice", cfg=AcsConfig(filter="none")).drop("summary"),
    "build_by_flag_status": lambda s, d: build.build_summary(table(s, d, "lineitem"), "l_extendedprice", ["l_returnflag", "l_linestatus"]).drop("summary"),
    "build_heavy_quantity": lambda s, d: build.build_summary(table(s, d, "lineitem"), "l_quantity").drop("summary"),
    "build_bell": lambda s, d: build.build_summary(workloads.bell(s, d), "v").drop("summary"),
    "merge_64_chunks": merged_chunks,
    "ranks_100k": ranks_100k,
    "rank_error_uniform": catalog.QUERIES["stream_rank_error_uniform"],
    "rank_error_power_like": catalog.QUERIES["stream_rank_error_power_like"],
    "rollup_flag_status": catalog.QUERIES["rollup_flag_status_counts"],
    "rolling_24h": catalog.QUERIES["rolling_24h_n_min_max"],
    "exact_value_ranks": lambda s, d: exact.value_ranks(table(s, d, "lineitem"), "l_extendedprice").agg(F.max("cum")),
}


def kernels() -> dict[str, float]:
    """µs for each item, query and merge on normal data; no Spark."""
    random = np.random.default_rng(1)
    x = random.normal(size=2_000_000)
    out = {}

    def timed(name: str, work, per: int):
        best = min(_seconds(work) for _ in range(3))
        out[name] = round(best / per * 1e6, 4)

    timed("update_us_k100", lambda: kernel.summarize(x, AcsConfig(k=100, filter="none")), len(x))
    timed("update_us_k100_filter", lambda: kernel.summarize(x, AcsConfig(k=100)), len(x))
    timed("update_us_k400", lambda: kernel.summarize(x, AcsConfig(k=400, filter="none")), len(x))
    heavy = np.concatenate([x[:1_000_000], random.integers(0, 42, 1_000_000).astype(float)])
    timed("update_us_heavy_filter", lambda: kernel.summarize(heavy, AcsConfig(k=100)), len(x))
    timed("update_us_heavy_none", lambda: kernel.summarize(heavy, AcsConfig(k=100, filter="none")), len(x))
    done = kernel.Answers(kernel.summarize(x, AcsConfig(k=100)))
    asked = np.sort(x)[:: len(x) // 100_000]
    timed("query_us_100k", lambda: done.rank(asked), len(asked))
    for name, size in (("centroids", 190), ("compactor", 8), ("moments", 15)):
        timed(f"update_us_{name}", lambda k=BASELINES[name], s=size: k(s).update(x), len(x))
        other = BASELINES[name](size).update(x[:200_000])
        timed(f"query_us_{name}", lambda o=other: o.rank(asked[::10]), len(asked[::10]))
    chunks = [kernel.summarize(p, AcsConfig(k=100), whole=False) for p in np.array_split(x, 257)]
    from rankfit.operators import codec

    raws = [codec.encode(c) for c in chunks]
    states = [[codec.decode(r) for r in raws] for _ in range(3)]
    timed("merge_us", lambda: build.balanced(states.pop()), 256)
    return out


def _seconds(work) -> float:
    began = time.perf_counter()
    work()
    return time.perf_counter() - began


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("rankfit-bench").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    found = {}
    for name, run in HEADLINE.items():
        run(spark, FOLDER).collect()  # compiles code and starts workers
        found[name] = round(_seconds(lambda r=run: r(spark, FOLDER).collect()), 3)
        print(name, found[name], file=sys.stderr, flush=True)
    spark.stop()
    print(json.dumps({"metric": "headline_total", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "kernel_us": kernels(), "sf": os.path.basename(FOLDER.rstrip("/"))}))


if __name__ == "__main__":
    main()
