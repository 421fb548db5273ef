"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Networks, parts and operands are prepared outside the clock, as stored networks would be; a query's time is the join itself.
``python bench.py --sweeps`` runs the experiment sweeps instead and prints one JSON line for each value; ``--parallel`` large distance joins in pools of
1 to 14, ``--bounds`` local against shared bounds over numbers of parts, ``--contrast`` parts by separation against parts by edge cut and by size; ``--cores`` runs large distance joins
on 2, 4 and 8 cores, each in a process of its own, and prints the share of the time on two.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession

from netjoin.functions.workspace import release_scratch
from netjoin.plans import catalog, workloads
from netjoin.plans.joins import closest_pairs, distance_join


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "8g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def clocked(run) -> float:
    start = time.time()
    run()
    return round(time.time() - start, 3)


def headline(spark: SparkSession, d: str) -> dict[str, float]:
    out: dict[str, float] = {}
    for name in ("urban", "interstate"):
        p = workloads.prepare(spark, d, name)
        p.r.count(), p.s.count()
        workloads.timed_pairs(p, 80)  # warm
        heavy = workloads.HEAVY[name]
        out[f"kcp_{name}"] = clocked(lambda: closest_pairs(p.net, p.r, p.s, 80, hierarchy=p.tree).count())
        out[f"kcp_{name}_per_level"] = clocked(lambda: closest_pairs(p.net, p.r, p.s, 80, hierarchy=p.tree, crossings="per_level").count())
        out[f"kcp_{name}_frontier"] = clocked(lambda: closest_pairs(p.net, p.r, p.s, 80, hierarchy=p.tree, engine="frontier").count())
        out[f"kcp_{name}_unpartitioned"] = clocked(lambda: closest_pairs(p.net, p.r, p.s, 80).count())
        out[f"dj_{name}_large"] = clocked(lambda: distance_join(p.net, p.r, p.s, heavy, hierarchy=p.tree).count())
        out[f"dj_{name}"] = clocked(lambda: distance_join(p.net, p.r, p.s, 400 if name == "urban" else 200, hierarchy=p.tree).count())
    p = workloads.prepare(spark, d, "urban")
    out["kcp_urban_pool_8"] = clocked(lambda: closest_pairs(p.net, p.r, p.s, 80, hierarchy=p.tree, schedule="pool", parallelism=8).count())
    for name in ("net_urban_edges", "net_interstate_edges", "rollup_pairs_by_region", "asof_position", "session_positions"):
        out[name] = clocked(lambda: catalog.queries()[name](spark, d).write.format("noop").mode("overwrite").save())
    release_scratch(spark)
    try:
        from netjoin.llm import entries
    except ModuleNotFoundError:
        return out
    for name in ("op1_exact_dedup", "op2_secrets", "op3_mixing", "op4_bpe", "op5_pii", "op6_quality", "op7_language", "op8_urls", "op9_warc", "op10_minhash"):
        out[name] = clocked(lambda: entries.queries()[name](spark, d).write.format("noop").mode("overwrite").save())
    return out


def cores_sweep(counts: tuple[int, ...] = (2, 4, 8)) -> None:
    first: dict[str, float] = {}
    for n in counts:
        got = subprocess.run([sys.executable, __file__, "--heavy"], env=os.environ | {"BENCH_CPUS": str(n)}, stdout=subprocess.PIPE, text=True, check=True)
        for line in filter(lambda x: x.startswith("{"), got.stdout.splitlines()):
            row = json.loads(line)
            base = first.setdefault(row["network"], row["seconds"])
            print(json.dumps(row | {"share": round(row["seconds"] / base, 3)}), flush=True)


def main() -> None:
    d = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    if "--cores" in sys.argv:
        return cores_sweep()
    spark = session()
    if "--heavy" in sys.argv:
        for name in workloads.HEAVY:
            print(json.dumps(workloads.heavy_join(spark, d, name)), flush=True)
        return
    more = {"--parallel": workloads.parallel_sweep, "--bounds": workloads.bound_sweep, "--contrast": workloads.contrast_sweep}
    for name in ("urban", "interstate"):
        for flag, run in more.items():
            if flag in sys.argv:
                for row in run(spark, d, name):
                    print(json.dumps(row), flush=True)
        if "--sweeps" in sys.argv:
            for parameter in workloads.SWEEPS:
                for row in workloads.sweep(spark, d, name, parameter):
                    print(json.dumps(row), flush=True)
            for row in workloads.theta_sweep(spark, d, name):
                print(json.dumps(row), flush=True)
    if {"--sweeps", *more} & set(sys.argv):
        return
    times = headline(spark, d)
    print(json.dumps({"metric": "total of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(d.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
