"""Prepared inputs and the parameter sweeps of the experiments."""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.functions.workspace import materialise
from netjoin.operators.network import Network
from netjoin.operators.measures import imbalance, shuffle_totals
from netjoin.operators.partition import Hierarchy, balanced_assign, build_hierarchy, from_assignment
from netjoin.plans.joins import JoinReport, closest_pairs, distance_join
from netjoin.plans.schedule import cut_hierarchy
from netjoin.sources.networks import NETWORKS, hash_sets

#: Numbers of leaves over which local and shared bounds are compared.
BOUND_LEAVES = (2, 3, 4, 8, 16)
#: Defaults and values of the sweeps. alpha has a default of 0; joins not about alpha use 0.5, as unsmoothed splits leave parts of a few vertices.
DEFAULTS = {"alpha": 0.0, "parallelism": 8, "k": 80, "r": 8, "s": 8}
SWEEPS = {"alpha": (0.0, 0.25, 0.5, 0.75, 1.0), "parallelism": (2, 4, 6, 8, 10, 12, 14), "k": (20, 40, 60, 80, 100, 120, 140), "r": (2, 4, 6, 8, 10, 12, 14), "s": (2, 4, 6, 8, 10, 12, 14)}
THETAS = {"urban": (200, 400, 800, 1500), "interstate": (50, 100, 200, 400, 900), "lines": (500, 2000), "mesh": (3000, 6000)}


@dataclass(frozen=True)
class Prepared:
    net: Network
    tree: Hierarchy | None
    r: DataFrame
    s: DataFrame


_READY: dict[tuple, Network | Hierarchy] = {}


def prepared_network(spark: SparkSession, sf_dir: str, name: str) -> Network:
    """A network written once for an application and read from the shared folder afterwards."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _READY:
        net = NETWORKS[name](spark, sf_dir)
        _READY[key] = replace(net, vertices=materialise(net.vertices, f"{name}-vertices"), edges=materialise(net.edges, f"{name}-edges"))
    return _READY[key]


def prepared_tree(spark: SparkSession, sf_dir: str, name: str, *, leaves: int = 16, alpha: float = 0.5, seeds: str = "double_sweep") -> Hierarchy:
    key = (spark.sparkContext.applicationId, sf_dir, name, leaves, alpha, seeds)
    if key not in _READY:
        _READY[key] = build_hierarchy(prepared_network(spark, sf_dir, name), leaves=leaves, alpha=alpha, seeds=seeds)
    return _READY[key]


def prepare(spark: SparkSession, sf_dir: str, name: str, *, r: float = 8, s: float = 8, leaves: int | None = 16, alpha: float = 0.5) -> Prepared:
    net = prepared_network(spark, sf_dir, name)
    return Prepared(net, prepared_tree(spark, sf_dir, name, leaves=leaves, alpha=alpha) if leaves else None, *hash_sets(net, r, s))


def timed_pairs(p: Prepared, k: int | None, theta: int | None = None, **options) -> dict:
    """Seconds of one join without a report, then its work, idle share, and what it shuffled and spilled, from a second run."""
    spark, start = p.net.vertices.sparkSession, time.time()
    rows = closest_pairs(p.net, p.r, p.s, k, theta, hierarchy=p.tree, **options).count()
    seconds, before, report = time.time() - start, shuffle_totals(spark)["stages"], JoinReport()
    closest_pairs(p.net, p.r, p.s, k, theta, hierarchy=p.tree, report=report, **options).count()
    moved = shuffle_totals(spark, before)
    return {"seconds": round(seconds, 3), "search_seconds": round(report.search_seconds(), 3), "rows": rows, "settled": report.settled, "relaxed": report.relaxed, "bound": report.trace[-1], "sigma": report.sigma, "bridges": report.bridges_live, "refreshes": report.refreshes, "pruned": report.pruned,
            "idle": round(report.idle_share(options.get("parallelism", 8)), 3), "stages": moved["stages"] - before, "shuffle_kb": moved["shuffle_write"] // 1024, "spilled_kb": moved["spilled"] // 1024}


def sweep(spark: SparkSession, sf_dir: str, name: str, parameter: str) -> list[dict]:
    """One row for each value of a parameter, the others at their defaults: seconds and work. Parts and operands are prepared outside the clock."""
    out = []
    for value in SWEEPS[parameter]:
        at = DEFAULTS | {"alpha": 0.5} | {parameter: value}
        p = prepare(spark, sf_dir, name, r=at["r"], s=at["s"], alpha=at["alpha"])
        p.r.count(), p.s.count()
        options = {}
        if parameter == "parallelism":
            p = replace(p, tree=cut_hierarchy(p.tree, p.net, value))
            options = {"schedule": "pool", "parallelism": value}
        out.append({"network": name, parameter: value} | timed_pairs(p, at["k"], **options))
    return out


def bound_sweep(spark: SparkSession, sf_dir: str, name: str) -> list[dict]:
    """Local and shared bounds over numbers of leaves, without a pilot, a slot for each leaf."""
    out = []
    for n in BOUND_LEAVES:
        p = prepare(spark, sf_dir, name, leaves=n)
        p.tree.parts, p.r.count(), p.s.count()  # noqa: B018
        for threshold in ("local", "wave"):
            out.append({"network": name, "leaves": n, "threshold": threshold} | timed_pairs(p, DEFAULTS["k"], threshold=threshold, schedule="pool", parallelism=8))
    return out


def parallel_sweep(spark: SparkSession, sf_dir: str, name: str) -> list[dict]:
    """Large distance joins in pools of 1 to 14 slots over the same 32 leaves."""
    p, out = prepare(spark, sf_dir, name, leaves=32), []
    timed_pairs(p, None, THETAS[name][0])
    for n in (1, *SWEEPS["parallelism"]):
        out.append({"network": name, "theta": HEAVY[name], "parallelism": n} | timed_pairs(p, None, HEAVY[name], schedule="pool", parallelism=n))
    return out


def contrast_sweep(spark: SparkSession, sf_dir: str, name: str) -> list[dict]:
    """Separation, cut and balance of 16 parts by separation, by edge cut and by equal size, and the time of a join over each."""
    net, out = prepared_network(spark, sf_dir, name), []
    trees = {"separation": prepared_tree(spark, sf_dir, name)}
    for objective in ("cut", "size"):
        trees[objective] = from_assignment(net, balanced_assign(net, 16, objective=objective), renumber=True)
    for how, tree in trees.items():
        p = replace(prepare(spark, sf_dir, name), tree=tree)
        cut = tree.cross.agg(F.count_distinct("eid").alias("n"), (F.sum("w") / 2).cast("long").alias("w")).first()
        row = {"network": name, "parts": how, "sigma": tree.sigma, "n_cut": cut["n"], "cut_weight": cut["w"], "largest": round(imbalance(tree).first()["ratio"], 2)}
        out.append(row | {"seconds_theta": timed_pairs(p, None, THETAS[name][2])["seconds"]} | {k: v for k, v in timed_pairs(p, 80).items() if k in ("seconds", "settled", "bridges")})
    return out


def theta_sweep(spark: SparkSession, sf_dir: str, name: str) -> list[dict]:
    out = []
    for theta in THETAS[name]:
        p, start = prepare(spark, sf_dir, name), time.time()
        rows = distance_join(p.net, p.r, p.s, theta, hierarchy=p.tree).count()
        out.append({"network": name, "theta": theta, "seconds": round(time.time() - start, 3), "rows": rows})
    return out


#: Distance joins with enough work for parallelism to show.
HEAVY = {"urban": 6000, "interstate": 1200}


def heavy_join(spark: SparkSession, sf_dir: str, name: str) -> dict:
    """A large distance join on the session's cores, after a warm-up on a small one."""
    p = prepare(spark, sf_dir, name)
    distance_join(p.net, p.r, p.s, THETAS[name][0], hierarchy=p.tree).count()
    start = time.time()
    rows = distance_join(p.net, p.r, p.s, HEAVY[name], hierarchy=p.tree).count()
    return {"network": name, "theta": HEAVY[name], "cores": spark.sparkContext.defaultParallelism, "seconds": round(time.time() - start, 3), "rows": rows}
