"""What runs when: waves of a hierarchy's parts, dealt to a number of slots, and how deep the hierarchy is used.

Leaves form wave 0, a part runs a wave after both its children. In a wave every slot is one task that works through its parts in order, so that no more
than that many run at once. The plan is made on the driver from the rows of the parts, and the joins run by it.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from netjoin.operators.network import Network
from netjoin.operators.partition import Hierarchy, from_assignment


def cut_hierarchy(tree: Hierarchy, net: Network, parallelism: int, *, tasks_per_slot: int = 2) -> Hierarchy:
    """The hierarchy down to the level that keeps ``parallelism`` slots busy; deeper parts join their ancestor there."""
    level = math.ceil(math.log2(max(1, parallelism * tasks_per_slot)))
    if max((r["level"] for r in tree.parts.values()), default=0) <= level:
        return tree
    cut = tree.assign.select("id", F.element_at("path", F.least(F.size("path"), F.lit(level + 1))).alias("gp"))
    return from_assignment(net, cut, tree.nodes.where("seed_l IS NOT NULL").where(F.col("level") < level).select("gp", "seed_l", "seed_r", "method"))


@dataclass(frozen=True)
class Step:
    """A part in the schedule: its wave, its slot there, and its turn in that slot."""

    wave: int
    gp: int
    height: int
    slot: int
    turn: int


def plan_steps(tree: Hierarchy, parallelism: int) -> list[Step]:
    """The schedule of all parts. In a wave, parts nearer to a leaf come first, of these the larger, and are dealt round the slots in turn."""
    wave: dict[int, int] = {}
    for g in sorted(tree.parts, reverse=True):  # children have larger numbers than their parent
        wave[g] = 0 if tree.parts[g]["leaf"] else 1 + max(wave.get(2 * g, -1), wave.get(2 * g + 1, -1))
    out = []
    for w in sorted(set(wave.values())):
        order = sorted((g for g in wave if wave[g] == w), key=lambda g: (tree.parts[g]["height"], -tree.parts[g]["n_edges"], g))
        out += [Step(w, g, tree.parts[g]["height"], i % parallelism, i // parallelism) for i, g in enumerate(order)]
    return out


def schedule_plan(tree: Hierarchy, parallelism: int) -> DataFrame:
    """(wave, gp, height, slot, turn) of every part, as the pool runs them."""
    rows = [(s.wave, s.gp, s.height, s.slot, s.turn) for s in plan_steps(tree, parallelism)]
    return tree.nodes.sparkSession.createDataFrame(rows, "wave int, gp long, height int, slot int, turn int")


def default_slots(spark: SparkSession) -> int:
    """Tasks of a wave outside the pool: twice the cores, so that a slow one does not hold up the rest."""
    return 2 * spark.sparkContext.defaultParallelism
