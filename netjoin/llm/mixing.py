"""Mixing sources to target weights by hierarchical budgets.

The tree is domain -> language -> source. Weights propagate a token budget from the root down; at every node the children share what their
parent got by water filling, so what a child lacks goes to its siblings, and leaves the subtree only
when the whole subtree is exhausted. Each leaf then takes its budget as a token prefix of seeded epochs: whole epochs first, then
the first documents of the next epoch's order.

Only counts are shuffled, never texts. Order keys are uniform hashes; a leaf of n documents has about sqrt(n) buckets of the keys' highest bits. Running
sums of the buckets find the one where the leaf's prefix ends, only that bucket is sorted to find the document, and one last pass keeps what lies before it. A leaf that holds a third of all rows costs no more than others.
"""

from __future__ import annotations

import json
from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from netjoin.llm.common import BROADCAST_ROWS, WORD, materialise

LEVELS = ("domain", "lang", "source")
#: Production parameters: weights by node name at each level (others count 1), and the domain of a source.
DOMAIN_WEIGHTS: dict[str, float] = {"books": 2.0, "web": 3.0, "forum": 1.0}
LANG_WEIGHTS: dict[str, float] = {"en": 4.0, "de": 2.0, "fr": 2.0, "es": 2.0}


def default_domain(source: Column) -> Column:
    """Domain of a source by the number in its name: 0-9 web, 10-14 books, others forum; no number: other."""
    n = F.regexp_extract(source, r"([0-9]{1,6})", 1)
    k = n.try_cast("int")
    return F.when(n == "", F.lit("other")).when(k < 10, F.lit("web")).when(k < 15, F.lit("books")).otherwise(F.lit("forum"))


def weight_of(name: Column, weights: Mapping[str, float]) -> Column:
    """A node's weight; 1 where the mapping has none. The mapping is read from one JSON literal."""
    known = F.from_json(F.lit(json.dumps(dict(weights))), "map<string,double>")
    return F.coalesce(F.try_element_at(known, name), F.lit(1.0))


def share_out(children: DataFrame, parent: list[str]) -> DataFrame:
    """children (…, weight, capacity, parent_budget) with an integer ``budget`` each: water filling inside each parent.

    Children with the least capacity for their weight fill up first; the others share the rest by weight, whole tokens by
    the largest fraction. Weights of 0 or less get nothing.
    """
    name = F.col("node")
    order = Window.partitionBy(*parent).orderBy("ratio", "node")
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    rows = children.withColumn("node", name).withColumn("w", F.greatest("weight", F.lit(0.0)))
    rows = rows.withColumn("ratio", F.when(F.col("w") > 0, F.col("capacity") / F.col("w")).otherwise(F.lit(float("inf"))))
    rows = rows.withColumn("taken", F.coalesce(F.sum("capacity").over(before), F.lit(0))).withColumn("weights", F.sum("w").over(after))
    rows = rows.withColumn("full", F.expr("w > 0 AND capacity * weights <= (parent_budget - taken) * w"))
    every = Window.partitionBy(*parent)
    rows = rows.withColumn("left", F.col("parent_budget") - F.sum(F.when(F.col("full"), F.col("capacity")).otherwise(0)).over(every))
    rows = rows.withColumn("open", F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("w"))).over(every))
    rows = rows.withColumn("exact", F.when(F.col("full"), F.col("capacity").cast("double")).when(F.col("open") > 0, F.greatest("left", F.lit(0)) * F.col("w") / F.col("open")).otherwise(0.0))
    rows = rows.withColumn("whole", F.when(F.col("full"), F.col("capacity")).otherwise(F.least(F.floor("exact"), "capacity")))
    rows = rows.withColumn("spare", F.when(F.col("open") > 0, F.greatest("left", F.lit(0)) - F.sum(F.when(F.col("full"), 0).otherwise(F.col("whole"))).over(every)).otherwise(0))
    rest = Window.partitionBy(*parent).orderBy(F.when(F.col("full") | (F.col("w") <= 0), 1).otherwise(0), F.desc(F.col("exact") - F.floor("exact")), "node")
    rows = rows.withColumn("nth", F.row_number().over(rest))
    extra = F.when(~F.col("full") & (F.col("w") > 0) & (F.col("nth") <= F.col("spare")) & (F.col("whole") < F.col("capacity")), 1).otherwise(0)
    return rows.withColumn("budget", (F.col("whole") + extra).cast("long")).select(*children.columns, "budget")


def leaf_budgets(leaves: DataFrame, total: Column, *, domain_weights: Mapping[str, float], lang_weights: Mapping[str, float], source_weights: Mapping[str, float], max_epochs: int) -> DataFrame:
    """leaves (domain, lang, source, tokens, docs) with ``budget``; ``total`` is the root's budget as a column over ``all_tokens``."""
    maps = dict(zip(LEVELS, (domain_weights, lang_weights, source_weights)))
    leaf = leaves.withColumn("capacity", (F.col("tokens") * max_epochs).cast("long"))
    root = leaf.agg(F.sum("tokens").alias("all_tokens")).select(F.greatest(total, F.lit(0)).cast("long").alias("parent_budget"), F.lit(0).alias("root"))
    budgets, above = None, ["root"]
    for depth, level in enumerate(LEVELS, 1):
        keys = ["root", *LEVELS[:depth]]
        nodes = leaf.withColumn("root", F.lit(0)).groupBy(*keys).agg(F.sum("capacity").alias("capacity"))
        up = root if budgets is None else budgets.select(*above, F.col("budget").alias("parent_budget"))
        filled = nodes.join(up, above).withColumn("node", F.col(level)).withColumn("weight", weight_of(F.col(level), maps[level]))
        budgets = share_out(filled, above).select(*keys, "budget")
        above = keys
    return leaf.join(budgets.drop("root"), list(LEVELS))


def mix(docs: DataFrame, *, share: float = 0.5, total: int | None = None, seed: int = 17, max_epochs: int = 2, domain=default_domain,
        domain_weights: Mapping[str, float] = DOMAIN_WEIGHTS, lang_weights: Mapping[str, float] = LANG_WEIGHTS, source_weights: Mapping[str, float] | None = None, keep: bool = False,
        id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """The mixture: one row for each document and epoch that is taken.

    Columns: doc_id, domain, lang, source, epoch (from 0), n_tokens, take_tokens (the part of the document inside the leaf's
    token prefix), leaf_budget. With ``keep`` the rows carry all columns of ``docs`` instead, whole documents.
    Tokens are words between white space. The budget is ``total`` tokens, or ``share`` of all; a leaf gives its tokens at most ``max_epochs`` times.
    Null languages and sources are leaves named ''; null texts have no tokens and are never taken. Rows that
    repeat an id inside a leaf are taken together. An empty table gives no rows. Order inside an epoch: hash of seed, epoch and id, then id.
    """
    names = docs.columns
    columns = [f"`{n}`" for n in (names if keep else [id_col, lang_col, source_col, text_col])]
    rows = docs.select(F.struct(*map(F.col, columns)).alias("row"))
    get = lambda c: F.col("row").getField(c)
    rows = rows.select("row", get(id_col).alias("doc_id"), F.coalesce(get(lang_col).cast("string"), F.lit("")).alias("lang"), F.coalesce(get(source_col).cast("string"), F.lit("")).alias("source"), get(text_col).cast("string").alias("text"))
    rows = rows.withColumn("domain", domain(F.col("source")))
    counted = rows.select("doc_id", *LEVELS, F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("n_tokens")).where("n_tokens > 0")
    counted = materialise(counted, "mix-counted")

    leaves = materialise(counted.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("tokens"), F.count(F.lit(1)).alias("docs")), "mix-leaves")
    want = F.lit(total) if total is not None else F.floor(F.col("all_tokens") * F.lit(float(share)))
    plan = leaf_budgets(leaves, want, domain_weights=domain_weights, lang_weights=lang_weights, source_weights=source_weights or {}, max_epochs=max_epochs)
    plan = plan.select(*LEVELS, F.col("budget").alias("leaf_budget"), F.expr("int(budget div tokens)").alias("whole_epochs"), F.expr("budget % tokens").alias("rest"),
                       F.ceil(F.log2("docs") / 2).cast("int").alias("depth"))
    plan = materialise(plan, "mix-plan")
    near = F.broadcast if plan.count() <= BROADCAST_ROWS else (lambda x: x)

    def keyed(df: DataFrame, plan: DataFrame) -> DataFrame:
        """Order key of the leaf's last, partial epoch, and its bucket: the key's highest bits."""
        k = df.join(near(plan), list(LEVELS)).withColumn("k", F.xxhash64(F.lit(seed), "whole_epochs", "doc_id"))
        return k.withColumn("bucket", F.expr("CASE WHEN depth = 0 THEN 0L ELSE shiftrightunsigned(k, 64 - depth) END"))

    # where a leaf's prefix ends: the bucket by running sums of buckets, then the document inside that bucket alone
    sums = keyed(counted, plan).where("rest > 0").groupBy(*LEVELS, "bucket", "rest").agg(F.sum("n_tokens").alias("n"))
    over = lambda *order: Window.partitionBy(*LEVELS).orderBy(*order)
    edge = sums.withColumn("upto", F.sum("n").over(over("bucket"))).where("upto >= rest AND upto - n < rest").select(*LEVELS, F.col("bucket").alias("edge"), (F.col("upto") - F.col("n")).alias("before"))
    edged = materialise(plan.join(edge, list(LEVELS), "left"), "mix-edges")
    last = keyed(counted, edged).where("bucket = edge").groupBy(*LEVELS, "rest", "before", "k", "doc_id").agg(F.sum("n_tokens").alias("n"))
    last = last.withColumn("upto", F.col("before") + F.sum("n").over(over("k", "doc_id").rowsBetween(Window.unboundedPreceding, 0))).where("upto >= rest AND upto - n < rest")
    cut = last.select(*LEVELS, F.struct("k", "doc_id").alias("cut"), (F.col("rest") - F.col("upto") + F.col("n")).alias("cut_take"))
    final = materialise(edged.drop("before").join(cut, list(LEVELS), "left"), "mix-cuts")

    spot = F.struct("k", "doc_id")
    partial = F.expr("rest > 0") & ((F.col("bucket") < F.col("edge")) | ((F.col("bucket") == F.col("edge")) & (spot <= F.col("cut"))))
    times = F.col("whole_epochs") + F.when(partial, 1).otherwise(0)
    taken = keyed(rows.where(F.col("text").rlike(WORD)) if keep else counted, final).withColumn("times", times).where("times > 0").withColumn("epoch", F.explode(F.expr("sequence(0, times - 1)")))
    if keep:
        return taken.select("row.*")
    ends = (F.col("epoch") == F.col("whole_epochs")) & (F.col("bucket") == F.col("edge")) & (spot == F.col("cut"))
    return taken.select("doc_id", *LEVELS, "epoch", "n_tokens", F.when(ends, F.least("n_tokens", "cut_take")).otherwise(F.col("n_tokens")).alias("take_tokens"), "leaf_budget")
