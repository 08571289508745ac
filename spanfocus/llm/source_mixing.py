"""Mixing sources to target weights by hierarchical budgeting, in DataFrame expressions only.

Weights run down a tree of domain, language and source. At each node the budget is dealt to the children
in proportion to their weights, but no child gets more than it can fill with at most ``max_epochs`` passes
over its texts; what a child cannot fill goes to its siblings first, and leaves the node only when all of
them are full. Each leaf then takes whole passes of its documents and a prefix of one more, in an order
drawn by hash from the seed and the pass. A child of weight zero gets nothing, and what it holds is no
capacity of its ancestors: their budget goes to those that can take it.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.session import cut

#: Slices of a leaf's order; only the slice in which the budget ends is summed row by row.
SLICES = 4096
LEVELS = ("domain", "lang", "source")


def draw(seed: int, epoch: Column, key: str) -> Column:
    """60-bit number of the row in the order of a pass: the head of md5 over seed, pass and id."""
    text = F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.col(key).cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")


def weight_of(level: str, weights: Mapping[str, Mapping[str, float]]) -> Column:
    """A node's weight among its siblings: as stated for its name, else 1."""
    out = F.lit(1.0)
    for name, w in sorted(weights.get(level, {}).items()):
        out = F.when(F.col(level) == name, F.lit(float(w))).otherwise(out)
    return out


def fill(nodes: DataFrame, parents: Sequence[str], name: str) -> DataFrame:
    """Adds ``share`` to (parents, name, capacity, weight, budget): budget dealt in proportion, up to capacity.

    In the order of capacity per weight, a child is full if an even split of what is left over it and all
    later children exceeds its capacity; the others split the rest by weight.
    """
    group = list(parents) or [F.lit(0)]
    ratio = F.when(F.col("weight") > 0, F.col("capacity") / F.col("weight")).otherwise(float("inf"))
    order = Window.partitionBy(*group).orderBy("ratio", name)
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*group)
    left = F.col("budget") - F.coalesce(F.sum("capacity").over(before), F.lit(0.0))
    rest = F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    step = nodes.withColumn("ratio", ratio).withColumn("level", F.when(rest > 0, F.greatest(left, F.lit(0.0)) / rest))
    full = F.col("level").isNotNull() & (F.col("ratio") <= F.col("level"))
    step = step.withColumn("full", full)
    # The first child that is not full sets the level of all later ones.
    level = F.min(F.when(~F.col("full") & (F.col("weight") > 0), F.struct("ratio", name, "level"))).over(whole)["level"]
    share = F.when(F.col("full"), F.col("capacity")).otherwise(F.coalesce(level, F.lit(0.0)) * F.col("weight"))
    return step.withColumn("share", F.least("capacity", share)).drop("ratio", "level", "full")


def _same(names: Sequence[str]) -> Column:
    """Join condition on the level names against their copies with an underscore; null equals null."""
    on = F.lit(True)
    for p in names:
        on = on & F.col(p).eqNullSafe(F.col(f"_{p}"))
    return on


def _copies(names: Sequence[str]) -> list[Column]:
    return [F.col(p).alias(f"_{p}") for p in names]


def leaf_budgets(
    leaves: DataFrame, budget_share: float, weights: Mapping[str, Mapping[str, float]], max_epochs: int, levels: Sequence[str] = LEVELS
) -> DataFrame:
    """(levels, tokens, share): the tokens each leaf is to give. ``leaves`` has (levels, tokens)."""
    given = None
    for depth, name in enumerate(levels):
        path, parents = list(levels[: depth + 1]), list(levels[:depth])
        # What a child of weight zero holds cannot be taken: it adds nothing to the capacity of any node above.
        taking = reduce(and_, (weight_of(n, weights) > 0 for n in levels[depth:]))
        can_take = F.sum(F.when(taking, F.col("tokens")).otherwise(0)).cast("double") * max_epochs
        here = leaves.groupBy(*path).agg(F.sum("tokens").alias("tokens"), can_take.alias("capacity"))
        here = here.withColumn("weight", weight_of(name, weights))
        if given is None:
            whole = Window.partitionBy(F.lit(0))
            here = here.withColumn("budget", F.sum("tokens").over(whole) * F.lit(float(budget_share)))
        else:
            up = given.select(*_copies(parents), F.col("share").alias("budget"))
            here = here.join(up, _same(parents)).drop(*(f"_{p}" for p in parents))
        given = fill(here, parents, name)
    return given.select(*levels, "tokens", "share")


def word_count(text: str) -> Column:
    """Tokens of a text: runs of characters other than space, tab, newline and carriage return."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit("[^ \\t\\n\\r]+")), F.lit(0)).cast("bigint")


def mix(
    docs: DataFrame, budget_share: float = 0.8, weights: Mapping[str, Mapping[str, float]] | None = None, max_epochs: int = 2,
    seed: int = 17, key: str = "doc_id", levels: Sequence[str] = LEVELS, tokens: str = "n_tokens",
) -> DataFrame:
    """(key, levels, tokens, copies): the documents chosen and how often each is taken.

    ``docs`` has the levels and a token count. The budget is ``budget_share`` of all tokens. A leaf's
    partial pass takes the longest prefix of its order whose tokens do not exceed what is left; rows of
    equal order follow by id. Documents without tokens cost nothing and come along when the prefix passes
    them. Repeated rows are separate documents. Null level names form nodes of their own. An empty table
    gives an empty result.
    """
    names, weights = list(levels), weights or {}
    rows = cut(docs.select(key, *names, F.col(tokens).cast("bigint").alias("n")))
    leaves = cut(rows.groupBy(*names).agg(F.sum("n").alias("tokens")))
    passes = F.least(F.floor(F.col("share") / F.greatest("tokens", F.lit(1))), F.lit(max_epochs)).cast("bigint")
    plan = leaf_budgets(leaves, budget_share, weights, max_epochs, names).select(
        *_copies(names), passes.alias("passes"), (F.col("share") - passes * F.col("tokens")).alias("rest")
    )
    plan = cut(plan)  # a row per leaf; used three times
    on = _same(names)
    dealt = rows.join(plan, on).select(key, *names, "n", "passes", "rest")
    dealt = dealt.withColumn("order", draw(seed, F.col("passes"), key)).withColumn("slice", F.shiftright("order", 48).cast("int"))
    sums = dealt.groupBy(*names, "rest", "slice").agg(F.sum("n").alias("sum"))
    slices = sums.groupBy(*names, "rest").agg(F.sort_array(F.collect_list(F.struct("slice", "sum"))).alias("slices"))
    # The slice in which a leaf's budget ends: the first whose end exceeds what is left of the budget.
    start = F.struct(F.lit(0).cast("bigint").alias("before"), F.lit(SLICES).alias("end"))
    ends = slices.withColumn(
        "e",
        F.aggregate(
            "slices",
            start,
            lambda a, s: F.when(a["end"] < SLICES, a)
            .when(a["before"] + s["sum"] > F.col("rest"), F.struct(a["before"].alias("before"), s["slice"].alias("end")))
            .otherwise(F.struct((a["before"] + s["sum"]).alias("before"), a["end"].alias("end"))),
        ),
    ).select(*_copies(names), F.col("e.end").alias("end"), F.col("e.before").alias("before"))
    placed = dealt.join(ends, on).select(key, *names, "n", "passes", "rest", "order", "slice", "end", "before")
    decided = placed.where("slice <> end").withColumn("more", F.col("slice") < F.col("end"))
    order = Window.partitionBy(*names).orderBy("order", key, "n").rowsBetween(Window.unboundedPreceding, 0)
    edge = placed.where("slice = end").withColumn("more", F.col("before") + F.sum("n").over(order) <= F.col("rest"))
    out = decided.unionByName(edge)
    copies = F.col("passes") + F.when((F.col("passes") < max_epochs) & F.col("more"), 1).otherwise(0)
    return out.select(key, *names, F.col("n").alias(tokens), copies.cast("bigint").alias("copies")).where("copies > 0")
