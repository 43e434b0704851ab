"""Mixing sources to target weights: a token budget dealt down a tree of domains, languages and sources.

Each node's capacity is max_epochs times the tokens below it. From the root down, a node's budget is dealt to its
children by their weights; a child that can't use its share takes its capacity, and what it leaves goes to its siblings,
again by weight. As no node is dealt more than the capacity below it, a shortage is first met among siblings, then among
the siblings of the parent, and so on up. Each leaf takes whole seeded epochs of its documents and, of the next epoch, the
longest prefix of a seeded order that fits the rest of its budget.

Only DataFrame functions. The prefix needs no sort of a leaf: tokens are summed by the leading bits of the order's hash, the
sum in which the budget ends is found, and the rows under it are summed by the next bits, until one hash is left. Every leaf is
then described by that bound, and a map-only pass with the table of leaves picks the rows, so texts are not shuffled.

Defined results: null texts and null levels count as 0 tokens and the value "" of the level; rows of equal id in one leaf have
equal hashes and are taken together; documents without tokens are in every prefix that reaches them; an empty table gives
no rows. Integer arithmetic throughout, so that engines agree.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_PATTERN, free_name, materialize

LEVELS = ("domain", "lang", "source")
#: The order's hash, and the bits by which a bound is narrowed per round: a leaf has 2**STEP_BITS sums at most in a round.
HASH_BITS, STEP_BITS = 60, 10
#: More leaves than this are joined, not broadcast.
BROADCAST_LEAVES = 200_000


@dataclass
class MixPlan:
    """weights: by level, then by value; others have default_weight. budget: budget_parts[0]/budget_parts[1] of all tokens."""

    weights: Mapping[str, Mapping[str, int]] = field(default_factory=lambda: {"lang": {"en": 4, "de": 2, "fr": 2, "es": 2}})
    default_weight: int = 1
    budget_parts: tuple[int, int] = (3, 5)
    max_epochs: int = 2
    seed: int = 42


def default_levels() -> dict[str, Column]:
    """The domain is the number at the end of the source, modulo four; lang and source are columns."""
    digits = F.regexp_extract(F.coalesce(F.col("source"), F.lit("")), r"([0-9]{1,9})$", 1)
    return {
        "domain": F.when(digits == "", F.lit("other")).otherwise(F.concat(F.lit("d"), (digits.cast("long") % 4).cast("string"))),
        "lang": F.coalesce(F.col("lang"), F.lit("")),
        "source": F.coalesce(F.col("source"), F.lit("")),
    }


def _wide(c: Column | str) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("decimal(38,0)")


def _weight(level: str, plan: MixPlan) -> Column:
    out = F.lit(plan.default_weight)
    for value, weight in plan.weights.get(level, {}).items():
        out = F.when(F.col(level) == value, F.lit(weight)).otherwise(out)
    return out.cast("long")


def deal(children: DataFrame, parent: list[str], level: str) -> DataFrame:
    """children(parent..., level, cap, weight, budget of the parent) with share: what each child is dealt."""
    whole = Window.partitionBy(*parent) if parent else Window.partitionBy()
    order = whole.orderBy(F.col("cap") / F.col("weight"), level)
    open_ = children.where("weight > 0 and cap > 0")
    ranked = open_.withColumn("_before", F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn(
        "_rest", F.sum("weight").over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    )
    # A child is full if its share of what the fuller ones leave is no less than its capacity.
    full = _wide("cap") * F.col("_rest") <= _wide(F.col("budget") - F.col("_before")) * F.col("weight")
    ranked = ranked.withColumn("_full", full)
    taken = F.coalesce(F.sum(F.when(F.col("_full"), F.col("cap"))).over(whole), F.lit(0))
    hungry = F.sum(F.when(~F.col("_full"), F.col("weight"))).over(whole)
    ranked = ranked.withColumn("_left", F.col("budget") - taken).withColumn("_hungry", hungry)
    share = F.floor(_wide("_left") * F.col("weight") / F.col("_hungry")).cast("long")
    return ranked.withColumn("share", F.when(F.col("_full"), F.col("cap")).otherwise(F.least("cap", share))).drop("_before", "_rest", "_full", "_left", "_hungry")


def leaf_budgets(leaves: DataFrame, plan: MixPlan) -> DataFrame:
    """leaves(levels..., tokens) with budget: the tokens that each leaf is to give."""
    caps = leaves.withColumn("cap", F.col("tokens") * plan.max_epochs)
    total = leaves.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0]
    budget = min(total * plan.budget_parts[0] // plan.budget_parts[1], total * plan.max_epochs)
    above = None
    for depth, level in enumerate(LEVELS):
        parent = list(LEVELS[:depth])
        nodes = caps.groupBy(*parent, level).agg(F.sum("cap").alias("cap")).withColumn("weight", _weight(level, plan))
        nodes = nodes.join(above, parent) if parent else nodes.withColumn("budget", F.lit(budget).cast("long"))
        above = deal(nodes, parent, level).select(*parent, level, F.col("share").alias("budget"))
    return leaves.join(above, list(LEVELS), "left").withColumn("budget", F.coalesce("budget", F.lit(0)))


def order_hash(seed: int, epoch: Column, key: Column) -> Column:
    """60 bits that order the documents of an epoch; the same in every engine that has md5."""
    text = F.concat_ws("|", F.lit(str(seed)), epoch.cast("string"), F.coalesce(key.cast("string"), F.lit("")))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def leaf_bounds(narrow: DataFrame, plan: MixPlan) -> DataFrame:
    """narrow(levels..., id, tokens) -> one row per leaf: budget, epochs (whole ones) and bound (largest hash taken of the next; -1: none)."""
    leaves = materialize(narrow.groupBy(*LEVELS).agg(F.sum("tokens").alias("tokens")), "leaves")
    plan_rows = leaf_budgets(leaves, plan).withColumn("epochs", F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(F.lit(0)).cast("long"))
    plan_rows = plan_rows.withColumn("rest", F.col("budget") - F.col("epochs") * F.col("tokens"))
    plan_rows = materialize(plan_rows, "budgets")
    hashed = with_leaves(narrow, plan_rows.where("rest > 0").select(*LEVELS, "epochs"), "inner")
    hashed = materialize(hashed.select(*LEVELS, order_hash(plan.seed, F.col("epochs"), F.col("id")).alias("h"), "tokens"), "hashed")
    ends = plan_rows.where("rest > 0").select(*LEVELS, "rest", F.lit(0).cast("long").alias("before"), F.lit(0).cast("long").alias("prefix"))
    run = Window.partitionBy(*LEVELS).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    for left in range(HASH_BITS - STEP_BITS, -1, -STEP_BITS):
        # Of a leaf that a third of all rows share, each task sends one row per bucket.
        within = with_leaves(hashed, ends, "inner").where(F.shiftright("h", left + STEP_BITS) == F.col("prefix"))
        sums = within.groupBy(*LEVELS, F.shiftright("h", left).alias("bucket")).agg(F.sum("tokens").alias("t"), F.first("rest").alias("rest"), F.first("before").alias("base"))
        sums = sums.withColumn("before", F.col("base") + F.coalesce(F.sum("t").over(run), F.lit(0))).where("before <= rest and before + t > rest")
        ends = materialize(sums.select(*LEVELS, "rest", "before", F.col("bucket").alias("prefix")), "ends")
    # The rest is less than a whole epoch, so some hash goes beyond it; all smaller ones are taken.
    bound = ends.select(*LEVELS, (F.col("prefix") - 1).alias("bound"))
    return plan_rows.join(bound, list(LEVELS), "left").withColumn("bound", F.coalesce("bound", F.lit(-1)))


def with_leaves(rows: DataFrame, leaves: DataFrame, how: str) -> DataFrame:
    """Join with the table of leaves, broadcast if it is counted to be small."""
    small = leaves.limit(BROADCAST_LEAVES + 1).count() <= BROADCAST_LEAVES
    return rows.join(F.broadcast(leaves) if small else leaves, list(LEVELS), how)


def mix(docs: DataFrame, plan: MixPlan | None = None, *, id_col: str = "doc_id", text_col: str = "text", levels: Mapping[str, Column] | None = None, keep: list[str] | None = None) -> DataFrame:
    """The chosen rows, once per epoch: the columns in keep (default all) with domain, n_tokens and epoch (from 1)."""
    plan = plan or MixPlan()
    levels = levels or default_levels()
    tokens = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD_PATTERN)), F.lit(0)).cast("long")
    narrow = materialize(docs.select(*(levels[k].alias(k) for k in LEVELS), F.col(id_col).alias("id"), tokens.alias("tokens")), "narrow")
    bounds = materialize(leaf_bounds(narrow, plan).select(*LEVELS, "epochs", "bound"), "bounds")
    keep = list(docs.columns) if keep is None else keep
    own = {k: free_name(docs, f"_leaf_{k}") for k in LEVELS}
    key, size, whole, bound, times = (free_name(docs, f"_mix_{x}") for x in ("id", "tokens", "epochs", "bound", "times"))
    n, epoch = (free_name(docs.select(*(F.col(f"`{c}`") for c in keep)) if keep else docs, x) for x in ("n_tokens", "epoch"))
    rows = docs.select(*(F.col(f"`{c}`") for c in keep), F.col(f"`{id_col}`").alias(key), *(levels[k].alias(own[k]) for k in LEVELS), tokens.alias(size))
    table = bounds.select(*(F.col(k).alias(own[k]) for k in LEVELS), F.col("epochs").alias(whole), F.col("bound").alias(bound))
    small = bounds.limit(BROADCAST_LEAVES + 1).count() <= BROADCAST_LEAVES
    rows = rows.join(F.broadcast(table) if small else table, list(own.values()))
    taken = F.col(whole) + F.when(order_hash(plan.seed, F.col(whole), F.col(key)) <= F.col(bound), 1).otherwise(0)
    rows = rows.withColumn(times, taken.cast("long")).where(F.col(times) > 0)
    domain = [] if "domain" in {c.lower() for c in keep} else [F.col(own["domain"]).alias("domain")]
    return rows.select(*(F.col(f"`{c}`") for c in keep), *domain, F.col(size).alias(n), F.explode(F.sequence(F.lit(1).cast("long"), F.col(times))).alias(epoch))
