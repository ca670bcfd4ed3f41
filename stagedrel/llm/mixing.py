"""Mixing sources to target weights by hierarchical budgets (DataFrame functions only).

A token budget runs down a tree of levels (domain, language, source). At each node it is shared among the
children by weight, but no child gets more than its subtree holds (tokens times the epochs allowed): what a
child can't take goes to its siblings first, and only what a whole family can't take goes to the families
beside it. Each leaf then reads a seeded permutation per epoch and takes the prefix that fills its quota.

Defined results: null or empty texts count 0 tokens; a null level value is the branch ``(null)``; a leaf of 0
tokens yields nothing; repeated rows are separate rows; ties of the permutation break by doc_id, then by text;
empty tables give empty results; other columns of the input pass through.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialize

NULL_NAME = "(null)"


def token_count(text: Column) -> Column:
    """Number of runs without white space."""
    t = F.coalesce(text, F.lit(""))
    parts = F.size(F.split(t, r"\s+"))
    return F.when(t == "", 0).otherwise(parts - t.rlike(r"^\s").cast("int") - t.rlike(r"\s$").cast("int")).cast("long")


def branch(name: str) -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(NULL_NAME))


def weight_of(level: Column, weights: Mapping[str, int], default: int = 1) -> Column:
    if not weights:
        return F.lit(default).cast("long")
    table = F.create_map(*[F.lit(x) for kv in weights.items() for x in kv])
    return F.coalesce(F.try_element_at(table, level), F.lit(default)).cast("long")


def leaf_budgets(leaves: DataFrame, levels: Sequence[str], weights: Mapping[str, Mapping[str, int]], budget: Column, max_epochs: int) -> DataFrame:
    """leaves: level columns and ``tokens``. Adds ``quota``: the leaf's tokens out of the budget.

    ``budget`` is an aggregate over the leaves (such as a share of their sum). Shares are whole tokens, rounded
    down, so at most one token per child is left over at each node. Weights are non-negative whole numbers.
    """
    leaves = leaves.withColumn("cap", F.col("tokens") * F.lit(max_epochs))
    given = leaves.agg(budget.cast("long").alias("given"))
    parents: list[str] = []
    for level in levels:
        keys = [*parents, level]
        nodes = leaves.groupBy(*keys).agg(F.sum("cap").alias("cap")).withColumn("w", weight_of(F.col(level), weights.get(level, {})))
        nodes = nodes.join(given, parents) if parents else nodes.crossJoin(F.broadcast(given))  # the root is one row
        family = W.partitionBy(*parents) if parents else W.partitionBy(F.lit(0))
        fills = F.when(F.col("w") == 0, F.lit(float("inf"))).otherwise(F.col("cap") / F.col("w"))
        before = family.orderBy("fills", level).rowsBetween(W.unboundedPreceding, -1)
        full = F.col("cap") * (F.col("all_w") - F.col("w_before")) <= (F.col("given") - F.col("cap_before")) * F.col("w")
        nodes = (
            nodes.withColumn("fills", fills)
            .withColumns({"cap_before": F.coalesce(F.sum("cap").over(before), F.lit(0)), "w_before": F.coalesce(F.sum("w").over(before), F.lit(0)), "all_w": F.sum("w").over(family)})
            .withColumn("full", (F.col("w") > 0) & full)
            .withColumns({"full_cap": F.coalesce(F.sum(F.when(F.col("full"), F.col("cap"))).over(family), F.lit(0)), "open_w": F.sum(F.when(F.col("full"), 0).otherwise(F.col("w"))).over(family)})
        )
        share = F.when(F.col("w") == 0, 0).when(F.col("full"), F.col("cap")).otherwise(F.expr("(given - full_cap) * w div nullif(open_w, 0)"))
        given = nodes.select(*keys, share.cast("long").alias("given"))
        parents = keys
    return leaves.join(given.withColumnRenamed("given", "quota"), list(levels)).drop("cap")


def mix(
    docs: DataFrame,
    levels: Sequence[str] = ("domain", "lang", "source"),
    weights: Mapping[str, Mapping[str, int]] | None = None,
    budget_share: float = 0.6,
    budget_tokens: int | None = None,
    max_epochs: int = 2,
    seed: int = 17,
    id_col: str = "doc_id",
    text_col: str = "text",
    tokens_col: str | None = None,
) -> DataFrame:
    """The rows of docs that the mixture reads, once per epoch, with ``epoch`` and ``n_tokens`` added.

    Parameters: ``budget_tokens``, or ``budget_share`` of the tokens at hand; ``weights`` by level (1 where not
    given); ``max_epochs`` a leaf may be read; ``tokens_col`` where counts exist already. A document belongs to
    its leaf's prefix if the tokens before it are less than the quota.

    No leaf is ranked as a whole: its permutation is cut in 256 hash ranges, the range that holds the boundary in
    256 again, and only rows of that last range (1 in 65,536) are put in order.
    """
    levels = list(levels)
    names = [f"__level{i}" for i in range(len(levels))]
    keyed = docs.withColumns({n: branch(level) for n, level in zip(names, levels, strict=True)})
    keyed = keyed.withColumn("__tokens", F.coalesce(F.col(tokens_col), F.lit(0)).cast("long") if tokens_col else token_count(F.col(text_col)))
    slim = materialize(keyed.select(*names, F.col(id_col).alias("__id"), "__tokens"), "mix-rows")
    leaves = slim.groupBy(*names).agg(F.sum("__tokens").alias("tokens"))
    budget = F.lit(budget_tokens) if budget_tokens is not None else F.floor(F.coalesce(F.sum("tokens"), F.lit(0)) * F.lit(budget_share))
    quotas = leaf_budgets(leaves, names, {n: (weights or {}).get(level, {}) for n, level in zip(names, levels, strict=True)}, budget, max_epochs)
    plan = materialize(
        quotas.select(
            *names,
            F.expr("case when tokens > 0 then quota div tokens else 0 end").alias("__full"),
            F.expr("case when tokens > 0 then quota % tokens else 0 end").alias("__rest"),
        ),
        "mix-plan",
    )

    def order(epoch: Column, doc: Column) -> Column:
        return F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(doc.cast("string"), F.lit("null"))).cast("binary"))

    def cut(rows: DataFrame, digits: int, start: Column, carry: list[str]) -> DataFrame:
        """For each leaf the hash range that holds the boundary, and the tokens before it."""
        sums = rows.groupBy(*names, *carry, "__rest", start.alias("__start"), F.substring("__order", 1, digits).alias("__range")).agg(F.sum("__tokens").alias("__sum"))
        before = W.partitionBy(*names).orderBy("__range").rowsBetween(W.unboundedPreceding, -1)
        sums = sums.withColumn("__before", F.col("__start") + F.coalesce(F.sum("__sum").over(before), F.lit(0)))
        return sums.where((F.col("__before") < F.col("__rest")) & (F.col("__rest") <= F.col("__before") + F.col("__sum"))).drop("__sum", "__start")

    part = slim.join(plan.where("__rest > 0"), names).withColumn("__order", order(F.col("__full"), F.col("__id")))
    first = materialize(cut(part, 2, F.lit(0).cast("long"), []).select(*names, F.col("__range").alias("__range1"), F.col("__before").alias("__before1")), "mix-cut")
    inner = part.join(first, names).where(F.substring("__order", 1, 2) == F.col("__range1"))
    second = cut(inner, 4, F.col("__before1"), ["__range1"]).select(*names, F.col("__range").alias("__range2"), F.col("__before").alias("__before2"))
    plan = materialize(plan.join(second, names, "left"), "mix-plan")

    rows = keyed.join(plan, names).withColumn("__order", order(F.col("__full"), F.col(id_col)))
    range_of = F.substring("__order", 1, 4)
    whole = F.when(F.col("__full") > 0, F.sequence(F.lit(0).cast("long"), F.col("__full") - 1)).otherwise(F.array().cast("array<bigint>"))
    partial = F.when((F.col("__rest") > 0) & (range_of < F.col("__range2")), F.array("__full")).otherwise(F.array().cast("array<bigint>"))
    sure = rows.withColumn("epoch", F.explode(F.concat(whole, partial)))
    edge = rows.where((F.col("__rest") > 0) & (range_of == F.col("__range2")))
    tie = F.xxhash64(text_col) if text_col in docs.columns else F.lit(0)
    running = W.partitionBy(*names).orderBy("__order", id_col, "__tie").rowsBetween(W.unboundedPreceding, -1)
    edge = (
        edge.withColumn("__tie", tie)
        .withColumn("__sofar", F.col("__before2") + F.coalesce(F.sum("__tokens").over(running), F.lit(0)))
        .where("__sofar < __rest")
        .withColumn("epoch", F.col("__full"))
    )
    columns = [c for c in docs.columns if c not in ("epoch", "n_tokens")]
    both = [x.select(*columns, "epoch", F.col("__tokens").alias("n_tokens")) for x in (sure, edge)]
    return both[0].unionByName(both[1])
