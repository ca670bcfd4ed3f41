"""Difficulty pools and the easy/hard mix: ratios, quotas, epoch pools and batches."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.labels import NONE
from ..functions.portable import hash_hex
from .sampling import hash_rank, hash_select

STRATEGIES = ("raw", "equal", "hard_only", "progressive")


def mix_ratio(t: int, alpha: float = 0.5, strategy: str = "progressive") -> float:
    """Easy rows for each hard row in epoch t (from 1). hard_only is a strategy of its own, not a limit of alpha."""
    if strategy not in STRATEGIES or strategy == "raw":
        raise ValueError("a ratio is defined for equal, hard_only and progressive")
    if strategy == "hard_only":
        return 0.0
    if not 0 < alpha <= 1:
        raise ValueError("alpha lies above 0 and is at most 1")
    return 1.0 if strategy == "equal" else alpha ** (t - 1)


def batch_quota(batch: int, t: int, alpha: float = 0.5, fit: str = "paper", strategy: str = "progressive") -> tuple[int, int]:
    """(easy, hard) rows of a batch in epoch t; both are rounded up, and ``fit="trim"`` takes a surplus off the easy ones."""
    ratio = mix_ratio(t, alpha, strategy)
    hard = math.ceil(batch / (1 + ratio) - 1e-9)
    easy = math.ceil(batch * ratio / (1 + ratio) - 1e-9)
    if fit == "trim":
        easy = batch - hard
    elif fit != "paper":
        raise ValueError("fit is paper or trim")
    return easy, hard


def quota_table(steps: DataFrame, alphas=(0.25, 0.5, 1.0), fit: str = "paper") -> DataFrame:
    """steps (with ``batch`` and ``t``) for each alpha, and (ratio, easy, hard): the quotas of every batch."""
    grid = steps.withColumn("alpha", F.explode(F.array(*[F.lit(float(a)) for a in alphas]))).withColumn("ratio", F.pow("alpha", F.col("t") - 1))
    hard = F.ceil(F.col("batch") / (1 + F.col("ratio")) - 1e-9).cast("long")
    easy = F.ceil(F.col("batch") * F.col("ratio") / (1 + F.col("ratio")) - 1e-9).cast("long") if fit == "paper" else F.col("batch").cast("long") - hard
    return grid.select(*steps.columns, "alpha", F.round("ratio", 6).alias("ratio"), easy.alias("easy"), hard.alias("hard"))


def ratio_table(epochs: DataFrame, alphas=(0.25, 0.5, 1.0)) -> DataFrame:
    """epochs (with ``t`` and the rows ``easy`` and ``hard``) for each alpha, the ratio and how many easy rows are drawn for it."""
    grid = epochs.withColumn("alpha", F.explode(F.array(*[F.lit(float(a)) for a in alphas]))).withColumn("ratio", F.pow("alpha", F.col("t") - 1))
    drawn = F.least(F.col("easy"), F.floor(F.col("hard") * F.col("ratio") + 0.5).cast("long"))
    return grid.select(*epochs.columns, "alpha", F.round("ratio", 6).alias("ratio"), drawn.alias("drawn"))


def warmup(step: Column, total: Column, base: float, ratio: float = 0.05) -> Column:
    """The learning rate of a step (from 0) of ``total``, as ``policy.softmax.warmup_lr`` has it."""
    ramp = F.greatest(F.lit(1.0), F.floor(total * F.lit(ratio)).cast("double"))
    return F.lit(base) * F.least(F.lit(1.0), (step + 1) / ramp)


def split_by_difficulty(rest: DataFrame, predictions: DataFrame, key: str = "sample_id") -> DataFrame:
    """(key, gold, pool): easy where the policy's greedy answer is right."""
    both = rest.select(key, "gold").join(predictions.select(key, "pred"), key)
    return both.select(key, "gold", F.when(F.col("pred").eqNullSafe(F.col("gold")), "easy").otherwise("hard").alias("pool"))


def pool_profile(pools: DataFrame) -> DataFrame:
    """Rows, share, and share of none in each pool and in both."""
    by = pools.withColumn("is_none", (F.col("gold") == NONE).cast("int")).rollup("pool").agg(F.count("*").alias("rows"), F.sum("is_none").alias("none_rows"))
    return by.select(F.coalesce("pool", F.lit("all")).alias("pool"), F.col("rows").cast("long").alias("rows"), F.col("none_rows").cast("long").alias("none_rows"), F.round(F.col("none_rows") / F.col("rows"), 6).alias("none_share"))


def proportional_easy_draw(easy: DataFrame, n: int, none_share: float, order: Column, key: str = "sample_id") -> DataFrame:
    """n easy rows (or all), with the training set's share of none as far as both strata reach."""
    kinds = easy.withColumn("_kind", F.when(F.col("gold") == NONE, "none").otherwise("real"))
    have = {r[0]: r[1] for r in kinds.groupBy("_kind").count().collect()}  # two rows
    n = min(n, sum(have.values()))
    none = min(have.get("none", 0), int(math.floor(n * none_share + 0.5)))
    real = min(have.get("real", 0), n - none)
    none = min(have.get("none", 0), n - real)
    quotas = easy.sparkSession.createDataFrame([("none", none), ("real", real)], "_kind string, quota long")
    return hash_select(kinds, ["_kind"], order, [key], quotas).drop("_kind")


def epoch_pool(pools: DataFrame, t: int, none_share: float, alpha: float = 0.5, seed: int = 42, strategy: str = "progressive", nested: bool = False, key: str = "sample_id") -> DataFrame:
    """What epoch t trains on: all hard rows and a draw of easy ones, drawn anew each epoch (or as subsets, nested)."""
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy is one of {STRATEGIES}")
    if strategy == "raw":
        return pools
    hard = pools.where("pool = 'hard'")  # a partition of the pool table: easy rows aren't read for it
    ratio = mix_ratio(t, alpha, strategy)
    n = int(math.floor(hard.count() * ratio + 0.5)) if ratio else 0
    if not n:
        return hard
    order = hash_hex(seed, "easy" if nested else f"easy{t}", F.col(key))
    return hard.unionByName(proportional_easy_draw(pools.where("pool = 'easy'"), n, none_share, order, key))


def assign_batches(pool: DataFrame, easy: int, hard: int, t: int, seed: int = 42, key: str = "sample_id") -> DataFrame:
    """(key, gold, pool, step, slot): both kinds in hash order, dealt to steps by their quotas; slots mix them by hash."""
    parts = []
    for kind, per in (("easy", easy), ("hard", hard)):
        if per:
            ranked = hash_rank(pool.where(F.col("pool") == kind), hash_hex(seed, f"batch{t}", F.col(key)), [key])
            parts.append(ranked.withColumn("step", F.expr(f"rank div {per}")).drop("rank"))
    dealt = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    from pyspark.sql import Window as W

    slot = F.row_number().over(W.partitionBy("step").orderBy(hash_hex(seed, f"slot{t}", F.col(key)), key)) - 1
    return dealt.withColumn("slot", slot.cast("long"))
