"""Group-standardised advantages and the terms of the clipped objective."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def _scaled(delta: Column, spread: Column, eps: float) -> Column:
    return F.when(F.coalesce(spread, F.lit(0.0)) <= 1e-12, 0.0).otherwise(delta / (spread + F.lit(eps)))


def advantage_flat(reward: str, group: Sequence[str], ddof: int = 0, eps: float = 0.0) -> Column:
    """Over rows of single responses: one shuffle on the group. A group without spread has advantage 0."""
    window = W.partitionBy(*group)
    spread = (F.stddev_pop if ddof == 0 else F.stddev_samp)(reward).over(window)
    return _scaled(F.col(reward) - F.avg(reward).over(window), spread, eps)


def advantage_nested(rewards: Column, ddof: int = 0, eps: float = 0.0) -> Column:
    """Over a row's array of rewards: no shuffle."""
    n = F.size(rewards)
    total = F.aggregate(rewards, F.lit(0.0), lambda a, x: a + x)
    mean = total / n
    square = F.aggregate(rewards, F.lit(0.0), lambda a, x: a + (x - mean) * (x - mean))
    spread = F.when(n > ddof, F.sqrt(square / F.nullif(n - F.lit(ddof), F.lit(0))))
    return F.transform(rewards, lambda x: _scaled(x - mean, spread, eps))


def sequence_log_prob(token_log_probs: Column) -> Column:
    return F.aggregate(token_log_probs, F.lit(0.0), lambda a, x: a + x)


def sequence_nll(token_log_probs: Column) -> Column:
    return -sequence_log_prob(token_log_probs)


def policy_ratio(current: Column, old: Column, clamp: float = 20.0) -> Column:
    return F.exp(F.greatest(F.lit(-clamp), F.least(F.lit(clamp), current - old)))


def clipped_term(ratio: Column, advantage: Column, eps: float = 0.2) -> Column:
    bounded = F.greatest(F.lit(1 - eps), F.least(F.lit(1 + eps), ratio))
    return F.least(ratio * advantage, bounded * advantage)


def divergence_term(current: Column, reference: Column, clamp: float = 20.0) -> Column:
    """x - ln x - 1 with x the reference's probability over the current one: never below 0."""
    log_x = F.greatest(F.lit(-clamp), F.least(F.lit(clamp), reference - current))
    return F.exp(log_x) - log_x - 1


def is_clipped(ratio: Column, advantage: Column, eps: float = 0.2) -> Column:
    """Whether the clip holds the gradient of this response at 0."""
    return ((advantage > 0) & (ratio > 1 + eps)) | ((advantage < 0) & (ratio < 1 - eps))


def gradient_weight(ratio: Column, advantage: Column, current: Column, reference: Column, eps: float = 0.2, beta: float = 0.001, clamp: float = 20.0) -> Column:
    """What multiplies the gradient of a response's log-probability in the objective."""
    log_x = F.greatest(F.lit(-clamp), F.least(F.lit(clamp), reference - current))
    surrogate = F.when(is_clipped(ratio, advantage, eps), 0.0).otherwise(ratio * advantage)
    return surrogate - F.lit(beta) * (1 - F.exp(log_x))
