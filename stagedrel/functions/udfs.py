"""Pandas functions for what expressions can't say: a policy's score of each row, and a grouped aggregate to cross-check spreads."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..policy import softmax
from ..policy.softmax import Policy


def policy_score(policy: Policy, x: Column) -> Column:
    """Log-probability of the policy's best outcome, in Arrow batches."""
    steps, best = policy.steps, softmax.sampler(0, {})

    def run(batch):
        import numpy as np
        import pandas as pd

        return pd.Series(steps(np.stack(batch.to_numpy()), best)[1] if len(batch) else [], dtype="float64")

    return F.pandas_udf(run, "double")(x)


def group_spread():
    """A grouped aggregate: the population standard deviation of a group's rewards, rounded to 6 digits."""
    import pandas as pd

    def spread(v: pd.Series) -> float:
        return round(float(v.std(ddof=0)), 6)

    spread.__annotations__ = {"v": pd.Series, "return": float}
    return F.pandas_udf(spread, "double")
