"""Rule rewards: format, length and answer, each 0 or 1, and their sum."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

from .responses import parse_response


def as_reward(condition: Column) -> Column:
    return F.coalesce(condition, F.lit(False)).cast("double")


def format_reward(response: Column, labels: Column) -> Column:
    p = parse_response(response)
    return as_reward(p["well_formed"] & F.array_contains(labels, p["answer"]))


def length_reward(response: Column, threshold: int = 1024, unit: str = "char") -> Column:
    """1 if the response is longer than the threshold, in characters or in tokens between white space."""
    if unit not in ("char", "token"):
        raise ValueError("unit is char or token")
    size = F.length(response) if unit == "char" else F.size(F.filter(F.split(response, r"\s+"), lambda t: t != ""))
    return as_reward(size > threshold)


def answer_reward(predicted: Column, gold: Column) -> Column:
    return as_reward(predicted.eqNullSafe(gold))


def total_reward(fmt: Column, length: Column, answer: Column, weights: Sequence[float] = (1.0, 1.0, 1.0), gate_on_format: bool = False) -> Column:
    if gate_on_format:
        answer = answer * fmt
    return fmt * weights[0] + length * weights[1] + answer * weights[2]
