"""Prompts in three parts: the task, the guide in six steps, and a hint that depends on the gold label."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

from .labels import NONE, split_label

STEPS = (
    "Describe the picture as a whole and the marked object.",
    "Judge whether the text and the object have to do with each other.",
    "Match what the text says with what the picture shows.",
    "Name the type of the object and the type of the entity.",
    "List the relations that these two types allow.",
    "Choose one relation from the list, or none.",
)


def task_brief(labels: Sequence[str], text: Column, entity: Column) -> Column:
    head = "Given a picture, a marked object in it and a text with an entity, tell how the object relates to the entity. "
    rule = "Think between <think> and </think> and give one label between <answer> and </answer>. Labels: "
    return F.concat(F.lit(head + rule + ", ".join(labels) + ". Entity: "), F.coalesce(entity, F.lit("")), F.lit(". Text: "), F.coalesce(text, F.lit("")))


def step_guide(enabled: Sequence[int] | None = None) -> str:
    """The steps in order; ``enabled`` (numbers from 1) leaves the others out."""
    chosen = range(1, len(STEPS) + 1) if enabled is None else [k for k in range(1, len(STEPS) + 1) if k in set(enabled)]
    return "Go through these steps. " + " ".join(f"Step {k}: {STEPS[k - 1]}" for k in chosen)


def answer_hint(gold: Column) -> Column:
    p = split_label(gold)
    real = F.format_string("Hint: the object is of type %s, the entity of type %s, and the relation is %s.", p["obj_type"], p["ent_type"], p["relation"])
    return F.when(gold == NONE, F.lit("Hint: nothing relates the object to the entity.")).otherwise(real)


def expert_prompt(labels: Sequence[str], text: Column, entity: Column, gold: Column) -> Column:
    return F.concat_ws("\n", task_brief(labels, text, entity), F.lit(step_guide()), answer_hint(gold))


def learner_prompt(labels: Sequence[str], text: Column, entity: Column) -> Column:
    return task_brief(labels, text, entity)
