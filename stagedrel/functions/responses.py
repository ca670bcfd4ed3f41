"""Responses: a think block with six numbered steps, then an answer, and nothing else. All checks are linear in the text."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The tags and the step mark of a response, and white space around them.
THINK, THINK_END, ANSWER, ANSWER_END = "<think>", "</think>", "<answer>", "</answer>"
STEP = "Step ([0-9]+):"
ORDER = "1,2,3,4,5,6"
WHITE = " \t\n\r"


def _bare(text: Column) -> Column:
    return F.btrim(text, F.lit(WHITE))


def _between(text: Column, opening: str, closing: str) -> tuple[Column, Column]:
    """(whether there is one such block, what it holds; empty without one)."""

    def once(tag: str) -> Column:
        return F.length(text) - F.length(F.replace(text, F.lit(tag), F.lit(""))) == len(tag)

    there = once(opening) & once(closing) & (F.instr(text, opening) < F.instr(text, closing))
    return there, F.when(there, F.substring_index(F.substring_index(text, closing, 1), opening, -1)).otherwise("")


def parse_response(text: Column) -> Column:
    """struct(steps, order, answer, has_think, well_formed); order holds the numbers of the steps, joined.

    A step ends where the next one begins, on the same line or another. Well formed: one think block that begins the
    response and holds the six steps in order and nothing before them, then one answer block that ends it. The answer
    is read wherever the only answer block stands; of several blocks none counts.
    """
    t = _bare(F.coalesce(text, F.lit("")))
    has_think, think = _between(t, THINK, THINK_END)
    has_answer, said = _between(t, ANSWER, ANSWER_END)
    answer = _bare(said)
    order = F.array_join(F.regexp_extract_all(think, F.lit(STEP), F.lit(1)), ",")
    parts = F.split(think, "Step [0-9]+:")
    steps = F.transform(F.slice(parts, 2, F.size(parts) - 1), _bare)
    gap = F.substring_index(F.substring_index(t, ANSWER, 1), THINK_END, -1)
    laid = t.startswith(THINK) & t.endswith(ANSWER_END) & (_bare(gap) == "") & (_bare(F.get(parts, F.lit(0))) == "")
    return F.struct(
        steps.alias("steps"), order.alias("order"), answer.alias("answer"), has_think.alias("has_think"),
        (has_think & has_answer & laid & (order == ORDER) & (answer != "")).alias("well_formed"),
    )


def reject_reason(parsed: Column, gold: Column, labels: Column) -> Column:
    """ok, or the first reason to leave an annotation out."""
    return (
        F.when(~parsed["has_think"], "no_think")
        .when(parsed["order"] != ORDER, "bad_steps")
        .when(parsed["answer"] == "", "no_answer")
        .when(~parsed["well_formed"], "bad_layout")
        .when(~F.array_contains(labels, parsed["answer"]), "unknown_label")
        .when(parsed["answer"] != gold, "wrong_answer")
        .otherwise("ok")
    )


def truncate_tokens(text: Column, n: int) -> Column:
    """The first n tokens between single spaces; shorter texts as they are."""
    tokens = F.split(text, " ")
    return F.when(F.size(tokens) > n, F.array_join(F.slice(tokens, 1, n), " ")).otherwise(text)
