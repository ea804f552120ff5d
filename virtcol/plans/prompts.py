"""A plan's steps as the prompts that a backend will get."""

from __future__ import annotations

from dataclasses import dataclass

from ..lang.parser import Phrase, Query
from ..model.base import classify_prompt, extract_prompt, judge_prompt, packed_prompt
from .planner import Costs, Plan, phrases

#: Where a row's text, or a taxonomy found at run time, is put into a prompt.
ROW, CATEGORY = "{row}", "{category}"


@dataclass(frozen=True)
class Backend:
    """How a backend is addressed: what precedes every prompt."""

    name: str = "default"
    preamble: str = "You answer questions about the records of a table, exactly in the form asked for."


@dataclass(frozen=True)
class PromptCall:
    step: str
    phrase: str
    source: str  # the column that ROW stands for
    system: str
    template: str
    rows: int  # records a prompt holds


def instantiate(plan: Plan, q: Query, info, backend: Backend = Backend(), costs: Costs = Costs()) -> list[PromptCall]:
    """The plan's prompts in the order of its steps; fused steps share theirs, and SELECT's phrases share one."""
    out = []

    def add(step: str, phrase: str, template: str, rows: int = 1) -> None:
        out.append(PromptCall(step, phrase, info.source, backend.preamble, template, rows))

    selected = list(dict.fromkeys(x.text for x in q.select if isinstance(x, Phrase)))
    for step in plan.steps:
        if step == "where":
            for p in phrases(q.where):
                add(step, p, judge_prompt(info.about, p, ROW))
        elif step == "group":
            for g in (g.text for g in q.group if isinstance(g, Phrase)):
                add("taxonomy", g, packed_prompt("groups", info.about, g, [ROW] * costs.taxonomy_rows), costs.taxonomy_rows)
                add("classify", g, classify_prompt(info.about, g, ROW, [CATEGORY]))
        elif step == "select" and "extract+classify" not in plan.fused and selected:
            add(step, ", ".join(selected), extract_prompt(info.about, selected, ROW))
    return out
