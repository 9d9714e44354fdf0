"""Judges: who says yes, no or unknown to a proposed type. The loop asks one about at most a probe of columns at a time."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from typing import Protocol

from lakeadapt.functions.draws import rank
from lakeadapt.sources.catalog import KNOWLEDGE
from lakeadapt.sources.lake import PROMPT_CELLS, PROMPT_CHARS

ANSWERS = ("yes", "no", "unknown")


@dataclass(frozen=True)
class Proposal:
    column_id: str
    cells: tuple[str, ...]
    label: str


class Judge(Protocol):
    #: Whether it reads cells; a judge that does not is spared the fetch.
    reads_cells: bool

    def answer(self, proposals: list[Proposal]) -> list[str]: ...


@dataclass(frozen=True)
class ConstantJudge:
    reply: str
    reads_cells: bool = False

    def answer(self, proposals: list[Proposal]) -> list[str]:
        return [self.reply] * len(proposals)


@dataclass(frozen=True)
class NoisyJudge:
    """Right with a known rate, silent with another, by draws of its own seed. For lakes whose truth is known."""

    truth: Callable[[list[str]], dict[str, str]]
    accuracy: float = 0.807
    abstains: float = 0.009
    seed: int = 1
    reads_cells: bool = False

    def answer(self, proposals: list[Proposal]) -> list[str]:
        truth = self.truth([p.column_id for p in proposals])
        out = []
        for p in proposals:
            if rank(f"judge:silent:{self.seed}", p.column_id) / 2**32 < self.abstains:
                out.append("unknown")
            else:
                kept = rank(f"judge:right:{self.seed}", p.column_id) / 2**32 < self.accuracy
                out.append("yes" if (p.label == truth[p.column_id]) == kept else "no")
        return out


@dataclass(frozen=True)
class KnowledgeJudge:
    """Generic knowledge: patterns that a share of the cells must match. The same answers as `gap.knowledge_judge`."""

    knowledge: tuple[tuple[str, str, float], ...] = KNOWLEDGE
    reads_cells: bool = True

    def answer(self, proposals: list[Proposal]) -> list[str]:
        patterns = [(name, re.compile(pattern), least) for name, pattern, least in self.knowledge]
        known, out = {name for name, _, _ in self.knowledge}, []
        for p in proposals:
            n = len(p.cells)
            fits = {name for name, pattern, least in patterns if n and sum(bool(pattern.search(c)) for c in p.cells) / n >= least}
            out.append("yes" if p.label in fits else "no" if p.label in known or fits else "unknown")
        return out


@dataclass(frozen=True)
class ClientJudge:
    """A model behind ask(prompts) -> answers, asked in batches side by side. Cells are cut and masked before they leave."""

    ask: Callable[[list[str]], list[str]]
    types: tuple[str, ...]
    batch: int = 16
    concurrency: int = 4
    reads_cells: bool = True
    asked: list[str] = field(default_factory=list, compare=False)

    def answer(self, proposals: list[Proposal]) -> list[str]:
        prompts = [prompt_text(self.types, p.cells, p.label) for p in proposals]
        self.asked.extend(p.column_id for p in proposals)
        cuts = [prompts[k : k + self.batch] for k in range(0, len(prompts), self.batch)]
        with ThreadPoolExecutor(self.concurrency) as pool:
            return [parsed(a) for part in pool.map(self.ask, cuts) for a in part]


#: The masks of `gap.redact`.
MASKS = ((r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}", "<mail>"), (r"\b[0-9]{1,3}(\.[0-9]{1,3}){3}\b", "<ip>"), (r"\b[0-9a-f]{32,}\b", "<hex>"), (r"\b[0-9]{12,}\b", "<digits>"))


def prompt_text(types: Iterable[str], cells: Iterable[str], label: str) -> str:
    shown = [c[:PROMPT_CHARS] for c in list(cells)[:PROMPT_CELLS]]
    for pattern, mask in MASKS:
        shown = [re.sub(pattern, mask, c, flags=re.ASCII) for c in shown]
    head = f"You check a proposed type for a table column. Reply with one word: yes, no or unknown.\nTypes: {', '.join(sorted(types))}\nValues: "
    return f"{head}{'; '.join(shown)}\nProposed: {label}"


def parsed(text: str | None) -> str:
    found = re.match(r"(yes|no)\b", (text or "").strip().lower())
    return found.group(1) if found else "unknown"
