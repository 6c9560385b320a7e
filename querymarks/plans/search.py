"""Cheapest edit sequences: shortest path over all guided edits, or greedily by benefit minus cost."""

from __future__ import annotations

import heapq
import time
from dataclasses import dataclass, field
from typing import Any

from ..sources.catalog import Catalog
from .canon import label, prepare, semantic, text
from .distance import Weights, _both, edit_distance, least_pairing, total_marks
from .edits import KINDS, Edit, Editor

#: States after which a worker leaves a pair to the search over a table; None: never.
MOST_STATES = 20_000


@dataclass
class Correct:
    """A correct query, prepared once: its syntactic tree guides edits, its canonical text tests equivalence."""

    cq_id: str
    sql: str
    tree: Any = None
    canonical: Any = None
    text: str = ""
    total: float = 0.0

    @classmethod
    def of(cls, cq_id: str, sql: str, catalog: Catalog, weights: Weights = Weights(), off: tuple[str, ...] = ()) -> Correct:
        tree, _ = prepare(sql, catalog, off)
        canonical = semantic(tree, catalog, off)
        return cls(cq_id, sql, tree, canonical, text(canonical), total_marks(tree, weights))


@dataclass
class Found:
    """marks: share of full marks, None for a search that was stopped. status: exact, greedy, none (no sequence leaves
    marks), capped (stopped) or error."""

    marks: float | None
    cost: float | None
    edits: list[Edit] = field(default_factory=list)
    status: str = "exact"
    states: int = 0
    peak: int = 0
    ms: float = 0.0


class Searcher:
    def __init__(self, catalog: Catalog, weights: Weights = Weights(), off: tuple[str, ...] = (), extended: bool = False, most_states: int | None = MOST_STATES):
        self.catalog, self.weights, self.off, self.extended, self.most = catalog, weights, off, extended, most_states
        self.forms: dict[str, Any] = {}

    def canonical(self, state: Any, key: str) -> Any:
        """Canonical form by the state's text; labels are renewed on a copy, the state keeps those it is paired by."""
        if key not in self.forms:
            if len(self.forms) > 200_000:
                self.forms.clear()
            self.forms[key] = semantic(label(state), self.catalog, self.off)
        return self.forms[key]

    def start(self, student: Any, correct: Correct) -> Any:
        """The student's tree with its instances named as those of the correct tree that they fit best."""
        worth = lambda t: sum(self.weights.of(k) * v for k, v in _both(t, correct.tree, self.weights, False).items())
        return least_pairing(student, correct.tree, worth)[1]

    def equal(self, state: Any, key: str, correct: Correct) -> bool:
        return text(self.canonical(state, key)) == correct.text

    def shortest(self, student: Any, correct: Correct, shared: frozenset = frozenset()) -> Found:
        """Least cost over all sequences of guided edits. The state with most marks left is taken first, so that the
        first canonical match is the best one. States that were taken are closed, which also ends walks of no cost."""
        began = time.perf_counter()
        editor = Editor(self.weights, self.extended, shared)
        first = self.start(student, correct)
        open_: list[tuple] = [(-correct.total, 0, text(first), first, ())]
        best = {text(first): correct.total}
        closed: set[str] = set()
        taken = peak = made = 0
        while open_:
            peak = max(peak, len(open_))
            negative, _, key, state, edits = heapq.heappop(open_)
            if key in closed:
                continue
            closed.add(key)
            taken += 1
            marks = -negative
            if self.equal(state, key, correct):
                return Found(marks / correct.total if correct.total else 1.0, correct.total - marks, list(edits), "exact", taken, peak, (time.perf_counter() - began) * 1e3)
            if self.most and taken >= self.most:
                return Found(None, None, [], "capped", taken, peak, (time.perf_counter() - began) * 1e3)
            for s in editor.steps(state, correct.tree):
                left = marks - s.cost
                if left <= 1e-9:
                    continue
                k = text(s.tree)
                if k not in closed and left > best.get(k, 0.0):
                    best[k] = left
                    made += 1
                    heapq.heappush(open_, (-left, made, k, s.tree, (*edits, s.edit)))
        return Found(0.0, correct.total, [], "none", taken, peak, (time.perf_counter() - began) * 1e3)

    def greedy(self, student: Any, correct: Correct, shared: frozenset = frozenset()) -> Found:
        """One state at a time: of all edits the one with the largest fall of distance minus cost, even below zero."""
        began = time.perf_counter()
        editor = Editor(self.weights, self.extended, shared)
        state, marks, edits, taken = self.start(student, correct), correct.total, [], 0
        seen: set[str] = set()
        while True:
            taken += 1
            key = text(state)
            seen.add(key)
            form = self.canonical(state, key)
            if text(form) == correct.text:
                return Found(marks / correct.total if correct.total else 1.0, correct.total - marks, edits, "greedy", taken, 1, (time.perf_counter() - began) * 1e3)
            before, choice = edit_distance(form, correct.canonical, self.weights), None
            for s in editor.steps(state, correct.tree):
                k = text(s.tree)
                if k in seen:
                    continue
                after = edit_distance(self.canonical(s.tree, k), correct.canonical, self.weights)
                order = (-(before - after - s.cost), s.cost, KINDS.index(s.edit.op), k)
                if choice is None or order < choice[0]:
                    choice = (order, s)
            if choice is None or marks - choice[1].cost <= 1e-9:
                return Found(0.0, correct.total, [], "none", taken, 1, (time.perf_counter() - began) * 1e3)
            s = choice[1]
            state, marks = s.tree, marks - s.cost
            edits = [*edits, s.edit]

    def grade(self, sql: str, correct: list[Correct], method: str = "greedy") -> tuple[Correct, Found]:
        """The best result over all correct queries: most marks, then least cost, then the first id."""
        student, shared = prepare(sql, self.catalog, self.off)
        run = self.greedy if method == "greedy" else self.shortest
        results = [(c, run(student, c, shared)) for c in correct]
        return min(results, key=lambda r: (r[1].marks is None, -(r[1].marks or 0.0), r[1].cost or 0.0, r[0].cq_id))
