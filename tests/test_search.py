import itertools

import pytest

from querymarks.operators.experiments import EXAMPLES, measure_example
from querymarks.plans import canon, distance
from querymarks.plans.distance import Weights
from querymarks.plans.edits import Editor
from querymarks.plans.search import Correct, Searcher
from querymarks.sources import corpus
from querymarks.sources import workloads as wl
from querymarks.sources.catalog import default_catalog

CATALOG = default_catalog()


@pytest.mark.parametrize("name", EXAMPLES)
def test_worked_examples(name):
    _, _, _, apart, cost = EXAMPLES[name]
    assert measure_example(name) == (apart, cost, cost)


@pytest.mark.parametrize("question", corpus.EXERCISES)
def test_hand_derived_costs(question):
    correct, s = Correct.of("c", wl.CORRECT[wl.BASE[question]], CATALOG), Searcher(CATALOG)
    assert correct.total == corpus.TOTALS[question]
    for mask in range(32):
        if question == 10 and mask > 15:
            continue
        tree, shared = canon.prepare(corpus.submission_text(question, mask, 0), CATALOG)
        want = max(0.0, correct.total - sum(k for i, k in enumerate(corpus.COSTS[question]) if mask >> i & 1)) / correct.total
        best, greedy = s.shortest(tree, correct, shared), s.greedy(tree, correct, shared)
        assert best.marks == pytest.approx(want)
        assert greedy.marks <= best.marks + 1e-9


@pytest.mark.parametrize("question", corpus.EXERCISES)
def test_spelling_does_not_matter(question):
    for mask in (0, 9, 22, 31):
        assert len({canon.text(canon.prepare(corpus.submission_text(question, mask, style), CATALOG)[0]) for style in range(8)}) == 1


def test_best_of_several_correct_queries():
    rows = [Correct.of(k, v, CATALOG) for k, v in wl.CORRECT.items() if k.startswith("w10")]
    chosen, found = Searcher(CATALOG).grade(wl.CORRECT["w10d"], rows)
    assert (chosen.cq_id, found.marks) == ("w10d", 1.0)


def test_shortest_path_against_all_subsets_of_edits():
    """Brute force: every order of up to three of the first state's edits, followed by edits made new each time."""
    correct = Correct.of("c", wl.CORRECT["w03"], CATALOG)
    s = Searcher(CATALOG)
    for mask in range(32):
        tree, _ = canon.prepare(corpus.submission_text(3, mask, 0), CATALOG)
        level, best = {canon.text(tree): (tree, 0.0)}, None
        for _ in range(5):
            for t, c in level.values():
                if s.equal(t, canon.text(t), correct) and (best is None or c < best):
                    best = c
            following = {}
            for t, c in level.values():
                for step in Editor().steps(t, correct.tree):
                    key = canon.text(step.tree)
                    if c + step.cost < correct.total and (key not in following or following[key][1] > c + step.cost):
                        following[key] = (step.tree, c + step.cost)
            level = following
        found = s.shortest(tree, correct)
        assert (best is None) == (found.status == "none")
        assert best is None or found.cost == best


def test_free_edits_end():
    w = Weights((("predicate", 0.0),))
    correct = Correct.of("c", wl.CORRECT["w08a"], CATALOG, w)
    tree, _ = canon.prepare(corpus.submission_text(8, 7, 0), CATALOG)
    found = Searcher(CATALOG, w).shortest(tree, correct)
    assert found.status == "exact" and found.cost == 1.0


def test_cap_is_reported():
    correct = Correct.of("c", wl.CORRECT["w08a"], CATALOG)
    tree, _ = canon.prepare(corpus.submission_text(8, 31, 0), CATALOG)
    assert Searcher(CATALOG, most_states=3).shortest(tree, correct).status == "capped"


def test_no_edit_takes_half_a_condition():
    correct = Correct.of("c", "SELECT c_custkey FROM customer", CATALOG)
    tree, _ = canon.prepare("SELECT c_custkey FROM customer WHERE c_acctbal > 10", CATALOG)
    assert [(x.edit.op, x.edit.before) for x in Editor().steps(tree, correct.tree)] == [("delete", "10 < customer$0_1.c_acctbal")]


def test_relation_goes_only_after_what_needs_it():
    correct = Correct.of("c", "SELECT c_custkey FROM customer", CATALOG)
    tree, _ = canon.prepare("SELECT c_custkey FROM customer, region WHERE r_regionkey > 2", CATALOG)
    assert {x.edit.component for x in Editor().steps(tree, correct.tree)} == {"predicate"}


def test_weights_scale_costs():
    w = Weights((("relation", 3.0),))
    correct = Correct.of("c", wl.CORRECT["w03"], CATALOG, w)
    tree, _ = canon.prepare(corpus.submission_text(3, 16, 0), CATALOG)
    assert (correct.total, Searcher(CATALOG, w).shortest(tree, correct).cost) == (5.0, 3.0)


def test_assignment_is_least():
    import numpy as np

    rng = np.random.default_rng(5)
    for n in range(1, 6):
        c = rng.integers(0, 9, (n, n)).astype(float).tolist()
        want = min(sum(c[i][p[i]] for i in range(n)) for p in itertools.permutations(range(n)))
        assert distance.assignment(c) == want


def test_sizes():
    size = lambda sql: distance.query_size(canon.prepare(sql, CATALOG)[0])
    assert [size(wl.CORRECT[k]) for k in ("w01", "w03")] == [3, 5]


def test_node_granularity():
    w = Weights(granularity="node")
    a, b = (canon.canonicalize(x, CATALOG) for x in ("SELECT p_name FROM part WHERE p_size > 20", "SELECT p_name FROM part WHERE p_size > 25"))
    none = canon.canonicalize("SELECT p_name FROM part", CATALOG)
    assert distance.edit_distance(a, b, w) == 1.0 and distance.edit_distance(none, b, w) == 3.0


def test_combined_verdict_takes_any_correct_query(monkeypatch):
    """Right if it agrees with one correct query on all datasets; agreeing with another one on each stage is not enough."""
    from querymarks.operators import datasets

    class Rows(list):
        collect = lambda self: list(self)

    agrees = {("first", "a"): False, ("first", "b"): True, ("own", "a"): True, ("own", "b"): True}
    monkeypatch.setattr(datasets.canon, "canonical_text", lambda sql, catalog: sql)
    monkeypatch.setattr(datasets, "verdicts", lambda spark, students, correct, data, catalog: Rows({"passed": agrees[d, correct]} for d in data))
    judge = lambda: datasets.combined_verdict(None, "s", ["a", "b"], {"first": None}, {"own": None}, object())
    assert judge() == (True, "all datasets")
    agrees["own", "b"] = False
    assert judge() == (False, "datasets of the student's query")
