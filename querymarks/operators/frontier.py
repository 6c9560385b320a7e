"""Exhaustive search level by level over a table of open states, for pairs too large for one worker."""

from __future__ import annotations

import json
import pickle
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import canon
from ..plans.distance import Weights
from ..plans.edits import Editor
from ..plans.search import Correct, Searcher
from ..session import Workspace
from ..sources.catalog import Catalog, default_catalog
from .grade import vars_of

STATES = "pair string, key string, state binary, left double, total double, edits string, goal boolean"


def shortest_path_frontier(pairs: DataFrame, catalog: Catalog | None = None, weights: Weights = Weights(), off: tuple[str, ...] = ()) -> DataFrame:
    """pair, marks, cost, edits for each pair (pair, student, correct).

    A round takes, for each pair, all open states with the most marks left, expands them in workers, keeps the best
    of equal states in one aggregation and leaves out those that were taken. A goal ends its pair as soon as no open
    state has more marks. It goes on until no pair has an open state: costs use marks up, and states that were taken
    never open again. Pairs without a way that leaves marks get 0 and no cost. Only one count a round comes to the driver.
    """
    catalog = catalog or default_catalog()
    ws = Workspace(pairs.sparkSession, "frontier")

    def begin(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        searcher = Searcher(catalog, weights, off)
        for frame in frames:
            rows = []
            for pair, student, correct in zip(frame["pair"], frame["student"], frame["correct"]):
                c = Correct.of("c", correct, catalog, weights, off)
                tree, shared = canon.prepare(student, catalog, off)
                tree = searcher.start(tree, c)
                key = canon.text(tree)
                rows.append((str(pair), key, pickle.dumps((tree, c.tree, c.text, shared)), c.total, c.total, "[]", searcher.equal(tree, key, c)))
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in STATES.split(", ")])

    def expand(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        searcher = Searcher(catalog, weights, off)
        for frame in frames:
            rows = []
            for pair, data, left, total, edits in zip(frame["pair"], frame["state"], frame["left"], frame["total"], frame["edits"]):
                tree, goal, goal_text, shared = pickle.loads(data)
                said = json.loads(edits)
                for s in Editor(weights, False, shared).steps(tree, goal):
                    if left - s.cost > 1e-9:
                        key = canon.text(s.tree)
                        hit = canon.text(searcher.canonical(s.tree, key)) == goal_text
                        rows.append((pair, key, pickle.dumps((s.tree, goal, goal_text, shared)), left - s.cost, total, json.dumps([*said, vars_of(s.edit)]), hit))
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in STATES.split(", ")])

    open_ = ws.save(pairs.select("pair", "student", "correct").mapInPandas(begin, STATES), "open")
    closed = ws.save(open_.select("pair", "key").where("false"), "closed")
    found = None
    while True:
        top = open_.groupBy("pair").agg(F.max("left").alias("top"))
        ranked = open_.join(top, "pair")
        goals = ranked.where("goal and left >= top - 1e-9").groupBy("pair").agg(F.min_by(F.struct("left", "total", "edits"), F.struct("key")).alias("g")).select("pair", "g.*")
        goals = ws.save(goals, "goals")
        found = goals if found is None else found.unionByName(goals)
        going = ranked.join(goals.select("pair"), "pair", "left_anti")
        take, rest = going.where("left >= top - 1e-9").drop("top"), going.where("left < top - 1e-9").drop("top")
        closed = ws.save(closed.unionByName(take.select("pair", "key")), "closed")
        more = rest.unionByName(take.mapInPandas(expand, STATES)).join(closed, ["pair", "key"], "left_anti")
        cols = ["state", "left", "total", "edits", "goal"]
        open_ = ws.save(more.groupBy("pair", "key").agg(F.max_by(F.struct(*cols), F.struct("left", "edits")).alias("b")).select("pair", "key", "b.*").select([x.split()[0] for x in STATES.split(", ")]), "open")
        if open_.isEmpty():
            break
    done = found.select("pair", (F.col("left") / F.col("total")).alias("marks"), (F.col("total") - F.col("left")).alias("cost"), "edits")
    none = pairs.select(F.col("pair").cast("string").alias("pair")).join(done.select("pair"), "pair", "left_anti")
    return done.unionByName(none.select("pair", F.lit(0.0).alias("marks"), F.lit(None).cast("double").alias("cost"), F.lit("[]").alias("edits")))
