"""Grading of submission tables.

Submissions collapse twice before any search runs: to distinct texts, and to distinct forms after the syntactic
rules. Correct queries, the catalog and the weights are a few rows and go along with the tasks.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans import canon, distance
from ..plans.ir import GradingError, Unsupported
from ..plans.search import MOST_STATES, Correct, Found, Searcher
from ..session import Workspace
from ..sources.catalog import Catalog, default_catalog

#: Forms that one task of a search takes.
SPREAD = 64
#: Correct queries that are sent to the tasks; more would need a join by question.
MOST_CORRECT = 5_000
FORMS = "question int, sql string, parse_error string, form string, canonical_sql string, canonical_hash long, size long, total double"


def unique_texts(subs: DataFrame) -> DataFrame:
    """question, sql: combined before the shuffle, so that a popular text is one row of each task."""
    return subs.select("question", "sql").distinct()


def _form(sql: str, catalog: Catalog, weights: distance.Weights, off: tuple[str, ...]) -> tuple:
    try:
        tree, shared = canon.prepare(sql, catalog, off)
        full = canon.semantic(tree, catalog, off)
        text = canon.text(full)
        form = canon.text(tree) + "".join(sorted(f" shared {canon.text(p)}" for p in shared))
        return None, form, text, canon.fingerprint(text), distance.query_size(tree), distance.total_marks(tree, weights)
    except GradingError as e:
        return f"{'unsupported' if isinstance(e, Unsupported) else 'error'}: {e}", None, None, None, None, None
    except RecursionError:
        return "unsupported: the query is nested too deeply", None, None, None, None, None
    except (RuntimeError, ValueError, KeyError, IndexError, AttributeError, TypeError) as e:  # one odd query must not end the run
        return f"unsupported: {type(e).__name__}", None, None, None, None, None


def canonical_or_none(sql: str | None, catalog: Catalog | None = None) -> str | None:
    return _form(sql or "", catalog or default_catalog(), distance.Weights(), ())[2]


def with_forms(texts: DataFrame, catalog: Catalog | None = None, weights: distance.Weights = distance.Weights(), off: tuple[str, ...] = ()) -> DataFrame:
    """Each text with its parse error or its syntactic form, canonical text, fingerprint, size and worth."""
    catalog = catalog or default_catalog()

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = [(q, s, *_form(s or "", catalog, weights, off)) for q, s in zip(frame["question"], frame["sql"])]
            out = pd.DataFrame(rows, columns=[c.split()[0] for c in FORMS.split(", ")])
            yield out.astype({"canonical_hash": "Int64", "size": "Int64"})

    return texts.select("question", "sql").mapInPandas(work, FORMS)


def collect_correct(correct: DataFrame) -> list[tuple[int, str, str]]:
    """(question, cq_id, sql): checked to be few before they are sent anywhere."""
    rows = correct.select("question", "cq_id", "sql").limit(MOST_CORRECT + 1).collect()
    if len(rows) > MOST_CORRECT:
        raise ValueError(f"more than {MOST_CORRECT} correct queries")
    return [tuple(r) for r in rows]


PAIRS = "question int, form string, cq_id string, marks double, cost double, n_edits int, edits string, status string, states long, peak long, ms double, distance double, distance_marks double, equal boolean, components string"


def search_pairs(forms: DataFrame, correct: list[tuple[int, str, str]], method: str = "greedy", catalog: Catalog | None = None, weights: distance.Weights = distance.Weights(), off: tuple[str, ...] = (), most_states: int | None = MOST_STATES) -> DataFrame:
    """A row for each distinct form and correct query of its question. One pass in workers; nothing is shuffled but
    the forms, which are spread by hash so that costly neighbours part: SPREAD of them in a task, or one for each core.
    A search that stops at ``most_states`` has status capped and no marks; one that fails has status error, no marks
    and ends nobody else's. finish_capped() completes the former."""
    catalog = catalog or default_catalog()
    spark = forms.sparkSession
    one = forms.where("parse_error is null").groupBy("question", "form").agg(F.min("sql").alias("sql"))
    one = Workspace(spark, "forms").save(one)
    spread = one.repartition(max(spark.sparkContext.defaultParallelism, -(-one.count() // SPREAD)), F.xxhash64("form"))

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        searcher, prepared = Searcher(catalog, weights, off, most_states=most_states), {}
        for frame in frames:
            rows = []
            for question, form, sql in zip(frame["question"], frame["form"], frame["sql"]):
                if question not in prepared:
                    prepared[question] = [Correct.of(k, s, catalog, weights, off) for q, k, s in correct if q == question]
                tree, shared = canon.prepare(sql, catalog, off)
                full = canon.semantic(tree, catalog, off)
                for c in prepared[question]:
                    parts = distance.components(full, c.canonical, weights)
                    d = sum(weights.of(k) * v for k, v in parts.items())
                    try:
                        found = (searcher.greedy if method == "greedy" else searcher.shortest)(tree, c, shared)
                    except (RuntimeError, RecursionError, ValueError, KeyError, IndexError, AttributeError, TypeError):
                        found = Found(None, None, [], "error")
                    edits = json.dumps([vars_of(e) for e in found.edits])
                    by_distance = max(0.0, c.total - d) / c.total if c.total else 0.0
                    differing = json.dumps({k: v for k, v in parts.items() if v})
                    row = (question, form, c.cq_id, found.marks, found.cost, len(found.edits), edits, found.status, found.states, found.peak, found.ms)
                    rows.append((*row, d, by_distance, canon.text(full) == c.text, differing))
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in PAIRS.split(", ")]).astype({"marks": float, "cost": float})

    return spread.mapInPandas(work, PAIRS)


def finish_capped(pairs: DataFrame, forms: DataFrame, correct: list[tuple[int, str, str]], catalog: Catalog | None = None, weights: distance.Weights = distance.Weights(), off: tuple[str, ...] = ()) -> DataFrame:
    """``pairs`` with the capped ones finished by the search over a table, whose open states may fill a cluster."""
    from .frontier import shortest_path_frontier

    ws = Workspace(pairs.sparkSession, "capped")
    pairs = ws.save(pairs, "pairs")
    capped = pairs.where("status = 'capped'")
    if capped.isEmpty():
        return pairs
    rights = pairs.sparkSession.createDataFrame(correct, "question int, cq_id string, correct string")
    name = F.to_json(F.struct("question", "form", "cq_id")).alias("pair")
    texts = forms.where("parse_error is null").groupBy("question", "form").agg(F.min("sql").alias("student"))
    todo = capped.select("question", "form", "cq_id").join(texts, ["question", "form"]).join(F.broadcast(rights), ["question", "cq_id"])  # rights: at most MOST_CORRECT
    done = shortest_path_frontier(todo.select(name, "student", "correct"), catalog, weights, off)
    done = done.select("pair", F.col("marks").alias("f_marks"), F.col("cost").alias("f_cost"), F.col("edits").alias("f_edits"))
    joined = pairs.withColumn("pair", F.when(F.col("status") == "capped", name)).join(done, "pair", "left")
    new = {
        "marks": F.coalesce("f_marks", "marks"), "cost": F.coalesce("f_cost", "cost"), "edits": F.coalesce("f_edits", "edits"),
        "n_edits": F.when(F.col("f_edits").isNotNull(), F.json_array_length("f_edits")).otherwise(F.col("n_edits")),
        "status": F.when(F.col("f_cost").isNotNull(), "exact").when(F.col("f_marks").isNotNull(), "none").otherwise(F.col("status")),
    }
    return joined.select(*(new.get(c, F.col(c)).alias(c) for c in pairs.columns))


def vars_of(e: object) -> dict:
    return {k: getattr(e, k) for k in ("op", "component", "path", "before", "after", "cost")}


def best_of(pairs: DataFrame) -> DataFrame:
    """The best correct query of each form: most marks, then least cost, then the first id; unfinished searches last."""
    order = F.struct(F.col("marks").isNull(), -F.round("marks", 9), F.round("cost", 9), "cq_id")
    rest = [c for c in pairs.columns if c not in ("question", "form")]
    return pairs.groupBy("question", "form").agg(F.min_by(F.struct(*rest), order).alias("b")).select("question", "form", "b.*")


def attach(subs: DataFrame, forms: DataFrame, graded: DataFrame) -> DataFrame:
    """Back to submissions. Texts that do not parse get no marks and their message. Hot texts are split by the
    adaptive join; neither side is broadcast unless the engine sees that it is small. Columns of ``subs`` that are named
    like results keep their place, and the results replace them."""
    known = forms.select("question", "sql", "parse_error", "form", "canonical_sql", "canonical_hash", "size")
    rest = [c for c in graded.columns if c not in ("question", "form")]
    known = known.join(graded, ["question", "form"], "left")
    zero = lambda c: F.when(F.col("status").isin("capped", "error"), F.col(c)).otherwise(F.coalesce(c, F.lit(0.0)))
    results = {c: F.col(c) for c in ("parse_error", "canonical_sql", "canonical_hash", "size", *rest)}
    results |= {c: zero(c).alias(c) for c in ("marks", "distance_marks") if c in rest}
    own = [c for c in subs.columns if c not in results]
    return subs.select(*own).join(known.select("question", "sql", *results.values()), ["question", "sql"], "left").select(*own, *results)


def grade(subs: DataFrame, correct: DataFrame, weights: distance.Weights = distance.Weights(), method: str = "greedy", catalog: Catalog | None = None, off: tuple[str, ...] = ()) -> DataFrame:
    """Every submission with its verdict by canonical form, marks (share), cost, edits (JSON) and best correct query."""
    forms = with_forms(unique_texts(subs), catalog, weights, off)
    rights = collect_correct(correct)
    pairs = search_pairs(forms, rights, method, catalog, weights, off)
    graded = best_of(pairs if method == "greedy" else finish_capped(pairs, forms, rights, catalog, weights, off))
    return attach(subs, forms, graded)


def with_equivalence(subs: DataFrame, correct: DataFrame, catalog: Catalog | None = None, off: tuple[str, ...] = ()) -> DataFrame:
    """subs with canonical_match: some correct query of the question has the same canonical text."""
    collect_correct(correct)  # few, or an error
    forms = with_forms(unique_texts(subs), catalog, off=off)
    truths = with_forms(correct.select("question", "sql"), catalog, off=off).where("canonical_hash is not null").select("question", "canonical_hash", "canonical_sql").distinct()
    matched = forms.join(F.broadcast(truths.withColumn("hit", F.lit(True))), ["question", "canonical_hash", "canonical_sql"], "left")  # as few as correct queries
    return subs.join(matched.select("question", "sql", F.coalesce("hit", F.lit(False)).alias("canonical_match"), "parse_error"), ["question", "sql"], "left")


def feedback(graded: DataFrame) -> DataFrame:
    """graded with feedback: what a student sees in learning mode."""
    edit = "array<struct<op:string,component:string,path:string,before:string,after:string,cost:double>>"
    said = F.transform(F.from_json("edits", edit), lambda e: F.concat_ws(" ", F.upper(e["op"]), e["component"], F.when(e["path"] != "", F.concat(F.lit("in"), F.lit(" "), e["path"])), F.when(e["before"] != "", F.concat(F.lit("'"), e["before"], F.lit("'"))), F.when((e["before"] != "") & (e["after"] != ""), F.lit("to")), F.when(e["after"] != "", F.concat(F.lit("'"), e["after"], F.lit("'")))))
    text = F.when(F.col("parse_error").isNotNull(), F.concat(F.lit("Not graded: "), "parse_error")).when(F.col("n_edits") == 0, F.lit("Correct.")).when(F.col("status") == "none", F.lit("Too far from a correct query.")).otherwise(F.concat(F.lit("Not correct yet. "), F.array_join(said, "; ")))
    return graded.withColumn("feedback", F.when(F.col("status").isin("capped", "error"), F.lit("Not graded: the search was not finished.")).when((F.col("status") == "none") & F.col("parse_error").isNull(), F.lit("Too far from a correct query.")).otherwise(text))


def clusters(subs: DataFrame, correct: DataFrame, catalog: Catalog | None = None) -> DataFrame:
    """question, canonical_hash, canonical_sql, size, exemplar, matched: submissions with one canonical form.

    Counted from the counts of distinct texts, which are combined first: a popular form is no hot key.
    """
    counted = subs.groupBy("question", "sql").agg(F.count(F.lit(1)).alias("n"), F.min("sub_id").alias("first"))
    forms = with_forms(counted, catalog).where("parse_error is null")
    joined = counted.join(forms.select("question", "sql", "canonical_hash", "canonical_sql"), ["question", "sql"])
    out = joined.groupBy("question", "canonical_hash", "canonical_sql").agg(F.sum("n").alias("size"), F.min("first").alias("exemplar"))
    collect_correct(correct)  # few, or an error
    truths = with_forms(correct.select("question", "sql"), catalog).select("question", "canonical_hash", "canonical_sql").distinct().withColumn("hit", F.lit(True))
    return out.join(F.broadcast(truths), ["question", "canonical_hash", "canonical_sql"], "left").withColumn("matched", F.coalesce("hit", F.lit(False))).drop("hit")


def attempt_rank(graded: DataFrame) -> DataFrame:
    w = Window.partitionBy("question", "student_id").orderBy("ts", "sub_id")
    return graded.withColumn("attempt", F.row_number().over(w)).withColumn("gain", F.col("marks") - F.lag("marks").over(w))
