"""Verdicts of whole classes: canonical forms first, then rows on datasets made for the correct queries, then rows on
datasets made for the student's own conditions."""

from __future__ import annotations

import datetime
from collections import defaultdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import canon, distance, ir
from ..plans.resolve import table_of
from ..session import Workspace
from ..sources.catalog import Catalog, default_catalog
from . import grade
from .datasets import Dataset, digests

#: Distinct forms whose plans run in one job.
BATCH = 48
#: What a column of a made row holds that no condition speaks of; an int names a row that exists where it refers to one.
PLAIN = {"int": 1, "num": 1.0, "str": "w", "ts": datetime.datetime(1996, 6, 15)}
_DAY = datetime.timedelta(days=1)
_HOLDS = {"=": lambda a, b: a == b, "<>": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b}
Condition = tuple[str, object, bool]


def _value(lit: ir.Lit, kind: str) -> object:
    try:
        if kind == "ts":
            return datetime.datetime.fromisoformat(str(lit.value))
        return {"int": int, "num": float, "str": str}[kind](lit.value)
    except (KeyError, ValueError, TypeError):
        return None


def conditions(sql: str, catalog: Catalog) -> tuple[set[str], dict[tuple[str, str], list[Condition]]]:
    """The tables of a query, and of each (table, column) the comparisons with constants: operator, constant, and
    whether the constant stands on the left. LIKE is the operator "like"."""
    tree, _ = canon.prepare(sql, catalog)
    tables, found = set(), defaultdict(list)

    def note(col: ir.Col, op: str, lit: ir.Lit, left: bool) -> None:
        table = catalog.table(table_of(col.rel))
        value = _value(lit, table.columns.get(col.name, "other")) if table else None
        if value is not None:
            found[table_of(col.rel), col.name].append((op, value, left))

    for x in ir.walk(tree):
        if isinstance(x, ir.Table):
            tables.add(x.name)
        elif isinstance(x, ir.Cmp) and x.op in _HOLDS:
            if isinstance(x.left, ir.Col) and isinstance(x.right, ir.Lit):
                note(x.left, x.op, x.right, False)
            elif isinstance(x.right, ir.Col) and isinstance(x.left, ir.Lit):
                note(x.right, x.op, x.left, True)
        elif isinstance(x, ir.Like) and isinstance(x.arg, ir.Col) and isinstance(x.pattern, ir.Lit):
            note(x.arg, "like", x.pattern, False)
    return tables, dict(found)


def _near(op: str, value: object) -> list:
    """A constant and its neighbours; strings that fit a pattern and strings that nearly do."""
    if op == "like":
        fits = value.replace("_", "x")
        return [fits.replace("%", ""), fits.replace("%", "z"), "~" + fits.replace("%", "") + "~", value.replace("_", "").replace("%", "")]
    if isinstance(value, datetime.datetime):
        return [value - _DAY, value, value + _DAY]
    return [value, value + "!", value[:-1]] if isinstance(value, str) else [value - 1, value, value + 1]


def _holds(x: object, c: Condition) -> bool:
    op, value, left = c
    if op == "like":
        return x == value.replace("_", "x").replace("%", "")
    return _HOLDS[op](value, x) if left else _HOLDS[op](x, value)


def made_rows(sql: str, catalog: Catalog, first: int = 1) -> dict[str, list[tuple]]:
    """Rows for the tables of a query: small worlds of one row for each table, linked by fresh negative keys. In the
    first world all comparisons with constants hold as far as they can together; each other one gives a single column
    a constant or a neighbour of it, to tell operators, constants and added or missing conditions apart. Connectives
    meet rows with and without partners so. The rows depend on the query and the catalog alone and keep all keys."""
    tables, found = conditions(sql, catalog)
    choices = {at: list(dict.fromkeys(v for op, value, _ in cs for v in _near(op, value))) for at, cs in found.items()}
    usual = {at: next((v for v in values if all(_holds(v, c) for c in found[at])), values[0]) for at, values in choices.items()}
    worlds = [usual, *({**usual, at: v} for at, values in sorted(choices.items()) for v in values if v != usual[at])]
    # Worlds of parents without rows that refer to them: the least table stays out.
    out: dict[str, list[tuple]] = defaultdict(list)
    for k, world in enumerate([*worlds, usual]):
        key = -(first + k)
        children = {t for t in tables if catalog.table(t).foreign and not any(f.table == t for s in tables for f in catalog.table(s).foreign)}
        for t in sorted(tables - (children if k == len(worlds) and children != tables else set())):
            own = catalog.table(t)
            refers = {c: f.table for f in own.foreign for c in f.columns}
            single = {c for s in own.keys if len(s) == 1 for c in s}
            row = []
            for c, kind in own.columns.items():
                value = world.get((t, c), PLAIN.get(kind))
                if c in single and c not in refers:
                    value = key if kind == "int" else f"{value}~{key}"
                elif refers.get(c) in tables and (t, c) not in world:
                    value = key
                row.append(value)
            out[t].append(tuple(row))
    return dict(out)


def made_for(spark: SparkSession, sqls: list[str], tables: Dataset, catalog: Catalog | None = None) -> Dataset:
    """``tables`` with the rows made for all ``sqls``."""
    catalog, rows, first = catalog or default_catalog(), defaultdict(list), 1
    for sql in sqls:
        made = made_rows(sql, catalog, first)
        first += max(map(len, made.values()), default=0)
        for t, more in made.items():
            rows[t] += more
    plus = {t: spark.createDataFrame(more, tables[t].schema).coalesce(1) for t, more in rows.items() if t in tables}
    return tables | {t: tables[t].unionByName(df) for t, df in plus.items()}


def _told(spark: SparkSession, queries: dict[str, str], data: dict[str, Dataset], catalog: Catalog) -> dict[str, tuple]:
    """Of each query its digests by dataset; None for one that does not run. The plans of one batch form one job."""
    try:
        got = defaultdict(dict)
        for r in digests(spark, queries, data, catalog).collect():
            got[r["query"]][r["dataset"]] = (r["n"], r["h"])
        return {q: tuple(sorted(got[q].items())) for q in queries}
    except Exception:
        if len(queries) == 1:
            return dict.fromkeys(queries)
        return {k: v for q, sql in queries.items() for k, v in _told(spark, {q: sql}, data, catalog).items()}


def _order(sql: str, catalog: Catalog) -> tuple[str, ...]:
    return tuple(map(canon.text, canon.canonicalize(sql, catalog).order))


def _judge(spark: SparkSession, students: dict[str, str], correct: list[str], tables: Dataset, catalog: Catalog) -> dict[str, tuple[bool, str]]:
    """(correct, reason) of students' queries that no correct query matches canonically."""
    out: dict[str, tuple[bool, str]] = {}
    rights = {f"$c{k}": sql for k, sql in enumerate(correct)}
    order = {k: _order(sql, catalog) for k, sql in (students | rights).items()}
    told = _told(spark, students | rights, {"whole": tables, "made": made_for(spark, correct, tables, catalog)}, catalog)
    for k, sql in students.items():
        alike = [c for c in rights if told[k] is not None and told[c] == told[k]]
        ordered = [c for c in alike if not order[c] or order[c] == order[k]]
        if not ordered:
            out[k] = (False, "does not run" if told[k] is None else "order of rows" if alike else "datasets of the correct queries")
            continue
        few = {k: sql} | {c: rights[c] for c in ordered}
        own = _told(spark, few, {"own": made_for(spark, [sql], tables, catalog)}, catalog)
        same = any(own[c] == own[k] for c in ordered)
        out[k] = (same, "all datasets" if same else "datasets of the student's query")
    return out


def form_verdicts(forms: DataFrame, correct: DataFrame, tables: Dataset, catalog: Catalog | None = None, batch: int = BATCH) -> DataFrame:
    """question, canonical_sql, correct, reason: a row for each distinct canonical form of with_forms().

    A form that some correct query of its question has is right without running anything. Of the others one query each
    is run on datasets, ``batch`` plans in a job: the tables with and without rows made for the constants, patterns and
    connectives of the correct queries; who agrees there with some correct query is run beside it on the tables with rows
    made for the student's own conditions. Rows are compared as bags, and where the correct query orders its rows the
    reduced ORDER BY lists as well. The driver holds one batch of texts and verdicts at a time.
    """
    spark, catalog = forms.sparkSession, catalog or default_catalog()
    ws = Workspace(spark, "verdicts")
    rights = defaultdict(list)
    for question, _, sql in grade.collect_correct(correct):
        rights[question].append(sql)
    truths = grade.with_forms(correct.select("question", "sql"), catalog).where("parse_error is null").select("question", "canonical_sql").distinct()
    truths = ws.save(truths, "truths")
    one = ws.save(forms.where("parse_error is null").groupBy("question", "canonical_sql").agg(F.min("sql").alias("sql")), "one")
    out = one.join(truths, ["question", "canonical_sql"], "left_semi").select("question", "canonical_sql", F.lit(True).alias("correct"), F.lit("canonical form").alias("reason"))
    rest = one.join(truths, ["question", "canonical_sql"], "left_anti")
    rest = ws.save(rest.withColumn("part", F.floor((F.row_number().over(_by_question()) - 1) / batch)), "rest")
    for question, part in sorted(tuple(r) for r in rest.select("question", "part").distinct().collect()):
        rows = rest.where((F.col("question") == question) & (F.col("part") == part)).collect()
        told = _judge(spark, {str(k): r["sql"] for k, r in enumerate(rows)}, rights[question], tables, catalog)
        frame = [(question, r["canonical_sql"], *told[str(k)]) for k, r in enumerate(rows)]
        out = out.unionByName(ws.save(spark.createDataFrame(frame, "question int, canonical_sql string, correct boolean, reason string"), "batch"))
    return out


def _by_question():
    from pyspark.sql import Window

    return Window.partitionBy("question").orderBy("canonical_sql")


def with_verdict(subs: DataFrame, correct: DataFrame, tables: Dataset, catalog: Catalog | None = None) -> DataFrame:
    """subs with correct and reason; texts that do not parse are wrong, with their message."""
    forms = Workspace(subs.sparkSession, "forms").save(grade.with_forms(grade.unique_texts(subs), catalog))
    told = form_verdicts(forms, correct, tables, catalog)
    known = forms.select("question", "sql", "parse_error", "canonical_sql").join(told, ["question", "canonical_sql"], "left")
    known = known.select("question", "sql", F.coalesce("correct", F.lit(False)).alias("correct"), F.coalesce("reason", "parse_error").alias("reason"))
    return subs.join(known, ["question", "sql"], "left").select(*(subs[c] for c in subs.columns), known["correct"], known["reason"])


def run_grading(subs: DataFrame, correct: DataFrame, tables: Dataset, weights: distance.Weights = distance.Weights(), method: str = "greedy", catalog: Catalog | None = None) -> DataFrame:
    """The whole workflow: subs with correct, reason, marks, cost, edits and feedback. A query that all datasets call
    right has full marks although its canonical form differs; its edits still show the way to the nearest correct query."""
    graded = grade.feedback(grade.grade(subs, correct, weights, method, catalog))
    told = with_verdict(subs.select("question", "sql").distinct(), correct, tables, catalog)
    joined = graded.join(told, ["question", "sql"], "left")
    marks = F.when(F.col("correct"), F.lit(1.0)).otherwise(F.col("marks"))
    said = F.when(F.col("correct"), F.lit("Correct.")).otherwise(F.col("feedback"))
    return joined.select(*subs.columns, "correct", "reason", marks.alias("marks"), "cost", "edits", said.alias("feedback"))
