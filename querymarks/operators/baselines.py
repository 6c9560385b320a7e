"""Other ways to judge a query: what the main methods are compared with."""

from __future__ import annotations

import re
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import canon, ir
from ..plans.ir import Cmp, Col, Lit, Same, Table
from ..sources.catalog import Catalog, default_catalog


def normalized(sql: Column) -> Column:
    """Lower case, single spaces, no final semicolon."""
    return F.lower(F.trim(F.regexp_replace(F.regexp_replace(sql, r"\s+", " "), r"\s*;\s*$", "")))


def textual_match(subs: DataFrame, correct: DataFrame) -> DataFrame:
    """subs with textual_match: the text is that of a correct query but for spaces and case."""
    truths = correct.select("question", normalized(F.col("sql")).alias("__t")).distinct().withColumn("hit", F.lit(True))
    out = subs.withColumn("__t", normalized(F.col("sql"))).join(F.broadcast(truths), ["question", "__t"], "left")
    return out.withColumn("textual_match", F.coalesce("hit", F.lit(False))).drop("hit", "__t")


def binary_marks(graded: DataFrame) -> DataFrame:
    return graded.withColumn("binary_marks", F.when(F.col("cost") == 0, 1.0).otherwise(0.0))


def plan_match(spark: SparkSession, a: str, b: str, level: str = "optimized") -> bool:
    """Whether the engine's own plans are the same: optimized ones by their canonicalized form, analyzed ones by
    sameSemantics(). Plans only; nothing runs."""
    x, y = spark.sql(a), spark.sql(b)
    if level == "analyzed":
        return x.sameSemantics(y)
    plan = lambda d: d._jdf.queryExecution().optimizedPlan().canonicalized()
    return plan(x).equals(plan(y))


def _tableau(sql: str, catalog: Catalog) -> tuple[list, list] | None:
    """(head, rows) of a query that only joins, filters by equality and projects; variables are classes."""
    q, _ = canon.prepare(sql, catalog)
    if not isinstance(q, ir.Select) or q.group or q.having or q.limit is not None or not all(isinstance(x, Table) for x in q.frm.items):
        return None
    parent: dict[Any, Any] = {}

    def find(x: Any) -> Any:
        while parent.get(x, x) != x:
            x = parent[x]
        return x

    for p in q.frm.preds:
        members = p.members if isinstance(p, Same) else (p.left, p.right) if isinstance(p, Cmp) and p.op == "=" else None
        if members is None or not all(isinstance(m, (Col, Lit)) for m in members):
            return None
        for m in members[1:]:
            a, b = find(members[0]), find(m)
            if a != b:
                if isinstance(b, Lit):
                    a, b = b, a
                parent[b] = a
    if not all(isinstance(x.expr, (Col, Lit)) for x in q.items):
        return None
    rows = [(x.name, {c: find(Col(x.alias, c)) for c in catalog.table(x.name).columns}) for x in q.frm.items]
    return [find(x.expr) for x in q.items], rows


def _maps_to(a: tuple[list, list], b: tuple[list, list]) -> bool:
    """Whether the tableau ``a`` has a homomorphism to ``b``."""

    def bind(m: dict, x: Any, y: Any) -> dict | None:
        if isinstance(x, Lit):
            return m if x == y else None
        if x in m:
            return m if m[x] == y else None
        return {**m, x: y}

    if len(a[0]) != len(b[0]):
        return False
    start: dict | None = {}
    for x, y in zip(a[0], b[0]):
        start = bind(start, x, y) if start is not None else None

    def go(k: int, m: dict | None) -> bool:
        if m is None:
            return False
        if k == len(a[1]):
            return True
        name, vars_ = a[1][k]
        for other, theirs in b[1]:
            if other == name:
                n: dict | None = m
                for c, x in vars_.items():
                    n = bind(n, x, theirs[c]) if n is not None else None
                if go(k + 1, n):
                    return True
        return False

    return go(0, start)


def tableau_equivalent(a: str, b: str, catalog: Catalog | None = None) -> bool | None:
    """Equivalence of conjunctive queries as sets, by homomorphisms both ways; None outside that class."""
    catalog = catalog or default_catalog()
    x, y = _tableau(a, catalog), _tableau(b, catalog)
    return None if x is None or y is None else _maps_to(x, y) and _maps_to(y, x)
