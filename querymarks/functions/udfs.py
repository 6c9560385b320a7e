"""The methods as SQL functions: Arrow-batched scalars, an aggregate and table functions. register_all() names them."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache
from typing import Any

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import BooleanType, DoubleType, IntegerType, LongType, StringType, StructType

from ..operators.nodes import tree_nodes
from ..plans import canon, distance, ir
from ..plans.edits import Editor
from ..plans.mutants import mutants as mutants_of
from ..plans.search import Correct, Searcher
from ..sources.catalog import default_catalog


@lru_cache(1)
def _catalog() -> Any:
    return default_catalog()


@lru_cache(1)
def _searcher() -> Searcher:
    return Searcher(_catalog())


@lru_cache(4096)
def _correct(sql: str) -> Correct:
    return Correct.of("c", sql, _catalog())


def _safe(fn: Callable[..., Any], *args: Any) -> Any:
    try:
        return None if any(a is None for a in args) else fn(*args)
    except (ir.GradingError, RecursionError):
        return None


def _error(sql: str) -> str:
    try:
        canon.prepare(sql, _catalog())
        return ""
    except (ir.GradingError, RecursionError) as e:
        return str(e) or "nested too deeply"


def _form(sql: str) -> Any:
    return canon.canonicalize(sql, _catalog())


@pandas_udf(StringType())
def canonical_sql(sql: pd.Series) -> pd.Series:
    return sql.map(lambda s: _safe(lambda x: canon.canonical_text(x, _catalog()), s))


@pandas_udf(LongType())
def canonical_hash(sql: pd.Series) -> pd.Series:
    return sql.map(lambda s: _safe(lambda x: canon.fingerprint(canon.canonical_text(x, _catalog())), s)).astype("Int64")


@pandas_udf(IntegerType())
def query_size(sql: pd.Series) -> pd.Series:
    return sql.map(lambda s: _safe(lambda x: distance.query_size(canon.prepare(x, _catalog())[0]), s)).astype("Int32")


@pandas_udf(StringType())
def parse_error(sql: pd.Series) -> pd.Series:
    return sql.map(lambda s: "the query is empty" if s is None else _error(s))


@pandas_udf(DoubleType())
def edit_distance(student: pd.Series, correct: pd.Series) -> pd.Series:
    return pd.Series([_safe(lambda a, b: distance.edit_distance(_form(a), _correct(b).canonical), a, b) for a, b in zip(student, correct)], dtype="float64")


def _marks(student: str, correct: str, method: str) -> float:
    tree, shared = canon.prepare(student, _catalog())
    s = _searcher()
    return (s.greedy if method == "greedy" else s.shortest)(tree, _correct(correct), shared).marks


@pandas_udf(DoubleType())
def marks_greedy(student: pd.Series, correct: pd.Series) -> pd.Series:
    return pd.Series([_safe(lambda a, b: _marks(a, b, "greedy"), a, b) for a, b in zip(student, correct)], dtype="float64")


@pandas_udf(DoubleType())
def marks_exhaustive(student: pd.Series, correct: pd.Series) -> pd.Series:
    return pd.Series([_safe(lambda a, b: _marks(a, b, "exhaustive"), a, b) for a, b in zip(student, correct)], dtype="float64")


@pandas_udf(DoubleType())
def best_marks(marks: pd.Series) -> float:
    """The best marks of a group; none counts as 0."""
    return float(marks.fillna(0.0).max()) if len(marks) else 0.0


@udtf(returnType=StructType().add("component", StringType()).add("kind", StringType()).add("label", StringType()).add("ord", IntegerType()).add("ordered", BooleanType()))
class FlattenTree:
    def eval(self, sql: str) -> Iterator[tuple]:
        for row in _safe(lambda s: tree_nodes(_form(s)), sql) or ():
            yield row


@udtf(returnType=StructType().add("op", StringType()).add("component", StringType()).add("path", StringType()).add("before", StringType()).add("after", StringType()).add("cost", DoubleType()))
class GuidedEdits:
    def eval(self, student: str, correct: str) -> Iterator[tuple]:
        def run(a: str, b: str) -> list:
            tree, shared = canon.prepare(a, _catalog())
            c = _correct(b)
            return [s.edit for s in Editor(shared=shared).steps(_searcher().start(tree, c), c.tree)]

        for e in _safe(run, student, correct) or ():
            yield e.op, e.component, e.path, e.before, e.after, float(e.cost)


@udtf(returnType=StructType().add("step", IntegerType()).add("op", StringType()).add("component", StringType()).add("before", StringType()).add("after", StringType()).add("cost", DoubleType()))
class EditSequence:
    def eval(self, student: str, correct: str) -> Iterator[tuple]:
        def run(a: str, b: str) -> list:
            tree, shared = canon.prepare(a, _catalog())
            return _searcher().greedy(tree, _correct(b), shared).edits

        for k, e in enumerate(_safe(run, student, correct) or ()):
            yield k + 1, e.op, e.component, e.before, e.after, float(e.cost)


@udtf(returnType=StructType().add("kind", StringType()).add("change", StringType()).add("sql", StringType()))
class Mutants:
    def eval(self, sql: str) -> Iterator[tuple]:
        for kind, change, text in _safe(lambda s: mutants_of(s, _catalog()), sql) or ():
            yield kind, change, text


def register_all(spark: SparkSession) -> None:
    for name, fn in {"canonical_sql": canonical_sql, "canonical_hash": canonical_hash, "query_size": query_size, "parse_error": parse_error, "edit_distance": edit_distance, "marks_greedy": marks_greedy, "marks_exhaustive": marks_exhaustive, "best_marks": best_marks}.items():
        spark.udf.register(name, fn)
    for name, table in {"flatten_tree": FlattenTree, "guided_edits": GuidedEdits, "edit_sequence": EditSequence, "mutants": Mutants}.items():
        spark.udtf.register(name, table)
