"""The methods, baselines, measures and workloads as queries, with the SQL that each answers to."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable
from functools import reduce
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import udfs
from ..plans import canon, distance
from ..plans.render import render
from ..plans.search import Correct, Searcher
from ..session import Workspace
from ..sources import corpus
from ..sources import workloads as wl
from ..sources.catalog import default_catalog, participates, read_tables, register_tables
from ..streaming import stream
from . import baselines, datasets, frontier, grade, measures, nodes, verdict

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}
_SAVED: dict[tuple, Any] = {}


def _add(name: str, query: Query, oracle: str | None = None) -> None:
    _QUERIES[name] = query
    if oracle:
        _ORACLES[name] = oracle


def _values(rows: list[tuple], columns: str) -> str:
    show = lambda v: "NULL" if v is None else str(v).upper() if isinstance(v, bool) else repr(float(v)) + "::DOUBLE" if isinstance(v, float) else "'" + v.replace("'", "''") + "'" if isinstance(v, str) else str(v)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(show, r)) + ')' for r in rows)}) v({columns})"


def _correct_frame(spark: SparkSession, base_only: bool = False) -> DataFrame:
    rows = [r for r in wl.correct_rows() if not base_only or r[1] in wl.BASE.values()]
    return spark.createDataFrame(rows, "question int, cq_id string, sql string")


def _signature(spark: SparkSession, sf_dir: str) -> tuple:
    """Names, sizes and times of the tables' files: what is kept for them lasts until one changes."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(sf_dir)
    files = folder.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(folder)
    return tuple(sorted((x.getPath().getName(), x.getLen(), x.getModificationTime()) for x in files))


def _once(spark: SparkSession, key: tuple, make: Callable[[], Any]) -> Any:
    """What several queries need is computed once a session, as long as the tables (named second in the key) stay."""
    key = (spark.sparkContext.applicationId, _signature(spark, key[1]), *key)
    if key not in _SAVED:
        _SAVED[key] = make()
    return _SAVED[key]


def _forms(spark: SparkSession, sf_dir: str) -> DataFrame:
    def make() -> DataFrame:
        return Workspace(spark, "forms").save(grade.with_forms(grade.unique_texts(corpus.submissions(spark, sf_dir))))

    return _once(spark, ("forms", sf_dir), make)


def _pairs(spark: SparkSession, sf_dir: str, method: str, base_only: bool = True, off: tuple[str, ...] = ()) -> DataFrame:
    def make() -> DataFrame:
        correct = grade.collect_correct(_correct_frame(spark, base_only))
        return Workspace(spark, "pairs").save(grade.search_pairs(_forms(spark, sf_dir), correct, method, off=off))

    return _once(spark, ("pairs", sf_dir, method, base_only, off), make)


def _graded(spark: SparkSession, sf_dir: str, method: str, base_only: bool = True) -> DataFrame:
    return grade.attach(corpus.submissions(spark, sf_dir), _forms(spark, sf_dir), grade.best_of(_pairs(spark, sf_dir, method, base_only)))


def graded_marks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sub_id, question, cost, marks, n_edits of every submission against its base query, greedily."""
    return _graded(spark, sf_dir, "greedy").select("sub_id", "question", F.round("cost", 6).alias("cost"), F.round("marks", 6).alias("marks"), F.col("n_edits").cast("long").alias("n_edits"))


# -- the submissions in SQL, from the events and the table of hand-derived costs alone
_COSTS_SQL = ", ".join(f"({q}, {', '.join(map(str, c))}, {corpus.TOTALS[q]})" for q, c in corpus.COSTS.items())
TRUTH_SQL = f"""
WITH hand(question, f0, f1, f2, f3, f4, total) AS (VALUES {_COSTS_SQL}),
coded AS (SELECT event_id AS sub_id, user_id, ts, CAST(event_id % 15 + 1 AS INT) AS question, CAST(event_id // 15 % 32 AS INT) AS mask FROM events),
truth AS (
  SELECT c.*, h.total, CAST((mask & 1) * f0 + (mask >> 1 & 1) * f1 + (mask >> 2 & 1) * f2 + (mask >> 3 & 1) * f3 + (mask >> 4 & 1) * f4 AS DOUBLE) AS cost,
         CAST((mask & 1) * sign(f0) + (mask >> 1 & 1) * f1 + (mask >> 2 & 1) * f2 + (mask >> 3 & 1) * f3 + (mask >> 4 & 1) * f4 AS BIGINT) AS n_edits
  FROM coded c JOIN hand h USING (question)
), marked AS (SELECT *, greatest(0.0, total - cost) / total AS marks FROM truth)
"""
# A cost of all that a query is worth leaves no marks; then no sequence is reported.
_MARKS_SQL = TRUTH_SQL + "SELECT sub_id, question, CAST(least(cost, total) AS DOUBLE) AS cost, round(marks, 6) AS marks, CASE WHEN marks = 0 THEN 0 ELSE n_edits END AS n_edits FROM marked"


def _marks_query(method: str) -> Query:
    return lambda spark, d: _graded(spark, d, method).select("sub_id", "question", F.round("cost", 6).alias("cost"), F.round("marks", 6).alias("marks"), F.col("n_edits").cast("long").alias("n_edits"))


_add("path_greedy_marks", _marks_query("greedy"), _MARKS_SQL)
_add("path_exhaustive_marks", _marks_query("exhaustive"), _MARKS_SQL)
_add("path_best_of_many", lambda s, d: _graded(s, d, "greedy", False).join(_graded(s, d, "greedy").select("sub_id", F.col("marks").alias("base")), "sub_id").select("sub_id", (F.col("marks") >= F.col("base") - 1e-9).alias("no_worse")), "SELECT event_id AS sub_id, TRUE AS no_worse FROM events")
_EDITS = "array<struct<component:string,cost:double>>"
# Hand-derived: f0 edits the outputs, f1 and f2 conditions, f3 DISTINCT or a subquery's connective, f4 a relation.
_KINDS_SQL = TRUTH_SQL + """, done AS (SELECT m.*, h.f0 FROM marked m JOIN hand h USING (question) WHERE marks > 0), edits AS (
  SELECT 'projection' AS component, CAST(f0 AS DOUBLE) AS cost FROM done WHERE mask & 1 = 1
  UNION ALL SELECT 'predicate', 1.0 FROM done WHERE mask & 2 = 2 AND question <> 1
  UNION ALL SELECT 'predicate', 1.0 FROM done WHERE mask & 4 = 4
  UNION ALL SELECT CASE WHEN question IN (3, 14) THEN 'distinct' ELSE 'subquery' END, 1.0 FROM done WHERE mask & 8 = 8 AND question IN (3, 6, 7, 8, 9, 11, 12, 14, 15)
  UNION ALL SELECT 'relation', 1.0 FROM done WHERE mask & 16 = 16
) SELECT component, count(*) AS n, sum(cost) AS cost FROM edits GROUP BY component"""
_add(
    "path_edit_kinds",
    lambda s, d: _graded(s, d, "exhaustive").select(F.explode(F.from_json("edits", _EDITS)).alias("e")).groupBy(F.col("e.component").alias("component")).agg(F.count("*").alias("n"), F.sum("e.cost").alias("cost")),
    _KINDS_SQL,
)
_add("path_feedback", lambda s, d: grade.feedback(_graded(s, d, "greedy")).select("sub_id", (F.col("feedback") == "Correct.").alias("told_correct")), TRUTH_SQL + "SELECT sub_id, cost = 0 AS told_correct FROM marked")
_add("path_marks_by_question", lambda s, d: _graded(s, d, "greedy").groupBy("question").agg(F.count("*").alias("n"), F.count_if(F.col("cost") == 0).alias("full"), F.round(F.sum("marks"), 4).alias("sum_marks")), TRUTH_SQL + "SELECT question, count(*) AS n, count(*) FILTER (cost = 0) AS full, round(sum(marks), 4) AS sum_marks FROM marked GROUP BY question")


# -- worked examples with known distances: (correct, student, participation declared, distance, cost)
EXAMPLES: dict[str, tuple[str, str, bool, float, float]] = {
    "failure_class": ("SELECT c_custkey FROM customer JOIN supplier ON c_nationkey = s_nationkey WHERE c_nationkey > 10", "SELECT c_custkey FROM customer JOIN supplier ON c_nationkey = s_suppkey WHERE s_nationkey > 10", False, 2.0, 1.0),
    "failure_join": ("SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderstatus = 'F'", "SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey", True, 4.0, 1.0),
    "failure_join_undeclared": ("SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderstatus = 'F'", "SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey", False, 1.0, 1.0),
    "edit_direction": ("SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderstatus = 'F'", "SELECT c_custkey, c_name FROM customer", False, 4.0, 4.0),
    "with_origin": ("SELECT a.k FROM (SELECT c_custkey AS k FROM customer WHERE c_acctbal > 5) a, (SELECT c_custkey AS k FROM customer WHERE c_acctbal > 5) b WHERE a.k < b.k", "WITH r AS (SELECT c_custkey AS k FROM customer WHERE c_acctbal > 6) SELECT a.k FROM r a, r b WHERE a.k < b.k", False, 2.0, 1.0),
    "dangling_relation": ("SELECT c_custkey FROM customer", "SELECT c_custkey FROM customer, region WHERE r_regionkey > 2", False, 2.0, 2.0),
    "filter_in_outer_join": ("SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id AND quality = 0", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE quality = 0", False, 5.0, 1.0),
    "order_reorder": ("SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey", "SELECT o_orderkey FROM orders ORDER BY o_orderkey, o_orderdate", False, 1.0, 1.0),
    "except_branch": ("SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'", "SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'", False, 1.0, 1.0),
    "aggregate": ("SELECT o_custkey, sum(o_totalprice) FROM orders GROUP BY o_custkey", "SELECT o_custkey, avg(o_totalprice) FROM orders GROUP BY o_custkey", False, 1.0, 1.0),
    "group_by_insert": ("SELECT o_custkey, o_orderstatus, count(*) FROM orders GROUP BY o_custkey, o_orderstatus", "SELECT o_custkey, o_orderstatus, count(*) FROM orders GROUP BY o_custkey", False, 1.0, 1.0),
    "group_by_delete": ("SELECT o_custkey, count(*) FROM orders GROUP BY o_custkey", "SELECT o_custkey, count(*) FROM orders GROUP BY o_custkey, o_orderstatus", False, 1.0, 1.0),
    "group_by_replace": ("SELECT max(o_totalprice) FROM orders GROUP BY o_orderstatus", "SELECT max(o_totalprice) FROM orders GROUP BY o_orderpriority", False, 1.0, 1.0),
    # By distance the join with the parent is redundant for the student: relation, join, condition and output differ.
    "outer_join": ("SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey, o_orderkey FROM customer JOIN orders ON c_custkey = o_custkey", False, 4.0, 1.0),
    # A subquery is worth its connective, relation and two conditions.
    "subquery_insert": (
        "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')",
        "SELECT c_custkey FROM customer", False, 4.0, 4.0,
    ),
    "subquery_delete": (
        "SELECT c_custkey, c_name, c_acctbal FROM customer WHERE c_acctbal > 5",
        "SELECT c_custkey, c_name, c_acctbal FROM customer WHERE c_acctbal > 5 AND NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')", False, 4.0, 4.0,
    ),
    # Between a block and a set operator the distance is what the larger is worth; the edit adds or drops one branch.
    "except_insert": ("SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'", "SELECT c_custkey FROM customer", False, 6.0, 4.0),
    "intersect_insert": ("SELECT c_custkey FROM customer INTERSECT SELECT o_custkey FROM orders", "SELECT c_custkey, c_name FROM customer", False, 5.0, 4.0),
    "union_delete": ("SELECT c_custkey, c_name FROM customer WHERE c_acctbal > 5", "SELECT c_custkey, c_name FROM customer WHERE c_acctbal > 5 UNION SELECT s_suppkey, s_name FROM supplier", False, 8.0, 4.0),
}
#: The same for edits that only the extended editor makes.
EXTENDED: dict[str, tuple[str, str, bool, float, float]] = {
    "set_kind": ("SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier", "SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier", False, 1.0, 1.0),
    "limit": ("SELECT p_name FROM part ORDER BY p_partkey LIMIT 5", "SELECT p_name FROM part ORDER BY p_partkey LIMIT 10", False, 1.0, 1.0),
    "having": ("SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(*) > 3", "SELECT o_custkey FROM orders GROUP BY o_custkey HAVING count(*) > 2", False, 1.0, 1.0),
}


def measure_example(name: str) -> tuple[float, float, float]:
    """(distance, exhaustive cost, greedy cost)"""
    correct, student, declared, _, _ = (EXAMPLES | EXTENDED)[name]
    catalog = default_catalog().changed(participation=(("orders", "o_custkey"),)) if declared else default_catalog()
    c = Correct.of(name, correct, catalog)
    tree, shared = canon.prepare(student, catalog)
    s = Searcher(catalog, extended=name in EXTENDED)
    return distance.edit_distance(canon.semantic(tree, catalog), c.canonical), s.shortest(tree, c, shared).cost, s.greedy(tree, c, shared).cost


for _name, _e in (EXAMPLES | EXTENDED).items():
    _add(f"path_{_name}", lambda s, d, n=_name: s.createDataFrame([measure_example(n)], "distance double, exhaustive double, greedy double"), _values([(_e[3], _e[4], _e[4])], "distance, exhaustive, greedy"))

_FRONTIER = [(f"{q}-{m}", q, m) for q in (5, 8, 13) for m in (0, 1, 6, 13)]
_add(
    "path_frontier",
    lambda s, d: frontier.shortest_path_frontier(s.createDataFrame([(p, corpus.submission_text(q, m, 3), wl.CORRECT[wl.BASE[q]]) for p, q, m in _FRONTIER], "pair string, student string, correct string")).select("pair", "cost", F.round("marks", 6).alias("marks")),
    _values([(p, float(c := sum(k for i, k in enumerate(corpus.COSTS[q]) if m >> i & 1)), round((corpus.TOTALS[q] - c) / corpus.TOTALS[q], 6)) for p, q, m in _FRONTIER], "pair, cost, marks"),
)


#: Columns of part whose conditions a student gets wrong, all at once: the ways to mend them multiply.
_HARD_COLUMNS = ("p_size", "p_retailprice", "p_partkey", "p_name", "p_brand", "p_type")


def hard_pair(n: int) -> tuple[str, str]:
    """(correct, student): n conditions, each with another constant."""
    said = lambda k: " AND ".join(f"{c} < '{k}x'" if c in ("p_name", "p_brand", "p_type") else f"{c} < {k}0" for c in _HARD_COLUMNS[:n])
    return tuple(f"SELECT p_partkey, p_name, p_brand, p_type, p_size FROM part WHERE {said(k)}" for k in (3, 4))


def _hard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """conditions, cost of both searches, and whether the exhaustive one took more states than the greedy one."""
    catalog, rows = default_catalog(), []
    for n in (2, 3, 4):
        correct, student = hard_pair(n)
        c, tree, s = Correct.of("c", correct, catalog), canon.prepare(student, catalog)[0], Searcher(catalog)
        e, g = s.shortest(tree, c), s.greedy(tree, c)
        rows.append((n, e.cost, g.cost, e.states > g.states))
    return spark.createDataFrame(rows, "conditions int, exhaustive double, greedy double, more_states boolean")


_add("path_hard", _hard, _values([(n, float(n), float(n), True) for n in (2, 3, 4)], "conditions, exhaustive, greedy, more_states"))


def _capped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Searches stopped after five states, and the same pairs finished by the search over a table."""
    pairs = [hard_pair(n) for n in (1, 2, 3)]
    forms = Workspace(spark, "forms").save(grade.with_forms(spark.createDataFrame([(n + 1, p[1]) for n, p in enumerate(pairs)], "question int, sql string")))
    rights = [(n + 1, "c", p[0]) for n, p in enumerate(pairs)]
    stopped = Workspace(spark, "stopped").save(grade.search_pairs(forms, rights, "exhaustive", most_states=5))
    done = grade.finish_capped(stopped, forms, rights).select("question", "cost", F.round("marks", 6).alias("marks"), "status", F.col("n_edits").cast("long").alias("n_edits"))
    return done.join(stopped.select("question", (F.col("status") == "capped").alias("was_capped"), F.col("marks").isNull().alias("had_no_marks")), "question")


_add(
    "path_capped_then_finished", _capped,
    _values([(n, float(n), round(6 / (6 + n), 6), "exact", n, n > 1, n > 1) for n in (1, 2, 3)], "question, cost, marks, status, n_edits, was_capped, had_no_marks"),
)


# -- workloads and rules: Spark runs the canonical rendering, the oracle is the text as written
def _run(sql: str, declared: bool = False) -> Query:
    """``declared``: every customer has orders, which is used only where it holds in the tables at hand."""

    def go(spark: SparkSession, sf_dir: str) -> DataFrame:
        catalog = default_catalog()
        register_tables(spark, sf_dir)
        (buys,) = catalog.table("orders").foreign
        if declared and participates(read_tables(spark, sf_dir, ("customer", "orders")), buys, "orders"):
            catalog = catalog.changed(participation=(("orders", "o_custkey"),))
        return spark.sql(render(canon.canonicalize(sql, catalog)))

    return go


for _k, _text in {**wl.CORRECT, **wl.EXTRA}.items():
    _add(f"wl_{_k}", _run(_text), _text)
for _k, (_text, _) in wl.RULE_PAIRS.items():
    _add(f"{'syn' if _k[0] == 's' else 'sem'}_{_k}", _run(_text), _text)
_add("sem_c07b", _run(wl.PARTICIPATION_PAIR[0], True), wl.PARTICIPATION_PAIR[0])
for _k, (_text, _) in wl.GUARDS.items():
    _add(f"guard_{_k}", _run(_text), _text)

# -- distances over node tables
_LEFT = [("a", "projection", "c_custkey"), ("a", "projection", "c_custkey"), ("a", "relation", "customer"), ("a", "relation", "orders"), ("a", "predicate", "p1"), ("a", "distinct", "distinct"), ("b", "projection", "x"), ("b", "aggregate", "sum(y)"), ("b", "group_by", "x"), ("b", "having", "h"), ("b", "order_by", "x"), ("b", "limit", "5"), ("b", "set_op", "union"), ("b", "join_type", "left orders"), ("b", "subquery", "exists")]
_RIGHT = [("a", "projection", "c_custkey"), ("a", "projection", "c_name"), ("a", "relation", "customer"), ("a", "predicate", "p1"), ("a", "predicate", "p2"), ("b", "projection", "x"), ("b", "aggregate", "avg(y)"), ("b", "group_by", "x"), ("b", "group_by", "z"), ("b", "order_by", "z"), ("b", "limit", "6"), ("b", "set_op", "except"), ("b", "subquery", "not exists")]
_DISTANCE_SQL = """
keys AS (SELECT pair, component FROM l UNION SELECT pair, component FROM r),
x AS (SELECT pair, component, count(*) AS extra FROM (SELECT * FROM l EXCEPT ALL SELECT * FROM r) GROUP BY ALL),
m AS (SELECT pair, component, count(*) AS missing FROM (SELECT * FROM r EXCEPT ALL SELECT * FROM l) GROUP BY ALL),
d AS (SELECT pair, component, CAST(coalesce(missing, 0) AS BIGINT) AS missing, CAST(coalesce(extra, 0) AS BIGINT) AS extra, CAST(greatest(coalesce(missing, 0), coalesce(extra, 0)) AS BIGINT) AS distance FROM keys LEFT JOIN x USING (pair, component) LEFT JOIN m USING (pair, component))
"""
_NODE_SQL = f"""
WITH l AS ({_values(_LEFT, "pair, component, label")}), r AS ({_values(_RIGHT, "pair, component, label")}),{_DISTANCE_SQL}"""
# Each event is a node: of its user's pair of trees, on the side and of the component that its id says, named by its type.
_EVENT_NODE_SQL = f"""
WITH n AS (SELECT CAST(user_id AS VARCHAR) AS pair, event_id % 2 AS side, ({list(distance.COMPONENTS)})[CAST(event_id // 2 % {len(distance.COMPONENTS)} AS INT) + 1] AS component, event_type AS label FROM events),
l AS (SELECT pair, component, label FROM n WHERE side = 0), r AS (SELECT pair, component, label FROM n WHERE side = 1),{_DISTANCE_SQL}"""


def _node_parts(spark: SparkSession) -> DataFrame:
    frame = lambda rows: spark.createDataFrame(rows, "pair string, component string, label string")
    return nodes.component_distance(frame(_LEFT), frame(_RIGHT))


def _event_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = F.array(*map(F.lit, distance.COMPONENTS))
    events = read_tables(spark, sf_dir, ("events",))["events"]
    component = names[F.expr(f"cast(event_id div 2 % {len(distance.COMPONENTS)} as int)")].alias("component")
    each = events.select((F.col("event_id") % 2).alias("side"), F.col("user_id").cast("string").alias("pair"), component, F.col("event_type").alias("label"))
    return nodes.component_distance(each.where("side = 0"), each.where("side = 1"))


for _c in distance.COMPONENTS:
    if _c not in ("set_op", "subquery"):
        _add(f"ced_{_c}", lambda s, d, c=_c: _event_parts(s, d).where(F.col("component") == c).select("pair", "component", "missing", "extra", "distance"), _EVENT_NODE_SQL + f"SELECT pair, component, missing, extra, distance FROM d WHERE component = '{_c}'")
for _c in ("set_op", "subquery"):
    _add(f"ced_{_c}", lambda s, d, c=_c: _node_parts(s).where(F.col("component") == c).select("pair", "component", "missing", "extra", "distance"), _NODE_SQL + f"SELECT pair, component, missing, extra, distance FROM d WHERE component = '{_c}'")
_WEIGHTS = [("predicate", 2.0), ("projection", 0.5)]
_add("ced_weighted", lambda s, d: nodes.weighted_distance(_node_parts(s), s.createDataFrame(_WEIGHTS, "component string, weight double")), _NODE_SQL + f"SELECT pair, sum(distance * coalesce(weight, 1.0)) AS distance FROM d LEFT JOIN ({_values(_WEIGHTS, 'component, weight')}) w USING (component) GROUP BY pair")


def _corpus_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances of the flat questions 3 and 14, from node tables of canonical trees."""
    rows = [(f"{q}-{m}", corpus.submission_text(q, m, 2), wl.CORRECT[wl.BASE[q]]) for q in (3, 14) for m in range(32)]
    frame = spark.createDataFrame(rows, "query_id string, student string, correct string")
    side = lambda c: nodes.nodes(frame.select("query_id", F.col(c).alias("sql"))).select(F.col("query_id").alias("pair"), "component", "label")
    parts = nodes.component_distance(side("student"), side("correct"))
    return parts.groupBy("pair").agg(F.sum("distance").alias("distance"))


_add("ced_total", _corpus_nodes, _values([(f"{q}-{m}", sum(k for i, k in enumerate(corpus.COSTS[q]) if m >> i & 1)) for q in (3, 14) for m in range(32)], "pair, distance"))
_add("ced_marks_by_distance", lambda s, d: _graded(s, d, "greedy").where("question IN (3, 14)").select("sub_id", F.round("distance_marks", 6).alias("marks")), TRUTH_SQL + "SELECT sub_id, round(marks, 6) AS marks FROM marked WHERE question IN (3, 14)")
_add("ced_against_path", lambda s, d: _pairs(s, d, "exhaustive").groupBy("question").agg(F.count("*").alias("forms"), F.count_if(F.col("distance") > F.col("cost")).alias("distance_higher"), F.count_if(F.col("distance") < F.col("cost")).alias("distance_lower")))

# -- reports
_P = "SELECT sum(submitted) AS submitted, sum(data) AS data, sum(canon) AS canon, sum(false_pos_data) AS false_pos_data, round(100.0 * sum(canon) / (sum(data) - sum(false_pos_data)), 1) AS accuracy FROM"
_add(
    "rep_published_equivalence",
    lambda s, d: measures.published_equivalence(s).agg(*(F.sum(c).alias(c) for c in ("submitted", "data", "canon", "false_pos_data"))).withColumn("accuracy", measures.share(F.col("canon"), F.col("data") - F.col("false_pos_data"))),
    f"{_P} ({_values(list(measures.PUBLISHED_EQUIVALENCE), 'question, submitted, correct, size, data, canon, false_pos_data')})",
)
_add(
    "rep_published_equivalence_each",
    lambda s, d: measures.published_equivalence(s).select("question", measures.share(F.col("canon"), F.col("data") - F.col("false_pos_data")).alias("accuracy")),
    f"SELECT question, round(100.0 * canon / (data - false_pos_data), 1) AS accuracy FROM ({_values(list(measures.PUBLISHED_EQUIVALENCE), 'question, submitted, correct, size, data, canon, false_pos_data')})",
)
_add(
    "rep_published_fairness",
    lambda s, d: measures.published_fairness(s).agg(F.sum("pairs").alias("pairs"), measures.share(F.sum("distance_matches"), F.sum("pairs")).alias("distance_accuracy"), measures.share(F.sum("edit_matches"), F.sum("pairs")).alias("edit_accuracy")),
    f"SELECT sum(pairs) AS pairs, round(100.0 * sum(d) / sum(pairs), 1) AS distance_accuracy, round(100.0 * sum(e) / sum(pairs), 1) AS edit_accuracy FROM ({_values(list(measures.PUBLISHED_FAIRNESS), 'question, pairs, d, e')})",
)
_add(
    "rep_published_search",
    lambda s, d: measures.published_search(s).join(measures.published_equivalence(s).select("question", "submitted", "data"), "question").select("question", "incorrect", (F.col("incorrect") == F.col("submitted") - F.col("data")).alias("agrees"), F.round(F.col("exhaustive_ms") / F.col("greedy_ms"), 1).alias("ratio")),
    f"SELECT question, incorrect, TRUE AS agrees, round(e / g, 1) AS ratio FROM ({_values(list(measures.PUBLISHED_SEARCH), 'question, incorrect, g, e, capped')})",
)
_N, _C, _G = measures.PUBLISHED_USAGE
_add(
    "rep_published_usage", lambda s, d: measures.contest_report(s.range(_N).select((F.col("id") < _C).alias("contested"), (F.col("id") < _G).alias("genuine"))),
    f"SELECT {_N} AS graded, {_C} AS contested, {_G} AS genuine, round(100.0 * {_C} / {_N}, 3) AS contested_share, round(100.0 * {_G} / {_C}, 1) AS genuine_share",
)


def _scale_up(spark: SparkSession, sf_dir: str) -> DataFrame:
    """factor, submissions, texts, forms: what is left to parse and to search when there are more submissions."""
    subs, parts = corpus.submissions(spark, sf_dir), []
    for factor in (1, 4, 16):
        more = subs.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(factor))))
        texts = grade.unique_texts(more).join(_forms(spark, sf_dir).select("question", "sql", "form"), ["question", "sql"])
        told = texts.agg(F.count(F.lit(1)).alias("texts"), F.countDistinct("question", "form").alias("forms"))
        parts.append(more.agg(F.count(F.lit(1)).alias("submissions")).crossJoin(told).select(F.lit(factor).alias("factor"), "submissions", "texts", "forms"))
    return reduce(DataFrame.unionByName, parts)


_add(
    "rep_scale_up", lambda s, d: _scale_up(s, d).select("factor", "submissions", "forms"),
    TRUTH_SQL + "SELECT f AS factor, count(*) * f AS submissions, count(DISTINCT question * 32 + CASE WHEN question = 1 THEN mask & ~2 WHEN question = 13 THEN mask & ~8 ELSE mask END) AS forms FROM truth, (VALUES (1), (4), (16)) v(f) GROUP BY f",
)
_BUCKETS = [(0.5, 0.4001), (0.5, 0.4), (0.4, 0.5), (0.7, 0.7), (1.0, 0.0), (0.35, 0.25)]
_add(
    "rep_buckets",
    lambda s, d: s.createDataFrame(_BUCKETS, "a double, b double").select("a", "b", measures.bucket(F.col("a"), F.col("b")).alias("bucket"), measures.bucket(F.col("a"), F.col("b"), relative=True).alias("relative")),
    f"SELECT a, b, CASE WHEN round(abs(a - b), 9) >= 0.1 THEN CASE WHEN a > b THEN 'first' ELSE 'second' END ELSE 'same' END AS bucket, CASE WHEN round(abs(a - b), 9) >= round(0.1 * greatest(a, b), 9) AND a <> b THEN CASE WHEN a > b THEN 'first' ELSE 'second' END ELSE 'same' END AS relative FROM ({_values(_BUCKETS, 'a, b')})",
)
_THIN = {"orders": "o_orderkey % 3 = 1", "lineitem": "l_orderkey % 15 = 1"}


def class_texts(question: int) -> dict[str, str]:
    """Every combination of faults in the first spelling, and two forms that rules are known to miss: the right query
    united and intersected with itself."""
    right = corpus.submission_text(question, 0, 0)
    return {str(m): corpus.submission_text(question, m, 0) for m in range(32)} | {"united": f"({right}) UNION ({right})", "intersected": f"({right}) INTERSECT ({right})"}


def _class_rows(question: int) -> dict[str, list[tuple]]:
    """Rows made for the conditions of the right query and of those with another or one more condition."""
    out: dict[str, list[tuple]] = {}
    for m in (0, 2, 4):
        for t, rows in verdict.made_rows(corpus.submission_text(question, m, 0), default_catalog(), 1 + 100 * m).items():
            out.setdefault(t, []).extend(rows)
    return out


#: Forms that _judged() runs in one job: what their joins send to all tasks stands in the driver together.
JUDGED = 4


def _judged(spark: SparkSession, sf_dir: str, question: int) -> DataFrame:
    """question, text, data_correct (on the tables as they are), canonical_match, truly_correct (on those, on thinner
    ones and on ones with rows made for the conditions). Only one query of each canonical form runs."""

    def make() -> DataFrame:
        catalog, tables = default_catalog(), read_tables(spark, sf_dir, datasets.STAR)
        texts, right = class_texts(question), wl.CORRECT[wl.BASE[question]]
        form = {k: canon.canonical_text(t, catalog) for k, t in texts.items()}
        first = {f: k for k, f in reversed(form.items())}
        thin = tables | {t: tables[t].where(c) for t, c in _THIN.items()}
        made = tables | {t: tables[t].unionByName(spark.createDataFrame(rows, tables[t].schema)) for t, rows in _class_rows(question).items()}

        def passed(names: Iterable[str], data: datasets.Dataset) -> set[str]:
            some, out = list(names), set()
            for k in range(0, len(some), JUDGED):
                told = datasets.verdicts(spark, {x: texts[x] for x in some[k : k + JUDGED]}, right, {"d": data})
                with datasets.few_sent(spark):
                    out |= {r["query"] for r in told.collect() if r["passed"]}
            return out

        fixed = passed(first.values(), tables)
        true = passed(fixed, thin) & passed(fixed, made) if fixed else set()
        rows = [(question, k, first[form[k]] in fixed, form[k] == canon.canonical_text(right, catalog), first[form[k]] in true) for k in texts]
        return Workspace(spark, "judged").save(spark.createDataFrame(rows, "question int, text string, data_correct boolean, canonical_match boolean, truly_correct boolean"))

    return _once(spark, ("judged", sf_dir, question), make)


def _judged_sql(question: int) -> str:
    """The same judgement from the texts as written: a table's name is that of the table in a dataset, and digests of
    whole results are compared. A canonical match is expected where the hand-derived cost is 0."""
    import datetime
    import re

    show = lambda v: f"TIMESTAMP '{v}'" if isinstance(v, datetime.datetime) else "'" + v.replace("'", "''") + "'" if isinstance(v, str) else f"{v!r}::DOUBLE" if isinstance(v, float) else str(v)
    tables = [f"{t}__thin AS (SELECT * FROM {t}{' WHERE ' + _THIN[t] if t in _THIN else ''})" for t in datasets.STAR]
    made = _class_rows(question)
    for t in datasets.STAR:
        more = f" UNION ALL SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(show, r)) + ')' for r in made[t])}) v" if t in made else ""
        tables.append(f"{t}__made AS (SELECT * FROM {t}{more})")
    on = lambda sql, data: re.sub(rf"\b({'|'.join(datasets.STAR)})\b", lambda m: m[1] + data, sql)
    texts = {**class_texts(question), "right": wl.CORRECT[wl.BASE[question]]}
    parts = [f"SELECT '{k}' AS text, '{d}' AS data, count(*) AS n, sum(hash(x)) AS h FROM ({on(t, d)}) x" for k, t in texts.items() for d in ("", "__thin", "__made")]
    costs = {str(m): sum(c for i, c in enumerate(corpus.COSTS[question]) if m >> i & 1) for m in range(32)}
    hand = ", ".join(f"('{k}', {str(costs.get(k) == 0).upper()})" for k in class_texts(question))
    return f"""WITH {', '.join(tables)}, told AS ({' UNION ALL '.join(parts)}),
same AS (SELECT a.text, a.data, a.n = b.n AND a.h IS NOT DISTINCT FROM b.h AS same FROM told a JOIN told b ON b.text = 'right' AND a.data = b.data)
SELECT {question} AS question, c.text, bool_and(same) FILTER (data = '') AS data_correct, c.matched AS canonical_match, bool_and(same) AS truly_correct
FROM (VALUES {hand}) c(text, matched) JOIN same s ON s.text = c.text GROUP BY c.text, c.matched"""


_REPORT_SQL = """SELECT question, count(*) AS submitted, count(*) FILTER (data_correct) AS data, count(*) FILTER (canonical_match) AS canon,
count(*) FILTER (data_correct AND NOT truly_correct) AS false_pos_data,
round(100.0 * count(*) FILTER (canonical_match) / count(*) FILTER (data_correct AND truly_correct), 1) AS accuracy FROM"""
for _q in range(1, 16):
    _add(f"base_fixed_dataset_q{_q}", lambda s, d, q=_q: _judged(s, d, q), _judged_sql(_q))
    _add(f"rep_equivalence_q{_q}", lambda s, d, q=_q: measures.equivalence_report(_judged(s, d, q)), f"{_REPORT_SQL} ({_judged_sql(_q)}) GROUP BY question")


#: Rules that turn outer joins inner and drop redundant relations: without them marks are less lenient.
_LENIENT = ("C7", "C7b", "C8", "C9", "C10")


def _fairness(spark: SparkSession, sf_dir: str, off: tuple[str, ...] = ()) -> DataFrame:
    """All pairs of the incorrect forms of a question: a stated set of at most 465. The reference is the hand-derived marks."""
    cost = {(q, m): sum(c for i, c in enumerate(corpus.COSTS[q]) if m >> i & 1) for q in corpus.EXERCISES for m in range(32)}
    hand = {(q, corpus.submission_text(q, m, 0)): max(0.0, corpus.TOTALS[q] - c) / corpus.TOTALS[q] for (q, m), c in cost.items() if c}
    ref = spark.createDataFrame([(*k, r) for k, r in hand.items()], "question int, sql string, ref double")
    marked = ref.join(grade.with_forms(ref.select("question", "sql")).select("question", "sql", "form"), ["question", "sql"])
    marked = marked.join(_pairs(spark, sf_dir, "greedy", off=off).select("question", "form", "marks", "distance_marks"), ["question", "form"])

    def side(k: int) -> DataFrame:
        return marked.select("question", F.col("form").alias(f"f{k}"), F.col("ref").alias(f"ref_{k}"), F.col("distance_marks").alias(f"distance_{k}"), F.col("marks").alias(f"edit_{k}"))

    return measures.fairness_report(side(1).join(side(2), "question").where("f1 < f2"))


#: Texts differ for all masks but those whose fault has no text: the second of question 1, the fourth of question 13.
_PAIRS_OF = {q: len({m & ~2 if q == 1 else m & ~8 if q == 13 else m for m in range(32) if sum(c for i, c in enumerate(corpus.COSTS[q]) if m >> i & 1)}) for q in corpus.COSTS}
_add("rep_fairness", _fairness)
_add(
    "rep_fairness_edit_match",
    lambda s, d: _fairness(s, d).select("question", "pairs", "edit_matches", (F.col("edit_matches") >= F.col("distance_matches")).alias("no_worse")),
    _values([(q, n * (n - 1) // 2, n * (n - 1) // 2, True) for q, n in _PAIRS_OF.items()], "question, pairs, edit_matches, no_worse"),
)


def _fairness_without(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matches of distance and edit marks with all rules and without the lenient ones."""
    picked = lambda df, x: df.select("question", "pairs", F.col("distance_matches").alias(f"distance_{x}"), F.col("edit_matches").alias(f"edit_{x}"))
    return picked(_fairness(spark, sf_dir), "all").join(picked(_fairness(spark, sf_dir, _LENIENT), "without"), ["question", "pairs"])


_add("rep_fairness_without_rules", _fairness_without)
_add(
    "rep_search_match",
    lambda s, d: measures.search_report(_pairs(s, d, "greedy"), _pairs(s, d, "exhaustive")).select("question", "pairs", "finished", "matches", "match_share"),
    TRUTH_SQL + ", forms AS (SELECT question, count(DISTINCT CASE WHEN question = 1 THEN mask & ~2 WHEN question = 13 THEN mask & ~8 ELSE mask END) AS n FROM truth GROUP BY question) SELECT question, n AS pairs, n AS finished, n AS matches, 100.0 AS match_share FROM forms",
)
_add("rep_search_times", lambda s, d: measures.search_report(_pairs(s, d, "greedy"), _pairs(s, d, "exhaustive")))
_KILLED = ("w03", "w05a", "w06b", "w08a", "w13")
_GROUPED = "SELECT o_custkey, o_orderstatus, sum(o_totalprice) AS worth FROM orders WHERE o_orderpriority LIKE '1%' GROUP BY o_custkey, o_orderstatus"


def _kills(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mutants of queries with all eight kinds of changes, on the whole tables without and with rows made for the
    conditions, and on a slice."""

    def make() -> DataFrame:
        ws, parts = Workspace(spark, "kills"), []
        queries = {**{k: wl.CORRECT[k] for k in _KILLED}, "grouped": _GROUPED}
        tables = {q: verdict.conditions(t, default_catalog())[0] for q, t in queries.items()}
        data = datasets.kill_datasets(read_tables(spark, sf_dir, datasets.STAR))
        part = {t: ws.save(data["slice1"][t], t) for t in sorted(set().union(*tables.values()))}
        for q, t in queries.items():
            own = {"whole": data["whole"], "slice1": data["slice1"] | part, "made": verdict.made_for(spark, [t], data["whole"])}
            parts.append(ws.save(datasets.kill_matrix(spark, t, own).withColumn("query", F.lit(q))))
        return ws.save(reduce(DataFrame.unionByName, parts))

    return _once(spark, ("kills", sf_dir), make)


_add("rep_kills", lambda s, d: measures.kill_report(_kills(s, d)))
_add(
    "rep_kill_kinds", lambda s, d: measures.kill_report(_kills(s, d)).select("kind", (F.col("killed") > 0).alias("some_killed")),
    _values([(k, True) for k in ("join", "comparison", "aggregate", "group_by", "like", "subquery", "set_op", "distinct")], "kind, some_killed"),
)
_add("rep_kill_matrix", lambda s, d: _kills(s, d).select("query", "mutant", "kind", "change", "killed", "by"))



def _ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rule, equal, of: how many of the rule pairs keep one canonical form without the rule; "-" is the full set."""
    catalog = default_catalog()
    rows = []
    for rule in ("-", *(f"S{k}" for k in (3, 4, 5, 7, 8, 9, 11, 12, 13)), "C7b", *(f"C{k}" for k in range(1, 18))):
        off = () if rule == "-" else (rule,)
        rows.append((rule, sum(canon.canonical_text(a, catalog, off) == canon.canonical_text(b, catalog, off) for a, b in wl.RULE_PAIRS.values()), len(wl.RULE_PAIRS)))
    return spark.createDataFrame(rows, "rule string, equal int, of int")


_add("rep_ablation", _ablation)
# -- other judges
def _textual_sql() -> str:
    """The texts as written, by what an event stands for, against those of the correct queries."""
    plain = lambda x: f"lower(trim(regexp_replace(regexp_replace({x}, '\\s+', ' ', 'g'), '\\s*;\\s*$', '')))"
    quoted = lambda x: "'" + x.replace("'", "''") + "'"
    texts = ", ".join(f"({q}, {m}, {s}, {quoted(t)})" for q, m, s, t in corpus.all_texts())
    rights = ", ".join(f"({q}, {quoted(t)})" for q, _, t in wl.correct_rows())
    return f"""WITH texts(question, mask, style, sql) AS (VALUES {texts}), rights(question, sql) AS (VALUES {rights}),
known AS (SELECT DISTINCT question, {plain('sql')} AS t FROM rights),
told AS (SELECT x.question, mask, style, k.t IS NOT NULL AS hit FROM texts x LEFT JOIN known k ON x.question = k.question AND {plain('x.sql')} = k.t),
coded AS (SELECT CAST(event_id % 15 + 1 AS INT) AS question, CAST(event_id // 15 % 32 AS INT) AS mask, CAST(event_id // 480 % 8 AS INT) AS style FROM events)
SELECT question, count(*) FILTER (hit) AS matches, count(*) AS n FROM coded JOIN told USING (question, mask, style) GROUP BY question"""


_add(
    "base_textual",
    lambda s, d: baselines.textual_match(corpus.submissions(s, d), _correct_frame(s)).groupBy("question").agg(F.count_if("textual_match").alias("matches"), F.count("*").alias("n")),
    _textual_sql(),
)
_add("base_binary", lambda s, d: baselines.binary_marks(_graded(s, d, "greedy")).select("sub_id", "binary_marks"), TRUTH_SQL + "SELECT sub_id, CASE WHEN cost = 0 THEN 1.0 ELSE 0.0 END AS binary_marks FROM marked")


def _of_events(spark: SparkSession, sf_dir: str, pairs: Iterable[str], judge: Callable[[str], tuple], columns: str) -> DataFrame:
    """sub_id, pair and the judgement of it, for each event: its id says which pair it hands in. Each pair that some event
    hands in is judged once."""
    names = F.array(*map(F.lit, pairs))
    handed = read_tables(spark, sf_dir, ("events",))["events"].select(F.col("event_id").alias("sub_id"), names[(F.col("event_id") % F.size(names)).cast("int")].alias("pair"))
    met = [r["pair"] for r in handed.select("pair").distinct().collect()]  # as few as pairs
    return handed.join(F.broadcast(spark.createDataFrame([(k, *judge(k)) for k in met], f"pair string, {columns}")), "pair").select("sub_id", "pair", *(c.split()[0] for c in columns.split(", ")))


def _of_events_sql(rows: list[tuple], columns: str) -> str:
    return f"SELECT event_id AS sub_id, {columns} FROM events JOIN ({_values([(k, *r) for k, r in enumerate(rows)], f'k, {columns}')}) p ON event_id % {len(rows)} = k"


def _plan_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_tables(spark, sf_dir)
    catalog = default_catalog()

    def judge(pair: str) -> tuple[bool, bool, bool]:
        a, b, _, _ = wl.PLAN_PAIRS[pair]
        return baselines.plan_match(spark, a, b), baselines.plan_match(spark, a, b, "analyzed"), canon.canonical_text(a, catalog) == canon.canonical_text(b, catalog)

    return _of_events(spark, sf_dir, wl.PLAN_PAIRS, judge, "optimized boolean, analyzed boolean, canonical boolean")


_add("base_plan_match", _plan_matches, _of_events_sql([(k, o, a, True) for k, (_, _, o, a) in wl.PLAN_PAIRS.items()], "pair, optimized, analyzed, canonical"))
_TABLEAUX = {
    "redundant_self_join": ("SELECT DISTINCT a.c_custkey FROM customer a, customer b WHERE a.c_nationkey = b.c_nationkey", "SELECT DISTINCT c_custkey FROM customer", True),
    "constant": ("SELECT DISTINCT c_custkey FROM customer WHERE c_nationkey = 3", "SELECT DISTINCT c_custkey FROM customer WHERE c_nationkey = 4", False),
    "order_of_joins": (wl.CORRECT["w04a"], "SELECT c_custkey FROM nation JOIN customer ON n_nationkey = c_nationkey WHERE 2 = n_regionkey", True),
    "outside": (wl.CORRECT["w03"], wl.CORRECT["w03"], None),
}
_add(
    "base_tableau", lambda s, d: _of_events(s, d, _TABLEAUX, lambda k: (baselines.tableau_equivalent(*_TABLEAUX[k][:2]),), "equivalent boolean"),
    _of_events_sql([(k, e) for k, (_, _, e) in _TABLEAUX.items()], "pair, equivalent"),
)
#: A student's reversed bound, a query about something else that is always empty, and a right one.
_NAIVE = {"reversed": "SELECT c_custkey FROM customer WHERE c_acctbal < 9000", "unrelated": "SELECT p_partkey FROM part WHERE p_size < 0", "right": "SELECT c_custkey FROM customer WHERE 9000 < c_acctbal"}
_NAIVE_RIGHT = "SELECT c_custkey FROM customer WHERE c_acctbal > 9000"


def _naive(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = read_tables(spark, sf_dir, ("customer", "part"))
    data = {"whole": t, "rich": t | {"customer": t["customer"].where("c_acctbal > 9000")}, "poor": t | {"customer": t["customer"].where("c_acctbal BETWEEN 0 AND 100")}, "empty": {k: df.limit(0) for k, df in t.items()}}
    naive = datasets.marks_by_datasets(spark, _NAIVE, _NAIVE_RIGHT, data)
    catalog = default_catalog()
    right = Correct.of("c", _NAIVE_RIGHT, catalog)
    path = [(k, round(Searcher(catalog).shortest(canon.prepare(q, catalog)[0], right).marks, 6)) for k, q in _NAIVE.items()]
    return naive.join(spark.createDataFrame(path, "query string, path_marks double"), "query")


# By datasets the unrelated query outranks the reversed bound; by edits it gets nothing.
_add("base_datasets_fraction", _naive, _values([("reversed", 0.25, 0, round(2 / 3, 6)), ("unrelated", 0.5, 0, 0.0), ("right", 1.0, 1, 1.0)], "query, marks, all_or_nothing, path_marks"))


_TWO = "SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderstatus = 'F' AND o_orderpriority = '1-URGENT'"
#: question, student, text, correct, reason: a cross join that DISTINCT undoes is right though no rule sees it, and one
#: more condition that the tables satisfy is wrong; the second query of question 14 asks for something else, and is right.
_CLASS = [
    (5, "same", corpus.submission_text(5, 0, 4), True, "canonical form"),
    (5, "other form", wl.CORRECT["w05b"], True, "canonical form"),
    (5, "wrong", corpus.submission_text(5, 2, 0), False, "datasets of the correct queries"),
    (5, "cross", corpus.submission_text(5, 16, 0), True, "all datasets"),
    (5, "extra", f"{_TWO} AND o_totalprice > -1", False, "datasets of the student's query"),
    (5, "united", f"({_TWO}) UNION ({_TWO})", True, "all datasets"),
    (5, "syntax", "SELECT FROM", False, "error: expected a name before 'FROM'"),
    (14, "second", wl.CORRECT["w14b"], True, "canonical form"),
    (14, "cross", corpus.submission_text(14, 16, 0), True, "all datasets"),
    (3, "many rows", "SELECT p_name FROM part WHERE p_size > (SELECT p_size FROM part)", False, "does not run"),
]


def _combined(spark: SparkSession, sf_dir: str) -> DataFrame:
    def make() -> DataFrame:
        subs = spark.createDataFrame([c[:3] for c in _CLASS], "question int, student string, sql string")
        told = verdict.run_grading(subs, _correct_frame(spark).where("question IN (3, 5, 14)"), read_tables(spark, sf_dir, datasets.STAR))
        return Workspace(spark, "graded").save(told)

    return _once(spark, ("combined", sf_dir), make)


_add("ver_combined", lambda s, d: _combined(s, d).select("question", "student", "correct", "reason"), _values([(c[0], c[1], *c[3:]) for c in _CLASS], "question, student, correct, reason"))
# The condition too many costs one of the eight marks of the first correct query; the changed constant as well.
_add(
    "ver_run_grading", lambda s, d: _combined(s, d).where("question = 5").select("student", F.round("marks", 6).alias("marks"), (F.col("feedback") == "Correct.").alias("told_correct")),
    _values([(c[1], {"wrong": 0.875, "extra": 0.875, "syntax": 0.0}.get(c[1], 1.0), c[3]) for c in _CLASS if c[0] == 5], "student, marks, told_correct"),
)

# -- clusters: masks with one canonical form. Faults without cost vanish; DISTINCT on a key stays while a cross join repeats rows.
_SIGNATURE = "CASE WHEN question IN (1, 2) THEN CASE WHEN mask & 16 = 0 THEN mask & ~8 ELSE mask END WHEN question IN (4, 5, 10, 13) THEN mask & ~8 ELSE mask END"
_SIGNED = TRUTH_SQL + f", signed AS (SELECT *, CASE WHEN question = 1 THEN ({_SIGNATURE}) & ~2 ELSE {_SIGNATURE} END AS sig FROM truth)"
_clusters = lambda s, d: _once(s, ("clusters", d), lambda: Workspace(s, "clusters").save(grade.clusters(corpus.submissions(s, d), _correct_frame(s))))
_add("clu_clusters", lambda s, d: _clusters(s, d).select("question", "exemplar", "size"), _SIGNED + "SELECT question, min(sub_id) AS exemplar, count(*) AS size FROM signed GROUP BY question, sig")
_add("clu_sizes", lambda s, d: _clusters(s, d).groupBy("question").agg(F.count("*").alias("clusters"), F.max("size").alias("largest")), _SIGNED + "SELECT question, count(*) AS clusters, max(n) AS largest FROM (SELECT question, sig, count(*) AS n FROM signed GROUP BY ALL) GROUP BY question")
_add("clu_unmatched", lambda s, d: _clusters(s, d).where("not matched").groupBy("question").agg(F.count("*").alias("clusters")), _SIGNED + "SELECT question, count(DISTINCT sig) AS clusters FROM signed WHERE cost > 0 GROUP BY question")
_add("eq_canonical_match", lambda s, d: grade.with_equivalence(corpus.submissions(s, d), _correct_frame(s)).select("sub_id", "canonical_match"), TRUTH_SQL + "SELECT sub_id, cost = 0 AS canonical_match FROM marked")

# -- functions in SQL
_A, _B = wl.CORRECT["w08a"], corpus.submission_text(8, 5, 1)
_lit = lambda s: "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _udf(text: str) -> Query:
    def go(spark: SparkSession, sf_dir: str) -> DataFrame:
        udfs.register_all(spark)
        return spark.sql(text)

    return go


_SUBS = f"VALUES ({_lit(_A)}), ({_lit(_B)}), ('SELECT FROM x')"
_add("udf_canonical_sql", _udf(f"SELECT canonical_sql(sql) IS NULL AS failed, canonical_sql(sql) = canonical_sql({_lit(_A)}) AS same FROM {_SUBS} t(sql)"), _values([(False, True), (False, False), (True, None)], "failed, same"))
_add("udf_canonical_hash", _udf(f"SELECT canonical_hash(sql) = canonical_hash({_lit(corpus.submission_text(8, 0, 6))}) AS same FROM {_SUBS} t(sql)"), _values([(True,), (False,), (None,)], "same"))
_add("udf_query_size", _udf("SELECT query_size('SELECT c_custkey, c_name FROM customer') AS a, query_size('SELECT p_name FROM part WHERE p_size > 25') AS b"), "SELECT 3 AS a, 5 AS b")
_add("udf_parse_error", _udf(f"SELECT parse_error(sql) AS e FROM VALUES ({_lit(_A)}), ('SELECT x FROM nowhere'), ('DROP TABLE t'), ('SELECT a b c FROM customer') t(sql)"), _values([("",), ("there is no table nowhere",), ("only SELECT statements are graded",), ("unexpected 'c'",)], "e"))
_add("udf_edit_distance", _udf(f"SELECT edit_distance({_lit(_B)}, {_lit(_A)}) AS d"), "SELECT 2.0::DOUBLE AS d")
_add("udf_marks", _udf(f"SELECT marks_greedy({_lit(_B)}, {_lit(_A)}) AS g, marks_exhaustive({_lit(_B)}, {_lit(_A)}) AS e"), "SELECT 0.75::DOUBLE AS g, 0.75::DOUBLE AS e")
_add("udf_best_marks", _udf("SELECT k, best_marks(m) AS best FROM VALUES (1, 0.5D), (1, 0.75D), (2, CAST(NULL AS DOUBLE)) t(k, m) GROUP BY k"), _values([(1, 0.75), (2, 0.0)], "k, best"))
_add("udtf_flatten_tree", _udf(f"SELECT component, count(*) AS n FROM flatten_tree({_lit(_A)}) GROUP BY component"), _values([("projection", 2), ("relation", 2), ("predicate", 3), ("subquery", 1)], "component, n"))
_add("udtf_guided_edits", _udf(f"SELECT op, component, cost FROM guided_edits({_lit(corpus.submission_text(3, 16, 0))}, {_lit(wl.CORRECT['w03'])})"), _values([("delete", "relation", 1.0)], "op, component, cost"))
_add("udtf_edit_sequence", _udf(f"SELECT op, component, cost FROM edit_sequence({_lit(_B)}, {_lit(_A)})"), _values([("insert", "projection", 1.0), ("delete", "predicate", 1.0)], "op, component, cost"))
_add("udtf_mutants", _udf(f"SELECT kind, count(*) AS n FROM mutants({_lit('SELECT DISTINCT p_name FROM part WHERE p_size > 25')}) GROUP BY kind"), _values([("distinct", 1), ("comparison", 5)], "kind, n"))


# -- streams: run to their end, and held against the batch answer
def _streamed(spark: SparkSession, sf_dir: str, make: Callable[[DataFrame], DataFrame], mode: str = "append") -> DataFrame:
    ws = Workspace(spark, "stream")
    # A last row far ahead moves the watermark past all windows; it is left out of the answers.
    subs = corpus.submissions(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))
    end = subs.limit(1).withColumn("ts", F.lit("2030-01-01 00:00:00").cast("timestamp")).withColumn("question", F.lit(99)).withColumn("student_id", F.lit(-1).cast("long"))
    stream.write_ordered(subs.unionByName(end), f"{ws.root}/in")
    name = f"qm_{uuid.uuid4().hex}"
    return stream.run_to_end(make(stream.submission_stream(spark, f"{ws.root}/in", 1000)), name, mode, f"{ws.root}/checkpoint")


_day = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
_add("str_tumbling", lambda s, d: _streamed(s, d, stream.tumbling).where("question <> 99").select("question", _day("start").alias("start"), "attempts"), TRUTH_SQL + "SELECT question, strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS attempts FROM truth GROUP BY ALL")
_add("str_sliding", lambda s, d: _streamed(s, d, stream.sliding).where("question <> 99").select("question", _day("start").alias("start"), "attempts"), TRUTH_SQL + "SELECT question, strftime(time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS attempts FROM truth, (VALUES (0), (1), (2), (3)) v(k) GROUP BY ALL")
_add(
    "str_session",
    lambda s, d: _streamed(s, d, stream.sessions).where("student_id <> -1").groupBy("student_id").agg(F.count("*").alias("sessions"), F.sum("attempts").alias("attempts")),
    "SELECT user_id AS student_id, count(*) FILTER (g IS NULL OR g >= INTERVAL 30 MINUTE) AS sessions, count(*) AS attempts FROM (SELECT user_id, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM events) x GROUP BY 1",
)


def _late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily attempts of a stream in which every submission comes once more after the watermark has passed it, and how
    many rows the engine says it dropped."""
    ws = Workspace(spark, "late")
    subs = corpus.submissions(spark, sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))
    end = subs.limit(1).withColumn("ts", F.lit("2030-01-01 00:00:00").cast("timestamp")).withColumn("question", F.lit(99))
    # One file each, and one a trigger: rows are late by the watermark that the batch before began with.
    stream.write_ordered(subs.unionByName(end), f"{ws.root}/in", 1)
    for more in (end, subs):
        more.repartition(1).write.mode("append").parquet(f"{ws.root}/in")
    dropped: list[int] = []
    out = stream.run_to_end(stream.tumbling(stream.submission_stream(spark, f"{ws.root}/in")), f"qm_{uuid.uuid4().hex}", "append", f"{ws.root}/checkpoint", dropped)
    return out.where("question <> 99").select("question", _day("start").alias("start"), "attempts", F.lit(sum(dropped) > 0).alias("some_dropped"))


def _stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Canonical matches of a stream of submissions with a table of correct queries."""
    return _streamed(spark, sf_dir, lambda df: stream.matched(df, _correct_frame(spark))).where("question <> 99").select("sub_id", "canonical_match")


_add(
    "str_late", _late,
    TRUTH_SQL + "SELECT question, strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS attempts, TRUE AS some_dropped FROM truth GROUP BY ALL",
)
_add("str_static_join", _stream_static, TRUTH_SQL + "SELECT sub_id, cost = 0 AS canonical_match FROM marked")


def _deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the stream keeps each text of a student and question once."""
    kept = _streamed(spark, sf_dir, stream.without_resubmits).where("question <> 99").agg(F.count("*").alias("n"), F.countDistinct("student_id", "question", "sql").alias("k"))
    whole = corpus.submissions(spark, sf_dir).agg(F.countDistinct("student_id", "question", "sql").alias("w"))
    return kept.crossJoin(whole).select((F.col("n") == F.col("w")).alias("all_kept"), (F.col("n") == F.col("k")).alias("once"))


_add("str_dedup", _deduplicated, "SELECT TRUE AS all_kept, TRUE AS once")
_add(
    "str_best_so_far",
    lambda s, d: _streamed(s, d, lambda df: stream.best_so_far(df.select("student_id", "question", (F.col("mask") / 32.0).alias("marks"))), "update").where("question <> 99").groupBy("student_id", "question").agg(F.max("attempts").alias("attempts"), F.max("best").alias("best")),
    TRUTH_SQL + "SELECT user_id AS student_id, question, count(*) AS attempts, max(mask / 32.0) AS best FROM truth GROUP BY ALL",
)

__all__ = ["EXAMPLES", "graded_marks", "oracle_sql", "queries"]


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_ORACLES)
