import random

import pytest

from querymarks.plans import canon, ir
from querymarks.plans.rules_semantic import RULES as SEMANTIC
from querymarks.plans.rules_syntactic import RULES as SYNTACTIC
from querymarks.plans.sqltext import parse_sql
from querymarks.sources import workloads as wl
from querymarks.sources.catalog import default_catalog

CATALOG = default_catalog()
TOTAL = CATALOG.changed(participation=(("orders", "o_custkey"),))


def form(sql, catalog=CATALOG, off=()):
    return canon.text(canon.canonicalize(sql, catalog, off))


@pytest.mark.parametrize("rule", wl.RULE_PAIRS)
def test_rule_makes_pair_equal(rule):
    a, b = wl.RULE_PAIRS[rule]
    assert form(a) == form(b)


@pytest.mark.parametrize("guard", wl.GUARDS)
def test_guard_keeps_pair_apart(guard):
    a, b = wl.GUARDS[guard]
    assert form(a) != form(b)


@pytest.mark.parametrize("miss", wl.KNOWN_MISSES)
def test_known_misses_stay_misses(miss):
    a, b = wl.KNOWN_MISSES[miss]
    assert form(a) != form(b)


def test_child_join_needs_declared_participation():
    a, b = wl.PARTICIPATION_PAIR
    assert form(a, TOTAL) == form(b, TOTAL) and form(a) != form(b)


@pytest.mark.parametrize(("rule", "pair"), [("S3", "s03"), ("S8", "s08"), ("C1", "c01"), ("C2", "c02"), ("C3", "c03"), ("C8", "c08"), ("C13", "c13"), ("C16", "c16"), ("C17", "c17")])
def test_each_rule_can_be_switched_off(rule, pair):
    a, b = wl.RULE_PAIRS[pair]
    assert form(a, off=(rule,)) != form(b, off=(rule,))
    assert rule in SYNTACTIC or rule in SEMANTIC


@pytest.mark.parametrize("key", wl.CORRECT)
def test_canonical_form_is_a_fixpoint(key):
    q = canon.canonicalize(wl.CORRECT[key], CATALOG)
    assert canon.text(canon.semantic(q, CATALOG)) == canon.text(q)


@pytest.mark.parametrize("seed", range(6))
def test_order_of_conditions_and_tables_does_not_matter(seed):
    rng = random.Random(seed)
    tables = ["part", "lineitem", "orders", "customer"]
    conds = ["p_partkey = l_partkey", "l_orderkey = o_orderkey", "o_custkey = c_custkey", "p_size > 10", "NOT (c_acctbal < 5)", "o_orderstatus IN ('F', 'P')"]
    want = form(f"SELECT p_name, c_name FROM {', '.join(tables)} WHERE {' AND '.join(conds)}")
    rng.shuffle(tables)
    rng.shuffle(conds)
    assert form(f"SELECT p_name, c_name FROM {', '.join(tables)} WHERE {' AND '.join(conds)}") == want


def test_self_joins_are_named_by_use():
    a = "SELECT x.o_orderkey FROM orders x, orders y WHERE x.o_custkey = y.o_custkey AND y.o_orderstatus = 'F' AND x.o_orderstatus = 'O'"
    b = "SELECT q.o_orderkey FROM orders p JOIN orders q ON p.o_custkey = q.o_custkey WHERE p.o_orderstatus = 'F' AND q.o_orderstatus = 'O'"
    assert form(a) == form(b)


def test_nullable_operands_keep_null_tests():
    nullable = CATALOG.changed(nullable=("orders.o_custkey",))
    sql = "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)"
    assert "is null" in form(sql, nullable) and "is null" not in form(sql)


def test_doubles_are_not_put_in_place_of_each_other():
    a = "SELECT c_acctbal FROM customer, supplier WHERE c_acctbal = s_acctbal"
    b = "SELECT s_acctbal FROM customer, supplier WHERE c_acctbal = s_acctbal"
    assert form(a) != form(b)


def test_least_integer_is_left_alone():
    assert f"< {-(1 << 63)}" in form(f"SELECT p_partkey FROM part WHERE p_size < {-(1 << 63)}")


def test_registered_rules_run():
    seen = []
    canon.register_rule("watch", lambda q, catalog: seen.append(1) or q)
    try:
        form("SELECT c_custkey FROM customer WHERE c_custkey = 77777")
        assert seen
    finally:
        canon.EXTRA_RULES.pop("watch")


def test_trace_names_rules():
    trace = []
    canon.canonicalize("SELECT DISTINCT c_custkey FROM customer WHERE c_custkey < 5", CATALOG, trace=trace)
    assert {"C1", "C13"} <= set(trace)


@pytest.mark.parametrize(("sql", "said"), [
    ("SELECT c.x FROM customer c", "no column"), ("SELECT nothing FROM customer", "no column"), ("SELECT a.c_name FROM customer", "no column"), ("SELECT c_name c_custkey c_x FROM customer", "unexpected"),
    ("SELECT c_name FROM", "expected a name"), ("", "empty"), ("UPDATE customer SET x = 1", "only SELECT"), ("SELECT c_custkey FROM customer, customer", "two relations"), ("SELECT n_nationkey FROM nation, customer WHERE doc_id = 1", "no column"),
    ("SELECT doc_id FROM documents, labels", "ambiguous"), ("SELECT 1 FROM customer EXCEPT SELECT 1, 2 FROM customer", "different numbers"), ("WITH RECURSIVE r AS (SELECT 1) SELECT 1 FROM r", "recursive"), ("SELECT # FROM customer", "unexpected character"),
])
def test_errors_are_said(sql, said):
    with pytest.raises(ir.GradingError, match=said):
        canon.prepare(sql, CATALOG)


def test_parser_reads_all_clauses():
    q = parse_sql("WITH a(x) AS (SELECT 1) SELECT DISTINCT x, count(*) FILTER_ FROM a LEFT JOIN LATERAL (SELECT 2 AS y) b ON a.x = b.y WHERE x LIKE 'a%' GROUP BY x HAVING count(*) > 1 ORDER BY x DESC NULLS LAST LIMIT 3 OFFSET 1")
    assert isinstance(q, ir.With) and q.body.limit == ir.Lit("int", 3) and q.body.order[0].nulls == "last"


@pytest.mark.parametrize(
    "preds",
    [
        [f"{{0}}.c_nationkey = {{{k}}}.c_nationkey" for k in range(1, 7)], [f"{{{k}}}.c_acctbal < {{{(k + 1) % 7}}}.c_acctbal" for k in range(7)],
        [f"{{{k}}}.c_acctbal <> {{{(k + 1) % 7}}}.c_acctbal" for k in range(7)], [],
    ],
)
def test_seven_instances_have_one_form(preds):
    """Whatever the order of FROM, the names and the order of conditions."""
    import random

    from querymarks.plans import canon
    from querymarks.sources.catalog import default_catalog

    rng, forms = random.Random(1), set()
    for _ in range(6):
        names, places, said = [f"t{k}" for k in rng.sample(range(7), 7)], rng.sample(range(7), 7), rng.sample(preds, len(preds))
        where = " WHERE " + " AND ".join(p.format(*names) for p in said) if said else ""
        forms.add(canon.canonical_text(f"SELECT DISTINCT {names[0]}.c_name FROM {', '.join(f'customer {names[k]}' for k in places)}{where}", default_catalog()))
    assert len(forms) == 1


def test_strict_bounds_between_integers():
    from querymarks.plans import canon
    from querymarks.sources.catalog import default_catalog

    form = lambda p: canon.canonical_text(f"SELECT c_custkey FROM customer, orders WHERE {p}", default_catalog())
    assert form("c_custkey < o_custkey") == form("c_custkey <= o_custkey - 1") == form("c_custkey + 1 <= o_custkey") == form("o_custkey > c_custkey")
    assert form("c_acctbal < o_totalprice") != form("c_acctbal <= o_totalprice - 1")


def test_made_rows_keep_keys_and_tell_conditions_apart(duck):
    from querymarks.operators.verdict import made_rows
    from querymarks.sources import workloads as wl
    from querymarks.sources.catalog import default_catalog

    catalog = default_catalog()
    for key in ("w04a", "w05a", "w08a", "w12b", "w13", "w15c"):
        rows = made_rows(wl.CORRECT[key], catalog)
        for table, own in rows.items():
            names = list(catalog.table(table).columns)
            for unique in catalog.table(table).keys:
                picked = [tuple(r[names.index(c)] for c in sorted(unique)) for r in own]
                assert len(set(picked)) == len(picked), (key, table)
    orders = made_rows("SELECT o_orderkey FROM orders WHERE o_totalprice > 100 AND o_orderstatus = 'F'", catalog)["orders"]
    assert {100.0, 99.0, 101.0} <= {r[3] for r in orders} and {"F", "F!", ""} <= {r[2] for r in orders}
