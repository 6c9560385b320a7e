"""The exercises on the given tables: 35 correct queries for 15 questions, and the pairs that test single rules."""

from __future__ import annotations

#: The exercises' constants.
URGENT, FINISHED = "1-URGENT", "F"

_JOINED = "FROM customer, orders WHERE c_custkey = o_custkey AND o_orderstatus = 'F'"
_BAD_SUPPLIER = "lineitem, orders WHERE l_orderkey = o_orderkey AND l_returnflag = 'R' AND l_quantity = 50 AND o_orderstatus = 'F'"

CORRECT: dict[str, str] = {
    "w01": "SELECT c_custkey, c_name FROM customer",
    "w02": "SELECT * FROM customer WHERE c_name < 'Customer#000000100'",
    "w03": "SELECT p_name FROM part WHERE p_size > 25",
    "w04a": "SELECT c_custkey FROM customer, nation WHERE c_nationkey = n_nationkey AND n_regionkey = 2",
    "w04b": "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 2)",
    "w05a": "SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderstatus = 'F' AND o_orderpriority = '1-URGENT'",
    "w05b": "SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' AND o_orderpriority = '1-URGENT')",
    "w06a": "SELECT c_custkey, c_name FROM customer WHERE NOT EXISTS (SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F' AND o_custkey = c_custkey)",
    "w06b": "WITH tried AS (SELECT c_custkey, c_name, o_orderkey FROM customer LEFT OUTER JOIN orders ON c_custkey = o_custkey AND o_orderstatus = 'F') SELECT c_custkey, c_name FROM tried WHERE o_orderkey IS NULL",
    "w06c": f"SELECT c_custkey, c_name FROM customer EXCEPT SELECT c_custkey, c_name {_JOINED}",
    "w07a": "SELECT c_custkey, c_name FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')",
    "w07b": "WITH tried AS (SELECT c_custkey, c_name, o_orderkey FROM customer LEFT OUTER JOIN orders ON c_custkey = o_custkey AND o_orderpriority = '1-URGENT') SELECT c_custkey, c_name FROM tried WHERE o_orderkey IS NULL",
    "w07c": "SELECT c_custkey, c_name FROM customer EXCEPT SELECT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderpriority = '1-URGENT'",
    "w08a": "SELECT c_custkey, c_name FROM customer WHERE c_acctbal > 5000 AND NOT EXISTS (SELECT * FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')",
    "w08b": "(SELECT c_custkey, c_name FROM customer WHERE c_acctbal > 5000) EXCEPT (SELECT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey AND o_orderpriority = '1-URGENT')",
    "w08c": "SELECT c_custkey, c_name FROM customer WHERE c_custkey IN ((SELECT c_custkey FROM customer WHERE c_acctbal > 5000) EXCEPT (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT'))",
    "w09a": "SELECT p_partkey, p_name FROM part EXCEPT SELECT p_partkey, p_name FROM part, lineitem, orders WHERE p_partkey = l_partkey AND l_orderkey = o_orderkey AND o_orderdate < DATE '1995-04-01'",
    "w09b": "SELECT p_partkey, p_name FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem, orders WHERE l_orderkey = o_orderkey AND o_orderdate < DATE '1995-04-01')",
    "w10a": "SELECT DISTINCT o_orderkey, c_custkey, c_name, s_suppkey, s_name FROM orders, customer, lineitem, supplier WHERE o_custkey = c_custkey AND l_orderkey = o_orderkey AND l_suppkey = s_suppkey AND c_nationkey <> s_nationkey",
    "w10b": "SELECT DISTINCT o_orderkey, c_custkey, c_name, s_suppkey, s_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> (SELECT max(n_nationkey) FROM nation WHERE n_nationkey = s_nationkey)",
    "w10c": "WITH buyers AS (SELECT o_orderkey, c_custkey, c_name, c_nationkey FROM orders, customer WHERE o_custkey = c_custkey), sellers(okey, skey, sname, snation) AS (SELECT l_orderkey, s_suppkey, s_name, s_nationkey FROM lineitem INNER JOIN supplier ON l_suppkey = s_suppkey) SELECT DISTINCT b.o_orderkey, b.c_custkey, b.c_name, t.skey AS s_suppkey, t.sname AS s_name FROM buyers b, sellers t WHERE t.okey = b.o_orderkey AND b.c_nationkey <> t.snation",
    "w10d": "(SELECT o_orderkey, c_custkey, c_name, s_suppkey, s_name FROM orders, customer, lineitem, supplier WHERE o_custkey = c_custkey AND l_orderkey = o_orderkey AND l_suppkey = s_suppkey) EXCEPT (SELECT o_orderkey, c_custkey, c_name, s_suppkey, s_name FROM orders, customer, lineitem, supplier WHERE o_custkey = c_custkey AND l_orderkey = o_orderkey AND l_suppkey = s_suppkey AND c_nationkey = s_nationkey)",
    "w10e": "SELECT DISTINCT o_orderkey, c_custkey, c_name, s_suppkey, s_name FROM orders, customer, lineitem, supplier WHERE o_custkey = c_custkey AND l_orderkey = o_orderkey AND l_suppkey = s_suppkey AND c_nationkey NOT IN (SELECT n_nationkey FROM nation WHERE n_nationkey = s_nationkey)",
    "w11a": f"SELECT s_suppkey, s_name FROM supplier EXCEPT SELECT s_suppkey, s_name FROM supplier, {_BAD_SUPPLIER} AND l_suppkey = s_suppkey",
    "w11b": f"SELECT s_suppkey, s_name FROM supplier WHERE NOT EXISTS (SELECT l_suppkey FROM {_BAD_SUPPLIER} AND l_suppkey = s_suppkey)",
    "w12a": "SELECT DISTINCT o_orderpriority FROM orders, lineitem WHERE l_orderkey = o_orderkey AND o_orderstatus = 'F' AND l_suppkey = 7 AND l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1997-02-01'",
    "w12b": "SELECT DISTINCT o_orderpriority FROM orders WHERE o_orderstatus = 'F' AND EXISTS (SELECT * FROM lineitem WHERE l_orderkey = o_orderkey AND l_suppkey = 7 AND l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1997-02-01')",
    "w12c": "SELECT DISTINCT o_orderpriority FROM orders WHERE o_orderstatus = 'F' AND o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_shipdate >= DATE '1997-01-01' AND l_shipdate < DATE '1997-02-01' AND l_suppkey IN (SELECT s_suppkey FROM supplier WHERE s_suppkey = 7))",
    "w13": "(SELECT c_custkey, c_name FROM customer, orders, lineitem WHERE c_custkey = o_custkey AND o_orderkey = l_orderkey AND l_returnflag = 'R' AND l_shipdate < DATE '1996-01-01') INTERSECT (SELECT c_custkey, c_name FROM customer, orders, lineitem WHERE c_custkey = o_custkey AND o_orderkey = l_orderkey AND l_returnflag = 'R' AND l_shipdate >= DATE '2000-01-01')",
    "w14a": "SELECT DISTINCT p_partkey, p_name FROM part, lineitem, orders WHERE p_partkey = l_partkey AND l_orderkey = o_orderkey AND o_orderdate >= DATE '1995-06-01' AND p_brand = 'Brand#13'",
    "w14b": "(SELECT p_partkey, p_name FROM part, lineitem, orders WHERE p_brand = 'Brand#13' AND p_partkey = l_partkey AND l_orderkey = o_orderkey) EXCEPT (SELECT p_partkey, p_name FROM part, lineitem, orders WHERE p_brand = 'Brand#13' AND p_partkey = l_partkey AND l_orderkey = o_orderkey AND o_orderdate < DATE '1995-06-01')",
    "w15a": f"(SELECT s_suppkey, s_name FROM supplier, lineitem, orders WHERE l_suppkey = s_suppkey AND l_orderkey = o_orderkey AND o_orderpriority IS NOT NULL) EXCEPT (SELECT s_suppkey, s_name FROM supplier, {_BAD_SUPPLIER} AND l_suppkey = s_suppkey)",
    "w15b": f"SELECT DISTINCT s_suppkey, s_name FROM supplier, lineitem, orders WHERE l_suppkey = s_suppkey AND l_orderkey = o_orderkey AND o_orderpriority IS NOT NULL AND s_suppkey NOT IN (SELECT l_suppkey FROM {_BAD_SUPPLIER})",
    "w15c": f"SELECT s_suppkey, s_name FROM supplier WHERE s_suppkey NOT IN (SELECT l_suppkey FROM {_BAD_SUPPLIER}) AND s_suppkey IN (SELECT l_suppkey FROM lineitem, orders WHERE l_orderkey = o_orderkey AND o_orderpriority IS NOT NULL)",
    "w15d": f"(SELECT s_suppkey, s_name FROM supplier EXCEPT SELECT s_suppkey, s_name FROM supplier JOIN lineitem ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity = 50 AND o_orderstatus = 'F') INTERSECT (SELECT s_suppkey, s_name FROM supplier JOIN lineitem ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey WHERE o_orderpriority IS NOT NULL)",
}
#: Beside the 35: a case in which IS NOT NULL bites.
EXTRA: dict[str, str] = {"w15n": "SELECT d.doc_id, lang FROM documents d LEFT OUTER JOIN labels l ON d.doc_id = l.doc_id WHERE quality IS NULL"}
#: The correct query of each question that submissions are derived from.
BASE = {1: "w01", 2: "w02", 3: "w03", 4: "w04a", 5: "w05a", 6: "w06a", 7: "w07a", 8: "w08a", 9: "w09b", 10: "w10a", 11: "w11b", 12: "w12b", 13: "w13", 14: "w14a", 15: "w15c"}


def question_of(form: str) -> int:
    return int(form[1:3])


def correct_rows() -> list[tuple[int, str, str]]:
    """correct_queries(question, cq_id, sql): 35 rows, a fixed number."""
    return [(question_of(k), k, v) for k, v in CORRECT.items()]


#: rule: pairs of texts that it makes equal; the first is run as written, the second is what is compared with it.
RULE_PAIRS: dict[str, tuple[str, str]] = {
    "s01": ("SELECT c.c_custkey FROM customer c WHERE c.c_nationkey = 3", "SELECT c_custkey FROM customer WHERE customer.c_nationkey = 3"),
    "s02": ("WITH rich AS (SELECT c_custkey AS k, c_name FROM customer WHERE c_acctbal > 5000), named(x, y) AS (SELECT k, c_name FROM rich) SELECT x, y FROM named", "SELECT c_custkey AS x, c_name AS y FROM customer WHERE c_acctbal > 5000"),
    "s03": ("SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_partkey NOT BETWEEN 5 AND 50", "SELECT p_partkey FROM part WHERE p_size >= 10 AND p_size <= 20 AND (p_partkey < 5 OR p_partkey > 50)"),
    "s04": ("SELECT o_orderkey FROM orders WHERE NOT (o_orderstatus = 'F' AND NOT (o_totalprice > 1000 OR o_orderpriority IS NULL))", "SELECT o_orderkey FROM orders WHERE o_orderstatus <> 'F' OR o_totalprice > 1000 OR o_orderpriority IS NULL"),
    "s05": ("SELECT p_partkey FROM part WHERE p_retailprice > 950", "SELECT p_partkey FROM part WHERE 950 < p_retailprice"),
    "s06": ("SELECT c_custkey, n_name FROM customer INNER JOIN nation ON c_nationkey = n_nationkey AND n_regionkey = 1", "SELECT c_custkey, n_name FROM customer, nation WHERE c_nationkey = n_nationkey AND n_regionkey = 1"),
    "s07": ("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT * FROM orders WHERE o_totalprice > 300000 AND o_custkey = c_custkey)"),
    "s08": ("SELECT s_suppkey FROM supplier WHERE s_nationkey NOT IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 0)", "SELECT s_suppkey FROM supplier WHERE NOT EXISTS (SELECT 1 FROM nation WHERE n_regionkey = 0 AND n_nationkey = s_nationkey)"),
    "s09": ("SELECT c_custkey FROM customer WHERE EXISTS (SELECT DISTINCT o_orderpriority FROM orders WHERE o_custkey = c_custkey)", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey)"),
    "s10": ("SELECT doc_id, lang, quality FROM documents NATURAL JOIN labels", "SELECT documents.doc_id, lang, quality FROM documents JOIN labels ON documents.doc_id = labels.doc_id"),
    "s11": ("SELECT o_orderkey, l_quantity FROM lineitem RIGHT OUTER JOIN orders ON l_orderkey = o_orderkey", "SELECT o_orderkey, l_quantity FROM orders LEFT OUTER JOIN lineitem ON l_orderkey = o_orderkey"),
    "s12": ("SELECT k FROM (SELECT c_custkey AS k FROM customer WHERE c_acctbal > 9000 ORDER BY c_name) t", "SELECT c_custkey AS k FROM customer WHERE c_acctbal > 9000"),
    "s13": ("SELECT k, r_name FROM (SELECT c_custkey AS k, n_regionkey AS r FROM customer, nation WHERE c_nationkey = n_nationkey) t, region WHERE r = r_regionkey", "SELECT c_custkey AS k, r_name FROM region, nation, customer WHERE n_regionkey = r_regionkey AND n_nationkey = c_nationkey"),
    "s14": ("SELECT * FROM nation, region WHERE n_regionkey = r_regionkey", "SELECT n_nationkey, n_name, n_regionkey, r_regionkey, r_name FROM nation, region WHERE n_regionkey = r_regionkey"),
    "c01": ("SELECT DISTINCT c_custkey, o_orderkey FROM customer, orders WHERE c_custkey = o_custkey AND o_totalprice > 100000", "SELECT c_custkey, o_orderkey FROM customer, orders WHERE c_custkey = o_custkey AND o_totalprice > 100000"),
    "c02": ("SELECT c_custkey FROM customer INTERSECT ALL SELECT o_custkey FROM orders", "SELECT c_custkey FROM customer INTERSECT SELECT o_custkey FROM orders"),
    "c03": ("SELECT c_custkey FROM customer EXCEPT ALL SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'", "SELECT c_custkey FROM customer EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'"),
    "c04": ("SELECT DISTINCT t.o_custkey FROM (SELECT DISTINCT o_custkey, o_orderstatus FROM orders) t", "SELECT DISTINCT o_custkey FROM orders"),
    "c05": ("SELECT t.o_orderkey, n_name FROM (SELECT DISTINCT o_orderkey, o_custkey FROM orders) t, customer, nation WHERE t.o_custkey = c_custkey AND c_nationkey = n_nationkey", "SELECT o_orderkey, n_name FROM orders, customer, nation WHERE o_custkey = c_custkey AND c_nationkey = n_nationkey"),
    "c06": ("SELECT p_partkey, t.l_suppkey, t.l_partkey FROM part, (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem) t WHERE p_partkey = t.l_partkey AND p_size > 40", "SELECT DISTINCT p_partkey, l_suppkey, l_partkey FROM part, lineitem WHERE p_partkey = l_partkey AND p_size > 40"),
    "c07": ("SELECT c_custkey, n_nationkey FROM customer, nation WHERE c_nationkey = n_nationkey", "SELECT c_custkey, c_nationkey AS n_nationkey FROM customer"),
    "c08": ("SELECT c_custkey, o_orderkey FROM customer LEFT OUTER JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus = 'O'", "SELECT c_custkey, o_orderkey FROM customer INNER JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus = 'O'"),
    "c09": ("SELECT c_custkey, n_name FROM customer LEFT OUTER JOIN nation ON c_nationkey = n_nationkey", "SELECT c_custkey, n_name FROM customer INNER JOIN nation ON c_nationkey = n_nationkey"),
    "c10": ("SELECT c_custkey, n_name FROM nation RIGHT OUTER JOIN customer ON c_nationkey = n_nationkey", "SELECT c_custkey, n_name FROM customer INNER JOIN nation ON c_nationkey = n_nationkey"),
    "c11": ("SELECT k, n FROM (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY o_custkey) t WHERE k > 100", "SELECT k, n FROM (SELECT o_custkey AS k, count(*) AS n FROM orders WHERE o_custkey > 100 GROUP BY o_custkey) t"),
    "c12": ("SELECT c_custkey, o_orderkey FROM customer LEFT OUTER JOIN orders ON c_custkey = o_custkey AND o_orderstatus = 'F' WHERE c_acctbal > 0", "SELECT k AS c_custkey, o AS o_orderkey FROM (SELECT c_custkey AS k FROM customer WHERE c_acctbal > 0) t LEFT OUTER JOIN (SELECT o_orderkey AS o, o_custkey AS f FROM orders WHERE o_orderstatus = 'F') u ON k = f"),
    "c13": ("SELECT p_partkey FROM part WHERE p_size > 25 AND p_partkey < 1000", "SELECT p_partkey FROM part WHERE p_size >= 26 AND p_partkey <= 999"),
    "c14": ("SELECT c_custkey FROM customer, nation, supplier WHERE c_nationkey = n_nationkey AND n_nationkey = s_nationkey AND s_acctbal > 9000", "SELECT c_custkey FROM customer, nation, supplier WHERE s_nationkey = c_nationkey AND s_nationkey = n_nationkey AND s_acctbal > 9000"),
    "c15": ("SELECT s_nationkey FROM customer, supplier WHERE c_nationkey = s_nationkey AND s_nationkey < 5", "SELECT c_nationkey AS s_nationkey FROM customer, supplier WHERE c_nationkey = s_nationkey AND c_nationkey < 5"),
    "c16": ("SELECT o_orderkey, o_orderdate FROM orders WHERE o_orderstatus = 'P' ORDER BY o_orderkey, o_orderdate, o_custkey", "SELECT o_orderkey, o_orderdate FROM orders WHERE o_orderstatus = 'P' ORDER BY o_orderkey"),
    "c17": ("SELECT c_custkey, count(*) AS n FROM customer, orders WHERE c_custkey = o_custkey AND c_acctbal > 0 GROUP BY c_custkey, c_name", "SELECT c_custkey, count(*) AS n FROM customer, orders WHERE c_custkey = o_custkey AND c_acctbal > 0 GROUP BY c_name, c_custkey, c_acctbal"),
}
#: Needs the declaration that every customer has an order, true at the two smaller scales only.
PARTICIPATION_PAIR = ("SELECT DISTINCT c_custkey, c_name FROM customer, orders WHERE c_custkey = o_custkey", "SELECT c_custkey, c_name FROM customer")
#: Pairs that must stay different: a rule's guard holds.
GUARDS: dict[str, tuple[str, str]] = {
    "distinct_without_key": ("SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem", "SELECT l_orderkey, l_linenumber FROM lineitem"),
    "preserved_on": ("SELECT c_custkey, o_orderkey FROM customer LEFT OUTER JOIN orders ON c_custkey = o_custkey AND c_acctbal > 0", "SELECT c_custkey, o_orderkey FROM customer LEFT OUTER JOIN orders ON c_custkey = o_custkey WHERE c_acctbal > 0"),
    "participation_undeclared": PARTICIPATION_PAIR,
    "double_bound": ("SELECT p_partkey FROM part WHERE p_retailprice > 950", "SELECT p_partkey FROM part WHERE p_retailprice >= 951"),
    "mixed_union": ("SELECT n_regionkey FROM nation UNION ALL (SELECT n_regionkey FROM nation UNION SELECT r_regionkey FROM region)", "SELECT n_regionkey FROM nation UNION ALL SELECT n_regionkey FROM nation UNION ALL SELECT r_regionkey FROM region"),
    "order_swapped": ("SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey LIMIT 5", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 5"),
    "except_all": ("SELECT o_custkey FROM orders EXCEPT ALL SELECT c_custkey FROM customer WHERE c_acctbal > 0", "SELECT o_custkey FROM orders EXCEPT SELECT c_custkey FROM customer WHERE c_acctbal > 0"),
    "is_null_filter": ("SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE quality IS NULL", "SELECT d.doc_id FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE quality IS NULL"),
    "filter_placement": ("SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id AND quality = 0", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE quality = 0"),
    "child_join": ("SELECT c_custkey FROM customer, orders WHERE c_custkey = o_custkey", "SELECT c_custkey FROM customer"),
}
#: Equivalent, but beyond the rules.
KNOWN_MISSES: dict[str, tuple[str, str]] = {
    "union_self": ("SELECT c_custkey FROM customer UNION SELECT c_custkey FROM customer", "SELECT c_custkey FROM customer"),
    "intersect_self": ("SELECT c_custkey FROM customer INTERSECT SELECT c_custkey FROM customer", "SELECT c_custkey FROM customer"),
    "unnesting": (CORRECT["w04a"], CORRECT["w04b"]),
}
#: Pairs on which comparing plans of the engine's optimizer (and analyzer) does what the two flags say; all are equivalent.
PLAN_PAIRS: dict[str, tuple[str, str, bool, bool]] = {
    "operands": ("SELECT c_custkey FROM customer WHERE c_acctbal > 10 AND c_nationkey = 3", "SELECT c_custkey FROM customer WHERE 3 = c_nationkey AND 10 < c_acctbal", True, True),
    "negation": ("SELECT c_custkey FROM customer WHERE NOT (c_acctbal > 10)", "SELECT c_custkey FROM customer WHERE c_acctbal <= 10", True, True),
    "between": ("SELECT p_partkey FROM part WHERE p_size BETWEEN 3 AND 9", "SELECT p_partkey FROM part WHERE p_size >= 3 AND p_size <= 9", True, False),
    "with": ("WITH t AS (SELECT c_custkey, c_acctbal FROM customer) SELECT c_custkey FROM t WHERE c_acctbal > 10", "SELECT c_custkey FROM customer WHERE c_acctbal > 10", True, False),
    "in": ("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", True, False),
    "null_rejecting": ("SELECT c_custkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus = 'F'", "SELECT c_custkey FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus = 'F'", True, False),
    "sides": ("SELECT c_custkey FROM customer JOIN orders ON c_custkey = o_custkey", "SELECT c_custkey FROM orders JOIN customer ON c_custkey = o_custkey", False, False),
    "right_join": ("SELECT c_custkey, o_orderkey FROM orders RIGHT JOIN customer ON c_custkey = o_custkey", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN orders ON c_custkey = o_custkey", False, False),
    "distinct_key": ("SELECT DISTINCT c_custkey FROM customer", "SELECT c_custkey FROM customer", False, False),
    "strict_bound": ("SELECT p_partkey FROM part WHERE p_size > 5", "SELECT p_partkey FROM part WHERE p_size >= 6", False, False),
}
