from collections import Counter

import pytest

from querymarks.plans import ir
from querymarks.plans.mutants import mutant_trees
from querymarks.plans.render import render
from querymarks.plans.setwise import setwise
from querymarks.sources import workloads as wl
from querymarks.sources.catalog import default_catalog, read_tables

USED = ("customer", "orders", "lineitem")


@pytest.fixture(scope="module")
def holes(small):
    """A few rows of the tables with nulls in every column that queries compare, and the same without orders or lines."""
    import duckdb

    con = duckdb.connect()
    null = lambda column, n: f"CASE WHEN hash({column}, {n}) % 4 <> 0 THEN {column} END AS {column}"
    few = {"customer": ("c_custkey", "c_acctbal"), "orders": ("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus"), "lineitem": ("l_orderkey", "l_returnflag", "l_shipdate")}
    for t, columns in few.items():
        con.execute(f"CREATE TABLE {t}0 AS SELECT * REPLACE ({', '.join(null(c, k) for k, c in enumerate(columns))}) FROM (FROM '{small}/{t}.parquet' ORDER BY 1, 2 LIMIT {40 if t == 'customer' else 90})")
    return con


def _states(con):
    for out in ((), ("orders",), ("lineitem",), ("orders", "lineitem"), ("customer",)):
        for t in USED:
            con.execute(f"CREATE OR REPLACE VIEW {t} AS FROM {t}0{' LIMIT 0' if t in out else ''}")
        yield out


@pytest.mark.parametrize("key", ["w05a", "w06b", "w07b", "w08a", "w11b", "w13"])
def test_setwise_queries_have_the_rows_of_the_mutants(duck, holes, key):
    catalog, changed = default_catalog(), []
    for _, _, text, tree in mutant_trees(wl.CORRECT[key], catalog):
        new = render(setwise(tree, catalog))
        if new != render(tree):
            changed.append((text.replace("`", '"'), new.replace("`", '"')))
    rows = lambda con, s: Counter(map(str, con.execute(s).fetchall()))
    assert changed
    if key != "w11b":
        for out in _states(holes):
            for text, new in changed:
                assert rows(holes, text) == rows(holes, new), (out, text, new)
    for text, new in changed:
        assert rows(duck, text) == rows(duck, new), (text, new)


@pytest.mark.parametrize("key", ["w05a", "w06b", "w08a", "w13"])
def test_no_mutant_pairs_rows_of_two_tables_by_an_order(key):
    """Such pairs, and tables without a condition between them, grow with the product of the tables' rows; but for those
    that a query keeps for a null key, which are rows of its result."""
    catalog = default_catalog()
    for _, change, _, tree in mutant_trees(wl.CORRECT[key], catalog):
        new = setwise(tree, catalog)
        kept = {p for g in ir.walk(new) if isinstance(g, ir.Group) and any(isinstance(p, ir.IsNull) for p in g.preds) for p in g.preds}
        for x in (x for x in ir.walk(new) if x not in kept):
            two = isinstance(x, ir.Cmp) and x.op != "=" and {type(x.left), type(x.right)} == {ir.Col}
            assert not two or any(c.rel.startswith("ends$") for c in (x.left, x.right)), change
        if change == "inner to left at orders" and key == "w13":
            assert " JOIN lineitem AS lineitem_0_1) LEFT OUTER" in render(tree) and "LEFT OUTER" not in render(new)


def test_multiplicities_stay_where_they_count():
    catalog = default_catalog()
    for sql in ("SELECT c_custkey FROM customer, orders WHERE c_custkey < o_custkey", "SELECT count(*) FROM customer, orders WHERE c_custkey < o_custkey", "SELECT c_custkey FROM customer, orders WHERE c_custkey < o_custkey INTERSECT ALL SELECT o_custkey FROM orders", "SELECT DISTINCT c_custkey, o_orderkey FROM customer, orders WHERE c_custkey < o_custkey"):
        from querymarks.plans.canon import prepare

        tree, _ = prepare(sql, catalog)
        assert setwise(tree, catalog) == tree


@pytest.mark.parametrize("key", ["w05a", "w06b"])
def test_kill_matrix_agrees_with_sql(spark, holes, tmp_path, key):
    from querymarks.operators.datasets import kill_matrix

    for t in USED:
        holes.execute(f"COPY {t}0 TO '{tmp_path}/{t}.parquet'")
        holes.execute(f"CREATE OR REPLACE VIEW {t} AS FROM {t}0")
    catalog = default_catalog()
    rows = lambda s: Counter(map(str, holes.execute(s.replace("`", '"')).fetchall()))
    right = rows(wl.CORRECT[key])
    want = [(kind, change, rows(text) != right) for kind, change, text, _ in mutant_trees(wl.CORRECT[key], catalog)]
    got = kill_matrix(spark, wl.CORRECT[key], {"d": read_tables(spark, str(tmp_path), USED)}).orderBy("mutant").collect()
    assert [(r["kind"], r["change"], r["killed"]) for r in got] == want
    assert all(r["by"] == ("d" if r["killed"] else "") for r in got)


def test_kill_queries_read_whole_tables(spark, small, monkeypatch):
    from querymarks.operators import datasets, experiments

    seen = []
    empty = "mutant string, kind string, change string, killed boolean, `by` string"
    monkeypatch.setattr(experiments, "_SAVED", {})
    monkeypatch.setattr(datasets, "kill_matrix", lambda s, sql, data: seen.append(data) or s.createDataFrame([], empty))
    experiments._kills(spark, small)
    tables = read_tables(spark, small, datasets.STAR)
    assert len(seen) == 6
    for data in seen[:2]:
        assert set(data) == {"whole", "slice1", "made"}
        for t, df in tables.items():
            assert data["whole"][t].count() == df.count() and data["made"][t].exceptAll(df).count() == data["made"][t].count() - df.count()
