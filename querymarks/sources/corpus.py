"""Synthetic submissions: every combination of five faults and eight spellings of the fifteen base queries.

Which one an event stands for follows from its id by integer arithmetic alone, so that any engine can say what a
submission's hand-derived cost is without seeing its text.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .catalog import default_catalog

QUESTIONS, FAULTS, STYLES = 15, 5, 8
#: Hand-derived cost of faults f0 to f4 of each question, and the worth of its base query.
COSTS: dict[int, tuple[int, ...]] = {
    1: (1, 0, 1, 0, 1), 2: (1, 1, 1, 0, 1), 3: (1, 1, 1, 1, 1), 4: (1, 1, 1, 0, 1), 5: (1, 1, 1, 0, 1), 6: (1, 1, 1, 1, 1), 7: (1, 1, 1, 1, 1), 8: (1, 1, 1, 1, 1),
    9: (1, 1, 1, 1, 1), 10: (1, 1, 1, 0, 1), 11: (1, 1, 1, 1, 1), 12: (1, 1, 1, 1, 1), 13: (2, 1, 1, 0, 1), 14: (1, 1, 1, 1, 1), 15: (1, 1, 1, 1, 1),
}
TOTALS = {1: 3, 2: 7, 3: 3, 4: 5, 5: 8, 6: 7, 7: 7, 8: 8, 9: 9, 10: 14, 11: 11, 12: 10, 13: 19, 14: 10, 15: 17}
_NEGATED = {"=": "<>", "<>": "=", "<": ">=", ">=": "<", ">": "<=", "<=": ">"}
_SWAPPED = {"=": "=", "<>": "<>", "<": ">", ">": "<", "<=": ">=", ">=": "<="}
_OWNER = {c: t for t, d in default_catalog().tables.items() for c in d.columns if t not in ("documents", "labels", "pages", "benchmark", "conversations", "embeddings", "events")}
Pred = tuple[str, str, str]


@dataclass(frozen=True)
class Sub:
    """A subquery: column IN (SELECT own ...) or EXISTS with own = column."""

    column: str
    own: str
    tables: tuple[str, ...]
    joins: tuple[Pred, ...]
    conds: tuple[Pred, ...]
    no: bool = False
    exists: bool = False
    not_null: str = ""


@dataclass(frozen=True)
class Block:
    items: tuple[str, ...]
    tables: tuple[str, ...]
    joins: tuple[Pred, ...] = ()
    conds: tuple[Pred, ...] = ()
    subs: tuple[Sub, ...] = ()
    distinct: bool = False
    left: bool = False  # the last table is joined by a left outer join


@dataclass(frozen=True)
class Exercise:
    blocks: tuple[Block, ...]
    instead: str  # output that stands for the only one, if it is the only one
    changed: tuple[Pred, Pred] | None  # a condition and what f1 makes of it
    added: Pred
    third: str  # distinct, undistinct, left, connective or none
    extra: dict = field(default_factory=dict)


_RQF = (("l_returnflag", "=", "'R'"), ("l_quantity", "=", "50"), ("o_orderstatus", "=", "'F'"))
_LO = (("l_orderkey", "=", "o_orderkey"),)
_RICH: Pred = ("c_acctbal", "<", "9500")
_BUY = (("c_custkey", "=", "o_custkey"), ("o_orderkey", "=", "l_orderkey"))
_URGENT: Pred = ("o_orderpriority", "=", "'1-URGENT'")
_DAYS = (("l_shipdate", ">=", "DATE '1997-01-01'"), ("l_shipdate", "<", "DATE '1997-02-01'"))
_NAMED = ("c_custkey", "c_name")

EXERCISES: dict[int, Exercise] = {
    1: Exercise((Block(_NAMED, ("customer",)),), "", None, _RICH, "distinct"),
    2: Exercise((Block(("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"), ("customer",), (), (("c_name", "<", "'Customer#000000100'"),)),), "", (("c_name", "<", "'Customer#000000100'"), ("c_name", "<", "'Customer#000000200'")), _RICH, "distinct"),
    3: Exercise((Block(("p_name",), ("part",), (), (("p_size", ">", "25"),)),), "p_type", (("p_size", ">", "25"), ("p_size", ">", "20")), ("p_retailprice", "<", "1500"), "distinct"),
    4: Exercise((Block(("c_custkey",), ("customer", "nation"), (("c_nationkey", "=", "n_nationkey"),), (("n_regionkey", "=", "2"),)),), "c_name", (("n_regionkey", "=", "2"), ("n_regionkey", "=", "3")), _RICH, "left"),
    5: Exercise((Block(_NAMED, ("customer", "orders"), (("c_custkey", "=", "o_custkey"),), (("o_orderstatus", "=", "'F'"), _URGENT), (), True),), "", (_URGENT, ("o_orderpriority", "=", "'2-HIGH'")), _RICH, "left"),
    6: Exercise((Block(_NAMED, ("customer",), (), (), (Sub("c_custkey", "o_custkey", ("orders",), (), (("o_orderstatus", "=", "'F'"),), True, True),)),), "", (("o_orderstatus", "=", "'F'"), ("o_orderstatus", "=", "'O'")), _RICH, "connective"),
    7: Exercise((Block(_NAMED, ("customer",), (), (), (Sub("c_custkey", "o_custkey", ("orders",), (), (_URGENT,), True),)),), "", (_URGENT, ("o_orderpriority", "=", "'2-HIGH'")), _RICH, "connective"),
    8: Exercise((Block(_NAMED, ("customer",), (), (("c_acctbal", ">", "5000"),), (Sub("c_custkey", "o_custkey", ("orders",), (), (_URGENT,), True, True),)),), "", (("c_acctbal", ">", "5000"), ("c_acctbal", ">", "4000")), ("c_nationkey", "<>", "3"), "connective"),
    9: Exercise((Block(("p_partkey", "p_name"), ("part",), (), (), (Sub("p_partkey", "l_partkey", ("lineitem", "orders"), _LO, (("o_orderdate", "<", "DATE '1995-04-01'"),), True),)),), "", (("o_orderdate", "<", "DATE '1995-04-01'"), ("o_orderdate", "<", "DATE '1995-06-01'")), ("p_size", "<>", "7"), "connective"),
    10: Exercise((Block(("o_orderkey", "c_custkey", "c_name", "s_suppkey", "s_name"), ("orders", "customer", "lineitem", "supplier"), (("o_custkey", "=", "c_custkey"), ("l_orderkey", "=", "o_orderkey"), ("l_suppkey", "=", "s_suppkey")), (("c_nationkey", "<>", "s_nationkey"),), (), True),), "", (("c_nationkey", "<>", "s_nationkey"), ("c_nationkey", "<", "s_nationkey")), ("o_orderstatus", "<>", "'P'"), "left"),
    11: Exercise((Block(("s_suppkey", "s_name"), ("supplier",), (), (), (Sub("s_suppkey", "l_suppkey", ("lineitem", "orders"), _LO, _RQF, True, True),)),), "", (("l_quantity", "=", "50"), ("l_quantity", "=", "40")), ("s_acctbal", "<", "9500"), "connective"),
    12: Exercise((Block(("o_orderpriority",), ("orders",), (), (("o_orderstatus", "=", "'F'"),), (Sub("o_orderkey", "l_orderkey", ("lineitem",), (), (("l_suppkey", "=", "7"), *_DAYS), False, True),), True),), "o_custkey", (("l_suppkey", "=", "7"), ("l_suppkey", "=", "8")), ("o_totalprice", "<", "400000"), "connective"),
    13: Exercise(tuple(Block(_NAMED, ("customer", "orders", "lineitem"), _BUY, (("l_returnflag", "=", "'R'"), d)) for d in (("l_shipdate", "<", "DATE '1996-01-01'"), ("l_shipdate", ">=", "DATE '2000-01-01'"))), "", (("l_shipdate", "<", "DATE '1996-01-01'"), ("l_shipdate", "<", "DATE '1997-01-01'")), _RICH, "none"),
    14: Exercise((Block(("p_partkey", "p_name"), ("part", "lineitem", "orders"), (("p_partkey", "=", "l_partkey"), ("l_orderkey", "=", "o_orderkey")), (("o_orderdate", ">=", "DATE '1995-06-01'"), ("p_brand", "=", "'Brand#13'")), (), True),), "", (("p_brand", "=", "'Brand#13'"), ("p_brand", "=", "'Brand#12'")), ("p_size", "<>", "7"), "undistinct"),
    15: Exercise((Block(("s_suppkey", "s_name"), ("supplier",), (), (), (Sub("s_suppkey", "l_suppkey", ("lineitem", "orders"), _LO, _RQF, True), Sub("s_suppkey", "l_suppkey", ("lineitem", "orders"), _LO, (), False, False, "o_orderpriority"))),), "", (("l_quantity", "=", "50"), ("l_quantity", "=", "40")), ("s_acctbal", "<", "9500"), "connective"),
}


def with_faults(question: int, mask: int) -> tuple[Block, ...]:
    from dataclasses import replace

    e = EXERCISES[question]
    blocks = list(e.blocks)
    swap = lambda preds: tuple(e.changed[1] if p == e.changed[0] else p for p in preds)
    if mask & 1:
        blocks = [replace(b, items=b.items[:-1] if len(b.items) > 1 else (e.instead,)) for b in blocks]
    if mask & 2 and e.changed:
        blocks = [replace(b, conds=swap(b.conds), subs=tuple(replace(s, conds=swap(s.conds)) for s in b.subs)) for b in blocks]
    first = blocks[0]
    if mask & 4:
        first = replace(first, conds=(*first.conds, e.added))
    if mask & 8:
        if e.third in ("distinct", "undistinct"):
            first = replace(first, distinct=e.third == "distinct")
        elif e.third == "left":
            first = replace(first, left=True)
        elif e.third == "connective":
            first = replace(first, subs=(replace(first.subs[0], no=not first.subs[0].no), *first.subs[1:]))
    if mask & 16:
        first = replace(first, tables=("region", *first.tables))
    return (first, *blocks[1:])


class Writer:
    """Spells blocks. Styles: 0 operands swapped, 1 NOT of the contrary, 2 other join order, 3 aliases, 4 JOIN ON
    and nested joins, 5 WITH around a table, 6 IN and EXISTS exchanged, 7 ORDER BY in a subquery."""

    def __init__(self, style: int):
        self.style, self.aliases = style, 0

    def text(self, blocks: tuple[Block, ...]) -> str:
        shown = [self.block(b) for b in blocks]
        out = shown[0] if len(shown) == 1 else " INTERSECT ".join(f"({x})" for x in shown)
        if self.style == 5:
            table = blocks[0].tables[-1] if blocks[0].tables[0] == "region" and len(blocks[0].tables) > 1 else blocks[0].tables[0]
            out = f"WITH base_{table} AS (SELECT * FROM {table}) {out}".replace(f"FROM {table} ", f"FROM base_{table} ", 0)
            head, _, rest = out.partition(") ")
            out = f"{head}) {rest.replace(f' {table}', f' base_{table} {table}', 1)}"
        return out

    def names(self, tables: tuple[str, ...]) -> dict[str, str]:
        out = {}
        for t in tables:
            self.aliases += 1
            out[t] = f"{t[0]}{self.aliases}" if self.style == 3 else t
        return out

    def value(self, x: str, names: dict[str, str]) -> str:
        return f"{names[_OWNER[x]]}.{x}" if x in _OWNER and (self.style == 3 or self.style == 7) and _OWNER[x] in names else x

    def pred(self, p: Pred, names: dict[str, str], plain: bool = False) -> str:
        a, op, b = self.value(p[0], names), p[1], self.value(p[2], names)
        if self.style == 0:
            return f"{b} {_SWAPPED[op]} {a}"
        return f"NOT ({a} {_NEGATED[op]} {b})" if self.style == 1 and not plain else f"{a} {op} {b}"

    def relation(self, t: str, names: dict[str, str]) -> str:
        return t if names[t] == t else f"{t} {names[t]}"

    def block(self, b: Block) -> str:
        names = self.names(b.tables)
        tables, joins = list(b.tables), list(b.joins)
        where = []
        if b.left:
            last = tables.pop()
            on = [p for p in joins if last in (_OWNER[p[0]], _OWNER[p[2]])]
            joins = [p for p in joins if p not in on]
            first = [t for t in tables if t != "region"]
            side = self.chain(first, joins, names) if len(first) > 1 else self.relation(first[0], names)
            joins = [] if len(first) > 1 else joins
            cond = " AND ".join(self.pred(p, names, True) for p in on)
            if self.style == 2 and len(first) == 1:
                tree = f"{self.relation(last, names)} RIGHT OUTER JOIN {side} ON {cond}"
            else:
                tree = f"{side} LEFT OUTER JOIN {self.relation(last, names)} ON {cond}"
            frm = ", ".join([*(["region" if names["region"] == "region" else f"region {names['region']}"] if "region" in b.tables else []), tree])
        elif self.style == 4 and len(tables) > 1:
            frm, joins = self.chain(tables, joins, names), []
        else:
            order = tables[::-1] if self.style == 2 else tables
            frm = ", ".join(self.relation(t, names) for t in order)
        if self.style == 7 and not b.subs and not b.left:
            t = [x for x in tables if x != "region"][0]
            key = next(c for c in _OWNER if _OWNER[c] == t)
            frm = ", ".join(f"(SELECT * FROM {x} ORDER BY {key}) {x}" if x == t else x for x in tables)
        where += [self.pred(p, names, True) for p in joins] + [self.pred(p, names) for p in b.conds] + [self.sub(s, names) for s in b.subs]
        items = ", ".join(self.value(x, names) for x in b.items)
        return f"SELECT {'DISTINCT ' * b.distinct}{items} FROM {frm}" + (f" WHERE {' AND '.join(where)}" if where else "")

    def chain(self, tables: list[str], joins: list[Pred], names: dict[str, str]) -> str:
        """tables joined one after the other by JOIN ON, in an order in which each has a condition if it can."""
        rest, left = tables[1:], list(joins)
        done, out = [tables[0]], self.relation(tables[0], names)
        while rest:
            links = lambda t: [p for p in left if {_OWNER[p[0]], _OWNER[p[2]]} <= {*done, t} and t in (_OWNER[p[0]], _OWNER[p[2]])]  # noqa: B023, E731  used at once
            t = next((t for t in rest if links(t)), rest[0])
            on = links(t)
            out += f" JOIN {self.relation(t, names)} ON {' AND '.join(self.pred(p, names, True) for p in on)}" if on else f" CROSS JOIN {self.relation(t, names)}"
            left = [p for p in left if p not in on]
            rest.remove(t)
            done.append(t)
        return out

    def sub(self, s: Sub, outer: dict[str, str]) -> str:
        inner = self.names(s.tables)
        names = outer | inner
        exists = s.exists != (self.style == 6)
        where = [self.pred(p, names, True) for p in s.joins] + [self.pred(p, names) for p in s.conds]
        where += [f"{self.value(s.not_null, names)} IS NOT NULL"] if s.not_null else []
        if exists:
            where.append(self.pred((s.own, "=", s.column), names, True))
        tables = s.tables[::-1] if self.style == 2 else s.tables
        order = f" ORDER BY {self.value(s.own, names)}" if self.style == 7 else ""
        body = f"SELECT {'*' if exists else self.value(s.own, names)} FROM {', '.join(self.relation(t, inner) for t in tables)} WHERE {' AND '.join(where)}{order if not exists else ''}"
        return f"{'NOT ' * s.no}EXISTS ({body})" if exists else f"{self.value(s.column, outer)} {'NOT ' * s.no}IN ({body})"


def submission_text(question: int, mask: int, style: int) -> str:
    return Writer(style).text(with_faults(question, mask))


def all_texts() -> list[tuple[int, int, int, str]]:
    """15 x 32 x 8 rows: a fixed number."""
    return [(q, m, s, submission_text(q, m, s)) for q in EXERCISES for m in range(1 << FAULTS) for s in range(STYLES)]


def submissions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sub_id, student_id, question, ts, mask, style, sql: one submission for each event."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "user_id", "ts")
    texts = spark.createDataFrame(all_texts(), "question int, mask int, style int, sql string")
    coded = events.select(
        F.col("event_id").alias("sub_id"), F.col("user_id").alias("student_id"), (F.col("event_id") % QUESTIONS + 1).cast("int").alias("question"), "ts",
        F.expr(f"cast(event_id div {QUESTIONS} % {1 << FAULTS} as int)").alias("mask"), F.expr(f"cast(event_id div {QUESTIONS << FAULTS} % {STYLES} as int)").alias("style"),
    )
    return coded.join(F.broadcast(texts), ["question", "mask", "style"]).select("sub_id", "student_id", "question", "ts", "mask", "style", "sql")
