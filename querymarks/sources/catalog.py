"""Tables, their columns and declared constraints."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@dataclass(frozen=True)
class ForeignKey:
    columns: tuple[str, ...]
    table: str
    ref_columns: tuple[str, ...]
    participation: bool = False  # every row of the referenced table has a referencing one


@dataclass
class TableDef:
    columns: dict[str, str]  # name: int, num, str, ts or other
    keys: list[frozenset[str]] = field(default_factory=list)
    not_null: set[str] = field(default_factory=set)
    foreign: list[ForeignKey] = field(default_factory=list)


class Catalog:
    def __init__(self, tables: dict[str, TableDef]):
        self.tables = tables

    def table(self, name: str) -> TableDef | None:
        return self.tables.get(name)

    def changed(self, nullable: tuple[str, ...] = (), participation: tuple[tuple[str, str], ...] = ()) -> Catalog:
        """A copy with columns ("table.column") made nullable and foreign keys (table, column) declared total."""
        out = {}
        for name, t in self.tables.items():
            foreign = [ForeignKey(f.columns, f.table, f.ref_columns, f.participation or any((name, c) in participation for c in f.columns)) for f in t.foreign]
            out[name] = TableDef(dict(t.columns), list(t.keys), {c for c in t.not_null if f"{name}.{c}" not in nullable}, foreign)
        return Catalog(out)

    def constraints(self, spark: SparkSession) -> DataFrame:
        """constraints(table, kind, columns, ref_table, ref_columns)"""
        rows = []
        for name, t in self.tables.items():
            rows += [(name, "unique", sorted(k), None, None) for k in t.keys]
            rows += [(name, "not_null", [c], None, None) for c in sorted(t.not_null)]
            rows += [(name, "participation" if f.participation else "foreign", list(f.columns), f.table, list(f.ref_columns)) for f in t.foreign]
        return spark.createDataFrame(rows, '`table` string, kind string, columns array<string>, ref_table string, ref_columns array<string>')


def _table(columns: str, keys: str, foreign: str = "") -> TableDef:
    """columns: "name:type ..."; keys: "a,b c"; foreign: "column>table.column ...". All columns are declared not null."""
    cols = dict(x.split(":") for x in columns.split())
    fks = []
    for x in foreign.split():
        own, ref = x.split(">")
        fks.append(ForeignKey((own,), ref.split(".")[0], (ref.split(".")[1],)))
    return TableDef(cols, [frozenset(k.split(",")) for k in keys.split()], set(cols), fks)


def default_catalog() -> Catalog:
    """The given tables with the constraints declared for them; participation is never declared by default."""
    return Catalog(
        {
            "region": _table("r_regionkey:int r_name:str", "r_regionkey"),
            "nation": _table("n_nationkey:int n_name:str n_regionkey:int", "n_nationkey n_name", "n_regionkey>region.r_regionkey"),
            "customer": _table("c_custkey:int c_name:str c_nationkey:int c_acctbal:num c_mktsegment:str", "c_custkey c_name", "c_nationkey>nation.n_nationkey"),
            "supplier": _table("s_suppkey:int s_name:str s_nationkey:int s_acctbal:num", "s_suppkey s_name", "s_nationkey>nation.n_nationkey"),
            "part": _table("p_partkey:int p_name:str p_brand:str p_type:str p_size:int p_retailprice:num", "p_partkey"),
            "orders": _table("o_orderkey:int o_custkey:int o_orderstatus:str o_totalprice:num o_orderdate:ts o_orderpriority:str", "o_orderkey", "o_custkey>customer.c_custkey"),
            "lineitem": _table(
                "l_orderkey:int l_partkey:int l_suppkey:int l_linenumber:int l_quantity:num l_extendedprice:num l_discount:num l_tax:num l_returnflag:str l_linestatus:str l_shipdate:ts",
                "", "l_orderkey>orders.o_orderkey l_partkey>part.p_partkey l_suppkey>supplier.s_suppkey",
            ),
            "events": _table("event_id:int ts:ts user_id:int event_type:str value:num props:str", "event_id", "user_id>customer.c_custkey"),
            "documents": _table("doc_id:int text:str lang:str source:str n_chars:int", "doc_id"),
            "labels": _table("doc_id:int quality:int toxic:int", "doc_id", "doc_id>documents.doc_id"),
            "pages": _table("page_id:int url:str html:str", "page_id url"),
            "benchmark": _table("item_id:int text:str", "item_id"),
            "conversations": _table("conv_id:int turn:int role:str text:str", "conv_id,turn"),
            "embeddings": _table("vec_id:int embedding:other label:int", "vec_id"),
        }
    )


def participates(tables: dict[str, DataFrame], fk: ForeignKey, referencing: str) -> bool:
    """Whether every row of the referenced table has a referencing one in the data: what a declaration only promises."""
    child = tables[referencing].select(*(F.col(c).alias(r) for c, r in zip(fk.columns, fk.ref_columns)))
    # Merged, as a packed file that looks small may unfold to more keys than the driver can send to all tasks.
    return tables[fk.table].join(child.hint("merge"), list(fk.ref_columns), "left_anti").isEmpty()


def read_tables(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> dict[str, DataFrame]:
    return {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names}


def register_tables(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    for n, df in read_tables(spark, sf_dir, names).items():
        df.createOrReplaceTempView(n)
