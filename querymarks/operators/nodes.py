"""The relational form of trees and of component distances."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import canon, distance, ir
from ..plans.resolve import table_of
from ..sources.catalog import Catalog, default_catalog

NODES = "query_id string, node_id int, component string, kind string, label string, ord int, ordered boolean"


def tree_nodes(q: object) -> list[tuple]:
    """(component, kind, label, ord, ordered) of one tree; subqueries bring their own nodes, named by their place."""
    out: list[tuple] = []

    def block(b: object, path: str, exists: bool) -> None:
        if isinstance(b, ir.SetOp):
            out.append(("set_op", "operator", f"{path}{b.kind}{' all' * b.every}", 0, b.kind == "except"))
            for k, p in enumerate(b.parts):
                block(p, f"{path}part{k + 1}/", False)
            return
        p = distance.take_apart(b, exists)
        add = lambda component, kind, label, k=0, ordered=False: out.append((component, kind, path + label, k, ordered))
        for x in p.projection:
            add("projection", "attribute", canon.text(x))
        for x in p.aggregate:
            add("aggregate", "call", canon.text(x))
        for x in p.relation:
            add("relation", "relation", table_of(x))
        for x in p.outer:
            add("join_type", "operator", x)
        for place, x in p.predicate:
            add("predicate", "comparison", f"{place}: {canon.text(x)}")
        for place, x in p.classes:
            for m in sorted(map(canon.text, x.members))[1:]:
                add("predicate", "comparison", f"{place}: {min(map(canon.text, x.members))} = {m}")
        if b.distinct:
            add("distinct", "flag", "distinct")
        for x in b.group:
            add("group_by", "attribute", canon.text(x))
        for x in b.having or ():
            add("having", "comparison", canon.text(x))
        for k, x in enumerate(b.order):
            add("order_by", "attribute", canon.text(x), k, True)
        if b.limit is not None:
            add("limit", "literal", canon.text(b.limit))
        for k, (place, x) in enumerate(p.subquery):
            add("subquery", "block", f"{place}: {'not ' * x.no}exists")
            block(x.query, f"{path}sub{k + 1}/", True)
        for k, d in enumerate(p.derived):
            add("relation", "relation", "derived")
            block(d.query, f"{path}from{k + 1}/", False)

    block(q, "", False)
    return out


def nodes(queries: DataFrame, catalog: Catalog | None = None, canonical: bool = True) -> DataFrame:
    """A row for each node of each query (query_id, sql); texts that do not parse give none."""
    catalog = catalog or default_catalog()

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for qid, sql in zip(frame["query_id"], frame["sql"]):
                try:
                    tree = canon.prepare(sql, catalog)[0]
                except ir.GradingError:
                    continue
                tree = canon.semantic(tree, catalog) if canonical else tree
                rows += [(str(qid), k, *n) for k, n in enumerate(tree_nodes(tree))]
            yield pd.DataFrame(rows, columns=[x.split()[0] for x in NODES.split(", ")])

    return queries.select("query_id", "sql").mapInPandas(work, NODES)


def component_distance(left: DataFrame, right: DataFrame) -> DataFrame:
    """pair, component, missing, extra, distance of two node tables (pair, component, label): the larger of what is
    missing and what is extra. Both sides are counted in one aggregation, so that nothing is joined."""
    both = left.select("pair", "component", "label", F.lit(1).alias("s")).unionByName(right.select("pair", "component", "label", F.lit(-1).alias("s")))
    each = both.groupBy("pair", "component", "label").agg(F.sum("s").alias("d"))
    split = each.groupBy("pair", "component").agg(F.sum(F.greatest(-F.col("d"), F.lit(0))).alias("missing"), F.sum(F.greatest("d", F.lit(0))).alias("extra"))
    return split.withColumn("distance", F.greatest("missing", "extra"))


def weighted_distance(parts: DataFrame, weights: DataFrame) -> DataFrame:
    """pair, distance: component distances times weights(component, weight); 1 where no weight is given."""
    joined = parts.join(F.broadcast(weights), "component", "left")  # one row for each component at most
    return joined.groupBy("pair").agg(F.sum(F.col("distance") * F.coalesce("weight", F.lit(1.0))).alias("distance"))
