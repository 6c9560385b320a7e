"""Datasets, verdicts by running queries on them, and which mutants they kill."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import AbstractContextManager, contextmanager
from decimal import Decimal
from functools import reduce
from multiprocessing.pool import ThreadPool

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import canon
from ..plans.mutants import mutant_trees, on_dataset, tree_on_dataset
from ..sources.catalog import Catalog, default_catalog

STAR = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")
Dataset = dict[str, DataFrame]


def hashes(df: DataFrame) -> DataFrame:
    """h of each row. Nulls count by flags of their own, values by common types, and columns by their order; names do
    not matter."""
    wide = {"tinyint": "bigint", "smallint": "bigint", "int": "bigint", "float": "double"}
    cols: list[Column] = []
    plain = df.toDF(*(f"c{k}" for k in range(len(df.columns))))
    for name, kind in plain.dtypes:
        value = F.col(name).cast(wide.get(kind, "double" if kind.startswith("decimal") else kind))
        cols += [value, F.col(name).isNull()]
    return plain.select(F.xxhash64(F.lit(len(df.columns)), *cols).cast("decimal(38,0)").alias("h"))


def digest(df: DataFrame) -> DataFrame:
    """n, h: equal for equal bags of rows. One pass without a sort."""
    return hashes(df).agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("h"), F.lit(0)).cast("decimal(38,0)").alias("h"))


def same_rows(a: DataFrame, b: DataFrame) -> bool:
    """Bag equality by both differences: for confirmation where digests agree."""
    return len(a.columns) == len(b.columns) and a.exceptAll(b.toDF(*a.columns)).isEmpty() and b.toDF(*a.columns).exceptAll(a).isEmpty()


def closed_slice(tables: Dataset, modulus: int, remainder: int) -> Dataset:
    """A slice that keeps foreign keys: orders, customers, parts and suppliers by key, lines of the orders kept, and
    whatever these refer to. Small parents come whole."""
    part = lambda t, key: tables[t].where(F.pmod(F.col(key), F.lit(modulus)) == remainder)
    orders = part("orders", "o_orderkey")
    lines = tables["lineitem"].join(orders.select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey", "left_semi").select(tables["lineitem"].columns)

    def with_parents(t: str, key: str, child: DataFrame, ref: str) -> DataFrame:
        wanted = child.select(F.col(ref).alias(key)).unionByName(part(t, key).select(key)).distinct()
        return tables[t].join(wanted, key, "left_semi").select(tables[t].columns)

    out = {t: tables[t] for t in ("region", "nation")}
    return out | {"orders": orders, "lineitem": lines, "customer": with_parents("customer", "c_custkey", orders, "o_custkey"), "part": with_parents("part", "p_partkey", lines, "l_partkey"), "supplier": with_parents("supplier", "s_suppkey", lines, "l_suppkey")}


def boundary(tables: Dataset, table: str, column: str, values: list) -> Dataset:
    """The dataset with copies of one row of ``table`` whose ``column`` takes each value: the constants of a query,
    one less and one more, to tell comparison operators apart."""
    kind = dict(tables[table].dtypes)[column]
    row = tables[table].orderBy(*[c for c in tables[table].columns if c.endswith("key")][:1]).limit(1)
    more = row.withColumn(column, F.explode(F.array(*(F.lit(v).cast(kind) for v in values))))
    return tables | {table: tables[table].unionByName(more)}


def empty(tables: Dataset) -> Dataset:
    return {t: df.limit(0) for t, df in tables.items()}


def kill_datasets(tables: Dataset) -> dict[str, Dataset]:
    """Whole tables, two closed slices, one with childless parents only and one without rows."""
    whole = {t: tables[t] for t in STAR}
    slices = {f"slice{k}": closed_slice(whole, 7, k) for k in (1, 4)}
    childless = whole | {"orders": tables["orders"].where("o_orderkey % 3 = 1"), "lineitem": tables["lineitem"].where("l_orderkey % 15 = 1")}
    return {"whole": whole, **slices, "sparse": childless, "empty": empty(whole)}


def _views(spark: SparkSession, name: str, data: Dataset) -> dict[str, str]:
    views = {t: f"qm_{name}_{t}" for t in data}
    for t, df in data.items():
        df.createOrReplaceTempView(views[t])
    return views


#: Bytes of a table's files that a join may send to all tasks while queries of students run.
SENT = 64 << 10


@contextmanager
def _conf(spark: SparkSession, values: dict[str, str]) -> Iterator[None]:
    before = {k: spark.conf.get(k, None) for k in values}
    try:
        for k, v in values.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def few_sent(spark: SparkSession, sent: int = SENT) -> AbstractContextManager[None]:
    """Joins planned and run inside send only tables of ``sent`` bytes to all tasks. Packed files of a megabyte
    may unfold to hash tables a hundred times that size, which the driver builds, for all plans of a job at once."""
    return _conf(spark, {k: str(sent) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")})


#: Bytes of files for a partition of what static plans deal out.
DEALT = 8 << 20


def static_plans(spark: SparkSession, data: Dataset) -> AbstractContextManager[None]:
    """Plans made inside are not planned anew while they run: where plans are many, that takes the driver a thread for
    each exchange of a minute, up to a thousand. Partitions go by the sizes of the files."""
    path, conf = spark._jvm.org.apache.hadoop.fs.Path, spark._jsc.hadoopConfiguration()
    size = sum((p := path(f)).getFileSystem(conf).getFileStatus(p).getLen() for df in data.values() for f in df.inputFiles())
    return _conf(spark, {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(max(spark.sparkContext.defaultParallelism, size // DEALT))})


def digests(spark: SparkSession, queries: dict[str, str], datasets: dict[str, Dataset], catalog: Catalog | None = None) -> DataFrame:
    """query, dataset, n, h: all in one job, a row for each. Only parsed SELECTs over known tables are run."""
    catalog, rows = catalog or default_catalog(), []
    for name, data in datasets.items():
        views = _views(spark, name, data)
        for q, sql in queries.items():
            rows.append(digest(spark.sql(on_dataset(sql, catalog, views))).select(F.lit(q).alias("query"), F.lit(name).alias("dataset"), "n", "h"))
    return reduce(DataFrame.unionByName, rows)


def verdicts(spark: SparkSession, students: dict[str, str], correct: str, datasets: dict[str, Dataset], catalog: Catalog | None = None) -> DataFrame:
    """query, dataset, passed: whether the student's rows are those of the correct query."""
    every = digests(spark, {"$correct": correct, **students}, datasets, catalog)
    truth = every.where("query = '$correct'").select("dataset", F.col("n").alias("n0"), F.col("h").alias("h0"))
    return every.where("query <> '$correct'").join(F.broadcast(truth), "dataset").select("query", "dataset", ((F.col("n") == F.col("n0")) & (F.col("h") == F.col("h0"))).alias("passed"))


def marks_by_datasets(spark: SparkSession, students: dict[str, str], correct: str, datasets: dict[str, Dataset]) -> DataFrame:
    """query, marks, all_or_nothing: the share of datasets passed, the naive baseline, and binary marks."""
    v = verdicts(spark, students, correct, datasets)
    return v.groupBy("query").agg(F.round(F.avg(F.col("passed").cast("int")), 6).alias("marks"), F.min(F.col("passed").cast("int")).alias("all_or_nothing"))


#: Plans of a query's mutants that run in one job, and jobs that run at a time.
AT_ONCE, JOBS = 4, 2
#: Bytes of a row or few, which a join may send to all tasks beside mutants; jobs after which the driver drops what it holds of them.
ONE_ROW, KEPT = 1 << 10, 6


def kill_matrix(spark: SparkSession, sql: str, datasets: dict[str, Dataset], catalog: Catalog | None = None) -> DataFrame:
    """mutant, kind, change, killed, by: which datasets tell each mutant from the query. The driver gets a digest of each
    mutant on each dataset."""
    catalog = catalog or default_catalog()
    names = {f"m{k:03d}": m for k, m in enumerate(mutant_trees(sql, catalog))}
    trees = {"$correct": canon.prepare(sql, catalog)[0], **{k: m[3] for k, m in names.items()}}
    plans = []
    for name, data in datasets.items():
        views = _views(spark, name, data)
        plans += [(q, name, tree_on_dataset(tree, catalog, views)) for q, tree in trees.items()]

    def told(some: list[tuple[str, str, str]]) -> list[tuple]:
        rows = reduce(DataFrame.unionByName, (hashes(spark.sql(text)).select(F.lit(k).alias("k"), "h") for k, (_, _, text) in enumerate(some)))
        got = {r["k"]: (r["n"], r["h"]) for r in rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.sum("h").cast("decimal(38,0)").alias("h")).collect()}
        return [(q, name, *got.get(k, (0, Decimal(0)))) for k, (q, name, _) in enumerate(some)]

    jobs, rows = [plans[k : k + AT_ONCE] for k in range(0, len(plans), AT_ONCE)], []
    with few_sent(spark, ONE_ROW), static_plans(spark, next(iter(datasets.values()))), ThreadPool(JOBS) as pool:
        for k in range(0, len(jobs), KEPT):
            rows += [r for some in pool.map(told, jobs[k : k + KEPT], 1) for r in some]
            spark._jvm.System.gc()  # else shuffle files, plans and their classes stay until the driver's heap is full
    every = spark.createDataFrame(rows, "query string, dataset string, n bigint, h decimal(38,0)").coalesce(1)
    truth = every.where("query = '$correct'").select("dataset", F.col("n").alias("n0"), F.col("h").alias("h0"))
    told_apart = every.where("query <> '$correct'").join(F.broadcast(truth), "dataset").withColumn("differs", (F.col("n") != F.col("n0")) | (F.col("h") != F.col("h0")))
    by = told_apart.groupBy("query").agg(F.max("differs").alias("killed"), F.array_join(F.array_sort(F.collect_list(F.when(F.col("differs"), F.col("dataset")))), ",").alias("by"))
    label = spark.createDataFrame([(k, m[0], m[1]) for k, m in names.items()], "query string, kind string, change string")
    return label.join(by, "query").withColumnRenamed("query", "mutant")


def combined_verdict(spark: SparkSession, student: str, correct: list[str], datasets: dict[str, Dataset], student_datasets: dict[str, Dataset] | None = None, catalog: Catalog | None = None) -> tuple[bool, str]:
    """(correct, reason). A canonical match is right without running anything; who differs on the
    datasets so far from each correct query is wrong; what is left is run on datasets made for the student's own conditions."""
    catalog = catalog or default_catalog()
    mine = canon.canonical_text(student, catalog)
    if any(canon.canonical_text(c, catalog) == mine for c in correct):
        return True, "canonical form"
    for stage, data in (("datasets of the correct query", datasets), ("datasets of the student's query", student_datasets or {})):
        if data:
            correct = [c for c in correct if all(r["passed"] for r in verdicts(spark, {"s": student}, c, data, catalog).collect())]
            if not correct:
                return False, stage
    return True, "all datasets"
