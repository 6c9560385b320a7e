import time

from querymarks.sources import files
from querymarks.sources.catalog import Catalog, default_catalog
from querymarks.streaming import stream
from pyspark.sql import functions as F

ROWS = [(1, 10, 3, "2024-01-01 10:00:00", "SELECT p_name,\n \"p_size\" FROM part"), (2, 11, 3, None, None)]


def frame(spark):
    return spark.createDataFrame(ROWS, "sub_id long, student_id long, question int, ts string, sql string").withColumn("ts", F.to_timestamp("ts"))


def test_files_round_trip(spark, tmp_path):
    df = frame(spark)
    df.write.parquet(f"{tmp_path}/p")
    df.write.json(f"{tmp_path}/j")
    df.write.option("header", True).option("escape", '"').csv(f"{tmp_path}/c")
    want = sorted(map(tuple, df.collect()))
    for kind in "pjc":
        got = files.read_submissions(spark, f"{tmp_path}/{kind}", {"p": "parquet", "j": "json", "c": "csv"}[kind])
        assert sorted(map(tuple, got.collect())) == want


def test_texts_and_partitioned_results(spark, tmp_path):
    (tmp_path / "t").mkdir()
    (tmp_path / "t" / "a17.sql").write_text("SELECT 1\nFROM part")
    row = files.read_texts(spark, f"{tmp_path}/t", 4).first()
    assert (row["student_id"], row["question"], row["sql"]) == (17, 4, "SELECT 1\nFROM part")
    graded = frame(spark).withColumn("marks", F.lit(1.0)).withColumn("feedback", F.lit("Correct."))
    files.write_graded(graded, f"{tmp_path}/g")
    assert (tmp_path / "g" / "question=3").is_dir() and spark.read.parquet(f"{tmp_path}/g").count() == 2
    files.write_feedback(graded, f"{tmp_path}/f")
    assert spark.read.json(f"{tmp_path}/f").count() == 2


def test_late_rows_are_dropped(spark, tmp_path):
    for k, (day, n) in enumerate((("2024-01-05", 3), ("2024-01-08", 1), ("2024-01-01", 5), ("2024-02-01", 1))):
        rows = spark.range(n).select(F.col("id").alias("sub_id"), F.lit(1).cast("long").alias("student_id"), F.lit(2).alias("question"), F.to_timestamp(F.lit(f"{day} 12:00:00")).alias("ts"), F.lit(0).alias("mask"), F.lit(0).alias("style"), F.lit("x").alias("sql"))
        rows.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        time.sleep(1.1)
    out = stream.run_to_end(stream.tumbling(stream.submission_stream(spark, f"{tmp_path}/in")), "qm_late", "append", f"{tmp_path}/checkpoint")
    got = {str(r["start"])[:10]: r["attempts"] for r in out.collect()}
    assert got == {"2024-01-05": 3, "2024-01-08": 1}


def test_appended_rows_stay_out_of_the_driver(spark, tmp_path):
    for n in (0, 3):
        folder = f"{tmp_path}/{n}"
        rows = spark.range(n).select("id", F.timestamp_seconds("id").alias("ts"))
        rows.write.parquet(f"{folder}/in")
        out = stream.run_to_end(spark.readStream.schema(rows.schema).parquet(f"{folder}/in"), f"qm_appended_{n}", "append", f"{folder}/checkpoint")
        assert (out.count(), out.columns) == (n, ["id", "ts"])
        assert out.inputFiles() and all("/checkpoint-rows/" in f for f in out.inputFiles())
        assert not spark.catalog.tableExists(f"qm_appended_{n}")


def test_a_repeated_text_is_judged_once_in_a_task(spark, tmp_path):
    from querymarks.sources import workloads as wl

    path, log = f"{tmp_path}/in", f"{tmp_path}/log"
    texts = [wl.CORRECT["w03"], "SELECT p_name FROM part", None, "SELECT FROM"] * 50
    frame = spark.createDataFrame([(k, 1, 3, None, 0, 0, t) for k, t in enumerate(texts)], stream.SUBMISSIONS)
    stream.write_ordered(frame, path, 1)
    correct = spark.createDataFrame([(3, "w03", wl.CORRECT["w03"])], "question int, cq_id string, sql string")

    class Noted(Catalog):
        """Is asked for each text that is judged."""

        def table(self, name):
            with open(log, "a") as f:
                f.write(f"{name}\n")
            return super().table(name)

    noted = Noted(default_catalog().tables)
    out = stream.run_to_end(stream.matched(stream.submission_stream(spark, path), correct, noted), "qm_once", "append", f"{tmp_path}/checkpoint")
    assert {(r["sql"], r["canonical_match"]) for r in out.collect()} == {(t, t == texts[0]) for t in texts}
    assert out.count() == 200
    with open(log) as f:
        assert len(f.readlines()) < 100


def test_feedback_sink_replaces_a_repeated_batch(spark, tmp_path):
    from querymarks.sources import workloads as wl

    correct = spark.createDataFrame([(3, "w03", wl.CORRECT["w03"])], "question int, cq_id string, sql string")
    write = stream.feedback_sink(correct, str(tmp_path))
    for _ in range(2):
        write(frame(spark).where("sql is not null"), 7)
    assert spark.read.json(str(tmp_path)).count() == 1


def test_declared_constraints_hold(spark, small):
    """Keys and foreign keys of the catalog, on the data: declarations are by hand and only checked here."""
    catalog = default_catalog()
    kinds = {r["kind"] for r in catalog.constraints(spark).collect()}
    assert kinds == {"unique", "not_null", "foreign"}
    for name, t in catalog.tables.items():
        df = spark.read.parquet(f"{small}/{name}.parquet")
        for key in t.keys:
            assert df.select(*key).distinct().count() == df.count(), (name, key)
        for f in t.foreign:
            ref = spark.read.parquet(f"{small}/{f.table}.parquet").select(F.col(f.ref_columns[0]).alias(f.columns[0]))
            assert df.join(ref, f.columns[0], "left_anti").isEmpty(), (name, f)
