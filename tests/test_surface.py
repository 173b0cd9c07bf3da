"""Sources, user functions, plans and streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from textgroups.functions.text import strip_html, tokens
from textgroups.functions.udfs import register
from textgroups.functions.vectors import text_vectors
from textgroups.operators.assign import assign_nearest
from textgroups.operators.lloyd import lloyd
from textgroups.operators.relational import asof_join, band_join, event_windows
from textgroups.plans.audit import explain, plan_uses
from textgroups.plans.skew import join_lookup, running_totals
from textgroups.sources import tables
from textgroups.streaming import stream as S


def test_formats_round_trip(spark, small, tmp_path):
    docs = tables.require_schema(tables.load(spark, small, "labels"), tables.SCHEMAS["labels"])
    for fmt, read in (("csv", lambda p: tables.load_csv(spark, p, tables.SCHEMAS["labels"], header=False)), ("json", lambda p: tables.load_jsonl(spark, p, tables.SCHEMAS["labels"]))):
        tables.save(docs, f"{tmp_path}/{fmt}", fmt=fmt)
        assert sorted(map(tuple, read(f"{tmp_path}/{fmt}").drop("_corrupt").collect())) == sorted(map(tuple, docs.collect()))
    tables.save_model(docs, {"k": 3}, f"{tmp_path}/m")
    got, info = tables.load_model(spark, f"{tmp_path}/m")
    assert got.count() == docs.count() and info == {"k": 3}
    with pytest.raises(ValueError):
        tables.require_schema(docs.drop("toxic"), tables.SCHEMAS["labels"])


def test_tokens_stop_and_ngrams(spark):
    docs = spark.createDataFrame([(1, "The cat, the CAT sat!"), (2, None), (3, "")], "doc_id long, text string")
    assert [r["term"] for r in tokens(docs).orderBy("pos").collect()] == ["the", "cat", "the", "cat", "sat"]
    stop = spark.createDataFrame([("the",)], "term string")
    assert [r["term"] for r in tokens(docs, stop=stop, ngram=2).orderBy("pos").collect()] == ["cat cat", "cat sat"]
    page = spark.createDataFrame([("<p>a &amp; b</p><script>x</script>",)], "h string")
    assert page.select(strip_html(F.col("h"))).first()[0].split() == ["a", "&", "b"]


def test_scan_is_pruned_and_pushed_down(spark, small):
    df = tables.load(spark, small, "documents").filter("n_chars > 100").select("doc_id")
    text = explain(df)
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars,100)]" in text and "text" not in text.split("ReadSchema:")[1].split("\n")[0]
    assert not plan_uses(df, "Exchange")


def test_assignment_has_no_shuffle(spark, small):
    v = text_vectors(tables.load(spark, small, "documents"))
    plan = explain(assign_nearest(v, np.ones((v.v, 3))))
    assert "MapInArrow" in plan and "Exchange" not in plan


def test_running_totals_and_lookup(spark):
    rows = spark.createDataFrame([("x" if i % 3 else "y", i, i // 10, i % 4) for i in range(100)], "g string, i int, b int, v int")
    got = running_totals(rows, ["g"], "b", [F.col("i")], F.col("v"), "p", "s").orderBy("i").collect()
    seen = {"x": (0, 0), "y": (0, 0)}
    for r in got:
        assert (r["p"], r["s"]) == seen[r["g"]]
        seen[r["g"]] = (r["p"] + 1, r["s"] + r["v"])
    lookup = rows.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.max("i").alias("top"))
    assert join_lookup(rows, lookup, "g", "n").count() == 100


def test_time_joins(spark):
    left = spark.createDataFrame([("a", 5, 1), ("a", 9, 2), ("b", 1, 3)], "k string, t int, id int")
    right = spark.createDataFrame([("a", 4, "x"), ("a", 9, "y"), ("b", 2, "z")], "k string, t int, v string")
    assert {r["id"]: r["v"] for r in asof_join(left, right, "t", ["k"], ["v"]).collect()} == {1: "x", 2: "y", 3: None}
    a, b = spark.range(20).withColumnRenamed("id", "x"), spark.range(20).withColumnRenamed("id", "y")
    assert band_join(a, b, "x", "y", 2).count() == sum(abs(i - j) <= 2 for i in range(20) for j in range(20))


def test_sql_functions(spark):
    register(spark)
    assert spark.sql("SELECT cos_sim(array(1D, 0D), array(1D, 1D))").first()[0] == pytest.approx(0.5**0.5)
    assert spark.sql("SELECT purity(x) FROM VALUES ('a'), ('a'), ('b') t(x)").first()[0] == pytest.approx(2 / 3)
    assert spark.sql("SELECT cf_triple(v) FROM VALUES (array(1D, 0D)), (array(0D, 1D)) t(v)").first()[0] == [2, 2, 1, 1]
    assert [tuple(r) for r in spark.sql("SELECT * FROM tokenize('A b, c')").collect()] == [(0, "a"), (1, "b"), (2, "c")]


@pytest.fixture(scope="module")
def model(spark, small):
    v = text_vectors(tables.load(spark, small, "documents"))
    return S.Frozen(v.terms, lloyd(v, 4, max_iter=2).centers, v.n), v


def run(query, name):
    q = query.format("memory").queryName(name).start()
    q.processAllAvailable()
    q.stop()


def test_stream_assign_equals_batch(spark, small, model, tmp_path):
    frozen, v = model
    docs = tables.load(spark, small, "documents")
    docs.repartition(3).write.parquet(f"{tmp_path}/d")
    stream = S.read_documents(spark, f"{tmp_path}/d", docs.schema)
    run(S.stream_assign(stream, frozen).writeStream.outputMode("append"), "assigned")
    batch = assign_nearest(v, frozen.centers).withColumnRenamed("center_id", "cluster_id").select("doc_id", "cluster_id")
    assert sorted(map(tuple, spark.sql("SELECT doc_id, cluster_id FROM assigned").collect())) == sorted(map(tuple, batch.collect()))


def test_late_rows_and_state(spark, tmp_path):
    schema = "id long, ts timestamp, cluster_id long, sim double"
    first = [(1, "2024-01-01 00:10:00", 0, 0.5), (2, "2024-01-03 00:00:00", 0, 0.25), (2, "2024-01-03 00:00:00", 1, 1.0)]
    late = [(3, "2024-01-01 00:20:00", 0, 0.5), (4, "2024-01-04 12:00:00", 1, 0.5)]
    between = [(5, "2024-01-03 01:00:00", 2, 0.5)]  # late rows are judged by the watermark of the batch before
    for i, rows in enumerate((first, between, late)):
        spark.createDataFrame(rows, "id long, ts string, cluster_id long, sim double").select("id", F.col("ts").cast("timestamp").alias("ts"), "cluster_id", "sim").coalesce(1).write.parquet(f"{tmp_path}/s/{i}")
    source = lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/s/*")
    run(S.stream_cf(source()).writeStream.outputMode("append"), "cf")
    assert [r["n"] for r in spark.sql("SELECT n FROM cf WHERE start < '2024-01-02'").collect()] == [1]  # the late row is dropped
    run(S.cf_state(source()).writeStream.outputMode("update"), "state")
    assert spark.sql("SELECT max(n), max(sum_sim) FROM state WHERE cluster_id = 0").first()[0] == 3
    run(S.dedupe_stream(source(), ["id"]).writeStream.outputMode("append"), "once")
    assert spark.sql("SELECT count(*) FROM once").first()[0] == spark.sql("SELECT count(DISTINCT id) FROM once").first()[0]


def test_minibatch_centres(spark, small, model, tmp_path):
    frozen, _ = model
    docs = tables.load(spark, small, "documents")
    docs.repartition(2).write.parquet(f"{tmp_path}/m")
    q = S.stream_minibatch(S.read_documents(spark, f"{tmp_path}/m", docs.schema), frozen, f"{tmp_path}/state").start()
    q.processAllAvailable()
    q.stop()
    last = spark.read.parquet(f"{tmp_path}/state/1").filter("term_id < 0").agg(F.sum("s")).first()[0]
    assert last == docs.count() + frozen.centers.shape[1]


@pytest.mark.parametrize("kind", ["tumbling", "sliding", "session"])
def test_windows(spark, small, kind):
    events = tables.load(spark, small, "events")
    total = event_windows(events, kind).agg(F.sum("n")).first()[0]
    assert total == events.count() * (4 if kind == "sliding" else 1)


def test_running_totals_in_two_levels(spark):
    from textgroups.plans.skew import running_totals

    rows = spark.range(3000).selectExpr("if(id % 3 = 0, 'hot', concat('g', id % 7)) g", "id", "cast(id / 10 as long) b")
    want, seen = {}, {}
    for r in rows.orderBy("id").collect():
        n, s = seen.get(r["g"], (0, 0))
        want[r["id"]], seen[r["g"]] = (n, s), (n + 1, s + r["id"])
    for coarse in (None, F.floor(F.col("b") / 16)):
        got = running_totals(rows, ["g"], "b", [F.col("id")], F.col("id"), "at", "before", coarse).collect()
        assert {r["id"]: (r["at"], r["before"]) for r in got} == want


def test_workspaces_are_cleared(spark):
    from textgroups.plans import storage

    kept = storage.workspace(spark, "kept")
    spark.range(3).write.parquet(kept)
    assert kept.startswith(storage._own(spark) + "/") and spark.sparkContext.applicationId in kept
    storage.drop_path(spark, kept)
    with pytest.raises(Exception):
        spark.read.parquet(kept)
