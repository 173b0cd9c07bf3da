"""What the driver has to hold at once: exchanges of a plan, and how often a stage builds components."""

from pyspark.sql import functions as F

import corpus_pipeline
from textgroups.llm import mixing, near_copies
from textgroups.plans.audit import explain
from textgroups.plans.skew import join_lookup


def exchanges(spark, first):
    """Exchanges of the plan of each execution from number ``first`` on."""
    store = spark._jsparkSession.sharedState().statusStore()
    names = []
    for k in range(first, next_execution(spark)):
        nodes = store.planGraph(k).allNodes()
        names.append(sum("Exchange" in nodes.apply(i).name() for i in range(nodes.size())))
    return names


def next_execution(spark):
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    store = spark._jsparkSession.sharedState().statusStore()
    return store.executionsList().last().executionId() + 1 if store.executionsCount() else 0


def test_mixing_in_small_plans(spark, small):
    """No plan of the mixing stage holds the lines, the schedule and their join together."""
    docs = spark.read.parquet(f"{small}/documents.parquet")
    docs.limit(1).count()
    first = next_execution(spark)
    assert corpus_pipeline.mix(spark, docs, small).count() > 0
    assert max(exchanges(spark, first)) <= 16


def test_lookup_of_one_kind_of_keys(spark):
    rows = spark.range(9000).select((F.col("id") % 3000).alias("k"), "id")
    lookup = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    light = join_lookup(rows, lookup, "k", "n")
    assert "BroadcastExchange" not in explain(light) and light.count() == 9000
    few = rows.withColumn("k", F.col("k") % 3)
    heavy = join_lookup(few, few.groupBy("k").agg(F.count(F.lit(1)).alias("n")), "k", "n")
    assert "SortMergeJoin" not in explain(heavy) and heavy.count() == 9000
    assert light.columns == heavy.columns == ["k", "id", "n"]
    both = rows.filter("k < 2500").withColumn("k", F.when(F.col("id") % 2 == 0, F.lit(-1)).otherwise(F.col("k")))
    mixed = join_lookup(both, both.groupBy("k").agg(F.count(F.lit(1)).alias("n")), "k", "n")
    assert mixed.count() == both.count() and mixed.filter("k = -1").first()["n"] == both.filter("k = -1").count()
    assert join_lookup(rows, lookup.filter("n < 0"), "k", "n").count() == 0


def test_components_once_a_turn(spark, small, monkeypatch):
    calls = []
    built = near_copies.components
    monkeypatch.setattr(near_copies, "components", lambda *a, **b: calls.append(1) or built(*a, **b))
    texts = [" ".join(f"w{n % 20}-{i}" for i in range(60)) + f" end{n}" for n in range(60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert sorted(r["doc_id"] for r in near_copies.keep_one(docs).collect()) == list(range(20))
    assert len(calls) <= near_copies.TURNS


def test_pieces_of_the_mix_add_up(spark, small):
    """Each source gives its target rounded down, to the word, as before the parts were written."""
    rows = mixing.mixture(spark.read.parquet(f"{small}/documents.parquet"))
    for r in rows.groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target")).collect():
        assert r["taken"] == int(r["target"])
