"""Worked examples, brute force and invariants of the clustering methods."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors, point_vectors, text_vectors
from textgroups.operators import assign, hac, metrics, related
from textgroups.operators.assign import Totals, assign_nearest, totals, unit, vectors_of
from textgroups.operators.components import SCHEMES, components
from textgroups.operators.lloyd import lloyd
from textgroups.operators.microgroup import Links, MicroTable, build, choose_groups, count_groups, exact_threshold, group, initial_threshold, link_by_rank, link_edges, micro_similarity, microgroup, regroup, rss_of, threshold_search
from textgroups.operators.sampleseed import sampleseed
from textgroups.operators.sampling import draw_sample, everything, pick_centers, random_parts, sample_size
from textgroups.plans.audit import plan_uses
from textgroups.plans.storage import materialise
from textgroups.queries import PUBLISHED
from textgroups.sources.tables import load, replicate


@pytest.fixture(scope="module")
def vecs(spark, small):
    return text_vectors(load(spark, small, "documents"))


@pytest.fixture(scope="module")
def points(spark, small):
    return point_vectors(load(spark, small, "embeddings"))


def g1(zero_rule="either"):
    """Four micro-clusters with given cosines and lowest similarities (G1)."""
    low = np.array([0.10, 0.10, 0.30, 0.90])
    cos = {(0, 1): 0.50, (1, 2): 0.35, (0, 2): 0.05}
    a, b = np.triu_indices(4, 1)
    c = np.array([cos.get(p, 0.0) for p in zip(a.tolist(), b.tolist())])
    raw = np.round(c - low[a] - low[b], 12)
    zero = (c >= low[a]) | (c >= low[b]) if zero_rule == "either" else np.zeros(len(a), bool)
    return low, Links(a, b, c, np.maximum(raw, 0), np.where(raw > 0, 2, np.where(zero, 1, 0)))


def test_links_of_worked_example():
    low, links = g1()
    assert initial_threshold(low) == pytest.approx(0.35)
    sim = dict(zip(zip(links.a.tolist(), links.b.tolist()), links.sim.tolist()))
    assert sim[0, 1] == pytest.approx(0.30) and sim[1, 2] == 0
    assert group(links, link_edges(links, 0.35), 4).tolist() == [0, 1, 1, 2]
    assert group(links, link_edges(links, 0.30), 4, "closure").tolist() == [0, 0, 0, 1]
    assert group(links, link_edges(links, 0.30, strict=True), 4, "closure").tolist() == [0, 1, 1, 2]


def test_rank_cuts_the_order_where_a_threshold_reaches_k():
    low, links = g1()
    exact, info = choose_groups(links, low, 3, "first", "exact", "rank")
    assert exact.tolist() == [0, 1, 1, 2] and info["policy_used"] == "threshold"
    ranked, info = choose_groups(links, low, 3, "first", "rank", "rank")
    assert ranked.tolist() == [0, 0, 1, 2] and (info["policy_used"], info["groups_literal"], info["k_reached"]) == ("rank", 3, True)


def test_micro_similarity_matches_formula():
    rng = np.random.default_rng(1)
    c = unit(rng.random((12, 6)))
    low = rng.random(6) * 0.5
    links = micro_similarity(c, low)
    gram = c.T @ c / UNIT / UNIT
    for a, b, cos, sim, kind in zip(*links):
        raw = gram[a, b] - low[a] - low[b]
        assert cos == pytest.approx(gram[a, b]) and sim == pytest.approx(max(raw, 0), abs=1e-9)
        assert kind == (2 if round(raw, 12) > 0 else 1 if cos >= min(low[a], low[b]) else 0)


def test_first_match_differs_from_closure():
    links = Links(np.array([0, 0, 1]), np.array([1, 2, 2]), np.array([0.0, 0.5, 0.5]), np.array([0.0, 0.5, 0.5]), np.array([0, 2, 2]))
    linked = link_edges(links, 0.1)
    assert group(links, linked, 3, "first").tolist() == [0, 1, 0]
    assert group(links, linked, 3, "closure").tolist() == [0, 0, 0]


@pytest.mark.parametrize("link", ["first", "closure"])
def test_threshold_by_order_statistic_equals_trials(link):
    rng = np.random.default_rng(3)
    c = unit(rng.random((20, 15)) ** 4)
    links = micro_similarity(c, rng.random(15) * 0.3, "off")
    counts = [count_groups(links, s, 15, link) for s in np.linspace(0, 1, 60)]
    assert counts == sorted(counts)
    for k in range(1, 16):
        s, g = exact_threshold(links, 15, k, link)
        assert g == count_groups(links, s, 15, link)
        _, g2, _ = threshold_search(links, 15, k, 0.2, "bisect", link)
        assert abs(g - k) <= abs(g2 - k)
        assert group(links, link_by_rank(links, 15, k, link), 15, link).max() + 1 == k


def test_sample_sizes():
    assert [sample_size(20000, k) for k in (50, 100, 200)] == [1000, 1415, 2000] and sample_size(250000, 400) == 10000
    assert sample_size(3, 10) == 3


def test_agglomerate_against_naive():
    rng = np.random.default_rng(5)
    x = unit(rng.random((8, 14)))
    sim = x.T @ x / UNIT / UNIT
    for linkage in ("single", "complete", "average"):
        clusters = {i: [i] for i in range(14)}
        how = {"single": max, "complete": min, "average": lambda v: sum(v) / len(v)}[linkage]
        while len(clusters) > 4:
            pairs = [(-round(how([sim[p, q] for p in clusters[a] for q in clusters[b]]), 12), a, b) for a in clusters for b in clusters if a < b]
            _, a, b = min(pairs)
            clusters[a] += clusters.pop(b)
        want = np.empty(14, int)
        for n, a in enumerate(sorted(clusters)):
            want[clusters[a]] = n
        merges, labels = hac.agglomerate(sim, 4, linkage)
        assert labels.tolist() == want.tolist() and len(merges) == 10
        full, _ = hac.agglomerate(sim, 1, linkage)
        assert hac.cut_tree(full, 14, 4).tolist() == want.tolist()


def test_spanning_tree_cut_is_threshold_graph(spark, points):
    drawn = materialise(draw_sample(points.packed.select("doc_id"), 60))
    tree = sorted(((r["a"], r["b"], r["dp"]) for r in hac.mst(points, drawn, 4, 2).collect()), key=lambda e: (-e[2], e[0], e[1]))
    assert len(tree) == 59
    labels = {r["doc_id"]: r["cluster_id"] for r in hac.mst_link(points, drawn, k=5, parts=3).collect()}
    level = tree[60 - 5 - 1][2] / UNIT / UNIT
    edges = hac.pairwise_sim(points, drawn, level).select("a", "b")
    comp = {r["node"]: r["comp"] for r in components(edges.unionByName(drawn.select(F.col("doc_id").alias("a"), F.col("doc_id").alias("b")))).collect()}
    assert len(set(zip(labels.values(), (comp[i] for i in labels)))) == 5 == len(set(comp.values()))


def test_micro_clusters_where_no_matrix_fits(spark, vecs, monkeypatch):
    one = build(vecs, 30)
    want = rss_of(vecs, regroup(vecs, one, 6).centers)
    assert rss_of(vecs, regroup(vecs, build(vecs, 30, strategy="shuffle"), 6, strategy="shuffle").centers) == pytest.approx(want)
    monkeypatch.setattr(assign, "MATRIX_BYTES", 29 * vecs.v * 8)
    many = build(vecs, 30)
    assert isinstance(many, MicroTable) and many.m == one.m and many.rss == pytest.approx(one.rss)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(one.head(spark)) == rows(many.head(spark)) and rows(one.sums(spark)) == rows(many.sums(spark))
    assert all(np.array_equal(x, y) for x, y in zip(one.links(), many.links()))
    got = regroup(vecs, many, 6)
    assert rss_of(vecs, got.centers) == pytest.approx(want)
    monkeypatch.setattr(assign, "MATRIX_BYTES", 5 * vecs.v * 8)
    got = regroup(vecs, many, 6)
    assert not isinstance(got.centers, np.ndarray) and rss_of(vecs, got.centers) == pytest.approx(want)


def test_dense_pairs_by_blocks(spark, small, monkeypatch):
    monkeypatch.setattr(hac, "PAIR_ROWS", 20)
    e = load(spark, small, "embeddings").filter("label = 3")
    x = {r["vec_id"]: np.array(r["embedding"], float) for r in e.collect()}
    none = e.limit(1).select(F.lit(-1).cast("long").alias("vec_id"), F.lit(None).cast("array<float>").alias("embedding"))
    got = {(r["a"], r["b"]): r["cos"] for r in hac.dense_pairs(e.select("vec_id", "embedding").unionByName(none), "vec_id", "embedding").collect()}
    assert [got.pop((-1, a)) for a in x] == [None] * len(x)
    assert set(got) == {(a, b) for a in x for b in x if a < b} and len(x) > 40
    assert all(c == pytest.approx(x[a] @ x[b] / np.sqrt((x[a] @ x[a]) * (x[b] @ x[b]))) for (a, b), c in got.items())


def test_density_start_holds_no_matrix_of_the_sample(vecs, monkeypatch):
    sample = draw_sample(vecs.packed.select("doc_id"), sample_size(vecs.n, 5))
    x = vectors_of(vecs, sample.select(F.col("rk").alias("center_id"), "doc_id"))
    gram = x.T @ x / UNIT / UNIT
    picked, nearest = [], np.zeros(len(gram))
    for _ in range(5):
        value = np.round(gram.sum(axis=0) * (1 - nearest), 9)
        value[picked] = -np.inf
        picked.append(int(value.argmax()))
        nearest = np.maximum(nearest, gram[picked[-1]])
    monkeypatch.setattr(assign, "MATRIX_BYTES", 5 * vecs.v * 8)  # the five centres and no more
    assert np.array_equal(related.seed_centers(vecs, 5, "density"), x[:, picked])


def test_centroid_linkage_needs_no_vectors():
    rng = np.random.default_rng(6)
    x = unit(rng.random((8, 14))) / UNIT
    clusters = {i: [i] for i in range(14)}
    while len(clusters) > 4:
        mean = {c: x[:, m].sum(axis=1) for c, m in clusters.items()}
        _, a, b = min((-round(mean[a] @ mean[b] / np.sqrt((mean[a] @ mean[a]) * (mean[b] @ mean[b])), 12), a, b) for a in clusters for b in clusters if a < b)
        clusters[a] += clusters.pop(b)
    _, labels = hac.agglomerate(x.T @ x, 4, "centroid")
    assert sorted(map(sorted, clusters.values())) == sorted(np.flatnonzero(labels == c).tolist() for c in range(4))


@pytest.mark.parametrize("scheme", SCHEMES)
def test_threshold_components_write_no_pairs(spark, points, scheme, monkeypatch):
    monkeypatch.setattr(hac, "BLOCK_ROWS", -(-points.n // 3))
    info: dict = {}
    got = {r["node"]: r["comp"] for r in hac.threshold_components(points, 0.4, scheme, info).collect()}
    rows = sorted((r["doc_id"], r["val"]) for r in points.packed.collect())
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], np.int64)
    linked = (x @ x.T >= 0.4 * UNIT * UNIT) | np.eye(len(x), dtype=bool)
    want = ids
    for _ in ids:
        want = np.where(linked, want, 1 << 60).min(axis=1)
    assert got == dict(zip(ids.tolist(), want.tolist())) and 1 < len(set(want)) < len(ids)
    assert info["messages"] < len(x) ** 2 / 8


def test_threshold_components_deal_no_copies(spark, points, monkeypatch):
    """Blocks meet in tasks that read the written tiles: no exchange of points, which was one copy a block."""
    seen = []
    met = hac._met_tiles
    monkeypatch.setattr(hac, "BLOCK_ROWS", -(-points.n // 5))
    monkeypatch.setattr(hac, "_TILE_BYTES", 4 * points.v * 7)
    monkeypatch.setattr(hac, "_met_tiles", lambda tiles: seen.append(met(tiles)) or seen[-1])
    few = {r["node"]: r["comp"] for r in hac.threshold_components(points, 0.4, "full_exchange").collect()}
    assert len(seen) == 1 and plan_uses(seen[0], "CartesianProduct") and not plan_uses(seen[0], "Exchange")
    monkeypatch.setattr(hac, "BLOCK_ROWS", points.n)
    assert few == {r["node"]: r["comp"] for r in hac.threshold_components(points, 0.4).collect()} and len(seen) == 1


def test_links_between_blocks_are_exact(spark, monkeypatch):
    """Products of 2^39 - 1 and 2^39, which single precision cannot tell apart; only the second is half of 2^40."""
    monkeypatch.setattr(hac, "BLOCK_ROWS", 1)
    ids = sorted(r["id"] for r in spark.range(100).groupBy(F.pmod(F.xxhash64("id"), F.lit(4))).agg(F.min("id").alias("id")).collect())
    one, half = 1 << 20, 1 << 19
    rows = [[one, 1, 0, 0], [half - 1, one - 1, 0, 0], [0, 0, one, 1], [0, 0, half - 1, one]]
    packed = spark.createDataFrame([(i, [0, 1, 2, 3], x) for i, x in zip(ids, rows, strict=True)], "doc_id long, idx array<int>, val array<long>")
    got = {r["node"]: r["comp"] for r in hac.threshold_components(Vectors(packed, None, 4, 4), 0.5, "full_exchange").collect()}
    assert got == {ids[0]: ids[0], ids[1]: ids[1], ids[2]: ids[2], ids[3]: ids[2]}


def test_full_exchange_of_large_components(spark):
    """A path, a star, a clique and chained stars: messages grow with the links, not with the square of a component."""
    path = [(i, i + 1) for i in range(600)]
    star = [(1000, i) for i in range(1001, 1400)]
    clique = [(a, b) for a in range(2000, 2040) for b in range(a + 1, 2040)]
    chain = [(3000 + 50 * k, 3000 + 50 * k + i) for k in range(12) for i in range(1, 51)]
    far = [(9_007, 9_001), (9_001, 9_003), (-5, 9_003)]
    edges = path + star + clique + chain + far
    info: dict = {}
    got = {r["node"]: r["comp"] for r in components(spark.createDataFrame(edges, "a long, b long"), "full_exchange", info=info).collect()}
    low = [0, 1000, 2000, 3000, -5]
    assert got == {x: r for part, r in zip((path, star, clique, chain, far), low, strict=True) for e in part for x in e}
    assert info["messages"] < 60 * len(edges) and info["rounds"] < 40


@pytest.mark.parametrize("k", [1, 7, 40])
def test_one_task_seeding_is_the_spanning_tree_of_parts(vecs, k):
    drawn = materialise(draw_sample(vecs.packed.select("doc_id"), 40))
    table, centers = hac.link_in_one_task(vecs, drawn, k)
    parts = hac.mst_link(vecs, drawn, k=k, parts=3)
    assert sorted(zip(*(table.column(i).to_pylist() for i in (0, 1)))) == sorted((r["doc_id"], r["cluster_id"]) for r in parts.collect())
    assert np.array_equal(centers, hac.cluster_centers(vecs, parts, k))


def test_product_matrix_of_frequent_and_rare_terms(vecs, monkeypatch):
    pdf = vecs.packed.orderBy("doc_id").limit(60).toPandas()
    full = np.zeros((len(pdf), vecs.v))
    for i, (idx, val) in enumerate(zip(pdf["idx"], pdf["val"], strict=True)):
        full[i, idx] = val
    monkeypatch.setattr(hac, "_PAIRS", 500)
    assert np.array_equal(hac._gram(pdf), full @ full.T)
    monkeypatch.setattr(hac, "_DENSE", 10**9)
    assert np.array_equal(hac._gram(pdf, block=100), full @ full.T)


@pytest.mark.parametrize("scheme", SCHEMES)
def test_component_schemes(spark, scheme):
    path = [(i, i + 1) for i in range(1, 8)]
    star = [(20, i) for i in range(21, 30)]
    rng = np.random.default_rng(9)
    loose = [(int(a), int(b)) for a, b in rng.integers(100, 160, (45, 2))]
    edges = path + star + loose + [(50, 50), (None, 3)]
    info = {}
    got = {r["node"]: r["comp"] for r in components(spark.createDataFrame(edges, "a long, b long"), scheme, info=info).collect()}
    parent = {}
    find = lambda x: x if parent.setdefault(x, x) == x else find(parent[x])
    for a, b in edges:
        if a is not None:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    assert got == {x: find(x) for x in parent} and info["rounds"] >= 1


def test_components_of_nothing(spark):
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_rss_from_cf_triples():
    t = Totals(np.array([[UNIT], [UNIT]], float), np.array([2.0]), np.array([2.0 * UNIT * UNIT]), np.array([0.0]))
    assert t.rss() == pytest.approx(1.0)  # two orthogonal unit vectors (G7)


def test_unequal_partials_add_up(spark, vecs):
    c = vectors_of(vecs, pick_centers(vecs.packed.select("doc_id"), 4))
    one, many = totals(vecs.packed.coalesce(1), c), totals(vecs.packed.repartition(7), c)
    assert (one.sums == many.sums).all() and (one.count == many.count).all() and one.rss() == many.rss()


def test_strategies_agree(vecs, points):
    c = vectors_of(vecs, pick_centers(vecs.packed.select("doc_id"), 6))
    rows = lambda v, m, s: sorted(tuple(r) for r in assign_nearest(v, m, s).collect())
    assert rows(vecs, c, "block") == rows(vecs, c, "join") == rows(vecs, c, "shuffle")
    p = vectors_of(points, pick_centers(points.packed.select("doc_id"), 6))
    assert rows(points, p, "dense") == rows(points, p, "expr") == rows(points, p, "join")
    exact = {r["doc_id"]: r["center_id"] for r in assign_nearest(vecs, c).collect()}
    for s in ("truncate", "prune"):
        near = assign_nearest(vecs, c, s, terms=300).collect()
        assert np.mean([exact[r["doc_id"]] == r["center_id"] for r in near]) >= 0.9


def test_zero_policies(spark):
    rows = [(1, [0], [UNIT]), (2, [], []), (3, [1], [UNIT])]
    v = Vectors(spark.createDataFrame(rows, "doc_id long, idx array<int>, val array<long>"), None, 3, 2)
    c = np.eye(2)[:, ::-1] * UNIT
    label = lambda z: {r["doc_id"]: r["center_id"] for r in assign_nearest(v, c, zero_docs=z).collect()}
    assert label("lowest") == {1: 1, 2: 0, 3: 0} and label("drop") == {1: 1, 3: 0} and label("noise") == {1: 1, 2: -1, 3: 0}


def test_lloyd_objective_and_order(spark, vecs, small):
    got = lloyd(vecs, 8)
    assert got.info["rounds"] <= 8 and got.assign.count() == vecs.n
    sims = [assign_nearest(vecs, lloyd(vecs, 8, max_iter=i).centers).agg(F.sum("sim")).first()[0] for i in (0, 1, 3)]
    assert sims == sorted(sims)
    shuffled = Vectors(vecs.packed.repartition(5), vecs.terms, vecs.n, vecs.v)
    assert (lloyd(shuffled, 8).centers == got.centers).all()


def test_duplicate_centres_are_dropped(spark):
    rows = [(i, [i % 2], [UNIT]) for i in range(6)]
    v = Vectors(spark.createDataFrame(rows, "doc_id long, idx array<int>, val array<long>"), None, 6, 2)
    got = microgroup(v, 2, 6)
    assert got.info["n_micro"] == 2 and sorted(got.micro.stats.count.tolist()) == [3, 3]
    assert microgroup(v, 2, 6, keep_empty=True).info["n_micro"] == 6


def test_microgroup_and_sampleseed(vecs):
    a = microgroup(vecs, 6, 30)
    assert a.info["k_reached"] and a.info["passes"] == 2 and a.assign.count() == vecs.n
    base = totals(vecs.packed, lloyd(vecs, 6).centers).rss()
    assert metrics.rss_loss(metrics.rss(vecs, a.assign), base) < 15
    b = sampleseed(vecs, 6)
    assert b.info["s"] == sample_size(vecs.n, 6) and b.assign.select("cluster_id").distinct().count() == 6
    fixed = b.sample.join(b.assign.withColumnRenamed("cluster_id", "now"), "doc_id").filter("now <> cluster_id")
    assert fixed.isEmpty()
    with pytest.raises(ValueError):
        microgroup(vecs, 6, 30, unreachable="error")


def test_rss_two_ways_and_replication(spark, vecs, small):
    c = lloyd(vecs, 5, max_iter=2).centers
    labels = assign_nearest(vecs, c).withColumnRenamed("center_id", "cluster_id")
    assert metrics.rss(vecs, labels) == pytest.approx(totals(vecs.packed, c).rss(), rel=1e-9)
    twice = Vectors(replicate(vecs.packed, 2), vecs.terms, 2 * vecs.n, vecs.v)
    assert totals(twice.packed, c).rss() == pytest.approx(2 * totals(vecs.packed, c).rss(), rel=1e-9)
    assert replicate(load(spark, small, "documents"), 1.5).count() in range(250, 350)


def test_random_parts_are_balanced(spark, vecs):
    sizes = [r["count"] for r in random_parts(draw_sample(vecs.packed.select("doc_id"), 50), 4).groupBy("part").count().collect()]
    assert max(sizes) - min(sizes) <= 1


@pytest.mark.parametrize("method", ["bernoulli", "reservoir", "stratified", "hash"])
def test_draws_repeat(spark, small, method):
    docs = load(spark, small, "documents")
    draw = lambda: {r["doc_id"] for r in draw_sample(docs, 40, method=method, stratum="lang" if method == "stratified" else None, n=200).collect()}
    assert draw() == draw() and 20 <= len(draw()) <= 80


def test_related_methods(vecs, points):
    assert related.bisecting(vecs, 4, rounds=2, trials=2).select("cluster_id").distinct().count() == 4
    _, _, errors = related.nmf(points._replace(packed=points.packed.select("doc_id", "idx", F.transform("val", lambda x: F.abs(x)).alias("val"))), 4, 4)
    assert all(a >= b - 1e-9 for a, b in zip(errors, errors[1:]))
    assert related.factorkm(vecs, 4, 4, 2, "heaviest").count() == vecs.n
    assert related.mllib_kmeans(points, 5).count() == points.n
    assert related.seed_centers(points, 5, "oversample").shape == (64, 5)


def test_measures():
    for k, nodes, t, r, tm, rm, ts, rs in PUBLISHED:
        assert 70 <= metrics.time_gain(tm, t) <= 88 and 5 <= metrics.rss_loss(rm, r) <= 8 and 3.5 <= metrics.rss_loss(rs, r) <= 5.5
        assert metrics.time_gain(ts, t) > metrics.time_gain(tm, t) and rs < rm
    assert metrics.logical_cost("sampleseed", 1000, 10, s=100, rounds=2) == 23000
    assert metrics.stability([1.0, 1.1])["spread_pct"] == pytest.approx(100 * 0.1 / 1.05)


def test_external_measures(spark):
    truth = spark.createDataFrame([(i, "ab"[i % 2]) for i in range(10)], "doc_id long, l string")
    same = spark.createDataFrame([(i, i % 2, 1.0) for i in range(10)], "doc_id long, cluster_id long, sim double")
    got = metrics.external(same, truth, "l")
    assert got["purity"] == 1 and got["nmi"] == pytest.approx(1) and got["ari"] == pytest.approx(1) and got["pair_f"] == pytest.approx(1)


def test_trees_aligned_from_the_root_down(points):
    """One part is the plain tree; k parts of the whole collection give k clusters over all documents, the same each time."""
    every = materialise(everything(points.packed.select("doc_id")))
    n = every.count()
    assert sorted(r["rk"] for r in every.collect()) == list(range(n))
    one = {r["doc_id"]: r["cluster_id"] for r in hac.parthac(points, every, 6, 1, "average")[0].collect()}
    whole = {r["doc_id"]: r["cluster_id"] for r in hac.sample_clusters(points, every, 6, "average").collect()}
    assert len(set(zip((one[i] for i in whole), whole.values()))) == 6 == len(set(one.values()))
    four = {r["doc_id"]: r["cluster_id"] for r in hac.parthac(points, every, 6, 4, "average")[0].collect()}
    assert len(four) == n and set(four.values()) == set(range(6))
    assert four == {r["doc_id"]: r["cluster_id"] for r in hac.parthac(points, every, 6, 4, "average")[0].collect()}


def test_alignment_of_equal_trees():
    """Two parts with the same tree, one with its halves swapped: the same leaves meet."""
    vec = lambda *w: (np.array([i for i, x in enumerate(w) if x]), np.array([x for x in w if x]))
    leaf = lambda *w: hac.Node(-1, -1, 1.0, 2, *vec(*w))
    a, b, c = (9, 1, 0), (8, 4, 0), (0, 1, 9)
    ab = tuple(x + y for x, y in zip(a, b))
    root = tuple(x + y for x, y in zip(ab, c))
    first = [leaf(*a), leaf(*b), leaf(*c), hac.Node(0, 1, 0.9, 4, *vec(*ab)), hac.Node(3, 2, 0.1, 6, *vec(*root))]
    second = [leaf(*c), leaf(*b), leaf(*a), hac.Node(1, 2, 0.8, 4, *vec(*ab)), hac.Node(0, 3, 0.2, 6, *vec(*root))]
    got = hac.align_trees_down({0: first, 1: second}, 3, 3)
    assert got[0, 0] == got[1, 2] and got[0, 1] == got[1, 1] and got[0, 2] == got[1, 0] and len(set(got.values())) == 3
    two = hac.align_trees_down({0: first, 1: second}, 2, 3)
    assert two[0, 0] == two[0, 1] == two[1, 1] == two[1, 2] != two[0, 2] == two[1, 0]


def test_limits_are_errors(points, monkeypatch):
    drawn = draw_sample(points.packed.select("doc_id"), 30)
    monkeypatch.setattr(hac, "MOST_ROWS", 20)
    with pytest.raises(ValueError):
        hac.sample_clusters(points, drawn, 3, "average")
    monkeypatch.setattr(assign, "MATRIX_BYTES", 100)
    with pytest.raises(ValueError):
        lloyd(points, 5, max_iter=1, strategy="matrix")
    assert lloyd(points, 5, max_iter=2).info["rounds"] == 2  # goes by table
