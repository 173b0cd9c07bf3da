"""Every method, measure and operator as a query over the given tables, with its SQL twin where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from textgroups import oracles as O
from textgroups.functions import text as X
from textgroups.functions.vectors import Vectors, as_map, cos_sparse, point_vectors, text_vectors
from textgroups.operators import hac, metrics, microgroup, relational, sampleseed
from textgroups.operators.assign import assign_nearest, vectors_of
from textgroups.operators.lloyd import lloyd, lloyd_euclidean
from textgroups.operators.related import bisecting, cf_onepass, factorkm, mllib_bisecting, mllib_kmeans, random_medoids, rep_points, seed_centers
from textgroups.operators.sampling import draw_sample, everything, pick_centers, random_parts, sample_size, sample_size_of, split_sample
from textgroups.sources.tables import load

K, M, FULL = 10, 50, O.FULL
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_held: dict[tuple, object] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _once(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], object]):
    """Fitted things are made once per application and input."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _held:
        _held[key] = make()
    return _held[key]


def docs_of(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "documents")


def vecs_of(spark, sf_dir) -> Vectors:
    return _once(spark, sf_dir, "vecs", lambda: text_vectors(docs_of(spark, sf_dir)))


def points_of(spark, sf_dir) -> Vectors:
    return _once(spark, sf_dir, "points", lambda: point_vectors(load(spark, sf_dir, "embeddings")))


def micro_of(spark, sf_dir):
    return _once(spark, sf_dir, "micro", lambda: microgroup.build(vecs_of(spark, sf_dir), M))


def links_of(spark, sf_dir):
    return _once(spark, sf_dir, "links", lambda: micro_of(spark, sf_dir).links())


def lloyd_of(spark, sf_dir, rounds=3):
    return _once(spark, sf_dir, f"lloyd{rounds}", lambda: lloyd(vecs_of(spark, sf_dir), K, max_iter=rounds))


def sample_of(spark, sf_dir, rounds=2, reassign=False):
    return _once(spark, sf_dir, f"sample{rounds}{reassign}", lambda: sampleseed.sampleseed(vecs_of(spark, sf_dir), K, rounds=rounds, reassign_sample=reassign))


def micro_result(spark, sf_dir):
    return _once(spark, sf_dir, "microgroup", lambda: microgroup.regroup(vecs_of(spark, sf_dir), micro_of(spark, sf_dir), K, threshold="rank"))


def _drawn(ids: DataFrame) -> DataFrame:
    """The sample of the second proposal: sqrt(k n) ids."""
    n = ids.count()
    return draw_sample(ids, sample_size(n, K), n=n)


def _sims(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


D = O.documents()
P = O.points()

# ---------------------------------------------------------------- text to vectors


@query(O.with_(D[:2], "SELECT doc_id, count(*) AS n, count(DISTINCT term) AS terms FROM tok WHERE term <> '' GROUP BY doc_id"))
def tokens(spark, sf_dir):
    """O5"""
    return X.tokens(docs_of(spark, sf_dir)).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("term").alias("terms"))


@query(O.with_(D[:3], "SELECT doc_id, term, tf FROM tf"))
def term_freq(spark, sf_dir):
    """O6"""
    return X.term_freq(X.tokens(docs_of(spark, sf_dir)))


@query(O.with_(D[:4], "SELECT term, df FROM dfq"))
def doc_freq(spark, sf_dir):
    """O7"""
    return X.doc_freq(X.term_freq(X.tokens(docs_of(spark, sf_dir))))


@query(O.with_(D[:3], "SELECT term, count(*) AS df FROM tf GROUP BY term HAVING count(*) BETWEEN 5 AND 200"))
def df_band(spark, sf_dir):
    """O7"""
    return X.doc_freq(X.term_freq(X.tokens(docs_of(spark, sf_dir))), 5, 200)


@query(O.with_(D[:6], "SELECT doc_id, term, tf, wq FROM post"))
def tfidf(spark, sf_dir):
    """O8"""
    docs = docs_of(spark, sf_dir)
    tf = X.term_freq(X.tokens(docs))
    return X.tfidf(tf, X.doc_freq(tf), docs.count()).select("doc_id", "term", "tf", "wq")


@query(O.with_(D[:5], "SELECT doc_id, round(sqrt(sum(w * w)), 6) AS norm FROM raw WHERE w > 0 GROUP BY doc_id"))
def doc_norms(spark, sf_dir):
    """DM2"""
    docs = docs_of(spark, sf_dir)
    tf = X.term_freq(X.tokens(docs))
    w = X.tfidf(tf, X.doc_freq(tf), docs.count(), norm="none")
    return w.groupBy("doc_id").agg(F.round(F.sqrt(F.sum(F.col("w") * F.col("w"))), 6).alias("norm"))


@query("""WITH t AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[^\\p{L}\\p{N}]+'), lambda x: x <> '') AS ws FROM documents),
g AS (SELECT doc_id, unnest(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1])) AS term FROM t WHERE len(ws) > 1)
SELECT term, count(*) AS n FROM g GROUP BY term HAVING count(*) >= 20""")
def bigrams(spark, sf_dir):
    """O5 with n-grams"""
    return X.tokens(docs_of(spark, sf_dir), ngram=2).groupBy("term").agg(F.count(F.lit(1)).alias("n")).filter("n >= 20")


@query(O.with_(D[:2], f"SELECT doc_id, ('0x' || substr(md5(term), 1, 15))::BIGINT % {1 << 18} AS term_id, count(*) AS tf FROM tok WHERE term <> '' GROUP BY 1, 2"))
def hash_tf(spark, sf_dir):
    """O9"""
    return X.hash_tf(X.tokens(docs_of(spark, sf_dir)))


@query(O.with_(D[:6], "SELECT doc_id, count(*) AS terms, CAST(sum(wq) AS BIGINT) AS total FROM post GROUP BY doc_id"))
def packed_vectors(spark, sf_dir):
    """O10"""
    return vecs_of(spark, sf_dir).packed.filter(F.size("idx") > 0).select("doc_id", F.size("idx").cast("long").alias("terms"), F.aggregate("val", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"))


_TEXT_OF_PAGE = "replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '\"'), '&nbsp;', ' '), '&amp;', '&')"


@query(f"SELECT doc_id, count(*) AS n FROM (SELECT page_id AS doc_id, unnest(string_split_regex(lower({_TEXT_OF_PAGE}), '[^\\p{{L}}\\p{{N}}]+')) AS term FROM pages) WHERE term <> '' GROUP BY doc_id")
def pages_tokens(spark, sf_dir):
    """W15"""
    pages = load(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), X.strip_html(F.col("html")).alias("text"))
    return X.tokens(pages).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, count(*) AS n FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^\\p{L}\\p{N}]+')) AS term FROM (SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn) AS text FROM conversations GROUP BY conv_id)) WHERE term <> '' GROUP BY doc_id")
def conv_tokens(spark, sf_dir):
    """W15"""
    return X.tokens(X.join_turns(load(spark, sf_dir, "conversations"))).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))


# ---------------------------------------------------------------- samples and parts


@query(O.with_([D[0], *O.ordered()], f"SELECT doc_id, rk FROM ord WHERE rk < (SELECT CAST(ceil(sqrt({K} * count(*)::DOUBLE)) AS BIGINT) FROM ids)"))
def doc_sample(spark, sf_dir):
    """H1, H2"""
    ids = docs_of(spark, sf_dir).select("doc_id")
    n = ids.count()
    return draw_sample(ids, sample_size(n, K), n=n)


@query(O.with_([D[0], ("o", "SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY md5('42:' || doc_id)) AS i, count(*) OVER (PARTITION BY lang) AS c FROM documents")], f"SELECT doc_id, lang FROM o WHERE i <= ceil(c * ({O.sample_rows(K)}::DOUBLE / (SELECT count(*) FROM documents)))"))
def stratified_sample(spark, sf_dir):
    """H2b"""
    docs = docs_of(spark, sf_dir)
    n = docs.count()
    return draw_sample(docs, sample_size(n, K), method="stratified", stratum="lang", n=n).join(docs.select("doc_id", "lang"), "doc_id").select("doc_id", "lang")


@query(O.with_([D[0]], f"SELECT doc_id, row_number() OVER (ORDER BY md5('42:' || doc_id), doc_id) - 1 AS rk FROM ids WHERE substr(md5('42:' || doc_id), 1, 8) < printf('%08x', CAST(floor({O.sample_rows(K)}::DOUBLE / (SELECT count(*) FROM ids) * 4294967295) AS BIGINT))"))
def bernoulli_sample(spark, sf_dir):
    """H2b"""
    ids = docs_of(spark, sf_dir).select("doc_id")
    n = ids.count()
    return draw_sample(ids, sample_size(n, K), method="bernoulli", n=n)


@query("SELECT lang, n, k, least(n, CAST(ceil(sqrt(n::DOUBLE * k)) AS BIGINT)) AS s FROM (SELECT lang, count(text) AS n FROM documents GROUP BY lang) CROSS JOIN (SELECT unnest([50, 100, 200, 400]) AS k)")
def sample_sizes(spark, sf_dir):
    """H1 on the documents of each language that have a text"""
    n = docs_of(spark, sf_dir).groupBy("lang").agg(F.count("text").alias("n"))
    return n.withColumn("k", F.explode(F.array(*map(F.lit, (50, 100, 200, 400))))).select("lang", "n", "k", sample_size_of(F.col("n"), F.col("k")).alias("s"))


@query(O.with_([D[0], *O.ordered()], f"SELECT doc_id, rk, rk % 4 AS part FROM ord WHERE rk < {O.sample_rows(K)}"))
def random_parts_of_sample(spark, sf_dir):
    """H6"""
    return random_parts(_drawn(docs_of(spark, sf_dir).select("doc_id")), 4)


@query(O.with_([D[0], *O.ordered()], f"SELECT CASE WHEN rk < {O.sample_rows(K)} THEN 'member' ELSE 'rest' END AS side, count(*) AS n, CAST(sum(doc_id) AS BIGINT) AS total FROM ord GROUP BY 1"))
def sample_members(spark, sf_dir):
    """O16"""
    ids = docs_of(spark, sf_dir).select("doc_id")
    inside, outside = split_sample(ids, _drawn(ids))
    both = inside.withColumn("side", F.lit("member")).unionByName(outside.withColumn("side", F.lit("rest")))
    return both.groupBy("side").agg(F.count(F.lit(1)).alias("n"), F.sum("doc_id").alias("total"))


# ---------------------------------------------------------------- baseline


@query(O.with_([*D, *O.first_centres(K), *O.labels("c0", "l0")], f"SELECT doc_id, c AS center_id, round(dp / {FULL}.0, 6) AS sim FROM l0"))
def assign_once(spark, sf_dir):
    """A1, A2, B1m"""
    v = vecs_of(spark, sf_dir)
    return _sims(assign_nearest(v, vectors_of(v, pick_centers(v.packed.select("doc_id"), K))), "sim")


@query(ORACLES["assign_once"])
def assign_join(spark, sf_dir):
    """The same by joins"""
    v = vecs_of(spark, sf_dir)
    return _sims(assign_nearest(v, vectors_of(v, pick_centers(v.packed.select("doc_id"), K)), "join"), "sim")


@query(ORACLES["assign_once"])
def assign_shuffle(spark, sf_dir):
    """The same by a salted shuffle join"""
    v = vecs_of(spark, sf_dir)
    return _sims(assign_nearest(v, vectors_of(v, pick_centers(v.packed.select("doc_id"), K)), "shuffle"), "sim")


_POINT_LABELS = O.with_([*P, *O.first_centres(K), *O.labels("c0", "l0")], f"SELECT doc_id, c AS center_id, round(dp / {FULL}.0, 6) AS sim FROM l0")


@query(_POINT_LABELS)
def assign_expr(spark, sf_dir):
    """Points, inside the JVM"""
    v = points_of(spark, sf_dir)
    return _sims(assign_nearest(v, vectors_of(v, pick_centers(v.packed.select("doc_id"), K)), "expr"), "sim")


@query(_POINT_LABELS)
def assign_dense(spark, sf_dir):
    """D3"""
    v = points_of(spark, sf_dir)
    return _sims(assign_nearest(v, vectors_of(v, pick_centers(v.packed.select("doc_id"), K)), "dense"), "sim")


@query(O.with_([*D, *O.lloyd(K, 3), O.heaviest("c3", 200), *O.labels("heavy", "lt")], f"SELECT doc_id, c AS center_id, round(dp / {FULL}.0, 6) AS sim FROM lt"))
def assign_truncated(spark, sf_dir):
    """D6"""
    return _sims(assign_nearest(vecs_of(spark, sf_dir), lloyd_of(spark, sf_dir).centers, "truncate", terms=200), "sim")


_PRUNED = [*D, *O.lloyd(K, 3), O.heaviest("c3", 200), ("met", "SELECT DISTINCT p.doc_id, h.c FROM post p JOIN heavy h USING (term)"), ("pd", "SELECT p.doc_id, c.c, CAST(sum(p.wq * c.cq) AS BIGINT) AS dp FROM post p JOIN c3 c USING (term) SEMI JOIN met ON met.doc_id = p.doc_id AND met.c = c.c GROUP BY p.doc_id, c.c"), ("lp", "SELECT i.doc_id, coalesce(x.c, 0) AS c, coalesce(x.dp, 0) AS dp FROM ids i LEFT JOIN (SELECT * FROM pd QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY dp DESC, c) = 1) x USING (doc_id)")]


@query(O.with_(_PRUNED, f"SELECT doc_id, c AS center_id, round(dp / {FULL}.0, 6) AS sim FROM lp"))
def assign_pruned(spark, sf_dir):
    """D7"""
    return _sims(assign_nearest(vecs_of(spark, sf_dir), lloyd_of(spark, sf_dir).centers, "prune", terms=200), "sim")


def _lloyd_query(r: int):
    def run(spark, sf_dir):
        return lloyd_of(spark, sf_dir, r).assign.select("doc_id", "cluster_id")

    run.__name__ = f"lloyd_r{r}"
    query(O.with_([*D, *O.lloyd(K, r)], f"SELECT doc_id, c AS cluster_id FROM l{r}"))(run)


for _r in (1, 2, 3):
    _lloyd_query(_r)


@query(ORACLES["lloyd_r2"])
def lloyd_shuffled(spark, sf_dir):
    """B1 with centres that stay a table"""
    return lloyd(vecs_of(spark, sf_dir), K, max_iter=2, strategy="shuffle").assign.select("doc_id", "cluster_id")


@query(O.with_([*D, *O.lloyd(K, 2)], "\nUNION ALL\n".join(f"SELECT {i + 1} AS round, round({O.rss(f'l{i}')}, 4) AS rss" for i in range(3))))
def lloyd_rss_by_round(spark, sf_dir):
    """B1, M1"""
    got = lloyd_of(spark, sf_dir, 3).info["rss_by_round"]
    return spark.createDataFrame([(i + 1, x) for i, x in enumerate(got)], "round int, rss double").withColumn("rss", F.round("rss", 4))


@query(O.with_([*P, *O.lloyd(K, 3)], "SELECT doc_id, c AS cluster_id FROM l3"))
def lloyd_points(spark, sf_dir):
    """B1 on points"""
    return lloyd(points_of(spark, sf_dir), K, max_iter=3).assign.select("doc_id", "cluster_id")


_EUCLID = f"""WITH x AS (SELECT vec_id AS doc_id, embedding::DOUBLE[] AS v FROM embeddings),
o AS (SELECT doc_id, v, row_number() OVER (ORDER BY md5('42:' || doc_id), doc_id) - 1 AS c FROM x QUALIFY c < {K}),
d AS (SELECT x.doc_id, o.c, round(list_dot_product(o.v, o.v) - 2 * list_dot_product(x.v, o.v), 9) AS d FROM x CROSS JOIN o)
SELECT doc_id, c AS cluster_id FROM d QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY d, c) = 1"""


@query(_EUCLID)
def lloyd_euclid_assign(spark, sf_dir):
    """B1u: the first assignment"""
    return lloyd_euclidean(load(spark, sf_dir, "embeddings"), K, 0)[0].select("doc_id", "cluster_id")


@query(O.with_(O.euclid_rounds(K, 8), "SELECT doc_id, c AS cluster_id FROM l8"))
def lloyd_euclid(spark, sf_dir):
    """B1u"""
    return lloyd_euclidean(load(spark, sf_dir, "embeddings"), K, 8)[0].select("doc_id", "cluster_id")


@query(O.with_([*D, *O.lloyd(K, 2)], "SELECT doc_id, c AS cluster_id FROM l2 EXCEPT SELECT doc_id, c FROM l1"))
def labels_moved(spark, sf_dir):
    """O17"""
    return relational.moved(lloyd_of(spark, sf_dir, 1).assign, lloyd_of(spark, sf_dir, 2).assign)


@query(O.with_([*D, *O.lloyd(K, 2)], "SELECT doc_id, c AS cluster_id FROM l2 INTERSECT SELECT doc_id, c FROM l1"))
def labels_stable(spark, sf_dir):
    """O17, B1t"""
    return relational.stable(lloyd_of(spark, sf_dir, 1).assign, lloyd_of(spark, sf_dir, 2).assign)


@query(O.with_([*D, *O.lloyd(K, 1), ("all_c", f"SELECT unnest(range({K})) AS c")], "SELECT c AS cluster_id, count(l1.doc_id) AS n FROM all_c LEFT JOIN l1 USING (c) GROUP BY c"))
def empty_clusters(spark, sf_dir):
    """B1e: sizes with the empty ones"""
    got = lloyd_of(spark, sf_dir, 1).assign
    return spark.range(K).withColumnRenamed("id", "cluster_id").join(got, "cluster_id", "left").groupBy("cluster_id").agg(F.count("doc_id").alias("n"))


# ---------------------------------------------------------------- proposal (a)

MC = [*D, *O.micro(M)]


@query(O.with_(MC, "SELECT mc AS mc_id, n, round(ss, 6) AS ss, round(min_sim, 6) AS min_sim FROM head"))
def micro_head(spark, sf_dir):
    """A3"""
    return _sims(micro_of(spark, sf_dir).head(spark), "ss", "min_sim")


@query(O.with_(MC, "SELECT h.mc AS mc_id, p.term, CAST(sum(p.wq) AS BIGINT) AS s FROM l0 JOIN head h USING (c) JOIN post p USING (doc_id) GROUP BY h.mc, p.term"))
def micro_ls(spark, sf_dir):
    """A3"""
    return micro_of(spark, sf_dir).sums(spark).join(vecs_of(spark, sf_dir).terms, "term_id").select("mc_id", "term", "s")


@query(O.with_(MC, "SELECT round(avg(min_sim), 6) AS s0 FROM head"))
def micro_threshold(spark, sf_dir):
    """A4"""
    return spark.createDataFrame([(microgroup.initial_threshold(micro_of(spark, sf_dir).least),)], "s0 double").select(F.round("s0", 6).alias("s0"))


@query(O.with_(MC, "SELECT a, b, round(cos, 6) AS cos, round(sim, 6) AS sim, kind FROM pairs"))
def micro_links(spark, sf_dir):
    """A5-A7"""
    return _sims(links_of(spark, sf_dir).frame(spark), "cos", "sim").withColumn("kind", F.col("kind").cast("int"))


_AT_S0 = ("linked", "SELECT a, b FROM pairs WHERE kind = 1 OR (kind = 2 AND sim >= (SELECT avg(min_sim) FROM head))")


def _groups(spark, sf_dir, link):
    mc, links = micro_of(spark, sf_dir), links_of(spark, sf_dir)
    g = microgroup.group(links, microgroup.link_edges(links, microgroup.initial_threshold(mc.least)), mc.m, link)
    return spark.createDataFrame([(i, int(x)) for i, x in enumerate(g)], "mc_id long, group_id long")


@query(O.with_([*MC, _AT_S0, *O.first_groups("linked")], "SELECT mc AS mc_id, g AS group_id FROM groups"))
def micro_groups_first(spark, sf_dir):
    """A8b"""
    return _groups(spark, sf_dir, "first")


@query(O.with_([*MC, _AT_S0, *O.closure_groups("linked")], "SELECT mc AS mc_id, g AS group_id FROM groups"))
def micro_groups_closure(spark, sf_dir):
    """A8a"""
    return _groups(spark, sf_dir, "closure")


ML = [*D, *O.micro_labels(K, M)]


@query(O.with_(ML, "SELECT mc AS mc_id, g AS group_id FROM groups"))
def micro_groups_exact(spark, sf_dir):
    """A9c, A10"""
    return spark.createDataFrame([(i, int(x)) for i, x in enumerate(micro_result(spark, sf_dir).groups)], "mc_id long, group_id long")


_CURVE = """SELECT s, CAST((SELECT count(*) FROM head) - (SELECT count(DISTINCT b) FROM pairs WHERE kind = 1 OR (kind = 2 AND sim >= s)) AS BIGINT) AS groups
FROM (SELECT unnest([0.0, 0.05, 0.1, 0.15, 0.2, 0.3, 0.5])::DOUBLE AS s)"""


@query(O.with_(MC, _CURVE))
def micro_count_curve(spark, sf_dir):
    """Groups by threshold"""
    mc, links = micro_of(spark, sf_dir), links_of(spark, sf_dir)
    return spark.createDataFrame([(s, microgroup.count_groups(links, s, mc.m)) for s in (0.0, 0.05, 0.1, 0.15, 0.2, 0.3, 0.5)], "s double, groups long")


@query(O.with_(ML, "SELECT doc_id, c AS cluster_id FROM fin"))
def micro_labels(spark, sf_dir):
    """A0, A11, A12"""
    return micro_result(spark, sf_dir).assign.select("doc_id", "cluster_id")


@query(ORACLES["micro_labels"])
def micro_shuffled(spark, sf_dir):
    """A0 with centres that stay a table"""
    return microgroup.microgroup(vecs_of(spark, sf_dir), K, M, threshold="rank", strategy="shuffle").assign.select("doc_id", "cluster_id")


@query(O.with_(ML, f"SELECT round({O.rss('fin')}, 4) AS rss, round({O.rss('l0')}, 4) AS cf_rss"))
def micro_rss(spark, sf_dir):
    """M1, A13"""
    got = micro_result(spark, sf_dir)
    x = metrics.rss(vecs_of(spark, sf_dir), got.assign)
    return spark.createDataFrame([(x, got.info["cf_rss"])], "rss double, cf_rss double").select(F.round("rss", 4).alias("rss"), F.round("cf_rss", 4).alias("cf_rss"))


@query(O.with_([*P, *O.micro_labels(K, M)], "SELECT doc_id, c AS cluster_id FROM fin"))
def micro_points(spark, sf_dir):
    """W14 with cosine"""
    return microgroup.microgroup(points_of(spark, sf_dir), K, M, threshold="rank").assign.select("doc_id", "cluster_id")


@query(O.with_(O.micro_euclid(K, M), "SELECT doc_id, c AS cluster_id FROM fin"))
def micro_points_euclid(spark, sf_dir):
    """A14"""
    return microgroup.micro_points_euclidean(load(spark, sf_dir, "embeddings"), K, M)


@query()
def micro_policies(spark, sf_dir):
    """A5r-A10: groups, RSS and policy under every link rule"""
    v, mc, rows = vecs_of(spark, sf_dir), micro_of(spark, sf_dir), []
    for link in ("first", "closure"):
        for rule, clamp in (("either", True), ("both", True), ("off", True), ("cosine", True), ("either", False)):
            got = microgroup.regroup(v, mc, K, link=link, zero_rule=rule, clamp=clamp)
            rows.append((link, rule, clamp, got.info["groups_literal"], got.info["groups"], got.info["policy_used"], microgroup.rss_of(v, got.centers)))
    return spark.createDataFrame(rows, "link string, zero_rule string, clamp boolean, groups_literal int, groups int, policy string, rss double")


@query()
def micro_threshold_search(spark, sf_dir):
    """A9a, A9b"""
    mc, links = micro_of(spark, sf_dir), links_of(spark, sf_dir)
    s0 = microgroup.initial_threshold(mc.least)
    rows = [(how, *microgroup.threshold_search(links, mc.m, 3, s0, how)) for how in ("step", "bisect")]
    return spark.createDataFrame(rows, "how string, s double, groups int, trials int")


_SWEPT = [*D, *[(f"w{i}", "SELECT " + f"{r}::DOUBLE AS ratio, (SELECT count(*) FROM head)::INTEGER AS n_micro, (SELECT max(g) + 1 FROM groups)::INTEGER AS groups, round({O.rss('fin')}, 4) AS rss") for i, r in enumerate((5, 3, 2.25, 2))]]
_SWEPT = [*D, *[(n, O.with_(O.micro_labels(K, int(r * K)), q)) for (n, q), r in zip(_SWEPT[len(D) :], (5, 3, 2.25, 2), strict=True)]]


@query(O.with_(_SWEPT, "SELECT * FROM w0 UNION ALL SELECT * FROM w1 UNION ALL SELECT * FROM w2 UNION ALL SELECT * FROM w3"))
def micro_sweep(spark, sf_dir):
    """A15"""
    rows = [(float(r["ratio"]), r["n_micro"], r["groups"], r["rss"]) for r in microgroup.sweep_micro(vecs_of(spark, sf_dir), K)]
    return spark.createDataFrame(rows, "ratio double, n_micro int, groups int, rss double").withColumn("rss", F.round("rss", 4))


# ---------------------------------------------------------------- proposal (b)

S = [*D, *O.sample(O.sample_rows(K))]


@query(O.with_(S, f"SELECT a, b, round(dp / {FULL}.0, 6) AS sim FROM sdot WHERE a < b"))
def sample_edges(spark, sf_dir):
    """H3, pairwise_cos"""
    v = vecs_of(spark, sf_dir)
    return _sims(hac.pairwise_sim(v, _drawn(v.packed.select("doc_id"))), "sim")


@query(O.with_(S, f"SELECT a, b, round(dp / {FULL}.0, 6) AS sim FROM sdot WHERE a < b ORDER BY dp DESC, a, b LIMIT 1"))
def best_pair(spark, sf_dir):
    """O22"""
    v = vecs_of(spark, sf_dir)
    return _sims(relational.best_pair(hac.pairwise_sim(v, _drawn(v.packed.select("doc_id")))), "sim")


_THRESHOLD = O.with_([*P, *O.sample(O.ALL_ROWS), ("twoway", f"SELECT a, b FROM sdot WHERE dp >= {FULL} * 0.5"), ("reach", "SELECT doc_id, doc_id AS x FROM smp UNION SELECT r.doc_id, w.b FROM reach r JOIN twoway w ON w.a = r.x")], "SELECT doc_id AS node, min(x) AS comp FROM reach GROUP BY doc_id")


def _components_query(name: str, scheme: str):
    def run(spark, sf_dir):
        return hac.threshold_components(points_of(spark, sf_dir), 0.5, scheme)

    run.__name__ = name
    query(_THRESHOLD)(run)


for _name, _scheme in (("components_minlabel", "min_label"), ("components_full", "full_exchange"), ("components_to_min", "cluster_to_min"), ("components_greater", "greater_to_min"), ("components_stars", "stars")):
    _components_query(_name, _scheme)


@query(O.with_([*P, *O.sample(O.ALL_ROWS), *O.single_link(K)], "SELECT doc_id, c AS cluster_id FROM seeded"))
def single_link_k(spark, sf_dir):
    """H5a, B6 over all points"""
    v = points_of(spark, sf_dir)
    return hac.mst_link(v, everything(v.packed.select("doc_id")), k=K, parts=max(3, -(-v.n // sampleseed.PART_ROWS)))


@query(O.with_([*P, *O.sample(O.ALL_ROWS), ("twoway", f"SELECT a, b FROM sdot WHERE dp / {FULL}.0 >= 0.6"), ("reach", "SELECT doc_id, doc_id AS x FROM smp UNION SELECT r.doc_id, w.b FROM reach r JOIN twoway w ON w.a = r.x"), ("comp", "SELECT r.doc_id, min(s.rk) AS low FROM reach r JOIN smp s ON s.doc_id = r.x GROUP BY r.doc_id")], "SELECT doc_id, dense_rank() OVER (ORDER BY low) - 1 AS cluster_id FROM comp"))
def single_link_threshold(spark, sf_dir):
    """H5a, B6 over all points, cut at a similarity"""
    v = points_of(spark, sf_dir)
    return hac.mst_link(v, everything(v.packed.select("doc_id")), threshold=0.6, parts=max(3, -(-v.n // sampleseed.PART_ROWS)))


@query(O.with_([*S, *O.single_link(K)], "SELECT doc_id, c AS cluster_id FROM seeded"))
def single_link_sequential(spark, sf_dir):
    """H4: merges in one task give the same clusters as the spanning tree"""
    v = vecs_of(spark, sf_dir)
    return hac.sample_clusters(v, _drawn(v.packed.select("doc_id")), K, "single")


def _linkage_query(linkage: str):
    def run(spark, sf_dir):
        v = vecs_of(spark, sf_dir)
        return hac.sample_clusters(v, _drawn(v.packed.select("doc_id")), K, linkage)

    run.__name__ = f"{linkage}_link"
    query(None if linkage == "centroid" else O.with_([*S, *O.linkage(linkage, K)], "SELECT doc_id, c AS cluster_id FROM seeded"))(run)


for _l in ("complete", "average", "centroid"):
    _linkage_query(_l)


@query()
def local_trees(spark, sf_dir):
    """H7"""
    v = vecs_of(spark, sf_dir)
    return hac.local_trees(v, random_parts(_drawn(v.packed.select("doc_id")), 4))


def _parthac_query(align: str):
    def run(spark, sf_dir):
        v = points_of(spark, sf_dir)
        return hac.parthac(v, everything(v.packed.select("doc_id")), K, max(4, -(-v.n // sampleseed.PART_ROWS)), "average", align)[0]

    run.__name__ = f"parthac_{align}"
    query()(run)


for _a in ("tree", "cut", "topdown"):
    _parthac_query(_a)


def _sample_query(name: str, rounds: int, reassign: bool):
    def run(spark, sf_dir):
        return sample_of(spark, sf_dir, rounds, reassign).assign.select("doc_id", "cluster_id")

    run.__name__ = name
    query(O.with_([*D, *O.sampleseed(K, rounds, reassign)], f"SELECT doc_id, c AS cluster_id FROM r{rounds}"))(run)


for _n, _rr, _re in (("sampleseed_r1", 1, False), ("sampleseed_r2", 2, False), ("sampleseed_r3", 3, False), ("sampleseed_reassign", 2, True)):
    _sample_query(_n, _rr, _re)


@query(ORACLES["sampleseed_r2"])
def sampleseed_shuffled(spark, sf_dir):
    """H0 with centres that stay a table"""
    return sampleseed.sampleseed(vecs_of(spark, sf_dir), K, strategy="shuffle").assign.select("doc_id", "cluster_id")


@query(O.with_([*D, *O.sampleseed(K, 1)], "SELECT side, count(*) AS n FROM (SELECT 'fixed' AS side FROM seeded UNION ALL SELECT 'attached' FROM t1) GROUP BY side"))
def label_union(spark, sf_dir):
    """H10, O17"""
    got = sample_of(spark, sf_dir, 1)
    attached = got.assign.join(got.sample.select("doc_id"), "doc_id", "left_anti").select(F.lit("attached").alias("side"), "doc_id")
    return relational.merge_labels(got.sample.select(F.lit("fixed").alias("side"), "doc_id"), attached).groupBy("side").agg(F.count(F.lit(1)).alias("n"))


# ---------------------------------------------------------------- related methods


@query(O.with_([*D, *O.lloyd(2, 2)], "SELECT doc_id, c AS side FROM l2"))
def bisect_first_split(spark, sf_dir):
    """The first split"""
    return bisecting(vecs_of(spark, sf_dir), 2, rounds=2).select("doc_id", F.col("cluster_id").alias("side"))


@query()
def bisecting_k(spark, sf_dir):
    """B3"""
    return bisecting(vecs_of(spark, sf_dir), 4, rounds=3)


_FAR = [("e", f"SELECT vec_id, list_transform(embedding, lambda x: CAST(round(x::DOUBLE * {O.UNIT}) AS BIGINT)) AS q FROM embeddings"), ("f0", "SELECT 0 AS rk, vec_id FROM embeddings QUALIFY row_number() OVER (ORDER BY md5('42:' || vec_id), vec_id) = 1"), ("f1", "SELECT rk, vec_id FROM f0 UNION ALL (SELECT 1, x.vec_id FROM e x JOIN f0 f ON true JOIN e y ON y.vec_id = f.vec_id GROUP BY x.vec_id ORDER BY max(list_sum(list_transform(list_zip(x.q, y.q), lambda p: p[1] * p[2]))), x.vec_id LIMIT 1)"), ("f2", "SELECT rk, vec_id FROM f1 UNION ALL (SELECT 2, x.vec_id FROM e x JOIN f1 f ON true JOIN e y ON y.vec_id = f.vec_id GROUP BY x.vec_id ORDER BY max(list_sum(list_transform(list_zip(x.q, y.q), lambda p: p[1] * p[2]))), x.vec_id LIMIT 1)"), ("f3", "SELECT rk, vec_id FROM f2 UNION ALL (SELECT 3, x.vec_id FROM e x JOIN f2 f ON true JOIN e y ON y.vec_id = f.vec_id GROUP BY x.vec_id ORDER BY max(list_sum(list_transform(list_zip(x.q, y.q), lambda p: p[1] * p[2]))), x.vec_id LIMIT 1)"), ("f4", "SELECT rk, vec_id FROM f3 UNION ALL (SELECT 4, x.vec_id FROM e x JOIN f3 f ON true JOIN e y ON y.vec_id = f.vec_id GROUP BY x.vec_id ORDER BY max(list_sum(list_transform(list_zip(x.q, y.q), lambda p: p[1] * p[2]))), x.vec_id LIMIT 1)")]


@query(O.with_(_FAR, "SELECT rk, vec_id FROM f4"))
def farthest_seeds(spark, sf_dir):
    """B4"""
    v = points_of(spark, sf_dir)
    centers = seed_centers(v, 5, "farthest")
    found = assign_nearest(v, centers).groupBy("center_id").agg(F.max_by("doc_id", F.struct("sim", -F.col("doc_id"))).alias("vec_id"))
    return found.select(F.col("center_id").cast("int").alias("rk"), "vec_id")


@query()
def bestseed_oversample(spark, sf_dir):
    """B4"""
    v = vecs_of(spark, sf_dir)
    return lloyd(v, K, init="oversample", max_iter=3).assign


@query()
def bestseed_density(spark, sf_dir):
    """B4"""
    v = vecs_of(spark, sf_dir)
    return lloyd(v, K, init="density", max_iter=3).assign


@query()
def nmf_labels(spark, sf_dir):
    """B8"""
    return factorkm(vecs_of(spark, sf_dir), K, 8, iters=4)


@query()
def onepass_labels(spark, sf_dir):
    """B9"""
    return cf_onepass(points_of(spark, sf_dir), 0.6, 40)[0]


@query()
def representatives(spark, sf_dir):
    """B10"""
    return rep_points(points_of(spark, sf_dir), K)


@query()
def medoids(spark, sf_dir):
    """B11"""
    return random_medoids(points_of(spark, sf_dir), K)


@query()
def mllib_kmeans_labels(spark, sf_dir):
    """B2"""
    return mllib_kmeans(points_of(spark, sf_dir), K)


@query()
def mllib_bisecting_labels(spark, sf_dir):
    """B2"""
    return mllib_bisecting(points_of(spark, sf_dir), K)


# ---------------------------------------------------------------- measures


@query(O.with_([*D, *O.lloyd(K, 3)], f"SELECT c AS cluster_id, n, round(rss, 4) AS rss FROM (SELECT h.c, h.n, (h.ss - coalesce(x.ls2, 0) / h.n) / {FULL}.0 AS rss FROM (SELECT l.c, count(*) AS n, sum(coalesce(q.q, 0))::DOUBLE AS ss FROM l3 l LEFT JOIN (SELECT doc_id, sum(wq * wq) AS q FROM post GROUP BY doc_id) q USING (doc_id) GROUP BY l.c) h LEFT JOIN (SELECT c, sum(s::DOUBLE * s) AS ls2 FROM (SELECT c, term, sum(wq) AS s FROM l3 JOIN post USING (doc_id) GROUP BY c, term) GROUP BY c) x USING (c))"))
def cluster_rss(spark, sf_dir):
    """M1 by cluster"""
    return metrics.cluster_rss(vecs_of(spark, sf_dir), lloyd_of(spark, sf_dir).assign).select("cluster_id", "n", F.round("rss", 4).alias("rss"))


@query(O.with_([*D, *O.lloyd(K, 3)], f"SELECT c AS cluster_id, count(*) AS n, round(any_value(x.ls2) / count(*) / count(*) / {FULL}.0, 6) AS internal FROM l3 JOIN (SELECT c, sum(s::DOUBLE * s) AS ls2 FROM (SELECT c, term, sum(wq) AS s FROM l3 JOIN post USING (doc_id) GROUP BY c, term) GROUP BY c) x USING (c) GROUP BY c"))
def internal_similarity(spark, sf_dir):
    """M10"""
    return metrics.internal_similarity(vecs_of(spark, sf_dir), lloyd_of(spark, sf_dir).assign).withColumn("internal", F.round("internal", 6))


_COMPARED = [*D, ("base", O.with_(O.lloyd(K, 8), f"SELECT {O.rss('l8')} AS rss")), ("mg", O.with_(O.micro_labels(K, M), f"SELECT {O.rss('fin')} AS rss")), ("ss", O.with_(O.sampleseed(K, 2), f"SELECT {O.rss('r2')} AS rss"))]


@query(O.with_(_COMPARED, "SELECT method, round(rss, 4) AS rss, round(100 * (rss / (SELECT rss FROM base) - 1), 4) + 0.0 AS loss_pct FROM (SELECT 'lloyd' AS method, rss FROM base UNION ALL SELECT 'microgroup', rss FROM mg UNION ALL SELECT 'sampleseed', rss FROM ss)"))
def rss_compare(spark, sf_dir):
    """The three methods side by side"""
    v = vecs_of(spark, sf_dir)
    base = metrics.rss(v, lloyd(v, K).assign)
    rows = [("lloyd", base), ("microgroup", metrics.rss(v, micro_result(spark, sf_dir).assign)), ("sampleseed", metrics.rss(v, sample_of(spark, sf_dir).assign))]
    return spark.createDataFrame([(m, x, metrics.rss_loss(x, base)) for m, x in rows], "method string, rss double, loss_pct double").select("method", F.round("rss", 4).alias("rss"), F.round("loss_pct", 4).alias("loss_pct"))


@query(O.with_([*D, *O.lloyd(K, 3)], "SELECT 'lloyd' AS method, round(sum(m)::DOUBLE / (SELECT count(*) FROM l3), 6) AS purity FROM (SELECT c, max(n) AS m FROM (SELECT l3.c, d.lang, count(*) AS n FROM l3 JOIN documents d USING (doc_id) GROUP BY l3.c, d.lang) GROUP BY c)"))
def cluster_purity(spark, sf_dir):
    """M11"""
    got = metrics.external(lloyd_of(spark, sf_dir).assign, docs_of(spark, sf_dir), "lang")
    return spark.createDataFrame([("lloyd", got["purity"])], "method string, purity double").withColumn("purity", F.round("purity", 6))


@query(O.with_([*D, *O.lloyd(K, 3), ("cell", "SELECT l3.c, d.lang AS y, count(*)::DOUBLE AS n FROM l3 JOIN documents d USING (doc_id) GROUP BY l3.c, d.lang")], f"SELECT measure, round(value, 6) AS value FROM ({O.external('l3')})"))
def external_measures(spark, sf_dir):
    """M11"""
    got = metrics.external(lloyd_of(spark, sf_dir).assign, docs_of(spark, sf_dir), "lang")
    return spark.createDataFrame([(m, float(x)) for m, x in got.items()], "measure string, value double").withColumn("value", F.round("value", 6))


@query(O.with_([*D, *O.lloyd(K, 3)], "SELECT c AS cluster_id, count(*) AS n, round(count(*) / avg(count(*)) OVER (), 6) AS share_of_mean FROM l3 GROUP BY c"))
def cluster_sizes(spark, sf_dir):
    """M12"""
    return metrics.sizes(lloyd_of(spark, sf_dir).assign).withColumn("share_of_mean", F.round("share_of_mean", 6))


@query(O.with_([*P, *O.lloyd(K, 3)], f"SELECT round({O.silhouette('l3')}, 6) AS silhouette"))
def silhouette(spark, sf_dir):
    """M12"""
    v = points_of(spark, sf_dir)
    return spark.createDataFrame([(metrics.silhouette(v, lloyd(v, K, max_iter=3).assign, K),)], "silhouette double").withColumn("silhouette", F.round("silhouette", 6))


_COST_N = [("ids", "SELECT doc_id FROM documents WHERE text IS NOT NULL"), ("t", f"SELECT (SELECT count(*) FROM ids) AS n, least((SELECT count(*) FROM ids), {O.sample_rows(K)}) AS s")]
_COSTS = {"lloyd": f"8 * n * {K}", "microgroup": f"n * {M} + {M} * {M} // 2 + n * {K}", "sampleseed": f"s * s // 2 + 2 * (n - s) * {K}"}


@query(O.with_(_COST_N, " UNION ALL ".join(f"SELECT '{m}' AS method, CAST({c} AS BIGINT) AS evals FROM t" for m, c in _COSTS.items())))
def logical_cost(spark, sf_dir):
    """M7 for the documents that have a text"""
    n = docs_of(spark, sf_dir).agg(F.count("text")).first()[0]
    return spark.createDataFrame([(m, x) for m, x in _evaluations(n).items()], "method string, evals long")


def _evaluations(n: int) -> dict[str, int]:
    """Similarity evaluations of the three methods over ``n`` documents (M7)."""
    return {"lloyd": metrics.logical_cost("lloyd", n, K), "microgroup": metrics.logical_cost("microgroup", n, K, n_micro=M), "sampleseed": metrics.logical_cost("sampleseed", n, K, s=sample_size(n, K), rounds=2)}


#: Published seconds and RSS (k, nodes, baseline, micro-clusters, sample).
PUBLISHED = (
    (50, 1, 4677, 140.39, 607, 148.52, 577, 145.55), (50, 3, 2605, 140.12, 344, 148.42, 327, 145.45), (50, 10, 701, 140.78, 187, 150.19, 178, 147.19),
    (100, 1, 4915, 135.82, 777, 144.87, 738, 141.97), (100, 3, 3270, 135.19, 456, 145.30, 433, 142.39), (100, 10, 955, 136.21, 235, 145.27, 223, 142.36),
    (200, 1, 9501, 129.17, 1215, 137.95, 1154, 135.19), (200, 3, 5493, 128.92, 764, 137.76, 726, 135.00), (200, 10, 1725, 129.53, 249, 139.34, 237, 136.55),
    (400, 10, 19481, 1131.30, 4301, 1195.36, 4086, 1171.45),
)


_GAIN_N = [("t", "SELECT count(*) AS n, least(count(*), (SELECT CAST(ceil(sqrt(%d * count(*)::DOUBLE)) AS BIGINT) FROM ids)) AS s FROM ids" % K), ("evals", "SELECT " + ", ".join(f"({c})::DOUBLE AS {m}" for m, c in _COSTS.items()) + " FROM t")]


@query(O.with_([*_COMPARED, *_GAIN_N], f"SELECT {K} AS k, round(100 * (1 - evals.microgroup / evals.lloyd), 4) AS micro_gain, round(100 * (mg.rss / base.rss - 1), 4) + 0.0 AS micro_loss, round(100 * (1 - evals.sampleseed / evals.lloyd), 4) AS sample_gain, round(100 * (ss.rss / base.rss - 1), 4) + 0.0 AS sample_loss FROM evals, base, mg, ss"))
def published_gain(spark, sf_dir):
    """M2, M3, the published measures, on the documents: evaluations saved and RSS above the baseline's"""
    v = vecs_of(spark, sf_dir)
    evals, base = _evaluations(v.n), metrics.rss(v, lloyd(v, K).assign)
    row = [K]
    for method, got in (("microgroup", micro_result(spark, sf_dir)), ("sampleseed", sample_of(spark, sf_dir))):
        row += [metrics.time_gain(evals[method], evals["lloyd"]), metrics.rss_loss(metrics.rss(v, got.assign), base)]
    names = ("micro_gain", "micro_loss", "sample_gain", "sample_loss")
    return spark.createDataFrame([tuple(row)], "k int, " + ", ".join(f"{c} double" for c in names)).select("k", *[F.round(c, 4).alias(c) for c in names])


_NODES = (3, 10)
_BUSY = [("r", "SELECT doc_id, row_number() OVER (ORDER BY md5('42:' || doc_id), doc_id) - 1 AS rk FROM ids"), ("dealt", " UNION ALL ".join(f"SELECT {p} AS nodes, doc_id % {p} AS node, rk FROM r" for p in (1, *_NODES))), ("busy", "SELECT nodes, max(n) AS n, max(rest) AS rest FROM (SELECT nodes, node, count(*) AS n, count(*) FILTER (rk >= (SELECT s FROM t)) AS rest FROM dealt GROUP BY nodes, node) GROUP BY nodes")]
_TIMES = ("times", f"SELECT nodes, (8 * b.n * {K})::DOUBLE AS lloyd, (b.n * {M} + {M} * {M} // 2 + b.n * {K})::DOUBLE AS microgroup, (t.s * t.s // 2 + 2 * b.rest * {K})::DOUBLE AS sampleseed FROM busy b, t")


@query(O.with_([*_COST_N, *_BUSY, _TIMES], f"SELECT {K} AS k, b.nodes, round(a.lloyd / b.lloyd, 4) AS lloyd, round(a.microgroup / b.microgroup, 4) AS microgroup, round(a.sampleseed / b.sampleseed, 4) AS sampleseed FROM times a JOIN times b ON a.nodes = 1 AND b.nodes > 1"))
def published_speed_up(spark, sf_dir):
    """M4, the published measure, on the documents dealt to nodes by id: evaluations of one node over those of the busiest
    of several; links of micro-clusters and the clustering of the sample are not shared out"""
    ids = docs_of(spark, sf_dir).filter("text is not null").select("doc_id")
    n = ids.count()
    s = sample_size(n, K)
    flagged = ids.join(F.broadcast(draw_sample(ids, s, n=n)), "doc_id", "left").select("doc_id", F.col("rk").isNull().cast("long").alias("rest"))
    dealt = flagged.withColumn("nodes", F.explode(F.array(*map(F.lit, (1, *_NODES))))).groupBy("nodes", (F.col("doc_id") % F.col("nodes")).alias("node"))
    busy = {r["nodes"]: r for r in dealt.agg(F.count(F.lit(1)).alias("n"), F.sum("rest").alias("rest")).groupBy("nodes").agg(F.max("n").alias("n"), F.max("rest").alias("rest")).collect()}
    times = {p: (metrics.logical_cost("lloyd", b["n"], K), metrics.logical_cost("microgroup", b["n"], K, n_micro=M), metrics.logical_cost("sampleseed", b["rest"] + s, K, s=s, rounds=2)) for p, b in busy.items()}
    rows = [(K, p, *[metrics.speed_up(one, many) for one, many in zip(times[1], times[p], strict=True)]) for p in _NODES]
    return spark.createDataFrame(rows, "k int, nodes int, lloyd double, microgroup double, sampleseed double").select("k", "nodes", *[F.round(c, 4).alias(c) for c in ("lloyd", "microgroup", "sampleseed")])


# ---------------------------------------------------------------- around the methods

L3 = [*D, *O.lloyd(K, 3)]
_LAB = f"(SELECT doc_id, c AS cluster_id, dp / {FULL}.0 AS sim FROM l3)"


@query("SELECT doc_id, n_chars FROM documents WHERE n_chars BETWEEN 500 AND 5000")
def scan_documents(spark, sf_dir):
    """O1"""
    return docs_of(spark, sf_dir).filter(F.col("n_chars").between(500, 5000)).select("doc_id", "n_chars")


@query("SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def scan_embeddings(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, lang, source FROM documents WHERE lang IN ('de', 'fr') AND source LIKE 'src1%' AND regexp_matches(text, '[0-9]')")
def filter_lang(spark, sf_dir):
    return docs_of(spark, sf_dir).filter(F.col("lang").isin("de", "fr") & F.col("source").like("src1%") & F.col("text").rlike("[0-9]")).select("doc_id", "lang", "source")


@query(O.with_(L3, f"SELECT a.cluster_id, count(*) AS n, round(avg(d.n_chars), 4) AS mean_chars, round(min(a.sim), 6) AS min_sim, round(avg(a.sim), 6) AS mean_sim, round(max(a.sim), 6) AS max_sim FROM {_LAB} a JOIN documents d USING (doc_id) GROUP BY a.cluster_id"))
def cluster_profile(spark, sf_dir):
    """O18"""
    return _sims(relational.profile(lloyd_of(spark, sf_dir).assign, docs_of(spark, sf_dir)).withColumn("mean_chars", F.round("mean_chars", 4)), "min_sim", "mean_sim", "max_sim")


def _labelled(spark, sf_dir) -> DataFrame:
    return lloyd_of(spark, sf_dir).assign.select("doc_id", "cluster_id", "sim").join(docs_of(spark, sf_dir).select("doc_id", "lang", "source", "n_chars"), "doc_id")


_ROWS = f"{_LAB} a JOIN documents d USING (doc_id)"


@query(O.with_(L3, f"SELECT d.lang, a.cluster_id, count(*) AS n, grouping_id(d.lang, a.cluster_id) AS gid FROM {_ROWS} GROUP BY CUBE (d.lang, a.cluster_id)"))
def cube_lang_cluster(spark, sf_dir):
    """O19"""
    return relational.cube_profile(_labelled(spark, sf_dir), "lang", "cluster_id")


@query(O.with_(L3, f"SELECT d.source, a.cluster_id, count(*) AS n, grouping_id(d.source, a.cluster_id) AS gid FROM {_ROWS} GROUP BY ROLLUP (d.source, a.cluster_id)"))
def rollup_source(spark, sf_dir):
    """O19"""
    return relational.rollup_profile(_labelled(spark, sf_dir), "source", "cluster_id")


@query(O.with_(L3, f"SELECT d.lang, d.source, count(*) AS n, grouping_id(d.lang, d.source) AS gid FROM {_ROWS} GROUP BY GROUPING SETS ((d.lang), (d.source), ())"))
def gs_labels(spark, sf_dir):
    """O19"""
    return relational.grouping_sets_profile(_labelled(spark, sf_dir), [("lang",), ("source",), ()], "lang", "source")


@query(O.with_(L3, f"SELECT a.cluster_id, count(*) FILTER (d.lang = 'de') AS de, count(*) FILTER (d.lang = 'en') AS en, count(*) FILTER (d.lang = 'es') AS es, count(*) FILTER (d.lang = 'fr') AS fr FROM {_ROWS} GROUP BY a.cluster_id"))
def pivot_lang(spark, sf_dir):
    """O18"""
    return _labelled(spark, sf_dir).groupBy("cluster_id").pivot("lang", ["de", "en", "es", "fr"]).count().na.fill(0)


@query(O.with_([*L3, ("ls", "SELECT c AS cluster_id, term, CAST(sum(wq) AS BIGINT) AS s FROM l3 JOIN post USING (doc_id) GROUP BY c, term")], "SELECT cluster_id, term, s, row_number() OVER (PARTITION BY cluster_id ORDER BY s DESC, term) AS rank FROM ls QUALIFY rank <= 5"))
def top_terms_per_cluster(spark, sf_dir):
    """O20"""
    v = vecs_of(spark, sf_dir)
    sums = v.postings.join(lloyd_of(spark, sf_dir).assign.select("doc_id", "cluster_id"), "doc_id").groupBy("cluster_id", "term_id").agg(F.sum("wq").alias("s")).join(v.terms, "term_id")
    return relational.top_per_group(sums.select("cluster_id", "term", "s"), "cluster_id", [F.desc("s"), F.col("term")], 5)


@query(O.with_(L3, f"SELECT cluster_id, doc_id, round(sim, 6) AS sim, row_number() OVER (PARTITION BY cluster_id ORDER BY sim DESC, doc_id) AS rank FROM {_LAB} QUALIFY rank <= 3"))
def closest_docs_per_center(spark, sf_dir):
    """O21"""
    return _sims(relational.top_per_group(lloyd_of(spark, sf_dir).assign.select("cluster_id", "doc_id", "sim"), "cluster_id", [F.desc("sim"), F.col("doc_id")], 3), "sim")


@query(O.with_(L3, f"SELECT doc_id, c1, c2, round((d1 - d2) / {FULL}.0, 6) AS margin FROM (SELECT doc_id, c AS c1, dp AS d1, lead(c) OVER w AS c2, lead(dp) OVER w AS d2, row_number() OVER w AS r FROM d_l3 WINDOW w AS (PARTITION BY doc_id ORDER BY dp DESC, c)) WHERE r = 1 AND d2 > 0"))
def nearest_two_margin(spark, sf_dir):
    """O15"""
    v = vecs_of(spark, sf_dir)
    two = assign_nearest(v, lloyd_of(spark, sf_dir).centers, top=2)
    w = Window.partitionBy("doc_id").orderBy("rank")
    rows = two.withColumn("c2", F.lead("center_id").over(w)).withColumn("s2", F.lead("sim").over(w)).filter("rank = 1 and s2 > 0")
    return rows.select("doc_id", F.col("center_id").alias("c1"), "c2", F.round(F.col("sim") - F.col("s2"), 6).alias("margin"))


@query(O.with_(L3, f"SELECT doc_id, ntile(10) OVER (PARTITION BY cluster_id ORDER BY sim, doc_id) AS tile, round(percent_rank() OVER (PARTITION BY cluster_id ORDER BY sim, doc_id), 6) AS pr FROM {_LAB}"))
def ntile_sim(spark, sf_dir):
    """O24"""
    rows = relational.placed(lloyd_of(spark, sf_dir).assign.select("doc_id", "cluster_id", "sim"), "cluster_id", [F.col("sim"), F.col("doc_id")], F.floor(F.col("sim") * 4096))
    pr = F.when(F.col("n") > 1, F.col("at") / (F.col("n") - 1)).otherwise(F.lit(0.0))
    return rows.select("doc_id", relational.tiles(10).alias("tile"), F.round(pr, 6).alias("pr"))


@query(O.with_(L3, f"SELECT cluster_id, doc_id, round(sum(1 - sim) OVER (PARTITION BY cluster_id ORDER BY sim DESC, doc_id ROWS UNBOUNDED PRECEDING), 4) + 0.0 AS running FROM {_LAB}"))
def running_rss(spark, sf_dir):
    """O23"""
    far = 1 - F.col("sim")
    rows = relational.placed(lloyd_of(spark, sf_dir).assign.select("cluster_id", "doc_id", "sim"), "cluster_id", [F.desc("sim"), F.col("doc_id")], F.floor(far * 4096), far)
    return rows.select("cluster_id", "doc_id", F.round(F.col("before") + far, 4).alias("running"))


@query(O.with_(L3, f"SELECT cluster_id, doc_id, round(avg(sim) OVER (PARTITION BY cluster_id ORDER BY sim DESC, doc_id ROWS 4 PRECEDING), 6) AS moving FROM {_LAB}"))
def moving_sim(spark, sf_dir):
    """Mean similarity over five documents, from the nearest on"""
    rows = lloyd_of(spark, sf_dir).assign.select("cluster_id", "doc_id", "sim")
    return relational.moving_mean(rows, "cluster_id", [F.desc("sim"), F.col("doc_id")], "sim", 5, F.floor((1 - F.col("sim")) * 4096)).select("cluster_id", "doc_id", F.round("moving", 6).alias("moving"))


@query(O.with_([D[0], *O.ordered()], f"SELECT doc_id FROM ord WHERE rk >= {O.sample_rows(K)}"))
def remainder_docs(spark, sf_dir):
    """The documents outside the sample"""
    ids = docs_of(spark, sf_dir).select("doc_id")
    return split_sample(ids, _drawn(ids))[1]


@query(O.with_([*D, ("near", "SELECT doc_id, lead(doc_id) OVER (ORDER BY doc_id) AS other FROM ids"), ("len", "SELECT doc_id, sum(wq::DOUBLE * wq) AS q FROM post GROUP BY doc_id")], "SELECT n.doc_id, n.other, round(coalesce(sum(x.wq::DOUBLE * y.wq) / any_value(sqrt(a.q * b.q)), 0), 6) + 0.0 AS cos FROM near n JOIN len a ON a.doc_id = n.doc_id JOIN len b ON b.doc_id = n.other LEFT JOIN post x ON x.doc_id = n.doc_id LEFT JOIN post y ON y.doc_id = n.other AND y.term = x.term GROUP BY n.doc_id, n.other"))
def sparse_cos(spark, sf_dir):
    """Cosine of each document with the one of the next id"""
    v = vecs_of(spark, sf_dir)
    rows = relational.placed(v.packed.select(F.lit(0).alias("g"), "doc_id", as_map(F.col("idx"), F.col("val")).alias("m")).filter(F.size("m") >= 0), "g", [F.col("doc_id")], F.floor(F.col("doc_id") / 100_000))
    one, two = rows.select("at", "doc_id", "m"), rows.select((F.col("at") - 1).alias("at"), F.col("doc_id").alias("other"), F.col("m").alias("o"))
    return one.join(two.hint("merge"), "at").filter((F.size("m") > 0) & (F.size("o") > 0)).select("doc_id", "other", F.round(cos_sparse(F.col("m"), F.col("o")), 6).alias("cos"))


@query(O.with_([*P, *O.sample(O.sample_rows(K)), *O.single_link(K)], f"SELECT row_number() OVER (ORDER BY dp DESC, a, b) AS step, round((dp - lag(dp) OVER (ORDER BY dp DESC, a, b)) / {FULL}.0, 6) AS gap FROM tree"))
def merge_gap(spark, sf_dir):
    """Falls of the merge heights"""
    v = points_of(spark, sf_dir)
    tree = hac.mst(v, _drawn(v.packed.select("doc_id")), 3)
    w = Window.orderBy(F.desc("dp"), "a", "b")
    return tree.select(F.row_number().over(w).alias("step"), F.round((F.col("dp") - F.lag("dp").over(w)) / float(FULL), 6).alias("gap"))


@query(O.with_(L3, f"SELECT cluster_id, round(quantile_cont(sim, 0.5), 6) AS median, round(quantile_cont(sim, 0.9), 6) AS p90 FROM {_LAB} GROUP BY cluster_id"))
def sim_quantiles(spark, sf_dir):
    """O24"""
    got = relational.group_quantiles(lloyd_of(spark, sf_dir).assign, "cluster_id", "sim", F.floor(F.col("sim") * 4096), {"median": 0.5, "p90": 0.9})
    return got.select("cluster_id", F.round("median", 6).alias("median"), F.round("p90", 6).alias("p90"))


@query(O.with_(D[:3], "SELECT d.lang, count(DISTINCT tf.term) AS terms FROM tf JOIN documents d USING (doc_id) GROUP BY d.lang"))
def distinct_terms(spark, sf_dir):
    """O25"""
    tf = X.term_freq(X.tokens(docs_of(spark, sf_dir)))
    return tf.join(docs_of(spark, sf_dir).select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.count_distinct("term").alias("terms"))


@query()
def sketch_vocab(spark, sf_dir):
    """O25 by sketches"""
    toks = X.tokens(docs_of(spark, sf_dir))
    return toks.agg(F.hll_sketch_estimate(F.hll_sketch_agg("term")).alias("terms_hll"), F.approx_count_distinct("term", 0.01).alias("terms_approx"))


@query(O.with_(L3, f"SELECT a.doc_id, a.cluster_id FROM {_LAB} a JOIN (SELECT cluster_id, avg(sim) AS m FROM {_LAB} GROUP BY cluster_id) m USING (cluster_id) WHERE round(a.sim, 9) > round(m.m, 9)"))
def above_mean_sim(spark, sf_dir):
    """documents nearer to their centre than their cluster's mean"""
    rows = lloyd_of(spark, sf_dir).assign
    mean = rows.groupBy("cluster_id").agg(F.avg("sim").alias("m"))
    return rows.join(mean, "cluster_id").filter(F.round("sim", 9) > F.round("m", 9)).select("doc_id", "cluster_id")


@query("SELECT md5(text) AS h, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 1")
def exact_copies(spark, sf_dir):
    """O27"""
    return relational.exact_copies(docs_of(spark, sf_dir))


@query("SELECT doc_id, length(text) AS chars, length(regexp_replace(text, '[^0-9]', '', 'g')) AS digits, lower(substring(text, 1, 5)) AS head, md5(concat_ws('|', lang, source)) AS tag FROM documents")
def text_stats(spark, sf_dir):
    return docs_of(spark, sf_dir).select("doc_id", F.length("text").cast("long").alias("chars"), F.length(F.regexp_replace("text", "[^0-9]", "")).cast("long").alias("digits"), F.lower(F.substring("text", 1, 5)).alias("head"), F.md5(F.concat_ws("|", "lang", "source")).alias("tag"))


@query("SELECT item_id, trim(regexp_replace(lower(text), '[^a-z0-9]+', ' ', 'g')) AS plain FROM benchmark")
def clean_text(spark, sf_dir):
    return load(spark, sf_dir, "benchmark").select("item_id", F.trim(F.regexp_replace(F.lower("text"), "[^a-z0-9]+", " ")).alias("plain"))


@query("SELECT vec_id, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm, list_position(list_transform(embedding, lambda x: x = list_max(embedding)), true) AS top FROM embeddings")
def vec_norms(spark, sf_dir):
    e = F.col("embedding")
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate(e, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))), 6).alias("norm"), F.array_position(e, F.array_max(e)).cast("int").alias("top"))


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cos FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id WHERE a.label = 3")
def dense_cos(spark, sf_dir):
    """O11"""
    e = load(spark, sf_dir, "embeddings").filter("label = 3")
    return _sims(hac.dense_pairs(e, "vec_id", "embedding"), "cos")


@query("SELECT label, d AS dim, round(avg(x::DOUBLE), 6) AS mean FROM (SELECT label, generate_subscripts(embedding, 1) - 1 AS d, unnest(embedding) AS x FROM embeddings) GROUP BY label, d")
def dense_centroid(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("dim", "x")).groupBy("label", F.col("dim").cast("long").alias("dim")).agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))


@query(O.with_(P[:2], "SELECT o.doc_id AS a, p.doc_id AS b FROM (SELECT doc_id, wq FROM post WHERE term = 0) o JOIN (SELECT doc_id, wq FROM post WHERE term = 0) p ON abs(o.wq - p.wq) <= 5000"))
def band_join(spark, sf_dir):
    """Points whose first coordinates lie within a band"""
    first = points_of(spark, sf_dir).packed.select("doc_id", F.element_at("val", 1).alias("x"))
    return relational.band_join(first.select(F.col("doc_id").alias("a"), "x"), first.select(F.col("doc_id").alias("b"), F.col("x").alias("y")), "x", "y", 5000).select("a", "b")


@query("SELECT e.event_id, o.o_orderkey FROM events e JOIN orders o ON o.o_custkey % 500 = e.user_id % 500 AND o.o_orderdate + INTERVAL 9500 DAY <= e.ts AND e.ts <= o.o_orderdate + INTERVAL 9502 DAY")
def interval_events(spark, sf_dir):
    """Events in the days after a shifted order date"""
    e = load(spark, sf_dir, "events").select("event_id", "ts", (F.col("user_id") % 500).alias("u"))
    o = load(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_custkey") % 500).alias("v"), (F.col("o_orderdate") + F.expr("interval 9500 days")).alias("a"), (F.col("o_orderdate") + F.expr("interval 9502 days")).alias("b"))
    return relational.interval_join(e, o, "ts", "a", "b").filter("u = v").select("event_id", "o_orderkey")


_ASOF = """WITH v AS (SELECT * FROM events WHERE event_type = (SELECT min(event_type) FROM events)), p AS (SELECT user_id, ts, max(event_id) AS last_id FROM events WHERE event_type = (SELECT max(event_type) FROM events) GROUP BY user_id, ts)
SELECT v.event_id, p.last_id FROM v ASOF LEFT JOIN p ON v.user_id = p.user_id AND v.ts >= p.ts"""


@query(_ASOF)
def asof_snapshot(spark, sf_dir):
    """The latest event of the last type before each event of the first type"""
    e = load(spark, sf_dir, "events")
    kinds = e.agg(F.min("event_type"), F.max("event_type")).first()
    left = e.filter(F.col("event_type") == kinds[0]).select("user_id", "ts", "event_id")
    right = e.filter(F.col("event_type") == kinds[1]).groupBy("user_id", "ts").agg(F.max("event_id").alias("last_id"))
    return relational.asof_join(left, right, "ts", ["user_id"], ["last_id"]).select("event_id", "last_id")


@query("SELECT CAST(date_trunc('day', ts) AS DATE) AS day, count(*) AS n, round(sum(value), 4) AS total, max(date_diff('day', TIMESTAMP '2024-01-01', ts)) AS since FROM events GROUP BY 1")
def events_daily(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.groupBy(F.to_date("ts").alias("day")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"), F.max(F.datediff("ts", F.lit("2024-01-01").cast("date"))).cast("long").alias("since"))


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def props_k(spark, sf_dir):
    return load(spark, sf_dir, "events").select(F.get_json_object("props", "$.k").cast("long").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def _stamp(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.date_format(c, "yyyy-MM-dd HH:mm:ss") for c in ("start", "end")}).withColumn("total", F.round("total", 4))


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, strftime(date_trunc('day', ts) + INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS \"end\", event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2, 3")
def win_tumbling(spark, sf_dir):
    """O30"""
    return _stamp(relational.event_windows(load(spark, sf_dir, "events"), "tumbling"))


@query("""SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, strftime(s + INTERVAL 1 DAY, '%Y-%m-%d %H:%M:%S') AS "end", event_type, count(*) AS n, round(sum(value), 4) AS total
FROM (SELECT *, time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2000-01-01') - to_hours(6 * CAST(i AS BIGINT)) AS s FROM events CROSS JOIN (SELECT unnest([0, 1, 2, 3]) AS i)) GROUP BY 1, 2, 3""")
def win_sliding(spark, sf_dir):
    """O30"""
    return _stamp(relational.event_windows(load(spark, sf_dir, "events"), "sliding"))


@query("""WITH a AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM a)
SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, strftime(max(ts) + INTERVAL 30 MINUTE, '%Y-%m-%d %H:%M:%S') AS "end", user_id, count(*) AS n, round(sum(value), 4) AS total FROM b GROUP BY user_id, g""")
def win_session(spark, sf_dir):
    """O30"""
    return _stamp(relational.event_windows(load(spark, sf_dir, "events"), "session"))


@query("SELECT o_custkey, p_type, sum(l_quantity) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")
def behaviour(spark, sf_dir):
    """O28"""
    return relational.behaviour_vectors(*[load(spark, sf_dir, t) for t in ("orders", "lineitem", "part")])


@query("SELECT r_name, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def region_revenue(spark, sf_dir):
    """O29, O38"""
    rows = relational.by_region(load(spark, sf_dir, "orders").select("o_custkey", "o_totalprice"), *[load(spark, sf_dir, t) for t in ("customer", "nation", "region")])
    return rows.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS net, count(*) AS n FROM lineitem GROUP BY 1, 2")
def pricing(spark, sf_dir):
    """O38"""
    return relational.pricing(load(spark, sf_dir, "lineitem")).withColumn("net", F.round("net", 2))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def top_orders(spark, sf_dir):
    """O38"""
    return load(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


_CUSTOMERS = [
    ("q", "SELECT o_custkey AS doc_id, p_type, sum(l_quantity) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"),
    ("ids", "SELECT DISTINCT doc_id FROM q"),
    ("tf", "SELECT doc_id, term, CAST(sum(times) AS BIGINT) AS tf FROM (SELECT doc_id, unnest(string_split_regex(lower(replace(p_type, ' ', '')), '[^\\p{L}\\p{N}]+')) AS term, ceil(qty / 10) AS times FROM q) WHERE term <> '' AND times > 0 GROUP BY doc_id, term"),
    *D[3:],
]


@query(O.with_([*_CUSTOMERS, *O.micro_labels(5, 20)], "SELECT r_name, c AS cluster_id, count(*) AS n FROM fin JOIN customer ON doc_id = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, c"))
def clusters_by_region(spark, sf_dir):
    """Customers by what they buy, clustered, by region"""
    rows = relational.behaviour_vectors(*[load(spark, sf_dir, t) for t in ("orders", "lineitem", "part")])
    docs = rows.groupBy(F.col("o_custkey").alias("doc_id")).agg(F.array_join(F.array_sort(F.collect_list(F.array_join(F.array_repeat(F.regexp_replace("p_type", " ", ""), F.ceil(F.col("qty") / 10).cast("int")), " "))), " ").alias("text"))
    v = text_vectors(docs)
    got = microgroup.microgroup(v, 5, 20, threshold="rank").assign
    found = relational.by_region(got.select(F.col("doc_id").alias("o_custkey"), "cluster_id"), *[load(spark, sf_dir, t) for t in ("customer", "nation", "region")])
    return found.groupBy("r_name", "cluster_id").agg(F.count(F.lit(1)).alias("n"))


@query(O.with_([*O.documents("WHERE lang = 'en'"), *O.micro_labels(K, M)], "SELECT doc_id, c AS cluster_id FROM fin"))
def micro_english(spark, sf_dir):
    """One language"""
    v = text_vectors(docs_of(spark, sf_dir).filter("lang = 'en'"))
    return microgroup.microgroup(v, K, M, threshold="rank").assign.select("doc_id", "cluster_id")


_PASSAGES = [
    *D, *O.lloyd(K, 3),
    ("btf", "SELECT doc_id, term, count(*) AS tf FROM (SELECT item_id AS doc_id, unnest(string_split_regex(lower(coalesce(text, '')), '[^\\p{L}\\p{N}]+')) AS term FROM benchmark) WHERE term <> '' GROUP BY doc_id, term"),
    ("bw", "SELECT doc_id, term, w, sqrt(sum(w * w) OVER (PARTITION BY doc_id)) AS len FROM (SELECT doc_id, term, tf * ln((SELECT count(*) FROM ids)::DOUBLE / df) AS w FROM btf JOIN dfq USING (term)) WHERE w > 0"),
    ("bd", f"SELECT doc_id, c, CAST(sum(CAST(floor(w / len * {O.UNIT} + 0.5) AS BIGINT) * cq) AS BIGINT) AS dp FROM bw JOIN c3 USING (term) GROUP BY doc_id, c"),
]


@query(O.with_(_PASSAGES, f"SELECT b.item_id AS doc_id, coalesce(x.c, 0) AS cluster_id, round(coalesce(x.dp, 0) / {FULL}.0, 6) + 0.0 AS sim FROM benchmark b LEFT JOIN (SELECT * FROM bd QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY dp DESC, c) = 1) x ON x.doc_id = b.item_id"))
def benchmark_nearest(spark, sf_dir):
    """Passages against frozen centres"""
    from textgroups.streaming.stream import Frozen, stream_assign

    v = vecs_of(spark, sf_dir)
    model = Frozen(v.terms, lloyd_of(spark, sf_dir).centers, v.n)
    return _sims(stream_assign(load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), "text"), model), "sim")


@query("SELECT vec_id, round(list_cosine_similarity(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS one, round(sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS norm FROM embeddings")
def udf_cos(spark, sf_dir):
    """O36"""
    from textgroups.functions.udfs import register

    register(spark)
    load(spark, sf_dir, "embeddings").createOrReplaceTempView("tg_embeddings")
    return spark.sql("SELECT vec_id, round(cos_sim(embedding, embedding), 6) AS one, round(l2norm(embedding), 6) AS norm FROM tg_embeddings")


@query("SELECT label, count(*) AS n, round(sum(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 4) AS ss FROM embeddings GROUP BY label")
def udaf_cf(spark, sf_dir):
    """O36"""
    from textgroups.functions.udfs import cf_triple

    return load(spark, sf_dir, "embeddings").groupBy("label").agg(cf_triple("embedding").alias("cf")).select("label", F.element_at("cf", 1).cast("long").alias("n"), F.round(F.element_at("cf", 2), 4).alias("ss"))


@query("SELECT item_id, term, count(*) AS n FROM (SELECT item_id, unnest(string_split_regex(lower(text), '[^\\p{L}\\p{N}]+')) AS term FROM benchmark) WHERE term <> '' GROUP BY 1, 2")
def udtf_tokens(spark, sf_dir):
    """O36"""
    from textgroups.functions.udfs import register

    register(spark)
    load(spark, sf_dir, "benchmark").createOrReplaceTempView("tg_benchmark")
    return spark.sql("SELECT item_id, term, count(*) AS n FROM tg_benchmark, LATERAL tokenize(text) GROUP BY item_id, term")


@query(O.with_(L3, f"SELECT doc_id, cluster_id::INTEGER AS cluster_id, round(sim, 6) AS sim FROM {_LAB}"))
def write_read_assign(spark, sf_dir):
    """O3: labels written by cluster and read back"""
    from textgroups.plans.storage import workspace
    from textgroups.sources.tables import save

    path = workspace(spark, "assign")
    save(lloyd_of(spark, sf_dir).assign, path, ["cluster_id"])
    return _sims(spark.read.parquet(path), "sim")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)

