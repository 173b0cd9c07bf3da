"""DuckDB SQL that recomputes the methods from the tables, independently of the Spark code."""

from __future__ import annotations

UNIT = 1 << 20
FULL = UNIT * UNIT
SEED = 42


def with_(ctes: list[tuple[str, str]], select: str, recursive: bool = True) -> str:
    body = ",\n".join(f"{name} AS {'' if name.startswith(('walk', 'reach', 'prim')) else 'MATERIALIZED '}({sql})" for name, sql in ctes)
    return f"WITH {'RECURSIVE ' if recursive else ''}{body}\n{select}"


def documents(where: str = "", table: str = "documents", min_df: int = 2) -> list[tuple[str, str]]:
    """ids, tokens, term and document frequencies, fixed-point weights."""
    return [
        ("ids", f"SELECT doc_id FROM {table} {where}"),
        ("tok", f"SELECT doc_id, unnest(string_split_regex(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+')) AS term FROM {table} {where}"),
        ("tf", "SELECT doc_id, term, count(*) AS tf FROM tok WHERE term <> '' GROUP BY doc_id, term"),
        ("dfq", f"SELECT term, count(*) AS df FROM tf GROUP BY term HAVING count(*) >= {min_df}"),
        ("raw", "SELECT doc_id, term, tf, tf * ln((SELECT count(*) FROM ids)::DOUBLE / df) AS w FROM tf JOIN dfq USING (term)"),
        ("post", f"SELECT doc_id, term, tf, CAST(round(w / sqrt(sum(w * w) OVER (PARTITION BY doc_id)) * {UNIT}) AS BIGINT) AS wq FROM raw WHERE w > 0"),
        *ordered(),
    ]


def points() -> list[tuple[str, str]]:
    return [
        ("ids", "SELECT vec_id AS doc_id FROM embeddings"),
        ("post", f"SELECT vec_id AS doc_id, generate_subscripts(embedding, 1) - 1 AS term, CAST(round(unnest(embedding)::DOUBLE * {UNIT}) AS BIGINT) AS wq FROM embeddings"),
        *ordered(),
    ]


def ordered() -> list[tuple[str, str]]:
    return [("ord", f"SELECT doc_id, row_number() OVER (ORDER BY md5('{SEED}:' || doc_id), doc_id) - 1 AS rk FROM ids")]


def first_centres(k: int, name: str = "c0") -> list[tuple[str, str]]:
    return [(name, f"SELECT rk AS c, term, wq AS cq FROM ord JOIN post USING (doc_id) WHERE rk < {k}")]


def labels(centres: str, out: str, among: str = "ids") -> list[tuple[str, str]]:
    return [
        (f"d_{out}", f"SELECT p.doc_id, c.c, CAST(sum(p.wq * c.cq) AS BIGINT) AS dp FROM post p JOIN {centres} c USING (term) GROUP BY p.doc_id, c.c"),
        (out, f"SELECT i.doc_id, coalesce(x.c, 0) AS c, coalesce(x.dp, 0) AS dp FROM {among} i LEFT JOIN (SELECT doc_id, c, dp FROM d_{out} QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY dp DESC, c) = 1) x USING (doc_id)"),
    ]


def means(lab: str, out: str, old: str | None = None) -> list[tuple[str, str]]:
    keep = f" UNION ALL SELECT c, term, cq FROM {old} WHERE c NOT IN (SELECT c FROM {lab})" if old else ""
    return [
        (f"s_{out}", f"SELECT c, term, CAST(sum(wq) AS BIGINT) AS s FROM {lab} JOIN post USING (doc_id) GROUP BY c, term"),
        (f"n_{out}", f"SELECT c, sqrt(sum(s::DOUBLE * s)) AS len FROM s_{out} GROUP BY c"),
        (out, f"SELECT c, term, CAST(sign(s) * floor(abs(s) / len * {UNIT} + 0.5) AS BIGINT) AS cq FROM s_{out} JOIN n_{out} USING (c) WHERE s <> 0{keep}"),
    ]


def lloyd(k: int, rounds: int) -> list[tuple[str, str]]:
    out = first_centres(k)
    for i in range(rounds):
        out += [*labels(f"c{i}", f"l{i}"), *means(f"l{i}", f"c{i + 1}", f"c{i}")]
    return out + labels(f"c{rounds}", f"l{rounds}")


def rss(lab: str) -> str:
    """RSS of a labelling as a scalar query."""
    return f"""(SELECT sum(ss - ls2 / n) / {FULL}.0 FROM (SELECT l.c, count(*) AS n, sum(q.q)::DOUBLE AS ss FROM {lab} l LEFT JOIN (SELECT doc_id, sum(wq * wq) AS q FROM post GROUP BY doc_id) q USING (doc_id) GROUP BY l.c) h
  LEFT JOIN (SELECT c, sum(s::DOUBLE * s) AS ls2 FROM (SELECT c, term, sum(wq) AS s FROM {lab} JOIN post USING (doc_id) GROUP BY c, term) GROUP BY c) x USING (c))"""


def micro(m: int) -> list[tuple[str, str]]:
    """Micro-clusters renumbered over the non-empty ones: head(mc, n, ss, min_sim), vec, all pairs with kind and rank."""
    return [
        *first_centres(m),
        *labels("c0", "l0"),
        ("head0", f"SELECT l.c, count(*) AS n, CAST(sum(coalesce(q.q, 0)) AS DOUBLE) / {FULL}.0 AS ss, min(l.dp) / {FULL}.0 AS min_sim FROM l0 l LEFT JOIN (SELECT doc_id, sum(wq * wq) AS q FROM post GROUP BY doc_id) q USING (doc_id) GROUP BY l.c"),
        ("head", "SELECT row_number() OVER (ORDER BY c) - 1 AS mc, c, n, ss, min_sim FROM head0"),
        ("gram", "SELECT x.c AS ca, y.c AS cb, sum(x.cq * y.cq) AS dp FROM c0 x JOIN c0 y USING (term) WHERE x.c < y.c GROUP BY x.c, y.c"),
        ("pair0", f"SELECT a.mc AS a, b.mc AS b, round(coalesce(g.dp, 0) / {FULL}.0, 12) AS cos, a.min_sim AS ma, b.min_sim AS mb FROM head a JOIN head b ON a.mc < b.mc LEFT JOIN gram g ON g.ca = a.c AND g.cb = b.c"),
        ("pairs", "SELECT a, b, cos, greatest(round(cos - ma - mb, 12), 0) AS sim, CASE WHEN round(cos - ma - mb, 12) > 0 THEN 2 WHEN cos >= ma OR cos >= mb THEN 1 ELSE 0 END AS kind FROM pair0"),
        ("ranked", "SELECT *, row_number() OVER (ORDER BY kind DESC, CASE WHEN kind = 2 THEN sim ELSE cos END DESC, cos DESC, a, b) AS rn FROM pairs"),
    ]


def first_groups(linked: str) -> list[tuple[str, str]]:
    """groups(mc, g) of first-match grouping over linked(a, b)."""
    return [
        ("par", f"SELECT b, min(a) AS p FROM {linked} GROUP BY b"),
        ("walk", "SELECT mc, mc AS cur FROM head UNION ALL SELECT w.mc, par.p FROM walk w JOIN par ON par.b = w.cur"),
        ("roots", "SELECT mc, min(cur) AS root FROM walk GROUP BY mc"),
        ("groups", "SELECT mc, dense_rank() OVER (ORDER BY root) - 1 AS g FROM roots"),
    ]


def closure_groups(linked: str) -> list[tuple[str, str]]:
    return [
        ("twoway", f"SELECT a, b FROM {linked} UNION ALL SELECT b, a FROM {linked}"),
        ("reach", "SELECT mc, mc AS x FROM head UNION SELECT r.mc, w.b FROM reach r JOIN twoway w ON w.a = r.x"),
        ("roots", "SELECT mc, min(x) AS root FROM reach GROUP BY mc"),
        ("groups", "SELECT mc, dense_rank() OVER (ORDER BY root) - 1 AS g FROM roots"),
    ]


def micro_labels(k: int, m: int) -> list[tuple[str, str]]:
    return [
        *micro(m),
        ("crit", "SELECT b, min(rn) AS r FROM ranked GROUP BY b"),
        ("cut", f"SELECT r FROM crit QUALIFY row_number() OVER (ORDER BY r) = (SELECT count(*) FROM head) - {k}"),
        ("linked", "SELECT a, b FROM ranked WHERE rn <= (SELECT r FROM cut)"),
        *first_groups("linked"),
        ("member", "SELECT l0.doc_id, g.g AS c, l0.dp FROM l0 JOIN head USING (c) JOIN groups g USING (mc)"),
        *means("member", "gc"),
        *labels("gc", "fin"),
    ]


def sample(s: int | str) -> list[tuple[str, str]]:
    """The first ``s`` documents of the draw; ``s`` is a number or a scalar query."""
    return [
        ("smp", f"SELECT doc_id, rk FROM ord WHERE rk < {s}"),
        ("sp", "SELECT doc_id, term, wq FROM post JOIN smp USING (doc_id)"),
        ("sdot", "SELECT x.doc_id AS a, y.doc_id AS b, CAST(sum(x.wq * y.wq) AS BIGINT) AS dp FROM sp x JOIN sp y USING (term) WHERE x.doc_id <> y.doc_id GROUP BY x.doc_id, y.doc_id"),
        ("e", "SELECT x.doc_id AS a, y.doc_id AS b, coalesce(d.dp, 0) AS dp FROM smp x JOIN smp y ON x.doc_id <> y.doc_id LEFT JOIN sdot d ON d.a = x.doc_id AND d.b = y.doc_id"),
    ]


def single_link(k: int) -> list[tuple[str, str]]:
    """seeded(doc_id, c): single-link clusters of the sample by a spanning tree grown node by node."""
    better = "(e.dp > p.best OR (e.dp = p.best AND (least(p.node, p.chosen), greatest(p.node, p.chosen)) < (least(p.node, p.link), greatest(p.node, p.link))))"
    pick = "first_value(node) OVER (ORDER BY best DESC, least(node, link), greatest(node, link))"
    return [
        ("root0", "SELECT min(doc_id) AS r FROM smp"),
        ("prim", f"SELECT 1 AS step, e.b AS node, e.dp AS best, e.a AS link FROM e WHERE e.a = (SELECT r FROM root0) UNION ALL SELECT p.step + 1, p.node, CASE WHEN {better} THEN e.dp ELSE p.best END, CASE WHEN {better} THEN p.chosen ELSE p.link END FROM (SELECT *, {pick} AS chosen FROM prim) p JOIN e ON e.a = p.chosen AND e.b = p.node WHERE p.node <> p.chosen"),
        ("tree", "SELECT least(node, link) AS a, greatest(node, link) AS b, best AS dp FROM prim QUALIFY row_number() OVER (PARTITION BY step ORDER BY best DESC, least(node, link), greatest(node, link)) = 1"),
        ("kept", f"SELECT a, b FROM tree QUALIFY row_number() OVER (ORDER BY dp DESC, a, b) <= (SELECT count(*) FROM smp) - {k}"),
        ("kept2", "SELECT a, b FROM kept UNION ALL SELECT b, a FROM kept"),
        ("reach", "SELECT doc_id, doc_id AS x FROM smp UNION SELECT r.doc_id, kept2.b FROM reach r JOIN kept2 ON kept2.a = r.x"),
        ("comp", "SELECT r.doc_id, min(s.rk) AS low FROM reach r JOIN smp s ON s.doc_id = r.x GROUP BY r.doc_id"),
        ("seeded", "SELECT doc_id, dense_rank() OVER (ORDER BY low) - 1 AS c, 0 AS dp FROM comp"),
    ]


def sampleseed(k: int, rounds: int, reassign: bool = False) -> list[tuple[str, str]]:
    """Last labels are ``r{rounds}``; the sample has sqrt(k n) documents."""
    out = [*sample(f"(SELECT CAST(ceil(sqrt({k} * count(*)::DOUBLE)) AS BIGINT) FROM ids)"), *single_link(k), *means("seeded", "k0"), ("rest", "SELECT doc_id FROM ids WHERE doc_id NOT IN (SELECT doc_id FROM smp)")]
    for i in range(1, rounds + 1):
        if reassign:
            out += labels(f"k{i - 1}", f"r{i}")
        else:
            out += [*labels(f"k{i - 1}", f"t{i}", "rest"), (f"r{i}", f"SELECT doc_id, c, dp FROM t{i} UNION ALL SELECT doc_id, c, dp FROM seeded")]
        if i < rounds:
            out += means(f"r{i}", f"k{i}", f"k{i - 1}")
    return out


#: Documents of the sample of the second proposal, as a scalar query over ``ids``.
def sample_rows(k: int) -> str:
    return f"(SELECT CAST(ceil(sqrt({k} * count(*)::DOUBLE)) AS BIGINT) FROM ids)"


ALL_ROWS = "(SELECT count(*) FROM ids)"


def linkage(kind: str, k: int) -> list[tuple[str, str]]:
    """seeded(doc_id, c): the sample's clusters by ``complete`` or ``average`` linkage, merged pair by pair."""
    weight = "CASE WHEN a2 = i AND b2 <> i THEN na WHEN b2 = i THEN nb ELSE 1 END"
    value = "min(sim)" if kind == "complete" else f"round(sum(sim * {weight}) / sum({weight}), 12)"
    first = "OVER (ORDER BY sim DESC, a, b)"
    return [
        ("walk", f"""SELECT 0::BIGINT AS step, x.rk AS a, y.rk AS b, round(e.dp / {FULL}.0, 12) AS sim, 1::BIGINT AS na, 1::BIGINT AS nb, 0::BIGINT AS i, 0::BIGINT AS j FROM e JOIN smp x ON x.doc_id = e.a JOIN smp y ON y.doc_id = e.b
  UNION ALL SELECT step + 1, a2, b2, {value}, CAST(CASE WHEN a2 = i THEN sum(na) ELSE max(na) END AS BIGINT), CAST(CASE WHEN b2 = i THEN sum(nb) ELSE max(nb) END AS BIGINT), i, j
  FROM (SELECT *, CASE WHEN a = j THEN i ELSE a END AS a2, CASE WHEN b = j THEN i ELSE b END AS b2 FROM (SELECT step, a, b, sim, na, nb, first_value(a) {first} AS i, first_value(b) {first} AS j FROM walk))
  WHERE a2 <> b2 AND step < (SELECT count(*) FROM smp) - {k} GROUP BY step, a2, b2, i, j"""),
        ("kept", "SELECT DISTINCT i AS a, j AS b FROM walk WHERE step > 0"),
        ("kept2", "SELECT a, b FROM kept UNION ALL SELECT b, a FROM kept"),
        ("reach", "SELECT rk, rk AS x FROM smp UNION SELECT r.rk, kept2.b FROM reach r JOIN kept2 ON kept2.a = r.x"),
        ("comp", "SELECT rk, min(x) AS low FROM reach GROUP BY rk"),
        ("seeded", "SELECT doc_id, dense_rank() OVER (ORDER BY low) - 1 AS c FROM comp JOIN smp USING (rk)"),
    ]


def euclid_rounds(k: int, rounds: int) -> list[tuple[str, str]]:
    """x(doc_id, v), o0..(c, v) and l0..(doc_id, c, dist2): squared distances to the means, empty clusters keep theirs."""
    out = [("x", "SELECT vec_id AS doc_id, embedding::DOUBLE[] AS v FROM embeddings"), ("o0", f"SELECT v, row_number() OVER (ORDER BY md5('{SEED}:' || doc_id), doc_id) - 1 AS c FROM x QUALIFY c < {k}")]
    for i in range(rounds + 1):
        out.append((f"l{i}", f"SELECT x.doc_id, o.c, list_sum(list_transform(list_zip(x.v, o.v), lambda p: (p[1] - p[2]) * (p[1] - p[2]))) AS dist2 FROM x CROSS JOIN o{i} o QUALIFY row_number() OVER (PARTITION BY x.doc_id ORDER BY round(list_dot_product(o.v, o.v) - 2 * list_dot_product(x.v, o.v), 9), o.c) = 1"))
        if i < rounds:
            out.append((f"m{i}", f"SELECT c, list(m ORDER BY d) AS v FROM (SELECT c, d, avg(e) AS m FROM (SELECT l.c, generate_subscripts(x.v, 1) AS d, unnest(x.v) AS e FROM l{i} l JOIN x USING (doc_id)) GROUP BY c, d) GROUP BY c"))
            out.append((f"o{i + 1}", f"SELECT c, v FROM m{i} UNION ALL SELECT c, v FROM o{i} WHERE c NOT IN (SELECT c FROM m{i})"))
    return out


def micro_euclid(k: int, m: int) -> list[tuple[str, str]]:
    """fin(doc_id, c): spheres around m points, the smallest gaps linked first until k groups are left, then their means."""
    return [
        *euclid_rounds(m, 0),
        ("head", "SELECT row_number() OVER (ORDER BY c) - 1 AS mc, c, n, r FROM (SELECT c, count(*) AS n, sqrt(max(dist2)) AS r FROM l0 GROUP BY c)"),
        ("vec", "SELECT h.mc, h.r, o.v FROM head h JOIN o0 o USING (c)"),
        ("pairs", "SELECT a.mc AS a, b.mc AS b, sqrt(list_sum(list_transform(list_zip(a.v, b.v), lambda p: (p[1] - p[2]) * (p[1] - p[2])))) - a.r - b.r AS gap FROM vec a JOIN vec b ON a.mc < b.mc"),
        ("ranked", "SELECT *, row_number() OVER (ORDER BY gap, a, b) AS rn FROM pairs"),
        ("crit", "SELECT b, min(rn) AS r FROM ranked GROUP BY b"),
        ("cut", f"SELECT r FROM crit QUALIFY row_number() OVER (ORDER BY r) = (SELECT count(*) FROM head) - {k}"),
        ("linked", "SELECT a, b FROM ranked WHERE rn <= (SELECT r FROM cut)"),
        *first_groups("linked"),
        ("gm", "SELECT c, list(m ORDER BY d) AS v FROM (SELECT g AS c, d, sum(e) / any_value(n) AS m FROM (SELECT g.g, generate_subscripts(x.v, 1) AS d, unnest(x.v) AS e, gn.n FROM l0 JOIN head USING (c) JOIN groups g USING (mc) JOIN x USING (doc_id) JOIN (SELECT g, sum(n) AS n FROM groups JOIN head USING (mc) GROUP BY g) gn ON gn.g = g.g) GROUP BY g, d) GROUP BY c"),
        ("fin", "SELECT x.doc_id, gm.c FROM x CROSS JOIN gm QUALIFY row_number() OVER (PARTITION BY x.doc_id ORDER BY round(list_dot_product(gm.v, gm.v) - 2 * list_dot_product(x.v, gm.v), 9), gm.c) = 1"),
    ]


def external(lab: str, label: str = "lang") -> str:
    """(measure, value) of a labelling against a column of documents."""
    return f"""SELECT unnest(['purity', 'nmi', 'ari', 'pair_f']) AS measure, unnest([purity, nmi, ari, pair_f]) AS value FROM (
  SELECT purity, CASE WHEN hr + hc > 0 THEN 2 * mi / (hr + hc) ELSE 1 END AS nmi, (t - r * c / ev) / ((r + c) / 2 - r * c / ev) AS ari, 2 * (t / r) * (t / c) / (t / r + t / c) AS pair_f FROM (
    SELECT (SELECT sum(m) FROM (SELECT max(n) AS m FROM cell GROUP BY c)) / t0.n AS purity, t0.n * (t0.n - 1) / 2 AS ev,
      (SELECT sum(cell.n / t0.n * ln(cell.n * t0.n / (a.n * b.n))) FROM cell JOIN (SELECT c, sum(n) AS n FROM cell GROUP BY c) a USING (c) JOIN (SELECT y, sum(n) AS n FROM cell GROUP BY y) b USING (y)) AS mi,
      (SELECT -sum(x / t0.n * ln(x / t0.n)) FROM (SELECT sum(cell.n) AS x FROM cell GROUP BY c)) AS hr, (SELECT -sum(x / t0.n * ln(x / t0.n)) FROM (SELECT sum(cell.n) AS x FROM cell GROUP BY y)) AS hc,
      (SELECT sum(cell.n * (cell.n - 1) / 2) FROM cell) AS t, (SELECT sum(x * (x - 1) / 2) FROM (SELECT sum(cell.n) AS x FROM cell GROUP BY c)) AS r, (SELECT sum(x * (x - 1) / 2) FROM (SELECT sum(cell.n) AS x FROM cell GROUP BY y)) AS c
    FROM (SELECT sum(cell.n) AS n FROM cell) t0))"""


def silhouette(lab: str) -> str:
    """Mean cosine silhouette of a labelling of points."""
    return f"""(SELECT avg(CASE WHEN sz > 1 AND other IS NOT NULL THEN (other - inner_) / greatest(greatest(inner_, other), 1e-12) ELSE 0 END) FROM (
  SELECT d.doc_id, max(CASE WHEN d.c = l.c THEN z.n END) AS sz, max(CASE WHEN d.c = l.c THEN 1 - (d.dp / {FULL}.0 - q.q / {FULL}.0) / greatest(z.n - 1, 1) END) AS inner_, min(CASE WHEN d.c <> l.c THEN 1 - d.dp / {FULL}.0 / z.n END) AS other
  FROM (SELECT p.doc_id, s.c, sum(p.wq * s.s)::DOUBLE AS dp FROM post p JOIN (SELECT c, term, CAST(sum(wq) AS BIGINT) AS s FROM {lab} JOIN post USING (doc_id) GROUP BY c, term) s USING (term) GROUP BY p.doc_id, s.c) d
  JOIN {lab} l USING (doc_id) JOIN (SELECT c, count(*) AS n FROM {lab} GROUP BY c) z ON z.c = d.c JOIN (SELECT doc_id, sum(wq * wq)::DOUBLE AS q FROM post GROUP BY doc_id) q ON q.doc_id = d.doc_id GROUP BY d.doc_id))"""


def heaviest(centres: str, t: int) -> tuple[str, str]:
    """The t heaviest terms of each centre, ties by the order of the terms' md5."""
    return ("heavy", f"SELECT c, term, cq FROM {centres} QUALIFY row_number() OVER (PARTITION BY c ORDER BY abs(cq) DESC, md5(term), term) <= {t}")
