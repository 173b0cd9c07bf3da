"""Related methods: repeated splits, careful seeds, factorisation, one-pass and sample methods, MLlib."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors
from textgroups.operators.assign import checked, assign_nearest, totals, unit, vectors_of
from textgroups.operators.hac import agglomerate
from textgroups.operators.lloyd import lloyd
from textgroups.operators.sampling import draw_sample, order_key, pick_centers, sample_size
from textgroups.plans.storage import materialise


def seed_centers(vecs: Vectors, k: int, how: str = "oversample", seed: int = 42, rounds: int = 4) -> np.ndarray:
    """Carefully chosen starting centres.

    ``farthest``: from the first drawn document on, always the document least similar to all chosen. ``oversample``: a
    few rounds draw about 2 k / rounds documents each with chances by distance, then the candidates are grouped to k.
    ``density``: of a sample, the documents with most similarity to the sample and least to those chosen.
    """
    spark = vecs.packed.sparkSession
    first = vectors_of(vecs, pick_centers(vecs.packed.select("doc_id"), 1, seed, n=vecs.n))
    if how == "farthest":
        chosen = first
        while chosen.shape[1] < k:
            far = assign_nearest(vecs, chosen).orderBy("sim", "doc_id").limit(1).first()["doc_id"]
            chosen = np.hstack([chosen, vectors_of(vecs, spark.createDataFrame([(0, far)], "center_id long, doc_id long"))])
        return chosen
    if how == "oversample":
        chosen = first
        for i in range(rounds):
            far = materialise(assign_nearest(vecs, chosen).select("doc_id", F.greatest(1 - F.col("sim"), F.lit(0.0)).alias("d")), "far")
            total = far.agg(F.sum("d")).first()[0] or 1.0
            chance = F.conv(F.substring(order_key(F.col("doc_id"), seed + i + 1), 1, 12), 16, 10).cast("double") / float(16**12)
            drawn = far.filter(chance < F.col("d") * (2.0 * k / rounds / total)).orderBy("doc_id").select("doc_id").collect()  # about 2 k / rounds
            if drawn:
                chosen = np.hstack([chosen, vectors_of(vecs, spark.createDataFrame([(j, r["doc_id"]) for j, r in enumerate(drawn)], "center_id long, doc_id long"))])
        if chosen.shape[1] <= k:
            return np.hstack([chosen, vectors_of(vecs, pick_centers(vecs.packed.select("doc_id"), k, seed, n=vecs.n))])[:, :k]
        weight = totals(vecs.packed, chosen).count
        _, labels = agglomerate(chosen.T @ chosen / UNIT / UNIT, k, "average")
        return unit(np.stack([(chosen[:, labels == g] * np.maximum(weight[labels == g], 1)).sum(axis=1) for g in range(k)], axis=1))
    return vectors_of(vecs, densest(vecs, k, seed))


def densest(vecs: Vectors, k: int, seed: int = 42) -> DataFrame:
    """(center_id, doc_id) of the ``density`` start. One task holds the sample's sparse rows, never a matrix of its terms.

    The products with the whole sample are those with its sum, and each choice needs the products with one row, so all
    is whole numbers over the sample's own cells.
    """
    sample = draw_sample(vecs.packed.select("doc_id"), sample_size(vecs.n, k), seed, n=vecs.n)
    rows = vecs.packed.join(F.broadcast(sample), "doc_id").select("doc_id", "rk", "idx", "val").repartition(1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        table = pa.Table.from_batches(got).sort_by("rk").combine_chunks()
        ids, s = table.column("doc_id").to_numpy(), table.num_rows
        idx, val = (table.column(c).combine_chunks() for c in ("idx", "val"))
        row = np.repeat(np.arange(s), np.diff(idx.offsets.to_numpy()))
        _, cell = np.unique(idx.flatten().to_numpy(), return_inverse=True)
        x = val.flatten().to_numpy().astype(np.float64)
        ends = np.searchsorted(row, np.arange(s + 1))

        def dots(y: np.ndarray) -> np.ndarray:
            return np.bincount(row, x * y[cell], s) / UNIT / UNIT

        density, picked, nearest = dots(np.bincount(cell, x)), [], np.zeros(s)
        for _ in range(min(k, s)):
            value = np.round(density * (1 - nearest), 9)
            value[picked] = -np.inf
            picked.append(int(value.argmax()))
            one, own = np.zeros(int(cell.max(initial=-1)) + 1), slice(*ends[picked[-1] : picked[-1] + 2])
            one[cell[own]] = x[own]
            nearest = np.maximum(nearest, dots(one))
        yield pa.record_batch([pa.array(np.arange(len(picked))), pa.array(ids[picked])], names=["center_id", "doc_id"])

    return materialise(rows.mapInArrow(run, "center_id long, doc_id long"), "densest")


def _subset(vecs: Vectors, labels: DataFrame, cluster: int) -> Vectors:
    rows = materialise(vecs.packed.join(labels.filter(F.col("cluster_id") == cluster).select("doc_id"), "doc_id"), "subset")
    return vecs._replace(packed=rows, n=rows.count())


def bisecting(vecs: Vectors, k: int, pick: str = "lowest_similarity", trials: int = 1, rounds: int = 5, seed: int = 42) -> DataFrame:
    """Split in two until there are ``k`` clusters (B3): (doc_id, cluster_id).

    The next cluster is the one of lowest internal similarity, the ``largest``, or that of highest ``rss``; of several
    trial splits the one with the lowest RSS is taken. A cluster that does not split is left alone.
    """
    labels = materialise(vecs.packed.select("doc_id", F.lit(0).cast("long").alias("cluster_id")), "labels")
    state = {0: _state(vecs)}
    frozen: set[int] = set()
    while len(state) < k:
        ready = [c for c in state if c not in frozen and state[c]["n"] > 1]
        if not ready:
            break
        key = {"lowest_similarity": lambda c: state[c]["internal"], "largest": lambda c: -state[c]["n"], "rss": lambda c: -state[c]["rss"]}[pick]
        target = min(ready, key=lambda c: (key(c), c))
        part = _subset(vecs, labels, target)
        tried = []
        for t in range(trials):
            got = lloyd(part, 2, max_iter=rounds, seed=seed + t)
            sums = totals(part.packed, got.centers)
            if (sums.count > 0).all():
                tried.append((sums.rss(), t, got, sums))
        if not tried:
            frozen.add(target)
            continue
        _, _, got, sums = min(tried, key=lambda x: x[:2])
        fresh = len(state)
        sides = got.assign.select("doc_id", F.when(F.col("cluster_id") == 1, F.lit(fresh)).otherwise(F.lit(target)).cast("long").alias("side"))
        labels = materialise(labels.join(sides, "doc_id", "left").select("doc_id", F.coalesce("side", "cluster_id").alias("cluster_id")), "labels")
        for side, c in ((0, target), (1, fresh)):
            n, ls2 = sums.count[side], float((sums.sums[:, side] ** 2).sum()) / UNIT / UNIT
            state[c] = {"n": n, "internal": ls2 / n / n, "rss": sums.square[side] / UNIT / UNIT - ls2 / n}
    return labels


def _state(vecs: Vectors) -> dict:
    got = totals(vecs.packed, np.zeros((vecs.v, 1)))
    n, ls2 = max(got.count[0], 1), float((got.sums[:, 0] ** 2).sum()) / UNIT / UNIT
    return {"n": n, "internal": ls2 / n / n, "rss": got.square[0] / UNIT / UNIT - ls2 / n}


def nmf(vecs: Vectors, rank: int, iters: int = 10, seed: int = 42) -> tuple[DataFrame, np.ndarray, list[float]]:
    """Non-negative factorisation of the document-term matrix by multiplicative updates.

    The term side (v x rank) is on the driver and goes to the tasks by broadcast, a document's loadings are solved in
    its task, and one pass a round brings back the two sums that the term side needs. Returns the loadings
    (doc_id, load), the term side, and the squared error of each round, which never rises.
    """
    checked(rank, vecs.v)
    rng, v = np.random.default_rng(seed), vecs.v
    terms = rng.random((v, rank)) * 0.1 + 0.01
    spark, history = vecs.packed.sparkSession, []
    loads = materialise(vecs.packed.select("doc_id", "idx", "val", F.array(*[F.lit(1.0 / rank)] * rank).alias("load")), "loads")
    for _ in range(iters):
        held = spark.sparkContext.broadcast(terms)

        def step(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            h = held.value
            gram = h.T @ h
            for batch in batches:
                sizes = np.diff(batch.column("idx").offsets.to_numpy())
                idx, val = batch.column("idx").flatten().to_numpy(), batch.column("val").flatten().to_numpy() / UNIT
                row = np.repeat(np.arange(len(sizes)), sizes)
                w = batch.column("load").flatten().to_numpy().reshape(len(sizes), -1)
                xh = np.zeros_like(w)
                np.add.at(xh, row, h[idx] * val[:, None])
                w = w * xh / np.maximum(w @ gram, 1e-12)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("idx"), batch.column("val"), pa.array(list(w), pa.list_(pa.float64()))], names=["doc_id", "idx", "val", "load"])

        loads = materialise(loads.mapInArrow(step, loads.schema), "loads")

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            xw, ww, xx = np.zeros((v, rank)), np.zeros((rank, rank)), 0.0
            for batch in batches:
                sizes = np.diff(batch.column("idx").offsets.to_numpy())
                idx, val = batch.column("idx").flatten().to_numpy(), batch.column("val").flatten().to_numpy() / UNIT
                w = batch.column("load").flatten().to_numpy().reshape(len(sizes), -1)
                np.add.at(xw, idx, w[np.repeat(np.arange(len(sizes)), sizes)] * val[:, None])
                ww += w.T @ w
                xx += float((val * val).sum())
            some = np.flatnonzero(xw.any(axis=1))
            yield pa.record_batch([pa.array(np.concatenate([some, [-1, -2]])), pa.array([*xw[some], ww.ravel(), np.array([xx])])], names=["t", "x"])

        got = loads.mapInArrow(add, "t long, x array<double>").select("t", F.posexplode("x").alias("i", "x")).groupBy("t", "i").agg(F.sum("x").alias("x")).toArrow()
        at, place, x = (got.column(i).to_numpy() for i in range(3))
        xw, ww = np.zeros((vecs.v, rank)), np.zeros(rank * rank)
        xw[at[at >= 0], place[at >= 0]] = x[at >= 0]
        ww[place[at == -1]] = x[at == -1]
        ww, xx = ww.reshape(rank, rank), float(x[at == -2].sum())
        terms = terms * xw / np.maximum(terms @ ww, 1e-12)
        history.append(float(xx - 2 * (terms * xw).sum() + ((terms.T @ terms) * ww).sum()))
        held.unpersist()
    return loads.select("doc_id", "load"), terms, history


def factorkm(vecs: Vectors, k: int, rank: int | None = None, iters: int = 10, how: str = "lloyd", seed: int = 42) -> DataFrame:
    """Labels from the factorisation (B8): K-Means on the loadings, or each document's heaviest loading."""
    loads, _, _ = nmf(vecs, rank or k, iters, seed)
    if how == "heaviest":
        return loads.select("doc_id", (F.array_position("load", F.array_max("load")) - 1).cast("long").alias("cluster_id"))
    length = F.sqrt(F.aggregate("load", F.lit(0.0), lambda s, x: s + x * x))
    scaled = F.transform("load", lambda x: F.coalesce(F.round(F.try_divide(x, length) * UNIT), F.lit(0)).cast("long"))
    idx = F.transform(F.sequence(F.lit(0), F.size("load") - 1), lambda i: i.cast("int"))
    packed = materialise(loads.select("doc_id", idx.alias("idx"), scaled.alias("val")), "loadings")
    return lloyd(Vectors(packed, None, vecs.n, rank or k), k, seed=seed).assign.select("doc_id", "cluster_id")


def cf_onepass(vecs: Vectors, threshold: float, max_nodes: int = 200) -> tuple[DataFrame, np.ndarray]:
    """One pass over the documents (B9): a task absorbs a document in its most similar entry if the similarity to the
    entry's centroid reaches the threshold, else opens one; a full list first merges its most similar entries. Entries
    (count and sums) of all tasks are then merged the same way; labels come from one assignment."""
    v = vecs.v

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n = np.zeros((v, 0)), np.zeros(0)
        for batch in batches:
            ends = batch.column("idx").offsets.to_numpy()
            idx, val = batch.column("idx").flatten().to_numpy(), batch.column("val").flatten().to_numpy()
            for a, b in zip(ends[:-1] - ends[0], ends[1:] - ends[0], strict=True):
                if a == b:
                    continue
                norms = np.sqrt((sums**2).sum(axis=0))
                cos = val[a:b] @ sums[idx[a:b]] / np.maximum(norms * UNIT, 1e-9)
                if len(cos) and cos.max() >= threshold:
                    j = int(cos.argmax())
                else:
                    if len(n) >= max_nodes:
                        sums, n = merge_closest(sums, n, max_nodes - max(1, max_nodes // 4))
                    sums, n, j = np.hstack([sums, np.zeros((v, 1))]), np.append(n, 0), len(n)
                sums[idx[a:b], j] += val[a:b]
                n[j] += 1
        for j in range(len(n)):
            t = np.flatnonzero(sums[:, j])
            yield pa.record_batch([pa.array([int(n[j])]), pa.array([t]), pa.array([sums[t, j].astype(np.int64)])], names=["n", "idx", "val"])

    rows = vecs.packed.select("idx", "val").mapInArrow(run, "n long, idx array<long>, val array<long>").collect()  # max_nodes a task
    sums, n = np.zeros((v, len(rows))), np.array([r["n"] for r in rows], float)
    for j, r in enumerate(rows):
        sums[r["idx"], j] = r["val"]
    sums, n = merge_closest(sums, n, max_nodes, threshold)
    centers = unit(sums)
    return assign_nearest(vecs, centers).withColumnRenamed("center_id", "cluster_id"), centers


def merge_closest(sums: np.ndarray, n: np.ndarray, most: int, threshold: float = 2.0) -> tuple[np.ndarray, np.ndarray]:
    """Entries merged, most similar first, until at most ``most`` are left and none reach the threshold."""
    c = unit(sums)
    gram = c.T @ c / UNIT / UNIT
    merges, _ = agglomerate(gram, 1, "average") if len(n) > 1 else ([], None)
    owner = np.arange(len(n))
    left = len(n)
    for a, b, h, _ in merges:
        if left <= most and h < threshold:
            break
        owner[owner == b] = a
        left -= 1
    groups = np.unique(owner)
    return np.stack([sums[:, owner == g].sum(axis=1) for g in groups], axis=1) if len(groups) else sums, np.array([n[owner == g].sum() for g in groups])


def rep_points(vecs: Vectors, k: int, n_rep: int = 5, shrink: float = 0.3, s: int | None = None, seed: int = 42) -> DataFrame:
    """Representatives (B10): a sample is clustered, each cluster gets ``n_rep`` scattered members drawn towards its
    centroid by ``shrink``, and every document follows its most similar representative."""
    sample = draw_sample(vecs.packed.select("doc_id"), s or sample_size(vecs.n, k), seed, n=vecs.n)
    x = vectors_of(vecs, sample.select(F.col("rk").alias("center_id"), "doc_id"))
    _, labels = agglomerate(x.T @ x / UNIT / UNIT, k, "average")
    reps, owner = [], []
    for g in range(k):
        members = x[:, labels == g]
        mean = unit(members.sum(axis=1, keepdims=True))
        chosen: list[int] = []
        for _ in range(min(n_rep, members.shape[1])):
            near = (members.T @ (members[:, chosen] if chosen else mean)).max(axis=1)
            near[chosen] = np.inf
            chosen.append(int(near.argmin()))
        reps.append(unit((1 - shrink) * members[:, chosen] + shrink * mean))
        owner += [g] * len(chosen)
    table = vecs.packed.sparkSession.createDataFrame([(i, g) for i, g in enumerate(owner)], "center_id long, cluster_id long")
    return assign_nearest(vecs, np.hstack(reps)).join(F.broadcast(table), "center_id").select("doc_id", "cluster_id", "sim")


def random_medoids(vecs: Vectors, k: int, num_local: int = 2, max_neighbor: int = 10, s: int | None = None, seed: int = 42) -> DataFrame:
    """Random search over sets of medoids on a sample (B11): a random swap is kept if it lowers the sum of 1 - cosine;
    ``max_neighbor`` failures in a row end a search; the best of ``num_local`` searches labels all documents."""
    sample = draw_sample(vecs.packed.select("doc_id"), s or sample_size(vecs.n, k), seed, n=vecs.n)
    x = vectors_of(vecs, sample.select(F.col("rk").alias("center_id"), "doc_id"))
    gram, rng, best = x.T @ x / UNIT / UNIT, np.random.default_rng(seed), (np.inf, None)
    cost = lambda m: float((1 - gram[:, m].max(axis=1)).sum())
    for _ in range(num_local):
        now = rng.choice(len(gram), min(k, len(gram)), replace=False)
        value, failed = cost(now), 0
        while failed < max_neighbor and len(gram) > k:
            tried = now.copy()
            tried[rng.integers(len(now))] = rng.choice(np.setdiff1d(np.arange(len(gram)), now))
            if (c := cost(tried)) < value:
                now, value, failed = tried, c, 0
            else:
                failed += 1
        best = min(best, (value, now), key=lambda t: t[0])
    return assign_nearest(vecs, x[:, best[1]]).withColumnRenamed("center_id", "cluster_id")


def _ml_vectors(vecs: Vectors) -> DataFrame:
    """(doc_id, features) for MLlib; documents without a term are left out (their cosine is undefined)."""
    from pyspark.ml.functions import array_to_vector

    from pyspark.ml.linalg import Vectors as MlVectors, VectorUDT

    if vecs.terms is None:
        return vecs.packed.select("doc_id", array_to_vector(F.transform("val", lambda x: x.cast("double"))).alias("features"))
    v = vecs.v
    sparse = F.udf(lambda idx, val: MlVectors.sparse(v, idx, [float(x) for x in val]), VectorUDT())
    return vecs.packed.filter(F.size("idx") > 0).select("doc_id", sparse("idx", "val").alias("features"))


def mllib_kmeans(vecs: Vectors, k: int, distance: str = "cosine", init: str = "random", seed: int = 42, max_iter: int = 8) -> DataFrame:
    """The library's K-Means as a comparator (B2)."""
    from pyspark.ml.clustering import KMeans

    rows = _ml_vectors(vecs)
    model = KMeans(k=k, distanceMeasure=distance, initMode=init, seed=seed, maxIter=max_iter).fit(rows)
    return model.transform(rows).select("doc_id", F.col("prediction").cast("long").alias("cluster_id"))


def mllib_bisecting(vecs: Vectors, k: int, distance: str = "cosine", seed: int = 42) -> DataFrame:
    """The library's repeated splits as a comparator (B2)."""
    from pyspark.ml.clustering import BisectingKMeans

    rows = _ml_vectors(vecs)
    model = BisectingKMeans(k=k, distanceMeasure=distance, seed=seed).fit(rows)
    return model.transform(rows).select("doc_id", F.col("prediction").cast("long").alias("cluster_id"))
