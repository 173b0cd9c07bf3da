"""Cost and accuracy measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textgroups.functions.text import UNIT
from textgroups.functions.vectors import Vectors


def _cluster_sums(vecs: Vectors, assign: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(cluster_id, n, ss) and (cluster_id, term_id, s); both shuffles carry partial sums."""
    rows = vecs.packed.join(assign.select("doc_id", "cluster_id"), "doc_id")
    square = F.aggregate("val", F.lit(0).cast("long"), lambda s, x: s + x * x)
    head = rows.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.sum(square.cast("decimal(20,0)")).cast("double").alias("ss"))
    sums = rows.select("cluster_id", F.explode(F.arrays_zip("idx", "val")).alias("p")).groupBy("cluster_id", F.col("p.idx").alias("term_id")).agg(F.sum("p.val").alias("s"))
    return head, sums


def cluster_rss(vecs: Vectors, assign: DataFrame) -> DataFrame:
    """(cluster_id, n, ss, ls2, rss): SS - LS LS / N of each cluster."""
    head, sums = _cluster_sums(vecs, assign)
    ls2 = sums.groupBy("cluster_id").agg(F.sum(F.col("s").cast("double") * F.col("s")).alias("ls2"))
    return head.join(ls2, "cluster_id", "left").select("cluster_id", "n", "ss", F.coalesce("ls2", F.lit(0.0)).alias("ls2"), ((F.col("ss") - F.coalesce("ls2", F.lit(0.0)) / F.col("n")) / float(UNIT * UNIT)).alias("rss"))


def rss(vecs: Vectors, assign: DataFrame, kind: str = "squared") -> float:
    """Residual sum of squares (M1); ``mean`` and ``root`` of it, or ``cosine``: the sum of 1 - similarity."""
    if kind == "cosine":
        return float(assign.agg(F.sum(1 - F.col("sim"))).first()[0] or 0.0)
    got = cluster_rss(vecs, assign).agg(F.sum("rss"), F.sum("n")).first()
    total, n = float(got[0] or 0.0), got[1] or 0
    return {"squared": total, "mean": total / max(1, n), "root": total**0.5}[kind]


def rss_loss(new: float, base: float) -> float:
    """100 (new / base - 1) (M2)."""
    return 100.0 * (new / base - 1.0)


def time_gain(new: float, base: float) -> float:
    """100 (1 - new / base) (M3)."""
    return 100.0 * (1.0 - new / base)


def speed_up(one: float, many: float) -> float:
    """t(1) / t(p) (M4)."""
    return one / many


def logical_cost(method: str, n: int, k: int, n_micro: int = 0, s: int = 0, rounds: int = 8) -> int:
    """Similarity evaluations of a method (M7)."""
    return {"lloyd": rounds * n * k, "microgroup": n * n_micro + n_micro * n_micro // 2 + n * k, "sampleseed": s * s // 2 + rounds * (n - s) * k}[method]


def internal_similarity(vecs: Vectors, assign: DataFrame) -> DataFrame:
    """(cluster_id, internal): squared length of the mean of a cluster's unit vectors."""
    return cluster_rss(vecs, assign).select("cluster_id", "n", (F.col("ls2") / F.col("n") / F.col("n") / float(UNIT * UNIT)).alias("internal"))


def contingency(assign: DataFrame, truth: DataFrame, label: str) -> DataFrame:
    """(cluster_id, label, n)."""
    return assign.join(truth.select("doc_id", F.col(label).alias("label")), "doc_id").groupBy("cluster_id", "label").agg(F.count(F.lit(1)).alias("n"))


def external(assign: DataFrame, truth: DataFrame, label: str) -> dict[str, float]:
    """Purity, normalised mutual information, adjusted Rand index and pairwise F against given labels."""
    table = contingency(assign, truth, label).toPandas().pivot_table(index="cluster_id", columns="label", values="n", fill_value=0).to_numpy(dtype=float)
    n = table.sum()
    if not n:
        return {"purity": 0.0, "nmi": 0.0, "ari": 0.0, "pair_f": 0.0}
    rows, cols = table.sum(axis=1), table.sum(axis=0)
    p = table / n
    with np.errstate(divide="ignore", invalid="ignore"):
        mutual = np.nansum(p * np.log(p / np.outer(rows / n, cols / n)))
    entropy = lambda q: float(-(q[q > 0] * np.log(q[q > 0])).sum())
    both = entropy(rows / n) + entropy(cols / n)
    pairs = lambda x: float((x * (x - 1) / 2).sum())
    together, by_row, by_col, every = pairs(table), pairs(rows), pairs(cols), n * (n - 1) / 2
    expected = by_row * by_col / every if every else 0.0
    top = (by_row + by_col) / 2 - expected
    precision, recall = together / by_row if by_row else 0.0, together / by_col if by_col else 0.0
    return {"purity": float(table.max(axis=1).sum() / n), "nmi": float(2 * mutual / both) if both else 1.0, "ari": (together - expected) / top if top else 1.0, "pair_f": 2 * precision * recall / (precision + recall) if precision + recall else 0.0}


def sizes(assign: DataFrame) -> DataFrame:
    """(cluster_id, n, share_of_mean): sizes and imbalance."""
    n = assign.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    mean = n.agg(F.avg("n").alias("mean"))
    return n.join(F.broadcast(mean)).select("cluster_id", "n", (F.col("n") / F.col("mean")).alias("share_of_mean"))


def silhouette(vecs: Vectors, assign: DataFrame, k: int) -> float:
    """Mean cosine silhouette (M12): a document's mean distance to a cluster follows from the cluster's sums."""
    head, sums = _cluster_sums(vecs, assign)
    matrix = np.zeros((vecs.v, k))
    got = sums.toArrow()
    matrix[got.column("term_id").to_numpy(), got.column("cluster_id").to_numpy()] = got.column("s").to_numpy()
    counts = {r["cluster_id"]: r["n"] for r in head.collect()}
    held = vecs.packed.sparkSession.sparkContext.broadcast(matrix)
    n = np.array([counts.get(c, 0) for c in range(k)], float)

    def run(batches):
        import pyarrow as pa

        from textgroups.operators.assign import nearest_in_batch

        for batch in batches:
            order, dots = nearest_in_batch(batch, held.value, k)
            dense = np.empty_like(dots)
            np.put_along_axis(dense, order, dots, axis=1)
            dense /= UNIT * UNIT
            own = batch.column("cluster_id").to_numpy()
            at = np.arange(len(own))
            sizes_, flat = np.diff(batch.column("idx").offsets.to_numpy()), batch.column("val").flatten().to_numpy().astype(float)
            self_dot = np.bincount(np.repeat(at, sizes_), flat * flat, len(own)) / UNIT / UNIT
            inner = 1 - (dense[at, own] - self_dot) / np.maximum(n[own] - 1, 1)
            outer = np.where(n > 0, 1 - dense / np.maximum(n, 1), np.inf)
            outer[at, own] = np.inf
            b = outer.min(axis=1)
            value = np.where((n[own] > 1) & np.isfinite(b), (b - inner) / np.maximum(np.maximum(inner, b), 1e-12), 0.0)
            yield pa.record_batch([pa.array(value)], names=["s"])

    rows = vecs.packed.join(assign.select("doc_id", "cluster_id"), "doc_id").select("doc_id", "idx", "val", "cluster_id")
    return float(rows.mapInArrow(run, "s double").agg(F.avg("s")).first()[0] or 0.0)


def stability(values: list[float]) -> dict[str, float]:
    """Spread of a measure over seeds (M9)."""
    x = np.asarray(values, float)
    return {"runs": float(len(x)), "mean": float(x.mean()), "std": float(x.std()), "spread_pct": float(100 * (x.max() - x.min()) / x.mean())}
