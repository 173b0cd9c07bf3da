"""User-defined functions for SQL users (O36): cosine, length, document tokens, CF triples, purity."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def cos_sim(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two arrays; null where one is null or zero."""
    out = []
    for x, y in zip(a, b, strict=True):
        if x is None or y is None:
            out.append(None)
            continue
        x, y = np.asarray(x, float), np.asarray(y, float)
        length = np.sqrt((x @ x) * (y @ y))
        out.append(float(x @ y / length) if length else None)
    return pd.Series(out, dtype=object).astype(float)


@F.pandas_udf(T.DoubleType())
def l2norm(a: pd.Series) -> pd.Series:
    return a.map(lambda x: None if x is None else float(np.sqrt((np.asarray(x, float) ** 2).sum()))).astype(float)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def cf_triple(x: pd.Series) -> list:
    """Count, square sum and linear sum of a group of arrays (DM7), as one array (n, ss, ls...)."""
    m = np.stack([np.asarray(v, float) for v in x]) if len(x) else np.zeros((0, 0))
    return [float(len(m)), float((m * m).sum()), *m.sum(axis=0).tolist()]


@F.pandas_udf(T.DoubleType())
def purity(label: pd.Series) -> float:
    """Share of the commonest label of a group."""
    return float(label.value_counts().iloc[0] / len(label)) if len(label) else 0.0


@F.udtf(returnType=T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("term", T.StringType())]))
class tokenize:
    """Terms of a text, one row each."""

    def eval(self, text: str):
        import regex

        for i, t in enumerate(t for t in regex.split(r"[^\p{L}\p{N}]+", (text or "").lower()) if t):
            yield i, t


def register(spark: SparkSession) -> None:
    """``SELECT cos_sim(a, b)``, ``l2norm(a)``, ``cf_triple(v)``, ``purity(l)`` and ``FROM tokenize(text)``."""
    for name, f in (("cos_sim", cos_sim), ("l2norm", l2norm), ("cf_triple", cf_triple), ("purity", purity)):
        spark.udf.register(name, f)
    spark.udtf.register("tokenize", tokenize)
