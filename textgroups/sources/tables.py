"""Reading and writing (O1-O4), schemas and enlargement."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_L, _S, _D, _I, _N = T.LongType(), T.StringType(), T.DoubleType(), T.IntegerType(), T.TimestampNTZType()
#: Columns of the given tables.
SCHEMAS = {
    name: T.StructType([T.StructField(c, t) for c, t in columns])
    for name, columns in {
        "documents": [("doc_id", _L), ("text", _S), ("lang", _S), ("source", _S), ("n_chars", _L)],
        "embeddings": [("vec_id", _L), ("embedding", T.ArrayType(T.FloatType())), ("label", _I)],
        "pages": [("page_id", _L), ("url", _S), ("html", _S)],
        "conversations": [("conv_id", _L), ("turn", _L), ("role", _S), ("text", _S)],
        "benchmark": [("item_id", _L), ("text", _S)],
        "labels": [("doc_id", _L), ("quality", _I), ("toxic", _I)],
        "events": [("event_id", _L), ("ts", _N), ("user_id", _L), ("event_type", _S), ("value", _D), ("props", _S)],
        "lineitem": [("l_orderkey", _L), ("l_partkey", _L), ("l_suppkey", _L), ("l_linenumber", _I), ("l_quantity", _D), ("l_extendedprice", _D), ("l_discount", _D), ("l_tax", _D), ("l_returnflag", _S), ("l_linestatus", _S), ("l_shipdate", _N)],
        "orders": [("o_orderkey", _L), ("o_custkey", _L), ("o_orderstatus", _S), ("o_totalprice", _D), ("o_orderdate", _N), ("o_orderpriority", _S)],
        "customer": [("c_custkey", _L), ("c_name", _S), ("c_nationkey", _I), ("c_acctbal", _D), ("c_mktsegment", _S)],
        "part": [("p_partkey", _L), ("p_name", _S), ("p_brand", _S), ("p_type", _S), ("p_size", _I), ("p_retailprice", _D)],
        "supplier": [("s_suppkey", _L), ("s_name", _S), ("s_nationkey", _I), ("s_acctbal", _D)],
        "nation": [("n_nationkey", _I), ("n_name", _S), ("n_regionkey", _I)],
        "region": [("r_regionkey", _I), ("r_name", _S)],
    }.items()
}


def require_schema(df: DataFrame, schema: T.StructType) -> DataFrame:
    """The columns of ``schema``; a missing one or another type is an error."""
    have = {f.name: f.dataType for f in df.schema.fields}
    wrong = [f"{f.name} {f.dataType.simpleString()}" for f in schema.fields if f.name not in have or have[f.name] != f.dataType]
    if wrong:
        raise ValueError("missing or of another type: " + ", ".join(wrong))
    return df.select(*[f.name for f in schema.fields])


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables (O1); its Parquet schema is taken as it is, columns are pruned by the plan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_text(spark: SparkSession, path: str) -> DataFrame:
    """(value) lines of text files (O2)."""
    return spark.read.text(path)


def load_csv(spark: SparkSession, path: str, schema: T.StructType, header: bool = True) -> DataFrame:
    """CSV with a schema (O2); a broken record is kept in ``_corrupt``."""
    wide = T.StructType([*schema.fields, T.StructField("_corrupt", _S)])
    return spark.read.schema(wide).option("header", header).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").csv(path)


def load_jsonl(spark: SparkSession, path: str, schema: T.StructType) -> DataFrame:
    """JSON lines with a schema (O2); a broken record is kept in ``_corrupt``."""
    wide = T.StructType([*schema.fields, T.StructField("_corrupt", _S)])
    return spark.read.schema(wide).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").json(path)


def save(df: DataFrame, path: str, partition_by: list[str] | None = None, fmt: str = "parquet", mode: str = "overwrite") -> None:
    """Labels, centres or micro-clusters as Parquet, JSON lines or CSV (O3)."""
    df.write.mode(mode).format(fmt).partitionBy(*(partition_by or [])).save(path)


def save_model(centers: DataFrame, info: dict, path: str) -> None:
    """Centres (Parquet) with their description (one JSON line)."""
    centers.write.mode("overwrite").parquet(f"{path}/centers")
    centers.sparkSession.createDataFrame([(json.dumps(info, default=str),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/info")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/centers"), json.loads(spark.read.text(f"{path}/info").first()[0])


def replicate(df: DataFrame, factor: float, id_col: str = "doc_id") -> DataFrame:
    """The collection multiplied (DM14, O40): ids of copy c are shifted by c times (largest id + 1); a fraction of the
    last copy is drawn by a hash of the id."""
    step = (df.agg(F.max(id_col)).first()[0] or 0) + 1
    whole = int(factor)
    copies = df.withColumn("_c", F.explode(F.sequence(F.lit(0), F.lit(whole)))).filter((F.col("_c") < whole) | (F.pmod(F.xxhash64(id_col), F.lit(1_000_000)) < (factor - whole) * 1_000_000))
    return copies.withColumn(id_col, F.col(id_col) + F.col("_c") * F.lit(step)).drop("_c")
