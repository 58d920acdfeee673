"""Reading, writing and registering the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
REQUIRED = {
    "orders": ("o_orderkey",),
    "lineitem": ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_quantity"),
    "part": ("p_partkey", "p_name", "p_brand", "p_type", "p_size"),
    "embeddings": ("vec_id", "embedding"),
    "documents": ("doc_id", "text"),
    "benchmark": ("item_id", "text"),
    "labels": ("doc_id", "quality", "toxic"),
    "conversations": ("conv_id", "turn", "role", "text"),
    "pages": ("page_id", "url", "html"),
    "events": ("event_id", "ts", "user_id", "event_type", "value", "props"),
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table; missing columns fail at once."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if missing := set(REQUIRED.get(name, ())) - set(df.columns):
        raise ValueError(f"{name} lacks {sorted(missing)}")
    return df


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        read_table(spark, sf_dir, name).createOrReplaceTempView(name)


def read_answers(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = "model string, variant_id string, item_id string, raw string") -> DataFrame:
    """An external table of model answers: parquet, orc, json or csv."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).format(fmt).load(path)


def write_variants(df: DataFrame, path: str, by: tuple[str, ...] = ("variant_id",)) -> None:
    """Partitioned by variant; a rerun replaces the partitions that it writes and no others."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*by).parquet(path)
