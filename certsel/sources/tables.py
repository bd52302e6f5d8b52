"""Tables in, scored tables and ledgers out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from certsel.spec import GRID

BANDS = 100


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text with a stated schema, which is never inferred."""
    reader = spark.read.schema(schema)
    return reader.option("header", "true").csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def require_unique(df: DataFrame, key: str) -> DataFrame:
    """Sampling is keyed, so a repeated or null key is an error."""
    bad = df.groupBy(key).count().where((F.col("count") > 1) | F.col(key).isNull()).limit(1).collect()
    if bad:
        raise ValueError(f"key {key} is null or repeated: {bad[0][key]!r}")
    return df


def save_scored(scored: DataFrame, path: str, score: str = "score_u") -> None:
    """Write a scored table clustered by score: one folder per band, sorted within files, so that a cut-off reads few row groups."""
    band = F.least(F.lit(BANDS - 1), F.floor(F.col(score) * BANDS / GRID)).cast("int")
    (scored.withColumn("score_band", band).repartitionByRange("score_band", F.col(score)).sortWithinPartitions(F.desc(score))
     .write.partitionBy("score_band").mode("overwrite").parquet(path))


def read_above(spark: SparkSession, path: str, tau_u: int, score: str = "score_u") -> DataFrame:
    """Rows of a saved scored table at or above tau: bands are pruned and the rest is pushed to the scan."""
    return spark.read.parquet(path).where((F.col("score_band") >= min(BANDS - 1, tau_u * BANDS // GRID)) & (F.col(score) >= tau_u)).drop("score_band")


def read_ledger(spark: SparkSession, path: str, key_type) -> DataFrame:
    """(key, y) bought so far; no rows where there is no ledger yet."""
    schema = StructType([StructField("key", key_type), StructField("y", IntegerType())])
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p):
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).parquet(path)


def save_ledger(labels: DataFrame, path: str) -> None:
    """Append bought labels (key, y); a later run reads them before it asks again."""
    labels.select("key", F.coalesce("y", F.lit(0)).cast("int").alias("y")).write.mode("append").parquet(path)
