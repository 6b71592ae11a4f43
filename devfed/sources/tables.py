"""Reading tables with declared columns, and writing what training leaves behind."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str, columns: Sequence[str] | None = None) -> DataFrame:
    """A Parquet table; only the declared columns are scanned. Zoneless times become timestamps (UTC sessions)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.select(*columns) if columns else df
    zoneless = [f.name for f in df.schema if isinstance(f.dataType, T.TimestampNTZType)]
    return df.withColumns({c: F.col(c).cast("timestamp") for c in zoneless}) if zoneless else df


def csv(spark: SparkSession, path: str, schema: T.StructType | str, sep: str = ";", header: bool = True) -> DataFrame:
    """Delimited text with a declared schema; a malformed row fails the read."""
    return spark.read.schema(schema).csv(path, sep=sep, header=header, mode="FAILFAST")


def json(spark: SparkSession, path: str, schema: T.StructType | str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.orc(path)


def rows(spark: SparkSession, values: list, schema: T.StructType | str) -> DataFrame:
    """A small table of values known to the driver."""
    return spark.createDataFrame(values, schema)


def write_clients(df: DataFrame, path: str, buckets: int = 64, mode: str = "overwrite") -> None:
    """Rows laid out by bucket of clients, so that a few clients can be read alone and files stay bounded in number."""
    bucket = F.pmod(F.hash("client_id"), F.lit(buckets))
    df.withColumn("client_bucket", bucket).repartition("client_bucket").sortWithinPartitions("client_bucket", "client_id").write.mode(mode).partitionBy("client_bucket").parquet(path)


def read_clients(spark: SparkSession, path: str, clients: Sequence[int] | None = None, buckets: int = 64) -> DataFrame:
    """Rows written by write_clients; for some clients only their buckets are read."""
    df = spark.read.parquet(path)
    if clients is not None:
        wanted = spark.createDataFrame([(int(c),) for c in clients], "client_id int").select(F.pmod(F.hash("client_id"), F.lit(buckets))).distinct().collect()
        df = df.where(F.col("client_bucket").isin([r[0] for r in wanted]) & F.col("client_id").isin([int(c) for c in clients]))
    return df.drop("client_bucket")


def append_history(history: DataFrame, path: str) -> None:
    """Rounds appended to a history; one file for each call."""
    history.coalesce(1).write.mode("append").parquet(path)


def last_round(spark: SparkSession, path: str) -> tuple[int, list[float]] | None:
    """Round and vector at which a run can resume, or None if there is no history."""
    try:
        found = spark.read.parquet(path).orderBy(F.desc("round")).select("round", "w").first()
    except Exception as error:  # noqa: BLE001
        if "PATH_NOT_FOUND" in str(error) or "UNABLE_TO_INFER_SCHEMA" in str(error):
            return None
        raise
    return (found["round"], list(found["w"])) if found else None
