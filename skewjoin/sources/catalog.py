"""Tables in, tables out: thin wrappers that keep pruning and pushdown to Spark."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table, lazily; column pruning and filters reach the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    """Temporary views, so that SQL users can name the tables."""
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, path: str, kind: str = "parquet", schema=None, **options) -> DataFrame:
    """parquet, orc, csv or json; text formats want a schema, so that no pass infers one."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError("give a schema: inferring one reads the input twice")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def save(df: DataFrame, path: str, kind: str = "parquet", mode: str = "overwrite", partition_by: tuple[str, ...] = ()) -> None:
    writer = df.write.format(kind).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir.  Where it is unset, a local session gets a
    temporary folder; on a cluster no folder of one machine would do, so that is an error."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not path:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="skewjoin-shared-"))
        path = spark.sparkContext.getCheckpointDir()
    return path.rstrip("/")


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write df once to the shared folder and read it back."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def text_bytes(df: DataFrame) -> int:
    """Bytes of all values of df as text, and 16 for each value: a measured size, by one aggregation of df."""
    quoted = ["`" + c.replace("`", "``") + "`" for c in dict.fromkeys(df.columns)]
    values = [F.coalesce(F.octet_length(F.to_json(F.struct(F.col(c)))), F.lit(0)) for c in quoted]
    total = sum((v.cast("long") for v in values), F.lit(16 * len(df.columns)).cast("long"))
    return df.agg(F.sum(total)).first()[0] or 0


def observed(df: DataFrame, **measures: Column) -> tuple[DataFrame, Observation]:
    """df, and aggregates of the rows that pass through it, known once an action has run: counts without a job of their own."""
    seen = Observation(f"seen-{uuid.uuid4().hex}")
    return df.observe(seen, *[c.alias(name) for name, c in measures.items()]), seen


def input_files(df: DataFrame) -> list[str]:
    """The files that df reads, as its readers know them."""
    return sorted(df.inputFiles())


def consume(df: DataFrame) -> None:
    """Run df to the end without keeping its rows: the timing sink."""
    df.write.format("noop").mode("overwrite").save()
