"""What the text operators share: scratch tables, Arrow batches, column checks."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables; only Spark touches the path."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


#: Rows of (id, text key) that are broadcast, at most: 50 bytes each as a hashed relation.
MAX_BROADCAST = 500_000


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares. Only a local master, whose executors are the driver, gets a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and the executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="relstrata-"))
        base = spark.sparkContext.getCheckpointDir()
    return base


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/relstrata/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet into the shared folder and read it back.

    A lost executor then costs a re-read and never the upstream work.
    """
    spark = df.sparkSession
    schema = df.schema
    path = scratch_path(spark, name)
    df.write.mode("error").parquet(path)
    del df  # the plan, and with it its shuffle files, must be unreachable when they are released
    release(spark)
    return spark.read.schema(schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Let Spark delete shuffle files of plans that nothing refers to any more, instead of at some later collection.

    A hint only: where the session has no JVM of its own, Spark's cleaner works when it does.
    """
    jvm = getattr(spark.sparkContext, "_jvm", None)
    for _ in range(2 if jvm else 0):  # the listener bus holds the last job a little longer
        gc.collect()
        jvm.System.gc()
        time.sleep(0.2)


def keyed(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Only the two columns that matter, under fixed names, so extra columns can't clash."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def text_key(text_col: str = "text") -> Column:
    """A hash that tells apart the texts of rows which share an id."""
    return F.xxhash64(F.col(text_col).cast("string"))


def without(docs: DataFrame, gone: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` less the rows named in ``gone`` (doc_id, text_key), a written table; null ids are compared like any other.

    Texts stay where they are while the narrow side is small enough to be sent to them, else both meet by key.
    """
    side = gone.select(F.col("doc_id").alias("_gone_id"), F.col("text_key").alias("_gone_key")).distinct()
    few = gone.limit(MAX_BROADCAST + 1).count() <= MAX_BROADCAST
    same = F.col(id_col).cast("long").eqNullSafe(F.col("_gone_id")) & (text_key(text_col) == F.col("_gone_key"))
    return docs.join(F.broadcast(side) if few else side, same, "left_anti")


def slices(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """Smaller Arrow batches: bounds what a worker holds when texts are long."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def with_fields(df: DataFrame, fields: str) -> T.StructType:
    """The schema of ``df`` with further fields; ``df.schema`` itself stays as it is."""
    return T.StructType([*df.schema.fields, *T._parse_datatype_string(fields).fields])


def hash_sample(df: DataFrame, key: Column, size: int, seed: int, total: int) -> DataFrame:
    """The ``size`` rows of the smallest hashes, of ``total``; about twice that many are moved, whatever the input."""
    span = 1 << 40
    h = F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(span))
    bound = span if total <= 2 * size else span * 2 * size // total
    return df.withColumn("_hash", h).where(F.col("_hash") < bound).orderBy("_hash", key).limit(size).drop("_hash")
