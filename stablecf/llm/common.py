"""Session helpers shared by the operators: shared folder, staged tables, chunks of documents."""

from __future__ import annotations

import gc
import math
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.sources.session import ship  # noqa: F401  (the operators take it from here)

#: No stored id: null ids take part as this value, the largest, and come back as null.
NO_ID = (1 << 63) - 1
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a temporary one only where the session names none and runs on one machine (tests)."""
    d = spark.conf.get("spark.checkpoint.dir", None)
    if not d:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            return found.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        d = tempfile.mkdtemp(prefix="stablecf-shared-")
        spark.sparkContext.setCheckpointDir(d)
        return spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return d


def staged(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the shared folder and read back: lineage ends there, and a lost executor costs a re-read."""
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    schema = df.schema
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(schema).parquet(path)
    del df
    gc.collect()
    spark.sparkContext._jvm.System.gc()  # lets Spark's cleaner drop the shuffle files of the finished job
    return out


def ids_and_texts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id long not null, text string not null): nothing else of the input is read, so clashing names can't matter."""
    return df.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def id_back(c: str = "doc_id") -> Column:
    return F.when(F.col(c) != NO_ID, F.col(c)).alias(c)


def ascii_lower(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def text_bytes(df: DataFrame) -> int:
    return int(df.agg(F.sum(F.octet_length("text")).alias("b")).first()[0] or 0)


def chunked(spark: SparkSession, docs: DataFrame, chunk_bytes: int = 4 << 20, total: int | None = None) -> tuple[DataFrame, int, int]:
    """Documents dealt at random, but reproducibly, into chunks of about ``chunk_bytes``: (chunk, doc_id, text), number of chunks, total bytes.

    The dealing hashes id and length, so neither a hot source nor repeated ids can make one chunk heavy.
    """
    total = text_bytes(docs) if total is None else total
    n = max(1, math.ceil(total / chunk_bytes))
    c = F.pmod(F.xxhash64("doc_id", F.octet_length("text")), F.lit(n)).cast("int").alias("chunk")
    return docs.select(c, "doc_id", "text").repartition(partitions(spark), "chunk"), n, total
