"""Files shared by the driver and the executors, and size-checked broadcasts."""

from __future__ import annotations

import tempfile
import uuid
import warnings

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Most rows, and most bytes of their values, that a side of a join may have to be broadcast.
BROADCAST_ROWS, BROADCAST_BYTES = 150_000, 24 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in ``spark.checkpoint.dir``; a temporary one only where none is set."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        base = getattr(spark.sparkContext, "_own_checkpoints", None)
        if base is None:
            warnings.warn("spark.checkpoint.dir is not set: tables between steps go to a local folder, which other machines cannot read", stacklevel=2)
            base = spark.sparkContext._own_checkpoints = tempfile.mkdtemp(prefix="graphsplit-")
    return base.rstrip("/")


def spill(df: DataFrame, name: str, **facts: Column) -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it back; this cuts lineage and outlives lost executors.

    ``facts`` are aggregates that are observed while the rows are written, without a second scan; the result has them as ``_observed``.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/graphsplit/{name}-{uuid.uuid4().hex}"
    seen = Observation(f"{name}-{uuid.uuid4().hex}") if facts else None
    if seen:
        df = df.observe(seen, *[v.alias(k) for k, v in facts.items()])
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._spilled_at = path
    out._observed = seen.get if seen else {}
    return out


def release(*frames: DataFrame) -> None:
    """Delete what ``spill`` wrote for frames that no later plan reads."""
    for df in frames:
        path = getattr(df, "_spilled_at", None)
        if path:
            jvm = df.sparkSession._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def modest_batches(spark: SparkSession) -> None:
    """Let Arrow batches of this session end by bytes: a batch of long texts else takes memory beside an executor's heap, several times over, and pools keep it."""
    rows = int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch"))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(min(rows, 2000) if rows > 0 else 2000))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(4 << 20))


def value_bytes(df: DataFrame):
    """A column: about how many bytes a row's values take."""
    total = F.lit(16)
    for f in df.schema.fields:
        c = F.col(f"`{f.name}`")
        if isinstance(f.dataType, T.StringType | T.BinaryType):
            total = total + F.coalesce(F.octet_length(c), F.lit(0)) + 8
        elif isinstance(f.dataType, T.ArrayType):
            total = total + F.greatest(F.coalesce(F.size(c), F.lit(0)), F.lit(0)) * 16 + 8
            if isinstance(f.dataType.elementType, T.StringType | T.BinaryType):
                total = total + F.coalesce(F.aggregate(c, F.lit(0), lambda held, x: held + F.coalesce(F.octet_length(x), F.lit(0))), F.lit(0))
        else:
            total = total + (64 if isinstance(f.dataType, T.StructType | T.MapType) else 8)
    return total


def small(df: DataFrame, rows: int = BROADCAST_ROWS, most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``df`` with a broadcast hint if both its rows and their bytes are few, else unchanged (the join then shuffles).

    One aggregate over ``df`` counts both; so ``df`` should be a written table or cheap to make.
    """
    n, size = df.agg(F.count(F.lit(1)), F.coalesce(F.sum(value_bytes(df)), F.lit(0))).first()
    return F.broadcast(df) if n <= rows and size <= most_bytes else df


def width(spark: SparkSession) -> int:
    """Number of shuffle partitions the session is set up for; bucket counts follow it."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
