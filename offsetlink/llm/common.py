"""What the training-data operators share: shared folders, tables, word and hash helpers."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid

import numpy as np
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TOKENIZER_DIR = "/opt/tokenizers"
SEED = 20240607


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``); a temporary one only where it is unset and there is one machine."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not at:
        known = sc._jsc.sc().getCheckpointDir()
        if known.isDefined():
            at = known.get()
        elif not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        else:
            own = tempfile.mkdtemp(prefix="offsetlink-")
            atexit.register(shutil.rmtree, own, ignore_errors=True)
            at = f"file://{own}"
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(at)
    return at.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read again: ends the lineage and survives lost executors."""
    path = new_folder(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.cut_path = path
    return out


def drop(*tables: DataFrame) -> None:
    """Delete what cut() wrote, once nothing that is still to be computed reads it."""
    for t in tables:
        remove(t.sparkSession, t.cut_path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared store."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def share(spark: SparkSession, value):
    """A broadcast of any value, with its classes by value; loads() of what it holds gives the value."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(value))


def bound_batches(spark: SparkSession) -> None:
    """Arrow batches of whole texts: bounded in rows and bytes, as long texts would make 10,000 rows very large."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "400")
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "2m")


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def fold(column: Column, n: int) -> Column:
    """crc32 of the id as text, modulo n; a null id falls in no fold (null)."""
    return F.crc32(column.cast("string").cast("binary")) % F.lit(n)


def tokenizer_file(name: str, folder: str = TOKENIZER_DIR) -> bytes:
    with open(os.path.join(folder, name), "rb") as f:
        return f.read()


def mix64(x: np.ndarray) -> np.ndarray:
    """A well-mixing bijection of uint64 arrays."""
    x = x.astype(np.uint64, copy=True)
    with np.errstate(over="ignore"):
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return x


def words(text: str | None) -> list[bytes]:
    """A-Z in lower case, then the runs without ASCII white space (0x20, 0x09-0x0D); null has none."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []
