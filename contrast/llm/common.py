"""What several operators of this subpackage share."""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The ASCII white space that separates words: tab, line feed, vertical tab, form feed, carriage return.
BREAKS = ("\t", "\n", "\x0b", "\x0c", "\r")


def give_back() -> None:
    """Returns a worker's free memory to the machine: workers wait for further tasks beside the JVM.

    What the C library has no such call for keeps its memory.
    """
    pa.default_memory_pool().release_unused()
    try:
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD: arrays from a megabyte on go back as soon as they are freed
        libc.malloc_trim(0)
    except (OSError, AttributeError):
        pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or the context's checkpoint folder.

    On one machine the warehouse's folder will do; a cluster without a shared folder is an error.
    """
    sc = spark.sparkContext
    known = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if known is None:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        known = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/contrast-scratch"
    return known


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder, deleted when the session's JVM ends."""
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    jvm_path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return path


def materialise(df: DataFrame, name: str) -> DataFrame:
    """The same rows as a table in the shared folder: computed once, and safe from lost executors."""
    df.write.parquet(path := scratch_path(df.sparkSession, name))
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spaced(text: Column) -> Column:
    """The text with a space for each ASCII break; null becomes empty."""
    out = F.coalesce(text, F.lit(""))
    for c in BREAKS:
        out = F.replace(out, F.lit(c), F.lit(" "))
    return out


def words(text: Column) -> Column:
    """Maximal runs of characters other than ASCII white space, in order."""
    return F.array_remove(F.split(spaced(text), " "), "")


def bind(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), where the value is computed once however often the body names it."""
    return F.transform(F.array(value), body)[0]


def crc_remainder(doc_id: Column, modulus: int) -> Column:
    """crc32 of the id's decimal text modulo a number; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(modulus))
