"""Shared helpers of the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space of the word contracts: space and \t \n \v \f \r.
SPACE_CLASS = r"[\x20\x09-\x0D]"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder the cluster names; fall back to a private one only in local mode."""
    sc = spark.sparkContext
    if sc.getCheckpointDir():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = tempfile.mkdtemp(prefix="phraseloom-checkpoint-")
    sc.setCheckpointDir(named)


def durable(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder, so that losing executors never replays what came before."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


class Scratch:
    """Written tables in the shared checkpoint folder, dropped one by one as soon as they have served."""

    def __init__(self, spark: SparkSession) -> None:
        ensure_checkpoint_dir(spark)
        self.spark, self.paths = spark, {}
        self.folder = f"{spark.sparkContext.getCheckpointDir()}/scratch-{uuid.uuid4().hex}"

    def keep(self, df: DataFrame) -> DataFrame:
        path = f"{self.folder}/{len(self.paths)}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = (path, out)
        return out

    def drop(self, *tables: DataFrame) -> None:
        for df in tables:
            folder = self.spark._jvm.org.apache.hadoop.fs.Path(self.paths[id(df)][0])
            folder.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(folder, True)


def drop_finished_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner remove the shuffle files of jobs whose results are checkpointed; it acts on collected garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def release_memory() -> None:
    """Give freed buffers back to the system: Python workers live on between stages, beside the executor's heap."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def tidy(batches: Iterator) -> Iterator:
    """Pass batches on and release memory at their end."""
    try:
        yield from batches
    finally:
        release_memory()


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once and use it many times inside ``body`` (a lambda variable is never inlined)."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


#: Bits of the fixed-size sets that tell which rows of a scan may be wanted.
FILTER_BITS = 23


def bit_set(hashes: DataFrame) -> Column:
    """A scalar bit set of a fixed size over the only (long) column of ``hashes``; false positives only."""
    slots = hashes.select(F.pmod(F.col(hashes.columns[0]), F.lit(1 << FILTER_BITS)).alias("slot"))
    words = slots.select(F.expr("slot div 64").alias("id"), F.expr("shiftleft(1L, cast(slot % 64 as int))").alias("bits"))
    none = hashes.sparkSession.range(1 << (FILTER_BITS - 6)).select("id", F.lit(0).cast("long").alias("bits"))
    every = words.unionByName(none).groupBy("id").agg(F.expr("bit_or(bits)").alias("bits"))
    return durable(every.agg(F.transform(F.array_sort(F.collect_list(F.struct("id", "bits"))), lambda e: e["bits"]).alias("bits"))).scalar()


def is_lit(bits: Column, value: Column) -> Column:
    slot = F.pmod(value, F.lit(1 << FILTER_BITS))
    word = F.get(bits, (slot / 64).cast("int"))
    return F.call_function("shiftrightunsigned", word, F.pmod(slot, F.lit(64)).cast("int")).bitwiseAND(F.lit(1).cast("long")) == 1


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def word_array(text: Column) -> Column:
    """Maximal runs of characters other than ASCII white space."""
    return F.filter(F.split(text, SPACE_CLASS + "+"), lambda w: w != "")
