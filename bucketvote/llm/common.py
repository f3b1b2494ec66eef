"""Shared folder, written tables, file access and column helpers of the training-data operators."""

from __future__ import annotations

import atexit
import ctypes
import functools
import getpass
import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space as the operators' contracts define it.
WHITE = " \t\n\x0b\x0c\r"


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir; set here only where the cluster names none (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        set_dir = spark.sparkContext._jsc.sc().getCheckpointDir()
        if set_dir.isDefined():
            return set_dir.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + os.path.join(tempfile.gettempdir(), f"bucketvote-shared-{getpass.getuser()}")
        spark.sparkContext.setCheckpointDir(root)
    return root


def run_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder under the shared root, deleted when the driver's Python ends."""
    path = f"{shared_root(spark).rstrip('/')}/bucketvote/{name}-{uuid.uuid4().hex}"
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    fs.mkdirs(hadoop)

    def drop() -> None:
        try:
            fs.delete(hadoop, True)
        except Exception:  # the JVM may have ended before
            pass

    atexit.register(drop)
    return str(fs.makeQualified(hadoop).toString())


def written(df: DataFrame, name: str, codec: str | None = None) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts lineage and survives lost executors."""
    path = run_folder(df.sparkSession, name) + "/table"
    (df.write.option("compression", codec) if codec else df.write).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def file_system(uri: str):
    """(pyarrow file system, path inside it) of a URI; works on executors for file:, hdfs: and s3:."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def give_back() -> None:
    """Returns to the system what Arrow's pool and the C library hold unused: a worker waits for its next task with little memory."""
    import pyarrow

    pyarrow.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim:
        trim(0)


def lean(task):
    """A task over frames that gives unused memory back after each of them."""

    @functools.wraps(task)
    def run(frames):
        try:
            for out in task(frames):
                yield out
                give_back()
        finally:
            give_back()

    return run


def new_file(folder: str, stem: str) -> str:
    """A file name no other task attempt uses; only files named in a committed manifest count."""
    from pyspark import TaskContext

    context = TaskContext.get()
    part = context.partitionId() if context else 0
    return f"{folder}/{stem}-{part:06d}-{uuid.uuid4().hex}"


#: Stands for a null id inside Python, where a null would turn whole numbers into floats.
NO_ID = -(1 << 63)


def id_in(name: str) -> Column:
    return F.coalesce(F.col(name), F.lit(NO_ID)).alias(name)


def id_out(df: DataFrame, name: str) -> DataFrame:
    return df.withColumn(name, F.when(F.col(name) != NO_ID, F.col(name)))


def held_out(doc_id: Column) -> Column:
    """Documents whose crc32 of the id as text leaves remainder 2 by 4 are never learned from; a null id is not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def bounded_sample(df: DataFrame, key: Column, bound: int, seed: int) -> DataFrame:
    """About bound rows, at most twice that, chosen by a hash of the key: the same rows in every run."""
    total = df.count()
    if total <= bound:
        return df
    scale = 1 << 30
    return df.where(F.pmod(F.xxhash64(F.lit(seed), key), F.lit(scale)) < int(scale * bound / total)).limit(2 * bound)


#: Shares of all rows at which a key counts as hot: no more keys than this can.
HOT_KEYS = 4096


def with_facts(rows: DataFrame, facts: DataFrame, *key: str, count: str = "n", least: int = 10_000) -> DataFrame:
    """rows left-joined with facts (one row a key, `count` rows of it). Hot keys are not dealt to one task each.

    Keys with a HOT_KEYS-th of all counted rows are HOT_KEYS at most, whatever the data: they are broadcast, and only
    rows of other keys are shuffled. rows is read twice and should be a table.
    """
    total = facts.agg(F.sum(count)).first()[0] or 0
    many = F.col(count) >= max(least, -(-int(total) // HOT_KEYS))
    common, rare = F.broadcast(facts.where(many)), facts.where(~many)
    keys = list(key)
    if total < least:
        return rows.join(rare, keys, "left")
    return rows.join(common, keys).unionByName(rows.join(common.select(*keys), keys, "left_anti").join(rare, keys, "left"))
