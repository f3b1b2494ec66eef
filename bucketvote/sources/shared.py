"""Tables written to the folder that driver and executors share."""

from __future__ import annotations

import getpass
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh path under spark.checkpoint.dir; under the temporary folder only where the session names none (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        named = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not named.isDefined() and not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = named.get() if named.isDefined() else "file://" + os.path.join(tempfile.gettempdir(), f"bucketvote-shared-{getpass.getuser()}")
    return f"{root.rstrip('/')}/bucketvote-engine/{name}-{uuid.uuid4().hex}"


def opened(uri: str):
    """(pyarrow file system, path inside it) of a URI of the shared folder; works on executors."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def dropped(uri: str) -> None:
    """Deletes a folder that `shared_folder` named, once nothing reads it any more."""
    if "/bucketvote-engine/" not in uri:
        raise ValueError(uri)
    fs, inside = opened(uri)
    fs.delete_dir(inside)


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written once and read back: cuts lineage, and later plans start from files."""
    path = shared_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def reachable(spark: SparkSession) -> None:
    """Lets checkpoint() work where the session has no folder for it yet."""
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(shared_folder(spark, "checkpoints"))
