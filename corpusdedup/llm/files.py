"""Files of an operator's own format in a folder that every executor reaches.

Tasks write under a temporary name and rename when the file is whole, so a task that
is repeated or that dies half-way leaves either the same complete file or none.
"""

from __future__ import annotations

import os
import uuid

import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a narrow table may be broadcast; at some 100 bytes a row, 10 MB.
SMALL_ROWS = 100_000


def open_folder(uri: str) -> tuple[pafs.FileSystem, str]:
    """The file system and path of a folder's URI: file, hdfs, s3 and what else pyarrow reads."""
    if uri.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    if uri.startswith("/"):
        return pafs.LocalFileSystem(), uri
    return pafs.FileSystem.from_uri(uri)


def make_folder(spark: SparkSession, uri: str) -> None:
    """Create a folder through Spark's own file systems, so that it is there even if no task writes to it."""
    path = spark._jvm.org.apache.hadoop.fs.Path(uri)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).mkdirs(path)


def write_whole(folder: str, name: str, data: bytes) -> str:
    """Write one file; returns its URI."""
    fs, path = open_folder(folder)
    fs.create_dir(path, recursive=True)
    part = f"{path}/.{name}.{uuid.uuid4().hex}"
    with fs.open_output_stream(part) as out:
        out.write(data)
    if isinstance(fs, pafs.LocalFileSystem):
        os.replace(part, f"{path}/{name}")
    else:
        fs.move(part, f"{path}/{name}")
    return f"{folder.rstrip('/')}/{name}"


def small(df: DataFrame, rows: int = SMALL_ROWS) -> DataFrame:
    """A staged narrow table, marked for broadcast if it is counted to be small; else Spark shuffles."""
    return F.broadcast(df) if df.count() <= rows else df
