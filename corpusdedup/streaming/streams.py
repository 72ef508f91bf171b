"""Structured Streaming extensions; the method itself is a batch method.

Streaming counts end equal to batch counts. Admission under a budget does not: a
budget depends on the final frequency, so what a stream admits is another policy.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.retention import RetentionPolicy
from ..functions.text import chunks_of, content_hash, normalize_text
from ..session import fresh_path, shuffle_partitions


def occurrences_stream(stream: DataFrame, tau_seg: int = 32) -> DataFrame:
    """Narrow occurrences of a stream of (doc_id, text)."""
    x = stream.select("doc_id", F.posexplode_outer(chunks_of(F.col("text"), tau_seg)).alias("pos", "chunk")).where("pos is not null")
    norm = normalize_text(F.col("chunk"))
    return x.select("doc_id", "pos", content_hash(norm).alias("h"), F.length(norm).alias("norm_len"), F.length("chunk").alias("raw_len"))


def read_documents(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def _drain(query) -> None:
    query.awaitTermination()
    if query.exception() is not None:
        raise query.exception()


def stream_counts(stream: DataFrame, old: DataFrame | None = None) -> DataFrame:
    """Counts of everything that has arrived: each micro-batch appends its own partial counts to a table.

    No state grows without bound in a task; reading the table sums the parts. A batch
    that is replayed overwrites its own part, so counts stay exact.
    """
    spark = stream.sparkSession
    path = fresh_path(spark, "stream-counts")

    def add(batch: DataFrame, number: int) -> None:
        batch.groupBy("h", "norm_len").agg(F.count("*").alias("freq")).write.mode("overwrite").parquet(f"{path}/batch={number}")

    _drain(occurrences_stream(stream).writeStream.foreachBatch(add).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).start())
    parts = spark.read.parquet(path).select("h", "norm_len", "freq")
    return (parts if old is None else parts.unionByName(old)).groupBy("h", "norm_len").agg(F.sum("freq").alias("freq"))


def admit_copies(seen: int, kept: int, copies: int, length: int, n: float, full_length: float) -> tuple[int, int]:
    """Copies seen and admitted after ``copies`` more of one group.

    A copy is admitted while fewer are than the budget of the frequency seen so far. That
    budget falls once n copies are seen, so a group that is full then stays so.
    """
    q, a = 1 - 1 / n, max(0.0, 1 - length / full_length)
    for seen in range(seen + 1, seen + copies + 1):  # noqa: B020
        allowed = max(1, min(seen, math.ceil(1 + (seen * q ** (seen - 1) - 1) * a)))
        if kept < allowed:
            kept += 1
        elif seen > n:
            break
    return seen, kept


def stream_admit(stream: DataFrame, policy: RetentionPolicy | None = None) -> DataFrame:
    """Copies seen and admitted so far by group, with state of two numbers a key.

    The state is a table to which a batch appends the new numbers of the groups it holds;
    they follow from the last ones and the batch's count, which is a partial aggregate, so a
    frequent text is a few rows. A batch that is replayed overwrites its own part and reads
    those before it. Rows pass through Python in batches, not a call a group.
    """
    policy = policy or RetentionPolicy()
    n, full = policy.n, policy.full_length
    kind = "h binary, norm_len int, seen long, kept long"

    def admit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        once = functools.lru_cache(100_000)(admit_copies)  # most groups have few copies and share their numbers
        for batch in batches:
            h, length, seen, kept, copies = batch.columns
            seen, copies = seen.to_pylist(), copies.to_pylist()
            new = [once(s, k, c, x, n, full)[1] for s, k, c, x in zip(seen, kept.to_pylist(), copies, length.to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([h, length, pa.array([s + c for s, c in zip(seen, copies, strict=True)], pa.int64()), pa.array(new, pa.int64())], names=["h", "norm_len", "seen", "kept"])

    spark = stream.sparkSession
    path = fresh_path(spark, "stream-admitted")

    def state(before: int | None = None) -> DataFrame:
        parts = spark.read.schema(kind + ", batch long").parquet(path)
        parts = parts if before is None else parts.where(F.col("batch") < before)
        return parts.groupBy("h", "norm_len").agg(F.max("seen").alias("seen"), F.max("kept").alias("kept"))

    def add(batch: DataFrame, number: int) -> None:
        counts = batch.groupBy("h", "norm_len").agg(F.count("*").alias("copies"))
        zero = lambda c: F.coalesce(c, F.lit(0).cast("long")).alias(c)
        if number:
            counts = counts.join(state(number), ["h", "norm_len"], "left").select("h", "norm_len", zero("seen"), zero("kept"), "copies")
        else:
            counts = counts.select("h", "norm_len", F.lit(0).cast("long").alias("seen"), F.lit(0).cast("long").alias("kept"), "copies")
        counts.mapInArrow(admit, kind).write.mode("overwrite").parquet(f"{path}/batch={number}")

    spark.createDataFrame([], kind).write.parquet(f"{path}/batch=-1")  # a stream without a row has a state too
    # a batch of one file would be cut into chunks by one task
    dealt = stream.repartition(shuffle_partitions(spark))
    _drain(occurrences_stream(dealt).select("h", "norm_len").writeStream.foreachBatch(add).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).start())
    return state().select(F.lower(F.hex("h")).alias("h"), "seen", F.col("kept").alias("admitted"))


def stream_doc_dedup(stream: DataFrame, time_col: str = "arrived", within: str = "1 hour") -> DataFrame:
    """The stream without texts that came before within the watermark; later copies come through.

    A row whose time is not after the watermark is late and dropped, also where it is at
    the epoch, at which the watermark starts; null texts are one text.
    """
    return stream.withColumn("text_md5", F.md5("text")).withWatermark(time_col, within).dropDuplicatesWithinWatermark(["text_md5"])


def stream_static(stream: DataFrame, groups: DataFrame) -> DataFrame:
    """New documents' chunks with the frequencies of a frozen group table."""
    return occurrences_stream(stream).join(groups, ["h", "norm_len"], "left")


def run_to_table(stream: DataFrame, name: str) -> DataFrame:
    """Drain what is available into a table of the shared folder."""
    spark = stream.sparkSession
    path = fresh_path(spark, name)
    _drain(stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).start())
    return spark.read.schema(stream.schema).parquet(path)


def register_segment_udtf(spark: SparkSession, name: str = "segment_text") -> None:
    """``segment_text(text, tau)`` → (pos, text, kind), fences kept whole."""
    from pyspark.sql.functions import udtf

    from ..functions.text import KINDS
    from ..operators.segment import cut_with_spans, protected_spans

    class SegmentText:
        def eval(self, text: str, tau: int):
            if text:
                for k, c in enumerate(cut_with_spans(text, protected_spans(text), tau, KINDS)):
                    yield k, c["text"], c["kind"]

    spark.udtf.register(name, udtf(SegmentText, returnType="pos int, text string, kind string"))
