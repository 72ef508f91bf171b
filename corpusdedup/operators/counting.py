"""Global frequencies of chunks."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KEY = ["h", "norm_len"]


def count_groups(occ: DataFrame) -> DataFrame:
    """(h, norm_len, freq): occurrences of each normalised text, summed before the shuffle."""
    return occ.groupBy(*KEY).agg(F.count("*").alias("freq"))


def count_groups_with_docs(occ: DataFrame) -> DataFrame:
    """(h, norm_len, freq, n_docs): also in how many documents, from the counts by document."""
    return group_doc_counts(occ).groupBy(*KEY).agg(F.sum("copies").alias("freq"), F.count("*").alias("n_docs"))


def duplicate_groups(groups: DataFrame, min_freq: int = 2) -> DataFrame:
    return groups.where(F.col("freq") >= min_freq)


def group_doc_counts(occ: DataFrame) -> DataFrame:
    """(h, norm_len, doc_id, copies)."""
    return occ.groupBy(*KEY, "doc_id").agg(F.count("*").alias("copies"))


def merge_counts(old: DataFrame, new: DataFrame) -> DataFrame:
    """Counts of two batches of documents as one."""
    return old.unionByName(new).groupBy(*KEY).agg(F.sum("freq").alias("freq"))


def heavy_hitters(occ: DataFrame, share: float = 0.001, room: int = 20_000) -> DataFrame:
    """(h, norm_len, freq) of all groups that hold at least ``share`` of the occurrences.

    A sketch of ``room`` counters in each task keeps every text of more than 1/room of the
    rows, so it names all heavy groups and some others; a second pass over the narrow rows
    counts just these. No group table is made. ``room`` must be above 1/share.
    """
    if room * share <= 1:
        raise ValueError("room must be above 1 / share")
    total = occ.count()
    named = occ.agg(F.expr(f"approx_top_k(hex(h), {math.ceil(1 / share)}, {room})").alias("top")).select(F.explode("top").alias("t")).select(F.unhex("t.item").alias("h"))
    counted = occ.join(F.broadcast(named.distinct()), "h", "left_semi").groupBy(*KEY).agg(F.count("*").alias("freq"))
    return counted.where(F.col("freq") >= share * total)


def approx_group_count(occ: DataFrame, rsd: float = 0.02) -> DataFrame:
    """An estimate of the number of groups and the exact number of occurrences, in one pass."""
    return occ.agg(F.approx_count_distinct(F.struct(*KEY), rsd).alias("approx_groups"), F.count("*").alias("occurrences"))
