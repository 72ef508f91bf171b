"""The compared settings as whole pipelines; each returns documents."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.retention import KeepK, KeepOne, RetentionPolicy
from ..functions.text import KINDS
from ..operators.counting import KEY, count_groups
from ..operators.deletion import candidate_runs, coherent_delete, first_places, initial_decision, past, rebuild
from ..operators.documents import minhash_dedup
from ..operators.segment import occurrences, segment
from ..operators.substring import assign_shard, remove_spans, suffix_array_spans, winnowed_spans
from ..session import stage
from ..sources.io import assert_unique_ids


def no_dedup(docs: DataFrame) -> DataFrame:
    return docs


def occurrence_table(docs: DataFrame, tau_seg: int = 32, kinds: tuple[str, ...] = KINDS, **options) -> DataFrame:
    """The narrow occurrences, written once: counting, ranking and runs all read this table."""
    return stage(occurrences(segment(docs, tau_seg=tau_seg, kinds=kinds), **options), "occurrences")


def runs_of(occ: DataFrame, policy, tau_del: int | None = None) -> DataFrame:
    tau = policy.tau_del if tau_del is None else tau_del
    return coherent_delete(candidate_runs(initial_decision(occ, count_groups(occ), policy)), tau)


def subdocument(docs: DataFrame, policy, **options) -> DataFrame:
    """Segment, count, budget, delete and rebuild under any policy.

    Positions belong to ids, so an id that repeats raises ValueError. Rows without id
    count as copies that come first, and stay whole. Other columns pass untouched.
    """
    assert_unique_ids(docs)
    occ = occurrence_table(docs.select("doc_id", "text"), policy.tau_seg, **options)
    return rebuild(docs, runs_of(occ, policy), policy.tau_seg)


def adaptive_dedup(docs: DataFrame, policy: RetentionPolicy = RetentionPolicy(), **options) -> DataFrame:
    return subdocument(docs, policy, **options)


def keep_one(docs: DataFrame, coherence: bool = False) -> DataFrame:
    """One copy of each chunk; ``coherence`` adds the run rule and the rule for ties."""
    return subdocument(docs, KeepOne(tau_del=100, ties="document") if coherence else KeepOne())


def keep_k(docs: DataFrame, k: int) -> DataFrame:
    return subdocument(docs, KeepK(k))


def full_pipeline(docs: DataFrame, policy: RetentionPolicy = RetentionPolicy(), **minhash) -> DataFrame:
    """Near-duplicate documents first, then sub-document deletion with counts of the survivors."""
    return adaptive_dedup(stage(minhash_dedup(docs, **minhash), "survivors"), policy)


def keep_one_pipeline(docs: DataFrame, **minhash) -> DataFrame:
    return keep_one(stage(minhash_dedup(docs, **minhash), "survivors"))


def substring_pipeline(docs: DataFrame, shards: int = 4, min_len: int = 50, by: str = "hash", keep_first: bool = False, suffix_array: bool = False, minhash: bool = True, **options) -> DataFrame:
    """Near-duplicate documents first, then removal of exact substrings repeated in a shard."""
    assert_unique_ids(docs)
    d = stage(minhash_dedup(docs, **options), "survivors") if minhash else docs
    sharded = assign_shard(d.select("doc_id", "text", *(["source"] if by == "source" else [])), shards, by)
    spans = suffix_array_spans(sharded, min_len) if suffix_array else winnowed_spans(sharded, min_len, min(32, min_len), "shard", keep_first)
    return remove_spans(d, spans)


def code_pipeline(docs: DataFrame, policy: RetentionPolicy = RetentionPolicy(), braces: bool = True) -> DataFrame:
    """Sub-document deletion with code units kept whole; the segmented form is written, since it passed Python."""
    assert_unique_ids(docs)
    cut = stage(segment(docs, tau_seg=policy.tau_seg, protect_code=True, braces=braces, out="__chunks"), "segmented")
    occ = stage(occurrences(cut, chunks="__chunks"), "occurrences")
    return rebuild(cut, runs_of(occ, policy), chunks="__chunks").drop("__chunks")


def ablations() -> dict[str, object]:
    """Named policies around the final one."""
    final = RetentionPolicy()
    return {
        "adaptive": final,
        "adaptive_no_runs": replace(final, tau_del=0),
        "frequency_only": replace(final, length_aware=False),
        "keep_one": KeepOne(),
        "keep_one_runs": KeepOne(tau_del=100, ties="document"),
        "keep_3": KeepK(3),
        "n_5": replace(final, n=5.0),
        "n_10": replace(final, n=10.0),
        "n_100": replace(final, n=100.0),
        "full_length_128": replace(final, full_length=128),
        "full_length_2048": replace(final, full_length=2048),
    }


def ablation_grid(docs: DataFrame, policies: dict[str, object] | None = None) -> DataFrame:
    """Deleted chunks and characters of each policy, in one plan: policies are a column of the active groups."""
    policies = policies or ablations()
    occ = occurrence_table(docs)
    groups = count_groups(occ)
    plan = F.explode(F.array(*(F.struct(F.lit(name).alias("policy"), F.lit(p.ties == "strict").alias("strict"), F.lit(p.tau_del).alias("tau_del"), p.budget(F.col("freq"), F.col("norm_len")).alias("budget")) for name, p in policies.items())))
    active = groups.where("freq > 1").select(*KEY, "freq", plan.alias("p")).where("p.budget < freq").select(*KEY, "p.*")
    # the places of both tie rules; a strict place is never before the shared one
    places = first_places(occ, max(p.max_budget() for p in policies.values()), False)
    places = places.withColumn("seat", F.row_number().over(Window.partitionBy(*KEY).orderBy("doc_id", "pos")))
    mine = F.when(F.col("strict"), F.col("seat")).otherwise(F.col("place")) <= F.col("budget")
    last = places.join(active, KEY).where(mine).groupBy(*KEY, "policy", "strict", "tau_del").agg(F.max(F.struct("doc_id", "pos")).alias("last"))
    last = last.select(*KEY, "policy", "tau_del", F.col("last.doc_id").alias("last_doc"), F.when(F.col("strict"), F.col("last.pos")).otherwise(2147483647).alias("last_pos"))
    runs = candidate_runs(occ.join(last, KEY).where(past()), "policy", "tau_del").where(F.col("run_chars") >= F.col("tau_del"))
    sums = runs.groupBy("policy").agg(F.sum(F.col("last_pos") - F.col("first_pos") + 1).alias("deleted_chunks"), F.sum("run_chars").alias("deleted_chars"))
    names = docs.sparkSession.createDataFrame([(n,) for n in policies], "policy string")
    return names.join(sums, "policy", "left").select("policy", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("deleted_chunks", "deleted_chars")))
