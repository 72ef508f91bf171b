"""From budgets to deleted runs and rebuilt documents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import KINDS, chunks_of
from .counting import KEY, count_groups


def with_budget(groups: DataFrame, policy) -> DataFrame:
    return groups.withColumn("budget", policy.budget(F.col("freq"), F.col("norm_len")))


def attach_groups(occ: DataFrame, groups: DataFrame) -> DataFrame:
    """Each occurrence with its group's columns."""
    return occ.join(groups, KEY)


def rank_occurrences(occ: DataFrame) -> DataFrame:
    """Two ranks of each copy in its group: shared by a document's copies, and strict by position.

    For inspection; it sorts whole groups. Decisions use :func:`cutoffs`.
    """
    w = Window.partitionBy(*KEY).orderBy("doc_id")
    return occ.withColumn("rank", F.rank().over(w).cast("long")).withColumn("row", F.row_number().over(w.orderBy("doc_id", "pos")).cast("long"))


def first_places(occ: DataFrame, top: int, strict: bool) -> DataFrame:
    """(h, norm_len, doc_id, pos, place) of the copies of each group whose place is ``top`` at most.

    A place is the strict one by document and position, or one more than the copies in
    earlier documents, which a document's copies share. The limit is a literal and stands
    before any join, so Spark applies it in each task before the shuffle and again after it:
    a text with a billion copies sends each task's first few rows.
    """
    order = ("doc_id", "pos") if strict else ("doc_id",)
    w = Window.partitionBy(*KEY).orderBy(*order)
    place = F.row_number() if strict else F.rank()
    return occ.select(*KEY, "doc_id", "pos").withColumn("place", place.over(w)).where(F.col("place") <= top)


def cutoffs(occ: DataFrame, active: DataFrame, policy) -> DataFrame:
    """(h, norm_len, last_doc, last_pos): the last copy that each active group's budget keeps.

    No group keeps more than ``policy.max_budget()`` places. Rows without an id come first.
    """
    strict = policy.ties == "strict"
    x = first_places(occ, policy.max_budget(), strict).join(active.select(*KEY, "budget"), KEY)
    if strict:
        return x.where(F.col("place") == F.col("budget")).select(*KEY, F.col("doc_id").alias("last_doc"), F.col("pos").alias("last_pos"))
    return x.where(F.col("place") <= F.col("budget")).groupBy(*KEY).agg(F.max("doc_id").alias("last_doc")).withColumn("last_pos", F.lit(2147483647))


def past() -> Column:
    """Whether a copy comes after the last that its group keeps; a row without id never does."""
    doc, pos, last = F.col("doc_id"), F.col("pos"), F.col("last_doc")
    return doc.isNotNull() & (last.isNull() | (doc > last) | ((doc == last) & (pos > F.col("last_pos"))))


def initial_decision(occ: DataFrame, groups: DataFrame, policy) -> DataFrame:
    """Candidate occurrences: copies beyond their group's budget.

    Groups whose budget covers them leave before the join; an occurrence is a candidate
    if it comes after its group's last kept copy.
    """
    active = with_budget(groups, policy).where(F.col("budget") < F.col("freq"))
    return occ.join(cutoffs(occ, active, policy), KEY).where(past()).drop("last_doc", "last_pos")


def candidate_runs(candidates: DataFrame, *by: str) -> DataFrame:
    """(doc_id, first_pos, last_pos, run_chars) of maximal runs of neighbouring candidates, for each value of ``by``."""
    w = Window.partitionBy("doc_id", *by).orderBy("pos")
    x = candidates.select("doc_id", *by, "pos", "raw_len").withColumn("island", F.col("pos") - F.row_number().over(w))
    return x.groupBy("doc_id", *by, "island").agg(F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"), F.sum("raw_len").alias("run_chars")).drop("island")


def coherent_delete(runs: DataFrame, tau_del: int = 100) -> DataFrame:
    """Runs long enough to go; of the others every chunk stays."""
    return runs.where(F.col("run_chars") >= tau_del)


def deleted_positions(runs: DataFrame) -> DataFrame:
    """(doc_id, pos) of the chunks of runs."""
    return runs.select("doc_id", F.explode(F.sequence("first_pos", "last_pos")).alias("pos"))


def decide(occ: DataFrame, policy, groups: DataFrame | None = None) -> DataFrame:
    """Runs to delete under a policy."""
    groups = count_groups(occ) if groups is None else groups
    return coherent_delete(candidate_runs(initial_decision(occ, groups, policy)), policy.tau_del)


def rebuild(docs: DataFrame, runs: DataFrame, tau_seg: int = 32, kinds: tuple[str, ...] = KINDS, empty_docs: str = "drop", chunks: str | None = None) -> DataFrame:
    """The documents without the runs, in order, with original text.

    Only positions travel: they meet the documents in one join, and the text is cut
    again there. ``chunks`` names a column of chunks to take instead of cutting. All other
    columns pass as they are; rows whose text or id is null are kept whole.
    """
    gone = runs.groupBy(F.col("doc_id").alias("__doc")).agg(F.collect_list(F.struct("first_pos", "last_pos")).alias("__gone"))
    pieces = F.transform(chunks, lambda c: c["text"]) if chunks else chunks_of(F.col("text"), tau_seg, kinds)
    kept = F.filter(pieces, lambda c, i: ~F.exists("__gone", lambda r: (i >= r["first_pos"]) & (i <= r["last_pos"])))
    out = docs.join(gone, docs["doc_id"] == gone["__doc"], "left").withColumn("text", F.when(F.col("__gone").isNull(), F.col("text")).otherwise(F.array_join(kept, "")))
    out = out.drop("__doc", "__gone")
    return out.where("text is null or text != ''") if empty_docs == "drop" else out


def explain_decisions(occ: DataFrame, policy) -> DataFrame:
    """Every occurrence with its group's frequency, budget and fate.

    unique, within_budget, tie_kept (beyond the budget, but of the document at the edge), run_restored or deleted.
    """
    groups = with_budget(count_groups(occ), policy)
    cand = initial_decision(occ, groups.drop("budget"), policy)
    gone = deleted_positions(coherent_delete(candidate_runs(cand), policy.tau_del)).withColumn("gone", F.lit(True))
    row = Window.partitionBy(*KEY).orderBy("doc_id", "pos")
    x = attach_groups(occ, groups).withColumn("row", F.row_number().over(row).cast("long"))
    x = x.join(cand.select("doc_id", "pos").withColumn("cand", F.lit(True)), ["doc_id", "pos"], "left").join(gone, ["doc_id", "pos"], "left")
    fate = F.when(F.col("freq") == 1, "unique").when(F.col("gone"), "deleted").when(F.col("cand"), "run_restored").when(F.col("row") > F.col("budget"), "tie_kept").otherwise("within_budget")
    return x.withColumn("fate", fate).drop("row", "cand", "gone")
