"""Ties, runs, rebuilding, plans."""

import pytest
from pyspark.sql import functions as F

from corpusdedup.functions.retention import KeepAll, KeepK, KeepOne, RetentionPolicy
from corpusdedup.operators.counting import count_groups
from corpusdedup.operators.deletion import attach_groups, candidate_runs, coherent_delete, first_places, initial_decision, rank_occurrences, rebuild, with_budget
from corpusdedup.plans import pipelines as P

SF = "/root/testdata/sf0.001"


def occ(spark, rows):
    return spark.createDataFrame([(d, p, h.encode(), n, r, 0) for d, p, h, n, r in rows], "doc_id long, pos int, h binary, norm_len int, raw_len int, kind byte")


def cands(df, policy):
    return {(r.doc_id, r.pos) for r in initial_decision(df, count_groups(df), policy).collect()}


def test_a_documents_copies_stay_together(spark):
    df = occ(spark, [(1, 0, "a", 40, 40), (2, 0, "a", 40, 40), (2, 1, "a", 40, 40), (3, 0, "a", 40, 40)])
    assert cands(df, RetentionPolicy(n=5)) == {(3, 0)}
    assert cands(df, KeepK(2)) == {(2, 1), (3, 0)}


def test_copies_of_one_document(spark):
    df = occ(spark, [(7, k, "a", 40, 40) for k in range(5)])
    assert cands(df, RetentionPolicy(n=2)) == set()
    assert cands(df, KeepOne()) == {(7, k) for k in range(1, 5)}
    assert cands(df, KeepAll()) == set()


def test_runs(spark):
    lens = [("K", 40), ("c", 60), ("c", 50), ("K", 33), ("c", 99), ("K", 35), ("c", 100)]
    df = spark.createDataFrame([(1, p, n) for p, (k, n) in enumerate(lens) if k == "c"] + [(2, 0, 60), (2, 2, 60), (3, 0, 120)], "doc_id long, pos int, raw_len int")
    runs = candidate_runs(df)
    assert {(r.doc_id, r.first_pos, r.last_pos) for r in coherent_delete(runs).collect()} == {(1, 1, 2), (1, 6, 6), (3, 0, 0)}
    assert coherent_delete(runs, 0).count() == 6


@pytest.mark.parametrize("policy", [RetentionPolicy(n=2.0), RetentionPolicy(), KeepOne(), KeepK(3), KeepK(2, ties="document")])
def test_cutoffs_equal_ranks(spark, policy):
    df = P.occurrence_table(spark.read.parquet(f"{SF}/documents.parquet"))
    groups = count_groups(df)
    ranked = attach_groups(rank_occurrences(df), with_budget(groups, policy))
    want = ranked.where(F.col("row" if policy.ties == "strict" else "rank") > F.col("budget"))
    assert cands(df, policy) == {(r.doc_id, r.pos) for r in want.collect()}


@pytest.mark.parametrize("policy", [RetentionPolicy(), KeepOne()])
def test_groups_are_limited_before_their_shuffle(spark, policy):
    """Without broadcasts, as on large tables, the rows of a group are cut to the budget's maximum below the exchange."""
    df = P.occurrence_table(spark.read.parquet(f"{SF}/documents.parquet"))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        places = first_places(df, policy.max_budget(), policy.ties == "strict")
        lines = places._jdf.queryExecution().executedPlan().toString().splitlines()
        at = lambda what: next(k for k, x in enumerate(lines) if what in x)
        assert at("Window [") < at(", Final") < at("Exchange hashpartitioning") < at(", Partial")
        # every text in every document: what the shuffle carries is bounded by tasks, not by copies
        hot = occ(spark, [(d, 0, "a", 40, 40) for d in range(5_000)]).repartition(3)
        got = {r.doc_id for r in first_places(hot, policy.max_budget(), policy.ties == "strict").collect()}
        assert got == set(range(policy.max_budget()))
        kept = RetentionPolicy().max_budget() if policy.ties != "strict" else 1
        assert len(cands(hot, policy)) >= 5_000 - kept
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_columns_of_any_name_pass(spark):
    names = ["gone", "chunks", "shard", "budget", "place", "freq", "h", "pos", "first_pos", "last_doc", "run_chars", "n"]
    same = "The same sentence stands in each of these documents and is long enough to be cut from them all. "
    docs = spark.createDataFrame([(k, f"Document {'abcdefghij'[k]} opens with words of its own here. {same}") for k in range(10)] + [(99, None)], "doc_id long, text string").withColumns({c: F.lit(f"own {c}") for c in names})
    for out in (P.subdocument(docs, KeepOne()), P.adaptive_dedup(docs), P.substring_pipeline(docs, 1, 30), P.code_pipeline(docs, RetentionPolicy(n=2.0)), P.full_pipeline(docs)):
        rows = out.collect()
        assert out.columns == docs.columns and rows
        assert all(r[c] == f"own {c}" for r in rows for c in names)
        assert any(r.doc_id == 99 and r.text is None for r in rows)
    assert sum(same.strip() in (r.text or "") for r in P.subdocument(docs, KeepOne()).collect()) == 1


def test_null_and_repeated_ids(spark):
    same = "The same sentence stands in each of these documents and is long enough to be cut from them all. "
    docs = spark.createDataFrame([(None, same), (None, same), (1, same), (2, same)], "doc_id long, text string")
    out = P.subdocument(docs, KeepOne()).collect()
    assert sorted((r.doc_id is not None, r.text) for r in out) == [(False, same)] * 2
    with pytest.raises(ValueError):
        P.subdocument(docs.unionByName(docs), KeepOne())


def test_ablations_in_one_plan_equal_single_policies(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    grid = {r.policy: (r.deleted_chunks, r.deleted_chars) for r in P.ablation_grid(docs).collect()}
    table = P.occurrence_table(docs)
    for name, policy in P.ablations().items():
        runs = P.runs_of(table, policy).collect()
        assert grid[name] == (sum(r.last_pos - r.first_pos + 1 for r in runs), sum(r.run_chars for r in runs)), name


def test_plan_limits_windows_and_keeps_text_out_of_shuffles(spark):
    df = P.occurrence_table(spark.read.parquet(f"{SF}/documents.parquet"))
    plan = initial_decision(df, count_groups(df), RetentionPolicy())._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in plan and "NestedLoop" not in plan
    cut = P.segment(spark.read.parquet(f"{SF}/documents.parquet"))
    once = P.occurrences(cut)._jdf.queryExecution().optimizedPlan().toString()
    assert once.count("regexp_extract_all(") == 1


def test_rebuild_and_orders(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = lambda p: {r.doc_id: r.text for r in P.subdocument(docs, p).collect()}
    size = lambda x: sum(map(len, x.values()))
    one, few, alls = kept(KeepOne()), kept(RetentionPolicy(n=2.0, tau_del=0)), kept(KeepAll())
    assert size(one) <= size(few) <= size(alls)
    assert alls == {r.doc_id: r.text for r in docs.where("text != ''").collect()}


def test_result_does_not_depend_on_partitions(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    runs = [sorted(map(tuple, P.runs_of(P.occurrence_table(docs.repartition(n)), RetentionPolicy(n=2.0)).collect())) for n in (1, 7, 32)]
    assert runs[0] == runs[1] == runs[2]


def test_null_and_empty_texts_pass(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "Some text. " * 10), (4, "Some text. " * 10)], "doc_id long, text string")
    out = {r.doc_id: r.text for r in P.adaptive_dedup(docs).collect()}
    assert out[1] is None and 2 not in out and out[3] == "Some text. " * 10
    runs = spark.createDataFrame([(3, 0, 99)], "doc_id long, first_pos int, last_pos int")
    assert {r.doc_id for r in rebuild(docs, runs, empty_docs="keep").where("text = ''").collect()} == {2, 3}


def test_code_pipeline_keeps_surplus_blocks_whole(spark):
    block = "```py\n" + "value = 1\n" * 15 + "```\n"
    docs = spark.createDataFrame([(k, f"Document number {'abcdefghijklmnopqrstuvwxyz'[k % 26] * (k + 3)} begins here.\n{block}") for k in range(200)], "doc_id long, text string")
    kept = [r.text for r in P.code_pipeline(docs, braces=False).collect()]
    assert all(("```" in t) == (block in t) for t in kept) and sum(block in t for t in kept) < 200
