"""Registered queries against their SQL on the smallest tables; sources and streams."""

import datetime
import time

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from corpusdedup.plans.all_queries import ORACLES, QUERIES
from corpusdedup.sources import io

SF = "/root/testdata/sf0.001"
#: One query or two of each kind; all run in the driver's comparison.
PICKED = ["seg_merge", "seg_edge", "norm_typed", "norm_code_identity", "group_counts", "budget_grid", "policy_sweep", "keep0_ties", "keep0_strict", "deleted_runs", "rebuilt_docs", "decision_audit", "adaptive_subdoc", "keep_one", "verified_pairs", "dup_clusters", "shard_sensitivity", "retention_report", "freq_profile_line", "deletion_report", "fragmentation", "score_averages", "score_ranks", "html_text", "asof_events", "cube_retention", "win_session", "stream_counts", "stream_admit", "stream_doc_dedup", "ablation_grid", "exact_doc_dedup", "minhash_sig_arrow", "kgram_spans", "winnowed_spans", "substring_keep_first", "proxy_benchmark", "seg_brace", "seg_code_mixed", "adaptive_code", "heavy_hitters", "approx_groups", "count_invariance", "agg_udaf", "fn_variant"]


def plain(v):
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return v


@pytest.fixture(scope="module")
def sql():
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", PICKED)
def test_query_equals_sql(spark, sql, name):
    got = QUERIES[name](spark, SF)
    cols = sorted(got.columns)
    want = sql.sql(f"SELECT {', '.join(cols)} FROM ({ORACLES[name]})").fetchall()
    key = lambda r: tuple((v is None, str(v)) for v in r)
    mine = sorted((tuple(plain(r[c]) for c in cols) for r in got.collect()), key=key)
    assert mine == sorted((tuple(plain(v) for v in r) for r in want), key=key)


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES) and set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_sources(spark, tmp_path):
    rows = spark.createDataFrame([(1, 'a "quoted"\nline', "en", "s"), (2, None, "de", "s")], io.CORPUS)
    io.write_jsonl(rows, f"file://{tmp_path}/j")
    assert sorted(map(tuple, io.read_jsonl(spark, f"file://{tmp_path}/j").collect())) == sorted(map(tuple, rows.collect()))
    rows.where("doc_id = 1").write.option("header", True).option("escape", '"').option("quoteAll", True).csv(f"file://{tmp_path}/c")
    assert io.read_csv(spark, f"file://{tmp_path}/c").first().text == 'a "quoted"\nline'
    io.write_manifest(spark, f"file://{tmp_path}/m", n=1)
    assert spark.read.text(f"file://{tmp_path}/m").first()[0] == '{"n": 1}'
    io.assert_unique_ids(rows)
    with pytest.raises(ValueError):
        io.assert_unique_ids(rows.unionByName(rows))


def test_admission_against_one_copy_after_another():
    import math

    from corpusdedup.streaming.streams import admit_copies

    for n, full, length in ((2.0, 512, 40), (100 / 3, 512, 0), (100 / 3, 512, 300), (5.0, 128, 500)):
        seen = kept = 0
        for k in range(1, 400):
            budget = max(1, min(k, math.ceil(1 + (k * (1 - 1 / n) ** (k - 1) - 1) * max(0.0, 1 - length / full))))
            kept += kept < budget
            seen += 1
            assert admit_copies(0, 0, k, length, n, full)[1] == kept
            half = admit_copies(0, 0, k // 2, length, n, full)[1]
            assert admit_copies(k // 2, half, k - k // 2, length, n, full)[1] == kept


def test_admission_over_batches_without_a_call_for_each_group(spark, tmp_path, monkeypatch):
    from corpusdedup.functions.retention import RetentionPolicy
    from corpusdedup.streaming import streams

    calls = [f"line number {'x' * k} that is long enough" for k in range(30)]
    batches = [[calls[k] for k in range(30) if k % (b + 1) == 0 for _ in range(k % 4 + 1)] for b in range(3)]
    for b, lines in enumerate(batches):
        spark.createDataFrame([(100 * b + k, x) for k, x in enumerate(lines)], "doc_id long, text string").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        time.sleep(1.1)  # files are read in order of their times
    policy = RetentionPolicy(n=3.0, full_length=128)
    monkeypatch.setattr("pyspark.sql.GroupedData.applyInPandasWithState", None)
    stream = streams.read_documents(spark, f"{tmp_path}/in", "doc_id long, text string")
    got = sorted((r.seen, r.admitted) for r in streams.stream_admit(stream, policy).collect())
    want = []
    for k, x in enumerate(calls):
        seen = kept = 0
        for b in range(3):
            copies = batches[b].count(x)
            kept = streams.admit_copies(seen, kept, copies, len(x), 3.0, 128)[1]
            seen += copies
        want.append((seen, kept))
    assert got == sorted(want)
    (tmp_path / "none").mkdir()
    assert streams.stream_admit(streams.read_documents(spark, f"{tmp_path}/none", "doc_id long, text string"), policy).count() == 0


def test_late_rows_of_a_stream_are_dropped(spark, tmp_path):
    from corpusdedup.streaming import streams

    # a batch's late rows are those before the watermark of the batch before it
    rows = [(1, "a", 7200), (2, "b", 7300), (3, "a", 7400)], [(4, "m", 7500)], [(5, "late", 100), (6, "b", 9000), (7, "c", 9001)]
    for part in rows:
        spark.createDataFrame(part, "doc_id long, text string, t long").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        time.sleep(1.1)  # files are read in order of their times
    stream = streams.read_documents(spark, f"{tmp_path}/in", "doc_id long, text string, t long").withColumn("arrived", F.timestamp_seconds("t"))
    got = {r.text for r in streams.run_to_table(streams.stream_doc_dedup(stream), "late").collect()}
    assert got == {"a", "b", "m", "c"}


def test_heavy_hitters_need_room(spark):
    from corpusdedup.operators.counting import heavy_hitters

    occ = spark.createDataFrame([(b"hot", 3)] * 50 + [(str(k).encode(), 3) for k in range(2000)], "h binary, norm_len int")
    assert [(bytes(r.h), r.freq) for r in heavy_hitters(occ, 0.02, 200).collect()] == [(b"hot", 50)]
    with pytest.raises(ValueError):
        heavy_hitters(occ, 0.01, 100)


def test_stage_metrics(spark):
    from corpusdedup.operators.measures import stage_metrics

    last = max((r.stage for r in stage_metrics(spark).collect()), default=-1)
    spark.range(1000).repartition(3).count()
    rows = stage_metrics(spark, last).collect()
    assert rows and sum(r.shuffle_written for r in rows) > 0


def test_spread(spark):
    from corpusdedup.session import spread

    one = spark.range(100).coalesce(1)
    assert spread(one).rdd.getNumPartitions() == spark.sparkContext.defaultParallelism and spread(one).count() == 100
    many = spark.range(0, 100, 1, 4)
    assert spread(many) is many


def test_table_function(spark):
    assert QUERIES["udtf_segment"](spark, SF).count() == QUERIES["seg_merge"](spark, SF).count()


@pytest.mark.parametrize("name", ["seg_merge", "adaptive_subdoc"])
def test_cuts_after_long_white_space(spark, tmp_path, name):
    words = "some words of a chunk that is long enough to stand alone"
    gaps = ["\n" + " " * k for k in (31, 32, 33, 40, 1024, 1025, 3000)] + ["." + " \t" * 600, "。" + " " * 50, " " * 2000 + "\n", " " * 40, "\n" + " " * 40 + "\n" + " " * 1100, "| a |" + " " * 90 + "| b |\n"]
    rows = [(d, "".join(f"{words} {d * (k % 3)}{g}" for k, g in enumerate(gaps)) + words, "en", "s", 1) for d in range(60)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    got = QUERIES[name](spark, str(tmp_path))
    cols = sorted(got.columns)
    want = con.sql(f"SELECT {', '.join(cols)} FROM ({ORACLES[name]})").fetchall()
    assert sorted(map(str, (tuple(plain(r[c]) for c in cols) for r in got.collect()))) == sorted(map(str, (tuple(plain(v) for v in r) for r in want)))
