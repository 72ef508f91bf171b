"""Closed forms, hand answers and invariants of the budget and of segmentation."""

import math
from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from corpusdedup.functions.retention import KeepK, RetentionPolicy, sql_budget
from corpusdedup.functions.text import chunks_of, content_hash, normalize_text
from corpusdedup.operators.segment import brace_spans, cut_with_spans, fence_spans, occurrences, protected_spans, segment

FINAL = RetentionPolicy()


def budgets(spark, pairs, policy=FINAL):
    df = spark.createDataFrame(pairs, "c long, l long")
    return [r[0] for r in df.select(policy.budget(F.col("c"), F.col("l"))).collect()]


def test_budget_hand_values(spark):
    cases = {(1, 0): 1, (2, 511): 2, (2, 512): 1, (10, 0): 8, (10, 128): 6, (10, 256): 5, (10, 511): 2, (33, 0): 13, (33, 128): 10, (33, 256): 7, (33, 511): 2, (33, 512): 1, (100, 0): 5, (100, 128): 4, (100, 256): 3, (169, 0): 2, (170, 0): 1, (24_500, 0): 1}
    assert budgets(spark, list(cases)) == list(cases.values())
    assert budgets(spark, [(4, 40)], RetentionPolicy(n=5)) == [2]
    assert budgets(spark, [(2, 10), (9, 10)], KeepK(3)) == [2, 3]
    assert FINAL.max_budget() == 13


def test_budget_bounds_and_exact_fractions(spark):
    q = 1 - Fraction(3, 100)
    pairs = [(c, length) for c in range(1, 61) for length in range(0, 600, 37)]
    want = [max(1, min(c, math.ceil(1 + (c * q ** (c - 1) - 1) * max(Fraction(0), 1 - Fraction(length, 512))))) for c, length in pairs]
    assert budgets(spark, pairs) == want
    for n in (1.5, 2.0, 500.0):
        got = budgets(spark, [(c, length) for c in (1, 2, 10, 1000, 10**6) for length in (0, 300, 512, 1024)], RetentionPolicy(n=n))
        assert all(1 <= b for b in got) and got[:4] == [1, 1, 1, 1]


def test_real_fraction_falls_with_frequency(spark):
    df = spark.range(1, 400).select(F.col("id").alias("c"), F.lit(100).alias("l"))
    x = [r[0] for r in df.select((FINAL.real_budget(F.col("c"), F.col("l")) / F.col("c")).alias("f"), "c").orderBy("c").collect()]
    assert all(a >= b for a, b in zip(x, x[1:], strict=False))


def test_sql_budget(spark):
    spark.sql(sql_budget())
    assert spark.sql("SELECT retention_budget(33, 128), retention_budget(24500, 0)").first() == (10, 1)


def chunks(spark, text, **options):
    return spark.createDataFrame([(text,)], "t string").select(chunks_of(F.col("t"), **options)).first()[0]


@pytest.mark.parametrize(
    "text, want",
    [
        ("Hi.\n\nOne two. Three four five six seven eight nine ten. Tail", ["Hi.\n\nOne two. Three four five six seven eight nine ten. ", "Tail"]),
        ("", []),
        (None, None),
        ("short", ["short"]),
        ("x" * 40, ["x" * 40]),
        ("a" * 31 + "\nNext line", ["a" * 31 + "\n", "Next line"]),
        ("a" * 30 + "\nNext line", ["a" * 30 + "\nNext line"]),
        ("ａ" * 40 + "。" + "ｂ" * 40, ["ａ" * 40 + "。", "ｂ" * 40]),
    ],
)
def test_segmentation_by_hand(spark, text, want):
    assert chunks(spark, text) == want


def test_no_cut_inside_a_number(spark):
    assert all("1.5" in c or "5" not in c for c in chunks(spark, "Version 1.5 is out now. It is good.", tau_seg=1))


def test_segmentation_is_lossless_and_minimal(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    for r in docs.select("text", chunks_of(F.col("text")).alias("c")).collect():
        assert "".join(r.c) == r.text and all(len(c) >= 32 for c in r.c[:-1])


@pytest.mark.parametrize(
    "left, right, norm",
    [("Page 3 of 12", "Page 7 of 90", "Page <NUM> of <NUM>"), ("Price: $4.50 today", "Price: $1,299.00 today", "Price: <NUM> today"), ("Updated 2024-01-05", "Updated 2023-12-31", "Updated <NUM>"), ("up 12.5% overall", "up 7% overall", "up <NUM> overall")],
)
def test_numbers_fold_in_prose_only(spark, left, right, norm):
    df = spark.createDataFrame([(left,), (right,)], "t string")
    assert {r[0] for r in df.select(normalize_text(F.col("t"))).collect()} == {norm}
    code = spark.createDataFrame([(k, [(t, "code")]) for k, t in enumerate((left, right))], "doc_id long, chunks array<struct<text:string,kind:string>>")
    assert occurrences(code).select("h").distinct().count() == 2


def test_hashes_group_alike(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    x = segment(docs).select(F.explode("chunks.text").alias("t"))
    n = {a: x.select(content_hash(F.col("t"), a)).distinct().count() for a in ("md5", "sha256", "xxhash128", "none")}
    assert len(set(n.values())) == 1


def test_code_units_stay_whole():
    fence = "```py\na = 1.\n\nb = 2. \n```\n"
    text = "Prose comes first.\n" + fence + "Then prose again, and then some more of it. End."
    (span,) = protected_spans(text)
    assert text[span[0] : span[1]] == fence
    cut = cut_with_spans(text, [span], 8, ("line", "sentence"))
    assert "".join(c["text"] for c in cut) == text and sum(fence in c["text"] for c in cut) == 1
    assert fence_spans("```\nopen and never closed") == []
    code = "f {\n a { b { c; } }\n}\nrest"
    assert [code[a:b] for a, b in brace_spans(code)] == ["f {\n a { b { c; } }\n}"]
    assert brace_spans("open { and a sentence. Another one.") == []
    assert [("} x {y}")[a:b] for a, b in brace_spans("} x {y}", attach_header=False)] == ["{y}"]


def test_short_code_joins_prose_as_code():
    text = "```\nx=1\n```\nProse with 42 in it follows here, long enough to end the chunk."
    cut = cut_with_spans(text, protected_spans(text), 32, ("line", "sentence"))
    assert cut[0]["kind"] == "code" and cut[0]["text"].startswith("```")
