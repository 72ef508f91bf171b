"""Queries of the method itself: segmentation, hashing, counting, budgets, deletion, settings."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.retention import KeepK, KeepOne, RetentionPolicy, expected_kept, kept_fraction, length_factor, sql_budget
from ..functions.text import normalize_text
from ..operators.counting import approx_group_count, count_groups, count_groups_with_docs, duplicate_groups, group_doc_counts, heavy_hitters, merge_counts
from ..operators.deletion import attach_groups, candidate_runs, coherent_delete, explain_decisions, initial_decision, rank_occurrences, rebuild, with_budget
from ..operators.segment import chunk_rows, hexed, is_code, occurrences, segment
from ..session import spread, stage
from ..sources.io import table
from . import pipelines as P
from . import sql as S
from .registry import query

FINAL = RetentionPolicy()
#: With so few copies allowed, small tables have candidates too.
TIGHT = RetentionPolicy(n=2.0)
TIGHT_SQL = S.budget(n=2.0)
FIXTURES = [(1, "Hi.\n\nOne two. Three four five six seven eight nine ten. Tail"), (2, ""), (3, "short"), (4, "x" * 40), (5, "a" * 31 + "\nNext line"), (6, "a" * 30 + "\nNext line"), (7, "ａ" * 40 + "。" + "ｂ" * 40), (8, "Version 1.5 is out now and it is quite good. More text follows here."), (9, None), (10, " \n \n "), (11, "Wait... what?! Yes. " * 6)]
FIXTURE_SQL = "SELECT * FROM (VALUES " + ", ".join(f"({i}, {'NULL' if t is None else S.quoted(t)})" for i, t in FIXTURES) + ") t(doc_id, text)"


def docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spread(table(spark, sf_dir, "documents"))


def occ_of(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    return P.occurrence_table(docs(spark, sf_dir).select("doc_id", "text"), **options)


# --- segmentation -------------------------------------------------------------------


@query(f"WITH {S.chunk_ctes(tau=0)} SELECT doc_id, count(*) AS pieces, max(length(text)) AS longest FROM chunk GROUP BY doc_id")
def seg_boundaries(spark, d):
    c = chunk_rows(segment(docs(spark, d), tau_seg=0))
    return c.groupBy("doc_id").agg(F.count("*").alias("pieces"), F.max(F.length("text")).alias("longest"))


@query(f"WITH {S.chunk_ctes()} SELECT doc_id, pos, text FROM chunk")
def seg_merge(spark, d):
    return chunk_rows(segment(docs(spark, d)))


@query(f"WITH {S.chunk_ctes()} SELECT doc_id, max(pos) AS pos, length(max_by(text, pos)) AS tail_len FROM chunk GROUP BY doc_id HAVING length(max_by(text, pos)) < 32")
def seg_residual(spark, d):
    c = chunk_rows(segment(docs(spark, d)))
    return c.groupBy("doc_id").agg(F.max("pos").alias("pos"), F.length(F.max_by("text", "pos")).alias("tail_len")).where("tail_len < 32")


@query(f"WITH {S.chunk_ctes(tau=0, kinds=('line',))} SELECT doc_id, pos, text FROM chunk")
def seg_line(spark, d):
    return chunk_rows(segment(docs(spark, d), tau_seg=0, kinds=("line",)))


@query(f"WITH {S.chunk_ctes(tau=0, kinds=('sentence',))} SELECT doc_id, pos, text FROM chunk")
def seg_sentence(spark, d):
    return chunk_rows(segment(docs(spark, d), tau_seg=0, kinds=("sentence",)))


@query(f"WITH {S.chunk_ctes(FIXTURE_SQL)} SELECT doc_id, pos, text FROM chunk")
def seg_edge(spark, d):
    return chunk_rows(segment(spark.createDataFrame(FIXTURES, "doc_id int, text string")))


def _with_fences(spark, d):
    fence = F.concat(F.lit("\n```python\ndef f(x):\n\n    return x. \n"), F.concat(F.lit("value = "), (F.col("doc_id") % 7).cast("string")), F.lit("\n```\nAfter the code comes prose. It goes on for a while.\n"))
    return docs(spark, d).select("doc_id", F.when(F.col("doc_id") % 5 == 0, F.concat("text", fence)).otherwise(F.col("text")).alias("text"))


_FENCED = "\n```python\ndef f(x):\n\n    return x. \nvalue = 0\n```\nAfter the code comes prose. It goes on for a while.\n"
_WITH_FENCE = "SELECT doc_id, CASE WHEN doc_id % 5 = 0 THEN text || replace(" + S.quoted(_FENCED) + ", 'value = 0', 'value = ' || (doc_id % 7)) ELSE text END AS text FROM documents"
#: The only fence of these texts: from the line break before it to that after its end.
_FENCE_SPAN = "span AS (SELECT doc_id, strpos(text, '```python') - 1 AS s, strpos(text, '```python') - 1 + strpos(substr(text, strpos(text, '```python')), chr(10) || '```' || chr(10)) + 4 AS e FROM src WHERE contains(text, '```python'))"
_PAGES = "SELECT page_id AS doc_id, html AS text FROM pages"


@query(f"WITH {S.spanned_chunk_ctes(_WITH_FENCE, _FENCE_SPAN)} SELECT doc_id, pos, text, kind FROM chunk")
def seg_fence(spark, d):
    return segment(_with_fences(spark, d), protect_code=True).select("doc_id", F.posexplode("chunks").alias("pos", "c")).select("doc_id", "pos", "c.text", "c.kind")


@query(f"WITH {S.spanned_chunk_ctes(_PAGES, S.brace_spans_cte())} SELECT doc_id, pos, text, kind FROM chunk")
def seg_brace(spark, d):
    return segment(table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.col("html").alias("text")), protect_code=True, braces=True).select("doc_id", F.posexplode("chunks").alias("pos", "c")).select("doc_id", "pos", "c.text", "c.kind")


@query(f"WITH {S.spanned_chunk_ctes(_WITH_FENCE, _FENCE_SPAN)} SELECT (kind = 'code')::BIGINT AS kind, count(*) AS chunks, sum(length(text))::BIGINT AS chars FROM chunk GROUP BY ALL")
def seg_code_mixed(spark, d):
    return occurrences(segment(_with_fences(spark, d), protect_code=True, braces=True)).groupBy("kind").agg(F.count("*").alias("chunks"), F.sum("raw_len").alias("chars"))


# --- normalisation and hashing ------------------------------------------------------

_SENTENCE = "'Order ' || o_orderkey || ' was placed on ' || strftime(o_orderdate, '%Y-%m-%d') || ' for $' || (o_orderkey % 900 + 100) || ',000.50, up ' || (o_orderkey % 40) || '% on page ' || (o_orderkey % 12) || '; ' || o_orderpriority"


def _order_sentences(spark, d):
    k = F.col("o_orderkey")
    s = lambda c: c.cast("string")
    return table(spark, d, "orders").select(k.alias("doc_id"), F.concat(F.lit("Order "), s(k), F.lit(" was placed on "), F.date_format("o_orderdate", "yyyy-MM-dd"), F.lit(" for $"), s(k % 900 + 100), F.lit(",000.50, up "), s(k % 40), F.lit("% on page "), s(k % 12), F.lit("; "), F.col("o_orderpriority")).alias("text"))


def _norm_query(name: str, placeholders: str | None):
    @query(f"SELECT {S.normal('text', placeholders)} AS norm, count(*) AS n FROM (SELECT {_SENTENCE} AS text FROM orders) GROUP BY ALL", name=name)
    def run(spark, d):
        return _order_sentences(spark, d).groupBy(normalize_text(F.col("text"), placeholders).alias("norm")).agg(F.count("*").alias("n"))


_norm_query("norm_numeric", "single")
_norm_query("norm_typed", "typed")
_norm_query("norm_off", None)


@query(f"SELECT 'code' AS kind, count(DISTINCT props) AS groups FROM events UNION ALL SELECT 'prose', count(DISTINCT {S.normal('props')}) FROM events")
def norm_code_identity(spark, d):
    """The same strings as code, kept apart by their constants, and as prose, folded."""
    e = table(spark, d, "events").select("event_id", "props")
    out = None
    for kind in ("code", "prose"):
        cut = e.select(F.col("event_id").alias("doc_id"), F.array(F.struct(F.col("props").alias("text"), F.lit(kind).alias("kind"))).alias("chunks")).where("props is not null")
        row = count_groups(occurrences(cut)).agg(F.count("*").alias("groups")).select(F.lit(kind).alias("kind"), "groups")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT doc_id, md5(nfc_normalize(replace(replace(text, 'é', 'e' || chr(769)), 'ü', 'u' || chr(776)))) AS norm_md5 FROM documents")
def norm_nfc(spark, d):
    """Letters written with a mark of their own are composed."""
    apart = F.replace(F.replace("text", F.lit("é"), F.lit("e\u0301")), F.lit("ü"), F.lit("u\u0308"))
    return docs(spark, d).select("doc_id", F.md5(normalize_text(apart, None, unicode_nfc=True)).alias("norm_md5"))


@query(f"SELECT doc_id, md5(lower(regexp_replace({S.normal('text')}, '^{S.WS}+|{S.WS}+$', '', 'g'))) AS norm_md5 FROM documents")
def norm_options(spark, d):
    return docs(spark, d).select("doc_id", F.md5(normalize_text(F.col("text"), trim_edges=True, lowercase=True)).alias("norm_md5"))


def _hash_query(name: str, algo: str):
    @query(f"SELECT doc_id, {algo}(text) AS h FROM documents", name=name)
    def run(spark, d):
        from ..functions.text import content_hash

        return hexed(docs(spark, d).select("doc_id", content_hash(F.col("text"), algo).alias("h")))


_hash_query("hash_md5", "md5")
_hash_query("hash_sha256", "sha256")

# --- counting -----------------------------------------------------------------------

_GROUPS = f"WITH {S.occ_ctes()} SELECT h, norm_len, freq, n_docs FROM (SELECT h, norm_len, count(*) AS freq, count(DISTINCT doc_id) AS n_docs FROM occ GROUP BY ALL)"


@query(_GROUPS)
def group_counts(spark, d):
    return hexed(count_groups_with_docs(occ_of(spark, d)))


@query(f"WITH {S.occ_ctes()} SELECT * FROM grp WHERE freq >= 2")
def dup_groups(spark, d):
    return hexed(duplicate_groups(count_groups(occ_of(spark, d))))


@query(f"WITH {S.occ_ctes()} SELECT *, 3::BIGINT AS dealings FROM grp")
def count_invariance(spark, d):
    """Counts of documents dealt to 1, 7 and 64 partitions: each group has one count in all three."""
    out = None
    for n in (1, 7, 64):
        part = count_groups(occurrences(segment(docs(spark, d).repartition(n))))
        out = part if out is None else out.unionByName(part)
    return hexed(out.groupBy("h", "norm_len", "freq").agg(F.count("*").alias("dealings")))


@query(f"WITH {S.occ_ctes()} SELECT h, norm_len, doc_id, count(*) AS copies FROM occ GROUP BY ALL", name="group_doc_counts")
def group_doc_counts_query(spark, d):
    return hexed(group_doc_counts(occ_of(spark, d)))


@query(f"WITH {S.occ_ctes()} SELECT (SELECT count(*) FROM occ) AS occurrences, (SELECT count(*) FROM grp) AS exact_groups, TRUE AS within_a_tenth")
def approx_groups(spark, d):
    """The estimated number of groups beside the exact one."""
    occ = occ_of(spark, d)
    exact = count_groups(occ).agg(F.count("*").alias("exact_groups"))
    near = F.abs(F.col("approx_groups") - F.col("exact_groups")) <= 0.1 * F.col("exact_groups")
    return approx_group_count(occ).crossJoin(exact).select("occurrences", "exact_groups", near.alias("within_a_tenth"))


@query(f"WITH {S.occ_ctes()} SELECT h, norm_len, freq FROM grp WHERE freq >= 0.001 * (SELECT count(*) FROM occ)", name="heavy_hitters")
def heavy_hitters_query(spark, d):
    return hexed(heavy_hitters(occ_of(spark, d)))


@query(f"WITH {S.occ_ctes()} SELECT * FROM grp", name="merge_counts")
def merge_counts_query(spark, d):
    occ = occ_of(spark, d)
    return hexed(merge_counts(count_groups(occ.where("doc_id % 2 = 0")), count_groups(occ.where("doc_id % 2 != 0"))))


# --- retention ----------------------------------------------------------------------

_C = "SELECT unnest(range(1, 301)) AS freq"
_GRID = f"SELECT freq, len FROM ({_C}), (SELECT unnest([0, 32, 128, 256, 384, 511, 512, 1024]) AS len)"


def _freqs(spark, top: int = 300):
    return spark.range(1, top + 1).select(F.col("id").alias("freq"))


def _grid(spark):
    return _freqs(spark).select("freq", F.explode(F.array(*(F.lit(x).cast("long") for x in (0, 32, 128, 256, 384, 511, 512, 1024)))).alias("len"))


@query(f"SELECT freq, round({S.g('freq')}, 6) AS g FROM ({_C})")
def g_curve(spark, d):
    return _freqs(spark).select("freq", F.round(expected_kept(F.col("freq")), 6).alias("g"))


@query(f"SELECT freq, round({S.g('freq')} / freq, 6) AS r FROM ({_C})")
def r_curve(spark, d):
    return _freqs(spark).select("freq", F.round(kept_fraction(F.col("freq")), 6).alias("r"))


@query(f"SELECT len, round({S.alpha('len')}, 6) AS alpha FROM (SELECT unnest(range(0, 700)) AS len)")
def alpha_curve(spark, d):
    return spark.range(700).select(F.col("id").alias("len"), F.round(length_factor(F.col("id")), 6).alias("alpha"))


def _budget_query(name: str, policy, sql: str):
    @query(f"SELECT freq, len, {sql} AS budget FROM ({_GRID})", name=name)
    def run(spark, d):
        return _grid(spark).select("freq", "len", policy.budget(F.col("freq"), F.col("len")).alias("budget"))


_budget_query("budget_grid", FINAL, S.budget("freq", "len"))
_budget_query("budget_freq_only", RetentionPolicy(length_aware=False), S.budget("freq", "len", length_aware=False))
_budget_query("budget_keep_one", KeepOne(), "1::BIGINT")
_budget_query("budget_keep_k", KeepK(3), "least(3, freq)::BIGINT")


@query(f"SELECT freq, len, round(greatest(1.0::DOUBLE, 1 + ({S.g('freq')} - 1) * {S.alpha('len')}), 6) AS budget, round(greatest(1.0::DOUBLE, 1 + ({S.g('freq')} - 1) * {S.alpha('len')}) / freq, 6) AS fraction FROM ({_GRID})")
def budget_real(spark, d):
    b = FINAL.real_budget(F.col("freq"), F.col("len"))
    return _grid(spark).select("freq", "len", F.round(b, 6).alias("budget"), F.round(b / F.col("freq"), 6).alias("fraction"))


@query(f"SELECT min(b) AS least, max(b) AS most FROM (SELECT {S.budget('freq', 'len')} AS b FROM ({_GRID}) WHERE len >= 512)")
def budget_saturated(spark, d):
    return _grid(spark).where("len >= 512").select(FINAL.budget(F.col("freq"), F.col("len")).alias("b")).agg(F.min("b").alias("least"), F.max("b").alias("most"))


_NS = (5.0, 10.0, 100 / 3, 50.0, 100.0)
_FULLS = (128, 512, 2048)


@query("WITH " + S.occ_ctes() + ", pol AS (SELECT * FROM (VALUES " + ", ".join(f"({n!r}::DOUBLE, {f})" for n in _NS for f in _FULLS) + f") p(n, full_length)) SELECT n, full_length, sum(b)::BIGINT AS kept, count_if(b < freq) AS active_groups FROM (SELECT n, full_length, freq, {S.budget(n='n', full='full_length')} AS b FROM grp, pol) GROUP BY ALL")
def policy_sweep(spark, d):
    """Sum of budgets for a table of policies: groups are counted once, by frequency and length, for all."""
    shapes = count_groups(occ_of(spark, d)).groupBy("freq", "norm_len").agg(F.count("*").alias("groups"))
    pol = F.explode(F.array(*(F.struct(F.lit(n).alias("n"), F.lit(f).alias("full_length")) for n in _NS for f in _FULLS)))
    x = shapes.select("freq", "norm_len", "groups", pol.alias("p")).select("freq", "norm_len", "groups", "p.*")
    raw = F.ceil(F.lit(1.0) + (expected_kept(F.col("freq"), F.col("n")) - 1) * length_factor(F.col("norm_len"), F.col("full_length").cast("double"))).cast("long")
    b = F.least(F.col("freq"), F.greatest(F.lit(1).cast("long"), raw))
    return x.withColumn("b", b).groupBy("n", "full_length").agg(F.sum(F.col("b") * F.col("groups")).alias("kept"), F.sum(F.when(F.col("b") < F.col("freq"), F.col("groups")).otherwise(0)).alias("active_groups"))


@query(f"SELECT freq, len, {S.budget('freq', 'len')} AS budget FROM ({_GRID})", name="sql_budget")
def sql_budget_query(spark, d):
    spark.sql(sql_budget())
    _grid(spark).createOrReplaceTempView("budget_grid_rows")
    return spark.sql("SELECT freq, len, retention_budget(freq, len) AS budget FROM budget_grid_rows")


# --- deletion -----------------------------------------------------------------------


@query(f"WITH {S.occ_ctes()} SELECT doc_id, pos, h, norm_len, raw_len, freq FROM occ JOIN grp USING (h, norm_len)", name="attach_groups")
def attach_groups_query(spark, d):
    occ = occ_of(spark, d)
    return hexed(attach_groups(occ, count_groups(occ))).drop("kind")


@query(f"WITH {S.occ_ctes()} SELECT doc_id, pos, rank() OVER (PARTITION BY h, norm_len ORDER BY doc_id) AS rank, row_number() OVER (PARTITION BY h, norm_len ORDER BY doc_id, pos) AS row FROM occ")
def occurrence_rank(spark, d):
    return rank_occurrences(occ_of(spark, d)).select("doc_id", "pos", "rank", "row")


def _candidates(name: str, policy, sql: str, ties: str):
    @query(f"WITH {S.decision_ctes(sql, ties)} SELECT doc_id, pos, raw_len FROM cand", name=name)
    def run(spark, d):
        occ = occ_of(spark, d)
        return initial_decision(occ, count_groups(occ), policy).select("doc_id", "pos", "raw_len")


_candidates("keep0_ties", TIGHT, TIGHT_SQL, "document")
_candidates("keep0_strict", KeepOne(), "1", "strict")


@query(f"WITH {S.decision_ctes(TIGHT_SQL)} SELECT * FROM runs", name="candidate_runs")
def candidate_runs_query(spark, d):
    occ = occ_of(spark, d)
    return candidate_runs(initial_decision(occ, count_groups(occ), TIGHT))


@query(f"WITH {S.decision_ctes(TIGHT_SQL)} SELECT * FROM runs WHERE run_chars >= 100")
def deleted_runs(spark, d):
    occ = occ_of(spark, d)
    return coherent_delete(candidate_runs(initial_decision(occ, count_groups(occ), TIGHT)), 100)


@query(f"WITH {S.decision_ctes()} SELECT doc_id, pos FROM cand")
def delete_no_coherence(spark, d):
    from ..operators.deletion import deleted_positions

    occ = occ_of(spark, d)
    return deleted_positions(coherent_delete(candidate_runs(initial_decision(occ, count_groups(occ), FINAL)), 0))


@query(f"WITH {S.rebuilt_ctes(budget_sql=TIGHT_SQL)} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM kept")
def rebuilt_docs(spark, d):
    x = docs(spark, d)
    out = rebuild(x, P.runs_of(P.occurrence_table(x), TIGHT)).where("text != ''")
    return out.select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


@query(f"WITH {S.rebuilt_ctes(0, budget_sql='1', ties='strict')} SELECT doc_id FROM documents WHERE text <> '' AND doc_id NOT IN (SELECT doc_id FROM kept)")
def empty_docs(spark, d):
    """Documents of which exact keep-one leaves nothing."""
    x = docs(spark, d)
    return rebuild(x, P.runs_of(P.occurrence_table(x), KeepOne()), empty_docs="keep").where("text = ''").join(x.where("text != ''").select("doc_id"), "doc_id", "left_semi").select("doc_id")


@query(f"""WITH {S.decision_ctes(TIGHT_SQL)} SELECT doc_id, pos, freq, norm_len, budget, CASE WHEN freq = 1 THEN 'unique' WHEN place <= budget THEN CASE WHEN seat > budget THEN 'tie_kept' ELSE 'within_budget' END
WHEN EXISTS (SELECT 1 FROM runs r WHERE r.doc_id = dec.doc_id AND dec.pos BETWEEN first_pos AND last_pos AND run_chars >= 100) THEN 'deleted' ELSE 'run_restored' END AS fate FROM dec""")
def decision_audit(spark, d):
    return explain_decisions(occ_of(spark, d), TIGHT).select("doc_id", "pos", "freq", "norm_len", "budget", "fate")


# --- settings -----------------------------------------------------------------------

_REPORT = "SELECT doc_id, md5(text) AS text_md5, length(text) AS chars"


def _report(df):
    return df.select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


@query(f"{_REPORT} FROM documents")
def raw_corpus(spark, d):
    return _report(P.no_dedup(docs(spark, d)))


@query(f"WITH {S.rebuilt_ctes(0, budget_sql='1', ties='strict')} {_REPORT} FROM kept")
def keep_one(spark, d):
    return _report(P.keep_one(docs(spark, d)))


@query(f"WITH {S.rebuilt_ctes(100, budget_sql='1', ties='document')} {_REPORT} FROM kept")
def keep_one_coherent(spark, d):
    return _report(P.keep_one(docs(spark, d), coherence=True))


ADAPTIVE_SQL = f"""WITH {S.rebuilt_ctes()} SELECT d.doc_id, (SELECT count(*) FROM occ WHERE occ.doc_id = d.doc_id) AS n_chunks,
coalesce((SELECT sum(last_pos - first_pos + 1) FROM runs r WHERE r.doc_id = d.doc_id AND run_chars >= 100), 0)::BIGINT AS n_deleted, length(d.text) AS chars_before, length(kept.text) AS chars_after, md5(kept.text) AS text_md5
FROM documents d JOIN kept ON kept.doc_id = d.doc_id"""


@query(ADAPTIVE_SQL)
def adaptive_subdoc(spark, d):
    """The flagship: sub-document deletion under the adaptive budget, with a line for each document left."""
    x = docs(spark, d).select("doc_id", "text")
    occ = P.occurrence_table(x)
    runs = stage(P.runs_of(occ, FINAL), "runs")
    out = rebuild(x.withColumn("chars_before", F.length("text")), runs).where("text != ''")
    gone = runs.groupBy("doc_id").agg(F.sum(F.col("last_pos") - F.col("first_pos") + 1).alias("n_deleted"))
    n = occ.groupBy("doc_id").agg(F.count("*").alias("n_chunks"))
    return out.join(n, "doc_id").join(gone, "doc_id", "left").select("doc_id", "n_chunks", F.coalesce("n_deleted", F.lit(0)).cast("long").alias("n_deleted"), "chars_before", F.length("text").alias("chars_after"), F.md5("text").alias("text_md5"))


CODE_RULE = "(regexp_matches(lower(html), '<(pre|code|script|style)[ >]') OR contains(html, '```') OR (length(html) - length(translate(html, '{};', ''))) * 50 > length(html))"
CODE_PAGES = f"SELECT page_id AS doc_id, html AS text FROM pages WHERE {CODE_RULE}"
CODE_KEPT = S.rebuilt_ctes(budget_sql=TIGHT_SQL, occ=S.code_occ_ctes(CODE_PAGES, S.brace_spans_cte()))


def code_pages(spark, d):
    """Pages that the rule takes for code-bearing, as documents."""
    return spread(table(spark, d, "pages")).where(is_code(F.col("html"))).select(F.col("page_id").alias("doc_id"), F.col("html").alias("text"))


@query(f"WITH {CODE_KEPT} {_REPORT} FROM kept")
def adaptive_code(spark, d):
    """Code-bearing pages with braces kept whole, under a budget small enough for small tables."""
    return _report(P.code_pipeline(code_pages(spark, d), TIGHT))


@query(" UNION ALL ".join(f"(WITH {S.decision_ctes(b, t)} SELECT '{name}' AS policy, coalesce(sum(last_pos - first_pos + 1), 0)::BIGINT AS deleted_chunks, coalesce(sum(run_chars), 0)::BIGINT AS deleted_chars FROM runs WHERE run_chars >= {tau})" for name, b, t, tau in (
    ("adaptive", S.budget(), "document", 100), ("adaptive_no_runs", S.budget(), "document", 0), ("frequency_only", S.budget(length_aware=False), "document", 100), ("keep_one", "1", "strict", 0), ("keep_one_runs", "1", "document", 100),
    ("keep_3", "least(3, freq)", "strict", 0), ("n_5", S.budget(n=5.0), "document", 100), ("n_10", S.budget(n=10.0), "document", 100), ("n_100", S.budget(n=100.0), "document", 100), ("full_length_128", S.budget(full=128), "document", 100), ("full_length_2048", S.budget(full=2048), "document", 100))))
def ablation_grid(spark, d):
    return P.ablation_grid(docs(spark, d).select("doc_id", "text"))

