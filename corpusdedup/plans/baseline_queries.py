"""Queries of the document-level and substring baselines and of the measures."""

from __future__ import annotations

from pyspark.sql import functions as F


from ..operators import documents as D
from ..operators import measures as M
from ..operators import substring as B
from ..operators.counting import count_groups, count_groups_with_docs
from ..functions.retention import KeepOne
from ..operators.segment import hexed
from ..session import stage
from ..sources.io import table
from . import pipelines as P
from . import sql as S
from .core_queries import CODE_KEPT, CODE_PAGES, FINAL, TIGHT, TIGHT_SQL, code_pages, docs, occ_of
from .registry import query

_SIG = f"{S.shingle_ctes()}, {S.signature_cte()}"
_PAIRS = f"{_SIG}, {S.pair_ctes(32, 4)}"


@query("SELECT d.* FROM documents d JOIN (SELECT min(doc_id) AS doc_id FROM documents GROUP BY md5(text)) USING (doc_id)")
def exact_doc_dedup(spark, d):
    return D.exact_doc_dedup(docs(spark, d))


@query(f"WITH wd AS (SELECT doc_id, {S.words()} AS w FROM documents) SELECT doc_id, CASE WHEN len(w) = 0 THEN 0 ELSE len(list_distinct(list_transform(range(1, greatest(1, len(w) - 4) + 1), lambda i: array_to_string(w[i:i + 4], ' ')))) END AS n FROM wd")
def shingle_counts(spark, d):
    return docs(spark, d).select("doc_id", F.size(D.shingles(F.col("text"))).alias("n"))


@query(f"WITH {_SIG} SELECT doc_id, md5(array_to_string(sig, ',')) AS sig_md5 FROM sg")
def minhash_sig(spark, d):
    return D.minhash_signature(docs(spark, d)).select("doc_id", F.md5(F.array_join("sig", ",")).alias("sig_md5"))


@query(f"WITH {_SIG} SELECT doc_id, md5(array_to_string(sig, ',')) AS sig_md5 FROM sg")
def minhash_sig_arrow(spark, d):
    return D.minhash_signature_numpy(docs(spark, d)).select("doc_id", F.md5(F.array_join("sig", ",")).alias("sig_md5"))


@query(f"WITH {_PAIRS} SELECT a, b FROM cp")
def lsh_pairs(spark, d):
    return D.lsh_pairs(stage(D.minhash_signature_numpy(docs(spark, d)), "signatures"), 32, 4)


@query(f"WITH {_PAIRS} SELECT a, b, similarity FROM vp")
def verified_pairs(spark, d):
    sig = stage(D.minhash_signature_numpy(docs(spark, d)), "signatures")
    return D.verify_pairs(D.lsh_pairs(sig, 32, 4), sig)


@query(f"WITH RECURSIVE {_PAIRS}, {S.cluster_ctes()} SELECT doc_id, component FROM cl")
def dup_clusters(spark, d):
    return D.dup_clusters(docs(spark, d))


@query(f"WITH {S.shingle_ctes()}, n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY 1), p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS o FROM sh x JOIN sh y ON x.base = y.base AND x.doc_id < y.doc_id GROUP BY ALL) SELECT a, b, o / (na.n + nb.n - o)::DOUBLE AS jaccard FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE o / (na.n + nb.n - o)::DOUBLE >= 0.7")
def exact_jaccard(spark, d):
    return D.exact_jaccard_pairs(docs(spark, d))


_TRUE = "na AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY 1), tp AS MATERIALIZED (SELECT a, b FROM (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS o FROM sh x JOIN sh y ON x.base = y.base AND x.doc_id < y.doc_id GROUP BY ALL) JOIN na p ON p.doc_id = a JOIN na q ON q.doc_id = b WHERE o / (p.n + q.n - o)::DOUBLE >= 0.7)"
_SCHEMES = " UNION ALL ".join(f"(WITH {S.pair_ctes(b, r)} SELECT {b}::BIGINT AS bands, {r}::BIGINT AS rows, (SELECT count(*) FROM cp) AS candidates, (SELECT count(*) FROM tp) AS true_pairs, round((SELECT count(*) FROM tp JOIN cp USING (a, b)) / (SELECT count(*) FROM tp)::DOUBLE, 6) AS recall, round(1 - pow(1 - pow(0.7::DOUBLE, {r}), {b}), 6) AS expected_at_threshold)" for b, r in ((16, 8), (32, 4), (64, 2)))


@query(f"WITH {_SIG}, {_TRUE} {_SCHEMES}")
def lsh_quality(spark, d):
    return D.lsh_quality(docs(spark, d)).withColumns({c: F.round(c, 6) for c in ("recall", "expected_at_threshold")})


@query(f"WITH {S.shingle_ctes()}, {_TRUE} SELECT count(*) AS true_pairs, 0::BIGINT AS false_pairs, TRUE AS most_found FROM tp")
def ml_minhash(spark, d):
    """Spark's own MinHash against the exact pairs: none is false, and nine of ten are found."""
    near = stage(D.exact_jaccard_pairs(docs(spark, d), threshold=0.7 - D.FEATURE_ERROR), "near")
    truth = near.where("jaccard >= 0.7D").select("a", "b", F.lit(1).alias("t"))
    x = truth.join(D.ml_minhash_pairs(docs(spark, d), near=near).withColumn("f", F.lit(1)), ["a", "b"], "full")
    sums = x.agg(F.count("t").alias("true_pairs"), F.count_if(F.col("t").isNull()).alias("false_pairs"), F.count_if(F.col("t").isNotNull() & F.col("f").isNotNull()).alias("found"))
    return sums.select("true_pairs", "false_pairs", (F.col("found") >= 0.9 * F.col("true_pairs")).alias("most_found"))


@query(f"WITH RECURSIVE {S.survivor_ctes()} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM surv")
def minhash_survivors(spark, d):
    return D.minhash_dedup(docs(spark, d)).select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


@query(f"WITH RECURSIVE {S.survivor_ctes()}, {S.rebuilt_ctes(source='SELECT doc_id, text FROM surv')} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM kept")
def adaptive_full(spark, d):
    return P.full_pipeline(docs(spark, d)).select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


@query(f"WITH RECURSIVE {S.survivor_ctes()}, {S.rebuilt_ctes(0, budget_sql='1', ties='strict', source='SELECT doc_id, text FROM surv')} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM kept")
def keep_one_full(spark, d):
    return P.keep_one_pipeline(docs(spark, d)).select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


# --- substring baseline -------------------------------------------------------------


@query(f"SELECT {S.shard(4)} AS shard, count(*) AS docs, sum(length(text))::BIGINT AS chars FROM documents GROUP BY 1")
def shard_sizes(spark, d):
    return B.assign_shard(docs(spark, d), 4).groupBy("shard").agg(F.count("*").alias("docs"), F.sum(F.length("text")).alias("chars"))


@query(f"WITH {S.kgram_ctes(shard_sql=S.shard(4))} SELECT doc_id, start, stop FROM sp")
def kgram_spans(spark, d):
    return B.kgram_spans(B.assign_shard(docs(spark, d), 4), 50, "shard")


@query(f"WITH {S.kgram_ctes(shard_sql=S.shard(4))} SELECT doc_id, start, stop FROM sp")
def winnowed_spans(spark, d):
    """Only places whose winnowed fingerprint repeats are counted; the spans are those of all k-grams."""
    return B.winnowed_spans(B.assign_shard(docs(spark, d), 4), 50, shard_col="shard")


@query(f"WITH {S.kgram_ctes(shard_sql=S.shard(64))} SELECT doc_id, start, stop FROM sp")
def suffix_spans(spark, d):
    """The suffix array of each of 64 shards must cover just what repeated k-grams cover."""
    return B.suffix_array_spans(B.assign_shard(docs(spark, d), 64), 50)


def _removed(name: str, shard_sql: str, n: int, keep_first: bool):
    @query(f"WITH {S.kgram_ctes(shard_sql=shard_sql, keep_first=keep_first)}, {S.cut_cte()} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM cutdoc", name=name)
    def run(spark, d):
        out = P.substring_pipeline(docs(spark, d), n, keep_first=keep_first, minhash=False)
        return out.select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


_removed("substring_removed", S.shard(4), 4, False)
_removed("substring_keep_first", S.shard(4), 4, True)
_removed("substring_global", "0", 1, False)


@query(f"WITH RECURSIVE {S.survivor_ctes()}, {S.kgram_ctes('surv', shard_sql=S.shard(4))}, {S.cut_cte('surv')} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM cutdoc")
def suffix_pipeline(spark, d):
    return P.substring_pipeline(docs(spark, d), 4).select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


@query(f"WITH {S.occ_ctes()}, s AS (SELECT *, {S.shard(10)} AS shard FROM occ) SELECT doc_id, pos FROM (SELECT *, count(*) OVER (PARTITION BY shard, h, norm_len) AS n FROM s) WHERE n = 1")
def singleton_only(spark, d):
    return B.singleton_only(B.assign_shard(occ_of(spark, d), 10)).select("doc_id", "pos")


_SENS = " UNION ALL ".join(f"SELECT '{by}' AS assigned_by, {n} AS n_shards, {S.shard(n, by)} AS shard, h, norm_len, raw_len FROM so" for by in ("hash", "source") for n in (1, 2, 5, 10, 33))


@query(f"WITH {S.occ_ctes()}, so AS (SELECT occ.*, source FROM occ JOIN documents USING (doc_id)), x AS ({_SENS}), gr AS (SELECT assigned_by, n_shards, count(*) AS n, sum(raw_len) AS c FROM x GROUP BY assigned_by, n_shards, shard, h, norm_len) SELECT assigned_by, n_shards::BIGINT AS n_shards, count_if(n = 1) AS kept_chunks, sum(CASE WHEN n = 1 THEN c ELSE 0 END)::BIGINT AS kept_chars, sum(n)::BIGINT AS chunks FROM gr GROUP BY ALL")
def shard_sensitivity(spark, d):
    return B.shard_sensitivity(occ_of(spark, d), docs(spark, d))


@query(f"WITH t AS (SELECT freq, unnest(range(1, freq + 1)) AS copy FROM (SELECT unnest([1, 2, 5, 10, 33]) AS freq)), u AS (SELECT freq, copy, unnest(range(1, 301)) AS trial FROM t), s AS (SELECT freq, trial, ('0x' || substr(md5('1-' || freq || '-' || copy || '-' || trial), 1, 8))::BIGINT % 10 AS shard FROM u), k AS (SELECT freq, trial, count_if(n = 1) AS kept FROM (SELECT freq, trial, shard, count(*) AS n FROM s GROUP BY ALL) GROUP BY ALL) SELECT freq::BIGINT AS freq, 10::BIGINT AS n_shards, round(avg(kept), 6) AS mean_kept, round(stddev_samp(kept), 6) AS sd_kept, round({S.g('freq', 10.0)}, 6) AS expected_kept FROM k GROUP BY freq")
def shard_simulation(spark, d):
    return B.simulate_sharding(spark, (1, 2, 5, 10, 33), 10, 300).select("freq", "n_shards", F.round("mean_kept", 6).alias("mean_kept"), F.round("sd_kept", 6).alias("sd_kept"), F.round("expected_kept", 6).alias("expected_kept"))


# --- measures -----------------------------------------------------------------------

_SIZE = f"count(*) AS docs, sum({S.tokens()})::BIGINT AS tokens, sum(length(text))::BIGINT AS chars"


@query(f"SELECT {_SIZE}, sum(octet_length(encode(text)))::BIGINT AS bytes FROM documents")
def corpus_size(spark, d):
    return M.corpus_size(docs(spark, d))


def _retention_sql(stages: list[tuple[str, str]]) -> str:
    rows = " UNION ALL ".join(f"SELECT {k}::BIGINT AS step, '{name}' AS setting, {_SIZE} FROM {source}" for k, (name, source) in enumerate(stages))
    return f"SELECT step, setting, docs, tokens, chars, round(100 * tokens / (max(CASE WHEN step = 0 THEN tokens END) OVER ())::DOUBLE, 6) AS token_percent, round(100 * chars / (max(CASE WHEN step = 0 THEN chars END) OVER ())::DOUBLE, 6) AS char_percent FROM ({rows})"


def _rounded(df):
    return df.withColumns({c: F.round(c, 6) for c in ("token_percent", "char_percent")})


@query(f"WITH {S.rebuilt_ctes()} {_retention_sql([('raw', 'documents'), ('adaptive', 'kept')])}")
def retention_report(spark, d):
    raw = docs(spark, d)
    return _rounded(M.retention_report(raw, {"adaptive": stage(P.adaptive_dedup(raw), "adaptive")}))


_PROFILE = "SELECT least(freq, 21) AS freq_bucket, sum(chars)::BIGINT AS chars, round(sum(chars) / (sum(sum(chars)) OVER ())::DOUBLE, 6) AS share FROM (SELECT count(*) AS freq, sum(raw_len) AS chars FROM occ GROUP BY h, norm_len) GROUP BY 1"


def _profile(name: str, kinds: tuple[str, ...]):
    @query(f"WITH {S.occ_ctes(tau=0, kinds=kinds)} {_PROFILE}", name=name)
    def run(spark, d):
        return M.frequency_profile(occ_of(spark, d, tau_seg=0, kinds=kinds)).withColumn("share", F.round("share", 6))


_profile("freq_profile_line", ("line",))
_profile("freq_profile_sentence", ("sentence",))


@query(f"WITH {S.occ_ctes()}, gc AS (SELECT count(*) AS freq, sum(raw_len) AS c FROM occ GROUP BY h, norm_len) SELECT " + ", ".join(f"round(sum(CASE WHEN freq BETWEEN {a} AND {b} THEN c ELSE 0 END) / sum(c)::DOUBLE, 6) AS {n}" for n, a, b in (("unique_share", 1, 1), ("low_share", 2, 4), ("middle_share", 5, 20), ("high_share", 21, 1 << 60))) + " FROM gc")
def freq_regimes(spark, d):
    r = M.frequency_regimes(occ_of(spark, d))
    return r.select(*(F.round(c, 6).alias(c) for c in r.columns))


_BINS = "CASE WHEN freq = 1 THEN '1' WHEN freq <= 4 THEN '2-4' WHEN freq <= 20 THEN '5-20' ELSE '>20' END AS freq_bin, CASE WHEN norm_len < 64 THEN '<64' WHEN norm_len < 128 THEN '64-127' WHEN norm_len < 512 THEN '128-511' ELSE '>=512' END AS len_bin"


@query(f"WITH {S.occ_ctes()}, b AS (SELECT *, {_BINS} FROM grp WHERE freq > 1) SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY freq_bin, len_bin ORDER BY h, norm_len) AS pick FROM b) WHERE pick <= 5")
def stratified_groups(spark, d):
    return hexed(M.sample_groups(count_groups(occ_of(spark, d))))


@query(f"""WITH {S.decision_ctes(TIGHT_SQL)}, r AS (SELECT *, last_pos - first_pos + 1 AS n, run_chars >= 100 AS gone FROM runs) SELECT (SELECT count(*) FROM occ) AS chunks, (SELECT sum(raw_len) FROM occ)::BIGINT AS chars, (SELECT count(*) FROM grp) AS groups, (SELECT count_if({TIGHT_SQL} < freq) FROM grp) AS active_groups,
count(*) AS runs, sum(n)::BIGINT AS candidate_chunks, sum(run_chars)::BIGINT AS candidate_chars, count_if(gone) AS deleted_runs, sum(CASE WHEN gone THEN n ELSE 0 END)::BIGINT AS deleted_chunks, sum(CASE WHEN gone THEN run_chars ELSE 0 END)::BIGINT AS deleted_chars, sum(CASE WHEN gone THEN 0 ELSE n END)::BIGINT AS restored_chunks, count(DISTINCT CASE WHEN gone THEN doc_id END) AS docs_touched FROM r""")
def deletion_report(spark, d):
    return M.deletion_report(occ_of(spark, d), TIGHT)


@query(f"WITH {S.decision_ctes(TIGHT_SQL)}, l AS (SELECT doc_id, max(pos) AS e FROM occ GROUP BY 1), x AS (SELECT runs.*, (first_pos > 0)::BIGINT + (last_pos < e)::BIGINT AS edges FROM runs JOIN l USING (doc_id)) SELECT sum(edges)::BIGINT AS edges_without_rule, sum(CASE WHEN run_chars >= 100 THEN edges ELSE 0 END)::BIGINT AS edges_with_rule, count(DISTINCT doc_id) AS docs_with_candidates FROM x")
def fragmentation(spark, d):
    return M.fragmentation_report(occ_of(spark, d), TIGHT)


def _values(which: str) -> str:
    benchmarks, rows = M.SCORES[which]
    return "(VALUES " + ", ".join(f"('{m}', '{b}', '{dom}', {s}::DOUBLE)" for m, scores in rows.items() for (b, dom), s in zip(benchmarks, scores, strict=True)) + ") s(method, benchmark, domain, score)"


def _averages(name: str, which: str):
    @query(f"SELECT method, round(avg(score), 6) AS average, round(avg(score) - (SELECT avg(score) FROM {_values(which)} WHERE method = 'raw'), 6) AS gain FROM {_values(which)} GROUP BY method", name=name)
    def run(spark, d):
        return M.macro_average(M.score_table(spark, which)).select("method", F.round("average", 6).alias("average"), F.round("gain", 6).alias("gain"))


_averages("score_averages", "web")
_averages("score_averages_code", "code")


@query(f"SELECT method, domain, round(avg(score), 4) AS mean_score FROM {_values('web')} GROUP BY ALL")
def score_domains(spark, d):
    return M.domain_means(M.score_table(spark)).withColumn("mean_score", F.round("mean_score", 4))


@query(f"SELECT *, dense_rank() OVER (PARTITION BY benchmark ORDER BY score DESC) AS place FROM {_values('web')}")
def score_ranks(spark, d):
    return M.rank_methods(M.score_table(spark))


@query("SELECT step::BIGINT AS step, step * 2000 * 4096 AS tokens FROM (SELECT unnest(range(2000, 36001, 2000)) AS step)")
def train_budget(spark, d):
    return spark.range(2000, 36001, 2000).select(F.col("id").alias("step"), (F.col("id") * 2000 * 4096).alias("tokens"))


@query(f"WITH {S.rebuilt_ctes(budget_sql=TIGHT_SQL)} SELECT quality, toxic, count(*) AS docs, sum(length(d.text))::BIGINT AS chars_before, sum(coalesce(length(kept.text), 0))::BIGINT AS chars_after FROM documents d JOIN labels l USING (doc_id) LEFT JOIN kept ON kept.doc_id = d.doc_id GROUP BY ALL")
def proxy_labels(spark, d):
    """Kept characters by label: a stand-in for training runs, not one of the published measures."""
    x = docs(spark, d)
    out = P.subdocument(x, TIGHT).select("doc_id", F.length("text").alias("after"))
    y = x.select("doc_id", F.length("text").alias("before")).join(table(spark, d, "labels"), "doc_id").join(out, "doc_id", "left")
    return y.groupBy("quality", "toxic").agg(F.count("*").alias("docs"), F.sum("before").alias("chars_before"), F.sum(F.coalesce("after", F.lit(0))).alias("chars_after"))


@query(f"WITH {S.rebuilt_ctes(budget_sql=TIGHT_SQL)} SELECT count(*) AS items, count_if(EXISTS (SELECT 1 FROM documents d WHERE contains(d.text, b.text))) AS in_raw, count_if(EXISTS (SELECT 1 FROM kept WHERE contains(kept.text, b.text))) AS in_kept FROM benchmark b")
def proxy_benchmark(spark, d):
    """Benchmark passages still contained after deletion: a stand-in, not one of the published measures."""
    x = docs(spark, d)
    out = stage(P.subdocument(x, TIGHT), "tight")
    b = table(spark, d, "benchmark")
    here = lambda df, name: M.contained_items(df, b).select("item_id", F.lit(1).alias(name))
    return b.join(here(x, "raw"), "item_id", "left").join(here(out, "kept"), "item_id", "left").agg(F.count("*").alias("items"), F.count("raw").alias("in_raw"), F.count("kept").alias("in_kept"))


# --- experiment workloads -----------------------------------------------------------


@query(f"WITH RECURSIVE {S.survivor_ctes()}, {S.occ_ctes(source='SELECT doc_id, text FROM surv', tau=0, kinds=('line',))} {_PROFILE}")
def w_freq_profile(spark, d):
    """The frequency profile of lines after document-level deduplication."""
    x = stage(D.minhash_dedup(docs(spark, d)), "survivors")
    return M.frequency_profile(P.occurrence_table(x, 0, ("line",))).withColumn("share", F.round("share", 6))


@query(f"WITH {S.occ_ctes()}, b AS (SELECT h, norm_len, freq, {_BINS} FROM grp WHERE freq > 1) SELECT freq_bin, len_bin, count(DISTINCT (h, norm_len)) AS groups, count(*) AS copies, count_if(quality = 1) AS good_copies, count_if(quality = 0) AS bad_copies FROM occ JOIN b USING (h, norm_len) LEFT JOIN labels USING (doc_id) GROUP BY ALL")
def w_strata(spark, d):
    occ = occ_of(spark, d)
    b = count_groups(occ).where("freq > 1").withColumns({"freq_bin": M.freq_bin(F.col("freq")), "len_bin": M.len_bin(F.col("norm_len"))})
    x = occ.join(b, ["h", "norm_len"]).join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    return x.groupBy("freq_bin", "len_bin").agg(F.count_distinct("h", "norm_len").alias("groups"), F.count("*").alias("copies"), F.count_if(F.col("quality") == 1).alias("good_copies"), F.count_if(F.col("quality") == 0).alias("bad_copies"))


_RN = (5.0, 10.0, 100 / 3, 50.0, 100.0, 500.0)


@query(f"SELECT n, freq, round({S.g('freq', 'n')} / freq, 6) AS r FROM (SELECT unnest(range(1, 101)) AS freq), (VALUES " + ", ".join(f"({n!r}::DOUBLE)" for n in _RN) + ") p(n)")
def w_r_family(spark, d):
    from ..functions.retention import kept_fraction

    x = spark.range(1, 101).select(F.col("id").alias("freq"), F.explode(F.array(*map(F.lit, _RN))).alias("n"))
    return x.select("n", "freq", F.round(kept_fraction(F.col("freq"), F.col("n")), 6).alias("r"))


@query(f"SELECT freq, len, round(greatest(1.0::DOUBLE, 1 + ({S.g('freq')} - 1) * {S.alpha('len')}), 6) AS budget, round(greatest(1.0::DOUBLE, 1 + ({S.g('freq')} - 1) * {S.alpha('len')}) / freq, 6) AS fraction FROM (SELECT unnest(range(1, 301)) AS freq), (SELECT unnest([0, 128, 256, 384, 512]) AS len)")
def w_budget_curves(spark, d):
    x = spark.range(1, 301).select(F.col("id").alias("freq"), F.explode(F.array(*(F.lit(v).cast("long") for v in (0, 128, 256, 384, 512)))).alias("len"))
    b = FINAL.real_budget(F.col("freq"), F.col("len"))
    return x.select("freq", "len", F.round(b, 6).alias("budget"), F.round(b / F.col("freq"), 6).alias("fraction"))


_SUB = "SELECT doc_id, text FROM surv"
_KEPT = {
    "raw": "documents",
    "doc_minhash": "surv",
    "minhash_suffix": f"(WITH {S.kgram_ctes('surv', shard_sql=S.shard(4))}, {S.cut_cte('surv')} SELECT doc_id, text FROM cutdoc)",
    "minhash_keep_one": f"(WITH {S.rebuilt_ctes(0, budget_sql='1', ties='strict', source=_SUB)} SELECT * FROM kept)",
    "adaptive": f"(WITH {S.rebuilt_ctes()} SELECT * FROM kept)",
    "minhash_adaptive": f"(WITH {S.rebuilt_ctes(source=_SUB)} SELECT * FROM kept)",
}


def _settings_sql(names: tuple[str, ...]) -> str:
    of = lambda q: f"coalesce(sum(CASE WHEN quality = {q} THEN length(coalesce(text, '')) END), 0)"
    rows = " UNION ALL ".join(f"SELECT {k}::BIGINT AS step, '{n}' AS setting, {_SIZE}, {of(1)} AS good, {of(0)} AS bad FROM {_KEPT[n]} x LEFT JOIN labels USING (doc_id)" for k, n in enumerate(names))
    part = lambda c: f"round(100 * {c} / (max(CASE WHEN step = 0 THEN {c} END) OVER ())::DOUBLE, 6)"
    return f"WITH RECURSIVE {S.survivor_ctes()} SELECT step, setting, docs, tokens, chars, {part('tokens')} AS token_percent, {part('chars')} AS char_percent, {part('good')} AS good_percent, {part('bad')} AS bad_percent FROM ({rows})"


@query(_settings_sql(tuple(_KEPT)))
def w_web_settings(spark, d):
    """The six settings on one corpus: sizes, retention and the stand-ins of each; also the comparison of granularities."""
    raw = docs(spark, d)
    doc = stage(D.minhash_dedup(raw), "survivors")
    return M.setting_report(raw, {"doc_minhash": doc, "minhash_suffix": stage(P.substring_pipeline(doc, 4, minhash=False), "s"), "minhash_keep_one": stage(P.keep_one(doc), "s"), "adaptive": stage(P.adaptive_dedup(raw), "s"), "minhash_adaptive": stage(P.adaptive_dedup(doc), "s")}, table(spark, d, "labels"))


_KEPT2 = S.rebuilt_ctes(source="SELECT doc_id, text FROM surv")


@query(f"WITH RECURSIVE {S.survivor_ctes()}, {_KEPT2} {_retention_sql([('raw', 'documents'), ('doc_minhash', 'surv'), ('minhash_adaptive', 'kept')])}")
def w_sizes(spark, d):
    """Corpus sizes after the document level and after the sub-document level, relative to the raw corpus."""
    raw = docs(spark, d)
    doc = stage(D.minhash_dedup(raw), "survivors")
    return _rounded(M.retention_report(raw, {"doc_minhash": doc, "minhash_adaptive": stage(P.adaptive_dedup(doc), "s")}))


@query(_settings_sql(("raw", "doc_minhash", "minhash_keep_one", "minhash_adaptive")))
def w_policy(spark, d):
    """Retention control at equal detection: keep-one and the adaptive budget on the same survivors and chunks."""
    raw = docs(spark, d)
    doc = stage(D.minhash_dedup(raw), "survivors")
    return M.setting_report(raw, {"doc_minhash": doc, "minhash_keep_one": stage(P.keep_one(doc), "s"), "minhash_adaptive": stage(P.adaptive_dedup(doc), "s")}, table(spark, d, "labels"))


def _deletion_sql(name: str, budget: str, ties: str, tau: int) -> str:
    r = "(SELECT *, last_pos - first_pos + 1 AS n, run_chars >= %d AS gone FROM runs)" % tau
    return f"(WITH {S.decision_ctes(budget, ties, source=_SUB)} SELECT '{name}' AS policy, (SELECT count(*) FROM occ) AS chunks, count(*) AS runs, sum(n)::BIGINT AS candidate_chunks, sum(CASE WHEN gone THEN n ELSE 0 END)::BIGINT AS deleted_chunks, sum(CASE WHEN gone THEN run_chars ELSE 0 END)::BIGINT AS deleted_chars, sum(CASE WHEN gone THEN 0 ELSE n END)::BIGINT AS restored_chunks, count(DISTINCT CASE WHEN gone THEN doc_id END) AS docs_touched FROM {r})"


@query(f"WITH RECURSIVE {S.survivor_ctes()} {_deletion_sql('keep_one', '1', 'strict', 0)} UNION ALL {_deletion_sql('adaptive', TIGHT_SQL, 'document', 100)}")
def w_policy_deletion(spark, d):
    """What each policy deletes and restores of the same chunks; the budget is small enough for small tables."""
    occ = P.occurrence_table(stage(D.minhash_dedup(docs(spark, d)), "survivors"))
    out = None
    for name, policy in (("keep_one", KeepOne()), ("adaptive", TIGHT)):
        row = M.deletion_report(occ, policy).select(F.lit(name).alias("policy"), "chunks", "runs", "candidate_chunks", "deleted_chunks", "deleted_chars", "restored_chunks", "docs_touched")
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT page_id, regexp_matches(lower(html), '<(pre|code|script|style)[ >]') OR contains(html, '```') OR (length(html) - length(translate(html, '{};', ''))) * 50 > length(html) AS code FROM pages")
def w_code_filter(spark, d):
    from ..operators.segment import is_code

    return table(spark, d, "pages").select("page_id", is_code(F.col("html")).alias("code"))


@query(f"WITH {CODE_KEPT}, code AS ({CODE_PAGES}) {_retention_sql([('raw', 'code'), ('adaptive_code', 'kept')])}")
def w_code_settings(spark, d):
    """Code-bearing pages: no deduplication against the adaptive setting with code kept whole."""
    raw = code_pages(spark, d)
    return _rounded(M.retention_report(raw, {"adaptive_code": stage(P.code_pipeline(raw, TIGHT), "s")}))


@query(f"WITH {S.occ_ctes()}, n AS (SELECT h, norm_len, count(DISTINCT doc_id) AS nd, count(*) AS freq FROM occ GROUP BY ALL), s AS (SELECT occ.*, freq, {S.shard(10)} AS shard FROM occ JOIN n USING (h, norm_len) WHERE nd = freq), k AS (SELECT freq, h, norm_len, count_if(c = 1) AS kept FROM (SELECT freq, h, norm_len, shard, count(*) AS c FROM s GROUP BY ALL) GROUP BY ALL) SELECT freq, count(*) AS groups, round(avg(kept), 6) AS mean_kept, round({S.g('freq', 10.0)}, 6) AS expected_kept FROM k GROUP BY freq")
def w_shard(spark, d):
    """Copies left by shard-local removal over ten shards, by frequency, beside the closed form.

    Only groups with one copy a document: copies of one document share a shard, which the closed form does not know.
    """
    from ..functions.retention import expected_kept

    occ = B.assign_shard(occ_of(spark, d), 10)
    apart = count_groups_with_docs(occ).where("n_docs = freq").select("h", "norm_len", "freq")
    k = occ.join(apart, ["h", "norm_len"]).groupBy("freq", "h", "norm_len", "shard").agg(F.count("*").alias("c")).groupBy("freq", "h", "norm_len").agg(F.count_if(F.col("c") == 1).alias("kept"))
    return k.groupBy("freq").agg(F.count("*").alias("groups"), F.round(F.avg("kept"), 6).alias("mean_kept")).select("freq", "groups", "mean_kept", F.round(expected_kept(F.col("freq"), 10.0), 6).alias("expected_kept"))


@query(f"WITH {S.rebuilt_ctes(budget_sql=TIGHT_SQL, source='SELECT conv_id * 1000 + turn AS doc_id, text FROM conversations')} SELECT doc_id, md5(text) AS text_md5, length(text) AS chars FROM kept")
def w_conversations(spark, d):
    x = table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), "text")
    return P.subdocument(x, TIGHT).where("text != ''").select("doc_id", F.md5("text").alias("text_md5"), F.length("text").alias("chars"))


def _template(spark, d):
    from .core_queries import _order_sentences

    x = _order_sentences(spark, d)
    return x.unionByName(x.select((F.col("doc_id") + 10_000_000).alias("doc_id"), F.concat("text", F.lit(" and the sentence goes on until it is long enough to be deleted at last.")).alias("text")))


def _template_sql() -> str:
    from .core_queries import _SENTENCE

    return f"SELECT o_orderkey AS doc_id, {_SENTENCE} AS text FROM orders UNION ALL SELECT o_orderkey + 10000000, {_SENTENCE} || ' and the sentence goes on until it is long enough to be deleted at last.' FROM orders"


@query(f"WITH {S.decision_ctes(source=_template_sql())} SELECT h, norm_len, freq, any_value(budget) AS budget, count_if(place > budget) AS candidates, count_if(place > budget AND raw_len >= 100) AS deleted FROM dec GROUP BY h, norm_len, freq")
def w_numeric_template(spark, d):
    """Template sentences that differ in numbers alone fold into a few large groups; the short rendering is restored."""
    from ..operators.deletion import initial_decision, with_budget

    occ = P.occurrence_table(_template(spark, d))
    g = with_budget(count_groups(occ), FINAL)
    c = initial_decision(occ, g.drop("budget"), FINAL).groupBy("h", "norm_len").agg(F.count("*").alias("candidates"), F.count_if(F.col("raw_len") >= 100).alias("deleted"))
    return hexed(g.join(c, ["h", "norm_len"], "left").select("h", "norm_len", "freq", "budget", F.coalesce("candidates", F.lit(0)).alias("candidates"), F.coalesce("deleted", F.lit(0)).alias("deleted")))


