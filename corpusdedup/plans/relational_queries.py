"""Operators around the method: sources, joins, aggregates, windows, sets, functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators.counting import count_groups
from ..operators.deletion import deleted_positions
from ..operators.measures import freq_bin
from ..operators.segment import chunk_rows, segment
from ..session import fresh_path
from ..sources import io
from ..sources.html import html_to_text, html_to_text_sql
from ..sources.io import table
from . import pipelines as P
from . import sql as S
from .core_queries import TIGHT, TIGHT_SQL, docs, occ_of
from .registry import query


@query("SELECT lang, count(*) AS docs FROM documents WHERE source = 'src1' GROUP BY lang")
def scan_prune(spark, d):
    return docs(spark, d).where("source = 'src1'").groupBy("lang").agg(F.count("*").alias("docs"))


@query("SELECT doc_id, md5(text) AS text_md5, lang FROM documents")
def io_jsonl(spark, d):
    path = fresh_path(spark, "jsonl")
    io.write_jsonl(docs(spark, d).select("doc_id", "text", "lang", "source"), path)
    return io.read_jsonl(spark, path).select("doc_id", F.md5("text").alias("text_md5"), "lang")


@query("SELECT doc_id, md5(text) AS text_md5, lang FROM documents")
def io_roundtrip(spark, d):
    path = fresh_path(spark, "corpus")
    io.write_corpus(docs(spark, d), path, ("lang",))
    return spark.read.parquet(path).select("doc_id", F.md5("text").alias("text_md5"), F.col("lang").cast("string").alias("lang"))


@query(f"SELECT page_id, md5({html_to_text_sql('html')}) AS text_md5 FROM pages")
def html_text(spark, d):
    return table(spark, d, "pages").select("page_id", F.md5(html_to_text(F.col("html"))).alias("text_md5"))


@query("SELECT doc_id, length(text) AS chars, n_chars FROM documents")
def project_len(spark, d):
    return docs(spark, d).select("doc_id", F.length("text").alias("chars"), "n_chars")


@query("SELECT doc_id FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 500 AND 5000 AND regexp_matches(text, '[0-9]') AND source IS NOT DISTINCT FROM source")
def filter_predicates(spark, d):
    c = F.col
    return docs(spark, d).where(c("lang").isin("en", "de") & c("n_chars").between(500, 5000) & c("text").rlike("[0-9]") & c("source").eqNullSafe(c("source"))).select("doc_id")


@query("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(spark, d):
    n = F.broadcast(table(spark, d, "nation"))  # 25 rows by definition
    return table(spark, d, "customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("customers"))


@query("SELECT doc_id FROM documents SEMI JOIN labels USING (doc_id)")
def join_semi(spark, d):
    return docs(spark, d).join(table(spark, d, "labels"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
def join_anti(spark, d):
    return docs(spark, d).join(table(spark, d, "labels"), "doc_id", "left_anti").select("doc_id")


@query(f"WITH {S.rebuilt_ctes(budget_sql=TIGHT_SQL)} SELECT coalesce(d.doc_id, k.doc_id) AS doc_id, CASE WHEN k.doc_id IS NULL THEN 'gone' WHEN d.text = k.text THEN 'same' ELSE 'changed' END AS fate FROM documents d FULL JOIN kept k ON d.doc_id = k.doc_id")
def join_full_diff(spark, d):
    x = docs(spark, d).select("doc_id", F.md5("text").alias("before"))
    y = P.subdocument(docs(spark, d), TIGHT).where("text != ''").select("doc_id", F.md5("text").alias("after"))
    return x.join(y, "doc_id", "full").select("doc_id", F.when(F.col("after").isNull(), "gone").when(F.col("before") == F.col("after"), "same").otherwise("changed").alias("fate"))


_BANDS = [("short", 0, 500), ("middle", 500, 5000), ("long", 5000, 1 << 40)]


@query("SELECT band, count(*) AS docs FROM documents JOIN (VALUES " + ", ".join(f"('{n}', {a}, {b})" for n, a, b in _BANDS) + ") t(band, low, high) ON n_chars >= low AND n_chars < high GROUP BY band")
def join_range(spark, d):
    b = F.broadcast(spark.createDataFrame(_BANDS, "band string, low long, high long"))  # three rows
    return docs(spark, d).join(b, (F.col("n_chars") >= F.col("low")) & (F.col("n_chars") < F.col("high"))).groupBy("band").agg(F.count("*").alias("docs"))


@query("SELECT e.event_id, max(p.ts) AS last_purchase FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts GROUP BY e.event_id")
def asof_events(spark, d):
    """Each event with its user's last purchase so far, by one window instead of a range join."""
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    return table(spark, d, "events").select("event_id", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(w).alias("last_purchase"))


@query(f"WITH {S.decision_ctes(TIGHT_SQL)} SELECT c.doc_id, string_agg(c.pos, ',' ORDER BY c.pos) AS positions FROM cand c JOIN runs r ON r.doc_id = c.doc_id AND c.pos BETWEEN first_pos AND last_pos WHERE run_chars >= 100 GROUP BY c.doc_id")
def agg_collect(spark, d):
    gone = deleted_positions(P.runs_of(occ_of(spark, d), TIGHT))
    return gone.groupBy("doc_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list("pos")), lambda x: x.cast("string")), ",").alias("positions"))


@query(f"WITH {S.occ_ctes()} SELECT count(DISTINCT h) AS groups, count(DISTINCT doc_id) AS docs, max(norm_len) AS longest FROM occ")
def agg_distinct(spark, d):
    return occ_of(spark, d).agg(F.count_distinct("h").alias("groups"), F.count_distinct("doc_id").alias("docs"), F.max("norm_len").alias("longest"))


_LEVELS = "lang, source, grouping(lang) + 2 * grouping(source) AS level, count(*) AS docs, sum(n_chars)::BIGINT AS chars FROM documents"


def _levels(df):
    return df.agg((F.grouping("lang") + 2 * F.grouping("source")).alias("level"), F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))


@query(f"SELECT {_LEVELS} GROUP BY ROLLUP (lang, source)")
def rollup_retention(spark, d):
    return _levels(docs(spark, d).rollup("lang", "source"))


@query(f"SELECT {_LEVELS} GROUP BY CUBE (lang, source)")
def cube_retention(spark, d):
    return _levels(docs(spark, d).cube("lang", "source"))


@query(f"SELECT {_LEVELS} GROUP BY GROUPING SETS ((lang), (source), ())")
def gsets_retention(spark, d):
    return _levels(docs(spark, d).groupingSets([[F.col("lang")], [F.col("source")], []], "lang", "source"))


@query("SELECT lang, round(quantile_cont(n_chars, 0.5), 4) AS median, round(quantile_cont(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY lang")
def len_percentiles(spark, d):
    return docs(spark, d).groupBy("lang").agg(F.round(F.percentile("n_chars", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("p90"))


@query("SELECT source, count_if(lang = 'de') AS de, count_if(lang = 'en') AS en, count_if(lang = 'es') AS es, count_if(lang = 'fr') AS fr FROM documents GROUP BY source")
def score_pivot(spark, d):
    return docs(spark, d).groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count().na.fill(0)


@query("SELECT doc_id, ntile(10) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS decile FROM documents")
def len_ntile(spark, d):
    return docs(spark, d).select("doc_id", F.ntile(10).over(Window.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("decile"))


@query(f"WITH {S.chunk_ctes()} SELECT doc_id, pos, lag(length(text)) OVER w AS before, lead(length(text)) OVER w AS after FROM chunk WINDOW w AS (PARTITION BY doc_id ORDER BY pos)")
def chunk_neighbors(spark, d):
    w = Window.partitionBy("doc_id").orderBy("pos")
    return chunk_rows(segment(docs(spark, d))).select("doc_id", "pos", F.lag(F.length("text")).over(w).alias("before"), F.lead(F.length("text")).over(w).alias("after"))


@query(f"WITH {S.chunk_ctes()} SELECT doc_id, pos, coalesce(sum(length(text)) OVER (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM chunk")
def chunk_offsets(spark, d):
    w = Window.partitionBy("doc_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return chunk_rows(segment(docs(spark, d))).select("doc_id", "pos", F.coalesce(F.sum(F.length("text")).over(w), F.lit(0)).alias("start"))


@query(f"WITH {S.occ_ctes()} SELECT h, norm_len, freq FROM grp ORDER BY freq DESC, h, norm_len LIMIT 20")
def top_groups(spark, d):
    from ..operators.counting import count_groups
    from ..operators.segment import hexed

    return hexed(count_groups(occ_of(spark, d))).orderBy(F.desc("freq"), "h", "norm_len").limit(20)


def _set_query(name: str, word: str, method: str):
    @query(f"SELECT source, lang FROM documents WHERE n_chars < 3000 {word} SELECT source, lang FROM documents WHERE n_chars > 500", name=name)
    def run(spark, d):
        x = docs(spark, d)
        a, b = x.where("n_chars < 3000").select("source", "lang"), x.where("n_chars > 500").select("source", "lang")
        out = getattr(a, method)(b)
        return out.distinct() if method == "unionByName" else out


_set_query("setop_union", "UNION", "unionByName")
_set_query("setop_intersect", "INTERSECT", "intersect")
_set_query("setop_except", "EXCEPT ALL", "exceptAll")


@query("SELECT doc_id, length(text) AS chars, octet_length(encode(text)) AS bytes, substr(text, 3, 10) AS part, replace(lower(lang), 'e', 'E') AS marked, concat_ws('-', lang, source) AS joined, repeat(lang, 3) AS thrice, levenshtein(source, 'src10') AS edits FROM documents")
def fn_string(spark, d):
    return docs(spark, d).select("doc_id", F.length("text").alias("chars"), F.octet_length("text").alias("bytes"), F.substring("text", 3, 10).alias("part"), F.translate(F.lower("lang"), "e", "E").alias("marked"), F.concat_ws("-", "lang", "source").alias("joined"), F.repeat("lang", 3).alias("thrice"), F.levenshtein("source", F.lit("src10")).alias("edits"))


@query("SELECT doc_id, round(ln(n_chars + 1), 6) AS ln, ceil(n_chars / 7.0::DOUBLE)::BIGINT AS up, floor(n_chars / 7.0::DOUBLE)::BIGINT AS down, greatest(n_chars, 100) AS big, least(n_chars, 100) AS small, n_chars % 13 AS rest, n_chars & 15 AS bits, round(pow(0.97::DOUBLE, n_chars), 9) AS power FROM documents")
def fn_math(spark, d):
    n = F.col("n_chars")
    return docs(spark, d).select("doc_id", F.round(F.ln(n + 1), 6).alias("ln"), F.ceil(n / 7.0).alias("up"), F.floor(n / 7.0).alias("down"), F.greatest(n, F.lit(100)).alias("big"), F.least(n, F.lit(100)).alias("small"), F.pmod(n, F.lit(13)).alias("rest"), n.bitwiseAND(15).alias("bits"), F.round(F.pow(F.lit(0.97), n), 9).alias("power"))


@query("WITH x AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents) SELECT doc_id, len(list_distinct(w)) AS distinct_words, array_to_string(w[1:3], '|') AS head, len(list_filter(w, lambda x: length(x) > 5)) AS long_words, list_contains(w, 'the') AS has_the FROM x")
def fn_array(spark, d):
    x = docs(spark, d).select("doc_id", F.split("text", " ").alias("w"))
    return x.select("doc_id", F.size(F.array_distinct("w")).alias("distinct_words"), F.array_join(F.slice("w", 1, 3), "|").alias("head"), F.size(F.filter("w", lambda x: F.length(x) > 5)).alias("long_words"), F.array_contains("w", "the").alias("has_the"))


@query(f"WITH {S.occ_ctes()}, b AS (SELECT CASE WHEN freq = 1 THEN '1' WHEN freq <= 4 THEN '2-4' WHEN freq <= 20 THEN '5-20' ELSE '>20' END AS bin, count(*) AS n FROM grp GROUP BY 1) SELECT bin, n FROM b WHERE n > 1")
def fn_map(spark, d):
    """The histogram of frequencies as one map, filtered and exploded again."""
    from ..operators.counting import count_groups

    b = count_groups(occ_of(spark, d)).groupBy(freq_bin(F.col("freq")).alias("bin")).agg(F.count("*").alias("n"))
    m = b.agg(F.map_from_entries(F.collect_list(F.struct("bin", "n"))).alias("m"))
    return m.select(F.explode(F.map_filter("m", lambda k, v: v > 1)).alias("bin", "n"))


@query("SELECT event_id, (props::JSON ->> '$.k')::BIGINT AS k FROM events")
def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT date_trunc('hour', ts) AS hour, count(*) AS events, (floor(epoch(max(ts))) - floor(epoch(min(ts))))::BIGINT AS seconds FROM events GROUP BY 1")
def fn_date(spark, d):
    return table(spark, d, "events").groupBy(F.date_trunc("hour", "ts").alias("hour")).agg(F.count("*").alias("events"), (F.unix_timestamp(F.max("ts")) - F.unix_timestamp(F.min("ts"))).alias("seconds"))


@query("SELECT event_id, (props::JSON ->> '$.k')::BIGINT AS k, json_type(props) = 'OBJECT' AS is_object FROM events")
def fn_variant(spark, d):
    v = F.parse_json(F.col("props"))
    return table(spark, d, "events").select("event_id", F.variant_get(v, "$.k", "long").alias("k"), F.schema_of_variant(v).startswith("OBJECT").alias("is_object"))


@query(f"WITH {S.occ_ctes()} SELECT floor(norm_len / 64)::BIGINT AS band, sum({S.budget(n=2.0)})::BIGINT AS budget FROM grp GROUP BY 1")
def agg_udaf(spark, d):
    """A grouped-aggregate Arrow UDF that sums budgets, as a check of the built-in expression from outside the JVM."""
    import math

    q, full = 1 - 1 / TIGHT.n, TIGHT.full_length

    @F.pandas_udf("long")
    def budgets(freq: pd.Series, length: pd.Series) -> int:
        return sum(min(c, max(1, math.ceil(1 + (c * q ** (c - 1) - 1) * max(0.0, 1 - n / full)))) for c, n in zip(freq.tolist(), length.tolist(), strict=True))

    return count_groups(occ_of(spark, d)).groupBy(F.floor(F.col("norm_len") / 64).alias("band")).agg(budgets("freq", "norm_len").alias("budget"))


@query(f"WITH {S.chunk_ctes()} SELECT doc_id, pos, text, 'prose' AS kind FROM chunk")
def udtf_segment(spark, d):
    """Segmentation as a table function for SQL users; the documents hold no fence."""
    from ..streaming.streams import register_segment_udtf

    register_segment_udtf(spark)
    docs(spark, d).createOrReplaceTempView("udtf_documents")
    return spark.sql("SELECT d.doc_id, s.pos, s.text, s.kind FROM udtf_documents d, LATERAL segment_text(d.text, 32) s")
