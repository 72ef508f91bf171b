"""The registered queries of this subpackage, thin over its operators, with their SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..session import spread, stage
from . import perspectives, sharding
from .decontaminate import find_matches
from .html_text import extract
from .ngram_join import similar_components
from .ngram_lm import fit_and_score
from .packing import pack, word_lengths
from .quality import fit_measured, judge_measured, measured
from .sharding import place
from .token_files import read_ids, write_ids
from .warc import read_archives, write_archives


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(spark: SparkSession, sf_dir: str, name: str = "documents") -> DataFrame:
    """A table of long texts, worth dealing over idle cores where it is one small file."""
    return spread(table(spark, sf_dir, name))


def op1_deleted_interpolation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fit_and_score(texts(spark, sf_dir).select("doc_id", "text"), order=3)[0]


def op2_perspective_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return perspectives.rotate(table(spark, sf_dir, "conversations"))


def op3_token_group_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_components(texts(spark, sf_dir).select("doc_id", "text"))


def op4_isolation_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = stage(measured(texts(spark, sf_dir).select("doc_id", "text")), "quality-measured")
    return judge_measured(rows, fit_measured(rows, table(spark, sf_dir, "labels")))


def op5_variable_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(word_lengths(texts(spark, sf_dir)))


def op6_segment_reassembly(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder, files = write_archives(texts(spark, sf_dir, "pages"))
    return read_archives(spark, folder, files, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "error")


def op7_pigeonhole_edit_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_matches(texts(spark, sf_dir), table(spark, sf_dir, "benchmark"))


def op8_template_deduction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(texts(spark, sf_dir, "pages"))


def op9_bit_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    folder, files = write_ids(texts(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))
    return read_ids(spark, folder, files)


def op10_permutation_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return place(table(spark, sf_dir, "documents").select("doc_id"), "doc_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (
        op1_deleted_interpolation,
        op2_perspective_rotation,
        op3_token_group_join,
        op4_isolation_forest,
        op5_variable_best_fit,
        op6_segment_reassembly,
        op7_pigeonhole_edit_match,
        op8_template_deduction,
        op9_bit_packed_ids,
        op10_permutation_table,
    )
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op2_perspective_rotation": perspectives.ORACLE, "op10_permutation_table": sharding.oracle()}
