"""The registered queries of the text operators; each reads its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from localcoef.llm.chat import ORACLE as CHAT_SQL
from localcoef.llm.lines import ORACLE as LINES_SQL
from localcoef.llm.store import small_batches
from localcoef.ship import ship

BYTE_BPE, PIECE_BPE = "byte_bpe_50k.json", "piece_bpe_32k.model"


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op6_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.bpe import encode_documents

    return encode_documents(table(spark, sf_dir, "documents"), vocabulary(BYTE_BPE))


def op1_suffix_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.substrings import remove_repeats

    return remove_repeats(table(spark, sf_dir, "documents"))


def op2_repetition_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.quality import score_quality

    return score_quality(table(spark, sf_dir, "documents"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.lines import dedup_lines

    return dedup_lines(table(spark, sf_dir, "documents"))


def op4_string_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.decontam import contamination

    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.withColumn("kept", found["coverage"].isNull())


def op5_language_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.language import detect

    return detect(table(spark, sf_dir, "documents"))


def op7_best_path_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.counts import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), vocabulary(PIECE_BPE))


def op8_lsh_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.neardup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op9_host_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.wrappers import extract_pages

    return extract_pages(table(spark, sf_dir, "pages"))


def op10_chat_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    from localcoef.llm.chat import PROBE, digest, format_examples

    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return digest(format_examples(given.unionByName(spark.createDataFrame(PROBE, given.schema))))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_suffix_automata": op1_suffix_automata,
    "op2_repetition_rules": op2_repetition_rules,
    "op3_line_dedup": op3_line_dedup,
    "op4_string_tiling": op4_string_tiling,
    "op5_language_profiles": op5_language_profiles,
    "op6_bpe_codec": op6_bpe_codec,
    "op7_best_path_counts": op7_best_path_counts,
    "op8_lsh_forest": op8_lsh_forest,
    "op9_host_wrappers": op9_host_wrappers,
    "op10_chat_examples": op10_chat_examples,
}

ORACLE_SQL: dict[str, str] = {"op3_line_dedup": LINES_SQL, "op10_chat_examples": CHAT_SQL}
