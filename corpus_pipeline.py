"""A corpus in five stages: language, repeated lines, near duplicates, benchmark passages, token ids.

Each stage takes all documents that the one before kept, and is written to the shared folder and read again. The first
four return the columns of documents; the last returns what the codec reports of each document.

Cases: a document without a letter goes in the first stage, so a null or empty text does; a document whose lines are
all later occurrences goes in the second; extra columns, whatever their names, pass through the first four stages;
repeated rows with one id and one text stay together in the near-duplicate stage, and of rows with one id and different
texts each is judged by its text; documents without an id stay there; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcoef.llm.bpe import encode_documents
from localcoef.llm.decontam import contamination
from localcoef.llm.language import UNDETERMINED, fit, predict
from localcoef.llm.lines import without_repeated_lines
from localcoef.llm.neardup import near_duplicates
from localcoef.llm.queries import BYTE_BPE, table, vocabulary
from localcoef.llm.store import small_batches, written
from localcoef.ship import ship

#: A document whose best language is this far from its profile's order is rejected; clean prose scores 0.4 and more.
LEAST_SCORE = 0.2
#: Rows of near duplicates up to this number, of sixteen bytes each, are broadcast; more are shuffled.
BROADCAST_IDS = 1_000_000


def _packed(docs: DataFrame) -> DataFrame:
    """All columns in one, so that no name of theirs can clash."""
    return docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("__row"))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents whose language can be told."""
    small_batches(spark)
    found = predict(_packed(docs), fit(docs, F.lit(True)), "__row.text", keep=["__row"])
    return found.where((F.col("lang_pred") != UNDETERMINED) & (F.col("score") >= LEAST_SCORE)).select("__row.*")


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts later occurrences of three lines in a row."""
    return without_repeated_lines(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the least id of each group of near duplicates."""
    found = near_duplicates(docs, with_key=True).where("not kept")
    gone = written(found.select(F.col("doc_id").alias("__gone"), F.col("text_key").alias("__key")).distinct(), "gone")
    few = gone.count() <= BROADCAST_IDS
    same = (docs["doc_id"] == gone["__gone"]) & (F.xxhash64(docs["text"]) == gone["__key"])
    return docs.join(F.broadcast(gone) if few else gone, same, "left_anti")


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark item."""
    found = contamination(_packed(docs), table(spark, sf_dir, "benchmark"), text_col="__row.text", keep=["__row"])
    return found.where("coverage is null").select("__row.*")


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Encodes and decodes every document."""
    return encode_documents(docs, vocabulary(BYTE_BPE))


STAGES = [("language", language), ("lines", lines), ("near", near), ("benchmark", benchmark), ("tokens", tokens)]

#: The token stage cannot be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
