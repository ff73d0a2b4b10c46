"""Removal of repeated passages of lines, by overlapping windows of three lines, with DataFrame functions only.

A line counts if it has a word. Three such lines in a row form a window; a window whose lines equal those of an
earlier one, by (id, position), is a later occurrence, and every line that a later occurrence covers goes.

Cases: null or empty text has no lines and stays as it is; a text of fewer than three counted lines stays; rows with
the same id and text are taken as one and share their fate; a null id is an id of its own and comes first; an empty
table gives an empty table. Extra columns of any name are neither read nor lost by ``without_repeated_lines``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The white space that separates words.
BLANKS = " \t\n\x0b\f\r"


def _trimmed(line: Column) -> Column:
    return F.btrim(line, F.lit(BLANKS))


def _windows(base: DataFrame) -> DataFrame:
    """One row for each window: id, text key, its three line numbers, and 128 bits of its lines."""
    lines = F.filter(
        F.transform(F.split("text", "\n", -1), lambda x, i: F.struct(i.alias("i"), _trimmed(x).alias("s"))),
        lambda x: x["s"] != "",
    )
    hashed = F.transform(lines, lambda x: F.struct(x["i"].alias("i"), F.xxhash64(x["s"]).alias("a"), F.xxhash64(F.lit(7), x["s"]).alias("b")))
    triples = F.transform(
        F.sequence(F.lit(0), F.size("h") - 3),
        lambda k: F.struct(*[F.get("h", k + d)["i"].alias(f"i{d}") for d in range(3)], F.xxhash64(*[F.get("h", k + d)["a"] for d in range(3)]).alias("wa"), F.xxhash64(*[F.get("h", k + d)["b"] for d in range(3)]).alias("wb")),
    )
    return base.withColumn("h", hashed).where(F.size("h") >= 3).select("id", "key", F.inline(triples))


def later_windows(base: DataFrame) -> DataFrame:
    """Windows that repeat an earlier one; ``base`` has the columns id, key and text."""
    spot = F.struct("id", "key", "i0")
    windows = _windows(base)
    first = windows.groupBy("wa", "wb").agg(F.min(spot).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    # a third key makes both sides of the join shuffles of their own, which can be split where one window is very frequent
    first, windows = (x.withColumn("wc", F.hash("wa", "wb")) for x in (first, windows))
    return windows.join(first, ["wa", "wb", "wc"]).where(~spot.eqNullSafe(F.col("first"))).select("id", "key", "i0", "i1", "i2")


def repeated_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For each (id, key) with a removal: ``covered``, the numbers of the lines to remove."""
    base = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.col(text_col)).alias("key"), F.col(text_col).cast("string").alias("text"))
    return later_windows(base).groupBy("id", "key").agg(F.array_distinct(F.flatten(F.collect_set(F.array("i0", "i1", "i2")))).alias("covered"))


def _kept_text(text: Column, covered: Column) -> Column:
    lines = F.split(text, "\n", -1)
    left = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), covered)
    return F.when(covered.isNull(), text).otherwise(F.array_join(F.transform(left, lambda i: F.get(lines, i)), "\n"))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id, the counted lines before, the lines removed, and the text that is left."""
    found = repeated_lines(docs, id_col, text_col)
    rows = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("text"), F.xxhash64(F.col(text_col)).alias("key"))
    joined = rows.join(found, rows[id_col].eqNullSafe(found["id"]) & (rows["key"] == found["key"]), "left")
    counted = F.size(F.filter(F.split(F.coalesce(rows["text"], F.lit("")), "\n", -1), lambda x: _trimmed(x) != ""))
    return joined.select(
        rows[id_col],
        counted.cast("long").alias("n_lines"),
        F.coalesce(F.size("covered"), F.lit(0)).cast("long").alias("n_removed"),
        _kept_text(rows["text"], F.col("covered")).alias("text"),
    )


def without_repeated_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chars_col: str = "n_chars") -> DataFrame:
    """The rows with all their columns and their text cut; a row left without a word goes, as its content is elsewhere."""
    found = repeated_lines(docs, id_col, text_col)
    rows = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), F.xxhash64(F.col(text_col)).alias("key"))
    joined = rows.join(found, F.col(f"row.{id_col}").eqNullSafe(found["id"]) & (rows["key"] == found["key"]), "left")
    text = _kept_text(F.col(f"row.{text_col}"), F.col("covered"))
    changed = joined.withColumn("__text", text).where(F.col("covered").isNull() | (_trimmed(F.col("__text")) != ""))
    out = []
    for c in docs.columns:
        if c == text_col:
            out.append(F.col("__text").alias(c))
        elif c == chars_col:
            out.append(F.when(F.col("covered").isNull(), F.col(f"row.{c}")).otherwise(F.char_length("__text").cast(docs.schema[c].dataType)).alias(c))
        else:
            out.append(F.col(f"row.`{c}`").alias(c))
    return changed.select(*out)


ORACLE = """
WITH line AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS raw, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS i FROM documents
), counted AS (
  SELECT doc_id, i, trim(raw, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS s FROM line
), w AS (
  SELECT doc_id, i AS i0, lead(i, 1) OVER o AS i1, lead(i, 2) OVER o AS i2, s AS s0, lead(s, 1) OVER o AS s1, lead(s, 2) OVER o AS s2
  FROM counted WHERE s <> '' WINDOW o AS (PARTITION BY doc_id ORDER BY i)
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY s0, s1, s2 ORDER BY doc_id, i0) AS r FROM w WHERE i2 IS NOT NULL
), gone AS (
  SELECT doc_id, i0 AS i FROM ranked WHERE r > 1 UNION SELECT doc_id, i1 FROM ranked WHERE r > 1 UNION SELECT doc_id, i2 FROM ranked WHERE r > 1
), kept AS (
  SELECT l.doc_id, string_agg(l.raw, chr(10) ORDER BY l.i) AS text FROM line l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.i = l.i WHERE g.i IS NULL GROUP BY l.doc_id
), n AS (SELECT doc_id, count(*) AS n FROM counted WHERE s <> '' GROUP BY doc_id), m AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_lines, coalesce(m.n, 0)::BIGINT AS n_removed,
  CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(k.text, '') END AS text
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN m ON m.doc_id = d.doc_id LEFT JOIN kept k ON k.doc_id = d.doc_id
"""
