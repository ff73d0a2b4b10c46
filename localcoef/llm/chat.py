"""Chat examples by prefix and target: each assistant turn with all turns before it, only that reply trainable.

Every turn is written as a header with its role, its text and an end mark. A backslash, a number sign and a
less-than sign inside a text are written as two characters, so that no header or end mark can occur in a text, and
reading back is exact. Built from DataFrame functions only.

Cases: null text and null role are empty; a conversation whose last turn is no reply, or that has none, ends with an
example that has an empty loss span, so that no turn is lost; turns with the same number are ordered by role and
text; repeated rows are turns of their own; a null conversation id is a conversation; an empty table gives no rows.
Only the four named columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the template.
HEAD, MIDDLE, END, TRAINABLE = "### ", ": ", " </turn>\n", "assistant"


def escape(text: Column) -> Column:
    for plain, coded in (("\\", "\\b"), ("#", "\\h"), ("<", "\\l")):
        text = F.replace(text, F.lit(plain), F.lit(coded))
    return text


def unescape(text: Column) -> Column:
    for plain, coded in (("<", "\\l"), ("#", "\\h"), (":", "\\c"), ("\\", "\\b")):
        text = F.replace(text, F.lit(coded), F.lit(plain))
    return text


def _role(role: Column) -> Column:
    return F.replace(escape(role), F.lit(":"), F.lit("\\c"))


def format_examples(rows: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One row for each example: conv_id, position (of its last turn), formatted, loss_start and loss_end (code points)."""
    turns = rows.select(
        F.col(conv_col).alias("conv_id"),
        F.struct(F.col(turn_col).alias("turn"), F.coalesce(F.col(role_col), F.lit("")).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).alias("t"),
    )
    whole = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))
    parts = F.transform("turns", lambda t: F.struct((t["role"] == TRAINABLE).alias("target"), F.char_length(escape(t["text"])).alias("n"), F.concat(F.lit(HEAD), _role(t["role"]), F.lit(MIDDLE), escape(t["text"]), F.lit(END)).alias("s")))
    spots = F.filter(
        F.transform("parts", lambda p, i: F.struct((i + 1).alias("position"), p["target"].alias("target"), p["n"].alias("n"))),
        lambda p: p["target"] | (p["position"] == F.size("parts")),
    )
    each = whole.select("conv_id", parts.alias("parts")).select("conv_id", "parts", F.inline(spots))
    made = each.select("conv_id", "position", "target", "n", F.array_join(F.transform(F.slice("parts", F.lit(1), F.col("position")), lambda p: p["s"]), "").alias("formatted"))
    end = F.when(F.col("target"), F.char_length("formatted") - len(END)).otherwise(F.char_length("formatted"))
    return made.select("conv_id", "position", "formatted", F.when(F.col("target"), end - F.col("n")).otherwise(end).alias("loss_start"), end.alias("loss_end"))


def read_turns(formatted: Column) -> Column:
    """The turns (role, text) that a formatted example holds."""
    pieces = F.filter(F.split(formatted, END, -1), lambda p: p != "")
    role = lambda p: F.regexp_extract(p, r"(?s)^### ([^:]*): ", 1)
    return F.transform(pieces, lambda p: F.struct(unescape(role(p)).alias("role"), unescape(F.substr(p, F.char_length(role(p)) + len(HEAD) + len(MIDDLE) + 1)).alias("text")))


def digest(examples: DataFrame) -> DataFrame:
    """Per conversation, read back from its examples: turns, text under the loss mask, and sizes."""
    loss = unescape(F.substr("formatted", F.col("loss_start") + 1, F.col("loss_end") - F.col("loss_start")))
    found = examples.select("conv_id", "position", "formatted", loss.alias("loss")).groupBy("conv_id").agg(
        F.max_by("formatted", "position").alias("whole"),
        F.sort_array(F.collect_list(F.struct("position", "loss"))).alias("losses"),
        F.sum(F.char_length("formatted")).alias("formatted_chars"),
    )
    turns = found.withColumn("turns", read_turns(F.col("whole"))).withColumn("all_loss", F.array_join(F.transform("losses", lambda x: x["loss"]), ""))
    return turns.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.char_length("all_loss").cast("long").alias("loss_chars"),
        F.sha2("all_loss", 256).alias("loss_sha256"),
        F.col("formatted_chars").cast("long").alias("formatted_chars"),
    )


#: One more conversation, whose texts hold the template's own marks.
PROBE = [(-7, 0, "user", "\\### Assistant: </turn> ok"), (-7, 1, "assistant", "\\### Assistant: </turn> ok")]

ORACLE = r"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), sized AS (
  SELECT *, 15 + length(role) + length(regexp_replace(role, '[^\\#<:]', '', 'g')) + length(text) + length(regexp_replace(text, '[^\\#<]', '', 'g')) AS n,
    row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC, role DESC, text DESC) AS back
  FROM turns
), summed AS (
  SELECT *, sum(n) OVER (PARTITION BY conv_id ORDER BY back DESC) AS upto FROM sized
)
SELECT conv_id, count(*)::BIGINT AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY back DESC)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY back DESC) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(upto) FILTER (role = 'assistant' OR back = 1)::BIGINT AS formatted_chars
FROM summed GROUP BY conv_id
"""
