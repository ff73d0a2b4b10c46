"""Language of a text by rank-order profiles of character n-grams and the out-of-place distance.

Every letter of any script is a symbol of its own, every run of other characters one word edge, and grams of one to
three symbols are packed into an integer. A text's most frequent grams, in order of frequency, are compared to each
language's list: each gram adds how far its place differs, or the list's length if it is missing.

Cases: null text, or text without a letter (numerals such as a half are none): ``und`` with score 0; ties between grams
go to the smaller gram, ties between languages to the first by name; rows without a language take no part in learning;
without any learned language every row is ``und``; repeated rows give repeated rows; a text of any length is read whole.
Only the named columns are read.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from localcoef.llm.textcore import text_blocks

UNDETERMINED = "und"
PROFILE_GRAMS = 400
#: The fit reads about this many documents of each language, chosen by a hash of their id.
SAMPLE_DOCUMENTS = 1000
#: The word edge, and the bits of a symbol in a packed gram.
_EDGE, _BITS = 32, 21


@dataclass
class Profiles:
    """For each language its grams, most frequent first."""

    names: list[str]
    grams: list[list[int]]
    size: int = PROFILE_GRAMS

    def prepared(self):
        """The grams of each language in rising order, with their places."""
        lists = []
        for g in self.grams:
            order = np.argsort(np.array(g, np.int64), kind="stable")
            lists.append((np.array(g, np.int64)[order], order))
        return lists


@lru_cache(1)
def _symbol_table() -> np.ndarray:
    return np.fromiter((c if chr(c).isalpha() else _EDGE for c in range(0x110000)), np.int64, 0x110000)


def symbols(text: str) -> np.ndarray:
    """Symbols of a text between two edges, a run of edges as one."""
    codes = _symbol_table()[np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)]
    codes = np.concatenate([[_EDGE], codes, [_EDGE]])
    keep = np.ones(len(codes), bool)
    keep[1:] = (codes[1:] != _EDGE) | (codes[:-1] != _EDGE)
    return codes[keep]


def packed(gram: str) -> int:
    value = 0
    for c in gram:
        value = value << _BITS | ord(c)
    return value


def grams(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct packed grams of one to three symbols, none across a word edge, with their counts."""
    one = codes[codes != _EDGE]
    two = codes[:-1] << _BITS | codes[1:]
    inner = codes[1:-1] != _EDGE
    three = (two[:-1] << _BITS | codes[2:])[inner]
    every = np.concatenate([one, two, three])
    every.sort()
    if not len(every):
        return every, every
    cut = np.flatnonzero(np.concatenate([[True], every[1:] != every[:-1]]))
    return every[cut], np.diff(np.concatenate([cut, [len(every)]]))


def most_frequent(codes: np.ndarray, counts: np.ndarray, size: int) -> np.ndarray:
    """Up to ``size`` grams by falling count, then by gram."""
    if len(counts) > size:  # only grams that are as frequent as the last one taken can count
        often = counts >= np.partition(counts, len(counts) - size)[len(counts) - size]
        codes, counts = codes[often], counts[often]
    return codes[np.argsort(-counts, kind="stable")[:size]]


def distances(top: np.ndarray, lists, size: int) -> np.ndarray:
    place = np.arange(len(top))
    out = np.empty(len(lists))
    for k, (codes, ranks) in enumerate(lists):
        at = np.minimum(np.searchsorted(codes, top), max(len(codes) - 1, 0))
        hit = codes[at] == top if len(codes) else np.zeros(len(top), bool)
        out[k] = np.where(hit, np.minimum(np.abs(ranks[at] - place), size) if len(codes) else 0, size).sum()
    return out


def _fit_counts(batches):
    """Per language, how often each letter-level gram (as text, edges as blanks) occurs in the batch."""
    for batch in batches:
        langs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
        total: dict[str, Counter] = {}
        for lang, text in zip(langs, texts, strict=True):
            words = Counter("".join(c if c.isalpha() else " " for c in (text or "").lower()).split())
            mine = total.setdefault(lang, Counter())
            for word, n in words.items():
                padded = f" {word} "
                for size in (1, 2, 3):
                    for i in range(len(padded) - size + 1):
                        if (gram := padded[i : i + size]) != " ":
                            mine[gram] += n
        rows = [(lang, gram, n) for lang, mine in total.items() for gram, n in mine.items()]
        yield pa.RecordBatch.from_arrays(
            [pa.array(x, kind) for x, kind in zip(zip(*rows, strict=True) if rows else ([], [], []), (pa.string(), pa.string(), pa.int64()), strict=True)],
            ["lang", "gram", "n"],
        )


def fit(docs: DataFrame, learn: Column, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", sample: int = SAMPLE_DOCUMENTS, size: int = PROFILE_GRAMS) -> Profiles:
    """Profiles from the rows where ``learn`` holds and the language is known.

    ``sample`` bounds the fit: of each language about that many documents are read, by a hash of the id, so the
    share falls as the table grows. What comes to the driver is ``size`` grams for each language.
    """
    at = F.pmod(F.xxhash64(F.col(id_col).cast("string"), F.col(text_col)), F.lit(1 << 30))
    known = docs.where(learn & F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"), at.alias("at"))
    share = known.groupBy("lang").agg(((1 << 30) * F.lit(float(sample)) / F.count("*")).alias("share"))
    # one row for each language, far less than the profiles that every worker gets
    chosen = known.join(F.broadcast(share), "lang").where(F.col("at") < F.col("share") + 1).select("lang", "text")
    counts = chosen.mapInArrow(_fit_counts, "lang string, gram string, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    # the most frequent grams of a language, of a bounded number of texts
    best = counts.groupBy("lang").agg(F.expr(f"slice(sort_array(collect_list(struct(-n AS n, gram))), 1, {size})").alias("top"))
    tops = {r["lang"]: [(-x["n"], packed(x["gram"])) for x in r["top"]] for r in best.collect()}
    names = sorted(tops)
    return Profiles(names, [[g for _, g in sorted(tops[name], key=lambda x: (-x[0], x[1]))] for name in names], size)


def classify(texts: list[str | None], profiles: Profiles, lists) -> tuple[list[str], list[float]]:
    names, scores = [], []
    for text in texts:
        codes = symbols(text) if lists and text else ()
        if len(codes) < 2:  # one edge and no letter
            names.append(UNDETERMINED)
            scores.append(0.0)
            continue
        top = most_frequent(*grams(codes), profiles.size)
        far = distances(top, lists, profiles.size)
        best = int(far.argmin())
        names.append(profiles.names[best])
        scores.append(1.0 - float(far[best]) / (len(top) * profiles.size))
    return names, scores


def predict(docs: DataFrame, profiles: Profiles, text_col: str = "text", id_col: str = "doc_id", keep: list[str] | None = None) -> DataFrame:
    """Per row: the kept columns (the id unless given), lang_pred and score."""
    keep, text = keep if keep is not None else [id_col], [F.col(text_col).cast("string").alias("__text")]
    inside = None
    if "." in text_col:  # the text is in a kept struct and need not be sent twice
        text, inside = [], text_col.split(".", 1)[1]
    model = docs.sparkSession.sparkContext.broadcast(profiles)
    schema = T.StructType([*docs.select(*keep).schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def run(batches):
        ready = None
        for batch in batches:
            if ready is None:
                ready = model.value.prepared()
            names, scores = [], []
            last = batch.column(batch.num_columns - 1)
            for _, _, texts in text_blocks(last.field(inside) if inside else last):
                for out, got in zip((names, scores), classify(texts, model.value, ready), strict=True):
                    out += got
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(names, pa.string()), pa.array(scores, pa.float64())], [*keep, "lang_pred", "score"])

    return docs.select(*keep, *text).mapInArrow(run, schema)


def held_out(id_col: str = "doc_id") -> Column:
    return F.crc32(F.col(id_col).cast("string")) % 3 == 1


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Per row: id, held_out, lang_pred, score; learned from the rows that are not held out."""
    profiles = fit(docs, ~F.coalesce(held_out(id_col), F.lit(True)), text_col, lang_col, id_col)
    marked = docs.select(F.col(id_col), F.coalesce(held_out(id_col), F.lit(False)).alias("held_out"), F.col(text_col))
    return predict(marked, profiles, text_col, id_col, [id_col, "held_out"])
