"""Quality rules on whole texts: repeated passages by suffix array and longest-common-prefix intervals.

The words of a block of documents form one integer sequence with a different end mark after each document, so no
common prefix crosses a document. The suffix array comes from prefix doubling over the still undecided suffixes;
the longest common prefixes of neighbours come from the ranks kept of each doubling step. A maximal repeat starts at
a suffix with the longer of its two neighbour prefixes; the union of these spans is the repeated part.

A block is about 256 KB of texts or one longer text. For a text of n words the ranks take 4 bytes a word for each
doubling step, of which there are log2 of its longest repeat, so at most 4 * 25 * n bytes.

Cases: null or empty text has no words and fails the word rule; a text of one word has no repeat; repeated rows
give repeated rows; an empty table gives an empty table. Only the named columns are read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.textcore import WordBlock, mix, text_blocks

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True


@dataclass(frozen=True)
class Rules:
    """Limits of the verdict; ``min_words`` and ``repeat_percent`` are those of the base rules."""

    min_words: int = 50
    repeat_percent: int = 50
    #: A repeat counts for the verdict from this many words on.
    long_repeat: int = 6
    #: Of all words, at most this share may lie in such repeats.
    covered: float = 0.3
    #: No repeat may be longer than this share of the text.
    longest: float = 0.2


def suffix_ranks(values: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Suffix array of an integer sequence and the rank of each position after each doubling step."""
    n = len(values)
    _, rank = np.unique(values, return_inverse=True)
    rank = rank.astype(np.int64)
    order = np.argsort(rank, kind="stable")
    rank = _head_ranks(rank[order], order, n)
    levels = [rank.astype(np.int32)]
    width = 1
    while True:
        sorted_rank = rank[order]
        same = sorted_rank[1:] == sorted_rank[:-1]
        tied = np.concatenate([same, [False]]) | np.concatenate([[False], same])
        spots = np.flatnonzero(tied)
        if not len(spots):
            return order, levels
        pos = order[spots]
        nxt = pos + width
        second = np.where(nxt < n, rank[np.minimum(nxt, n - 1)], -1)
        key = rank[pos] * (n + 1) + second + 1
        by = np.argsort(key, kind="stable")
        order[spots] = pos[by]
        key = key[by]
        fresh = np.concatenate([[True], key[1:] != key[:-1]])
        head = np.maximum.accumulate(np.where(fresh, spots, 0))
        rank = rank.copy()
        rank[pos[by]] = head
        levels.append(rank.astype(np.int32))
        width *= 2


def _head_ranks(sorted_values: np.ndarray, order: np.ndarray, n: int) -> np.ndarray:
    fresh = np.concatenate([[True], sorted_values[1:] != sorted_values[:-1]])
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(fresh, np.arange(n), 0))
    return rank


def repeat_lengths(values: np.ndarray) -> np.ndarray:
    """For each position, the longest prefix of its suffix that also starts elsewhere in the sequence."""
    n = len(values)
    if n < 2:
        return np.zeros(n, np.int64)
    order, levels = suffix_ranks(values)
    a, b = order[:-1], order[1:]
    common = np.zeros(n - 1, np.int64)
    for k in range(len(levels) - 1, -1, -1):
        rank = levels[k]
        x, y = a + common, b + common
        inside = (x < n) & (y < n)
        equal = inside & (rank[np.minimum(x, n - 1)] == rank[np.minimum(y, n - 1)])
        common += equal.astype(np.int64) << k
    out = np.zeros(n, np.int64)
    out[a] = common
    out[b] = np.maximum(out[b], common)
    return out


def measure(texts: list[str | None], rules: Rules) -> dict[str, list]:
    """All measures of one block of texts."""
    block = WordBlock(texts)
    words = block.hashes()
    sizes = np.diff(block.first)
    doc = block.doc_of()
    # a word of one document differs from the same word of another, so repeats stay within a document
    _, ids = np.unique(mix(words + doc.astype(np.uint64)), return_inverse=True)
    # one end mark after each document: larger than every word and different from every other
    values = np.empty(block.n + len(texts), np.int64)
    values[np.arange(block.n) + doc] = ids
    ends = np.cumsum(sizes + 1) - 1
    values[ends] = len(ids) + 1 + np.arange(len(texts))
    repeat = np.delete(repeat_lengths(values), ends)

    def covered(least: int) -> np.ndarray:
        reach = np.where(repeat >= least, np.arange(block.n) + repeat, 0)
        hit = np.maximum.accumulate(reach) > np.arange(block.n) if block.n else np.zeros(0, bool)
        return np.add.reduceat(np.append(hit, False), block.first[:-1]) * (sizes > 0) if len(texts) else np.zeros(0)

    cont = (block.data & 0xC0) == 0x80
    lead = np.concatenate([[0], np.cumsum(~cont)])
    per_word = lead[block.end] - lead[block.start]
    chars = np.concatenate([[0], np.cumsum(per_word)])
    symbols = np.concatenate([[0], np.cumsum(_SYMBOL[block.data])])
    longest = np.array([repeat[a:b].max() if b > a else 0 for a, b in zip(block.first[:-1], block.first[1:], strict=True)], np.int64)
    thrice, long_part = covered(3), covered(rules.long_repeat)
    dup = []
    for text in texts:
        lines = [x for x in (text or "").split("\n") if x.strip(" \t\n\r\x0b\x0c")]
        dup.append(len(lines) - len(set(lines)))
    failed = (sizes < rules.min_words) | (100 * thrice > rules.repeat_percent * sizes)
    some = np.maximum(sizes, 1)
    chars, symbols = (x[at[1:]] - x[at[:-1]] for x, at in ((chars, block.first), (symbols, block.offset)))
    kept = ~failed & (long_part <= rules.covered * some) & (longest <= np.maximum(rules.longest * some, rules.long_repeat))
    return {
        "n_words": sizes, "word_chars": chars, "n_symbols": symbols,
        "n_dup_lines": dup, "n_repeat_words": thrice, "base_failed": failed, "kept": kept, "n_long_repeat_words": long_part, "longest_repeat": longest,
    }


MEASURES = {"n_words": "long", "word_chars": "long", "n_symbols": "long", "n_dup_lines": "long", "n_repeat_words": "long", "base_failed": "boolean", "kept": "boolean", "n_long_repeat_words": "long", "longest_repeat": "long"}


def score_quality(docs: DataFrame, rules: Rules = Rules(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id, the base measures, the two base flags, and the repeat measures behind the verdict."""
    kind = docs.select(id_col).schema[0].dataType.simpleString()

    def run(batches):
        for batch in batches:
            keys = batch.column(0)
            for low, high, texts in text_blocks(batch.column(1)):
                got = measure(texts, rules)
                columns = [pa.array(np.asarray(got[c]), pa.bool_() if t == "boolean" else pa.int64()) for c, t in MEASURES.items()]
                yield pa.RecordBatch.from_arrays([keys.slice(low, high - low), *columns], [id_col, *MEASURES])

    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"`{id_col}` {kind}, " + ", ".join(f"{c} {t}" for c, t in MEASURES.items()))
