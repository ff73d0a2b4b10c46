"""Token counts of whole texts by a count-only best path over a unigram vocabulary.

An automaton of all pieces reports every vocabulary match in a word by its end. For each end only the best score and
its number of tokens are kept; on equal scores the longer piece stays, as in the public tokenizer: a path replaces
another only if its score is greater, and starts are tried from left to right. A character that no single-character
piece covers may be unknown, at ten below the least score, and then counts as its UTF-8 bytes.

Cases: null or empty text has no tokens; a word of any length is scored whole; repeated rows give repeated rows; an
empty table gives an empty table. Only the named columns are read.
"""

from __future__ import annotations

from collections.abc import Sequence

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.textcore import text_blocks

MARK = "▁"
UNKNOWN_PENALTY = 10.0
CACHE_WORDS = 150_000


def read_pieces(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a SentencePiece file."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(model.id_to_piece(i), model.get_score(i)) for i in range(model.get_piece_size())]


class BestPathCounter:
    def __init__(self, pieces: Sequence[tuple[str, float]]):
        self.found = ahocorasick.Automaton()
        for piece, score in pieces:
            if piece:
                self.found.add_word(piece, (len(piece), float(score)))
        if len(self.found):
            self.found.make_automaton()
        self.unknown = min((float(s) for _, s in pieces), default=0.0) - UNKNOWN_PENALTY
        self.cache: dict[str, int] = {}
        self.older: dict[str, int] = {}

    def count(self, word: str) -> int:
        """Tokens of a word that already starts with its mark."""
        n = len(word)
        best, tokens = [0.0] * (n + 1), [0] * (n + 1)
        unknown = self.unknown
        done, single, top, least = 0, False, None, 0  # the state of the end after `done`
        for last, (length, score) in self.found.iter(word) if len(self.found) else ():
            while done < last:  # ends without a further match are settled
                if not single:
                    value = best[done] + unknown
                    if top is None or value > top:
                        top, least = value, tokens[done] + len(word[done].encode("utf-8", "surrogatepass"))
                done += 1
                best[done], tokens[done] = top, least
                single, top = False, None
            start = last + 1 - length
            value = best[start] + score
            if top is None or value > top:
                top, least = value, tokens[start] + 1
            if length == 1:
                single = True
        while done < n:
            if not single:
                value = best[done] + unknown
                if top is None or value > top:
                    top, least = value, tokens[done] + len(word[done].encode("utf-8", "surrogatepass"))
            done += 1
            best[done], tokens[done] = top, least
            single, top = False, None
        return tokens[n]

    def words(self, text: str) -> list[str]:
        """The text's words without their marks."""
        if not text:
            return []
        marked = text.replace(" ", MARK)
        return marked.split(MARK)[1:] if marked[0] == MARK else marked.split(MARK)

    def counts(self, texts: Sequence[str | None]) -> list[int]:
        split = [self.words(t or "") for t in texts]
        if len(self.cache) > CACHE_WORDS:
            self.cache, self.older = {}, self.cache
        cache, older = self.cache, self.older
        for w in {w for words in split for w in words}:
            if w not in cache:
                cache[w] = older[w] if w in older else self.count(MARK + w)
        return [sum(map(cache.__getitem__, words)) for words in split]


def count_tokens(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id and n_tokens. The pieces are read on the driver and broadcast; their number is the vocabulary's."""
    pieces = docs.sparkSession.sparkContext.broadcast(read_pieces(path))
    kind = docs.select(id_col).schema[0].dataType.simpleString()

    def run(batches):
        tool = None
        for batch in batches:
            tool = tool or _counter(pieces)
            got: list[int] = []
            for _, _, texts in text_blocks(batch.column(1), 1 << 20):
                got += tool.counts(texts)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got, pa.int64())], [id_col, "n_tokens"])

    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"`{id_col}` {kind}, n_tokens long")


_COUNTERS: dict[int, BestPathCounter] = {}


def _counter(pieces) -> BestPathCounter:
    """One counter for each worker process and broadcast, so that later tasks find its words known."""
    key = hash(tuple(pieces.value))
    if key not in _COUNTERS:
        _COUNTERS.clear()
        _COUNTERS[key] = BestPathCounter(pieces.value)
    return _COUNTERS[key]
