"""Benchmark decontamination by greedy string tiling of documents against benchmark items.

Documents and items meet where they share a seed, a run of a few words. For each such pair whose seeds could cover
enough of the item, the longest matches that overlap no earlier tile are marked again and again, found by running
hashes of falling length, and verified word by word by their 64-bit hashes. Only the stretches of the document that
seeds of the item cover are tiled, and of equal stretches as many as the item has room for, so a phrase that a text
repeats and many items share costs little. A document is contaminated by an item if its tiles cover enough of the
item's words, in whatever order, or if one tile is long by itself.

Cases: null and empty texts, and items without words, match nothing; an item shorter than a seed must occur as a
whole; ties between tiles go to the first in the item, then in the document; between items to the greater coverage,
then the smaller id, null last; an item without an id matches as others do, and its documents have a coverage but no
item_id, so the coverage tells what is contaminated; repeated rows give repeated rows; ids may be of any type; an empty table on either side leaves all documents clean.
Only the named columns are read.
"""

from __future__ import annotations

from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.textcore import WordBlock, text_blocks, window_hashes

#: Characters of benchmark text that are broadcast at once; a larger benchmark is taken in several blocks.
BLOCK_CHARS = 32_000_000
#: Shared seeds that are held at once, for several documents; one document meets each seed of the block once at most.
HELD_ENTRIES = 1_000_000


@dataclass(frozen=True)
class Tiling:
    seed: int = 4
    #: Share of an item's words that the tiles must cover.
    coverage: float = 0.5
    #: A tile of so many words contaminates by itself.
    long_tile: int = 13


def tiles(doc: np.ndarray, item: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """Greedy tiling of two sequences of word hashes: (start in doc, start in item, length), longest first."""
    free_doc, free_item = np.ones(len(doc), bool), np.ones(len(item), bool)
    out: list[tuple[int, int, int]] = []
    width = max(least, min(len(item), len(doc)) // 2)
    while width >= least:
        found = _matches(doc, item, free_doc, free_item, width)
        if found and found[0][0] > 2 * width:
            width = found[0][0]
            continue
        queue = [(-size, at_item, at_doc) for size, at_item, at_doc in found]
        heapify(queue)
        while queue:
            size, at_item, at_doc = heappop(queue)
            size = -size
            free = free_item[at_item : at_item + size] & free_doc[at_doc : at_doc + size]
            if free.all():
                free_item[at_item : at_item + size] = False
                free_doc[at_doc : at_doc + size] = False
                out.append((at_doc, at_item, size))
                continue
            edge = np.flatnonzero(np.diff(np.concatenate([[False], free, [False]])))
            for low, high in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True):
                if high - low >= width:  # what earlier tiles have left of a match
                    heappush(queue, (low - high, at_item + low, at_doc + low))
        if width == least:
            break
        width = max(least, width // 2)
    return out


def _matches(doc, item, free_doc, free_item, width) -> list[tuple[int, int, int]]:
    """Maximal free matches of at least ``width`` words: (length, start in item, start in doc), longest first."""
    open_doc, open_item = _open(free_doc, width), _open(free_item, width)
    if not len(open_doc) or not len(open_item):
        return []
    hash_doc, hash_item = window_hashes(doc, width)[open_doc], window_hashes(item, width)[open_item]
    by: dict[int, list[int]] = {}
    for h, i in zip(hash_item.tolist(), open_item.tolist(), strict=True):
        by.setdefault(h, []).append(i)
    hit = np.flatnonzero(np.isin(hash_doc, hash_item))
    found = []
    reach: dict[int, int] = {}  # of each diagonal, up to where a match has been extended
    for h, j in zip(hash_doc[hit].tolist(), open_doc[hit].tolist(), strict=True):
        for i in by[h]:
            if reach.get(j - i, -1) > j or not np.array_equal(doc[j : j + width], item[i : i + width]):
                continue
            n = width
            while i + n < len(item) and j + n < len(doc) and item[i + n] == doc[j + n] and free_item[i + n] and free_doc[j + n]:
                n += 1
            reach[j - i] = j + n - width + 1
            found.append((n, i, j))
    return sorted(found, key=lambda x: (-x[0], x[1], x[2]))


def _open(free: np.ndarray, width: int) -> np.ndarray:
    """Starts of the runs of ``width`` free positions."""
    total = np.concatenate([[0], np.cumsum(free)])
    return np.flatnonzero(total[width:] - total[:-width] == width) if len(free) >= width else np.zeros(0, np.int64)


class Items:
    """The items of one block: word hashes, and their seeds in order of hash."""

    def __init__(self, ids: list, texts: list[str | None], rule: Tiling):
        self.ids, self.rule = ids, rule
        block = WordBlock(texts, lower=True)
        words = block.hashes()
        self.words = [words[a:b] for a, b in zip(block.first[:-1], block.first[1:], strict=True)]
        self.size = np.diff(block.first)
        seeds, owner, spot = [], [], []
        for k, w in enumerate(self.words):
            if 0 < len(w):
                h = window_hashes(w, min(rule.seed, len(w)))
                seeds.append(h)
                owner.append(np.full(len(h), k))
                spot.append(np.arange(len(h)))
        self.by_width = {}
        for width in sorted({min(rule.seed, len(w)) for w in self.words if len(w)}):
            take = [i for i, o in enumerate(owner) if min(rule.seed, len(self.words[o[0]])) == width]
            h = np.concatenate([seeds[i] for i in take])
            order = np.argsort(h, kind="stable")
            self.by_width[width] = (h[order], np.concatenate([owner[i] for i in take])[order], np.concatenate([spot[i] for i in take])[order])

    def match(self, texts: list[str | None]) -> list[tuple[float, int, int] | None]:
        """For each text: (coverage, item, longest tile) of the item that contaminates it most, or None."""
        block = WordBlock(texts, lower=True)
        best: list[tuple[float, int, int] | None] = [None] * len(texts)
        if not block.n:
            return best
        words, doc_of, room = block.hashes(), block.doc_of(), block.room()
        for width, (seeds, owner, spot) in self.by_width.items():
            h = window_hashes(words, width)
            at = np.minimum(np.searchsorted(seeds, h), len(seeds) - 1)
            hit = np.flatnonzero((seeds[at] == h) & (room[: len(h)] >= width))
            if not len(hit):
                continue
            # each seed once for a document; a document meets an entry of the index once at most
            doc_hit, first = np.unique(np.stack([doc_of[hit].astype(np.uint64), h[hit]], 1), axis=0, return_index=True)
            low, high = np.searchsorted(seeds, doc_hit[:, 1], "left"), np.searchsorted(seeds, doc_hit[:, 1], "right")
            docs, n = doc_of[hit][first], high - low
            total = np.cumsum(n)
            edge = np.flatnonzero(np.concatenate([[True], docs[1:] != docs[:-1], [True]]))
            a = 0
            while a < len(edge) - 1:  # so many documents at once that the entries they meet stay few
                b = a + 1
                while b < len(edge) - 1 and total[edge[b + 1] - 1] - total[edge[a]] + n[edge[a]] <= HELD_ENTRIES:
                    b += 1
                part = slice(edge[a], edge[b])
                entry = np.repeat(low[part], n[part]) + np.arange(n[part].sum()) - np.repeat(np.cumsum(n[part]) - n[part], n[part])
                self._tile(width, np.repeat(docs[part], n[part]), owner[entry], spot[entry], words, block, best)
                a = b
        return best

    def _tile(self, width, doc_of, owner, spot, words, block, best) -> None:
        """Tiles the pairs whose shared seeds could cover enough of the item, and keeps each document's worst item."""
        order = np.lexsort([spot, owner, doc_of])
        doc_of, owner, spot = doc_of[order], owner[order], spot[order]
        head = np.concatenate([[True], (doc_of[1:] != doc_of[:-1]) | (owner[1:] != owner[:-1]), [True]])
        cut = np.flatnonzero(head)
        step = np.minimum(np.append(np.diff(spot), width), width)
        step[cut[1:] - 1] = width
        covered = np.add.reduceat(step, cut[:-1])  # no tiling covers more words of the item
        size = self.size[owner[cut[:-1]]]
        for k in np.flatnonzero(covered >= np.minimum(self.rule.coverage * size, self.rule.long_tile)).tolist():
            doc, item = int(doc_of[cut[k]]), int(owner[cut[k]])
            shared = _stretches(words[block.first[doc] : block.first[doc + 1]], self.words[item], width)
            got = tiles(shared, self.words[item], width)
            share, longest = sum(t[2] for t in got) / len(self.words[item]), max((t[2] for t in got), default=0)
            if (share >= self.rule.coverage or longest >= self.rule.long_tile) and _better((share, item, longest), best[doc], self.ids):
                best[doc] = (share, item, longest)


def _stretches(doc: np.ndarray, item: np.ndarray, width: int) -> np.ndarray:
    """The words of a document that runs of ``width`` words of the item cover, stretch by stretch in order, with a word
    that the item lacks between them; of equal stretches as many as the item can hold."""
    hit = np.flatnonzero(np.isin(window_hashes(doc, width), window_hashes(item, width)))
    if not len(hit):
        return doc[:0]
    gap = np.flatnonzero(np.diff(hit) > width)
    first, last = hit[np.append(0, gap + 1)], hit[np.append(gap, len(hit) - 1)] + width
    lacks = np.uint64(next(x for x in range(len(item) + 1) if x not in set(item[item <= len(item)].tolist())))
    seen: dict[bytes, int] = {}
    out = []
    for a, b in zip(first.tolist(), last.tolist(), strict=True):
        run = doc[a:b]
        at = run.tobytes()
        seen[at] = seen.get(at, 0) + 1
        if seen[at] <= max(1, len(item) // width):
            out += [run, lacks[None]]
    return np.concatenate(out)


def _better(new, old, ids) -> bool:
    return old is None or _rank(new[0], ids[new[1]]) < _rank(old[0], ids[old[1]])


def _rank(coverage: float, item) -> tuple:
    return -coverage, item is None, 0 if item is None else item


def contamination(docs: DataFrame, items: DataFrame, rule: Tiling = Tiling(), id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", keep: list[str] | None = None, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """Per row: the kept columns (the id unless given), and item_id, coverage and longest_tile of the worst item, or nulls.

    The items come to the driver in blocks of about ``block_chars`` characters, by a hash of the item, so a benchmark of
    any size is matched as a series of bounded broadcasts; no pair is formed but where a seed is shared.
    """
    spark = docs.sparkSession
    keep, kind = keep if keep is not None else [id_col], items.schema[item_col].dataType
    chosen = items.select(F.col(item_col).alias("item"), F.col(item_text).cast("string").alias("text")).where("text is not null")
    chars = chosen.agg(F.coalesce(F.sum(F.char_length("text")), F.lit(0)).alias("n")).first()["n"]
    n_blocks = max(1, -(-chars // block_chars))
    packed = text_col.split(".", 1)[1] if "." in text_col else None  # in a kept struct, so not sent twice
    state = docs.select(*keep, *([] if packed else [F.col(text_col).cast("string").alias("__text")]), F.lit(None).cast(kind).alias("item_id"), F.lit(None).cast("double").alias("coverage"), F.lit(None).cast("long").alias("longest_tile"))
    schema = state.schema
    for k in range(n_blocks):
        rows = chosen.where(F.pmod(F.xxhash64("item", "text"), F.lit(n_blocks)) == k).orderBy("item", "text").collect()
        state = state.mapInArrow(_matcher(spark.sparkContext.broadcast(([r["item"] for r in rows], [r["text"] for r in rows], rule)), packed, len(keep)), schema)
    return state.drop("__text")


def _matcher(shared, packed: str | None, n_keep: int):
    def run(batches):
        items = None
        for batch in batches:
            items = items or Items(*shared.value)
            same = n_keep + (packed is None)
            old = list(zip(*[batch.column(same + i).to_pylist() for i in range(3)], strict=True))
            for low, _, texts in text_blocks(batch.column(0).field(packed) if packed else batch.column(n_keep)):
                for i, got in enumerate(items.match(texts), low):
                    if got and (old[i][1] is None or _rank(got[0], items.ids[got[1]]) < _rank(old[i][1], old[i][0])):
                        old[i] = (items.ids[got[1]], got[0], got[2])
            new = [pa.array([o[j] for o in old], batch.column(same + j).type) for j in range(3)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:same], *new], batch.schema.names)

    return run
