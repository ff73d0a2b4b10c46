"""Byte-level pair-merge encoding and decoding by an index from each adjacent pair to all its positions.

A partition's distinct pieces of text are laid side by side. Every adjacent pair that has a merge rank is indexed
to its positions; the active ranks are taken in ascending order, all positions of the pair are merged, and the
lists of the pairs that appear next to the new symbols are extended. A merge only creates pairs of a higher rank,
so one ascending pass is the same as merging the lowest rank again and again in each piece.

Cases: null text is the empty text; an empty text has no ids and decodes to itself; repeated rows give repeated
rows; an empty table gives an empty table; the text of an added token counts as that token. Only the named id and
text columns are read, so other columns of any name do no harm.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.textcore import text_blocks

#: Fixed pattern of the public byte-level tokenizer.
PIECE = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
CACHE_PIECES = 80_000


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte in a byte-level vocabulary."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class PairIndexCodec:
    def __init__(self, config: str):
        spec = json.loads(config)
        vocab: dict[str, int] = spec["model"]["vocab"]
        symbols = byte_symbols()
        byte_of = {s: b for b, s in enumerate(symbols)}
        self.base = np.array([vocab[s] for s in symbols])
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = 1 + max([*vocab.values(), *self.added.values()])
        self.bytes_of: list[bytes] = [b""] * size
        for token, i in vocab.items():
            self.bytes_of[i] = bytes(byte_of[c] for c in token)
        for token, i in self.added.items():
            self.bytes_of[i] = token.encode()
        self.size = size
        pairs = [p if isinstance(p, list) else p.split(" ") for p in spec["model"]["merges"]]
        self.parts = [(vocab[a], vocab[b]) for a, b in pairs]
        self.made = [vocab[a + b] for a, b in pairs]
        keys = np.array([a * size + b for a, b in self.parts] + [size * size])
        self.ranks = np.argsort(keys, kind="stable")
        self.keys = keys[self.ranks]
        self.split = regex.compile(PIECE).findall
        self.special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self.cache: dict[str, tuple[bytes, bytes]] = {}
        self.older: dict[str, tuple[bytes, bytes]] = {}

    def ranked(self, keys: np.ndarray, spots: np.ndarray, where: dict[int, list[np.ndarray]]) -> list[int]:
        """Adds the positions whose pair has a merge rank to the index; returns the ranks that are new in it."""
        at = np.searchsorted(self.keys, keys)
        known = np.flatnonzero(self.keys[at] == keys)
        if not len(known):
            return []
        ranks, spots = self.ranks[at[known]], spots[known]
        order = np.argsort(ranks, kind="stable")
        ranks, spots = ranks[order], spots[order]
        cuts = np.flatnonzero(np.diff(ranks)) + 1
        fresh = []
        for r, part in zip(ranks[np.concatenate([[0], cuts])].tolist(), np.split(spots, cuts), strict=True):
            if r in where:
                where[r].append(part)
            else:
                where[r] = [part]
                fresh.append(r)
        return fresh

    def merge(self, pieces: list[str]) -> list[list[int]]:
        """Ids of each piece, by one ascending pass over the ranks active in all of them."""
        if not pieces:
            return []
        data = np.frombuffer(b"".join([p.encode("utf-8", "surrogatepass") for p in pieces]), np.uint8)
        length = np.fromiter((len(p.encode("utf-8", "surrogatepass")) for p in pieces), np.int64, len(pieces))
        first = 1 + np.concatenate([[0], np.cumsum(length + 1)])  # a gap of -1 before, between and after the pieces
        sym = np.full(first[-1], -1, np.int64)
        sym[np.arange(len(data)) + np.repeat(np.arange(len(pieces)), length) + 1] = self.base[data]
        after, before = np.arange(1, len(sym) + 1), np.arange(-1, len(sym) - 1)
        where: dict[int, list[np.ndarray]] = {}
        near = np.flatnonzero((sym[:-1] >= 0) & (sym[1:] >= 0))
        active = self.ranked(sym[near] * self.size + sym[near + 1], near, where)
        heapq.heapify(active)
        while active:
            r = heapq.heappop(active)
            spots = np.unique(np.concatenate(where.pop(r)))
            left, right = self.parts[r]
            spots = spots[sym[spots] == left]
            spots = spots[sym[after[spots]] == right]
            if left == right and len(spots) > 1:  # in a run of equal symbols the leftmost pairs come first
                kept, taken = [], -1
                for i, j in zip(spots.tolist(), after[spots].tolist(), strict=True):
                    if i != taken:
                        kept.append(i)
                        taken = j
                spots = np.array(kept)
            if not len(spots):
                continue
            other = after[spots]
            follow = after[other]
            sym[spots], sym[other] = self.made[r], -2
            after[spots], before[follow] = follow, spots
            lead = before[spots]
            has_lead, has_follow = sym[lead] >= 0, sym[follow] >= 0
            keys = np.concatenate([sym[lead[has_lead]] * self.size + self.made[r], self.made[r] * self.size + sym[follow[has_follow]]])
            for q in self.ranked(keys, np.concatenate([lead[has_lead], spots[has_follow]]), where):
                heapq.heappush(active, q)
        at = np.flatnonzero(sym >= 0)
        cuts = np.searchsorted(at, first)
        ids = sym[at].tolist()
        return [ids[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]

    def pieces(self, text: str) -> list[str]:
        if self.special is None or not any(t in text for t in self.added):
            return self.split(text)
        parts = self.special.split(text)
        return list(chain.from_iterable([p] if i % 2 else self.split(p) for i, p in enumerate(parts)))

    def learn(self, texts: list[list[str]]) -> None:
        """Makes sure that ids (as joined decimals) and decoded bytes of all these pieces are at hand."""
        if len(self.cache) > CACHE_PIECES:
            self.cache, self.older = {}, self.cache
        cache, older = self.cache, self.older
        fresh = []
        for p in set(chain.from_iterable(texts)):
            if p not in cache:
                if p in older:
                    cache[p] = older[p]
                elif p in self.added:
                    cache[p] = (b"%d" % self.added[p], self.decode([self.added[p]]))
                else:
                    fresh.append(p)
        for p, ids in zip(fresh, self.merge(fresh), strict=True):
            cache[p] = (",".join(map(str, ids)).encode(), self.decode(ids))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join([self.bytes_of[i] for i in ids])

    def encode(self, text: str | None) -> list[int]:
        pieces = self.pieces(text or "")
        self.learn([pieces])
        return [int(x) for p in pieces for x in self.cache[p][0].split(b",")]


@lru_cache(maxsize=2)
def codec(config: str) -> PairIndexCodec:
    return PairIndexCodec(config)


def read_config(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Per row: id, n_tokens, ids_sha256, decoded_sha256, and with ``with_ids`` also ids and decoded.

    The vocabulary file is read on the driver and broadcast; its size does not depend on the data.
    """
    config = docs.sparkSession.sparkContext.broadcast(read_config(path))

    def run(batches):
        tool = codec(config.value)
        for batch in batches:
            keys = batch.column(0)
            for low, high, texts in text_blocks(batch.column(1), 1 << 20):
                split = [tool.pieces(t) if t else [] for t in texts]
                tool.learn(split)
                cache = tool.cache
                count, digest, back, all_ids, decoded = [], [], [], [], []
                for pieces in split:
                    got = [cache[p] for p in pieces]
                    ids = b",".join([g[0] for g in got])
                    plain = b"".join([g[1] for g in got]).decode("utf-8", "replace")
                    count.append(ids.count(b",") + 1 if ids else 0)
                    digest.append(hashlib.sha256(ids).hexdigest())
                    back.append(hashlib.sha256(plain.encode()).hexdigest())
                    if with_ids:
                        all_ids.append(np.array(ids.split(b",") if ids else [], dtype=np.int32))
                        decoded.append(plain)
                columns = [keys.slice(low, high - low), pa.array(count, pa.int64()), pa.array(digest, pa.string()), pa.array(back, pa.string())]
                names = [id_col, "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    columns += [pa.array(all_ids, pa.list_(pa.int32())), pa.array(decoded, pa.string())]
                    names += ["ids", "decoded"]
                yield pa.RecordBatch.from_arrays(columns, names)

    kind = docs.select(id_col).schema[0].dataType.simpleString()
    schema = f"`{id_col}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string"
    schema += ", ids array<int>, decoded string" if with_ids else ""
    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, schema)
