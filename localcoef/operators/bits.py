"""Dense graphs as rows of bits: profiles and edges without a list or a row for each edge.

Nodes with the same groups are one class of twins, which are joined to each other and to the same others; a class has one row
of bits, with a place for each class, and counts by its size. Classes of one size share words of 64 places, so that sums over
a row are numbers of bits times a size. A block of rows is made in one task from all groups (or vectors); the common
neighbours of two joined classes are the bits that both rows have. Places are known to the driver and to every task, so at
most ``PLACES`` classes are taken; larger graphs, and those of small groups, keep their packed lists.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.operators.packed import squeezed, unsqueezed

#: Rows of a group on average from which a graph of groups is made of bits; classes at most (8.6 GB of bits undivided).
CROWD, PLACES = 64, 1 << 18
#: Nodes of edges at most; pairs of a batch.
NODES, PAIRS = 1 << 20, 500_000
#: Bytes of the bits of a block, of a written row, and words that are met at a time.
BLOCK, SLICE, MET = 1 << 25, 1 << 22, 1 << 15
_ROWS = "block int, at long, bits binary"


@dataclass(frozen=True)
class Places:
    """Classes in order of their ids, with their sizes and places, and the number of rows in a block."""

    ids: np.ndarray
    size: np.ndarray
    place: np.ndarray
    words: int
    per: int

    @staticmethod
    def of(ids: np.ndarray, size: np.ndarray) -> Places:
        order = np.argsort(ids)
        ids, size = ids[order].astype(np.int64), size[order].astype(np.int64)
        kinds, kind, n = np.unique(size, return_inverse=True, return_counts=True)
        wide = -(-n // 64) * 64
        place = np.empty(len(ids), np.int64)
        by = np.argsort(kind, kind="stable")
        place[by] = np.arange(len(ids)) + np.repeat(np.cumsum(wide - n) - (wide - n), n)
        words = max(1, int(wide.sum()) // 64)
        per = min(BLOCK // (8 * words), -(-len(ids) // 12)) // 64 * 64
        return Places(ids, size, place, words, max(64, per))

    @property
    def blocks(self) -> int:
        return -(-self.words * 64 // self.per)

    def of_id(self, x: np.ndarray) -> np.ndarray:
        return self.place[np.searchsorted(self.ids, x)]

    def spread(self, x: np.ndarray) -> np.ndarray:
        """Values of classes by place, 0 where no class is."""
        out = np.zeros(self.words * 64, np.int64)
        out[self.place] = x
        return out

    def runs(self) -> list[tuple[int, int, int]]:
        """Words from, to, and the size of their classes."""
        size = self.spread(self.size).reshape(-1, 64).max(axis=1, initial=0)
        cut = np.r_[0, np.flatnonzero(np.diff(size)) + 1, len(size)]
        return [(int(a), int(b), int(size[a])) for a, b in zip(cut[:-1], cut[1:], strict=True) if size[a]]


@dataclass(frozen=True)
class Bits:
    """Written rows of bits, their classes, and (i, c), the class of each node where it is not the node itself."""

    rows: DataFrame
    places: Places
    classed: DataFrame | None = None


def _binary(names: str, *values) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    fields = [f.split() for f in names.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([x], kinds[k]) for x, (_, k) in zip(values, fields, strict=True)], names=[n for n, _ in fields])


def _union(branches: list[DataFrame]) -> DataFrame:
    """A task for each branch of one partition; Spark would run a union of such branches alone as one task."""
    branches = [*branches, branches[0].sparkSession.range(0, 2, 1, 2).mapInArrow(_none, branches[0].schema)]
    while len(branches) > 1:
        branches = [x.unionAll(y) for x, y in zip(branches[::2], branches[1::2], strict=False)] + branches[len(branches) // 2 * 2 :]
    return branches[0]


def _none(batches) -> Iterator[pa.RecordBatch]:
    yield from ()


def _put(block: int, first: int, bits: np.ndarray) -> Iterator[pa.RecordBatch]:
    step = max(1, SLICE // (8 * bits.shape[1]))
    for at in range(0, len(bits), step):
        piece = np.ascontiguousarray(bits[at : at + step])
        yield _binary(_ROWS, block, first + at, pa.Codec("zstd").compress(piece.tobytes(), asbytes=True))


def _got(data, most: int, words: int) -> np.ndarray:
    """The bits of a written row of a block of ``most`` rows at most."""
    reader = pa.CompressedInputStream(pa.BufferReader(pa.py_buffer(data)), "zstd")
    return np.frombuffer(reader.read(most * words * 8), np.uint64).reshape(-1, words)


def _marked(places: np.ndarray, words: int) -> np.ndarray:
    """A row of bits from places."""
    out = np.zeros(words * 64, np.uint8)
    out[places] = 1
    return np.packbits(out, bitorder="little").view(np.uint64)


def _cleared(bits: np.ndarray, first: int) -> np.ndarray:
    """No class is its own neighbour."""
    at = np.arange(len(bits))
    bits[at, (first + at) >> 6] &= ~(np.uint64(1) << ((first + at) & 63).astype(np.uint64))
    return bits


# --- of groups


def _as_places(p: Places):
    def run(batches) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for g in batch.column(0):
                x = p.of_id(g.values.to_numpy(zero_copy_only=False))
                yield _binary("members binary", squeezed(np.sort(x)))

    return run


def _of_block(p: Places, block: int):
    a, b = block * p.per, min((block + 1) * p.per, p.words * 64)

    def run(batches) -> Iterator[pa.RecordBatch]:
        bits = np.zeros((b - a, p.words), np.uint64)
        for batch in batches:
            for x in batch.column(0):
                x = unsqueezed(x.as_buffer())
                own = x[np.searchsorted(x, a) : np.searchsorted(x, b)] - a
                if len(own) and len(x) > 1:
                    bits[own] |= _marked(x, p.words)
        yield from _put(block, a, _cleared(bits, a))

    return run


def of_groups(rows: DataFrame) -> Bits | None:
    """Bits of the graph of (g, i), where two members are joined if they share a group; None where groups are small or classes many."""
    from localcoef.plans.store import written

    seen = rows.agg(F.count("*").alias("n"), F.approx_count_distinct("g").alias("g")).first()
    if seen["n"] < CROWD * max(1, seen["g"]):
        return None
    kept = written(rows.select(F.col("g").cast("long").alias("g"), F.col("i").cast("long").alias("i")).repartition("i").distinct(), "members")
    marks = written(kept.groupBy("i").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("g")).alias("x"), F.bit_xor(F.xxhash64("g", F.lit(1))).alias("y")), "marks")
    twins = marks.groupBy("n", "x", "y").agg(F.min("i").alias("c"), F.count("*").alias("size"))
    classed = written(marks.join(twins, ["n", "x", "y"]).select("i", "c", "size"), "classes")
    reduced = written(_reduced(kept, classed), "reduced")
    if reduced.where("n <> size").limit(1).count():  # marks of different groups agree
        classed = marks.select("i", F.col("i").alias("c"), F.lit(1).cast("long").alias("size"))
        reduced = _reduced(kept, classed)
    classes = classed.where("i = c").select("c", "size")
    if classes.count() > PLACES:
        return None
    found = classes.toArrow()
    p = Places.of(*(found.column(c).to_numpy() for c in ("c", "size")))
    groups = written(reduced.groupBy("g").agg(F.collect_list("c").alias("cs")).select("cs").mapInArrow(_as_places(p), "members binary"), "groups")
    made = _union([groups.coalesce(1).mapInArrow(_of_block(p, k), _ROWS) for k in range(p.blocks)])
    return Bits(written(made, "bits"), p, classed.select("i", "c"))


def _reduced(kept: DataFrame, classed: DataFrame) -> DataFrame:
    """(g, c, n, size): how many of a class are in a group; all of them where they are twins."""
    return kept.join(classed, "i").groupBy("g", "c").agg(F.count("*").alias("n"), F.first("size").alias("size"))


# --- of vectors

_VECTORS = "block int, dim int, places binary, x binary"


def _numbered(p: Places):
    def run(batches) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            place = p.of_id(batch.column(0).to_numpy(zero_copy_only=False))
            yield pa.RecordBatch.from_arrays([pa.array((place // p.per).astype(np.int32)), pa.array(place), batch.column(1)], names=["block", "place", "x"])

    return run


def _dealt(batches) -> Iterator[pa.RecordBatch]:
    """Vectors of a block and of one length as packed rows."""
    for batch in batches:
        block, place = (batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
        x = batch.column(2)
        sizes, values = np.diff(x.offsets.to_numpy()), x.flatten().to_numpy(zero_copy_only=False)
        at = np.r_[0, np.cumsum(sizes)]
        for dim in np.unique(sizes):
            for k in np.unique(block[sizes == dim]):
                own = np.flatnonzero((sizes == dim) & (block == k))
                vectors = values[at[own][:, None] + np.arange(dim)]
                yield _binary(_VECTORS, int(k), int(dim), squeezed(place[own]), pa.Codec("zstd").compress(vectors.tobytes(), asbytes=True))


def _above(p: Places, threshold: float, block: int, own: int, slab: int = 128):
    """The rows of a block: the places whose vectors have a larger cosine with that of the row."""
    a, b = block * p.per, min((block + 1) * p.per, p.words * 64)

    def run(batches) -> Iterator[pa.RecordBatch]:
        bits, mine, waiting, left = np.zeros((b - a, p.words), np.uint64), [], [], own

        def vectors(row) -> tuple:
            k, dim, places, x = row
            places = unsqueezed(places)
            raw = pa.Codec("zstd").decompress(pa.py_buffer(x), decompressed_size=len(places) * dim * 8)
            x = np.frombuffer(raw, np.float64).reshape(-1, dim)
            norm = np.sqrt(np.cumsum(x * x, axis=1)[:, -1])
            return k, dim, places, x, norm, (x / norm[:, None]).astype(np.float32)

        def met(row) -> None:
            k, dim, others, y, far, unit = vectors(row)
            first, to = k * p.per, min((k + 1) * p.per, p.words * 64)
            near = 1.2e-7 * (dim + 8)  # what sums of single precision may differ by, twice
            for _, size, places, x, norm, own_unit in mine:
                if size != dim:  # vectors of other lengths have no cosine
                    continue
                for at in range(0, len(x), slab):
                    cosine = own_unit[at : at + slab] @ unit.T
                    larger = ~(cosine <= np.float32(threshold + near))  # not a number counts as larger, as in SQL
                    i, j = np.nonzero(larger != ~(cosine <= np.float32(threshold - near)))  # in double precision, summed in order
                    if len(i):
                        larger[i, j] = ~(np.cumsum(x[at + i] * y[j], axis=1)[:, -1] / (norm[at + i] * far[j]) <= threshold)
                    marks = np.zeros((len(larger), to - first), bool)
                    marks[:, others - first] = larger
                    bits[places[at : at + slab] - a, first // 64 : to // 64] |= np.packbits(marks, axis=1, bitorder="little").view(np.uint64)

        for batch in batches:
            kinds, ks, dims = (batch.column(c).to_pylist() for c in (4, 0, 1))
            for n, (kind, k, dim) in enumerate(zip(kinds, ks, dims, strict=True)):
                row = (k, dim, *(batch.column(c)[n].as_buffer().to_pybytes() for c in (2, 3)))
                if kind == 0:
                    mine.append(vectors(row))
                    left -= 1
                    if not left:
                        for x in waiting:
                            met(x)
                        waiting = []
                elif left:
                    waiting.append(row)
                else:
                    met(row)
        yield from _put(block, a, _cleared(bits, a))

    return run


def of_vectors(rows: DataFrame, threshold: float) -> Bits | None:
    """Bits of the graph of (id, x) whose vectors have a larger cosine; None where there are too many or an id repeats."""
    from localcoef.plans.store import written

    n = rows.count()
    if not 0 < n <= PLACES:
        return None
    ids = rows.select(F.col("id").cast("long").alias("id")).toArrow().column(0).to_numpy()
    if len(np.unique(ids)) < n:
        return None
    p = Places.of(ids, np.ones(n, np.int64))
    numbered = rows.select(F.col("id").cast("long").alias("id"), "x").mapInArrow(_numbered(p), "block int, place long, x array<double>")
    dealt = written(numbered.repartitionById(p.blocks, "block").mapInArrow(_dealt, _VECTORS), "vectors")
    own = {r["block"]: r["n"] for r in dealt.groupBy("block").agg(F.count("*").alias("n")).collect()}
    both = lambda k: dealt.where(F.col("block") == k).withColumn("kind", F.lit(0)).unionAll(dealt.withColumn("kind", F.lit(1)))
    made = _union([both(k).coalesce(1).mapInArrow(_above(p, threshold, k, own[k]), _ROWS) for k in sorted(own)])
    return Bits(written(made, "bits"), p)


# --- what is read of them


def _added(bits: np.ndarray, runs: list[tuple[int, int, int]], low: int = 0) -> np.ndarray:
    """For each row, the sizes of the classes of its bits; the first word is ``low``."""
    count, out = np.bitwise_count(bits), np.zeros(len(bits), np.int64)
    for a, b, size in runs:
        if b > low and a < low + bits.shape[1]:
            out += count[:, max(0, a - low) : b - low].sum(axis=1, dtype=np.uint32).astype(np.int64) * size
    return out


def _degrees(p: Places):
    runs, size = p.runs(), p.spread(p.size)

    def run(batches) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, data in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                bits = _got(data.as_buffer(), p.per, p.words)
                own = np.arange(at, at + len(bits))
                own, deg = own[size[own] > 0], (_added(bits, runs) + size[own] - 1)[size[own] > 0]
                yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(deg)], names=["place", "deg"])

    return run


def _upto(bits: np.ndarray, first: int, words: int) -> np.ndarray:
    """The rows with the places before their own only, and with those of so many words."""
    out = bits[:, :words].copy()
    for k in range(len(out)):
        at = first + k
        out[k, at >> 6] &= (np.uint64(1) << np.uint64(at & 63)) - np.uint64(1)
        out[k, (at >> 6) + 1 :] = 0
    return out


def _triangles(p: Places, deg: np.ndarray, block: int, own: int):
    """(place, t, wh) of a block: all headed wedges of its rows, and the triangles of two joined classes u < v, u in the block,
    with a third one beyond v (which u and v gain) or before u (which v gains)."""
    a, b = block * p.per, min((block + 1) * p.per, p.words * 64)
    runs, size = p.runs(), p.spread(p.size)
    ahead = (size * (deg - 1)).astype(np.float64)

    def run(batches) -> Iterator[pa.RecordBatch]:
        held, waiting, left = {}, [], own
        mine = lower = None
        t, wh = np.zeros(p.words * 64, np.int64), np.zeros(p.words * 64, np.int64)

        def ready() -> None:
            nonlocal mine, lower
            mine = np.concatenate([held[k] for k in sorted(held)])
            held.clear()
            lower = _upto(mine, a, b // 64)
            near, pairs = _added(mine, runs), np.zeros(len(mine), np.int64)
            for x, y, s in runs:
                if s > 1:
                    pairs += np.bitwise_count(mine[:, x:y]).sum(axis=1, dtype=np.int64) * (s * (s - 1) // 2)
            w = size[a:b]
            t[a:b] += np.where(w > 0, (w - 1) * (w - 2) // 2 + (w - 1) * near + pairs, 0)
            for k in range(0, len(mine), 64):  # whole numbers below 2**53, so exact
                some = np.unpackbits(mine[k : k + 64].view(np.uint8), axis=1, bitorder="little").astype(np.float64)
                wh[a + k : a + k + 64] = (some @ ahead).astype(np.int64)
            wh[a:b] += np.where(w > 0, (w - 1) * (deg[a:b] - 1), 0)

        def met(at: int, data) -> None:
            rows = _got(data, p.per, p.words)
            for k in range(max(0, a + 1 - at), len(rows)):
                v, row = at + k, rows[k]
                us = np.flatnonzero(np.unpackbits(row[a // 64 : b // 64].view(np.uint8), bitorder="little"))
                us = us[: np.searchsorted(us, v - a)]
                if not len(us):
                    continue
                low = v >> 6
                beyond = row[low:].copy()
                beyond[0] &= np.uint64(2**64 - (2 << (v & 63)))
                before = row[: b // 64]
                gain, w = 0, size[us + a]
                step = max(8, MET // p.words)
                for x in range(0, len(us), step):
                    u, sizes = us[x : x + step], w[x : x + step]
                    far = _added(np.bitwise_and(mine[u, low:], beyond), runs, low)
                    near = _added(np.bitwise_and(lower[u], before), runs) if a or u[-1] else 0
                    t[u + a] += far * size[v]
                    gain += int((sizes * (far + near)).sum())
                t[v] += gain

        for batch in batches:
            kinds, ats = batch.column(3).to_pylist(), batch.column(1).to_pylist()
            for k, (kind, at) in enumerate(zip(kinds, ats, strict=True)):
                data = batch.column(2)[k].as_buffer()
                if kind == 0:
                    held[at] = _got(data, p.per, p.words)
                    left -= 1
                    if not left:
                        ready()
                        for x in waiting:
                            met(*x)
                        waiting = []
                elif left:
                    waiting.append((at, data.to_pybytes()))
                else:
                    met(at, data)
        found = np.flatnonzero(t + wh)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (found, t[found], wh[found])], names=["place", "t", "wh"])

    return run


def profile(g: Bits) -> DataFrame:
    """(id, size, deg, t, wc, wh) of the classes that have an edge; ``size`` nodes have these numbers each."""
    p, spark = g.places, g.rows.sparkSession
    found = g.rows.mapInArrow(_degrees(p), "place long, deg long").toArrow()
    deg = np.zeros(p.words * 64, np.int64)
    deg[found.column(0).to_numpy()] = found.column(1).to_numpy()
    own = {r["block"]: r["n"] for r in g.rows.groupBy("block").agg(F.count("*").alias("n")).collect()}
    both = lambda k: g.rows.where(F.col("block") == k).withColumn("kind", F.lit(0)).unionAll(g.rows.where(F.col("block") >= k).withColumn("kind", F.lit(1)))
    sums = _union([both(k).coalesce(1).mapInArrow(_triangles(p, deg, k, own[k]), "place long, t long, wh long") for k in sorted(own)])
    sums = sums.groupBy("place").agg(F.sum("t").alias("t"), F.sum("wh").alias("wh"))
    at = pa.table({"place": p.place, "id": p.ids, "size": p.size, "deg": deg[p.place]})
    nodes = spark.createDataFrame(at).where("deg > 0").join(sums, "place", "left")
    return nodes.select("id", "size", "deg", F.coalesce("t", F.lit(0)).alias("t"), F.expr("deg * (deg - 1) div 2").alias("wc"), F.coalesce("wh", F.lit(0)).alias("wh"))


def _edges(p: Places, nodes: np.ndarray, places: np.ndarray):
    """(u, v) of the nodes of some rows: those of joined classes and of the same one, each pair once."""
    order = np.argsort(places, kind="stable")
    first = np.searchsorted(places[order], np.arange(p.words * 64 + 1))

    def pairs(batches) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for batch in batches:
            for at, data in zip(batch.column(1).to_pylist(), batch.column(2), strict=True):
                bits = _got(data.as_buffer(), p.per, p.words)
                for k in np.flatnonzero(first[at + 1 : at + len(bits) + 1] > first[at : at + len(bits)]):
                    joined = np.unpackbits(bits[k].view(np.uint8), bitorder="little")
                    joined[at + k] = 1
                    near = nodes[joined[places] > 0]
                    for u in nodes[order[first[at + k] : first[at + k + 1]]]:
                        v = near[np.searchsorted(near, u, "right") :]
                        if len(v):
                            yield np.full(len(v), u), v

    def run(batches) -> Iterator[pa.RecordBatch]:
        us, vs, n = [], [], 0
        for u, v in pairs(batches):
            us.append(u)
            vs.append(v)
            n += len(u)
            if n >= PAIRS:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (us, vs)], names=["u", "v"])
                us, vs, n = [], [], 0
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (us, vs)], names=["u", "v"])

    return run


def edges(g: Bits) -> DataFrame | None:
    """(u, v) of a graph of groups, each pair once and none in a shuffle; None where there are too many nodes."""
    p = g.places
    if g.classed.count() > NODES:
        return None
    found = g.classed.toArrow()
    nodes, classes = (found.column(c).to_numpy() for c in ("i", "c"))
    order = np.argsort(nodes)
    pairs = _edges(p, nodes[order], p.of_id(classes[order]))
    return _union([g.rows.where(F.col("block") == k).coalesce(1).mapInArrow(pairs, "u long, v long") for k in range(p.blocks)])
