"""Degrees, headed wedges and triangles from packed neighbour lists, without a row for each wedge.

An edge stands in the list of its lower end. A list meets the lists of its members: the members are cut into ranges of ids
with about as many edges each, and a list meets every range in which it has a member with another one after it. There
the shorter of two lists is looked up in the longer, so the work is bounded by the sum of smaller degrees over the edges,
whatever the order of ids; where both are dense, they are multiplied as matrices. Small graphs send their lists to the ranges;
in larger ones the task of a range reads the lists that reach it from the shared folder, so that no list is shuffled.
Groups are shuffled as packed lists too, never as pairs: a group goes once to every block of ids that it has a member in.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.model import Graph

#: Entries of a packed row at most, unless one list has more; rows held before repeats are dropped; edges of a range.
BUNDLE, HELD, RANGE = 500_000, 4_000_000, 3_000_000
#: Cells of the marks of a batch of lists, a power of two; entries of a batch that shares them by a hash; candidates looked up at a time.
MARKS, FILL, STEP = 1 << 23, 1 << 18, 1 << 21
#: A list so many times longer than another is searched, not walked.
LONGER = 8
#: Edges from which ranges read the lists; cells of a range that is multiplied at most, and cells of it worth a look-up.
DIRECT, DENSE, CELLS = 2_000_000, 1 << 23, 100
#: Ids whose lists are made in one task, so that the far ends repeat there.
NEAR_BITS = 12
_PACKED = "part int, kind int, ids binary, counts binary, entries binary"
_SENT = "q int, kind int, ids binary, counts binary, entries binary"
_LISTS = 0
#: Packed rows with their least and largest head and their largest entry; and sums by id.
_KEPT = _PACKED + ", low long, top long, high long"
_SUMS = "q int, ids binary, counts binary"


@dataclass(frozen=True)
class Packed:
    """Written lists, (id, deg) of all nodes, and the number of edges."""

    rows: DataFrame
    deg: DataFrame
    m: int


def squeezed(x: np.ndarray) -> bytes:
    """Whole numbers as compressed steps from one to the next."""
    if not len(x):
        return b""
    steps = np.diff(x)
    small = not len(steps) or (steps.min() >= -(2**31) and steps.max() < 2**31)
    return struct.pack("<qq?", len(x), int(x[0]), small) + pa.Codec("zstd").compress(steps.astype(np.int32 if small else np.int64).tobytes(), asbytes=True)


def unsqueezed(data) -> np.ndarray:
    data = memoryview(data)
    if not len(data):
        return np.empty(0, np.int64)
    n, first, small = struct.unpack("<qq?", data[:17])
    raw = pa.Codec("zstd").decompress(pa.py_buffer(data[17:]), decompressed_size=(n - 1) * (4 if small else 8)) if n > 1 else b""
    out = np.empty(n, np.int64)
    out[0], out[1:] = first, np.frombuffer(raw, np.int32 if small else np.int64)
    return np.cumsum(out, out=out)


def ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """starts[0], starts[0] + 1, ... for sizes[0] numbers, then the same of the next."""
    return np.repeat(starts - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())


def _distinct(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pairs in order, each once."""
    if not len(u):
        return u, v
    low_u, low_v, span = int(u.min()), int(v.min()), int(v.max()) - int(v.min()) + 1
    if (int(u.max()) - low_u + 1) * span < 2**62:
        key = np.unique((u - low_u) * span + (v - low_v))
        return key // span + low_u, key % span + low_v
    order = np.lexsort((v, u))
    u, v = u[order], v[order]
    fresh = np.r_[True, (u[1:] != u[:-1]) | (v[1:] != v[:-1])]
    return u[fresh], v[fresh]


def _cut(sizes: np.ndarray) -> Iterator[tuple[int, int]]:
    """Stretches of lists with about BUNDLE entries."""
    ends, at = np.cumsum(sizes), 0
    while at < len(sizes):
        before = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + BUNDLE, "right")))
        yield at, to
        at = to


def _row(names: str, *values) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "binary": pa.binary()}
    fields = [f.split() for f in names.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([x], kinds[k]) for x, (_, k) in zip(values, fields, strict=True)], names=[n for n, _ in fields])


def _bundles(names: str, key: int, kind: int, ids: np.ndarray, sizes: np.ndarray, entries: np.ndarray) -> Iterator[pa.RecordBatch]:
    at = np.r_[0, np.cumsum(sizes)]
    for a, b in _cut(sizes):
        yield _row(names, key, kind, squeezed(ids[a:b]), squeezed(sizes[a:b]), squeezed(entries[at[a] : at[b]]))


def _read(batches) -> Iterator[tuple]:
    """(key, kind, ids, counts, entries) of packed rows."""
    for batch in batches:
        keys, kinds = batch.column(0).to_pylist(), batch.column(1).to_pylist()
        for i, (key, kind) in enumerate(zip(keys, kinds, strict=True)):
            yield key, kind, *(unsqueezed(batch.column(c)[i].as_buffer() or b"") for c in (2, 3, 4))


class _Pairs:
    """Pairs that come in pieces; repeats are dropped when many are held."""

    def __init__(self):
        self.us, self.vs, self.n, self.limit = [], [], 0, HELD

    def add(self, u: np.ndarray, v: np.ndarray) -> None:
        self.us.append(u)
        self.vs.append(v)
        self.n += len(u)
        if self.n >= self.limit:
            self.settle()
            self.limit = max(HELD, 2 * self.n)

    def settle(self) -> tuple[np.ndarray, np.ndarray]:
        u, v = _distinct(np.concatenate(self.us), np.concatenate(self.vs))
        self.us, self.vs, self.n = [u], [v], len(u)
        return u, v


def _kept(pairs: _Pairs) -> Iterator[pa.RecordBatch]:
    """The lists of a task's pairs."""
    from pyspark import TaskContext

    if not pairs.n:
        return
    u, v = pairs.settle()
    heads, sizes = np.unique(u, return_counts=True)
    at, part = np.r_[0, np.cumsum(sizes)], TaskContext.get().partitionId()
    for a, b in _cut(sizes):
        entries = v[at[a] : at[b]]
        row = _row(_PACKED, part, _LISTS, squeezed(heads[a:b]), squeezed(sizes[a:b]), squeezed(entries))
        for name, x in (("low", heads[a]), ("top", heads[b - 1]), ("high", entries.max())):
            row = row.append_column(name, pa.array([int(x)], pa.int64()))
        yield row


def _make(batches) -> Iterator[pa.RecordBatch]:
    pairs = _Pairs()
    for batch in batches:
        pairs.add(batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False))
    yield from _kept(pairs)


def _mixed(x: np.ndarray) -> np.ndarray:
    """Numbers without the order of x."""
    x = x.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (x ^ (x >> np.uint64(32))).astype(np.int64) & 0x7FFFFFFF


def _dealt(goal: np.ndarray, sizes: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """The places of each goal in order, BUNDLE entries at a time."""
    if not len(goal):
        return
    order = np.argsort(goal, kind="stable")
    goals, first = np.unique(goal[order], return_index=True)
    for q, a, b in zip(goals, first, np.r_[first[1:], len(order)], strict=True):
        for x, y in _cut(sizes[order[a:b]]):
            yield int(q), order[a + x : a + y]


def _deal_groups(parts: int):
    """Rows (group, member) as packed groups, each to one task."""

    def packed(pairs: _Pairs) -> Iterator[pa.RecordBatch]:
        g, i = pairs.settle()
        groups, sizes = np.unique(g, return_counts=True)
        at = np.cumsum(sizes) - sizes
        for q, x in _dealt(_mixed(groups) % parts, sizes):
            yield _row(_SENT, q, 0, squeezed(groups[x]), squeezed(sizes[x]), squeezed(i[ragged(at[x], sizes[x])]))

    def run(batches) -> Iterator[pa.RecordBatch]:
        pairs = _Pairs()
        for batch in batches:
            pairs.add(batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False))
            if pairs.n >= HELD:
                yield from packed(pairs)
                pairs = _Pairs()
        if pairs.n:
            yield from packed(pairs)

    return run


def _deal_members(parts: int, bits: int):
    """Whole groups, each from its first member in a block of ids on, to the task of that block."""

    def run(batches) -> Iterator[pa.RecordBatch]:
        pairs = _Pairs()
        for _, _, groups, sizes, entries in _read(batches):
            pairs.add(np.repeat(groups, sizes), entries)
        if not pairs.n:
            return
        g, i = pairs.settle()
        block = i >> bits
        other = np.r_[True, g[1:] != g[:-1]]
        start = np.flatnonzero(other | np.r_[True, block[1:] != block[:-1]])
        end = np.r_[np.flatnonzero(other)[1:], len(g)][np.cumsum(other)[start] - 1]
        start, end = start[end - start >= 2], end[end - start >= 2]
        for q, x in _dealt(block[start] % parts, end - start):
            x = x[np.argsort(i[start[x]], kind="stable")]
            n = (end - start)[x]
            yield _row(_SENT, q, 0, b"", squeezed(n), squeezed(i[ragged(start[x], n)]))

    return run


def _join_members(bits: int):
    """The lists of a block's ids from its groups."""

    def run(batches) -> Iterator[pa.RecordBatch]:
        pairs = _Pairs()
        for _, _, _, sizes, entries in _read(batches):
            last = np.cumsum(sizes)
            owner = np.repeat(np.arange(len(sizes)), sizes)
            head = np.flatnonzero(entries >> bits == (entries[last - sizes] >> bits)[owner])
            after = last[owner[head]] - head - 1
            for a, b in _steps(after):
                n = after[a:b]
                pairs.add(np.repeat(entries[head[a:b]], n), entries[ragged(head[a:b] + 1, n)])
        yield from _kept(pairs)

    return run


def _of_groups(rows: DataFrame, parts: int) -> DataFrame:
    """The lists of the graph of (g, i), where two members are joined if they share a group."""
    rows = rows.select(F.col("g").cast("long").alias("g"), F.col("i").cast("long").alias("i"))
    ends = rows.agg(F.min("i").alias("a"), F.max("i").alias("b")).first()
    bits = min(NEAR_BITS, max(0, (((ends["b"] or 0) - (ends["a"] or 0)) // parts).bit_length() - 1))
    groups = rows.mapInArrow(_deal_groups(parts), _SENT).repartitionById(parts, "q").mapInArrow(_deal_members(parts, bits), _SENT)
    return groups.repartitionById(parts, "q").mapInArrow(_join_members(bits), _KEPT)


def _pairs(names: tuple[str, ...], *columns: np.ndarray) -> Iterator[pa.RecordBatch]:
    for a in range(0, len(columns[0]), 100_000):
        yield pa.RecordBatch.from_arrays([pa.array(c[a : a + 100_000]) for c in columns], names=list(names))


class _Sums:
    """Sums by id; repeats are added up when many are held."""

    def __init__(self):
        self.ids, self.by, self.n, self.limit = [], [], 0, HELD

    def add(self, ids: np.ndarray, by: np.ndarray) -> None:
        self.ids.append(ids)
        self.by.append(by)
        self.n += len(ids)
        if self.n >= self.limit:
            self.settle()
            self.limit = max(HELD, 2 * self.n)

    def settle(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.n:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        ids, by = np.concatenate(self.ids), np.concatenate(self.by)
        order = np.argsort(ids, kind="stable")
        ids, by = ids[order], by[order]
        first = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
        ids, by = ids[first], np.add.reduceat(by, first)
        self.ids, self.by, self.n = [ids], [by], len(ids)
        return ids, by

    def sent(self, parts: int) -> Iterator[pa.RecordBatch]:
        ids, by = self.settle()
        for q, x in _dealt((ids >> NEAR_BITS) % parts, np.ones(len(ids), np.int64)):
            yield _row(_SUMS, q, squeezed(ids[x]), squeezed(by[x]))


def _add_up(name: str):
    def run(batches) -> Iterator[pa.RecordBatch]:
        sums = _Sums()
        for batch in batches:
            for i in range(batch.num_rows):
                sums.add(*(unsqueezed(batch.column(c)[i].as_buffer()) for c in (1, 2)))
        yield from _pairs(("id", name), *sums.settle())

    return run


def _summed(sent: DataFrame, parts: int, name: str) -> DataFrame:
    """(id, name) from packed sums, which are shuffled as they are."""
    return sent.repartitionById(parts, "q").mapInArrow(_add_up(name), f"id long, {name} long")


def _parts(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _degrees(parts: int):
    def run(batches) -> Iterator[pa.RecordBatch]:
        sums = _Sums()
        for _, _, ids, sizes, entries in _read(batches):
            sums.add(ids, sizes)
            sums.add(*np.unique(entries, return_counts=True))
        yield from sums.sent(parts)

    return run


def _touched(batches) -> Iterator[pa.RecordBatch]:
    for part, _, ids, _, entries in _read(batches):
        every = np.union1d(ids, entries)
        yield from _pairs(("part", "id"), np.full(len(every), part, np.int32), every)


def _unpack(batches) -> Iterator[pa.RecordBatch]:
    for _, _, ids, sizes, entries in _read(batches):
        yield from _pairs(("u", "v"), np.repeat(ids, sizes), entries)


def _spread(batches) -> Iterator[pa.RecordBatch]:
    """Some ids of a row with the edges up to each."""
    for _, _, ids, sizes, _ in _read(batches):
        ends = np.cumsum(sizes)
        at = np.unique(np.searchsorted(ends, np.linspace(1, ends[-1], min(len(ids), 32)).astype(np.int64)))
        yield from _pairs(("id", "n"), ids[at], np.diff(ends[at], prepend=0) + np.where(np.arange(len(at)) == len(at) - 1, ends[-1] - ends[at[-1]], 0))


def pack(g: Graph) -> Packed:
    """Lists of a graph, made in one pass over its groups, or over its edges, which may repeat in ``g.pairs``."""
    from localcoef.plans.store import written

    if g.groups is not None:
        rows = _of_groups(g.groups, _parts(g.groups))
    else:
        pairs = g.edges if g.pairs is None else g.pairs
        near = pairs.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).repartition(F.shiftright("u", NEAR_BITS))
        rows = near.mapInArrow(_make, _KEPT)
    rows = written(rows, "lists")
    deg = _summed(rows.mapInArrow(_degrees(_parts(rows)), _SUMS), _parts(rows), "deg")
    if not g.ends:
        deg = g.nodes.join(deg, "id", "left").select("id", F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))
    deg = written(deg, "degrees")
    m = (deg.agg(F.sum("deg").alias("n")).first()["n"] or 0) // 2
    return Packed(rows, deg, m)


def indexed(g: Graph) -> Graph:
    """The same graph with its lists and degrees written."""
    if g.packed is not None:
        return g
    p = pack(g)
    return Graph(p.deg.select("id"), p.rows.mapInArrow(_unpack, "u long, v long"), packed=p, ends=g.ends)


def _ranges(p: Packed, n: int) -> np.ndarray:
    """Where ids are cut into n ranges with about as many edges each."""
    seen = sorted((r["id"], r["n"]) for r in p.rows.mapInArrow(_spread, "id long, n long").collect())
    ids, weight = np.array([i for i, _ in seen], np.int64), np.cumsum([k for _, k in seen])
    return np.unique(ids[np.searchsorted(weight, weight[-1] * np.arange(1, n) / n)]) if len(ids) and n > 1 else np.empty(0, np.int64)


def _send(cuts: np.ndarray):
    def run(batches) -> Iterator[pa.RecordBatch]:
        for _, _, ids, sizes, entries in _read(batches):
            at = np.r_[0, np.cumsum(sizes)]
            home = np.searchsorted(cuts, ids, "right")
            first = np.r_[0, np.flatnonzero(np.diff(home)) + 1, len(ids)]
            for a, b in zip(first[:-1], first[1:], strict=True):
                yield from _bundles(_SENT, int(home[a]), 0, ids[a:b], sizes[a:b], entries[at[a] : at[b]])
            owner = np.repeat(np.arange(len(ids)), sizes)
            to = np.searchsorted(cuts, entries, "right")
            start = np.flatnonzero(np.r_[True, (owner[1:] != owner[:-1]) | (to[1:] != to[:-1])])
            start = start[at[owner[start] + 1] - start >= 2]
            start = start[np.argsort(to[start], kind="stable")]
            length, goal = at[owner[start] + 1] - start, to[start]
            for q in np.unique(goal):
                x, y = np.searchsorted(goal, (q, q + 1))
                for a, b in _cut(length[x:y]):
                    s, n = start[x + a : x + b], length[x + a : x + b]
                    yield _row(_SENT, int(q), 1, squeezed(ids[owner[s]]), squeezed(n), squeezed(entries[ragged(s, n)]))

    return run


class _Places:
    """Where ids stand in a sorted array; -1 where they do not."""

    def __init__(self, ids: np.ndarray):
        self.ids, self.low = ids, int(ids[0])
        self.table = None
        if (spread := int(ids[-1]) - self.low + 1) <= max(1 << 20, 4 * len(ids)):
            self.table = np.full(spread, -1, np.int32)
            self.table[ids - self.low] = np.arange(len(ids), dtype=np.int32)

    def of(self, x: np.ndarray) -> np.ndarray:
        if self.table is not None:
            inside = (x >= self.low) & (x <= self.ids[-1])
            return np.where(inside, self.table[np.where(inside, x - self.low, 0)], -1)
        at = np.minimum(np.searchsorted(self.ids, x), len(self.ids) - 1)
        return np.where(self.ids[at] == x, at, -1)


class _Tally:
    """Sums by place, added up when many have come."""

    def __init__(self, n: int):
        self.sum, self.held, self.n = np.zeros(n, np.int64), [], 0

    def add(self, at: np.ndarray, by: np.ndarray | None = None) -> None:
        self.held.append((at, np.ones(len(at), np.int64) if by is None else by))
        self.n += len(at)
        if self.n > max(1 << 20, len(self.sum)):
            self.settle()

    def settle(self) -> np.ndarray:
        if self.held:
            self.sum += np.bincount(np.concatenate([a for a, _ in self.held]), np.concatenate([b for _, b in self.held]), len(self.sum)).astype(np.int64)
        self.held, self.n = [], 0
        return self.sum


class _Range:
    """The lists of one range of ids; arriving lists are met with them."""

    def __init__(self, lists: list[tuple[np.ndarray, np.ndarray, np.ndarray]]):
        heads = np.concatenate([x[0] for x in lists])
        sizes, entries = np.concatenate([x[1] for x in lists]), np.concatenate([x[2] for x in lists])
        order = np.argsort(heads, kind="stable")
        starts = (np.cumsum(sizes) - sizes)[order]
        self.heads, self.sizes = heads[order], sizes[order]
        self.far, place = np.unique(entries[ragged(starts, self.sizes)], return_inverse=True)
        self.near, self.starts = place.astype(np.int32), np.cumsum(self.sizes) - self.sizes
        self.head_of, self.far_of, self.keys = _Places(self.heads), _Places(self.far), None
        self.middle, self.last, self.square, self.both = _Tally(len(self.heads)), _Tally(len(self.far)), None, None

    def meet(self, ids: np.ndarray, sizes: np.ndarray, entries: np.ndarray, listing: bool) -> Iterator[tuple[np.ndarray, ...]]:
        """Triangles of arriving lists: (u, number) or, listed, (u, v, w)."""
        middle, far = self.head_of.of(entries), self.far_of.of(entries)
        at, width = np.r_[0, np.cumsum(sizes)], len(self.far)
        per = max(1, MARKS // width)
        hashed = per * len(entries) < FILL // 4 * len(ids)
        mark = np.zeros(MARKS if hashed else min(per, len(ids)) * width, bool)
        for a, b in _steps(sizes, FILL) if hashed else ((a, min(a + per, len(ids))) for a in range(0, len(ids), per)):
            lo, hi = at[a], at[b]
            who = np.repeat(np.arange(b - a), sizes[a:b])
            seen = far[lo:hi] >= 0
            known = who[seen] * width + far[lo:hi][seen]
            marked = _slots(known) if hashed else known
            mark[marked] = True
            pair = np.flatnonzero(middle[lo:hi] >= 0)
            if len(pair):
                x, y = who[pair], middle[lo:hi][pair].astype(np.int64)
                cells = (b - a) * len(self.heads) * width
                if not (listing or hashed) and len(self.heads) * width <= DENSE and CELLS * np.minimum(self.sizes[y], LONGER * sizes[a:b][x]).sum() > cells:
                    yield from self._multiplied(mark[: (b - a) * width].reshape(b - a, width), x, y, ids[a:b])
                else:
                    long = self.sizes[y] > LONGER * sizes[a:b][x]
                    yield from self._walked(mark, known if hashed else None, width, x[~long], y[~long], ids[a:b], listing)
                    yield from self._searched(x[long], y[long], ids[a:b], at[a:b], sizes[a:b], far, width, listing)
            mark[marked] = False

    def _multiplied(self, mark, x, y, ids) -> Iterator[tuple[np.ndarray, ...]]:
        """All members at once: what the lists of a list's members hold, and what the lists of a member hold, as products. Sums below 2**24 are exact."""
        if self.square is None:
            self.square = np.zeros((len(self.heads), len(self.far)), np.float32)
            self.square[np.repeat(np.arange(len(self.heads)), self.sizes), self.near] = 1
            self.both = np.zeros(self.square.shape, np.int64)
        marks, joined = mark.astype(np.float32), np.zeros((len(ids), len(self.heads)), np.float32)
        joined[x, y] = 1
        self.both += (joined.T @ marks).astype(np.int64)
        mine = np.einsum("ij,ij->i", joined @ self.square, marks, dtype=np.float64).astype(np.int64)
        yield ids[mine > 0], mine[mine > 0]

    def _walked(self, mark, known, width, x, y, ids, listing) -> Iterator[tuple[np.ndarray, ...]]:
        """Each member of the range's list is looked up among the marks of the arriving one; hashed marks are confirmed among what is known."""
        for s, e in _steps(self.sizes[y]):
            xs, ys, n = x[s:e], y[s:e], self.sizes[y[s:e]]
            w = self.near[ragged(self.starts[ys], n)]
            key = np.repeat(xs * width, n) + w
            hit = np.flatnonzero(mark[key if known is None else _slots(key)])
            if known is not None and len(hit):
                found = key[hit]
                hit = hit[known[np.minimum(np.searchsorted(known, found), len(known) - 1)] == found]
            yield from self._found(np.searchsorted(np.cumsum(n), hit, "right"), xs, ys, w[hit], ids, listing)

    def _searched(self, x, y, ids, at, sizes, far, width, listing) -> Iterator[tuple[np.ndarray, ...]]:
        """Each member of the arriving list is searched in the much longer list of the range."""
        if len(x) and self.keys is None:
            self.keys = np.repeat(np.arange(len(self.heads)) * width, self.sizes) + self.near
        for s, e in _steps(sizes[x]):
            xs, ys, n = x[s:e], y[s:e], sizes[x[s:e]]
            w = far[ragged(at[xs], n)]
            known = np.flatnonzero(w >= 0)
            pair = np.repeat(np.arange(len(xs)), n)[known]
            key = ys[pair] * width + w[known]
            hit = self.keys[np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)] == key
            yield from self._found(pair[hit], xs, ys, w[known][hit], ids, listing)

    def _found(self, pair, x, y, w, ids, listing) -> Iterator[tuple[np.ndarray, ...]]:
        if not len(pair):
            return
        if listing:
            yield ids[x[pair]], self.heads[y[pair]], self.far[w]
            return
        n = np.bincount(pair, minlength=len(x))
        self.last.add(w)
        self.middle.add(y, n)
        mine = np.bincount(x, n, len(ids)).astype(np.int64)
        yield ids[mine > 0], mine[mine > 0]

    def sums(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        if self.both is not None:
            self.both *= self.square > 0
        for axis, (ids, tally) in enumerate(((self.heads, self.middle), (self.far, self.last))):
            n = tally.settle() + (self.both.sum(axis=1 - axis, dtype=np.int64) if self.both is not None else 0)
            yield ids[n > 0], n[n > 0]


def _slots(key: np.ndarray) -> np.ndarray:
    """Cells of keys that are too many for a cell each."""
    return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(65 - MARKS.bit_length())).astype(np.int64)


def _steps(sizes: np.ndarray, most: int = 0) -> Iterator[tuple[int, int]]:
    ends, at = np.cumsum(sizes), 0
    while at < len(sizes):
        before = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + (most or STEP), "right")))
        yield at, to
        at = to


def _meet(listing: bool):
    names = ("a", "b", "c") if listing else ("id", "t")

    def run(batches) -> Iterator[pa.RecordBatch]:
        q, lists, here = None, [], None
        for key, kind, ids, sizes, entries in _read(batches):
            if key != q:
                if here is not None and not listing:
                    for found in here.sums():
                        yield from _pairs(names, *found)
                q, lists, here = key, [], None
            if kind == 0:
                lists.append((ids, sizes, entries))
                continue
            if here is None:
                if not lists:
                    continue
                here, lists = _Range(lists), []
            for found in here.meet(ids, sizes, entries, listing):
                yield from _pairs(names, *found)
        if here is not None and not listing:
            for found in here.sums():
                yield from _pairs(names, *found)

    return run


def _reach(start: int, end: int, ids: np.ndarray, sizes: np.ndarray, entries: np.ndarray) -> tuple[np.ndarray, ...]:
    """Lists from their first member in the range on, where it has another one after it."""
    last = np.cumsum(sizes)
    n = np.add.reduceat((entries >= start).astype(np.int64), last - sizes)
    first = last - n
    ok = np.flatnonzero((n >= 2) & (entries[np.minimum(first, len(entries) - 1)] < end))
    return ids[ok], n[ok], entries[ragged(first[ok], n[ok])]


def _meet_here(start: int, end: int, own: int, listing: bool, parts: int):
    """One range: ``own`` rows of kind 0 that hold its lists, and those of kind 1 that reach it, which wait for the former."""

    def run(batches) -> Iterator[pa.RecordBatch]:
        lists, waiting, here, left, sums = [], [], None, own, _Sums()

        def met(ids: np.ndarray, sizes: np.ndarray, entries: np.ndarray) -> Iterator[pa.RecordBatch]:
            ids, sizes, entries = _reach(start, end, ids, sizes, entries)
            for found in here.meet(ids, sizes, entries, listing) if len(ids) else ():
                if listing:
                    yield from _pairs(("a", "b", "c"), *found)
                else:
                    sums.add(*found)

        for batch in batches:
            kinds = batch.column(1).to_pylist()
            for i, kind in enumerate(kinds):
                row = tuple(batch.column(c)[i].as_buffer().to_pybytes() if here is None and kind else batch.column(c)[i].as_buffer() for c in (2, 3, 4))
                if kind and here is None:
                    waiting.append(row)
                    continue
                ids, sizes, entries = map(unsqueezed, row)
                if kind:
                    yield from met(ids, sizes, entries)
                    continue
                inside = np.flatnonzero((ids >= start) & (ids < end))
                at = np.cumsum(sizes) - sizes
                lists.append((ids[inside], sizes[inside], entries[ragged(at[inside], sizes[inside])]))
                left -= 1
                if not left and sum(len(x[0]) for x in lists):
                    here, lists = _Range(lists), []
                    for row in waiting:
                        yield from met(*map(unsqueezed, row))
                    waiting = []
        if here is not None and not listing:
            for found in here.sums():
                sums.add(*found)
            yield from sums.sent(parts)

    return run


def _nothing(batches) -> Iterator[pa.RecordBatch]:
    yield from ()


def _ranges_read(p: Packed, cuts: np.ndarray, listing: bool) -> DataFrame:
    """Every range in a task of its own that reads what it needs of the written lists."""
    heads = [(r["low"], r["top"]) for r in p.rows.select("low", "top").collect()]
    bounds, branches = [-(2**63), *map(int, cuts), 2**63 - 1], []
    for start, end in zip(bounds[:-1], bounds[1:], strict=True):
        end += end == bounds[-1]  # the last range holds the largest number too
        upto = F.col("low") < end if end < 2**63 else F.lit(True)
        mine, rows = upto & (F.col("top") >= start), sum(a < end and b >= start for a, b in heads)
        if rows:
            near = p.rows.where(mine).withColumn("kind", F.lit(0)).unionAll(p.rows.where(upto & (F.col("high") >= start)).withColumn("kind", F.lit(1)))
            branches.append(near.coalesce(1).mapInArrow(_meet_here(start, end, rows, listing, _parts(p.rows)), "a long, b long, c long" if listing else _SUMS))
    # Spark runs a union of single partitions as one task; with a branch of two, which has no rows, it keeps a task for each
    branches.append(p.rows.sparkSession.range(0, 2, 1, 2).mapInArrow(_nothing, branches[0].schema))
    while len(branches) > 1:
        branches = [x.unionAll(y) for x, y in zip(branches[::2], branches[1::2], strict=False)] + branches[len(branches) // 2 * 2 :]
    return branches[0]


def _met(p: Packed, listing: bool) -> DataFrame:
    """(a, b, c), or packed sums."""
    n = max(1, min(24, p.m // 20_000), -(-p.m // RANGE))
    cuts = _ranges(p, n)
    if p.m >= DIRECT:
        return _ranges_read(p, cuts, listing)
    sent = p.rows.mapInArrow(_send(cuts), _SENT).repartitionById(len(cuts) + 1, "q").sortWithinPartitions("q", "kind")
    return sent.mapInArrow(_meet(listing), "a long, b long, c long") if listing else sent.mapInArrow(_sent_sums(_parts(p.rows)), _SUMS)


def _sent_sums(parts: int):
    def run(batches) -> Iterator[pa.RecordBatch]:
        sums = _Sums()
        for batch in _meet(False)(batches):
            sums.add(*(batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1)))
        yield from sums.sent(parts)

    return run


def listed_triangles(p: Packed) -> DataFrame:
    """(a, b, c) with a < b < c, each triangle once."""
    return _met(p, True)


def counted_triangles(p: Packed) -> DataFrame:
    """(id, t) of the nodes with a triangle."""
    return _summed(_met(p, False), _parts(p.rows), "t")


def _ahead(batches) -> Iterator[pa.RecordBatch]:
    """Degrees come first, then the lists between the nodes they belong to."""
    part, ids, deg = None, [], []
    place = known = out = None

    def done():
        if out is not None:
            yield from _pairs(("id", "wh"), place.ids[out > 0], out[out > 0])

    for batch in batches:
        cols = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
        kinds, parts = cols["kind"].to_numpy(zero_copy_only=False), cols["part"].to_numpy(zero_copy_only=False)
        edges = np.r_[0, np.flatnonzero(np.diff(parts) | np.diff(kinds)) + 1, len(kinds)]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            if parts[a] != part:
                yield from done()
                part, ids, deg, place, out = parts[a], [], [], None, None
            if kinds[a] == 0:
                ids.append(cols["id"].slice(a, b - a).to_numpy(zero_copy_only=False))
                deg.append(cols["deg"].slice(a, b - a).to_numpy(zero_copy_only=False))
                continue
            if place is None:
                every, size = np.concatenate(ids), np.concatenate(deg)
                order = np.argsort(every)
                place, known, out = _Places(every[order]), size[order].astype(np.int64), np.zeros(len(every), np.int64)
            for i in range(a, b):
                heads, sizes, entries = (unsqueezed(cols[c][i].as_buffer()) for c in ("ids", "counts", "entries"))
                u, v = np.repeat(place.of(heads), sizes), place.of(entries)
                out += np.bincount(u, known[v] - 1, len(out)).astype(np.int64) + np.bincount(v, known[u] - 1, len(out)).astype(np.int64)
    yield from done()


def headed_wedges(p: Packed) -> DataFrame:
    """(id, wh) of the nodes with a headed wedge: a node's degree goes once to each part that has an edge of it."""
    touched = p.rows.mapInArrow(_touched, "part int, id long").distinct()
    none = lambda kind, *names: [F.lit(None).cast(kind).alias(n) for n in names]
    given = touched.join(p.deg, "id").select("part", F.lit(0).alias("kind"), "id", "deg", *none("binary", "ids", "counts", "entries"))
    lists = p.rows.select("part", F.lit(1).alias("kind"), *none("long", "id", "deg"), "ids", "counts", "entries")
    dealt = given.unionByName(lists).repartition("part").sortWithinPartitions("part", "kind")
    return dealt.mapInArrow(_ahead, "id long, wh long").groupBy("id").agg(F.sum("wh").alias("wh"))
