"""Near-duplicate groups by a forest of sorted min-hash signatures.

Each document's set of distinct word shingles has a signature of ``trees * depth`` minima. Documents with equal sets
are one class from the start. For each tree the classes are sorted by that tree's minima; classes next to each other
whose common prefix is long enough are candidates, so crowded regions are compared at a greater depth than sparse
ones. Candidates are confirmed on full sets, and links give components.

Where a region (equal prefixes of the least depth) holds more classes than its neighbours cover and they fall into
several components, its depth grows: its classes are sorted again by ``deep`` minima, and neighbours of different
components are candidates. Before that, classes that cannot have a link to another component are left out exactly: a
link needs ``percent`` of either set, and only shingles that stand in several components count. What is still apart is
compared, in blocks of bounded size, by exact overlaps of the shingles left, outside the region's largest component.
No pair is emitted there but links that join two components, and no pair is dropped by an estimate.

Cases: null text, and text without words, has an empty set, no link, and is its own group; a text shorter than a
shingle is one shingle; equal sets are one class; rows with the same id and text fall into the same group; of rows
with the same id and different texts each has its own group; a null id has a null group and is kept; ids that are not
whole numbers are refused; an empty table gives an empty table. Only the named columns are read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from localcoef.llm.components import components
from localcoef.llm.store import discard, kept, written
from localcoef.llm.textcore import WordBlock, mix, text_blocks, window_hashes


@dataclass(frozen=True)
class Forest:
    shingle: int = 5
    #: Links need 100 * intersection >= percent * union.
    percent: int = 75
    trees: int = 24
    depth: int = 5
    #: Least common prefix of candidates; a pair at the threshold is missed by all trees with probability 2e-6.
    least: int = 3
    #: Minima that a crowded region is sorted by.
    deep: int = 24
    #: Following classes in a sorted order that each class is a candidate with.
    reach: int = 2
    #: Bytes of shingles of a region that are compared at once.
    block_bytes: int = 8_000_000


#: Bytes of one minimum in a signature.
MARK = 2


def shingle_sets(texts: list[str | None], size: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's shingles."""
    block = WordBlock(texts, lower=True)
    words = block.hashes()
    runs = window_hashes(words, size)
    out = []
    for a, b in zip(block.first[:-1].tolist(), block.first[1:].tolist(), strict=True):
        if b - a >= size:
            out.append(np.unique(runs[a : b - size + 1]))
        else:
            out.append(window_hashes(words[a:b], b - a) if b > a else np.zeros(0, np.uint64))
    return out


_RNG = np.random.default_rng(77)
_FLIP, _TIMES = _RNG.integers(0, 2**32, (2, 4096), dtype=np.uint32)
_TIMES |= np.uint32(1)


def signatures(sets: list[np.ndarray], size: int) -> np.ndarray:
    """Sixteen bits of the minima of ``size`` hash orders over each set."""
    out = np.full((len(sets), size), 0xFFFF, np.uint16)
    full = [i for i, s in enumerate(sets) if len(s)]
    if full:
        every = (np.concatenate([sets[i] for i in full]) >> np.uint64(32)).astype(np.uint32)
        start = np.concatenate([[0], np.cumsum([len(sets[i]) for i in full])[:-1]])
        for k in range(size):
            least = np.minimum.reduceat((every ^ _FLIP[k]) * _TIMES[k], start)
            out[full, k] = (least ^ (least >> np.uint32(16))).astype(np.uint16)
    return out


def _size_mark(n: int, percent: int) -> int:
    """A step of the set's size; sets that can be linked are at most one step apart."""
    return int(math.log(n) / math.log(101 / percent)) if n > 1 else 0


def sketch(docs: DataFrame, rule: Forest, id_col: str, text_col: str) -> DataFrame:
    """Per row: id, a hash of the text, n_shingles, two hashes of the set (null if empty) and the signature with a size mark."""
    if not isinstance(docs.select(id_col).schema[0].dataType, IntegralType):
        raise TypeError("ids of near duplicates are whole numbers, as the least of them names a group")

    def run(batches):
        for batch in batches:
            for low, high, texts in text_blocks(batch.column(2)):
                sets = shingle_sets(texts, rule.shingle)
                marks = signatures(sets, rule.trees * rule.depth)
                a = [int(s.sum(dtype=np.uint64)) - (1 << 63) if len(s) else None for s in sets]
                b = [int(mix(s ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64)) - (1 << 63) if len(s) else None for s in sets]
                signed = [m.tobytes() + bytes([_size_mark(len(s), rule.percent)]) if len(s) else None for m, s in zip(marks, sets, strict=True)]
                heads = [c.slice(low, high - low) for c in batch.columns[:2]]
                yield pa.RecordBatch.from_arrays([*heads, pa.array([len(s) for s in sets], pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(signed, pa.binary())], ["id", "key", "n_shingles", "fa", "fb", "marks"])

    rows = docs.select(F.col(id_col).cast("long"), F.xxhash64(F.col(text_col).cast("string")), F.col(text_col).cast("string"))
    return rows.mapInArrow(run, "id long, key long, n_shingles long, fa long, fb long, marks binary")


def _tree_key(tree: Column, rule: Forest, minima: int) -> Column:
    """A tree's number, its first minima, going on with those of the next trees, and the size mark."""
    whole = MARK * rule.trees * rule.depth
    turned = F.concat(F.substring("marks", 1, whole), F.substring("marks", 1, MARK * minima)) if minima > rule.depth else F.col("marks")
    return F.concat(F.unhex(F.lpad(F.hex(tree), 4, "0")), F.substring(turned, tree * (MARK * rule.depth) + 1, F.lit(MARK * minima)), F.substring("marks", whole + 1, 1))


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    """Equally long binary values as a byte matrix."""
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, width)


def _neighbours(rule: Forest, minima: int):
    width, prefix = 3 + MARK * minima, 2 + MARK * rule.least

    def run(batches):
        """Pairs of near rows of different groups in a sorted part, and the part's outermost rows."""
        keep = np.zeros((0, width), np.uint8), np.zeros(0, np.int64), np.zeros(0, np.int64)
        first = True
        for batch in batches:
            if not batch.num_rows:
                continue
            new = _matrix(batch.column(0), width), batch.column(1).to_numpy(), batch.column(batch.num_columns - 1).to_numpy()
            if first:
                yield _edge(*(x[: rule.reach] for x in new))
                first = False
            rows = [np.concatenate(x) for x in zip(keep, new, strict=True)]
            pairs = _near(*rows, len(keep[1]), rule.reach, prefix)
            yield pa.RecordBatch.from_arrays([pa.nulls(len(pairs), pa.binary()), pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["key", "u", "v"])
            keep = tuple(x[-rule.reach :] for x in rows)
        if not first:
            yield _edge(*keep)

    return run


def _edge(key: np.ndarray, ids: np.ndarray, groups: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([k.tobytes() for k in key], pa.binary()), pa.array(ids), pa.array(groups)], ["key", "u", "v"])


def _near(key: np.ndarray, ids: np.ndarray, groups: np.ndarray, old: int, reach: int, prefix: int) -> np.ndarray:
    """Pairs up to ``reach`` rows apart with the same tree and prefix and sizes alike, of which one row at least is not old."""
    found = [np.zeros((0, 2), np.int64)]
    for step in range(1, reach + 1):
        if len(key) > step:
            same = (key[step:, :prefix] == key[:-step, :prefix]).all(1) & (groups[step:] != groups[:-step])
            same &= np.abs(key[step:, -1].astype(np.int16) - key[:-step, -1]) <= 1
            same[: max(0, old - step)] = False
            at = np.flatnonzero(same)
            found.append(np.stack([ids[at], ids[at + step]], 1))
    return np.concatenate(found)


def _sorted_pairs(rows: DataFrame, rule: Forest, minima: int) -> DataFrame:
    """Distinct pairs (u < v) of neighbours in the order of ``key``; rows are (key, rep) or (key, rep, component)."""
    spark = rows.sparkSession
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    ordered = rows.repartitionByRange(n, "key", "rep").sortWithinPartitions("key", "rep")
    schema, run = "key binary, u long, v long", _neighbours(rule, minima)
    found = kept(ordered.mapInArrow(run, schema))
    # the outermost rows of the parts, a few for each, meet across the borders
    borders = found.where("key is not null").select("key", "u", "v").distinct().repartition(1).sortWithinPartitions("key", "u")
    across = borders.mapInArrow(run, schema).where("key is null")
    every = found.where("key is null").select("u", "v").unionByName(across.select("u", "v"))
    out = written(every.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u <> v").distinct(), "pairs")
    found.unpersist()
    return out


def _in_trees(rule: Forest, make) -> Column:
    return F.explode(F.transform(F.sequence(F.lit(0), F.lit(rule.trees - 1)), make))


def candidates(classes: DataFrame, rule: Forest) -> DataFrame:
    """Distinct pairs (u < v) of classes that are neighbours in a sorted order with a long enough common prefix."""
    return _sorted_pairs(classes.select(_in_trees(rule, lambda t: _tree_key(t, rule, rule.depth)).alias("key"), "rep"), rule, rule.depth)


#: Ids up to this number, of eight bytes each, are broadcast to pick their texts; more are shuffled.
BROADCAST_IDS = 1_000_000


def full_sets(docs: DataFrame, ids: DataFrame, rule: Forest, id_col: str, text_col: str) -> DataFrame:
    """(rep, items): the sets, as bytes, of the classes in ``ids``, pairs of a class and the hash of its set."""
    few = ids.count() <= BROADCAST_IDS
    texts = docs.select(F.col(id_col).cast("long").alias("rep"), F.col(text_col).cast("string").alias("text"))
    texts = texts.join(F.broadcast(ids) if few else ids, "rep", "inner")

    def run(batches):
        for batch in batches:
            reps, wanted = batch.column(0), batch.column(2).to_numpy()
            for low, high, texts in text_blocks(batch.column(1)):
                sets = shingle_sets(texts, rule.shingle)
                # of rows with one id and different texts only those of the class count
                right = pa.array([len(s) > 0 and int(s.sum(dtype=np.uint64)) - (1 << 63) == w for s, w in zip(sets, wanted[low:high].tolist(), strict=True)], pa.bool_())
                yield pa.RecordBatch.from_arrays([reps.slice(low, high - low), pa.array([s.tobytes() for s in sets], pa.binary())], ["rep", "items"]).filter(right)

    return texts.select("rep", "text", "fa").mapInArrow(run, "rep long, items binary").dropDuplicates(["rep"])


def similar(x: np.ndarray, y: np.ndarray, percent: int, n: int | None = None, m: int | None = None) -> bool:
    """Whether two sets overlap enough; of the sets, of n and m items, the given parts hold all that they can share."""
    n, m = n or len(x), m or len(y)
    if 100 * min(n, m) < percent * max(n, m):
        return False
    both = np.concatenate([x, y])
    both.sort(kind="stable")
    common = int(np.count_nonzero(both[1:] == both[:-1]))
    return 100 * common >= percent * (n + m - common)


def _confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) that are similar enough by ``sets`` of (rep, n, items)."""

    def run(batches):
        for batch in batches:
            keep = []
            for n, a, m, b in zip(*(batch.column(i) for i in range(2, 6)), strict=True):
                keep.append(similar(np.frombuffer(a.as_buffer(), np.uint64), np.frombuffer(b.as_buffer(), np.uint64), percent, n.as_py(), m.as_py()))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["u", "v"]).filter(pa.array(keep, pa.bool_()))

    left, right = (sets.select(F.col("rep").alias(x), F.col("n").alias(f"n{x}"), F.col("items").alias(f"items{x}")) for x in "uv")
    return pairs.join(left, "u").join(right, "v").select("u", "v", "nu", "itemsu", "nv", "itemsv").mapInArrow(run, "u long, v long")


def confirmed(docs: DataFrame, classes: DataFrame, pairs: DataFrame, rule: Forest, id_col: str, text_col: str) -> DataFrame:
    """The pairs (u, v) whose full sets are similar enough."""
    ids = kept(classes.select("rep", "fa").join(pairs.select(F.explode(F.array("u", "v")).alias("rep")).distinct(), "rep", "left_semi"))
    sets = written(full_sets(docs, ids, rule, id_col, text_col).withColumn("n", (F.length("items") / 8).cast("long")), "sets")
    links = written(_confirm(pairs, sets, rule.percent), "links")
    discard(docs.sparkSession, sets)
    ids.unpersist()
    return links


def _open_regions(member: DataFrame, least: int, weight: Column) -> DataFrame:
    """Of rows (rep, component, tree, region): the regions of more than ``least`` classes and of several components, with
    the weight of all classes, and the largest component with its weight."""
    parts = member.groupBy("tree", "region", "component").agg(F.count("*").alias("n"), F.sum(weight).alias("w"))
    regions = parts.groupBy("tree", "region").agg(F.sum("n").alias("n"), F.sum("w").alias("w"), F.count("*").alias("parts"), F.max(F.struct("n", "w", "component")).alias("top"))
    regions = regions.where((F.col("n") > least) & (F.col("parts") > 1))
    return regions.select("tree", "region", F.hash("tree", "region").alias("x"), "w", F.col("top.w").alias("top"), F.col("top.component").alias("main"))


def _placed(classes: DataFrame, rule: Forest, *columns: str) -> DataFrame:
    """A row for each class and tree: the named columns, the tree and the region, a hash of its least prefix."""
    spots = _in_trees(rule, lambda t: F.struct(t.alias("tree"), F.xxhash64(F.substring("marks", t * (MARK * rule.depth) + 1, F.lit(MARK * rule.least))).alias("region")))
    return classes.select(*columns, spots.alias("s")).select(*columns, "s.tree", "s.region")


def _labelled(classes: DataFrame, found: DataFrame) -> DataFrame:
    named = found.select(F.col("id").alias("rep"), F.col("component").alias("__label"))
    return classes.drop("component").join(named, "rep", "left").withColumn("component", F.coalesce("__label", "rep")).drop("__label")


def _spread(batches):
    """From (rep, component, items): a row for each shingle."""
    for batch in batches:
        items = [np.frombuffer(x.as_buffer(), np.int64) for x in batch.column(2)]
        sizes = [len(x) for x in items]
        reps, parts = (np.repeat(batch.column(i).to_numpy(), sizes) for i in range(2))
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(items) if items else np.zeros(0, np.int64)), pa.array(reps), pa.array(parts)], ["shingle", "rep", "component"])


def linkable(mates: DataFrame, rule: Forest) -> DataFrame:
    """Of classes (rep, component, n, marks, items): those that can have a link to another component, with the shingles
    that other components have as well. A link needs ``percent`` of either set, so no link is lost."""
    every = mates.select("rep", "component", "items").mapInArrow(_spread, "shingle long, rep long, component long")
    several = every.groupBy("shingle").agg(F.min("component").alias("a"), F.max("component").alias("b")).where("a <> b").select("shingle", F.hash("shingle").alias("x"))
    shared = every.withColumn("x", F.hash("shingle")).join(several, ["shingle", "x"]).groupBy("rep").agg(F.collect_list("shingle").alias("shared"))
    return mates.drop("items").join(shared, "rep").where(100 * F.size("shared") >= rule.percent * F.col("n"))


def _as_bytes(batches):
    """The last column, lists of shingles, as bytes of sorted values."""
    for batch in batches:
        lists = batch.column(batch.num_columns - 1)
        packed = [np.sort(x.values.to_numpy(zero_copy_only=False).view(np.uint64)).tobytes() for x in lists]
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(packed, pa.binary())], [*batch.schema.names[:-1], "items"])


def _compare(rule: Forest):
    def run(frame):
        """Links between the asking classes and those of the block, one for each two components that a link joins."""
        import pandas as pd

        rep, part, ask, n = (frame[c].to_numpy() for c in ("rep", "component", "ask", "n"))
        inside = np.flatnonzero(~ask)
        us, vs = [], []
        if len(inside) and ask.any():
            items = [np.frombuffer(x, np.uint64) for x in frame["items"]]
            number = np.unique(np.concatenate(items), return_inverse=True)[1].astype(np.int32)
            ends = np.cumsum([len(x) for x in items])
            spans = [number[b - len(x) : b] for x, b in zip(items, ends.tolist(), strict=True)]
            held = np.concatenate([spans[i] for i in inside])
            start = np.concatenate([[0], np.cumsum([len(spans[i]) for i in inside])[:-1]])
            flag = np.zeros(int(number.max()) + 1, np.int32)
            root: dict[int, int] = {}

            def find(c):
                while c in root:
                    c = root[c]
                return c

            for i in np.flatnonzero(ask).tolist():
                flag[spans[i]] = 1
                common = np.add.reduceat(flag[held], start)
                flag[spans[i]] = 0
                linked = (100 * common >= rule.percent * (n[inside] + n[i] - common)) & (part[inside] != part[i])
                for k in inside[np.flatnonzero(linked)].tolist():
                    a, b = find(part[i]), find(part[k])
                    if a != b:
                        root[a] = b
                        us.append(rep[i])
                        vs.append(rep[k])
        return pd.DataFrame({"u": np.array(us, np.int64), "v": np.array(vs, np.int64)})

    return run


def crowded(docs: DataFrame, classes: DataFrame, found: DataFrame, tried: DataFrame, rule: Forest, id_col: str, text_col: str) -> DataFrame:
    """The components after the links across components in crowded regions; ``tried`` has the pairs that need no second look."""
    spark = docs.sparkSession
    placed = _placed(_labelled(classes.select("rep", "marks"), found), rule, "rep", "component")
    regions = written(_open_regions(placed, rule.reach + 1, F.lit(1)), "regions")
    if regions.isEmpty():
        return found
    mates = kept(placed.withColumn("x", F.hash("tree", "region")).join(regions.select("tree", "region", "x"), ["tree", "region", "x"]).select("rep", "component").distinct())
    ids = kept(classes.select("rep", "fa", "marks", F.col("n")).join(mates, "rep"))
    sets = full_sets(docs, ids.select("rep", "fa"), rule, id_col, text_col)
    full = written(ids.drop("fa").join(sets, "rep"), "mates")
    few = linkable(full, rule)
    schema = "rep long, marks binary, n long, component long, items binary"
    few = written(few.select("rep", "marks", "n", "component", "shared").mapInArrow(_as_bytes, schema), "linkable")
    for table in (mates, ids):
        table.unpersist()
    discard(spark, full)
    discard(spark, regions)

    # the regions at a greater depth: neighbours of different components
    keys = few.select(_in_trees(rule, lambda t: _tree_key(t, rule, rule.deep)).alias("key"), "rep", "component")
    near = _sorted_pairs(keys, rule, rule.deep)
    links = _confirm(near.join(tried, ["u", "v"], "left_anti"), few.select("rep", "n", "items"), rule.percent)
    deeper = components(found.select(F.col("id").alias("u"), F.col("component").alias("v")).unionByName(links))
    few = _labelled(few, deeper)

    # the classes outside the main component of a region, in blocks of queries, meet every class of the region, in blocks
    weight = F.length("items")
    placed = _placed(few.withColumn("w", weight), rule, "rep", "component", "w").withColumn("x", F.hash("tree", "region"))
    cut = lambda w: F.greatest(F.lit(1), F.ceil(w / rule.block_bytes)).cast("int")
    regions = kept(_open_regions(placed, 1, F.col("w")).select("tree", "region", "x", "main", cut(F.col("w")).alias("blocks"), cut(F.col("w") - F.col("top")).alias("queries")))
    inside = placed.join(regions, ["tree", "region", "x"])
    of = lambda n: F.pmod(F.xxhash64("rep"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    stays = inside.select("tree", "region", of("blocks").alias("block"), every("queries").alias("query"), F.lit(False).alias("ask"), "rep")
    asks = inside.where("component <> main").select("tree", "region", every("blocks").alias("block"), of("queries").alias("query"), F.lit(True).alias("ask"), "rep")
    rows = stays.unionByName(asks).join(few.select("rep", "component", "n", "items"), "rep")
    more = rows.groupBy("tree", "region", "block", "query").applyInPandas(_compare(rule), "u long, v long")
    out = components(deeper.select(F.col("id").alias("u"), F.col("component").alias("v")).unionByName(more))
    regions.unpersist()
    return out


def near_duplicates(docs: DataFrame, rule: Forest = Forest(), id_col: str = "doc_id", text_col: str = "text", with_key: bool = False) -> DataFrame:
    """Per row: the id, n_shingles, component_id (the least id that links reach) and kept (whether that is its own).

    ``with_key`` adds ``text_key``, a 64-bit hash of the row's text, to tell rows with the same id apart.
    """
    rows = kept(sketch(docs, rule, id_col, text_col))
    classes = kept(rows.where("fa is not null and id is not null").groupBy("fa", "fb").agg(F.min("id").alias("rep"), F.min("marks").alias("marks"), F.min("n_shingles").alias("n")))
    tried = candidates(classes, rule)
    links = confirmed(docs, classes, tried, rule, id_col, text_col)
    found = crowded(docs, classes, components(links), tried, rule, id_col, text_col)
    labels = written(classes.select("fa", "fb", "rep").join(found.withColumnRenamed("id", "rep"), "rep", "left").select("fa", "fb", F.coalesce("component", "rep").alias("group")), "labels")
    classes.unpersist()
    joined = rows.select("id", "key", "n_shingles", "fa", "fb").join(labels, ["fa", "fb"], "left")
    group = F.when(F.col("id").isNotNull(), F.coalesce("group", "id"))
    key = [F.col("key").alias("text_key")] if with_key else []
    return joined.select(F.col("id").alias(id_col), "n_shingles", group.alias("component_id"), F.coalesce(group == F.col("id"), F.lit(True)).alias("kept"), *key)
