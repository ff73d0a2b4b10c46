"""Removal of words that lie in repeated runs of words, by suffix automata of reference shards.

The reference is the corpus itself, so its automata would grow with it if they were broadcast. Instead the runs that
can be equal meet in one shard: every run of ``width`` words has an anchor, its least run of ``anchor`` words by hash,
and equal runs have equal anchors. The runs that follow one another with the same anchor form a segment. Segments of
anchors that occur once go at once; equal segments are counted once with their number; the segments that are left are
dealt to shards by anchor. Each shard builds the suffix automaton of its segments and streams them through it; a run
that ends at places of total weight two or more is repeated. The rare anchor with very many different segments is not
gathered in one shard: its segments are split by longer and longer anchors until each has few enough, and these go
through automata in the same way. The last anchor is a whole run: then all parts of an anchor are equal, and equal parts
are counted once with their number, as everywhere.

``remove_reference_spans`` is the plain form for a reference of its own: automata of bounded shards are broadcast and
every document is streamed through them.

Cases: null text has no words; a text shorter than ``width`` words keeps them all; a run that repeats within its own
text counts, overlapping or not; rows with equal id and text are separate texts, so their runs repeat; a null id is an
id; ids may be of any type that can be ordered; an empty table gives an empty table. Only the named columns are read.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.automaton import SuffixAutomaton
from localcoef.llm.store import written
from localcoef.llm.textcore import WordBlock, mix, text_blocks, window_hashes


@dataclass(frozen=True)
class Runs:
    width: int = 35
    anchor: int = 6
    #: Words of a shard's automaton, about.
    shard_words: int = 20_000
    #: Different segments of one anchor that a shard takes; beyond, they are split by the next of the longer anchors.
    segments: int = 1000
    #: Words of the longer anchors; a whole run is the last.
    longer: tuple[int, ...] = (20,)
    #: Rows up to this number are picked by a broadcast of their ids; more are shuffled.
    broadcast_rows: int = 1_000_000


def anchors(words: np.ndarray, room: np.ndarray, rule: Runs) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first run, number of runs, anchor hash) of the segments of a block of texts."""
    inner = rule.width - rule.anchor + 1
    value = window_hashes(words, rule.anchor)
    n = len(value) - inner + 1
    if n <= 0:
        none = np.zeros(0, np.int64)
        return none, none, none.astype(np.uint64)
    place = np.arange(len(value))
    best, size = value, 1

    def left_least(a, b, x, y):
        take = a <= b
        return np.where(take, a, b), np.where(take, x, y)

    while size < inner:  # doubling, the last step overlapping
        step = min(size, inner - size)
        best, place = left_least(best[:-step], best[step:], place[:-step], place[step:])
        size += step
    fits = room[:n] >= rule.width
    run = np.flatnonzero(fits)
    if not len(run):
        none = np.zeros(0, np.int64)
        return none, none, none.astype(np.uint64)
    spot = place[run]
    head = np.concatenate([[True], (spot[1:] != spot[:-1]) | (run[1:] != run[:-1] + 1)])
    first = run[head]
    count = np.diff(np.concatenate([np.flatnonzero(head), [len(run)]]))
    return first, count, value[spot[head]]


def _signed(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint64).view(np.int64)


def _span_hash(words: np.ndarray, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Hashes of spans of different sizes."""
    out = np.zeros(len(first), np.uint64)
    for n in np.unique(size).tolist():
        at = size == n
        out[at] = window_hashes(words, n)[first[at]]
    return mix(out + size.astype(np.uint64))


def segments(rows: DataFrame, rule: Runs) -> DataFrame:
    """Of rows (id, key, text): each segment with its anchor, the hash of its words, and where it is.

    ``spot`` holds the number of the first run in the text and the number of runs (64 * first + runs).
    """

    def run(batches):
        for batch in batches:
            ids, keys = batch.column(0), batch.column(1)
            for low, _, texts in text_blocks(batch.column(2)):
                block = WordBlock(texts)
                words = block.hashes()
                first, count, value = anchors(words, block.room(), rule)
                doc = np.searchsorted(block.first, first, "right") - 1
                seg = _span_hash(words, first, count + rule.width - 1)
                take = pa.array(low + doc)
                spot = (first - block.first[doc]) * 64 + count
                yield pa.RecordBatch.from_arrays([pa.array(_signed(value)), pa.array(_signed(seg)), ids.take(take), keys.take(take), pa.array(spot.astype(np.int64))], ["anchor", "seg", "id", "key", "spot"])

    if rule.width - rule.anchor + 1 > 63:
        raise ValueError("a segment has at most 63 runs")
    kind = rows.schema["id"].dataType.simpleString()
    return rows.mapInArrow(run, f"anchor long, seg long, id {kind}, key int, spot long")


def _read_segments(rule: Runs):
    """From texts with lists of wanted segments, the word hashes of each segment."""

    def run(batches):
        for batch in batches:
            wanted = batch.column(1)
            for low, high, texts in text_blocks(batch.column(0)):
                out: list[list] = [[], [], [], []]
                block = WordBlock(texts)
                words = block.hashes()
                for i in range(low, high):
                    base = int(block.first[i - low])
                    for w in wanted[i].as_py():
                        start, runs = base + w["spot"] // 64, w["spot"] % 64
                        span = words[start : start + runs + rule.width - 1]
                        for column, v in zip(out, (w["anchor"], w["seg"], w["n"], span.tobytes()), strict=True):
                            column.append(v)
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], ["anchor", "seg", "n", "words"])

    return run


def _judge(rule: Runs):
    """Repeated runs, as bits, of the segments of each shard; the rows come sorted by anchor."""

    def verdicts(rows):
        tool = SuffixAutomaton()
        lists = [np.frombuffer(r[3], np.int64).tolist() for r in rows]
        for r, words in zip(rows, lists, strict=True):
            tool.add(words, r[2])
        tool.finish()
        bits = [sum(1 << s for s in tool.stream(words, rule.width, 2)) for words in lists]
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array(bits, pa.int64())], ["anchor", "seg", "bits"])

    def run(batches):
        rows, size = [], 0
        for batch in batches:
            for row in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if size > rule.shard_words and row[0] != rows[-1][0]:
                    yield verdicts(rows)
                    rows, size = [], 0
                rows.append(row)
                size += len(row[3]) // 8
        if rows:
            yield verdicts(rows)

    return run


def _split(rule: Runs, anchor: int):
    """Parts (anchor, part, n, words) split by a longer anchor: the new anchor and part, and the old ones with the place
    of the new part in the old one."""
    longer = replace(rule, anchor=anchor)

    def run(batches):
        for batch in batches:
            columns: list[list] = [[] for _ in range(7)]
            for old, part, n, words in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                span = np.frombuffer(words, np.uint64)
                first, count, value = anchors(span, len(span) - np.arange(len(span)), longer)
                parts = _span_hash(span, first, count + rule.width - 1)
                for f, c, v, h in zip(first.tolist(), count.tolist(), _signed(value).tolist(), _signed(parts).tolist(), strict=True):
                    for column, x in zip(columns, (v, h, old, part, f, n, span[f : f + c + rule.width - 1].tobytes()), strict=True):
                        column.append(x)
            kinds = (*[pa.int64()] * 6, pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["anchor", "seg", "old", "part", "first", "n", "words"])

    return run


def _judged(words: DataFrame, rule: Runs, longer: tuple[int, ...]) -> DataFrame:
    """(anchor, seg, bits) of the repeated runs of distinct parts (anchor, seg, n, words), by automata of shards; anchors
    with too many different parts are split first."""
    if not longer:  # a whole run is the anchor, so its parts are equal and have been counted
        return words.where("n > 1").select("anchor", "seg", F.lit(1).cast("long").alias("bits"))
    size = words.groupBy("anchor").agg(F.count("*").alias("d")).where(F.col("d") > rule.segments).select("anchor")
    many = written(size, "many")
    judge = lambda rows: rows.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(_judge(rule), "anchor long, seg long, bits long")
    if many.isEmpty():
        return judge(words)
    many = many.withColumn("x", F.hash("anchor"))
    found = judge(words.withColumn("x", F.hash("anchor")).join(many, ["anchor", "x"], "left_anti").select("anchor", "seg", "n", "words"))
    crowd = words.withColumn("x", F.hash("anchor")).join(many, ["anchor", "x"]).select("anchor", "seg", "n", "words")
    parts = written(crowd.mapInArrow(_split(rule, longer[0]), "anchor long, seg long, old long, part long, first long, n long, words binary"), "parts")
    # what occurs once goes, equal parts are counted once; parts of different old anchors never hold the same run
    twice = parts.groupBy("anchor").agg(F.sum("n").alias("total")).where("total > 1").select("anchor", F.hash("anchor").alias("x"))
    kinds = parts.withColumn("x", F.hash("anchor")).join(twice, ["anchor", "x"]).groupBy("anchor", "seg").agg(F.sum("n").alias("n"), F.min("words").alias("words"))
    verdict = _judged(written(kinds, "kinds"), rule, longer[1:])
    back = parts.select("anchor", "seg", "old", "part", "first").withColumn("x", F.hash("anchor", "seg")).join(verdict.withColumn("x", F.hash("anchor", "seg")), ["anchor", "seg", "x"])
    back = back.groupBy("old", "part").agg(F.bit_or(F.expr("shiftleft(bits, int(first))")).alias("bits"))
    return found.unionByName(back.select(F.col("old").alias("anchor"), F.col("part").alias("seg"), "bits"))


def _with_texts(rows: DataFrame, lists: DataFrame, rule: Runs, how: str) -> tuple[DataFrame, DataFrame | None]:
    """Rows joined to their lists by (id, key); for an outer join also the rows without one, if they can stay in place."""
    n = lists.count()
    lists = lists.withColumnRenamed("id", "__id").withColumnRenamed("key", "__key")
    same = F.col("id").eqNullSafe(F.col("__id")) & F.col("key").eqNullSafe(F.col("__key"))
    if n > rule.broadcast_rows:
        return rows.join(lists, same, how).drop("__id", "__key"), None
    ids = F.broadcast(lists.select("__id", "__key"))
    near = rows.join(ids, same, "left_semi").join(lists, same, "inner").drop("__id", "__key")
    return near, rows.join(ids, same, "left_anti") if how == "left" else None


def repeated_runs(rows: DataFrame, rule: Runs) -> DataFrame:
    """Of rows (id, key, text): for each text with a repeated run, a list of (spot, bits of its repeated runs)."""
    every = segments(rows, rule)
    again = written(every.groupBy("anchor").agg(F.count("*").alias("n")).where("n > 1").select("anchor", F.hash("anchor").alias("x")), "anchors")
    met = written(every.withColumn("x", F.hash("anchor")).join(again, ["anchor", "x"]).drop("x"), "met")
    kinds = met.groupBy("anchor", "seg").agg(F.count("*").alias("n"), F.min(F.struct("id", "key", "spot")).alias("where"))
    kinds = written(kinds, "kinds")
    several = kinds.groupBy("anchor").agg(F.count("*").alias("d")).where("d > 1").withColumn("x", F.hash("anchor"))
    mixed = kinds.withColumn("x", F.hash("anchor")).join(several, ["anchor", "x"]).select("where.*", "anchor", "seg", "n")
    lists = written(mixed.groupBy("id", "key").agg(F.collect_list(F.struct("anchor", "seg", "n", "spot")).alias("wanted")), "wanted")
    joined, _ = _with_texts(rows, lists, rule, "inner")
    words = written(joined.select("text", "wanted").mapInArrow(_read_segments(rule), "anchor long, seg long, n long, words binary"), "words")
    found = _judged(words, rule, (*rule.longer, rule.width))
    # a segment that occurs twice is repeated as a whole, whatever else its anchor meets
    whole = kinds.where("n > 1").select("anchor", "seg", F.expr("shiftleft(1L, int(where.spot % 64)) - 1").alias("bits"))
    verdict = written(found.where("bits <> 0").unionByName(whole).groupBy("anchor", "seg").agg(F.bit_or("bits").alias("bits")).withColumn("x", F.hash("anchor", "seg")), "verdicts")
    marked = met.withColumn("x", F.hash("anchor", "seg")).join(verdict, ["anchor", "seg", "x"])
    return marked.groupBy("id", "key").agg(F.collect_set(F.struct("spot", "bits")).alias("marks"))


def removed_mask(marks: list | None, n: int, width: int) -> np.ndarray:
    """Which of a text's words its repeated runs cover; rows with equal id and text may list a run more than once."""
    starts = [m["spot"] // 64 + j for m in marks or () for j in range(m["spot"] % 64) if m["bits"] >> j & 1]
    step = np.zeros(n + 1, np.int64)
    if starts:
        at = np.array(starts)
        np.add.at(step, at, 1)
        np.add.at(step, at + width, -1)
    return np.cumsum(step[:n]) > 0


def _cut(rule: Runs, with_text: bool):
    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            total, gone, digest, left = [], [], [], []
            for text, mark in ((t, batch.column(2)[i].as_py()) for low, _, texts in text_blocks(batch.column(1)) for i, t in enumerate(texts, low)):
                words = text.encode("utf-8", "surrogatepass").split() if text else []
                n_removed = 0
                if mark:
                    mask = removed_mask(mark, len(words), rule.width)
                    n_removed = int(mask.sum())
                kept = b" ".join([w for w, m in zip(words, mask.tolist(), strict=True) if not m] if n_removed else words)
                total.append(len(words))
                gone.append(n_removed)
                digest.append(hashlib.sha256(kept).hexdigest())
                if with_text:
                    left.append(kept.decode("utf-8", "replace"))
            columns = [ids, pa.array(total, pa.int64()), pa.array(gone, pa.int64()), pa.array(digest, pa.string())]
            names = ["id", "n_words", "n_removed", "kept_sha256"]
            if with_text:
                columns, names = [*columns, pa.array(left, pa.string())], [*names, "kept_text"]
            yield pa.RecordBatch.from_arrays(columns, names)

    return run


def remove_repeats(docs: DataFrame, rule: Runs = Runs(), id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """Per row: the id, n_words, n_removed, kept_sha256, and with ``with_text`` the kept words."""
    rows = docs.select(F.col(id_col).alias("id"), F.hash(F.col(text_col)).alias("key"), F.col(text_col).cast("string").alias("text"))
    marks = written(repeated_runs(rows, rule), "marks")
    near, rest = _with_texts(rows, marks, rule, "left")
    near = near.select("id", "text", "marks")
    if rest is not None:
        near = near.unionByName(rest.select("id", "text", F.lit(None).cast(marks.schema["marks"].dataType).alias("marks")))
    kind = docs.select(id_col).schema[0].dataType.simpleString()
    schema = f"id {kind}, n_words long, n_removed long, kept_sha256 string" + (", kept_text string" if with_text else "")
    return near.mapInArrow(_cut(rule, with_text), schema).withColumnRenamed("id", id_col)


def remove_reference_spans(docs: DataFrame, reference: DataFrame, width: int, shard_chars: int = 4_000_000, id_col: str = "doc_id", text_col: str = "text", ref_text: str = "text") -> DataFrame:
    """Words of each document that lie in a run of ``width`` words of the reference go.

    The reference is cut by hash into shards of about ``shard_chars`` characters; each shard's automaton is built where
    it is used from a broadcast of its distinct texts, and all documents are streamed through one shard after another.
    """
    spark = docs.sparkSession
    texts = reference.select(F.col(ref_text).cast("string").alias("t")).where("t is not null").distinct()
    n = max(1, -(-int(texts.agg(F.coalesce(F.sum(F.char_length("t")), F.lit(0)).alias("n")).first()["n"]) // shard_chars))
    kind = docs.select(id_col).schema[0].dataType.simpleString()
    state = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.expr("cast(array() as array<long>)").alias("starts"))
    for k in range(n):
        shard = [r["t"] for r in texts.where(F.pmod(F.xxhash64("t"), F.lit(n)) == k).orderBy("t").collect()]
        state = state.mapInArrow(_streamer(spark.sparkContext.broadcast(shard), width), f"id {kind}, text string, starts array<long>")

    def run(batches):
        for batch in batches:
            ids, given, starts = batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist()
            out, gone = [], []
            for text, at in zip(given, starts, strict=True):
                words = (text or "").encode("utf-8", "surrogatepass").split()
                mask = removed_mask([{"spot": 64 * s + 1, "bits": 1} for s in at], len(words), width).tolist()
                out.append(b" ".join([w for w, m in zip(words, mask, strict=True) if not m]).decode("utf-8", "replace"))
                gone.append(sum(mask))
            yield pa.RecordBatch.from_arrays([ids, pa.array(gone, pa.int64()), pa.array(out, pa.string())], [id_col, "n_removed", "kept_text"])

    return state.mapInArrow(run, f"`{id_col}` {kind}, n_removed long, kept_text string")


def _streamer(shared, width: int):
    def run(batches):
        tool = None
        for batch in batches:
            if tool is None:
                tool = SuffixAutomaton()
                block = WordBlock(shared.value)
                words = _signed(block.hashes()).tolist()
                for a, b in zip(block.first[:-1].tolist(), block.first[1:].tolist(), strict=True):
                    tool.add(words[a:b])
                tool.finish()
            starts = batch.column(2).to_pylist()
            for low, high, texts in text_blocks(batch.column(1)):
                block = WordBlock(texts)
                words = _signed(block.hashes()).tolist()
                for i in range(low, high):
                    a, b = int(block.first[i - low]), int(block.first[i - low + 1])
                    starts[i] = sorted({*starts[i], *tool.stream(words[a:b], width, 1)})
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(starts, pa.list_(pa.int64()))], ["id", "text", "starts"])

    return run
