"""The graph model: simple undirected graphs, node partitions, and the tables derived from them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from typing import TYPE_CHECKING

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

if TYPE_CHECKING:
    from localcoef.operators.bits import Bits
    from localcoef.operators.packed import Packed

COEFFICIENTS = ("clustering", "closure")


@dataclass(frozen=True)
class Graph:
    """``nodes(id)`` and ``edges(u, v)`` with u < v, each edge once; isolated nodes are only in ``nodes``."""

    nodes: DataFrame
    edges: DataFrame
    #: The edges with repeats, and (g, i) with whole numbers whose groups join their members, where these come cheaper;
    #: the written lists, see ``operators.packed``; no node is isolated.
    pairs: DataFrame | None = None
    groups: DataFrame | None = None
    packed: Packed | None = None
    ends: bool = False
    #: Makes rows of bits of a dense graph, or None where lists are better; see ``operators.bits``.
    bits: Callable[[], Bits | None] | None = None

    @staticmethod
    def of(edges: DataFrame, nodes: DataFrame | None = None, pairs: DataFrame | None = None, groups: DataFrame | None = None, bits: Callable[[], Bits | None] | None = None) -> Graph:
        """From edges that are canonical; without nodes, the nodes are those with an edge."""
        ends = nodes is None
        if nodes is None:
            nodes = edges.select(F.explode(F.array("u", "v")).alias("id")).distinct()
        return Graph(nodes.select("id"), edges.select("u", "v"), pairs, groups, ends=ends, bits=bits)

    @property
    def adjacency(self) -> DataFrame:
        """(src, dst) in both directions; one row for each direction, never a list, so a hub is no wide row."""
        return self.edges.select(F.inline(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))))


def canonical(pairs: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    """Edges of a table of pairs: loops and nulls dropped, endpoints in order, each edge once."""
    return pairs.where(F.col(a) != F.col(b)).select(F.least(a, b).cast("long").alias("u"), F.greatest(a, b).cast("long").alias("v")).distinct()


def check_coefficient(coefficient: str) -> None:
    if coefficient not in COEFFICIENTS:
        raise ValueError(f"unknown coefficient {coefficient!r}; known are {', '.join(COEFFICIENTS)}")


def check_partition(nodes: DataFrame, buckets: DataFrame) -> None:
    """Raises unless every node has exactly one bucket and every bucket a node."""
    if nodes.select("id").join(buckets.select("id"), "id", "left_anti").limit(1).count():
        raise ValueError("a node has no bucket")
    if buckets.groupBy("id").agg(F.count("*").alias("n")).where("n > 1").limit(1).count():
        raise ValueError("a node has more than one bucket")
    if buckets.join(nodes.select("id"), "id", "left_anti").limit(1).count():
        raise ValueError("a bucket holds something that is no node")


def bucket_sizes(buckets: DataFrame) -> DataFrame:
    """(bucket, size): as many rows as buckets."""
    return buckets.groupBy("bucket").agg(F.count("*").alias("size"))
