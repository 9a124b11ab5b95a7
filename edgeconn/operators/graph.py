"""Simple undirected graphs as two tables, and what degrees alone tell."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from edgeconn.operators import blocks as X
from edgeconn.plans.staging import stage

#: Vertex ids below this give edge ids by packing both ends in one long.
PACK = 1 << 31


def canonical_edges(raw: DataFrame, a: str = "a", b: str = "b", repeats: bool = True) -> DataFrame:
    """(eid, src, dst) with src < dst: loops, nulls and repeats are gone.
    ``repeats=False``: the caller knows that no pair comes twice.

    The edge id packs both ends where ids are in 0..2**31-1 and is a 64-bit
    hash of them elsewhere (``check_ids`` tells a collision);
    ``encode_vertices`` gives dense ids, also to texts.
    """
    ends = raw.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).filter("a <> b")
    pairs = ends.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))
    return with_ids(pairs.distinct() if repeats else pairs)


def with_ids(pairs: DataFrame) -> DataFrame:
    """(eid, src, dst) of canonical pairs (src, dst)."""
    packed = F.when((F.col("src") >= 0) & (F.col("dst") < PACK), F.col("src") * F.lit(PACK) + F.col("dst")).otherwise(F.xxhash64("src", "dst"))
    return pairs.select(packed.alias("eid"), "src", "dst")


def numbered(rows: DataFrame, by: str, name: str) -> DataFrame:
    """``rows`` with a column ``name`` of 0, 1, ... in the order of the column
    ``by``, whose values differ. Rows are dealt into ranges of the order and
    numbered there, so no single task orders them all."""
    held = stage(rows.repartitionByRange(by).withColumn("part", F.spark_partition_id()), "numbered").df
    sizes = held.groupBy("part").count()
    base = sizes.select("part", (F.sum("count").over(Window.orderBy("part")) - F.col("count")).alias("base"))  # a row per range
    no = F.row_number().over(Window.partitionBy("part").orderBy(by)) - 1
    return held.join(F.broadcast(base), "part").withColumn(name, F.col("base") + no).drop("part", "base")


def check_ids(edges: DataFrame) -> None:
    """Raise where two edges have one id, which only hashed ids can have."""
    hashed = edges.filter((F.col("src") < 0) | (F.col("dst") >= PACK))
    if not hashed.isEmpty() and not edges.groupBy("eid").count().filter("count > 1").isEmpty():
        raise ValueError("edge ids collide; give dense vertex ids by encode_vertices")


def encode_vertices(raw: DataFrame, a: str = "a", b: str = "b") -> tuple[DataFrame, DataFrame]:
    """(pairs a, b as longs; dictionary v, name): ids of 0..n-1 in name order.

    Equal names have equal ids, so edges of dense ids are packed exactly.
    """
    names = raw.select(F.col(a).cast("string").alias("name")).unionByName(raw.select(F.col(b).cast("string").alias("name"))).filter("name IS NOT NULL").distinct()
    dictionary = numbered(names, "name", "v")
    left = dictionary.withColumnsRenamed({"v": "va", "name": "name_a"})
    right = dictionary.withColumnsRenamed({"v": "vb", "name": "name_b"})
    pairs = raw.join(left, F.col(a).cast("string") == F.col("name_a")).join(right, F.col(b).cast("string") == F.col("name_b"))
    return pairs.select(F.col("va").alias("a"), F.col("vb").alias("b")), dictionary


def half_edges(edges: DataFrame, *extra: str) -> DataFrame:
    """(v, nbr, eid, *extra): each edge as seen from both ends, in one scan."""
    both = F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("nbr")), F.struct(F.col("dst").alias("v"), F.col("src").alias("nbr"))))
    return edges.select("eid", *extra, both.alias("h")).select("h.v", "h.nbr", "eid", *extra)


@dataclass(frozen=True)
class Graph:
    """vertices (v long) may hold vertices without an edge."""

    vertices: DataFrame
    edges: DataFrame
    #: Whether each vertex is known to have an edge.
    covered: bool = False
    #: The same edges as blocks, where they are known as such.
    blocks: DataFrame | None = None

    @staticmethod
    def of_blocks(blocks: DataFrame) -> Graph:
        """The graph of staged blocks, in which no edge comes twice. Its edges are
        made whenever they are read."""
        degrees = stage(X.degrees_of(blocks), "block-degrees").df
        g = Graph(degrees.select("v"), with_ids(X.edges_of(blocks)), True, blocks)
        g.__dict__["degrees"] = degrees
        return g

    @staticmethod
    def of(edges: DataFrame, vertices: DataFrame | None = None) -> Graph:
        if vertices is None:
            return Graph(edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct(), edges, True)
        return Graph(vertices, edges)

    @cached_property
    def degrees(self) -> DataFrame:
        """(v, deg long), zero for vertices without an edge."""
        counted = half_edges(self.edges).groupBy("v").agg(F.count(F.lit(1)).alias("deg"))
        if self.covered:
            return counted
        return self.vertices.join(counted, "v", "left").select("v", F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))

    @cached_property
    def profile(self) -> dict[str, int | None]:
        """n, m, min degree and the least vertex that has it."""
        row = self.degrees.agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("d"), F.min(F.struct("deg", "v")).alias("low")).first()
        low = row.low
        return {"n": row.n, "m": (row.d or 0) // 2, "min_degree": low.deg if low else 0, "argmin": low.v if low else None}


def min_degree_cut(g: Graph) -> DataFrame:
    """(v, deg): the smallest cut of one vertex against the rest."""
    return g.degrees.agg(F.min(F.struct("deg", "v")).alias("low")).select("low.v", "low.deg")


def cut_edges(g: Graph, side: DataFrame) -> DataFrame:
    """Edges of the graph between ``side`` (v, in_s) and the rest."""
    s = side.filter("in_s").select("v")
    a = s.withColumnRenamed("v", "src").withColumn("a", F.lit(True))
    b = s.withColumnRenamed("v", "dst").withColumn("b", F.lit(True))
    marked = g.edges.join(a, "src", "left").join(b, "dst", "left")
    return marked.filter(F.coalesce("a", F.lit(False)) != F.coalesce("b", F.lit(False))).select("eid", "src", "dst")
