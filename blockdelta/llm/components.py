"""Connected components of a link table by star contraction, in joins and aggregates only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import staged


def _with_least(edges: DataFrame) -> DataFrame:
    """(u, v) with the least number among u and its neighbours v."""
    least = edges.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("w"), F.least("u", "m").alias("m"))
    return edges.join(least, F.col("u") == F.col("w")).select("u", "v", "m")


def _mark(edges: DataFrame) -> tuple:
    """Tells one set of edges from another: their number and two sums of hashes."""
    each = F.xxhash64("u", "v")
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.shiftright(each, 20)), F.sum(each.bitwiseAND(F.lit((1 << 40) - 1)))).first())


def connected(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component) of every node in ``links`` (a, b); a component is named by its least node.

    Each round ties every node's larger neighbours, then its smaller ones, to the least of them. Paths shrink by a
    constant factor a round, whatever their shape, and each round is written to the shared folder.
    """
    edges = staged(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "links")
    before = _mark(edges)
    for _ in range(most_rounds if before[0] else 0):
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small = _with_least(large)
        tied = small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(small.select("u", F.col("m").alias("v")))
        edges = staged(tied.where("u > v").distinct(), "links")
        after = _mark(edges)
        if after == before:
            break
        before = after
    else:
        if before[0]:
            raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def extended(parts: DataFrame, links: DataFrame) -> DataFrame:
    """``parts`` (node, component) with further ``links`` (a, b): only components that these join are worked on."""
    ends = links
    for end in "ab":
        known = parts.select(F.col("node").alias(f"node_{end}"), F.col("component").alias(f"part_{end}"))
        ends = ends.join(known, F.col(end) == F.col(f"node_{end}"), "left")
    joined = ends.select(F.coalesce("part_a", "a").alias("a"), F.coalesce("part_b", "b").alias("b")).where("a <> b")
    merged = staged(connected(joined), "components").select(F.col("node").alias("old"), F.col("component").alias("new"))
    renamed = parts.join(merged, F.col("component") == F.col("old"), "left").select("node", F.coalesce("new", "component").alias("component"))
    fresh = merged.join(parts.select(F.col("node").alias("old")), "old", "left_anti").select(F.col("old").alias("node"), F.col("new").alias("component"))
    return staged(renamed.union(fresh), "components")
