"""Connected components of a link table, by rounds of star contraction.

Each round hangs every node's larger neighbours, then its smaller ones, on the least node it sees; the
number of rounds grows with the logarithm of a component's diameter.  Rounds are kept in the shared folder
until the next one has been.  Null ends and loops are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzcount.sources.tables import cut, drop


def _hang(links: DataFrame) -> DataFrame:
    """(node, neighbour) rows to (node, least) for each node, kept apart so that hot nodes can be split in joins."""
    return cut(links.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m")))


def components(links: DataFrame) -> DataFrame:
    """(node, component) of every node in `links` (u, v); the component is its least node."""
    edges = cut(links.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    while not _are_stars(edges):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = _hang(both)
        larger = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        larger = cut(larger.where("u <> v").distinct())
        drop(edges, least)
        least = _hang(larger)
        smaller = larger.join(least, "u")
        edges = smaller.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(smaller.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        edges = cut(edges)
        drop(larger, least)
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    found = cut(edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots))
    drop(edges)
    return found


def _are_stars(edges: DataFrame) -> bool:
    """Whether each node hangs on one other, and what it hangs on hangs on nothing."""
    ends = edges.select(F.col("u").alias("x"), F.lit(1).alias("hangs"), F.lit(0).alias("holds"))
    ends = ends.unionByName(edges.select(F.col("v").alias("x"), F.lit(0).alias("hangs"), F.lit(1).alias("holds")))
    return ends.groupBy("x").agg(F.sum("hangs").alias("n"), F.max("holds").alias("h")).where("n > 1 OR (n = 1 AND h = 1)").limit(1).count() == 0


def merged(groups: DataFrame, links: DataFrame) -> DataFrame:
    """`groups` (node, component) after some more links (u, v), which a cut has written; without any, as they are."""
    if not links.limit(1).count():
        return groups
    tree = groups.where("node <> component").select(F.col("node").alias("u"), F.col("component").alias("v"))
    return components(tree.unionByName(links))
