"""Connected components of a table of links, by rounds of joins and aggregates.

Half-rounds by turns point every node's larger neighbours at the smallest node around it, and every node and its smaller
neighbours at the smallest of those.  The links turn into one star per component in a number of rounds that grows with
the logarithm of the longest chain.  The aggregate each half-round needs also tells whether the links are stars already,
so links that are cost one pass.  It is written to the shared folder; the driver sees counts only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import counted, discard, kept_at, stage

MAX_ROUNDS = 60


def _around(edges: DataFrame) -> tuple[DataFrame, int]:
    """kind, u, m: the smallest node linked with each node, and the number of nodes that keep the links from being stars.

    In a star the centre is smaller than all around it and the others have one neighbour.
    """
    both = edges.unionByName(edges.select("kind", F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("kind", "u").agg(F.min("v").alias("m"), F.max("v").alias("most"))
    return counted(least, "stars-least", (F.col("m") < F.col("u")) & (F.col("m") < F.col("most")))


def components(links: DataFrame) -> DataFrame:
    """node, component for every node of ``links`` (a, b longs); the component is its smallest node."""
    every = components_by_kind(links.select(F.lit(0).alias("kind"), "a", "b"))
    return kept_at(every.drop("kind"), every)


def components_by_kind(links: DataFrame) -> DataFrame:
    """kind, node, component of several sets of links (kind, a, b) in the same rounds.

    Links are read twice, so what is dear to make should be written before.  Each one stays one row, which may repeat others.
    Both sides of the joins are stored, so a node with very many links can be split.
    """
    edges, mine = links.select("kind", F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u > v"), []
    for half in range(2 * MAX_ROUNDS):
        least, unsettled = _around(edges)
        if not unsettled:
            discard(*mine)
            return kept_at(least.select("kind", F.col("u").alias("node"), F.least("u", "m").alias("component")), least)
        least = least.select("kind", "u", "m")
        if half % 2:
            to = edges.join(least, ["kind", "u"])
            to = to.select("kind", F.when(F.col("v") > F.col("m"), F.col("v")).otherwise(F.col("u")).alias("u"), F.col("m").alias("v"))
        else:
            to = edges.select("kind", F.col("v").alias("u"), F.col("u").alias("far")).join(least, ["kind", "u"])
            to = to.select("kind", F.col("far").alias("u"), F.least("u", "m").alias("v"))
        to = stage(to, "stars")
        discard(least, *mine)
        edges, mine = to, [to]
    raise RuntimeError("components did not settle")
