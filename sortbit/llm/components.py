"""Connected components of a table of links, by passing least labels and jumping to the label's own label."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import Kept, keep


def components(links: DataFrame, start: DataFrame | None = None) -> DataFrame:
    """(id, component): the least id reachable, for every id in links (a, b) or in `start`.

    start: (id, component) from links seen before, each label being some id of its own component.
    Rounds go on until nothing changes; each is one written table, so no lineage grows.
    """
    both = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    if start is not None:
        known = start.where("id <> component")
        both = both.union(known.select(F.col("id").alias("a"), F.col("component").alias("b"))).union(known.select(F.col("component").alias("a"), F.col("id").alias("b")))
    edges = keep(both.where("a <> b").distinct())
    labels = Kept(edges.groupBy("a").agg(F.min("b").alias("least")).select(F.col("a").alias("id"), F.least("a", "least").alias("component")))
    while True:
        near = edges.join(labels.df.select(F.col("id").alias("b"), "component"), "b").groupBy(F.col("a").alias("id")).agg(F.min("component").alias("near"))
        jump = labels.df.select(F.col("id").alias("component"), F.col("component").alias("far"))
        best = labels.df.join(near, "id").join(jump, "component", "left")
        now = Kept(best.select("id", F.col("component").alias("old"), F.least("component", "near", "far").alias("component")))
        labels.drop()
        if now.df.where("old <> component").isEmpty():
            return now.df.select("id", "component")
        labels = now
