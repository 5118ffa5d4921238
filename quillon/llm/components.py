"""Connected components of links by contraction, without gathering a component anywhere."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored


def components(edges: DataFrame) -> DataFrame:
    """(a, b) links to (id, component): component is the smallest id that links reach.

    Each round points every vertex at its smallest neighbour, follows the pointers to their
    roots by doubling, and keeps the links between different roots. All steps are joins and
    aggregates with partial sums; each round is written to the shared folder. Nulls and
    self-links are left out; an empty input gives an empty result.
    """
    links = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct()
    links, labels, spark = stored(links, "links"), None, edges.sparkSession
    while not links.isEmpty():
        both = links.union(links.select("b", "a"))
        parent = held = stored(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("parent")), "parent")
        while True:
            up = parent.select(F.col("id").alias("parent"), F.col("parent").alias("above"))
            jumped = parent.join(up, "parent", "left").select("id", F.coalesce("above", "parent").alias("parent"), (F.col("above") != F.col("parent")).alias("moved"))
            jumped = stored(jumped, "jump")
            discard(spark, held)
            parent, held = jumped.select("id", "parent"), jumped
            if jumped.where("moved").isEmpty():
                break
        of = lambda k: parent.select(F.col("id").alias(k), F.col("parent").alias(f"p{k}"))  # noqa: E731,B023
        rest = links.join(of("a"), "a").join(of("b"), "b").where("pa != pb")
        done, links = links, stored(rest.select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).distinct(), "links")
        discard(spark, done)
        if labels is None:
            labels, kept = parent.withColumnRenamed("parent", "component"), held
        else:
            up = parent.select(F.col("id").alias("component"), F.col("parent").alias("above"))
            labels = stored(labels.join(up, "component", "left").select("id", F.coalesce("above", "component").alias("component")), "labels")
            discard(spark, kept, held)
            kept = labels
    discard(spark, links)
    return edges.select(F.col("a").alias("id"), F.col("b").alias("component")).where("false") if labels is None else labels


def local_roots(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest member of each of n vertices' component under the links (i, j), in memory."""
    root = np.arange(n)
    while len(i):
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, root[i], low)
        np.minimum.at(new, root[j], low)
        while True:
            jumped = new[new]
            if np.array_equal(jumped, new):
                break
            new = jumped
        root = new[root]
        keep = root[i] != root[j]
        i, j = i[keep], j[keep]
    return root
