"""Connected components of links between ids, by hooking, pointer jumping and contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, stored


def components(links: DataFrame) -> DataFrame:
    """``links`` (a, b) of longs to (id, component): the least id reachable.

    In a phase every id with a smaller neighbour hooks onto its smallest one,
    pointer jumping brings the hooked ids to their roots, and the links are
    contracted to links between roots; phases end when no link is left.  A root
    that nothing hooks onto in a phase hooks itself in the next one, as its
    neighbours came under smaller roots.  So two phases halve the ids at least,
    in whatever order ids lie along the links, and a phase jumps as often as the
    logarithm of its longest chain.  All of it lives in tables of the shared
    folder; nothing but a count comes to the driver.
    """
    pairs = links.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    edges, phases = stored(pairs.distinct(), "edges"), []
    while not edges.isEmpty():
        phases.append(rooted(edges.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("root"))))
        before, edges = edges, stored(contracted(edges, phases[-1]), "edges")
        dropped(before)
    if not phases:
        return edges.select(F.col("a").alias("id"), F.col("b").alias("component"))
    whole = phases.pop()
    while phases:
        later = whole.select(F.col("id").alias("root"), F.col("root").alias("far"))
        phase, before = phases.pop(), whole
        earlier = phase.join(later, "root", "left").select("id", F.coalesce("far", "root").alias("root"))
        whole = stored(earlier.unionAll(before), "roots")
        dropped(phase, before)
    least = whole.select(F.col("root").alias("id"), "root").distinct()
    return whole.unionAll(least).withColumnRenamed("root", "component")


def rooted(hooks: DataFrame) -> DataFrame:
    """Hooks (id, root) onto smaller ids, those of roots left out, followed to their ends."""
    found = stored(hooks, "hooks")
    while True:
        ahead = found.select(F.col("id").alias("root"), F.col("root").alias("far"))
        jumped = found.select("id", "root").join(ahead, "root", "left")
        done = stored(jumped.select("id", F.coalesce("far", "root").alias("root"), F.col("far").isNotNull().alias("moved")), "hooks")
        dropped(found)
        if done.filter("moved").isEmpty():
            roots = done.select("id", "root")
            roots.stored_at = done.stored_at
            return roots
        found = done


def contracted(edges: DataFrame, roots: DataFrame) -> DataFrame:
    """The links between different roots, each once, the larger id first."""
    of_a = roots.select(F.col("id").alias("a"), F.col("root").alias("root_a"))
    of_b = roots.select(F.col("id").alias("b"), F.col("root").alias("root_b"))
    ends = edges.join(of_a, "a").join(of_b, "b", "left").select("root_a", F.coalesce("root_b", "b").alias("root_b"))
    return ends.filter("root_a <> root_b").select(F.greatest("root_a", "root_b").alias("a"), F.least("root_a", "root_b").alias("b")).distinct()
