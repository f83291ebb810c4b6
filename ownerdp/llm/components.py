"""Connected components of any number of links, by contraction: no driver-side union, no group in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.common import materialise


def _roots(hooks: DataFrame) -> DataFrame:
    """Follows (node, parent), where a parent is never larger than its node, to the roots by repeated squaring."""
    while True:
        up = hooks.select(F.col("node").alias("parent"), F.col("parent").alias("above"))
        step = materialise(
            hooks.join(up, "parent", "left").select("node", F.coalesce("above", "parent").alias("parent"), (F.coalesce("above", "parent") != F.col("parent")).alias("moved")), "components-roots"
        )
        hooks = step.select("node", "parent")
        if step.filter("moved").isEmpty():
            return hooks


def connected_components(links: DataFrame) -> DataFrame:
    """(node, component) for every node of the links (a, b): two columns of one comparable type. component is the smallest node reachable.

    Every round hooks each node to its smallest neighbour, contracts the trees to their roots and drops links inside
    them; at least half of the nodes that still have links disappear, so rounds grow with the logarithm of the nodes.
    Links with a null end are ignored.
    """
    edges = materialise(links.select("a", "b").filter("a <> b").distinct(), "components-links")
    label = None
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        hooks = both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).select("node", F.least("node", "low").alias("parent"))
        roots = _roots(materialise(hooks, "components-hooks"))
        root_of = lambda name: roots.select(F.col("node").alias(name), F.col("parent").alias(f"{name}_root"))
        if label is None:
            label = roots.select("node", F.col("parent").alias("component"))
        else:
            label = materialise(label.join(root_of("component"), "component", "left").select("node", F.coalesce("component_root", "component").alias("component")), "components-labels")
        edges = materialise(
            edges.join(root_of("a"), "a").join(root_of("b"), "b").select(F.col("a_root").alias("a"), F.col("b_root").alias("b")).filter("a <> b").distinct(), "components-links"
        )
    if label is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return label
