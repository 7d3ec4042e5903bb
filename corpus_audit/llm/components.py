"""Connected components over links by hooking roots to smaller ones and contracting, as DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def components(links: DataFrame) -> DataFrame:
    """(node, label): label is the smallest node reachable. links: (a, b), any direction, repeats allowed.

    In every round each node that has a smaller neighbour hooks to the least one; the trees that arise are flattened by
    pointer jumping, and the links are carried over to the roots. A round takes every node but the local minima from
    the links, whatever the length of paths, so it ends without a bound on the rounds, and tables shrink from round to
    round; each is written, so lineage stays flat. Nodes without links do not appear."""
    links = links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    links = first = written(links, "links")
    labels = None
    while True:
        hooks = _flat(written(links.groupBy("a").agg(F.min("b").alias("to")), "hooks"))
        if labels is None:
            roots = first.select("b").distinct().join(hooks.select(F.col("a").alias("b")), "b", "left_anti")
            labels = hooks.select(F.col("a").alias("node"), F.col("to").alias("label")).unionByName(roots.select(F.col("b").alias("node"), F.col("b").alias("label")))
        else:
            further = hooks.select(F.col("a").alias("label"), "to")
            labels = labels.join(further, "label", "left").select("node", F.coalesce("to", "label").alias("label"))
        upper = links.join(hooks, "a").select(F.col("to").alias("a"), "b")
        both = upper.join(hooks.select(F.col("a").alias("b"), "to"), "b", "left").select("a", F.coalesce("to", "b").alias("b"))
        links = written(both.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
        if links.isEmpty():
            return written(labels, "labels")


def _flat(hooks: DataFrame) -> DataFrame:
    """hooks (a, to) with every ``to`` a root; paths halve each time."""
    while True:
        up = hooks.select(F.col("a").alias("to"), F.col("to").alias("above"))
        jumped = written(hooks.join(up, "to", "left").select("a", F.coalesce("above", "to").alias("to"), F.col("above").isNotNull().alias("moved")), "hooks")
        hooks = jumped.select("a", "to")
        if jumped.where("moved").isEmpty():
            return hooks
