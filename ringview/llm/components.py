"""Connected components of an edge table, for any number of nodes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.llm.common import components, materialize

#: Edges that one task may finish; a larger graph is contracted by joins first.
ONE_TASK = 1_000_000


def _forest(batches):
    """Edges of one partition become, block by block, node-to-smallest edges with the same components."""
    for held in batches:
        if held.num_rows:
            node, root = components(held.column("u").to_numpy(), held.column("v").to_numpy())
            keep = node != root
            yield pa.RecordBatch.from_arrays([pa.array(root[keep]), pa.array(node[keep])], names=["u", "v"])


def _finish(batches):
    held = [(b.column("u").to_numpy(), b.column("v").to_numpy()) for b in batches]
    node, root = components(*(np.concatenate(x) for x in zip(*held, strict=True))) if held else (np.zeros(0, np.int64),) * 2
    yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(root)], names=["node", "root"])


def connected_components(edges: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """(u long, v long) edges to (node, root): root is the smallest node that can be reached.

    Rounds of contraction: each root joins its smallest neighbour, hops are shortened twice, edges are renamed to
    roots and made distinct.  All tables are in the shared folder.  Once at most ``one_task`` edges are left, one
    task ends the work; the answer does not depend on that bound.
    """
    edges = materialize(edges.where("u <> v").mapInArrow(_forest, "u long, v long").distinct(), "edges")
    steps: list[DataFrame] = []
    while (n := edges.count()) > one_task:
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        hop = materialize(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("node"), F.least("u", "m").alias("to")), "hop")
        for _ in range(2):
            up = hop.select(F.col("node").alias("to"), F.col("to").alias("top"))
            hop = materialize(hop.join(up, "to").select("node", F.col("top").alias("to")), "hop")
        steps.append(hop)
        for side in ("u", "v"):
            edges = edges.join(hop.select(F.col("node").alias(side), "to"), side).drop(side).withColumnRenamed("to", side)
        edges = materialize(edges.where("u <> v").select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct(), "edges")
    last = edges.coalesce(1).mapInArrow(_finish, "node long, root long") if n else edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for hop in reversed(steps):
        last = materialize(last, "roots")
        up = last.select(F.col("node").alias("to"), "root")
        named = hop.join(up, "to", "left").select("node", F.coalesce("root", "to").alias("root"))
        last = named
    return last
