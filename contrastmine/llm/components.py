"""Connected components with DataFrame operations only.

Each round sends the smallest label over every edge, to the neighbour and to the neighbour's current root, and then
halves the paths by reading the label of the label. Every aggregation is a minimum, so it combines before it shuffles;
joins know how many edges a node and how many nodes a label has, so a hub with a third of all edges, or a component with
a third of all nodes, is spread and not gathered. Rounds are written to the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import files_for, join_by_size, stored


def connected_components(edges: DataFrame, left: str = "a", right: str = "b") -> DataFrame:
    """(node, component) for each node of an edge list; component is the least node that can be reached.

    Nulls and self loops in the edges are ignored; repeated edges count once. An empty edge list gives an empty table.
    """
    pairs = edges.select(F.col(left).alias("a"), F.col(right).alias("b")).where("a is not null and b is not null and a <> b")
    pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    both = stored(pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))), "edges")
    n_edges = both.count()
    files = files_for(n_edges)
    labels = stored(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("component"), F.count(F.lit(1)).alias("degree")), "labels", files)
    n_nodes = labels.count()
    while n_edges:
        sent = join_by_size(both, labels.withColumnRenamed("node", "a"), "a", "degree", n_edges)
        reached = sent.groupBy(F.col("b").alias("node")).agg(F.min("component").alias("offer"))
        seen = stored(labels.join(reached, "node"), "seen", files)
        offers = seen.select("node", F.least("component", "offer").alias("component"), "degree", F.col("component").alias("old")).unionByName(
            seen.where("offer < component").select(F.col("component").alias("node"), F.col("offer").alias("component"), F.lit(None).cast("long").alias("degree"), F.lit(None).cast(seen.schema["component"].dataType).alias("old"))
        )
        hooked = stored(offers.groupBy("node").agg(F.min("component").alias("component"), F.max("degree").alias("degree"), F.max("old").alias("old")), "hooked", files)
        used = hooked.groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))
        parent = used.join(hooked.select(F.col("node").alias("component"), F.col("component").alias("above")), "component")
        labels = stored(join_by_size(hooked, stored(parent, "parents", files), "component", "nodes", n_nodes).select("node", F.col("above").alias("component"), "degree", "old"), "labels", files)
        moved = labels.where("component <> old").limit(1).count()
        labels = labels.drop("old")
        if not moved:
            break
    return labels.select("node", "component")
