"""Connected components of an edge table, without gathering links anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.llm.common import written


def components(edges: DataFrame, rounds: int = 64) -> DataFrame:
    """Rows (v, label) for every end of an edge (u, v): label is the smallest vertex reachable.

    Each round hangs every vertex and its neighbours below the smallest label among them and
    then jumps from label to label; both are summed before the shuffle, so that a vertex with
    very many edges is not gathered. Each round is written to the shared folder.
    """
    both = edges.select(F.col("u").alias("a"), F.col("v").alias("b")).where("a <> b")
    both = written(both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    labels = written(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("v"), F.least("a", "m").alias("label")), "labels")
    for _ in range(rounds):
        # the smallest label around each vertex, for the vertex and for the tree it hangs in
        near = both.join(labels.select(F.col("v").alias("b"), F.col("label").alias("lb")), "b").groupBy("a").agg(F.min("lb").alias("near"))
        own = labels.join(near, labels.v == near.a).select("v", "label", F.least("label", "near").alias("low"))
        hung = own.groupBy("label").agg(F.min("low").alias("up"))
        new = own.join(hung, "label").select("v", F.least("low", "up").alias("label"), (F.least("low", "up") < F.col("label")).alias("moved"))
        jumped = new.alias("x").join(new.select(F.col("v").alias("label"), F.col("label").alias("up")), "label", "left").select("v", F.least("label", F.coalesce("up", "label")).alias("label"), "moved")
        jumped = written(jumped, "labels")
        labels = jumped.select("v", "label")
        if jumped.where("moved").isEmpty():
            return labels
    raise RuntimeError(f"labels still moved after {rounds} rounds")
