"""Connected components of a table of links, by smallest labels and pointer jumping.

Every round writes its labels to the shared folder. Links stay distributed; a vertex with very many links is
only one row of labels, so adaptive execution can split its links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densekeys.llm.common import Cuts


def components(links: DataFrame, cuts: Cuts | None = None) -> DataFrame:
    """vertex, component (the smallest vertex that links reach), for every vertex of `links` (a, b); `cuts` gets what the result reads."""
    own = Cuts(links.sparkSession)
    both = own.write(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "links")
    labels = own.write(both.groupBy("a").agg(F.min("b").alias("near")).select(F.col("a").alias("vertex"), F.least("a", "near").alias("component")), "labels")
    while True:
        near = both.join(labels.withColumnRenamed("vertex", "b"), "b").groupBy("a").agg(F.min("component").alias("near"))
        stepped = labels.join(near.withColumnRenamed("a", "vertex"), "vertex").select("vertex", F.col("component").alias("before"), F.least("component", "near").alias("component"))
        stepped = own.write(stepped, "labels-step")
        root = stepped.select(F.col("vertex").alias("component"), F.col("component").alias("root"))
        jumped = own.write(stepped.join(root, "component").select("vertex", "before", F.least("component", "root").alias("component")), "labels")
        changed = jumped.where("component <> before").limit(1).count()
        labels = jumped.select("vertex", "component")
        own.drop(jumped, *([both] if changed else []))
        if not changed:
            if cuts is not None:
                cuts.held += own.held
            return labels
