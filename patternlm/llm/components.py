"""Connected components by minimum labels with pointer jumping; all state stays in tables, one number a round reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from patternlm.session import cut


def components(links: DataFrame) -> DataFrame:
    """links (a, b) -> (node, comp): comp is the smallest node that links reach. Nodes without links have no row."""
    edges = cut(links.select("a", "b").union(links.select(F.col("b"), F.col("a"))).where("a <> b").distinct(), "cc-edges")
    labels = cut(edges.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("comp")), "cc-labels")
    while True:
        seen = edges.join(labels.select(F.col("node").alias("b"), "comp"), "b").groupBy(F.col("a").alias("node")).agg(F.min("comp").alias("near"))
        hop = labels.join(seen, "node").select("node", F.col("comp").alias("old"), F.least("comp", "near").alias("comp"))
        far = hop.select(F.col("node").alias("comp"), F.col("comp").alias("far"))
        jump = hop.join(far, "comp", "left").select("node", "old", F.least("comp", F.coalesce("far", "comp")).alias("comp"))
        jump = cut(jump, "cc-labels")
        if jump.where("comp <> old").isEmpty():
            return jump.select("node", "comp")
        labels = jump.select("node", "comp")
