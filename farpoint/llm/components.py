"""Connected components by contraction, for link tables of any size.

Each round every node points to the smallest node among itself and its neighbours, pointer
jumping takes it to the root of that forest, and the links are rewritten between roots. Every node
with a smaller neighbour disappears, so the node count at least halves; links that became inner
ones go. All state is in written tables, the driver sees counts only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.llm.common import Staging


def connected_components(stage: Staging, links: DataFrame) -> DataFrame:
    """links (a, b) -> (node, root) for each node of a link; root is the smallest node reachable."""
    edges = stage.keep(_between(links.select("a", "b")), "links")
    labels = None
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = stage.keep(both.groupBy("a").agg(F.min("b").alias("low")).select(F.col("a").alias("node"), F.least("a", "low").alias("root")), "up")
        while True:
            hop = up.select(F.col("node").alias("root"), F.col("root").alias("far"))
            jumped = stage.keep(up.join(hop, "root").select("node", F.col("far").alias("root"), (F.col("far") != F.col("root")).alias("moved")), "jump")
            up = jumped.select("node", "root")
            if jumped.where("moved").isEmpty():
                break
        a, b = up.select(F.col("node").alias("a"), F.col("root").alias("ra")), up.select(F.col("node").alias("b"), F.col("root").alias("rb"))
        edges = stage.keep(_between(edges.join(a, "a").join(b, "b").select(F.col("ra").alias("a"), F.col("rb").alias("b"))), "links")
        if labels is None:
            labels = up
        else:
            step = up.select(F.col("node").alias("root"), F.col("root").alias("next"))
            labels = stage.keep(labels.join(step, "root", "left").select("node", F.coalesce("next", "root").alias("root")), "labels")
    return labels if labels is not None else links.select(F.col("a").alias("node"), F.col("b").alias("root")).limit(0)


def _between(links: DataFrame) -> DataFrame:
    return links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
