"""Connected components of an edge table, by least labels and pointer jumping; nothing is collected but counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packsum.llm.runtime import materialize


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, label): the least node reachable, for every node that has an edge.

    Each round gives a node the least label among its own and its neighbours', then lets labels jump to their own
    labels, so long chains take logarithmically many rounds. Rounds end when none changes.
    """
    both = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).unionByName(edges.select(F.col(b).alias("u"), F.col(a).alias("v")))
    both = materialize(both.filter(F.col("u") != F.col("v")).distinct())
    labels = materialize(both.groupBy(F.col("u").alias("node")).agg(F.least(F.min("v"), F.first("u")).alias("label")))
    while True:
        old = labels
        heard = both.join(old.withColumnRenamed("node", "v"), "v").groupBy("u").agg(F.min("label").alias("heard"))
        hooked = old.join(heard, F.col("node") == F.col("u"), "left").select("node", F.col("label").alias("before"), F.least("label", F.coalesce("heard", "label")).alias("label"))
        # A label's own new label: a hub's followers all jump at once.
        top = hooked.select(F.col("node").alias("t"), F.col("label").alias("further"))
        jumped = hooked.join(top, F.col("label") == F.col("t"), "left").select("node", "before", F.least("label", F.coalesce("further", "label")).alias("label"))
        step = materialize(jumped)
        labels = step.select("node", "label")
        if not step.filter(F.col("label") != F.col("before")).limit(1).count():
            return labels
