"""Connected components of a distributed list of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from axisgrove.llm.common import cut, release


def components(links: DataFrame) -> DataFrame:
    """(node, label) for every node of ``links`` (a, b); label: the smallest node connected to it.

    Each round points every label to its smallest smaller neighbour, follows those pointers
    four steps on, and rewrites the links between labels; links inside a component disappear.
    The number of rounds grows with the logarithm of the longest path; two tables are written in each.
    """
    ends = F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")
    pairs = cut(links.select(*ends).filter("lo <> hi").distinct())
    label = links.select(F.explode(F.array("a", "b")).alias("node")).distinct().select("node", F.col("node").alias("label"))
    hooks: list[DataFrame] = []
    while not pairs.isEmpty():
        hook = cut(pairs.groupBy(F.col("hi").alias("from")).agg(F.min("lo").alias("to")))
        further = hook.select(F.col("from").alias("at"), F.col("to").alias("beyond"))
        far = hook
        for _ in range(3):
            far = far.join(further, F.col("to") == F.col("at"), "left").select("from", F.coalesce("beyond", "to").alias("to"))
        far = cut(far)
        one, two = (far.select(F.col("from").alias(f"from{i}"), F.col("to").alias(f"to{i}")) for i in (1, 2))
        moved = pairs.join(one, F.col("lo") == F.col("from1"), "left").join(two, F.col("hi") == F.col("from2"), "left")
        moved = moved.select(F.coalesce("to1", "lo").alias("a"), F.coalesce("to2", "hi").alias("b")).select(*ends).filter("lo <> hi")
        after = cut(moved.distinct())
        release(pairs, hook)
        pairs = after
        hooks.append(far)
    for hook in hooks:
        label = label.join(hook, F.col("label") == F.col("from"), "left").select("node", F.coalesce("to", "label").alias("label"))
    label = cut(label)
    release(pairs, *hooks)
    return label
