"""Connected components of a link table, by smallest label with pointer jumping.

Each pass hands every node the smallest label among its neighbours and then the label of
that label's own node, so a path's length at least halves where labels chain. Labels are
written to the shared folder after each pass; nothing but a count reaches the driver.

Cases: loops and repeated links are harmless; null ends are dropped; no links, no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._shared import Scratch


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node reachable, for every node that has a link."""
    scratch = Scratch()
    durable = scratch.durable
    pairs = links.select(F.col(a).alias("u"), F.col(b).alias("v")).filter("u is not null and v is not null and u <> v")
    both = durable(pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))), "links")
    labels = durable(both.groupBy("u").agg(F.least("u", F.min("v")).alias("l")).withColumnRenamed("u", "n"), "labels")
    while True:
        # the smallest label next to each node; labels of hubs are spread by adaptive skew joins
        near = both.join(labels.withColumnRenamed("n", "u"), "u").groupBy("v").agg(F.min("l").alias("m"))
        step = labels.join(near.withColumnRenamed("v", "n"), "n", "left").select("n", "l", F.least("l", "m").alias("k"))
        # hooking: the old label's node learns of the smaller one too
        hook = step.filter("k < l").groupBy(F.col("l").alias("n")).agg(F.min("k").alias("h"))
        hooked = durable(step.join(hook, "n", "left").select("n", "l", F.least("k", "h").alias("k")), "hooked")
        jump = hooked.select(F.col("n").alias("k"), F.col("k").alias("j"))
        new = durable(hooked.join(jump, "k", "left").select("n", F.least("k", "j").alias("l"), (F.least("k", "j") < F.col("l")).alias("moved")), "labels")
        moved = new.filter("moved").limit(1).count()
        labels = new.select("n", "l")
        if not moved:
            scratch.drop(keep=1)
            return labels.select(F.col("n").alias("node"), F.col("l").alias("component"))
