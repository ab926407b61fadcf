"""Connected components over a table of links, in DataFrame functions; nothing but counts reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangekeep.llm._shared import forget, keep


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node reachable, for every node that has a link to another.

    Every node takes the least label among its neighbours and then its label's label, until nothing changes; a label
    only falls, so the sum of all labels tells. Each round is written to the shared folder. A hub's links are joined,
    never gathered.
    """
    pairs = links.where(F.col(a) != F.col(b)).select(F.col(a).alias("x"), F.col(b).alias("y"))
    edges = keep(pairs.union(pairs.select(F.col("y").alias("x"), F.col("x").alias("y"))).distinct())
    now = keep(edges.groupBy(F.col("x").alias("node")).agg(F.least(F.first("x"), F.min("y")).alias("component")))
    total = lambda t: t.agg(F.sum(F.col("component").cast("decimal(38,0)"))).first()[0]
    last = total(now)
    while last is not None:
        heard = edges.join(now, edges.y == now.node).groupBy("x").agg(F.min("component").alias("m"))
        step = now.join(heard, now.node == heard.x).select("node", F.least("component", "m").alias("component"))
        step = keep(step)
        up = step.select(F.col("node").alias("up"), F.col("component").alias("top"))
        jumped = keep(step.join(up, F.col("component") == F.col("up")).select("node", F.least("component", "top").alias("component")))
        forget(now, step)
        now, before, last = jumped, last, total(jumped)
        if last == before:
            break
    forget(edges)
    return now
