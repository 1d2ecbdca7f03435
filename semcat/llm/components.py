"""Connected components of a distributed edge list; nothing but a counter reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise


#: Rows of a written round that make a file; small rounds make few files, whatever the number of shuffle partitions.
ROWS = 1 << 18


def components(edges: DataFrame) -> DataFrame:
    """Edges (a, b: long) to (id, label): the smallest id reachable from each endpoint. Every round takes the least label of
    the neighbours, then follows labels of labels, so long chains shrink quickly; each round is a written table."""
    both = materialise(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "edges")
    parts = both.count() // ROWS + 1
    written = lambda df: materialise(df.coalesce(parts), "labels")
    labels = written(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m")).select("id", F.least("id", "m").alias("label"), F.lit(True).alias("changed")))
    while not labels.where("changed").isEmpty():
        near = both.join(labels.select(F.col("id").alias("b"), "label"), "b").groupBy(F.col("a").alias("id")).agg(F.min("label").alias("m"))
        step = labels.join(near, "id").select("id", F.col("label").alias("before"), F.least("label", "m").alias("mid"))
        jump = labels.select(F.col("id").alias("mid"), F.col("label").alias("far"))
        step = step.join(jump, "mid", "left").select("id", F.least("mid", F.coalesce("far", "mid")).alias("label"), "before")
        before, labels = labels, written(step.select("id", "label", (F.col("label") < F.col("before")).alias("changed")))
        discard(before)
    discard(both)
    return labels.select("id", "label")
