"""Connected components of a link table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """id, label for every vertex of links: label is the smallest id reachable.

    Each round takes the smallest label among the neighbours, hands it also to the vertex that the old label names, so that
    all that follow that vertex come along, and then follows labels once (label of the label). Labels only fall, so the
    rounds end by themselves, with the exact result. Every round is written to the shared folder; only whether something
    changed reaches the driver."""
    edges = links.select(F.col(a).alias("u"), F.col(b).alias("v"))
    edges = stored(edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "graph-edges")
    labels = stored(edges.groupBy(F.col("u").alias("id")).agg(F.least(F.min("v"), F.first("u")).alias("label")), "graph-labels")
    while True:
        seen = edges.join(labels.select(F.col("id").alias("v"), "label"), "v").groupBy(F.col("u").alias("id")).agg(F.min("label").alias("near"))
        hooked = labels.join(seen, "id").select("id", F.col("label").alias("old"), F.least("label", "near").alias("low"))
        told = F.array(F.struct("id", "old", "low"), F.struct(F.col("old").alias("id"), F.lit(None).cast("long").alias("old"), "low"))
        roots = hooked.select(F.explode(told).alias("x")).select("x.*").groupBy("id").agg(F.max("old").alias("old"), F.min("low").alias("label"))
        roots = stored(roots, "graph-roots")
        jumped = roots.join(roots.select(F.col("id").alias("label"), F.col("label").alias("next")), "label").select("id", "old", F.least("label", "next").alias("label"))
        new = stored(jumped, "graph-labels")
        labels = new.select("id", "label")
        if not new.where("old <> label").take(1):
            return labels
