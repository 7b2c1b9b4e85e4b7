"""Connected components of a table of links, with joins and aggregates only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.llm.common import drop_stored, stored


def components(links: DataFrame, left: str = "a", right: str = "b") -> DataFrame:
    """(node, label): label is the smallest node reachable over links, taken both ways.

    A round gives each node the smallest label among its neighbours and then the
    label of its label, so labels travel at doubling speed.  Hot nodes cost one
    row a task in the partial minimum.  Every round is a written table in the
    shared folder; the driver sees one count a round.
    """
    both = stored(
        links.select(F.explode(F.array(F.struct(F.col(left).alias("u"), F.col(right).alias("v")), F.struct(F.col(right).alias("u"), F.col(left).alias("v")))).alias("x"))
        .select("x.*").where("u is not null and v is not null").distinct(),
        "links",
    )
    labels = stored(both.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("v")).select("node", F.least("node", "v").alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("node").alias("v"), "label"), "v").groupBy(F.col("u").alias("node")).agg(F.min("label").alias("near"))
        hooked = stored(labels.join(near, "node").select("node", F.col("label").alias("old"), F.least("label", "near").alias("label")), "hooked")
        jump = hooked.select(F.col("node").alias("label"), F.col("label").alias("next"))
        following = stored(hooked.join(jump, "label").select("node", "old", F.least("label", "next").alias("label")), "labels")
        drop_stored(labels)
        drop_stored(hooked)
        labels = following
        if labels.where("old <> label").limit(1).count() == 0:
            drop_stored(both)
            return labels.select("node", "label")
