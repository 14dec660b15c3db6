"""Connected components of a table of links, without bringing links to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, written


def components(links: DataFrame) -> DataFrame:
    """(id, component) for every id in ``links(a, b)``; a component's name is its smallest id.

    Each round takes the smallest name among the neighbours and then the name's own name, so that paths shorten fast.
    Rounds are written to the shared folder: a lost executor repeats one round at most.
    """
    both = written(links.select("a", "b").union(links.select("b", "a")).filter("a <> b").distinct(), "links")
    names = written(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m")).select("id", F.least("id", "m").alias("component")), "names")
    while True:
        heard = both.join(names, both["b"] == names["id"]).groupBy("a").agg(F.min("component").alias("m"))
        new = names.join(heard, names["id"] == heard["a"]).select("id", F.col("component").alias("old"), F.least("component", "m").alias("near"))
        of_name = names.select(F.col("id").alias("near"), F.col("component").alias("far"))
        new = written(new.join(of_name, "near", "left").select("id", F.least("near", F.coalesce("far", "near")).alias("component"), "old"), "names")
        drop_written(names)
        changed = new.filter("component <> old").limit(1).count()
        names = new.select("id", "component")
        if not changed:
            drop_written(both)
            return names
