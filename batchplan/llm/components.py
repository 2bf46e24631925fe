"""Connected components of a table of links, by alternating star contractions.

Links point from their greater to their lesser end. A round first hangs every greater neighbour of a
node on the least node that the node knows, then does the same with its lesser neighbours; each half
is a minimum that is combined before it is shuffled and a join, so a hub that a third of all links
share is one aggregated row, and Spark splits its partition in the join. No round makes more links than
there were. The links are stars, and the work is done, when no node knows two roots; the table that shows
it has the minima that the next round starts with. Rounds are written to the shared folder, which cuts the
lineage; nothing but a count reaches the driver, at every size of graph.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from batchplan.llm.shared import written


def connected_components(links: DataFrame) -> DataFrame:
    """links (a, b: long) to (node, component): the smallest node that each linked node can reach.

    Null ends and links of a node with itself count for nothing; no links give no rows.
    """
    stars = links.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct()
    while True:
        stars = written(stars, "cc-links")
        roots = stars.select(F.explode(F.array("hi", "lo")).alias("node"), "lo")
        known = written(roots.groupBy("node").agg(F.min("lo").alias("m"), F.max("lo").alias("other")), "cc-known")
        if not known.where("m <> other").count():
            return known.select("node", F.col("m").alias("component"))
        large = stars.join(known, F.col("lo") == F.col("node")).select("hi", F.col("m").alias("lo"))
        top = large.groupBy(F.col("hi").alias("at")).agg(F.min("lo").alias("m"))
        small = large.join(top, F.col("hi") == F.col("at")).select("hi", "lo", "m")
        pairs = small.select(F.explode(F.array(F.struct("hi", F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("p"))
        stars = pairs.select("p.hi", "p.lo").where("hi <> lo").distinct()
