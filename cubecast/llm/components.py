"""Connected components of an edge table by alternating stars, in DataFrame operations.

A large star hangs a node's larger neighbours on its least neighbour, a small star its smaller ones; the two alternate until
only stars are left. Each round is written to the shared folder, so no lineage grows; hubs are pre-aggregated before
the shuffle, and joins on them can be split. Loops and repeated edges are dropped; nulls take no part; no edges, no rows.
"""

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tables import forget, shared_table


def components(edges: DataFrame) -> DataFrame:
    """node, root (the least node of its component) from edges a, b; only nodes with an edge."""
    e = shared_table(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    while not stars(e):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("x")).select("x.*")
        e, old = shared_table(small.where("u <> v").distinct()), e
        forget(old)
    roots = e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())


def stars(e: DataFrame) -> bool:
    """Whether each node hangs on one other, and that one on none."""
    hangs = e.groupBy(F.col("u").alias("node")).agg(F.count("*").alias("n"))
    bears = e.select(F.col("v").alias("node"), F.lit(1).cast("long").alias("n")).distinct()
    return hangs.unionByName(bears).groupBy("node").agg(F.sum("n").alias("n")).where("n > 1").isEmpty()
