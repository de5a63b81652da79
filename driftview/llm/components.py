"""Connected components of links that may form large stars and long chains."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.llm.scratch import discard, materialize


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Smallest reachable id of every id that has a link: rows (node, root).

    Each round, every node takes the smallest root among its neighbours', every
    root takes the smallest root proposed to one of its nodes, and roots are
    then followed one step, so that chains halve.  Minima are combined before
    they are shuffled, and joins on a hot node are ordinary equi-joins, which
    adaptive execution splits.  Null ids and links of a node to itself are
    ignored; no links give no rows.
    """
    spark = links.sparkSession
    both = links.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u is not null and v is not null and u <> v")
    edges = materialize(both.unionByName(both.select(F.col("v").alias("u"), F.col("u").alias("v"))), "edges", by_size=True)
    roots = materialize(edges.groupBy(F.col("u").alias("node")).agg(F.least(F.min("u"), F.min("v")).alias("root")), "roots", by_size=True)
    while True:
        near = edges.join(roots.select(F.col("node").alias("v"), "root"), "v").groupBy(F.col("u").alias("node")).agg(F.min("root").alias("seen"))
        seen = roots.join(near, "node").select("node", "root", F.least("root", "seen").alias("seen"))
        seen = materialize(seen, "seen", by_size=True)
        hooks = seen.where("seen < root").groupBy(F.col("root").alias("node")).agg(F.min("seen").alias("hook"))
        hooked = seen.join(hooks, "node", "left").select("node", "root", F.least("seen", F.coalesce("hook", "seen")).alias("next"))
        hooked = materialize(hooked, "hooked", by_size=True)
        jump = hooked.select(F.col("node").alias("next"), F.col("next").alias("further"))
        # a root is a node as well, so every step can be followed
        after = materialize(hooked.join(jump, "next").select("node", F.col("further").alias("root"), (F.col("further") < F.col("root")).alias("moved")), "roots", by_size=True)
        moved = after.where("moved").limit(1).count()
        discard(spark, roots, seen, hooked, *([] if moved else [edges]))
        roots = after.select("node", "root")
        if not moved:
            return roots
