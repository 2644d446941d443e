"""Connected components of a graph given as a table of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nbflow.llm.common import discard, settle


def components(links: DataFrame) -> DataFrame:
    """Rows (key, root) for every key of ``links`` (a, b): root is the smallest key that links reach.

    Each round a key takes the least root among its own and its neighbours', then the root of that root,
    so chains halve; rounds end when no root changes. Links of one key are folded before the shuffle."""
    edges = settle(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    roots = settle(edges.groupBy(F.col("a").alias("key")).agg(F.least(F.min("b"), F.first("a")).alias("root")), "roots")
    while True:
        seen = edges.join(roots.select(F.col("key").alias("b"), F.col("root").alias("theirs")), "b").groupBy(F.col("a").alias("key")).agg(F.min("theirs").alias("theirs"))
        least = roots.join(seen, "key").select("key", F.col("root").alias("was"), F.least("root", "theirs").alias("root"))
        above = roots.select(F.col("key").alias("root"), F.col("root").alias("top"))
        after = settle(least.join(above, "root", "left").select("key", "was", F.least("root", F.coalesce("top", "root")).alias("root")), "roots")
        changed = after.filter("root <> was").limit(1).count()
        discard(roots)
        if not changed:
            discard(edges)
            return after.select("key", "root")
        roots = after
