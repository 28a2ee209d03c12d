"""Connected components of an undirected link table, in DataFrame rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from frontfill.llm.common import checkpointed


def components(links: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 64) -> DataFrame:
    """``node, root``: for every end of a link the smallest node that it reaches.

    Each round hooks a node to the smallest root among its own and its neighbours',
    then halves the paths by looking up the root of the root; the rounds grow with the
    logarithm of the longest path, not with the data.  Aggregations run map-side first,
    so a hub's many links meet as one row a task.  The state is checkpointed a round.
    """
    both = checkpointed(links.select(F.col(a).alias("u"), F.col(b).alias("v")).union(links.select(F.col(b).alias("u"), F.col(a).alias("v"))).where("u <> v").distinct())
    state = checkpointed(both.groupBy(F.col("u").alias("node")).agg(F.least(F.min("v"), F.first("u")).alias("root")))
    for _ in range(max_rounds):
        near = both.join(state.select(F.col("node").alias("v"), F.col("root").alias("r")), "v").groupBy(F.col("u").alias("node")).agg(F.min("r").alias("r"))
        hooked = state.join(near, "node", "left").select("node", F.col("root").alias("was"), F.least("root", F.coalesce("r", "root")).alias("root"))
        # what a root has learnt from any of its nodes is passed to all of them
        lifted = hooked.groupBy(F.col("was").alias("root0")).agg(F.min("root").alias("best"))
        merged = hooked.join(lifted, hooked["was"] == lifted["root0"], "left").select("node", "was", F.least("root", F.coalesce("best", "root")).alias("root"))
        jump = merged.select(F.col("node").alias("root1"), F.col("root").alias("far"))
        merged = merged.select("node", "was", F.col("root").alias("root1")).join(jump, "root1", "left").select("node", "was", F.least("root1", F.coalesce("far", "root1")).alias("root"))
        merged = checkpointed(merged)
        done = merged.where("root <> was").isEmpty()
        state = merged.select("node", "root")
        if done:
            return state
    raise RuntimeError("components did not settle")
