"""Connected components of a large edge list with DataFrame joins only.

Rounds of lowest-neighbour hooking and pointer jumping: every node takes the smallest label around it, then its label's label.
Each round is one aggregate and two joins, kept as a table in the shared folder; the number of rounds grows with the logarithm of the
longest chain. Hot labels are on the probe side of a join whose build side has one row a key, which adaptive execution splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._util import drop, keep


def components(edges: DataFrame) -> DataFrame:
    """``node, root`` (root: smallest node reachable) of every node that an edge ``a, b`` names. Self loops and repeats count
    once; null ends are dropped; an empty list gives an empty frame."""
    edges = edges.select("a", "b").filter("a is not null and b is not null and a <> b")
    arcs = keep(edges.union(edges.select(F.col("b"), F.col("a"))).groupBy("a", "b").agg(F.lit(1).alias("one")).select("a", "b"), "arcs")
    state = keep(arcs.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("root")), "labels")
    while True:
        around = arcs.join(state.select(F.col("node").alias("b"), F.col("root").alias("r")), "b").groupBy("a").agg(F.min("r").alias("m"))
        hooked = state.join(around.select(F.col("a").alias("node"), "m"), "node", "left").select("node", "root", F.least("root", F.coalesce("m", "root")).alias("low"))
        # a root that sees something lower passes it on to its whole tree
        pulled = hooked.groupBy("root").agg(F.min("low").alias("best"))
        step = hooked.join(pulled, "root").select("node", F.col("root").alias("was"), F.least("low", "best").alias("next"))
        step = keep(step, "hooked")
        jump = step.select(F.col("node").alias("next"), F.col("next").alias("over"))
        new = keep(step.join(jump, "next", "left").select("node", "was", F.least("next", F.coalesce("over", "next")).alias("root")), "labels")
        changed = new.filter("root <> was").limit(1).count()
        old, state = state, new.select("node", "root")
        state._kept_at = getattr(new, "_kept_at", None)
        drop(old)
        drop(step)
        if not changed:
            drop(arcs)
            return state
