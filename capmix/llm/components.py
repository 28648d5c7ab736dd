"""Connected components of a graph held in DataFrames, by randomised contraction.

Each round every node hooks to the neighbour (or itself) whose hashed id is smallest, the edges are
rewritten to the hooks and parallel ones dropped. Hash order changes from round to round, so a round
removes a constant share of the nodes on average whatever the graph's shape (chains, stars, cliques), and
the number of rounds grows with the logarithm of the longest component. The hooks of all rounds
are composed at the end. Minima are aggregated before they are shuffled, so a node with very many
edges costs no more in one task than the number of map tasks. Nothing but a count of edges reaches the
driver, and each round is cut off by a table in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of `edges` (a, b): equal roots, the same component."""
    edges = materialise(edges.select("a", "b").filter("a <> b").distinct(), "edges")
    rounds = []
    while edges.limit(1).count():
        salt = F.lit(len(rounds))
        both = edges.select(F.col("a").alias("node"), F.col("b").alias("to")).union(edges.select(F.col("b"), F.col("a")))
        rank = lambda c: F.struct(F.xxhash64(salt, c).alias("h"), F.col(c).alias("id"))
        hooks = both.groupBy("node").agg(F.min(rank("to")).alias("least")).select("node", F.least(rank("node"), F.col("least"))["id"].alias("hook"))
        hooks = materialise(hooks, "hooks")
        rounds.append(hooks)
        left = edges.join(hooks.select(F.col("node").alias("a"), F.col("hook").alias("ha")), "a")
        moved = left.join(hooks.select(F.col("node").alias("b"), F.col("hook").alias("hb")), "b")
        moved = moved.select(F.least("ha", "hb").alias("a"), F.greatest("ha", "hb").alias("b"))
        edges = materialise(moved.filter("a <> b").distinct(), "edges")
    if not rounds:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    found = rounds.pop()
    while rounds:
        later = found.select(F.col("node").alias("hook"), F.col("hook").alias("root"))
        found = rounds.pop().join(later, "hook", "left").select("node", F.coalesce("root", "hook").alias("hook"))
    return found.select("node", F.col("hook").alias("root"))
