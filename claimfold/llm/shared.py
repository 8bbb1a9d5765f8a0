"""Batch counts, bounded samples and connected components for the operators."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.workspace import settle

__all__ = ["Forest", "components", "fresh", "settle", "spread", "text_bytes_total", "thin"]


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df doesn't have, whatever its case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def text_bytes_total(docs: DataFrame, text: str) -> int:
    return docs.agg(F.sum(F.octet_length(text))).first()[0] or 0


def thin(rows: DataFrame, hash: str, total: int, wanted: int) -> DataFrame:
    """About 1.3 times the wanted rows, those of the smallest hashes: what a final top-k then sorts is bounded."""
    if total <= 2 * wanted + 1000:
        return rows
    share = (1.3 * wanted + 500) / total
    return rows.where(F.col(hash) < F.lit(int(-(2**63) + share * 2**64)))


def spread(docs: DataFrame) -> int:
    """Shuffle partitions of the session, the number of tasks that wide steps get."""
    return int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))


class Forest:
    """Union-find over dense integers, roots being the smallest members."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        if x == y:
            return False
        self.up[max(x, y)] = min(x, y)
        return True


def _local_roots(batches):
    """Union-find over the edges of one partition: (node, smallest node it reaches here)."""
    parts = [b for b in batches if b.num_rows]
    if not parts:
        return
    u = np.concatenate([b.column(0).to_numpy(zero_copy_only=False) for b in parts])
    v = np.concatenate([b.column(1).to_numpy(zero_copy_only=False) for b in parts])
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    forest = Forest(len(nodes))
    for x, y in zip(at[: len(u)].tolist(), at[len(u) :].tolist(), strict=True):
        forest.join(x, y)
    roots = nodes[[forest.root(i) for i in range(len(nodes))]]
    yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(roots)], names=["node", "root"])


def components(edges: DataFrame, name: str, rounds: int = 60) -> DataFrame:
    """(node, component) for the ends of edges (u, v); component is the smallest node reached.

    Every round contracts the edges of each partition on their own, which leaves
    each node with one root a partition at most.  Nodes with one root are done;
    the roots of a node with several are linked, and these links, far fewer, are
    the edges of the next round.  A node that very many edges share never meets
    all of them in one task: what is gathered is a root for each partition.
    Each round has half the partitions of the one before, so even a long chain of
    edges ends after about log2(partitions) rounds.  Null ends are dropped; no edges give no rows.
    """
    spark = edges.sparkSession
    parts = spread(edges)
    level = edges.toDF("u", "v").where("u is not null and v is not null and u <> v")
    maps = []
    for k in range(rounds):
        # By the larger end: a hub is the smaller end of its star, and isn't gathered.
        dealt = level.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).repartition(max(1, parts >> k), "v")
        local = dealt.mapInArrow(_local_roots, "node long, root long")
        rooted = settle(local.groupBy("node").agg(F.sort_array(F.collect_set("root")).alias("roots")), f"{name}-roots{k}")
        maps.append(rooted.select("node", F.element_at("roots", 1).alias("component")))
        links = rooted.where("size(roots) > 1").select(F.element_at("roots", 1).alias("u"), F.explode(F.slice("roots", 2, 1 << 30)).alias("v")).distinct()
        level = settle(links, f"{name}-links{k}")
        if level.isEmpty():
            break
    else:
        raise RuntimeError(f"{name}: components did not settle in {rounds} rounds")
    whole = maps[-1]
    for lower in reversed(maps[:-1]):
        over = whole.select(F.col("node").alias("component"), F.col("component").alias("higher"))
        low = lower.join(over, "component", "left").select("node", F.coalesce("higher", "component").alias("component"))
        whole = settle(low, f"{name}-map")
    return whole
