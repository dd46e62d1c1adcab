"""Connected components of links, by star contraction over DataFrames."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import staged

MOST_ROUNDS = 60
CHUNK = 200_000  # links that a task joins up before it sends them


def _forests(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Links of a chunk as stars: each node under the least node that the chunk ties it to. A combiner: what is connected stays so."""

    def stars(parent: dict[int, int]) -> pd.DataFrame:
        out = [(u, _root(parent, u)) for u in parent]
        return pd.DataFrame([x for x in out if x[0] != x[1]], columns=["u", "v"])

    parent: dict[int, int] = {}
    held = 0
    for batch in batches:
        for u, v in zip(batch["u"].tolist(), batch["v"].tolist(), strict=True):
            a, b = _root(parent, parent.setdefault(u, u)), _root(parent, parent.setdefault(v, v))
            if a != b:
                parent[max(a, b)] = min(a, b)
        held += len(batch)
        if held >= CHUNK:
            yield stars(parent)
            parent, held = {}, 0
    yield stars(parent)


def _root(parent: dict[int, int], x: int) -> int:
    while parent[x] != x:
        parent[x] = parent[parent[x]]
        x = parent[x]
    return x


def _least(links: DataFrame) -> DataFrame:
    return links.groupBy("u").agg(F.min("v").alias("m"))


def components(links: DataFrame) -> DataFrame:
    """(node, root) of every node in links (u, v): root is the least node that it is linked with over any number of links.

    Each round hangs the greater neighbours of a node, then the lesser ones,
    under its least neighbour. Only links move; nothing of a group is gathered,
    and least neighbours are found by sums that combine before the shuffle.
    Rounds end when no link changes; their number grows as the logarithm of
    the longest chain.
    """
    stars = links.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).where("u <> v").mapInPandas(_forests, "u long, v long")
    cur = staged(stars.distinct(), "links")
    mark = None
    for _ in range(MOST_ROUNDS):
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.join(_least(both), "u").where("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v"))
        large = large.distinct()
        low = large.join(_least(large), "u")
        small = low.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        cur = staged(small.mapInPandas(_forests, "u long, v long").distinct(), "links")
        now = cur.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"components did not settle in {MOST_ROUNDS} rounds")
    roots = cur.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return roots.unionByName(roots.select(F.col("root").alias("node"), "root").distinct())
