"""Distributed connected components by alternating star contractions.

Each round every vertex tells its larger neighbours (large star), then its smaller ones (small
star), about the smallest id that it sees. The edge list converges to stars whose centres are the
smallest ids of the components. Per-vertex minima are partial aggregates; they are staged before
they are joined back, so that a vertex with very many links is split by the adaptive skew join.

Edge cases: loops and repeated links do no harm; links with a null end are dropped; an empty list
gives no rows; vertices are any longs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from avcurate.llm.common import stage


def _minima(edges: DataFrame, tag: str) -> DataFrame:
    """edges (u, v): the least id among u and its neighbours v, for vertices that have any."""
    return stage(edges.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m")), tag)


def _signature(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.lit(0))).first()
    return tuple(row)


def connected_components(edges: DataFrame, max_rounds: int = 64) -> DataFrame:
    """edges (u long, v long), in any direction -> (id, component) of every vertex with a link.

    component is the smallest id reachable. Loops and repeated edges do no harm; null ends are
    dropped; an empty edge list gives an empty result.
    """
    cur = stage(
        edges.where("u is not null and v is not null and u <> v")
        .select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        .distinct(),
        "cc-edges",
    )
    seen = _signature(cur)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = (
            both.join(_minima(both, "cc-min"), "u")
            .where("v > u and v <> m")
            .select(F.col("v").alias("u"), F.col("m").alias("v"))
            .distinct()
        )
        large = stage(large, "cc-large")
        mins = _minima(large, "cc-min")
        joined = large.join(mins, "u")
        small = (
            joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(mins.where("u <> m").select("u", F.col("m").alias("v")))
            .distinct()
        )
        cur = stage(small, "cc-small")
        now = _signature(cur)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return cur.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(
        cur.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
    )
