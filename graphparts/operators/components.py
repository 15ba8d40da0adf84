"""Connected components by alternating star contractions.

Every round hangs the larger neighbours of a vertex on the smallest vertex it knows, then
does the same for the smaller ones, until the edge set is a set of stars. The number of
rounds grows with the logarithm of the diameter. Minima are aggregated before the shuffle and
joined back. Where a vertex has a large share of all edges, they meet its minimum by a broadcast
of such vertices alone (``plans.skew``), so they are never gathered in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.plans.scratch import dropped, written
from graphparts.plans.skew import hub_limit, join_per_key


def _hang(edges: DataFrame, larger: bool, most: int, scratch: list[DataFrame]) -> DataFrame:
    """One contraction over (a, b) with a > b, as edges of the same form; ``scratch`` gets tables to delete when that is written."""

    def with_low(rows: DataFrame, low: DataFrame) -> DataFrame:
        return join_per_key(rows, low, "a", "n", most) if most else rows.join(low.select("a", "low"), "a")

    def kept(low: DataFrame) -> DataFrame:
        if most:
            scratch.append(low := written(low, "lows"))
        return low

    if larger:
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = kept(both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("low"), F.count("*").alias("n")))
        out = with_low(both.where("b > a"), low).select(F.col("b").alias("a"), F.col("low").alias("b"))
    else:
        low = kept(edges.groupBy("a").agg(F.min("b").alias("low"), F.count("*").alias("n")))
        moved = with_low(edges, low).where("b <> low").select(F.col("b").alias("a"), F.col("low").alias("b"))
        out = moved.unionByName(low.select("a", F.col("low").alias("b")))
    return out.where("a <> b").distinct()


def _state(edges: DataFrame) -> tuple[tuple, int]:
    """Number and checksum of the edges, and the limit above which a vertex is a hub (0: none is)."""
    ends = edges.select(F.explode(F.array("a", "b")).alias("v"), F.xxhash64("a", "b").cast("decimal(38,0)").alias("h"))
    one = ends.groupBy("v").agg(F.count("*").alias("n"), F.sum("h").alias("h")).agg(F.coalesce(F.max("n"), F.lit(0)), F.coalesce(F.sum("n"), F.lit(0)), F.sum("h")).first()
    most = hub_limit(one[1])
    return (one[1], one[2]), most if one[0] > most else 0


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """``(v, component)`` for every endpoint; ``component`` is the smallest vertex reachable.

    Null endpoints and loops are ignored; direction and repeats do not matter.
    """
    pairs = edges.where(F.col(src).isNotNull() & F.col(dst).isNotNull() & (F.col(src) != F.col(dst)))
    a, b = F.col(src).cast("bigint"), F.col(dst).cast("bigint")
    now = written(pairs.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct(), "components")
    seen, most = _state(now)
    for _ in range(max_rounds):
        scratch = [now]
        half = _hang(now, True, most, scratch)
        if most:  # each half round is written, as its minima are read apart from its edges
            scratch.append(half := written(half, "components"))
        following = written(_hang(half, False, most, scratch), "components")
        dropped(now.sparkSession, *scratch)
        now = following
        state, most = _state(now)
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    stars = now.select(F.col("a").alias("v"), F.col("b").alias("component"))
    return stars.unionByName(now.select(F.col("b").alias("v"), F.col("b").alias("component")).distinct())
