"""Choices that Catalyst can't make: engine, orientation, coloring strategy, weights."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.functions.pattern import broom_runs

#: An index of so many weights (8 bytes in memory, several times that in Python) may be sent to each worker.
LOCAL_WEIGHTS = 20_000_000
#: Of exact weights, which are Python objects on the driver and in each worker, so many.
LOCAL_EXACT = 1_000_000
#: The kernel also keeps each vertex's neighbours as bits: at most a bit for each pair of vertices, in so many bytes.
LOCAL_BITS_BYTES = 256 << 20
GREEDY_EDGES = 1_000_000
#: Beyond this degree, walks meet the neighbours of the chosen vertex with fewest, and adjacency is counted by joins
#: instead of looked up in an array of all neighbours.
HUB_DEGREE = 100_000


@dataclass(frozen=True)
class Choice:
    engine: str
    strategy: str
    weight: str
    transpose: bool
    blocks: int | None
    meet: str = "shared"
    contain: str = "array"


def statistics(edges: DataFrame) -> dict[str, int]:
    """edges, largest degrees; one pass a side."""
    row = edges.groupBy("u").agg(F.count(F.lit(1)).alias("d")).agg(F.sum("d"), F.max("d"), F.count(F.lit(1))).first()
    right = edges.groupBy("v").agg(F.count(F.lit(1)).alias("d")).agg(F.max("d"), F.count(F.lit(1))).first()
    return {"edges": row[0] or 0, "max_u": row[1] or 0, "max_v": right[0] or 0, "left": row[2], "right": right[1]}


def fewer_turned(p: int, q: int) -> bool:
    """Whether the broom has fewer runs with the sides exchanged."""
    return len(broom_runs(q, p)) < len(broom_runs(p, q))


def choose(stats: dict[str, int], p: int, q: int, weight: str = "double") -> Choice:
    """Fewer runs mean fewer shuffles, so the orientation with fewer is taken; hubs get the skew-safe sums."""
    e = stats["edges"]
    return Choice(
        engine="local" if e * (p + q - 1) <= (LOCAL_EXACT if weight == "decimal" else LOCAL_WEIGHTS) and stats["left"] * stats["right"] // 8 <= LOCAL_BITS_BYTES else "join",
        strategy="greedy" if e <= GREEDY_EDGES else "rounds",
        weight="double",
        transpose=fewer_turned(p, q),
        blocks=4096 if max(stats["max_u"], stats["max_v"]) > 5_000_000 else None,
        meet="least" if max(stats["max_u"], stats["max_v"]) > HUB_DEGREE else "shared",
        contain="join" if max(stats["max_u"], stats["max_v"]) > HUB_DEGREE else "array",
    )
