"""Connected components of an edge table, without moving edges to the driver."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from overlapix.llm.storage import discard, materialise

EDGE = "u bigint, v bigint"
#: Edges that one task contracts; a table of no more needs no rounds.
CHUNK = 200_000


def forest(pairs: Iterator[tuple[int, int]]) -> dict[int, int]:
    """node -> smallest node of its component, for an in-memory edge list."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while up[top] != top:
            top = up[top]
        while up[x] != top:
            up[x], x = top, up[x]
        return top

    for a, b in pairs:
        up.setdefault(a, a)
        up.setdefault(b, b)
        ra, rb = root(a), root(b)
        if ra != rb:
            up[max(ra, rb)] = min(ra, rb)
    return {x: root(x) for x in up}


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Replace the edges of each chunk of at most ``CHUNK`` or one batch by the stars of their components."""
    held: list[pa.RecordBatch] = []
    count = 0

    def stars() -> pa.RecordBatch:
        pairs = ((a, b) for batch in held for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True))
        kept = [(x, r) for x, r in forest(pairs).items() if x != r]
        held.clear()
        return pa.RecordBatch.from_arrays([pa.array([x for x, _ in kept], pa.int64()), pa.array([r for _, r in kept], pa.int64())], names=["u", "v"])

    for batch in batches:
        if held and count + batch.num_rows > CHUNK:
            yield stars()
            count = 0
        held.append(batch)
        count += batch.num_rows
    if held:
        yield stars()


def least_labels(near: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The smallest node that each end of a block's links reaches by them."""
    most = np.iinfo(np.int64).max
    while near.any():
        to_right = np.minimum(right, np.where(near, left[:, None], most).min(0))
        to_left = np.minimum(left, np.where(near, to_right[None, :], most).min(1))
        if (to_right == right).all() and (to_left == left).all():
            break
        left, right = to_left, to_right
    return left, right


def _with_least(edges: DataFrame, total: int) -> tuple[DataFrame, DataFrame]:
    """Edges with ``m``, the least ``v`` of their ``u``, and (u, m) alone.

    Nodes with more than their share of all edges, a partition's, are no more than
    there are partitions: their least ends are broadcast, so that no task has a hub
    whole.  The others meet theirs in a shuffle join.
    """
    parts = max(1, int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    least = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
    share = max(16, total // (4 * parts))
    hubs = F.broadcast(least.where(F.col("n") > share).select("u", "m"))
    rest = edges.join(hubs.select("u"), "u", "left_anti").join(least.where(F.col("n") <= share).select("u", "m").hint("merge"), "u")
    return edges.join(hubs, "u").select("u", "v", "m").unionByName(rest.select("u", "v", "m")), least.select("u", "m")


def _large_star(edges: DataFrame, total: int) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    joined, _ = _with_least(both, 2 * total)
    return joined.where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.least("u", "m").alias("v")).distinct()


def _small_star(edges: DataFrame, total: int) -> DataFrame:
    joined, least = _with_least(edges, total)
    moved = joined.where(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(u, v)`` edges -> ``(node, component)`` for every node that has an edge.

    ``component`` is the smallest node reachable.  Edges are first contracted
    in chunks inside tasks; where one chunk holds what is left, one task ends the
    work.  Else alternate large- and small-star rounds run until the edge set stops
    changing; each round is written to the shared folder, so a lost executor costs
    one round.  Self-loops and repeats are ignored; an empty table gives an empty
    result.
    """
    clean = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v")
    now = materialise(clean.mapInArrow(_contract, EDGE).distinct(), "edges")
    seen = _digest(now)
    if seen[0] <= CHUNK:
        last = materialise(now.coalesce(1).mapInArrow(_contract, EDGE), "edges")
        discard(now)
        now, seen = last, (0, 0)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        then = materialise(_small_star(_large_star(now, seen[0]), 2 * seen[0]), "edges")
        mark = _digest(then)
        discard(now)
        now, settled = then, mark == seen
        if settled:
            break
        seen = mark
    else:
        raise RuntimeError("components did not settle")
    ends = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return ends.unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _digest(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40)))).first()
    return (row[0], row[1])
