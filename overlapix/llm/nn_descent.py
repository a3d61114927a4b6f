"""Near-duplicate vectors by NN-descent over a neighbour graph.

1. Equal vectors become one node, which keeps how many they are.
2. Sign projections give each node first neighbours: those beside it in the
   order of its bucket, in several tables.
3. Rounds of neighbours-of-neighbours joins refine lists of the ``k`` best: each
   node's forward and reverse neighbours meet, and pairs with a fresh edge whose
   similarity beats an end's worst neighbour are proposed to it.
4. A list of ``k`` links only is saturated: its node may have more, and closer
   copies may hide all of a looser group.  Saturated nodes search again, for
   nodes outside their component of near links alone: in blocks, all with all,
   where they are few, else by descent, until the lists of none are saturated or
   no component gains a link.
5. An audit compares a set of nodes, which grows with the table, with all others
   in blocks; below the wanted recall, ``k`` doubles, new tables of projections
   come in and the rounds go on, up to whole lists.
6. Every link inside a component of near links is counted in double precision,
   in blocks of a component.

The graph is refined on 8-bit codes; ``MARGIN`` covers their error, and step 6
decides on the original numbers.
"""

from __future__ import annotations


from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from overlapix.llm.arrow_groups import whole_groups
from overlapix.llm.components import connected_components, least_labels
from overlapix.llm.storage import discard, materialise

MARGIN = 0.015
TABLES = 8
BUCKET_BITS = 32
BESIDE = 6
ROUNDS = 7
#: Rounds end when fresh edges fall below this share of all.
SETTLED = 0.03
AUDIT_NODES = 48
#: Audited nodes are so many square roots of the table, first and at most; more are taken while they show fewer links than AUDIT_NODES.
AUDIT_ROOTS = (2, 8)
RECALL = 0.98
BLOCK_ROWS = 1024
#: Saturated nodes up to this number are compared with each other in blocks.
EXACT_NODES = 1 << 15
SEED = 20_011

EDGE = "u bigint, v bigint, s float, fresh int"


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """vectors -> bytes of float64; null where a vector can link with nothing."""
    for batch in batches:
        out: list[bytes | None] = []
        for x in batch.column(1):
            value = x.as_py()
            raw = None
            if value and None not in value:
                v = np.array(value, np.float64)
                if np.isfinite(v).all() and v.any() and np.isfinite(np.linalg.norm(v)):
                    raw = (v + 0.0).astype("<f8").tobytes()
            out.append(raw)
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["vec_id", "raw"])


def _unit(raw: np.ndarray) -> np.ndarray:
    x = np.ascontiguousarray(raw).view("<f8")
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _codes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        codes = []
        for raw in batch.column(1).to_pylist():
            v = np.frombuffer(raw, "<f8")
            codes.append(np.rint(v * (127 / np.abs(v).max())).astype(np.int8).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(codes, pa.binary())], names=["node", "code"])


def _code_unit(code: np.ndarray) -> np.ndarray:
    x = np.ascontiguousarray(code).view(np.int8).astype(np.float32)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _project(tables: int, turn: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(node, code, comp) -> (table and dimension, bits, node, code, comp), one row a table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            nodes, codes, comp = batch.column(0).to_numpy(), batch.column(1).to_pylist(), batch.column(2).to_numpy()
            sizes = np.array([len(c) for c in codes])
            for d in np.unique(sizes):
                at = np.flatnonzero(sizes == d)
                if d not in planes:
                    planes[d] = np.random.default_rng([SEED, int(d), turn]).standard_normal((d, tables * BUCKET_BITS)).astype(np.float32)
                x = np.frombuffer(b"".join(codes[i] for i in at), np.int8).reshape(len(at), d).astype(np.float32)
                bits = (x @ planes[d] > 0).reshape(len(at), tables, BUCKET_BITS)
                keys = bits @ (1 << np.arange(BUCKET_BITS, dtype=np.int64)[::-1])
                for t in range(tables):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), int(d) * tables + t)), pa.array(keys[:, t].astype(np.int64)), pa.array(nodes[at]), pa.array([codes[i] for i in at], pa.binary()), pa.array(comp[at])], names=["t", "bits", "node", "code", "comp"])

    return run


def _edges(u: np.ndarray, v: np.ndarray, s: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(s, pa.float32()), pa.array(np.ones(len(u), np.int32))], names=["u", "v", "s", "fresh"])


def _beside(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Similarities of nodes to those of other components that stand next in a
    bucket's order, after the run of their own component or before it."""
    for (_, _, _, nodes, code, comp), starts in whole_groups(batches, 2):
        n = len(nodes)
        group = np.repeat(np.arange(len(starts)), np.diff([*starts, n]))
        x = _code_unit(code)
        first = np.flatnonzero(np.concatenate([[True], (group[1:] != group[:-1]) | (comp[1:] != comp[:-1])]))
        sizes = np.diff([*first, n])
        start, end = np.repeat(first, sizes), np.repeat(first + sizes, sizes)
        here = np.arange(n)
        deep = here[here - start >= BESIDE]  # the run before has met the others
        for lag in range(BESIDE):
            a, b = np.concatenate([here, deep]), np.concatenate([end + lag, start[deep] - 1 - lag])
            inside = (b >= 0) & (b < n)
            a, b = a[inside], b[inside]
            differ = (group[a] == group[b]) & (comp[a] != comp[b])
            a, b = a[differ], b[differ]
            s = np.einsum("ij,ij->i", x[a], x[b])
            yield _edges(np.concatenate([nodes[a], nodes[b]]), np.concatenate([nodes[b], nodes[a]]), np.concatenate([s, s]))


def _local_join(k: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(centre, member, fresh, low, code, comp) groups -> better pairs of different components."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, members, fresh, low, code, comp), starts in whole_groups(batches):
            out = []
            for a, b in zip(starts, [*starts[1:], len(members)], strict=True):
                if b - a < 2 or not fresh[a:b].any():
                    continue
                m, f, w = members[a:b], fresh[a:b] > 0, low[a:b]
                x = _code_unit(code[a:b])
                s = x @ x.T
                np.fill_diagonal(s, -2)
                s[~f[:, None] & ~f[None, :]] = -2
                good = s > w[:, None]
                i, j = np.nonzero(good)
                differ = comp[a:b][i] != comp[a:b][j]
                i, j = i[differ], j[differ]
                if len(i):
                    out.append((m[i], m[j], s[i, j]))
            if out:
                yield _edges(*(np.concatenate([o[c] for o in out]) for c in range(3)))

    return run


def _best(edges: DataFrame, k: int) -> DataFrame:
    """The ``k`` most similar neighbours of each node; one shuffle, by node."""
    single = edges.repartition("u").groupBy("u", "v").agg(F.max("s").alias("s"), F.min("fresh").alias("fresh"))
    rank = F.row_number().over(Window.partitionBy("u").orderBy(F.desc("s"), "v"))
    return single.withColumn("r", rank).where(F.col("r") <= k).drop("r")


def tables_for(n: int) -> int:
    """Projection tables of ``n`` nodes."""
    return max(TABLES, int(np.ceil(np.log2(max(2, n)) / 2)))


def first_graph(nodes: DataFrame, k: int, n: int, turn: int = 0) -> DataFrame:
    """Lists of neighbours of other components for ``(node, code, comp)``; each ``turn`` has its own projections."""
    spread = max(0, BUCKET_BITS - max(1, int(np.log2(max(2, n / 16)))))
    rows = nodes.select("node", "code", "comp").mapInArrow(_project(tables_for(n), turn), "t bigint, bits bigint, node bigint, code binary, comp bigint").withColumn("bucket", F.shiftright("bits", spread))
    ordered = rows.select("t", "bucket", "bits", "node", "code", "comp").repartition("t", "bucket").sortWithinPartitions("t", "bucket", "bits", "node")
    return _best(ordered.mapInArrow(_beside, EDGE), k)


def refine(graph: DataFrame, codes: DataFrame, k: int, inner: DataFrame | None = None) -> DataFrame:
    """One round: the graph after its neighbours' neighbours met.  ``inner`` edges
    lead from a node to more members of its component and take no place in lists."""
    low = graph.groupBy("u").agg(F.when(F.count("*") >= k, F.min("s")).otherwise(-1.0).cast("float").alias("low"))
    nodes = codes.join(low, codes["node"] == low["u"], "left").select("node", "code", "comp", F.coalesce("low", F.lit(-1.0)).cast("float").alias("low"))
    back = F.row_number().over(Window.partitionBy("v").orderBy(F.desc("fresh"), F.desc("s"), "u"))
    reverse = graph.withColumn("r", back).where(F.col("r") <= k).select(F.col("v").alias("c"), F.col("u").alias("m"), "fresh")
    itself = codes.select(F.col("node").alias("c"), F.col("node").alias("m"), F.lit(0).alias("fresh"))
    meet = graph.select(F.col("u").alias("c"), F.col("v").alias("m"), "fresh").unionByName(reverse).unionByName(itself)
    if inner is not None:
        meet = meet.unionByName(inner.select(F.col("u").alias("c"), F.col("v").alias("m"), F.lit(0).alias("fresh")))
    meet = meet.groupBy("c", "m").agg(F.max("fresh").alias("fresh"))
    members = meet.join(nodes, meet["m"] == nodes["node"]).select("c", "m", "fresh", "low", "code", "comp")
    better = members.repartition("c").sortWithinPartitions("c").mapInArrow(_local_join(k), EDGE)
    return _best(graph.withColumn("fresh", F.lit(0)).unionByName(better), k)


def settle(graph: DataFrame, codes: DataFrame, k: int, n: int, inner: DataFrame | None = None) -> DataFrame:
    """Rounds until few edges are new."""
    for _ in range(max(ROUNDS, int(np.log2(max(2, n))))):
        new = materialise(refine(graph, codes, k, inner), "graph")
        discard(graph)
        graph = new
        fresh, all_ = graph.agg(F.coalesce(F.sum("fresh"), F.lit(0)), F.count("*")).first()
        if fresh <= SETTLED * all_:
            break
    return graph


def _audit_blocks(queries: list[tuple[int, bytes]], threshold: float) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by: dict[int, list[tuple[int, bytes]]] = {}
        for q in queries:
            by.setdefault(len(q[1]), []).append(q)
        for batch in batches:
            nodes, raws = batch.column(0).to_numpy(), batch.column(1).to_pylist()
            sizes = np.array([len(r) for r in raws])
            for d, qs in by.items():
                at = np.flatnonzero(sizes == d)
                if not len(at):
                    continue
                x = _unit(np.frombuffer(b"".join(raws[i] for i in at), np.uint8).reshape(len(at), d))
                for first in range(0, len(qs), BLOCK_ROWS):
                    part = qs[first : first + BLOCK_ROWS]
                    q = _unit(np.frombuffer(b"".join(r for _, r in part), np.uint8).reshape(len(part), d))
                    i, j = np.nonzero(q @ x.T >= threshold)
                    ids = np.array([n for n, _ in part])[i]
                    other = nodes[at][j]
                    keep = ids != other
                    if keep.any():
                        yield pa.RecordBatch.from_arrays([pa.array(ids[keep]), pa.array(other[keep])], names=["u", "v"])

    return run


def audit(vectors: DataFrame, threshold: float, nodes: int = AUDIT_NODES) -> DataFrame:
    """All links of ``nodes`` nodes of ``(node, raw)``, by comparison with every node in blocks."""
    chosen = vectors.orderBy(F.xxhash64("node"), "node").limit(nodes).select("node", "raw").collect()
    return vectors.select("node", "raw").mapInArrow(_audit_blocks([(r.node, bytes(r.raw)) for r in chosen], threshold), "u bigint, v bigint")


def _pairs(threshold: float) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(component, block, other block, own block, node, size, raw) groups -> each
    node's links there, and edges enough to connect what they connect."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, first, second, own, nodes, sizes, raw), starts in whole_groups(batches, 3):
            for a, b in zip(starts, [*starts[1:], len(nodes)], strict=True):
                x = _unit(raw[a:b])
                n, w, o = nodes[a:b], sizes[a:b], own[a:b]
                p, q = (np.flatnonzero(o == first[a]), np.flatnonzero(o == second[a]))
                same = first[a] == second[a]
                links = np.zeros(b - a, np.int64)
                for i in range(0, len(p), BLOCK_ROWS):
                    at = p[i : i + BLOCK_ROWS]
                    near = x[at] @ x[q].T >= threshold
                    if same:
                        near[at[:, None] == q[None, :]] = False
                    links[at] += near @ w[q]
                    if not same:
                        links[q] += near.T @ w[at]
                    low_p, low_q = least_labels(near, n[at], n[q])
                    ends, stars = np.concatenate([n[at], n[q]]), np.concatenate([low_p, low_q])
                    moved = ends != stars
                    yield _found(ends[moved], np.zeros(moved.sum(), np.int64), stars[moved])
                yield _found(n, links, n)

    return run


def _found(u: np.ndarray, links: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(links, pa.int64()), pa.array(v, pa.int64())], names=["node", "links", "v"])


def count_links(vectors: DataFrame, near: DataFrame, threshold: float) -> DataFrame:
    """``(node, links, v)`` over the components of ``near`` edges: sums of ``links``
    are exact within a component, and (node, v) edges connect what links connect."""
    comps = connected_components(near)
    sizes = comps.groupBy("component").agg(F.count("*").alias("n")).select("component", F.ceil(F.col("n") / BLOCK_ROWS).cast("int").alias("blocks"))
    members = comps.join(sizes, "component").join(vectors, "node").select("component", "node", "size", "raw", "blocks", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("own"))
    others = members.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = others.select("component", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "node", "size", "raw")
    return rows.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j").mapInArrow(_pairs(threshold), "node bigint, links bigint, v bigint")


def near_duplicates(table: DataFrame, vector: str = "embedding", vec_id: str = "vec_id", threshold: float = 0.9, k: int = 12) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)``, one row per input row.

    Vectors that are null, empty, zero or hold null or non-finite numbers link
    with nothing: no links, a component of their own.  Vectors of different
    lengths never link.  A null id links with nothing and has a null component.
    Repeated rows count as vectors of their own.  An empty table gives none.
    """
    rows = table.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.col(vector).cast("array<double>").alias("e"))
    packed = materialise(rows.mapInArrow(_pack, "vec_id bigint, raw binary"), "vectors")
    vectors = materialise(packed.where("raw is not null and vec_id is not null").groupBy("raw").agg(F.min("vec_id").alias("node"), F.count("*").alias("size")), "distinct-vectors")
    codes = materialise(vectors.select("node", "raw").mapInArrow(_codes, "node bigint, code binary"), "codes")
    near = neighbour_links(vectors, codes, threshold, k)
    found = materialise(count_links(vectors, near, threshold), "links")
    comps = connected_components(found.where("node <> v").select(F.col("node").alias("u"), "v"))
    totals = found.groupBy("node").agg(F.sum("links").alias("links"))
    named = vectors.join(totals, "node", "left").join(comps, "node", "left").select("raw", (F.coalesce("links", F.lit(0)) + F.col("size") - 1).cast("bigint").alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    own = packed.where("raw is not null and vec_id is not null").join(named, "raw").select("vec_id", "n_links", "component_id")
    alone = packed.where("raw is null or vec_id is null").select("vec_id", F.lit(0).cast("bigint").alias("n_links"), F.col("vec_id").alias("component_id"))
    both = own.unionByName(alone)
    return both.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


def grown_audit(vectors: DataFrame, threshold: float, n: int) -> DataFrame:
    """Links of some square roots of ``n`` nodes; of more where those show few."""
    root = np.sqrt(n)
    nodes = int(max(AUDIT_NODES, AUDIT_ROOTS[0] * root))
    while True:
        truth = materialise(audit(vectors, threshold, nodes), "audit")
        if nodes >= min(n, AUDIT_ROOTS[1] * root) or truth.count() >= AUDIT_NODES:
            return truth
        discard(truth)
        nodes *= 2


def _meet_blocks(bar: float) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(d, i, j, own, node, comp, code) groups -> near edges between components, one
    for each node and component that it meets there."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, first, second, own, node, comp, code), starts in whole_groups(batches, 3):
            for a, b in zip(starts, [*starts[1:], len(node)], strict=True):
                x, v, c, o = _code_unit(code[a:b]), node[a:b], comp[a:b], own[a:b]
                p, q = np.flatnonzero(o == first[a]), np.flatnonzero(o == second[a])
                i, j = np.nonzero((x[p] @ x[q].T >= bar) & (c[p][:, None] != c[q][None, :]))
                _, one = np.unique(np.stack([v[p][i], c[q][j]]), axis=1, return_index=True)
                yield pa.RecordBatch.from_arrays([pa.array(v[p][i][one]), pa.array(v[q][j][one])], names=["u", "v"])

    return run


def meet_in_blocks(nodes: DataFrame, n: int, bar: float) -> DataFrame:
    """``(u, v)``: near edges between components of ``(node, code, comp)``, by all pairs of blocks."""
    blocks = max(1, -(-n // (2 * BLOCK_ROWS)))
    own = nodes.withColumn("own", F.pmod(F.xxhash64("node"), F.lit(blocks)).cast("int"))
    other = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    rows = other.select(F.length("code").alias("d"), F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "node", "comp", "code")
    return rows.repartition("d", "i", "j").sortWithinPartitions("d", "i", "j").mapInArrow(_meet_blocks(bar), "u bigint, v bigint")


def join_saturated(graph: DataFrame, nodes: DataFrame, bar: float, k: int) -> DataFrame:
    """Near edges ``(u, v)`` of ``graph``, and of lists of nodes outside their own
    component for those whose ``k`` neighbours are all near.

    Such lists need not hold the links inside a component, since step 6 counts
    them all; so no list grows with a group.  A link between a saturated node and
    one that is not is in the latter's list.
    """
    near = materialise(graph.where(F.col("s") >= bar).select("u", "v"), "near")
    latest, turn = graph, 0
    while True:
        turn += 1
        full = latest.where(F.col("s") >= bar).groupBy(F.col("u").alias("node")).agg(F.count("*").alias("c")).where(F.col("c") >= k).select("node")
        if not full.limit(1).count():
            return near
        own = connected_components(near).withColumnRenamed("component", "own")
        still = materialise(nodes.join(full, "node").join(own, "node").select("node", "code", F.col("own").alias("comp")), "saturated")
        if still.select("comp").distinct().limit(2).count() < 2:
            return near
        n = still.count()
        if n <= EXACT_NODES:
            return near.unionByName(materialise(meet_in_blocks(still, n, bar), "near"))
        latest = settle(materialise(first_graph(still, k, n, turn), "graph"), still, k, n, graph)
        links = materialise(latest.where(F.col("s") >= bar).select("u", "v"), "near")
        if not links.limit(1).count():
            return near
        near = near.unionByName(links)


def neighbour_links(vectors: DataFrame, codes: DataFrame, threshold: float, k: int) -> DataFrame:
    """Graph edges near the threshold, after descent, saturated lists and audit."""
    nodes = codes.withColumn("comp", F.col("node"))
    n = codes.count()
    graph = materialise(first_graph(nodes, k, n), "graph")
    truth = grown_audit(vectors, threshold, n)
    wanted = truth.count()
    turn = 0
    while True:
        graph = settle(graph, nodes, k, n)
        near = join_saturated(graph, nodes, threshold - MARGIN, k)
        if not wanted or k >= n:
            break
        # step 6 counts a link if, and only if, its ends share a component
        comps = connected_components(near)
        ends = truth.join(comps.select(F.col("node").alias("u"), F.col("component").alias("cu")), "u", "left").join(comps.select(F.col("node").alias("v"), F.col("component").alias("cv")), "v", "left")
        if ends.where("cu = cv").count() >= RECALL * wanted:
            break
        k *= 2
        turn += 1
        more = first_graph(nodes, k, n, (1 << 20) + turn)
        graph = materialise(_best(graph.withColumn("fresh", F.lit(1)).unionByName(more), k), "graph")
    return near.unionByName(truth)


__all__ = ["audit", "count_links", "join_saturated", "near_duplicates", "neighbour_links"]
