"""Approximate nearest neighbours by cosine: a neighbour graph by NN-descent, searched greedily.

1. Rows with equal vectors form one node, which keeps its ``answers`` + 1 least
   ids; a vector that a third of all rows have is one node.
2. Random-projection trees, fitted on a bounded sample, and one dealing at random
   put every node into small chunks of at most about ``LEAF`` nodes, at any size
   of the table. Neighbours inside chunks are a first, poor graph. The trees also
   give entry points to searches.
3. NN-descent: around every node meet the nodes that it lists and a sample of
   those that list it, brought together by joins; who is a neighbour's neighbour
   is likely a neighbour. Edges that haven't taken part yet are fresh; pairs
   meet only where at least one of both came by a fresh edge, and of each
   meeting a node keeps its ``OFFERS`` best partners, if they beat its worst
   neighbour. The best ``DEGREE`` of old and new make the next graph. Rounds go
   on until at most ``SETTLED`` of its edges are fresh. Lists only get better, so
   they end.
4. Greedy search: a query holds its best nodes, ``BEAM`` at first, starting from
   its own list in the graph, the nodes that list it, and entry points of its
   leaves; in each step its best unexpanded nodes are joined with the graph,
   whose lists carry the neighbours' directions; neighbours better than the worst
   one held come in, until nothing unexpanded is left. The graph is a table in
   buckets of its nodes, so steps don't shuffle it.
5. The nearest of a sample of queries are found exactly, by one scan. While
   searches miss more than 1 - ``RECALL`` of them, all go on with beams twice as
   wide; beyond ``WIDEST`` all queries are compared with all nodes, in blocks.
6. Scores are computed anew in double precision on the original vectors.

Cases: null ids, and vectors that are null, empty, zero or hold null or
non-finite components, take no part; neither do vectors of another length than
the commonest (the longest at equal counts). Repeated rows are separate
candidates. A query's own row is left out once. Ties go to the smaller id. An
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Row, Window
from pyspark.sql import functions as F

from rangecut.llm.shared import forget, written

#: Vectors that the trees are fitted on, those whose id hashes lowest.
TREE_SAMPLE = 20_000
TREES, LEAF = 4, 64
#: Neighbours in the graph; how many of each kind (listed or listing, fresh or not) meet in a round; what a meeting offers a node.
DEGREE, MEET, OFFERS = 32, 16, 6
#: Rounds end once at most this share of the graph is fresh.
SETTLED = 0.05
ENTRIES, BEAM, EXPANDED = 16, 192, 192
#: Share of the nearest to be found, the queries it is measured on, the widest beam before all is compared.
RECALL, MEASURED, WIDEST = 0.95, 400, 2048
#: Queries compared with all nodes at once.
COMPARED = 2000
#: Nodes in a bucket of the graph, about.
BUCKET_ROWS = 20_000


def usable(vectors: DataFrame, vector_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """id and vector (doubles) of the rows that take part."""
    v = F.col(vector).cast("array<double>")
    finite = F.forall(v, lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < float("inf")), F.lit(False)))
    nonzero = F.exists(v, lambda x: x != 0)
    good = vectors.where(F.col(vector_id).isNotNull() & F.coalesce(finite & nonzero, F.lit(False))).select(F.col(vector_id).cast("long").alias("id"), v.alias("v"))
    sizes = good.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), F.desc("n")).limit(1).collect()
    return good.where(F.size("v") == sizes[0].n) if sizes else good


def nodes_of(good: DataFrame, answers: int) -> DataFrame:
    """node (its least id), ids (the ``answers`` + 1 least), v, unit (the direction in 8 bits a component)."""
    first = F.row_number().over(Window.partitionBy("v").orderBy("id"))
    few = good.withColumn("row", first).where(F.col("row") <= answers + 1)
    grouped = few.groupBy("v").agg(F.sort_array(F.collect_list("id")).alias("ids"))

    def direction(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            packed = pack_units(_directions(_matrix(batch.column(2))))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([u.tobytes() for u in packed], pa.binary())], names=["node", "ids", "v", "unit"])

    rows = grouped.select(F.element_at("ids", 1).alias("node"), "ids", "v")
    return rows.mapInArrow(direction, "node long, ids array<long>, v array<double>, unit binary")


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


def _directions(v: np.ndarray) -> np.ndarray:
    # Scaled first, so that squares neither overflow nor vanish.
    v = v / np.abs(v).max(1, keepdims=True)
    return v / np.sqrt((v * v).sum(1, keepdims=True))


def pack_units(unit: np.ndarray) -> np.ndarray:
    """Rows of bytes: a 32-bit scale, then a signed byte a component. Only the choice of candidates sees the rounding."""
    scale = (np.abs(unit).max(1, keepdims=True) / 127).astype("<f4")
    whole = np.rint(unit / scale).clip(-127, 127).astype(np.int8)
    return np.hstack([scale.view(np.uint8), whole.view(np.uint8)])


def unpack_units(raw: bytes, n: int) -> np.ndarray:
    rows = np.frombuffer(raw, np.uint8).reshape(n, -1)
    return rows[:, 4:].view(np.int8) * np.ascontiguousarray(rows[:, :4]).view("<f4")


def _units(column: pa.Array) -> np.ndarray:
    return unpack_units(b"".join(column.to_pylist()), len(column))


class Tree:
    """Splits at the median of the projection on the difference of two sample points; an array of levels."""

    def __init__(self, sample: np.ndarray, depth: int, seed: int):
        rng = np.random.default_rng(seed)
        self.depth = depth
        n, d = 2**depth - 1, sample.shape[1]
        self.normal, self.cut = np.zeros((n, d), np.float32), np.zeros(n, np.float32)
        at = np.zeros(len(sample), np.int64)
        for node in range(n):
            mine = np.flatnonzero(at == node)
            if len(mine) > 1:
                a, b = sample[rng.choice(mine, 2, replace=False)]
                self.normal[node] = a - b
                side = sample[mine] @ self.normal[node]
                self.cut[node] = np.median(side)
                at[mine] = 2 * node + 1 + (side > self.cut[node])
            else:
                at[mine] = 2 * node + 1

    def leaves(self, unit: np.ndarray) -> np.ndarray:
        at = np.zeros(len(unit), np.int64)
        for _ in range(self.depth):
            side = np.einsum("ij,ij->i", unit, self.normal[at])
            at = 2 * at + 1 + (side > self.cut[at])
        return at


def fit_trees(nodes: DataFrame, total: int) -> list[Tree]:
    rows = nodes.select("node", "unit").orderBy(F.xxhash64("node"), "node").limit(TREE_SAMPLE).collect()
    sample = unpack_units(b"".join(bytes(r.unit) for r in rows), len(rows))
    depth = int(max(0, min(np.ceil(np.log2(max(1, total / LEAF))), np.log2(max(1, len(rows) / 8)))))
    return [Tree(sample, depth, seed) for seed in range(TREES)]


def leaves_of(rows: DataFrame, trees: list[Tree], carried: str) -> DataFrame:
    """``node``, ``unit`` and what ``carried`` names, once for each tree: tree, leaf."""

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            unit = _units(batch.column("unit"))
            for k, tree in enumerate(trees):
                leaf = tree.leaves(unit)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(leaf), k, np.int32)), pa.array(leaf), *batch.columns], names=["tree", "leaf", *batch.schema.names])

    names = [x.split()[0] for x in carried.split(", ")]
    return rows.select(*names).mapInArrow(route, f"tree int, leaf long, {carried}")


def _groups(batches: Iterator[pa.RecordBatch], *keys: str) -> Iterator[pa.Table]:
    """Sorted rows, a table for each key."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
        change = np.zeros(batch.num_rows - 1, bool)
        for c in columns:
            change |= c[1:] != c[:-1]
        cuts = np.flatnonzero(change) + 1
        for start, end in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
            here = tuple(c[start] for c in columns)
            if held and here != last:
                yield pa.Table.from_batches(held)
                held = []
            last = here
            held.append(batch.slice(start, end - start))
    if held:
        yield pa.Table.from_batches(held)


PAIRS = "node long, other long, sim float"


def _pair_batch(node: np.ndarray, other: np.ndarray, sim: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(other, pa.int64()), pa.array(sim, pa.float32())], names=["node", "other", "sim"])


#: A node's list: ``edges`` packs it for the next round's merge, the arrays are for joins.
GRAPH = "node long, edges binary, worst float, others array<long>, sims array<float>, fresh array<boolean>, meets array<boolean>"
#: A partner in packed lists and offers.
PARTNER = np.dtype([("other", "<i8"), ("sim", "<f4"), ("fresh", "?")])


def _packed(partners: np.ndarray, sizes: np.ndarray) -> pa.Array:
    """Rows of ``sizes`` partners each, as bytes."""
    offsets = np.zeros(len(sizes) + 1, np.int32)
    np.cumsum(sizes * PARTNER.itemsize, out=offsets[1:])
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(offsets), pa.py_buffer(partners.tobytes())])


def _complete(batches: Iterator[pa.RecordBatch], key: str, at_once: int) -> Iterator[pa.Table]:
    """Rows sorted by ``key`` in tables of about ``at_once`` rows; no key is divided."""
    held: list[pa.RecordBatch] = []
    size = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        size += batch.num_rows
        if size >= at_once:
            rows = pa.Table.from_batches(held)
            keys = rows.column(key).to_numpy()
            cut = int(np.searchsorted(keys, keys[-1]))
            if cut:
                yield rows.slice(0, cut)
            held = rows.slice(cut).to_batches()
            size = len(rows) - cut
    if held:
        yield pa.Table.from_batches(held)


def _place(of: np.ndarray) -> np.ndarray:
    """Position of each element inside its run of equal values."""
    first = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]]))
    return np.arange(len(of)) - np.repeat(first, np.diff(np.append(first, len(of))))


def best(offered: DataFrame, round_: int) -> DataFrame:
    """Each node's ``DEGREE`` best different partners of all packed lists (node, edges), and which meet in the coming round."""

    def choose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _complete(batches, "node", 60_000):
            packed = rows.column("edges").to_pylist()
            partner = np.frombuffer(b"".join(packed), PARTNER)
            node = np.repeat(rows.column("node").to_numpy(), np.fromiter(map(len, packed), np.int64, len(packed)) // PARTNER.itemsize)
            other, sim, fresh = (partner[c] for c in ("other", "sim", "fresh"))
            order = np.lexsort((fresh, other, node))  # an edge that isn't fresh stays so, however often it is found
            node, other, sim, fresh = node[order], other[order], sim[order], fresh[order]
            once = np.concatenate([[True], (node[1:] != node[:-1]) | (other[1:] != other[:-1])])
            node, other, sim, fresh = node[once], other[once], sim[once], fresh[once]
            order = np.lexsort((other, -sim, node))
            order = order[_place(node[order]) < DEGREE]
            node, other, sim, fresh = node[order], other[order], sim[order], fresh[order]
            row = _place(node)
            first = np.flatnonzero(row == 0)
            sizes = np.diff(np.append(first, len(row)))
            worst = np.where(sizes >= DEGREE, sim[first + sizes - 1], np.float32(-2)).astype(np.float32)
            # Of the fresh edges the best meet, of the others those that a draw of the round favours.
            drawn = (node.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) ^ ((other + round_).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))
            drawn = (drawn ^ (drawn >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
            order = np.lexsort((np.where(fresh, row, drawn.view(np.int64) >> 8), fresh, node))
            meets = np.empty(len(node), bool)
            meets[order] = _place(2 * node[order] + fresh[order]) < MEET
            partners = np.empty(len(node), PARTNER)
            partners["other"], partners["sim"], partners["fresh"] = other, sim, fresh & ~meets
            offsets = pa.array(np.append(first, len(row)).astype(np.int32))
            lists = [pa.ListArray.from_arrays(offsets, pa.array(x)) for x in (other, sim, fresh, meets)]
            yield pa.RecordBatch.from_arrays([pa.array(node[first]), _packed(partners, sizes), pa.array(worst), *lists], names=["node", "edges", "worst", "others", "sims", "fresh", "meets"])

    return offered.select("node", "edges").repartition("node").sortWithinPartitions("node").mapInArrow(choose, GRAPH)


def edges(graph: DataFrame) -> DataFrame:
    """node, other, sim, fresh, meets: a row for each edge."""
    zipped = F.explode(F.arrays_zip("others", "sims", "fresh", "meets")).alias("e")
    return graph.select("node", zipped).select("node", F.col("e.others").alias("other"), F.col("e.sims").alias("sim"), F.col("e.fresh").alias("fresh"), F.col("e.meets").alias("meets"))


def first_graph(placed: DataFrame, nodes: DataFrame, total: int) -> DataFrame:
    """Neighbours inside small chunks of the trees' leaves, and of one dealing at random."""
    sizes = placed.groupBy("tree", "leaf").agg(F.ceil(F.count("*") / F.lit(LEAF)).alias("chunks"))
    chunked = placed.join(F.broadcast(sizes), ["tree", "leaf"])  # at most trees times sample rows
    dealt = nodes.select(F.lit(-1).alias("tree"), F.lit(0).cast("long").alias("leaf"), "node", "unit", F.lit(max(1, -(-total // LEAF))).cast("long").alias("chunks"))
    chunked = chunked.unionByName(dealt).withColumn("chunk", F.pmod(F.xxhash64("node", "tree"), "chunks")).drop("chunks")

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _groups(batches, "tree", "leaf", "chunk"):
            node, unit = rows.column("node").to_numpy(), _units(rows.column("unit"))
            n = len(node)
            if n < 2:
                continue
            k = min(DEGREE, n - 1)
            sim = unit @ unit.T
            np.fill_diagonal(sim, -2)
            at = np.argpartition(-sim, k - 1, axis=1)[:, :k]
            partners = np.empty((n, k), PARTNER)
            partners["other"], partners["sim"], partners["fresh"] = node[at], np.take_along_axis(sim, at, 1), True
            yield pa.RecordBatch.from_arrays([pa.array(node), _packed(partners, np.full(n, k))], names=["node", "edges"])

    dealt = chunked.repartition("tree", "leaf", "chunk").sortWithinPartitions("tree", "leaf", "chunk")
    return best(dealt.mapInArrow(meet, "node long, edges binary"), 0)


def descend(graph: DataFrame, nodes: DataFrame, round_: int) -> DataFrame:
    """One round of NN-descent: the graph joined with itself through the nodes in the middle."""
    edge = edges(graph)
    forward = edge.where("meets").select(F.col("node").alias("middle"), F.col("other").alias("node"), "fresh")
    sampled = F.row_number().over(Window.partitionBy("middle", "fresh").orderBy(F.xxhash64("node", "middle", F.lit(round_))))
    reverse = edge.select(F.col("other").alias("middle"), "node", "fresh").withColumn("nth", sampled).where(F.col("nth") <= MEET).drop("nth")
    carried = nodes.select("node", "unit").join(graph.select("node", "worst"), "node")

    def offers(sim: np.ndarray, other: np.ndarray, others: np.ndarray, sims: np.ndarray) -> None:
        """The best of ``other`` for each row of ``sim``, written into ``others`` and ``sims``."""
        k = min(OFFERS, sim.shape[1])
        at = np.argpartition(-sim, k - 1, axis=1)[:, :k]
        others[:, :k], sims[:, :k] = other[at], np.take_along_axis(sim, at, 1)

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _complete(batches, "middle", 60_000):
            middle, node, fresh, worst = (rows.column(c).to_numpy() for c in ("middle", "node", "fresh", "worst"))
            order = np.lexsort((~fresh, node, middle))
            once = np.concatenate([[True], (node[order][1:] != node[order][:-1]) | (middle[order][1:] != middle[order][:-1])])
            order = order[once]  # what came both ways meets once, as fresh if either was
            order = order[np.lexsort((~fresh[order], middle[order]))]  # fresh ones first
            middle, node, fresh, worst, unit = middle[order], node[order], fresh[order], worst[order], _units(rows.column("unit"))[order]
            starts = np.append(np.flatnonzero(np.concatenate([[True], middle[1:] != middle[:-1]])), len(middle))
            new = np.add.reduceat(fresh, starts[:-1], dtype=np.int64)
            others, sims = np.zeros((len(node), OFFERS), np.int64), np.full((len(node), OFFERS), np.float32(-3))
            for at, end, n in zip(starts[:-1], starts[1:], new, strict=True):
                if not n or end - at < 2:
                    continue
                sim = unit[at : at + n] @ unit[at:end].T
                sim[np.arange(n), np.arange(n)] = -3
                offers(sim, node[at:end], others[at : at + n], sims[at : at + n])
                if at + n < end:
                    offers(sim[:, n:].T, node[at : at + n], others[at + n : end], sims[at + n : end])
            better = sims > worst[:, None]  # the others don't come into their lists
            sizes = better.sum(1)
            partners = np.empty(int(sizes.sum()), PARTNER)
            partners["other"], partners["sim"], partners["fresh"] = others[better], sims[better], True
            some = sizes > 0
            yield pa.RecordBatch.from_arrays([pa.array(node[some]), _packed(partners, sizes[some])], names=["node", "edges"])

    dealt = forward.unionByName(reverse).join(carried, "node").select("middle", "node", "fresh", "unit", "worst").repartition("middle").sortWithinPartitions("middle")
    return best(graph.select("node", "edges").union(dealt.mapInArrow(meet, "node long, edges binary")), round_)


def settled_graph(placed: DataFrame, nodes: DataFrame, total: int, rounds: int | None = None) -> DataFrame:
    """Rounds of NN-descent on the first graph until hardly an edge is fresh (or, to look at them, so many ``rounds``)."""
    graph = written(first_graph(placed, nodes, total), "graph")
    round_ = 0
    while rounds is None or round_ < rounds:
        following = written(descend(graph, nodes, round_ + 1), "graph")
        forget(graph)
        graph, round_ = following, round_ + 1
        fresh, all_ = graph.agg(F.sum(F.size(F.filter("fresh", lambda f: f))), F.sum(F.size("fresh"))).first()
        if (fresh or 0) <= SETTLED * (all_ or 0):
            break
    return graph


def _similar(rows: DataFrame, keep: str) -> DataFrame:
    """Adds ``sim``, the similarity of q and unit in double precision, and drops both."""
    names = [x.split()[0] for x in keep.split(", ")]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                sim = np.einsum("ij,ij->i", _units(batch.column("q")), _units(batch.column("unit"))).astype(np.float64)
                yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(sim)], names=[*names, "sim"])

    return rows.select(*names, "q", "unit").mapInArrow(compare, f"{keep}, sim double")


def listed(graph: DataFrame, nodes: DataFrame, total: int) -> str:
    """The graph as a table: node, others, and the others' directions in one piece; bucketed by node. Returns its name."""
    name = f"rangecut_graph_{uuid.uuid4().hex}"
    near = edges(graph).select("node", "other").join(nodes.select(F.col("node").alias("other"), "unit"), "other")
    pair = F.sort_array(F.collect_list(F.struct("other", "unit")))
    whole = near.groupBy("node").agg(pair.alias("near")).select("node", F.col("near.other").alias("others"), F.array_join(F.transform("near.unit", F.hex), "").alias("units"))
    packed = whole.select("node", "others", F.unhex("units").alias("units"))
    n = max(1, -(-total // BUCKET_ROWS))
    packed.repartition(n, "node").write.bucketBy(n, "node").sortBy("node").saveAsTable(name)
    return name


def starts(queries: DataFrame, placed: DataFrame, trees: list[Tree], graph: DataFrame, width: int) -> DataFrame:
    """query, node, sim: entry points of each query's leaves, its own list and the best of the nodes that list it."""
    few = F.row_number().over(Window.partitionBy("tree", "leaf").orderBy(F.xxhash64("node")))
    entries = placed.withColumn("row", few).where(F.col("row") <= ENTRIES).select("tree", "leaf", "node", "unit")
    routed = leaves_of(queries.select("query", F.col("q").alias("unit")), trees, "query long, unit binary").withColumnRenamed("unit", "q")
    entered = _similar(routed.join(entries, ["tree", "leaf"]), "query long, node long")
    asked = queries.select("query")
    edge = edges(graph)
    own = edge.select(F.col("node").alias("query"), F.col("other").alias("node"), F.col("sim").cast("double").alias("sim")).join(asked, "query", "left_semi")
    nearest = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("sim"), "node"))
    back = edge.select(F.col("other").alias("query"), "node", F.col("sim").cast("double").alias("sim")).join(asked, "query", "left_semi")
    back = back.withColumn("row", nearest).where(F.col("row") <= width).drop("row")
    return entered.unionByName(own).unionByName(back)


def held(width: int) -> Column:
    return F.slice(F.sort_array(F.collect_list(F.struct("sim", "node", "open")), False), 1, width).alias("beam")


def search(queries: DataFrame, lists: DataFrame, started: DataFrame, width: int) -> DataFrame:
    """query, node, sim: the ``width`` nodes that each query (query, q: a unit vector's bytes) ends with, from those in ``started``."""
    once = started.groupBy("query", "node").agg(F.max("sim").alias("sim"))
    beam = written(once.withColumn("open", F.lit(True)).groupBy("query").agg(held(width)), "beam")
    is_open = F.exists("beam", lambda b: b["open"])
    finished: list[DataFrame] = []

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            q = _units(batch.column("q")).astype(np.float64)
            query, worst = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("query", "worst"))
            size = batch.column("others").value_lengths().to_numpy(zero_copy_only=False)
            others = batch.column("others").flatten().to_numpy(zero_copy_only=False)
            unit = np.frombuffer(b"".join(batch.column("units").to_pylist()), np.uint8).reshape(len(others), -1)
            ends = np.cumsum(size)
            for i in range(0, len(size), 256):  # bounds what stands in doubles at once
                rows = slice(ends[i] - size[i], ends[min(i + 256, len(size)) - 1])
                at = np.repeat(np.arange(i, min(i + 256, len(size))), size[i : i + 256])
                sim = np.einsum("ij,ij->i", q[at], unpack_units(unit[rows].tobytes(), len(at)))
                good = sim > worst[at]
                yield pa.RecordBatch.from_arrays([pa.array(query[at[good]]), pa.array(others[rows][good]), pa.array(sim[good])], names=["query", "node", "sim"])

    def step(active: DataFrame) -> DataFrame:
        opened = F.slice(F.filter("beam", lambda b: b["open"]), 1, EXPANDED)
        worst = F.when(F.size("beam") < width, F.lit(-2.0)).otherwise(F.element_at("beam", -1)["sim"])
        front = active.select("query", "beam", opened.alias("front"), worst.alias("worst"))
        reached = front.select("query", "worst", F.explode("front.node").alias("node")).join(queries.select("query", "q"), "query")
        found = reached.join(lists, "node").select("query", "worst", "q", "others", "units").mapInArrow(compare, "query long, node long, sim double")
        stayed = F.transform("beam", lambda b: F.struct(b["sim"].alias("sim"), b["node"].alias("node"), (b["open"] & ~F.array_contains(F.col("front.node"), b["node"])).alias("open")))
        closed = front.select("query", F.inline(stayed)).select("query", "node", "sim", "open")
        both = closed.unionByName(found.withColumn("open", F.lit(True)))
        # A node that was expanded isn't open again, however it is found.
        once = both.groupBy("query", "node").agg(F.max("sim").alias("sim"), F.min("open").alias("open"))
        return once.groupBy("query").agg(held(width))

    while True:
        going, all_ = beam.agg(F.count_if(is_open), F.count("*")).first()
        if not going:
            break
        if 2 * going <= all_:  # those that are through needn't be carried along
            finished.append(written(beam.where(~is_open), "beam"))
            active = beam.where(is_open)
        else:
            active = beam
        following = written(step(active), "beam")
        forget(beam, steps=False)
        beam = following
    for part in finished:
        beam = beam.unionByName(part)
    return beam.select("query", F.inline("beam")).select("query", "node", "sim")


def nearest_nodes(nodes: DataFrame, asked: list[Row], answers: int) -> DataFrame:
    """query, node: the ``answers`` nearest other nodes of each of ``asked`` (query, a), compared with all nodes in one scan."""
    spark = nodes.sparkSession
    if not asked:
        return spark.createDataFrame([], "query long, node long")
    own = np.array([r.query for r in asked], np.int64)
    a = _directions(np.array([r.a for r in asked], np.float64))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sims, found = np.full((len(own), answers), -2.0), np.zeros((len(own), answers), np.int64)
        for batch in batches:
            for i in range(0, batch.num_rows, 2000):
                part = batch.slice(i, 2000)
                node = part.column(0).to_numpy()
                sim = a @ _directions(_matrix(part.column(1))).T
                sim[own[:, None] == node] = -2
                both = np.hstack([sims, sim])
                at = np.argpartition(-both, answers - 1, axis=1)[:, :answers]
                sims = np.take_along_axis(both, at, 1)
                found = np.take_along_axis(np.hstack([found, np.broadcast_to(node, sim.shape)]), at, 1)
        good = sims > -2
        yield _pair_batch(np.broadcast_to(own[:, None], sims.shape)[good], found[good], sims[good])

    # Each task leaves its own best, so a window over tasks times answers rows decides.
    met = nodes.select("node", "v").mapInArrow(compare, "node long, other long, sim float")
    rank = F.row_number().over(Window.partitionBy("node").orderBy(F.desc("sim"), "other"))
    return met.withColumn("row", rank).where(F.col("row") <= answers).select(F.col("node").alias("query"), F.col("other").alias("node"))


def compared(queries: DataFrame, nodes: DataFrame, answers: int) -> DataFrame:
    """query, node: the nearest nodes of all queries, exactly: a scan of the nodes for each block of queries."""
    numbered = queries.select("query").join(nodes.select(F.col("node").alias("query"), F.col("v").alias("a")), "query")
    n = max(1, -(-numbered.count() // COMPARED))
    out = None
    for block in range(n):
        mine = numbered.where(F.pmod(F.xxhash64("query"), F.lit(n)) == block).collect()
        part = written(nearest_nodes(nodes, mine, answers), "compared")
        out = part if out is None else out.unionByName(part)
    return out


def reach(queries: DataFrame, lists: DataFrame, placed: DataFrame, trees: list[Tree], graph: DataFrame, nodes: DataFrame, answers: int) -> DataFrame:
    """query, node: the nodes whose scores are computed, at least ``RECALL`` of the nearest ones by the measured queries."""
    few = queries.select("query").orderBy(F.xxhash64("query"), "query").limit(MEASURED)
    asked = few.join(nodes.select(F.col("node").alias("query"), F.col("v").alias("a")), "query").collect()
    truth = written(nearest_nodes(nodes, asked, answers), "truth")
    known = truth.count()
    width, before = BEAM, None
    while True:
        started = starts(queries, placed, trees, graph, width)
        found = written(search(queries, lists, started if before is None else started.unionByName(before), width), "reached")
        met = found.select("query", "node").join(F.broadcast(truth), ["query", "node"]).count()  # at most MEASURED times answers rows
        if met >= RECALL * known:
            return found.select("query", "node")
        if 2 * width > WIDEST:
            return compared(queries, nodes, answers)
        width, before = 2 * width, found


def exact_scores(rows: DataFrame, keep: str) -> DataFrame:
    """Adds ``score``, the cosine of a and v in double precision."""
    names = [x.split()[0] for x in keep.split(", ")]

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                a, v = _matrix(batch.column("a")), _matrix(batch.column("v"))
                a, v = (x / 2.0 ** np.floor(np.log2(np.abs(x).max(1, keepdims=True))) for x in (a, v))  # exact
                score = (a * v).sum(1) / (np.sqrt((a * a).sum(1)) * np.sqrt((v * v).sum(1)))
                yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(np.clip(score, -1.0, 1.0))], names=[*names, "score"])

    return rows.select(*names, "a", "v").mapInArrow(compare, f"{keep}, score double")


def neighbours(vectors: DataFrame, is_query: Column, answers: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score: the ``answers`` nearest other rows found for each query row of ``vectors``."""
    good = usable(vectors)
    nodes = written(nodes_of(good, answers), "nodes")
    total = nodes.count()
    if not total:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    trees = fit_trees(nodes, total)
    placed = written(leaves_of(nodes, trees, "node long, unit binary"), "leaves")
    graph = settled_graph(placed, nodes, total)
    # Queries with equal vectors search once, as their node.
    asking = good.where(is_query).select("id", "v").join(nodes.select("node", "v", "unit"), "v").select("id", "node", "unit")
    asking = written(asking, "asking")
    queries = written(asking.select(F.col("node").alias("query"), F.col("unit").alias("q")).distinct(), "queries")
    lists = listed(graph, nodes, total)
    reached = reach(queries, vectors.sparkSession.table(lists), placed, trees, graph, nodes, answers)
    reached = written(reached.union(queries.select("query", F.col("query").alias("node"))).distinct(), "reached")
    vectors.sparkSession.sql(f"DROP TABLE {lists}")
    pairs = reached.join(nodes.select(F.col("node").alias("query"), F.col("v").alias("a")), "query").join(nodes.select("node", "ids", "v"), "node")
    scored = exact_scores(pairs, "query long, ids array<long>")
    near = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id"))
    few = scored.select("query", "score", F.explode("ids").alias("vec_id")).withColumn("row", near).where(F.col("row") <= answers + 1)
    found = few.groupBy("query").agg(F.sort_array(F.collect_list(F.struct("row", "vec_id", "score"))).alias("found"))
    # Every query row drops one row of its own id; should rounding have put others before it, the last one goes.
    own = F.array_position(F.transform("found", lambda f: f["vec_id"]), F.col("query_id"))
    others = F.filter("found", lambda f, i: i != F.when(own > 0, own.cast("int") - 1).otherwise(F.lit(answers)))
    answered = asking.select(F.col("id").alias("query_id"), F.col("node").alias("query")).join(found, "query")
    answered = answered.select("query_id", F.posexplode(others).alias("at", "f"))
    return answered.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), "f.vec_id", "f.score")
