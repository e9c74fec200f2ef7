"""N-gram Jaccard join by chosen paths: near copies among all documents.

1. A text is the set of its runs of five words (all its words, where fewer).
   Texts with equal sets form one node; from here on only nodes are compared.
   A node carries a signature of ``COORDINATES`` minima of hash functions over
   its set: a fixed-size sample of its tokens.
2. A run puts every node into the bucket of one sampled token, that is of the
   signature's value at a coordinate that the run draws. A bucket above
   ``BUCKET`` nodes is split again by the values at one or two coordinates that
   its path draws (1/similarity on average, so that a pair at the threshold
   doesn't die out), and so on. All runs are worked on together, level by level.
3. Small buckets are compared by brute force, in two steps. The first sees
   signatures and drops pairs whose estimate is ``MARGIN`` (over five standard
   deviations) below the threshold; the second fetches the whole sets of what
   is left and computes exact similarities. A pair that shares several buckets
   is looked at in the one with the smallest key only.
4. From how many pairs were met in one run and in two the number of pairs met
   in none is estimated; runs are added until ``recall`` is reached. Should
   ``DOUBLINGS`` not be enough, all pairs that share a token of their prefixes
   are compared instead, which misses none: similar sets share one of the
   n - least * n + 1 rarest tokens of either.
5. A bucket gives a row for each node: the nodes that it is linked with, counted
   with their copies, and a spanning forest of the links. Connected components
   of the forests (alternating large and small stars) are the groups.

No step emits the pairs of a group, and a bucket that ``LEVELS`` splits leave
large is compared exactly in blocks.

Cases: a null text is an empty one; texts without words are copies of each
other; texts of fewer than five words are one run; very long texts are read
whole, by one task each; a similarity of exactly the threshold links; of equal
ids the least text hash stands for its group; a null id stays null; repeated
rows are copies; an empty table gives no rows; other columns, whatever their
names, are left out by ``links`` and kept by ``keep_one``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rangecut.llm.shared import forget, written

COORDINATES = 64
#: Runs at first, and how often they may be doubled.
RUNS, DOUBLINGS = 8, 2
#: Nodes that are compared by brute force at once.
BUCKET = 2048
LEVELS = 10
#: A pair whose estimated similarity is so far below the threshold isn't looked at exactly.
MARGIN = 0.27
RECALL = 0.99
_REMEMBERED = 400_000
_GOLD = 0x9E3779B97F4A7C15


class Shingler:
    """Sets of hashed word runs."""

    def __init__(self, words: int):
        self.words = words
        self.known: dict[bytes, int] = {}
        rng = np.random.default_rng(7)
        self.factors = (rng.integers(0, 2**63, COORDINATES, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)

    def set_of(self, text: str) -> np.ndarray:
        words = text.encode("utf-8", "surrogatepass").split()
        if not words:
            return np.empty(0, np.uint64)
        known = self.known
        if len(known) > _REMEMBERED:
            known.clear()
        hashes = np.empty(len(words), np.uint64)
        for i, word in enumerate(words):
            h = known.get(word)
            if h is None:
                h = known[word] = xxhash.xxh3_64_intdigest(word)
            hashes[i] = h
        n = min(self.words, len(words))
        size = len(hashes) - n + 1
        total = np.zeros(size, np.uint64)
        for k in range(n):
            total = (total ^ hashes[k : k + size]) * np.uint64(_GOLD)
            total ^= total >> np.uint64(29)
        return np.unique(total)

    def signature(self, found: np.ndarray) -> np.ndarray:
        if not len(found):
            return np.zeros(COORDINATES, np.int32)
        least = np.full(COORDINATES, 2**32 - 1, np.uint64)
        for i in range(0, len(found), 4096):
            mixed = (found[i : i + 4096, None] * self.factors[None, :]) >> np.uint64(32)
            least = np.minimum(least, mixed.min(0))
        return least.astype(np.uint32).view(np.int32)


def node_of(found: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh3_64_intdigest(found.tobytes())).view(np.int64))


def signed(docs: DataFrame, words: int) -> DataFrame:
    """doc_id, text_key, node, n, signature of every document."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(words)
        for batch in batches:
            node, n, signatures = [], [], []
            for text in batch.column(2):
                found = shingler.set_of(text.as_py() or "")
                node.append(node_of(found))
                n.append(len(found))
                signatures.append(shingler.signature(found))
            flat = np.concatenate(signatures) if signatures else np.empty(0, np.int32)
            offsets = np.arange(len(node) + 1, dtype=np.int32) * COORDINATES
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(node, pa.int64()), pa.array(n, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))],
                names=["doc_id", "text_key", "node", "n", "signature"],
            )

    keyed = docs.select(F.col("doc_id").cast("long"), text_key(docs), "text")
    return keyed.mapInArrow(sign, "doc_id long, text_key long, node long, n long, signature array<int>")


def text_key(docs: DataFrame):
    return F.xxhash64(F.coalesce(docs["text"], F.lit(""))).alias("text_key")


def paths(nodes: DataFrame, runs: int) -> DataFrame:
    """node, run, bucket, block, chunk: the buckets of at least two nodes that each node is compared in.

    ``block`` and ``chunk`` are 0 but in buckets that stayed large: there a
    node's chunk meets all others, in as many blocks.
    """

    def coordinate(*seed):
        return F.element_at("signature", (F.pmod(F.xxhash64(*seed), F.lit(COORDINATES)) + 1).cast("int"))

    # Every run starts at a coordinate of its own, as long as there are any left.
    own = F.element_at("signature", (F.pmod(F.col("run") * 27 + 5, F.lit(COORDINATES)) + 1).cast("int"))

    level = nodes.select("node", "signature", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run"))
    level = level.select("node", "run", F.xxhash64("run", own).alias("bucket"))
    done, used = [], []
    for depth in range(1, LEVELS + 1):
        level = written(level, f"paths-{depth}")
        used.append(level)
        sizes = level.groupBy("bucket").agg(F.count("*").alias("members")).where("members > 1")
        placed = level.join(sizes, "bucket")
        done.append(placed.where(F.col("members") <= BUCKET).select("node", "run", "bucket", F.lit(0).alias("chunk"), F.lit(1).alias("chunks")))
        large = sizes.where(F.col("members") > BUCKET)
        if not large.take(1):
            break
        large = placed.where(F.col("members") > BUCKET)
        if depth == LEVELS:
            done.append(chunked(large))
            break
        # One coordinate, and for one path in four a second one.
        turns = F.when(F.pmod(F.xxhash64("bucket", F.lit("turns")), F.lit(4)) == 0, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))
        split = large.join(nodes.select("node", "signature"), "node").withColumn("turn", F.explode(turns))
        level = split.select("node", "run", F.xxhash64("bucket", "turn", coordinate("bucket", "turn")).alias("bucket"))
    every = done[0]
    for more in done[1:]:
        every = every.unionByName(more)
    found = blocked(every)
    for step in used:
        forget(step)
    return found


def chunked(large: DataFrame) -> DataFrame:
    """Buckets that stay large (node, run, bucket, members), dealt into chunks that meet two at a time."""
    chunks = F.ceil(F.col("members") / F.lit(BUCKET // 2)).cast("int")
    return large.select("node", "run", "bucket", F.pmod(F.xxhash64("node"), chunks).cast("int").alias("chunk"), chunks.alias("chunks"))


def blocked(every: DataFrame) -> DataFrame:
    blocks = F.when(F.col("chunks") == 1, F.array(F.lit(0))).otherwise(
        F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda o: F.least(o, F.col("chunk")) * F.col("chunks") + F.greatest(o, F.col("chunk")))
    )
    return written(every.withColumn("block", F.explode(blocks)).select("node", "run", "bucket", "block", "chunk", "chunks"), "buckets")


def prefixes(docs: DataFrame, nodes: DataFrame, least: float, words: int) -> DataFrame:
    """The buckets of an exact join: each node under the rarest tokens of its set, so many that similar sets share one."""
    sets = sets_of(docs, nodes.select("node", "rep_id", "rep_key"), words)
    tokens = written(sets.select("node", F.size("tokens").alias("n"), F.explode("tokens").alias("bucket")), "tokens")
    known = tokens.join(tokens.groupBy("bucket").agg(F.count("*").alias("held_by")), "bucket")
    nth = F.row_number().over(Window.partitionBy("node").orderBy("held_by", "bucket"))
    prefix = known.withColumn("nth", nth).where(F.col("nth") <= F.col("n") - F.ceil(F.lit(least) * F.col("n") - 1e-9) + 1)
    level = prefix.select("node", F.lit(0).alias("run"), "bucket")
    placed = level.join(level.groupBy("bucket").agg(F.count("*").alias("members")).where("members > 1"), "bucket")
    small = placed.where(F.col("members") <= BUCKET).select("node", "run", "bucket", F.lit(0).alias("chunk"), F.lit(1).alias("chunks"))
    found = blocked(small.unionByName(chunked(placed.where(F.col("members") > BUCKET))))
    forget(tokens)
    return found


def _by_bucket(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Sorted rows, one table for each (bucket, block)."""
    held: list[pa.RecordBatch] = []
    key = None
    for batch in batches:
        if not batch.num_rows:
            continue
        bucket = batch.column("bucket").to_numpy(zero_copy_only=False)
        block = batch.column("block").to_numpy(zero_copy_only=False)
        cuts = np.flatnonzero((bucket[1:] != bucket[:-1]) | (block[1:] != block[:-1])) + 1
        for start, end in zip([0, *cuts], [*cuts, len(bucket)], strict=True):
            here = (bucket[start], block[start])
            if held and here != key:
                yield pa.Table.from_batches(held)
                held = []
            key = here
            held.append(batch.slice(start, end - start))
    if held:
        yield pa.Table.from_batches(held)


class Bucket:
    """The nodes of one bucket and which pairs of them are to be looked at here."""

    def __init__(self, rows: pa.Table, least: float):
        self.node = rows.column("node").to_numpy()
        n = len(self.node)
        signature = rows.column("signature").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(n, COORDINATES)
        self.n = rows.column("n").to_numpy()
        bucket, chunks = rows.column("bucket")[0].as_py(), rows.column("chunks")[0].as_py()
        runs = np.zeros((n, n), np.int8)
        first = np.ones((n, n), bool)
        lists = rows.column("buckets").combine_chunks()
        ids = lists.flatten().to_numpy(zero_copy_only=False)
        owner = np.repeat(np.arange(n), lists.value_lengths().to_numpy(zero_copy_only=False))
        order = np.argsort(ids, kind="stable")
        ids, owner = ids[order], owner[order]
        ends = np.flatnonzero(np.append(ids[1:] != ids[:-1], True)) + 1
        for start, end in zip([0, *ends[:-1]], ends, strict=True):
            if end - start > 1:
                at = np.ix_(owner[start:end], owner[start:end])
                runs[at] += 1
                if ids[start] < bucket:
                    first[at] = False
        self.runs = runs
        wanted = np.triu(first, 1)
        block = rows.column("block")[0].as_py()
        if chunks > 1 and block // chunks != block % chunks:
            chunk = rows.column("chunk").to_numpy()
            wanted &= chunk[:, None] != chunk[None, :]
        # Sets whose sizes differ too much can't be similar enough.
        size = np.maximum(self.n, 1)
        wanted &= np.minimum(size[:, None], size[None, :]) >= least * np.maximum(size[:, None], size[None, :])
        a, b = np.nonzero(wanted)
        keep = []
        for i in range(0, len(a), 65536):
            equal = (signature[a[i : i + 65536]] == signature[b[i : i + 65536]]).mean(1)
            keep.append(equal >= least - MARGIN)
        kept = np.concatenate(keep) if keep else np.empty(0, bool)
        self.a, self.b = a[kept], b[kept]


def suspects(members: DataFrame, least: float) -> DataFrame:
    """bucket, block, node: who has a partner that the signatures don't rule out."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _by_bucket(batches):
            found = Bucket(rows, least)
            at = np.unique(np.concatenate([found.a, found.b]))
            if len(at):
                names = ["bucket", "block", "node"]
                yield pa.RecordBatch.from_arrays([rows.column(c).combine_chunks().take(pa.array(at)) for c in names], names=names)

    return members.mapInArrow(compare, "bucket long, block int, node long")


LINKS = "node long, root long, n_links long, met_once long, met_twice long, met long"


def verified(members: DataFrame, least: float) -> DataFrame:
    """node, root, n_links of each bucket's nodes, by exact similarity; how many links were met in one run, in two, in any."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in _by_bucket(batches):
            found = Bucket(rows, least)
            inside = intersections(rows.column("tokens").combine_chunks(), found.a, found.b)
            union = found.n[found.a] + found.n[found.b] - inside
            linked = inside >= least * union - 1e-9
            a, b = found.a[linked], found.b[linked]
            if not len(a):
                continue
            copies = rows.column("copies").to_numpy()
            n = len(copies)
            n_links = np.bincount(a, copies[b], n) + np.bincount(b, copies[a], n)
            times = found.runs[a, b]
            once, twice = np.bincount(a[times == 1], minlength=n), np.bincount(a[times == 2], minlength=n)
            met, root = np.bincount(a, minlength=n), forest(n, a, b)
            at = np.unique(np.concatenate([a, b]))
            columns = [found.node[at], found.node[root[at]], n_links[at].astype(np.int64), once[at], twice[at], met[at]]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=[x.split()[0] for x in LINKS.split(", ")])

    return members.mapInArrow(compare, LINKS)


def intersections(tokens: pa.Array, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of sets a[i] and b[i]; a is sorted."""
    lengths = tokens.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    values, code = np.unique(tokens.flatten().to_numpy(zero_copy_only=False), return_inverse=True)
    code = code.astype(np.int32)
    start = np.concatenate([[0], np.cumsum(lengths)])
    out = np.zeros(len(a), np.int64)
    mark = np.zeros(len(values) + 1, bool)
    edges = np.flatnonzero(np.append(True, a[1:] != a[:-1])) if len(a) else np.empty(0, np.int64)
    for i, j in zip(edges, [*edges[1:], len(a)], strict=True):
        mine = code[start[a[i]] : start[a[i] + 1]]
        mark[mine] = True
        for k in range(i, j, 512):  # bounds what is gathered at once
            others = b[k : min(k + 512, j)]
            size = lengths[others]
            flat = np.repeat(start[others] - np.cumsum(size) + size, size) + np.arange(size.sum())
            hits = np.concatenate([[0], np.cumsum(mark[code[flat]])])
            ends = np.cumsum(size)
            out[k : k + len(others)] = hits[ends] - hits[ends - size]
        mark[mine] = False
    return out


def forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least member of each one's connected component."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def sets_of(docs: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """node and tokens for the wanted nodes, each from the one document that stands for it."""

    def shingle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(words)
        for batch in batches:
            sets = [shingler.set_of(t.as_py() or "").view(np.int64) for t in batch.column(1)]
            offsets = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
            flat = np.concatenate(sets) if sets else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], names=["node", "tokens"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_key(docs), "text")
    one = texts.join(wanted, (texts["doc_id"].eqNullSafe(wanted["rep_id"])) & (texts["text_key"] == wanted["rep_key"]))
    return one.groupBy("node").agg(F.min("text").alias("text")).select("node", "text").mapInArrow(shingle, "node long, tokens array<long>")


def components(edges: DataFrame) -> DataFrame:
    """node and its component's least node, from (node, root) edges, by alternating stars."""
    both = lambda e: e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    current = written(edges.select(F.col("node").alias("u"), F.col("root").alias("v")).where("u != v").distinct(), "edges")
    while True:
        # Large star: neighbours above a node move to the least node around it.
        around = both(current)
        least = around.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = around.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        # Small star: a node and its neighbours below move to the least of them.
        low = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u != v")
        least = low.groupBy("u").agg(F.min("v").alias("m"))
        small = low.join(least, "u").select(F.explode(F.array(F.col("u"), F.col("v"))).alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        following = written(small, "edges")
        same = following.count() == current.count() and not following.exceptAll(current).take(1)
        forget(current)
        current = following
        if same:
            return current.select(F.col("u").alias("node"), F.col("v").alias("root"))


def links(docs: DataFrame, least: float = 0.8, words: int = 5, recall: float = RECALL) -> DataFrame:
    """A row for each document: doc_id, text_key, class_id (least id of its group), n_links, n_copies, node, group, rep_key, rep_rows."""
    base = written(signed(docs, words), "signatures")
    rep = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_key")).alias("rep")
    nodes = base.groupBy("node", "n").agg(rep, F.count("*").alias("copies"), F.first("signature").alias("signature"))
    nodes = written(nodes.select("node", "n", "copies", F.col("rep.doc_id").alias("rep_id"), F.col("rep.text_key").alias("rep_key"), "signature"), "nodes")
    runs = RUNS
    for attempt in range(DOUBLINGS + 2):
        exact = attempt > DOUBLINGS
        buckets = prefixes(docs, nodes, least, words) if exact else paths(nodes, runs)
        of_node = buckets.groupBy("node").agg(F.collect_set("bucket").alias("buckets"))
        carried = of_node.join(nodes, "node").select("node", "n", "copies", "signature", "buckets")
        seen = buckets.drop("run").distinct().join(carried, "node")
        near = written(suspects(_dealt(seen), least), "suspects")
        wanted = near.select("node").distinct().join(nodes.select("node", "rep_id", "rep_key"), "node")
        sets = sets_of(docs, wanted, words)
        again = near.join(buckets.drop("run").distinct(), ["node", "bucket", "block"]).join(carried.join(sets, "node"), "node")
        linked = written(verified(_dealt(again), least), "links")
        forget(near)
        forget(buckets)
        once, twice, met = linked.agg(F.sum("met_once"), F.sum("met_twice"), F.sum("met")).first()
        missed = once**2 / (2 * twice + 2) if met else 0
        if exact or (not met and recall <= 1) or met / (met + missed) >= recall:
            break
        forget(linked)
        runs *= 2
    grouped = components(linked)
    counts = linked.groupBy("node").agg(F.sum("n_links").alias("n_links"))
    known = nodes.drop("signature", "n").join(counts, "node", "left").join(grouped, "node", "left").withColumn("group", F.coalesce("root", "node"))
    known = written(known.drop("root"), "known")
    best = known.groupBy("group").agg(F.min(F.struct(F.col("rep_id").isNull().alias("no_id"), "rep_id", "rep_key")).alias("best"))
    known = known.join(best, "group").select(
        "node", "group", "copies", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.col("best.rep_id").alias("class_id"), F.col("best.rep_key").alias("class_key")
    )
    return base.select("doc_id", "text_key", "node").join(known, "node").select(
        "doc_id", "class_id", (F.col("n_links") + F.col("copies") - 1).alias("n_links"), F.col("copies").alias("n_copies"), "text_key", "class_key", "group"
    )


def _dealt(rows: DataFrame) -> DataFrame:
    return rows.repartition("bucket", "block").sortWithinPartitions("bucket", "block", "node")


def keep_one(docs: DataFrame, least: float = 0.8, words: int = 5) -> DataFrame:
    """The rows of ``docs`` without near copies: of each group the one with the least id (then text hash) stays."""
    found = written(links(docs, least, words), "found")
    stays = F.col("doc_id").eqNullSafe(F.col("class_id")) & (F.col("text_key") == F.col("class_key"))
    # Rows that look just like the one that stays, ids included, are told apart by numbers among them only.
    twins = found.where(stays).groupBy("doc_id", "text_key").count().where("count > 1").select("doc_id", "text_key")
    goes = found.where(~stays).select("doc_id", "text_key").distinct()
    columns = docs.columns
    keyed = docs.withColumn("_rc_key", F.xxhash64(F.coalesce(docs["text"], F.lit(""))))
    same = lambda t: keyed["doc_id"].eqNullSafe(t["doc_id"]) & (keyed["_rc_key"] == t["text_key"])
    if not twins.take(1):
        return keyed.join(goes, same(goes), "left_anti").select(*columns)
    either = goes.union(twins)
    rest = keyed.join(either, same(either), "left_anti").select(*columns)
    one = keyed.join(twins, same(twins), "left_semi").dropDuplicates(["doc_id", "_rc_key"]).select(*columns)
    return rest.unionByName(one)
