"""Mixing sources to target weights, by blocks that are joined by index.

1. Each source's texts, in a fixed order, are one stream of words, cut into
   blocks of ``BLOCK`` words; only a stream's last block may be shorter.
2. Targets: all sources share ``volume`` times the corpus by weight; a target
   stops at ``most_repeats`` times its source, the excess is shared again by
   weight among the others until none is above.
3. The mix is written in shards. How many slots of a shard each source gets is
   drawn from a multinomial distribution over what the sources still have to
   give, so that the totals end at the targets, however the draws fall.
4. A source's n-th slot takes block p(n mod blocks) of its stream, p being a
   pseudorandom permutation of the source's own: a Feistel network over
   the block index with rejection by walking. No block is drawn again before
   all have been drawn, and none more often than ``most_repeats`` times. The last
   slot of a source takes no more words of its block than the target lacks, so
   the words taken are the target's whole words.
5. Slots and blocks are joined by (source, block index).

Words before a document in its stream come from sums per (source, salt) and
running sums inside these, so a source with a third of all rows is spread over
many tasks. The list of sources (name, size) is the only thing the driver gets;
``MOST_SOURCES`` bounds it.

Cases: a null text has no words; a null source is a source, the last in order;
a null id stays null; repeated rows are separate documents with counts and
stretches of their own; ties of the order within a source go by id, then text
hash; very long texts span blocks and are never cut short; an empty table gives
no rows; other columns are left out by ``taken_words`` and kept by
``mixed_documents``, but for names that begin with ``_rc_``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rangecut.llm.shared import WORD, written

BLOCK = 256
#: A shard has at least so many slots; beyond ``MOST_SHARDS`` shards grow instead, so the driver's list of draws is bounded.
SLOTS_A_SHARD, MOST_SHARDS = 4096, 50_000
MOST_SOURCES = 1_000_000
#: Documents of one source and salt that one task sums up, about.
SUMMED_AT_ONCE = 10_000
SEED = 20_24


@dataclass(frozen=True)
class Source:
    number: int
    name: str | None
    size: int
    target: float
    blocks: int
    slots: int
    #: Words that the last slot takes of its block.
    last: int


def size_of(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def code_points(name: str | None) -> tuple[bool, list[int]]:
    return name is None, [ord(c) for c in name or ""]


def targets_of(sizes: Sequence[int], weights: Sequence[float], volume: float, most_repeats: float) -> list[float]:
    """``volume`` words shared by weight, none above ``most_repeats`` times its source's size."""
    target = [0.0] * len(sizes)
    open_, left = [i for i in range(len(sizes))], float(volume)
    while open_:
        total = sum(weights[i] for i in open_)
        above = [i for i in open_ if left * weights[i] / total > most_repeats * sizes[i]]
        if not above:
            for i in open_:
                target[i] = left * weights[i] / total
            break
        for i in above:
            target[i] = float(most_repeats * sizes[i])
        left -= sum(target[i] for i in above)
        open_ = [i for i in open_ if i not in set(above)]
    return target


def sources_of(sized: DataFrame, weights: Sequence[float], volume_share: float, most_repeats: float, seed: int = SEED) -> list[Source]:
    rows = sized.groupBy("source").agg(F.sum("size").alias("size")).limit(MOST_SOURCES + 1).collect()
    if len(rows) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    rows.sort(key=lambda r: code_points(r.source))
    sizes = [r["size"] for r in rows]
    targets = targets_of(sizes, [weights[i % len(weights)] for i in range(len(rows))], volume_share * sum(sizes), most_repeats)
    found = []
    for i, (row, target) in enumerate(zip(rows, targets, strict=True)):
        found.append(Source(i, row.source, row["size"], target, -(-row["size"] // BLOCK), *slots_for(i, row["size"], target, seed)))
    return found


def slots_for(number: int, size: int, target: float, seed: int) -> tuple[int, int]:
    """How many slots reach the target's whole words, and how many words the last one takes of its block."""
    words, blocks = int(target), -(-size // BLOCK)
    if not words:
        return 0, 0
    turns, rest = divmod(words, size)
    if not rest:
        return turns * blocks, BLOCK  # the short block is short by itself
    short = size - (blocks - 1) * BLOCK
    at = int(unpermuted(np.array([blocks - 1]), np.array([blocks]), np.array([number + 1_000_003 * seed]))[0])
    k = -(-rest // BLOCK)
    if at < k and k * BLOCK - (BLOCK - short) < rest:
        k += 1
    before = (k - 1) * BLOCK - (BLOCK - short if at < k - 1 else 0)
    return turns * blocks + k, rest - before


def draw_shards(slots: Sequence[int], a_shard: int, seed: int) -> Iterator[np.ndarray]:
    """For each shard, how many slots each source gets: multinomial over what is left, never more than that."""
    rng = np.random.default_rng(seed)
    left = np.array(slots, np.int64)
    while left.sum() > 0:
        want = int(min(a_shard, left.sum()))
        drawn = np.zeros_like(left)
        while want:
            rest = left - drawn
            drawn += np.minimum(rng.multinomial(want, rest / rest.sum()), rest)
            want = int(min(a_shard, left.sum()) - drawn.sum())
        left -= drawn
        yield drawn


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def _feistel(index: np.ndarray, n: np.ndarray, key: np.ndarray, turns: Sequence[int]) -> np.ndarray:
    """Feistel rounds on the smallest even number of bits, walked until inside 0..n-1; ``turns`` backwards undo them."""
    bits = np.maximum(1, (np.ceil(np.log2(np.maximum(n, 2).astype(np.float64))) + 1) // 2).astype(np.uint64)
    mask = (np.uint64(1) << bits) - np.uint64(1)
    out = index.astype(np.uint64)
    key = key.astype(np.uint64)
    going = np.ones(len(out), bool)
    with np.errstate(over="ignore"):
        while going.any():
            at = np.flatnonzero(going)
            left, right = out[at] >> bits[at], out[at] & mask[at]
            for turn in turns:
                f = lambda half: _mix(half + (key[at] * np.uint64(4) + np.uint64(turn + 1)) * np.uint64(0x9E3779B97F4A7C15)) & mask[at]  # noqa: B023, E731
                left, right = (right, left ^ f(right)) if turns[0] == 0 else (right ^ f(left), left)
            out[at] = (left << bits[at]) | right
            going[at] = out[at] >= n[at].astype(np.uint64)
    return out.astype(np.int64)


def permuted(index: np.ndarray, n: np.ndarray, key: np.ndarray) -> np.ndarray:
    """A permutation of 0..n-1 for each key."""
    return _feistel(index, n, key, (0, 1, 2, 3))


def unpermuted(index: np.ndarray, n: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Where ``permuted`` has put each index."""
    return _feistel(index, n, key, (3, 2, 1, 0))


SLOTS = "shard long, slot int, number int, block_index long, turn int, most int"


def slots_of(spark, sources: list[Source], seed: int) -> DataFrame:
    """The mix as slots: shard, slot, source number, block index, how often the block was taken before, and its words at most. A shard's slots are spread by a permutation of their own."""
    taken = np.zeros(len(sources), np.int64)
    shards = []
    a_shard = max(SLOTS_A_SHARD, -(-sum(s.slots for s in sources) // MOST_SHARDS))
    for shard, drawn in enumerate(draw_shards([s.slots for s in sources], a_shard, seed)):
        at = np.flatnonzero(drawn)
        shards.append((shard, at.tolist(), drawn[at].tolist(), taken[at].tolist()))
        taken += drawn
    drawn_rows = spark.createDataFrame(shards, "shard long, numbers array<int>, counts array<int>, begins array<long>")
    blocks, slots, last = (np.array([getattr(s, c) for s in sources], np.int64) for c in ("blocks", "slots", "last"))

    def fill(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for row in part.itertuples(index=False):
                counts = np.asarray(row.counts, np.int64)
                number = np.repeat(np.asarray(row.numbers, np.int64), counts)
                before = np.repeat(np.cumsum(counts) - counts, counts)
                nth = np.arange(len(number)) - before + np.repeat(np.asarray(row.begins, np.int64), counts)
                n = blocks[number]
                shard = np.full(len(number), row.shard)
                slot = permuted(np.arange(len(number)), np.full(len(number), len(number)), shard + 1_000_003 * (seed + 1))
                yield pd.DataFrame({"shard": shard, "slot": slot.astype("int32"), "number": number.astype("int32"), "block_index": permuted(nth % n, n, number + 1_000_003 * seed), "turn": (nth // n).astype("int32"), "most": np.where(nth == slots[number] - 1, last[number], BLOCK).astype("int32")})

    return drawn_rows.repartition(max(1, min(len(shards), 4096))).mapInPandas(fill, SLOTS)


def streamed(sized: DataFrame, sources: list[Source]) -> DataFrame:
    """Adds each document's source number and first word's place in its source's stream."""
    spark = sized.sparkSession
    names = spark.createDataFrame([(s.number, s.name, s.size, float(s.target)) for s in sources], "number int, source string, source_size long, target double")
    total = sized.count()
    salts = max(1, -(-total // SUMMED_AT_ONCE))
    names = names.withColumnRenamed("source", "_name")
    numbered = sized.join(F.broadcast(names), sized["source"].eqNullSafe(names["_name"])).drop("_name")  # at most MOST_SOURCES rows
    salted = numbered.withColumn("_salt", F.pmod(F.xxhash64("doc_id", "text_key"), F.lit(salts)))
    sums = salted.groupBy("number", "_salt").agg(F.sum("size").alias("words"))
    before = sums.select("number", "_salt", (F.sum("words").over(Window.partitionBy("number").orderBy("_salt")) - F.col("words")).alias("_before"))
    inside = F.sum("size").over(Window.partitionBy("number", "_salt").orderBy("doc_id", "text_key").rowsBetween(Window.unboundedPreceding, 0)) - F.col("size")
    return salted.withColumn("_inside", inside).join(before, ["number", "_salt"]).withColumn("first_word", F.col("_inside") + F.col("_before")).drop("_salt", "_inside", "_before")


def block_pieces(stream: DataFrame) -> DataFrame:
    """A row for each block that a document has words in: block_index, from_word (within the document), n_words."""
    last = F.col("first_word") + F.col("size") - 1
    exploded = stream.where("size > 0").withColumn("block_index", F.explode(F.sequence(F.floor(F.col("first_word") / F.lit(BLOCK)), F.floor(last / F.lit(BLOCK)))))
    begin = F.greatest(F.col("first_word"), F.col("block_index") * BLOCK)
    end = F.least(F.col("first_word") + F.col("size"), (F.col("block_index") + 1) * BLOCK)
    return exploded.withColumn("from_word", begin - F.col("first_word")).withColumn("n_words", end - begin)


def mix(docs: DataFrame, weights: Sequence[float], volume_share: float, most_repeats: int, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """The mix and the documents' streams.

    The mix has a row for each piece of a document in a slot: shard, slot,
    number, block_index, doc_id, from_word, n_words; in the order of (shard,
    slot, first_word) the words are the training text.
    """
    spark = docs.sparkSession
    key = F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_key")
    sized = written(docs.select("doc_id", "source", key, size_of(F.col("text")).alias("size")), "sizes")
    sources = sources_of(sized, weights, volume_share, most_repeats, seed)
    stream = streamed(sized, sources)
    # Slots grow with the corpus, which the planner can't see through the function that fills them: no broadcast.
    mixed = slots_of(spark, sources, seed).hint("merge").join(block_pieces(stream), ["number", "block_index"])
    # The part of the piece that the slot still takes.
    left = F.col("block_index") * BLOCK + F.col("most") - (F.col("first_word") + F.col("from_word"))
    return mixed.withColumn("n_words", F.least("n_words", left)).where("n_words > 0").drop("most"), stream


def taken_words(docs: DataFrame, weights: Sequence[float], volume_share: float, most_repeats: int, seed: int = SEED) -> DataFrame:
    """doc_id, size, source_size, target and taken for every document."""
    mixed, stream = mix(docs, weights, volume_share, most_repeats, seed)
    columns = ["doc_id", "size", "source_size", "target"]
    used = mixed.groupBy("number", "first_word", *columns).agg(F.sum("n_words").alias("taken"))
    # Documents with words have a first word of their own, so this brings back those that no slot drew.
    whole = stream.select("number", "first_word", *columns, F.lit(0).cast("long").alias("taken"))
    with_words = whole.where("size > 0").unionByName(used).groupBy("number", "first_word", *columns).agg(F.sum("taken").alias("taken"))
    return with_words.select(*columns, "taken").unionByName(whole.where("size = 0").select(*columns, "taken"))


_WORD = re.compile(WORD)


def cut_out(text: str, pieces: list[tuple[int, int]]) -> list[str]:
    """The text's stretches that hold these words (from, how many), adjoining pieces in one; the whole text as it is."""
    runs: list[list[int]] = []
    for start, n in sorted(pieces):
        if runs and runs[-1][1] == start:
            runs[-1][1] += n
        else:
            runs.append([start, start + n])
    words = [m.span() for m in _WORD.finditer(text)]
    return [text if (i, j) == (0, len(words)) else text[words[i][0] : words[j - 1][1]] for i, j in runs]


def mixed_documents(docs: DataFrame, weights: Sequence[float], volume_share: float, most_repeats: int, seed: int = SEED) -> DataFrame:
    """The mix as documents, with the columns of ``docs``: a row for each stretch of a text that is taken, as often as it is.

    ``n_chars``, where there is one, is the stretch's. Documents without words
    have nothing to take.
    """
    mixed, stream = mix(docs, weights, volume_share, most_repeats, seed)
    one = F.struct("number", "first_word", "turn", "from_word", "n_words")
    same = ["doc_id", "text_key", "source"]
    lists = mixed.groupBy(*same, "first_word").agg(F.collect_list(one).alias("_rc_pieces"))
    keyed = docs.withColumn("_rc_key", F.xxhash64(F.coalesce(docs["text"], F.lit(""))))
    nth = F.lit(1)
    if stream.groupBy(*same).count().where("count > 1").take(1):
        # Rows with the same id, text and source have places of their own in the stream: the n-th row takes the n-th place.
        number = F.row_number().over(Window.partitionBy(*same).orderBy("first_word"))
        lists = lists.join(stream.where("size > 0").select(*same, "first_word", number.alias("_rc_nth")).withColumnRenamed("source", "_s").withColumnRenamed("doc_id", "_d").withColumnRenamed("text_key", "_t"), "first_word", "inner").where(
            F.col("source").eqNullSafe(F.col("_s")) & F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("text_key") == F.col("_t"))
        )
        nth = F.row_number().over(Window.partitionBy("doc_id", "_rc_key", "source").orderBy(F.xxhash64(*docs.columns)))
    else:
        lists = lists.withColumn("_rc_nth", F.lit(1))
    lists = lists.select(F.col("doc_id").alias("_rc_id"), F.col("text_key").alias("_rc_text"), F.col("source").alias("_rc_source"), "_rc_nth", "_rc_pieces")
    keyed = keyed.withColumn("_rc_own", nth)

    @F.pandas_udf("array<string>")
    def stretches(text: pd.Series, pieces: pd.Series) -> pd.Series:
        out = []
        for t, listed in zip(text, pieces, strict=True):
            turns: dict[tuple, list[tuple[int, int]]] = {}
            for p in listed:
                turns.setdefault((p["number"], p["first_word"], p["turn"]), []).append((p["from_word"], p["n_words"]))
            out.append([s for turn in sorted(turns) for s in cut_out(t or "", turns[turn])])
        return pd.Series(out, dtype=object)

    mine = keyed["doc_id"].eqNullSafe(lists["_rc_id"]) & (keyed["_rc_key"] == lists["_rc_text"]) & keyed["source"].eqNullSafe(lists["_rc_source"])
    joined = keyed.join(lists, mine & (keyed["_rc_own"] == lists["_rc_nth"]))
    out = joined.withColumn("_rc_out", F.explode(stretches("text", "_rc_pieces")))
    new = {"text": F.col("_rc_out"), "n_chars": F.length("_rc_out").cast("long")}
    return out.select(*(new[c].alias(c) if c in new else F.col(c) for c in docs.columns))
