"""Exact frequent itemset mining.

Level-wise counting works on bit columns: for blocks of transactions, a bit of
each for every item of a pool.  Sets of a level that begin alike are counted
together, by the bits that their columns share, and a task sends its sums.  The
pool of a top-k has at most k items and a level at most CANDIDATES sets at a
time, so what is broadcast or collected doesn't grow with the data; listings
below a threshold are bounded by MOST_ITEMS and MOST_SETS and refuse beyond.
Where the sets stay in Spark (Sets), only items and pairs are so bounded: those
of three items or more are counted pair by pair of first items, by tasks that
have the transactions with both.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations, groupby

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.transactions import Transactions

Itemset = tuple[str, ...]

#: Candidates that are broadcast at a time, and sums of a row that a task sends.
CANDIDATES, SUMS = 1 << 20, 1 << 12
#: Transactions of a block of bit columns, and most bytes of one.
BLOCK_ROWS, BLOCK_BYTES = 1 << 14, 4 << 20
#: Frequent items and sets that a listing on the driver may have.
MOST_ITEMS, MOST_SETS = 20_000, 2_000_000
#: Sets of a block that stays in Spark, and bytes of bit columns that a pair's task makes at a time.
BLOCK_SETS, STEP_BYTES = 1 << 16, 1 << 20
#: Bits of the number of a bucket, into which sets of one size are dealt to be compared.
BUCKET_BITS = 7
#: Bits of a mask column.
BITS = 62

TOPK_SCHEMA = "rank int, itemset string, size int, support long, freq double"


class TooManySets(ValueError):
    """A listing that isn't bounded by k would outgrow the driver."""


def key_of(items: Itemset) -> str:
    return "|".join(sorted(items))


@dataclass(frozen=True, slots=True)
class Found:
    items: Itemset
    support: int

    @property
    def order(self) -> tuple:
        """Support first, then fewer items, then the key."""
        return (-self.support, len(self.items), key_of(self.items))


@dataclass(frozen=True, slots=True)
class Sets:
    """Any number of sets, which stay in Spark.

    blocks: (size int, sets binary, supports binary), a row of ascending places in the pool for each set.
    """

    blocks: DataFrame
    pool: list[str]

    @property
    def kind(self) -> np.dtype:
        """Of a place."""
        return _kind(self.pool)

    def frame(self) -> DataFrame:
        """(itemset, size, support)."""
        names, kind = sorted(self.pool), self.kind
        rank = {name: k for k, name in enumerate(names)}
        ranks, texts = np.array([rank[name] for name in self.pool], np.int32), pa.array(names, pa.string())

        def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for size, sets, n in _blocks(batches, kind):
                ordered = np.sort(ranks[sets], axis=1)
                items = pa.ListArray.from_arrays(np.arange(0, ordered.size + 1, size, np.int32), texts.take(pa.array(ordered.ravel())))
                yield pa.RecordBatch.from_arrays([pc.binary_join(items, "|"), pa.array(np.full(len(sets), size, np.int32)), pa.array(n)], ["itemset", "size", "support"])

        return self.blocks.mapInArrow(named, "itemset string, size int, support long")


SETS_SCHEMA = "size int, sets binary, supports binary"


def _kind(pool: list[str]) -> np.dtype:
    return np.min_scalar_type(max(len(pool) - 1, 0))


def _block(sets: np.ndarray, supports: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([sets.shape[1]], pa.int32()), pa.array([sets.tobytes()], pa.binary()), pa.array([supports.astype(np.int64).tobytes()], pa.binary())], ["size", "sets", "supports"])


def _blocks(batches: Iterator[pa.RecordBatch], kind: np.dtype) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(size, sets, supports) of each block."""
    for batch in batches:
        for size, sets, n in zip(batch.column("size").to_pylist(), batch.column("sets"), batch.column("supports"), strict=True):
            yield size, np.frombuffer(sets.as_buffer(), kind).reshape(-1, size), np.frombuffer(n.as_buffer(), np.int64)


def mask_columns(items: Column, size: int) -> list[Column]:
    """Longs with a bit for each place in an array of places."""

    def word(w: int) -> Column:
        own = F.filter(items, lambda x: F.floor(x / BITS) == w)
        bit = lambda x: F.call_function("shiftleft", F.lit(1).cast("long"), x - F.lit(w * BITS))
        return F.aggregate(own, F.lit(0).cast("long"), lambda mask, x: mask.bitwiseOR(bit(x)))

    return [word(w).alias(f"m{w}") for w in range(max(1, -(-size // BITS)))]


class Projection:
    """Transactions over a pool of items, kept as bit columns."""

    def __init__(self, tx: Transactions, pool: list[str]):
        self.pool, self.spark = pool, tx.spark
        blocks = tx.rows.select("items").mapInArrow(lambda batches: _bit_columns(batches, pool), "words int, bits binary")
        self.tasks = tx.spark.sparkContext.defaultParallelism
        self.blocks = blocks.repartition(self.tasks).persist()

    def close(self) -> None:
        self.blocks.unpersist()

    def pairs(self, above: int) -> dict[tuple[int, int], int]:
        """Supports of pairs of places that exceed ``above``."""
        out: dict[tuple[int, int], int] = {}
        waiting, size = [], 0
        for a in range(len(self.pool) - 1):
            waiting.append(((a,), range(a + 1, len(self.pool))))
            size += len(self.pool) - 1 - a
            if size >= CANDIDATES or a == len(self.pool) - 2:
                out |= self._counted(waiting, above)
                waiting, size = [], 0
                if len(out) > MOST_SETS:
                    raise TooManySets(f"more than {MOST_SETS} pairs have a support above {above}")
        return out

    def count(self, sets: list[tuple[int, ...]], above: int = 0) -> dict[tuple[int, ...], int]:
        """Supports of sorted sets of places that exceed ``above``."""
        out: dict[tuple[int, ...], int] = {}
        ordered = sorted(set(sets), key=lambda s: (len(s), s))
        for start in range(0, len(ordered), CANDIDATES):
            part = ordered[start : start + CANDIDATES]
            for _, same in groupby(part, len):
                out |= self._counted([(head, [s[-1] for s in group]) for head, group in groupby(same, lambda s: s[:-1])], above)
        return out

    def _counted(self, groups: list[tuple[tuple[int, ...], list[int] | range]], above: int) -> dict[tuple[int, ...], int]:
        """Supports above a bound; groups: the sorted heads of sets of one size, and the last places of each."""
        heads = np.array([h for h, _ in groups], np.int32).reshape(len(groups), -1)
        ends = np.cumsum([len(last) for _, last in groups])
        lasts = np.concatenate([np.asarray(last, np.int32) for _, last in groups])
        sent = self.spark.sparkContext.broadcast((heads, ends, lasts))

        def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            heads, ends, lasts = sent.value
            total = _tally(batches, heads, ends, lasts)
            for k in range(0, lasts.size if total is not None else 0, SUMS):
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([total[k : k + SUMS].tobytes()], pa.binary())], ["start", "n"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for batch in batches:
                for k, n in zip(batch.column("start").to_pylist(), batch.column("n").to_pylist(), strict=True):
                    own = np.frombuffer(n, np.int64)
                    sums[k] = sums[k] + own if k in sums else own
            for k, n in sums.items():
                at = np.flatnonzero(n > above)
                yield pa.RecordBatch.from_arrays([pa.array((at + k).astype(np.int32)), pa.array(n[at])], ["id", "n"])

        rows = self.blocks.mapInArrow(tally, "start int, n binary").repartition(self.tasks, "start").mapInArrow(add, "id int, n long").toArrow()
        sent.unpersist()
        ids, counts = rows.column("id").to_numpy(), rows.column("n").to_numpy()
        whose = np.searchsorted(ends, ids, "right")
        return {(*groups[g][0], last): n for g, last, n in zip(whose.tolist(), lasts[ids].tolist(), counts.tolist(), strict=True)}


def _bit_columns(batches: Iterator[pa.RecordBatch], pool: list[str]) -> Iterator[pa.RecordBatch]:
    """(words, bits): a block of transactions as 64-bit words for each item of the pool; those without any such item are left out."""
    names = pa.array(pool, pa.string())
    most = max(64, min(BLOCK_ROWS, BLOCK_BYTES * 8 // max(len(pool), 1)) // 64 * 64)
    grid, filled = np.zeros((len(pool), most), bool), 0

    def block() -> pa.RecordBatch:
        words = -(-filled // 64)
        bits = np.packbits(grid[:, : words * 64], axis=1, bitorder="little")
        return pa.RecordBatch.from_arrays([pa.array([words], pa.int32()), pa.array([bits.tobytes()], pa.binary())], ["words", "bits"])

    for batch in batches:
        items = batch.column(0)
        place = pc.index_in(items.flatten(), value_set=names)
        found = pc.is_valid(place).to_numpy(zero_copy_only=False)
        own, row = np.unique(pc.list_parent_indices(items).to_numpy()[found], return_inverse=True)
        column, at = place.drop_null().to_numpy(), 0
        while at < own.size:
            take = min(own.size - at, most - filled)
            inside = (row >= at) & (row < at + take)
            grid[column[inside], row[inside] - at + filled] = True
            at, filled = at + take, filled + take
            if filled == most:
                yield block()
                grid[:], filled = False, 0
    if filled:
        yield block()


def _tally(batches: Iterator[pa.RecordBatch], heads: np.ndarray, ends: np.ndarray, lasts: np.ndarray) -> np.ndarray | None:
    """Supports of a task's transactions: of each head with each of its last places."""
    depth, total = heads.shape[1], None
    keep = np.zeros(len(heads), np.int64)  # how many places a head has in common with the one before
    if depth:
        keep[1:] = np.cumprod(heads[1:] == heads[:-1], axis=1).sum(axis=1)
    plan = list(zip(heads.tolist(), keep.tolist(), np.r_[0, ends[:-1]].tolist(), ends.tolist(), strict=True))
    for grid in _joined(batches):
        total = np.zeros(lasts.size, np.int64) if total is None else total
        shared: list[np.ndarray] = []
        for head, same, start, end in plan:
            del shared[same:]
            for x in head[len(shared) :]:
                shared.append(grid[x] & shared[-1] if shared else grid[x])
            held = grid[lasts[start:end]]
            if depth:
                held &= shared[-1]
            total[start:end] += np.bitwise_count(held).sum(axis=1, dtype=np.int64)
    return total


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[np.ndarray]:
    """Blocks side by side, while they stay small: (places, words)."""
    waiting, size = [], 0
    for batch in batches:
        for words, bits in zip(batch.column("words").to_pylist(), batch.column("bits"), strict=True):
            waiting.append(np.frombuffer(bits.as_buffer(), np.uint64).reshape(-1, words))
            size += waiting[-1].nbytes
            if size >= BLOCK_BYTES:
                yield np.concatenate(waiting, axis=1)
                waiting, size = [], 0
    if waiting:
        yield np.concatenate(waiting, axis=1)


def extended(sets: list[tuple[int, ...]]) -> list[tuple[int, ...]]:
    """Sets one larger all of whose subsets are among the sorted ``sets``."""
    known, by_prefix, out = set(sets), {}, []
    for s in sorted(sets):
        by_prefix.setdefault(s[:-1], []).append(s[-1])
    for prefix, last in by_prefix.items():
        for a, b in combinations(last, 2):
            new = (*prefix, a, b)
            if all(new[:k] + new[k + 1 :] in known for k in range(len(new) - 2)):
                out.append(new)
    return out


def numbered(counts: DataFrame, number: str = "item_id") -> DataFrame:
    """``counts`` (item, n) with the item's number by descending support, then name, from 1.

    Numbers of equal supports are given inside a window of their own, from where
    the higher ones end; only the distinct supports reach the driver.
    """
    rows, start = [], 0
    for r in sorted(counts.groupBy("n").agg(F.count("*").alias("m")).collect(), key=lambda r: -r["n"]):
        rows.append((r["n"], start))
        start += r["m"]
    starts = counts.sparkSession.createDataFrame(rows, "n long, _start long")
    place = F.row_number().over(Window.partitionBy("n").orderBy("item"))
    return counts.join(F.broadcast(starts), "n").select((F.col("_start") + place).cast("int").alias(number), "item", "n")


def top_items(tx: Transactions, k: int) -> list[tuple[str, int]]:
    """The k most frequent items that occur, ties by name."""
    rows = tx.item_counts().where("n > 0").orderBy(F.desc("n"), "item").limit(k).collect()
    return [(r["item"], r["n"]) for r in rows]


def topk(tx: Transactions, k: int, max_len: int | None = None) -> list[Found]:
    """The k most frequent itemsets, in order, exactly; made once where the transactions remember."""
    most, found = tx.kept(("topk", max_len), lambda: (k, _topk(tx, k, max_len)))
    if most < k:  # a longer list begins with the shorter one
        most, found = tx.kept_anew(("topk", max_len), (k, _topk(tx, k, max_len)))
    return found[:k]


def _topk(tx: Transactions, k: int, max_len: int | None) -> list[Found]:
    """Level by level under a rising floor.

    The k-th best support so far is a rising floor.  A larger set that only
    ties with it comes later in the order, so only sets strictly above the
    floor are extended.
    """
    held = [Found((i,), n) for i, n in top_items(tx, k)]

    def floor() -> int:
        return held[k - 1].support if len(held) >= k else 0

    pool = [f.items[0] for f in held if f.support > floor()]
    if len(pool) > 1 and max_len != 1:
        projection = Projection(tx, pool)
        try:
            level, size = projection.pairs(floor()), 2
            while level:
                held += [Found(tuple(pool[x] for x in s), n) for s, n in level.items()]
                held = sorted(held, key=lambda f: f.order)[:k]
                size += 1
                alive = [s for s, n in level.items() if n > floor()]
                if max_len is not None and size > max_len or len(alive) < size:
                    break
                level = projection.count(extended(alive), floor())
        finally:
            projection.close()
    return sorted(held, key=lambda f: f.order)[:k]


def apriori(tx: Transactions, min_count: int, max_len: int | None = None, listed: bool = True) -> list[Found] | Sets:
    """All itemsets with a support of ``min_count`` (1 or more) or above, level by level: a list on the driver, or any number of them in Spark."""
    most = MOST_SETS if max_len == 1 else MOST_ITEMS
    items = tx.item_counts().where(F.col("n") >= max(min_count, 1)).orderBy(F.desc("n"), "item").limit(most + 1).collect()
    if len(items) > most:
        raise TooManySets(f"more than {most} items have a support of {min_count}")
    if not listed:
        return _apriori_sets(tx, [(r["item"], r["n"]) for r in reversed(items)], max(min_count, 1), max_len)
    out, pool = [Found((r["item"],), r["n"]) for r in items], [r["item"] for r in items]
    if len(pool) < 2 or max_len == 1:
        return out
    projection = Projection(tx, pool)
    try:
        level, size = projection.pairs(max(min_count, 1) - 1), 2
        while level:
            out += [Found(tuple(pool[x] for x in s), n) for s, n in level.items()]
            if len(out) > MOST_SETS:
                raise TooManySets(f"more than {MOST_SETS} sets have a support of {min_count}")
            size += 1
            if max_len is not None and size > max_len:
                break
            level = projection.count(extended(list(level)), max(min_count, 1) - 1)
    finally:
        projection.close()
    return sorted(out, key=lambda f: f.order)


def _apriori_sets(tx: Transactions, items: list[tuple[str, int]], least: int, max_len: int | None) -> Sets:
    """``apriori`` whose sets stay in Spark; items: the frequent ones, the rarest first, so that those with most sets have the fewest to follow.

    Items and pairs are counted as ever.  Of a frequent pair, a task gets the
    transactions with both, as bit columns of the later items that are frequent
    with each, and counts the pair's larger sets level by level.
    """
    pool, spark = [i for i, _ in items], tx.spark
    kind, levels = _kind(pool), [(np.arange(len(pool)).reshape(-1, 1), np.array([n for _, n in items], np.int64))]
    later: list[np.ndarray] = []
    if len(pool) > 1 and max_len != 1:
        projection = _columns(tx, pool)
        pairs = projection.pairs(least - 1)
        heads = np.array(sorted(pairs), np.int32).reshape(-1, 2)
        levels.append((heads, np.array([pairs[a, b] for a, b in heads.tolist()], np.int64)))
        later = np.split(heads[:, 1], np.searchsorted(heads[:, 0], np.arange(1, len(pool))))
    rows = [(sets.shape[1], bytearray(sets[k : k + BLOCK_SETS].astype(kind).tobytes()), bytearray(n[k : k + BLOCK_SETS].tobytes())) for sets, n in levels for k in range(0, len(sets), BLOCK_SETS)]
    out = spark.createDataFrame(rows, SETS_SCHEMA)
    if any(x.size > 1 for x in later) and max_len != 2:
        sent = spark.sparkContext.broadcast(later)
        tasks = min(len(pairs), 8 * spark.sparkContext.defaultParallelism)
        bits = projection.blocks.mapInArrow(lambda batches: _pair_columns(batches, sent.value), "a int, b int, bits binary")
        dealt = bits.repartition(tasks, "a", "b").sortWithinPartitions("a", "b")
        out = out.unionByName(dealt.mapInArrow(lambda batches: _pair_sets(batches, sent.value, least, max_len, kind), SETS_SCHEMA))
    return Sets(out, pool)


#: By application, the bit columns of the last listing that stays in Spark.
_last: dict[str, Projection] = {}


def _columns(tx: Transactions, pool: list[str]) -> Projection:
    """Bit columns that are kept until the next listing, for sets that are counted when they are read; columns that went are made again."""
    application = tx.spark.sparkContext.applicationId
    if application in _last:
        _last.pop(application).close()
    _last[application] = Projection(tx, pool)
    return _last[application]


def _followers(later: list[np.ndarray], a: int, b: int) -> np.ndarray:
    """Items after b that are frequent with a and with b."""
    return np.intersect1d(later[a], later[b], assume_unique=True)


def _pair_columns(blocks: Iterator[pa.RecordBatch], later: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    """(a, b, bits) of the pairs in a block: the transactions with both, as bytes of bits for each follower."""
    after: dict[tuple[int, int], np.ndarray] = {}
    for block in blocks:
        for words, packed in zip(block.column("words").to_pylist(), block.column("bits"), strict=True):
            grid = np.frombuffer(packed.as_buffer(), np.uint8).reshape(-1, words * 8)
            rows = np.ascontiguousarray(np.unpackbits(grid, axis=1, bitorder="little").T)
            for a, partners in enumerate(later):
                own = rows[rows[:, a] > 0] if partners.size > 1 else rows[:0]
                out: list[tuple[int, bytes]] = []
                for b in partners.tolist() if len(own) else ():
                    if (a, b) not in after:
                        after[a, b] = _followers(later, a, b)
                    if after[a, b].size and (both := np.flatnonzero(own[:, b])).size:
                        out.append((b, np.packbits(own[both[:, None], after[a, b]], axis=0, bitorder="little").T.tobytes()))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array([a] * len(out), pa.int32()), pa.array([b for b, _ in out], pa.int32()), pa.array([x for _, x in out], pa.binary())], ["a", "b", "bits"])


def _pair_sets(batches: Iterator[pa.RecordBatch], later: list[np.ndarray], least: int, max_len: int | None, kind: np.dtype) -> Iterator[pa.RecordBatch]:
    """Blocks of the frequent sets of three items or more, from the bit columns of their pairs, which come one after the other."""
    waiting: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
    held: dict[int, int] = {}
    records = ((ab, bits) for batch in batches for *ab, bits in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("bits"), strict=True))
    for (a, b), own in groupby(records, lambda r: r[0]):
        after = _followers(later, a, b)
        grid = np.concatenate([np.frombuffer(bits.as_buffer(), np.uint8).reshape(after.size, -1) for _, bits in own], axis=1)
        grid = np.pad(grid, ((0, 0), (0, -grid.shape[1] % 8))).view(np.uint64)
        n = np.bitwise_count(grid).sum(axis=1, dtype=np.int64)
        frequent = n >= least
        sets = np.empty((int(frequent.sum()), 3), kind)
        sets[:, 0], sets[:, 1], sets[:, 2] = a, b, after[frequent]
        for level, supports in _grown(sets, n[frequent], grid[frequent], np.full(len(sets), len(sets)), least, max_len):
            size = level.shape[1]
            waiting.setdefault(size, []).append((level, supports))
            held[size] = held.get(size, 0) + len(level)
            if held[size] >= BLOCK_SETS:
                yield _block(*map(np.concatenate, zip(*waiting.pop(size), strict=True)))
                del held[size]
    for found in waiting.values():
        yield _block(*map(np.concatenate, zip(*found, strict=True)))


def _grown(sets: np.ndarray, supports: np.ndarray, bits: np.ndarray, ends: np.ndarray, least: int, max_len: int | None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Given sets of a level and all larger frequent ones; ends: for each set, where those with the same head end.

    A set is joined with each later one that has the same head.  The next level
    is made for as many sets at a time as keep its bit columns small.
    """
    if len(sets):
        yield sets, supports
    if max_len is not None and sets.shape[1] >= max_len:
        return
    joins = ends - np.arange(len(sets)) - 1
    upto, start = np.cumsum(joins), 0
    most = max(1, STEP_BYTES // max(bits.shape[1] * 8, 1))
    while start < len(sets):
        stop = max(start + 1, int(np.searchsorted(upto, (upto[start - 1] if start else 0) + most, "right")))
        own = joins[start:stop]
        left = np.repeat(np.arange(start, stop), own)
        right = left + 1 + np.arange(left.size) - np.repeat(np.cumsum(own) - own, own)
        start = stop
        if not left.size:
            continue
        held = bits[left]
        held &= bits[right]
        n = np.bitwise_count(held).sum(axis=1, dtype=np.int64)
        at = np.flatnonzero(n >= least)
        if at.size:
            head = left[at]
            yield from _grown(np.column_stack([sets[head], sets[right[at], -1]]), n[at], held[at], np.searchsorted(head, head, "right"), least, max_len)


def topk_of_size(tx: Transactions, k: int, size: int) -> list[Found]:
    """The k most frequent sets of exactly ``size`` items: a threshold falls from the k-th item's support until there are k above it."""
    if size == 1:
        return topk(tx, k, 1)
    items = top_items(tx, k + size)
    least = items[-1][1] if items else 0
    while least >= 1:
        found = [f for f in apriori(tx, least, size) if len(f.items) == size]
        if len(found) >= k or least == 1:
            return sorted(found, key=lambda f: f.order)[:k]
        least = max(1, least // 2)
    return []


def fp_growth(tx: Transactions, min_count: int) -> DataFrame:
    """(itemset, size, support) by the distributed pattern-growth of the machine-learning library."""
    n = tx.size()
    model = FPGrowth(itemsCol="items", minSupport=max(min_count - 0.5, 0.5) / max(n, 1)).fit(tx.rows)
    return model.freqItemsets.select(F.array_join(F.sort_array("items"), "|").alias("itemset"), F.size("items").alias("size"), F.col("freq").alias("support"))


def topk_bitmap(tx: Transactions, items: list[str], k: int) -> DataFrame:
    """Top-k among all sets of at most 16 items from one histogram of masks, in SQL expressions alone."""
    if len(items) > 16:
        raise ValueError("at most 16 items")
    masks = tx.projected(items).select(*mask_columns(F.col("items"), len(items)), "cnt").groupBy("m0").agg(F.sum("cnt").alias("cnt"))
    every = tx.spark.range(1, 1 << len(items)).select(F.col("id").alias("c"))
    counted = masks.join(F.broadcast(every), F.col("m0").bitwiseAND(F.col("c")) == F.col("c")).groupBy("c").agg(F.sum("cnt").alias("support"))
    named = counted.select(itemset_of(F.col("c"), items).alias("itemset"), F.bit_count("c").cast("int").alias("size"), "support")
    return named.orderBy(F.desc("support"), "size", "itemset").limit(k)


def itemset_of(mask: Column, items: list[str]) -> Column:
    """Sorted, joined names of a mask's items."""
    names = F.array(*[F.when(mask.bitwiseAND(F.lit(1 << k)) != 0, F.lit(i)) for k, i in enumerate(items)])
    return F.array_join(F.sort_array(F.array_compact(names)), "|")


def supports(tx: Transactions, sets: list[Itemset]) -> dict[Itemset, int]:
    """Exact supports of given sets, in one pass over a projection on their items."""
    pool = sorted({i for s in sets for i in s})
    projection = Projection(tx, pool)
    place = {i: k for k, i in enumerate(pool)}
    try:
        got = projection.count([tuple(sorted(place[i] for i in s)) for s in sets])
    finally:
        projection.close()
    return {s: got.get(tuple(sorted(place[i] for i in s)), 0) for s in sets}


def pair_counts(tx: Transactions, items: list[str]) -> DataFrame:
    """(a, b, n) of all pairs of the items with a < b by name, zero supports included."""
    names = sorted(set(items))
    projection = tx.projected(names)
    both = F.flatten(F.transform("items", lambda x, i: F.transform(F.slice("items", i + 2, F.size("items")), lambda y: F.struct(x.alias("a"), y.alias("b")))))
    counted = projection.where(F.size("items") > 1).select(F.explode(both).alias("p"), "cnt").groupBy("p.a", "p.b").agg(F.sum("cnt").alias("n"))
    # at most C(len(items), 2) rows
    every = tx.spark.createDataFrame([(x, y, names[x], names[y]) for x, y in combinations(range(len(names)), 2)], "a int, b int, left string, right string")
    return every.join(counted, ["a", "b"], "left").select(F.col("left").alias("a"), F.col("right").alias("b"), F.coalesce("n", F.lit(0)).alias("n"))


def maximal(found: list[Found] | Sets) -> list[Found] | Sets:
    """Those that no other found set contains; sets in Spark are as ``apriori`` lists them, with all subsets."""
    if isinstance(found, Sets):
        return _maximal_sets(found)
    sets = {frozenset(f.items) for f in found}
    below = {s - {i} for s in sets for i in s if len(s) > 1}
    if below <= sets:  # all subsets are there, so a larger set has one that is larger by one
        return [f for f in found if frozenset(f.items) not in below]
    by_size: dict[int, list[frozenset]] = {}
    for s in sets:
        by_size.setdefault(len(s), []).append(s)
    larger = lambda s: any(frozenset(s) < other for size, sets in by_size.items() if size > len(s) for other in sets)
    return [f for f in found if not larger(f.items)]


def _maximal_sets(found: Sets) -> Sets:
    """Those that aren't a set of the listing less one item; sets and such subsets meet in buckets of a size."""
    kind, buckets = found.kind, 1 << BUCKET_BITS

    def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for size, sets, supports in _blocks(batches, kind):
            yield from _in_buckets(sets, supports)
            if size > 1:
                below = np.concatenate([np.delete(sets, k, axis=1) for k in range(size)])
                yield from _in_buckets(below[_first(_keys(below))], None)

    def uncovered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        records = (r for batch in batches for r in zip(batch.column("bucket").to_pylist(), batch.column("sets"), batch.column("supports"), strict=True))
        for bucket, group in groupby(records, lambda r: r[0]):
            own, supports, below = [], [], []
            for _, sets, n in group:
                (own if n.is_valid else below).append(np.frombuffer(sets.as_buffer(), kind).reshape(-1, bucket // buckets))
                if n.is_valid:
                    supports.append(np.frombuffer(n.as_buffer(), np.int64))
            if not own:
                continue
            sets, n = np.concatenate(own), np.concatenate(supports)
            covered = sum(map(len, below))
            # a subset comes before the set that equals it, which then isn't the first of its kind
            first = _first(_keys(np.concatenate([*below, sets])))
            top = first[first >= covered] - covered
            for k in range(0, top.size, BLOCK_SETS):
                yield _block(sets[top[k : k + BLOCK_SETS]], n[top[k : k + BLOCK_SETS]])

    tasks = 8 * found.blocks.sparkSession.sparkContext.defaultParallelism
    met = found.blocks.mapInArrow(dealt, "bucket int, sets binary, supports binary").repartition(tasks, "bucket").sortWithinPartitions("bucket")
    return Sets(met.mapInArrow(uncovered, SETS_SCHEMA), found.pool)


def _keys(sets: np.ndarray) -> np.ndarray:
    """Sets of one size as words."""
    per = 8 // sets.itemsize
    return np.pad(sets, ((0, 0), (0, -sets.shape[1] % per))).view(np.uint64)


def _first(keys: np.ndarray) -> np.ndarray:
    """Where a key stands for the first time."""
    if keys.shape[1] == 1:
        order = np.argsort(keys[:, 0], kind="stable")
    else:
        order = np.lexsort(keys.T)
    ordered = keys[order]
    return order[np.r_[True, (ordered[1:] != ordered[:-1]).any(axis=1)][: len(order)]]


def _in_buckets(sets: np.ndarray, supports: np.ndarray | None) -> Iterator[pa.RecordBatch]:
    """(bucket, sets, supports) by a hash of the sets, supports null where there are none; the sets of a bucket have one size."""
    mixed = np.zeros(len(sets), np.uint64)
    for word in _keys(sets).T:
        mixed = (mixed ^ word) * np.uint64(0x9E3779B97F4A7C15)
        mixed ^= mixed >> np.uint64(32)
    bucket = (mixed * np.uint64(0xD1B54A32D192ED03) >> np.uint64(64 - BUCKET_BITS)).astype(np.int32)
    order = np.argsort(bucket, kind="stable")
    found, start = np.unique(bucket[order], return_index=True)
    ends = [*start[1:].tolist(), len(sets)]
    ordered, own = sets[order], None if supports is None else supports[order]
    spans = list(zip(start.tolist(), ends, strict=True))
    yield pa.RecordBatch.from_arrays(
        [pa.array(found + (sets.shape[1] << BUCKET_BITS), pa.int32()), pa.array([ordered[s:e].tobytes() for s, e in spans], pa.binary()), pa.array([None if own is None else own[s:e].tobytes() for s, e in spans], pa.binary())],
        ["bucket", "sets", "supports"],
    )


def k_for_threshold(tx: Transactions, theta: float, n: int | None = None) -> int:
    """How many itemsets have a frequency of theta or more; more than a listing may have are counted where pattern growth finds them."""
    with tx.remembering() as own:
        n = own.size() if n is None else n
        least = max(1, least_count(theta, n))
        try:
            return len(apriori(own, least))
        except TooManySets:
            return fp_growth(tx, least).count()


def least_count(theta: float, n: int) -> int:
    """The smallest support whose frequency is theta or more."""
    count = int(theta * n)
    return count if count >= theta * n - 1e-9 else count + 1


def threshold_for_k(tx: Transactions, k: int) -> float:
    """Frequency of the k-th most frequent itemset (0 if there are fewer)."""
    found = topk(tx, k)
    return found[k - 1].support / tx.size() if len(found) >= k else 0.0


def as_frame(spark: SparkSession, found: list[Found], n: int) -> DataFrame:
    return spark.createDataFrame([(r, key_of(f.items), len(f.items), f.support, f.support / n if n else 0.0) for r, f in enumerate(found, 1)], TOPK_SCHEMA)


def topk_frame(tx: Transactions, k: int, max_len: int | None = None) -> DataFrame:
    """(rank, itemset, size, support, freq) of the k most frequent itemsets."""
    with tx.remembering() as own:
        return as_frame(own.spark, topk(own, k, max_len), own.size())


def dataset_profile(tx: Transactions, k: int) -> dict[str, float]:
    """Size, items, mean length, and what the top k is made of."""
    with tx.remembering() as own:
        n, found = own.size(), topk(own, k)
        distinct, total = own.item_counts().agg(F.count("*"), F.sum("n")).first()
    return {
        "n": n, "items": distinct, "avg_len": (total or 0) / n if n else 0.0, "k": k,
        "lam": len({i for f in found for i in f.items}), "lam2": sum(len(f.items) == 2 for f in found), "lam3": sum(len(f.items) == 3 for f in found),
        "c_k": found[k - 1].support if len(found) >= k else 0,
    }


def rules(published: DataFrame, count: str, min_confidence: float) -> DataFrame:
    """(antecedent, consequent, confidence) from published itemset counts alone: post-processing."""
    whole = published.select(F.split("itemset", r"\|").alias("w"), F.col(count).alias("nw"))
    part = published.select(F.split("itemset", r"\|").alias("p"), F.col(count).alias("np"))
    inside = (F.size("p") < F.size("w")) & (F.size(F.array_intersect("p", "w")) == F.size("p")) & (F.col("np") > 0)
    return (
        whole.join(F.broadcast(part), inside).withColumn("confidence", F.col("nw") / F.col("np")).where(F.col("confidence") >= min_confidence)
        .select(F.array_join("p", "|").alias("antecedent"), F.array_join(F.array_except("w", "p"), "|").alias("consequent"), "confidence")
    )
