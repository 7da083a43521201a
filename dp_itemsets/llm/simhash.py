"""SimHash near-duplicates by anchor-point covering.

Fingerprints of 64 bits link if they differ in at most two bits.  Two blocks of
31 bits each are covered by the perfect Hamming code of that length, whose
covering radius is 1: the codewords are the anchors, and every block lies
within 1 of exactly one of them, its home.  A pair that differs in two bits at
most differs in one at most in one of the blocks (the two bits outside the
blocks only make that easier), so there the home anchor of one fingerprint
lies within 1 + 1 of the other.  Each fingerprint is therefore sent to its home
and, as a guest, to all anchors within covering radius plus threshold: 16 for a
block.  At an anchor, residents are compared with residents and guests.

Equal fingerprints are one before that.  A task keeps only links that join two
parts of an anchor's group, a forest, so no group gives all its pairs.  Groups
too large for pairwise comparison look up the neighbours of each resident in
the sorted group, which is linear in the group.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import blocks, checkpointed, drop_checkpoint, free_names, space_words, texts

SEED = 42
SHINGLE = 3
THRESHOLD = 2
#: Bits in a block: a perfect one-error code needs 2^r - 1.
BLOCK_BITS = 31
#: Residents times members beyond which neighbours are looked up instead of compared.
PAIRS = 1 << 24

_LOW = np.uint64((1 << BLOCK_BITS) - 1)


def shingle_hashes(words: list[bytes], size: int = SHINGLE) -> list[int]:
    """XXH64 of each run of ``size`` words, repeats included; of the whole sequence if it is shorter."""
    if not words:
        return []
    h = xxhash.xxh64_intdigest
    if len(words) <= size:
        return [h(b" ".join(words), SEED)]
    return [h(b" ".join(s), SEED) for s in zip(*(words[k:] for k in range(size)), strict=False)]


def fingerprints_of(docs: list[bytes], size: int = SHINGLE) -> np.ndarray:
    """A bit is 1 if it is set in over half of a text's shingle hashes; 0 for texts without words."""
    out = np.zeros(len(docs), np.uint64)
    for k, text in enumerate(docs):
        hashes = np.array(shingle_hashes(space_words(text), size), dtype="<u8")
        if not hashes.size:
            continue
        ones = np.zeros(64, np.int64)
        for start in range(0, hashes.size, 1 << 16):  # bounds the unpacked bits of a very long text
            part = hashes[start : start + (1 << 16)]
            ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        out[k] = np.packbits(ones * 2 > hashes.size, bitorder="little").view("<u8")[0]
    return out


def fingerprint(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """(doc_id, fp): one row per row of ``docs``; fp holds the 64 bits as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            prints = fingerprints_of(texts(batch.column("text")), size)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(prints.view(np.int64))], ["doc_id", "fp"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, fp long")


def syndromes(block: np.ndarray) -> np.ndarray:
    """XOR of the 1-based places of the set bits: 0 for a codeword, else the place whose flip makes one."""
    out = np.zeros(block.shape, np.uint64)
    for place in range(1, BLOCK_BITS + 1):
        out ^= (block >> np.uint64(place - 1) & np.uint64(1)) * np.uint64(place)
    return out


def _flips() -> tuple[np.ndarray, np.ndarray]:
    """For each syndrome the masks that lead to anchors within 2, the home first; and how many there are."""
    masks, n = np.zeros((BLOCK_BITS + 1, (BLOCK_BITS + 1) // 2), np.uint64), np.zeros(BLOCK_BITS + 1, np.int64)
    for s in range(BLOCK_BITS + 1):
        found = [1 << (s - 1)] if s else [0]
        if s:
            found += [1 << (i - 1) | 1 << ((i ^ s) - 1) for i in range(1, BLOCK_BITS + 1) if i < i ^ s]
        masks[s, : len(found)], n[s] = found, len(found)
    return masks, n


def anchor_rows(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Anchor keys, fingerprints and whether at home, for both blocks of all fingerprints."""
    masks, n = _flips()
    keys, prints, home = [], [], []
    for number in range(2):
        block = fps >> np.uint64(number * BLOCK_BITS) & _LOW
        s = syndromes(block).astype(np.int64)
        filled = np.arange(masks.shape[1]) < n[s][:, None]
        anchors = (block[:, None] ^ masks[s]) | np.uint64(number << 62)
        keys.append(anchors[filled])
        prints.append(np.repeat(fps, n[s]))
        home.append(np.broadcast_to(np.arange(masks.shape[1]) == 0, filled.shape)[filled])
    return np.concatenate(keys), np.concatenate(prints), np.concatenate(home)


class Forest:
    """Union-find over the indices of a group."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        up = self.up
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        a, b = self.root(i), self.root(j)
        self.up[max(a, b)] = min(a, b)
        return a != b


def group_links(fps: np.ndarray, home: np.ndarray, threshold: int = THRESHOLD) -> list[tuple[int, int]]:
    """Links of one anchor's group that join parts of it; fps are distinct, residents first."""
    residents = int(home.sum())
    out: list[tuple[int, int]] = []
    if not residents or fps.size < 2:
        return out
    forest = Forest(fps.size)
    if residents * fps.size <= PAIRS:
        step = max(1, (1 << 20) // fps.size)
        for a in range(0, residents, step):
            close = np.bitwise_count(fps[a : min(a + step, residents), None] ^ fps[None, :]) <= threshold
            for i, j in np.argwhere(close):
                if i + a < j and forest.join(int(i + a), int(j)):
                    out.append((i + a, j))
    else:
        order = np.argsort(fps)
        listed = fps[order]
        single = [1 << b for b in range(64)]
        for mask in [*single, *(x | y for k, x in enumerate(single) for y in single[:k])] if threshold >= 2 else single:
            want = fps[:residents] ^ np.uint64(mask)
            at = np.minimum(np.searchsorted(listed, want), listed.size - 1)
            for i in np.flatnonzero(listed[at] == want):
                if forest.join(int(i), int(order[at[i]])):
                    out.append((int(i), int(order[at[i]])))
    return out


def _partition_links(batches: Iterator[pa.RecordBatch], threshold: int) -> Iterator[pa.RecordBatch]:
    """Groups of equal keys in a sorted stream; only an unfinished group is carried on."""

    def links(keys: np.ndarray, fps: np.ndarray, home: np.ndarray) -> pa.RecordBatch:
        edges = np.flatnonzero(np.diff(keys)) + 1
        starts, ends = np.r_[0, edges], np.r_[edges, keys.size]
        residents = np.add.reduceat(home.astype(np.int64), starts)
        left, right = [], []
        sizes = ends - starts
        # pairs of one resident and its guests, all such groups at once
        lone = np.flatnonzero((residents == 1) & (sizes > 1))
        at = np.repeat(starts[lone], sizes[lone] - 1)
        other = at + 1 + np.arange(at.size) - np.repeat(np.cumsum(sizes[lone] - 1) - (sizes[lone] - 1), sizes[lone] - 1)
        close = np.bitwise_count(fps[at] ^ fps[other]) <= threshold
        left.append(fps[at[close]])
        right.append(fps[other[close]])
        for g in np.flatnonzero(residents > 1):
            own = fps[starts[g] : ends[g]]
            found = group_links(own, home[starts[g] : ends[g]], threshold)
            if found:
                i, j = np.array(found, dtype=np.int64).T
                left.append(own[i])
                right.append(own[j])
        a, b = np.concatenate(left), np.concatenate(right)
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    held: tuple | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        now = (batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64), batch.column(2).to_numpy(zero_copy_only=False))
        if held is not None:
            now = tuple(np.concatenate(x) for x in zip(held, now, strict=True))
        last = int(np.searchsorted(now[0], now[0][-1]))
        held = tuple(x[last:] for x in now)
        if last:
            yield links(*(x[:last] for x in now))
    if held is not None:
        yield links(*held)


def fingerprint_links(prints: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """(a, b): links between distinct fingerprints (column fp) that connect all that are within ``threshold`` (1 or 2) bits."""
    if threshold not in (1, 2):
        raise ValueError("two blocks of covering radius 1 serve thresholds of 1 and 2")

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 1 << 15):
                fps = batch.column(0).slice(start, 1 << 15).to_numpy().view(np.uint64)
                keys, prints, home = anchor_rows(fps)
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(prints.view(np.int64)), pa.array(home)], ["anchor", "fp", "home"])

    rows = prints.select("fp").mapInArrow(spread, "anchor long, fp long, home boolean")
    met = rows.repartition("anchor").sortWithinPartitions("anchor", F.desc("home"), "fp")
    return met.mapInArrow(lambda it: _partition_links(it, threshold), "a long, b long")


def connected(links: DataFrame) -> DataFrame:
    """(node, root): components of the links by alternating star contraction; nodes without a link don't appear.

    Each round points neighbours above a node to the node's smallest neighbour
    (large star) and those below likewise (small star), until nothing moves.
    """
    edges = checkpointed(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct())
    state = None
    while True:
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        before, edges = edges, checkpointed(small)
        drop_checkpoint(before)
        now = tuple(edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first())
        if now == state:
            break
        state = now
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def named_classes(distinct: DataFrame, roots: DataFrame) -> DataFrame:
    """(fp, component_id, head): for each distinct fingerprint (fp, least) its component's smallest doc_id and that document's fingerprint."""
    members = distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = members.groupBy("root").agg(F.min(F.struct(F.col("least").isNull().alias("none"), "least", "fp")).alias("head"))
    return members.join(named, "root").select("fp", F.col("head.least").alias("component_id"), F.col("head.fp").alias("head"))


def _distinct(prints: DataFrame) -> DataFrame:
    return checkpointed(prints.groupBy("fp").agg(F.min("doc_id").alias("least")))


def _classes(prints: DataFrame, threshold: int) -> DataFrame:
    distinct = _distinct(prints)
    return named_classes(distinct, connected(fingerprint_links(distinct, threshold)))


def components(docs: DataFrame, size: int = SHINGLE, threshold: int = THRESHOLD) -> DataFrame:
    """One row per row of ``docs``: doc_id, fingerprint (16 hex digits) and component_id, the smallest doc_id reachable by links.

    Null and empty texts have fingerprint zero and are linked like any other.
    A null doc_id takes part, but names a component only if it has no other.
    """
    prints = checkpointed(fingerprint(docs, size))
    return prints.join(_classes(prints, threshold).drop("head"), "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def keyed_fingerprint(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """(doc_id, key, fp): as ``fingerprint``, with the hash of the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            rows = texts(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), text_keys(rows), pa.array(fingerprints_of(rows, size).view(np.int64))], ["doc_id", "key", "fp"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, key long, fp long")


def text_keys(rows: list[bytes]) -> pa.Array:
    return pa.array(np.array([xxhash.xxh64_intdigest(t) for t in rows], np.uint64).view(np.int64))


def keep_first(docs: DataFrame, size: int = SHINGLE, threshold: int = THRESHOLD) -> DataFrame:
    """The rows of ``docs``, all columns as they are, with one of each component: that of the smallest doc_id (null last).

    Where rows of that id have several texts, the one with the smallest hash of
    its text stays; of fully equal ids and texts the first by the other columns'
    JSON.
    """
    return keep_heads(docs, checkpointed(keyed_fingerprint(docs, size)), lambda prints: connected(fingerprint_links(prints.select("fp").distinct(), threshold)))


def keep_heads(docs: DataFrame, prints: DataFrame, roots_of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``keep_first`` for any mark of a text: prints holds (doc_id, key, fp) of every row, key the hash of its text, and roots_of gives (node, root) of linked marks.

    Marks are costly, and made once: rows find out whether they stay by their id
    and the hash of their text.
    """
    key, head_key, head_doc, chosen = free_names(docs.columns, "key", "head_key", "head_doc", "row")
    schema = T.StructType([*docs.schema.fields, T.StructField(key, T.LongType())])

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            yield pa.RecordBatch.from_arrays([*batch.columns, text_keys(texts(batch.column("text")))], schema.names)

    least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")).alias("least")
    distinct, roots = prints.groupBy("fp").agg(least), roots_of(prints)
    members = distinct.join(roots, distinct["fp"] == roots["node"], "left").select(F.coalesce("root", "fp").alias("root"), "least")
    heads = checkpointed(members.groupBy("root").agg(F.min("least").alias("least")).select(F.col("least.key").alias(head_key), F.col("least.doc_id").alias(head_doc)))
    # rows of a head that repeat: few, or none
    repeated = prints.groupBy("doc_id", "key").agg(F.count("*").alias("n")).where("n > 1").select(F.col("key").alias(head_key), F.col("doc_id").alias(head_doc))
    twice = checkpointed(repeated.join(heads, repeated[head_key].eqNullSafe(heads[head_key]) & repeated[head_doc].eqNullSafe(heads[head_doc]), "left_semi"))

    def among(rows: DataFrame, some: DataFrame, how: str) -> DataFrame:
        return rows.join(some, (rows[key] == some[head_key]) & rows["doc_id"].eqNullSafe(some[head_doc]), how)

    kept = among(docs.mapInArrow(keyed, schema), heads, "left_semi")
    if twice.isEmpty():
        return kept.drop(key)
    row = F.struct(*[F.col(c) for c in docs.columns])
    one = among(kept, twice, "left_semi").groupBy(key, "doc_id").agg(F.min_by(row, F.to_json(row)).alias(chosen))
    return among(kept, twice, "left_anti").drop(key).unionByName(one.select(f"{chosen}.*"))
