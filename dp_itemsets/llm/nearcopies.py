"""Near copies by the similarity of their shingle sets, and by fingerprints.

Texts link if their 64-bit fingerprints do (in the pipeline; they meet at the
anchors that cover them).  They link as well if the sets of their five-word shingles have a Jaccard
similarity of 0.8 or more.  At that similarity fingerprints differ in far more
bits than anchors can cover, so these candidates come from minima: a set's minima under
``BANDS`` times ``ROWS`` hash functions, ``ROWS`` at a time, make its band keys,
and sets that share a key are candidates.  Two sets at just 0.8 share none with
a probability of (1 - 0.8^6)^32, about 6 in 100,000, and more similar ones with
far less.  Every candidate is verified on the whole sets.

Equal sets are one before that.  First each member of a key is compared with
the key's least one, which keys of one group of copies mostly share, so that a
group gives about as many pairs as it has members.  Where members of a key
aren't all connected then, their sets meet in the key's task, which compares
each with all that are connected otherwise, and gives only the links that join
two parts.  At the end all pairs of a key are either compared or connected, and
no key gave more links than it has members.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, checkpointed, drop_checkpoint, space_words, texts
from .simhash import Forest, connected, fingerprint_links, fingerprints_of, keep_heads, shingle_hashes, text_keys

SHINGLE = 5
#: Least similarity of a link, as a fraction.
SIMILAR = (4, 5)
BANDS, ROWS = 32, 6
_DRAW = np.random.default_rng(17)
_FACTORS = _DRAW.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_TERMS = _DRAW.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)
_EMPTY = 0


def shingle_set(text: bytes) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles; of the whole sequence if it is shorter."""
    return np.unique(np.array(shingle_hashes(space_words(text), SHINGLE), dtype=np.uint64))


def set_id(shingles: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(shingles.tobytes(), 1)).view(np.int64)) if shingles.size else _EMPTY


def band_keys(shingles: np.ndarray) -> bytes:
    """``BANDS`` keys of 8 bytes; none for an empty set."""
    if not shingles.size:
        return b""
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max)
    for start in range(0, shingles.size, 1 << 12):  # bounds the table of a very long text
        least = np.minimum(least, (shingles[start : start + (1 << 12), None] * _FACTORS + _TERMS).min(axis=0))
    return b"".join(xxhash.xxh64_digest(row.tobytes(), band) for band, row in enumerate(least.reshape(BANDS, ROWS)))


def are_similar(a: np.ndarray, b: np.ndarray) -> bool:
    both = np.intersect1d(a, b, assume_unique=True).size
    return SIMILAR[1] * both >= SIMILAR[0] * (a.size + b.size - both)


def _marks(docs: DataFrame) -> DataFrame:
    """(doc_id, key, fp, bands, print) of every row; key: the hash of its text; fp: the id of its shingle set; print: its fingerprint."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            ids, keys, rows = [], [], texts(batch.column("text"))
            for t in rows:
                own = shingle_set(t)
                ids.append(set_id(own))
                keys.append(band_keys(own))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), text_keys(rows), pa.array(ids, pa.int64()), pa.array(keys, pa.binary()), pa.array(fingerprints_of(rows).view(np.int64))], ["doc_id", "key", "fp", "bands", "print"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, key long, fp long, bands binary, print long")


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[pa.RecordBatch]]]:
    """The groups of a stream sorted by its column key, each as the parts of batches that hold it."""
    key, held = None, []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column("key").to_numpy()
        cuts = np.r_[0, np.flatnonzero(np.diff(keys)) + 1, keys.size]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if held and keys[a] != key:
                yield key, held
                held = []
            key = keys[a]
            held.append(batch.slice(int(a), int(b - a)))
    if held:
        yield key, held


def _members(marks: DataFrame) -> DataFrame:
    """(key, lead, fp): for every key that distinct sets share, each set but the least, which leads."""

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(np.frombuffer(keys, "<i8"), fp) for fp, keys in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if keys]
            if rows:
                fps = np.repeat(np.array([fp for _, fp in rows], np.int64), BANDS)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([k for k, _ in rows])), pa.array(fps)], ["key", "fp"])

    def led(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before = None  # key and lead of the group that the stream is in; groups themselves aren't held
        for batch in batches:
            if not batch.num_rows:
                continue
            keys, fps = (c.to_numpy() for c in batch.columns)
            new = np.r_[before is None or keys[0] != before[0], np.diff(keys) != 0]
            at = np.maximum.accumulate(np.where(new, np.arange(keys.size), -1))
            leads = np.where(at < 0, before[1] if before is not None else 0, fps[np.maximum(at, 0)])
            before = (keys[-1], leads[-1])
            yield pa.RecordBatch.from_arrays([pa.array(c[~new]) for c in (keys, leads, fps)], ["key", "lead", "fp"])

    rows = marks.groupBy("fp").agg(F.min("bands").alias("bands")).mapInArrow(spread, "key long, fp long")
    return rows.repartition("key").sortWithinPartitions("key", "fp").mapInArrow(led, "key long, lead long, fp long")


def part_links(fps: np.ndarray, parts: np.ndarray, sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Links (places in the group) between similar sets of different parts that join parts: a forest.

    Each set outside the largest part is compared with all others at once: the
    sets that hold each of its elements are counted.
    """
    _, own = np.unique(parts, return_inverse=True)
    forest, sizes = Forest(int(own.max()) + 1), np.array([x.size for x in sets])
    where = np.repeat(np.arange(len(sets)), sizes)
    elements, column = np.unique(np.concatenate(sets), return_inverse=True)
    order = np.argsort(column, kind="stable")
    ends = np.cumsum(np.bincount(column, minlength=elements.size))
    holders, starts = where[order], np.r_[0, ends[:-1]]
    first = np.cumsum(sizes) - sizes
    out = []
    for i in np.flatnonzero(own != np.bincount(own).argmax()):
        mine = column[first[i] : first[i] + sizes[i]]
        both = np.zeros(len(sets), np.int64)
        for c in mine:
            both[holders[starts[c] : ends[c]]] += 1  # a set holds an element once
        for j in np.flatnonzero(SIMILAR[1] * both >= SIMILAR[0] * (sizes[i] + sizes - both)):
            if forest.join(int(own[i]), int(own[j])):
                out.append((int(i), int(j)))
    return out


def _open_links(rest: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b): links that join parts of a key; rest: (key, fp, part) of keys of more than one part.

    Elements are cut to 32 bits here, which loses no link; what is found is
    verified on the sets themselves.
    """

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, rows in _groups(batches):
            fps, parts = (np.concatenate([r.column(c).to_numpy() for r in rows]) for c in ("fp", "part"))
            own = [np.unique(np.frombuffer(x, "<u8").astype(np.uint32)) for r in rows for x in r.column("shingles").to_pylist()]
            found = part_links(fps, parts, own)
            yield pa.RecordBatch.from_arrays([pa.array([fps[k] for k, _ in found], pa.int64()), pa.array([fps[k] for _, k in found], pa.int64())], ["a", "b"])

    met = rest.join(sets, "fp").select("key", "fp", "part", "shingles")
    return met.repartition("key").sortWithinPartitions("key").mapInArrow(compare, "a long, b long").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = [are_similar(np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")) for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    left, right = sets.select(F.col("fp").alias("a"), F.col("shingles").alias("x")), sets.select(F.col("fp").alias("b"), F.col("shingles").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def _sets(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(fp, shingles): the whole sets of the wanted ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            found = {set_id(own): own.tobytes() for own in map(shingle_set, texts(batch.column("text")))}
            yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int64()), pa.array(list(found.values()), pa.binary())], ["fp", "shingles"])

    # of a text only what belongs to a wanted set crosses the network
    rows = docs.select("doc_id", "text").join(wanted.select("doc_id").distinct(), "doc_id", "left_semi").select("text")
    return rows.mapInArrow(run, "fp long, shingles binary").groupBy("fp").agg(F.min("shingles").alias("shingles"))


def print_links(marks: DataFrame) -> DataFrame:
    """(a, b): links that connect the set ids of texts whose fingerprints link, by the least id of each fingerprint."""
    own = checkpointed(marks.groupBy("print").agg(F.min("fp").alias("least")))
    alike = marks.select("print", "fp").distinct().join(own, "print").select(F.col("least").alias("a"), F.col("fp").alias("b"))
    met = fingerprint_links(own.select(F.col("print").alias("fp"))).withColumnsRenamed({"a": "x", "b": "y"})
    left, right = own.select(F.col("print").alias("x"), F.col("least").alias("a")), own.select(F.col("print").alias("y"), F.col("least").alias("b"))
    links = checkpointed(met.join(left, "x").join(right, "y").select("a", "b").union(alike).where("a <> b").distinct())
    drop_checkpoint(own)
    return links


def similar_roots(docs: DataFrame, marks: DataFrame, printed: DataFrame | None = None) -> DataFrame:
    """(node, root): components of set ids that share a key and are similar, or that ``printed`` (a, b) links; sets without a link don't appear."""
    members = checkpointed(_members(marks))
    ids = marks.groupBy("fp").agg(F.min("doc_id").alias("doc_id"))
    sets = checkpointed(_sets(docs, ids.join(members.select("fp").union(members.select("lead")).distinct(), "fp", "left_semi")))
    links = _verified(members.select(F.col("lead").alias("a"), F.col("fp").alias("b")).distinct(), sets)
    links = checkpointed(links if printed is None else links.unionByName(printed))
    roots = connected(links)
    every = members.select("key", "fp").union(members.select("key", F.col("lead").alias("fp")).distinct())
    placed = every.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("key", "fp", F.coalesce("root", "fp").alias("part"))
    # a key of two has been compared; larger ones are open while they have more than one part
    open_ = placed.groupBy("key").agg(F.min("part").alias("least"), F.max("part").alias("most"), F.count("*").alias("n")).where("least <> most and n > 2").select("key")
    rest = checkpointed(placed.join(open_, "key"))
    used = [members, sets, links, rest]
    if not rest.isEmpty():
        more = checkpointed(links.unionByName(_verified(_open_links(rest, sets), sets)))
        used.append(more)
        roots = connected(more)
    for df in used:
        drop_checkpoint(df)
    return roots


def keep_first(docs: DataFrame, by_fingerprint: bool = False) -> DataFrame:
    """The rows of ``docs``, all columns as they are, with one of each component of similar texts: that of the smallest doc_id (null last).

    by_fingerprint: texts whose fingerprints link are in one component as well.

    Texts without words are one component, as they are equal.  Where rows of
    that id have several texts, see ``simhash.keep_first``.
    """
    marks = checkpointed(_marks(docs))
    printed = print_links(marks) if by_fingerprint else None
    return keep_heads(docs, marks, lambda marks: similar_roots(docs, marks, printed))
