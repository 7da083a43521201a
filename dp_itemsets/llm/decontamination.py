"""Benchmark decontamination with a distributed positional inverted index.

The index is partitioned by document: each shard holds, for every stored term,
the sorted positions at which it occurs.  Positions of a shard's documents lie
in one number line with a gap between documents, so that no phrase crosses from
one document into the next.  A phrase is looked up from its rarest term: that
term's list, less the term's offset in the phrase, gives candidate starts, and
the lists of the other terms, rarest first, thin them out.  No text is needed
for that, and nothing is shuffled: queries go to all shards.

The query side (a benchmark) is sent to every shard in blocks of bounded size,
one block at a time; several blocks take several passes over the index.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import alnum_words, blocks, checkpointed, free_name, shared_folder, texts

#: Words in a window of an item.
WINDOW = 13
#: Text bytes of query items that go to the shards at a time.
QUERY_BYTES = 32 << 20

INDEX_SCHEMA = "doc_ids array<{kind}>, starts array<int>, n_words array<int>, terms array<binary>, ends array<int>, positions binary"


class Shard:
    """Postings of a few documents: for each term a sorted list of positions."""

    def __init__(self, starts: np.ndarray, n_words: np.ndarray, terms: dict[bytes, int], ends: np.ndarray, positions: np.ndarray):
        self.starts, self.n_words, self.terms, self.ends, self.positions = starts, n_words, terms, ends, positions

    @classmethod
    def build(cls, docs: Iterable[bytes], vocabulary: dict[bytes, int] | None = None) -> Shard:
        """Index of whole documents; with a vocabulary, postings of its terms only."""
        own: dict[bytes, int] = {} if vocabulary is None else vocabulary
        ids, sizes = [], []
        for text in docs:
            words = alnum_words(text)
            sizes.append(len(words))
            if vocabulary is None:
                for w in words:
                    own.setdefault(w, len(own))
            get = own.get
            ids.append(np.array([get(w, -1) for w in words] + [-1], dtype=np.int32))
        n_words = np.array(sizes, dtype=np.int32)
        starts = (np.cumsum(n_words + 1) - n_words - 1).astype(np.int32)
        flat = np.concatenate(ids) if ids else np.zeros(0, np.int32)
        where = np.flatnonzero(flat >= 0).astype(np.int32)
        # a 16-bit key sorts in linear time
        key = flat[where].astype(np.uint16) if len(own) < 1 << 16 else flat[where]
        order = np.argsort(key, kind="stable")
        ends = np.cumsum(np.bincount(key, minlength=len(own))).astype(np.int64)
        return cls(starts, n_words, own, ends, where[order])

    def frequencies(self) -> np.ndarray:
        return np.diff(self.ends, prepend=0)

    def postings(self, term: int) -> np.ndarray:
        return self.positions[self.ends[term - 1] if term else 0 : self.ends[term]]

    def phrase(self, terms: np.ndarray, frequencies: np.ndarray) -> np.ndarray:
        """Start positions of the exact phrase; terms: ids in this shard."""
        by_rarity = np.argsort(frequencies[terms], kind="stable")
        first = by_rarity[0]
        found = self.postings(terms[first]) - first
        for k in by_rarity[1:]:
            if not found.size:
                break
            listed = self.postings(terms[k])
            want = found + k
            at = np.searchsorted(listed, want)
            at[at == listed.size] = 0
            found = found[listed[at] == want] if listed.size else found[:0]
        return found

    def near(self, terms: list[int], slop: int) -> list[tuple[int, int]]:
        """Spans (start, end) around each posting of the first term that have all terms within ``slop`` words of it, in its document."""
        anchors = self.postings(terms[0]).astype(np.int64)
        doc = np.searchsorted(self.starts, anchors, "right") - 1
        first, last = self.starts[doc], self.starts[doc] + self.n_words[doc] - 1
        low, high, alive = anchors.copy(), anchors.copy(), np.ones(anchors.size, bool)
        for term in terms[1:]:
            listed = self.postings(term).astype(np.int64)
            if not listed.size:
                return []
            at = np.searchsorted(listed, anchors)
            left, right = listed[np.maximum(at - 1, 0)], listed[np.minimum(at, listed.size - 1)]
            # each side must lie in the anchor's document before the nearer one is chosen
            far = np.int64(1) << 40
            back = np.where((at > 0) & (left >= first), anchors - left, far)
            ahead = np.where((at < listed.size) & (right <= last), right - anchors, far)
            near = np.where(ahead <= back, right, left)
            alive &= np.minimum(ahead, back) <= slop
            low, high = np.where(alive, np.minimum(low, near), low), np.where(alive, np.maximum(high, near), high)
        return [(int(a), int(b) + 1) for a, b in zip(low[alive], high[alive], strict=True)]


@dataclass
class Queries:
    """Distinct windows of a block of items, as ids of the block's own vocabulary."""

    vocabulary: dict[bytes, int] = field(default_factory=dict)
    windows: dict[tuple[int, ...], dict] = field(default_factory=dict)
    _tables: list | None = None

    @classmethod
    def of(cls, items: Iterable[tuple[object, str | None]], window: int = WINDOW) -> Queries:
        out = cls()
        for item, text in items:
            words = alnum_words((text or "").encode())
            ids = [out.vocabulary.setdefault(w, len(out.vocabulary)) for w in words]
            for k in range(max(len(ids) - window, 0) + 1) if ids and item is not None else ():
                out.windows.setdefault(tuple(ids[k : k + window]), {})[item] = None
        return out

    def tables(self) -> list[tuple[np.ndarray, list[list]]]:
        """For each window length: a row of term ids for each window, and the items of each."""
        if self._tables is None:
            by: dict[int, list[tuple[int, ...]]] = {}
            for words in self.windows:
                by.setdefault(len(words), []).append(words)
            self._tables = [(np.array(rows, np.int64), [list(self.windows[w]) for w in rows]) for rows in by.values()]
        return self._tables


def query_blocks(benchmark: DataFrame, window: int = WINDOW, limit: int = QUERY_BYTES) -> Iterator[Queries]:
    """The items' windows, in blocks of about ``limit`` bytes of text, read to the driver one block at a time.

    Items without words or without an id have no windows.
    """
    items, size, some = [], 0, False
    for row in benchmark.select("item_id", "text").toLocalIterator():
        items.append((row[0], row[1]))
        size += len(row[1] or "")
        if size > limit:
            yield Queries.of(items, window)
            items, size, some = [], 0, True
    if items or not some:
        yield Queries.of(items, window)


def occurrences(shard: Shard, queries: Queries) -> tuple[np.ndarray, np.ndarray, list[list]]:
    """Starts, lengths and item names of all windows that occur in the shard."""
    same = shard.terms is queries.vocabulary
    ids = np.arange(len(queries.vocabulary)) if same else np.array([shard.terms.get(w, -1) for w in queries.vocabulary], dtype=np.int64)
    frequencies = shard.frequencies()
    known = np.zeros(ids.size, bool)
    if frequencies.size and ids.size:
        known = (ids >= 0) & (frequencies[ids] > 0)
    starts, lengths, names = [], [], []
    for rows, items in queries.tables():
        # only windows all of whose terms the shard holds are looked up one by one
        for k in np.flatnonzero(known[rows].all(axis=1)):
            found = shard.phrase(ids[rows[k]], frequencies)
            if found.size:
                starts.append(found)
                lengths.append(np.full(found.size, rows.shape[1]))
                names += [items[k]] * found.size
    if not starts:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), []
    return np.concatenate(starts).astype(np.int64), np.concatenate(lengths), names


def judge(shard: Shard, queries: Queries) -> tuple[np.ndarray, list[set[str]]]:
    """Whether each position lies in an occurrence, and the items that occur in each document."""
    width = int(shard.n_words.sum()) + len(shard.n_words) + 1
    edges, items = np.zeros(width + 1, np.int64), [set() for _ in shard.n_words]
    starts, lengths, names = occurrences(shard, queries)
    np.add.at(edges, starts, 1)
    np.add.at(edges, starts + lengths, -1)
    for doc, found in zip(np.searchsorted(shard.starts, starts, "right") - 1, names, strict=True):
        items[doc].update(map(str, found))
    return np.cumsum(edges)[:width] > 0, items


def hits_of(shard: Shard, covered: np.ndarray) -> np.ndarray:
    return np.add.reduceat(covered.astype(np.int64), shard.starts) if shard.starts.size else np.zeros(0, np.int64)


def is_contaminated(n_hit: np.ndarray, n_words: np.ndarray) -> np.ndarray:
    """A hit, and hits are at least a twentieth of the words."""
    return (n_hit > 0) & (20 * n_hit >= n_words)


def build_index(docs: DataFrame, vocabulary: dict[bytes, int] | None = None) -> DataFrame:
    """Shards of the positional index, one row each, of all rows of ``docs``.

    A vocabulary keeps postings of its terms only, as a filter that is pushed
    down; without one every term is stored.  A shard lists the terms that occur
    in it.  Null texts have no words.  The result can be written as a table and
    searched later, any number of times.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            s = Shard.build(texts(batch.column("text")), vocabulary)
            ids = batch.column("doc_id")
            lists = [pa.ListArray.from_arrays([0, len(ids)], ids)]
            used = s.frequencies() > 0
            terms = [w for w, k in zip(s.terms, used, strict=True) if k]
            for values, kind in ((s.starts, pa.int32()), (s.n_words, pa.int32()), (terms, pa.binary()), (s.ends[used], pa.int32())):
                lists.append(pa.ListArray.from_arrays([0, len(values)], pa.array(values, kind)))
            yield pa.RecordBatch.from_arrays([*lists, pa.array([s.positions.astype("<i4").tobytes()], pa.binary())], names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = INDEX_SCHEMA.format(kind=kind)
    names = ["doc_ids", "starts", "n_words", "terms", "ends", "positions"]
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def _shards(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Array, Shard]]:
    for batch in batches:
        for i in range(batch.num_rows):
            lists = [batch.column(k)[i].values for k in range(5)]
            terms = {w: k for k, w in enumerate(lists[3].to_pylist())}
            arrays = [lists[k].to_numpy(zero_copy_only=False) for k in (1, 2, 4)]
            positions = np.frombuffer(batch.column(5)[i].as_py(), "<i4")
            yield lists[0], Shard(arrays[0], arrays[1], terms, arrays[2].astype(np.int64), positions)


RESULT = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "item_ids"]


def _result(ids: pa.Array, n_words: np.ndarray, hits: np.ndarray, found: list[set[str]]) -> pa.RecordBatch:
    items = [sorted(x) for x in found]
    digests = [hashlib.sha256(",".join(x).encode()).hexdigest() for x in items]
    return pa.RecordBatch.from_arrays([
        ids, pa.array(n_words, pa.int64()), pa.array(hits, pa.int64()), pa.array([len(x) for x in items], pa.int64()),
        pa.array(digests), pa.array(is_contaminated(hits, n_words)), pa.array(items, pa.list_(pa.string())),
    ], RESULT)


def search(index: DataFrame, queries: Iterable[Queries]) -> DataFrame:
    """One row per indexed document: what of the queries occurs in it.

    Columns: doc_id, n_words, n_hit (words inside an occurrence of a window),
    n_items, items_sha256 (of the item ids as strings, sorted, comma-joined),
    contaminated, item_ids.

    One block of queries is sent to all shards and answered in one pass.  Of
    more blocks each is sent in a pass of its own, and dropped after it, so what
    executors hold is a block, whatever the benchmark's size; what a pass finds
    is written down by shard, and the passes meet at the end.
    """
    queries = iter(queries)
    first = next(queries, Queries())
    second = next(queries, None)
    kind = index.schema["doc_ids"].dataType.elementType.simpleString()
    schema = f"doc_id {kind}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, item_ids array<string>"
    if second is None:
        sent = index.sparkSession.sparkContext.broadcast(first)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for ids, shard in _shards(batches):
                covered, items = judge(shard, sent.value)
                yield _result(ids, shard.n_words, hits_of(shard, covered), items)

        return index.mapInArrow(run, schema)
    return _search_in_passes(index, chain((first, second), queries), schema)


def _search_in_passes(index: DataFrame, queries: Iterator[Queries], schema: str) -> DataFrame:
    spark = index.sparkSession
    # shards get their number once, in a table, so that all passes mean the same ones
    numbered = checkpointed(index.select(F.monotonically_increasing_id().alias("shard"), *index.columns))
    folder = f"{shared_folder(spark)}/matches-{uuid.uuid4().hex}"
    for k, block in enumerate(queries):
        sent = spark.sparkContext.broadcast(block)

        def match(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for number, (_, shard) in zip(batch.column(0).to_pylist(), _shards([batch.drop_columns(["shard"])]), strict=True):
                    covered, items = judge(shard, sent.value)
                    docs = [d for d, x in enumerate(items) if x]
                    marks = [np.packbits(covered[shard.starts[d] : shard.starts[d] + shard.n_words[d]]).tobytes() for d in docs]
                    yield pa.RecordBatch.from_arrays([
                        pa.array([number] * len(docs), pa.int64()), pa.array(docs, pa.int32()), pa.array(marks, pa.binary()), pa.array([sorted(items[d]) for d in docs], pa.list_(pa.string())),
                    ], ["shard", "doc", "marks", "items"])

        numbered.mapInArrow(match, "shard long, doc int, marks binary, items array<string>").write.parquet(f"{folder}/block={k}")
        sent.unpersist()

    def merge(key: tuple, groups: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marks, items = None, set()
        for batch in groups:  # one row for each block that occurs in the document
            for m, x in zip(batch.column("marks").to_pylist(), batch.column("items").to_pylist(), strict=True):
                bits = np.frombuffer(m, np.uint8)
                marks = bits if marks is None else marks | bits
                items.update(x)
        yield pa.RecordBatch.from_arrays([pa.array([k.as_py()], t) for k, t in zip(key, (pa.int64(), pa.int32()), strict=True)] + [pa.array([int(np.bitwise_count(marks).sum())], pa.int64()), pa.array([sorted(items)], pa.list_(pa.string()))], ["shard", "doc", "n_hit", "found"])

    found = spark.read.parquet(folder).drop("block").groupBy("shard", "doc").applyInArrow(merge, "shard long, doc int, n_hit long, found array<string>")
    every = numbered.select("shard", F.posexplode(F.arrays_zip("doc_ids", "n_words")).alias("doc", "d")).select("shard", "doc", F.col("d.doc_ids").alias("doc_id"), F.col("d.n_words").cast("long").alias("n_words"))
    joined = every.join(found, ["shard", "doc"], "left").withColumn("n_hit", F.coalesce("n_hit", F.lit(0))).withColumn("item_ids", F.coalesce("found", F.array().cast("array<string>")))
    names = F.array_join("item_ids", ",")
    return joined.select(
        "doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"), F.sha2(names, 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"), "item_ids",
    ).to(T._parse_datatype_string(schema))


def proximity(index: DataFrame, queries: dict[str, str], slop: int) -> DataFrame:
    """(query, doc_id, start, end): word spans in which all terms of a query lie within ``slop`` words of its rarest term.

    The rarest is that of the whole index (of equal ones the first in the
    query), so that results don't depend on which documents share a shard.
    """
    wanted = {name: list(dict.fromkeys(alnum_words(text.encode()))) for name, text in queries.items()}
    every = sorted({w for words in wanted.values() for w in words})

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, shard in _shards(batches):
            frequencies = shard.frequencies()
            found = [(k, int(frequencies[shard.terms[w]])) for k, w in enumerate(every) if w in shard.terms]
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], pa.int64()) for i in range(2)], ["term", "n"])

    totals = {every[r["term"]]: r["n"] for r in index.mapInArrow(count, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()}  # a row for each term of the queries
    ordered = {name: sorted(words, key=lambda w: totals.get(w, 0)) for name, words in wanted.items()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, shard in _shards(batches):
            rows = []
            for name, words in ordered.items():
                if words and all(w in shard.terms for w in words):
                    for a, b in shard.near([shard.terms[w] for w in words], slop):
                        doc = int(np.searchsorted(shard.starts, a, "right")) - 1
                        rows.append((name, ids[doc].as_py(), a - int(shard.starts[doc]), b - int(shard.starts[doc])))
            cols = list(zip(*rows, strict=True)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.string(), ids.type, pa.int32(), pa.int32()), strict=True)], ["query", "doc_id", "start", "end"])

    kind = index.schema["doc_ids"].dataType.elementType.simpleString()
    return index.mapInArrow(run, f"query string, doc_id {kind}, start int, end int")


def find_contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, limit: int = QUERY_BYTES) -> DataFrame:
    """Index all documents and look up every window of every item.

    A benchmark of one block pushes its terms into the build, so that no other
    postings are made; a larger one is searched in passes over an index of all
    terms.  Null texts and texts without words have no hits.  Repeated rows are
    judged each.  An empty benchmark hits nothing, nor do items without an id.
    """
    queries = query_blocks(benchmark, window, limit)
    first, second = next(queries), next(queries, None)
    if second is None:
        return search(build_index(docs, first.vocabulary), [first])
    return search(build_index(docs), chain((first, second), queries))


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, limit: int = QUERY_BYTES) -> DataFrame:
    """Rows of ``docs``, all columns as they are, that aren't contaminated.

    A benchmark of one block is answered where the rows are.  A larger one
    marks the rows of a written copy by number and joins the verdicts back.
    """
    queries = query_blocks(benchmark, window, limit)
    first, second = next(queries), next(queries, None)
    if second is None:
        sent = docs.sparkSession.sparkContext.broadcast(first)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in blocks(batches):
                shard = Shard.build(texts(batch.column("text")), sent.value.vocabulary)
                hits = hits_of(shard, judge(shard, sent.value)[0])
                yield batch.filter(pa.array(~is_contaminated(hits, shard.n_words)))

        return docs.mapInArrow(run, docs.schema)
    row = free_name(docs.columns, "row")
    kept = checkpointed(docs.withColumn(row, F.monotonically_increasing_id()))
    verdicts = search(build_index(kept.select(F.col(row).alias("doc_id"), "text")), chain((first, second), queries))
    return kept.join(verdicts.where("contaminated").select(F.col("doc_id").alias(row)), row, "left_anti").select(*docs.columns)
