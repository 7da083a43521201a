"""Line dedup with content-defined chunks of lines.

Lines are hashed, and a rolling hash over the last few line hashes chooses
where a chunk ends, so that boundaries follow the content and shift with it: a
line put in or taken out moves only the boundaries near it.  A line of ``LONG``
words always makes a chunk by itself, for a passage of two lines has one.
Chunks of several lines that occur more than once anywhere are removed except
at their first place, ordered by doc_id and place in the text.

Passages are found without regard to what stands around them: every shortest
run of lines of over ``PASSAGE`` words, from each line on and back from each
line, is a chunk as well.  A repeated passage of over ``PASSAGE`` words consists
of such runs: a line has enough words before it, after it, or lies in the run
from the passage's first line.  So no length or number of lines hides one, and
all its lines with words go.

Chunks are found by 128-bit BLAKE2 digests of their lines' digests.  Before any
is removed, the bytes of the lines of all repeated chunks are compared with
those of the same digest; a chunk with a digest that other bytes share stays.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import blocks, checkpointed, free_names, texts

#: Lines under the rolling hash.
SPAN = 2
#: One boundary for so many lines.
MEAN = 3
#: Most lines in a chunk.
MOST = 32
#: A passage holds more words than this.
PASSAGE = 50
#: Words from which a line is a chunk of its own and ends the one before.
LONG = PASSAGE // 2 + 1
#: Tasks over which the places of a repeated chunk are dealt.
SALTS = 4
#: Text bytes that a worker holds when texts and removals meet again.
REJOINED_BYTES = 2 << 20
#: Text bytes whose chunks a worker holds.
CHUNKED_BYTES = 3 << 20

_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


def passage_runs(lines: list[bytes]) -> set[tuple[int, int]]:
    """[start, end) of the shortest runs of over ``PASSAGE`` words from each line with words, and back from each."""
    counts = np.array([len(x.split()) for x in lines], np.int64)
    at = np.flatnonzero(counts)
    after = np.cumsum(counts[at])
    before = after - counts[at]
    end = np.searchsorted(after, before + PASSAGE, "right")
    start = np.searchsorted(before, after - PASSAGE, "left") - 1
    out = {(int(a), int(at[k]) + 1) for a, k in zip(at, end, strict=True) if k < at.size}
    return out | {(int(at[k]), int(b) + 1) for b, k in zip(at, start, strict=True) if k >= 0}


def chunk_bounds(lines: list[bytes]) -> list[tuple[int, int]]:
    """[start, end) of a text's content-defined chunks and of its runs of a passage's size, in order."""
    return sorted({*_content_bounds(lines), *passage_runs(lines)})


def _content_bounds(lines: list[bytes]) -> list[tuple[int, int]]:
    out, start, rolling, hashes = [], 0, 0, []
    drop = pow(_BASE, SPAN, 1 << 64)
    for i, line in enumerate(lines):
        h = xxhash.xxh64_intdigest(line)
        hashes.append(h)
        rolling = (rolling * _BASE + h) & _MASK
        if i >= SPAN:
            rolling = (rolling - hashes[i - SPAN] * drop) & _MASK
        long = len(line) > LONG and line.count(b" ") + 1 >= LONG
        if long:
            if start < i:
                out.append((start, i))
            out.append((i, i + 1))
            start = i + 1
        elif (rolling >> 32) % MEAN == 0 or i + 1 - start == MOST:
            out.append((start, i + 1))
            start = i + 1
    if start < len(lines):
        out.append((start, len(lines)))
    return out


def removable(lines: list[bytes], start: int, end: int) -> bool:
    """Chunks of several lines with some text, and single lines that are passages."""
    if end - start > 1:
        return any(lines[start:end])
    return len(lines[start].split()) > PASSAGE


def _digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def _text_key(text: bytes) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(text)).view(np.int64))


def _places(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(d, n, doc, key, span): distinct chunks of a block with their first place; and (d, doc, key, span) of every chunk.

    A span is start << 32 | end in lines, so that spans are in the order of their places.
    """

    def chunks(batch: pa.RecordBatch) -> Iterator[tuple]:
        for doc, text in zip(batch.column("doc_id").to_pylist(), texts(batch.column("text")), strict=True):
            key, lines = _text_key(text), text.split(b"\n")
            digests = [_digest(x) for x in lines]
            for a, b in chunk_bounds(lines):
                if removable(lines, a, b):
                    yield doc, key, a << 32 | b, _digest(b"".join(digests[a:b]))

    def distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=CHUNKED_BYTES):
            seen: dict[bytes, list] = {}
            for doc, key, span, d in chunks(batch):
                at = (doc is None, doc if doc is not None else nothing, key, span)
                if (old := seen.get(d)) is None:
                    seen[d] = [1, at]
                else:
                    old[0] += 1
                    old[1] = min(at, old[1])
            rows = [(d, n, None if at[0] else at[1], at[2], at[3]) for d, (n, at) in seen.items()]
            yield out(rows, [pa.binary(), pa.int64(), batch.column("doc_id").type, pa.int64(), pa.int64()], ["d", "n", "doc", "key", "span"])

    def every(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=CHUNKED_BYTES):
            rows = [(d, doc, key, span) for doc, key, span, d in chunks(batch)]
            yield out(rows, [pa.binary(), batch.column("doc_id").type, pa.int64(), pa.int64()], ["d", "doc", "key", "span"])

    def out(rows: list, kinds: list, names: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays(list(map(pa.array, zip(*rows, strict=True) if rows else [()] * len(kinds), kinds)), names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    nothing = "" if kind == "string" else 0
    read = docs.select("doc_id", "text")
    return (
        read.mapInArrow(distinct, f"d binary, n long, doc {kind}, key long, span long"),
        read.mapInArrow(every, f"d binary, doc {kind}, key long, span long"),
    )


def repeated_chunks(docs: DataFrame) -> DataFrame:
    """(d, n, doc, key, span): chunks that occur at more than one place, with the first place."""
    first = F.min(F.struct(F.col("doc").isNull().alias("none"), "doc", "key", "span")).alias("first")
    distinct, _ = _places(docs)
    return distinct.groupBy("d").agg(F.sum("n").alias("n"), first).where("n > 1").select("d", "n", "first.doc", "first.key", "first.span")


def removals(docs: DataFrame) -> DataFrame:
    """(doc, key, gone, first): for each text with repeated chunks the spans to remove, and the spans that are first places."""
    repeated = checkpointed(repeated_chunks(docs))
    # places of one chunk are dealt over SALTS tasks; only repeated chunks are copied for that
    dealt = repeated.select("d", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"), F.struct("doc", "key", "span").alias("first"))
    _, every = _places(docs)
    later = every.withColumn("salt", F.pmod("key", F.lit(SALTS)).cast("int")).join(dealt, ["d", "salt"]).where(~F.struct("doc", "key", "span").eqNullSafe(F.col("first")))
    both = later.select("doc", "key", "span", F.lit(True).alias("later")).unionByName(repeated.select("doc", "key", "span", F.lit(False).alias("later")))
    spans = lambda which: F.sort_array(F.collect_set(F.when(F.col("later") == which, F.col("span"))))
    return both.groupBy("doc", "key").agg(spans(True).alias("gone"), spans(False).alias("first"))


def _spans(packed: list[int] | None) -> list[tuple[int, int]]:
    return [(x >> 32, x & 0xFFFFFFFF) for x in packed or ()]


def _conflicts(joined: DataFrame, spans: tuple[str, str]) -> DataFrame:
    """(d): digests that different bytes share, among the lines and chunks that removal compares.

    The bytes of every line of a repeated chunk, and the digests of the lines of
    every such chunk, meet those of equal digest once a block, and neighbours in
    the sorted stream are compared.
    """

    def involved(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=REJOINED_BYTES):
            found: dict[bytes, bytes] = {}
            places = [[*(x or ()), *(y or ())] for x, y in zip(*(batch.column(c).to_pylist() for c in spans), strict=True)]
            some = [k for k, x in enumerate(places) if x]
            for k, text in zip(some, texts(batch.column("text").take(pa.array(some, pa.int64()))), strict=True):
                lines, digests = text.split(b"\n"), {}
                for a, b in _spans(places[k]):
                    for i in range(a, b):
                        if i not in digests:
                            digests[i] = _digest(lines[i])
                            found[digests[i]] = lines[i]
                    whole = b"".join(digests[i] for i in range(a, b))
                    found[_digest(whole)] = whole
            yield pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.binary()), pa.array(found.values(), pa.binary())], ["d", "data"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before, differ = (None, None), set()
        for batch in batches:
            for now in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if now[0] == before[0] and now[1] != before[1]:
                    differ.add(now[0])
                before = now
        yield pa.RecordBatch.from_arrays([pa.array(sorted(differ), pa.binary())], ["d"])

    return joined.mapInArrow(involved, "d binary, data binary").repartition("d").sortWithinPartitions("d").mapInArrow(compare, "d binary")


def _without(text: bytes, spans: list[tuple[int, int]], conflicts: set[bytes]) -> tuple[bytes, int, int, int]:
    """The text without those chunks; lines before and after, chunks removed.  A chunk whose digest, or a line's, stands for other bytes too stays."""
    lines = text.split(b"\n")
    keep, n = [True] * len(lines), 0
    for a, b in spans:
        if conflicts:
            digests = [_digest(x) for x in lines[a:b]]
            if not conflicts.isdisjoint([*digests, _digest(b"".join(digests))]):
                continue
        keep[a:b] = [False] * (b - a)
        n += 1
    kept = [line for line, stays in zip(lines, keep, strict=True) if stays]
    return b"\n".join(kept), len(lines), len(kept), n


def _joined(docs: DataFrame, spans: str, conflicts: str) -> DataFrame:
    """All columns of ``docs``, the spans to remove (null: none), joined on doc_id and the text's hash, and the digests that bytes don't bear out."""
    gone = checkpointed(removals(docs))
    key, first, gone_doc, gone_key = free_names([*docs.columns, spans, conflicts], "key", "first", "gone_doc", "gone_key")

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            keys = pa.array([_text_key(t) for t in texts(batch.column("text"))], pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns, keys], [*batch.schema.names, key])

    rows = docs.mapInArrow(keyed, T.StructType([*docs.schema.fields, T.StructField(key, T.LongType())]))
    gone = gone.select(F.col("doc").alias(gone_doc), F.col("key").alias(gone_key), F.col("gone").alias(spans), F.col("first").alias(first))
    met = rows.join(gone, rows["doc_id"].eqNullSafe(gone[gone_doc]) & (rows[key] == gone[gone_key]), "left").select(*docs.columns, spans, first)
    # the comparison reads the same shuffled rows that are rewritten; of 128-bit digests none is expected to be in the list
    return docs.sparkSession.sql(f"SELECT *, (SELECT collect_list(d) FROM {{bad}}) AS `{conflicts}` FROM {{met}}", bad=_conflicts(met, (spans, first)), met=met).select(*docs.columns, spans, conflicts)


def _cut(batch: pa.RecordBatch, spans: str, conflicts: str) -> list[tuple[bytes, int, int, int]]:
    """``_without`` of each row."""
    bad = set(batch.column(conflicts)[0].as_py() or ()) if batch.num_rows else set()
    out = []
    for text, gone in zip(texts(batch.column("text")), batch.column(spans).to_pylist(), strict=True):
        out.append(_without(text, _spans(gone), bad) if gone else (text, c := text.count(b"\n") + 1, c, 0))
    return out


def dedup_lines(docs: DataFrame) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_lines, n_kept, n_chunks_removed, n_bytes_removed, text (null stays null).

    Rows with equal doc_id and text count as one document: what one keeps, all
    keep.  A text whose chunks all occur earlier becomes empty.  Empty texts
    have one empty line and lose nothing.

    A chunk is removed at every place but its first.  Chunks overlap, so lines
    of a first place may go with another chunk that stands there for the second
    time; each line that goes has an equal one at an earlier place, so no line's
    content ever vanishes from the corpus.
    """
    spans, conflicts = free_names(docs.columns, "spans", "conflicts")
    both = _joined(docs.select("doc_id", "text"), spans, conflicts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=REJOINED_BYTES):
            sizes = pc.fill_null(pc.binary_length(batch.column("text")), 0).to_pylist()
            nulls = batch.column("text").is_null().to_pylist()
            rows = [(before, after, n, size - len(left), None if none else left) for (left, before, after, n), size, none in zip(_cut(batch, spans, conflicts), sizes, nulls, strict=True)]
            kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *map(pa.array, zip(*rows, strict=True), kinds)], ["doc_id", "n_lines", "n_kept", "n_chunks_removed", "n_bytes_removed", "text"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return both.mapInArrow(run, f"doc_id {kind}, n_lines int, n_kept int, n_chunks_removed int, n_bytes_removed long, text string")


def remove_repeats(docs: DataFrame) -> DataFrame:
    """All rows and columns of ``docs`` with repeated chunks gone from text; n_chars, where there is one, follows."""
    spans, conflicts = free_names(docs.columns, "spans", "conflicts")
    both = _joined(docs, spans, conflicts)
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=REJOINED_BYTES):
            columns = {name: batch.column(name) for name in schema.names}
            gone = batch.column(spans).to_pylist()
            if any(gone):
                raw = columns["text"]
                out = [x[0] for x in _cut(batch, spans, conflicts)]
                columns["text"] = pa.array([None if n else t for t, n in zip(out, raw.is_null().to_pylist(), strict=True)], raw.type)
                if "n_chars" in columns:
                    old = columns["n_chars"]
                    columns["n_chars"] = pa.array([len(t.decode()) if g else n for t, g, n in zip(out, gone, old.to_pylist(), strict=True)], old.type)
            yield pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

    return both.mapInArrow(run, schema)
