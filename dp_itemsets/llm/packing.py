"""Packing token sequences by minimum bin slack.

A document's tokens are cut into full windows and one remainder.  Full windows
are sequences as they are.  What is to be packed is thus a multiset of
remainder lengths below the window, and the plan depends on its histogram
alone: at most ``window - 1`` counts, whatever the size of the corpus.

A window is filled with the longest remainder left and the multiset of others
that comes closest to its capacity.  The sums that can be reached are the bits
of an integer; counts are added in doublings, and a walk back through the kept
integers gives the counts.  The filling is then repeated while its lengths
last, so each step uses up a length, and the number of steps doesn't grow with
the corpus.
"""

from __future__ import annotations

import base64
import zlib
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import blocks, checkpointed

WINDOW = 1024
#: Appended to each document's ids.
END_ID = 0


@lru_cache(maxsize=4)
def _encoder(path: str):
    """A function from str to ids, those of ``Tokenizer.encode(text, add_special_tokens=False)`` with its defaults.

    For a .json file whose ranks lie beside it as .tiktoken, ids of texts that
    hold none of the file's added tokens come from the ranks: the same, but
    several times faster.  A text that spells an added token gets that token's
    id, as the tokenizer itself gives it.
    """
    from pathlib import Path

    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(path)
    added = [token.content for token in slow.get_added_tokens_decoder().values()]

    def plain(text: str) -> list[int]:
        return slow.encode(text, add_special_tokens=False).ids

    ranks = Path(path).with_suffix(".tiktoken")
    if not ranks.exists():
        return plain
    import public_tokenizers
    import tiktoken

    merges = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.read_bytes().splitlines())}
    fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=merges, special_tokens={})

    def quick(text: str) -> list[int]:
        if any(token in text for token in added):
            return plain(text)
        try:
            return fast.encode_ordinary(text)
        except BaseException as e:
            # its regex engine gives up on some very long runs, with an exception type that it doesn't export
            if type(e).__name__ != "PanicException":
                raise
            return plain(text)

    return quick


def cut_documents(docs: DataFrame, tokenizer: str, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """Pieces of all documents: (doc_id, start, length, ids_crc32, doc_tokens, part, place).

    Null texts count as empty; every document has its end id, so none is
    without a piece.  (part, length, place) numbers the pieces of a length.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, seen = _encoder(tokenizer), TaskContext.get().partitionId(), Counter()
        for batch in blocks(batches):
            rows = []
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                ids = np.array([*encode(text or ""), end_id], dtype="<u4")
                for start in range(0, ids.size, window):
                    piece = ids[start : start + window]
                    rows.append((doc, start, piece.size, zlib.crc32(piece.tobytes()), ids.size, part, seen[piece.size]))
                    seen[piece.size] += 1
            kinds = [batch.column("doc_id").type, pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays(list(map(pa.array, zip(*rows, strict=True), kinds)), names)

    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "place"]
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, part int, place long")


def fullest(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """The multiset of lengths whose sum is the largest that is at most ``capacity``."""
    mask, reach = (2 << capacity) - 1, 1
    steps: list[tuple[int, int, int]] = []  # the sums before, the length, how many of it at once
    for length in sorted(counts, reverse=True):
        left, many = min(counts[length], capacity // length), 1
        while left > 0:
            many = min(many, left)
            steps.append((reach, length, many))
            reach |= reach << (length * many) & mask
            left, many = left - many, many * 2
        if reach >> capacity & 1:
            break
    total, out = reach.bit_length() - 1, Counter()
    for before, length, many in reversed(steps):
        if not before >> total & 1:
            out[length] += many
            total -= length * many
    return dict(out)


def plan(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[dict[int, int], int]]:
    """Fillings (length: count) and how often each is used, for all lengths below the window."""
    left = {n: c for n, c in histogram.items() if c and n < window}
    out = []
    while left:
        longest = max(left)
        others = {n: c - (n == longest) for n, c in left.items() if c > (n == longest)}
        filling = Counter(fullest(others, window - longest))
        filling[longest] += 1
        times = min(left[n] // c for n, c in filling.items())
        out.append((dict(filling), times))
        for n, c in filling.items():
            left[n] -= c * times
            if not left[n]:
                del left[n]
    return out


def place_pieces(pieces: DataFrame, window: int = WINDOW) -> DataFrame:
    """Adds sequence_id and offset to checkpointed pieces.

    A piece's rank among all of its length is its place in its part plus the
    pieces of earlier parts; the plan says which ranks of a length go where.
    """
    spark = pieces.sparkSession
    each = pieces.groupBy("part", "length").agg(F.count("*").alias("n"))
    earlier = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    before = each.select("part", "length", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))
    histogram = {r["length"]: r["n"] for r in each.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # a row for each length
    rows, used, sequences = [], Counter(), histogram.get(window, 0)
    if sequences:
        rows.append((window, 0, sequences, 1, 0, 0))
    for filling, times in plan(histogram, window):
        offset = 0
        for length, count in sorted(filling.items(), reverse=True):
            rows.append((length, used[length], used[length] + count * times, count, sequences, offset))
            used[length] += count * times
            offset += length * count
        sequences += times
    ways = spark.createDataFrame(rows or [(-1, 0, 0, 1, 0, 0)], "length long, low long, high long, many long, first long, base long")
    ranked = pieces.join(before, ["part", "length"]).withColumn("rank", F.col("place") + F.col("before"))
    within = F.col("rank") - F.col("low")
    # the plan has a bounded number of rows: it depends on the lengths, of which there are at most as many as tokens in a window
    return ranked.join(F.broadcast(ways), (ranked["length"] == ways["length"]) & F.col("rank").between(F.col("low"), F.col("high") - 1)).select(
        "doc_id", "start", ranked["length"], "ids_crc32", "doc_tokens",
        (F.col("first") + F.floor(within / F.col("many"))).cast("long").alias("sequence_id"),
        (F.col("base") + within % F.col("many") * ranked["length"]).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, tokenizer: str, window: int = WINDOW, end_id: int = END_ID) -> DataFrame:
    """All pieces of all documents with their sequence and offset; see the module's text."""
    return place_pieces(checkpointed(cut_documents(docs, tokenizer, window, end_id)), window)
