"""Quality classifier: a factorisation machine on hashed words, structure and metadata.

A text's features are its distinct words (hashed), statistics of its structure
(each put into one of a fixed number of buckets) and metadata columns (their
buckets too).  The machine scores

    w0 + sum w_i x_i + 1/2 sum_f ((sum v_if x_i)^2 - sum (v_if x_i)^2)

so that all pairwise interactions cost time linear in the features.  It is
trained in numpy by AdaGrad on the logistic loss, on a bounded sample of
labelled rows; scoring runs on the executors over whole texts.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks, checkpointed, doc_hash, drop_checkpoint, space_words, texts

#: Hash buckets of words.
WORDS = 1 << 16
#: Buckets of each statistic.
STEPS = 24
FACTORS = 8
#: Text bytes that are scored at a time; each feature takes a row of factors.
SCORED_BYTES = 4 << 20
#: Most labelled rows that training takes: those with the smallest hash of their id.
SAMPLE_ROWS = 12_000
#: Most features of the rows that training takes: rows are left out from the largest hash on.  Twelve bytes each reach the driver.
SAMPLE_FEATURES = 20_000_000

STATISTICS = ("length", "words", "word_length", "distinct", "upper", "digit", "symbol", "space", "non_ascii", "lines", "repeated_lines", "odd_ends", "lone_symbols", "commonest", "repeats")

_UPPER = np.zeros(256, bool)
_UPPER[ord("A") : ord("Z") + 1] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[ord("0") : ord("9") + 1] = True
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LETTER = _UPPER.copy()
_LETTER[ord("a") : ord("z") + 1] = True
_SYMBOL = ~(_LETTER | _DIGIT | _SPACE)
_SYMBOL[128:] = False
_SYMBOL[[ord("."), ord(",")]] = False
#: A word that ends in two symbols, or is none but symbols.
_ODD_END = re.compile(rb"[!-/:-@\[-`{-~]{2}(?=[\x09-\x0d ]|\Z)")
_LONE = re.compile(rb"(?<![^\x09-\x0d ])[!-/:-@\[-`{-~]+(?![^\x09-\x0d ])")


def statistics(text: bytes, words: list[bytes], counted: Counter) -> list[float]:
    """Values between 0 and 1, as listed in STATISTICS."""
    n, w = max(len(text), 1), max(len(words), 1)
    counts = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    rows = text.split(b"\n")
    same = sum(a == b for a, b in zip(words, words[1:], strict=False))
    most = max(counted.values(), default=0) / w
    return [
        np.log1p(len(text)) / 16, np.log1p(len(words)) / 14, min(len(text) / w / 24, 1), len(counted) / w,
        counts[_UPPER].sum() / n, counts[_DIGIT].sum() / n * 4, min(counts[_SYMBOL].sum() / n * 3, 1), counts[_SPACE].sum() / n * 2,
        counts[128:].sum() / n, np.log1p(len(rows)) / 10, 1 - len(set(rows)) / len(rows),
        len(_ODD_END.findall(text)) / w, len(_LONE.findall(text)) / w, most, same / w,
    ]


def features(text: bytes, metadata: list[float | None]) -> tuple[np.ndarray, np.ndarray]:
    """Indices and values; metadata: one value between 0 and 1 for each column, or None."""
    words = space_words(text)
    counted = Counter(words)
    hashed = np.fromiter(map(crc32, counted), np.int64, len(counted)) & (WORDS - 1)
    hashed.sort()
    stats = [*statistics(text, words, counted), *metadata]
    steps = [WORDS + k * (STEPS + 1) + (STEPS if v is None else min(int(v * STEPS), STEPS - 1)) for k, v in enumerate(stats)]
    values = np.empty(hashed.size + len(steps), np.float32)
    values[: hashed.size] = 1 / np.sqrt(max(hashed.size, 1))
    values[hashed.size :] = 1 / np.sqrt(len(steps))
    return np.concatenate([hashed, np.array(steps, np.int64)]).astype(np.int32), values


def size_of(metadata: int) -> int:
    return WORDS + (len(STATISTICS) + metadata) * (STEPS + 1)


@dataclass
class FactorisationMachine:
    bias: float
    weights: np.ndarray
    factors: np.ndarray

    @classmethod
    def fresh(cls, size: int, seed: int = 7) -> FactorisationMachine:
        draw = np.random.default_rng(seed)
        return cls(0.0, np.zeros(size, np.float32), draw.normal(0, 0.05, (size, FACTORS)).astype(np.float32))

    def raw(self, index: np.ndarray, value: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Scores of rows that begin at ``starts``; none may be empty."""
        linear = np.add.reduceat(self.weights[index] * value, starts)
        vx = self.factors[index] * value[:, None]
        sums = np.add.reduceat(vx, starts, axis=0)
        squares = np.add.reduceat(np.einsum("ij,ij->i", vx, vx), starts)
        return self.bias + linear + 0.5 * ((sums**2).sum(axis=1) - squares)

    def fit(self, index: np.ndarray, value: np.ndarray, starts: np.ndarray, labels: np.ndarray, epochs: int = 6, batch: int = 128, rate: float = 0.15, decay: float = 1e-5, seed: int = 7) -> FactorisationMachine:
        """AdaGrad on the logistic loss over rows in a seeded random order."""
        draw, ends = np.random.default_rng(seed), np.r_[starts[1:], index.size]
        # the rarer label weighs more, by the root of the ratio
        ratio = np.sqrt(max((labels > 0.5).sum(), 1) / max((labels < 0.5).sum(), 1))
        cost = np.where(labels > 0.5, min(1 / ratio, 5.0) if ratio < 1 else 1.0, min(ratio, 5.0) if ratio > 1 else 1.0)
        gw, gv, gb = np.full(self.weights.shape, 1e-3, np.float32), np.full(self.factors.shape, 1e-3, np.float32), 1e-3
        for _ in range(epochs):
            order = draw.permutation(starts.size)
            for k in range(0, order.size, batch):
                rows = order[k : k + batch]
                sizes = ends[rows] - starts[rows]
                first = np.cumsum(sizes) - sizes
                take = np.repeat(starts[rows] - first, sizes) + np.arange(sizes.sum())
                i, x = index[take], value[take]
                vx = self.factors[i] * x[:, None]
                sums = np.add.reduceat(vx, first, axis=0)
                squares = np.add.reduceat(np.einsum("ij,ij->i", vx, vx), first)
                out = self.bias + np.add.reduceat(self.weights[i] * x, first) + 0.5 * ((sums**2).sum(axis=1) - squares)
                error = ((1 / (1 + np.exp(-out)) - labels[rows]) * cost[rows]).astype(np.float32) / rows.size
                each = np.repeat(error, sizes) * x
                dv = each[:, None] * (np.repeat(sums, sizes, axis=0) - vx)
                by = np.argsort(i, kind="stable")
                same = np.flatnonzero(np.r_[True, np.diff(i[by]) > 0])
                at = i[by][same]
                dw = np.add.reduceat(each[by], same) + decay * self.weights[at]
                dv = np.add.reduceat(dv[by], same, axis=0) + decay * self.factors[at]
                gw[at] += dw**2
                gv[at] += dv**2
                self.weights[at] -= rate * dw / np.sqrt(gw[at])
                self.factors[at] -= rate / 3 * dv / np.sqrt(gv[at])
                gb += float(error.sum()) ** 2
                self.bias -= rate * float(error.sum()) / gb**0.5
        return self


def _metadata(columns: list[str]) -> list[Column]:
    """Numeric columns as log-scaled values between 0 and 1; null stays null."""
    # least and greatest pass over nulls, so null is asked for first
    scaled = lambda c: F.least(F.log1p(F.greatest(F.col(c).cast("double"), F.lit(0.0))) / F.lit(16.0), F.lit(1.0))
    return [F.when(F.col(c).isNotNull(), scaled(c)).alias(f"m{k}") for k, c in enumerate(columns)]


def _rows(batch: pa.RecordBatch, metadata: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    found = [features(t, list(m)) for t, *m in zip(texts(batch.column("text")), *(batch.column(f"m{k}").to_pylist() for k in range(metadata)), strict=True)]
    sizes = np.array([i.size for i, _ in found])
    return np.concatenate([i for i, _ in found]), np.concatenate([v for _, v in found]), np.cumsum(sizes) - sizes


def train(docs: DataFrame, labels: DataFrame, metadata: list[str], sample_rows: int = SAMPLE_ROWS, label: str = "quality", sample_features: int = SAMPLE_FEATURES) -> FactorisationMachine:
    """Fits on at most ``sample_rows`` labelled ids (the smallest hashes of their id) with ``sample_features`` features in all, which come to the driver.

    An id with several labels counts by their mean, one with several rows by
    the smallest text (null first).  Without any label the
    machine scores one half everywhere.
    """
    chosen = (
        labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).groupBy("doc_id").agg(F.avg(label).alias("y"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    )
    rows = docs.select("doc_id", "text", *_metadata(metadata))
    n = len(metadata)
    # bounded by sample_rows; an id may repeat in any number of rows, so one is chosen before anything is collected
    one = F.min(F.struct("text", *(f"m{k}" for k in range(n)))).alias("row")
    joined = rows.join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "y").agg(one).select("doc_id", "y", "row.*")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=SCORED_BYTES):
            index, value, starts = _rows(batch, n)
            cut = np.r_[starts, index.size].astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("y"), pa.ListArray.from_arrays(cut, index), pa.ListArray.from_arrays(cut, value)], ["doc_id", "y", "index", "value"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    found = checkpointed(joined.mapInArrow(run, f"doc_id {kind}, y double, index array<int>, value array<float>"))
    # the rows' sizes, at most sample_rows, say where the features stop
    sizes = sorted(found.select(F.xxhash64("doc_id").alias("h"), "doc_id", F.size("index").alias("n")).collect())
    total, last = 0, None
    for r in sizes:
        total += r["n"]
        if total > sample_features:
            break
        last = r
    if last is None:
        return FactorisationMachine.fresh(size_of(n))
    place = F.struct(F.xxhash64("doc_id").alias("h"), "doc_id")
    got = found.where(place <= F.struct(F.lit(last["h"]).alias("h"), F.lit(last["doc_id"]).cast(kind).alias("doc_id"))).toArrow().combine_chunks()
    drop_checkpoint(found)
    model = FactorisationMachine.fresh(size_of(n))
    if not got.num_rows:
        return model
    got = got.sort_by("doc_id")
    index, value = got.column("index").combine_chunks(), got.column("value").combine_chunks()
    return model.fit(index.flatten().to_numpy(), value.flatten().to_numpy(), index.offsets.to_numpy()[:-1].astype(np.int64), (got.column("y").to_numpy() >= 0.5).astype(np.float32))


def _scores(model: FactorisationMachine, batch: pa.RecordBatch, metadata: int) -> np.ndarray:
    index, value, starts = _rows(batch, metadata)
    return 1 / (1 + np.exp(-model.raw(index, value, starts).astype(np.float64)))


def score(docs: DataFrame, model: FactorisationMachine, metadata: list[str], held_out: Column) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row; null texts score like empty ones."""
    sent, n = docs.sparkSession.sparkContext.broadcast(model), len(metadata)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=SCORED_BYTES):
            s = _scores(sent.value, batch, n)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", held_out.alias("held_out"), "text", *_metadata(metadata))
    return rows.mapInArrow(run, f"doc_id {kind}, held_out boolean, score double, predicted int")


def held_out(doc_id: str = "doc_id") -> Column:
    return doc_hash(F.col(doc_id)) % 3 == 1


def classify(docs: DataFrame, labels: DataFrame, metadata: tuple[str, ...] = ("n_chars",)) -> DataFrame:
    """Learns from the labels of rows that aren't held out, and scores every row."""
    columns = [c for c in metadata if c in docs.columns]
    model = train(docs, labels.where(~held_out()), columns)
    return score(docs, model, columns, held_out())


def keep_good(docs: DataFrame, labels: DataFrame, metadata: tuple[str, ...] = ("n_chars",)) -> DataFrame:
    """Rows of ``docs``, all columns as they are, that are predicted good."""
    columns = [c for c in metadata if c in docs.columns]
    sent, n = docs.sparkSession.sparkContext.broadcast(train(docs, labels.where(~held_out()), columns)), len(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, limit=SCORED_BYTES):
            extra = [pa.array([None if v is None else min(np.log1p(max(float(v), 0.0)) / 16, 1.0) for v in batch.column(c).to_pylist()], pa.float64()) for c in columns]
            seen = pa.RecordBatch.from_arrays([batch.column("text"), *extra], ["text", *(f"m{k}" for k in range(n))])
            yield batch.filter(pa.array(_scores(sent.value, seen, n) >= 0.5))

    return docs.mapInArrow(run, docs.schema)
