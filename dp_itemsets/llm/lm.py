"""Language-model scoring with a gated recurrent network.

Tokens are lower-cased words and one end token a text.  The network is trained
in numpy by truncated backpropagation through time.  Its softmax is factored: a
class of the word, then the word in its class.  Words outside its short list
are one class member, and share that probability as the smoothed unigram model
divides it, so that scores are log-probabilities of texts over an open
vocabulary.  Scoring carries the hidden state through a whole text, however
long, many texts side by side.

Training begins on the driver, on one stretch of each document of a sample, so
that all tasks start from one network.  Then every task goes on from there with
all tokens of all its training texts, and the networks are averaged by the
tokens that they saw.  Every training token of the corpus takes part in this.

The unigram base counts every training token of the corpus exactly.  Common
words of the sample (the head) are counted block by block and sent back as one
bounded table, all others are summed before they meet the texts that hold them.
The short list is the most frequent words of the corpus by these exact counts:
if the head lacks one of them, it is looked up in the texts, joins the head,
and the words are counted again.

Counting is the one pass that splits all texts into words.  It also writes the
number in the head of every token of every text; training and scoring read
these numbers and no text.
"""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat
from zlib import crc32

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks, checkpointed, doc_hash, drop_checkpoint, keep_heap, remove_folder, shared_folder, space_words, texts

#: No word holds white space, so none is this.
END = b"\n"
#: Classes of the short list, and words in each; the last word stands for all others.
CLASSES, MEMBERS = 32, 32
UNITS = 16
#: Documents of the sample that the head comes from and training begins on: those with the smallest hash of their id.
SAMPLE_DOCS = 4_000
#: Tokens of a stretch of a sampled text.
STRETCH = 256
#: Parallel streams of training, steps of a window of backpropagation, and windows of a batch of texts.
STREAMS, STEPS, WINDOWS = 64, 16, 16
#: A task doubles its streams from batch to batch up to this number.
MOST_STREAMS = 512
#: Learning rates of the driver's pass and of the tasks'.
RATE, OWN_RATE = 4e-3, 2e-3
#: Most words of the head, and most bytes of one.
HEAD, HEAD_BYTES = 200_000, 64
SMOOTH = 0.1
#: Bytes of token numbers, 4 each, whose documents are scored side by side, and that a training task takes at a time.
SCORED_BYTES, LEARNT_BYTES = 20 << 20, 4 << 20
#: Tasks in which networks are summed before they come to the driver.
SUMMED = 32

OTHER = CLASSES * MEMBERS - 1
LOG10 = np.log(10.0)


def _sigmoid(x: np.ndarray) -> None:
    """In place; the exponential's overflow gives the right limit, 0."""
    np.negative(x, out=x)
    with np.errstate(over="ignore"):
        np.exp(x, out=x)
    x += 1
    np.reciprocal(x, out=x)


@dataclass
class Gru:
    """Parameters by name: inputs e (words, 3 * units), recurrent u, gate bias b, class c and cb, members m and mb."""

    p: dict[str, np.ndarray]

    @classmethod
    def fresh(cls, units: int = UNITS, seed: int = 5) -> Gru:
        draw = np.random.default_rng(seed)
        shapes = {"e": (CLASSES * MEMBERS, 3 * units), "u": (units, 3 * units), "b": (3 * units,), "c": (units, CLASSES), "cb": (CLASSES,), "m": (CLASSES, units, MEMBERS), "mb": (CLASSES, MEMBERS)}
        scale = {"e": 0.1, "u": units**-0.5, "c": 0.1, "m": 0.1}
        return cls({k: (draw.normal(0, scale[k], s) if k in scale else np.zeros(s)).astype(np.float32) for k, s in shapes.items()})

    def from_shares(self, shares: np.ndarray) -> Gru:
        """Sets the output biases so that training begins at given probabilities of the short list, the other words' last."""
        p = np.full((CLASSES, MEMBERS), 1e-9)
        p.ravel()[: shares.size - 1], p.ravel()[OTHER] = np.maximum(shares[:-1], 1e-9), max(shares[-1], 1e-9)
        self.p["cb"][:] = np.log(p.sum(axis=1))
        self.p["mb"][:] = np.log(p / p.sum(axis=1, keepdims=True))
        return self

    @property
    def units(self) -> int:
        return self.p["u"].shape[0]

    def _inputs(self) -> np.ndarray:
        """(3 * units, words): what each word adds to the gates."""
        return np.ascontiguousarray((self.p["e"] + self.p["b"]).T)

    def _advance(self, x: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, ...]:
        """The state after a token, the gates z and reset, and the inner and new state; a text is a column, x its column of inputs."""
        n = self.units
        r = self.p["u"].T @ h
        gates = np.add(x[: 2 * n], r[: 2 * n])
        _sigmoid(gates)
        new = gates[n:] * r[2 * n :]
        new += x[2 * n :]
        new *= 2  # tanh(x) = 2 * sigmoid(2 * x) - 1
        _sigmoid(new)
        new *= 2
        new -= 1
        h = h - new
        h *= gates[:n]
        h += new
        return h, gates[:n], gates[n:], r[2 * n :], new

    def step(self, h: np.ndarray, token: np.ndarray) -> tuple[np.ndarray, ...]:
        return tuple(v.T for v in self._advance(self._inputs().take(token, axis=1), np.ascontiguousarray(h.T)))

    def log_probabilities(self, h: np.ndarray, target: np.ndarray) -> np.ndarray:
        """Natural log-probability of each target after its hidden state."""
        return self._log_probabilities(np.ascontiguousarray(h.T), target)

    def _members(self, h: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, list[tuple[int, slice]]]:
        """Scores of the members of each state's class, and the places of each class; states are columns in the order of their classes."""
        ends = np.searchsorted(group, np.arange(CLASSES), "right")
        places = [(k, slice(int(ends[k - 1]) if k else 0, int(ends[k]))) for k in range(CLASSES)]
        places = [(k, s) for k, s in places if s.stop > s.start]
        out = np.empty((MEMBERS, group.size), h.dtype)
        for k, s in places:
            np.add(self.p["m"][k].T @ h[:, s], self.p["mb"][k][:, None], out=out[:, s])
        return out, places

    def _log_probabilities(self, h: np.ndarray, target: np.ndarray) -> np.ndarray:
        group, member = np.divmod(target.astype(np.int16), MEMBERS)
        order = np.argsort(group, kind="stable")
        group, at = group[order], np.arange(target.size)
        h = h.take(order, axis=1, mode="clip")
        scores = self.p["c"].T @ h
        scores += self.p["cb"][:, None]
        inside, _ = self._members(h, group)
        got = np.zeros(target.size)
        for v, own in ((scores, group), (inside, member[order])):
            v -= v.max(axis=0)
            got += v[own, at]
            np.exp(v, out=v)
            got -= np.log(v.sum(axis=0))
        out = np.empty(target.size)
        out[order] = got
        return out

    def _gradient(self, h0: np.ndarray, inputs: np.ndarray, targets: np.ndarray, end: int) -> tuple[dict[str, np.ndarray], np.ndarray, float]:
        """Gradients over one window (steps, streams), the state after it, and the summed loss.  Inside, a token is a column."""
        p, n, (steps, streams), size = self.p, self.units, inputs.shape, inputs.size
        kind, table = p["u"].dtype, self._inputs()
        went = (inputs != end).astype(kind)
        before, hs, z, reset, inner, new = np.empty((6, n, steps, streams), kind)
        h = h0.T
        for t in range(steps):
            before[:, t] = h * went[t]  # a text begins with an empty state
            h, z[:, t], reset[:, t], inner[:, t], new[:, t] = self._advance(table.take(inputs[t], axis=1, mode="clip"), before[:, t])
            hs[:, t] = h
        group, member = np.divmod(targets.reshape(-1).astype(np.int16), MEMBERS)
        order, at = np.argsort(group, kind="stable"), np.arange(size)
        group, member = group[order], member[order]
        states = hs.reshape(n, size).take(order, axis=1, mode="clip")
        scores = p["c"].T @ states
        scores += p["cb"][:, None]
        inside, places = self._members(states, group)
        loss = 0.0
        for v, own in ((scores, group), (inside, member)):
            v -= v.max(axis=0)
            np.exp(v, out=v)
            v /= v.sum(axis=0)
            loss -= float(np.log(v[own, at]).sum())
            v[own, at] -= 1
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["c"], g["cb"], back = states @ scores.T, scores.sum(axis=1), p["c"] @ scores
        for k, s in places:
            g["m"][k], g["mb"][k] = states[:, s] @ inside[:, s].T, inside[:, s].sum(axis=1)
            back[:, s] += p["m"][k] @ inside[:, s]
        place = np.empty(size, np.intp)
        place[order] = at
        dh = back.take(place, axis=1, mode="clip").reshape(n, steps, streams)
        by_new = (1 - z) * (1 - new * new)
        by_z = (before - new) * z * (1 - z)
        by_reset = by_new * inner * reset * (1 - reset)
        dr, dnew, carry = np.empty((3 * n, steps, streams), kind), np.empty((n, steps, streams), kind), 0
        for t in range(steps - 1, -1, -1):
            d = dh[:, t]
            d += carry
            np.multiply(d, by_z[:, t], out=dr[:n, t])
            np.multiply(d, by_reset[:, t], out=dr[n : 2 * n, t])
            np.multiply(d, by_new[:, t], out=dnew[:, t])
            np.multiply(dnew[:, t], reset[:, t], out=dr[2 * n :, t])
            carry = p["u"] @ dr[:, t]
            d *= z[:, t]
            carry += d
            carry *= went[t]
        g["u"] = before.reshape(n, size) @ dr.reshape(3 * n, size).T
        dr[2 * n :] = dnew
        dx, token = dr.reshape(3 * n, size), inputs.reshape(-1)
        g["b"] = dx.sum(axis=1)
        g["e"][OTHER] = dx @ (token == OTHER).astype(kind)
        # sums by word: of each class's tokens, by a matrix that marks their members
        group, member = np.divmod(token.astype(np.int16), MEMBERS)
        group[token == OTHER] = CLASSES
        order = np.argsort(group, kind="stable")
        ends = np.searchsorted(group[order], np.arange(CLASSES), "right")
        order = order[: ends[-1]]
        marks = np.zeros((order.size, MEMBERS), kind)
        marks[at[: order.size], member[order]] = 1
        dx = dx.take(order, axis=1, mode="clip")
        for k, (a, b) in enumerate(zip([0, *ends[:-1]], ends, strict=True)):
            if b > a:
                g["e"][k * MEMBERS : (k + 1) * MEMBERS] += (dx[:, a:b] @ marks[a:b]).T
        return g, h.T, loss

    def fit(self, tokens: np.ndarray, end: int, passes: int = 1, streams: int = STREAMS, window: int = STEPS, rate: float = RATE) -> Gru:
        """Adam over windows of parallel streams; tokens: stretches one after another."""
        length = tokens.size // streams
        if length < 2:
            streams, length = 1, tokens.size
        if not length:
            return self
        grid = tokens[: streams * length].reshape(streams, length).T
        own = Adam(self, passes * (-(-length // window)), rate)
        for _ in range(passes):
            h, last = np.zeros((streams, self.units), np.float32), np.full(streams, end)
            for t in range(0, length, window):
                h, last = own.step(grid[t : t + window], h, last, end)
        return self

    def score(self, docs: list[np.ndarray], end: int, chunk: int = 1 << 13) -> np.ndarray:
        """Log10-probability of each text (short-list ids, the end token last), state carried from its first to its last token."""
        sizes = np.array([d.size for d in docs], np.int64)
        order = np.argsort(-sizes, kind="stable")
        flat = np.concatenate([docs[k] for k in order])
        sizes = sizes[order]
        starts = np.cumsum(sizes) - sizes
        out, h, table = np.zeros(len(docs)), np.zeros((self.units, len(docs)), self.p["u"].dtype), self._inputs()
        shrink = np.searchsorted(-sizes, -np.arange(int(sizes[0])), "left")  # texts longer than t
        states, targets, whose, held = [], [], [], 0
        token = np.full(len(docs), end)

        def settle() -> None:
            got = self._log_probabilities(np.concatenate(states, axis=1), np.concatenate(targets))
            out[:] += np.bincount(np.concatenate(whose), got, len(docs))

        for t in range(int(sizes[0])):
            n = int(shrink[t])
            h, *_ = self._advance(table.take(token[:n], axis=1, mode="clip"), h[:, :n])
            token = flat[starts[:n] + t]
            states.append(h)
            targets.append(token)
            whose.append(np.arange(n))
            held += n
            if held >= chunk:
                settle()
                states, targets, whose, held = [], [], [], 0
        if held:
            settle()
        result = np.empty(len(docs))
        result[order] = out / LOG10
        return result


class Adam:
    """The moments of a network in training."""

    def __init__(self, net: Gru, steps: int | None = None, rate: float = RATE):
        self.net, self.steps, self.rate, self.done = net, steps, rate, 0
        self.first, self.second = ({k: np.zeros_like(v) for k, v in net.p.items()} for _ in range(2))

    def step(self, targets: np.ndarray, h: np.ndarray, last: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
        """One update on a window (steps, streams); the state and the tokens after it.  With a known number of steps the rate falls to a tenth."""
        g, h, _ = self.net._gradient(h, np.concatenate([last[None], targets[:-1]]), targets, end)
        self.done += 1
        size = np.sqrt(sum(float((v**2).sum()) for v in g.values())) / targets.size
        slow = self.rate * (1 - 0.9 * self.done / self.steps if self.steps else 1)
        for k, v in g.items():
            v = v / targets.size * min(1.0, 1 / max(size, 1e-9))
            self.first[k] += 0.1 * (v - self.first[k])
            self.second[k] += 0.01 * (v**2 - self.second[k])
            self.net.p[k] -= slow * (self.first[k] / (1 - 0.9**self.done)) / (np.sqrt(self.second[k] / (1 - 0.99**self.done)) + 1e-8)
        return h, targets[-1]


@dataclass
class Model:
    """The head's words, the most frequent in training first, and the network."""

    head: list[bytes]
    gru: Gru


def held_out(doc_id: str = "doc_id") -> Column:
    return doc_hash(F.col(doc_id)) % 10 == 0


def sampled(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """(doc_id, text) of a bounded sample of ids that aren't held out; of an id's rows the smallest text stands for it."""
    chosen = docs.select("doc_id").where(~held_out() & F.col("doc_id").isNotNull()).distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs)
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"))


def head_words(sample: DataFrame, most: int = HEAD) -> list[bytes]:
    """The most frequent words of the sample's whole texts that occur twice or more, and the end."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            found: Counter = Counter()
            for t in texts(batch.column("text")):
                found.update(w for w in space_words(t) if len(w) <= HEAD_BYTES)
            yield pa.RecordBatch.from_arrays([pa.array(found.keys(), pa.binary()), pa.array(found.values(), pa.int64())], ["word", "n"])

    counted = sample.mapInArrow(count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).where("n > 1")
    return [END, *(bytes(r["word"]) for r in counted.orderBy(F.desc("n"), "word").limit(most).collect())]


def by_count(head: list[bytes], counts: np.ndarray) -> tuple[list[bytes], np.ndarray]:
    """The head by exact count; the end stays in the short list."""
    order = sorted(range(len(head)), key=lambda k: (-counts[k], head[k]))
    if head.index(END) not in order[:OTHER]:
        order.remove(head.index(END))
        order.insert(0, head.index(END))
    return [head[k] for k in order], counts[order]


def short_ids(head: list[bytes]) -> dict[bytes, int]:
    return {w: k for k, w in enumerate(head[:OTHER])}


def token_ids(words: list[bytes], ids: dict[bytes, int], unknown: int = OTHER) -> np.ndarray:
    """Ids of the words; the end isn't added."""
    return np.fromiter(map(ids.get, words, repeat(unknown)), np.int32, len(words))


def numbers(words: list[bytes], ids: dict[bytes, int]) -> np.ndarray:
    """Places in the head of the words and, last, of the end; -1 for other words."""
    out = np.empty(len(words) + 1, np.int32)
    out[:-1], out[-1] = token_ids(words, ids, -1), ids[END]
    return out


def joined(tokens: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of all texts one after another, and how many each has."""
    tokens = tokens.cast(pa.binary())
    sizes = pc.binary_length(tokens).to_numpy(zero_copy_only=False).astype(np.int64) // 4
    offsets = np.frombuffer(tokens.buffers()[1], np.int32)
    return np.frombuffer(tokens.buffers()[2], np.int32, int(sizes.sum()), int(offsets[tokens.offset])), sizes


def stretch(text: bytes, ids: dict[bytes, int]) -> np.ndarray:
    """Short-list ids of one stretch of the text, drawn by the text's hash; the last one has the end."""
    words = space_words(text)
    n = len(words) // STRETCH + 1
    k = xxhash.xxh64_intdigest(b"%d:-1" % _key(text)) % n
    part = token_ids(words[k * STRETCH : (k + 1) * STRETCH], ids)
    return np.append(part, ids[END]) if k == n - 1 else part


def first_network(sample: DataFrame, head: list[bytes], shares: np.ndarray | None = None) -> Gru:
    """Trains on one stretch of each sampled document, in the order of their ids' hash; shares: unigram probabilities of the short list and of all others."""
    ids = short_ids(head)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            rows = [stretch(t, ids) for t in texts(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("place"), pa.array(rows, pa.list_(pa.int16()))], ["place", "tokens"])

    # STRETCH + 1 small numbers for each of the sampled documents
    rows = sample.select(F.xxhash64("doc_id", F.lit(3)).alias("place"), "text").mapInArrow(cut, "place long, tokens array<short>").toArrow()
    order = np.argsort(rows.column("place").to_numpy(), kind="stable")
    parts = rows.column("tokens").take(pa.array(order)).to_pylist()
    tokens = np.array([x for p in parts for x in p], np.int64)
    return (Gru.fresh() if shares is None else Gru.fresh().from_shares(shares)).fit(tokens, ids[END])


def learn(adam: Adam, tokens: np.ndarray, end: int, most: int) -> int:
    """Updates on windows of at most so many parallel streams; what doesn't fill them is learnt in fewer.  Returns the number of tokens."""
    left = tokens
    while left.size:
        streams = min(most, max(left.size // STEPS, 1))
        length = left.size // streams
        grid, left = left[: streams * length].reshape(streams, length).T, left[streams * length :]
        h, last = np.zeros((streams, adam.net.units), np.float32), np.full(streams, end)
        for t in range(0, length, STEPS):
            h, last = adam.step(grid[t : t + STEPS], h, last, end)
    return tokens.size


def refined(docs: DataFrame, model: Model) -> tuple[Gru, int]:
    """``learnt`` from the texts of the rows that aren't held out."""
    sent = docs.sparkSession.sparkContext.broadcast(model.head)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = {w: k for k, w in enumerate(sent.value)}
        for batch in blocks(batches):
            yield pa.RecordBatch.from_arrays([pa.array([numbers(space_words(t), ids).tobytes() for t in texts(batch.column("text"))], pa.binary())], ["tokens"])

    return learnt(docs.where(~held_out()).select("text").mapInArrow(split, "tokens binary"), model, np.arange(len(model.head)))


def learnt(tokens: DataFrame, model: Model, moved: np.ndarray) -> tuple[Gru, int]:
    """The network after every task has gone on training on its part of the rows, and the number of tokens that it learnt from.

    moved: the place in the model's head of each number.  A task takes all
    tokens of its texts in batches and makes one update a window; networks are
    averaged by tokens.  A retried task reads the same rows and makes the same
    network.  A task with less than a batch adds what it has.
    """
    spark = tokens.sparkSession
    # the last one is for number -1
    sent = spark.sparkContext.broadcast((model.gru, np.append(np.minimum(moved, OTHER), OTHER).astype(np.int32), model.head.index(END)))
    names, shapes = list(model.gru.p), {k: v.shape for k, v in model.gru.p.items()}

    def go_on(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_heap()
        first, short, end = sent.value
        net = Gru({k: v.copy() for k, v in first.p.items()})
        adam, left, seen, most = Adam(net, None, OWN_RATE), np.empty(0, np.int32), 0, STREAMS
        for batch in blocks(batches, "tokens", LEARNT_BYTES):
            left = np.concatenate([left, short[joined(batch.column("tokens"))[0]]])
            while left.size >= (size := most * STEPS * WINDOWS):
                seen += learn(adam, left[:size], end, most)
                left, most = left[size:], min(2 * most, MOST_STREAMS)
        if left.size:
            seen += learn(adam, left, end, most)
        if seen:
            flat = np.concatenate([net.p[k].ravel() for k in names]).astype(np.float64) * seen
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId() % SUMMED], pa.int32()), pa.array([seen], pa.int64()), pa.array([flat.tobytes()], pa.binary())], ["part", "n", "p"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = None, 0
        for batch in batches:
            for k, p in zip(batch.column("n").to_pylist(), batch.column("p").to_pylist(), strict=True):
                own = np.frombuffer(p)
                total, n = own.copy() if total is None else total + own, n + k
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([n], pa.int64()), pa.array([total.tobytes()], pa.binary())], ["part", "n", "p"])

    schema = "part int, n long, p binary"
    rows = tokens.select("tokens").mapInArrow(go_on, schema)
    got = sorted((bytes(r["p"]), r["n"]) for r in rows.repartition(SUMMED, "part").mapInArrow(add, schema).collect())  # SUMMED rows at most
    sent.unpersist()
    if not got:
        return model.gru, 0
    seen = sum(n for _, n in got)
    mean, at, out = np.sum([np.frombuffer(p) for p, _ in got], axis=0) / seen, 0, {}
    for k in names:
        size = int(np.prod(shapes[k]))
        out[k] = mean[at : at + size].reshape(shapes[k]).astype(np.float32)
        at += size
    return Gru(out), seen


def train(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Model:
    """Head and first network, from the sample alone; the head is in the order of the sample."""
    sample = sampled(docs, sample_docs)
    head = head_words(sample)
    return Model(head, first_network(sample, head))


def _key(text: bytes) -> int:
    return int(np.uint64(xxhash.xxh64_intdigest(text)).view(np.int64))


def _checks(words: list[bytes]) -> np.ndarray:
    """31 bits of each word's checksum, and whether it is too long for the head."""
    n = len(words)
    return (np.fromiter(map(crc32, words), np.uint32, n) & np.uint32(0xFFFFFFFE) | (np.fromiter(map(len, words), np.int64, n) > HEAD_BYTES)).view(np.int32)


def _hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words)).view(np.int64)


#: Kinds of the rows of the counting pass.
IN_HEAD, OTHER_WORD, TEXT = 0, 1, 2


def _word_rows(docs: DataFrame, head: list[bytes]) -> DataFrame:
    """(kind, word, check, key, size, n, train, doc_id, held_out, tokens): a row for each head word of a block (word: its number), one for each other word of each text, and one for each text.

    n: tokens, of all copies of the text in the block; train: those in
    training; tokens: the numbers of a text's tokens.
    """
    sent = docs.sparkSession.sparkContext.broadcast(head)
    types = {"word": pa.int64(), "check": pa.int32(), "key": pa.int64(), "size": pa.int32(), "n": pa.int64(), "train": pa.int64()}

    def rows(every_type: dict[str, pa.DataType], kind: int, **cols) -> pa.RecordBatch:
        n = len(next(iter(cols.values())))
        arrays = [(v if isinstance(v := cols[k], pa.Array) else pa.array(v, t)) if k in cols else pa.nulls(n, t) for k, t in every_type.items()]
        return pa.RecordBatch.from_arrays([pa.array(np.full(n, kind, np.int8)), *arrays], ["kind", *every_type])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = {w: k for k, w in enumerate(sent.value)}
        for batch in blocks(batches):
            listed, outs = texts(batch.column("text")), batch.column("held_out")
            every_type = types | {"doc_id": batch.column("doc_id").type, "held_out": outs.type, "tokens": pa.binary()}
            copies: dict[bytes, list[int]] = {}
            for t, out in zip(listed, outs.to_pylist(), strict=True):
                got = copies.setdefault(t, [0, 0])
                got[0] += 1
                got[1] += not out
            keys, lengths = _hashes(copies), np.fromiter(map(len, copies), np.int32, len(copies))
            found, rare, times, of_text = [], [], [], []
            for t, (_, in_training) in copies.items():
                words = space_words(t)
                own = numbers(words, ids)
                found.append(own)
                unknown = Counter([words[k] for k in np.flatnonzero(own < 0).tolist()])
                rare += unknown
                times += unknown.values()
                of_text.append(len(unknown))
            every, sizes = np.concatenate(found), np.array([f.size for f in found])
            in_copies, in_training = np.array(list(copies.values()), np.int64).T
            common = np.bincount(every + 1, np.repeat(in_training, sizes), len(ids) + 1)[1:].astype(np.int64)
            seen = np.flatnonzero(common)
            yield rows(every_type, IN_HEAD, word=seen, train=common[seen])
            whose, times = np.repeat(np.arange(len(copies)), of_text), np.array(times, np.int64)
            yield rows(every_type, OTHER_WORD, word=_hashes(rare), check=_checks(rare), key=keys[whose], size=lengths[whose], n=times * in_copies[whose], train=times * in_training[whose])
            place = {t: k for k, t in enumerate(copies)}
            place = np.fromiter(map(place.get, listed), np.int64, len(listed))
            yield rows(every_type, TEXT, key=keys[place], size=lengths[place], doc_id=batch.column("doc_id"), held_out=outs, tokens=[found[k].tobytes() for k in place])

    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"kind byte, word long, check int, key long, size int, n long, train long, doc_id {kind}, held_out boolean, tokens binary"
    return docs.select("doc_id", held_out().alias("held_out"), "text").mapInArrow(run, schema)


@dataclass
class Counted:
    """counts: training tokens of each head word; others: (key, size, n, known, s) of each text with other words; missed: (hash, check) of other words that belong in the short list.

    n: tokens of other words in all copies of the text; known: those whose
    training count c is above 0; s: sum of log10(c + 0.1).
    tokens: (doc_id, held_out, key, size, tokens) of each row, from the folder,
    which goes with ``drop_folder``.
    """

    counts: np.ndarray
    others: DataFrame
    total: int
    distinct: int
    missed: list[tuple[int, int]]
    tokens: DataFrame
    folder: str

    def drop_folder(self) -> None:
        remove_folder(self.others.sparkSession, self.folder)


def count_words(docs: DataFrame, head: list[bytes]) -> Counted:
    """Exact counts of all words, and the numbers of all tokens.

    A word outside the head is its hash and checksum.  Its rows are summed on
    the way to one count, so a frequent one is no large group; then the counts
    join the rows, where the engine deals out a word that many texts hold.
    """
    spark = docs.sparkSession
    folder = f"{shared_folder(spark)}/words-{uuid.uuid4().hex}"
    _word_rows(docs, head).write.parquet(f"{folder}/rows")
    rows = spark.read.parquet(f"{folder}/rows")
    counts = np.zeros(len(head))
    for k, c in rows.where(F.col("kind") == IN_HEAD).groupBy("word").agg(F.sum("train")).toLocalIterator():  # a row for each word of the head
        counts[k] = c
    rare = rows.where(F.col("kind") == OTHER_WORD).select("word", "check", "key", "size", "n", "train")
    rare.groupBy("word", "check").agg(F.sum("train").alias("c")).where("c > 0").write.parquet(f"{folder}/counts")
    known = spark.read.parquet(f"{folder}/counts")
    total, distinct = known.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    least = float(np.sort(counts)[-OTHER]) if counts.size >= OTHER else 0.0
    above = known.where((F.col("check") % 2 == 0) & (F.col("c") > least)).orderBy(F.desc("c"), "word", "check").limit(OTHER)
    missed = [(r["word"], r["check"]) for r in above.select("word", "check").collect()]
    met = rare.join(known, ["word", "check"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    others = checkpointed(met.groupBy("key", "size").agg(
        F.sum("n").alias("n"), F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("known"), F.sum(F.col("n") * F.log10(F.col("c") + F.lit(SMOOTH))).alias("s"),
    ))
    tokens = rows.where(F.col("kind") == TEXT).select("doc_id", "held_out", "key", "size", "tokens")
    return Counted(counts, others, int(total + counts.sum()), int(distinct + (counts > 0).sum()), missed, tokens, folder)


def named(docs: DataFrame, missed: list[tuple[int, int]]) -> list[bytes]:
    """The words of these hashes and checks, from the texts that aren't held out."""
    wanted = set(missed)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            words = list({w for t in texts(batch.column("text")) for w in space_words(t) if len(w) <= HEAD_BYTES})
            found = [w for w, *own in zip(words, _hashes(words).tolist(), _checks(words).tolist(), strict=True) if tuple(own) in wanted]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.binary())], ["word"])

    return sorted(bytes(r["word"]) for r in docs.where(~held_out()).select("text").mapInArrow(find, "word binary").distinct().collect())


def count_all(docs: DataFrame, head: list[bytes]) -> tuple[list[bytes], Counted]:
    """The head, with any word that belongs in the short list, and all counts."""
    counted = count_words(docs, head)
    if counted.missed:
        drop_checkpoint(counted.others)
        counted.drop_folder()
        head = head + named(docs, counted.missed)
        counted = count_words(docs, head)
    return head, counted


def score_documents(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """One row per row of ``docs``: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Null texts count as empty: one end token.  Rows with one text share its scores.
    """
    spark = docs.sparkSession
    sample = sampled(docs, sample_docs)
    first, counted = count_all(docs, head_words(sample))
    total = counted.total
    head, counts = by_count(first, counted.counts)
    norm = float(np.log10(total + SMOOTH * (counted.distinct + 1)))
    logs = np.log10(counts + SMOOTH)
    shares = 10 ** (logs[:OTHER] - norm)
    outside = float(np.log10(max(1 - shares.sum(), 1e-12)))
    model = Model(head, first_network(sample, head, np.append(shares, 10**outside)))
    place = {w: k for k, w in enumerate(head)}
    moved = np.array([place[w] for w in first])
    gru, _ = learnt(counted.tokens.where(~F.col("held_out")), model, moved)
    # of each number, and of -1 at the end
    outer = np.append(moved >= OTHER, True)
    own_logs = np.append(logs[moved], 0.0)
    sent = spark.sparkContext.broadcast((gru, np.append(np.minimum(moved, OTHER), OTHER).astype(np.int16), np.append(counts[moved] > 0, False), own_logs, own_logs * outer, outer))
    end = head.index(END)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep_heap()
        net, short, *tables = sent.value
        for batch in blocks(batches, "tokens", SCORED_BYTES):
            flat, sizes = joined(batch.column("tokens"))
            starts = np.cumsum(sizes) - sizes  # each text has its end
            sums = [np.add.reduceat(x, starts, dtype=np.float64 if x.dtype.kind == "f" else np.int64) for x in (*(x[flat] for x in tables), flat < 0)]
            got = net.score(np.split(short[flat], starts[1:]), end)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in ("doc_id", "held_out", "key", "size")), *map(pa.array, (got, sizes, *sums))], names)

    names = ["doc_id", "held_out", "key", "size", "net", "n_tokens", "head_known", "head_logs", "other_logs", "others", "rare"]
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, held_out boolean, key long, size int, net double, n_tokens long, head_known long, head_logs double, other_logs double, others long, rare long"
    scored = checkpointed(counted.tokens.mapInArrow(run, schema))
    counted.drop_folder()
    both = scored.join(counted.others, ["key", "size"], "left")
    # a text's part of what all its copies have together
    part = F.when(F.col("rare") > 0, F.col("rare") / F.col("n")).otherwise(F.lit(0.0))
    known = F.round(F.coalesce(F.col("known") * part, F.lit(0.0))).cast("long")
    s = F.coalesce(F.col("s") * part, F.lit(0.0))
    return both.select(
        "doc_id", "held_out", "n_tokens", (F.col("head_known") + known).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (F.col("head_logs") + s - F.col("n_tokens") * F.lit(norm)).alias("base_score"),
        (F.col("net") + F.col("other_logs") + s - F.col("others") * F.lit(norm + outside)).alias("score"),
    )
