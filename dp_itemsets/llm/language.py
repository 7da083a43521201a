"""Language ID with segmentation-marginalised unigrams.

Each language has a probability for every piece of one fixed public
vocabulary.  A word's probability under a language is the sum over all ways to
cut it into pieces, computed by a forward pass; a text's is the product over
its words.  Piece probabilities are learned by expectation maximisation from
all words of a sample of documents, with the same lattice and a backward pass.

Words are lower-cased and begin with the vocabulary's word mark.  A character
outside the vocabulary is spelled in byte pieces.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks, checkpointed, doc_hash, drop_checkpoint

MARK = "▁"
#: Most different languages that can be learned.
MOST_LANGUAGES = 10_000
#: Expected number of sampled documents for a language.
SAMPLE_DOCS = 3_000
#: Rounds of expectation maximisation, and what is added to each expected count.
ROUNDS, SMOOTH = 4, 0.02
#: Characters of the stretches that training cuts long words into.
STRETCH = 48
#: Longest word that is scored side by side with others; longer ones take the same sum one by one.
LONGEST = 48
#: Log-probability below which a sum of products may have lost terms.
UNDERFLOW = -600.0
#: Bytes of probabilities of seen words that a worker keeps, and of a batch of lattices.
KEPT_BYTES, LATTICE_BYTES = 64 << 20, 64 << 20
#: Bytes of words whose lattices training holds at a time.
WORD_BYTES = 1 << 20


@dataclass
class Vocabulary:
    pieces: dict[str, int]
    longest: int
    chars: dict[str, list[int]] = field(default_factory=dict)

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces: dict[str, int] = {}
        for i in range(model.get_piece_size()):
            piece = model.id_to_piece(i)
            if not (model.is_control(i) or model.is_unknown(i)):
                # pieces that differ in case only are one
                pieces.setdefault(piece if model.is_byte(i) else piece.lower(), len(pieces))
        return cls(pieces, max(len(p) for p in pieces if not p.startswith("<0x")))

    def spelled(self, char: str) -> list[int]:
        """The byte pieces of a character."""
        if char not in self.chars:
            if len(self.chars) > 20_000:
                self.chars.clear()
            self.chars[char] = [self.pieces[f"<0x{b:02X}>"] for b in char.encode("utf-8", "surrogatepass")]
        return self.chars[char]

    def edges(self, word: str) -> list[tuple[int, int, tuple[int, ...]]]:
        """(start, end, pieces) of every piece in a marked word, by start."""
        out, get = [], self.pieces.get
        n = len(word)
        for a in range(n):
            one = get(word[a])
            out.append((a, a + 1, (one,) if one is not None else tuple(self.spelled(word[a]))))
            for b in range(a + 2, min(n, a + self.longest) + 1):
                piece = get(word[a:b])
                if piece is not None:
                    out.append((a, b, (piece,)))
        return out


class Lattice:
    """The edges of many words, grouped by where they end and by where they begin; all passes work on logarithms."""

    def __init__(self, words: list[str], vocabulary: Vocabulary):
        lengths, where, start, end, piece, extra = [], [], [], [], [], {}
        size = len(vocabulary.pieces)
        for k, word in enumerate(words):
            lengths.append(len(word))
            for a, b, pieces in vocabulary.edges(word):
                where.append(k)
                start.append(a)
                end.append(b)
                piece.append(pieces[0] if len(pieces) == 1 else size + extra.setdefault(pieces, len(extra)))
        self.lengths = np.array(lengths, np.int64)
        self.width = int(self.lengths.max()) + 1 if lengths else 1
        self.where, self.start, self.end, self.piece = (np.array(x, np.int64) for x in (where, start, end, piece))
        self.extra = list(extra)

    def _groups(self, place: np.ndarray) -> list[np.ndarray]:
        by = np.lexsort((self.where, place))
        return np.split(by, np.flatnonzero(np.diff(place[by])) + 1) if by.size else []

    def weights(self, table: np.ndarray) -> np.ndarray:
        """Log-probability of each edge; table: (pieces, languages) of logarithms."""
        spelled = np.array([table[list(p)].sum(axis=0) for p in self.extra]).reshape(-1, table.shape[1])
        return np.concatenate([table, spelled])[self.piece]

    def forward(self, weight: np.ndarray) -> np.ndarray:
        """(words, places, languages): log of the summed probability of all segmentations up to a place."""
        alpha = np.zeros((self.lengths.size, self.width, weight.shape[1]))
        for g in self._groups(self.end):
            own = self.where[g]
            first = np.flatnonzero(np.r_[True, np.diff(own) > 0])
            alpha[own[first], self.end[g[0]]] = np.logaddexp.reduceat(alpha[own, self.start[g]] + weight[g], first, axis=0)
        return alpha

    def totals(self, alpha: np.ndarray) -> np.ndarray:
        return alpha[np.arange(self.lengths.size), self.lengths]

    def expected(self, weight: np.ndarray, counts: np.ndarray, size: int) -> np.ndarray:
        """Expected piece counts for one language; weight: (edges, 1)."""
        alpha = self.forward(weight)
        beta = np.zeros(alpha.shape[:2])
        for g in self._groups(-self.start):
            own = self.where[g]
            first = np.flatnonzero(np.r_[True, np.diff(own) > 0])
            beta[own[first], self.start[g[0]]] = np.logaddexp.reduceat(beta[own, self.end[g]] + weight[g, 0], first)
        share = np.exp(alpha[self.where, self.start, 0] + weight[:, 0] + beta[self.where, self.end] - self.totals(alpha)[self.where, 0]) * counts[self.where]
        out = np.bincount(self.piece, share, size + len(self.extra))
        for k, pieces in enumerate(self.extra):
            np.add.at(out, list(pieces), out[size + k])
        return out[:size]


#: Odd multiplier of the rolling hash of substrings.
_BASE = 0x9E3779B97F4A7C15


class PieceIndex:
    """Finds the pieces at all places of many words at once, by rolling 64-bit hashes of their substrings."""

    def __init__(self, vocabulary: Vocabulary):
        plain = [(p, i) for p, i in vocabulary.pieces.items() if not p.startswith("<0x")]
        width = max(len(p) for p, _ in plain)
        rows = _code_points([p for p, _ in plain], width)
        prefix = _prefix_hashes(rows)
        sizes = np.array([len(p) for p, _ in plain])
        hashes = _sized(prefix[np.arange(len(plain)), sizes], sizes)
        order = np.argsort(hashes)
        self.hashes, self.ids = hashes[order], np.array([i for _, i in plain], np.int32)[order]
        self.powers = [pow(_BASE, size, 1 << 64) for size in range(width + 1)]
        self.seen = np.zeros(1 << 20, bool)
        self.seen[hashes >> np.uint64(44)] = True
        self.longest = width

    def find(self, rows: np.ndarray) -> list[np.ndarray]:
        """For each size from 1: ids of the pieces that begin at each place, or -1; rows: zero-padded code points."""
        prefix, out = _prefix_hashes(rows), []
        for size in range(1, min(self.longest, rows.shape[1]) + 1):
            h = _sized(prefix[:, size:] - prefix[:, :-size] * np.uint64(self.powers[size]), size)
            found = np.full(h.shape, -1, np.int32)
            maybe = np.nonzero(self.seen[h >> np.uint64(44)])
            wanted = h[maybe]
            at = np.minimum(np.searchsorted(self.hashes, wanted), self.hashes.size - 1)
            found[maybe] = np.where(self.hashes[at] == wanted, self.ids[at], -1)
            out.append(found)
        return out


def _code_points(words: list[str], width: int) -> np.ndarray:
    return np.array(words, dtype=f"<U{width}").view(np.uint32).reshape(len(words), width)


def _prefix_hashes(rows: np.ndarray) -> np.ndarray:
    out = np.zeros((rows.shape[0], rows.shape[1] + 1), np.uint64)
    for k in range(rows.shape[1]):
        out[:, k + 1] = out[:, k] * np.uint64(_BASE) + rows[:, k] + np.uint64(1)
    return out


def _sized(hashes: np.ndarray, size: np.ndarray | int) -> np.ndarray:
    """Mixes the substring's size in, and its low bits into the high ones."""
    mixed = (hashes ^ (np.asarray(size).astype(np.uint64) << np.uint64(57))) * np.uint64(0xBF58476D1CE4E5B9)
    return mixed ^ (mixed >> np.uint64(29)) ^ (mixed << np.uint64(32))


def long_word(word: str, vocabulary: Vocabulary, log_table: np.ndarray) -> np.ndarray:
    """Log-probabilities of one word of any length; only the last places of the forward pass are held."""
    ring: dict[int, np.ndarray] = {0: np.zeros(log_table.shape[1])}
    get = vocabulary.pieces.get
    for b in range(1, len(word) + 1):
        one = get(word[b - 1])
        ways = [ring[b - 1] + (log_table[one] if one is not None else log_table[vocabulary.spelled(word[b - 1])].sum(axis=0))]
        for a in range(max(0, b - vocabulary.longest), b - 1):
            piece = get(word[a:b])
            if piece is not None:
                ways.append(ring[a] + log_table[piece])
        ring[b] = ways[0] if len(ways) == 1 else np.logaddexp.reduce(ways)
        ring.pop(b - vocabulary.longest - 1, None)
    return ring[len(word)]


@dataclass
class LanguageModel:
    """table: (pieces, languages) of probabilities, each column a distribution without zeros."""

    vocabulary: Vocabulary
    languages: list[str]
    table: np.ndarray

    @classmethod
    def uniform(cls, vocabulary: Vocabulary, languages: list[str]) -> LanguageModel:
        size = len(vocabulary.pieces)
        return cls(vocabulary, languages, np.full((size, len(languages)), 1 / size))

    def expected(self, language: int, words: dict[str, int]) -> np.ndarray:
        """Expected piece counts of a language's words.

        A word of ``STRETCH`` characters or more is cut into stretches, so that
        the lattice of a clause without spaces stays small; no text is left out.
        """
        size, log_p = len(self.vocabulary.pieces), np.log(self.table[:, language : language + 1])
        counted: Counter = Counter()
        for w, n in words.items():
            marked = MARK + w
            for k in range(0, len(marked), STRETCH):
                counted[marked[k : k + STRETCH]] += n
        got, listed = np.zeros(size), sorted(counted)
        for k in range(0, len(listed), 4000):
            part = listed[k : k + 4000]
            lattice = Lattice(part, self.vocabulary)
            got += lattice.expected(lattice.weights(log_p), np.array([counted[w] for w in part], float), size)
        return got

    def updated(self, expected: np.ndarray, smooth: float = SMOOTH) -> LanguageModel:
        """The next model of expectation maximisation; expected: (pieces, languages)."""
        got = expected + smooth
        return LanguageModel(self.vocabulary, self.languages, got / got.sum(axis=0))

    @classmethod
    def fit(cls, vocabulary: Vocabulary, counts: dict[str, Counter], rounds: int = ROUNDS) -> LanguageModel:
        """Expectation maximisation for each language from its word counts, on one machine."""
        model = cls.uniform(vocabulary, sorted(counts))
        for _ in range(rounds):
            columns = [model.expected(k, counts[name]) for k, name in enumerate(model.languages)]
            model = model.updated(np.array(columns).T.reshape(len(vocabulary.pieces), len(columns)))
        return model

    def words(self, words: list[str], index: PieceIndex) -> np.ndarray:
        """(words, languages) log-probabilities: a forward pass over words of like lengths, side by side.

        Words whose probability leaves the range of a double under any language
        take the same sum again in logarithms, so that none has a floor.
        """
        n_languages = len(self.languages)
        out = np.zeros((len(words), n_languages))
        sizes = np.array([len(w) for w in words])
        order = np.argsort(sizes, kind="stable")
        step = max(16, min(2048, LATTICE_BYTES // (8 * (LONGEST + 1) * max(n_languages, 1))))
        for start in range(0, len(words), step):
            part = order[start : start + step]
            part = part[sizes[part] < LONGEST]
            if part.size:
                out[part] = self._forward([MARK + words[k] for k in part], sizes[part] + 1, index)
        log_table = None
        for k in np.flatnonzero((sizes >= LONGEST) | (out < UNDERFLOW).any(axis=1)):
            log_table = np.log(self.table) if log_table is None else log_table
            out[k] = long_word(MARK + words[k], self.vocabulary, log_table)
        return out

    def _forward(self, marked: list[str], sizes: np.ndarray, index: PieceIndex) -> np.ndarray:
        width = int(sizes.max())
        rows = _code_points(marked, width)
        found = index.find(rows)
        spelled = np.argwhere((found[0] < 0) & (np.arange(width) < sizes[:, None]))
        # the last row of the table is no piece; characters outside the vocabulary get rows of their own
        table = np.concatenate([self.table, np.zeros((1, self.table.shape[1]))])
        found = [np.where(f < 0, len(self.table), f) for f in found]
        if spelled.size:
            codes, back = np.unique(rows[spelled[:, 0], spelled[:, 1]], return_inverse=True)
            own = np.array([self.table[self.vocabulary.spelled(chr(c))].prod(axis=0) for c in codes])
            found[0][spelled[:, 0], spelled[:, 1]] = len(table) + back
            table = np.concatenate([table, own])
        alpha = np.zeros((width + 1, len(marked), table.shape[1]))
        alpha[0] = 1
        for end in range(1, width + 1):
            for size in range(1, min(end, len(found)) + 1):
                alpha[end] += alpha[end - size] * table[found[size - 1][:, end - size]]
        with np.errstate(divide="ignore"):
            return np.log(alpha[sizes, np.arange(len(marked))])


class Scorer:
    """Scores texts with one model, keeping the probabilities of words it has seen."""

    def __init__(self, model: LanguageModel):
        self.model, self.known, self.index = model, {}, PieceIndex(model.vocabulary)
        self.rows = np.zeros((1 << 12, len(model.languages)))
        self.most = max(1 << 12, KEPT_BYTES // (8 * max(len(model.languages), 1)))

    def texts(self, batch: list[str]) -> np.ndarray:
        counted = [Counter(t.lower().split()) for t in batch]
        fresh = list({w for c in counted for w in c}.difference(self.known))
        if len(self.known) + len(fresh) > self.most:
            self.known.clear()
            fresh = list({w for c in counted for w in c})
        base = len(self.known)
        if base + len(fresh) > len(self.rows):
            self.rows = np.concatenate([self.rows[:base], np.zeros((len(fresh) + base // 2, self.rows.shape[1]))])
        self.rows[base : base + len(fresh)] = self.model.words(fresh, self.index)
        self.known.update(zip(fresh, range(base, base + len(fresh)), strict=True))
        get, out = self.known.__getitem__, np.zeros((len(batch), self.rows.shape[1]))
        for k, c in enumerate(counted):
            if c:
                out[k] = np.fromiter(c.values(), float, len(c)) @ self.rows[np.fromiter(map(get, c), np.int64, len(c))]
        return out


def predict(model: LanguageModel, log_p: np.ndarray) -> tuple[list[int], np.ndarray]:
    """Best language of each row and its posterior under equal priors."""
    best = log_p.argmax(axis=1)
    return best, 1 / np.exp(log_p - log_p.max(axis=1, keepdims=True)).sum(axis=1)


def has_letter(text: str) -> bool:
    return any(c.isalpha() for c in text)


def sampled(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """About ``sample_docs`` documents of each language: those whose hashed id lies below the language's share."""
    rows = docs.groupBy("lang").agg(F.count("*").alias("n")).limit(MOST_LANGUAGES + 1).collect()
    if len(rows) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    sizes = docs.sparkSession.createDataFrame(rows, "lang string, n long")
    share = F.least(F.lit(1.0), F.lit(float(sample_docs)) / F.col("n"))
    place = F.pmod(F.xxhash64("doc_id"), F.lit(1_000_003)) / F.lit(1_000_003.0)
    return docs.join(F.broadcast(sizes), "lang").where(place < share).drop("n")  # a row for each language


def sampled_words(docs: DataFrame, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """(lang, word, n) of the sampled documents' whole texts; rows without text or lang are left out."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            got: dict[str, Counter] = {}
            for lang, text in zip(batch.column("lang").to_pylist(), batch.column("text").to_pylist(), strict=True):
                got.setdefault(lang, Counter()).update(text.lower().split())
            rows = [(lang, w, n) for lang, c in got.items() for w, n in c.items()]
            cols = zip(*rows, strict=True) if rows else [()] * 3
            yield pa.RecordBatch.from_arrays(list(map(pa.array, cols, (pa.string(), pa.string(), pa.int64()))), ["lang", "word", "n"])

    known = sampled(docs.select("doc_id", "text", "lang").where("lang is not null and text is not null"), sample_docs)
    return known.select("lang", "text").mapInArrow(count, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def train(docs: DataFrame, vocabulary: str, sample_docs: int = SAMPLE_DOCS, rounds: int = ROUNDS) -> LanguageModel:
    """Learns from (doc_id, text, lang) rows, all words of the sampled documents.

    Each round's expectations are taken where the words are; what comes back is
    a number for each piece of each language.
    """
    words = checkpointed(sampled_words(docs, sample_docs))
    languages = [r["lang"] for r in words.select("lang").distinct().orderBy("lang").collect()]  # MOST_LANGUAGES at most
    model = LanguageModel.uniform(Vocabulary.load(vocabulary), languages)
    for _ in range(rounds if languages else 0):
        sent = docs.sparkSession.sparkContext.broadcast(model)

        def expect(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            model, held = sent.value, {}
            number = {name: k for k, name in enumerate(model.languages)}
            for batch in blocks(batches, "word", WORD_BYTES):
                by: dict[str, dict[str, int]] = {}
                for lang, w, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    by.setdefault(lang, {})[w] = n
                for lang, counts in by.items():
                    got = model.expected(number[lang], counts)
                    held[lang] = held[lang] + got if lang in held else got
            for lang, got in held.items():
                at = np.flatnonzero(got)
                yield pa.RecordBatch.from_arrays([pa.array([number[lang]] * at.size, pa.int32()), pa.array(at, pa.int32()), pa.array(got[at])], ["lang", "piece", "n"])

        got = words.mapInArrow(expect, "lang int, piece int, n double").groupBy("lang", "piece").agg(F.sum("n").alias("n")).toArrow()
        table = np.zeros((len(model.vocabulary.pieces), len(languages)))
        table[got.column("piece").to_numpy(), got.column("lang").to_numpy()] = got.column("n").to_numpy()
        model = model.updated(table)
        sent.unpersist()
    drop_checkpoint(words)
    return model


_scorers: dict[int, Scorer] = {}


def identify(docs: DataFrame, model: LanguageModel, held_out: Column) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every row.

    ``und`` with score 0 where the text is null or has no letter, or nothing
    was learned.  The score is the posterior of the language, all learned ones
    being equally likely before.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)
    number = int(sent._jbroadcast.id())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if number not in _scorers:
            _scorers.clear()
            _scorers[number] = Scorer(sent.value)
        scorer = _scorers[number]
        for batch in blocks(batches, limit=4 << 20):
            rows = [t or "" for t in batch.column("text").to_pylist()]
            real = [bool(scorer.model.languages) and has_letter(t) for t in rows]
            names, scores = ["und"] * len(rows), np.zeros(len(rows))
            if any(real):
                best, posterior = predict(scorer.model, scorer.texts([t for t, ok in zip(rows, real, strict=True) if ok]))
                scores[real] = posterior
                for k, b in zip(np.flatnonzero(real), best, strict=True):
                    names[k] = scorer.model.languages[b]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(names), pa.array(scores)], ["doc_id", "held_out", "lang_pred", "score"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", held_out.alias("held_out"), "text").mapInArrow(run, f"doc_id {kind}, held_out boolean, lang_pred string, score double")


def held_out(doc_id: str = "doc_id") -> Column:
    return doc_hash(F.col(doc_id)) % 4 == 2


def identify_languages(docs: DataFrame, vocabulary: str) -> DataFrame:
    """Learns from the rows that aren't held out and predicts every row."""
    return identify(docs, train(docs.where(~held_out()), vocabulary), held_out())
