"""Language identification by segmentation-marginalised unigrams over a fixed public vocabulary.

Each language has a probability for every piece of the vocabulary. A word's probability is the sum over all ways to cut it in
pieces, found by a forward pass; a text's is the product over its words. The piece probabilities are learned by expectation
maximisation over the counted words of all labelled texts: a forward-backward pass gives each piece's expected count.

Words are runs of letters, lower-cased, in stretches of up to 31 letters. Text that is null or has no letter gets `und` with
score 0, and so does all text when nothing was learned. Null ids count as the empty text where held-out rows are chosen. Rows
that repeat are predicted alike; ties between languages go to the first by name. Very long texts are scored whole. Columns
beside id, text and lang, those with names used here included, are not read. Empty tables give no rows.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator
from itertools import chain, islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.llm.common import Numbers, arrow_map, by_bytes, kept, keyed, light_batches
from netan.llm.token_counts import library
from netan.storage import drop, lasting, written

STRETCH = 31
#: Different words that a worker holds before it hands their counts on, and before it starts its scores anew.
COUNTED_WORDS = 100_000
KEPT_WORDS = 250_000
#: Words that a worker hands on at once, and those that it takes in before it cuts them.
LOT = 50_000
#: Numbers in a model at most: languages times pieces.
MOST_NUMBERS = 128_000_000


#: Multiplier of the rolling hash of characters, and bits of the table that finds pieces by it.
BASE = np.uint64(0x9E3779B97F4A7C15)
TABLE_BITS = 20


class Pieces:
    """Numbers of the vocabulary's pieces; a single character outside it has the number `other`.

    Pieces are found by a 64-bit hash of their characters, in a table of open addresses: all substrings of all words at once.
    """

    def __init__(self, vocabulary: str) -> None:
        tool = library(vocabulary)
        names = [tool.id_to_piece(k) for k in range(tool.get_piece_size()) if not (tool.is_control(k) or tool.is_unknown(k) or tool.is_byte(k))]
        self.other = len(names)
        self.longest = max(map(len, names))
        self.table = np.full(1 << TABLE_BITS, -1, np.int32)
        self.hashes = np.zeros(len(names), np.uint64)
        for some in _by_length(names):
            self.hashes[some] = list(self._spans(self._codes([names[k] for k in some])))[-1][:, -1]
        for k, at in enumerate(self._slot(self.hashes).tolist()):
            while self.table[at] >= 0:
                at = (at + 1) % len(self.table)
            self.table[at] = k

    def __len__(self) -> int:
        return self.other + 1

    @staticmethod
    def _codes(words: list[str]) -> np.ndarray:
        return np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4").reshape(len(words), -1).astype(np.uint64)

    @staticmethod
    def _slot(h: np.ndarray) -> np.ndarray:
        return ((h ^ h >> np.uint64(32)) * BASE >> np.uint64(64 - TABLE_BITS)).astype(np.int64)

    @staticmethod
    def _spans(codes: np.ndarray):
        """Hashes of all substrings of 1, 2, ... characters: (word, place of the first character)."""
        h = np.zeros_like(codes)
        for n in range(codes.shape[1]):
            h = h[:, : codes.shape[1] - n] * BASE + codes[:, n:] + np.uint64(1)
            yield h

    def lattice(self, words: list[str]) -> np.ndarray:
        """(end, length - 1, word): number of the piece that ends there, or -1; words are of one length."""
        m = len(words[0])
        top = min(m, self.longest)
        out = np.full((m, top, len(words)), -1, np.int32)
        for k, h in zip(range(top), self._spans(self._codes(words))):
            flat = h.T.ravel()
            at, found = self._slot(flat), out[k:, k].reshape(-1)
            piece = self.table[at]
            left = np.flatnonzero(piece >= 0)  # the others' slots are empty
            at, piece = at[left], piece[left]
            while len(left):
                hit = self.hashes[piece] == flat[left]
                found[left[hit]] = piece[hit]
                at = (at[~hit] + 1) % len(self.table)
                left, piece = left[~hit], self.table[at]
                at, left, piece = at[piece >= 0], left[piece >= 0], piece[piece >= 0]
            out[k:, k] = found.reshape(m - k, len(words))
        single = out[:, 0]
        single[single < 0] = self.other
        return out


#: Runs of letters.
LETTERS = re.compile(r"[^\W\d_]+")


def letter_runs(text: str) -> list[str]:
    """Words of a text as the model sees them, without the mark of a word's start: lower-cased runs of letters."""
    return LETTERS.findall(text.lower())


def stretches(run: str) -> list[str]:
    """A run of letters with the mark of a word's start; a long one in several parts."""
    return ["▁" + run[a : a + STRETCH] for a in range(0, len(run), STRETCH)]


def _by_length(words: list[str], most: int = 4096):
    order = sorted(range(len(words)), key=lambda k: len(words[k]))
    a = 0
    while a < len(order):
        b = a
        while b < len(order) and b - a < most and len(words[order[b]]) == len(words[order[a]]):
            b += 1
        yield order[a:b]
        a = b


#: Factor for each character in the sums over cuts, which would fall below the least number otherwise.
SCALE = 1e8


def forward(lattice: np.ndarray, p: np.ndarray) -> np.ndarray:
    """(end, word, ...): probability of all cuts of each word up to each end, times SCALE for each character; p: of pieces."""
    m, top, n = lattice.shape
    alpha = np.zeros((m + 1, n, *p.shape[1:]))
    alpha[0] = 1
    for j in range(1, m + 1):
        for k in range(min(j, top)):
            ids = lattice[j - 1, k]
            some = np.flatnonzero(ids >= 0)
            if len(some) == n:
                alpha[j] += alpha[j - k - 1] * SCALE ** (k + 1) * p[ids]
            elif len(some):
                alpha[j, some] += alpha[j - k - 1, some] * SCALE ** (k + 1) * p[ids[some]]
    return alpha


def log_probability(lattice: np.ndarray, p: np.ndarray) -> np.ndarray:
    """(word, ...): logarithms of the sums over all cuts, at any size of p."""
    m, top, n = lattice.shape
    end = forward(lattice, p)[-1]
    tiny = (end < 1e-250).reshape(n, -1).any(axis=1)
    out = np.log(np.where(end > 0, end, 1)) - m * np.log(SCALE)
    if tiny.any():  # once more, in logarithms
        part, log_p = lattice[:, :, tiny], np.log(p.astype(float))
        alpha = np.full((m + 1, part.shape[2], *p.shape[1:]), -np.inf)
        alpha[0] = 0
        for j in range(1, m + 1):
            for k in range(min(j, top)):
                some = np.flatnonzero(part[j - 1, k] >= 0)
                alpha[j, some] = np.logaddexp(alpha[j, some], alpha[j - k - 1, some] + log_p[part[j - 1, k, some]])
        out[tiny] = alpha[m]
    return out


def expected(lattice: np.ndarray, p: np.ndarray, weight: np.ndarray, out: np.ndarray) -> None:
    """Adds to out the expected count of each piece over words with these weights."""
    m, top, n = lattice.shape
    alpha = forward(lattice, p)
    beta = np.zeros((m + 1, n))
    beta[m] = weight / alpha[m]
    for j in range(m, 0, -1):
        for k in range(min(j, top)):
            some = np.flatnonzero(lattice[j - 1, k] >= 0)
            if len(some):
                ids = lattice[j - 1, k, some]
                flow = beta[j, some] * SCALE ** (k + 1) * p[ids]
                beta[j - k - 1, some] += flow
                np.add.at(out, ids, alpha[j - k - 1, some] * flow)


def lots(batches: Iterable[pa.RecordBatch], rows: int) -> Iterator[pa.Table]:
    """The batches in tables of this many rows or more; the last one may have fewer."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(map(len, held)) >= rows:
            yield pa.Table.from_batches(held)
            held = []
    if held:
        yield pa.Table.from_batches(held)


def count_words(docs: DataFrame) -> DataFrame:
    """(lang, word, n) over whole texts; docs: (text, lang) with no null lang. Workers hand on counts, which Spark adds up."""

    def work(batches):
        held: dict[str, Counter] = {}

        def handed():
            for lang, words in held.items():
                rest = iter(words.items())
                while some := list(islice(rest, LOT)):
                    parts = [(x, n) for w, n in some for x in stretches(w)]
                    yield {"lang": [lang] * len(parts), "word": [x for x, _ in parts], "n": [n for _, n in parts]}
            held.clear()

        for batch in batches:
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if text:
                    held.setdefault(lang, Counter()).update(letter_runs(text))
            if sum(map(len, held.values())) > COUNTED_WORDS:
                yield from handed()
        yield from handed()

    schema = T.StructType([T.StructField("lang", T.StringType()), T.StructField("word", T.StringType()), T.StructField("n", T.LongType())])
    return arrow_map(docs, work, schema).groupBy("lang", "word").agg(F.sum("n").alias("n"))


def train(docs: DataFrame, vocabulary: str = "piece_bpe_32k.model", rounds: int = 2, smoothing: float = 0.05) -> tuple[list[str], np.ndarray]:
    """Languages, and their log-probabilities by (piece, language)."""
    with light_batches(docs.sparkSession):
        words = written(count_words(docs), "language-words")
    langs = [r[0] for r in words.select("lang").distinct().orderBy("lang").collect()]
    size = len(Pieces(vocabulary))
    if len(langs) * size > MOST_NUMBERS:
        raise ValueError(f"{len(langs)} languages are more than a model may hold")
    sc = docs.sparkSession.sparkContext
    p = np.full((size, max(1, len(langs))), 1 / size, np.float32)
    for _ in range(rounds):
        sent = sc.broadcast((langs, p))

        def work(batches, sent=sent):
            pieces = kept(("pieces", vocabulary), lambda: Pieces(vocabulary))
            names, p = sent.value
            column = {x: k for k, x in enumerate(names)}
            total: dict[str, np.ndarray] = {}
            for rows in lots(batches, LOT):
                word = rows.column("word").to_pylist()
                whose = np.fromiter(map(column.__getitem__, rows.column("lang").to_pylist()), np.int64, len(word))
                n = rows.column("n").to_numpy().astype(float)
                for some in _by_length(word):
                    lattice, mine = pieces.lattice([word[k] for k in some]), whose[some]
                    for k in np.unique(mine):
                        one = np.flatnonzero(mine == k)
                        out = total.setdefault(names[k], np.zeros(size))
                        expected(lattice[:, :, one], p[:, k].astype(float), n[some][one], out)
            for x, out in total.items():
                yield {"lang": [x] * size, "piece": np.arange(size), "n": out}

        schema = T.StructType([T.StructField("lang", T.StringType()), T.StructField("piece", T.LongType()), T.StructField("n", T.DoubleType())])
        found = arrow_map(words, work, schema, keeps=True).groupBy("lang", "piece").agg(F.sum("n").alias("n")).toArrow()
        column = {x: k for k, x in enumerate(langs)}
        counts = np.zeros(p.shape)
        counts[found.column("piece").to_numpy(), [column[x] for x in found.column("lang").to_pylist()]] = found.column("n").to_numpy()
        p = ((counts + smoothing) / (counts.sum(axis=0) + smoothing * size)).astype(np.float32)
    drop(words)
    return langs, p


class Scorer:
    """Log-probabilities of words in all languages; each different word is scored once per worker."""

    def __init__(self, pieces: Pieces, p: np.ndarray) -> None:
        self.pieces, self.p = pieces, p.astype(np.float32)
        self._forget()

    def _forget(self) -> None:
        self.known = Numbers()
        self.scores = np.zeros((1 << 16, self.p.shape[1]), np.float32)

    def _learn(self) -> None:
        fresh, self.known.fresh = self.known.fresh, []
        k = len(self.known) - len(fresh)
        if len(self.known) > len(self.scores):
            grown = np.zeros((max(len(self.known), 2 * len(self.scores)), self.p.shape[1]), np.float32)
            grown[:k] = self.scores[:k]
            self.scores = grown
        parts, owner = ["▁" + w for w in fresh], np.arange(k, k + len(fresh))
        long = [i for i, w in enumerate(fresh) if len(w) > STRETCH]
        for i in long:
            first, *rest = stretches(fresh[i])
            parts[i] = first
            parts += rest
            owner = np.append(owner, np.full(len(rest), k + i))
        for some in _by_length(parts):
            found = log_probability(self.pieces.lattice([parts[i] for i in some]), self.p)
            np.add.at(self.scores, owner[some], found.astype(np.float32))

    def score(self, texts: list[list[str]]) -> np.ndarray:
        """(text, language): sums over each text's words."""
        if len(self.known) > KEPT_WORDS:
            self._forget()
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        ids = np.fromiter(map(self.known.__getitem__, chain.from_iterable(texts)), np.int64, int(sizes.sum()))
        self._learn()
        out = np.zeros((len(texts), self.p.shape[1]))
        some = np.flatnonzero(sizes)
        if len(some):
            out[some] = np.add.reduceat(self.scores[ids].astype(float), (np.cumsum(sizes) - sizes)[some])
        return out


def shared_scorer(vocabulary: str, p: np.ndarray) -> Scorer:
    """The words that this Python worker has scored under one model, kept from task to task."""
    key = ("scores", vocabulary, p.shape, xxhash.xxh3_128_hexdigest(np.ascontiguousarray(p)))
    return kept(key, lambda: Scorer(Pieces(vocabulary), p))


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], vocabulary: str = "piece_bpe_32k.model", id_col: str = "doc_id", text_col: str = "text", *more: Column) -> DataFrame:
    """(doc_id, lang_pred, score[, more]) of each row; score: the best language's share among all, all as likely beforehand."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    rows = keyed(docs, id_col, text_col, *more)
    others = rows.columns[2:]

    def work(batches):
        langs, p = sent.value
        scorer = shared_scorer(vocabulary, p)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for a, b in by_bytes(texts, 1 << 19):
                lettered = [bool(t) and any(map(str.isalpha, t)) for t in texts[a:b]]
                sums = scorer.score([letter_runs(t) if ok else [] for t, ok in zip(texts[a:b], lettered)])
                best = sums.argmax(axis=1)
                share = 1 / np.exp(sums - sums.max(axis=1, keepdims=True)).sum(axis=1)
                known = [ok and bool(langs) for ok in lettered]
                out = {"doc_id": batch.column(0).slice(a, b - a), "lang_pred": [langs[k] if ok else "und" for k, ok in zip(best, known)], "score": [float(s) if ok else 0.0 for s, ok in zip(share, known)]}
                yield out | {c: batch.column(c).slice(a, b - a) for c in others}

    schema = T.StructType([rows.schema["doc_id"], T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), *rows.schema.fields[2:]])
    return arrow_map(rows, work, schema, keeps=True)


def held_out(docs: DataFrame) -> Column:
    """Rows that are never learned from: crc32 of the id's text, modulo 4, is 2."""
    return F.crc32(F.coalesce(docs["doc_id"].cast("string"), F.lit("")).cast("binary")) % 4 == 2


def identify(docs: DataFrame, vocabulary: str = "piece_bpe_32k.model", lang_col: str = "lang") -> DataFrame:
    """(doc_id, held_out, lang_pred, score): learned from the labelled rows that are not held out, predicted for all."""
    out = held_out(docs)
    seen = docs.where(~out & docs[lang_col].isNotNull()).select(docs["text"].cast("string").alias("text"), docs[lang_col].cast("string").alias("lang"))
    rows = predict(docs, train(seen, vocabulary), vocabulary, "doc_id", "text", out.alias("held_out"))
    with light_batches(docs.sparkSession):
        return lasting(rows.select("doc_id", "held_out", "lang_pred", "score"), "languages")
