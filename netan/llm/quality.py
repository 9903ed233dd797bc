"""Quality rules: base counts of each text, and the perplexity of its words under a modified Kneser-Ney model of its language.

The model is one of characters within words, an n-gram model of order 4 per language, counted by Spark over the words of all
documents. A symbol has 16 bits: lower-cased code points as they are, of any script, all digits as one, those beyond the
basic plane by a hash. Four symbols are one 64-bit code; the model is sorted arrays of codes with their probabilities, sent to
the executors. If the languages' tables pass a fixed size together, languages are scored in lots, one after the other, each
with the whole tables of its languages: the model is the same at every size. A language that is larger alone is a lot of its
own.

Each language gets a band from its own documents: the median of their log-perplexities per letter, less a number of median
deviations of the scores below it, plus another number of those of the scores above it (from counts of binned scores, over all
documents). Documents beyond the band are rejected. The numbers were chosen on labelled rows: see ABOVE and BELOW.

Nulls and texts without words have no score and fail the base rule of 50 words. A null language is a language named "null".
Rows that repeat are scored alike. A document with fewer than `least` words is not scored. Very long texts are scored whole,
some at a time. Columns beside id, text and lang, those with names used here included, are not read. Empty tables give no rows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.llm.common import arrow_map, by_bytes, give_back
from netan.storage import lasting, scratch, written

SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
START, END, ORDER, BITS = 0, 1, 4, 16
#: Rows of counts whose model is sent to the executors at once, if more than one language's; a row is about 30 bytes of model.
MOST_ROWS = 8_000_000
#: Rows of counts that are fetched at once.
FETCHED_ROWS = 4_000_000
#: Different words of all languages that a task holds at most before it hands on its n-gram counts, or forgets their scores.
KEPT_WORDS = 200_000
#: Deviations of the band. On sf0.1's labels, 5 above rejects all 291 rows of quality 0 in the four languages; 6 lets 2 of them
#: pass and 4 rejects more rows of quality 1. No row of quality 0 lies below, so that limit only stands clear of quality 1.
ABOVE, BELOW = 5.0, 10.0
#: Width of a bin of scores.
BIN = 0.001
#: Bins of a language at most.
MOST_BINS = 1 << 16


def fold_table() -> np.ndarray:
    """Symbol (2 and up) of each code point of the basic plane; surrogates, which are no characters, stand for all beyond it."""
    table = np.arange(1 << BITS, dtype=np.uint16)
    for c in range(1 << BITS):
        low = chr(c).lower()
        if len(low) == 1 and ord(low) < 1 << BITS:
            table[c] = ord(low)
        if chr(c).isdigit():
            table[c] = ord("0")
    return np.maximum(table, 2)


FOLD = fold_table()


def folded(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of all words, three START before each and END behind it, and the place where each begins."""
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 4
    points = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), "<u4")
    codes = np.where(points < len(FOLD), FOLD[np.minimum(points, len(FOLD) - 1)], 0xD800 + points % 2048).astype(np.int64)
    first = np.cumsum(sizes) - sizes
    out = np.zeros(int(sizes.sum()), np.int64)
    kept = np.ones(len(out), bool)
    for j in range(3):
        kept[first + j] = False
    kept[first + sizes - 1] = False
    out[kept] = codes
    out[first + sizes - 1] = END
    return out, first


def grams(symbols: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes of the 4-grams that end at each symbol but START, and the index where each word's begin."""
    code = symbols[3:] | symbols[2:-1] << BITS | symbols[1:-2] << 2 * BITS | symbols[:-3] << 3 * BITS
    ends = np.append(first[1:], len(symbols))
    sizes = ends - first - 3
    place = np.arange(int(sizes.sum())) + np.repeat(first - (np.cumsum(sizes) - sizes), sizes)
    return code[place], np.cumsum(sizes) - sizes


def count_grams(docs: DataFrame) -> DataFrame:
    """(lang, gram, n) over all words of all documents; docs: (text, lang)."""

    def work(batches):
        from collections import Counter

        held: dict[str, Counter] = {}

        def handed():
            for lang, words in held.items():
                names = list(words)
                for a in range(0, len(names), 50_000):
                    part = names[a : a + 50_000]
                    code, first = grams(*folded(part))
                    weight = np.fromiter((words[w] for w in part), np.int64, len(part))
                    each = np.repeat(weight, np.diff(np.append(first, len(code))))
                    u, inverse = np.unique(code, return_inverse=True)
                    yield {"lang": [lang] * len(u), "gram": u, "n": np.bincount(inverse, each).astype(np.int64)}
            held.clear()

        for batch in batches:
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if text:
                    held.setdefault(lang, Counter()).update(_words(text))
            if sum(map(len, held.values())) > KEPT_WORDS:
                yield from handed()
        yield from handed()

    schema = T.StructType([T.StructField("lang", T.StringType()), T.StructField("gram", T.LongType()), T.StructField("n", T.LongType())])
    return arrow_map(docs, work, schema).groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def _words(text: str) -> list[str]:
    """Runs that hold no ASCII white space; str.split() would also part at other spaces."""
    if text.isascii() and not any(c in text for c in "\x1c\x1d\x1e\x1f"):
        return text.split()
    return [w.decode() for w in text.encode("utf-8", "surrogatepass").split()]


def train(docs: DataFrame) -> DataFrame:
    """(lang, gram, n): the counts that the model is made of, as a table; docs: (text, lang)."""
    return written(count_grams(docs), "gram-counts")


def estimate(gram: np.ndarray, n: np.ndarray) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Modified Kneser-Ney from sorted codes of 4-grams and their counts: by size, sorted codes, log_p and log_back of each.

    log_p: a gram's interpolated probability given the rest of it (nan for what is a context only); log_back: weight of the next
    smaller size in its context (0 if it is no context; none are kept at the highest size). Sizes below the highest count how
    many different symbols stand before a gram. Size 0 holds the weight of the uniform distribution.
    """
    counts = {ORDER: (gram, n)}
    for size in range(ORDER - 1, 0, -1):
        counts[size] = np.unique(counts[size + 1][0] & _mask(size), return_counts=True)
    shares: dict[int, np.ndarray] = {}
    backs: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for size in range(1, ORDER + 1):
        u, c = counts[size]
        ones = [np.count_nonzero(c == k) for k in (1, 2, 3, 4)]
        cut = [0.5, 1.0, 1.5]  # half a count, where no discount can be told
        if ones[0]:
            y = ones[0] / (ones[0] + 2 * ones[1])
            cut = [min(k, max(0.05 * k, k - (k + 1) * y * ones[k] / ones[k - 1])) if ones[k - 1] else 0.5 * k for k in (1, 2, 3)]
        off = np.minimum(np.array(cut)[np.minimum(c, 3) - 1], c)
        context, which = np.unique(u >> BITS & _mask(size - 1), return_inverse=True)
        total, spare = np.bincount(which, c), np.bincount(which, off)
        low = shares[size - 1][np.searchsorted(counts[size - 1][0], u & _mask(size - 1))] if size > 1 else 1 / (1 << BITS)
        shares[size] = (c - off + spare[which] * low) / total[which]
        backs[size - 1] = context, np.log(spare / total)
    out = {ORDER: (gram, np.log(shares[ORDER]).astype(np.float32), np.zeros(0, np.float32))}
    for size in range(ORDER):
        u = counts[size][0] if size else np.zeros(0, np.int64)
        context, weight = backs[size]
        codes = np.union1d(u, context)
        log_p, log_back = np.full(len(codes), np.nan, np.float32), np.zeros(len(codes), np.float32)
        log_p[np.searchsorted(codes, u)] = np.log(shares[size]) if size else 0
        log_back[np.searchsorted(codes, context)] = weight
        out[size] = codes, log_p, log_back
    return out


def lots(counts: DataFrame) -> list[list[str]]:
    """Languages whose tables are sent together: MOST_ROWS rows of counts at most, or one language."""
    out: list[list[str]] = []
    held = MOST_ROWS
    for lang, n in sorted((r["lang"], r["count"]) for r in counts.groupBy("lang").count().collect()):
        if held + n > MOST_ROWS:
            out.append([])
            held = 0
        out[-1].append(lang)
        held += n
    return out


def load(counts: DataFrame, langs: list[str] | None = None) -> tuple[int, dict]:
    """Order, and the tables of estimate() by language, of all languages or some; counts are fetched part by part."""
    if langs is not None:
        counts = counts.where(F.col("lang").isin(langs))
    ranges = -(-counts.count() // FETCHED_ROWS)
    parts: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
    for k in range(ranges):
        some = counts.where(F.pmod(F.xxhash64("gram"), F.lit(ranges)) == k) if ranges > 1 else counts
        rows = some.select("lang", "gram", "n").toArrow()
        if not len(rows):
            continue
        named = rows.column("lang").combine_chunks().dictionary_encode()
        which, gram, n = named.indices.to_numpy(), rows.column("gram").to_numpy(), rows.column("n").to_numpy()
        for j, lang in enumerate(named.dictionary.to_pylist()):
            parts.setdefault(lang, []).append((gram[which == j], n[which == j]))
    tables = {}
    for lang, found in parts.items():
        gram, n = map(np.concatenate, zip(*found))
        order_by = np.argsort(gram)
        tables[lang] = estimate(gram[order_by], n[order_by])
    rows = some = named = which = gram = n = found = parts = None
    give_back()
    return ORDER, tables


def _mask(size: int) -> int:
    """The last so many symbols of a code."""
    return (1 << BITS * size) - 1 if size < ORDER else -1


def _find(table, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at = np.minimum(np.searchsorted(table[0], codes), len(table[0]) - 1)
    return at, table[0][at] == codes


class Scorer:
    """Log-probabilities of words in one language; each different word is scored once."""

    def __init__(self, order: int, tables: dict) -> None:
        self.order, self.tables = order, tables
        self.known: dict[str, complex] = {}  # log-probability, and letters and digits

    def _score(self, words: list[str]) -> np.ndarray:
        code, first = grams(*folded(words))
        u, inverse = np.unique(code, return_inverse=True)
        return np.add.reduceat(self.log_probabilities(u)[inverse], first)

    def log_probabilities(self, u: np.ndarray) -> np.ndarray:
        """Of each 4-gram's last symbol, given those before it."""
        log_p = np.zeros(len(u))
        open_, back = np.ones(len(u), bool), np.zeros(len(u))
        for size in range(self.order, 0, -1):
            if size not in self.tables:
                continue
            at, hit = _find(self.tables[size], u & _mask(size))
            hit &= ~np.isnan(self.tables[size][1][at])
            take = open_ & hit
            log_p[take] = back[take] + self.tables[size][1][at[take]]
            open_ &= ~hit
            if size - 1 in self.tables:
                at, hit = _find(self.tables[size - 1], u >> BITS & _mask(size - 1))
                back += np.where(hit, self.tables[size - 1][2][at], 0)
        log_p[open_] = back[open_] - BITS * np.log(2)
        return log_p

    def score(self, words: list[str]) -> float:
        """Minus the words' log-probability for each of their letters and digits."""
        new = list(set(words).difference(self.known))
        if new:
            letters = [sum(map(str.isalnum, w)) for w in new]
            self.known.update(zip(new, map(complex, self._score(new).tolist(), letters)))
        total = sum(map(self.known.__getitem__, words), 0j)
        return -total.real / max(1.0, total.imag)


def base_counts(text: str | None, words: list[str]) -> tuple[int, int, int, int]:
    """(word_chars, n_symbols, n_dup_lines, n_repeat_words)."""
    if not text:
        return 0, 0, 0, 0
    count = text.count
    chars = len(text) - sum(map(count, SPACES))
    symbols = sum(map(count, SYMBOLS))
    lines = [x for x in text.split("\n") if x.strip(SPACES)]
    repeats, n = 0, len(words)
    if n >= 4:
        triples = list(zip(words, words[1:], words[2:]))
        if len(set(triples)) < len(triples):
            number: dict = {}
            ids = np.fromiter((number.setdefault(t, len(number)) for t in triples), np.int64, len(triples))
            twice = (np.bincount(ids) > 1)[ids]
            cover = np.zeros(n, bool)
            for j in range(3):
                cover[j : n - 2 + j] |= twice
            repeats = int(cover.sum())
    return chars, symbols, len(lines) - len(set(lines)), repeats


def measure(docs: DataFrame, model: tuple[int, dict], least: int = 50) -> DataFrame:
    """(doc_id, rid, lang, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, score) of each row.

    score: minus the log-probability of its words for each letter or digit, so that marks about words count against them.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def work(batches):
        order, tables = sent.value
        scorers = {lang: Scorer(order, t) for lang, t in tables.items()}
        for batch in batches:
            texts, langs = batch.column("text").to_pylist(), batch.column("lang").to_pylist()
            for a, b in by_bytes(texts):
                rows = []
                for text, lang in zip(texts[a:b], langs[a:b]):
                    words = _words(text) if text else []
                    n = len(words)
                    counts = base_counts(text, words)
                    failed = n < 50 or 2 * counts[3] > n
                    score = scorers[lang].score(words) if n >= least and lang in scorers else None
                    if sum(len(x.known) for x in scorers.values()) > KEPT_WORDS:
                        for x in scorers.values():
                            x.known.clear()
                    rows.append((n, *counts, failed, score))
                columns = dict(zip(("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "score"), zip(*rows)))
                yield {"doc_id": batch.column("doc_id").slice(a, b - a), "rid": batch.column("rid").slice(a, b - a), "lang": langs[a:b]} | columns

    long, double = T.LongType(), T.DoubleType()
    schema = T.StructType([T.StructField("doc_id", docs.schema["doc_id"].dataType), T.StructField("rid", long), T.StructField("lang", T.StringType()), *(T.StructField(c, long) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), T.StructField("base_failed", T.BooleanType()), T.StructField("score", double)])
    return arrow_map(docs, work, schema)


def measured_in_lots(rows: DataFrame, counts: DataFrame, least: int) -> DataFrame:
    """measure()'s table, lot by lot of languages; rows of languages without words go with the first lot."""
    parts = lots(counts) or [[]]
    out = None
    for k, langs in enumerate(parts):
        if len(parts) == 1:
            mine, some = rows, None
        elif k == 0:
            mine, some = rows.where(~F.col("lang").isin([x for p in parts[1:] for x in p])), langs
        else:
            mine, some = rows.where(F.col("lang").isin(langs)), langs
        measured = written(measure(mine, load(counts, some), least), f"quality-measures-{k}")
        give_back()
        out = measured if out is None else out.unionByName(measured)
    return out


def _middle(bins: np.ndarray, n: np.ndarray) -> int:
    """The bin that holds the middle of the counts; bins ascend."""
    return int(bins[np.searchsorted(2 * np.cumsum(n), n.sum())])


def bands(measured: DataFrame, above: float = ABOVE, below: float = BELOW) -> DataFrame:
    """(lang, low, high) of the scores of documents that pass the base rule.

    Their numbers by bin come to the driver, MOST_BINS rows of a language at most; scores beyond the last bin count in it.
    """
    bin_ = F.least(F.floor(F.col("score") / BIN), F.lit(MOST_BINS - 1)).cast("long").alias("bin")
    binned = measured.where("score IS NOT NULL AND NOT base_failed").select("lang", bin_)
    found: dict[str, list[tuple[int, int]]] = {}
    for r in binned.groupBy("lang", "bin").agg(F.count("*").alias("n")).collect():
        found.setdefault(r["lang"], []).append((r["bin"], r["n"]))
    rows = []
    for lang, pairs in sorted(found.items()):
        bins, n = np.array(sorted(pairs)).T
        mid = _middle(bins, n)
        under, over = bins <= mid, bins >= mid
        down, up = _middle((mid - bins[under])[::-1], n[under][::-1]), _middle(bins[over] - mid, n[over])
        rows.append((lang, (mid - max(down, 1) * below) * BIN, (mid + max(up, 1) * above + 1) * BIN))
    return measured.sparkSession.createDataFrame(rows, "lang string, low double, high double")


def assess(docs: DataFrame, above: float = ABOVE, below: float = BELOW, least: int = 50, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """measure()'s columns with low, high and kept for each row: kept if the base rule holds and the score is in its band."""
    text = docs[text_col].cast("string")
    lang = F.coalesce(docs[lang_col].cast("string"), F.lit("null")).alias("lang")
    with scratch():
        counts = train(docs.select(text.alias("text"), lang))
        rows = docs.select(docs[id_col].alias("doc_id"), text.alias("text"), lang, F.xxhash64(docs[id_col], text).alias("rid"))
        measured = measured_in_lots(rows, counts, least)
        out = measured.join(F.broadcast(bands(measured, above, below)), "lang", "left")
        inside = F.col("score").isNull() | F.col("low").isNull() | F.col("score").between(F.col("low"), F.col("high"))
        return lasting(out.withColumn("kept", ~F.col("base_failed") & inside), "assessed")
