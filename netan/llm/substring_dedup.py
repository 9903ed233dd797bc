"""Substring deduplication with suffix automata of reference shards and matching statistics.

A word is removed if it stands in a window of `length` consecutive words whose sequence starts anywhere else in the corpus too.
No automaton could hold the corpus, so the reference is cut in shards that share nothing: every window has one anchor, the
leftmost of its word 8-grams with the smallest hash, and equal windows have equal anchors at equal places. A segment is a run of
windows of one document with the same anchor, so every window lies in just one segment, and windows can only be equal to
windows of segments with the same anchor.

1. Segments are found in one pass, with hashes of anchor and content, and counted. Segments whose anchor comes once go.
2. Anchors with one content only, found twice or more: every window is a repeat.
3. Anchors with several contents: the different segments, each once with its count, are dealt by anchor in reference shards of
   bounded size. Each shard becomes a suffix automaton whose states carry the number of places; its segments are streamed
   through it, and a window is a repeat if the state of its `length` words has two places or more.
4. An anchor with more contents than a shard may hold is dealt by its windows instead, each a shard of its own whose
   automaton is a single path: the windows are counted. They come in lots of CORE neighbours that stand at the same places
   about the anchor; equal windows share the words that all of a lot have, its core. Equal lots are one, and only lots whose core
   others have too, with other windows, are taken apart.

Words are compared by 64-bit hashes. Nulls and texts shorter than a window lose nothing. Rows that repeat are copies of each
other and lose all their windows, whatever their ids. Columns beside id and text, those with names used here included, are
not read. Very long texts are treated whole, in overlapping pieces of windows. Empty tables give no rows.
"""

from __future__ import annotations

import hashlib
from itertools import chain

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.llm.common import arrow_map, by_bytes, fields, keyed, row_key, same_row
from netan.storage import drop, lasting, scratch, written

GRAM = 8
BASE = np.uint64(0x9E3779B97F4A7C15)
INVERSE = np.uint64(pow(int(BASE), -1, 1 << 64))
#: Bits that hold a place within a batch when smallest hashes are sought.
PLACE_BITS = np.uint64(26)
#: Windows of one text that are sought through at once.
PIECE_WINDOWS = 1 << 24
#: Different words that a worker keeps hashed.
KEPT_WORDS = 200_000
#: Words of segments in a reference shard, and different contents of one anchor that it may hold.
SHARD_WORDS = 100_000
SHARD_CONTENTS = 1_000
#: Windows in a lot.
CORE = 4


class WordHashes(dict):
    """Hashes of words; each different one is hashed once per worker."""

    def __missing__(self, word: bytes) -> int:
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def of(self, texts: list[list[bytes]]) -> np.ndarray:
        if len(self) > KEPT_WORDS:
            self.clear()
        return np.fromiter(map(self.__getitem__, chain.from_iterable(texts)), np.uint64, sum(map(len, texts)))


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ h >> np.uint64(31)) * np.uint64(0xBF58476D1CE4E5B9)
    return (h ^ h >> np.uint64(29)) * np.uint64(0x94D049BB133111EB)


class Spans:
    """Hashes of any stretch of a row of words."""

    def __init__(self, words: np.ndarray) -> None:
        n = len(words)
        powers = np.cumprod(np.concatenate((np.ones(1, np.uint64), np.full(n, BASE))), dtype=np.uint64)
        self.inverse = np.cumprod(np.concatenate((np.ones(1, np.uint64), np.full(n, INVERSE))), dtype=np.uint64)
        self.sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(words * powers[:-1], dtype=np.uint64)))

    def of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return mixed((self.sums[b] - self.sums[a]) * self.inverse[a])


def segments(words: np.ndarray, sizes: np.ndarray, length: int) -> dict[str, np.ndarray]:
    """Segments of texts that stand one after another in words: doc, start, count, off (place of the anchor), anchor, seg."""
    n, width = len(words), length - GRAM + 1
    if len(sizes) == 1 and n - length >= PIECE_WINDOWS:  # windows in several pieces; a run that is cut is two segments
        parts = [segments(words[a : a + PIECE_WINDOWS + length - 1], np.array([min(n - a, PIECE_WINDOWS + length - 1)]), length) for a in range(0, n - length + 1, PIECE_WINDOWS)]
        for k, part in enumerate(parts):
            part["start"] = part["start"] + k * PIECE_WINDOWS
        return {c: np.concatenate([part[c] for part in parts]) for c in parts[0]}
    bases = np.cumsum(sizes) - sizes
    if n < length:
        return {k: np.zeros(0, np.int64) for k in ("doc", "start", "count", "off", "anchor", "seg")}
    g = np.zeros(n - GRAM + 1, np.uint64)
    for j in range(GRAM):
        g = g * BASE + words[j : n - GRAM + 1 + j]
    g = mixed(g)
    least = g >> PLACE_BITS << PLACE_BITS | np.arange(len(g), dtype=np.uint64)
    step = 1
    while 2 * step <= width:
        least = np.minimum(least[:-step], least[step:])
        step *= 2
    if width > step:
        least = np.minimum(least[: len(least) - (width - step)], least[width - step :])
    at = (least & ((np.uint64(1) << PLACE_BITS) - np.uint64(1))).astype(np.int64)
    # windows that lie within one text
    n_windows = np.maximum(sizes - length + 1, 0)
    doc = np.repeat(np.arange(len(sizes)), n_windows)
    window = np.arange(len(doc)) + np.repeat(bases - (np.cumsum(n_windows) - n_windows), n_windows)
    at = at[window]
    first = np.flatnonzero(np.concatenate(([True], (np.diff(doc) != 0) | (np.diff(at) != 0)))) if len(doc) else np.zeros(0, np.int64)
    count = np.diff(np.append(first, len(doc)))
    start = window[first]
    seg = Spans(words).of(start, start + count + length - 1)
    off = at[first] - start
    seg = mixed(seg + off.astype(np.uint64) * np.uint64(64) + count.astype(np.uint64))
    return {"doc": doc[first], "start": start - bases[doc[first]], "count": count, "off": off, "anchor": g[at[first]].view(np.int64), "seg": seg.view(np.int64)}


def find_segments(rows: DataFrame, length: int) -> DataFrame:
    """(doc_id, rid, start, count, anchor, seg) of row_key() rows."""

    def work(batches):
        hashes = WordHashes()
        for batch in batches:
            texts = batch.column(1).to_pylist()
            ids, rids = batch.column(0), batch.column(2)
            for a, b in by_bytes(texts):
                split = [t.encode().split() if t else [] for t in texts[a:b]]
                sizes = np.fromiter(map(len, split), np.int64, b - a)
                found = segments(hashes.of(split), sizes, length)
                yield {"doc_id": ids.take(_arrow(found["doc"] + a)), "rid": rids.take(_arrow(found["doc"] + a)), **{k: found[k] for k in ("start", "count", "anchor", "seg")}}

    schema = T.StructType([*fields(rows, "doc_id", "rid"), T.StructField("start", T.IntegerType()), T.StructField("count", T.IntegerType()), T.StructField("anchor", T.LongType()), T.StructField("seg", T.LongType())])
    return arrow_map(rows, work, schema)


def _arrow(places: np.ndarray):
    import pyarrow as pa

    return pa.array(places)


class SuffixAutomaton:
    """Of several sequences, each with a weight; a state's `places` is the weight of all places where its words end."""

    def __init__(self) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.len, self.places = [-1], [0], [0]

    def _state(self, length: int, link: int, out: dict[int, int]) -> int:
        self.next.append(out)
        self.link.append(link)
        self.len.append(length)
        self.places.append(0)
        return len(self.link) - 1

    def _split(self, p: int, x: int, q: int) -> int:
        """A copy of q for the words that come by way of p."""
        clone = self._state(self.len[p] + 1, self.link[q], dict(self.next[q]))
        self.link[q] = clone
        while p >= 0 and self.next[p].get(x) == q:
            self.next[p][x] = clone
            p = self.link[p]
        return clone

    def add(self, sequence: list[int], weight: int = 1) -> None:
        last = 0
        for x in sequence:
            q = self.next[last].get(x)
            if q is not None:
                last = q if self.len[q] == self.len[last] + 1 else self._split(last, x, q)
            else:
                new, p = self._state(self.len[last] + 1, 0, {}), last
                while p >= 0 and x not in self.next[p]:
                    self.next[p][x] = new
                    p = self.link[p]
                if p >= 0:
                    q = self.next[p][x]
                    self.link[new] = q if self.len[q] == self.len[p] + 1 else self._split(p, x, q)
                last = new
            self.places[last] += weight

    def close(self) -> None:
        """To be called once, after the last add()."""
        for s in sorted(range(1, len(self.len)), key=self.len.__getitem__, reverse=True):
            self.places[self.link[s]] += self.places[s]

    def statistics(self, sequence: list[int], most: int):
        """(length, places) of the longest match that ends at each word, `most` words at most."""
        s, n = 0, 0
        for x in sequence:
            while s and x not in self.next[s]:
                s = self.link[s]
                n = self.len[s]
            if x in self.next[s]:
                s = self.next[s][x]
                n += 1
            while n > most or (n == most and self.len[self.link[s]] >= most):
                if self.len[self.link[s]] >= most:
                    s = self.link[s]
                n = most
            yield n, self.places[s]


def match_shard(rows: list[tuple[list[int], int]], length: int) -> list[int]:
    """For each (words, weight): bits of its windows of `length` words that have two places or more in all rows together."""
    automaton = SuffixAutomaton()
    for words, weight in rows:
        automaton.add(words, weight)
    automaton.close()
    out = []
    for words, _ in rows:
        bits = 0
        for k, (n, places) in enumerate(automaton.statistics(words, length)):
            if n == length and places > 1:
                bits |= 1 << (k - length + 1)
        out.append(bits)
    return out


def lots(words: np.ndarray, anchor: int, length: int) -> list[dict]:
    """Lots of the windows of a segment's words: core, first (the window in its first place; those that follow stand one less each), windows."""
    g = np.zeros(len(words) - GRAM + 1, np.uint64)
    for j in range(GRAM):
        g = g * BASE + words[j : len(g) + j]
    off, count = int(np.argmax(mixed(g).view(np.int64) == anchor)), len(words) - length + 1
    spans = Spans(words)
    hashes = spans.of(np.arange(count), np.arange(count) + length).view(np.int64).tolist()
    firsts = np.arange(off - (off - count + 1) // CORE * CORE, off - off // CORE * CORE - 1, -CORE)
    cores = mixed(spans.of(firsts, firsts - CORE + 1 + length) + (off - firsts).astype(np.uint64)).view(np.int64)
    return [{"core": c, "first": f, "windows": [hashes[j] if 0 <= j < count else None for j in range(f, f - CORE, -1)]} for c, f in zip(cores.tolist(), firsts.tolist())]


def _words_of(rows: DataFrame, wanted: DataFrame, length: int) -> DataFrame:
    """(anchor, seg, n, hot, words, lots) of wanted segments (doc_id, rid, start, count, anchor, seg, n, hot)."""
    lists = wanted.groupBy("rid", "doc_id").agg(F.collect_list(F.struct("start", "count", "anchor", "seg", "n", "hot")).alias("segs"))
    joined = rows.join(lists, same_row(rows, lists)).select(rows["text"], lists["segs"])

    def work(batches):
        hashes = WordHashes()
        for batch in batches:
            texts, lists = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for a, b in by_bytes(texts):
                out: dict[str, list] = {k: [] for k in ("anchor", "seg", "n", "hot", "words", "lots")}
                for text, segs in zip(texts[a:b], lists[a:b]):
                    words = hashes.of([text.encode().split()])
                    for s in segs:
                        p, c = s["start"], s["count"]
                        for k in ("anchor", "seg", "n", "hot"):
                            out[k].append(s[k])
                        mine = words[p : p + c + length - 1]
                        out["words"].append(None if s["hot"] else mine.tobytes())
                        out["lots"].append(lots(mine, s["anchor"], length) if s["hot"] else None)
                yield out

    long = T.LongType()
    lot = T.StructType([T.StructField("core", long), T.StructField("first", T.IntegerType()), T.StructField("windows", T.ArrayType(long))])
    schema = T.StructType([T.StructField("anchor", long), T.StructField("seg", long), T.StructField("n", long), T.StructField("hot", T.BooleanType()), T.StructField("words", T.BinaryType()), T.StructField("lots", T.ArrayType(lot))])
    return arrow_map(joined, work, schema)


def _match(dealt: DataFrame, length: int) -> DataFrame:
    """(anchor, seg, bits) of rows that are sorted by anchor within partitions."""

    def work(batches):
        held, size, last = [], 0, None

        def matched():
            got = match_shard([(np.frombuffer(w, "<u8").tolist(), n) for _, _, n, w in held], length)
            return {"anchor": [x[0] for x in held], "seg": [x[1] for x in held], "bits": got}

        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in ("anchor", "seg", "n", "words"))):
                if size >= SHARD_WORDS and row[0] != last:
                    yield matched()
                    held, size = [], 0
                held.append(row)
                size += len(row[3]) // 8
                last = row[0]
        if held:
            yield matched()

    long = T.LongType()
    return arrow_map(dealt, work, T.StructType([T.StructField("anchor", long), T.StructField("seg", long), T.StructField("bits", long)]))


def _counted(words: DataFrame) -> DataFrame:
    """(anchor, seg, bits) of hot segments' windows that have two places or more, by counts of lots and windows."""
    single = words.where("hot").select("anchor", "seg", "n", F.inline("lots"))
    kinds = written(single.groupBy("anchor", "core", "windows").agg(F.sum("n").alias("n")), "lots")
    mixed_ = kinds.groupBy("anchor", "core").agg((F.min("windows") != F.max("windows")).alias("several")).where("several").select("anchor", "core")
    each = kinds.join(mixed_, ["anchor", "core"], "left_semi").select("*", F.posexplode("windows").alias("at", "window")).where("window IS NOT NULL")
    twice = each.groupBy("anchor", "window").agg(F.sum("n").alias("total")).where("total > 1").select("anchor", "window")
    found = each.join(twice, ["anchor", "window"]).groupBy("anchor", "core", "windows").agg(F.bit_or(F.expr("shiftleft(1, at)")).alias("mask"))
    whole = kinds.where("n > 1").join(mixed_, ["anchor", "core"], "left_anti")
    whole = whole.select("anchor", "core", "windows", F.expr("aggregate(windows, struct(0 AS mask, 0 AS at), (s, w) -> struct(s.mask | IF(w IS NULL, 0, shiftleft(1, s.at)) AS mask, s.at + 1 AS at)).mask").alias("mask"))
    bit = lambda k: F.when(F.expr(f"mask & {1 << k}") != 0, F.expr(f"shiftleft(1L, first - {k})")).otherwise(F.lit(0).cast("long"))
    bits = bit(0)
    for k in range(1, CORE):
        bits = bits.bitwiseOR(bit(k))
    return single.join(found.unionByName(whole), ["anchor", "core", "windows"]).groupBy("anchor", "seg").agg(F.bit_or(bits).alias("bits"))


def repeats(docs: DataFrame, length: int = 35, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, rid, start, bits): bit j says that the window at word start + j is a repeat. length: 8 to 70 words."""
    if not GRAM <= length <= 62 + GRAM:
        raise ValueError("a window has 8 to 70 words")
    with scratch():
        return lasting(_repeats(row_key(keyed(docs, id_col, text_col)), length), "repeats")


def _repeats(rows: DataFrame, length: int) -> DataFrame:
    found = written(find_segments(rows, length), "segments")
    anchors = found.groupBy("anchor").agg(F.count("*").alias("c"), (F.min("seg") != F.max("seg")).alias("several")).where("c > 1").drop("c")
    again = written(found.join(anchors, "anchor"), "repeated-anchors")
    drop(found)
    whole = again.where("NOT several").select("doc_id", "rid", "start", (F.expr("shiftleft(1L, count) - 1")).alias("bits"))
    several = again.where("several")
    contents = several.groupBy("anchor", "seg").agg(F.count("*").alias("n"), F.min_by(F.struct("doc_id", "rid", "start", "count"), F.struct("rid", "start")).alias("r"))
    contents = written(contents, "contents")
    sizes = contents.groupBy("anchor").agg((F.count("*") > SHARD_CONTENTS).alias("hot"))
    wanted = contents.join(sizes, "anchor").select("r.*", "anchor", "seg", "n", "hot")
    words = written(_words_of(rows, wanted, length), "segment-words")
    bits = _match(words.where("NOT hot").select("anchor", "seg", "n", "words").repartition("anchor").sortWithinPartitions("anchor", "seg"), length)
    bits = bits.unionByName(_counted(words)).where("bits <> 0")
    part = several.join(bits, ["anchor", "seg"]).select("doc_id", "rid", "start", "bits")
    return whole.unionByName(part)


def remove(docs: DataFrame, length: int = 35, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256[, kept_text, removed]) of each row; removed: its maximal spans [start, end)."""
    rows = row_key(keyed(docs, id_col, text_col))
    flags = repeats(docs, length, id_col, text_col)
    flags = flags.groupBy("rid", "doc_id").agg(F.collect_set(F.struct("start", "bits")).alias("flags"))
    joined = rows.join(flags, same_row(rows, flags), "left").select(rows["doc_id"], rows["text"], flags["flags"])

    def work(batches):
        for batch in batches:
            out: dict[str, list] = {k: [] for k in ("doc_id", "n_words", "n_removed", "kept_sha256", *(("kept_text", "removed") if with_text else ()))}
            out["doc_id"] = batch.column(0)
            for text, flags in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                words = text.encode().split() if text else []
                gone: list[tuple[int, int]] = []
                if flags:
                    start = np.array([f["start"] for f in flags], np.int64)
                    bits = np.array([f["bits"] for f in flags], np.int64)
                    edge = np.zeros(len(words) + 1, np.int64)
                    for j in range(length - GRAM + 1):
                        hit = start[bits >> j & 1 == 1] + j
                        np.add.at(edge, hit, 1)
                        np.add.at(edge, hit + length, -1)
                    cover = np.concatenate(([0], np.cumsum(edge) > 0, [0]))
                    gone = list(zip(np.flatnonzero(np.diff(cover) == 1).tolist(), np.flatnonzero(np.diff(cover) == -1).tolist()))
                kept, at = [], 0
                for a, b in gone:
                    kept += words[at:a]
                    at = b
                kept += words[at:]
                joined = b" ".join(kept)
                out["n_words"].append(len(words))
                out["n_removed"].append(len(words) - len(kept))
                out["kept_sha256"].append(hashlib.sha256(joined).hexdigest())
                if with_text:
                    out["kept_text"].append(joined.decode())
                    out["removed"].append([{"start": a, "end": b} for a, b in gone])
            yield out

    long = T.LongType()
    extra = [T.StructField("kept_text", T.StringType()), T.StructField("removed", T.ArrayType(T.StructType([T.StructField("start", long), T.StructField("end", long)])))]
    schema = T.StructType([rows.schema["doc_id"], T.StructField("n_words", long), T.StructField("n_removed", long), T.StructField("kept_sha256", T.StringType()), *(extra if with_text else [])])
    return arrow_map(joined, work, schema)
