"""Benchmark decontamination by a distributed positional inverted index.

The index is partitioned by document: each row holds the postings of all terms of a few million characters of whole documents
(terms, and for each its sorted positions, numbered through the row's documents). It is stored as a table. Test items are
looked up in every row: the positions of a phrase's terms, each less its offset in the phrase, are intersected from the
rarest term on. A phrase with a term that the row lacks ends there. Exact phrases and proximity matches (all terms within a
given number of words, in any order) are found.

Items are the queries; they come to the driver and go to the executors in blocks of bounded size, one after the other, and a
document's hits of all blocks are put together. Nulls and texts without words have no terms and match nothing. Repeated rows
are judged alike; an item id that occurs twice counts once, with the windows of both texts. A very long text is a row of the
index of its own. Columns beside id and text, those with names used here included, are not read. Empty tables give no
rows, or no hits.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.llm.common import arrow_map, by_bytes, keyed, light_batches, row_key
from netan.storage import lasting, scratch, written

#: Words: lower-cased ASCII letters and digits and everything beyond ASCII; all other bytes part words.
TERM_BYTES = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))

#: Characters of documents in a row of the index, and of items in a block.
ROW_CHARS = 1 << 22
BLOCK_CHARS = 1 << 21


def terms(text: str | None) -> list[bytes]:
    return text.encode().translate(TERM_BYTES).split() if text else []


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The stored index: (part, row, doc_ids, rids, sizes, terms, ends, postings)."""
    rows = row_key(keyed(docs, id_col, text_col))

    def work(batches):
        from pyspark import TaskContext

        part, k = TaskContext.get().partitionId(), 0
        for batch in batches:
            ids, texts, rids = (batch.column(i).to_pylist() for i in range(3))
            for a, b in by_bytes(texts, ROW_CHARS):
                found = [terms(x) for x in texts[a:b]]
                sizes = np.fromiter(map(len, found), np.int64, b - a)
                number: dict[bytes, int] = {}
                for words in found:
                    for w in set(words).difference(number):
                        number[w] = len(number)
                get = number.__getitem__
                flat = np.fromiter((i for words in found for i in map(get, words)), np.int32, int(sizes.sum()))
                # one free position behind each document, so that no phrase spans two
                place = np.arange(len(flat)) + np.repeat(np.arange(b - a), sizes)
                postings = place[np.argsort(flat, kind="stable")].astype("<u4")
                ends = np.cumsum(np.bincount(flat, minlength=len(number))).astype("<u4")
                yield {"part": [part], "row": [k], "doc_ids": [ids[a:b]], "rids": [rids[a:b]], "sizes": [sizes], "terms": [b"\n".join(number)], "ends": [ends.tobytes()], "postings": [postings.tobytes()]}
                k += 1

    kind, long, binary = rows.schema["doc_id"].dataType, T.LongType(), T.BinaryType()
    schema = T.StructType([T.StructField("part", T.IntegerType()), T.StructField("row", T.IntegerType()), T.StructField("doc_ids", T.ArrayType(kind)), T.StructField("rids", T.ArrayType(long)), T.StructField("sizes", T.ArrayType(long)), T.StructField("terms", binary), T.StructField("ends", binary), T.StructField("postings", binary)])
    return written(arrow_map(rows, work, schema), "positional-index")


class Postings:
    """One row of the index."""

    def __init__(self, row: dict) -> None:
        self.sizes = np.array(row["sizes"], np.int64)
        self.bases = np.concatenate(([0], np.cumsum(self.sizes + 1)))
        words = row["terms"].split(b"\n") if row["terms"] else []
        self.number = dict(zip(words, range(len(words))))
        self.ends = np.concatenate(([0], np.frombuffer(row["ends"], "<u4"))).astype(np.int64)
        self.places = np.frombuffer(row["postings"], "<u4")

    def of(self, term: int) -> np.ndarray:
        return self.places[self.ends[term] : self.ends[term + 1]]

    def phrase(self, numbers: list[int]) -> np.ndarray:
        """Places where these terms stand one after another."""
        order = sorted(range(len(numbers)), key=lambda j: self.ends[numbers[j] + 1] - self.ends[numbers[j]])
        at = self.of(numbers[order[0]]).astype(np.int64) - order[0]
        for j in order[1:]:
            if not len(at):
                break
            there = self.of(numbers[j])
            k = np.searchsorted(there, at + j)
            at = at[there[np.minimum(k, len(there) - 1)] == at + j]
        return at

    def near(self, numbers: list[int], width: int) -> np.ndarray:
        """Starts of the shortest stretches of at most `width` words of one document that hold all these terms."""
        numbers = sorted(set(numbers))
        lists = [self.of(n).astype(np.int64) for n in numbers]
        place = np.concatenate(lists)
        kind = np.repeat(np.arange(len(lists)), [len(x) for x in lists])
        order = np.argsort(place)
        place, kind = place[order], kind[order]
        out, last = [], {}
        for p, k in zip(place.tolist(), kind.tolist()):
            last.pop(k, None)
            last[k] = p  # oldest first
            if len(last) == len(lists):
                first = next(iter(last.values()))
                if p - first < width and self.document(np.array([first]))[0] == self.document(np.array([p]))[0] and (not out or out[-1] != first):
                    out.append(first)
        return np.array(out, np.int64)

    def document(self, places: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.bases, places, "right") - 1


class Queries:
    """Windows of test items, each once, with the items that hold it."""

    def __init__(self, items: list[tuple[str, str]], window: int) -> None:
        held: dict[tuple[bytes, ...], set[str]] = {}
        for item, text in items:
            words = terms(text)
            for a in range(max(1, len(words) - window + 1) if words else 0):
                held.setdefault(tuple(words[a : a + window]), set()).add(item)
        self.windows = list(held)
        self.items = [sorted(x) for x in held.values()]
        vocabulary = {w for x in self.windows for w in x}
        self.words = sorted(vocabulary)
        number = {w: k for k, w in enumerate(self.words)}
        # rows of term numbers, short windows filled up with their first
        self.matrix = np.array([[number[w] for w in x] + [number[x[0]]] * (window - len(x)) for x in self.windows], np.int64).reshape(-1, window)

    def found(self, row: Postings):
        """(window, places) of the windows that occur in a row of the index."""
        here = np.array([row.number.get(w, -1) for w in self.words] or [-1], np.int64)
        if len(self.matrix):
            for k in np.flatnonzero((here[self.matrix] >= 0).all(axis=1)):
                at = row.phrase(here[self.matrix[k, : len(self.windows[k])]].tolist())
                if len(at):
                    yield int(k), at


def _blocks(items: DataFrame, id_col: str, text_col: str) -> tuple[int, Iterator[list[tuple[str, str]]]]:
    """Number of blocks, and items in blocks of about BLOCK_CHARS by a hash of their ids, fetched as they are asked for."""
    rows = items.where(items[text_col].isNotNull()).select(F.coalesce(items[id_col].cast("string"), F.lit("null")).alias("i"), items[text_col].alias("t"))
    size = rows.agg(F.sum(F.length("t"))).first()[0] or 0
    parts = max(1, -(-size // BLOCK_CHARS))
    rows = rows.withColumn("b", F.pmod(F.xxhash64("i"), F.lit(parts)))
    return parts, ([(r.i, r.t) for r in rows.where(F.col("b") == k).collect()] for k in range(parts))


def _spans(index: DataFrame, block: list[tuple[str, str]], window: int, per_cent: int | None = None) -> DataFrame:
    """(part, row, k, doc_id, rid, n_words, starts, ends, items) of every document of the index for one block of items.

    With per_cent, the block is all there is, and the worker that finds the spans judges them too: a second Python step behind it
    would keep twice as many workers on each executor, then and in later stages.
    """
    sent = index.sparkSession.sparkContext.broadcast(block)

    def work(batches):
        queries = Queries(sent.value, window)
        for batch in batches:
            for i in range(batch.num_rows):
                raw = batch.slice(i, 1).to_pylist()[0]
                row = Postings(raw)
                n = len(row.sizes)
                edge = np.zeros(int(row.bases[-1]) + 1, np.int32)
                held: list[set[str]] = [set() for _ in range(n)]
                for k, at in queries.found(row):
                    np.add.at(edge, at, 1)
                    np.add.at(edge, at + len(queries.windows[k]), -1)
                    for d in set(row.document(at).tolist()):
                        held[d].update(queries.items[k])
                hit = np.concatenate(([0], (np.cumsum(edge) > 0).astype(np.int8), [0]))
                starts, ends = np.flatnonzero(np.diff(hit) == 1), np.flatnonzero(np.diff(hit) == -1)
                of = row.document(starts)
                cut = np.searchsorted(of, np.arange(n + 1))
                base = row.bases
                found = {
                    "part": [raw["part"]] * n, "row": [raw["row"]] * n, "k": list(range(n)), "doc_id": raw["doc_ids"], "rid": raw["rids"], "n_words": row.sizes,
                    "starts": [starts[cut[d] : cut[d + 1]] - base[d] for d in range(n)], "ends": [ends[cut[d] : cut[d + 1]] - base[d] for d in range(n)], "items": [sorted(x) for x in held],
                }
                yield found if per_cent is None else _judged(found, per_cent)

    int_, long = T.IntegerType(), T.LongType()
    schema = T.StructType([T.StructField("part", int_), T.StructField("row", int_), T.StructField("k", int_), T.StructField("doc_id", index.schema["doc_ids"].dataType.elementType), T.StructField("rid", long), T.StructField("n_words", long), T.StructField("starts", T.ArrayType(long)), T.StructField("ends", T.ArrayType(long)), T.StructField("items", T.ArrayType(T.StringType()))])
    return arrow_map(index, work, schema if per_cent is None else _verdicts(schema["doc_id"].dataType))


def _judged(rows: dict, per_cent: int) -> dict:
    """The verdict's columns of spans' columns."""
    hits, sums, counts = [], [], []
    for a, b, items in zip(rows["starts"], rows["ends"], rows["items"]):
        n, upto = 0, 0
        for x, y in sorted(zip(a, b)):
            n += max(0, y - max(x, upto))
            upto = max(upto, y)
        names = sorted(set(items))
        hits.append(n)
        counts.append(len(names))
        sums.append(hashlib.sha256(",".join(names).encode()).hexdigest())
    bad = [bool(h > 0 and 100 * h >= per_cent * n) for h, n in zip(hits, rows["n_words"])]
    return {"doc_id": rows["doc_id"], "rid": rows["rid"], "n_words": rows["n_words"], "n_hit": hits, "n_items": counts, "items_sha256": sums, "items": rows["items"], "contaminated": bad}


def _verdicts(kind: T.DataType) -> T.StructType:
    long = T.LongType()
    return T.StructType([T.StructField("doc_id", kind), T.StructField("rid", long), T.StructField("n_words", long), T.StructField("n_hit", long), T.StructField("n_items", long), T.StructField("items_sha256", T.StringType()), T.StructField("items", T.ArrayType(T.StringType())), T.StructField("contaminated", T.BooleanType())])


def _verdict(spans: DataFrame, per_cent: int) -> DataFrame:
    def work(batches):
        for batch in batches:
            yield _judged({n: batch.column(n).to_pylist() for n in ("doc_id", "rid", "n_words", "starts", "ends", "items")}, per_cent)

    return arrow_map(spans, work, _verdicts(spans.schema["doc_id"].dataType))


def judge(index: DataFrame, items: DataFrame, window: int = 13, per_cent: int = 5, item_id: str = "item_id", text_col: str = "text") -> DataFrame:
    """(doc_id, rid, n_words, n_hit, n_items, items_sha256, items, contaminated) of each indexed document.

    A word is hit if it stands in an occurrence of a window of an item (of the whole item, if that is shorter); a document is
    contaminated if hit words are per_cent of its words or more.
    """
    parts, blocks = _blocks(items, item_id, text_col)
    if parts == 1:
        return _spans(index, next(blocks), window, per_cent)
    hits = None
    for b in blocks:  # each is done with before the next is fetched
        found = written(_spans(index, b, window).where(F.size("starts") > 0).select("part", "row", "k", "starts", "ends", "items"), "hits")
        hits = found if hits is None else hits.unionByName(found)
    hits = hits.groupBy("part", "row", "k").agg(*(F.flatten(F.collect_list(c)).alias(c) for c in ("starts", "ends", "items")))
    docs = index.select("part", "row", F.posexplode(F.arrays_zip("doc_ids", "rids", "sizes")).alias("k", "d"))
    docs = docs.select("part", "row", "k", F.col("d.doc_ids").alias("doc_id"), F.col("d.rids").alias("rid"), F.col("d.sizes").alias("n_words"))
    none = {"starts": "array<bigint>", "ends": "array<bigint>", "items": "array<string>"}
    both = docs.join(hits, ["part", "row", "k"], "left").withColumns({c: F.coalesce(c, F.array().cast(kind)) for c, kind in none.items()})
    return _verdict(both, per_cent)


def decontaminate(docs: DataFrame, items: DataFrame, window: int = 13, per_cent: int = 5) -> DataFrame:
    """judge() of documents, by an index that is dropped again."""
    with scratch(), light_batches(docs.sparkSession):
        return lasting(judge(build_index(docs), items, window, per_cent), "judged")


def search(index: DataFrame, items: DataFrame, slop: int | None = None, item_id: str = "item_id", text_col: str = "text") -> DataFrame:
    """(item_id, doc_id, rid, start, length) of every place where an item's whole text stands.

    Without slop, as a phrase; with it, all the item's terms within its length and slop more words, in any order (length 0).
    """
    out = None
    for block in _blocks(items, item_id, text_col)[1]:
        sent = index.sparkSession.sparkContext.broadcast(block)

        def work(batches, sent=sent):
            queries = [(i, terms(t)) for i, t in sent.value]
            for batch in batches:
                for raw in batch.to_pylist():
                    row = Postings(raw)
                    for item, words in queries:
                        numbers = [row.number.get(w, -1) for w in words]
                        if not numbers or min(numbers) < 0:
                            continue
                        at = row.phrase(numbers) if slop is None else row.near(numbers, len(words) + slop)
                        d = row.document(at)
                        yield {"item_id": [item] * len(at), "doc_id": [raw["doc_ids"][x] for x in d], "rid": [raw["rids"][x] for x in d], "start": at - row.bases[d], "length": [len(words) if slop is None else 0] * len(at)}

        long = T.LongType()
        schema = T.StructType([T.StructField("item_id", T.StringType()), T.StructField("doc_id", index.schema["doc_ids"].dataType.elementType), T.StructField("rid", long), T.StructField("start", long), T.StructField("length", long)])
        found = written(arrow_map(index, work, schema), "found")
        out = found if out is None else out.unionByName(found)
    return out
