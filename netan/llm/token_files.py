"""Token-ID output: ids of whole documents in Simple-8b coded blocks, and their reading back.

File format. A table of chunks in Parquet; each row holds whole documents, in order: `part`, `chunk` (their order), `doc_ids`,
`lengths` (ids of each document), `payload`. A payload is little-endian: magic, number of ids, ids per block, number of blocks
(unsigned 32-bit each), the word offset of each block (unsigned 64-bit), then 64-bit words. A word's top four bits select how
many ids of which width it packs; selector 0 is the escape: the next word holds one value of more than 60 bits as it is.
Blocks begin at a word of their own, so any block can be decoded alone and all of them at once, without a loop over ids.

Rows are written in ascending id order, null ids first, equal ids by text, repeated rows as often as they come. Null texts hold
the end id only. A very long text is one document of one chunk. Columns beside id and text, those with names used here
included, are not read. Empty tables give no rows.
"""

from __future__ import annotations

import re
import zlib
from itertools import chain

import numpy as np
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from netan.llm.common import Numbers, arrow_map, by_sizes, fields, kept, keyed, light_batches
from netan.llm.token_counts import library
from netan.storage import written

#: Fixed values of the coding: width in bits and number of values by selector, 1 to 14.
WIDTHS = np.array([0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60])
COUNTS = np.array([1, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1])
BLOCK = 4096
MAGIC = 0x53384201
#: A chunk closes at the first document that takes it past so many ids.
CHUNK_IDS = 1 << 18
#: Different pre-tokens that a worker keeps from task to task; beyond it starts anew.
KEPT_PIECES = 600_000
#: Pre-tokens that are encoded as one text, and in one call.
JOINED = 100
JOINED_AT_ONCE = 10_000

#: Fixed values of the tokenizer: its pre-tokens, for lower-case Latin-1 text.
PRE_TOKEN = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zªµºß-öø-ÿ]+|[0-9²³¹¼½¾]|[^\t-\r \x85\xa0a-zªµºß-öø-ÿ0-9²³¹¼½¾]+")


def pack(values: np.ndarray, block: int = BLOCK) -> bytes:
    """Non-negative integers of up to 64 bits, coded."""
    v = np.asarray(values, dtype=np.uint64)
    n, n_blocks = len(v), -(-len(v) // block)
    if not n:
        return np.array([MAGIC, 0, block, 0], "<u4").tobytes()
    # the selector that takes most values from each place on; zeros behind each block fit in any
    left = np.minimum(block - np.arange(n) % block, n - np.arange(n))
    gap = int(COUNTS.max())
    bits = np.zeros(n_blocks * block, np.uint8)
    bits[:n] = np.frexp(v.astype(np.float64))[1].clip(0, 64)
    bits = np.pad(bits.reshape(n_blocks, block), ((0, 0), (0, gap))).ravel()
    choice, widest, seen = np.zeros(len(bits), np.int8), bits.copy(), 1
    for s in range(len(WIDTHS) - 1, 0, -1):
        for j in range(seen, COUNTS[s]):  # widest of the values at each place and the next ones
            np.maximum(widest[:-j], bits[j:], out=widest[:-j])
        seen = COUNTS[s]
        choice[widest <= WIDTHS[s]] = s
    choice = choice.reshape(n_blocks, block + gap)[:, :block].ravel()[:n]
    step = np.minimum(COUNTS[choice], left).astype(np.int64)
    # all blocks are walked side by side, one word a turn
    at, ends = np.arange(n_blocks) * block, np.minimum(np.arange(1, n_blocks + 1) * block, n)
    turns_at, turns_block, live = [], [], np.arange(n_blocks)
    while len(live):
        turns_at.append(at[live])
        turns_block.append(live)
        at[live] += step[at[live]]
        live = live[at[live] < ends[live]]
    first, owner = np.concatenate(turns_at), np.concatenate(turns_block)
    order = np.argsort(first, kind="stable")
    first, owner = first[order], owner[order]
    sel = choice[first].astype(np.int64)
    size = np.where(sel == 0, 2, 1)
    where = np.concatenate(([0], np.cumsum(size)))[:-1]
    words = np.zeros(int(size.sum()), np.uint64)
    words[where] = sel.astype(np.uint64) << np.uint64(60)
    padded = np.concatenate((v, np.zeros(60, np.uint64)))
    for s in np.unique(sel):
        mine = np.flatnonzero(sel == s)
        if s == 0:
            words[where[mine] + 1] = v[first[mine]]
            continue
        took, word = step[first[mine]], words[where[mine]]
        for j in range(COUNTS[s]):
            word |= np.where(j < took, padded[first[mine] + j], np.uint64(0)) << np.uint64(j * WIDTHS[s])
        words[where[mine]] = word
    offsets = where[np.searchsorted(owner, np.arange(n_blocks))]
    return np.array([MAGIC, n, block, n_blocks], "<u4").tobytes() + offsets.astype("<u8").tobytes() + words.astype("<u8").tobytes()


def unpack(payload: bytes) -> np.ndarray:
    """The integers that `pack` has coded."""
    magic, n, block, n_blocks = (int(x) for x in np.frombuffer(payload, "<u4", 4))
    if magic != MAGIC:
        raise ValueError("not a block of ids")
    if not n:
        return np.zeros(0, np.uint64)
    offsets = np.frombuffer(payload, "<u8", n_blocks, 16).astype(np.int64)
    words = np.frombuffer(payload, "<u8", -1, 16 + 8 * n_blocks)
    sel = (words >> np.uint64(60)).astype(np.int64)
    if (sel == 0).any():  # words behind an escape are values
        is_head = np.ones(len(words), bool)
        for k in np.flatnonzero(sel == 0):
            if is_head[k]:
                is_head[k + 1] = False
    else:
        is_head = np.ones(len(words), bool)
    head = np.flatnonzero(is_head)
    sel = sel[head]
    took = COUNTS[sel]
    # a block's last word may hold fewer: what its block still lacks
    start = np.searchsorted(head, offsets)
    last = np.append(start[1:], len(head)) - 1
    sums = np.add.reduceat(took, start)
    took[last] -= sums - np.minimum(block, n - np.arange(n_blocks) * block)
    first = np.concatenate(([0], np.cumsum(took)))[:-1]
    out = np.zeros(n, np.uint64)
    for s in np.unique(sel):
        mine = np.flatnonzero(sel == s)
        if s == 0:
            out[first[mine]] = words[head[mine] + 1]
            continue
        mask = np.uint64((1 << int(WIDTHS[s])) - 1)
        for j in range(COUNTS[s]):
            some = mine[took[mine] > j]
            out[first[some] + j] = words[head[some]] >> np.uint64(j * WIDTHS[s]) & mask
    return out


class PieceIds:
    """Ids of texts under a tokenizer that drops white space and marks the last token of each pre-token by a suffix.

    Texts of Latin-1 characters are lower-cased and cut in pre-tokens as the tokenizer does it. Each different pre-token is
    encoded once per worker, many in one text: the suffix tells where one ends. Other texts are cut at white space only, and
    their words are encoded one by one.
    """

    def __init__(self, tokenizer) -> None:
        self.tokenizer = tokenizer
        suffix = tokenizer.model.end_of_word_suffix
        if not suffix:
            raise ValueError("the tokenizer must mark the ends of words")
        self.last = np.array([(tokenizer.id_to_token(i) or "").endswith(suffix) for i in range(tokenizer.get_vocab_size())])
        self._forget()

    def _forget(self) -> None:
        self.known = Numbers()
        self.pool, self.used = np.zeros(1 << 16, np.uint32), 0
        self.starts, self.sizes = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64)

    def _grown(self, a: np.ndarray, n: int) -> np.ndarray:
        return a if n <= len(a) else np.concatenate((a, np.zeros(max(n, 2 * len(a)) - len(a), a.dtype)))

    def _ids(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of pieces, one after another, and the number of each one's."""
        if all(map(PRE_TOKEN.fullmatch, pieces)):
            joined = [" ".join(pieces[a : a + JOINED]) for a in range(0, len(pieces), JOINED)]
            got = [x.ids for x in self.tokenizer.encode_batch_fast(joined, add_special_tokens=False)]
            flat = np.fromiter(chain.from_iterable(got), np.uint32, sum(map(len, got)))
            ends = np.flatnonzero(self.last[flat]) + 1
            if len(ends) == len(pieces):
                return flat, np.diff(ends, prepend=0)
        got = [x.ids for x in self.tokenizer.encode_batch_fast(pieces, add_special_tokens=False)]
        sizes = np.fromiter(map(len, got), np.int64, len(got))
        return np.fromiter(chain.from_iterable(got), np.uint32, int(sizes.sum())), sizes

    def _learn(self) -> None:
        fresh, self.known.fresh = self.known.fresh, []
        k = len(self.known) - len(fresh)
        for a in range(0, len(fresh), JOINED_AT_ONCE):
            part = fresh[a : a + JOINED_AT_ONCE]
            flat, sizes = self._ids(part)
            self.starts, self.sizes = (self._grown(x, k + len(part)) for x in (self.starts, self.sizes))
            self.pool = self._grown(self.pool, self.used + len(flat))
            self.starts[k : k + len(part)] = self.used + np.cumsum(sizes) - sizes
            self.sizes[k : k + len(part)] = sizes
            self.pool[self.used : self.used + len(flat)] = flat
            self.used += len(flat)
            k += len(part)

    def encode(self, texts: list[str], end: int) -> tuple[np.ndarray, np.ndarray]:
        """All ids, one text after another with `end` behind each, and the number of each text's."""
        if len(self.known) > KEPT_PIECES:
            self._forget()
        split = [_cut(x) for x in texts]
        n_pieces = np.fromiter(map(len, split), np.int64, len(split))
        keys = np.fromiter(map(self.known.__getitem__, chain.from_iterable(split)), np.int64, int(n_pieces.sum()))
        self._learn()
        sizes = self.sizes[keys]
        ends = np.cumsum(n_pieces)
        totals = np.concatenate(([0], np.cumsum(sizes)))
        counts = totals[ends] - totals[ends - n_pieces]
        total = int(totals[-1])
        place = np.repeat(self.starts[keys] - (totals[1:] - sizes), sizes) + np.arange(total)
        out = np.full(total + len(texts), end, np.uint32)
        spot = np.ones(len(out), bool)
        spot[np.cumsum(counts + 1) - 1] = False
        out[spot] = self.pool[place]
        return out, counts + 1


def _cut(text: str) -> list[str]:
    """Pre-tokens of a Latin-1 text without special tokens; of other texts the words, or the text where white space is odd."""
    if "<|" not in text:
        try:
            text.encode("latin-1")
            return PRE_TOKEN.findall(text.lower())
        except UnicodeEncodeError:
            pass
    # control characters 1C-1F part words for str.split(), but not for the tokenizer
    return [text] if any(c in text for c in "\x1c\x1d\x1e\x1f") else text.split()


def shared_pieces(tokenizer: str) -> PieceIds:
    """The words that this Python worker knows, kept from task to task."""
    return kept(("pieces", tokenizer), lambda: PieceIds(library(tokenizer)))


def write_ids(docs: DataFrame, tokenizer: str = "word_bpe_49k.json", end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", partitions: int | None = None) -> DataFrame:
    """The table of chunks, written in the shared folder: ids of all documents, end_id behind each, ascending by id."""
    rows = keyed(docs, id_col, text_col)
    by = [F.col("doc_id").asc_nulls_first()]
    dealt = rows.repartitionByRange(partitions, *by) if partitions else rows.repartitionByRange(*by)
    dealt = dealt.sortWithinPartitions(*by, F.col("text").asc_nulls_first())

    def work(batches):
        from pyspark import TaskContext

        part, chunk = TaskContext.get().partitionId(), 0
        pieces = shared_pieces(tokenizer)
        held_ids, held_counts, held = [], [], []

        def closed():
            return {"part": [part], "chunk": [chunk], "doc_ids": [held_ids], "lengths": [held_counts], "payload": [pack(np.concatenate(held))]}

        size = 0
        for batch in batches:
            ids, sizes = batch.column(0).to_pylist(), pc.binary_length(batch.column(1)).fill_null(0).to_pylist()
            for a, b in by_sizes(sizes, 1 << 19):
                texts = [x or "" for x in batch.column(1).slice(a, b - a).to_pylist()]
                flat, counts = pieces.encode(texts, end_id)
                held_ids += ids[a:b]
                held_counts += counts.tolist()
                held.append(flat)
                size += len(flat)
                if size >= CHUNK_IDS:
                    yield closed()
                    chunk, size, held_ids, held_counts, held = chunk + 1, 0, [], [], []
        if held:
            yield closed()

    kind = rows.schema["doc_id"].dataType
    schema = T.StructType([T.StructField("part", T.IntegerType()), T.StructField("chunk", T.IntegerType()), T.StructField("doc_ids", T.ArrayType(kind)), T.StructField("lengths", T.ArrayType(T.LongType())), T.StructField("payload", T.BinaryType())])
    with light_batches(docs.sparkSession):
        return written(arrow_map(dealt, work, schema, keeps=True), "token-ids")


def read_ids(chunks: DataFrame, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of every document in a table of chunks; start counts the ids before it."""
    sums = chunks.groupBy("part", "chunk").agg(F.sum(F.aggregate("lengths", F.lit(0).cast("long"), lambda a, x: a + x)).alias("n"))
    parts = sums.groupBy("part").agg(F.sum("n").alias("n"))  # a row for each file
    over = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("part", F.coalesce(F.sum("n").over(over), F.lit(0)).alias("before_part"))
    over = Window.partitionBy("part").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    before = sums.select("part", "chunk", F.coalesce(F.sum("n").over(over), F.lit(0)).alias("before")).join(parts, "part")
    before = before.select("part", "chunk", (F.col("before") + F.col("before_part")).alias("chunk_start"))

    def work(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                part, chunk, payload = (batch.column(c)[k].as_py() for c in ("part", "chunk", "payload"))
                flat = unpack(payload).astype("<u4")
                counts = batch.column("lengths")[k].values.to_numpy(zero_copy_only=False)
                ends = np.cumsum(counts)
                local = ends - counts
                out = {"part": np.full(len(counts), part), "chunk": np.full(len(counts), chunk), "doc_id": batch.column("doc_ids")[k].values, "local_start": local, "n_tokens": counts}
                bounds, raw = (4 * ends).tolist(), memoryview(flat).cast("B")
                out["ids_crc32"] = [zlib.crc32(raw[a:b]) for a, b in zip([0, *bounds], bounds)]
                if with_ids:
                    out["ids"] = [flat[a:b] for a, b in zip(local, ends)]
                yield out

    long = T.LongType()
    kind = chunks.schema["doc_ids"].dataType.elementType
    schema = T.StructType([T.StructField("part", T.IntegerType()), T.StructField("chunk", T.IntegerType()), T.StructField("doc_id", kind), T.StructField("local_start", long), T.StructField("n_tokens", long), T.StructField("ids_crc32", long), *([T.StructField("ids", T.ArrayType(long))] if with_ids else [])])
    rows = arrow_map(chunks, work, schema).join(before, ["part", "chunk"])
    return rows.select("doc_id", (F.col("chunk_start") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32", *(["ids"] if with_ids else []))
