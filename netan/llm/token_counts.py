"""Token counts: lengths only, out of Arrow batches that are balanced by bytes, long texts split at safe boundaries.

A boundary is safe if no token can span it: before a single space, or around a single newline, that stands between two
characters which are no white space. Texts are cut at all such boundaries, and the library encodes each different piece
once per worker; a text's count is the sum over its pieces. Texts with other white space (runs of spaces, blank lines) are
cut by a slower rule that leaves such runs whole.

Nulls count as empty texts. Repeated rows give repeated rows, a null id stays null, an empty table gives an empty table. Very
long texts are counted whole, piece by piece. Columns beside id and text, those with names used here included, are not read.
"""

from __future__ import annotations

import os
import re
from itertools import chain

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from netan.llm.common import arrow_map, by_bytes, fields, keyed

#: Different pieces that a worker keeps; beyond it starts anew, so memory stays bounded.
KEPT_PIECES = 3_000_000

SAFE = re.compile(r"(?<=\S)(?= \S)")

#: Plain letters, and such letters with ASCII marks behind: no token of either vocabulary spans the change from one to the other.
LETTERS = re.compile(r"[A-Za-zÀ-ÖØ-öø-ÿ]+")
LETTERS_MARKS = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([.,!?;:%&*#$|()\-]+)")


def library(name: str):
    """The tokenizer of a public vocabulary file by name (`*.json` or `*.model`), or of a path."""
    import public_tokenizers

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    path = name if os.path.isabs(name) else public_tokenizers.path(name)
    if path.endswith(".model"):
        import sentencepiece

        return sentencepiece.SentencePieceProcessor(model_file=path)
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


class PieceLengths:
    """Token counts of texts under a byte-level tokenizer, by pieces."""

    def __init__(self, tokenizer) -> None:
        self.tokenizer = tokenizer
        self.spaced: dict[str, int] = {}  # of " " + key
        self.plain: dict[str, int] = {}
        self.parts: dict[str, int] = {"": 0}
        self.newline = len(tokenizer.encode("\n", add_special_tokens=False).ids)

    def _learn(self, known: dict[str, int], wanted: set[str], before: str) -> None:
        new = list(wanted.difference(known))
        if len(known) + len(new) > KEPT_PIECES:
            known.clear()
            new = list(wanted)
        for a in range(0, len(new), 20_000):
            part = new[a : a + 20_000]
            cut = [m.groups() if (m := LETTERS_MARKS.fullmatch(x)) else (x, "") for x in part]
            texts = [before + x for x, _ in cut] + [x for _, x in cut]
            fresh = list(set(texts).difference(self.parts))
            if len(self.parts) + len(fresh) > KEPT_PIECES:
                self.parts = {"": 0}
                fresh = list(set(texts))
            self.parts.update(zip(fresh, map(len, self.tokenizer.encode_batch_fast(fresh, add_special_tokens=False))))
            known.update((x, self.parts[before + y] + self.parts[z]) for x, (y, z) in zip(part, cut))

    def count(self, texts: list[str]) -> list[int]:
        heads, tails, extra, odd = [], [], [0] * len(texts), []
        for k, text in enumerate(texts):
            head, tail = [], []
            for line in text.split("\n"):
                words = line.split(" ")
                if not all(words) or words[0][0].isspace() or words[-1][-1].isspace():
                    odd.append(k)
                    head, tail = [], []
                    break
                head.append(words[0])
                tail += words[1:]
            else:
                extra[k] = (len(head) - 1) * self.newline
            heads.append(head)
            tails.append(tail)
        # a piece inside which white space touches a space would not be cut safely
        for k, tail in enumerate(tails):
            if tail and (any(map(_touches, tail)) or any(map(_ends, heads[k]))):
                odd.append(k)
                heads[k], tails[k], extra[k] = [], [], 0
        for k in odd:
            pieces = SAFE.split(texts[k])
            heads[k] = [x for x in pieces if x[:1] != " " or x[1:2].isspace()]
            tails[k] = [x[1:] for x in pieces if x[:1] == " " and not x[1:2].isspace()]
            heads[k] = [x for x in heads[k] if x]
        self._learn(self.plain, set(chain.from_iterable(heads)), "")
        self._learn(self.spaced, set(chain.from_iterable(tails)), " ")
        plain, spaced = self.plain.__getitem__, self.spaced.__getitem__
        return [n + sum(map(plain, h)) + sum(map(spaced, t)) for n, h, t in zip(extra, heads, tails)]


def _touches(word: str) -> bool:
    return word[0].isspace() or word[-1].isspace()


def _ends(word: str) -> bool:
    return word[-1].isspace()


def count_tokens(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) of each row's whole text."""

    def work(batches):
        tool = library(tokenizer)
        pieces = None if tokenizer.endswith(".model") else PieceLengths(tool)
        for batch in batches:
            ids, texts = batch.column(0), [x or "" for x in batch.column(1).to_pylist()]
            for a, b in by_bytes(texts):
                part = texts[a:b]
                counts = pieces.count(part) if pieces else [len(x) for x in tool.encode(part, num_threads=1)]
                yield {"doc_id": ids.slice(a, b - a), "n_bytes": [len(x.encode()) for x in part], "n_tokens": counts, "over_limit": [n > limit for n in counts]}

    rows = keyed(docs, id_col, text_col)
    schema = T.StructType([*fields(rows, "doc_id"), T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType())])
    return arrow_map(rows, work, schema)
