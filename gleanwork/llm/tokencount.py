"""Token counts of whole texts, by overlap resynchronisation for huge ones.

A text up to CHUNK code points is encoded whole. A longer one is encoded in chunks that overlap; the tokens of two
neighbours, with their offsets, are compared inside the overlap, and the texts are spliced at a boundary where both agree
over STABLE tokens on either side and that white space follows, over which no token reaches. Where no such boundary
exists the overlap is doubled; if that uses up a chunk, the text is encoded whole.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from .common import map_text, table

LIMIT = 2048
CHUNK, OVERLAP, STABLE = 1 << 15, 1 << 10, 8
#: Bytes, about, of the pieces a worker remembers with the number of their tokens (an eighth of it with the tokens themselves),
#: and the longest piece it remembers, in code points.
MEMO_BYTES, LONGEST = 96 << 20, 128
#: What an entry takes beside the piece itself.
_ENTRY = 140
#: Pieces that go to the library in one call, and code points of the texts counted together.
JOINED, TOGETHER = 4096, 1 << 20
_CLOSING = ".,;:!?%#$&*"
_BLANK = {9: 32, 10: 32, 13: 32}
_PIECE = re.compile(r"[^ \n\r\t]+")


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Encoder:
    """Tokens (id, end offset) as the library gives them.

    The vocabulary's normaliser turns white space into one space and its splitter drops it, so no token reaches over a
    space and a piece between spaces always gives the same tokens: pieces up to LONGEST go to the library once and are
    remembered, until the memory for it is full; longer ones are asked for each time.
    """

    def __init__(self, vocabulary: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(vocabulary)
        self.library.no_padding()
        self.library.no_truncation()
        self.numbers: dict[str, int] = {"": 0}
        self.tokens: dict[str, tuple[list[int], list[int]]] = {}
        self.held_numbers = self.held_tokens = 0

    def _ask(self, pieces: list[str]) -> None:
        for i in range(0, len(pieces), JOINED):
            some = pieces[i : i + JOINED]
            self.numbers.update(zip(some, map(len, self.library.encode_batch_fast(some, add_special_tokens=False))))
        self.held_numbers += sum(map(len, pieces)) + _ENTRY * len(pieces)

    def _spare(self) -> None:
        """Forget when the memory is full, and long pieces always."""
        if self.held_numbers > MEMO_BYTES:
            self.numbers, self.held_numbers = {"": 0}, 0
        for p in self.long:
            self.numbers.pop(p, None)
        self.long = []

    def count(self, texts: list[str]) -> list[int]:
        """Tokens of each text. Closing punctuation after a letter or digit is looked up apart, as the splitter parts it
        there, and an ASCII stem in lower case, as the normaliser gives it.
        """
        pieces = [t.translate(_BLANK).split(" ") if "\t" in t or "\r" in t else t.replace("\n", " ").split(" ") for t in texts]
        new: set[str] = set()
        for p in pieces:
            new.update(set(p).difference(self.numbers))
        parts: dict[str, tuple[str, str]] = {}
        whole, wanted = [], set()
        for p in new:
            stem = p.rstrip(_CLOSING)
            if stem and "<|" not in p and (stem[-1].lower().isalpha() or "0" <= stem[-1] <= "9"):
                low = stem.lower() if stem.isascii() else stem
                if low != p:
                    parts[p] = (low, p[len(stem) :])
                    wanted.update(parts[p])
                    continue
            whole.append(p)
        wanted.update(whole)
        self._ask(list(wanted.difference(self.numbers)))
        known = self.numbers
        for p, (stem, tail) in parts.items():
            known[p] = known[stem] + known[tail]
            self.held_numbers += len(p) + _ENTRY
        counts = [sum(map(known.__getitem__, p)) for p in pieces]
        self.long = [p for p in [*new, *wanted] if len(p) > LONGEST]
        self._spare()
        return counts

    def encode(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Token ids and end offsets (code points)."""
        found = list(_PIECE.finditer(text))
        new = list({m[0] for m in found}.difference(self.tokens))
        for i in range(0, len(new), JOINED):
            for p, e in zip(new[i : i + JOINED], self.library.encode_batch(new[i : i + JOINED], add_special_tokens=False)):
                self.tokens[p] = (e.ids, [b for _, b in e.offsets])
                self.held_tokens += len(p) + _ENTRY + 72 * len(e.ids)
        ids: list[int] = []
        ends: list[int] = []
        for m in found:
            tokens, offsets = self.tokens[m[0]]
            ids += tokens
            start = m.start()
            ends += [start + b for b in offsets]
        if self.held_tokens > MEMO_BYTES >> 3:
            self.tokens, self.held_tokens = {}, 0
        return np.array(ids, np.int64), np.array(ends, np.int64)


#: A process's encoders: they outlive a task, so that a reused worker keeps what it has learnt.
_ENCODERS: dict[str, Encoder] = {}


def encoder_of(vocabulary: str) -> Encoder:
    if vocabulary not in _ENCODERS:
        _ENCODERS[vocabulary] = Encoder(vocabulary)
    return _ENCODERS[vocabulary]


def splice(text: str, left: tuple[np.ndarray, np.ndarray], right: tuple[np.ndarray, np.ndarray], low: int, high: int, stable: int) -> tuple[int, int] | None:
    """(tokens of left kept, tokens of right skipped) at the first boundary in [low, high) proven stable, or None.

    Proven: white space follows it, so neither side depends on the other, and the stable tokens before it and after it
    have equal ids and equal ends in both encodings.
    """
    (a_id, a_end), (b_id, b_end) = left, right
    i, j = int(np.searchsorted(a_end, low, "right")), int(np.searchsorted(b_end, low, "right"))
    i_of = {}
    for k in range(i, len(a_end)):
        if a_end[k] >= high:
            break
        i_of[int(a_end[k])] = k  # of tokens with one end, the last
    for k in range(j, len(b_end)):
        end = int(b_end[k])
        if end >= high:
            break
        at = i_of.get(end)
        if at is None or text[end] not in " \n\r\t" or (k + 1 < len(b_end) and b_end[k + 1] == end):
            continue
        a, b = slice(at + 1 - stable, at + 1 + stable), slice(k + 1 - stable, k + 1 + stable)
        if at + 1 - stable >= 0 and k + 1 - stable >= 0 and at + 1 + stable <= len(a_end) and k + 1 + stable <= len(b_end) and (a_id[a] == b_id[b]).all() and (a_end[a] == b_end[b]).all():
            return at + 1, k + 1
    return None


def count_long(encode, text: str, chunk: int = CHUNK, overlap: int = OVERLAP, stable: int = STABLE) -> int:
    """Tokens of a long text; encode(text) -> (ids, ends) of any piece of it."""
    ids, ends = encode(text[:chunk])
    total, begin, stop = 0, 0, min(chunk, len(text))
    while stop < len(text):
        wide = overlap
        while True:
            start = max(begin, stop - wide)
            if start == begin:
                return len(encode(text)[0])
            upto = min(len(text), stop + chunk)
            nxt, nxt_ends = encode(text[start:upto])
            nxt_ends = nxt_ends + start
            if cut := splice(text, (ids, ends), (nxt, nxt_ends), start, stop, stable):
                total += cut[0]
                ids, ends = nxt[cut[1] :], nxt_ends[cut[1] :]
                begin, stop = start, upto
                break
            wide *= 2
    return total + len(ids)


def _together(texts: list[str]) -> Iterator[list[str]]:
    """Texts in blocks of at most TOGETHER code points, or one text."""
    some, held = [], 0
    for t in texts:
        if some and held + len(t) > TOGETHER:
            yield some
            some, held = [], 0
        some.append(t)
        held += len(t)
    if some:
        yield some


def token_counts(docs: DataFrame, vocabulary: str | None = None, key: str = "doc_id", text: str = "text", chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """(key, n_bytes, n_tokens) for each row; null and empty texts have none; repeated rows repeat; other columns unread."""
    path = vocabulary or default_vocabulary()
    schema = T.StructType([T.StructField("key", docs.schema[key].dataType), T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType())])

    def work(blocks):
        encoder = encoder_of(path)
        for (keys,), texts in blocks:
            texts = [t or "" for t in texts]
            short = [t for t in texts if len(t) <= chunk]
            counted = []
            for some in _together(short):
                counted += encoder.count(some)
            of_short = iter(counted)
            counts = [next(of_short) if len(t) <= chunk else count_long(encoder.encode, t, chunk, overlap) for t in texts]
            yield [keys, [len(t.encode("utf-8", "surrogatepass")) for t in texts], counts]

    return map_text(docs.select(docs[key].alias("key"), docs[text].alias("text")), ["key"], "text", schema, work).withColumnRenamed("key", key)


def op5_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = token_counts(table(spark, sf_dir, "documents"))
    return counts.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > LIMIT).alias("over_limit"))
