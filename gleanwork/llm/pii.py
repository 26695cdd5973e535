"""Personal data: exact base patterns, and a character-level BiLSTM-CRF that adds what they miss.

The tagger is trained in numpy on labelled spans that a generator writes (addresses, numbers and keys in many spellings,
inside carrier words, with look-alikes that are not personal data). Every span it can add has a digit, an at sign or
the written form of one ("(at)", "[at]"; see _plausible), so it reads the surroundings of each of these in the whole text, out
to the ends of the tokens there, in overlapping windows; where windows overlap, their
emissions are averaged, weighted to a window's middle, and one Viterbi pass decodes the whole stretch.

Time grows linearly with a text's length, whatever it holds, and a stretch of any length is decoded in bounded memory. The
trained weights lie beside this module; `python -m gleanwork.llm.pii` trains them again and writes them.
"""

from __future__ import annotations

import bisect
import functools
import importlib.resources
import io
import itertools
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import map_text, table
from .tagger import Decoder, Tagger, encode

# Base kinds and their patterns. They match what the plain patterns of the contract match, but never try a start
# inside a run that was read from its beginning, and give nothing back; an address is sought from its at sign.
BASE = {
    "email": re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    "ip": re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}"),
    "card": re.compile(r"[0-9](?:[\x20-]?[0-9])++"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
KINDS = [*BASE, "secret"]
TAGS = 1 + 2 * len(KINDS)
WINDOW, OVERLAP, MARGIN = 96, 48, 40
TRAIN_TEXTS, EPOCHS, BATCH, RATE = 1500, 14, 48, 0.012
WEIGHTS = "tagger_weights.npz"
#: Windows that run together, and characters of short stretches that are held at a time.
TOGETHER, HELD = 256, 1 << 17
_DIGIT = re.compile(r"[0-9]")
_TRIGGER = re.compile(r"[0-9@]+|\((?:at|dot)\)|\[(?:at|dot)\]")
_REST = re.compile(r"\S*")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = int(c) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def valid(kind: str, found: str) -> bool:
    digits = "".join(c for c in found if "0" <= c <= "9")
    if kind == "ip":
        return all(len(p) <= 3 and int(p or "0") <= 255 for p in (x.lstrip("0") for x in found.split(".")))
    if kind == "card":
        return 13 <= len(digits) <= 19 and luhn(digits)
    if kind == "phone":
        return 9 <= len(digits) <= 15
    return True


def _matches(kind: str, text: str) -> Iterator[tuple[int, int]]:
    """Leftmost non-overlapping matches of a kind, valid or not."""
    pattern = BASE[kind]
    if kind != "email":
        yield from (m.span() for m in pattern.finditer(text))
        return
    end, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := pattern.match(text, at)):
            end = m.end()
            yield start, end
        at = text.find("@", max(at + 1, end))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind's number, start, end) of valid matches, leftmost and non-overlapping within each kind."""
    out = []
    number = bool(_DIGIT.search(text))
    for k, kind in enumerate(BASE):
        if kind == "email" or number and (kind != "phone" or "+" in text):
            out += [(k, a, b) for a, b in _matches(kind, text) if valid(kind, text[a:b])]
    return out


def _plausible(kind: str, found: str) -> bool:
    """What an added span must look like."""
    digits = sum("0" <= c <= "9" for c in found)
    if kind == "email":
        return bool(re.fullmatch(r"[\w.%+-]+ ?(?:@|\(at\)|\[at\]) ?[\w-]+(?: ?(?:\.|\(dot\)|\[dot\]) ?[\w-]+)+", found))
    if kind == "ip":
        return bool(re.fullmatch(r"\d{1,3}(?: ?(?:\.|\[\.\]) ?\d{1,3}){3}", found)) and all(int(p) <= 255 for p in re.findall(r"[0-9]+", found))
    if kind == "card":
        return bool(re.fullmatch(r"[0-9][0-9 ./-]+[0-9]", found)) and valid("card", found)
    if kind == "phone":
        return bool(re.fullmatch(r"[(0-9][()0-9 ./-]+[0-9]", found)) and 9 <= digits <= 15 and any(c in "() ./-" for c in found)
    return bool(re.fullmatch(r"[A-Za-z0-9_+/=-]{20,}", found)) and digits >= 3 and any(c.isalpha() for c in found)


def labelled_texts(n: int, seed: int = 5) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """Synthetic (text, spans) pairs; span kinds are numbers of KINDS. The same for the same seed."""
    rng = np.random.default_rng(seed)
    pick = lambda s: s[int(rng.integers(len(s)))]
    letters, hexes, alnum = "abcdefghijklmnopqrstuvwxyz", "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    word = lambda lo=2, hi=10: "".join(pick(letters + "éüñ") if rng.random() < 0.05 else pick(letters) for _ in range(int(rng.integers(lo, hi))))
    digits = lambda k: "".join(pick("0123456789") for _ in range(k))

    def card(good: bool) -> str:
        body = pick("3456") + digits(14)
        last = next(d for d in "0123456789" if luhn(body + d))
        full = body + (last if good else pick([d for d in "0123456789" if d != last]))
        sep = pick(["", "", " ", "-"])
        return sep.join(full[i : i + 4] for i in range(0, 16, 4))

    def span() -> tuple[int, str]:
        k = int(rng.integers(len(KINDS)))
        if KINDS[k] == "email":
            host = f"{word(3)}{pick(['', digits(1)])}.{pick(['com', 'org', 'net', 'de', 'example.com'])}"
            user = f"{word(3)}{pick(['', '.' + word(3), digits(2)])}"
            return k, pick([f"{user}@{host}"] * 4 + [f"{user} (at) {host}", f"{user}[at]{host}"])
        if KINDS[k] == "ip":
            return k, ".".join(str(int(rng.integers(0, 256))) for _ in range(4))
        if KINDS[k] == "card":
            return k, card(True)
        if KINDS[k] == "phone":
            a, b, c = digits(3), digits(3), digits(4)
            return k, pick([f"+{pick('123456789')} ({a}) {b}-{c}", f"+{digits(2)} {a} {b} {c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"+{pick('123456789')}-{a}-{b}-{c}"])
        return k, pick(["".join(pick(hexes) for _ in range(int(rng.integers(32, 41)))), "".join(pick(alnum) for _ in range(int(rng.integers(24, 41))))])

    def other() -> str:
        return pick([str(int(rng.integers(1, 3000))), f"{digits(2)}.{digits(1)}", f"version {digits(1)}.{digits(1)}", f"{digits(4)}-{digits(2)}-{digits(2)}", f"{digits(3)},{digits(3)}", f"{digits(1)}.{digits(1)}.{digits(1)}", f"@{word(3)}", f"{digits(2)}%", f"{digits(2)}:{digits(2)}"])

    out = []
    for _ in range(n):
        text, spans = " ".join(word() for _ in range(int(rng.integers(0, 6)))), []
        for _ in range(int(rng.integers(1, 3))):
            text += pick([" ", " ", ": ", ", ", " | "]) if text else ""
            if rng.random() < 0.65:
                k, s = span()
                quote = '"' if KINDS[k] == "secret" and rng.random() < 0.6 else ""
                text += (pick(["token = ", "key=", ""]) if KINDS[k] == "secret" else "") + quote
                spans.append((k, len(text), len(text) + len(s)))
                text += s + quote
            else:
                text += other()
            text += pick([" ", ". ", ", ", "\n"]) + " ".join(word() for _ in range(int(rng.integers(0, 5))))
        out.append((text, spans))
    return out


def tags_of(n: int, spans: list[tuple[int, int, int]]) -> np.ndarray:
    y = np.zeros(n, np.int64)
    for k, a, b in spans:
        y[a] = 1 + 2 * k
        y[a + 1 : b] = 2 + 2 * k
    return y


def train(texts: list[tuple[str, list]] | None = None, epochs: int = EPOCHS, seed: int = 3) -> Tagger:
    """Fit the tagger on labelled spans (the generator's by default); the same data give the same model."""
    data = texts if texts is not None else labelled_texts(TRAIN_TEXTS)
    model, state, rng = Tagger(TAGS, seed=seed), {}, np.random.default_rng(seed)
    coded = [(encode(t)[:WINDOW], tags_of(len(t), s)[:WINDOW]) for t, s in data if t]
    coded.sort(key=lambda x: len(x[0]))
    batches = [coded[i : i + BATCH] for i in range(0, len(coded), BATCH)]
    for epoch in range(epochs):
        for b in rng.permutation(len(batches)):
            rows = batches[b]
            longest = max(len(r[0]) for r in rows)
            ids, y, mask = (np.zeros((len(rows), longest), t) for t in (np.int64, np.int64, np.float32))
            for i, (x, tags) in enumerate(rows):
                ids[i, : len(x)], y[i, : len(x)], mask[i, : len(x)] = x, tags, 1
            model.step(ids, mask, y, state, RATE / (1 + epoch / 4))
    return model


@functools.cache
def default_tagger() -> Tagger:
    """The tagger on the generator's spans: its stored weights, or trained here where they are missing."""
    stored = importlib.resources.files(__package__) / WEIGHTS
    return Tagger.load(io.BytesIO(stored.read_bytes()), TAGS) if stored.is_file() else train()


def stretches(text: str) -> list[tuple[int, int]]:
    """Merged surroundings of every digit, at sign and written at or dot; none cuts a token."""
    out: list[list[int]] = []
    for m in _TRIGGER.finditer(text):
        a, b, seen = max(0, m.start() - MARGIN), min(len(text), m.end() + MARGIN), out[-1][1] if out else 0
        while a > seen and not text[a - 1].isspace():
            a -= 1
        b = _REST.match(text, b).end() if b > seen else seen
        if out and a <= out[-1][1]:
            out[-1][1] = b
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _runs(tags: list[int], start: int) -> Iterator[tuple[int, int, int]]:
    """(kind's number, start, end) of the spans that tags spell out."""
    i = 0
    while i < len(tags):
        j = i + 1
        if tags[i]:
            k = (tags[i] - 1) // 2
            while j < len(tags) and tags[j] == 2 + 2 * k:
                j += 1
            yield k, start + i, start + j
        i = j


def _emissions(model: Tagger, parts: list[str]) -> Iterator[tuple[int, np.ndarray]]:
    """(number of the part, emissions of its next characters): windows run together, overlaps are averaged."""
    step, weight = WINDOW - OVERLAP, np.minimum(np.arange(1, WINDOW + 1), np.arange(WINDOW, 0, -1)).astype(np.float32)
    windows = ((p, a) for p, t in enumerate(parts) for a in range(0, max(1, len(t) - OVERLAP), step))
    over: list = [-1, None, None]  # part, and sums and weights of the characters that its next window shares
    while some := list(itertools.islice(windows, TOGETHER)):
        ids, mask = np.zeros((len(some), WINDOW), np.int64), np.zeros((len(some), WINDOW), np.float32)
        for j, (p, a) in enumerate(some):
            x = encode(parts[p][a : a + WINDOW])
            ids[j, : len(x)], mask[j, : len(x)] = x, 1
        e = model.emissions(ids, mask)
        for j, (p, a) in enumerate(some):
            n = int(mask[j].sum())
            w = np.minimum(weight[:n], np.arange(n, 0, -1, dtype=np.float32))[:, None]
            sums, total = w * e[j, :n], w.copy()
            if over[0] == p:
                sums[: len(over[1])] += over[1]
                total[: len(over[2])] += over[2]
            ready = n if a + n >= len(parts[p]) else step
            yield p, sums[:ready] / total[:ready]
            over = [p, sums[ready:], total[ready:]]


def tag_stretches(model: Tagger, parts: list[str]) -> list[list[tuple[int, int, int]]]:
    """Spans of each stretch, by one decoding of the whole stretch."""
    out: list[list] = [[] for _ in parts]
    for p, group in itertools.groupby(_emissions(model, parts), lambda x: x[0]):
        decoder, tags, begin, look = Decoder(model), [], 0, HELD
        for last, (_, e) in _marked_last(group):
            tags += decoder.push(e)
            if last:
                tags += decoder.end()
            # What precedes the last untagged character is final; a span is never cut.
            if last or len(tags) > look:
                cut = len(tags) if last else next((i for i in range(len(tags) - 1, 0, -1) if not tags[i]), 0)
                out[p] += _runs(tags[:cut], begin)
                tags, begin = tags[cut:], begin + cut
                look = max(HELD, 2 * len(tags))
    return out


def _marked_last(found):
    found = iter(found)
    held = next(found)
    for x in found:
        yield False, held
        held = x
    yield True, held


def _free(spans: list[tuple[int, int, int]], base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """The spans that overlap no base span."""
    ends: list[int] = []
    starts: list[int] = []
    for _, a, b in sorted(base, key=lambda x: x[1]):
        if ends and a <= ends[-1]:
            ends[-1] = max(ends[-1], b)
        else:
            starts.append(a)
            ends.append(b)
    out = []
    for k, a, b in spans:
        i = bisect.bisect_right(ends, a)
        if i == len(ends) or starts[i] >= b:
            out.append((k, a, b))
    return out


def find_all(model: Tagger, texts: list[str]) -> list[tuple[list, list]]:
    """(base spans, added spans) of each text; an added span overlaps no base span and looks like its kind."""
    base = [base_spans(t) for t in texts]
    added: list[list] = [[] for _ in texts]
    some: list[tuple[int, int, int]] = []

    def tag():
        for (i, a, b), spans in zip(some, tag_stretches(model, [texts[i][a:b] for i, a, b in some])):
            added[i] += [(k, s + a, e + a) for k, s, e in spans if _plausible(KINDS[k], texts[i][s + a : e + a])]
        some.clear()

    held = 0
    for i, t in enumerate(texts):
        for a, b in stretches(t):
            some.append((i, a, b))
            held += b - a
            if held >= HELD:
                tag()
                held = 0
    tag()
    return [(b, _free(x, b)) for b, x in zip(base, added)]


def find_pii(docs: DataFrame, model: Tagger | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, base array<struct>, spans array<struct<kind,start,end>>) for each row, code points, end exclusive.

    Null and empty texts have no spans; repeated rows repeat; an empty table gives no rows; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(default_tagger() if model is None else model)
    where = T.ArrayType(T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))
    schema = T.StructType([T.StructField("key", docs.schema[key].dataType), T.StructField("base", where), T.StructField("spans", where)])

    def rows(spans):
        return [{"kind": KINDS[k], "start": a, "end": b} for k, a, b in sorted(spans)]

    def work(blocks):
        tagger = shared.value
        for (keys,), texts in blocks:
            found = find_all(tagger, [t or "" for t in texts])
            yield [keys, [rows(b) for b, _ in found], [rows(b + a) for b, a in found]]

    return map_text(docs.select(docs[key].alias("key"), docs[text].alias("text")), ["key"], "text", schema, work).withColumnRenamed("key", key)


def op9_pii(spark, sf_dir: str) -> DataFrame:
    """The contract's columns; n_secret and n_added count spans that only the tagger finds, n_spans all: 0 where a text has none."""
    found = find_pii(table(spark, sf_dir, "documents"))
    joined = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda c, kind: F.size(F.filter(c, lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    counts = [*(count("base", kind) for kind in BASE), count("spans", "secret"), (F.size("spans") - F.size("base")).cast("long").alias("n_added"), F.size("spans").cast("long").alias("n_spans")]
    return found.select("doc_id", *counts, F.sha2(joined("base").cast("binary"), 256).alias("base_sha256"), joined("spans").alias("spans"))


if __name__ == "__main__":
    train().save(importlib.resources.files(__package__) / WEIGHTS)
