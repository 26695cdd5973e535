"""Character n-grams by number: counted in Arrow passes, where exploded rows and substrings would be one row and one scan each.

Grams are numbered by the ranks of their characters in an alphabet, so that counting is a bincount or a sort of longs.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

#: Characters that are numbered at once, numbers that are counted in one array, and grams a task holds before it hands them on.
CHUNK, CELLS, HELD = 1 << 22, 1 << 22, 1 << 18


def codes_of(texts: list[str]) -> np.ndarray:
    return np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)


def chunks(texts: list[str]) -> Iterator[list[str]]:
    part, size = [], 0
    for t in texts:
        part.append(t)
        size += len(t)
        if size >= CHUNK:
            yield part
            part, size = [], 0
    if part:
        yield part


def count_grams(texts: list[str], n: int) -> Counter:
    """Grams of n characters in each of texts; a shorter text is one gram."""
    found: Counter = Counter(t for t in texts if len(t) < n)
    for part in chunks([t for t in texts if len(t) >= n]):
        code = codes_of(part)
        alphabet = np.flatnonzero(np.bincount(code))
        if len(alphabet) ** n >= 1 << 63:
            for t in part:
                found.update(t[i : i + n] for i in range(len(t) - n + 1))
            continue
        rank = np.zeros(alphabet[-1] + 1, np.int64)
        rank[alphabet] = np.arange(len(alphabet))
        r = rank[code]
        number = r[: len(r) - n + 1].copy()
        for k in range(1, n):
            number *= len(alphabet)
            number += r[k : len(r) - n + 1 + k]
        whole = np.ones(len(number), bool)
        ends = np.cumsum([len(t) for t in part])[:-1]
        for k in range(1, n):
            whole[ends - k] = False
        number = number[whole]
        if len(alphabet) ** n <= CELLS:
            counts = np.bincount(number)
            ids = np.flatnonzero(counts)
            counts = counts[ids]
        else:
            ids, counts = np.unique(number, return_counts=True)
        letters = [chr(c) for c in alphabet]
        places = [ids // len(alphabet) ** (n - 1 - k) % len(alphabet) for k in range(n)]
        for gram, c in zip(zip(*(p.tolist() for p in places)), counts.tolist()):
            found["".join([letters[i] for i in gram])] += c
    return found


def gram_counts(df: DataFrame, n: int, group: str | None = None, text: str = "text") -> DataFrame:
    """([group,] gram, n): how often each gram stands in the texts of a group (or in all); null texts and groups have none.

    A task hands on sums, so what is shuffled grows with the grams that differ.
    """
    fields = [T.StructField("_g", df.schema[group].dataType)] if group else [T.StructField("_g", T.IntegerType())]
    schema = T.StructType([*fields, T.StructField("gram", T.StringType()), T.StructField("n", T.LongType())])

    def run(batches):
        kind, held = None, {}

        def flush():
            rows = [(g, w, c) for g, counts in held.items() for w, c in counts.items()]
            held.clear()
            for i in range(0, len(rows), 1 << 16):
                g, w, c = zip(*rows[i : i + (1 << 16)])
                yield pa.RecordBatch.from_arrays([pa.array(g, kind), pa.array(w, pa.string()), pa.array(c, pa.int64())], names=["_g", "gram", "n"])

        for batch in batches:
            kind = batch.schema.field(0).type
            parts: dict = {}
            for g, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if t is not None and g is not None:
                    parts.setdefault(g, []).append(t)
            for g, texts in parts.items():
                held.setdefault(g, Counter()).update(count_grams(texts, n))
            if sum(map(len, held.values())) > HELD:
                yield from flush()
        if held:
            yield from flush()

    found = df.select((F.col(group) if group else F.lit(0)).alias("_g"), F.col(text).cast("string").alias("_t")).mapInArrow(run, schema)
    sums = found.groupBy("_g", "gram").agg(F.sum("n").alias("n"))
    return sums.withColumnRenamed("_g", group) if group else sums.select("gram", "n")
