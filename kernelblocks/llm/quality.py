"""Quality by ordinal cumulative-link regression on graded ratings.

Ratings come from the labels: 0 for poor text, 1 for good text with toxic passages, 2 for good and
clean text. Hashed features of the whole text share one weight vector; ordered thresholds give the
expected grade and the tail probability P(grade >= 1) that selects documents.

Hashed features: words and their shapes by share of the text's words, and marks of the whole text
(share of distinct words, share of immediate repeats, share of distinct lines). Defined results: null
and empty texts score expected grade 0 and tail 0 and are rejected; without labels every other
document is kept.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from itertools import islice
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.labelled import SAMPLE_ROWS, labelled_rows
from kernelblocks.llm.ordinal import OrdinalModel, Rows, fit
from kernelblocks.llm.runtime import id_and_text

BITS = 16
WIDTH = 1 << BITS
GRADES = 3
KEEP_TAIL = 0.5
CACHE_WORDS = 400_000
MARK_STEPS = 8


def _bucket(kind: str, what: str) -> int:
    return zlib.crc32(f"{kind}\0{what}".encode("utf-8", "surrogatepass")) & (WIDTH - 1)


def shape(word: str) -> str:
    """Classes of the characters with runs shortened: upper, lower, digit, or the sign itself."""
    out: list[str] = []
    for c in word[:64]:
        k = "A" if c.isupper() else "a" if c.isalpha() else "0" if c.isdigit() else c
        if len(out) < 2 or out[-1] != k or out[-2] != k:
            out.append(k)
    return "".join(out)


class _Codes(dict):
    """word -> both buckets of the word in one number; emptied when it has grown to its bound."""

    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        code = self[word] = _bucket("w", word.strip(".,;:!?\"'()").lower()) << BITS | _bucket("s", shape(word))
        return code


_codes = _Codes()


def _mark(name: str, share: float, words: int) -> int:
    return _bucket(name, f"{round(share * MARK_STEPS)}:{min(words, 1 << 14).bit_length()}")


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(columns, values) of one text; none at all for an empty one. Columns can repeat; their values add."""
    words = (text or "").split()
    n = len(words)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0)
    counts = Counter(words)
    codes = np.fromiter(map(_codes.__getitem__, counts), np.int64, len(counts))
    share = np.fromiter(counts.values(), np.float64, len(counts)) / n
    lines = [x for x in text.split("\n") if x.strip()]
    again = sum(map(eq, words, islice(words, 1, None))) / n
    marks = [
        _mark("distinct", len(counts) / n, n),
        _mark("again", again, n),
        _mark("lines", len(set(lines)) / max(len(lines), 1), len(lines)),
    ]
    return (
        np.concatenate((codes >> BITS, codes & (WIDTH - 1), marks)),
        np.concatenate((share, 4 * share, np.ones(len(marks)))),
    )


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, l2: float = 3e-5) -> OrdinalModel | None:
    """None where no document has a label."""
    grade = F.when(F.col("quality") == 0, 0).when(F.col("quality") > 0, F.when(F.col("toxic") > 0, 1).otherwise(2))
    rows, y = labelled_rows(docs, labels, grade, lambda texts: [features(t) for t in texts], sample_rows)
    return fit(Rows.of(rows, WIDTH), y, GRADES, l2) if len(y) else None


def score(model: OrdinalModel | None, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(expected grade, P(grade >= 1)) of each text."""
    expected, tail = np.zeros(len(texts)), np.zeros(len(texts))
    for i, t in enumerate(texts):
        idx, val = features(t)
        if not len(idx):
            continue
        if model is None:
            expected[i], tail[i] = GRADES - 1, 1.0
            continue
        p = model.tails(np.array([model.weights[idx] @ val]))[0]
        expected[i], tail[i] = p.sum(), p[0]
    return expected, tail


def graded(docs: DataFrame, model: OrdinalModel | None, keep_tail: float = KEEP_TAIL) -> DataFrame:
    """(doc_id, expected_grade, tail_probability, keep) for every row of docs."""
    src = id_and_text(docs)
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            expected, tail = score(held.value, b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(expected), pa.array(tail), pa.array(tail >= keep_tail)],
                names=["doc_id", "expected_grade", "tail_probability", "keep"],
            )

    kind = src.schema["doc_id"].dataType
    out = T.StructType(
        [
            T.StructField("doc_id", kind),
            T.StructField("expected_grade", T.DoubleType()),
            T.StructField("tail_probability", T.DoubleType()),
            T.StructField("keep", T.BooleanType()),
        ]
    )
    return src.mapInArrow(run, out)


def select_good(docs: DataFrame, model: OrdinalModel | None, keep_tail: float = KEEP_TAIL) -> DataFrame:
    """The rows of docs, all columns as they are, whose tail probability reaches keep_tail."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(score(held.value, b.column(at).to_pylist())[1] >= keep_tail))

    return docs.mapInArrow(run, docs.schema)
