"""Toxicity severity by cumulative-link ordinal regression on sparse text features.

The labels say toxic or not. Grades for training are 0 for clean text and, among toxic text, 1 or 2
by the number of distinct strongly associated words in it (2 above the median). The features are
presences of the words of the whole text and of the openings of 4, 5 and 6 letters of its longer words,
which stand for the forms of one stem; those are kept whose shares in the toxic and the clean texts of
the sample differ by a likelihood ratio that stands out. One weight vector is shared by both thresholds.

Defined results: null and empty texts, and all texts where no label exists, have severity 0.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.labelled import SAMPLE_ROWS, labelled_rows
from kernelblocks.llm.ordinal import OrdinalModel, Rows, fit
from kernelblocks.llm.runtime import id_and_text

BITS = 22
GRADES = 3
KEPT_FEATURES = 512
LEAST_Z = 5.0
STRONG_Z = 7.0
OPENINGS = (4, 5, 6)
CACHE_WORDS = 400_000
WORD = re.compile(r"\w+")


def codes_of(word: str) -> list[int]:
    """Hashed features of one lower-case word: itself and its openings."""
    mask = (1 << BITS) - 1
    forms = [word, *(f"{word[:k]}*" for k in OPENINGS if len(word) > k)]
    return [zlib.crc32(f.encode("utf-8", "surrogatepass")) & mask for f in forms]


def word_codes(text: str | None) -> np.ndarray:
    """Hashed features of a text, each once."""
    return np.unique(np.array([c for w in set(WORD.findall((text or "").lower())) for c in codes_of(w)], np.int64))


@dataclass
class ToxicityModel:
    columns: dict[int, int]
    ordinal: OrdinalModel

    def scores(self, texts: list[str | None]) -> np.ndarray:
        w, columns, known = self.ordinal.weights, self.columns, self._words
        out = np.zeros(len(texts))
        for i, t in enumerate(texts):
            hits = set()
            for x in set(WORD.findall((t or "").lower())):
                found = known.get(x)
                if found is None:
                    if len(known) >= CACHE_WORDS:
                        known.clear()
                    found = known[x] = tuple(columns[h] for h in codes_of(x) if h in columns)
                if found:
                    hits.update(found)
            out[i] = sum(w[c] for c in sorted(hits))
        return out

    def __post_init__(self) -> None:
        self._words: dict[str, tuple[int, ...]] = {}


def standing_out(rows: list[np.ndarray], toxic: np.ndarray, width: int) -> np.ndarray:
    """Signed root of the likelihood ratio of each feature: how far its shares in toxic and clean texts differ.

    Unlike a ratio of smoothed odds it doesn't weaken features that one side lacks.
    """
    hit, miss = np.zeros(width), np.zeros(width)
    for r, y in zip(rows, toxic, strict=True):
        (hit if y else miss)[r] += 1
    n1, n0 = int(toxic.sum()), int((~toxic).sum())
    out = np.zeros(width)
    seen = np.flatnonzero(hit + miss)
    h, m = hit[seen], miss[seen]
    total = np.zeros(len(seen))
    for got, own in ((h, n1), (n1 - h, n1), (m, n0), (n0 - m, n0)):
        pooled = (h + m if got is h or got is m else n1 + n0 - h - m) * own / max(n1 + n0, 1)
        total += np.where(got > 0, got * np.log(np.maximum(got, 1e-300) / np.maximum(pooled, 1e-300)), 0.0)
    side = np.sign(h * n0 - m * n1)
    out[seen] = side * np.sqrt(np.maximum(2 * total, 0.0))
    return out


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, l2: float = 1e-4) -> ToxicityModel | None:
    """None where no document has a label."""
    grade = F.when(F.col("toxic") > 0, 1).when(F.col("toxic") == 0, 0)
    rows, y = labelled_rows(
        docs, labels, grade, lambda texts: [(c := word_codes(t), np.ones(len(c))) for t in texts], sample_rows
    )
    if not len(y):
        return None
    words = [i for i, _ in rows]
    toxic = y > 0
    z = standing_out(words, toxic, 1 << BITS)
    kept = np.argsort(-np.abs(z), kind="stable")[:KEPT_FEATURES]
    kept = kept[np.abs(z[kept]) >= LEAST_Z]
    spot = np.full(1 << BITS, -1)
    spot[kept] = np.arange(len(kept))
    sparse = [(c := spot[w][spot[w] >= 0], np.ones(len(c))) for w in words]
    strong = np.array([int((z[w] >= STRONG_Z).sum()) for w in words])
    grades = y.copy()
    if toxic.any():
        grades[toxic & (strong > np.median(strong[toxic]))] = 2
    model = fit(Rows.of(sparse, max(len(kept), 1)), grades, GRADES, l2)
    return ToxicityModel({int(h): i for i, h in enumerate(kept)}, model)


def severity(docs: DataFrame, model: ToxicityModel | None) -> DataFrame:
    """(doc_id, expected_severity, grade, toxic) for every row of docs; toxic: grade 1 or more."""
    src = id_and_text(docs)
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        for b in batches:
            texts = b.column(1).to_pylist()
            if m is None:
                expected, grade = np.zeros(len(texts)), np.zeros(len(texts), np.int64)
            else:
                empty = np.array([not t for t in texts], dtype=bool)
                s = m.scores(texts)
                expected = np.where(empty, 0.0, m.ordinal.expected(s))
                grade = np.where(empty, 0, m.ordinal.grade(s))
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(expected), pa.array(grade.astype(np.int32)), pa.array(grade >= 1)],
                names=["doc_id", "expected_severity", "grade", "toxic"],
            )

    kind = src.schema["doc_id"].dataType
    out = T.StructType(
        [
            T.StructField("doc_id", kind),
            T.StructField("expected_severity", T.DoubleType()),
            T.StructField("grade", T.IntegerType()),
            T.StructField("toxic", T.BooleanType()),
        ]
    )
    return src.mapInArrow(run, out)
