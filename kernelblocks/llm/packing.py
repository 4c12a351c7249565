"""Order-preserving packing by dynamic programming.

The documents of a partition, in the order of their ids, form one row of token ids. Cuts are chosen
among the ends of documents (no penalty), the ends of sentences (a small one) and, inside long
stretches without either, places on a grid (a large one), so that padding plus penalties is least. A
window of n ids costs width - n in padding, except that n may be a power of two, which is stored
unpadded. The least sum over all earlier cuts in reach is kept in a monotone queue, so that a cut
costs a constant number of steps.

The row is cut block by block: the windows that begin in the last stretch of a block are planned
again with the next one, so memory is bounded by the longest document. Sequence ids are the
partition's number and a count within it, so a task that runs again gives the same ones.

Defined results: a null or empty text is the closing id alone; repeated rows are packed each, in the
order of the hash of their texts where ids tie; a text of any length is cut into as many pieces as it
takes, runs of white space without bound among them; of plans that cost the same the one found first
stays; an empty table gives no piece; other columns don't matter; any width of 1 or more will do.
"""

from __future__ import annotations

import re
import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.runtime import id_and_text
from kernelblocks.llm.tokencount import vocabulary_bytes

WIDTH = 1024
CLOSING_ID = 0
SENTENCE_PENALTY = 4.0
FORCED_PENALTY = 48.0
GRID = 64
BLOCK_TOKENS = 1 << 18
#: Planned again with the next block.
LOOSE_TOKENS = 1 << 13
#: The pattern of the byte-level vocabulary's words (fixed value).
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""

#: tiktoken gives up on much longer runs of white space; texts with such a run take the exact way.
LONG_BLANK = 100_000

_encoders: dict[str, tuple] = {}


def _has_long_blank(text: str) -> bool:
    return len(text) >= LONG_BLANK and any(m.end() - m.start() >= LONG_BLANK for m in re.finditer(r"\s+", text))


def encoder(path: str) -> tuple:
    """(text -> ids, whether each id ends a sentence, whether each id begins with white space), once for each worker.

    The ids are those of the tokenizers library for the file; a text that spells one of the file's
    special tokens or holds a very long run of white space goes through that library itself, all
    others through the same merges in tiktoken, which is several times as fast.
    """
    if path not in _encoders:
        import tiktoken
        from tokenizers import Tokenizer

        pieces = vocabulary_bytes(path)
        exact = Tokenizer.from_file(path)
        special = [t.content for t in exact.get_added_tokens_decoder().values()]
        ranks = {p: i for i, p in enumerate(pieces) if p.decode("utf-8", "replace") not in special}
        quick = tiktoken.Encoding("packing", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})

        def ids(text: str) -> np.ndarray:
            if any(s in text for s in special) or _has_long_blank(text):
                return np.array(exact.encode(text, add_special_tokens=False).ids, np.uint32)
            return np.array(quick.encode_ordinary(text), np.uint32)

        size = max(exact.get_vocab_size(), len(pieces), CLOSING_ID + 1)
        pieces = pieces + [b""] * (size - len(pieces))  # special tokens end and begin nothing
        ends = np.array([p.rstrip(b"\"')]").endswith((b".", b"!", b"?")) or b"\n" in p for p in pieces])
        blank = np.array([p[:1] in (b" ", b"\n", b"\t", b"\r") for p in pieces])
        _encoders[path] = ids, ends, blank
    return _encoders[path]


def padding(length: int, width: int = WIDTH) -> int:
    return 0 if length & (length - 1) == 0 else width - length


def cut_places(
    ends: np.ndarray, blank: np.ndarray, ids: np.ndarray, doc_ends: np.ndarray, width: int = WIDTH
) -> tuple[np.ndarray, np.ndarray]:
    """(places, penalties) where the row of ids may be cut; the first place is 0, the last its end.

    No two neighbours lie more than width apart, so that there always is a plan.
    """
    grid = max(1, min(GRID, width // 4))
    n = len(ids)
    inner = np.flatnonzero(ends[ids[:-1]] & blank[ids[1:]]) + 1 if n > 1 else np.zeros(0, np.int64)
    hard = np.unique(np.concatenate(([0], doc_ends, [n])))
    soft = np.setdiff1d(inner, hard, assume_unique=True)
    known = np.union1d(hard, soft)
    gaps = np.diff(known)
    wide = np.flatnonzero(gaps > min(4 * grid, width))
    extra = [np.arange(known[k] + grid, known[k + 1], grid) for k in wide]
    forced = np.concatenate(extra) if extra else np.zeros(0, np.int64)
    places = np.concatenate((hard, soft, forced))
    costs = np.concatenate((np.zeros(len(hard)), np.full(len(soft), SENTENCE_PENALTY), np.full(len(forced), FORCED_PENALTY)))
    order = np.argsort(places, kind="stable")
    return places[order], costs[order]


def plan(places: np.ndarray, costs: np.ndarray, width: int = WIDTH) -> list[int]:
    """Indexes of the places of the best cuts, the first and last included."""
    m = len(places)
    powers = []
    p = 1 << (width - 1).bit_length() >> 1
    while p >= width // 8 and p:
        want = places - p
        at = np.minimum(np.searchsorted(places, want), m - 1)
        powers.append(np.where(places[at] == want, at, -1).tolist())
        p >>= 1
    spot, cost = places.tolist(), costs.tolist()
    best, back = [0.0] * m, [0] * m
    queue: deque[tuple[float, int]] = deque([(0.0, 0)])
    for j in range(1, m):
        here = spot[j]
        low = here - width
        while spot[queue[0][1]] < low:
            queue.popleft()
        value, i = queue[0]
        # the queue holds best + place, so the padding of a window is a constant less its end
        value += width - here
        for near in powers:
            k = near[j]
            if k >= 0 and best[k] < value:
                value, i = best[k], k
        value += cost[j]
        best[j], back[j] = value, i
        key = value + here
        while queue and queue[-1][0] >= key:
            queue.pop()
        queue.append((key, j))
    out = [m - 1]
    while out[-1]:
        out.append(back[out[-1]])
    return out[::-1]


class _Row:
    """The ids that wait for their cuts, and the documents that they belong to."""

    def __init__(self, tables: tuple[np.ndarray, np.ndarray], shard: int, width: int) -> None:
        self.ends, self.blank = tables
        self.shard, self.width, self.made = shard, width, 0
        self.parts: list[np.ndarray] = []
        self.size = 0
        self.begins = 0  # where the waiting ids begin in the partition's row
        self.docs: deque[tuple[object, int, int]] = deque()  # id, begin, length
        self.out: list[tuple] = []

    def add(self, doc_id: object, ids: np.ndarray) -> None:
        self.docs.append((doc_id, self.begins + self.size, len(ids)))
        self.parts.append(ids)
        self.size += len(ids)

    def settle(self, last: bool) -> None:
        if not self.size:
            return
        ids = np.concatenate(self.parts).astype("<u4")
        doc_ends = np.array([b + n for _, b, n in self.docs]) - self.begins
        places, costs = cut_places(self.ends, self.blank, ids, doc_ends, self.width)
        cuts = places[plan(places, costs, self.width)].tolist()
        if not last:
            cuts = [c for c in cuts if c <= max(len(ids) - LOOSE_TOKENS, cuts[1])]
        raw = ids.tobytes()
        for a, b in zip(cuts, cuts[1:], strict=False):
            self._sequence(raw, a, b)
        done = cuts[-1]
        self.parts, self.size = [ids[done:]], len(ids) - done
        self.begins += done
        while self.docs and self.docs[0][1] + self.docs[0][2] <= self.begins:
            self.docs.popleft()

    def _sequence(self, raw: bytes, a: int, b: int) -> None:
        low, high = self.begins + a, self.begins + b
        name = self.shard << 33 | self.made
        self.made += 1
        while self.docs and self.docs[0][1] + self.docs[0][2] <= low:
            self.docs.popleft()
        for doc_id, begin, length in self.docs:
            if begin >= high:
                break
            s, e = max(begin, low), min(begin + length, high)
            part = raw[4 * (s - self.begins) : 4 * (e - self.begins)]
            self.out.append((doc_id, s - begin, e - s, zlib.crc32(part), length, name, s - low))


def pack(docs: DataFrame, path: str, width: int = WIDTH) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset): a row for each piece."""
    src = id_and_text(docs).sortWithinPartitions("doc_id", F.xxhash64("text"))
    names = ["start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    kind = src.schema["doc_id"].dataType
    schema = T.StructType([T.StructField("doc_id", kind), *(T.StructField(c, T.LongType()) for c in names)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, *tables = encoder(path)
        context = TaskContext.get()
        row = _Row(tuple(tables), context.partitionId() if context else 0, width)
        closing = np.array([CLOSING_ID], np.uint32)
        kinds = None

        def drain() -> Iterator[pa.RecordBatch]:
            if row.out:
                cols = list(zip(*row.out, strict=True))
                row.out = []
                yield pa.RecordBatch.from_arrays(
                    [pa.array(cols[0], kinds), *(pa.array(c, pa.int64()) for c in cols[1:])], names=["doc_id", *names]
                )

        for b in batches:
            kinds = b.schema.field(0).type
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                row.add(doc_id, np.concatenate((encode(text), closing)))
                if row.size >= BLOCK_TOKENS:
                    row.settle(False)
                    yield from drain()
        row.settle(True)
        yield from drain()

    return src.mapInArrow(run, schema)
