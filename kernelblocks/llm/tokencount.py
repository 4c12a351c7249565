"""Token counts by a linear longest-match automaton.

A vocabulary of word openings and of continuation pieces stands in two tries joined by failure links.
Every node knows how many pieces are popped when its link is followed, so a word's greedy
longest-match length is a sum of stored counts, in one pass, and no piece is built. A word that no
split covers counts as one unknown token. Words are runs of letters, digits and underscores, or single
other signs that aren't white space.

Defined results: null and empty texts have zero tokens; repeated rows give a row each.
"""

from __future__ import annotations

import json
import re
from collections import deque
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from kernelblocks.llm.runtime import id_and_text

WORD = re.compile(r"\w+|[^\w\s]")
UNKNOWN = -1
CACHE_WORDS = 400_000
_NODE_BITS = 21  # code points need no more


class PieceCounter:
    """Greedy longest-match lengths of words; openings start a word, continuations go on with it."""

    def __init__(self, openings: Iterable[str], continuations: Iterable[str]) -> None:
        self.next: dict[int, int] = {}
        self.fail: list[int] = []
        self.pops: list[int] = []
        ends: list[bool] = []
        above: list[tuple[int, int]] = []

        def node(parent: int, c: int) -> int:
            self.fail.append(-1)
            self.pops.append(0)
            ends.append(False)
            above.append((parent, c))
            return len(above) - 1

        self.start, self.rest = node(-1, 0), node(-1, 0)
        for root, pieces in ((self.start, openings), (self.rest, continuations)):
            for piece in pieces:
                at = root
                for c in map(ord, piece):
                    key = at << _NODE_BITS | c
                    to = self.next.get(key)
                    if to is None:
                        to = self.next[key] = node(at, c)
                    at = to
                if at != root:
                    ends[at] = True
        children: list[list[int]] = [[] for _ in above]
        for i, (parent, _) in enumerate(above):
            if parent >= 0:
                children[parent].append(i)
        queue = deque(children[self.start] + children[self.rest])
        while queue:
            v = queue.popleft()
            queue.extend(children[v])
            if ends[v]:
                self.fail[v], self.pops[v] = self.rest, 1
                continue
            parent, c = above[v]
            z, popped = self.fail[parent], self.pops[parent]
            while z >= 0:
                to = self.next.get(z << _NODE_BITS | c)
                if to is not None:
                    self.fail[v], self.pops[v] = to, popped
                    break
                popped += self.pops[z]
                z = self.fail[z]

    def count(self, word: str) -> int:
        """Pieces of the word, or UNKNOWN."""
        at, total = self.start, 0
        step, fail, pops = self.next, self.fail, self.pops
        for c in map(ord, word):
            to = step.get(at << _NODE_BITS | c)
            while to is None:
                total += pops[at]
                at = fail[at]
                if at < 0:
                    return UNKNOWN
                to = step.get(at << _NODE_BITS | c)
            at = to
        while at != self.rest:
            total += pops[at]
            at = fail[at]
            if at < 0:
                return UNKNOWN
        return total


class _Lengths(dict):
    """word -> its count; emptied when it has grown to its bound."""

    def __init__(self, counter: PieceCounter) -> None:
        super().__init__()
        self.counter = counter

    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        n = self[word] = self.counter.count(word)
        return n


def byte_signs() -> dict[str, int]:
    """The printable stand-in of each byte in byte-level vocabularies: printable bytes are themselves, others follow from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(others)}


def vocabulary_bytes(path: str) -> list[bytes]:
    """The pieces of a byte-level vocabulary file, by id."""
    with open(path, encoding="utf-8") as f:
        vocab = json.load(f)["model"]["vocab"]
    sign = byte_signs()
    return [bytes(sign[c] for c in piece) for piece, _ in sorted(vocab.items(), key=lambda x: x[1]) if all(c in sign for c in piece)]


def word_pieces(path: str) -> tuple[list[str], list[str]]:
    """(openings, continuations) of a byte-level vocabulary: pieces after a space open words, the others go on."""
    openings, continuations = [], []
    for raw in vocabulary_bytes(path):
        try:
            piece = raw.decode("utf-8")
        except UnicodeDecodeError:
            continue
        if piece.startswith(" ") and len(piece) > 1 and not piece[1:].isspace():
            openings.append(piece[1:])
        elif piece.strip() == piece and piece:
            continuations.append(piece)
    return openings, continuations


def token_counts(docs: DataFrame, counter: PieceCounter) -> DataFrame:
    """(doc_id, n_tokens, n_words, n_unknown) for every row of docs."""
    src = id_and_text(docs)
    held = docs.sparkSession.sparkContext.broadcast(counter)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lengths = _Lengths(held.value)
        for b in batches:
            tokens, words, unknown = [], [], []
            for text in b.column(1).to_pylist():
                got = list(map(lengths.__getitem__, WORD.findall(text)))
                lost = got.count(UNKNOWN)
                tokens.append(sum(got) + 2 * lost)  # an unknown word counts as one
                words.append(len(got))
                unknown.append(lost)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), *(pa.array(x, pa.int64()) for x in (tokens, words, unknown))],
                names=["doc_id", "n_tokens", "n_words", "n_unknown"],
            )

    kind = src.schema["doc_id"].dataType
    longs = [T.StructField(c, T.LongType()) for c in ("n_tokens", "n_words", "n_unknown")]
    return src.mapInArrow(run, T.StructType([T.StructField("doc_id", kind), *longs]))
