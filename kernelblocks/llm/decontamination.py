"""Benchmark decontamination by template windows and consistent slots.

A text becomes a row of words in which numbers, names and units stand as typed placeholders, so that
an exercise with other figures or other people keeps its template. Number words are numbers, and a unit
glued to its number is a word of its own. A capitalised word that isn't a common one is a name; where it
begins a sentence it may be an ordinary word too, and both readings are looked up. Windows of five
template words are joined by hash. The hits of one item on one alignment count as contamination when they
cover half of the item's windows or more and the placeholders agree: one value of the item always stands
for one value of the document, and the other way round. A window whose slots disagree with the others'
doesn't count, and where several slots and more than a fifth of them disagree the item is no match at all.

A window is a template only if three of its words at least are no placeholders; windows poorer than
that are looked up with all their words as they are, so that exact copies of them match. Half of the
windows means half of the templates in either reading or half of all windows. Items with fewer words
than a window are one window as they are.

Half of an item's windows can't be hit without one of the rarer half of them: only those, its keys, look
for documents, so windows that very many items share cost nothing where the items have others, and no
match is lost. The pairs found are then compared whole. A benchmark of up to BLOCK_WINDOWS words is an index
that every task holds. A larger one stays distributed: documents give the windows that pass a Bloom
filter of bounded size, these meet the keys in a salted shuffle join, and each pair's texts meet in one task.

Defined results: null and empty texts match nothing; repeated documents and items give a row each; of
alignments that tie the first counts; texts of any length are read whole; an empty benchmark or table gives
no row; other columns don't matter.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.runtime import cut, id_and_text

WINDOW = 5
LITERALS = 3
COVERAGE = 0.5
#: Slots that may disagree with the others where one item is compared: one, or this share of them.
SLOT_DISAGREEMENT = 0.2
#: Words of a benchmark that every task holds; a larger one is joined by a shuffle.
BLOCK_WINDOWS = 400_000
#: Bits of the filter of a larger benchmark's keys, and copies of each key.
FILTER_BITS, SALTS = 1 << 27, 8
CACHE_WORDS = 400_000
#: Texts of so many signs together are looked up at once, with a word between them that ends a sentence.
CHUNK_SIGNS, BETWEEN = 1 << 17, "\0."
#: Units of measure (fixed values).
UNITS = frozenset(
    "mm cm m km in ft yd mi mg g kg lb oz ml l s sec second seconds min minute minutes h hr hour hours day days "
    "week weeks month months year years meter meters metre metres mile miles foot feet inch inches gram grams "
    "kilogram kilograms pound pounds ounce ounces liter liters litre litres dollar dollars euro euros cent cents "
    "percent % $ € £ °c °f kmh km/h mph hz khz mhz ghz w kw v a j kj n pa".split()
)
NUMBER = re.compile(r"[+-]?[$€£]?\d[\d.,:/]*%?")
GLUED = re.compile(r"([+-]?[$€£]?\d[\d.,:/]*)([^\d\W][^\d]*|[€£$°][^\d]*)")
NUMBER_WORDS = frozenset(
    "zero one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen "
    "eighteen nineteen twenty thirty forty fifty sixty seventy eighty ninety hundred thousand million billion".split()
)
#: Words that are no names though they begin many sentences (fixed values).
COMMON = frozenset(
    "a an the this that these those there here it its he she they we you i his her their our your my him them us "
    "if in on at by for from to of with without and or but so as than then when while where who whom whose which what "
    "why how is are was were be been do does did has have had can could will would shall should may might must not no "
    "yes all each every some any both either neither many much more most few several other another after before during "
    "since until because although though however therefore thus also only just now once let suppose given find "
    "calculate compute determine show prove consider assume write explain describe".split()
)
EDGES = ".,;:!?\"'()[]{}«»“”‘’…|*#&~`_-"

# The packed record of a word: 56 bits of hash, then these flags.
NUM, CAP, UNIT, STOP, GLUE = 1, 2, 4, 8, 16
FLAG_BITS = 5
_HASH_STEP = np.uint64(0x9E3779B97F4A7C15)
_PLACE = {NUM: np.uint64(0x1D8E4E27C47D124F), CAP: np.uint64(0xA3EC647659359ACD), UNIT: np.uint64(0x7A1C8E5B7F2D93B1)}


def _glued(bare: str) -> int:
    """The length of the number before a unit, or 0."""
    m = GLUED.fullmatch(bare)
    return len(m[1]) if m and m[2].lower() in UNITS else 0


def _parted(word: str) -> tuple[str, ...]:
    bare = word.strip(EDGES)
    size = _glued(bare)
    at = word.index(bare) + size
    return (word[:at], word[at:]) if size else (word,)


class _Words(dict):
    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        bare = word.strip(EDGES)
        low = bare.lower()
        flags = STOP * word.rstrip("\"')]»”’").endswith((".", "!", "?", ":", "…"))
        if not bare:
            code = 0  # a sign alone is no word
        else:
            raw = low.encode("utf-8", "surrogatepass")
            code = (zlib.crc32(raw) << 24 | zlib.adler32(raw) & 0xFFFFFF) << FLAG_BITS
            if NUMBER.fullmatch(bare) or low in NUMBER_WORDS or ("-" in low and NUMBER_WORDS.issuperset(low.split("-"))):
                flags |= NUM
            elif low in UNITS:
                flags |= UNIT
            elif _glued(bare):
                flags |= GLUE
            if len(bare) > 1 and bare[0].isupper() and bare[1:].islower() and low not in COMMON:
                flags |= CAP
        out = self[word] = code | flags
        return out


_words = _Words()


def readings(text: str | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(code of each word, kind of its placeholder or 0, whether it may be an ordinary word as well)."""
    return _read(_coded((text or "").split())[0])[:3]


def _coded(tokens: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(records of the words, which of tokens each comes from); a unit glued to its number becomes a word."""
    codes = np.fromiter(map(_words.__getitem__, tokens), np.int64, len(tokens))
    source = np.arange(len(tokens))
    glued = np.flatnonzero(codes & GLUE)
    if len(glued):
        parts = [tuple(map(_words.__getitem__, _parted(tokens[k]))) for k in glued.tolist()]
        codes[glued] = [a for a, _ in parts]
        codes = np.insert(codes, glued + 1, [b for _, b in parts])
        source = np.insert(source, glued + 1, glued)
    return codes, source


def _read(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """readings of packed records, and which of them are words."""
    word = codes.view(np.uint64) >> np.uint64(FLAG_BITS)
    flags = codes & ((1 << FLAG_BITS) - 1)
    real = word != 0
    stops = np.concatenate(([True], (flags & STOP) > 0))[:-1]
    if not real.all():
        # a sign alone passes on whether a sentence ends before the next word
        ends = np.where(real | ((flags & STOP) > 0), np.arange(len(flags)), -1)
        last = np.maximum.accumulate(ends) if len(ends) else ends
        before = np.concatenate(([-1], last[:-1])) if len(last) else last
        stops = np.where(before < 0, True, (flags[np.maximum(before, 0)] & STOP) > 0)
    word, flags, stops = word[real], flags[real], stops[real]
    number = (flags & NUM) > 0
    unit = ((flags & UNIT) > 0) & np.concatenate(([False], number[:-1])) if len(word) else number
    name = ((flags & CAP) > 0) & ~unit & ~number
    kind = np.where(number, NUM, np.where(unit, UNIT, np.where(name, CAP, 0)))
    return word, kind, name & stops, real


def _template(word: np.ndarray, kind: np.ndarray) -> np.ndarray:
    out = word.copy()
    for k, v in _PLACE.items():
        out[kind == k] = v
    return out


def _hashed(row: np.ndarray, size: int) -> np.ndarray:
    return _hashed_at(row, None, size)


def _hashed_at(row: np.ndarray, at: np.ndarray | None, size: int) -> np.ndarray:
    """Hashes of the windows that begin at the given places, or of all."""
    count = len(row) - size + 1
    h = np.full(count if at is None else len(at), np.uint64(size))
    for k in range(size):
        h ^= row[k : k + count] if at is None else row[at + k]
        h *= _HASH_STEP
        h ^= h >> np.uint64(29)
    return h


def _within(marks: np.ndarray, size: int) -> np.ndarray:
    """How many marks each window holds."""
    count, ones = len(marks) - size + 1, marks.view(np.uint8)
    sums = ones[:count].copy()
    for k in range(1, size):
        sums += ones[k : k + count]
    return sums


def windows(
    word: np.ndarray, kind: np.ndarray, either: np.ndarray, size: int
) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hashes to look up, place of each, templates with all names, templates with no name at a sentence's start).

    Names at starts are read as names, as words, and in turns where a window holds several.
    """
    need = min(LITERALS, size)
    rich = _within(kind == 0, size) >= need
    hashes, places = [_hashed(_template(word, kind), size)[rich]], [np.flatnonzero(rich)]
    plain = rich
    if not rich.all():
        poor = np.flatnonzero(~rich)
        hashes.append(~_hashed_at(word, poor, size))
        places.append(poor)
    if either.any():
        held = _within(either, size)
        turn = np.cumsum(either) % 2 == 0
        for k, (words, least) in enumerate(((either, 1), (either & turn, 2), (either & ~turn, 2))):
            other = np.where(words, 0, kind)
            good = _within(other == 0, size) >= need
            if k == 0:
                plain = good
            at = np.flatnonzero(good & (held >= least))
            if len(at):
                hashes.append(_hashed_at(_template(word, other), at, size))
                places.append(at)
    return np.concatenate(hashes), np.concatenate(places), rich, plain


class _Item:
    """An item's words and windows, and which of its windows are templates in either reading."""

    def __init__(self, item_id: int, text: str | None) -> None:
        self.item_id = item_id
        self.word, self.kind, either = readings(text)
        self.size = min(WINDOW, len(self.word))
        self.hash, self.place = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.sets: list[np.ndarray] = []
        if self.size:
            self.hash, self.place, rich, plain = windows(self.word, self.kind, either, self.size)
            self.sets = [m for m in (rich, plain, np.ones(len(rich), bool)) if m.any()]

    def keys(self, owners: np.ndarray, coverage: float) -> np.ndarray:
        """The hashes of the places one of which every match hits; owners says how many items hold each window."""
        count = np.full(len(self.sets[-1]), np.iinfo(np.int64).max)
        np.minimum.at(count, self.place, owners)
        chosen = np.zeros(len(count), bool)
        for m in self.sets:
            at = np.flatnonzero(m)
            # the most places of this set that a text can miss, and one more, the rarest first
            miss = len(at) - max(1, int(np.ceil(coverage * len(at) - 1e-9)))
            chosen[at[np.argsort(count[at], kind="stable")][: miss + 1]] = True
        return np.unique(self.hash[chosen[self.place]])

    def covered(self, places: np.ndarray) -> tuple[int, float]:
        """(windows hit, their share) for the set of windows with the largest share."""
        counts = [(int(m[places].sum()), int(m.sum())) for m in self.sets]
        n, total = max(counts, key=lambda c: (c[0] / c[1], c[0]))
        return n, n / total

    def match(self, text: _Text, coverage: float) -> tuple[int, float, int, bool] | None:
        """(windows hit, coverage, slots, verbatim) where the text holds the item, else None."""
        hashes, at = text.windows(self.size)
        lo, hi = np.searchsorted(hashes, self.hash), np.searchsorted(hashes, self.hash, side="right")
        hit = hi - lo
        if not hit.any() or self.covered(np.unique(self.place[hit > 0]))[1] < coverage:
            return None
        q = np.repeat(self.place, hit)
        p = at[np.repeat(lo - (np.cumsum(hit) - hit), hit) + np.arange(len(q))]
        pairs = np.unique(np.stack((p, q), axis=1), axis=0)
        best = _aligned(pairs, text.word, self)
        return best if best and best[1] >= coverage else None


class _Text:
    """A text's words, and its windows of each size sorted by hash."""

    def __init__(self, text: str | None) -> None:
        self.word, self.kind, self.either = readings(text)
        self.made: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def raw(self, size: int) -> np.ndarray:
        if not size or size > len(self.word):
            return np.zeros(0, np.uint64)
        return windows(self.word, self.kind, self.either, size)[0]

    def windows(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        if size not in self.made:
            if size > len(self.word):
                self.made[size] = np.zeros(0, np.uint64), np.zeros(0, np.int64)
            else:
                h, at, _, _ = windows(self.word, self.kind, self.either, size)
                order = np.argsort(h, kind="stable")
                self.made[size] = h[order], at[order]
        return self.made[size]


def _aligned(pairs: np.ndarray, word: np.ndarray, item: _Item) -> tuple[int, float, int, bool] | None:
    """The best run of hits (place in the text, place in the item) whose alignments lie within two words, with slots that agree."""
    shift = pairs[:, 0] - pairs[:, 1]
    pairs = pairs[np.lexsort((pairs[:, 0], shift))]
    shift = np.sort(shift)
    best = None
    for run in np.split(pairs, np.flatnonzero(np.diff(shift) > 2) + 1):
        # each slot of the item with what stands in its place; the most frequent partner of a value counts
        at = (run[:, 1:] + np.arange(item.size)).ravel()
        there = (run[:, :1] + np.arange(item.size)).ravel()
        slot = item.kind[at] > 0
        rows = list(zip(item.kind[at[slot]].tolist(), item.word[at[slot]].tolist(), word[there[slot]].tolist(), at[slot].tolist(), strict=True))
        votes = Counter((k, a, b) for k, a, b, _ in dict.fromkeys(rows))
        one: dict[tuple[int, int], int] = {}
        other: dict[tuple[int, int], int] = {}
        for (k, a, b), _ in sorted(votes.items(), key=lambda v: (-v[1], v[0])):
            if (k, a) not in one and (k, b) not in other:
                one[k, a], other[k, b] = b, a
        wrong = {i for k, a, b, i in rows if one.get((k, a)) != b}
        right = {i for k, a, b, i in rows if one.get((k, a)) == b}
        if len(wrong) > 1 and len(wrong) > SLOT_DISAGREEMENT * len(wrong | right):
            continue
        agree = np.ones(len(at), bool)
        agree[slot] = [one.get((k, a)) == b for k, a, b, _ in rows]
        good = agree.reshape(-1, item.size).all(axis=1)
        if not good.any():
            continue
        kept = np.unique(run[good, 1])
        held = np.unique((kept[:, None] + np.arange(item.size)).ravel())
        slots = int((item.kind[held] > 0).sum())
        same = bool((item.word[at] == word[there])[np.repeat(good, item.size) & slot].all())
        n, share = item.covered(kept)
        if best is None or (share, n) > (best[1], best[0]):
            best = (n, share, slots, same)
    return best


def _owners(hashes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(hash, number of rows that hold it), sorted."""
    return np.unique(np.concatenate([np.zeros(0, np.uint64), *map(np.unique, hashes)]), return_counts=True)


class Index:
    """The keys of a bounded benchmark, sorted by hash, and its items."""

    def __init__(self, items: list[tuple[int, str | None]], coverage: float = COVERAGE) -> None:
        self.items = [i for i in (_Item(*row) for row in items) if i.size]
        self.sizes = {i.size for i in self.items}
        known, count = _owners([i.hash for i in self.items])
        keys = [i.keys(count[np.searchsorted(known, i.hash)], coverage) for i in self.items]
        hashes = np.concatenate([np.zeros(0, np.uint64), *keys])
        order = np.argsort(hashes, kind="stable")
        self.hash = hashes[order]
        self.owner = np.repeat(np.arange(len(keys)), [len(k) for k in keys])[order]
        #: whether a key ends in these bits
        self.mask = np.uint64((1 << min(24, 6 + max(8, len(self.hash).bit_length()))) - 1)
        self.ends = np.zeros(int(self.mask) + 1, bool)
        self.ends[self.hash & self.mask] = True

    def __len__(self) -> int:
        return len(self.hash)

    def all_matches(self, texts: list[str | None], coverage: float) -> list[list[tuple[int, int, float, int, bool]]]:
        """matches of each text. Keys are looked up in CHUNK_SIGNS of texts at once, whose windows are those of each alone."""
        found: list[list] = [[] for _ in texts]
        first, signs = 0, 0
        for k, text in enumerate(texts):
            signs += len(text or "") + 1
            if signs >= CHUNK_SIGNS or k == len(texts) - 1:
                for i in self._holding(texts[first : k + 1]):
                    found[first + i] = self.matches(texts[first + i], coverage)
                first, signs = k + 1, 0
        return found

    def _holding(self, texts: list[str | None]) -> list[int]:
        """Places of the texts that hold a key, or seem to across BETWEEN."""
        tokens, sizes = [], []
        for text in texts:
            own = (text or "").split()
            sizes.append(len(own) + 1)
            tokens.append(BETWEEN)
            tokens += own
        codes, source = _coded(tokens)
        word, kind, either, real = _read(codes)
        owner = np.repeat(np.arange(len(texts)), sizes)[source][real]
        who = []
        for size in self.sizes if len(self) else ():
            if len(word) >= size:
                h, at, _, _ = windows(word, kind, either, size)
                near = np.flatnonzero(self.ends[h & self.mask])
                h = h[near]
                hit = self.hash[np.minimum(np.searchsorted(self.hash, h), len(self.hash) - 1)] == h
                who.append(owner[at[near[hit]] + size - 1])
        return np.unique(np.concatenate(who)).tolist() if who else []

    def matches(self, text: str | None, coverage: float) -> list[tuple[int, int, float, int, bool]]:
        """(item_id, windows hit, coverage, slots, verbatim) of each item that the text holds."""
        own = _Text(text)
        if not len(own.word) or not len(self):
            return []
        who: list[np.ndarray] = []
        for size in self.sizes:
            h = own.raw(size)
            lo = np.searchsorted(self.hash, h)
            hit = np.unique(h[self.hash[np.minimum(lo, len(self.hash) - 1)] == h])
            lo, hi = np.searchsorted(self.hash, hit), np.searchsorted(self.hash, hit, side="right")
            who += [self.owner[a:b] for a, b in zip(lo, hi, strict=True)]
        found = []
        for k in np.unique(np.concatenate(who)) if who else ():
            best = self.items[k].match(own, coverage)
            if best:
                found.append((self.items[k].item_id, *best))
        return found


def small_index(benchmark: DataFrame, coverage: float = COVERAGE) -> Index | None:
    """The index of a benchmark of up to BLOCK_WINDOWS words, else None."""
    words = benchmark.agg(F.sum(F.size(F.split("text", r"\s+"))), F.count("*")).first()
    if (words[0] or 0) + words[1] > BLOCK_WINDOWS:
        return None
    rows = benchmark.select("item_id", "text").orderBy("item_id", F.xxhash64("text")).collect()
    return Index([(r["item_id"], r["text"]) for r in rows], coverage)


FOUND = ["item_id", "windows", "coverage", "slots", "verbatim"]
FOUND_KINDS = (pa.int64(), pa.int32(), pa.float64(), pa.int32(), pa.bool_())
_FOUND_FIELDS = [T.StructField(n, k()) for n, k in zip(FOUND, (T.LongType, T.IntegerType, T.DoubleType, T.IntegerType, T.BooleanType), strict=True)]


def _found_batch(lead: pa.Array, lead_name: str, rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [()] * len(FOUND)
    return pa.RecordBatch.from_arrays([lead, *(pa.array(c, k) for c, k in zip(cols, FOUND_KINDS, strict=True))], names=[lead_name, *FOUND])


def contaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE) -> DataFrame:
    """(doc_id, item_id, windows, coverage, slots, verbatim): the documents that hold an item, by item."""
    src = id_and_text(docs)
    index = small_index(benchmark, coverage)
    if index is None:
        keyed = src.select("doc_id", F.xxhash64("text").alias("key"))
        return keyed.join(_joined(src, benchmark, coverage), "key").drop("key")
    held = docs.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = held.value.all_matches(b.column(1).to_pylist(), coverage)
            take = [i for i, m in enumerate(rows) for _ in m]
            if take:
                yield _found_batch(b.column(0).take(pa.array(take)), "doc_id", [x for m in rows for x in m])

    return src.mapInArrow(run, T.StructType([T.StructField("doc_id", src.schema["doc_id"].dataType), *_FOUND_FIELDS]))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE) -> DataFrame:
    """The rows of docs, all columns as they are, that hold no item of the benchmark."""
    index = small_index(benchmark, coverage)
    if index is None:
        bad = cut(_joined(id_and_text(docs), benchmark, coverage).select(F.col("key").alias("_kb_key")).distinct())
        return docs.join(bad, F.xxhash64(F.coalesce(docs["text"], F.lit(""))) == bad["_kb_key"], "left_anti")
    at = docs.columns.index("text")
    held = docs.sparkSession.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array([not m for m in held.value.all_matches(b.column(at).to_pylist(), coverage)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def _bits(hashes: np.ndarray, bits: int) -> np.ndarray:
    """Two places in the filter for each hash."""
    mask = np.uint64(bits - 1)
    return np.concatenate((hashes & mask, (hashes >> np.uint64(32)) & mask)).astype(np.int64)


def _filter_of(keys: DataFrame, bits: int) -> np.ndarray:
    """The Bloom filter of all keys: words that hold a bit, added up on the executors, come to the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = np.unique(_bits(b.column(0).to_numpy().view(np.uint64), bits))
            word, start = np.unique(at >> 6, return_index=True)
            value = np.bitwise_or.reduceat(np.uint64(1) << (at & 63).astype(np.uint64), start) if len(at) else np.zeros(0, np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(word), pa.array(value.view(np.int64))], names=["word", "value"])

    rows = keys.select("hash").mapInArrow(run, "word long, value long").groupBy("word").agg(F.bit_or("value").alias("value")).toArrow()
    out = np.zeros(bits // 64, np.uint64)
    out[rows.column("word").to_numpy()] = rows.column("value").to_numpy().view(np.uint64)
    return out


def _joined(src: DataFrame, benchmark: DataFrame, coverage: float) -> DataFrame:
    """(key, item_id, ...): what each different text of src (doc_id, text) holds, key being its hash."""
    bench = benchmark.select("item_id", "text").withColumn("item", F.xxhash64("item_id", "text")).dropDuplicates(["item"])

    def of_items(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for item, text in zip(b.column(2).to_pylist(), b.column(1).to_pylist(), strict=True):
                h = np.unique(_Item(0, text).hash).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(np.full(len(h), item))], names=["hash", "item"])

    every = cut(bench.mapInArrow(of_items, "hash long, item long"))
    owners = every.groupBy("hash").agg(F.count("*").alias("owners"))
    counted = every.join(owners, "hash").groupBy("item").agg(F.sort_array(F.collect_list(F.struct("hash", "owners"))).alias("counts"))

    def keys_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for item, text, counts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                own = _Item(0, text)
                known = np.array([c["hash"] for c in counts], np.int64)
                order = np.argsort(known.view(np.uint64))
                count = np.array([c["owners"] for c in counts], np.int64)[order]
                h = own.keys(count[np.searchsorted(known.view(np.uint64)[order], own.hash)], coverage).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(np.full(len(h), item)), pa.array(np.full(len(h), own.size))], names=["hash", "item", "size"])

    keys = cut(bench.join(counted, "item").select("item", "text", "counts").mapInArrow(keys_of, "hash long, item long, size long"))
    sizes = sorted(r["size"] for r in keys.select("size").distinct().collect())
    spark = src.sparkSession
    passed = spark.sparkContext.broadcast(_filter_of(keys, FILTER_BITS))
    texts = src.select("text").withColumn("key", F.xxhash64("text"))

    def of_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = passed.value
        seen: set[int] = set()
        for b in batches:
            for text, key in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if key in seen:
                    continue
                seen.add(key)
                own = _Text(text)
                h = np.unique(np.concatenate([np.zeros(0, np.uint64), *(own.raw(s) for s in sizes)]))
                at = _bits(h, FILTER_BITS)
                in_filter = (held[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)
                h = h[(in_filter[: len(h)] & in_filter[len(h) :]) > 0].view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(np.full(len(h), key))], names=["hash", "key"])

    hits = texts.mapInArrow(of_texts, "hash long, key long").withColumn("salt", F.pmod("key", F.lit(SALTS)).cast("int"))
    salted = keys.select("hash", "item", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    pairs = cut(hits.join(salted, ["hash", "salt"]).select("key", "item").distinct())
    # one text and the items that may lie in it meet in one task: the text comes first, then the items one by one
    wanted = texts.join(pairs.select("key").distinct(), "key", "left_semi").dropDuplicates(["key"])
    items = pairs.join(bench.select("item", "item_id", F.col("text").alias("body")), "item").select("key", F.lit(1).alias("turn"), "item", "item_id", "body")
    lead = wanted.select("key", F.lit(0).alias("turn"), F.lit(0).cast("long").alias("item"), F.lit(0).cast("long").alias("item_id"), F.col("text").alias("body"))
    met = lead.union(items.select("key", "turn", "item", F.col("item_id").cast("long"), "body")).repartition("key").sortWithinPartitions("key", "turn", "item_id")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, at = None, None
        for b in batches:
            who, rows = [], []
            for key, turn, item, item_id, body in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if not turn:
                    own, at = _Text(body), key
                elif at == key and (best := _Item(item_id, body).match(own, coverage)):
                    who.append((key, item))
                    rows.append((item_id, *best))
            if rows:
                found = _found_batch(pa.array([k for k, _ in who], pa.int64()), "key", rows)
                yield pa.RecordBatch.from_arrays([*found.columns, pa.array([i for _, i in who], pa.int64())], names=[*found.schema.names, "item"])

    fields = [T.StructField("key", T.LongType()), *_FOUND_FIELDS, T.StructField("item", T.LongType())]
    found = met.mapInArrow(compare, T.StructType(fields))
    # items that repeat give a row each
    times = benchmark.select(F.xxhash64("item_id", "text").alias("item")).groupBy("item").agg(F.count("*").alias("times"))
    return found.join(times, "item").withColumn("_n", F.explode(F.sequence(F.lit(1), F.col("times")))).select("key", *FOUND)
