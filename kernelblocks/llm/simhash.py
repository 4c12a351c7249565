"""SimHash near-duplicates: fingerprints, exact candidate keys, bit-sliced comparison, components.

A fingerprint has 64 bits; two texts link when 3 bits or fewer differ. Six groups of bits give
20 keys of three groups each: fingerprints that differ in 3 bits or fewer agree on three groups at
least, so no link is lost. Equal texts share one fingerprint and are compared once, whatever their
number; a bucket with many fingerprints is dealt in blocks. Defined results: null and empty texts have
fingerprint zero and link like any other; repeated rows give a row each; a bit that half of the
shingles set stays 0; texts of any length are hashed whole, a slice of shingles at a time; an empty
table gives no row; other columns don't matter; a null id never becomes a component's name unless all
are null.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.components import connected_components
from kernelblocks.llm.hotkeys import in_blocks
from kernelblocks.llm.runtime import as_long, cut, id_and_text

RADIUS = 3
GROUP_BITS = (11, 11, 11, 11, 10, 10)
SLICE = 1 << 17
#: Hashes whose bits are counted at once for a wide fingerprint.
WIDE_SLICE = 1 << 12
#: Lanes are compared in blocks of this many 64-bit words.
BLOCK_WORDS = 16
#: Buckets of more fingerprints are compared in pairs of blocks.
BLOCK_ROWS = 8192


def _hashes(words: list[bytes], size: int) -> np.ndarray:
    digest = partial(xxhash.xxh64_intdigest, seed=42)
    if len(words) <= size:
        shingles: list[bytes] | Iterator[bytes] = [b" ".join(words)] if words else []
        count = len(shingles)
    else:
        count = len(words) - size + 1
        shingles = map(b" ".join, zip(*(words[k:] for k in range(size)), strict=False))
    return np.fromiter(map(digest, shingles), dtype=np.uint64, count=count)


def _ones(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """How often each of the 64 bits is set, for the runs of hashes that begin at starts."""
    bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.add.reduceat(bits, starts, axis=0, dtype=np.int64)


def fingerprint_texts(texts: list[str | None], size: int = 3) -> np.ndarray:
    """One unsigned 64-bit fingerprint for each text."""
    ones = np.zeros((len(texts), 64), dtype=np.int64)
    total = np.zeros(len(texts), dtype=np.int64)
    held: list[np.ndarray] = []
    who: list[int] = []
    waiting = 0

    def flush() -> None:
        nonlocal held, who, waiting
        if held:
            starts = np.cumsum([0] + [len(h) for h in held[:-1]])
            np.add.at(ones, who, _ones(np.concatenate(held), starts))
        held, who, waiting = [], [], 0

    for i, text in enumerate(texts):
        # bytes.lower() and bytes.split() know ASCII letters and ASCII white space only
        h = _hashes((text or "").encode("utf-8", "surrogatepass").lower().split(), size)
        total[i] = len(h)
        for k in range(0, len(h), SLICE):
            held.append(h[k : k + SLICE])
            who.append(i)
            waiting += len(held[-1])
            if waiting >= SLICE:
                flush()
    flush()
    return np.packbits(2 * ones > total[:, None], axis=1, bitorder="little").view(np.uint64).reshape(-1)


def wide_print(hashes: np.ndarray, words: int = 4) -> np.ndarray:
    """A fingerprint of words x 64 bits of one run of hashes: the first word is the usual one, the others are of mixed hashes."""
    ones = np.zeros(64 * words, np.int64)
    for k in range(0, len(hashes), WIDE_SLICE):
        part = hashes[k : k + WIDE_SLICE]
        all_bits = np.empty((len(part), words), np.uint64)
        for j in range(words):
            h = part ^ np.uint64(0x9E3779B97F4A7C15 * j & (1 << 64) - 1)
            if j:
                h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
                h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
                h ^= h >> np.uint64(31)
            all_bits[:, j] = h
        bits = np.unpackbits(all_bits.view(np.uint8), axis=1, bitorder="little")
        for at in range(0, len(bits), 255):  # what a byte can count
            ones += np.add.reduce(bits[at : at + 255], axis=0, dtype=np.uint8)
    return np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)


def fingerprints(docs: DataFrame, size: int = 3) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long."""
    src = id_and_text(docs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = fingerprint_texts(b.column(1).to_pylist(), size).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps)], names=["doc_id", "fp"])

    kind = src.schema["doc_id"].dataType
    return src.mapInArrow(run, T.StructType([T.StructField("doc_id", kind), T.StructField("fp", T.LongType())]))


def key_masks() -> list[int]:
    lows = np.cumsum((0, *GROUP_BITS))
    groups = [((1 << n) - 1) << int(lo) for n, lo in zip(GROUP_BITS, lows, strict=False)]
    keep = len(GROUP_BITS) - RADIUS
    return [sum(groups[g] for g in chosen) for chosen in combinations(range(len(groups)), keep)]


def bit_planes(fps: np.ndarray) -> np.ndarray:
    """A row for each bit, which holds it for every fingerprint, 64 fingerprints to a word, padded to whole blocks.

    A fingerprint is one word, or a row of several.
    """
    n, size = len(fps), fps.shape[1] if fps.ndim == 2 else 1
    words = -(-max(n, 1) // (64 * BLOCK_WORDS)) * BLOCK_WORDS
    bits = np.zeros((words * 64, 64 * size), dtype=np.uint8)
    bits[:n] = np.unpackbits(np.ascontiguousarray(fps).view(np.uint8).reshape(-1, 8 * size), axis=1, bitorder="little")
    return np.packbits(np.ascontiguousarray(bits.T), axis=1, bitorder="little").view(np.uint64)


def _slide(row: np.ndarray, by: int) -> np.ndarray:
    """The lanes of a packed row, each moved down by so many places."""
    whole, part = divmod(by, 64)
    out = np.zeros_like(row)
    kept = row[..., whole:]
    out[..., : kept.shape[-1]] = kept
    if part:
        above = np.zeros_like(out)
        above[..., :-1] = out[..., 1:]
        out = (out >> np.uint64(part)) | (above << np.uint64(64 - part))
    return out


def near_places(own: np.ndarray, other: np.ndarray, alive: np.ndarray, radius: int) -> np.ndarray:
    """Lanes of alive where the fingerprints of two sets of planes differ in at most radius bits.

    Counter planes add the differences of all lanes of a block at once, carries going from one to the
    next; they begin so that the lane past the radius is the one that overflows. A block whose lanes
    have all overflowed is left.
    """
    words = own.shape[1]
    packed = np.packbits(alive, bitorder="little")
    over = np.full(words * 8, 255, dtype=np.uint8)
    over[: len(packed)] = ~packed
    over = over.view(np.uint64).reshape(-1, BLOCK_WORDS).copy()
    live = np.flatnonzero((over != ~np.uint64(0)).any(axis=1))
    size = len(own)
    own, other = own.reshape(size, -1, BLOCK_WORDS), other.reshape(size, -1, BLOCK_WORDS)
    state = over[live]
    wide = radius.bit_length()
    begin = (1 << wide) - 1 - radius
    counts = [np.full_like(state, ~np.uint64(0) if begin >> k & 1 else np.uint64(0)) for k in range(wide)]
    for b in range(size):
        if not len(live):
            break
        carry = own[b, live] ^ other[b, live]
        for plane in counts:
            plane ^= carry
            carry &= ~plane  # the carry goes on where a one became a zero
        state |= carry
        if b % 8 == 7:
            keep = (state != ~np.uint64(0)).any(axis=1)
            if not keep.all():
                live, state, counts = live[keep], state[keep], [plane[keep] for plane in counts]
    lanes = np.flatnonzero(np.unpackbits(~state.reshape(-1).view(np.uint8), bitorder="little"))
    per = 64 * BLOCK_WORDS
    return live[lanes // per] * per + lanes % per if len(lanes) else lanes


def near_lanes(planes: np.ndarray, shift: int, alive: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """Lanes i of alive whose fingerprint differs from lane i+shift in at most radius bits."""
    return near_places(planes, _slide(planes, shift), alive, radius)


def bucket_links(keys: np.ndarray, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges that span the near groups inside each run of equal keys: (least of the group, member)."""
    n = len(fps)
    first = np.flatnonzero(np.concatenate(([True], np.any(keys[1:] != keys[:-1], axis=1)))) if n else np.zeros(0, int)
    sizes = np.diff(np.append(first, n))
    wanted = np.repeat(sizes > 1, sizes)
    if not wanted.any():
        return fps[:0], fps[:0]
    fps, sizes = fps[wanted], sizes[sizes > 1]
    # long runs first: the lanes still in play at a later shift lie together
    order = np.argsort(-sizes, kind="stable")
    starts = (np.cumsum(sizes) - sizes)[order]
    sizes = sizes[order]
    lead = np.cumsum(sizes) - sizes
    fps = fps[np.repeat(starts - lead, sizes) + np.arange(len(fps))]
    ends = np.repeat(np.cumsum(sizes), sizes)
    label = np.arange(len(fps))
    spot = np.arange(len(fps))
    planes = bit_planes(fps)
    per = 64 * BLOCK_WORDS
    for d in range(1, int(sizes[0])):
        reach = int(sizes[sizes > d].sum())
        near = near_lanes(planes[:, : -(-reach // per) * BLOCK_WORDS], d, spot[:reach] + d < ends[:reach])
        fresh = near[label[near] != label[near + d]]
        while len(fresh):
            x, y = label[fresh], label[fresh + d]
            np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
            while True:
                jumped = label[label]
                if np.array_equal(jumped, label):
                    break
                label = jumped
            fresh = fresh[label[fresh] != label[fresh + d]]
    moved = np.flatnonzero(label != spot)
    return fps[label[moved]], fps[moved]


def links(prints: DataFrame, fp: str = "fp", block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(a, b): edges between different fingerprints that connect all that link.

    A bucket of more than block_rows fingerprints is dealt in blocks, a task for each pair of blocks.
    """
    keys = F.explode(
        F.array(
            *(
                F.struct(F.lit(i).alias("t"), F.col(fp).bitwiseAND(F.lit(as_long(m))).alias("m"))
                for i, m in enumerate(key_masks())
            )
        )
    )
    rows = prints.select(fp).distinct().select(keys.alias("k"), F.col(fp).alias("fp")).select("k.t", "k.m", "fp")
    sizes = rows.groupBy("t", "m").agg(F.count("*").alias("n_rows"))
    order = ["t", "m", "lo", "hi"]
    dealt = in_blocks(rows, sizes, ["t", "m"], "fp", block_rows).select(*order, "fp").repartition(*order).sortWithinPartitions(*order, "fp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def out(rows: np.ndarray) -> pa.RecordBatch:
            a, b = bucket_links(rows[:, :4], rows[:, 4].copy().view(np.uint64))
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            held.append(np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns], axis=1))
            if sum(map(len, held)) >= SLICE:
                rows = np.concatenate(held)
                last = np.flatnonzero(np.any(rows[:, :4] != rows[-1, :4], axis=1))
                end = int(last[-1]) + 1 if len(last) else 0
                if end:
                    yield out(rows[:end])
                held = [rows[end:]]
        if held and sum(map(len, held)):
            yield out(np.concatenate(held))

    return dealt.mapInArrow(run, "a long, b long")


def components(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, component_id) for every row of docs."""
    prints = cut(fingerprints(docs))
    least = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    roots = connected_components(links(least), "a", "b")
    named = least.join(roots, least.fp == roots.node, "left").select(
        "fp", F.coalesce("root", "fp").alias("root"), "least_id"
    )
    named = cut(named)
    smallest = named.groupBy("root").agg(F.min("least_id").alias("component_id"))
    return prints.join(named.join(smallest, "root").select("fp", "component_id"), "fp").select(
        "doc_id", "fp", "component_id"
    )


def hex_fingerprint(fp) -> F.Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of docs."""
    found = components(docs)
    return found.select("doc_id", hex_fingerprint(found.fp).alias("fingerprint"), "component_id")
