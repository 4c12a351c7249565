"""Embedding near-duplicates by lattice hashing.

In each of several tables a vector is projected to 16 dimensions by an orthonormal random map and the
two halves are decoded to the nearest points of the E8 lattice; the pair of points names the vector's
home cell. The cells with the next nearest point in one half or both are its probes. Two vectors meet
where one's home is the other's home or probe, and every meeting is verified by cosine in double
precision. A link that several cells or tables find counts in the first of them alone, which both
vectors' cells tell without any exchange; so no list of pairs is made, only counts and edges that span
the groups found.

Names of cells travel first, without vectors; vectors go to the cells where several classes meet.
Equal vectors are one class with a multiplicity and are compared once. Cells with more than
BLOCK_ROWS members are split in blocks, and pairs of blocks go to different tasks, which count what they
find tile by tile.

Defined results: vectors that are null, empty, zero or hold null or non-finite numbers link with
nothing, and so do vectors of different lengths; they keep a row each with n_links 0. Rows that share
a vec_id keep a row each and count as vectors each, and as one where components are named; of equal
vectors the least id names the class, and rows without an id take its component; a cosine of exactly
the threshold links; vectors may be of any length; an empty table gives no row; other columns don't matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.components import connected_components
from kernelblocks.llm.hotkeys import in_blocks
from kernelblocks.llm.runtime import cut

COSINE = 0.95
TABLES = 10
HALVES = 2
CELL = 1.5
PROBES = 1 << HALVES
BLOCK_ROWS = 4096
TILE = 1024
CHUNK_ROWS = 1 << 14


def nearest_e8(x: np.ndarray) -> np.ndarray:
    """The E8 lattice point nearest to each row of eight numbers."""

    def even(y: np.ndarray) -> np.ndarray:
        """Nearest whole-number point with an even sum: where the sum is odd, the worst rounding goes the other way."""
        r = np.rint(y)
        gap = y - r
        worst = np.argmax(np.abs(gap), axis=1)
        rows = np.flatnonzero(r.sum(axis=1) % 2 != 0)
        at = worst[rows]
        r[rows, at] += np.where(gap[rows, at] >= 0, 1.0, -1.0)
        return r

    a, b = even(x), even(x - 0.5) + 0.5
    return np.where((((x - a) ** 2).sum(axis=1) <= ((x - b) ** 2).sum(axis=1))[:, None], a, b)


@lru_cache
def shortest() -> np.ndarray:
    """The 240 shortest nonzero points: steps to neighbouring cells."""
    out = []
    for i in range(8):
        for j in range(i):
            for s in (1, -1):
                for t in (1, -1):
                    v = [0.0] * 8
                    v[i], v[j] = s, t
                    out.append(v)
    for bits in range(256):
        if bits.bit_count() % 2 == 0:
            out.append([-0.5 if bits >> k & 1 else 0.5 for k in range(8)])
    return np.array(out)


@lru_cache
def projection(width: int, table: int) -> np.ndarray:
    """width x 16; lengths are kept as an independent direction of that many would keep them."""
    rng = np.random.Generator(np.random.Philox(key=[width, table + 17]))
    g = rng.standard_normal((max(width, 8 * HALVES), 8 * HALVES))
    q, _ = np.linalg.qr(g)
    return q[:width] * np.sqrt(max(width, 8 * HALVES)) / CELL


_MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB], np.uint64)


def _name(points: np.ndarray, salt: int) -> np.ndarray:
    """64-bit names of lattice points; half steps are counted, so the numbers are whole."""
    whole = np.rint(points * 2).astype(np.int64).view(np.uint64)
    h = (whole * _MIX).sum(axis=1, dtype=np.uint64) + np.uint64(salt)
    h ^= h >> np.uint64(31)
    h *= np.uint64(0x9FB21C651E98DF25)
    return h ^ (h >> np.uint64(28))


def cells(unit: np.ndarray) -> np.ndarray:
    """(vectors, TABLES, PROBES) names of cells; the first probe of a table is the home."""
    n, width = unit.shape
    out = np.empty((n, TABLES, PROBES), np.int64)
    steps = shortest()
    for t in range(TABLES):
        y = unit @ projection(width, t)
        near = []
        for half in range(HALVES):
            x = y[:, 8 * half : 8 * half + 8]
            home = nearest_e8(x)
            step = steps[np.argmax((x - home) @ steps.T, axis=1)]
            near.append((_name(home, half + 1), _name(home + step, half + 1)))
        for k in range(PROBES):
            h = np.full(n, np.uint64(t * 1000003 + width))
            for half in range(HALVES):
                h = (h ^ near[half][k >> half & 1]) * np.uint64(0xD6E8FEB86659FD93)
                h ^= h >> np.uint64(32)
            out[:, t, k] = h.view(np.int64)
    return out


def span(a: np.ndarray, b: np.ndarray, label: np.ndarray) -> np.ndarray:
    """For the edges a-b between places, and those that label stands for: the least place that each place reaches."""
    label = label.copy()
    while True:
        x, y = label[a], label[b]
        open_ = x != y
        if not open_.any():
            return label
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(label[label], label):
            label = label[label]


def unit_rows(v: np.ndarray) -> np.ndarray:
    """Rows of length one, in double precision."""
    v = v / np.abs(v).max(axis=1, keepdims=True)  # so that squares neither overflow nor vanish
    return v / np.sqrt((v * v).sum(axis=1, keepdims=True))


def _first_here(ca: np.ndarray, cb: np.ndarray, table: np.ndarray, cell: np.ndarray) -> np.ndarray:
    """Whether the cell at hand is the first place where the two vectors of each row meet."""
    a_in_b = (cb == ca[:, :, :1]).any(axis=2)
    b_in_a = (ca == cb[:, :, :1]).any(axis=2)
    rows = np.arange(len(table))
    first = np.argmax(a_in_b | b_in_a, axis=1) == table
    big = np.iinfo(np.int64).max
    at_a = np.where(a_in_b[rows, table], ca[rows, table, 0], big)
    at_b = np.where(b_in_a[rows, table], cb[rows, table, 0], big)
    return first & (np.minimum(at_a, at_b) == cell)


def _compare(rows: dict[str, np.ndarray], cosine: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(places a, places b, places of the cell's first row) of verified meetings; rows are sorted by cell and blocks."""
    cell, lo, hi, home, unit, own, block = (rows[k] for k in ("cell", "lo", "hi", "home", "unit", "rep", "block"))
    edges = np.flatnonzero(np.concatenate(([True], (cell[1:] != cell[:-1]) | (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1]))))
    for s, e in zip(edges, np.append(edges[1:], len(cell)), strict=True):
        if e - s < 2:
            continue
        for i in range(s, e, TILE):
            for j in range(i, e, TILE):
                x, y = slice(i, min(i + TILE, e)), slice(j, min(j + TILE, e))
                near = unit[x] @ unit[y].T >= cosine
                near &= (home[x][:, None] | home[y][None, :]) & (own[x][:, None] != own[y][None, :])
                if lo[s] != hi[s]:
                    near &= block[x][:, None] != block[y][None, :]
                a, b = np.nonzero(near)
                a, b = a + i, b + j
                once = a < b
                if once.any():
                    yield a[once], b[once], np.full(int(once.sum()), s)


def _links(rows: dict[str, np.ndarray], cosine: float) -> list[np.ndarray]:
    """[kind, a, b]: (0, class, links) and (1, class, least class reached) of a run of whole cells.

    Meetings are counted some tiles at a time and never held together.
    """
    rep, count, unit = rows["rep"], rows["n"], rows["unit"]
    who, at = np.unique(rep, return_inverse=True)
    links, label = np.zeros(len(who)), np.arange(len(who))
    known, named = np.zeros(len(rep), bool), None
    held: list[tuple[np.ndarray, ...]] = []
    waiting = 0

    def count_held() -> None:
        nonlocal links, label, named, held, waiting
        a, b, s = (np.concatenate(x) for x in zip(*held, strict=True))
        held, waiting = [], 0
        if named is None:
            named = np.empty((len(rep), TABLES, PROBES), np.int64)
        new = np.unique(np.concatenate((a, b)))
        new = new[~known[new]]
        if len(new):
            named[new], known[new] = cells(unit[new]), True
        for k in range(0, len(a), CHUNK_ROWS):
            x, y, z = a[k : k + CHUNK_ROWS], b[k : k + CHUNK_ROWS], s[k : k + CHUNK_ROWS]
            keep = _first_here(named[x], named[y], rows["table"][z], rows["cell"][z])
            links += np.bincount(at[x[keep]], weights=count[y[keep]], minlength=len(who))
            links += np.bincount(at[y[keep]], weights=count[x[keep]], minlength=len(who))
        label = span(at[a], at[b], label)

    for found in _compare(rows, cosine):
        held.append(found)
        waiting += len(found[0])
        if waiting >= CHUNK_ROWS:
            count_held()
    if held:
        count_held()
    linked = np.flatnonzero(links)
    moved = np.flatnonzero(label != np.arange(len(who)))
    return [
        np.concatenate((np.zeros(len(linked), np.int64), np.ones(len(moved), np.int64))),
        np.concatenate((who[linked], who[moved])),
        np.concatenate((links[linked].astype(np.int64), who[label[moved]])),
    ]


def _cells_of(classes: DataFrame) -> DataFrame:
    """(cell, rep, at): a row for each class and cell of it; at is the table, doubled, and one more where it is the home."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rep = batch.column(0).to_numpy()
            lists = batch.column(1)
            width = np.diff(lists.offsets.to_numpy())
            flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
            starts = np.cumsum(width) - width
            for w in np.unique(width):
                rows = np.flatnonzero(width == w)
                for k in range(0, len(rows), 1024):
                    own = rows[k : k + 1024]
                    c = cells(unit_rows(flat[starts[own][:, None] + np.arange(w)])).reshape(len(own), -1)
                    spot = np.tile(np.arange(TABLES * PROBES), len(own))
                    at = (spot // PROBES * 2 + (spot % PROBES == 0)).astype(np.int32)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(c.reshape(-1)), pa.array(np.repeat(rep[own], TABLES * PROBES)), pa.array(at)], names=["cell", "rep", "at"]
                    )

    return classes.select("rep", "embedding").mapInArrow(run, "cell long, rep long, at int")


def _whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str], rows: int) -> Iterator[pa.Table]:
    """Tables of some rows each, sorted by keys, none of which cuts a group of equal keys."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        held.append(b)
        size += b.num_rows
        if size >= rows:
            table = pa.Table.from_batches(held)
            last = np.stack([table.column(k).to_numpy() for k in keys])
            other = np.flatnonzero(np.any(last != last[:, -1:], axis=0))
            end = int(other[-1]) + 1 if len(other) else 0
            if end:
                yield table.slice(0, end)
            held = table.slice(end).to_batches()
            size = table.num_rows - end
    if size:
        yield pa.Table.from_batches(held)


def _shared(postings: DataFrame) -> DataFrame:
    """The postings, sorted by cell, of cells with several rows; they pass as they come, however many a cell has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        back, passed = None, False  # the last row, and whether it has been given
        for b in batches:
            if not b.num_rows:
                continue
            t = pa.Table.from_batches([back, b] if back is not None else [b]).combine_chunks()
            cell = t.column("cell").to_numpy()
            same = cell[1:] == cell[:-1]
            several = np.concatenate((same, [False])) | np.concatenate(([False], same))
            out = several.copy()
            out[0] &= not (back is not None and passed)
            yield from t.filter(pa.array(out)).to_batches()
            passed = bool(several[-1]) or (len(cell) == 1 and passed)
            back = t.slice(t.num_rows - 1).to_batches()[0]

    return postings.mapInArrow(run, "cell long, rep long, at int")


def near_vectors(vectors: DataFrame, cosine: float = COSINE, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of vectors."""
    # single-precision numbers travel as they are; the cosine is computed in double precision either way
    single = isinstance(vectors.schema["embedding"].dataType.elementType, T.FloatType)
    number = "float" if single else "double"
    src = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast(f"array<{number}>").alias("embedding"))
    sound = (
        f"coalesce(size(embedding), 0) > 0 AND forall(embedding, x -> x IS NOT NULL AND NOT isnan(x) AND abs(x) < {number}('infinity'))"
        " AND exists(embedding, x -> x <> 0)"
    )
    marked = src.withColumn("ok", F.coalesce(F.expr(sound), F.lit(False)))
    # 128 bits name a vector
    named = [F.xxhash64("embedding").alias("h1"), F.xxhash64(F.lit("second"), "embedding").alias("h2")]
    good = marked.where("ok").select("vec_id", *named, "embedding")
    classes = good.groupBy("h1", "h2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n"), F.first("embedding").alias("embedding"))
    classes = cut(classes.where("rep is not null"))
    # numbers alone are dealt by cell; vectors go where classes meet
    meets = cut(_shared(_cells_of(classes).repartition("cell").sortWithinPartitions("cell")))
    sizes = meets.groupBy("cell").agg(F.count("*").alias("n_rows"))
    raw = classes.select("rep", "n", "embedding")
    rows = in_blocks(meets, sizes, ["cell"], "rep", block_rows).join(raw, "rep")
    order = ["cell", "lo", "hi"]
    dealt = rows.select(*order, "at", "rep", "n", "block", "embedding").repartition(*order).sortWithinPartitions(*order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _whole_groups(batches, order, CHUNK_ROWS):
            cols = {k: table.column(k).to_numpy() for k in (*order, "rep", "n", "block")}
            at = table.column("at").to_numpy()
            cols |= {"table": at // 2, "home": at % 2 == 1}
            lists = table.column("embedding").combine_chunks()
            width = np.diff(lists.offsets.to_numpy())
            flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
            starts = np.cumsum(width) - width
            for w in np.unique(width):
                own = np.flatnonzero(width == w)
                part = {k: v[own] for k, v in cols.items()}
                part["unit"] = unit_rows(flat[starts[own][:, None] + np.arange(w)])
                out = _links(part, cosine)
                if len(out[0]):
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in out], names=["kind", "a", "b"])

    found = dealt.mapInArrow(run, "kind long, a long, b long").groupBy("kind", "a", F.when(F.col("kind") == 1, F.col("b")).alias("to")).agg(F.sum("b").alias("s"))
    found = cut(found)
    links = found.where("kind = 0").select(F.col("a").alias("rep"), F.col("s").alias("more"))
    roots = connected_components(found.where("kind = 1").select("a", F.col("to").alias("b")), "a", "b")
    named = cut(
        classes.select("h1", "h2", "rep", "n")
        .join(links, "rep", "left")
        .join(roots.withColumnRenamed("node", "rep"), "rep", "left")
        .select("h1", "h2", (F.coalesce("more", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("root", "rep").alias("component_id"))
    )
    out = good.select("vec_id", "h1", "h2").join(named, ["h1", "h2"], "left")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    alone = marked.where("NOT ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.union(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
