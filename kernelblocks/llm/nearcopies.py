"""Near copies by SimHash with keys that lose none: texts whose sets of word shingles have Jaccard 0.8 or more.

A text is its set of hashed shingles of five words (words and hash as in simhash.py) and a fingerprint of
256 bits of it; texts with equal sets are one node. The keys come from prefixes: with the members
of all sets in one common order, two sets as alike as that share a member among the first
n - ceil(0.8 n) + 1 of each, so no pair is lost. The order puts shingles that a sample shows to be
frequent last; the choice of the sample changes the work, never the result.

Nodes that share a key are compared bit-sliced (simhash.near_places), those of many keys at once: pairs whose
fingerprints differ in more than RADIUS bits are left. At Jaccard 0.8 some 39 bits of 256 differ, 6 more or less; the chance that a pair
lies past the radius is under 3e-8 at every size (from the exact probability that a majority bit differs). Sets
decide all others, in two steps: first a pair for each node, with the least node near it; then, once those links
have made components, the near pairs of different components, in tasks that hold the sets of some nodes and give
edges that span what they find. No step gives more rows than it has nodes and short lists; a group of n copies
costs some n comparisons of sets, and the components are those of all pairs.

Texts don't move before: postings hold numbers, and only the texts that must be compared are fetched.

Defined results: null and empty texts are near copies of each other; a text shorter than a shingle is one
shingle; of each component the row of the least (doc_id, hash of the text) stays, a null id last; rows
that repeat id and text are copies, rows that share an id alone aren't; texts of any length are read
whole; an empty table gives no row; other columns pass through as they are.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from kernelblocks.llm.components import connected_components
from kernelblocks.llm.hotkeys import in_blocks
from kernelblocks.llm.runtime import cut, id_and_text
from kernelblocks.llm.simhash import BLOCK_WORDS, SLICE, _hashes, _slide, bit_planes, near_places, wide_print

SHINGLE = 5
#: The least Jaccard similarity as a fraction, so that comparisons are exact.
ABOVE, BELOW = 4, 5
#: Bits of 256 in which the fingerprints of a pair may differ.
RADIUS = 84
#: Lists up to this length are compared pair by pair at once.
SHORT_LIST = 8
#: Longer lists and groups are compared in pairs of blocks of so many.
BLOCK_ROWS = 4096
#: The sample that says which shingles are frequent: texts, and how many of them must hold one.
SAMPLE_TEXTS, FREQUENT = 20_000, 4
#: A task compares the lists of so many rows at once, and where their texts are with them, of so many.
ROWS_AT_ONCE, GROUPED_ROWS = 1 << 15, 1 << 12
#: Texts that a task turns into sets at once.
TEXTS_AT_ONCE = 512
#: A task remembers so many nodes whose keys it has given.
SEEN_NODES = 1_000_000
NONE = np.zeros(0, np.uint64)


def shingle_set(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """The different shingles of a text as sorted hashes; a text shorter than a shingle is one, an empty one none."""
    h = _hashes((text or "").encode("utf-8", "surrogatepass").lower().split(), size)
    h.sort()
    return h[np.concatenate(([True], h[1:] != h[:-1]))] if len(h) else h


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two sorted sets reach the bound; two empty ones do."""
    if ABOVE * max(len(a), len(b)) > BELOW * min(len(a), len(b)):
        return False
    both = len(a) + len(b) - len(np.unique(np.concatenate((a, b))))
    return (ABOVE + BELOW) * both >= ABOVE * (len(a) + len(b))


def prefix(members: np.ndarray, frequent: np.ndarray) -> np.ndarray:
    """The first members in the common order, one of which each set that is alike shares among its own."""
    n = len(members)
    if n and len(frequent):
        spot = np.minimum(np.searchsorted(frequent, members), len(frequent) - 1)
        late = frequent[spot] == members
        members = np.concatenate((members[~late], members[late]))
    return members[: n - -(-ABOVE * n // BELOW) + 1]


def _node(members: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(members.tobytes(), seed=7) - (1 << 63)


def _packed(text: str | None) -> bytes:
    return zlib.compress((text or "").encode("utf-8", "surrogatepass"), 1)


def _packed_set(raw: bytes) -> np.ndarray:
    return shingle_set(zlib.decompress(raw).decode("utf-8", "surrogatepass"))


def _hashed(docs: DataFrame) -> DataFrame:
    """(doc_id, text, hash): the hash names a text."""
    return id_and_text(docs).withColumn("hash", F.xxhash64("text"))


def _few(batches: Iterator[pa.RecordBatch], rows: int = TEXTS_AT_ONCE) -> Iterator[pa.RecordBatch]:
    """Some rows at a time: what a task makes of texts is several times as large as they are."""
    for b in batches:
        for k in range(0, b.num_rows, rows):
            yield b.slice(k, rows)


def _named(src: DataFrame, frequent: np.ndarray = NONE) -> DataFrame:
    """(doc_id, hash, node, n, print, keys) of every row: the name, size and fingerprint of the text's set.

    keys, the set's prefix, is there once for each node of a task; an empty set has key 0.
    """
    held = src.sparkSession.sparkContext.broadcast(frequent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for b in _few(batches):
            nodes, sizes, prints, keys = [], [], [], []
            for text in b.column(1).to_pylist():
                members = shingle_set(text)
                node = _node(members)
                nodes.append(node)
                sizes.append(len(members))
                prints.append(wide_print(members).tobytes())
                if node in seen:
                    keys.append(None)
                    continue
                if len(seen) >= SEEN_NODES:
                    seen.clear()
                seen.add(node)
                keys.append((prefix(members, held.value) if len(members) else np.zeros(1, np.uint64)).tobytes())
            cols = [b.column(0), b.column(2), pa.array(nodes, pa.int64()), pa.array(sizes, pa.int32()), pa.array(prints, pa.binary()), pa.array(keys, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "hash", "node", "n", "print", "keys"])

    fields = [T.StructField("doc_id", src.schema["doc_id"].dataType)]
    fields += [T.StructField(c, k) for c, k in (("hash", T.LongType()), ("node", T.LongType()), ("n", T.IntegerType()), ("print", T.BinaryType()), ("keys", T.BinaryType()))]
    return src.mapInArrow(run, T.StructType(fields))


def frequent_shingles(src: DataFrame, total: int) -> np.ndarray:
    """Sorted hashes of the shingles that several texts of a bounded sample hold."""
    if not total:
        return np.zeros(0, np.uint64)
    part = min(1.0, SAMPLE_TEXTS / total)
    few = src.where(F.pmod("hash", F.lit(1_000_000)) < int(1_000_000 * part) + 1).select("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for b in _few(batches):
            sets = [shingle_set(t) for t in set(b.column(0).to_pylist()) if not (hash(t) in seen or seen.add(hash(t)))]
            h = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64))], names=["h"])

    top = few.mapInArrow(run, "h long").groupBy("h").count().where(F.col("count") >= FREQUENT)
    rows = top.orderBy(F.desc("count"), "h").limit(200_000).select("h").toPandas()["h"].to_numpy(np.int64)
    return np.sort(rows.view(np.uint64))


POSTING = "key long, node long, n int"


def _postings(named: DataFrame) -> DataFrame:
    """(key, node, n): a row for each key of named."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _few(batches):
            if b.num_rows:
                keys = [np.frombuffer(k, np.int64) for k in b.column(0).to_pylist()]
                times = [len(k) for k in keys]
                node, n = (np.repeat(b.column(c).to_numpy(), times) for c in (1, 2))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), pa.array(node), pa.array(n)], names=["key", "node", "n"])

    return named.where("keys is not null").select("keys", "node", "n").mapInArrow(run, POSTING)


def _lists(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, bool]]:
    """(rows, whether a list goes on in the next): rows sorted by their first column, whole lists where they fit.

    A list of more than SLICE rows comes in pieces; those after the first begin with the list's first
    row and the last row of the piece before.
    """
    held: list[np.ndarray] = []
    waiting, first = 0, None
    for batch in batches:
        held.append(np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns], axis=1))
        waiting += len(held[-1])
        if waiting >= SLICE:
            rows = np.concatenate(held)
            end = int(np.searchsorted(rows[:, 0], rows[-1, 0]))
            if end:
                yield rows[:end], first is not None and rows[0, 0] == first[0]
                held, first = [rows[end:]], None
            else:
                yield rows, first is not None
                first = rows[0] if first is None else first
                held = [np.stack((first, rows[-1]))]
            waiting = len(held[0])
    if waiting:
        yield np.concatenate(held), first is not None


def _fits(n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Where sets of n and m members can reach the bound by their sizes."""
    return ABOVE * np.maximum(n, m) <= BELOW * np.minimum(n, m)


def _fresh(rows: np.ndarray) -> np.ndarray:
    """Which rows, sorted, aren't the one before again."""
    return np.concatenate(([True], np.any(rows[1:, :2] != rows[:-1, :2], axis=1)))[: len(rows)]


def _edge_batch(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(a, np.int64)), pa.array(np.ascontiguousarray(b, np.int64))], names=["a", "b"])


def short_pairs(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The pairs of nodes (less, greater) of sorted short lists of (key, node, n) whose sizes fit."""
    starts = np.flatnonzero(np.concatenate(([True], rows[1:, 0] != rows[:-1, 0]))) if len(rows) else np.zeros(0, np.int64)
    sizes = np.diff(np.append(starts, len(rows)))
    start, spot = np.repeat(starts, sizes), np.arange(len(rows))
    none = np.zeros(0, np.int64)
    right = [none, *(np.flatnonzero(spot - d >= start) for d in range(1, SHORT_LIST))]
    left = [none, *(j - d for d, j in enumerate(right[1:], 1))]
    i, j = np.concatenate(left), np.concatenate(right)
    ok = _fits(rows[i, 2], rows[j, 2]) & (rows[i, 1] != rows[j, 1])
    a, b = rows[i[ok], 1], rows[j[ok], 1]
    pairs = np.unique(np.stack((np.minimum(a, b), np.maximum(a, b)), axis=1), axis=0)
    return pairs[:, 0], pairs[:, 1]


def _prints(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint64).reshape(len(column), -1)


def _near_only(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """The pairs (a, b) whose fingerprints lie within the radius."""
    one = nodes.select(F.col("node").alias("a"), F.col("print").alias("pa"))
    two = nodes.select(F.col("node").alias("b"), F.col("print").alias("pb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                hit = near_places(bit_planes(_prints(b.column(2))), bit_planes(_prints(b.column(3))), np.ones(b.num_rows, bool), RADIUS)
                yield _edge_batch(b.column(0).to_numpy()[hit], b.column(1).to_numpy()[hit])

    return pairs.join(one, "a").join(two, "b").select("a", "b", "pa", "pb").mapInArrow(run, "a long, b long")


def _merge(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Labels, each the least place reached, after the edges a-b."""
    while len(a):
        x, y = label[a], label[b]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(label[label], label):
            label = label[label]
        open_ = label[a] != label[b]
        a, b = a[open_], b[open_]
    return label


def _decided(label: np.ndarray, near: np.ndarray, other: np.ndarray, decide) -> np.ndarray:
    """Which of the near pairs to merge: those that decide(i, j) finds alike, without those that an earlier one has joined."""
    over: dict[int, int] = {}

    def top(k: int) -> int:
        while k in over:
            k = over[k]
        return k

    take = np.zeros(len(near), bool)
    for at, (i, j) in enumerate(zip(near.tolist(), other.tolist(), strict=True)):
        a, b = top(int(label[i])), top(int(label[j]))
        if a != b and decide(i, j):
            over[max(a, b)] = min(a, b)
            take[at] = True
    return take


def spanned_lists(starts: np.ndarray, n: np.ndarray, prints: np.ndarray, label: np.ndarray | None = None, decide=None) -> np.ndarray:
    """Labels, each the least place reached, after all near pairs inside each of the lists that begin at starts, sorted by size n.

    With decide only near pairs that decide(i, j) finds alike count; pairs that a label already joins are left. The lists are compared together at each distance in their orders. As the distance doubles, lists that are
    done are left, and those that reach furthest come first.
    """
    every = np.arange(len(n))
    label = every.copy() if label is None else label.copy()
    per = 64 * BLOCK_WORDS
    sizes = np.diff(np.append(starts, len(n)))
    who = np.repeat(np.arange(len(starts)), sizes) << 32
    # so many places on, no row of the list is small enough
    reach = np.searchsorted(who + n, who + BELOW * n.astype(np.int64) // ABOVE, side="right") - every
    d = 1
    while len(starts):
        far = np.maximum.reduceat(reach, starts)
        far = np.where(np.minimum.reduceat(label, starts) != np.maximum.reduceat(label, starts), far, 0)
        order = np.argsort(-far, kind="stable")[: int((far > d).sum())]
        if not len(order):
            break
        far, own = far[order], sizes[order]
        at = np.repeat(starts[order] - (np.cumsum(own) - own), own) + np.arange(int(own.sum()))
        ends, span, planes, spot = np.cumsum(own), reach[at], bit_planes(prints[at]), np.arange(len(at))
        for by in range(d, 2 * d):
            lists = int((far > by).sum())
            if not lists:
                break
            m = int(ends[lists - 1])
            now = label[at[:m]]
            alive = (span[:m] > by) & (now != now[np.minimum(spot[:m] + by, m - 1)])
            if alive.any():
                words = -(-m // per) * BLOCK_WORDS
                near = near_places(planes[:, :words], _slide(planes[:, :words], by), alive, RADIUS)
                a, b = at[near], at[near + by]
                if decide is not None:
                    take = _decided(label, a, b, decide)
                    a, b = a[take], b[take]
                label = _merge(label, a, b)
        d *= 2
    return label


def _texts(wanted: DataFrame, nodes: DataFrame, src: DataFrame) -> DataFrame:
    """(node, text), the text compressed, for each node of wanted."""
    texts = src.join(nodes.join(wanted.select("node").distinct(), "node").select("node", "hash"), "hash").select("node", "text")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for b in _few(batches):
            rows = []
            for node, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                # two texts may share a hash: only the one of this set counts
                if node not in seen and _node(shingle_set(text)) == node:
                    seen.add(node)
                    rows.append((node, _packed(text)))
            yield pa.RecordBatch.from_arrays([pa.array([n for n, _ in rows], pa.int64()), pa.array([t for _, t in rows], pa.binary())], names=["node", "text"])

    return cut(texts.mapInArrow(pack, "node long, text binary").dropDuplicates(["node"]))


def verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sets reach the bound; b is in one pair alone, so no task has many of one set."""
    one, two = (texts.select(F.col("node").alias(c), F.col("text").alias(f"t{c}")) for c in "ab")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, np.ndarray] = {}
        for batch in _few(batches):
            out = []
            for a, b, ta, tb in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if a not in known:
                    if len(known) > 256:
                        known.clear()
                    known[a] = _packed_set(ta)
                if alike(known[a], _packed_set(tb)):
                    out.append((a, b))
            yield _edge_batch(*np.array(out, np.int64).reshape(-1, 2).T)

    return pairs.join(one, "a").join(two, "b").select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def _whole(batches: Iterator[pa.RecordBatch], keys: int, rows: int) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """(some rows, where their runs of equal first columns begin): as many whole runs as it takes to so many rows."""
    held: list[pa.RecordBatch] = []
    waiting = 0

    def begins(table: pa.Table) -> np.ndarray:
        now = np.stack([table.column(k).to_numpy() for k in range(keys)])
        return np.flatnonzero(np.concatenate(([True], np.any(now[:, 1:] != now[:, :-1], axis=0))))

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            waiting += batch.num_rows
        if waiting >= rows:
            table = pa.Table.from_batches(held).combine_chunks()
            starts = begins(table)
            if len(starts) > 1:
                yield table.slice(0, starts[-1]), starts[:-1]
                table = table.slice(starts[-1])
            held, waiting = table.to_batches(), table.num_rows
    if waiting:
        table = pa.Table.from_batches(held).combine_chunks()
        yield table, begins(table)


def _near_in_lists(rows: DataFrame, nodes: DataFrame, block_rows: int) -> DataFrame:
    """(a, b): edges that span the near nodes of each long list (key, node)."""
    sizes = rows.groupBy("key").agg(F.count("*").alias("n_rows"))
    order = ["key", "lo", "hi"]
    spread = in_blocks(rows, sizes, ["key"], "node", block_rows).join(nodes.select("node", "n", "print"), "node")
    dealt = spread.select(*order, "node", "n", "print").repartition(*order).sortWithinPartitions(*order, "n", "node")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, starts in _whole(batches, 3, ROWS_AT_ONCE):
            node, n = table.column("node").to_numpy(), table.column("n").to_numpy()
            label = spanned_lists(starts, n, _prints(table.column("print").combine_chunks()))
            moved = np.flatnonzero(label != np.arange(len(n)))
            if len(moved):
                yield _edge_batch(node[label[moved]], node[moved])

    return dealt.mapInArrow(run, "a long, b long")


def _alike_in_groups(members: DataFrame, texts: DataFrame, nodes: DataFrame, block_rows: int) -> DataFrame:
    """(a, b): edges between alike nodes of different roots that span what the groups (group, node, root) hold.

    In a group of several blocks the nodes of its most frequent root lie in blocks of their own, which needn't meet.
    """
    counts = members.groupBy("group", "root").agg(F.count("*").alias("n_rows"))
    top = counts.groupBy("group").agg(F.max(F.struct("n_rows", "root")).alias("top"), F.sum("n_rows").alias("all"))
    large = cut(top.where(F.col("all") > block_rows).select(
        "group", F.col("top.root").alias("major"),
        F.ceil(F.col("top.n_rows") / block_rows).cast("int").alias("first"),
        F.ceil((F.col("all") - F.col("top.n_rows")) / block_rows).cast("int").alias("others"),
    ))
    own = F.col("root") == F.col("major")
    hashed = F.xxhash64("node")
    dealt = members.join(large, "group", "left").withColumn(
        "block",
        F.when(F.col("major").isNull(), 0).when(own, F.pmod(hashed, F.col("first"))).otherwise(F.col("first") + F.pmod(hashed, F.col("others"))).cast("int"),
    )
    last = F.col("first") + F.col("others") - 1
    partner = F.when(F.col("major").isNull(), F.array(F.lit(0))).when(own, F.sequence(F.col("first"), last)).otherwise(F.sequence(F.lit(0), last))
    order = ["group", "lo", "hi"]
    spread = dealt.withColumn("other", F.explode(partner)).select("group", "node", "root", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"))
    spread = spread.join(nodes.select("node", "n", "print"), "node").join(texts, "node")
    spread = spread.select(*order, "node", "root", "n", "print", "text").repartition(*order).sortWithinPartitions(*order, "n", "node")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, starts in _whole(batches, 3, GROUPED_ROWS):
            node, n, root = (table.column(c).to_numpy() for c in ("node", "n", "root"))
            # a root names its nodes in each list by itself
            own = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(n))))
            _, first, label = np.unique(np.stack((own, root)), axis=1, return_index=True, return_inverse=True)
            label = first[label.reshape(-1)]
            raw, sets = table.column("text"), {}

            def members(i: int, raw=raw, sets=sets) -> np.ndarray:
                if i not in sets:
                    sets[i] = _packed_set(raw[i].as_py())
                return sets[i]

            after = spanned_lists(starts, n, _prints(table.column("print").combine_chunks()), label, lambda i, j: alike(members(i), members(j)))
            moved = np.flatnonzero(after != label)
            if len(moved):
                yield _edge_batch(node[after[moved]], node[moved])

    return spread.mapInArrow(run, "a long, b long")


def links(named: DataFrame, src: DataFrame, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(node, root) of every node of named that has a near copy; src (doc_id, text, hash) holds the texts."""
    names = ["key", "node", "n"]

    def start(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # the pairs of short lists, under no key, and the rows of long ones: the whole of the rows is dealt once
        known: set[int] = set()
        for rows, goes_on in _lists(batches):
            lead = rows[:2] if goes_on else rows[:0]
            in_pieces = rows[0, 0] if goes_on or (len(rows) >= SLICE and rows[0, 0] == rows[-1, 0]) else None
            rows = rows[len(lead) :][_fresh(rows[len(lead) :])]
            _, first, spot, sizes = np.unique(rows[:, 0], return_index=True, return_inverse=True, return_counts=True)
            of_long = sizes[spot] > SHORT_LIST
            if in_pieces is not None:
                of_long |= rows[:, 0] == in_pieces
            a, b = short_pairs(rows[~of_long])
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.nulls(len(a), pa.int32())], names=names)
            # a whole list goes by a name made of its nodes, so that the many keys of a group of copies give it once
            for lo, size in zip(first.tolist(), sizes.tolist(), strict=True):
                if size > SHORT_LIST and rows[lo, 0] != in_pieces:
                    name = _node(rows[lo : lo + size, 1])
                    of_long[lo : lo + size] = name not in known
                    rows[lo : lo + size, 0] = name
                    if len(known) >= SEEN_NODES:
                        known.clear()
                    known.add(name)
            cols = rows[of_long].T.copy()
            yield pa.RecordBatch.from_arrays([pa.array(cols[0]), pa.array(cols[1]), pa.array(cols[2].astype(np.int32))], names=names)

    nodes = named.groupBy("node").agg(F.min("hash").alias("hash"), F.min("n").alias("n"), F.min("print").alias("print"))
    nodes = cut(nodes)
    dealt = _postings(named).repartition("key").sortWithinPartitions("key", "node")
    first = cut(dealt.mapInArrow(start, POSTING))
    pairs = first.where("n is null").select(F.col("key").alias("a"), F.col("node").alias("b")).distinct()
    lists = first.where("n is not null").select("key", "node").distinct()
    near = cut(_near_only(pairs, nodes).union(_near_in_lists(lists, nodes, block_rows)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    groups = cut(connected_components(near, "a", "b"))
    texts = _texts(groups, nodes, src)
    found = cut(verified(near.groupBy("b").agg(F.min("a").alias("a")).select("a", "b"), texts))
    roots = cut(connected_components(found, "a", "b"))
    # groups of two are decided, and so are those that have become one component
    members = groups.withColumnRenamed("root", "group").join(roots, "node", "left").select("group", "node", F.coalesce("root", "node").alias("root"))
    members = cut(members)
    left = members.groupBy("group").agg(F.count("*").alias("size"), F.min("root").alias("one"), F.max("root").alias("other")).where("size > 2 AND one <> other")
    more = cut(_alike_in_groups(members.join(left.select("group"), "group", "left_semi"), texts, nodes, block_rows))
    return connected_components(found.union(more), "a", "b")


def keep_one(docs: DataFrame) -> DataFrame:
    """docs with one row of each component of near copies."""
    src = _hashed(docs)
    named = cut(_named(src, frequent_shingles(src, src.count())))
    found = named.join(cut(links(named, src)), "node", "left").select("doc_id", "hash", F.coalesce("root", "node").alias("root"))
    least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "hash"))
    rows = found.groupBy("root").agg(least.alias("kept")).select("kept.doc_id", "kept.hash")
    times = named.groupBy("doc_id", "hash").agg(F.count("*").alias("times"))
    chosen = cut(times.join(rows.withColumnsRenamed({"doc_id": "_kb_id", "hash": "_kb_hash"}), F.col("doc_id").eqNullSafe(F.col("_kb_id")) & (F.col("hash") == F.col("_kb_hash"))).select("_kb_id", "_kb_hash", "times"))
    own = F.xxhash64(F.coalesce(docs["text"], F.lit("")))
    own_row = lambda c: docs["doc_id"].eqNullSafe(c["_kb_id"]) & (own == c["_kb_hash"])
    once, often = chosen.where("times = 1"), chosen.where("times > 1")
    single = docs.join(once, own_row(once), "left_semi")
    if often.isEmpty():
        return single
    again = docs.join(often, own_row(often)).dropDuplicates(["_kb_id", "_kb_hash"]).select(*(docs[c] for c in docs.columns))
    return single.union(again)
