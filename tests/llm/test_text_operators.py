"""Each text operator against brute force, an exact round trip or held-out accuracy, on small tables."""

import hashlib
import random
import re
import textwrap
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from kernelblocks.llm import (
    decontamination,
    lattice,
    licensescan,
    nearcopies,
    ordinal,
    packing,
    quality,
    secretscan,
    simhash,
    tokencount,
    toxicity,
    urlfilter,
)
from kernelblocks.llm.components import connected_components
from kernelblocks.llm.queries import tokenizer_path

DOC = "doc_id long, text string"


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").persist()


@pytest.fixture(scope="module")
def labels(spark, sf):
    return spark.read.parquet(f"{sf}/labels.parquet").persist()


def local(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


# --- SimHash


def slow_fingerprint(text):
    words = text.encode().lower().split()
    grams = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) > 2 else [b" ".join(words)] if words else []
    hashes = [xxhash.xxh64_intdigest(g, seed=42) for g in grams]
    return sum((2 * sum(h >> b & 1 for h in hashes) > len(hashes)) << b for b in range(64))


def slow_components(ids, prints, radius=3):
    label = list(ids)
    moved = True
    while moved:
        moved = False
        for i in range(len(ids)):
            for j in range(len(ids)):
                if (prints[i] ^ prints[j]).bit_count() <= radius and label[j] < label[i]:
                    label[i], moved = label[j], True
    return dict(zip(ids, label, strict=True))


def test_simhash_fingerprints_and_components(spark, docs):
    got = local(simhash.near_duplicates(docs))
    rows = docs.select("doc_id", "text").collect()
    prints = [slow_fingerprint(r["text"] or "") for r in rows]
    want = slow_components([r["doc_id"] for r in rows], prints)
    for r, p in zip(rows, prints, strict=True):
        assert got[r["doc_id"]]["fingerprint"] == f"{p:016x}" and got[r["doc_id"]]["component_id"] == want[r["doc_id"]]


def test_simhash_bit_sliced_comparison_loses_no_link():
    r = random.Random(4)
    prints = set()
    for _ in range(150):
        base = r.getrandbits(64)
        for _ in range(r.randint(1, 9)):
            p = base
            for _ in range(r.randint(0, 5)):
                p ^= 1 << r.randrange(64)
            prints.add(p)
    fps = np.array(sorted(prints), np.uint64)
    a, b = simhash.bucket_links(np.zeros((len(fps), 2), np.int64), fps)
    root = {int(p): int(p) for p in fps} | {int(y): int(x) for x, y in zip(a, b, strict=True)}
    want = slow_components([int(p) for p in fps], [int(p) for p in fps])
    assert root == want
    # pairs that differ in three bits share one of the keys at least
    masks = simhash.key_masks()
    for _ in range(500):
        p = r.getrandbits(64)
        q = p ^ sum(1 << k for k in r.sample(range(64), 3))
        assert any(p & m == q & m for m in masks)
    assert len(masks) == 20


def test_simhash_edges(spark):
    rows = [(5, None), (4, ""), (3, " \t"), (2, "One Two"), (1, "one two"), (9, "x"), (9, "x"), (7, "é É " * 5000)]
    got = simhash.near_duplicates(spark.createDataFrame(rows, DOC)).collect()
    by = {r["doc_id"]: r for r in got}
    assert len(got) == 8 and by[5]["fingerprint"] == "0" * 16 and by[5]["component_id"] == 3 == by[4]["component_id"]
    assert by[2]["component_id"] == 1 == by[1]["component_id"] and by[9]["component_id"] == 9
    assert simhash.near_duplicates(spark.createDataFrame([], DOC)).count() == 0


def test_near_copies_edges(spark):
    rows = [(5, None), (4, ""), (3, " \t"), (2, "One Two"), (1, "one two"), (9, "x"), (9, "x"), (7, "é É " * 5000)]
    src = spark.createDataFrame(rows, DOC).withColumn("fp", F.lit(1)).withColumn("root", F.lit(2)).withColumn("hash", F.lit("a"))
    kept = nearcopies.keep_one(src)
    assert sorted(r["doc_id"] for r in kept.collect()) == [1, 3, 7, 9] and kept.columns == src.columns
    # unlike texts of one id stay, copies without an id are one, and an id comes before none
    rows = [(1, "a b c"), (1, "d e f"), (None, "u v w"), (None, "u v w"), (None, "d e f"), (None, "y z")]
    kept = nearcopies.keep_one(spark.createDataFrame(rows, DOC)).collect()
    assert sorted((r["doc_id"] or 0, r["text"]) for r in kept) == [(0, "u v w"), (0, "y z"), (1, "a b c"), (1, "d e f")]
    assert nearcopies.keep_one(spark.createDataFrame([], DOC)).count() == 0


def test_wide_radius_and_split_buckets(spark):
    rng = np.random.default_rng(6)
    base = rng.integers(0, 2**64, 5, dtype=np.uint64)
    fps = np.array([int(base[k % 5]) ^ sum(1 << int(b) for b in set(rng.integers(0, 64, k % 40))) for k in range(700)], np.uint64)
    planes = simhash.bit_planes(fps)
    for radius in (0, 1, 2, 3, 7, 8, 26, 40):
        for shift in (1, 5, 64, 333):
            alive = np.arange(700) + shift < 700
            got = simhash.near_lanes(planes, shift, alive, radius).tolist()
            assert got == [i for i in range(700 - shift) if int(fps[i] ^ fps[i + shift]).bit_count() <= radius]
    wide = rng.integers(0, 2**64, (300, 4), dtype=np.uint64)
    wide[150:] = wide[:150] ^ (rng.random((150, 4, 64)) < 0.3).dot(1 << np.arange(64, dtype=object)).astype(np.uint64)
    planes = simhash.bit_planes(wide)
    for radius in (60, 84, 128):
        got = simhash.near_lanes(planes, 150, np.arange(300) < 150, radius).tolist()
        assert got == [i for i in range(150) if int(np.bitwise_count(wide[i] ^ wide[i + 150]).sum()) <= radius]
    few = np.unique(np.array([int(base[0]) ^ (1 << int(a)) ^ (1 << int(b)) for a, b in rng.integers(0, 20, (300, 2))], np.uint64))
    prints = spark.createDataFrame([(int(f),) for f in few.view(np.int64)], "fp long")
    names = few.view(np.int64).tolist()
    want = slow_components(names, few.tolist())
    for size in (7, 8192):
        got = {r["node"]: r["root"] for r in connected_components(simhash.links(prints, block_rows=size), "a", "b").collect()}
        assert {n: got.get(n, n) for n in names} == want


def test_wide_fingerprints_of_alike_sets_lie_within_the_radius():
    rng = np.random.default_rng(7)
    for n in (5, 9, 20, 100, 500):
        for _ in range(60):
            h = rng.integers(0, 2**64, n + n // 4 + 1, dtype=np.uint64)
            rest = n - -(-4 * n // 5)  # as many as may differ
            one, two = simhash.wide_print(h[: n - rest]), simhash.wide_print(h[:n])
            assert int(np.bitwise_count(one ^ two).sum()) <= nearcopies.RADIUS
            assert one[0] == np.packbits(2 * simhash._ones(h[: n - rest], np.zeros(1, np.int64))[0] > n - rest, bitorder="little").view(np.uint64)[0]


def test_near_copies_of_large_groups_are_found_in_pieces(spark, monkeypatch):
    rng = random.Random(9)
    words = [f"w{k}" for k in range(90)]
    texts = [" ".join([*words[:44], f"z{k}", *words[45:]]) for k in range(60)]  # one group
    texts += [" ".join(words[:30] + [f"y{rng.randrange(10**6)}" for _ in range(60)]) for _ in range(40)]  # a shared passage, no copies
    monkeypatch.setattr(nearcopies, "FREQUENT", 10**6)  # the passage stays in the keys
    monkeypatch.setattr(nearcopies, "SLICE", 64)  # lists come in pieces
    rows = [r for rows, _ in [next(nearcopies._lists(iter([pa.record_batch([pa.array([7] * 100), pa.array(range(100))], names=["k", "n"])])))] for r in rows]
    assert len(rows) == 100
    sets = [set(nearcopies.shingle_set(t).tolist()) for t in texts]
    label = slow_groups(sets)
    src = nearcopies._hashed(spark.createDataFrame(list(enumerate(texts)), DOC))
    named = nearcopies._named(src).persist()
    roots = {r["node"]: r["root"] for r in nearcopies.links(named, src, block_rows=8).collect()}
    nodes = {r["doc_id"]: r["node"] for r in named.collect()}
    found = [roots.get(nodes[k], nodes[k]) for k in range(len(texts))]
    assert [found.index(f) for f in found] == label


def test_many_lists_are_compared_at_once(monkeypatch):
    rng = np.random.default_rng(3)
    sizes = rng.choice([1, 2, 9, 12, 30, 70], size=800)
    starts, n = np.concatenate(([0], np.cumsum(sizes)[:-1])), []
    bits = np.zeros((int(sizes.sum()), 256), np.uint8)
    for at, k in zip(starts, sizes, strict=True):
        base = rng.integers(0, 2, (max(1, k // 4), 256), dtype=np.uint8)
        bits[at : at + k] = base[rng.integers(0, len(base), k)] ^ (rng.random((k, 256)) < rng.choice([0.1, 0.16, 0.2]))
        n.append(np.sort(rng.integers(20, 60, k)))
    n, prints = np.concatenate(n).astype(np.int32), np.packbits(bits, axis=1).view(np.uint64)
    want, odd = np.arange(len(n)), np.arange(len(n))
    for at, k in zip(starts, sizes, strict=True):
        for i in range(at, at + k):
            js = np.arange(i + 1, at + k)
            js = js[(4 * n[js] <= 5 * n[i]) & (np.bitwise_count(prints[js] ^ prints[i]).sum(axis=1) <= nearcopies.RADIUS)]
            want = nearcopies._merge(want, np.full(len(js), i), js)
            js = js[(js + i) % 2 == 1]
            odd = nearcopies._merge(odd, np.full(len(js), i), js)
    calls = []
    slow = nearcopies.near_places
    monkeypatch.setattr(nearcopies, "near_places", lambda *a: calls.append(1) or slow(*a))
    assert np.array_equal(nearcopies.spanned_lists(starts, n, prints), want)
    assert len(calls) < 70  # a call for a distance, not for each list and distance
    asked = lambda i, j: (i + j) % 2 == 1
    assert np.array_equal(nearcopies.spanned_lists(starts, n, prints, None, asked), odd)


def test_lists_of_the_same_nodes_are_compared_once(spark, monkeypatch):
    words = [f"w{k}" for k in range(90)]
    texts = [" ".join([*words[:44], f"z{k}", *words[45:]]) for k in range(30)]
    monkeypatch.setattr(nearcopies, "FREQUENT", 10**6)
    seen = []
    slow = nearcopies._near_in_lists
    monkeypatch.setattr(nearcopies, "_near_in_lists", lambda rows, *a: seen.append(rows.count()) or slow(rows, *a))
    kept = nearcopies.keep_one(spark.createDataFrame(list(enumerate(texts)), DOC).repartition(3))
    assert [r["doc_id"] for r in kept.collect()] == [0]
    assert seen and seen[0] <= 4 * len(texts)  # the group's keys are many more


def slow_groups(sets):
    """For each set the place of the first that it reaches by steps of Jaccard 0.8 or more."""
    near = [[j for j, b in enumerate(sets) if a == b or len(a & b) >= 0.8 * len(a | b)] for a in sets]
    label, moved = list(range(len(sets))), True
    while moved:
        new = [min(label[j] for j in row) for row in near]
        moved, label = new != label, new
    return label


def test_near_copies_lose_no_pair_of_jaccard_above_the_bound(spark, monkeypatch):
    monkeypatch.setattr(nearcopies, "FREQUENT", 3)
    rng = random.Random(4)
    common = " ".join(f"c{k}" for k in range(30))
    texts = []
    for g in range(12):
        words = [f"w{rng.randrange(4000)}" for _ in range(rng.choice((20, 120, 400)))] + (common.split() if g % 3 == 0 else [])
        for _ in range(14 if g == 0 else 6):
            own = list(words)
            for _ in range(rng.randrange(1 + len(own) // 40)):
                own[rng.randrange(len(own))] = f"x{rng.randrange(10**6)}"
            texts.append(" ".join(own))
    texts += ["", None, "one two", "One  Two"] + [common + f" t{k}" for k in range(12)]
    label = slow_groups([set(nearcopies.shingle_set(t).tolist()) for t in texts])
    kept = nearcopies.keep_one(spark.createDataFrame(list(enumerate(texts)), DOC).repartition(5))
    assert sorted(r["doc_id"] for r in kept.collect()) == [i for i, k in enumerate(label) if i == k]


# --- secrets

ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")


def slow_base(text):
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[1]) >= 6]
    out += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    out += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return [(secretscan.KINDS[k], a, b) for a, k, b in sorted(out)]


SECRETS = [
    "token=ab token=abcdef password:token:abcdef",
    "é😀 secret: \"Zk3v9Qp1Lx7RtY2w\" AKIA" + "A" * 16 + " AKIA1",
    "deadbeef" * 3 + "x" + "a" * 24,
    "API_KEY = 'abc.def-ghi' apikey:zz PASSWORD==x",
    "key mF3k9QzX7bLw2TnV5cRy8PdJ1hGs6A and getUserAccountByNumberAndName ------------------------------",
    "",
    None,
    "AKIAAKIAAKIA" + "Z9" * 8,
    "secret=" + "x" * 5 + " secret=" + "y" * 6,
]


def test_secret_spans_equal_the_patterns(spark, docs):
    extra = spark.createDataFrame([(10_000 + k, t) for k, t in enumerate(SECRETS)], DOC)
    src = docs.select("doc_id", "text").union(extra)
    got = local(secretscan.secrets(src))
    for r in src.collect():
        base = slow_base(r["text"] or "")
        row = got[r["doc_id"]]
        said = ",".join(f"{k}:{a}:{b}" for k, a, b in base)
        assert row["base_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert [row["n_assign"], row["n_access"], row["n_hex"]] == [sum(x[0] == k for x in base) for k in secretscan.KINDS[:3]]
        spans = [s for s in row["spans"].split(",") if s]
        assert [s for s in spans if not s.startswith("markov")] == [s for s in said.split(",") if s]
    added = got[10_004]["spans"]
    assert added == "markov:4:34"


def slow_added(text, ratios):
    """The models' spans by plain loops over the text."""
    place, n = {c: i for i, c in enumerate(secretscan.SIGNS)}, len(secretscan.SIGNS) + 1
    spans = []
    for m in re.finditer(secretscan.CANDIDATE, text):
        run, at = m[0], m.start()
        steps = [ratios[place[a] * n + place[b]] for a, b in zip(run, run[1:], strict=False)]
        if len(run) >= secretscan.WHOLE_LENGTH and sum(steps) >= max(secretscan.LEAST_TOTAL, secretscan.LEAST_MEAN * len(run)):
            spans.append((at, at + len(run)))
            continue
        total = peak = begin = stop = 0
        for k, step in enumerate([*steps, -10**6]):
            if total <= 0:
                total, begin = 0, k
            total += step
            if total > peak:
                peak, stop = total, k + 2
            if total <= 0 or peak - total >= secretscan.LEAST_DROP:
                part = run[begin:stop]
                mixed = re.search("[0-9].*[A-Za-z]|[A-Za-z].*[0-9]|[a-z].*[A-Z]", part)
                dense = len(part) >= secretscan.WHOLE_LENGTH and sum(steps[begin : stop - 1]) >= secretscan.LEAST_MEAN * len(part)
                if peak >= secretscan.LEAST_TOTAL and (mixed or dense):
                    left = begin - len(re.search("[A-Za-z0-9+]*$", run[:begin])[0])
                    spans.append((at + left, at + stop + len(re.match("[A-Za-z0-9+]*", run[stop:])[0])))
                total = peak = 0
    met = []
    for a, b in spans:
        if met and a <= met[-1][1]:
            met[-1][1] = max(met[-1][1], b)
        else:
            met.append([a, b])
    return [(a, b) for a, b in met if not any(x < b and a < y for _, x, y in slow_base(text))]


def test_added_spans_equal_plain_loops(spark, docs):
    rng = random.Random(3)
    signs = secretscan.SIGNS
    texts = []
    for _ in range(150):
        parts = []
        for _ in range(rng.randrange(1, 40)):
            kind = rng.randrange(7)
            size = rng.choice((8, 12, 20, 30, 60, 700))
            parts.append(
                rng.choice(secretscan.IDENTIFIER_WORDS) if kind < 2 else "".join(rng.choice(signs) for _ in range(size)) if kind < 4
                else "".join(rng.choice("0123456789abcdef") for _ in range(size)) if kind == 4 else "x" * size if kind == 5 else "token"
            )
        texts.append("".join(p + rng.choice((" ", "/", "_", "\n", ", ", "é ", "=", ": ", '"')) for p in parts))
    texts.append(" ".join(texts))  # longer than a part
    texts.append("ü" * 9000 + texts[0] + "日本" * 5000 + texts[1])
    src = spark.createDataFrame(list(enumerate(texts)), DOC)
    ratios = secretscan.train(secretscan.sample_strings())
    got = local(secretscan.secrets(src))
    assert any(slow_added(t, ratios) for t in texts)
    for k, t in enumerate(texts):
        said = [s for s in got[k]["spans"].split(",") if s.startswith("markov")]
        assert said == [f"markov:{a}:{b}" for a, b in slow_added(t, ratios)]
        assert got[k]["n_markov"] == len(said)
        base = ",".join(f"{n}:{a}:{b}" for n, a, b in slow_base(t))
        assert got[k]["base_sha256"] == hashlib.sha256(base.encode()).hexdigest()


def test_secrets_of_very_long_texts_take_time_in_proportion(spark):
    rng = random.Random(4)

    def seconds(text, mask=False):
        src = spark.createDataFrame([(1, text)], DOC)
        began = time.perf_counter()
        row = (secretscan.masked(src) if mask else secretscan.secrets(src)).first()
        return time.perf_counter() - began, row

    def hexes(n, sep):
        return sep.join(f"{rng.getrandbits(96):024x}" for _ in range(n))

    seconds("warm up")
    for sep in (" ", "-"):
        for mask in (False, True):
            one, _ = seconds(hexes(15_000, sep), mask)
            two, row = seconds(hexes(30_000, sep), mask)
            assert two < 3 * one + 2
        assert set(row["text"].split(secretscan.MASK)) == {"", sep}
    blob = "".join(rng.choice(secretscan.SIGNS[:62]) for _ in range(1_000_000))
    sec, row = seconds(blob)
    assert row["spans"] == "markov:0:1000000" and sec < 30
    for c in " \na\u3000":
        assert seconds(c * 1_000_000)[0] < 30


def test_secrets_of_repeated_and_clashing_rows(spark):
    rows = [(1, SECRETS[1], 3, "x")] * 3 + [(None, SECRETS[1], None, None)]
    src = spark.createDataFrame(rows, "doc_id long, text string, n_hex int, kind string")
    got = secretscan.secrets(src).collect()
    assert len(got) == 4 and len({r["spans"] for r in got}) == 1
    assert [r["n_hex"] for r in secretscan.masked(src).collect()] == [3, 3, 3, None]


def test_markov_models_part_random_from_ordinary():
    ratios, place = secretscan.train(secretscan.sample_strings()), {c: i for i, c in enumerate(secretscan.SIGNS)}
    n, r = len(secretscan.SIGNS) + 1, random.Random(8)

    def mean(s):
        return sum(ratios[place[a] * n + place[b]] for a, b in zip(s, s[1:], strict=False)) / len(s)

    held = ["".join(r.choice(secretscan.SIGNS[:62]) for _ in range(40)) for _ in range(200)]
    assert np.mean([mean(s) >= secretscan.LEAST_MEAN for s in held]) > 0.95
    for s in ("compute_next_buffer_offset", "internationalization", "ApplicationContextFactoryBean", "-" * 40, "x" * 30):
        assert mean(s) < secretscan.LEAST_MEAN


def test_random_parts_of_paths_and_short_keys_are_found(spark):
    rng = random.Random(5)
    words = [w for w in secretscan.IDENTIFIER_WORDS if len(w) > 3]
    rows, keys = [], []
    for n in (16, 24, 32):
        for before in range(5):
            for _ in range(20):
                key = "".join(rng.choice(secretscan.SIGNS[:62]) for _ in range(n))
                path = "/".join(rng.choice(words) for _ in range(before))
                rows.append((len(rows), f"see /{path}/{key}/{rng.choice(words)} there"))
                keys.append(key)
    plain = [(-1 - k, "see " + "/_-"[k % 3].join(rng.choice(words) for _ in range(7))) for k in range(300)]
    numbers = [(-1000, "numbers 4610568901970798 and 20240131 and understanding ofrehehely")]
    got = local(secretscan.masked(spark.createDataFrame(rows + plain + numbers, DOC)))
    assert sum(keys[i] not in got[i]["text"] for i in range(len(keys))) >= 0.98 * len(keys)
    assert all(got[i]["text"] == t for i, t in plain + numbers)


def test_secrets_stay_native_and_mask(spark):
    src = spark.createDataFrame([(1, SECRETS[1], "kept", 7), (2, "plain", "kept", 5), (3, None, None, None)], "doc_id long, text string, spans string, n_chars long")
    out = secretscan.masked(src)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
    got = local(out)
    assert got[1]["text"] == "é😀 [SECRET]\" [SECRET] AKIA1" and got[1]["n_chars"] == len(got[1]["text"]) and got[1]["spans"] == "kept"
    assert got[2]["text"] == "plain" and got[3]["text"] is None and out.columns == src.columns
    assert secretscan.secrets(src.limit(0)).count() == 0


# --- licences


def test_licences_are_found_and_others_left(spark, docs):
    samples = licensescan.built_in_samples()
    held = [("This code is licensed under the Apache License, Version 2.0, as stated.", "Apache-2.0"), ("All of it is released under the MIT License today.", "MIT"), ("This book is licensed under CC BY-NC 4.0.", "CC-BY-NC")]
    rows = [(k, f"first line\n{t}\nlast") for k, (t, _) in enumerate(held)] + [(10, "He lost his fishing licence.\nMIT!! MIT!!"), (11, None), (12, ""), (13, "\n\n")]
    found = licensescan.licences(spark.createDataFrame(rows, DOC))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan
    got = local(found)
    assert {k: got[k]["family"] for k in got} == {k: n for k, (_, n) in enumerate(held)}
    for k, (t, _) in enumerate(held):
        assert rows[k][1][got[k]["start"] : got[k]["stop"]] == t and got[k]["paragraph"] == 1
    want = {r["doc_id"] for r in docs.where("text rlike 'Licen[cs]ed under|Released under the MIT|General Public License'").collect()}
    assert {r["doc_id"] for r in licensescan.licences(docs).collect()} == want
    model = licensescan.LicenceModel([s for k, s in enumerate(samples) if k % 3])
    spot = {g: i for i, g in enumerate(model.vocabulary)}
    hits = 0
    test = [s for k, s in enumerate(samples) if k % 3 == 0]
    for text, name in test:
        z = model.bias.copy()
        for g in licensescan.grams(text):
            if g in spot:
                z += model.weights[spot[g]]
        hits += model.classes[int(np.argmax(z))] == name
    assert hits / len(test) > 0.9


def test_wrapped_notices_are_found(spark):
    notices = {
        "GPL": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
        "BSD": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
        "Apache-2.0": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.',
        "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction",
    }
    rows, want = [], []
    for width in (36, 72):
        for mark in ("", "# "):
            for head in ("Some words on what it does.\nMore of them here.\n", "Some words.\n \n"):
                for name, text in notices.items():
                    body = "\n".join(mark + line for line in textwrap.wrap(text, width))
                    rows.append((len(rows), f"{head}{body}\nimport of other things\nand the end of it"))
                    want.append(name)
    got = licensescan.licences(spark.createDataFrame(rows, DOC)).collect()
    for i, name in enumerate(want):
        own = [r for r in got if r["doc_id"] == i]
        assert own and {r["family"] for r in own} == {name}, (rows[i], own)
        assert all(r["confirmed"] and r["share"] >= 0.6 and rows[i][1][r["start"] : r["stop"]].strip() for r in own)
    twice = [(1, rows[0][1]), (1, rows[0][1])]
    assert len(licensescan.licences(spark.createDataFrame(twice, DOC)).collect()) == 2 * sum(r["doc_id"] == 0 for r in got)


def slow_findings(text, model):
    """Every run of lines judged by itself, and the best kept one after the other."""
    lines, at, out = text.split("\n"), 0, []
    starts = []
    for x in lines:
        starts.append(at)
        at += len(x) + 1
    spot = {g: i for i, g in enumerate(model.vocabulary)}
    for i in range(len(lines)):
        for size in range(1, licensescan.WINDOW_LINES + 1):
            part = lines[i : i + size]
            body = " ".join(part)
            if len(part) < size or any(not x.strip() for x in part) or not re.search(licensescan.CUES, body):
                continue
            own = licensescan.grams(body)
            z = (model.bias + sum(model.weights[spot[g]] for g in own if g in spot)) / model.temperature
            top = int(np.argmax(z))
            p = 1 / np.exp(z - z[top]).sum()
            if top == len(model.classes) - 1 or p < licensescan.LEAST_PROBABILITY:
                continue
            share = 0.0
            for t in licensescan.TEMPLATES[model.classes[top]]:
                pairs = [g for g in licensescan.grams(t) if " " in g] or licensescan.grams(t)
                share = max(share, len(set(pairs) & set(own)) / len(pairs))
            if share >= licensescan.LEAST_SHARE:
                out.append((-share, size, i, starts[i], starts[i + size - 1] + len(part[-1]), model.classes[top], round(float(p), 6)))
    kept = []
    for f in sorted(out):
        if all(f[4] <= k[3] or k[4] <= f[3] for k in kept):
            kept.append(f)
    return sorted((f[2], f[3], f[4], f[5], f[6], round(-f[0], 9)) for f in kept)


def test_findings_equal_a_judgement_of_every_run_of_lines(spark, docs):
    rng = random.Random(21)
    notices = [t for texts in (*licensescan.TEMPLATES.values(), *licensescan.NOTICES.values(), licensescan.UNLICENSED) for t in texts]
    texts = [r["text"] for r in docs.where("text rlike '(?i)licen|copyright|permission'").limit(60).collect()]
    for _ in range(60):
        parts = []
        for _ in range(rng.randrange(1, 9)):
            t = rng.choice(notices)
            parts.append("\n".join(textwrap.wrap(t, rng.choice((24, 40, 72, 500)))) if rng.random() < 0.8 else rng.choice(("", " ", "plain words here", "in the public\n# domain", "cc\nby 4.0")))
        texts.append("\n".join(parts))
    model = licensescan.LicenceModel(licensescan.built_in_samples())
    assert licensescan.LicenceModel.TEMPERATURES[0] < model.temperature < licensescan.LicenceModel.TEMPERATURES[-1]
    assert model.held_out_accuracy > 0.5 and 0 < model.held_out_unknown < 0.6  # whole notices unseen
    columns = "paragraph", "start", "stop", "family", "probability", "share"
    got = {}
    clash = spark.createDataFrame(list(enumerate(texts)), DOC).withColumn("body", F.lit("x")).withColumn("row", F.lit(1)).withColumn("share", F.lit(1))
    for r in licensescan.licences(clash).collect():
        got.setdefault(r["doc_id"], []).append((*(r[c] for c in columns[:4]), round(r["probability"], 6), round(r["share"], 9)))
    for k, t in enumerate(texts):
        assert sorted(got.get(k, [])) == slow_findings(t, model), t
    assert sum(map(len, got.values())) > 60


def test_licences_of_long_texts_of_new_families_and_of_none(spark, monkeypatch):
    text = "\n".join(f"line {i} is licensed under the MIT License of {i * 7919 % 1000}" for i in range(12_000))
    src = spark.createDataFrame([(1, text), (2, "Licensed under the MIT license."), (2, "Licensed under the MIT license.")], DOC)
    began = time.perf_counter()
    assert licensescan.licences(src).count() == 12_002 and time.perf_counter() - began < 120
    assert licensescan.licences(src.limit(0)).count() == 0
    monkeypatch.setattr(licensescan, "BROADCAST_BYTES", 0)  # the salted join
    assert licensescan.licences(src.where("doc_id = 2")).count() == 2
    own = "Covered by the Quux Community License, second edition."
    samples = [*licensescan.built_in_samples(), *((f"{a}{own}{b}", "QUUX") for a, b in licensescan.DRESSING)]
    got = licensescan.licences(spark.createDataFrame([(1, f"head\n{own}\nend")], DOC), samples).collect()
    assert [(r["family"], r["paragraph"]) for r in got] == [("QUUX", 1)]
    with pytest.raises(ValueError, match="no cue"):
        licensescan.licences(src, [("Gratis for all.", "FREE"), ("Something else.", licensescan.UNKNOWN)])


def test_licence_findings_meet_their_lines_without_the_texts(spark, monkeypatch):
    kinds = ("Licensed under the MIT license.", "Released under the GPL version 2 or later.", "Read the permission slip.", "Licensed under CC BY 4.0.\nnext line")
    src = spark.createDataFrame([(k, f"line {k // 7}\n{kinds[k % 4]}") for k in range(80)], DOC)
    want = sorted(licensescan.licences(src).collect())
    assert len(want) == 40
    monkeypatch.setattr(licensescan, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(licensescan, "HOT_ROWS", 15)  # paragraphs with a place in 20 texts are salted, joined ones of two lines aren't
    found = licensescan.licences(src)
    joins = [line for line in found._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join Inner" in line]
    assert joins and not any("body" in line for line in joins)
    assert sorted(found.collect()) == want


# --- packing


def test_packing_is_an_exact_cover_with_little_padding(spark, docs):
    from tokenizers import Tokenizer

    path = tokenizer_path()
    extra = spark.createDataFrame([(20_000, None), (20_001, ""), (20_002, "a <|endoftext|> b"), (20_003, "word " * 6000), (20_003, "x")], DOC)
    src = docs.select("doc_id", "text").where("doc_id <> 3").union(extra).repartition(3)
    rows = packing.pack(src, path).collect()
    exact = Tokenizer.from_file(path)
    texts = [(r["doc_id"], r["text"] or "") for r in src.collect() if r["doc_id"] != 20_003]
    by = {}
    for r in rows:
        by.setdefault(r["doc_id"], []).append(r)
    for doc_id, text in texts:
        ids = exact.encode(text, add_special_tokens=False).ids + [0]
        at = 0
        for p in sorted(by[doc_id], key=lambda r: r["start"]):
            raw = np.array(ids[p["start"] : p["start"] + p["length"]], "<u4").tobytes()
            assert p["start"] == at and p["ids_crc32"] == zlib.crc32(raw) and p["doc_tokens"] == len(ids)
            at += p["length"]
        assert at == len(ids)
    sequences = {}
    for r in rows:
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    padded = total = 0
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 1024
        padded, total = padded + packing.padding(at), total + at
    assert padded < 0.04 * total
    assert packing.pack(src.limit(0), path).count() == 0


def test_very_long_white_space_is_packed(spark):
    from tokenizers import Tokenizer

    exact = Tokenizer.from_file(tokenizer_path())
    texts = [" " * 2_000_000 + "x", "a" + "\n" * 1_200_000 + "x", "a b " * 30_000]
    got = packing.pack(spark.createDataFrame(list(enumerate(texts)), DOC), tokenizer_path()).collect()
    for i, text in enumerate(texts):
        assert sum(r["length"] for r in got if r["doc_id"] == i) == len(exact.encode(text).ids) + 1


@pytest.mark.parametrize("width", [1, 3, 16, 128, 200, 1000, 4096])
def test_packing_at_any_width(spark, width):
    texts = ["word " * 900, None, "x" * 3000, "One. Two. Three."]
    got = packing.pack(spark.createDataFrame(list(enumerate(texts)), DOC).coalesce(1), tokenizer_path(), width).collect()
    ids, *_ = packing.encoder(tokenizer_path())
    size: dict[int, int] = {}
    for r in got:
        size[r["sequence_id"]] = size.get(r["sequence_id"], 0) + r["length"]
    assert max(size.values()) <= width
    for k, t in enumerate(texts):
        pieces = sorted((r["start"], r["length"]) for r in got if r["doc_id"] == k)
        assert [a for a, _ in pieces] == [sum(n for _, n in pieces[:i]) for i in range(len(pieces))]
        assert sum(n for _, n in pieces) == len(ids(t or "")) + 1


def test_cuts_are_the_best_ones():
    r = random.Random(2)
    for _ in range(40):
        places = np.array(sorted({0, *(r.randrange(1, 60) for _ in range(14)), 60}))
        places = np.array([p for k, p in enumerate(places)])
        costs = np.array([r.choice([0.0, 2.0, 5.0]) for _ in places])
        costs[0] = costs[-1] = 0.0
        if np.diff(places).max() > 16:
            continue
        best = {0: 0.0}
        for j in range(1, len(places)):
            best[j] = min(best[i] + cost(places[j] - places[i]) for i in range(j) if places[j] - places[i] <= 16) + costs[j]
        cuts = packing.plan(places, costs, 16)
        got = sum(cost(places[b] - places[a]) + costs[b] for a, b in zip(cuts, cuts[1:], strict=False))
        assert got == best[len(places) - 1]


def cost(n):
    # the plan looks for unpadded windows of 2 ids or more (an eighth of the width)
    return 0 if n & (n - 1) == 0 and n >= 2 else 16 - n


# --- token counts


def test_automaton_counts_greedy_pieces(spark, docs):
    openings, continuations = tokencount.word_pieces(tokenizer_path())
    counter = tokencount.PieceCounter(openings, continuations)
    one, two = set(openings), set(continuations)

    def slow(word):
        at, n = 0, 0
        while at < len(word):
            end = next((e for e in range(len(word), at, -1) if word[at:e] in (two if at else one)), None)
            if end is None:
                return tokencount.UNKNOWN
            at, n = end, n + 1
        return n

    words = {w for r in docs.collect() for w in tokencount.WORD.findall(r["text"] or "")} | {"😀", "ñandú", "aaaaaaaa", "x" * 300}
    assert all(counter.count(w) == slow(w) for w in words)
    got = local(tokencount.token_counts(docs.select("doc_id", "text").union(spark.createDataFrame([(30_000, None), (30_001, "")], DOC)), counter))
    assert got[30_000]["n_tokens"] == 0 == got[30_001]["n_words"]
    r = docs.first()
    counts = [slow(w) for w in tokencount.WORD.findall(r["text"])]
    assert got[r["doc_id"]]["n_tokens"] == sum(max(c, 1) for c in counts)


def test_automaton_on_small_vocabularies():
    r = random.Random(1)
    for _ in range(60):
        one = {"".join(r.choice("ab") for _ in range(r.randint(1, 4))) for _ in range(6)}
        two = {"".join(r.choice("ab") for _ in range(r.randint(1, 4))) for _ in range(6)}
        counter = tokencount.PieceCounter(one, two)
        for _ in range(60):
            w = "".join(r.choice("ab") for _ in range(r.randint(1, 12)))
            at, n = 0, 0
            while at < len(w):
                end = next((e for e in range(len(w), at, -1) if w[at:e] in (two if at else one)), None)
                if end is None:
                    n = -1
                    break
                at, n = end, n + 1
            assert counter.count(w) == n


# --- graded classifiers


def test_ordinal_gradient_and_order():
    r = np.random.default_rng(5)
    rows = [(r.choice(12, 4, replace=False), r.standard_normal(4)) for _ in range(300)]
    x = ordinal.Rows.of(rows, 12)
    truth = r.standard_normal(12)
    s = x.dot(truth) * 2 + r.logistic(size=300)
    y = np.digitize(s, [-1.0, 1.5])
    p = r.standard_normal(14) * 0.3
    value, grad = ordinal.loss_and_gradient(p, x, y, 3, 1e-3)
    for k in range(14):
        step = np.zeros(14)
        step[k] = 1e-6
        up, down = (ordinal.loss_and_gradient(p + z, x, y, 3, 1e-3)[0] for z in (step, -step))
        assert abs((up - down) / 2e-6 - grad[k]) < 1e-6
    model = ordinal.fit(x, y, 3, 1e-3)
    assert model.thresholds[0] < model.thresholds[1]
    assert np.corrcoef(model.weights, truth)[0, 1] > 0.9
    tails = model.tails(np.array([0.3, -2.0]))
    assert (tails[:, 0] >= tails[:, 1]).all() and np.allclose(model.expected(np.array([0.3, -2.0])), tails.sum(1))
    assert ordinal.fit(ordinal.Rows.of([], 3), np.zeros(0, int), 3).weights.tolist() == [0, 0, 0]


@pytest.fixture(scope="module")
def larger(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")


def test_quality_on_held_out_rows(spark, larger):
    docs, labels = larger
    held = labels.where("doc_id % 3 = 0")
    model = quality.train(docs, labels.where("doc_id % 3 <> 0"))
    got = quality.graded(docs, model).join(held, "doc_id").collect()
    assert np.mean([r["keep"] == (r["quality"] == 1) for r in got]) > 0.95
    assert np.mean([r["keep"] for r in got if r["quality"] == 1]) > 0.98
    assert all(0 <= r["expected_grade"] <= 2 for r in got)


def test_toxicity_on_held_out_rows(spark, larger):
    docs, labels = larger
    model = toxicity.train(docs, labels.where("doc_id % 3 <> 0"))
    held = labels.where("doc_id % 3 = 0").select("doc_id", F.col("toxic").alias("label"))
    got = toxicity.severity(docs, model).join(held, "doc_id").collect()
    assert np.mean([r["toxic"] == (r["label"] == 1) for r in got]) > 0.93
    clean = [r["expected_severity"] for r in got if not r["label"]]
    assert np.mean(clean) < 0.2 < np.mean([r["expected_severity"] for r in got if r["label"]])


def test_classifiers_on_edges(spark):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    src = spark.createDataFrame([(1, None), (2, ""), (3, "fine words here"), (3, "fine words here")], DOC)
    assert quality.train(src, none) is None and toxicity.train(src, none) is None
    got = quality.graded(src, None).collect()
    assert [r["keep"] for r in sorted(got, key=lambda r: r["doc_id"])] == [False, False, True, True]
    assert not any(r["toxic"] for r in toxicity.severity(src, None).collect())
    wide = src.withColumn("keep", F.lit("a")).withColumn("expected_grade", F.lit(1))
    kept = quality.select_good(wide, None)
    assert kept.columns == wide.columns and kept.count() == 2
    one = spark.createDataFrame([(3, 1, 0), (3, 1, 0), (None, 0, 0), (1, None, None)], "doc_id long, quality int, toxic int")
    model = quality.train(src, one)
    assert quality.graded(src, model).count() == 4
    assert toxicity.severity(src, toxicity.train(src, one)).where("toxic").count() == 0


# --- decontamination

ITEM = "A train leaves Boston at 9 with 120 passengers and travels 60 km before Maria boards with 15 bags of rice"
OTHER = "a train leaves Denver at 7 with 340 passengers and travels 85 km before Pedro boards with 22 bags of rice"


def test_reparameterised_items_are_caught(spark):
    bench = spark.createDataFrame([(1, ITEM), (2, None), (3, "two words"), (4, "9 10 11 12 13 14")], "item_id long, text string")
    rows = [
        (1, f"Some text before. {ITEM}. And after."),
        (2, f"Some text before. {OTHER}. And after."),
        (3, "A train leaves at noon and nobody boards."),
        (4, None),
        (5, ""),
        (6, "word " * 20_000 + OTHER + " word" * 20_000),
        (7, ITEM),
        (7, ITEM),
        (8, "it holds two words"),
    ]
    got = decontamination.contaminated(spark.createDataFrame(rows, DOC), bench).collect()
    found = sorted((r["doc_id"], r["item_id"], r["verbatim"]) for r in got)
    assert found == [(1, 1, True), (2, 1, False), (6, 1, False), (7, 1, True), (7, 1, True), (8, 3, True)]
    clash = spark.createDataFrame(rows, DOC).withColumn("item_id", F.lit("x"))
    kept = decontamination.drop_contaminated(clash, bench)
    assert sorted(r["doc_id"] for r in kept.collect()) == [3, 4, 5] and kept.columns == clash.columns
    assert decontamination.contaminated(clash, bench.limit(0)).count() == 0
    assert decontamination.drop_contaminated(clash.limit(0), bench).count() == 0


def test_names_at_starts_and_glued_or_spelled_numbers_are_placeholders():
    pairs = [
        ("Alice buys 3 boxes of pencils. Alice pays 5 dollars for each box. Bob buys 2 boxes. Bob pays half as much. How much do they pay?",
         "Clara buys 7 boxes of pencils. Clara pays 9 dollars for each box. David buys 4 boxes. David pays half as much. How much do they pay?"),
        ("A train travels 60km in two hours. How far does it travel in five hours at 80km/h?",
         "A train travels 90km in three hours. How far does it travel in seven hours at 70km/h?"),
        ("Tom has 12 apples. Jane has 7 more apples than Tom. How many apples does Jane have?",
         "Sven has 31 apples. Lucy has 9 more apples than Sven. How many apples does Lucy have?"),
    ]
    index = decontamination.Index([(k, item) for k, (item, _) in enumerate(pairs)])
    for k, (item, other) in enumerate(pairs):
        assert [m[0] for m in index.matches(f"Here it is. {other} And so on.", 0.5)] == [k]
        assert [(m[0], m[4]) for m in index.matches(item, 0.5)] == [(k, True)]
    assert index.matches("Trees grow in the wood. How far it is to them nobody knows.", 0.5) == []


def test_items_poor_in_literals_match_as_exact_copies():
    items = ["Compute 12 * 14 + 9 / 3 - 5.", "3 5 8 13 21 34 55", "Anna Berta Clara 7 Doris Emma 12 Frida"]
    index = decontamination.Index(list(enumerate(items)))
    for k, item in enumerate(items):
        assert [(m[0], m[4]) for m in index.matches(f"some words before {item} and after", 0.5)] == [(k, True)]
    for other in ("Compute 13 * 15 + 8 / 2 - 6.", "4 6 9 14 22 35 56", "Gerda Hilde Ida 8 Jutta Karla 13 Lena"):
        assert not index.matches(other, 0.5)
    # a template's other figures still match where the rest of the item is poor
    mixed = decontamination.Index([(1, "the farmer counts all sheep and 4 5 6 7 8 9 10 11 12 13 14 15")])
    assert mixed.matches("the farmer counts all sheep and 9 8 7 6 5 4 3 2 1 0 7 8", 0.5)


def test_slots_must_agree():
    # the same name stands for two different ones
    item = "when Anna gave Berta her old coat then Anna went home but Berta stayed and so Anna cried while Berta laughed"
    index = decontamination.Index([(1, "x. " + item)])
    same = item.replace("Anna", "Clara").replace("Berta", "Doris")
    mixed = "when Clara gave Doris her old coat then Doris went home but Emma stayed and so Frida cried while Gerda laughed"
    assert index.matches("y. " + same, 0.5) and not index.matches("y. " + mixed, 0.5)
    turned = item.replace("Anna", "X1").replace("Berta", "Anna").replace("X1", "Berta")
    assert index.matches("y. " + turned, 0.5)


def slow_windows(text, size):
    """{what a window may be read as: its places}, and for each place whether it is a template, with and without names at starts."""
    word, kind, either = (x.tolist() for x in decontamination.readings(text))
    turns, seen = [], 0
    for e in either:
        seen += e
        turns.append(seen % 2)
    out, rich, plain = {}, [], []
    for i in range(len(word) - size + 1):
        span = range(i, i + size)

        def read(as_word, span=span):
            shown = [("kind", kind[k]) if kind[k] and not as_word(k) else ("word", word[k]) for k in span]
            return tuple(shown) if sum(w == "word" for w, _ in shown) >= min(3, size) else None

        starts = sum(either[k] for k in span)
        ways = [read(lambda k: False)]
        rich.append(ways[0] is not None)
        if ways[0] is None:
            ways.append(("as it is", *(word[k] for k in span)))
        free = read(lambda k: either[k])
        plain.append(free is not None)
        if starts:
            ways.append(free)
        if starts > 1:
            ways += [read(lambda k: either[k] and turns[k] == 0), read(lambda k: either[k] and turns[k] == 1)]
        for w in ways:
            if w is not None:
                out.setdefault(w, []).append(i)
    return word, kind, out, rich, plain


def slow_match(item, text, coverage=0.5):
    size = min(5, len(decontamination.readings(item)[0]))
    if not size or len(decontamination.readings(text)[0]) < size:
        return None
    word, kind, own, rich, plain = slow_windows(item, size)
    other, _, there, _, _ = slow_windows(text, size)
    pairs = sorted({(p, q) for w, places in own.items() for q in places for p in there.get(w, [])}, key=lambda x: (x[0] - x[1], x[0]))

    def covered(places):
        shares = [(sum(m[q] for q in places) / sum(m), sum(m[q] for q in places)) for m in (rich, plain, [True] * len(rich)) if any(m)]
        return max(shares)

    runs, best = [], None
    for p, q in pairs:
        if not runs or p - q - (runs[-1][-1][0] - runs[-1][-1][1]) > 2:
            runs.append([])
        runs[-1].append((p, q))
    for run in runs:
        seen = {(kind[q + k], word[q + k], other[p + k], q + k) for p, q in run for k in range(size) if kind[q + k]}
        votes = {}
        for k, x, y, _ in seen:
            votes[k, x, y] = votes.get((k, x, y), 0) + 1
        to, back = {}, {}
        for k, x, y in sorted(votes, key=lambda v: (-votes[v], v)):
            if (k, x) not in to and (k, y) not in back:
                to[k, x], back[k, y] = y, x
        wrong, right = {i for k, x, y, i in seen if to.get((k, x)) != y}, {i for k, x, y, i in seen if to.get((k, x)) == y}
        if len(wrong) > 1 and 5 * len(wrong) > len(wrong | right):
            continue
        kept = {q for p, q in run if all(not kind[q + k] or to.get((kind[q + k], word[q + k])) == other[p + k] for k in range(size))}
        if kept and (best is None or covered(kept) > best):
            best = covered(kept)
    return best if best and best[0] >= coverage else None


def test_matches_equal_a_search_of_every_item_in_every_text(spark, monkeypatch):
    rng = random.Random(12)
    plain = "the farmer has sold apples and then buys more of them at a market near home where prices fall every day".split()
    names, units = "Anna Bert Carla Dora Emil Otto Tom".split(), ["kg", "km", "dollars"]

    def sentence():
        words = []
        for _ in range(rng.randrange(3, 16)):
            kind = rng.randrange(8)
            words.append(str(rng.randrange(30)) + " " + rng.choice(units) if kind == 0 else rng.choice(names) if kind == 1 else str(rng.randrange(9)) if kind == 2 else rng.choice(plain))
        return " ".join(words) + rng.choice((".", "?", ""))

    items = [" ".join(sentence() for _ in range(rng.randrange(1, 4))) for _ in range(40)] + ["two words", "", None, "7 8 9 10 11 12"]
    items += [items[0], items[1]]  # windows that several items share
    texts = ["", None, "7 8 9 10 11 12"]
    for _ in range(160):
        text = rng.choice(items) or ""
        swap = dict(zip(names, rng.sample(names, len(names)), strict=True))
        changed = [swap.get(w, w) if rng.random() < 0.95 else rng.choice(plain + names) for w in text.split()]
        changed = [str(rng.randrange(30)) if w.isdigit() and rng.random() < 0.3 else w for w in changed]
        texts.append(" ".join([sentence(), " ".join(changed), sentence()]))
    index = decontamination.Index(list(enumerate(items)))
    want = {}
    for d, t in enumerate(texts):
        for k, item in enumerate(items):
            m = slow_match(item or "", t or "")
            if m:
                want[d, k] = (m[1], m[0])
    got = {(d, m[0]): (m[1], m[2]) for d, t in enumerate(texts) for m in index.matches(t, 0.5)}
    assert got == want and len(want) > 60
    src, bench = spark.createDataFrame(list(enumerate(texts)), DOC), spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    whole = sorted(map(tuple, decontamination.contaminated(src, bench).collect()))
    assert {(r[0], r[1]): (r[2], r[3]) for r in whole} == want
    left = sorted(r["doc_id"] for r in decontamination.drop_contaminated(src, bench).collect())
    monkeypatch.setattr(decontamination, "BLOCK_WINDOWS", 10)
    monkeypatch.setattr(decontamination, "FILTER_BITS", 1 << 12)  # false positives fall away in the join
    twice = src.union(src.where("doc_id < 9"))
    assert sorted(map(tuple, decontamination.contaminated(twice, bench).collect())) == sorted(whole + [r for r in whole if r[0] < 9])
    assert sorted(r["doc_id"] for r in decontamination.drop_contaminated(src, bench).collect()) == left
    assert left == [d for d in range(len(texts)) if d not in {k for k, _ in want}]


def test_a_distributed_benchmark_finds_the_same(spark, docs, sf, monkeypatch):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    whole = sorted(map(tuple, decontamination.contaminated(docs, bench).collect()))
    plain = {(d["doc_id"], b["item_id"]) for d in docs.collect() for b in bench.collect() if b["text"] in d["text"]}
    assert {r[:2] for r in whole} >= plain and len(plain) > 0
    monkeypatch.setattr(decontamination, "BLOCK_WINDOWS", 100)
    assert sorted(map(tuple, decontamination.contaminated(docs, bench.union(bench.limit(1))).collect())) == sorted(
        whole + [r for r in whole if r[1] == bench.first()["item_id"]]
    )
    assert decontamination.contaminated(docs.limit(0), bench).count() == 0


# --- URLs


def test_url_rules_and_parts(spark):
    urls = [
        ("http://Example.COM/en/a", "example.com", "/en/a", "example.com/en/", "block"),
        ("http://www.example.com/en/", "www.example.com", "/en/", "www.example.com/en/", "allow"),
        ("https://a.www.example.com/en/x?y", "a.www.example.com", "/en/x", "www.example.com/en/", "allow"),
        ("https://notexample.com/en/", "notexample.com", "/en/", "com/", "allow"),
        ("https://x.net/fr/1#f", "x.net", "/fr/1", "net/fr/", "block"),
        ("https://x.net/de/1", "x.net", "/de/1", None, "allow"),
        ("https://casino-win.x.org/p/", "casino-win.x.org", "/p/", None, "block"),
        ("http://a.com?x=/y", "a.com", "", None, "allow"),
        ("no scheme", "", "", None, "allow"),
        (None, "", "", None, "allow"),
        ("", "", "", None, "allow"),
        ("x://É.Net/es/", "É.net", "/es/", "net/es/", "block"),
    ]
    pages = spark.createDataFrame([(k, u[0], "clash") for k, u in enumerate(urls)], "page_id long, url string, host string")
    got = local(urlfilter.verdicts(pages, urlfilter.default_list(pages)), "page_id")
    for k, u in enumerate(urls):
        assert tuple(got[k])[1:5] == u[1:]
    assert urlfilter.verdicts(pages.limit(0), urlfilter.default_list(pages)).count() == 0
    assert urlfilter.verdicts(pages, urlfilter.default_list(pages).limit(0)).where("listed").count() == 0


def test_bloom_filter_has_no_false_negative(spark):
    keys = spark.range(3000).select(F.concat(F.lit("k"), "id").alias("url"))
    probe = spark.range(0, 9000, 2).select(F.concat(F.lit("k"), "id").alias("u"), "id").union(spark.createDataFrame([(None, 1)], "u string, id long"))
    got = urlfilter.on_list(probe, "u", keys, "url")
    assert got.count() == 4501 and got.where("_kb_listed").count() == 1500 and got.where("_kb_listed AND id >= 3000").count() == 0
    blocks = urlfilter.block_count(3000)
    assert urlfilter.bloom_filter(keys, "url", blocks).count() <= blocks
    assert urlfilter.block_count(1) == 1 and urlfilter.block_count(10**12) == urlfilter.MAX_BLOCKS


# --- embeddings


def test_e8_points_are_nearest():
    r = np.random.default_rng(1)
    x = r.standard_normal((200, 8)) * 2
    p = lattice.nearest_e8(x)
    assert np.all((np.abs(p - np.rint(p)).max(1) < 1e-9) | (np.abs(p - 0.5 - np.rint(p - 0.5)).max(1) < 1e-9))
    assert np.all(np.rint(p.sum(1)) % 2 == 0)
    steps = lattice.shortest()
    assert len(steps) == 240 and np.allclose((steps**2).sum(1), 2)
    own = ((x - p) ** 2).sum(1)
    assert np.all(own[:, None] <= ((x[:, None] - p[:, None] - steps[None]) ** 2).sum(2) + 1e-9)


def planted(seed, n=250, width=64):
    r = np.random.default_rng(seed)
    base = r.standard_normal((n, width))
    base /= np.linalg.norm(base, axis=1)[:, None]
    out = [base]
    for c in (0.952, 0.96, 0.98, 0.995):
        other = r.standard_normal((n, width))
        other -= (other * base).sum(1)[:, None] * base
        other /= np.linalg.norm(other, axis=1)[:, None]
        out.append((c * base + np.sqrt(1 - c * c) * other) * r.uniform(0.1, 9, (n, 1)))
    return np.vstack(out).astype(np.float32)


def test_lattice_links_are_true_and_few_are_missed(spark):
    v = planted(3).astype(np.float64)
    rows = spark.createDataFrame([(k, [float(x) for x in row]) for k, row in enumerate(v)], "vec_id long, embedding array<float>")
    unit = v / np.linalg.norm(v, axis=1)[:, None]
    exact = unit @ unit.T >= lattice.COSINE
    np.fill_diagonal(exact, False)
    got = local(lattice.near_vectors(rows), "vec_id")
    links = np.array([got[k]["n_links"] for k in range(len(v))])
    assert np.all(links <= exact.sum(1)) and links.sum() >= 0.95 * exact.sum()
    blocks = local(lattice.near_vectors(rows, block_rows=7), "vec_id")
    assert {k: tuple(r) for k, r in got.items()} == {k: tuple(r) for k, r in blocks.items()}


def test_lattice_edges(spark):
    one = [1.0] + [0.0] * 15
    rows = [
        (1, one), (2, one), (3, one), (4, [2.0] + [0.0] * 15), (5, None), (6, [0.0] * 16), (7, [float("nan")] + [0.0] * 15),
        (8, [None] + [1.0] * 15), (9, [float("inf")] + [0.0] * 15), (10, []), (11, [0.0, 1.0]), (12, [0.0, 1.0]), (13, [1e-30, 0.0]), (0, [-1.0] + [0.0] * 15),
    ]
    src = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("n_links", F.lit("clash"))
    got = local(lattice.near_vectors(src), "vec_id")
    assert len(got) == 14
    assert [got[k]["n_links"] for k in (1, 2, 3, 4)] == [3] * 4 and {got[k]["component_id"] for k in (1, 2, 3, 4)} == {1}
    assert all(got[k]["n_links"] == 0 and got[k]["component_id"] == k for k in (0, 5, 6, 7, 8, 9, 10, 13))
    assert got[12]["component_id"] == 11 and not got[12]["kept"] and got[11]["kept"]
    assert lattice.near_vectors(src.limit(0)).count() == 0


def test_lattice_repeated_ids_and_pieces(spark, monkeypatch):
    rng = np.random.default_rng(8)
    base = rng.standard_normal(24)
    near = [(base + 0.02 * rng.standard_normal(24)).tolist() for _ in range(30)]
    far = rng.standard_normal((5, 24)).tolist()
    rows = [(k, v) for k, v in enumerate(near)] + [(k, near[0]) for k in (3, 3, None)] + [(100 + k, v) for k, v in enumerate(far)]
    monkeypatch.setattr(lattice, "TILE", 4)
    got = lattice.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3), block_rows=9).collect()
    assert len(got) == len(rows)
    assert all(r["n_links"] == 32 and r["component_id"] == 0 for r in got if r["vec_id"] is None or r["vec_id"] < 100)
    assert all(r["n_links"] == 0 and r["kept"] for r in got if r["vec_id"] is not None and r["vec_id"] >= 100)
    cells = spark.createDataFrame([(c, k, 0) for k, c in enumerate([1, 2, 2, 3, 4, 4, 4, 4, 5])], "cell long, rep long, at int").coalesce(1)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "2")
    try:
        assert [r["rep"] for r in lattice._shared(cells).collect()] == [1, 2, 4, 5, 6, 7]
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


# --- components and the pipeline


def test_components_of_a_long_chain(spark):
    from kernelblocks.llm.components import connected_components

    edges = spark.range(300).selectExpr("id AS a", "id + 1 AS b").union(spark.createDataFrame([(900, 800), (800, 900), (5, 5)], "a long, b long"))
    got = {r["node"]: r["root"] for r in connected_components(edges, "a", "b").collect()}
    assert all(got[k] == 0 for k in range(301)) and got[900] == 800 == got[800]
    assert connected_components(edges.limit(0), "a", "b").count() == 0


def test_pipeline_stages(spark, sf, docs, labels):
    import corpus_pipeline as cp

    assert [n for n, _ in cp.STAGES] == ["quality", "near_copies", "leaks", "secrets", "packing"] and cp.ORACLE_SQL is None
    now = docs
    ids = {r["doc_id"] for r in docs.collect()}
    for name, stage in cp.STAGES[:-1]:
        before, now = now, stage(spark, now, sf).checkpoint()
        assert now.columns == docs.columns
        left = {r["doc_id"] for r in now.collect()}
        assert left <= ids and left
        if name == "quality":
            bad = {r["doc_id"] for r in labels.where("quality = 0").collect()}
            assert len(bad & left) <= 0.1 * len(bad) + 1
        elif name == "near_copies":
            rows = sorted((r["doc_id"], r["text"]) for r in before.collect())
            label = slow_groups([set(nearcopies.shingle_set(t).tolist()) for _, t in rows])
            assert left == {rows[k][0] for k in set(label)}
        elif name == "leaks":
            leaked = {r["doc_id"] for r in decontamination.contaminated(before, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
            assert left == ids - leaked
        else:
            assert left == ids and secretscan.secrets(now).where("n_assign + n_access + n_hex > 0").count() == 0
        ids = left
    want = {(r["doc_id"], r["start"], r["ids_crc32"]) for r in packing.pack(now, tokenizer_path()).collect()}
    got = {(r["doc_id"], r["start"], r["ids_crc32"]) for r in cp.run(spark, sf).collect()}
    assert {d for d, _, _ in got} == {d for d, _, _ in want} == ids


def test_pipeline_on_odd_tables(spark, tmp_path, sf):
    import corpus_pipeline as cp

    odd = spark.createDataFrame(
        [(1, None, None, None, None), (2, "", "en", "s", 0), (None, "good words of some text", "en", "s", 3), (4, "good words of some text", "en", None, 23), (4, "good words of some text", "en", None, 23)],
        "doc_id long, text string, lang string, source string, n_chars long",
    )
    for part, n in ((odd, 2), (odd.limit(0), 0)):
        now = part
        for _, stage in cp.STAGES[1:-1]:
            now = stage(spark, now, sf).checkpoint()
        assert now.columns == odd.columns
        assert cp.STAGES[-1][1](spark, now, sf).select("doc_id").distinct().count() == n
        first = cp.STAGES[0][1](spark, part, sf)
        assert first.columns == odd.columns and first.count() <= part.count()


def test_texts_are_looked_up_together_as_each_alone(sf, monkeypatch):
    rng = np.random.default_rng(5)
    items = [(k, f"Tom {w} has {3 + k} apples and 5 cm of red {w} rope. He gives Ann {k} of them before the {w} train leaves.") for k, w in enumerate(("old", "new", "blue"))]
    index = decontamination.Index([*items, (7, "only three words"), (8, "\0. begins \0. a word that parts texts")])
    words = [w for _, t in items for w in t.split()] + ["5cm", "-", ".", "\0.", "7", "km", "Zoe", "three", "only"]
    texts: list = [None, "", " . ", "only three words", *(t for _, t in items), *(t.replace("5 cm", "9cm") for _, t in items)]
    for k in range(60):  # ends of one text and beginnings of the next make no item together
        cut = int(rng.integers(1, 20))
        t = items[k % 3][1].split()
        texts += [" ".join(t[:cut]), " ".join(t[cut:]), " ".join(rng.choice(words, int(rng.integers(0, 40)))), "9", "cm of rope"]
    alone = [index.matches(t, 0.5) for t in texts]
    assert sum(map(bool, alone)) > 20
    calls, made = [], decontamination.windows
    monkeypatch.setattr(decontamination, "windows", lambda *a: calls.append(1) or made(*a))
    assert index.all_matches(texts, 0.5) == alone
    calls.clear()
    assert not any(index.all_matches(["nothing of theirs stands in here at all"] * 200, 0.5)) and len(calls) == len(index.sizes)
    monkeypatch.setattr(decontamination, "CHUNK_SIGNS", 50)
    assert index.all_matches(texts, 0.5) == alone and index.all_matches([], 0.5) == []
