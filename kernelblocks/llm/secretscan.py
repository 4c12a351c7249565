"""Secret scans with DataFrame functions only.

Fixed patterns find assignments, access keys and long hexadecimal strings; they are matched leftmost
and without overlap for each kind, and matches that are too short fall away afterwards. Two character
Markov models, of random strings and of ordinary identifiers, are trained from labelled samples; other
runs of key characters are reported where the log-likelihood ratio of the models favours randomness by
a margin: whole, where the whole run does, else each stretch that does, out to the next of the signs
/ _ - on both sides. So path words around a random part don't hide it. Spans of the patterns always
stay; the models only add spans that overlap none of them.

A long text is worked off in parts, cut where no span can lie, and places are running sums over
chunks, so the time grows with the length of the text whatever stands in it.

Offsets count code points and ends are exclusive. Defined results: null and empty texts have no
spans; repeated rows give a row each; an empty table gives no row; columns of other names don't
matter, nor does their order; spans that tie in where they begin come by kind. Texts of any length are
scanned whole; a run of more than 512 signs is judged in pieces, and random pieces that meet are one span.
"""

from __future__ import annotations

import base64
import hashlib
import math
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kernelblocks.llm.arrays import CHUNK, running
from kernelblocks.llm.runtime import id_and_text

# What the base patterns look like and how long a match must be.
ASSIGN = r"((?i:password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
ASSIGN_LENGTH, ACCESS_LENGTH, HEX_LENGTH = 6, 20, 24
KINDS = ("assign", "access", "hex", "markov")
#: Runs that the models judge, a very long one in pieces of 512 signs, of which those that are random and meet are one.
CANDIDATE = r"[A-Za-z0-9+/_-]{10,512}(?:[A-Za-z0-9+/_-]{1,9}(?![A-Za-z0-9+/_-]))?"
#: From this length on sum and mean decide; shorter stretches need the sum and signs of several sorts.
WHOLE_LENGTH = 20
SIGNS = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_-"
#: Thousandths of a nat, in sum and for each character.
LEAST_TOTAL, LEAST_MEAN = 9000, 450
#: A stretch ends where its sum has fallen by so much from its highest.
LEAST_DROP = 4500
MASK = "[SECRET]"
#: Longer texts are worked off in parts of about PART_SIGNS code points, cut behind a sign or at blanks that no span can hold.
WHOLE_TEXT, PART_SIGNS = 8192, 4096
PART = r"(?s).{%d}.*?(?:[^A-Za-z0-9+/_.=\x20\x22\x27:-]|(?<![:=\x20])\x20++(?![:=]))|.+" % PART_SIGNS

#: Words that ordinary identifiers are made of (fixed values).
IDENTIFIER_WORDS = (
    "get set is has make build read write open close start stop create delete update insert remove find search index "
    "count total number value name path file folder table column row key list map item node tree graph edge user "
    "account order price amount date time day month year hour minute second event page request response server client "
    "session config option default current previous next first last min max sum average length width height size "
    "color image text line word letter string buffer stream channel message error warning result status code type "
    "class method function module package version test sample train model feature vector matrix random hash sort "
    "filter group merge split join parse format encode decode load save print show hide enable disable handle process "
    "thread worker task queue stack cache memory disk network address port host domain language source target"
).split()
#: Ordinary words of the languages at hand, whose joints identifiers lack (fixed values).
PLAIN_WORDS = (
    "understanding international responsibility communication nevertheless straightforward characteristic "
    "verantwortung geschwindigkeit wissenschaft gesellschaftlich entwicklungen veranstaltung unterschiedlich "
    "developpement gouvernement particulierement internationale responsabilite communication naturellement "
    "desarrollo responsabilidad comunicacion naturalmente internacional conocimiento establecimiento"
).split()


def sample_strings(size: int = 3000) -> list[tuple[str, int]]:
    """The built-in labelled samples: (string, 1 for random or 0 for ordinary), the same at every call."""
    out: list[tuple[str, int]] = []
    for k in range(size):
        raw = hashlib.sha512(f"random {k}".encode()).digest()
        form = k % 4
        if form == 0:
            s = base64.b64encode(raw).decode().rstrip("=")[:40]
        elif form == 1:
            s = base64.urlsafe_b64encode(raw).decode().rstrip("=")[:32]
        elif form == 2:
            s = base64.b32encode(raw).decode().rstrip("=")[:24]
        else:
            s = "".join(SIGNS[b % 62] for b in raw[:36])
        out.append((s, 1))
        pick = [IDENTIFIER_WORDS[(raw[2 * i] << 8 | raw[2 * i + 1]) % len(IDENTIFIER_WORDS)] for i in range(2 + raw[40] % 3)]
        form = raw[41] % 6
        if form == 0:
            s = "_".join(pick)
        elif form == 1:
            s = pick[0] + "".join(w.title() for w in pick[1:])
        elif form == 2:
            s = "-".join(pick)
        elif form == 3:
            s = "_".join(pick).upper()
        elif form == 4:
            s = "/".join(pick) + f"_{raw[42] % 100}"
        else:
            s = PLAIN_WORDS[raw[43] % len(PLAIN_WORDS)]
        out.append((s, 0))
    # rules and fillers of one sign
    out += [(c * 60, 0) for c in SIGNS for _ in range(8)]
    return out


def train(samples: Iterable[tuple[str, int]], smoothing: float = 2.0) -> list[int]:
    """Log-likelihood ratio of each ordered pair of characters in thousandths of a nat, row by row.

    Each model is a first-order chain; the place after the last known character stands for all others.
    """
    place = {c: i for i, c in enumerate(SIGNS)}
    n = len(SIGNS) + 1
    counts = [[[smoothing] * n for _ in range(n)] for _ in range(2)]
    for text, label in samples:
        at = [place.get(c, n - 1) for c in text]
        for a, b in zip(at, at[1:], strict=False):
            counts[label][a][b] += 1
    out = []
    for a in range(n):
        sums = [sum(counts[k][a]) for k in range(2)]
        for b in range(n):
            out.append(round(1000 * (math.log(counts[1][a][b] / sums[1]) - math.log(counts[0][a][b] / sums[0]))))
    return out


def _quoted(pattern: str) -> str:
    return "r'" + pattern.replace("'", "\\x27") + "'"


def _with_matches(df: DataFrame, name: str, pattern: str, group: int = 0) -> DataFrame:
    """df with name: by part an array<struct<start,stop,m,g>> of the matches, g being the group of m."""
    found, ends, p = f"{name}_m", f"{name}_e", _quoted(pattern)
    lengths = f"zip_with(slice(split(part, {p}, -1), 1, size(found)), found, (x, y) -> length(x) + length(y))"
    caught = f"regexp_extract(x, {p}, {group})" if group else "x"
    return (
        df.withColumn(found, F.expr(f"transform(_kb_parts, part -> regexp_extract_all(part, {p}, 0))"))
        .withColumn(ends, F.expr(f"zip_with(_kb_parts, {found}, (part, found) -> CASE WHEN size(found) = 0 THEN cast(array() AS array<int>) ELSE {running(lengths, '+')} END)"))
        .withColumn(name, F.expr(f"zip_with({found}, {ends}, (found, ends) -> zip_with(found, ends, (x, e) -> named_struct('start', e - length(x), 'stop', e, 'm', x, 'g', {caught})))"))
        .drop(found, ends)
    )


def _stretches(r: str) -> str:
    """SQL for array<struct<start,stop>>: the whole of run r where it is random, else its random stretches."""
    total, size = f"aggregate({r}.steps, 0, (z, x) -> z + x)", f"length({r}.m)"
    # sum of the stretch so far, where it begins, its highest sum and the end of that; i is the step's place
    now = "(greatest(a.sum, 0) + x)"
    top = f"greatest(a.peak, {now})"
    over = f"({now} <= 0 OR {top} - {now} >= {LEAST_DROP})"
    begin = "CASE WHEN a.sum <= 0 THEN a.i ELSE a.begin END"
    end = f"CASE WHEN {now} > a.peak THEN a.i + 1 ELSE a.stop END"
    found = f"""aggregate(concat({r}.steps, array(-1000000)),
        named_struct('i', 1, 'sum', 0, 'begin', 1, 'peak', 0, 'stop', 1, 'out', cast(array() AS array<struct<begin:int,stop:int>>)),
        (a, x) -> named_struct('i', a.i + 1, 'sum', CASE WHEN {over} THEN 0 ELSE {now} END, 'begin', {begin},
          'peak', CASE WHEN {over} THEN 0 ELSE {top} END, 'stop', {end},
          'out', CASE WHEN {over} AND {top} >= {LEAST_TOTAL} THEN concat(a.out, array(named_struct('begin', {begin}, 'stop', {end}))) ELSE a.out END),
        a -> a.out)"""
    # words of one case and numbers reach the sum by chance: short ones need letters and digits or a capital after a small letter
    part = f"substring({r}.m, f.begin, f.stop - f.begin + 1)"
    steps = f"aggregate(slice({r}.steps, f.begin, f.stop - f.begin), 0, (z, x) -> z + x)"
    found = f"""filter({found}, f -> {part} RLIKE '[0-9].*[A-Za-z]|[A-Za-z].*[0-9]|[a-z].*[A-Z]' OR
        (f.stop - f.begin + 1 >= {WHOLE_LENGTH} AND {steps} >= {LEAST_MEAN} * (f.stop - f.begin + 1)))"""
    # out to the signs around it
    wide = f"""transform({found}, f -> named_struct(
        'start', {r}.start + f.begin - 1 - length(regexp_extract(substring({r}.m, 1, f.begin - 1), '[A-Za-z0-9+]*$', 0)),
        'stop', {r}.start + f.stop + length(regexp_extract(substring({r}.m, f.stop + 1), '^[A-Za-z0-9+]*', 0))))"""
    whole = f"array(named_struct('start', {r}.start, 'stop', {r}.start + {size}))"
    return f"CASE WHEN {size} >= {WHOLE_LENGTH} AND {total} >= {LEAST_TOTAL} AND {total} >= {LEAST_MEAN} * {size} THEN {whole} ELSE {wide} END"


def _with_met(df: DataFrame, name: str) -> DataFrame:
    """df with the spans of name, sorted and apart but for their ends, those that meet as one."""
    reach = running("transform(found, s -> s.stop)", "greatest")
    # heads: the first of those that meet; each ends where the one before the next head does
    heads = "filter(zip_with(transform(found, (s, i) -> named_struct('i', i, 'start', s.start)), concat(array(-1), slice(reach, 1, size(reach) - 1)), (h, r) -> named_struct('i', h.i, 'start', h.start, 'new', h.start > r)), h -> h.new)"
    last = "concat(transform(slice(heads, 2, size(heads)), h -> h.i), array(size(reach)))"
    return (
        df.withColumn("_kb_reach", F.expr(f"transform({name}, found -> CASE WHEN size(found) = 0 THEN cast(array() AS array<int>) ELSE {reach} END)"))
        .withColumn("_kb_heads", F.expr(f"zip_with({name}, _kb_reach, (found, reach) -> CASE WHEN size(found) = 0 THEN cast(array() AS array<struct<i:int,start:int,new:boolean>>) ELSE {heads} END)"))
        .withColumn(name, F.expr(f"zip_with(_kb_reach, _kb_heads, (reach, heads) -> CASE WHEN size(heads) = 0 THEN cast(array() AS array<struct<start:int,stop:int>>) ELSE zip_with(heads, {last}, (h, e) -> named_struct('start', h.start, 'stop', reach[e - 1])) END)"))
        .drop("_kb_reach", "_kb_heads")
    )


def _with_apart(df: DataFrame, name: str) -> DataFrame:
    """df with the spans of name that overlap none of _kb_base; both are sorted by start."""
    both = "array_sort(concat(transform(own, b -> named_struct('start', b.start, 'stop', b.stop, 'base', true)), transform(found, s -> named_struct('start', s.start, 'stop', s.stop, 'base', false))))"
    reach = running("transform(both, s -> CASE WHEN s.base THEN s.stop ELSE 0 END)", "greatest")
    ahead = running("transform(reverse(both), s -> CASE WHEN s.base THEN -s.start ELSE -2147483647 END)", "greatest")
    free = "filter(zip_with(r._kb_both, zip_with(r._kb_reach, reverse(r._kb_ahead), (w, x) -> named_struct('reach', w, 'ahead', -x)), (s, e) -> named_struct('start', s.start, 'stop', s.stop, 'ok', NOT s.base AND e.reach <= s.start AND e.ahead >= s.stop)), s -> s.ok)"
    # the furthest end of the base spans before a place, and the nearest start of those after it
    return (
        df.withColumn("_kb_both", F.expr(f"zip_with(_kb_base, {name}, (own, found) -> CASE WHEN size(found) = 0 THEN cast(array() AS array<struct<start:int,stop:int,base:boolean>>) ELSE {both} END)"))
        .withColumn("_kb_reach", F.expr(f"transform(_kb_both, both -> CASE WHEN size(both) = 0 THEN cast(array() AS array<int>) ELSE {reach} END)"))
        .withColumn("_kb_ahead", F.expr(f"transform(_kb_both, both -> CASE WHEN size(both) = 0 THEN cast(array() AS array<int>) ELSE {ahead} END)"))
        .withColumn(name, F.expr(f"transform(arrays_zip(_kb_both, _kb_reach, _kb_ahead), r -> {free})"))
        .drop("_kb_both", "_kb_reach", "_kb_ahead")
    )


def with_spans(docs: DataFrame, ratios: list[int], text: str = "text") -> DataFrame:
    """docs with _kb_parts, the text in parts, and by part _kb_at, where it begins, and _kb_base and _kb_all, its spans.

    Spans are structs of (start, kind's rank, stop), in order, counted from the part's beginning.
    """
    t = f"coalesce(`{text}`, '')"
    out = docs.withColumn("_kb_parts", F.expr(f"CASE WHEN length({t}) <= {WHOLE_TEXT} THEN array({t}) ELSE regexp_extract_all({t}, r'{PART}', 0) END"))
    lengths = running("transform(_kb_parts, x -> length(x))", "+")
    out = out.withColumn("_kb_at", F.expr(f"CASE WHEN size(_kb_parts) = 1 THEN array(0) ELSE concat(array(0), slice({lengths}, 1, size(_kb_parts) - 1)) END"))
    out = _with_matches(out, "_kb_assign", ASSIGN, 2)
    out = _with_matches(out, "_kb_access", ACCESS)
    # runs of these signs are taken whole, so the least length can stand in the pattern
    out = _with_matches(out, "_kb_hex", HEX[:-1] + f"{{{HEX_LENGTH},}}")
    keep = {"_kb_assign": f"length(s.g) >= {ASSIGN_LENGTH}", "_kb_access": f"length(s.m) >= {ACCESS_LENGTH}", "_kb_hex": "true"}
    ranked = ", ".join(f"transform(filter(r.{c}, s -> {w}), s -> named_struct('start', s.start, 'kind', {k}, 'stop', s.stop))" for k, (c, w) in enumerate(keep.items()))
    out = out.withColumn("_kb_base", F.expr(f"transform(arrays_zip({', '.join(keep)}), r -> array_sort(concat({ranked})))")).drop(*keep)
    out = _with_matches(out, "_kb_runs", CANDIDATE)
    n = len(SIGNS) + 1
    table = f"from_json('{ratios}', 'array<int>')"
    places = f"transform(split(s.m, ''), c -> CASE WHEN locate(c, '{SIGNS}') = 0 THEN {n} ELSE locate(c, '{SIGNS}') END)"
    steps = f"zip_with(slice(at, 1, size(at) - 1), slice(at, 2, size(at) - 1), (x, y) -> element_at({table}, (x - 1) * {n} + y))"
    scored = f"transform(found, s -> named_struct('start', s.start, 'm', s.m, 'steps', element_at(transform(array({places}), at -> {steps}), 1)))"
    hopeful = f"filter({scored}, r -> aggregate(r.steps, 0, (z, x) -> z + greatest(x, 0)) >= {LEAST_TOTAL})"
    out = out.withColumn("_kb_runs", F.expr(f"transform(_kb_runs, found -> {hopeful})"))
    out = out.withColumn("_kb_new", F.expr(f"transform(_kb_runs, found -> flatten(transform(found, r -> {_stretches('r')})))")).drop("_kb_runs")
    out = _with_apart(_with_met(out, "_kb_new"), "_kb_new")
    added = f"transform(found, s -> named_struct('start', s.start, 'kind', {len(KINDS) - 1}, 'stop', s.stop))"
    return out.withColumn("_kb_all", F.expr(f"zip_with(_kb_base, _kb_new, (own, found) -> array_sort(concat(own, {added})))")).drop("_kb_new")


def _whole(spans: str) -> str:
    """SQL for the spans of all parts, counted from the text's beginning."""
    return f"""flatten(zip_with({spans}, slice(_kb_at, 1, size({spans})), (own, z) ->
        transform(own, s -> named_struct('start', s.start + z, 'kind', s.kind, 'stop', s.stop + z))))"""


def _digest(spans: str) -> Column:
    kinds = ", ".join(f"'{k}'" for k in KINDS)
    return F.expr(
        f"array_join(transform({_whole(spans)}, s -> concat(element_at(array({kinds}), s.kind + 1), ':', s.start, ':', s.stop)), ',')"
    )


def _number(kind: int) -> Column:
    return F.expr(f"cast(aggregate(_kb_all, 0, (z, own) -> z + size(filter(own, s -> s.kind = {kind}))) AS bigint)")


def secrets(docs: DataFrame, samples: Iterable[tuple[str, int]] | None = None) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_markov) for every row of docs."""
    found = with_spans(id_and_text(docs), train(sample_strings() if samples is None else samples))
    return found.select(
        "doc_id",
        *(_number(k).alias(f"n_{KINDS[k]}") for k in range(3)),
        F.sha2(_digest("_kb_base"), 256).alias("base_sha256"),
        _digest("_kb_all").alias("spans"),
        _number(3).alias("n_markov"),
    )


def masked(docs: DataFrame, samples: Iterable[tuple[str, int]] | None = None, mask: str = MASK) -> DataFrame:
    """docs with every span of text replaced by mask and n_chars, where there is one, brought up to date.

    Spans that overlap are masked as one. Rows without a span stay as they are.
    """
    found = with_spans(docs, train(sample_strings() if samples is None else samples))
    reach = running("transform(own, s -> s.stop)", "greatest")
    found = found.withColumn("_kb_reach", F.expr(f"transform(_kb_all, own -> CASE WHEN size(own) = 0 THEN array(0) ELSE concat(array(0), {reach}) END)"))
    # what lies between the end of all spans before and this one's start, then the mask; CHUNK spans at a time,
    # since a place in a string is found from its beginning
    pieces = f"""zip_with(slice(r._kb_all, c + 1, {CHUNK}), slice(r._kb_reach, c + 1, {CHUNK}), (s, z) -> CASE WHEN s.start < z THEN '' ELSE
        concat(substring(sub, z - r._kb_reach[c] + 1, s.start - z), '{mask}') END)"""
    sub = f"substring(r._kb_parts, r._kb_reach[c] + 1, r._kb_reach[least(c + {CHUNK}, size(r._kb_all))] - r._kb_reach[c])"
    part = f"""CASE WHEN size(r._kb_all) = 0 THEN r._kb_parts ELSE
        array_join(concat(transform(sequence(0, size(r._kb_all) - 1, {CHUNK}), c -> element_at(transform(array({sub}), sub -> array_join({pieces}, '')), 1)),
          array(substring(r._kb_parts, element_at(r._kb_reach, -1) + 1))), '') END"""
    hit = "exists(_kb_all, own -> size(own) > 0)"
    clean = F.expr(f"CASE WHEN {hit} THEN array_join(transform(arrays_zip(_kb_parts, _kb_all, _kb_reach), r -> {part}), '') ELSE text END")
    changes = {"text": clean}
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        changes["n_chars"] = F.when(~F.expr(hit), F.col("n_chars")).otherwise(F.length(clean).cast(kind))
    return found.withColumns(changes).select(docs.columns)
