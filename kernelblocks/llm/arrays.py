"""SQL for arrays inside a row."""

from __future__ import annotations

#: Arrays grow by so many members at most before the next begins.
CHUNK = 256


def running(values: str, combine: str) -> str:
    """SQL for the running sums (combine +) or maxima (combine greatest) of an array of ints.

    Arrays grow by copying, so they grow to CHUNK numbers only, and the chunks' ends are carried on.
    """
    least = "0" if combine == "+" else "-2147483647"
    put = (lambda p, q: f"{p} + {q}") if combine == "+" else (lambda p, q: f"greatest({p}, {q})")
    inner = f"""transform(sequence(0, greatest(size(rv) - 1, 0) div {CHUNK}), c ->
        aggregate(slice(rv, c * {CHUNK} + 1, {CHUNK}), cast(array() AS array<int>), (z, q) ->
          concat(z, array(CASE WHEN size(z) = 0 THEN q ELSE {put("element_at(z, -1)", "q")} END))))"""
    carried = f"""aggregate(ri, array({least}), (z, v) -> concat(z, array(CASE WHEN size(v) = 0 THEN {least} ELSE
        {put("element_at(z, -1)", "element_at(v, -1)")} END)))"""
    added = f"flatten(zip_with(ri, slice({carried}, 1, size(ri)), (v, least) -> transform(v, q -> {put('least', 'q')})))"
    return f"element_at(transform(transform(array({values}), rv -> {inner}), ri -> {added}), 1)"
