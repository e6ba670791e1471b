"""Space-filling curves as Column expressions: everything stays in generated code."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _long(c: Column | str) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("bigint")


def _any_bits(parts: list[Column]) -> Column:
    return reduce(lambda a, b: a.bitwiseOR(b), parts)


def morton_encode(cols: list, bits: int) -> Column:
    """Interleaves the bits of N small integers, the first dimension most significant in each group."""
    n = len(cols)
    if n * bits > 62:
        raise ValueError("more than 62 bits: use morton_encode_wide")
    one = F.lit(1).cast("bigint")
    return _any_bits([F.shiftleft(F.shiftright(_long(c), b).bitwiseAND(one), b * n + n - 1 - d) for d, c in enumerate(cols) for b in range(bits)])


def morton_decode(code, n_dims: int, bits: int) -> list[Column]:
    """The integers of a Morton index, in order."""
    one, c = F.lit(1).cast("bigint"), _long(code)
    return [_any_bits([F.shiftleft(F.shiftright(c, b * n_dims + n_dims - 1 - d).bitwiseAND(one), b) for b in range(bits)]) for d in range(n_dims)]


def morton_encode_wide(cols: list, bits: int, word: int = 60) -> Column:
    """Indexes of any width as an array of words of ``word`` bits, most significant first: arrays order as the index does."""
    n = len(cols)
    one = F.lit(1).cast("bigint")
    total = n * bits
    places = [(b * n + n - 1 - d, d, b) for d in range(n) for b in range(bits)]
    words = []
    for w in reversed(range(-(-total // word))):
        here = [F.shiftleft(F.shiftright(_long(cols[d]), b).bitwiseAND(one), p - w * word) for p, d, b in places if w * word <= p < (w + 1) * word]
        words.append(_any_bits(here))
    return F.array(*words)


def rowmajor_encode(cols: list, bits: int) -> Column:
    """Plain flattening without locality, the ablation."""
    n = len(cols)
    return _any_bits([F.shiftleft(_long(c), bits * (n - 1 - d)) for d, c in enumerate(cols)])


def peano_encode(cols: list, digits: int) -> Column:
    """Peano curve, base 3: a digit is mirrored when the other dimensions' higher digits sum to odd.

    Digits are taken from the most significant, dimension by dimension.
    """
    n = len(cols)
    digit = lambda d, k: F.pmod(F.floor(_long(cols[d]) / F.lit(3**k)), F.lit(3))
    code = F.lit(0).cast("bigint")
    for k in reversed(range(digits)):
        for d in range(n):
            before = [digit(e, j) for e in range(n) if e != d for j in range(k + 1, digits)] + [digit(e, k) for e in range(d)]
            odd = F.pmod(reduce(lambda a, b: a + b, before, F.lit(0).cast("bigint")), F.lit(2)) == 1
            code = code * 3 + F.when(odd, F.lit(2) - digit(d, k)).otherwise(digit(d, k))
    return code


def hilbert_steps(n: int, bits: int) -> list[dict[str, str]]:
    """The published transpose construction as a chain of projections in SQL that engines share.

    Columns h0..h(n-1) hold the coordinates; each step rewrites one or two of them.  x ^ y is written
    (x | y) - (x & y).
    """
    xor = lambda a, b: f"(({a} | {b}) - ({a} & {b}))"
    steps: list[dict[str, str]] = []
    for level in range(bits - 1, 0, -1):
        q, p = 1 << level, (1 << level) - 1
        for i in range(n):
            if i == 0:
                steps.append({"h0": f"CASE WHEN (h0 & {q}) <> 0 THEN {xor('h0', p)} ELSE h0 END"})
            else:
                swap = f"({xor('h0', f'h{i}')} & {p})"
                steps.append({"h0": f"CASE WHEN (h{i} & {q}) <> 0 THEN {xor('h0', p)} ELSE {xor('h0', swap)} END", f"h{i}": f"CASE WHEN (h{i} & {q}) <> 0 THEN h{i} ELSE {xor(f'h{i}', swap)} END"})
    for i in range(1, n):
        steps.append({f"h{i}": xor(f"h{i}", f"h{i - 1}")})
    steps.append({"ht": "CAST(0 AS BIGINT)"})
    for level in range(bits - 1, 0, -1):
        steps.append({"ht": f"CASE WHEN (h{n - 1} & {1 << level}) <> 0 THEN {xor('ht', (1 << level) - 1)} ELSE ht END"})
    steps.append({f"h{i}": xor(f"h{i}", "ht") for i in range(n)})
    return steps


def hilbert_encode(df: DataFrame, cols: list[str], bits: int, out: str = "hilbert") -> DataFrame:
    """Adds the Hilbert index.  Steps are separate projections, so expressions do not multiply.

    A filter or join on the index would be pushed through them and multiply them after all: write the
    encoded rows first, as a curve-ordered copy does anyway.
    """
    n, keep = len(cols), df.columns
    df = df.select("*", *(_long(c).alias(f"h{i}") for i, c in enumerate(cols)))
    for step in hilbert_steps(n, bits):
        df = df.withColumns({k: F.expr(v) for k, v in step.items()})
    return df.select(*keep, morton_encode([f"h{i}" for i in range(n)], bits).alias(out))


def hilbert_decode(df: DataFrame, code: str, n: int, bits: int, out: list[str]) -> DataFrame:
    """The coordinates of a Hilbert index: the steps of the encoding undone in reverse."""
    keep = df.columns
    df = df.select("*", *(c.alias(f"h{i}") for i, c in enumerate(morton_decode(code, n, bits))))
    xor = lambda a, b: f"(({a} | {b}) - ({a} & {b}))"
    steps: list[dict[str, str]] = [{"ht": f"h{n - 1} >> 1"}]
    steps += [{f"h{i}": xor(f"h{i}", f"h{i - 1}")} for i in range(n - 1, 0, -1)]
    steps.append({"h0": xor("h0", "ht")})
    for level in range(1, bits):
        q, p = 1 << level, (1 << level) - 1
        for i in range(n - 1, -1, -1):
            if i == 0:
                steps.append({"h0": f"CASE WHEN (h0 & {q}) <> 0 THEN {xor('h0', p)} ELSE h0 END"})
            else:
                swap = f"({xor('h0', f'h{i}')} & {p})"
                steps.append({"h0": f"CASE WHEN (h{i} & {q}) <> 0 THEN {xor('h0', p)} ELSE {xor('h0', swap)} END", f"h{i}": f"CASE WHEN (h{i} & {q}) <> 0 THEN h{i} ELSE {xor(f'h{i}', swap)} END"})
    for step in steps:
        df = df.withColumns({k: F.expr(v) for k, v in step.items()})
    return df.select(*keep, *(F.col(f"h{i}").alias(o) for i, o in enumerate(out)))
