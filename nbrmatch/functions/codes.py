"""Integer codes of neighbourhoods, as plain Python integers and as Spark columns.

A vertex's neighbourhood is the vector x of how many of its neighbours have each pattern label. Its code is the sum over
j of step(j, x1 + ... + xj), with step(p, s) = C(s + p - 1, p): a bijection from vectors of length k to the naturals that
orders by the sum of the vector first (codes of sum n lie in band(n, k)). So codes need to be looked at only between
vertices of one degree, and those over the pattern's largest degree need none: they stay null, and 64 bits are enough.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, StringType

INT64 = 2**63 - 1
DECIMAL = 10**38 - 1


# ---- plain integers -------------------------------------------------------------------------------------------------


def pair(a: int, b: int) -> int:
    """The diagonal pairing of two naturals."""
    return (a + b) * (a + b + 1) // 2 + b


def unpair(c: int) -> tuple[int, int]:
    d = (math.isqrt(8 * c + 1) - 1) // 2
    b = c - d * (d + 1) // 2
    return d - b, b


def pair_nested(values: Sequence[int], shape: str = "balanced") -> int:
    """Many naturals as one by pairs of pairs: left ((a,b),c), right (a,(b,c)) or balanced ((a,b),(c,d)), the smallest."""
    values = list(values)
    if len(values) == 1:
        return values[0]
    at = {"left": len(values) - 1, "right": 1, "balanced": (len(values) + 1) // 2}[shape]
    return pair(pair_nested(values[:at], shape), pair_nested(values[at:], shape))


def step(p: int, s: int) -> int:
    """C(s + p - 1, p), 0 for s < 1."""
    return math.comb(s + p - 1, p) if s > 0 else 0


def step_interleaved(p: int, s: int) -> int:
    """step() by multiplying and dividing in turn: after t factors the value is C(s + t - 1, t), so no division leaves a rest."""
    if s < 1:
        return 0
    value = 1
    for t in range(1, p + 1):
        value = value * (s + t - 1) // t
    return value


def step_factorial(p: int, s: int) -> int:
    """step() by whole factorials, which leave 64 bits from 21! on: for comparison only."""
    return math.factorial(s + p - 1) // (math.factorial(p) * math.factorial(s - 1)) if s > 0 else 0


def ncode(x: Sequence[int]) -> int:
    total = code = 0
    for j, n in enumerate(x, 1):
        total += n
        code += step(j, total)
    return code


def decode(code: int, k: int) -> list[int]:
    """The vector of length k that has this code: its prefix sums come off greedily, the longest first."""
    sums = []
    for j in range(k, 0, -1):
        low, high = 0, 1
        while step(j, high) <= code:
            high *= 2
        while high - low > 1:
            mid = (low + high) // 2
            low, high = (mid, high) if step(j, mid) <= code else (low, mid)
        sums.append(low)
        code -= step(j, low)
    sums.reverse()
    return [b - a for a, b in zip([0, *sums[:-1]], sums, strict=True)]


def band(n: int, k: int) -> tuple[int, int]:
    """The least and the largest code of vectors of length k with sum n."""
    return math.comb(n + k - 1, k), math.comb(n + k, k) - 1


def bump(code: int, x: Sequence[int], rank: int) -> int:
    """The code after one more neighbour of this rank (1-based): terms from it on grow by a Pascal step each."""
    total = sum(x[: rank - 1])
    for j in range(rank, len(x) + 1):
        total += x[j - 1]
        code += step(j - 1, total + 1) if j > 1 else 1
    return code


def drop(code: int, x: Sequence[int], rank: int, by: int = 1) -> int:
    """The code after `by` neighbours of this rank are gone."""
    y = list(x)
    for _ in range(by):
        y[rank - 1] -= 1
        code -= bump(0, y, rank)
    return code


def max_width(degree: int, limit: int = INT64) -> int:
    """The most labels of which every vector with sum up to `degree` has a code within the limit."""
    s = 0
    while math.comb(degree + s + 1, s + 1) - 1 <= limit and s < 10_000:
        s += 1
    return s


def packets(x: Sequence[int], width: int) -> list[int]:
    """A code for each `width` labels: width 1 compares counts one by one, the full width is ncode()."""
    return [ncode(x[k : k + width]) for k in range(0, len(x), width)]


def log_code(x: Sequence[int]) -> float:
    """ln(1 + code). Not injective in doubles: may only be compared as "less", after the degree."""
    c = ncode(x)
    return math.log1p(c) if c < 2**53 else math.log(c + 1)


# ---- columns --------------------------------------------------------------------------------------------------------


def pair_column(a: Column, b: Column) -> Column:
    """The diagonal pairing of two long columns. ANSI mode raises on overflow (sums over about 4 * 10^9)."""
    s = a.cast("long") + b.cast("long")
    return F.call_function("div", s * (s + 1), F.lit(2)) + b.cast("long")


def unpair_column(c: Column) -> tuple[Column, Column]:
    """The two parts. The square root may be off by one for large values and is put right."""
    guess = F.floor((F.sqrt(c.cast("double") * 8 + 1) - 1) / 2).cast("long")
    tri = lambda d: F.call_function("div", d * (d + 1), F.lit(2))
    d = F.when(tri(guess) > c, guess - 1).when(tri(guess + 1) <= c, guess + 1).otherwise(guess)
    b = c - tri(d)
    return d - b, b


def pair_nested_column(columns: list[Column], shape: str = "balanced") -> Column:
    if len(columns) == 1:
        return columns[0].cast("long")
    at = {"left": len(columns) - 1, "right": 1, "balanced": (len(columns) + 1) // 2}[shape]
    return pair_column(pair_nested_column(columns[:at], shape), pair_nested_column(columns[at:], shape))


def step_column(p: int, s: Column) -> Column:
    """step(p, s) of a long column, unrolled: p multiplications and exact divisions inside generated code."""
    s = s.cast("long")
    value = s
    for t in range(2, p + 1):
        value = F.call_function("div", value * (s + (t - 1)), F.lit(t).cast("long"))
    return F.when(s < 1, F.lit(0).cast("long")).otherwise(value)


def step_hof(p: Column | int, s: Column) -> Column:
    """step(p, s) for any p by a fold, where p is large or a column."""
    p = F.lit(p) if isinstance(p, int) else p
    s = s.cast("long")
    terms = F.sequence(F.lit(1), p)
    folded = F.aggregate(terms, F.lit(1).cast("long"), lambda a, t: F.call_function("div", a * (s + t.cast("long") - 1), t.cast("long")))
    return F.when(s < 1, F.lit(0).cast("long")).when(p < 1, F.lit(1).cast("long")).otherwise(folded)


#: Labels up to which codes are unrolled; beyond, generated methods would exceed the JVM's limit.
UNROLLED = 16


def _prefix(counts: list[Column]) -> list[Column]:
    sums, total = [], None
    for c in counts:
        total = c.cast("long") if total is None else total + c.cast("long")
        sums.append(total)
    return sums


def ncode_column(counts: list[Column], cap: int | None = None) -> Column:
    """The code of a vector of columns as a long; null where the sum is over `cap` (see module docstring)."""
    sums = _prefix(counts)
    if not sums:
        return F.lit(0).cast("long")
    if len(sums) <= UNROLLED:
        code = sum((step_column(j, s) for j, s in enumerate(sums, 1)), F.lit(0).cast("long"))
    else:
        code = F.aggregate(F.arrays_zip(F.sequence(F.lit(1), F.lit(len(sums))).alias("p"), F.array(*sums).alias("s")), F.lit(0).cast("long"), lambda a, z: a + step_hof(z["p"], z["s"]))
    return code if cap is None else F.when(sums[-1] <= cap, code)


def ncode_array(x: Column) -> Column:
    """ncode of an array column of any length."""
    run = F.aggregate(x, F.struct(F.lit(0).cast("long").alias("s"), F.lit(0).alias("j"), F.lit(0).cast("long").alias("c")), _fold, lambda acc: acc["c"])
    return run


def _fold(acc: Column, n: Column) -> Column:
    s, j = acc["s"] + n.cast("long"), acc["j"] + 1
    return F.struct(s.alias("s"), j.alias("j"), (acc["c"] + step_hof(j, s)).alias("c"))


def ncode_decimal(counts: list[Column], most: int = 64) -> Column:
    """The code as DECIMAL(38, 0); null where it, or a product on the way, has over 32 digits.

    C(s + j - 1, j) is read from a table of literals for the sums 0 to `most`. Larger sums are multiplied and divided in
    turn; these divisions leave no rest, so a quotient is exact while its digits and the six decimals it gets fit.
    """
    code = None
    for j, s in enumerate(_prefix(counts), 1):
        known = F.array(*(F.lit(str(step(j, v)) if step(j, v) <= DECIMAL else None).cast("decimal(38,0)") for v in range(most + 1)))
        value = s.cast("decimal(38,0)")
        for t in range(2, j + 1):
            value = F.try_divide(F.try_multiply(value, (s + (t - 1)).cast("decimal(20,0)")), F.lit(t).cast("decimal(10,0)")).cast("decimal(38,0)")
        term = F.when(s <= most, F.get(known, F.least(s, F.lit(most)).cast("int"))).otherwise(value)
        code = term if code is None else F.try_add(code, term).cast("decimal(38,0)")
    return code


def edge_dims(x: list[Column], e: list[Column], how: str = "separate") -> Column:
    """The vector of vertex-label counts x and edge-label counts e as one array: in dimensions of their own, or shared (added rank by rank)."""
    if how == "separate":
        return F.array(*x, *e)
    if how != "shared":
        raise ValueError(how)
    zero = F.lit(0).cast("long")
    both = max(len(x), len(e))
    return F.array(*(a + b for a, b in zip([*x, *[zero] * (both - len(x))], [*e, *[zero] * (both - len(e))], strict=True)))


def ncode_log(counts: list[Column], slack: float = 0.0) -> Column:
    """ln(1 + code) as a double, by log-gamma-free sums of logs; finite for code 0."""
    terms = []
    for j, s in enumerate(_prefix(counts), 1):
        lnh = sum((F.ln(F.greatest(s + (t - 1), F.lit(1)).cast("double")) - math.log(t) for t in range(1, j + 1)), F.lit(0.0))
        terms.append(F.when(s < 1, F.lit(-1e300)).otherwise(lnh))
    top = F.greatest(F.lit(0.0), *terms)
    return top + F.ln(F.exp(-top) + sum((F.exp(t - top) for t in terms), F.lit(0.0))) + slack


def packet_columns(counts: list[Column], width: int, cap: int | None = None) -> Column:
    """Array of codes, one for each `width` labels."""
    return F.array(*(ncode_column(counts[k : k + width], cap) for k in range(0, len(counts), width)))


def labeled_code(rank: Column, code: Column) -> Column:
    """A vertex's own label folded into its code: the pair code of (rank, code)."""
    return ncode_column([rank, code])


def bump_column(code: Column, counts: list[Column], rank: int) -> Column:
    """ncode after one more neighbour of this rank, from the code so far."""
    sums = _prefix(counts)
    for j in range(rank, len(counts) + 1):
        code = code + (step_column(j - 1, sums[j - 1] + 1) if j > 1 else F.lit(1).cast("long"))
    return code


def drop_column(code: Column, counts: list[Column], rank: int) -> Column:
    """ncode after one neighbour of this rank is gone, from the code so far; its count must be 1 at least."""
    sums = _prefix(counts)
    for j in range(rank, len(counts) + 1):
        code = code - (step_column(j - 1, sums[j - 1]) if j > 1 else F.lit(1).cast("long"))
    return code


@F.pandas_udf(StringType())
def ncode_text(x: pd.Series) -> pd.Series:
    """Codes of any size in decimal digits. Null for null."""
    return pd.Series([None if v is None else str(ncode([int(n) for n in v])) for v in x], dtype=object)


def bytes_width(degree: int, k: int) -> int:
    """Bytes that hold the code of every vector of length k with a sum of up to `degree`."""
    return (math.comb(degree + k, k).bit_length() + 7) // 8


def ncode_bytes(x: Column, width: int = 64) -> Column:
    """Codes of any size as `width` bytes (bytes_width() tells how many), high byte first: Spark compares them as unsigned, so as the numbers.

    Null for null; a code that doesn't fit is an error.
    """

    @F.pandas_udf(BinaryType())
    def of(x: pd.Series) -> pd.Series:
        return pd.Series([None if v is None else ncode([int(n) for n in v]).to_bytes(width, "big") for v in x])

    return of(x)
