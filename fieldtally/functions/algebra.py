"""Finite fields as column expressions.

A field element is a LONG: the residue in a prime field, the bit mask in a field of 2^k
elements, the base-p digits of a polynomial in a field of p^k.  Zero is 0 in each.
Orders that aren't prime powers are refused when the field is made.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Up to this order products in extension fields go through literal log tables.
TABLE_LIMIT = 4096


#: Witnesses that decide primality of all numbers below 3.3 * 10^24 (fixed values: the first thirteen primes).
_WITNESSES = (2, 3, 5, 7, 11, 13, 17, 19, 23, 29, 31, 37, 41)
#: Prime fields are below this, so that a product of two residues fits DECIMAL(38).
PRIME_LIMIT = 1 << 62


def is_prime(n: int) -> bool:
    """Strong-pseudoprime test to enough bases to be exact."""
    if n < 2 or any(n % w == 0 for w in _WITNESSES):
        return n in _WITNESSES
    odd = (n - 1) // ((n - 1) & (1 - n))
    for w in _WITNESSES:
        x, e = pow(w, odd, n), odd
        while x not in (1, n - 1) and 2 * e < n - 1:
            x, e = x * x % n, e * 2
        if x != n - 1 and (x != 1 or e != odd):
            return False
    return True


def prime_power(q: int) -> tuple[int, int]:
    """(p, k) with q = p^k, or ValueError."""
    for k in range(1, max(q, 1).bit_length() + 1):
        root = round(q ** (1 / k)) if k > 1 else q
        for p in (root - 1, root, root + 1) if k > 1 else (root,):
            if p**k == q and is_prime(p):
                return p, k
    raise ValueError(f"{q} is not the order of a field")


def characteristic(n: Column) -> Column:
    """The prime that a LONG is a power of, or 0 where there is none: by division up to the root."""
    some = F.get(F.filter(F.sequence(F.lit(2).cast("long"), F.greatest(F.floor(F.sqrt(n)), F.lit(2)).cast("long")), lambda d: n % d == 0), F.lit(0))
    least = F.coalesce(some, n)
    rest = F.aggregate(F.sequence(F.lit(1), F.lit(62)), n, lambda x, _: F.when(x % least == 0, F.floor(x / least).cast("long")).otherwise(x))
    return F.when(n < 2, 0).otherwise(F.when(rest == 1, least).otherwise(0))


def _digits(n: int, p: int, width: int) -> list[int]:
    return [n // p**i % p for i in range(width)]


def _poly_mod(a: list[int], modulus: list[int], p: int) -> list[int]:
    a, top = a[:], len(modulus) - 1
    inverse = pow(modulus[-1], -1, p)
    for at in range(len(a) - 1, top - 1, -1):
        factor = a[at] * inverse % p
        if factor:
            for i, c in enumerate(modulus):
                a[at - top + i] = (a[at - top + i] - factor * c) % p
    return a[:top]


def _poly_times(a: list[int], b: list[int], modulus: list[int], p: int) -> list[int]:
    out = [0] * (len(a) + len(b) - 1)
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            out[i + j] = (out[i + j] + x * y) % p
    return _poly_mod(out, modulus, p)


def _poly_gcd_is_one(a: list[int], b: list[int], p: int) -> bool:
    trim = lambda x: x[: max((i + 1 for i, c in enumerate(x) if c), default=0)]
    a, b = trim(a), trim(b)
    while b:
        a, b = b, trim(_poly_mod(a, b, p)) if len(a) >= len(b) else a
    return len(a) == 1


def _frobenius(times: int, modulus: list[int], p: int) -> list[int]:
    """x^(p^times) mod the polynomial."""
    k = len(modulus) - 1
    out = _poly_mod([0, 1], modulus, p) if k == 1 else [0, 1] + [0] * (k - 2)
    for _ in range(times):
        base, power, n = out, [1] + [0] * (k - 1), p
        while n:
            if n & 1:
                power = _poly_times(power, base, modulus, p)
            base, n = _poly_times(base, base, modulus, p), n >> 1
        out = power
    return out


@functools.lru_cache(maxsize=64)
def find_irreducible(p: int, k: int) -> int:
    """The smallest monic irreducible polynomial of degree k over the field of p, as base-p digits."""
    if k == 1:
        return p
    x = [0, 1] + [0] * (k - 2)
    divisors = [d for d in range(2, k + 1) if k % d == 0 and is_prime(d)]
    for low in range(1, p**k):
        modulus = [*_digits(low, p, k), 1]
        if modulus[0] and _frobenius(k, modulus, p) == x:
            gaps = ([(a - b) % p for a, b in zip(_frobenius(k // d, modulus, p), x, strict=True)] for d in divisors)
            if all(_poly_gcd_is_one(modulus, g, p) for g in gaps):
                return low + p**k
    raise AssertionError("there is one for every degree")


@dataclass(frozen=True)
class FieldSpec:
    """The field of p^k elements."""

    p: int
    k: int

    @property
    def order(self) -> int:
        return self.p**self.k

    @property
    def modulus(self) -> int:
        return find_irreducible(self.p, self.k)

    @property
    def bits(self) -> int:
        return (self.order - 1).bit_length()

    @property
    def chained(self) -> bool:
        """Whether products are a chain of k projections (large binary fields)."""
        return self.p == 2 and self.order > TABLE_LIMIT

    def add(self, a: int, b: int) -> int:
        return sum((x + y) % self.p * self.p**i for i, (x, y) in enumerate(zip(_digits(a, self.p, self.k), _digits(b, self.p, self.k), strict=True)))

    def multiply(self, a: int, b: int) -> int:
        out = _poly_times(_digits(a, self.p, self.k), _digits(b, self.p, self.k), _digits(self.modulus, self.p, self.k + 1), self.p) if self.k > 1 else [a * b % self.p]
        return sum(c * self.p**i for i, c in enumerate(out))

    def tables(self) -> tuple[list[int], list[int]]:
        """(logs by element, elements by log twice over) to the smallest generator."""
        return _log_tables(self.p, self.k)


@functools.lru_cache(maxsize=16)
def _log_tables(p: int, k: int) -> tuple[list[int], list[int]]:
    field = FieldSpec(p, k)
    for g in range(2, field.order):
        powers, now = [1], g
        while now != 1:
            powers.append(now)
            now = field.multiply(now, g)
        if len(powers) == field.order - 1:
            logs = [0] * field.order
            for i, v in enumerate(powers):
                logs[v] = i
            return logs, powers + powers
    return [0, 0], [1, 1]


def prime_field(p: int) -> FieldSpec:
    if not is_prime(p):
        raise ValueError(f"{p} is not prime")
    if p >= PRIME_LIMIT:
        raise ValueError("primes must be below 2^62 for products to fit DECIMAL(38)")
    return FieldSpec(p, 1)


def binary_field(k: int) -> FieldSpec:
    if not 1 <= k <= 62:
        raise ValueError("k must be from 1 to 62")
    return FieldSpec(2, k)


def extension_field(p: int, k: int) -> FieldSpec:
    if k > 1 and p > 2 and p**k > TABLE_LIMIT:
        raise ValueError(f"odd extension fields go up to order {TABLE_LIMIT}")
    return binary_field(k) if p == 2 else prime_field(p) if k == 1 else FieldSpec(prime_field(p).p, k)


def field_of_order(q: int) -> FieldSpec:
    return extension_field(*prime_power(q))


def _wide(value: Column) -> Column:
    return value.cast("decimal(38,0)")


def embed(delta: Column, field: FieldSpec, wide: bool = False) -> Column:
    """A delta as an element: the residue in a prime field, else the value as it is encoded.  wide: deltas beyond LONG."""
    if field.k > 1:
        return delta.cast("long")
    return F.pmod(_wide(delta), _wide(F.lit(field.p))).cast("long") if wide else F.pmod(delta.cast("long"), F.lit(field.p))


def with_product(frame: DataFrame, a: str, b: str, out: str, field: FieldSpec) -> DataFrame:
    """``out`` = a * b in the field; built-in operators only."""
    x, y = F.col(a), F.col(b)
    if field.order == 2:
        return frame.withColumn(out, x.bitwiseAND(y))
    if field.k == 1:
        # A product of residues of 2^31 and more is beyond LONG.
        product = x * y if field.p <= 1 << 31 else (_wide(x) * _wide(y)).cast("decimal(38,0)")
        return frame.withColumn(out, F.pmod(product, F.lit(field.p) if field.p <= 1 << 31 else _wide(F.lit(field.p))).cast("long"))
    if field.order <= TABLE_LIMIT:
        logs, powers = field.tables()
        log = F.array(*[F.lit(v) for v in logs])
        power = F.array(*[F.lit(v).cast("long") for v in powers])
        product = F.get(power, F.get(log, x.cast("int")) + F.get(log, y.cast("int")))
        return frame.withColumn(out, F.when((x == 0) | (y == 0), F.lit(0).cast("long")).otherwise(product))
    # Shift and reduce, one projection for each bit so that no expression is doubled.
    top, low = field.k - 1, field.modulus - (1 << field.k)
    kept = [F.col(c) for c in frame.columns if c != out]
    frame = frame.select(*kept, F.lit(0).cast("long").alias("_acc"), x.alias("_x"))
    for bit in range(field.k):
        acc = F.col("_acc").bitwiseXOR(F.col("_x") * F.shiftright(y, bit).bitwiseAND(F.lit(1)))
        shifted = F.shiftleft(F.col("_x").bitwiseAND(F.lit((1 << top) - 1)), 1).bitwiseXOR(F.shiftright(F.col("_x"), top).bitwiseAND(F.lit(1)) * F.lit(low))
        frame = frame.select(*kept, acc.alias("_acc"), shifted.alias("_x"))
    return frame.select(*kept, F.col("_acc").alias(out))


def fold(value: Column, field: FieldSpec) -> Column:
    """Aggregate: the field's sum.  Sums of large residues are taken in DECIMAL, which 10^20 rows don't overflow."""
    if field.p == 2:
        return F.bit_xor(value)
    if field.k == 1 and field.p > 1 << 20:
        return F.pmod(F.sum(_wide(value)), _wide(F.lit(field.p))).cast("long")
    if field.k == 1:
        return F.pmod(F.sum(value), F.lit(field.p)).cast("long")
    total = None
    for i in range(field.k):
        digit = F.pmod(F.sum(F.pmod(F.floor(value / F.lit(field.p**i)), F.lit(field.p))), F.lit(field.p)) * F.lit(field.p**i)
        total = digit if total is None else total + digit
    return total.cast("long")


def negated(value: Column, field: FieldSpec) -> Column:
    """The additive inverse."""
    if field.p == 2:
        return value
    if field.k == 1:
        return F.pmod(F.lit(field.p) - value, F.lit(field.p)).cast("long")
    total = None
    for i in range(field.k):
        digit = F.pmod(F.lit(field.p) - F.pmod(F.floor(value / F.lit(field.p**i)), F.lit(field.p)), F.lit(field.p)) * F.lit(field.p**i)
        total = digit if total is None else total + digit
    return total.cast("long")


def sql_product(a: str, b: str, field: FieldSpec) -> str:
    """The same product for DuckDB (for tests); fields up to TABLE_LIMIT, or prime."""
    if field.order == 2:
        return f"({a} & {b})"
    if field.k == 1:
        return f"({a}::HUGEINT * {b}::HUGEINT % {field.p})::BIGINT" if field.p > 1 << 31 else f"({a} * {b} % {field.p})"
    logs, powers = field.tables()
    return f"CASE WHEN {a} = 0 OR {b} = 0 THEN 0 ELSE ({powers})[({logs})[{a} + 1] + ({logs})[{b} + 1] + 1] END"


def sql_fold(value: str, field: FieldSpec) -> str:
    if field.p == 2:
        return f"bit_xor({value})"
    if field.k == 1:
        return f"(sum({value}) % {field.p})::BIGINT"
    return "(" + " + ".join(f"(sum({value} // {field.p**i} % {field.p}) % {field.p}) * {field.p**i}" for i in range(field.k)) + ")::BIGINT"


def sql_embed(delta: str, field: FieldSpec) -> str:
    return f"(({delta} % {field.p} + {field.p}) % {field.p})" if field.k == 1 else delta


def check_uniform(field: FieldSpec) -> bool:
    """Whether a*R and a+R run over the field once as R does, for every non-zero a (and every a): an exhaustive check."""
    every = list(range(field.order))
    return all(sorted(field.multiply(a, r) for r in every) == every for a in every[1:]) and all(sorted(field.add(a, r) for r in every) == every for a in every)


@dataclass(frozen=True)
class Monoid:
    """How states of one kind start and combine; ``field``: the field of order q it is a field sketch's algebra for, if any."""

    name: str
    signed: bool
    sketchable: bool

    def fold(self, value: Column, field: FieldSpec | None = None) -> Column:
        if self.name in ("natural", "integer"):
            return F.sum(value)
        if self.name in ("toggle", "mask"):
            return F.bit_xor(value)
        if self.name == "boolean":
            return F.bit_or(value)
        if field is None:
            raise ValueError(f"the {self.name} monoid needs its field")
        return fold(value, field)


MONOIDS = {m.name: m for m in (Monoid("natural", False, True), Monoid("integer", True, True), Monoid("toggle", False, True), Monoid("mask", False, True), Monoid("cyclic", False, True), Monoid("field", False, True), Monoid("boolean", False, False), Monoid("group", True, False))}


def monoid(name: str, for_sketch: bool = False) -> Monoid:
    """The named monoid; those without field structure are refused for sketches."""
    if name not in MONOIDS:
        raise ValueError(f"no monoid {name!r}; there are {', '.join(MONOIDS)}")
    if for_sketch and not MONOIDS[name].sketchable:
        raise ValueError(f"the {name} monoid is no field and has no such sketch; count it exactly")
    return MONOIDS[name]
