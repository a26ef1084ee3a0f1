"""Monoids: the summaries that a map can carry.

A monoid is given as an aggregate over rows (`agg`), a way to combine two finished
summaries (`combine2`, in key order), an identity, and traits from which the batch
strategies are chosen. `inverse` undoes a left part: inverse(prefix, whole) = rest.
"""

from __future__ import annotations

import random
from collections.abc import Callable
from dataclasses import dataclass
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F

Pair = Callable[[Column, Column], Column]


@dataclass(frozen=True)
class Monoid:
    name: str
    dtype: str
    identity: Any
    agg: Callable[[Column], Column] | None
    combine2: Pair
    commutative: bool = True
    idempotent: bool = False
    inverse: Pair | None = None
    of: Callable[[Any, Any], Any] | None = None  # the same combine on Python values, for property checks

    def neutral(self) -> Column:
        return self.identity() if callable(self.identity) else F.lit(self.identity).cast(self.dtype)

    def total(self, a: Column) -> Column:
        """Aggregate over rows, the identity where there are none."""
        return F.coalesce(self.agg(a).cast(self.dtype), self.neutral())

    def fold(self, order: Column, a: Column) -> Column:
        """Aggregate in the order of a key; for groups bounded by a block."""
        if self.commutative and self.agg is not None:
            return self.total(a)
        rows = F.array_sort(F.collect_list(F.struct(order.alias("o"), a.alias("a"))))
        return F.aggregate(rows, self.neutral(), lambda s, x: self.combine2(s, x["a"]))


def _first_known(f: Callable[..., Column]) -> Pair:
    return lambda a, b: f(a, b)


def sum_(dtype: str = "bigint") -> Monoid:
    return Monoid("sum", dtype, 0, F.sum, lambda a, b: a + b, inverse=lambda p, w: w - p, of=lambda a, b: a + b)


def count() -> Monoid:
    """Number of entries; each entry's own summary, which the map's base gives, is 1."""
    return Monoid("count", "bigint", 0, F.sum, lambda a, b: a + b, inverse=lambda p, w: w - p, of=lambda a, b: a + b)


def max_(dtype: str = "bigint") -> Monoid:
    """Null is the identity, so that negative values keep their meaning."""
    return Monoid("max", dtype, None, F.max, _first_known(F.greatest), idempotent=True, of=lambda a, b: b if a is None else a if b is None else max(a, b))


def min_(dtype: str = "bigint") -> Monoid:
    return Monoid("min", dtype, None, F.min, _first_known(F.least), idempotent=True, of=lambda a, b: b if a is None else a if b is None else min(a, b))


def bool_or() -> Monoid:
    return Monoid("bool_or", "boolean", False, F.bool_or, lambda a, b: a | b, idempotent=True, of=lambda a, b: a or b)


def bool_and() -> Monoid:
    return Monoid("bool_and", "boolean", True, F.bool_and, lambda a, b: a & b, idempotent=True, of=lambda a, b: a and b)


def bit_or() -> Monoid:
    return Monoid("bit_or", "bigint", 0, F.bit_or, lambda a, b: a.bitwiseOR(b), idempotent=True, of=lambda a, b: a | b)


def bit_and() -> Monoid:
    return Monoid("bit_and", "bigint", -1, F.bit_and, lambda a, b: a.bitwiseAND(b), idempotent=True, of=lambda a, b: a & b)


def bit_xor() -> Monoid:
    return Monoid("bit_xor", "bigint", 0, F.bit_xor, lambda a, b: a.bitwiseXOR(b), inverse=lambda p, w: w.bitwiseXOR(p), of=lambda a, b: a ^ b)


def sum_count() -> Monoid:
    """Struct (s, n); the mean is s / n."""
    kind = "struct<s:bigint,n:bigint>"
    pair = lambda s, n: F.struct(s.cast("bigint").alias("s"), n.cast("bigint").alias("n"))
    return Monoid("sum_count", kind, lambda: pair(F.lit(0), F.lit(0)), lambda a: pair(F.coalesce(F.sum(a["s"]), F.lit(0)), F.coalesce(F.sum(a["n"]), F.lit(0))),
                  lambda a, b: pair(a["s"] + b["s"], a["n"] + b["n"]), inverse=lambda p, w: pair(w["s"] - p["s"], w["n"] - p["n"]), of=lambda a, b: (a[0] + b[0], a[1] + b[1]))


def moments() -> Monoid:
    """Struct (n, s, q): count, sum and sum of squares, for means and variances."""
    names, kind = "nsq", "struct<n:bigint,s:bigint,q:decimal(38,0)>"
    cast = lambda f: F.struct(*[f(x).cast("decimal(38,0)" if x == "q" else "bigint").alias(x) for x in names])
    return Monoid("moments", kind, lambda: cast(lambda x: F.lit(0)), lambda a: cast(lambda x: F.coalesce(F.sum(a[x]), F.lit(0))), lambda a, b: cast(lambda x: a[x] + b[x]),
                  inverse=lambda p, w: cast(lambda x: w[x] - p[x]), of=lambda a, b: tuple(x + y for x, y in zip(a, b)))


def keyed_sum() -> Monoid:
    """A map from names to sums; a name on one side only keeps its value."""
    kind = "map<string,bigint>"
    both = lambda a, b: F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
    return Monoid("keyed_sum", kind, lambda: F.create_map().cast(kind), None, both, of=lambda a, b: {k: a.get(k, 0) + b.get(k, 0) for k in {*a, *b}})


def top_k(k: int) -> Monoid:
    """The k largest values, as a descending array."""
    cut = lambda x: F.slice(F.sort_array(x, asc=False), 1, k)
    return Monoid(f"top_{k}", "array<bigint>", lambda: F.array().cast("array<bigint>"), None, lambda a, b: cut(F.concat(a, b)), of=lambda a, b: sorted(a + b, reverse=True)[:k])


def set_union(dtype: str = "array<bigint>") -> Monoid:
    return Monoid("set_union", dtype, lambda: F.array().cast(dtype), lambda a: F.array_sort(F.array_distinct(F.flatten(F.collect_list(a)))), lambda a, b: F.array_sort(F.array_union(a, b)),
                  idempotent=True, of=lambda a, b: sorted({*a, *b}))


def first(dtype: str) -> Monoid:
    return Monoid("first", dtype, None, None, lambda a, b: F.coalesce(a, b), commutative=False, idempotent=True, of=lambda a, b: b if a is None else a)


def last(dtype: str) -> Monoid:
    return Monoid("last", dtype, None, None, lambda a, b: F.coalesce(b, a), commutative=False, idempotent=True, of=lambda a, b: a if b is None else b)


def concat(sep: str = "") -> Monoid:
    """Strings one after the other; not commutative. The empty string is the identity."""
    def two(a: Column, b: Column) -> Column:
        return F.when((a == "") | (b == ""), F.concat(a, b)).otherwise(F.concat(a, F.lit(sep), b))

    return Monoid("concat", "string", "", None, two, commutative=False, of=lambda a, b: a + b if not a or not b else a + sep + b)


MODULUS = 1_000_003


def affine() -> Monoid:
    """Composition of x -> p x + q modulo a prime, the map with the smaller key first; not commutative."""
    kind = "struct<p:bigint,q:bigint>"
    make = lambda p, q: F.struct((p % MODULUS).cast("bigint").alias("p"), (q % MODULUS).cast("bigint").alias("q"))
    return Monoid("affine", kind, lambda: make(F.lit(1), F.lit(0)), None, lambda a, b: make(a["p"] * b["p"], b["p"] * a["q"] + b["q"]), commutative=False,
                  of=lambda a, b: (a[0] * b[0] % MODULUS, (b[0] * a[1] + b[1]) % MODULUS))


def product(**parts: Monoid) -> Monoid:
    """Several monoids side by side; base values are structs with the same field names."""
    kind = "struct<" + ",".join(f"{k}:{m.dtype}" for k, m in parts.items()) + ">"
    make = lambda f: F.struct(*[f(k, m).alias(k) for k, m in parts.items()])
    whole = all(m.agg is not None for m in parts.values())
    return Monoid("x".join(parts), kind, lambda: make(lambda k, m: m.neutral()), (lambda a: make(lambda k, m: m.total(a[k]))) if whole else None,
                  lambda a, b: make(lambda k, m: m.combine2(a[k], b[k])), commutative=all(m.commutative for m in parts.values()), idempotent=all(m.idempotent for m in parts.values()))


def custom(name: str, dtype: str, identity: Any, combine2: Pair, of=None, **traits) -> Monoid:
    return Monoid(name, dtype, identity, traits.pop("agg", None), combine2, of=of, **traits)


def check_laws(m: Monoid, values: list, rounds: int = 50, seed: int = 1) -> None:
    """Associativity and identity on Python values; raises ValueError on a counterexample."""
    rng, f = random.Random(seed), m.of
    for _ in range(rounds):
        a, b, c = (rng.choice(values) for _ in range(3))
        if f(f(a, b), c) != f(a, f(b, c)):
            raise ValueError(f"{m.name} is not associative on {a}, {b}, {c}")


def check_or_homomorphic(h: Callable[[Any], bool], m: Monoid, values: list, rounds: int = 200, seed: int = 1) -> None:
    """A filter through summaries needs h(a) or h(b) to say the same as h(a combined with b)."""
    rng = random.Random(seed)
    for _ in range(rounds):
        a, b = rng.choice(values), rng.choice(values)
        if bool(h(a) or h(b)) != bool(h(m.of(a, b))):
            raise ValueError(f"the predicate doesn't pass through {m.name}: {a}, {b}")


def check_distributes(g: Callable[[Any], Any], m: Monoid, m2: Monoid, values: list, rounds: int = 200, seed: int = 1) -> None:
    """A projected sum needs g(a combined with b) to be g(a) and g(b) combined by the second monoid."""
    rng = random.Random(seed)
    for _ in range(rounds):
        a, b = rng.choice(values), rng.choice(values)
        if g(m.of(a, b)) != m2.of(g(a), g(b)):
            raise ValueError(f"the projection doesn't carry {m.name} to {m2.name}: {a}, {b}")
