"""Checks the ring axioms on random payloads."""

from __future__ import annotations

import random
from collections.abc import Callable

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ringview.functions.rings import Payload, Ring


def _literal(ring: Ring, values: dict) -> Payload:
    return {s: F.lit(v) if not isinstance(v, list) else F.array(*map(F.lit, v)).cast("array<string>") for s, v in values.items()}


def _sum(ring: Ring, a: Payload, b: Payload) -> Payload:
    """A sum of two payloads as an expression, for rings of numbers; others pass their own."""
    return {s: (a[s] if s in a else F.lit(0)) + (b[s] if s in b else F.lit(0)) for s in {*a, *b}}


def check(spark: SparkSession, ring: Ring, draw: Callable[[random.Random], dict], plus: Callable[[Payload, Payload], Payload] | None = None, rounds: int = 5, seed: int = 1) -> dict[str, bool]:
    """Which laws hold on random triples: associativity, commutativity, identities, distributivity, inverse."""
    rng = random.Random(seed)
    add = plus or (lambda a, b: _sum(ring, a, b))
    laws: dict[str, list] = {}
    full = lambda p: F.array(*[F.coalesce(p.get(s, F.lit(0)).cast("double"), F.lit(0.0)) for s in ring.slots])

    def same(name: str, x: Payload, y: Payload) -> None:
        diff = F.array_max(F.zip_with(full(x), full(y), lambda u, v: F.abs(u - v) / (1 + F.abs(u))))
        laws.setdefault(name, []).append(diff < 1e-9)

    for _ in range(rounds):
        a, b, c = (_literal(ring, draw(rng)) for _ in range(3))
        same("sum associates", add(add(a, b), c), add(a, add(b, c)))
        same("sum commutes", add(a, b), add(b, a))
        same("product associates", ring.mul(ring.mul(a, b), c), ring.mul(a, ring.mul(b, c)))
        same("one", ring.mul(a, ring.one()), a)
        same("one on the left", ring.mul(ring.one(), a), a)
        same("distributes", ring.mul(a, add(b, c)), add(ring.mul(a, b), ring.mul(a, c)))
        same("distributes on the right", ring.mul(add(a, b), c), add(ring.mul(a, c), ring.mul(b, c)))
        same("product commutes", ring.mul(a, b), ring.mul(b, a))
        if ring.inverse:
            same("inverse", add(a, ring.neg(a)), {})
        same("zero annihilates", ring.mul(a, {s: F.lit(0) for s in ring.slots}), {})
    row = spark.range(1).select(*[F.array_min(F.array(*[x.cast("int") for x in v])).alias(k) for k, v in laws.items()]).first().asDict()
    return {k: bool(v) for k, v in row.items()}
