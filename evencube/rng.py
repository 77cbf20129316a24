"""Keyed randomness: the same key gives the same number in Spark, NumPy and SQL, however rows are laid out.

``uniform`` takes 52 bits of an md5 digest, so that plain SQL can repeat it.
``fast_uniform`` mixes 64-bit integers with NumPy for large experiments.
``permute`` is a keyed bijection of 0..N-1 (a Feistel network with cycle
walking), which shuffles rows without a sort or an exchange.
"""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52
ROUNDS = 4
#: Multipliers of the Feistel rounds.
MULTIPLIERS = (40503, 48271, 69621, 16807)
#: A walk leaves the range with chance below 3/4 a step; this many steps never failed to return for any N in tests, more raise.
MOST_STEPS = 200


def uniform(seed: int, tag: str, *keys: Column | int) -> Column:
    """Uniform in [0, 1) from a seed, a tag and integer keys, as a Column."""
    parts = [F.lit(f"{seed}|{tag}"), *(k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in keys)]
    digest = F.md5(F.concat_ws("|", *parts).cast("binary"))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long").cast("double") / F.lit(float(1 << BITS))


def uniform_py(seed: int, tag: str, *keys: int) -> float:
    text = "|".join([f"{seed}|{tag}", *map(str, keys)])
    return int(hashlib.md5(text.encode()).hexdigest()[:13], 16) / float(1 << BITS)


def uniform_sql(seed: int, tag: str, *keys: str) -> str:
    """The same number as a DuckDB expression; keys are SQL expressions."""
    text = " || '|' || ".join([f"'{seed}|{tag}'", *(f"CAST({k} AS VARCHAR)" for k in keys)])
    return f"(CAST(('0x' || substr(md5({text}), 1, 13)) AS BIGINT) / {float(1 << BITS)!r})"


def mix64(x: np.ndarray) -> np.ndarray:
    """splitmix64's finaliser."""
    with np.errstate(over="ignore"):
        x = np.asarray(x, np.uint64) + np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def fast_key(*keys: np.ndarray | int) -> np.ndarray:
    """One 64-bit hash of several integer keys, broadcast against each other."""
    out = np.uint64(0)
    for k in keys:
        with np.errstate(over="ignore"):
            out = mix64(np.asarray(out, np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.asarray(k).astype(np.uint64))
    return np.asarray(out, np.uint64)


def fast_uniform(*keys: np.ndarray | int) -> np.ndarray:
    return (fast_key(*keys) >> np.uint64(12)).astype(np.float64) / float(1 << BITS)


def _half_bits(n: int) -> int:
    return max(1, -(-max(1, n - 1).bit_length() // 2))


def _adds(seed: int, dim: int, bits: int) -> list[int]:
    return [int(uniform_py(seed, "perm", dim, k) * (1 << 16)) for k in range(ROUNDS)]


def permute(i: Column, n: int, seed: int, dim: int = 0) -> Column:
    """Image of row number ``i`` under the keyed bijection of 0..n-1, as a Column."""
    if n <= 1:
        return i.cast("long") * 0
    bits, adds = _half_bits(n), _adds(seed, dim, _half_bits(n))
    mask = (1 << bits) - 1

    def once(v: Column) -> Column:
        state = F.struct(F.shiftright(v, bits).alias("l"), v.bitwiseAND(F.lit(mask).cast("long")).alias("r"))
        rounds = F.array(*[F.struct(F.lit(m).cast("long").alias("m"), F.lit(a).cast("long").alias("a")) for m, a in zip(MULTIPLIERS, adds)])
        done = F.aggregate(
            rounds,
            state,
            lambda s, k: F.struct(s.r.alias("l"), s.l.bitwiseXOR(F.shiftright((s.r + 1) * k.m + k.a, 5).bitwiseAND(F.lit(mask).cast("long"))).alias("r")),
        )
        return F.shiftleft(done.l, bits).bitwiseOR(done.r)

    steps = F.sequence(F.lit(1), F.lit(MOST_STEPS))
    # the check sits in the finish, so that the walk is written once in the plan
    return F.aggregate(
        steps,
        once(i.cast("long")),
        lambda v, _: F.when(v >= n, once(v)).otherwise(v),
        lambda v: F.when(v < n, v).otherwise(F.raise_error(F.lit("the walk did not return")).cast("long")),
    )


def permute_np(i: np.ndarray, n: int, seed: int, dim: int = 0) -> np.ndarray:
    bits, adds = _half_bits(n), _adds(seed, dim, _half_bits(n))
    mask = (1 << bits) - 1

    def once(v: np.ndarray) -> np.ndarray:
        left, right = v >> bits, v & mask
        for m, a in zip(MULTIPLIERS, adds):
            left, right = right, left ^ ((((right + 1) * m + a) >> 5) & mask)
        return (left << bits) | right

    v = once(np.asarray(i, np.int64))
    for _ in range(MOST_STEPS):
        out = v >= n
        if not out.any():
            return v
        v[out] = once(v[out])
    raise RuntimeError("the walk did not return")


def permute_sql(n: int, seed: int, dim: int, name: str) -> str:
    """A CTE ``name(i, v)`` with v the image of every i in 0..n-1; needs WITH RECURSIVE."""
    bits, adds = _half_bits(n), _adds(seed, dim, _half_bits(n))
    mask = (1 << bits) - 1

    def once(v: str) -> str:
        left, right = f"({v} >> {bits})", f"({v} & {mask})"
        for m, a in zip(MULTIPLIERS, adds):
            left, right = right, f"xor({left}, (((({right} + 1) * {m} + {a}) >> 5) & {mask}))"
        return f"(({left} << {bits}) | {right})"

    first, again = once("CAST(range AS BIGINT)"), once("v")
    return (
        f"{name}_walk(i, v) AS (SELECT CAST(range AS BIGINT), {first} FROM range({n}) UNION ALL SELECT i, {again} FROM {name}_walk WHERE v >= {n}),"
        f" {name}(i, v) AS (SELECT i, v FROM {name}_walk WHERE v < {n})"
    )


def seeds(base: int, rep: Sequence[int] | int) -> list[int]:
    """Independent seeds of replications."""
    reps = range(rep) if isinstance(rep, int) else rep
    return [int(fast_key(base, r) >> np.uint64(33)) for r in reps]
