"""Shared randomness as deterministic functions of (seed, round, tag, feature); never rand().

A feature has a 60-bit code (MD5 of its name, once). A draw is a multiply-shift hash of the code's
halves with three multipliers of (seed, round, tag), then a fixed xor-multiply step: 31 bits, in
whole 64-bit arithmetic without overflow, so numpy, Spark and other SQL engines give the same number.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

HALF = (1 << 30) - 1
MASK = (1 << 31) - 1
STEP = 668265263
#: A null key sorts last.
NULL_KEY = (1 << 63) - 1


def code(name) -> Column:
    """The 60-bit code of a name."""
    return F.conv(F.substring(F.md5(name.cast("string").cast("binary")), 1, 15), 16, 10).cast("long")


def code_of(name: str) -> int:
    return int(hashlib.md5(name.encode()).hexdigest()[:15], 16)


def code_sql(name: str) -> str:
    return f"('0x' || substr(md5(({name})::varchar), 1, 15))::BIGINT"


def multipliers(seed: int, rounds, tag: str, scope: str = "") -> np.ndarray:
    """3 x rounds: the offset and the two odd multipliers of each round's draws."""
    out = np.empty((3, len(rounds)), dtype=np.int64)
    for i, r in enumerate(rounds):
        h = hashlib.md5(f"{seed}:{r}:{tag}{scope}".encode()).hexdigest()
        out[:, i] = int(h[:7], 16), int(h[7:14], 16) | 1, int(h[14:21], 16) | 1
    return out


def draw(codes: np.ndarray, m: np.ndarray) -> np.ndarray:
    """rounds x codes: 31-bit draws."""
    x = ((codes >> 30) ^ m[0][:, None]) * m[1][:, None]
    x += (codes & HALF) * m[2][:, None]
    x >>= 20
    x &= MASK
    x ^= x >> 15
    x *= STEP
    x >>= 15
    x &= MASK
    return x


def units(codes: np.ndarray, seed: int, rounds, tag: str, scope: str = "") -> np.ndarray:
    """rounds x codes: uniforms in (0, 1)."""
    return (draw(codes, multipliers(seed, rounds, tag, scope)) + 0.5) * 2.0**-31


def gamma2s(codes: np.ndarray, seed: int, rounds, tag: str, scope: str = "") -> np.ndarray:
    """Gamma(2, 1): the sum of two unit exponentials."""
    return -np.log(units(codes, seed, rounds, tag + "1", scope) * units(codes, seed, rounds, tag + "2", scope))


def gausses(codes: np.ndarray, seed: int, rounds) -> np.ndarray:
    """Standard Gaussians by Box-Muller."""
    return np.sqrt(-2 * np.log(units(codes, seed, rounds, "n1"))) * np.cos(2 * math.pi * units(codes, seed, rounds, "n2"))


def ranks(codes: np.ndarray, seed: int, rounds, scope: str = "") -> np.ndarray:
    """rounds x codes: 62-bit permutation ranks."""
    out = draw(codes, multipliers(seed, rounds, "perm1", scope))
    out <<= 31
    out |= draw(codes, multipliers(seed, rounds, "perm2", scope))
    return out


def _lit_draw(c: Column, seed: int, rnd: int, tag: str) -> Column:
    a, m, n = (F.lit(int(x)) for x in multipliers(seed, [rnd], tag)[:, 0])
    x = F.shiftright(F.shiftright(c, 30).bitwiseXOR(a) * m + c.bitwiseAND(F.lit(HALF)) * n, 20).bitwiseAND(F.lit(MASK))
    return F.shiftright(x.bitwiseXOR(F.shiftright(x, 15)) * F.lit(STEP), 15).bitwiseAND(F.lit(MASK))


def unit(seed: int, rnd: int, tag: str, c: Column) -> Column:
    """The uniform of a code as a Spark expression."""
    return (_lit_draw(c, seed, rnd, tag) + 0.5) / F.lit(2.0**31)


def gamma2(seed: int, rnd: int, tag: str, c: Column) -> Column:
    return -F.log(unit(seed, rnd, tag + "1", c) * unit(seed, rnd, tag + "2", c))


def rank(seed: int, rnd: int, c: Column) -> Column:
    return _lit_draw(c, seed, rnd, "perm1") * F.lit(1 << 31) + _lit_draw(c, seed, rnd, "perm2")


def multipliers_sql(seed: int, rounds: str, tags: list[str], scope: str = "''", extra: str = "") -> str:
    """A table of ``round`` and each tag's three numbers; ``rounds`` is SQL for rows of round (and ``extra`` columns)."""
    cells = [f"('0x' || substr(h_{t}, {1 + 7 * i}, 7))::BIGINT{' | 1' if i else ''} as {t}_{i}" for t in tags for i in range(3)]
    hashes = ", ".join(f"md5('{seed}:' || round || ':{t}' || {scope}) as h_{t}" for t in tags)
    return f"select round{extra}, {', '.join(cells)} from (select round{extra}, {hashes} from ({rounds}))"


def draw_sql(tag: str, code: str = "code") -> str:
    """31-bit draw of ``code`` with the numbers of ``multipliers_sql``."""
    x = f"(((xor({code} >> 30, {tag}_0) * {tag}_1 + ({code} & {HALF}) * {tag}_2) >> 20) & {MASK})"
    return f"(((xor({x}, {x} >> 15) * {STEP}) >> 15) & {MASK})"


def unit_sql(tag: str, code: str = "code") -> str:
    return f"(({draw_sql(tag, code)} + 0.5) / 2147483648.0)"


def gamma2_sql(tag: str, code: str = "code") -> str:
    return f"(-ln({unit_sql(tag + '1', code)} * {unit_sql(tag + '2', code)}))"


def gauss_sql(code: str = "code") -> str:
    return f"(sqrt(-2 * ln({unit_sql('n1', code)})) * cos({2 * math.pi!r} * {unit_sql('n2', code)}))"


def rank_sql(code: str = "code") -> str:
    return f"({draw_sql('perm1', code)} * 2147483648 + {draw_sql('perm2', code)})"


def rounds_sql(rounds) -> str:
    return f"select unnest([{', '.join(map(str, rounds))}]) as round"
