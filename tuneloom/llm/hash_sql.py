"""SQL text of XXH64, for engines with unsigned 128-bit integers and list functions but without the hash."""

from __future__ import annotations

#: The five primes of the hash.
P1, P2, P3, P4, P5 = 11400714785074694791, 14029467366897019727, 1609587929392839161, 9650029242287828579, 2870177450012600261
MASK = (1 << 64) - 1


def _u(x: int) -> str:
    return f"{x}::UHUGEINT"


def _mul(a: str, c: int) -> str:
    return f"(({a}) * {_u(c)} & {_u(MASK)})"


def _add(a: str, b: str) -> str:
    return f"(({a}) + ({b}) & {_u(MASK)})"


def _turn(a: str, bits: int) -> str:
    """Rotation to the left: 2^64 is 1 modulo 2^64 - 1. Only a word of 64 ones would come out as zero."""
    return f"(({a}) * {_u(1 << bits)} % {_u(MASK)})"


def _round(acc: str, lane: str) -> str:
    return _mul(_turn(_add(acc, _mul(lane, P2)), 31), P1)


def _word(h: str, at: str, size: int) -> str:
    """The little-endian number in `size` bytes of the hexadecimal string h from byte `at` (from 0)."""
    digits = " || ".join(f"substr({h}, CAST(2 * ({at}) AS BIGINT) + {2 * i + 1}, 2)" for i in reversed(range(size)))
    return f"CAST(CAST('0x' || {digits} AS UBIGINT) AS UHUGEINT)"


def _fold(times: str, start: str, step) -> str:
    """Runs step(acc, i) for i = 0 .. times - 1."""
    return f"list_reduce(list_transform(range(CAST({times} AS BIGINT)), lambda i: i::UHUGEINT), lambda a, i: {step('a', 'i')}, {start})"


def xxh64_ctes(source: str, seed: int = 42) -> str:
    """Common table expressions that end in xxh(s, h): the unsigned hash of the UTF-8 bytes of each s of the table `source`(s)."""
    lanes = [(seed + P1 + P2) & MASK, (seed + P2) & MASK, seed, (seed - P1) & MASK]
    stripes = ", ".join(f"{_fold('n // 32', _u(v), lambda a, i, j=j: _round(a, _word('x', f'32 * {i} + {8 * j}', 8)))} AS v{j}" for j, v in enumerate(lanes))
    joined = _add(_add(_turn("v0", 1), _turn("v1", 7)), _add(_turn("v2", 12), _turn("v3", 18)))
    for j in range(4):
        joined = _add(_mul(f"xor({joined}, {_round(_u(0), f'v{j}')})", P1), _u(P4))
    eight = _fold("n % 32 // 8", "c", lambda a, i: _add(_mul(_turn(f"xor({a}, {_round(_u(0), _word('x', f'n // 32 * 32 + 8 * {i}', 8))})", 27), P1), _u(P4)))
    four = f"CASE WHEN n % 8 >= 4 THEN {_add(_mul(_turn('xor(c, ' + _mul(_word('x', 'n // 8 * 8', 4), P1) + ')', 23), P2), _u(P3))} ELSE c END"
    one = _fold("n % 4", "c", lambda a, i: _mul(_turn(f"xor({a}, {_mul(_word('x', f'n // 4 * 4 + {i}', 1), P5)})", 11), P1))
    return f"""x0 AS MATERIALIZED (SELECT s, hex(encode(s)) AS x, strlen(s) AS n FROM {source}),
        x1 AS MATERIALIZED (SELECT s, x, n, {_add(_u((seed + P5) & MASK), "n::UHUGEINT")} AS c FROM x0 WHERE n < 32
          UNION ALL SELECT s, x, n, {_add(joined, "n::UHUGEINT")} FROM (SELECT s, x, n, {stripes} FROM x0 WHERE n >= 32)),
        x2 AS MATERIALIZED (SELECT s, x, n, {eight} AS c FROM x1),
        x3 AS MATERIALIZED (SELECT s, x, n, {four} AS c FROM x2),
        x4 AS MATERIALIZED (SELECT s, {one} AS c FROM x3),
        x5 AS MATERIALIZED (SELECT s, {_mul("xor(c, c >> 33)", P2)} AS c FROM x4),
        x6 AS MATERIALIZED (SELECT s, {_mul("xor(c, c >> 29)", P3)} AS c FROM x5),
        xxh AS MATERIALIZED (SELECT s, CAST(xor(c, c >> 32) AS UBIGINT) AS h FROM x6)"""
