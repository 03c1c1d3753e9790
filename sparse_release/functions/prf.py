"""Uniform draws that are pure functions of (seed, tag, keys): the same after retries, in any partitioning, and in any engine with MD5.

Never rand(): it depends on the partition, so a recomputed task would publish a second noise for one cell.
"""

from __future__ import annotations

#: Draws are whole numbers below 2^52, read as (h + 1/2) / 2^52.
BITS = 52

MODES = ("md5", "sha2", "xxhash64")


def draw(seed: str | int, tag: str, *keys: str, mode: str = "md5") -> str:
    """SQL for a whole number below 2^BITS. keys: SQL expressions. md5: portable, for tests; sha2: for production, with a secret seed; xxhash64: fast, not secret."""
    text = f"concat_ws(':', '{seed}', '{tag}', {', '.join(f'CAST({k} AS STRING)' for k in keys)})"
    if mode == "xxhash64":
        return f"shiftrightunsigned(xxhash64({text}), {64 - BITS})"
    digest = f"md5(CAST({text} AS BINARY))" if mode == "md5" else f"sha2({text}, 256)"
    if mode not in MODES:
        raise ValueError(f"mode must be one of {MODES}")
    return f"CAST(conv(substring({digest}, 1, {BITS // 4}), 16, 10) AS BIGINT)"


def uniform(seed: str | int, tag: str, *keys: str, mode: str = "md5") -> str:
    """SQL for a double strictly between 0 and 1."""
    return f"(({draw(seed, tag, *keys, mode=mode)} + 0.5D) / {float(1 << BITS)!r}D)"
