"""Words of many texts at once as 64-bit numbers, by array operations on their joined bytes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

BASE = np.uint64(0x9E3779B97F4A7C15)
INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_powers: dict[int, np.ndarray] = {}


def powers(base: np.uint64, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    got = _powers.get(int(base))
    if got is None or len(got) < n:
        size = 1 << max(16, (n - 1).bit_length())
        got = np.ones(size, np.uint64)
        got[1:] = base
        np.multiply.accumulate(got, out=got)
        _powers[int(base)] = got
    return got[:n]


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def chunks(rows: list, weigh, limit: int = 1 << 21) -> Iterator[list]:
    """Runs of rows of about `limit` bytes of text together, so that arrays stay small; one long text is a run of its own."""
    held, size = [], 0
    for row in rows:
        w = weigh(row)
        if held and size + w > limit:
            yield held
            held, size = [], 0
        held.append(row)
        size += w
    if held:
        yield held


def windows_hash(x: np.ndarray, n: int) -> np.ndarray:
    """Hash of each n consecutive numbers."""
    if len(x) < n:
        return np.zeros(0, np.uint64)
    up, down = powers(BASE, len(x)), powers(INVERSE, len(x))
    total = np.zeros(len(x) + 1, np.uint64)
    np.cumsum(x * up, out=total[1:])
    return mixed((total[n:] - total[:-n]) * down[: len(x) - n + 1] + np.uint64(n))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each word of all the texts in order, index in it where each text begins, with the end added).

    Words are runs of bytes other than 0x20 and 0x09-0x0D."""
    joined = b"\n".join(texts) + b"\n"
    data = np.frombuffer(joined, np.uint8)
    space = _SPACE[data]
    edge = np.flatnonzero(np.diff(space, prepend=True))
    starts, ends = edge[0::2], edge[1::2]
    lengths = np.fromiter(map(len, texts), np.int64, len(texts)) + 1
    begins = np.concatenate([[0], np.cumsum(lengths)])
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers(BASE, len(data)), out=total[1:])
    hashes = mixed((total[ends] - total[starts]) * powers(INVERSE, len(data))[starts] + (ends - starts).astype(np.uint64))
    return hashes, np.searchsorted(starts, begins)
