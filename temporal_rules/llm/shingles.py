"""Five-word shingle sets as 64-bit hashes, and fast similarity sketches of them, in numpy.

Text is lower-cased for A-Z only and cut into words at the six ASCII white-space
characters, which is what ``bytes.lower`` and ``bytes.split`` do.  A shingle's hash is the
difference of two prefix sums of a random-byte polynomial modulo 2**64, so all shingles of a
batch cost a few passes over its bytes and no Python loop over words.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INV = pow(_BASE, -1, 1 << 64)
_BYTE = np.random.default_rng(20_240_601).integers(1, 1 << 63, size=256, dtype=np.uint64) * U(2) + U(1)
_powers = {"up": np.ones(1, U), "down": np.ones(1, U)}


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit finaliser with full avalanche."""
    x = x ^ U((seed * 0xD6E8FEB86659FD93) & (2**64 - 1))
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def _power(kind: str, n: int) -> np.ndarray:
    if len(_powers[kind]) < n:
        size = max(n, 2 * len(_powers[kind]), 1 << 16)
        steps = np.full(size, _BASE if kind == "up" else _INV, U)
        steps[0] = 1
        _powers[kind] = np.cumprod(steps, dtype=U)
    return _powers[kind][:n]


def shingle_hashes(text: str | None, width: int = 5) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles; a shorter text is one shingle, an empty one has none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, U)
    joined = np.frombuffer(b" ".join(words) + b" ", np.uint8)
    sums = np.zeros(len(joined) + 1, U)
    np.cumsum(_BYTE[joined] * _power("up", len(joined)), out=sums[1:])
    ends = np.flatnonzero(joined == 32)
    starts = np.concatenate([[0], ends[:-1] + 1])
    k = min(width, len(words))
    first, last = starts[: len(starts) - k + 1], ends[k - 1 :]
    raw = (sums[last] - sums[first]) * _power("down", len(joined))[first]
    return np.unique(mix(raw))


def sketch(sets: list[np.ndarray], size: int = 128) -> np.ndarray:
    """One row of ``size`` coordinates for each set, filled in rounds of hashed bin placement.

    In round r < size every element falls in one bin by its round hash and the bin's least
    value is kept; a bin keeps what its earliest round gave it.  Rounds from ``size`` on
    address one bin each, so every coordinate of a non-empty set is filled at the end.
    Two sets agree in a coordinate with probability equal to their Jaccard similarity, and
    the number of agreements concentrates as for independent coordinates.  Empty sets get 0.
    """
    out = np.zeros((len(sets), size), U)
    full = np.array([len(s) == 0 for s in sets], bool)
    shift = U(64 - (size - 1).bit_length())
    if 1 << (size - 1).bit_length() != size:
        raise ValueError("the number of coordinates must be a power of two")
    filled = np.zeros((len(sets), size), bool)
    for turn in range(2 * size):
        active = np.flatnonzero(~full)
        if not len(active):
            break
        lengths = np.array([len(sets[i]) for i in active])
        row = np.repeat(np.arange(len(active)), lengths)
        h = mix(np.concatenate([sets[i] for i in active]), turn + 1)
        got = np.full(len(active) * size, ~U(0), U)
        if turn < size:
            np.minimum.at(got, row * size + (h >> shift).astype(np.int64), (h << U(64 - int(shift))) >> U(1))
        else:
            np.minimum.at(got, row * size + (turn - size), h >> U(1))
        got = got.reshape(len(active), size)
        fresh = (got != ~U(0)) & ~filled[active]
        rows, cols = np.nonzero(fresh)
        out[active[rows], cols] = mix(got[rows, cols] ^ U(turn << 1 | 1))
        filled[active[rows], cols] = True
        full[active] = filled[active].all(axis=1)
    return out


def bands(sketches: np.ndarray, rows: int) -> np.ndarray:
    """A 64-bit key for each run of ``rows`` coordinates, different for each band."""
    n, size = sketches.shape
    parts = sketches.reshape(n, size // rows, rows)
    key = np.broadcast_to(np.arange(size // rows, dtype=U), (n, size // rows)).copy()
    for r in range(rows):
        key = mix(key * U(_BASE) + parts[:, :, r], r + 1)
    return key


def jaccard_parts(a: np.ndarray, b: np.ndarray) -> tuple[int, int]:
    """Sizes of intersection and union of two sorted distinct arrays."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both, len(a) + len(b) - both
